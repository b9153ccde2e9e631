"""Boolean-matrix algebra over labeled graphs, written for Spark DataFrames."""
