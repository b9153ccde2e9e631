"""Path expressions: syntax, rewriting, ordering and evaluation."""
