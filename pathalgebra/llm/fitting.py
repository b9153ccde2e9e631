"""Fitting classifiers on bounded samples, in a task and not on the driver.

The sample is bounded three ways, all of them parameters: in rows, in characters
of a single text, and in characters of all texts together.  One task learns; the
driver handles nothing but the finished weights.  Learning takes far more memory
than scoring, and Spark's Python workers live on: so the task learns in a process
of its own, whose memory goes with it.
"""

from __future__ import annotations

import os
import pickle
import subprocess
import sys
from collections.abc import Callable, Iterator
from typing import Any

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathalgebra.llm.memory import lean
from pathalgebra.runtime import stored

#: A text of more characters isn't learned from; it is predicted whole like any other.
LONGEST = 100_000
#: All texts of a sample together.
MOST_CHARS = 24_000_000


def chosen_keys(rows: DataFrame, key: str, limit: int) -> DataFrame:
    """The ``limit`` distinct keys of the least hashes, in a column ``chosen``; nulls are never chosen."""
    keys = rows.select(F.col(key).alias("chosen")).where("chosen is not null").distinct()
    return stored(keys.orderBy(F.xxhash64("chosen"), "chosen").limit(limit), "chosen")


_CHILD = "import pickle, sys; train, rows = pickle.load(sys.stdin.buffer); sys.stdout.buffer.write(pickle.dumps(train(rows)))"


def _in_own_process(train: Callable[[list[tuple]], Any], rows: list[tuple]) -> bytes:
    """The pickled result of ``train``, which is a function of a module."""
    given = pickle.dumps((train, rows))
    rows.clear()
    paths = os.pathsep.join(p for p in sys.path if p)
    done = subprocess.run([sys.executable, "-c", _CHILD], input=given, stdout=subprocess.PIPE, check=True, env=os.environ | {"PYTHONPATH": paths})
    return done.stdout


def fit_in_task(rows: DataFrame, train: Callable[[list[tuple]], Any], most_chars: int = MOST_CHARS) -> Any:
    """``train`` of the rows (key, text, label), in the order of a hash of the key, run in one task.

    Rows are taken until their texts reach ``most_chars``, then sorted by key,
    text and label, so the result doesn't depend on the order of arrival.
    """
    key, text, label = rows.columns

    def learn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        total = 0
        for batch in batches:
            for row in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
                total += len(row[1])
                if total > most_chars:
                    break
                held.append(row)
        held.sort()  # in place: the child is given these rows, and none stay here beside it
        yield pa.RecordBatch.from_arrays([pa.array([_in_own_process(train, held)], pa.binary())], names=["model"])

    ordered = rows.where(F.col(text).isNotNull() & F.col(label).isNotNull()).repartition(1).sortWithinPartitions(F.xxhash64(key), key, text, label)
    found = ordered.mapInArrow(lean(learn), "model binary").first()
    return pickle.loads(found["model"]) if found is not None else train([])
