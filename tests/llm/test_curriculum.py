"""op3 gives its rows in training order."""

from __future__ import annotations

import hashlib

import numpy as np
from conftest import SF

from pathalgebra.llm import queries


def test_rows_come_in_training_order(spark):
    docs = {r.doc_id: r for r in spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "source").collect()}
    got = queries.op3_curriculum(spark, SF).collect()
    assert len({r.doc_id for r in got}) == len(got) == len(docs)
    sources = sorted({r.source for r in docs.values()}, key=lambda s: (s is None, (s or "").encode()))
    # The schedule of a source is integrated and inverted on a grid.
    u = np.linspace(0, 1, 20_001)
    position = {}
    for k, source in enumerate(sources):
        weight = 1 + (-0.5, 0.0, 0.5)[k % 3] * (2 * u - 1)
        demand = np.concatenate([[0], np.cumsum((weight[1:] + weight[:-1]) / 2 * np.diff(u))])
        before = 0
        for r in sorted((r for r in got if docs[r.doc_id].source == source), key=lambda r: hashlib.md5(str(r.doc_id).encode()).hexdigest()):
            position[r.doc_id] = float(np.interp(min(1, before / r.target), demand, u)) if r.taken else 2.0
            before += r.size
    along = [position[r.doc_id] for r in got]
    assert min(along) < 0.05 and 0.9 < max(x for x in along if x < 2) and len({round(x, 3) for x in along}) > 50
    assert all(a <= b + 1e-6 for a, b in zip(along, along[1:], strict=False))
