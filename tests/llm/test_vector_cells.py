"""All links of vectors are found, however many cells there are."""

from __future__ import annotations

import numpy as np

from pathalgebra.llm import vectors


def test_links_between_many_cells(spark):
    rng = np.random.default_rng(5)
    base = rng.normal(size=(600, 64))
    base /= np.linalg.norm(base, axis=1, keepdims=True)
    side = rng.normal(size=base.shape)
    side -= (side * base).sum(axis=1, keepdims=True) * base
    side /= np.linalg.norm(side, axis=1, keepdims=True)
    x = np.concatenate([base, 0.932 * base + (1 - 0.932**2) ** 0.5 * side])
    want = x @ x.T >= 0.93
    np.fill_diagonal(want, False)
    df = spark.createDataFrame([(i, v.tolist(), 0) for i, v in enumerate(x)], "vec_id long, embedding array<double>, label int")
    for block in (4096, 7):
        got = {r.vec_id: r.n_links for r in vectors.near_vectors(df, cell_rows=8, block=block).collect()}
        assert [got[i] for i in range(len(x))] == want.sum(axis=1).tolist()
