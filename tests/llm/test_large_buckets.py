"""Pairs of a bucket are tried alike whatever its size."""

from __future__ import annotations

import pytest

from pathalgebra.llm import near_dup


@pytest.mark.parametrize("bucket_rows", [2, 2000])
def test_members_that_share_one_band_only_meet(spark, bucket_rows):
    rows = [(7, 9, k, b"", [7, 100 + k], min(k, 5)) for k in range(9)]  # no second band in common; 5 to 8 are one component
    label = spark.createDataFrame(rows, "key long, n long, rep long, sketch binary, bands array<long>, comp long")
    groups: dict = {}
    with near_dup.scratch(spark):
        for r in near_dup._open_groups(label, bucket_rows).collect():
            groups.setdefault(tuple(r[k] for k in r.asDict() if k in ("key", "via", "sub", "part")), []).append(r)
    met = [(min(x["rep"], y["rep"]), max(x["rep"], y["rep"])) for g in groups.values() for x in g for y in g
           if x["minor"] and y["own"] and x["comp"] != y["comp"] and (not y["minor"] or y["rep"] > x["rep"])]
    assert sorted(met) == [(a, b) for a in range(9) for b in range(a + 1, 9) if min(a, 5) != min(b, 5)]
