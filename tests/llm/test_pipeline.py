"""The pipeline's stages, each against a plain rerun on its own input, and the whole run."""

from __future__ import annotations

import hashlib
from collections import Counter

import corpus_pipeline
import pyarrow as pa
import pytest
from conftest import SF
from test_operators import brute_components, words

from pathalgebra.llm import langid, toxicity


@pytest.fixture(scope="module")
def documents(spark):
    """The smallest table with nulls, empty texts and repeated rows in it, and a column that clashes."""
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    odd = spark.createDataFrame([(None, None, None, None, None), (90_001, None, "en", "s", 0), (90_002, "", None, None, 0), (90_003, "12 34 !!", "en", "s", 8)], docs.schema)
    return docs.unionByName(odd).unionByName(docs.orderBy("doc_id").limit(2))


def test_language(spark, documents):
    got = corpus_pipeline.language_stage(spark, documents, SF)
    assert got.columns == documents.columns
    chain = langid.fit_languages(documents)
    want = Counter()
    for r in documents.collect():
        share, n = langid.label_block(pa.array([r.text], pa.string()), chain)
        if n[0] and share[0].max() / n[0] >= corpus_pipeline.LEAST_SHARE:
            want[r] += 1
    assert Counter(got.collect()) == want and sum(want.values()) >= 190


def test_toxicity(spark, documents):
    got = corpus_pipeline.toxicity_stage(spark, documents, SF)
    assert got.columns == documents.columns
    net = toxicity.fit_toxicity(documents, spark.read.parquet(f"{SF}/labels.parquet"))
    want = Counter(r for r in documents.collect() if toxicity.score_block(net, pa.array([r.text], pa.string()))[0] < 0.5)
    assert Counter(got.collect()) == want


def test_near_duplicates(spark, documents):
    got = corpus_pipeline.near_dup_stage(spark, documents, SF)
    assert got.columns == documents.columns
    rows = documents.collect()
    want = brute_components([(r.doc_id, r.text) for r in rows], 5, 80)
    kept = {i for i, (_, root) in want.items() if i == root and i is not None}
    found = [r.doc_id for r in got.collect()]
    assert Counter(i for i in found if i is not None) == Counter(kept) and found.count(None) == 1


def test_mixing(spark, documents):
    got = corpus_pipeline.mixing_stage(spark, documents, SF)
    assert got.columns == documents.columns
    rows = documents.collect()
    sizes: dict = {}
    for r in rows:
        sizes[r.source] = sizes.get(r.source, 0) + len(words(r.text))
    names = sorted(sizes, key=lambda s: (s is None, (s or "").encode()))
    weight = {s: 1 + k % 3 for k, s in enumerate(names)}
    target, free, room = {}, set(names), sum(sizes.values())
    while free:
        share = {s: room * weight[s] / sum(weight[x] for x in free) for s in free}
        over = {s for s in free if share[s] > 3 * sizes[s]}
        if not over:
            target |= share
            break
        target |= {s: 3 * sizes[s] for s in over}
        room -= sum(3 * sizes[s] for s in over)
        free -= over
    taken: dict = {}
    times: Counter = Counter()
    for r in got.collect():
        times[r.doc_id] += 1
        taken[r.source] = taken.get(r.source, 0) + len(words(r.text))
    longest = max(len(words(r.text)) for r in rows)
    assert all(abs(taken.get(s, 0) - target[s]) <= longest for s in names)
    repeated = {i for i, n in Counter(r.doc_id for r in rows).items() if n > 1}
    assert len(repeated) == 2
    assert all(n <= 3 for i, n in times.items() if i not in repeated)
    # Within a source, documents are taken more often the earlier their hash comes.
    for s in names:
        own = sorted({r.doc_id for r in rows if r.source == s and words(r.text) and r.doc_id not in repeated}, key=lambda i: hashlib.md5(str(i).encode()).hexdigest())
        passes = [times[i] for i in own]
        assert passes == sorted(passes, reverse=True)


def test_whole_run(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, SF)
    pieces = lambda df: Counter((r.doc_id, r.start, r.length, r.ids_crc32, r.doc_tokens) for r in df.collect())
    assert pieces(corpus_pipeline.run(spark, SF)) == pieces(docs)


def test_no_documents(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, SF)
    assert docs.count() == 0
