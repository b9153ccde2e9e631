"""What the learned operators and the packing give on whole tables."""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from conftest import SF
from tokenizers import Tokenizer

from pathalgebra.llm import langid, packing, toxicity
from pathalgebra.llm.tokens import tokenizer_path

LARGE = "/root/testdata/sf0.1"


def test_languages_of_spliced_texts(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    chain = langid.fit_languages(docs)
    by_lang: dict = {}
    for r in docs.where("crc32(cast(doc_id as string)) % 3 = 1 and n_chars between 400 and 3000").orderBy("doc_id").collect():
        by_lang.setdefault(r.lang, []).append(r.text.split()[:40])
    names = [x for x in chain.languages if len(by_lang.get(x, [])) >= 3]
    checked = 0
    for a in names:
        for b in names:
            if a != b:
                for x, y in zip(by_lang[a][:3], by_lang[b][:3], strict=False):
                    share, words = langid.label_block(pa.array([" ".join(x + y)]), chain)
                    found = {n: share[0][chain.languages.index(n)] / max(1, words[0]) for n in (a, b)}
                    checked += 1
                    assert min(found.values()) > 0.3, (a, b, found)
    assert checked >= 6


def test_held_out_toxicity(spark):
    labels = spark.read.parquet(f"{LARGE}/labels.parquet")
    docs = spark.read.parquet(f"{LARGE}/documents.parquet").join(labels.select("doc_id").distinct(), "doc_id", "left_semi")
    got = toxicity.score_toxicity(docs, labels).where("held_out").join(labels, "doc_id").collect()
    hit = sum(r.predicted and r.toxic for r in got)
    assert hit >= 0.8 * sum(r.toxic for r in got) and hit >= 0.9 * sum(r.predicted for r in got)
    scores, truth = np.array([r.score for r in got]), np.array([r.toxic for r in got])
    order = np.argsort(scores)
    ranks = np.empty(len(order))
    ranks[order] = np.arange(len(order))
    area = (ranks[truth == 1].sum() - truth.sum() * (truth.sum() - 1) / 2) / (truth.sum() * (truth == 0).sum())
    assert area > 0.93


def test_scores_do_not_depend_on_neighbours(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    net = toxicity.fit_toxicity(docs, spark.read.parquet(f"{SF}/labels.parquet"))
    rows = docs.orderBy("doc_id").limit(40).collect()
    texts = [r.text for r in rows] + ["", None, "word " * 5000]
    together = toxicity.score_block(net, pa.array(texts, pa.string()))
    alone = [toxicity.score_block(net, pa.array([t], pa.string()))[0] for t in texts]
    assert np.allclose(together, alone, atol=1e-5)
    # The worst of all windows, one at a time.
    for text, score in zip(texts[:10], alone, strict=False):
        words = langid.split_words(pa.array([text]), langid.letter_table())
        flat = [words[2][c] for c in words[1]]
        starts = range(0, max(1, len(flat) - toxicity.STRIDE), toxicity.STRIDE)
        best = max(float(toxicity.score_block(net, pa.array([" ".join(flat[s : s + toxicity.WINDOW])]))[0]) for s in starts)
        assert abs(best - score) < 1e-4


def test_every_piece_of_a_packing(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    tokenizer = Tokenizer.from_file(tokenizer_path())
    ids = {r.doc_id: np.array([*tokenizer.encode(r.text or "", add_special_tokens=False).ids, 1], "<u4") for r in docs.collect()}
    got = packing.pack_documents(docs).collect()
    pieces: dict = {}
    sequences: dict = {}
    for r in got:
        own = ids[r.doc_id]
        assert r.doc_tokens == len(own) and r.ids_crc32 == zlib.crc32(own[r.start : r.start + r.length].tobytes())
        pieces.setdefault(r.doc_id, []).append((r.start, r.length))
        sequences.setdefault(r.sequence_id, []).append((r.offset, r.length))
    assert set(pieces) == set(ids)
    for members, size in [(sorted(v), len(ids[k])) for k, v in pieces.items()] + [(sorted(v), None) for v in sequences.values()]:
        at = 0
        for start, length in members:
            assert start == at and length > 0
            at += length
        assert at == size if size is not None else at <= 2048
    total = sum(map(len, ids.values()))
    tasks = docs.rdd.getNumPartitions()
    assert len(sequences) <= 1.01 * total / 2048 + tasks + 1
