"""Operators on messy small tables against brute force, and on empty tables."""

from __future__ import annotations

import random
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest

from pathalgebra import runtime
from pathalgebra.llm import elias_fano, html_text, langid, licenses, mixing, near_dup, packing, quality, token_store, toxicity, vectors
from pathalgebra.llm.tokens import WordEncoder, tokenizer_path

TEXTS = [
    None, "", " \n\t", "one", "one two three four five six seven", "One  two\nthree FOUR five six seven", "one two three four five six seven eight nine ten",
    "a b c a b c a b c", "All rights reserved. Licensed under CC BY 4.0", "Released under the MIT License.\nReleased under the MIT License.", "ß é́ <|endoftext|> don't 12 #*$%&|<>", "x" * 5000,
    " ".join(f"word{i}" for i in range(3000)), "all rights\nreserved general public license cc by cc by", "\x85nb sp", "one two three four five six seven",
]
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, size string, taken int, key int"


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, [None, "en", "fr"][i % 3], [None, "s1", "s2", "é"][i % 4], None, "clash", 7, 1) for i, t in enumerate(TEXTS)]
    rows += [rows[4], (None, "one two three four five six seven", "en", None, 1, None, None, None)]
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture(scope="module")
def nothing(spark):
    return spark.createDataFrame([], SCHEMA)


def words(text):
    return re.findall(r"[^\x20\x09-\x0D]+", text or "")


def test_elias_fano():
    rng = np.random.default_rng(0)
    for n, top in ((0, 5), (1, 0), (600, 50), (5000, 10**7)):
        v = np.sort(rng.integers(0, top + 1, n))
        e = elias_fano.EliasFano.from_bytes(elias_fano.EliasFano.encode(v).to_bytes())
        assert (e.decode() == v).all() and all(e.select(i) == v[i] for i in range(0, n, 13))
        assert (e.select_many(np.arange(n)) == v).all() and all(e.place_of(int(x)) == np.searchsorted(v, x) for x in v[::37])


def test_words_are_encoded_as_whole_texts():
    encoder = WordEncoder(tokenizer_path(), 1)
    want = [e.ids + [1] for e in encoder.tokenizer.encode_batch([t or "" for t in TEXTS], add_special_tokens=False)]
    assert [x.tolist() for x in encoder.encode(pa.array(TEXTS, pa.string()))] == want


def test_token_store(docs, nothing):
    encoder = WordEncoder(tokenizer_path(), 1)
    rows = docs.select("doc_id", "text").collect()
    rows.sort(key=lambda r: (r.doc_id is not None, r.doc_id or 0, r.text is not None, r.text or ""))
    got = sorted(token_store.encode_corpus(docs).collect(), key=lambda r: r.start)
    start = 0
    for r, g in zip(rows, got, strict=True):
        ids = next(iter(encoder.encode(pa.array([r.text], pa.string()))))
        assert (g.doc_id, g.start, g.n_tokens, g.ids_crc32) == (r.doc_id, start, len(ids), zlib.crc32(ids.astype("<u4").tobytes()))
        start += len(ids)
    assert token_store.encode_corpus(nothing).count() == 0
    path = runtime.fresh_path(docs.sparkSession, "store")
    token_store.write_token_store(docs, path, segment_tokens=500)
    found = token_store.tokens_of(docs.sparkSession, path, [3, 4, 12, 99]).collect()
    assert sorted(r.doc_id for r in found) == [3, 4, 4, 12]
    for r in found:
        assert r.ids == next(iter(encoder.encode(pa.array([TEXTS[r.doc_id]], pa.string())))).tolist()


def test_packing(docs, nothing):
    got = packing.pack_documents(docs, capacity=64).collect()
    by_sequence: dict[int, list] = {}
    for r in got:
        by_sequence.setdefault(r.sequence_id, []).append(r)
    for members in by_sequence.values():
        at = 0
        for r in sorted(members, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= 64
    pieces = sorted((r.start, r.length) for r in got if r.doc_id == 12)
    assert pieces[0][0] == 0 and all(a + n == b for (a, n), (b, _) in zip(pieces, pieces[1:], strict=False))
    assert packing.pack_documents(nothing).count() == 0


def test_minimum_bin_slack_fills_well():
    rng = random.Random(1)
    sizes = [rng.randint(1, 100) for _ in range(500)]
    bins = packing.minimum_bin_slack(sizes, 100)
    assert sorted(i for b in bins for i in b) == list(range(500))
    assert len(bins) <= 1.02 * sum(sizes) / 100 + 1 and all(sum(sizes[i] for i in b) <= 100 for b in bins)
    assert packing.best_fill({3: 2, 5: 1, 7: 1}, [7, 5, 3], 11) == {5: 1, 3: 2}


def brute_components(rows, width, percent):
    table = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    sets = []
    for i, t in rows:
        w = words((t or "").translate(table))
        sets.append((i, frozenset(tuple(w[k : k + width]) for k in range(len(w) - width + 1)) if len(w) >= width else frozenset([tuple(w)] if w else [])))
    up = {i: i for i, _ in sets}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for i, a in sets:
        for j, b in sets:
            if i is not None and j is not None and i < j and a and b and 100 * len(a & b) >= percent * len(a | b):
                x, y = sorted((root(i), root(j)))
                up[y] = x
    return {i: (len(s), root(i)) for i, s in sets}


@pytest.mark.parametrize(("width", "percent", "rows"), [(3, 85, 2000), (5, 80, 3)])
def test_near_duplicates(spark, docs, nothing, width, percent, rows):
    rng = random.Random(3)
    base = [f"w{k}" for k in range(60)]
    extra = []
    for k in range(60):  # a chain of versions, each a few words from the one before
        base = list(base)
        base[rng.randrange(60)] = f"v{k}"
        extra.append((1000 + k, " ".join(base)))
    both = docs.select("doc_id", "text").unionByName(spark.createDataFrame(extra, "doc_id long, text string"))
    want = brute_components([(r.doc_id, r.text) for r in both.collect()], width, percent)
    got = near_dup.near_duplicates(both, width, percent, bucket_rows=rows).collect()
    assert len(got) == both.count()
    for r in got:
        assert (r.n_shingles, r.component_id) == want[r.doc_id] if r.doc_id is not None else r.component_id is None
        assert r.kept == (r.doc_id is not None and r.doc_id == r.component_id)
    assert near_dup.near_duplicates(nothing).count() == 0
    left = near_dup.without_near_duplicates(docs)
    assert left.columns == docs.columns
    ids = [r.doc_id for r in left.collect() if r.doc_id is not None]
    assert len(ids) == len(set(ids))


def test_mixing(docs, nothing):
    got = mixing.mix_sources(docs, buckets=16).collect()
    assert len(got) == docs.count() and all(0 <= r.taken <= 3 * r.size for r in got)
    by_target: dict[tuple, int] = {}
    for r in got:
        by_target[r.source_size, r.target] = by_target.get((r.source_size, r.target), 0) + r.taken
    assert all(abs(v - t) < 1 or v == int(t) for (_, t), v in by_target.items())
    assert mixing.mix_sources(nothing).count() == 0
    assert mixing.repeat_by_mix(docs).columns == docs.columns and mixing.repeat_by_mix(nothing).count() == 0
    order = mixing.training_order(mixing.mix_sources(docs, buckets=16))
    positions = [r.position for r in order.collect()]
    assert positions == sorted(positions)


def test_quality(docs, nothing):
    got = quality.adaptive_quality(docs).collect()
    want = {}
    for r in docs.select("doc_id", "text").collect():
        w, t = words(r.text), r.text or ""
        grams = [tuple(w[k : k + 3]) for k in range(len(w) - 2)]
        again = {k + d for k, g in enumerate(grams) if grams.count(g) > 1 for d in range(3)} if len(w) < 100 else set()
        lines = [x for x in t.split("\n") if words(x)]
        want[r.doc_id] = (len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(again))
    for r in got:
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == want[r.doc_id]
        assert r.base_failed == (r.n_words < 50 or 2 * r.n_repeat_words > r.n_words) and not (r.kept and r.base_failed)
    assert len(got) == docs.count() and quality.adaptive_quality(nothing).count() == 0


def test_licenses(docs, nothing):
    rows = {r.doc_id: r for r in licenses.license_scan(docs).collect()}
    assert rows[8].base_labels == "cc-by,reserved" and rows[8].n_base == 2 and rows[8].first_word == 0
    assert rows[9].base_labels == "" and rows[9].labels == "mit" and rows[9].score == 1.0
    assert rows[13].n_base == 4 and rows[13].base_labels == "cc-by,gpl,reserved" and (rows[13].first_word, rows[13].last_word) == (0, 8)
    assert rows[0].n_words == 0 and rows[0].labels == "" and rows[0].first_word is None and rows[0].score == 0.0
    assert licenses.license_scan(docs).count() == docs.count() and licenses.license_scan(nothing).count() == 0


def test_vectors(spark):
    rng = np.random.default_rng(2)
    base = rng.normal(size=(20, 8))
    rows = [(i, (base[i % 20] + rng.normal(size=8) * 0.15).tolist(), i % 2, "x") for i in range(120)]
    rows += [(200, rows[0][1], 0, "x"), (201, None, 0, "x"), (202, [0.0] * 8, 0, "x"), (203, [1.0, None] + [0.0] * 6, 0, "x"), (204, [float("nan")] * 8, 1, "x"), (205, rows[1][1], None, "x"), (206, [1.0, 2.0], 0, "x"), rows[3]]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int, rep string")
    got = {r.vec_id: r for r in vectors.near_vectors(df, cell_rows=20, block=5).collect()}
    good = {i: (np.array(v, np.float32).astype(float), lab) for i, v, lab, _ in rows if lab is not None and v is not None and None not in v and np.isfinite(v).all() and any(v)}
    up = {i: i for i in got}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    links = dict.fromkeys(got, 0)
    for i, (a, la) in good.items():
        for j, (b, lb) in good.items():
            if i < j and la == lb and len(a) == len(b) and a @ b / np.linalg.norm(a) / np.linalg.norm(b) >= 0.93:
                links[i] += 1
                links[j] += 1
                x, y = sorted((root(i), root(j)))
                up[y] = x
    assert {i: r.n_links for i, r in got.items()} == links
    assert {i: r.component_id for i, r in got.items()} == {i: root(i) for i in got}
    assert vectors.near_vectors(df.limit(0)).count() == 0


def test_forward_backward_is_exact():
    rng = np.random.default_rng(0)
    n, k = 400, 3
    scores, start, moves = rng.normal(size=(n, k)), rng.normal(size=k), rng.normal(size=(k, k))
    starts = np.zeros(n, bool)
    starts[[0, 5, 6, 300]] = True
    got, _ = langid.forward_backward(scores, starts, start, moves)
    cuts = [*np.flatnonzero(starts).tolist(), n]
    for a, b in zip(cuts, cuts[1:], strict=False):
        e, t = np.exp(scores[a:b]), np.exp(moves)
        ahead, behind = [np.exp(start) * e[0]], [np.ones(k)]
        for i in range(1, b - a):
            x = (ahead[-1] @ t) * e[i]
            ahead.append(x / x.sum())
        for i in range(b - a - 1, 0, -1):
            x = t @ (e[i] * behind[-1])
            behind.append(x / x.sum())
        want = np.array(ahead) * np.array(behind[::-1])
        assert np.allclose(got[a:b], want / want.sum(axis=1, keepdims=True))


def test_languages(spark, docs, nothing):
    got = {r.doc_id: r for r in langid.identify_languages(docs).collect()}
    assert got[0].lang_pred == got[1].lang_pred == "und" and got[0].score == 0
    assert langid.identify_languages(nothing).count() == 0
    given = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    joined = langid.identify_languages(given).join(given.select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert sum(r.lang == r.lang_pred for r in joined) > 0.97 * len(joined)


def test_network_gradients():
    net = toxicity.Network(hidden=3, word_dim=2, gram_dim=2)
    net.w = {k: v.astype(np.float64) for k, v in net.w.items()}
    rng = np.random.default_rng(1)
    x, at, n, wrong = rng.normal(size=(9, 6)), rng.integers(0, 9, (5, 4)), np.array([5, 3, 1, 0]), rng.normal(size=4)
    trace: dict = {}
    net.forward(x, at, n, trace)
    g, _ = net.gradients(x, at, n, wrong, trace)
    for k in ("out", "att", "pick", "gates_f", "state_b", "in_f", "add_b"):
        p, i = net.w[k], tuple(rng.integers(0, s) for s in net.w[k].shape)
        old, step = p[i], 1e-2
        sides = []
        for d in (step, -step):
            p[i] = old + d
            sides.append((net.forward(x, at, n) * wrong).sum())
        p[i] = old
        assert abs((sides[0] - sides[1]) / (2 * step) - g[k][i]) < 1e-4


def test_toxicity(spark, docs, nothing):
    labels = spark.createDataFrame([(4, 1, 0), (6, 0, 1), (6, 0, None), (None, 1, 1)], "doc_id long, quality int, toxic int")
    got = toxicity.score_toxicity(docs, labels).collect()
    assert len(got) == docs.count() and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.5) for r in got)
    assert toxicity.score_toxicity(nothing, labels).count() == 0
    assert toxicity.score_toxicity(docs, labels.limit(0)).count() == docs.count()


def test_windows_cover_all_words():
    text, first, n = toxicity.cut_windows(np.array([0, 1, 32, 33, 100]))
    for k, size in enumerate([0, 1, 32, 33, 100]):
        seen = {w for t, f, c in zip(text, first, n, strict=True) if t == k for w in range(f, f + c)}
        assert seen == set(range(size))


def test_common_lines():
    assert html_text.common_lines([1, 2, 3, 4], [9, 2, 8, 4]) == {1, 3}
    assert len(html_text.common_lines([1, 1, 2, 1], [1, 2, 1])) == 3


def test_main_text(spark):
    rows = [
        (1, "http://a.example/x/1", "<html><head><title>t</title></head><body><nav>menu</nav><article><h1>T &amp; U</h1><p>one<br>two<p>three <b>x</b></article><footer>f</footer></body></html>"),
        (2, "http://b.example/n/1", "<div>Site line</div><div>Alpha</div><div class='sidebar'>side</div><div>End line</div>"),
        (3, "http://b.example/n/2", "<div>Site line</div><div>Beta</div><form>send</form><div>End line</div>"),
        (4, None, None), (5, "http://c.example/", ""), (6, "http://c.example/", "<p>cut off <b>here"), (None, "x", "<p>p</p>"),
    ]
    pages = spark.createDataFrame([(*r, 9) for r in [*rows, rows[1]]], "page_id long, url string, html string, text int")
    got = {r.page_id: r for r in html_text.main_text(pages).collect()}
    assert got[1].text == "T & U\none two\nthree x"
    assert (got[2].text, got[3].text) == ("Alpha", "Beta")
    assert got[4].text == got[5].text == "" and got[6].text == "cut off here" and got[6].n_chars == 12
    assert html_text.main_text(pages).count() == 8 and html_text.main_text(pages.limit(0)).count() == 0
