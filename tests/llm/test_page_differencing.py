"""Pairs over partition borders, and elements that the pages of a host share."""

from __future__ import annotations

import random

from pathalgebra.llm import html_text as h


def longest_common(a, b):
    best = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
    for i, x in enumerate(a):
        for j, y in enumerate(b):
            best[i + 1][j + 1] = best[i][j] + 1 if x == y else max(best[i][j + 1], best[i + 1][j])
    return best[-1][-1]


def some_pages(n: int, seed: int = 1):
    rng = random.Random(seed)
    pages = []
    for k in range(n):
        host = rng.choice(["a.example", "a.example", "b.example"])
        said = [f"<p>line {rng.randrange(6)}</p>" for _ in range(rng.randrange(8))]
        pages.append((k, f"http://{host}/x/{rng.randrange(40)}", "<div>" + "".join(said) + "</div><div class=z>same</div>"))
    return [*pages, pages[0], (None, None, "<p>x</p>"), (n, None, None)]


def test_pairs_do_not_depend_on_partitions(spark):
    pages = some_pages(120)
    frame = spark.createDataFrame(pages, "page_id long, url string, html string")
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "23")
    try:
        got = h.shared_lines(h.parsed_pages(frame)).collect()
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
    rows = sorted({(*h._address(u), h._key(i, u, s), s) for i, u, s in pages}, key=lambda r: r[:3])
    want = {}
    for k, (host, path, key, source) in enumerate(rows):
        near = [rows[j] for j in (k - 1, k + 1) if 0 <= j < len(rows) and rows[j][0] == host]
        if near:
            best = max(near, key=lambda r: h._common(path, r[1]))
            mine, other = ([x for x, _, _ in h.text_lines(s)[0]] for s in (source, best[3]))
            want[key] = (len(mine), longest_common(mine, other))
    total: dict = {}
    for r in got:
        n, m = total.get(r.key, (0, 0))
        total[r.key] = (n + r.n, m + r.shared)
        assert len(r.places) == r.shared
    assert {k: v for k, v in total.items() if v[0]} == {k: v for k, v in want.items() if v[0]}


def test_shared_elements_go_and_shared_passages_stay(spark):
    passage = "<p>A passage that articles of this site repeat.</p>"
    pages, want = [], {}
    for k in range(30):
        own = f"<p>Story {k} begins.</p>" + passage * (k % 2) + f"<p>Story {k} ends.</p>"
        box = "<div class='teaser box-7'><p>Read more of this site.</p><p>Write to us.</p></div>"
        pages.append((k, f"http://s.example/news/{k:03}", f"<main><h1>No {k}</h1>{own}{box}</main><footer>{k}</footer>"))
        want[k] = "\n".join([f"No {k}", f"Story {k} begins.", *["A passage that articles of this site repeat."] * (k % 2), f"Story {k} ends."])
    # Copies of one article under many addresses of another site are kept.
    pages += [(100 + k, f"http://c.example/{k:03}", "<article><p>One text.</p><p>Told again.</p></article>") for k in range(15)]
    want |= {100 + k: "One text.\nTold again." for k in range(15)}
    frame = spark.createDataFrame([(*p, "clash") for p in pages], "page_id long, url string, html string, lines string")
    got = {r.page_id: r.text for r in h.main_text(frame).collect()}
    assert got == want


def test_long_and_odd_pages(spark):
    odd = [
        (1, "http://o.example/1", "<p>" * 5000 + "deep"), (2, "http://o.example/2", "<div>" * 3000 + "x" + "</div>" * 10), (3, "http://o.example/3", "a" * 200_000),
        (4, "http://o.example/4", "&#xD800;&bogus;&amp <"), (5, "http://o.example/5", "<article>" + "<p>w</p>" * 3000), (6, "http://o.example/6", "</div></article><p>t"),
    ]
    got = {r.page_id: r for r in h.main_text(spark.createDataFrame(odd, "page_id long, url string, html string")).collect()}
    assert got[1].text == "deep" and got[2].text == "x" and got[3].n_chars == 200_000 and got[5].n_chars == 5999 and got[6].text == "t"
