"""License scans: base phrases, and an exact set-similarity join with templates.

A template is a statement that licenses are known by.  Its blocks are the runs of
so many words of a text as the statement has, and an eighth more, that begin with a
word of the statement, wherever lines end.  A block meets a template if it holds at least ``percent`` % of the template's
distinct words, all words that tell it from its relatives, and none that tells a
relative from it.  The join finds every such block and compares few sets: words of
templates are ordered by how many texts hold them, rarest first; a block must share
one of a template's first words in that order (prefix), must hold enough words of
templates (length), and must have enough words behind the shared one on both sides
(position).  Before that, a text must hold enough of a template's words at all.
Only DataFrame functions are used.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathalgebra.runtime import stored

#: The base phrases, their labels, and the separators of words.
BASE = (("cc by", "cc-by"), ("general public license", "gpl"), ("all rights reserved", "reserved"))
SEPARATORS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

#: Label, statement, words that it can't do without, words of its relatives.
TEMPLATES = (
    ("agpl", "under the terms of the gnu affero general public license", "gnu affero license", ""),
    ("apache-2.0", "licensed under the apache license version 2 0", "apache license", ""),
    ("as-is", "the software is provided as is without warranty of any kind express or implied", "provided without warranty", ""),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted", "redistribution permitted", ""),
    ("bsd-named", "released under the bsd license", "bsd license", ""),
    ("cc-by-4.0", "licensed under the creative commons attribution 4 0 international license", "creative commons attribution", "noncommercial sharealike noderivatives noderivs"),
    ("cc-by-nc-4.0", "licensed under cc by nc 4 0", "cc by nc", ""),
    ("cc-by-nc-4.0", "licensed under the creative commons attribution noncommercial 4 0 international license", "creative commons noncommercial", ""),
    ("cc-by-nd-4.0", "licensed under cc by nd 4 0", "cc by nd", ""),
    ("cc-by-sa-4.0", "licensed under cc by sa 4 0", "cc by sa", ""),
    ("cc-by-sa-4.0", "licensed under the creative commons attribution sharealike 4 0 international license", "creative commons sharealike", ""),
    ("cc0", "the person who associated a work with this deed has dedicated the work to the public domain", "deed dedicated domain", ""),
    ("epl-2.0", "made available under the terms of the eclipse public license 2 0", "eclipse license", ""),
    ("gpl-3.0", "this work is licensed under the gnu general public license version 3", "gnu license 3", "lesser affero"),
    ("gpl-notice", "you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation", "gnu redistribute license", "lesser affero"),
    ("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", "fee hereby granted", ""),
    ("lgpl", "under the terms of the gnu lesser general public license", "gnu lesser license", ""),
    ("mit", "released under the mit license", "mit license", ""),
    ("mit", "licensed under the mit license", "mit license", ""),
    ("mit-text", "permission is hereby granted free of charge to any person obtaining a copy of this software", "hereby granted obtaining", ""),
    ("mpl-2.0", "subject to the terms of the mozilla public license v 2 0", "mozilla license", ""),
    ("unlicense", "this is free and unencumbered software released into the public domain", "unencumbered domain", ""),
)


@dataclass(frozen=True)
class Template:
    """A statement as the join sees it; ``need`` of its words make a match, ``length`` words a block."""

    number: int
    label: str
    words: tuple[str, ...]
    need: int
    length: int
    must: tuple[str, ...]
    without: tuple[str, ...]


def compiled(templates: tuple, percent: int) -> list[Template]:
    out = []
    for k, (label, phrase, must, without) in enumerate(templates):
        said = phrase.split()
        words = tuple(dict.fromkeys(said))
        out.append(Template(k, label, words, -(-percent * len(words) // 100), len(said) + len(said) // 8, tuple(must.split()), tuple(without.split())))
    return out


def _words(text: Column) -> Column:
    folded = F.translate(F.coalesce(text, F.lit("")), _UPPER, _LOWER)
    return F.filter(F.split(folded, SEPARATORS), lambda w: w != "")


def _let(value: Column, body) -> Column:
    return F.element_at(F.transform(F.array(value), body), 1)


def _list(values) -> Column:
    return F.array(*map(F.lit, values)) if values else F.array().cast("array<string>")


def _places(words: Column) -> Column:
    """Where base phrases start: structs of start and label, by phrase."""

    def of(phrase: str, label: str) -> Column:
        parts = phrase.split()

        def here(i: Column) -> Column:
            found = F.get(words, i) == parts[0]
            for k, part in enumerate(parts[1:], 1):
                found = found & (F.get(words, i + k) == part)
            return found

        starts = F.filter(F.sequence(F.lit(0), F.size(words) - len(parts)), here)
        found = F.transform(starts, lambda i: F.struct(i.cast("long").alias("start"), F.lit(label).alias("label")))
        return F.when(F.size(words) >= len(parts), found).otherwise(F.array().cast("array<struct<start:bigint,label:string>>"))

    return F.concat(*(of(p, x) for p, x in BASE))


def scan_texts(documents: DataFrame, plan: list[Template]) -> DataFrame:
    """One pass over the texts: counts, places of base phrases, and known words.

    ``held``: distinct words of templates in the text; ``hits``: their places, in
    texts that hold enough words of some template.
    """
    vocabulary = sorted({w for t in plan for w in (*t.words, *t.without)})
    known = _list(vocabulary)
    signs = _list(p.split()[0] for p, _ in BASE)
    no_places = F.array().cast("array<struct<start:bigint,label:string>>")
    no_hits = F.array().cast("array<struct<at:int,word:string>>")

    def may_match(held: Column) -> Column:
        found = F.lit(False)
        for t in plan:
            enough = F.size(F.array_intersect(held, _list(t.words))) >= t.need
            for w in t.must:
                enough = F.array_contains(held, w) & enough
            found = found | enough
        return found

    def scan(words: Column) -> Column:
        places = F.when(F.arrays_overlap(words, signs), _places(words)).otherwise(no_places)

        def with_held(held: Column) -> Column:
            all_hits = F.filter(F.transform(words, lambda w, i: F.struct(i.alias("at"), w.alias("word"))), lambda h: F.array_contains(known, h["word"]))
            hits = F.when(may_match(held), all_hits).otherwise(no_hits)
            return F.struct(F.size(words).cast("long").alias("n_words"), places.alias("places"), held.alias("held"), hits.alias("hits"))

        return _let(F.array_intersect(words, known), with_held)

    rows = documents.select("doc_id", F.monotonically_increasing_id().alias("rid"), _let(_words(F.col("text")), scan).alias("s"))
    return rows.select("doc_id", "rid", "s.n_words", "s.places", "s.held", "s.hits")


def license_scan(documents: DataFrame, templates: tuple = TEMPLATES, percent: int = 80) -> DataFrame:
    """Per document: doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score.

    ``labels`` has the base labels and those of matching templates; ``score`` is 1
    with a base phrase, else the largest share of a template that a block holds
    among matches, else 0.  Null and empty texts have no words, no places and
    empty label lists.  Rows are told apart by themselves, so repeated ids and
    null ids are scanned like others.  Other columns are ignored.
    """
    plan = compiled(templates, percent)
    scanned = stored(scan_texts(documents, plan), "scanned")
    # The vocabulary is fixed, so its counts are a short list.
    held = {r["w"]: r["n"] for r in scanned.select(F.explode("held").alias("w")).groupBy("w").agg(F.count("*").alias("n")).collect()}
    vocabulary = {w for t in plan for w in (*t.words, *t.without)}
    rank = {w: k for k, w in enumerate(sorted(vocabulary, key=lambda w: (held.get(w, 0), w)))}
    prefixes = []
    for t in plan:
        ranks = sorted(rank[w] for w in t.words)
        rest = (t.need, t.length, t.label, ranks, [rank[w] for w in t.must], [rank[w] for w in t.without])
        prefixes += [(ranks[i], t.number, i, *rest) for i in range(len(ranks) - t.need + 1)]
    prefix = documents.sparkSession.createDataFrame(prefixes, "rank int, template int, i int, need int, length int, label string, ranks array<int>, must array<int>, without array<int>")
    numbers = F.create_map(*(x for w, k in rank.items() for x in (F.lit(w), F.lit(k))))
    firsts = F.array(*(F.lit(k) for k in sorted({p[0] for p in prefixes})))
    longest = max(t.length for t in plan)
    ranked = scanned.where(F.size("hits") > 0).select("rid", F.transform("hits", lambda h: F.struct(h["at"].alias("at"), numbers[h["word"]].alias("rank"))).alias("hits"))

    # A hit with what stands around it, as far as the longest block reaches.
    def around(h: Column, i: Column) -> Column:
        first = F.greatest(i + 1 - (longest - 1), F.lit(1))
        near = F.slice(F.col("hits"), first, i + longest - first + 1)
        return F.struct(h["at"].alias("at"), h["rank"].alias("rank"), near.alias("near"))

    probes = F.filter(F.transform("hits", around), lambda p: F.array_contains(firsts, p["rank"]))
    probes = ranked.select("rid", F.explode(probes).alias("p")).select("rid", F.col("p.at").alias("place"), "p.rank", "p.near")
    # The table has a few rows for each template in the code.
    joined = probes.join(F.broadcast(prefix), "rank")
    length = F.col("length")
    begins = F.filter("near", lambda h: (h["at"] <= F.col("place")) & (h["at"] > F.col("place") - length) & F.array_contains("ranks", h["rank"]))

    def block(begin: Column) -> Column:
        inside = F.filter("near", lambda h: (h["at"] >= begin["at"]) & (h["at"] < begin["at"] + length))
        return F.array_sort(F.array_distinct(F.transform(inside, lambda h: h["rank"])))

    blocks = joined.withColumn("own", F.explode(F.array_distinct(F.transform(begins, block))))
    left = 1 + F.least(F.size("ranks") - F.col("i") - 1, F.size("own") - F.array_position("own", F.col("rank")))
    candidates = blocks.where((F.size("own") >= F.col("need")) & (left >= F.col("need")))
    shared = F.size(F.array_intersect("own", "ranks"))
    matches = candidates.where((shared >= F.col("need")) & (F.size(F.array_intersect("own", "must")) == F.size("must")) & (F.size(F.array_intersect("own", "without")) == 0))
    matches = matches.groupBy("rid").agg(F.collect_set("label").alias("found"), F.max(shared / F.size("ranks")).alias("best"))
    joined = scanned.drop("held", "hits").join(stored(matches, "matches"), "rid", "left")
    base = F.array_distinct(F.transform("places", lambda p: p["label"]))
    found = F.coalesce("found", F.array().cast("array<string>"))
    starts = F.transform("places", lambda p: p["start"])
    return joined.select(
        "doc_id", "n_words", F.size("places").cast("long").alias("n_base"), F.array_min(starts).alias("first_word"), F.array_max(starts).alias("last_word"),
        F.concat_ws(",", F.array_sort(base)).alias("base_labels"), F.concat_ws(",", F.array_sort(F.array_union(base, found))).alias("labels"),
        F.when(F.size("places") > 0, F.lit(1.0)).otherwise(F.coalesce("best", F.lit(0.0))).alias("score"),
    )


def sql(templates: tuple = TEMPLATES, percent: int = 80) -> str:
    """All blocks against all templates whose indispensable words the text has."""
    plan = compiled(templates, percent)
    rows = ", ".join(f"({t.number}, '{t.label}', {t.need}, {t.length}, {len(t.words)}, {len(t.must)})" for t in plan)
    kinds = [(t.number, w, "must" if w in t.must else "word") for t in plan for w in t.words] + [(t.number, w, "without") for t in plan for w in t.without]
    words = ", ".join(f"({k}, '{w}', '{kind}')" for k, w, kind in kinds)
    cases = " UNION ALL ".join(
        f"SELECT rid, i - 1 AS start, '{label}' AS label FROM w, unnest(range(1, len(ws) + 1)) AS t(i) WHERE "
        + " AND ".join(f"ws[i + {k}] = '{part}'" if k else f"ws[i] = '{part}'" for k, part in enumerate(phrase.split()))
        for phrase, label in BASE
    )
    word = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
    return rf"""
WITH d AS (SELECT row_number() OVER () AS rid, doc_id, translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}') AS text FROM documents),
w AS (SELECT rid, doc_id, regexp_extract_all(text, '{word}') AS ws FROM d),
p AS ({cases}),
b AS (SELECT rid, count(*) AS n, min(start) AS first_word, max(start) AS last_word, list_sort(list(DISTINCT label)) AS labels FROM p GROUP BY rid),
t AS (SELECT * FROM (VALUES {rows}) AS v(template, label, need, length, size, musts)),
k AS (SELECT * FROM (VALUES {words}) AS v(template, word, kind)),
s AS (SELECT rid, unnest(ws) AS word, generate_subscripts(ws, 1) AS pos FROM w),
h AS MATERIALIZED (SELECT rid, pos, s.word, template, kind FROM s JOIN k ON s.word = k.word),
o AS (SELECT rid, template FROM h JOIN t USING (template) WHERE kind = 'must' GROUP BY rid, template, musts HAVING count(DISTINCT word) = musts),
g AS MATERIALIZED (SELECT h.* FROM h JOIN o USING (rid, template)),
m AS (SELECT x.rid, x.template, x.pos, any_value(t.label) AS label, any_value(t.size) AS size, count(DISTINCT CASE WHEN y.kind <> 'without' THEN y.word END) AS shared
      FROM g AS x JOIN t ON x.template = t.template JOIN g AS y ON x.rid = y.rid AND x.template = y.template AND y.pos >= x.pos AND y.pos < x.pos + t.length
      WHERE x.kind <> 'without' GROUP BY x.rid, x.template, x.pos
      HAVING count(DISTINCT CASE WHEN y.kind <> 'without' THEN y.word END) >= any_value(t.need)
         AND count(DISTINCT CASE WHEN y.kind = 'must' THEN y.word END) = any_value(t.musts) AND count(CASE WHEN y.kind = 'without' THEN 1 END) = 0),
f AS (SELECT rid, list(DISTINCT label) AS found, max(CAST(shared AS DOUBLE) / CAST(size AS DOUBLE)) AS best FROM m GROUP BY rid)
SELECT doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(coalesce(b.n, 0) AS BIGINT) AS n_base, CAST(first_word AS BIGINT) AS first_word,
  CAST(last_word AS BIGINT) AS last_word, coalesce(array_to_string(b.labels, ','), '') AS base_labels,
  coalesce(array_to_string(list_sort(list_distinct(list_concat(coalesce(b.labels, []), coalesce(f.found, [])))), ','), '') AS labels,
  CASE WHEN b.n > 0 THEN 1.0::DOUBLE ELSE coalesce(best, 0.0)::DOUBLE END AS score
FROM w LEFT JOIN b USING (rid) LEFT JOIN f USING (rid)
"""
