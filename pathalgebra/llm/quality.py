"""Quality rules whose cutoffs come from the corpus, in DataFrame functions only.

Every measure of a document is a whole number.  A quantile sketch counts, for
each language and source, how many documents fall into each bin; bins hold one
number each up to 63 and then 32 to every doubling, so a quantile is off by 3 %
at most.  Sketches are plain counts: they add up in any order, before and after
a shuffle, and reruns agree.  Cutoffs are fences far outside the middle of a
group; those of its language, from the merged sketches, stand in for a group that is
too small and bound one that is polluted.  One join brings them back to the documents.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pathalgebra.runtime import stored

#: The base rules' blanks and symbols.
_BLANKS = " \t\n\x0b\x0c\r"
_SYMBOLS = "#*$%&|<>"
_CUT = r"[\x20\x09-\x0D]+"
_HAS_WORD = r"[^\x20\x09-\x0D]"

#: Measures with cutoffs: name, expression, whether low or high values are suspect, least span of a fence.
_MEASURES = (
    ("word_length", "100 * word_chars div n_words", "both", 30),
    ("symbol_share", "1000 * n_symbols div greatest(word_chars, 1)", "high", 15),
    ("repeat_share", "1000 * n_repeat_words div n_words", "high", 40),
)


def _let(value: Column, body) -> Column:
    """``body`` of a value that is worked out once."""
    return F.element_at(F.transform(F.array(value), body), 1)


def _repeated_words(words: Column) -> Column:
    """Words in three-word windows that occur twice or more in ``words``.

    Windows are compared as 64-bit numbers first: a text in which all differ has
    none.  Otherwise the windows themselves are sorted, and equal neighbours give
    the places that count.
    """

    def places(sorted_windows: Column) -> Column:
        n = F.size(sorted_windows)

        def same(x: Column, i: Column) -> Column:
            before = F.when(i > 0, F.get(sorted_windows, i - 1)["g"] == x["g"]).otherwise(False)
            after = F.when(i < n - 1, F.get(sorted_windows, i + 1)["g"] == x["g"]).otherwise(False)
            return before | after

        found = F.array_sort(F.transform(F.filter(sorted_windows, same), lambda x: x["i"]))
        start = F.struct(F.lit(-3).alias("last"), F.lit(0).cast("long").alias("n"))
        step = F.aggregate(found, start, lambda acc, p: F.struct(p.alias("last"), (acc["n"] + F.least(F.lit(3), p - acc["last"])).alias("n")))
        return step["n"]

    def windows(w: Column) -> Column:
        return F.transform(F.sequence(F.lit(0), F.size(w) - 3), lambda i: F.struct(F.concat_ws(" ", F.get(w, i), F.get(w, i + 1), F.get(w, i + 2)).alias("g"), i.alias("i")))

    def hashes(w: Column) -> Column:
        return F.transform(F.sequence(F.lit(0), F.size(w) - 3), lambda i: F.xxhash64(F.get(w, i), F.get(w, i + 1), F.get(w, i + 2)))

    def count(w: Column) -> Column:
        distinct = _let(hashes(w), lambda h: F.size(F.array_distinct(h)))
        return F.when(F.size(w) < 4, F.lit(0).cast("long")).when(distinct == F.size(w) - 2, F.lit(0).cast("long")).otherwise(_let(F.array_sort(windows(w)), places))

    return _let(words, count)


def base_measures(documents: DataFrame) -> DataFrame:
    """Per document: the words' and lines' counts, in one pass over the text."""
    text = F.coalesce(F.col("text"), F.lit(""))
    words = F.filter(F.split(text, _CUT), lambda w: w != "")
    blank = F.translate(text, _BLANKS, "")
    lines = F.filter(F.split(text, "\n"), lambda x: x.rlike(_HAS_WORD))
    counted = _let(words, lambda w: F.struct(F.size(w).cast("long").alias("n"), _repeated_words(w).alias("r")))
    repeated = _let(lines, lambda x: (F.size(x) - F.size(F.array_distinct(x))).cast("long"))
    rows = documents.select(
        "doc_id", "lang", "source", counted.alias("counted"), F.length(blank).cast("long").alias("word_chars"),
        (F.length(text) - F.length(F.translate(text, _SYMBOLS, ""))).cast("long").alias("n_symbols"), repeated.alias("n_dup_lines"),
    )
    rows = rows.select("doc_id", "lang", "source", F.col("counted.n").alias("n_words"), "word_chars", "n_symbols", "n_dup_lines", F.col("counted.r").alias("n_repeat_words"))
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    return rows.withColumn("base_failed", failed)


def _bin(value: str) -> str:
    """The bin's least number: all but the six leading binary digits set to 0."""
    return f"CASE WHEN {value} < 64 THEN {value} ELSE shiftleft(shiftright({value}, length(bin({value})) - 6), length(bin({value})) - 6) END"


def _fences(sketch: DataFrame, keys: list[str], reach: int, prefix: str) -> DataFrame:
    """Per ``keys`` and measure: rows, inner fences (low, high) and outer ones (floor, top), by quartiles of the merged sketch."""
    by = [*keys, "measure"]
    merged = sketch.groupBy(*by, "bin").agg(F.sum("n").alias("n"))
    upto = Window.partitionBy(*by).orderBy("bin").rowsBetween(Window.unboundedPreceding, 0)
    ranked = merged.withColumn("upto", F.sum("n").over(upto)).withColumn("all", F.sum("n").over(Window.partitionBy(*by)))
    quartile = [F.min(F.when(F.col("upto") * 4 >= k * F.col("all"), F.col("bin"))).alias(f"q{k}") for k in (1, 2, 3)]
    table = ranked.groupBy(*by).agg(*quartile, F.max("all").alias(f"{prefix}rows"))
    least = F.expr("CASE measure " + " ".join(f"WHEN '{n}' THEN {unit}" for n, _, _, unit in _MEASURES) + " END")
    span = F.greatest(F.col("q3") - F.col("q1"), F.expr("q2 div 16"), least)
    lines = {"low": F.col("q1") - reach * span, "high": F.col("q3") + reach * span, "floor": F.col("q1") - 2 * reach * span, "top": F.col("q3") + 2 * reach * span}
    return table.select(*by, f"{prefix}rows", *(v.alias(prefix + k) for k, v in lines.items()))


def cutoffs(measured: DataFrame, reach: int = 4, least_rows: int = 20) -> DataFrame:
    """(lang, source, measure, low, high) from the documents that pass the base rules.

    With quartiles q1 <= q2 <= q3 of a group, fences stand ``reach`` spans below q1
    and above q3; a span is the greatest of q3 - q1, q2 / 16 and the measure's own
    least span.  They are never wider than twice that many spans around the
    quartiles of the whole language.  A group of fewer than ``least_rows`` documents
    takes the language's fences, a language of fewer those of the corpus; a corpus
    of fewer has none.
    """
    pairs = F.expr("explode(array(" + ", ".join(f"struct('{n}' as measure, cast({e} as bigint) as value)" for n, e, _, _ in _MEASURES) + ")) as m")
    sketch = measured.where("not base_failed").select("lang", "source", pairs)
    sketch = sketch.select("lang", "source", "m.measure", F.expr(_bin("m.value")).alias("bin"))
    sketch = stored(sketch.groupBy("lang", "source", "measure", "bin").agg(F.count("*").alias("n")), "sketch")
    own, language = _fences(sketch, ["lang", "source"], reach, ""), _fences(sketch, ["lang"], reach, "l_").withColumnRenamed("lang", "l_lang").withColumnRenamed("measure", "l_measure")
    corpus = _fences(sketch, [], reach, "c_").withColumnRenamed("measure", "c_measure")
    both = own.join(language, own["lang"].eqNullSafe(language["l_lang"]) & (own["measure"] == language["l_measure"]))
    both = both.join(F.broadcast(corpus), F.col("measure") == F.col("c_measure"))  # a row for each measure

    def pick(bounded, name: str):
        enough = F.when(F.col("c_rows") >= least_rows, F.col(f"c_{name}"))
        return F.when(F.col("rows") >= least_rows, bounded).when(F.col("l_rows") >= least_rows, F.col(f"l_{name}")).otherwise(enough).alias(name)

    return both.select("lang", "source", "measure", pick(F.greatest("low", "l_floor"), "low"), pick(F.least("high", "l_top"), "high"))


def adaptive_quality(documents: DataFrame, reach: int = 4, least_rows: int = 20) -> DataFrame:
    """Per document: doc_id, the base measures, base_failed and kept.

    A document is kept if it passes the base rules and lies inside its group's
    fences in mean word length, share of symbols and share of repeated words; a
    corpus too small to have fences admits everything.  Null or blank
    text has no words and fails the base rules; null languages and sources form
    groups of their own.  Repeated rows count each time.  Other columns are
    ignored; no rows give no rows.
    """
    measured = stored(base_measures(documents), "measured")
    fences = cutoffs(measured, reach, least_rows)
    tests = []
    for name, expression, side, _ in _MEASURES:
        value = f"cast({expression} as bigint)"
        parts = [f"{value} <= {name}_high"] if side != "low" else []
        parts += [f"{value} >= {name}_low"] if side != "high" else []
        tests.append(f"({name}_high is null or ({' and '.join(parts)}))")
    wide = fences.groupBy(F.col("lang").alias("l"), F.col("source").alias("s")).agg(
        *(F.max(F.when(F.col("measure") == n, F.col(c))).alias(f"{n}_{c}") for n, _, _, _ in _MEASURES for c in ("low", "high"))
    )
    wide = stored(wide, "fences")
    joined = measured.join(wide, measured["lang"].eqNullSafe(wide["l"]) & measured["source"].eqNullSafe(wide["s"]), "left")
    kept = F.when(F.col("base_failed"), F.lit(False)).otherwise(F.coalesce(F.expr(" and ".join(tests)), F.lit(True)))
    return joined.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", kept.alias("kept"))


_SQL_BIN = "CASE WHEN {0} < 64 THEN {0} ELSE ({0} >> (length(bin({0})) - 6)) << (length(bin({0})) - 6) END"


def _sql_fences(name: str, keys: str, reach: int) -> str:
    """The counterpart of ``_fences``: tables {name}u, {name}q and {name}."""
    by = keys + "measure"
    least = "CASE measure " + " ".join(f"WHEN '{n}' THEN {unit}" for n, _, _, unit in _MEASURES) + " END"
    quartiles = ", ".join(f"min(CASE WHEN upto * 4 >= {k} * total THEN bin END) AS q{k}" for k in (1, 2, 3))
    return f"""
{name}k AS (SELECT {by}, bin, sum(n) AS n FROM k GROUP BY ALL),
{name}u AS (SELECT *, sum(n) OVER (PARTITION BY {by} ORDER BY bin ROWS UNBOUNDED PRECEDING) AS upto, sum(n) OVER (PARTITION BY {by}) AS total FROM {name}k),
{name}q AS (SELECT {by}, {quartiles}, max(total) AS n FROM {name}u GROUP BY {by}),
{name}s AS (SELECT *, greatest(q3 - q1, q2 // 16, {least}) AS span FROM {name}q),
{name} AS (SELECT {by}, n, q1 - {reach} * span AS low, q3 + {reach} * span AS high, q1 - {2 * reach} * span AS least, q3 + {2 * reach} * span AS top FROM {name}s)"""


def sql(reach: int = 4, least_rows: int = 20) -> str:
    measures = [(n, e.replace(" div ", " // "), side) for n, e, side, _ in _MEASURES]
    stacked = " UNION ALL ".join(f"SELECT lang, source, '{n}' AS measure, CAST({e} AS BIGINT) AS value FROM m WHERE NOT base_failed" for n, e, _ in measures)
    tests = []
    for n, e, side in measures:
        low = f" AND CAST({e} AS BIGINT) >= lo.{n}" if side == "both" else ""
        tests.append(f"(hi.{n} IS NULL OR (CAST({e} AS BIGINT) <= hi.{n}{low}))")
    wide = ", ".join(f"max(CASE WHEN measure = '{n}' THEN {{0}} END) AS {n}" for n, _, _ in measures)

    def pick(bounded: str, name: str) -> str:
        return f"CASE WHEN g.n >= {least_rows} THEN {bounded} WHEN l.n >= {least_rows} THEN l.{name} WHEN c.n >= {least_rows} THEN c.{name} END AS {name}"

    return rf"""
WITH d AS (SELECT row_number() OVER () AS rid, doc_id, lang, source, coalesce(text, '') AS text FROM documents),
w AS (SELECT *, regexp_extract_all(text, '[^\x20\x09-\x0D]+') AS ws,
        list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS ls FROM d),
t AS (SELECT rid, unnest(list_transform(range(1, len(ws) - 1), lambda i: {{'i': i, 'g': ws[i] || ' ' || ws[i + 1] || ' ' || ws[i + 2]}})) AS t
      FROM w WHERE len(ws) >= 3),
o AS (SELECT rid, t.i AS i, count(*) OVER (PARTITION BY rid, t.g) AS n FROM t),
r AS (SELECT rid, count(DISTINCT i + k) AS n FROM o, (VALUES (0), (1), (2)) AS v(k) WHERE n > 1 GROUP BY rid),
b AS (SELECT w.rid, doc_id, lang, source, CAST(len(ws) AS BIGINT) AS n_words,
        CAST(length(regexp_replace(text, '[\x20\x09-\x0D]', '', 'g')) AS BIGINT) AS word_chars,
        CAST(length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
        CAST(len(ls) - len(list_distinct(ls)) AS BIGINT) AS n_dup_lines,
        CAST(coalesce(r.n, 0) AS BIGINT) AS n_repeat_words
      FROM w LEFT JOIN r USING (rid)),
m AS (SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM b),
x AS ({stacked}),
k AS (SELECT lang, source, measure, {_SQL_BIN.format("value")} AS bin, count(*) AS n FROM x GROUP BY ALL),{_sql_fences("g", "lang, source, ", reach)},{_sql_fences("l", "lang, ", reach)},{_sql_fences("c", "", reach)},
f AS (SELECT g.lang, g.source, g.measure, {pick("greatest(g.low, l.least)", "low")}, {pick("least(g.high, l.top)", "high")}
      FROM g JOIN l ON g.lang IS NOT DISTINCT FROM l.lang AND g.measure = l.measure JOIN c ON g.measure = c.measure),
lo AS (SELECT lang, source, {wide.format("low")} FROM f GROUP BY lang, source),
hi AS (SELECT lang, source, {wide.format("high")} FROM f GROUP BY lang, source)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
  CASE WHEN base_failed THEN false ELSE {" AND ".join(tests)} END AS kept
FROM m LEFT JOIN lo ON m.lang IS NOT DISTINCT FROM lo.lang AND m.source IS NOT DISTINCT FROM lo.source
       LEFT JOIN hi ON m.lang IS NOT DISTINCT FROM hi.lang AND m.source IS NOT DISTINCT FROM hi.source
"""
