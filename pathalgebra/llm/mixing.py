"""Mixing sources to target weights along a curriculum, in DataFrame functions only.

Each source has a weight that changes with training time ``u`` in [0, 1]:
``1 + tilt * (2u - 1)`` times its share.  Its integral is the source's token
demand up to ``u``; inverting it at the tokens that stand before a document
gives the document's training position.  Range-sorting by position gives the
order of training.

Targets share all words by weight, no source above ``most_repeats`` times its
size; what is over goes to the others by weight until none is above.  Documents
of a source stand in the order of a hash and are passed through again and again;
every pass of a document stands where the demand reaches the words before it.  A
pass whose position lies in [0, 1) is taken, the last one in part, so a source meets
its target to a word.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pathalgebra.runtime import stored

#: Fixed value: a word is a run of other characters than the six blanks.
WORD = r"[^\x20\x09-\x0D]+"
_NEVER = Window.unboundedPreceding


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = (1, 2, 3), most_repeats: int = 3) -> DataFrame:
    """(source, source_size, target, tilt) from (source, source_size).

    Sources by code point, null last, take the weights in turn.  The shares that
    resharing ends with are least(cap, level * weight) for one level; sorted by
    cap over weight, the first source whose cap isn't reached tells the level.
    One row per source, so the windows over all of them are small.
    """
    by_name = Window.orderBy(F.col("source").isNull(), F.encode("source", "UTF-8"))
    weight = F.element_at(F.array(*map(F.lit, weights)), ((F.row_number().over(by_name) - 1) % len(weights) + 1).cast("int")).cast("long")
    named = sizes.withColumn("weight", weight).withColumn("rank", F.row_number().over(by_name)).withColumn("cap", F.lit(most_repeats) * F.col("source_size"))
    # Order by cap / weight without division: all weights have a small common multiple.
    common = 1
    for w in weights:
        common *= w
    by_ratio = Window.orderBy(F.expr(f"cap * ({common} div weight)"), "rank")
    everything = Window.partitionBy()
    table = (
        named.withColumn("capped", F.coalesce(F.sum("cap").over(by_ratio.rowsBetween(_NEVER, -1)), F.lit(0)))
        .withColumn("heavy", F.sum("weight").over(by_ratio.rowsBetween(0, Window.unboundedFollowing)))
        .withColumn("all_words", F.sum("source_size").over(everything))
        .withColumn("at", F.row_number().over(by_ratio))
    )
    fits = F.col("cap") * F.col("heavy") >= F.col("weight") * (F.col("all_words") - F.col("capped"))
    table = table.withColumn("first", F.min(F.when(fits, F.col("at"))).over(everything))
    table = table.withColumn("room", F.max(F.when(F.col("at") == F.col("first"), F.col("all_words") - F.col("capped"))).over(everything))
    table = table.withColumn("rivals", F.max(F.when(F.col("at") == F.col("first"), F.col("heavy"))).over(everything))
    share = (F.col("weight") * F.col("room")).cast("double") / F.col("rivals").cast("double")
    target = F.when(F.col("at") < F.col("first"), F.col("cap").cast("double")).otherwise(share)
    # Later sources of the cycle of weights rise with time, the first ones fall.
    tilt = (F.lit(2.0) * (F.col("weight") - min(weights)) / max(1, max(weights) - min(weights)) - 1) * 0.5
    return table.select("source", "source_size", target.alias("target"), tilt.alias("tilt"))


def mix_sources(documents: DataFrame, weights: tuple[int, ...] = (1, 2, 3), most_repeats: int = 3, buckets: int = 4096) -> DataFrame:
    """Per document: doc_id, size, source_size, target, taken, position, last_position, passes.

    ``taken`` counts the words of all passes whose position lies in [0, 1);
    ``position`` and ``last_position`` are those of the first and the last of these
    ``passes``, null if there is none.  Documents without words have no pass.
    Null text has no words; a null source is a source of its own, the last one;
    rows that share a doc_id are taken like others.  Where all sizes are 0,
    targets are 0.  Other columns are ignored; no rows give no rows.

    The order within a source is that of a hash of doc_id, cut into ``buckets``:
    only their sums meet in one place, so a source of any share of the rows is
    spread over the cluster.
    """
    key = F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary"))
    rows = documents.select("doc_id", "source", word_count(F.col("text")).alias("size"), key.alias("key"))
    if buckets not in (16, 256, 4096):
        raise ValueError("buckets must be a power of 16 up to 4096")
    digits = {16: 1, 256: 2, 4096: 3}[buckets]
    rows = stored(rows.withColumn("bucket", F.substring("key", 1, digits)), "sizes")
    sums = stored(rows.groupBy("source", "bucket").agg(F.sum("size").alias("words")), "bucket-sums")
    targets = source_targets(sums.groupBy("source").agg(F.sum("words").alias("source_size")), weights, most_repeats)
    targets = stored(targets, "targets")
    before = Window.partitionBy("source").orderBy("bucket").rowsBetween(_NEVER, -1)
    starts = sums.select(F.col("source").alias("s"), F.col("bucket").alias("b"), F.coalesce(F.sum("words").over(before), F.lit(0)).alias("start"))
    starts = starts.join(targets, F.col("s").eqNullSafe(F.col("source"))).drop("source")
    starts = stored(starts, "starts")
    within = Window.partitionBy("source", "bucket").orderBy("key", "doc_id", "size").rowsBetween(_NEVER, 0)
    placed = rows.withColumn("upto", F.sum("size").over(within))
    placed = placed.join(starts, F.col("source").eqNullSafe(F.col("s")) & (F.col("bucket") == F.col("b")))
    placed = placed.withColumn("goal", F.floor("target").cast("long")).withColumn("before", F.col("start") + F.col("upto") - F.col("size"))
    # Where each pass begins in the source's words; those that begin before the goal are taken.
    begins = F.transform(F.sequence(F.lit(0), F.lit(most_repeats)), lambda k: F.col("before") + k * F.col("source_size"))
    placed = placed.withColumn("begins", F.when(F.col("size") > 0, F.filter(begins, lambda at: at < F.col("goal"))).otherwise(F.array().cast("array<bigint>")))
    part = F.aggregate("begins", F.lit(0).cast("long"), lambda acc, at: acc + F.least(F.col("size"), F.col("goal") - at))
    place = F.transform("begins", lambda at: F.round(training_position(at, F.col("target"), F.col("tilt")), 9))
    placed = placed.withColumn("taken", part).withColumn("places", place).withColumn("passes", F.size("begins").cast("long"))
    return placed.select("doc_id", "size", "source_size", "target", "taken", F.get("places", F.lit(0)).alias("position"), F.get("places", F.col("passes").cast("int") - 1).alias("last_position"), "passes")


def training_position(words: Column, target: Column, tilt: Column) -> Column:
    """Where in [0, 1] the demand of a source reaches ``words``.

    The demand up to u is target * ((1 - tilt) * u + tilt * u * u); this is its inverse.
    """
    share = F.when(target > 0, F.least(F.lit(1.0), words / target)).otherwise(0.0)
    root = F.sqrt((1 - tilt) * (1 - tilt) + 4 * tilt * share)
    return F.when(tilt == 0, share).otherwise((2 * share) / ((1 - tilt) + root))


def training_order(mixed: DataFrame, untaken: bool = False) -> DataFrame:
    """The mix in training order: one range-partitioned sort by position.

    Untaken documents are left out, or with ``untaken`` stand behind all others.
    """
    rows = mixed if untaken else mixed.where("taken > 0")
    order = (F.col("position").asc_nulls_last(), F.col("doc_id").asc_nulls_first())
    return rows.repartitionByRange(*order).sortWithinPartitions(*order)


def repeat_by_mix(documents: DataFrame, weights: tuple[int, ...] = (1, 2, 3), most_repeats: int = 3) -> DataFrame:
    """The documents that the mix takes, once for each pass, in training order.

    Passes are whole: the document that a source's target would cut is taken once
    more if at least half of it is due.  Columns are those of ``documents``.
    Documents without words are taken by no target and are left out.  The order
    needs no join by document: a document's hash, as a share of the range of
    hashes, is the share of its source's tokens that stand before it, and the
    demand inverted there is its position.  One join with a row for each source,
    one range-partitioned sort.
    """
    mixed = stored(mix_sources(documents, weights, most_repeats).select("doc_id", "size", "source_size", "target", "taken"), "mixed")
    key = F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary"))
    sized = documents.select("doc_id", F.col("source").alias("s")).withColumn("key", key)
    extra = F.expr("2 * (taken - (cast(floor(target) as bigint) div source_size) * size) >= size")
    per_id = mixed.where("size > 0").groupBy("doc_id").agg(F.max(extra).alias("extra"))
    last = sized.join(per_id, sized["doc_id"].eqNullSafe(per_id["doc_id"])).groupBy("s").agg(F.max(F.when(F.col("extra"), F.col("key"))).alias("last"))
    sums = documents.groupBy("source").agg(F.sum(word_count(F.col("text"))).alias("source_size"))
    plan = source_targets(sums, weights, most_repeats).where("source_size > 0")
    plan = plan.join(last, F.col("source").eqNullSafe(F.col("s"))).select("s", "source_size", "target", "tilt", "last")
    plan = stored(plan, "mix-plan")
    columns = [documents[c] for c in documents.columns]
    joined = documents.join(plan, documents["source"].eqNullSafe(plan["s"])).where(word_count(documents["text"]) > 0)
    whole = F.expr("cast(floor(target) as bigint) div source_size")
    joined = joined.select(*columns, (whole + F.coalesce((key <= F.col("last")).cast("int"), F.lit(0))).alias("_times"), key.alias("_key"), "source_size", "target", "tilt")
    joined = joined.where("_times > 0").withColumn("_pass", F.explode(F.sequence(F.lit(0).cast("long"), F.col("_times") - 1)))
    part = F.conv(F.substring("_key", 1, 8), 16, 10).cast("double") / float(1 << 32)
    placed = joined.withColumn("_at", training_position((F.col("_pass") + part) * F.col("source_size"), F.col("target"), F.col("tilt")))
    return placed.repartitionByRange("_at", "_key").sortWithinPartitions("_at", "_key").select(*documents.columns)


#: The rows of mix_sources() for the default parameters.
SQL = r"""
WITH d AS (
  SELECT doc_id, source, md5(coalesce(CAST(doc_id AS VARCHAR), '')) AS key,
         CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size
  FROM documents),
s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source),
w AS (SELECT *, row_number() OVER (ORDER BY source IS NULL, encode(source)) AS rnk FROM s),
c AS (SELECT *, CAST(1 + (rnk - 1) % 3 AS BIGINT) AS weight, 3 * source_size AS cap FROM w),
r AS (SELECT *, row_number() OVER o AS pos,
        coalesce(sum(cap) OVER (ORDER BY cap * (6 // weight), rnk ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS capped,
        sum(weight) OVER (ORDER BY cap * (6 // weight), rnk ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS heavy,
        (SELECT sum(source_size) FROM s) AS all_words
      FROM c WINDOW o AS (ORDER BY cap * (6 // weight), rnk)),
f AS (SELECT * FROM r WHERE cap * heavy >= weight * (all_words - capped) ORDER BY pos LIMIT 1),
t AS (SELECT r.source, r.source_size, 0.5 * (r.weight - 2) AS tilt,
        CASE WHEN r.pos < f.pos THEN CAST(r.cap AS DOUBLE)
             ELSE CAST(r.weight * (f.all_words - f.capped) AS DOUBLE) / CAST(f.heavy AS DOUBLE) END AS target
      FROM r, f),
p AS (SELECT d.doc_id, d.size, t.source_size, t.target, CAST(t.tilt AS DOUBLE) AS tilt, CAST(floor(t.target) AS BIGINT) AS goal,
        CAST(sum(d.size) OVER (PARTITION BY d.source ORDER BY d.key, d.doc_id, d.size ROWS UNBOUNDED PRECEDING) - d.size AS BIGINT) AS before
      FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source),
q AS (SELECT *, CASE WHEN size = 0 OR goal <= before THEN 0 ELSE 1 + (goal - 1 - before) // source_size END AS passes FROM p),
e AS (SELECT *, least(1.0::DOUBLE, CAST(before AS DOUBLE) / target) AS s1, least(1.0::DOUBLE, CAST(before + (passes - 1) * source_size AS DOUBLE) / target) AS s2 FROM q)
SELECT doc_id, size, source_size, target, passes,
  CAST(CASE WHEN passes = 0 THEN 0 ELSE (passes - 1) * size + least(size, goal - before - (passes - 1) * source_size) END AS BIGINT) AS taken,
  CASE WHEN passes > 0 THEN round(CASE WHEN tilt = 0 THEN s1 ELSE 2 * s1 / ((1 - tilt) + sqrt((1 - tilt) * (1 - tilt) + 4 * tilt * s1)) END, 9) END AS position,
  CASE WHEN passes > 0 THEN round(CASE WHEN tilt = 0 THEN s2 ELSE 2 * s2 / ((1 - tilt) + sqrt((1 - tilt) * (1 - tilt) + 4 * tilt * s2)) END, 9) END AS last_position
FROM e
"""
