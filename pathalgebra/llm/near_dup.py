"""Near-duplicate documents: MinHash bands, odd sketches, exact confirmation.

1. Documents with equal shingle sets form classes; one member stands for each.
2. Bands of MinHash samples bring representatives together.  In a bucket, odd
   sketches pick candidate pairs: at first only from leaders to members, so that
   a group of n near copies costs n pairs.
3. Candidates are confirmed on the full shingle sets.
4. Pairs of a bucket that are still in different components are tried in
   further rounds, best estimates first, until none is left untried.

Buckets of more than ``bucket_rows`` members are dealt over several groups by the
leaders.  Where members of several components are left in such a bucket, all but
those of its least component are copied to every group, so no pair of a bucket
depends on the bucket's size.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathalgebra.llm.components import components
from pathalgebra.llm.memory import lean
from pathalgebra.llm.shingles import OddSketcher, shingle_sets
from pathalgebra.runtime import kept, scratch, stored

_SIGNED = "doc_id long, n_shingles long, k1 long, k2 long, bands array<long>, sketch binary"
_SIGNED_ARROW = pa.schema([
    ("doc_id", pa.int64()), ("n_shingles", pa.int64()), ("k1", pa.int64()), ("k2", pa.int64()), ("bands", pa.list_(pa.int64())), ("sketch", pa.binary()),
])
_PAIR_ARROW = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("more", pa.bool_())])


def _set_key(items: np.ndarray) -> tuple[int, int]:
    digest = np.frombuffer(xxhash.xxh3_128_digest(items.tobytes()), "<i8")
    return int(digest[0]), int(digest[1])


def signatures(documents: DataFrame, width: int, sketcher: OddSketcher) -> DataFrame:
    """Per document its set's size, key, band keys and odd sketch."""

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n, k1, k2, bands, sketches = [], [], [], [], []
            for items in shingle_sets(batch.column(1), width):
                n.append(len(items))
                a, b = _set_key(items)
                k1.append(a)
                k2.append(b)
                if len(items):
                    least = sketcher.minima(items)
                    bands.append(sketcher.band_keys(least))
                    sketches.append(sketcher.sketch(items))
                else:
                    bands.append([])
                    sketches.append(b"")
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(n, pa.int64()), pa.array(k1, pa.int64()), pa.array(k2, pa.int64()), pa.array(bands, pa.list_(pa.int64())), pa.array(sketches, pa.binary())],
                schema=_SIGNED_ARROW,
            )

    return documents.select(F.col("doc_id").cast("long"), "text").mapInArrow(lean(sign), _SIGNED)


def _runs(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[dict[str, np.ndarray]]:
    """Groups of consecutive rows with equal keys, of at least two rows."""
    held: list[pa.Table] = []

    def groups(rows: pa.Table, last: bool) -> tuple[list[tuple[int, int]], int]:
        new = np.zeros(len(rows), bool)
        new[:1] = True
        for k in keys:
            v = rows[k].to_numpy()
            new[1:] |= v[1:] != v[:-1]
        starts = np.flatnonzero(new)
        stops = np.append(starts[1:], len(rows))
        if not last:
            starts, stops = starts[:-1], stops[:-1]
        keep = stops - starts > 1
        return list(zip(starts[keep].tolist(), stops[keep].tolist(), strict=True)), int(stops[-1]) if len(stops) else 0

    def cut(rows: pa.Table, spans: list[tuple[int, int]]) -> Iterator[dict[str, np.ndarray]]:
        columns = {c: rows[c].to_numpy() for c in rows.column_names} if spans else {}
        for a, b in spans:
            yield {c: v[a:b] for c, v in columns.items()}

    for batch in batches:
        held.append(pa.Table.from_batches([batch]))
        rows = pa.concat_tables(held).combine_chunks()
        spans, done = groups(rows, last=False)
        yield from cut(rows, spans)
        held = [rows.slice(done)]
    if held:
        rows = pa.concat_tables(held).combine_chunks()
        yield from cut(rows, groups(rows, last=True)[0])


def _leader_pairs(group: dict, sketcher: OddSketcher, percent: int) -> list[tuple[int, int]]:
    """Star pairs: each member to the first leader that it resembles."""
    ids, where = np.unique(group["rep"], return_index=True)
    bits = sketcher.table(group["sketch"][where])
    left, pairs = np.arange(len(ids)), []
    head = int(group["head"][0])
    while len(left):
        seed, rest = left[0], left[1:]
        alike = sketcher.similarity(bits[seed], bits[rest], percent)[1]
        pairs += [(int(ids[seed]), int(x)) for x in ids[rest[alike]]]
        if head < ids[seed]:  # the bucket's head ties together what was dealt to several groups
            pairs.append((head, int(ids[seed])))
        left = rest[~alike]
    return pairs


def _open_pairs(group: dict, sketcher: OddSketcher, percent: int, limit: int | None) -> tuple[list[tuple[int, int]], bool]:
    """Pairs of one minor member and one member of another component, best first.

    A pair that shares several bands is given in the bucket of its first one only,
    and in a bucket that is dealt out where its second member is the group's own.
    """
    ids, where = np.unique(group["rep"], return_index=True)
    bits, comp, minor = sketcher.table(group["sketch"][where]), group["comp"][where], group["minor"][where]
    bands = np.stack(group["bands"][where])
    place = int(np.flatnonzero(bands[0] == group["key"][0])[0])
    earlier, own = bands[:, :place], group["own"][where]
    pairs, more = [], False
    for i in np.flatnonzero(minor):
        other = np.flatnonzero(own & (comp != comp[i]) & (~minor | (ids > ids[i])))
        other = other[~(earlier[other] == earlier[i]).any(axis=1)]
        near, may = sketcher.similarity(bits[i], bits[other], percent)
        other, near = other[may], near[may]
        if limit is not None and len(other) > limit:
            more = True
            other = other[np.argsort(-near, kind="stable")[:limit]]
        pairs += [(int(min(ids[i], ids[j])), int(max(ids[i], ids[j]))) for j in other]
    return pairs, more


def _open_groups(label: DataFrame, bucket_rows: int) -> DataFrame:
    """Members of buckets with several components, as groups (key, part).

    Groups have about ``bucket_rows`` members of their own.  A larger bucket is dealt
    out over several, and minor members, whose component isn't the bucket's least, are
    copied to each, so the same pairs are tried whatever the bucket's size.
    """
    mixed = label.groupBy("key").agg(F.min("comp").alias("main"), F.max("comp").alias("top")).where("main <> top").select("key", "main")
    rows = label.join(stored(mixed, "mixed"), "key").withColumn("minor", F.col("comp") != F.col("main")).drop("main")
    parts = F.ceil(F.col("n") / bucket_rows).cast("int")
    mine = F.pmod(F.xxhash64("rep"), parts).cast("int")
    dealt = rows.withColumn("mine", mine).withColumn("part", F.explode(F.when(F.col("minor"), F.sequence(F.lit(0), parts - 1)).otherwise(F.array(mine))))
    return dealt.select("key", "part", "rep", "sketch", "bands", "comp", "minor", (F.col("part") == F.col("mine")).alias("own"))


def _confirmed(texts: DataFrame, reps: DataFrame, pairs: DataFrame, width: int, percent: int, fan: int) -> DataFrame:
    """Pairs (a, b) whose full sets have intersection * 100 >= percent * union."""
    spread = F.pmod(F.xxhash64("b"), F.lit(1 << 20))
    pairs = stored(pairs.select("a", "b").distinct(), "pairs")
    per = stored(pairs.groupBy("a").agg(F.ceil(F.count("*") / fan).cast("int").alias("parts")), "pair-fan")
    members = pairs.join(per, "a").select(F.col("b").alias("id"), "a", (spread % F.col("parts")).cast("int").alias("part"), F.lit(1).alias("member"))
    leaders = per.select(F.col("a").alias("id"), "a", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), F.lit(0).alias("member"))
    asked = members.unionByName(leaders)
    asked = asked.join(reps.select(F.col("rep").alias("id"), "k1"), "id")
    asked = stored(asked, "asked")

    def to_sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets, keep = [], []
            for k, items in enumerate(shingle_sets(batch.column(1), width)):
                if _set_key(items)[0] == batch.column(2)[k].as_py():
                    keep.append(k)
                    sets.append(items.tobytes())
            rest = batch.take(pa.array(keep, pa.int64()))
            yield pa.RecordBatch.from_arrays([rest.column(0), rest.column(3), rest.column(4), rest.column(5), pa.array(sets, pa.binary())], names=["id", "a", "part", "member", "items"])

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, leader = None, None
        for batch in batches:
            a_out, b_out = [], []
            for b, a, part, member, items in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                items = np.frombuffer(items, np.uint64)
                if not member:
                    at, leader = (a, part), items
                elif at == (a, part):
                    both = len(items) + len(leader) - len(np.unique(np.concatenate([items, leader])))
                    if 100 * both >= percent * (len(items) + len(leader) - both):
                        a_out.append(a)
                        b_out.append(b)
            yield pa.RecordBatch.from_arrays([pa.array(a_out, pa.int64()), pa.array(b_out, pa.int64())], names=["a", "b"])

    # What is asked for grows with the input, so neither side is ever broadcast.
    sets = texts.join(asked.hint("merge"), "id").select("id", "text", "k1", "a", "part", "member")
    sets = sets.mapInArrow(to_sets, "id long, a long, part int, member int, items binary")
    dealt = sets.repartition("a", "part").sortWithinPartitions("a", "part", "member")
    return dealt.mapInArrow(compare, "a long, b long")


def near_duplicates(
    documents: DataFrame, width: int = 5, percent: int = 80, sketcher: OddSketcher | None = None, bucket_rows: int = 2000, limits: tuple[int | None, ...] = (16, None)
) -> DataFrame:
    """Per row of ``documents``: doc_id, n_shingles, component_id, kept.

    Linked are documents whose shingle sets have a Jaccard similarity of at
    least ``percent`` / 100; a component's id is its least doc_id, and that
    document is the one to keep.  Null and wordless texts have an empty set and
    are linked with nothing.  Rows of one doc_id count as one document if their
    sets are equal.  A null doc_id is linked with nothing: its component_id is
    null and kept is false.  Other columns are ignored; no rows give no rows.

    Bands of five samples miss a pair of similarity 0.85 (0.8) with probability
    about 8e-6 (4e-4, or 2e-7 with 40 bands), whatever the sizes of buckets; sketches
    rule a pair out at four deviations.
    """
    sketcher = sketcher or OddSketcher(bands=20 if percent >= 85 else 40)
    with scratch(documents.sparkSession):
        return kept(_components_of(documents, width, percent, sketcher, bucket_rows, limits), "near-duplicates")


def _components_of(documents: DataFrame, width: int, percent: int, sketcher: OddSketcher, bucket_rows: int, limits: tuple[int | None, ...]) -> DataFrame:
    signed = stored(signatures(documents, width, sketcher), "signed")
    known = signed.where("n_shingles > 0 and doc_id is not null")
    classes = stored(known.groupBy("k1", "k2").agg(F.min("doc_id").alias("rep")), "classes")
    members = known.select("k1", "k2", F.col("doc_id").alias("rep"), "bands", "sketch").join(classes, ["k1", "k2", "rep"])
    reps = stored(members, "reps")
    # Only numbers are shuffled for all bands; sketches join what shares a bucket.
    keys = reps.select("rep", F.explode("bands").alias("key"))
    counts = stored(keys.groupBy("key").agg(F.count("*").alias("n"), F.min("rep").alias("head")).where("n > 1"), "buckets")
    parts = F.ceil(F.col("n") / bucket_rows)
    keys = keys.join(counts.hint("merge"), "key").withColumn("part", F.pmod(F.xxhash64("rep"), parts).cast("int"))
    keys = stored(keys.select("key", "part", "n", "head", "rep"), "bucket-keys")
    rows = stored(keys.join(reps.select("rep", "sketch", "bands").hint("merge"), "rep"), "bucket-rows")

    def leaders(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group in _runs(batches, ["key", "part"]):
            yield _as_pairs(_leader_pairs(group, sketcher, percent), False)

    # Texts of documents that share a bucket with another one; all later rounds read these only.
    shared = stored(rows.select(F.col("rep").alias("id")).distinct(), "candidates")
    texts = documents.select(F.col("doc_id").cast("long").alias("id"), "text").join(shared.hint("merge"), "id", "left_semi")
    texts = stored(texts, "candidate-texts")

    first = rows.drop("bands").repartition("key", "part").sortWithinPartitions("key", "part").mapInArrow(leaders, "a long, b long, more boolean")
    links = stored(_confirmed(texts, reps, first, width, percent, fan=500), "links")
    named = components(links)

    group_keys = ["key", "part"]
    for limit in limits:
        label = rows.join(named.select(F.col("id").alias("rep"), "component_id"), "rep", "left").withColumn("comp", F.coalesce("component_id", "rep"))
        label = stored(label.select("key", "n", "rep", "sketch", "bands", "comp"), "labelled")
        def tries(batches: Iterator[pa.RecordBatch], limit: int | None = limit) -> Iterator[pa.RecordBatch]:
            for group in _runs(batches, group_keys):
                yield _as_pairs(*_open_pairs(group, sketcher, percent, limit))

        tried = _open_groups(label, bucket_rows).repartition(*group_keys).sortWithinPartitions(*group_keys)
        tried = stored(tried.mapInArrow(tries, "a long, b long, more boolean"), "tried")
        state = tried.agg(F.count("*"), F.max(F.col("more").cast("int"))).first()
        if not state[0]:
            break
        found = stored(_confirmed(texts, reps, tried, width, percent, fan=500), "more-links")
        if not found.isEmpty():
            links = links.unionByName(found)
            named = components(links)
        if not state[1]:
            break

    final = classes.join(named.select(F.col("id").alias("rep"), "component_id"), "rep", "left")
    final = stored(final.select("k1", "k2", F.coalesce("component_id", "rep").alias("component")), "final")
    out = known.select("doc_id", "n_shingles", "k1", "k2").join(final, ["k1", "k2"]).select("doc_id", "n_shingles", F.col("component").alias("component_id"))
    alone = signed.where("not (n_shingles > 0 and doc_id is not null)").select("doc_id", "n_shingles", F.col("doc_id").alias("component_id"))
    return out.unionByName(alone).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(False)))


def without_near_duplicates(documents: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """One document of each component, with the columns of ``documents``.

    Of rows that share a doc_id one stays; rows without a doc_id all stay.
    """
    found = stored(near_duplicates(documents, width, percent).select("doc_id", "kept"), "near-dup-kept")
    gone = stored(found.where("not kept and doc_id is not null").select("doc_id").distinct(), "near-dup-gone")
    left = documents.join(gone, "doc_id", "left_anti").select(*documents.columns)
    again = stored(found.where("doc_id is not null").groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1").select("doc_id"), "near-dup-again")
    if again.isEmpty():
        return left
    single = left.join(again, "doc_id", "left_anti").select(*documents.columns)
    return single.unionByName(left.join(again, "doc_id", "left_semi").select(*documents.columns).dropDuplicates(["doc_id"]))


def _as_pairs(pairs: list[tuple[int, int]], more: bool) -> pa.RecordBatch:
    a, b = (list(x) for x in zip(*pairs, strict=True)) if pairs else ([], [])
    return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array([more] * len(a), pa.bool_())], schema=_PAIR_ARROW)
