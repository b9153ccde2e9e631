"""Near-duplicate vectors: spherical k-means cells and blocked cosine products.

Equal vectors of a label form a class that one vector stands for.  Every
representative belongs to its nearest cell and visits cells of a lower number;
inside a cell, members are compared with members and visitors, so every linked pair
that meets does so once.  A vector whose nearest centre is ``a`` visits cell ``b``
if it lies near the plane halfway between the two centres.  A linked vector beyond
that plane can't be farther away than the sine of the angle of ``least``; if the
difference of the two has no preferred direction, its part across the plane has a
deviation of that distance over the root of the dimensions, and ``deviations`` of
them are allowed for.  So the visits grow far slower than the cells.  A task gives
sums of links and a spanning forest, not pairs, so a group of n near copies
costs n rows.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathalgebra.llm.components import components
from pathalgebra.runtime import stored

_OUT = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("links", pa.int64())])


def spherical_kmeans(vectors: np.ndarray, cells: int, rounds: int = 8, seed: int = 7) -> np.ndarray:
    """Unit centres; a cell that loses all members takes the worst-fitting vector."""
    x = vectors / np.linalg.norm(vectors, axis=1, keepdims=True)
    centres = x[np.random.default_rng(seed).permutation(len(x))[:cells]]
    for _ in range(rounds):
        near = x @ centres.T
        best = near.argmax(axis=1)
        sums = np.zeros_like(centres)
        np.add.at(sums, best, x)
        empty = np.flatnonzero(np.bincount(best, minlength=len(centres)) == 0)
        if len(empty):
            sums[empty] = x[np.argsort(near.max(axis=1))[: len(empty)]]
        norms = np.linalg.norm(sums, axis=1, keepdims=True)
        centres = np.where(norms > 0, sums / np.maximum(norms, 1e-300), centres)
    return centres


def _usable() -> Column:
    """True for rows that can be linked; never null."""
    v = F.col("embedding")
    finite = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf")))
    nonzero = F.exists(v, lambda x: x != 0)
    return F.coalesce(F.col("label").isNotNull() & F.col("vec_id").isNotNull() & v.isNotNull() & finite & nonzero, F.lit(False))


def _matrix(column: pa.Array, dim: int) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, dim)


def _joined(label: np.ndarray, i: np.ndarray, j: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Labels of components after linking i with j, and the links that a forest needs.

    In a round every root hooks onto the least root that it is linked with, so the
    rounds grow with the logarithm of the links.
    """
    a_out, b_out = [], []
    while True:
        a, b = label[i], label[j]
        apart = a != b
        i, j, a, b = i[apart], j[apart], a[apart], b[apart]
        if not len(i):
            break
        high, low = np.maximum(a, b), np.minimum(a, b)
        order = np.lexsort((low, high))
        roots, first = np.unique(high[order], return_index=True)
        taken = order[first]
        a_out.append(i[taken])
        b_out.append(j[taken])
        up = np.arange(len(label))
        up[roots] = low[taken]
        while (further := up[up]).tobytes() != up.tobytes():
            up = further
        label = up[label]
    none = [np.empty(0, np.int64)]
    return label, np.concatenate(a_out or none), np.concatenate(b_out or none)


def _compare(rows: pa.Table, dim: int, least: float, step: int = 512) -> pa.RecordBatch:
    """All linked pairs of one task, as sums of links and forest edges."""
    ids = rows["rep"].to_numpy()
    role = rows["role"].to_numpy()
    weight = rows["n"].to_numpy()
    raw = _matrix(rows["embedding"].combine_chunks(), dim)
    norm = np.sqrt((raw * raw).sum(axis=1))
    left, right = np.flatnonzero(role == 0), np.flatnonzero(role != 0)
    same_block = not (role == 1).any()
    if same_block:
        # Further shares of the visitors meet the members, who have met each other in the first.
        right = np.arange(len(ids)) if rows["m"][0].as_py() == 0 else np.flatnonzero(role == 2)
    sums = np.zeros(len(ids), np.int64)
    label, a_out, b_out = np.arange(len(ids)), [np.empty(0, np.int64)], [np.empty(0, np.int64)]
    for at in range(0, len(left), step):
        rows_at = left[at : at + step]
        for to in range(0, len(right), 4 * step):
            cols_at = right[to : to + 4 * step]
            near = (raw[rows_at] @ raw[cols_at].T) / (norm[rows_at][:, None] * norm[cols_at][None, :])
            i, j = np.nonzero(near >= least)
            i, j = rows_at[i], cols_at[j]
            member = role[j] != 2
            # Members of one block meet twice.
            once = np.where(member, (i < j) | (role[j] == 1), True)
            i, j = i[once], j[once]
            np.add.at(sums, i, weight[j])
            np.add.at(sums, j, weight[i])
            label, p, q = _joined(label, i, j)
            a_out.append(p)
            b_out.append(q)
    some = np.flatnonzero(sums)
    p, q = np.concatenate(a_out), np.concatenate(b_out)
    edges = pa.RecordBatch.from_arrays([pa.array(ids[p]), pa.array(ids[q]), pa.nulls(len(p), pa.int64())], schema=_OUT)
    counts = pa.RecordBatch.from_arrays([pa.array(ids[some]), pa.nulls(len(some), pa.int64()), pa.array(sums[some])], schema=_OUT)
    return pa.Table.from_batches([edges, counts]).combine_chunks().to_batches()[0] if len(p) + len(some) else edges


def _fit_cells(picked: DataFrame, total: int, cell_rows: int) -> dict[int, np.ndarray]:
    """Centres by dimension, fitted in one task on the bounded sample."""

    def fit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = sorted((r for batch in batches for r in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True)), key=lambda r: r[0])
        by_dim: dict[int, list] = {}
        for _, v in rows:
            by_dim.setdefault(len(v), []).append(v)
        centres = {d: spherical_kmeans(np.array(x), max(1, min(-(-total // cell_rows), len(x) // 8))) for d, x in by_dim.items()}
        yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(centres)], pa.binary())], names=["centres"])

    found = picked.repartition(1).mapInArrow(fit, "centres binary").first()
    return pickle.loads(found["centres"]) if found is not None else {}


def near_vectors(
    vectors: DataFrame, least: float = 0.93, cell_rows: int = 2000, sample: int = 20_000, block: int = 4096, deviations: float | None = 4.0
) -> DataFrame:
    """Per row: vec_id, n_links, component_id, kept.

    Linked are vectors of equal label (and length) with cosine >= ``least`` in
    double precision.  Vectors that are null or zero, or hold null or non-finite
    parts, and those without a label or a vec_id, are linked with nothing.
    Repeated rows of a vec_id with equal vectors count as one vector.  Other
    columns are ignored; no rows give no rows.

    Cells are fitted on ``sample`` representatives at most; every representative
    is then assigned.  Cells of more than ``block`` members are compared block
    against block in tasks of their own, and visitors in shares of about ``4 * block``.
    Vectors without structure rule out few cells, and then all pairs are compared.
    """
    # Parts that come as floats are moved as floats and compared as doubles.
    kind = "array<float>" if vectors.schema["embedding"].dataType.simpleString() == "array<float>" else "array<double>"
    rows = vectors.select(F.col("vec_id").cast("long"), F.col("label"), F.col("embedding").cast(kind))
    usable = rows.where(_usable())
    classes = usable.distinct().groupBy("label", "embedding").agg(F.min("vec_id").alias("rep"), F.count("*").alias("n"))
    classes = stored(classes, "classes")
    # Only equal labels are compared, so the largest label decides how many cells there are.
    total = classes.groupBy("label").agg(F.count("*").alias("m")).agg(F.coalesce(F.max("m"), F.lit(0))).first()[0]
    centres = _fit_cells(classes.select("rep", "embedding").orderBy(F.xxhash64("rep"), "rep").limit(sample), total, cell_rows)
    apart = {dim: np.stack([np.linalg.norm(c - one, axis=1) for one in c]) for dim, c in centres.items()}

    def reach(dim: int) -> float:
        """How far from the plane between two centres a vector visits the other cell."""
        if least <= 0:
            return 2.0  # an obtuse angle rules nothing out
        sure = max(0.0, 1 - least * least) ** 0.5
        return sure if deviations is None or dim < 2 else min(sure, deviations * sure / least / (dim - 1) ** 0.5)

    def assign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = []
            for v in batch.column(batch.schema.get_field_index("embedding")).to_numpy(zero_copy_only=False):
                v = v.astype(np.float64)
                c = centres.get(len(v))
                if c is None:
                    found.append([0])
                    continue
                # Scaled first: squares of huge or tiny parts leave the range of doubles.
                v = v / np.abs(v).max()
                near = c @ (v / np.linalg.norm(v))
                home = int(near.argmax())
                visits = np.flatnonzero(near[home] - near[:home] <= reach(len(v)) * apart[len(v)][home, :home] + 1e-9)
                found.append([home, *visits.tolist()])
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(found, pa.list_(pa.int32()))], names=[*batch.schema.names, "visits"])

    columns = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in classes.schema)
    placed = classes.mapInArrow(assign, f"{columns}, visits array<int>").withColumn("dim", F.size("embedding")).withColumn("home", F.get("visits", F.lit(0)))
    placed = stored(placed, "placed")
    counts = placed.groupBy("label", "dim", "home").agg(F.ceil(F.count("*") / block).cast("int").alias("parts")).withColumnRenamed("home", "cell")
    counts = stored(counts, "cells")
    entries = placed.select("label", "dim", "home", F.explode("visits").alias("cell")).where("cell <> home")
    entries = entries.groupBy("label", "dim", "cell").agg(F.ceil(F.count("*") / (4 * block)).cast("int").alias("shares"))
    counts = stored(counts.join(entries, ["label", "dim", "cell"], "left").fillna(1, ["shares"]), "shares")
    spread = placed.withColumn("cell", F.explode("visits")).join(counts, ["label", "dim", "cell"])
    mine = F.pmod(F.xxhash64("rep"), F.col("parts")).cast("int")
    parts = F.sequence(F.lit(0), F.col("parts") - 1)

    share = F.pmod(F.xxhash64("rep", F.lit(1)), F.col("shares")).cast("int")
    shares = F.sequence(F.lit(0), F.col("shares") - 1)

    def task(i, j, m, role):
        return F.struct(i.cast("int").alias("i"), j.cast("int").alias("j"), m.cast("int").alias("m"), role.alias("role"))

    def pairs(k):
        other = F.array(task(F.least(mine, k), F.greatest(mine, k), F.lit(0), F.when(mine <= k, F.lit(0)).otherwise(F.lit(1))))
        return F.when(mine == k, F.transform(shares, lambda m: task(k, k, m, F.lit(0)))).otherwise(other)

    as_member = F.flatten(F.transform(parts, pairs))
    as_visitor = F.transform(parts, lambda k: task(k, k, share, F.lit(2)))
    spread = spread.withColumn("t", F.explode(F.when(F.col("cell") == F.col("home"), as_member).otherwise(as_visitor)))
    dealt = spread.select("label", "dim", "cell", "t.i", "t.j", "t.m", "t.role", "rep", "n", "embedding")
    keys = ["label", "dim", "cell", "i", "j", "m"]

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None
        for batch in batches:
            now = pa.Table.from_batches([batch])
            held = now if held is None else pa.concat_tables([held, now])
            new = np.zeros(len(held), bool)
            for k in keys:
                v = held[k].to_numpy()
                new[1:] |= v[1:] != v[:-1]
            starts = [0, *np.flatnonzero(new).tolist()]
            for a, b in zip(starts, starts[1:], strict=False):
                yield _compare(held.slice(a, b - a), held["dim"][a].as_py(), least)
            held = held.slice(starts[-1])
        if held is not None and len(held):
            yield _compare(held, held["dim"][0].as_py(), least)

    done = dealt.repartition(*keys).sortWithinPartitions(*keys).mapInArrow(compare, "a long, b long, links long")
    done = stored(done, "compared")
    named = components(done.where("b is not null").select("a", "b"))
    links = done.where("b is null").groupBy("a").agg(F.sum("links").alias("links"))
    final = classes.join(stored(links, "links").withColumnRenamed("a", "rep"), "rep", "left").join(named.withColumnRenamed("id", "rep"), "rep", "left")
    final = final.select("label", "embedding", (F.col("n") - 1 + F.coalesce("links", F.lit(0))).alias("n_links"), F.coalesce("component_id", "rep").alias("component_id"))
    final = stored(final, "final")
    found = usable.join(final, ["label", "embedding"]).select("vec_id", "n_links", "component_id")
    rest = rows.where(~_usable()).select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return found.unionByName(rest).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(False)))
