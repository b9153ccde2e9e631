"""Transitive closures: squaring, linear, two-pass quadrants, components, restricted.

Loops run on the driver; a round is a join, a ``distinct`` and an anti-join with
what is known.  What is known lies in a table bucketed by both ends to which every
round appends its new pairs: nothing that was written is written or shuffled again.
Where the other factor stays the same, it is bucketed by its rows once.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark import InheritableThread
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathalgebra.operators import matrix as m
from pathalgebra.operators.components import LEAF_ONES, closure_pairs, factored_closure, leaf_closure, saturated, undirected_components
from pathalgebra.runtime import checkpointed, fresh_path, stored


class _Known:
    """Pairs found so far, in a table bucketed by (r, c); each round is a partition."""

    def __init__(self, first: DataFrame):
        self.spark = first.sparkSession
        self.name, self.path, self.round = f"pairs_{uuid.uuid4().hex}", fresh_path(self.spark, "pairs"), 0
        self.buckets = int(self.spark.conf.get("spark.sql.shuffle.partitions"))
        self._add(first)

    def _add(self, pairs: DataFrame) -> None:
        out = pairs.select("r", "c", F.lit(self.round).alias("round")).write.mode("append").option("path", self.path)
        out.partitionBy("round").bucketBy(self.buckets, "r", "c").saveAsTable(self.name)
        self.spark.catalog.refreshTable(self.name)

    def fresh(self) -> DataFrame:
        return self.spark.table(self.name).where(F.col("round") == self.round).select("r", "c")

    def all(self) -> DataFrame:
        return self.spark.table(self.name).select("r", "c")

    def grow(self, found: DataFrame) -> DataFrame:
        """Append the pairs of ``found`` that aren't known; they are the new ``fresh`` ones."""
        known = self.all().select(F.col("r").alias("kr"), F.col("c").alias("kc"))
        new = found.join(known, (F.col("r") == F.col("kr")) & (F.col("c") == F.col("kc")), "left_anti")
        self.round += 1
        self._add(new)
        return self.fresh()

    def close(self) -> DataFrame:
        """All pairs; the table's name goes, its files stay."""
        self.spark.sql(f"DROP TABLE IF EXISTS {self.name}")
        return self.spark.read.schema("r long, c long, round int").parquet(self.path).select("r", "c")


def _by_rows(a: DataFrame) -> tuple[DataFrame, Callable[[], None]]:
    """A factor bucketed by its rows, and what removes the table's name."""
    spark = a.sparkSession
    name = f"factor_{uuid.uuid4().hex}"
    buckets = int(spark.conf.get("spark.sql.shuffle.partitions"))
    a.select("r", "c").write.option("path", fresh_path(spark, "factor")).bucketBy(buckets, "r").saveAsTable(name)
    return spark.table(name), lambda: spark.sql(f"DROP TABLE IF EXISTS {name}")


def _fixpoint(seen: DataFrame, step: Callable[[DataFrame, DataFrame], DataFrame], most_rounds: int | None = None, report: list | None = None, stop: Callable[[DataFrame], bool] | None = None) -> DataFrame:
    """Grow ``seen`` by ``step(seen, fresh)`` until a round adds nothing or ``stop`` says so."""
    known = _Known(seen)
    fresh, rounds = known.fresh(), 0
    while (most_rounds is None or rounds < most_rounds) and not (stop is not None and stop(fresh)):
        fresh = known.grow(step(known.all(), fresh))
        rounds += 1
        if report is not None:
            report.append(fresh.count())
        if fresh.isEmpty():
            break
    return known.close()


def _squaring(a: DataFrame, report: list | None) -> DataFrame:
    """Paths double in every round; new pairs are joined on both sides."""

    def step(seen: DataFrame, fresh: DataFrame) -> DataFrame:
        return m.union(m.product(seen, fresh), m.product(fresh, seen))

    return _fixpoint(a, step, report=report)


def _linear(a: DataFrame, report: list | None) -> DataFrame:
    a, done = _by_rows(a)
    try:
        return _fixpoint(a, lambda seen, fresh: m.product(fresh, a), report=report)
    finally:
        done()


def _together(*jobs: Callable[[], DataFrame]) -> list[DataFrame]:
    """Independent steps as concurrent Spark jobs, each in a thread that inherits the caller's job properties."""
    out: list = [None] * len(jobs)
    failed: list[BaseException] = []

    def run(k: int) -> None:
        try:
            out[k] = jobs[k]()
        except BaseException as error:  # noqa: BLE001 - handed to the caller below
            failed.append(error)

    threads = [InheritableThread(target=run, args=(k,)) for k in range(len(jobs))]
    for t in threads:
        t.start()
    for t in threads:
        t.join()
    if failed:
        raise failed[0]
    return out


#: Groups of whole components have about so many times a leaf's ones.
_GROUP_LEAVES = 4


def _grouped(a: DataFrame, leaf_ones: int, ones: int) -> DataFrame:
    """(b, r, c): ones with the number of their group; a component lies in one group, so groups are closed apart."""
    groups = max(1, ones // max(1, _GROUP_LEAVES * leaf_ones))
    if groups == 1:
        return a.select(F.lit(0).cast("long").alias("b"), "r", "c")
    names = undirected_components(a).select(F.col("id").alias("r"), F.pmod(F.xxhash64("comp"), F.lit(groups)).cast("long").alias("b"))
    return a.join(names, "r").select("b", "r", "c")


def _group_product(x: DataFrame, y: DataFrame) -> DataFrame:
    return x.select("b", "r", F.col("c").alias("k")).join(y.select("b", F.col("r").alias("k"), "c"), ["b", "k"]).select("b", "r", "c").distinct()


def _group_leaf(a: DataFrame, tasks: int | None = None) -> DataFrame:
    """Closures of groups of few ones, each in a task of its own; ``tasks`` of them, or as many as the ones need."""

    def close(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: dict[int, list[tuple[int, int]]] = {}
        for f in frames:
            for b, own in f.groupby("b", sort=False):
                for done in [x for x in held if x != b]:  # groups are in order
                    yield from pairs(done, held.pop(done))
                held.setdefault(b, []).extend(zip(own["r"].tolist(), own["c"].tolist(), strict=True))
        for done, edges in held.items():
            yield from pairs(done, edges)

    def pairs(b: int, edges: list[tuple[int, int]]) -> Iterator[pd.DataFrame]:
        rows: list[int] = []
        cols: list[int] = []
        for v, found in closure_pairs(edges):
            rows += [v] * len(found)
            cols += found
            if len(rows) > 100_000:
                yield pd.DataFrame({"b": b, "r": rows, "c": cols}, dtype="int64")
                rows, cols = [], []
        yield pd.DataFrame({"b": b, "r": rows, "c": cols}, dtype="int64")

    dealt = a.repartition("b") if tasks is None else a.repartition(tasks, "b")
    return dealt.sortWithinPartitions("b").mapInPandas(close, "b long, r long, c long")


#: Ones of a group of small components, which a task closes at a time; components of more go by themselves.
_GROUP_ONES = 1 << 14


def _leaf(a: DataFrame, leaf_ones: int) -> DataFrame:
    """Closures in tasks that hold few ones each: all in one place up to ``leaf_ones``, beyond by groups of whole components."""
    a = checkpointed(a.select("r", "c"))
    ones = a.count()
    if ones <= leaf_ones:
        return leaf_closure(a)
    names = undirected_components(a, leaf_ones).select(F.col("id").alias("r"), "comp")
    a = stored(a.join(names, "r").select("comp", "r", "c"), "components")
    large = stored(a.groupBy("comp").agg(F.count("*").alias("n")).where(F.col("n") > min(_GROUP_ONES, leaf_ones)).select("comp"), "large")
    alone = None if large.isEmpty() else a.join(large, "comp", "left_semi").select("r", "c")
    rest = a if alone is None else a.join(large, "comp", "left_anti")
    grouped = rest.select(F.pmod(F.xxhash64("comp"), F.lit(max(1, ones // _GROUP_ONES))).alias("b"), "r", "c")
    out = _group_leaf(grouped, 4 * int(a.sparkSession.conf.get("spark.sql.shuffle.partitions"))).select("r", "c")
    return out if alone is None else out.unionByName(closure(alone, leaf_ones=leaf_ones))


def _bisect(a: DataFrame, leaf_ones: int, variant: str, parallel_levels: int = 0) -> DataFrame:
    """Two passes over quadrants: first paths through low nodes, then through high ones.

    A matrix of many ones is dealt into groups of whole components, whose closures
    don't meet.  All groups go through their quadrants in the same jobs, each with a
    cut of its own, so jobs grow with the largest group and not with the matrix.
    In the top ``parallel_levels`` levels the quadrants that don't depend on each
    other are worked out by concurrent jobs: in the first pass the south-west one
    beside the north-east one, in the second likewise.
    """
    a = checkpointed(a)
    ones = a.count()
    if ones <= leaf_ones:
        return checkpointed(leaf_closure(a))
    return _bisect_groups(stored(_grouped(a, leaf_ones, ones)), leaf_ones, variant, parallel_levels).select("r", "c")


def _bisect_groups(a: DataFrame, leaf_ones: int, variant: str, parallel_levels: int) -> DataFrame:
    """Steps are stored: a checkpoint keeps what the optimizer knows of ``b``, under names that a later union doesn't find."""
    ends = a.select("b", F.col("r").alias("v")).union(a.select("b", F.col("c").alias("v"))).distinct()
    cuts = ends.groupBy("b").agg(F.percentile_approx("v", 0.5, 1000).alias("cut"), F.min("v").alias("low"), F.max("v").alias("high"))
    cuts = cuts.select("b", F.least("cut", F.col("high") - 1).alias("cut"), (F.col("low") == F.col("high")).alias("single"))
    sizes = a.groupBy("b").agg(F.count("*").alias("n"))
    state = sizes.join(cuts, "b").select(F.col("b"), "cut", (F.col("single") | (F.col("n") <= leaf_ones)).alias("leaf"))
    a = stored(a.join(state, "b"))
    small, large = a.where("leaf").select("b", "r", "c"), a.where("not leaf")
    if large.isEmpty():
        return stored(_group_leaf(small))

    def part(rows: str, cols: str) -> DataFrame:
        return large.where(f"r {rows} cut and c {cols} cut").select("b", "r", "c")

    nw, ne, sw, se = part("<=", "<="), part("<=", ">"), part(">", "<="), part(">", ">")

    def add(x: DataFrame, y: DataFrame) -> DataFrame:
        return x.unionByName(y).distinct()

    def both(first: Callable[[], DataFrame], second: Callable[[], DataFrame]) -> list[DataFrame]:
        steps = [lambda: stored(first()), lambda: stored(second())]
        return _together(*steps) if parallel_levels > 0 else [step() for step in steps]

    # First pass: what lies on the way may be a low node. Groups without a cut go along with the first quadrant.
    first = _bisect_groups(stored(nw.withColumn("b", 2 * F.col("b")).unionByName(small.withColumn("b", 2 * F.col("b") + 1))), leaf_ones, variant, parallel_levels - 1)
    nw1 = first.where("b % 2 = 0").withColumn("b", F.expr("b div 2"))
    small1 = first.where("b % 2 = 1").withColumn("b", F.expr("b div 2"))
    ne1, sw1 = both(lambda: add(ne, _group_product(nw1, ne)), lambda: add(sw, _group_product(sw, nw1)))
    through = _group_product(sw, ne1) if variant == "left" else _group_product(sw1, ne)
    # Second pass: or a high node.
    se2 = _bisect_groups(stored(add(se, through)), leaf_ones, variant, parallel_levels - 1)
    sw2, ne2 = both(lambda: add(sw1, _group_product(se2, sw1)), lambda: add(ne1, _group_product(ne1, se2)))
    back = _group_product(ne2, sw1) if variant == "left" else _group_product(ne1, sw2)
    whole = add(nw1, back).unionByName(ne2).unionByName(sw2).unionByName(se2).unionByName(small1)
    return stored(whole.coalesce(int(a.sparkSession.conf.get("spark.sql.shuffle.partitions"))))


def closure(
    a: DataFrame, method: str = "auto", nodes: DataFrame | None = None, leaf_ones: int = LEAF_ONES, variant: str = "left", report: list | None = None, parallel_levels: int = 0
) -> DataFrame:
    """Pairs joined by one or more steps; with ``nodes``, by none as well.

    ``squaring``, ``linear``, ``bisect`` (``variant`` left or right), ``components``
    and ``leaf`` give the same ones; ``leaf`` deals more than ``leaf_ones`` ones by whole components.  ``auto`` takes ``leaf`` for matrices of at most
    ``leaf_ones`` ones, and components beyond or where these make many pairs of few ones.
    """
    comp = None
    if method == "auto":
        a = checkpointed(a)
        ones = a.count()
        comp = saturated(a, ones, leaf_ones) if ones <= leaf_ones else None
        method = "leaf" if ones <= leaf_ones and comp is None else "components"
    if method == "squaring":
        out = _squaring(a, report)
    elif method == "linear":
        out = _linear(a, report)
    elif method == "bisect":
        out = _bisect(a, leaf_ones, variant, parallel_levels)
    elif method == "components":
        out = factored_closure(a, leaf_ones, comp).pairs()
    elif method == "leaf":
        out = _leaf(a, leaf_ones)
    else:
        raise ValueError(f"no closure method {method!r}")
    return out if nodes is None else m.union(m.identity(nodes), out)


def _walk(factors: list[DataFrame], seeds: DataFrame, most_steps: int | None) -> DataFrame:
    """Pairs (r, c): c is reached from a seed's c by up to ``most_steps`` steps, at least one. One task.

    A step goes through all ``factors`` in turn.
    """
    places = len(factors)
    last = places - 1

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        out: list[dict[int, list[int]]] = [{} for _ in range(places)]
        starts: dict[int, set[int]] = {}
        for f in frames:
            for r, c, k in zip(f["r"].tolist(), f["c"].tolist(), f["factor"].tolist(), strict=True):
                if k < 0:
                    starts.setdefault(r, set()).add(c)
                else:
                    out[k].setdefault(r, []).append(c)
        rows: list[int] = []
        cols: list[int] = []
        for r, first in starts.items():
            found: set[int] = set()
            passed: list[set[int]] = [set() for _ in range(last)]
            frontier, steps = first, 0
            while frontier and (most_steps is None or steps < most_steps):
                for k, follow in enumerate(out):
                    frontier = {c for v in frontier for c in follow.get(v, ())}
                    if k < last and most_steps is None:
                        # What has been passed at this place before leads nowhere new.
                        frontier -= passed[k]
                        passed[k] |= frontier
                frontier -= found
                found |= frontier
                steps += 1
            rows += [r] * len(found)
            cols += found
            if len(rows) > 100_000:
                yield pd.DataFrame({"r": rows, "c": cols}, dtype="int64")
                rows, cols = [], []
        yield pd.DataFrame({"r": rows, "c": cols}, dtype="int64")

    both = seeds.select("r", "c", F.lit(-1).alias("factor"))
    for k, a in enumerate(factors):
        both = both.unionByName(a.select("r", "c", F.lit(k).alias("factor")))
    return both.coalesce(1).mapInPandas(run, "r long, c long")


def _factors(a: DataFrame | list[DataFrame]) -> list[DataFrame]:
    return [x.select("r", "c") for x in (a if isinstance(a, list) else [a])]


def _turned(a: DataFrame | list[DataFrame]) -> list[DataFrame]:
    return [m.transpose(x) for x in reversed(_factors(a))]


def _small(frames: list[DataFrame], most: int) -> bool:
    """Whether all together have at most so many rows, without counting further."""
    if most <= 0:
        return False
    rows = frames[0].select("r")
    for x in frames[1:]:
        rows = rows.unionByName(x.select("r"))
    return rows.limit(most + 1).count() <= most


def closure_apply(
    a: DataFrame | list[DataFrame], seed: DataFrame, side: str = "left", reflexive: bool = False, most_steps: int | None = None, leaf_ones: int = LEAF_ONES,
    stop: Callable[[DataFrame], bool] | None = None,
) -> DataFrame:
    """Seed times closure (``left``) or closure times seed (``right``), without the closure.

    The seed is a factor already restricted or small.  ``a`` may be a list of
    factors whose product is closed; it is never worked out, as a round goes through
    the factors one after the other.  ``reflexive`` keeps the seed itself.  Rounds
    follow the frontier; factors and a seed of at most ``leaf_ones`` ones are walked
    in one task, as a long chain would need a job for each step.
    """
    if side == "right":
        return m.transpose(closure_apply(_turned(a), m.transpose(seed), "left", reflexive, most_steps, leaf_ones, stop))
    factors, seed = _factors(a), checkpointed(seed.select("r", "c"))
    if _small([*factors, seed], leaf_ones):
        found = _walk(factors, seed, most_steps)
    else:
        ready = [_by_rows(x) for x in factors]
        try:

            def step(frontier: DataFrame) -> DataFrame:
                for x, _ in ready:
                    frontier = m.product(frontier, x)
                return frontier

            rest = None if most_steps is None else most_steps - 1
            found = _fixpoint(step(seed), lambda seen, fresh: step(fresh), rest, stop=stop)
        finally:
            for _, done in ready:
                done()
    return m.union(found, seed) if reflexive else found


def _cell(spark, r: int, c: int) -> DataFrame:
    return spark.createDataFrame([(r, c)], "r long, c long")


def closure_from(a: DataFrame | list[DataFrame], row: int, reflexive: bool = False, most_steps: int | None = None, leaf_ones: int = LEAF_ONES) -> DataFrame:
    """One row of the closure, from that row alone."""
    return closure_apply(a, _cell(_factors(a)[0].sparkSession, row, row), "left", reflexive, most_steps, leaf_ones)


def closure_to(a: DataFrame | list[DataFrame], col: int, reflexive: bool = False, most_steps: int | None = None, leaf_ones: int = LEAF_ONES) -> DataFrame:
    """One column of the closure."""
    return closure_apply(a, _cell(_factors(a)[0].sparkSession, col, col), "right", reflexive, most_steps, leaf_ones)


def reachable(a: DataFrame | list[DataFrame], row: int, col: int, reflexive: bool = False, leaf_ones: int = LEAF_ONES) -> DataFrame:
    """The cell (row, col) of the closure as a matrix of at most one one.

    Starts at the emptier end and stops as soon as the cell is set.
    """
    factors = _factors(a)
    spark = factors[0].sparkSession
    if reflexive and row == col:
        return _cell(spark, row, col)
    ahead = factors[0].where(F.col("r") == row).count()
    behind = factors[-1].where(F.col("c") == col).count()
    forward = ahead <= behind
    base = factors if forward else _turned(factors)
    start, goal = (row, col) if forward else (col, row)
    seen = closure_apply(base, _cell(spark, start, start), leaf_ones=leaf_ones, stop=lambda fresh: not fresh.where(F.col("c") == goal).isEmpty())
    hit = m.restrict(seen, col=goal)
    return hit if forward else m.transpose(hit)
