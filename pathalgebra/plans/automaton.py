"""Product-automaton engine: breadth-first over (origin, node, state).

States are the places of labels in the expression, found by the position
construction, so there are no empty moves.  The table of moves is as small as
the expression and is broadcast; the work table grows with the graph only.  A label
is joined in the rounds that can use it, and a fixed start restricts the first scans.

Two places that a loop goes through in turn, one label there and back, make every
move between them one that can be undone.  Without a fixed end such moves are not
walked from each origin: what they connect is one (node, state) for the walk, and
origins that begin at the same ones walk together.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathalgebra.operators import matrix as m
from pathalgebra.operators.components import expanded, undirected_components
from pathalgebra.plans.paths import Alt, Eps, Expr, Label, Neg, Opt, Plus, Seq, Star, push_inverse
from pathalgebra.runtime import checkpointed
from pathalgebra.sources.graphs import Graph


@dataclass
class Positions:
    leaves: list[Label | Neg]
    empty: bool
    first: set[int]
    last: set[int]
    follow: set[tuple[int, int]]


def positions(e: Expr) -> Positions:
    """First, last and following places, by structure."""
    leaves: list[Label | Neg] = []
    follow: set[tuple[int, int]] = set()

    def visit(x: Expr) -> tuple[bool, set[int], set[int]]:
        match x:
            case Eps():
                return True, set(), set()
            case Label() | Neg():
                leaves.append(x)
                return False, {len(leaves) - 1}, {len(leaves) - 1}
            case Alt(parts):
                got = [visit(p) for p in parts]
                return any(g[0] for g in got), set().union(*(g[1] for g in got)), set().union(*(g[2] for g in got))
            case Seq(parts):
                empty, first, last = True, set(), set()
                for p in parts:
                    e2, f2, l2 = visit(p)
                    follow.update((i, j) for i in last for j in f2)
                    first = first | f2 if empty else first
                    last = last | l2 if e2 else l2
                    empty = empty and e2
                return empty, first, last
            case Opt(inner):
                _, first, last = visit(inner)
                return True, first, last
            case Plus(inner) | Star(inner):
                empty, first, last = visit(inner)
                follow.update((i, j) for i in last for j in first)
                return empty or isinstance(x, Star), first, last
        raise TypeError(x)

    empty, first, last = visit(e)
    return Positions(leaves, empty, first, last, follow)


def walk(graph: Graph, e: Expr, row: int | None = None, col: int | None = None) -> DataFrame:
    """Pairs (r, c) of ``e``; starts from the end that is fixed, if one is."""
    if row is None and col is not None:
        back = walk(graph, push_inverse(e, flip=True), row=col)
        return back.select(F.col("c").alias("r"), F.col("r").alias("c"))
    auto = positions(e)
    spark = graph.spark
    nodes = graph.nodes()
    out = m.identity(nodes) if auto.empty else m.identity(nodes).limit(0)
    if row is not None:
        out = out.where(F.col("r") == row)
    if not auto.leaves:
        return out if col is None else out.where(F.col("c") == col)

    def moves(state: int) -> DataFrame:
        """(u, v) of the label at a place of the expression."""
        leaf = auto.leaves[state]
        a = graph.without_labels(leaf.names) if isinstance(leaf, Neg) else graph.matrix(leaf.name)
        a = m.transpose(a) if leaf.inverse else a
        return a.select(F.col("r").alias("u"), F.col("c").alias("v"))

    turns = _turns(auto)
    if row is None and turns:
        hits = _walk_connected(auto, turns, moves)
        if auto.empty:
            hits = out.unionByName(hits.where("r <> c"))
        return hits if col is None else hits.where(F.col("c") == col)

    repeated = _repeated(auto)
    kept: dict[int, DataFrame] = {}

    def moves_of(state: int) -> DataFrame:
        # A place that a loop comes back to is read once and kept; others are read when they are due.
        if state not in repeated:
            return moves(state)
        if state not in kept:
            kept[state] = checkpointed(moves(state))
        return kept[state]

    # The fixed end restricts the scans of the first labels.
    begins = []
    for state in sorted(auto.first):
        first = moves(state)
        first = first if row is None else first.where(F.col("u") == row)
        begins.append(first.select(F.col("u").alias("origin"), F.col("v").alias("at"), F.lit(state).alias("state")))
    seen = [checkpointed(reduce(DataFrame.unionByName, begins).distinct())]
    fresh, live = seen[0], set(auto.first)
    next_of = spark.createDataFrame(sorted(auto.follow) or [(-1, -1)], "state int, then int")
    while True:
        live = {j for i, j in auto.follow if i in live}
        if not live or fresh.isEmpty():
            break
        options = fresh.join(F.broadcast(next_of), "state").select("origin", F.col("at").alias("u"), F.col("then").alias("state"))
        found = []
        for state in sorted(live):
            here = options.where(F.col("state") == state).select("origin", "u")
            found.append(here.join(moves_of(state), "u").select("origin", F.col("v").alias("at"), F.lit(state).alias("state")))
        new = reduce(DataFrame.unionByName, found).distinct()
        if live & repeated:
            known = reduce(DataFrame.unionByName, seen).select(F.col("origin").alias("o2"), F.col("at").alias("a2"), F.col("state").alias("s2"))
            same = (F.col("origin") == F.col("o2")) & (F.col("at") == F.col("a2")) & (F.col("state") == F.col("s2"))
            new = new.join(known, same, "left_anti")
        fresh = checkpointed(new)
        seen.append(fresh)
    hits = reduce(DataFrame.unionByName, seen).where(F.col("state").isin(sorted(auto.last))).select(F.col("origin").alias("r"), F.col("at").alias("c"))
    out = out.unionByName(hits).distinct()
    return out if col is None else out.where(F.col("c") == col)


def _turns(auto: Positions) -> set[tuple[int, int]]:
    """Pairs of places that follow each other both ways, the second one's label the first one's turned."""

    def turned(x: Label | Neg, y: Label | Neg) -> bool:
        return isinstance(x, Label) and isinstance(y, Label) and x.name == y.name and x.inverse != y.inverse

    return {(i, j) for i, j in auto.follow if i < j and (j, i) in auto.follow and turned(auto.leaves[i], auto.leaves[j])}


def _walk_connected(auto: Positions, turns: set[tuple[int, int]], moves: Callable[[int], DataFrame]) -> DataFrame:
    """Distinct pairs (r, c) from every origin by one move or more.

    A place (node, state) is one number.  Moves that can be undone connect places, and
    a connected set of them is one place, ``comp``.  A set of origins with the same
    first one or two places is walked once, under the name of its least origin.
    """
    states = len(auto.leaves)
    kept: dict[str | tuple[str, ...], DataFrame] = {}

    def of(state: int) -> DataFrame:
        # A label is read once, whichever way it is walked.
        leaf = auto.leaves[state]
        key = leaf.name if isinstance(leaf, Label) else leaf.names
        u, v = ("v", "u") if leaf.inverse else ("u", "v")
        if key not in kept:
            kept[key] = checkpointed(moves(state).select(F.col(u).alias("u"), F.col(v).alias("v")))
        return kept[key].select(F.col(u).alias("u"), F.col(v).alias("v"))

    def place(column: str, state: int) -> Column:
        return F.col(column) * states + state

    def edges(pairs: set[tuple[int, int]]) -> DataFrame:
        return reduce(DataFrame.unionByName, [of(j).select(place("u", i).alias("r"), place("v", j).alias("c")) for i, j in sorted(pairs)])

    comp = checkpointed(undirected_components(edges(turns)))

    def named(df: DataFrame, column: str) -> DataFrame:
        """``df`` with places replaced by what they are connected to; a place without such moves stays."""
        joined = df.join(comp.select(F.col("id").alias(column), F.col("comp").alias("named")), column, "left")
        return joined.withColumn(column, F.coalesce("named", column)).drop("named").distinct()

    begins = [of(s).select(F.col("u").alias("origin"), place("v", s).alias("comp")) for s in sorted(auto.first)]
    starts = checkpointed(named(reduce(DataFrame.unionByName, begins), "comp"))
    # One or two places are told by the least and the greatest; an origin with more stands for itself.
    sets = starts.groupBy("origin").agg(F.count("*").alias("n"), F.min("comp").alias("low"), F.max("comp").alias("high"))
    sets = checkpointed(sets.withColumn("own", F.when(F.col("n") > 2, F.col("origin"))))
    alike = F.struct("n", "low", "high", F.coalesce("own", F.lit(-1)).alias("own"))
    names = sets.groupBy(alike.alias("alike")).agg(F.min("origin").alias("key"))
    classes = checkpointed(sets.select("origin", alike.alias("alike")).join(names, "alike").select("key", F.col("origin").alias("r")))
    seen = [checkpointed(starts.join(names.select(F.col("key").alias("origin")), "origin", "left_semi").select(F.col("origin").alias("key"), "comp"))]
    onward = auto.follow - turns - {(j, i) for i, j in turns}
    if onward:
        steps = checkpointed(named(named(edges(onward), "r"), "c").where("r <> c").select(F.col("r").alias("comp"), F.col("c").alias("then")))
        while not seen[-1].isEmpty():
            new = seen[-1].join(steps, "comp").select("key", F.col("then").alias("comp")).distinct()
            seen.append(checkpointed(new.join(reduce(DataFrame.unionByName, seen), ["key", "comp"], "left_anti")))
    ends = [of(s).select(place("v", s).alias("comp"), F.col("v").alias("c")).distinct() for s in sorted(auto.last)]
    ends = named(reduce(DataFrame.unionByName, ends), "comp")
    reached = checkpointed(reduce(DataFrame.unionByName, seen).join(ends, "comp").select("key", "c").distinct())
    return expanded(classes, reached)


def _repeated(auto: Positions) -> set[int]:
    """Places that lie on a loop of following places."""
    found = set()
    for start in range(len(auto.leaves)):
        reached, work = set(), [start]
        while work:
            i = work.pop()
            for a, b in auto.follow:
                if a == i and b not in reached:
                    reached.add(b)
                    work.append(b)
        if start in reached:
            found.add(start)
    return found
