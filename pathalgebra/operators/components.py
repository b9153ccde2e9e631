"""Strongly connected components, condensation, and closures kept factored.

Small graphs, by a checked count, are solved in one task; larger ones are
trimmed, coloured by the greatest label that reaches a node, and confirmed by
walking backwards inside a colour, all as joins over the edge table.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathalgebra.operators.contraction import connected
from pathalgebra.runtime import checkpointed

#: A matrix of at most so many ones may be solved in one task.
LEAF_ONES = 200_000


def strong_components(edges: list[tuple[int, int]]) -> dict[int, int]:
    """Node -> least node of its component; an iterative depth-first search."""
    out: dict[int, list[int]] = {}
    for r, c in edges:
        out.setdefault(r, []).append(c)
        out.setdefault(c, [])
    index: dict[int, int] = {}
    low: dict[int, int] = {}
    on: set[int] = set()
    stack: list[int] = []
    comp: dict[int, int] = {}
    for root in out:
        if root in index:
            continue
        work = [(root, iter(out[root]))]
        index[root] = low[root] = len(index)
        stack.append(root)
        on.add(root)
        while work:
            v, it = work[-1]
            for w in it:
                if w not in index:
                    index[w] = low[w] = len(index)
                    stack.append(w)
                    on.add(w)
                    work.append((w, iter(out[w])))
                    break
                if w in on:
                    low[v] = min(low[v], index[w])
            else:
                work.pop()
                if work:
                    low[work[-1][0]] = min(low[work[-1][0]], low[v])
                if low[v] == index[v]:
                    members = []
                    while True:
                        w = stack.pop()
                        on.discard(w)
                        members.append(w)
                        if w == v:
                            break
                    name = min(members)
                    comp |= dict.fromkeys(members, name)
    return comp


#: Targets whose sets are worked out together; a component holds as many bits at a time.
_TARGETS = 4096


def closure_pairs(edges: list[tuple[int, int]], share: int = 0, shares: int = 1) -> Iterator[tuple[int, list[int]]]:
    """(node, some of what it reaches in one or more steps), through components and bit sets.

    Targets are taken in blocks, so memory is the graph's and one block's bits for
    each component, however many ones the closure has.  ``share`` of ``shares``
    takes every so many blocks only; shares may get the edges in different orders, so
    they are sorted before the order of targets, and with it the blocks, follows from them.
    """
    edges = sorted(set(edges))
    comp = strong_components(edges)
    members: dict[int, list[int]] = {}
    for v, k in comp.items():
        members.setdefault(k, []).append(v)
    after: dict[int, set[int]] = {k: set() for k in members}
    cyclic = {k for k, v in members.items() if len(v) > 1}
    for r, c in edges:
        if comp[r] != comp[c]:
            after[comp[r]].add(comp[c])
        elif r == c:
            cyclic.add(comp[r])
    order: list[int] = []  # components after all that they lead to
    state: dict[int, int] = {}
    for start in members:
        work = [(start, iter(after[start]))] if start not in state else []
        state.setdefault(start, 1)
        while work:
            k, rest = work[-1]
            for x in rest:
                if x not in state:
                    state[x] = 1
                    work.append((x, iter(after[x])))
                    break
            else:
                order.append(k)
                work.pop()
    targets = [v for k in order for v in members[k]]
    for at in range(share * _TARGETS, len(targets), shares * _TARGETS):
        block = targets[at : at + _TARGETS]
        own: dict[int, int] = {}
        for i, v in enumerate(block):
            own[comp[v]] = own.get(comp[v], 0) | 1 << i
        reach: dict[int, int] = {}
        for k in order:
            bits = own.get(k, 0) if k in cyclic else 0
            for x in after[k]:
                bits |= reach.get(x, 0) | own.get(x, 0)
            if bits:
                reach[k] = bits
        for k, bits in reach.items():
            found, left = [], bits
            while left:
                low = left & -left
                found.append(block[low.bit_length() - 1])
                left ^= low
            for v in members[k]:
                yield v, found


def _one_task(a: DataFrame, solve, schema: str) -> DataFrame:
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        edges: list[tuple[int, int]] = []
        for f in frames:
            edges += list(zip(f["r"].tolist(), f["c"].tolist(), strict=True))
        yield from solve(edges)

    return a.select("r", "c").coalesce(1).mapInPandas(run, schema)


def leaf_closure(a: DataFrame, shares: int = 8) -> DataFrame:
    """Closure of a matrix whose number of ones the caller has checked.

    Each of ``shares`` tasks holds the ones and gives the pairs of its share of the
    targets, so neither memory nor a partition grows with the ones of the closure.
    """

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        # Every share brings the same ones; a task that got several keeps those of one.
        edges: list[tuple[int, int]] = []
        mine: list[int] = []
        for f in frames:
            mine += [x for x in f["share"].unique().tolist() if x not in mine]
            own = f[f["share"] == mine[0]] if mine else f
            edges += list(zip(own["r"].tolist(), own["c"].tolist(), strict=True))
        rows: list[int] = []
        cols: list[int] = []
        for share in mine:
            for v, found in closure_pairs(edges, share, shares):
                rows += [v] * len(found)
                cols += found
                if len(rows) > 100_000:
                    yield pd.DataFrame({"r": rows, "c": cols}, dtype="int64")
                    rows, cols = [], []
        yield pd.DataFrame({"r": rows, "c": cols}, dtype="int64")

    copied = a.select("r", "c", F.explode(F.sequence(F.lit(0), F.lit(shares - 1))).alias("share"))
    return copied.repartition(shares, "share").mapInPandas(run, "r long, c long")


def _leaf_components(a: DataFrame) -> DataFrame:
    def solve(edges: list) -> Iterator[pd.DataFrame]:
        comp = strong_components(edges)
        yield pd.DataFrame({"id": list(comp), "comp": list(comp.values())}, dtype="int64")

    return _one_task(a, solve, "id long, comp long")


def _ends(a: DataFrame) -> DataFrame:
    return a.select(F.col("r").alias("id")).union(a.select(F.col("c").alias("id"))).distinct()


def _distributed_components(a: DataFrame) -> DataFrame:
    """Rounds of trimming, colouring and confirming until no edge is left."""
    edges = checkpointed(a.select("r", "c").where("r <> c").distinct())
    done = _ends(a).select("id").limit(0).withColumn("comp", F.col("id"))
    everyone = checkpointed(_ends(a))
    while not edges.isEmpty():
        while True:  # trim: a node without an edge in or out is alone
            live = edges.select(F.col("r").alias("id")).intersect(edges.select(F.col("c").alias("id")))
            left = edges.join(live.withColumnRenamed("id", "r"), "r", "left_semi").join(live.withColumnRenamed("id", "c"), "c", "left_semi").select("r", "c")
            left = checkpointed(left)
            same = left.count() == edges.count()
            edges = left
            if same:
                break
        if edges.isEmpty():
            break
        colour = checkpointed(_ends(edges).withColumn("colour", F.col("id")))
        while True:  # colour: the greatest label that reaches a node
            pushed = edges.join(colour.select(F.col("id").alias("r"), F.col("colour").alias("from")), "r").select(F.col("c").alias("id"), F.col("from").alias("colour"))
            new = checkpointed(colour.unionByName(pushed).groupBy("id").agg(F.max("colour").alias("colour")))
            moved = new.agg(F.sum(F.xxhash64("id", "colour").cast("decimal(38,0)"))).first()[0] != colour.agg(F.sum(F.xxhash64("id", "colour").cast("decimal(38,0)"))).first()[0]
            colour = new
            if not moved:
                break
        # Confirm: walk backwards inside a colour from the node that gave it.
        left_end = colour.select(F.col("id").alias("r"), F.col("colour").alias("x"))
        right_end = colour.select(F.col("id").alias("c"), F.col("colour").alias("y"))
        inside = checkpointed(edges.join(left_end, "r").join(right_end, "c").where("x = y").select("r", "c"))
        seen = checkpointed(colour.where("id = colour").select("id", "colour"))
        frontier = seen
        while not frontier.isEmpty():
            back = inside.join(frontier.select(F.col("id").alias("c"), "colour"), "c").select(F.col("r").alias("id"), "colour").distinct()
            frontier = checkpointed(back.join(seen.select("id"), "id", "left_anti"))
            seen = checkpointed(seen.unionByName(frontier))
        names = seen.groupBy("colour").agg(F.min("id").alias("comp"))
        done = checkpointed(done.unionByName(seen.join(names, "colour").select("id", "comp")))
        gone = seen.select("id")
        edges = checkpointed(edges.join(gone.withColumnRenamed("id", "r"), "r", "left_anti").join(gone.withColumnRenamed("id", "c"), "c", "left_anti").select("r", "c"))
    return everyone.join(done, "id", "left").select("id", F.coalesce("comp", "id").alias("comp"))


def components(a: DataFrame, leaf_ones: int = LEAF_ONES) -> DataFrame:
    """(id, comp) of all nodes with an edge; the least node names a component."""
    a = checkpointed(a.select("r", "c"))
    return _leaf_components(a) if a.count() <= leaf_ones else _distributed_components(a)


def _linked(edges: DataFrame, leaf_ones: int) -> DataFrame:
    """(id, component_id) of the ends of ``edges`` (a, b): in one task if they are few, else by star contraction."""
    edges = checkpointed(edges)
    if leaf_ones <= 0 or edges.limit(leaf_ones + 1).count() > leaf_ones:
        return connected(edges)

    def solve(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        up: dict[int, int] = {}

        def root(x: int) -> int:
            up.setdefault(x, x)
            while up[x] != x:
                up[x] = up[up[x]]
                x = up[x]
            return x

        for f in frames:
            for x, y in zip(f["a"].tolist(), f["b"].tolist(), strict=True):
                x, y = root(x), root(y)
                up[max(x, y)] = min(x, y)
        yield pd.DataFrame({"id": list(up), "component_id": [root(x) for x in list(up)]}, dtype="int64")

    return edges.coalesce(1).mapInPandas(solve, "id long, component_id long")


def undirected_components(a: DataFrame, leaf_ones: int = LEAF_ONES) -> DataFrame:
    """(id, comp) of all ends of ``a``, edges taken both ways; the least end names a component."""
    a = checkpointed(a.select("r", "c"))
    found = _linked(a.select(F.col("r").alias("a"), F.col("c").alias("b")), leaf_ones).select("id", F.col("component_id").alias("comp"))
    return _ends(a).join(found, "id", "left").select("id", F.coalesce("comp", "id").alias("comp"))


def mirrored_closure(x: DataFrame, leaf_ones: int = LEAF_ONES) -> FactoredClosure:
    """The closure of X times X transposed, without that product.

    Rows that share a column are linked, so rows belong together if they are
    connected in the two-sided graph of rows (even numbers) and columns (odd ones).
    """
    sided = x.select((2 * F.col("r")).alias("a"), (2 * F.col("c") + 1).alias("b"))
    rows = _linked(sided, leaf_ones).where("id % 2 = 0")
    rows = checkpointed(rows.select(F.shiftright("id", 1).alias("id"), F.col("component_id").alias("comp")))
    names = rows.groupBy("comp").agg(F.min("id").alias("least"))
    comp = checkpointed(rows.join(names, "comp").select("id", F.col("least").alias("comp")))
    nothing = comp.select(F.col("id").alias("r"), F.col("comp").alias("c")).limit(0)
    return FactoredClosure(comp, nothing, comp.select("comp").distinct())


#: Members of a key that go together on the left, and on the right; two blocks give about the product of pairs at most.
_BLOCK, _WIDE = 256, 2048


def _blocks(rows: DataFrame, key: str, member: str, size: int = _BLOCK) -> DataFrame:
    """(key, member): the members of a key dealt by hash into arrays of about ``size``."""
    loads = rows.groupBy(key).agg(F.ceil(F.count("*") / size).alias("blocks"))
    dealt = rows.select(key, member).join(loads, key).withColumn("block", F.pmod(F.xxhash64(member), F.col("blocks")))
    return dealt.groupBy(key, "block").agg(F.collect_list(member).alias(member)).select(key, member)


def _unfolded(blocks: DataFrame) -> DataFrame:
    """(r, c) from pairs of arrays, which are dealt to tasks evenly before they are unfolded.

    Generated code holds all that a row of its input makes before it hands on the first.
    The narrow step between the two sides is none, so a task holds the rows of one left
    member at a time, not those of the two blocks.
    """
    parts = 4 * int(blocks.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = blocks.select("r", "c").repartition(parts)
    rows = dealt.select(F.explode("r").alias("r"), "c").coalesce(parts)
    return rows.select("r", F.explode("c").alias("c"))


def expanded(left: DataFrame, right: DataFrame) -> DataFrame:
    """(r, c) of all rows (key, r) and (key, c) with equal keys, however many a key has."""
    return _unfolded(_blocks(left, "key", "r").join(_blocks(right, "key", "c", _WIDE), "key"))


@dataclass
class FactoredClosure:
    """A closure as components, reachable pairs of components, and cyclic ones."""

    comp: DataFrame
    reach: DataFrame
    cyclic: DataFrame

    def pairs(self) -> DataFrame:
        """All ones: members of a component with members of those it reaches.

        Members of large components meet as blocks, whose pairs are dealt evenly.
        """
        left = self.comp.select(F.col("id").alias("r"), F.col("comp").alias("from"))
        right = self.comp.select(F.col("id").alias("c"), F.col("comp").alias("to"))
        large = checkpointed(self.comp.groupBy(F.col("comp").alias("large")).agg(F.count("*").alias("n")).where(F.col("n") >= _BLOCK).select("large"))
        if large.isEmpty():
            return left.join(self._steps(), "from").join(right, "to").select("r", "c")
        tail, head = (large.select(F.col("large").alias(k), F.lit(True).alias(f"{k}_large")) for k in ("from", "to"))
        steps = self._steps().join(tail, "from", "left").join(head, "to", "left")
        few = steps.where("from_large is null and to_large is null").select("from", "to")
        many = steps.where("from_large or to_large").select("from", "to")
        blocks = _blocks(left, "from", "r").join(many, "from").join(_blocks(right, "to", "c", _WIDE), "to")
        return left.join(few, "from").join(right, "to").select("r", "c").unionByName(_unfolded(blocks))

    def _steps(self) -> DataFrame:
        own = self.cyclic.select(F.col("comp").alias("from"), F.col("comp").alias("to"))
        return self.reach.select(F.col("r").alias("from"), F.col("c").alias("to")).unionByName(own)

    def count_pairs(self) -> int:
        """Number of ones, without writing them out."""
        sizes = self.comp.groupBy("comp").agg(F.count("*").alias("n"))
        left, right = sizes.select(F.col("comp").alias("from"), F.col("n").alias("a")), sizes.select(F.col("comp").alias("to"), F.col("n").alias("b"))
        return self._steps().join(left, "from").join(right, "to").agg(F.coalesce(F.sum(F.col("a") * F.col("b")), F.lit(0))).first()[0]


def condense(a: DataFrame, comp: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(edges between components, cyclic components)."""
    left, right = comp.select(F.col("id").alias("r"), F.col("comp").alias("x")), comp.select(F.col("id").alias("c"), F.col("comp").alias("y"))
    mapped = checkpointed(a.select("r", "c").join(left, "r").join(right, "c").select(F.col("x").alias("r"), F.col("y").alias("c")).distinct())
    cyclic = mapped.where("r = c").select(F.col("r").alias("comp"))
    return mapped.where("r <> c"), cyclic


#: More pairs than these inside components are expanded from the factored form, however few ones make them.
_MOST_PAIRS = 5_000_000


def _squares(comp: DataFrame) -> tuple[int, int]:
    """Members of all components of more than one, and pairs that they make."""
    sizes = comp.groupBy("comp").agg(F.count("*").alias("n")).where("n > 1")
    return tuple(sizes.agg(F.coalesce(F.sum("n"), F.lit(0)), F.coalesce(F.sum(F.col("n") * F.col("n")), F.lit(0))).first())


def saturated(a: DataFrame, ones: int, leaf_ones: int = LEAF_ONES) -> DataFrame | None:
    """The components of a matrix if their members make many pairs, else nothing.

    A component has no more members than ones, so the smallest matrices aren't looked at.
    Strong components of many ones are looked for only where undirected ones are large
    and no mere chains, which take a round for each step.
    """
    if ones * ones <= _MOST_PAIRS:
        return None
    if ones > leaf_ones:
        members, most = _squares(undirected_components(a, leaf_ones))
        if most <= _MOST_PAIRS or ones < 2 * members:
            return None
    comp = checkpointed(_leaf_components(a) if ones <= leaf_ones else _distributed_components(a))
    return comp if _squares(comp)[1] > _MOST_PAIRS else None


def factored_closure(a: DataFrame, leaf_ones: int = LEAF_ONES, comp: DataFrame | None = None) -> FactoredClosure:
    """The closure by components, which may be given if they are known."""
    from pathalgebra.operators.closure import closure

    comp = checkpointed(components(a, leaf_ones)) if comp is None else comp
    dag, cyclic = condense(a, comp)
    # A graph without cycles has no smaller components, so a large one is squared.
    method = "leaf" if dag.count() <= leaf_ones else "squaring"
    return FactoredClosure(comp, closure(dag, method=method), cyclic)
