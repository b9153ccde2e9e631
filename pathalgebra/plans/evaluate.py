"""Evaluation of path queries: the matrix engine, and two others to compare with."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathalgebra.operators import closure as cl
from pathalgebra.operators import matrix as m
from pathalgebra.operators.components import factored_closure, mirrored_closure
from pathalgebra.plans.ordering import order_products, order_sums
from pathalgebra.plans.paths import Alt, Eps, Expr, Label, Neg, Opt, PathQuery, Plus, Seq, Star, normalise, nullable, parse_query, push_inverse, text_of
from pathalgebra.runtime import checkpointed
from pathalgebra.sources.graphs import Graph


@dataclass
class Engine:
    """Evaluates path expressions over one graph.

    ``plan``: ``optimized`` pushes restrictions down, fuses closures with what
    stands beside them and orders products by size; ``naive`` works every part
    out in full and restricts the result.  ``sums``: ``together`` adds all parts by
    one aggregate, ``by_size`` the two smallest first, by their true sizes.
    ``notes`` gets one line per step, ``cost`` the ones of all operands whose sizes
    were looked at.
    """

    graph: Graph
    plan: str = "optimized"
    closure_method: str = "auto"
    leaf_ones: int = cl.LEAF_ONES
    sums: str = "together"
    notes: list[str] = field(default_factory=list)
    cost: int = 0
    _done: dict = field(default_factory=dict)

    def _leaf(self, e: Expr, row: int | None, col: int | None, side: str | None = None) -> DataFrame:
        """A label's matrix; ``side`` tells on which side of a product it stands, for graphs with two views."""
        if isinstance(e, Neg):
            a = self.graph.without_labels(e.names)
        else:
            by = None if side is None else ("c" if side == "left" else "r")
            a = self.graph.view(e.name, by if by is None or not e.inverse else {"r": "c", "c": "r"}[by])
        return m.restrict(m.transpose(a) if e.inverse else a, row, col)

    def _identity(self, row: int | None, col: int | None) -> DataFrame:
        return m.restrict(m.identity(self.graph.nodes()), row, col)

    def matrix(self, e: Expr, row: int | None = None, col: int | None = None, side: str | None = None) -> DataFrame:
        """Ones of ``e``, in one row or column if asked; equal parts are planned once."""
        key = (text_of(e), row, col, side if isinstance(e, Label) else None)
        if key not in self._done:
            self._done[key] = self._work(e, row, col, side)
        return self._done[key]

    def _note(self, what: str, e: Expr, row: int | None, col: int | None) -> None:
        where = f" row={row}" * (row is not None) + f" col={col}" * (col is not None)
        self.notes.append(f"{what} {text_of(e)}{where}")

    def _work(self, e: Expr, row: int | None, col: int | None, side: str | None = None) -> DataFrame:
        if self.plan == "naive" and (row is not None or col is not None):
            return m.restrict(self.matrix(e), row, col)
        match e:
            case Eps():
                return self._identity(row, col)
            case Label() | Neg():
                self._note("scan", e, row, col)
                return self._leaf(e, row, col, side)
            case Alt(parts):
                self._note("sum", e, row, col)
                return self._sum([self.matrix(p, row, col) for p in parts])
            case Opt(inner):
                return m.union(self._identity(row, col), self.matrix(inner, row, col))
            case Plus(inner) | Star(inner):
                return self._closure(inner, isinstance(e, Star), row, col)
            case Seq(parts):
                return self._chain(parts, e, row, col)
        raise TypeError(e)

    def _sizes(self, parts: list[DataFrame]) -> list[int]:
        """The ones of several matrices, by one job."""
        tagged = [a.select(F.lit(k).alias("k")) for k, a in enumerate(parts)]
        counts = {r["k"]: r["n"] for r in reduce(DataFrame.unionByName, tagged).groupBy("k").agg(F.count("*").alias("n")).collect()}
        sizes = [counts.get(k, 0) for k in range(len(parts))]
        self.cost += sum(sizes)
        return sizes

    def _sum(self, parts: list[DataFrame]) -> DataFrame:
        if self.sums == "together" or len(parts) < 3:
            return m.union_all(parts)
        parts = [checkpointed(a) for a in parts]

        def add(i: int, j: int) -> int:
            parts.append(checkpointed(m.union(parts[i], parts[j])))
            size = self._sizes(parts[-1:])[0]
            self.notes.append(f"add {i} and {j}: {size} ones")
            return size

        order_sums(self._sizes(parts), add)
        return parts[-1]

    def _factors(self, inner: Expr) -> list[DataFrame] | DataFrame:
        """What a walked closure steps through: a chain's factors one by one, never their product."""
        if self.plan != "naive" and isinstance(inner, Seq) and all(isinstance(p, (Label, Neg, Alt)) for p in inner.parts):
            return [self.matrix(p) for p in inner.parts]
        return self.matrix(inner)

    def _closure(self, inner: Expr, reflexive: bool, row: int | None, col: int | None) -> DataFrame:
        e = (Star if reflexive else Plus)(inner)
        if row is None and col is None:
            self._note("closure", e, row, col)
            half = mirrored(inner) if self.plan != "naive" and self.closure_method == "auto" else None
            if half is not None:
                self.notes.append(f"undirected components of {text_of(half)}")
                found = mirrored_closure(self.matrix(half), self.leaf_ones).pairs()
            else:
                found = cl.closure(self.matrix(inner), self.closure_method, leaf_ones=self.leaf_ones)
        else:
            self._note("restricted closure", e, row, col)
            base = self._factors(inner)  # a restriction must not enter the operand
            if row is not None and col is not None:
                found = cl.reachable(base, row, col, leaf_ones=self.leaf_ones)
            elif row is not None:
                found = cl.closure_from(base, row, leaf_ones=self.leaf_ones)
            else:
                found = cl.closure_to(base, col, leaf_ones=self.leaf_ones)
        return m.union(self._identity(row, col), found) if reflexive else found

    def _step(self, done: DataFrame, e: Expr, side: str, line: int | None) -> DataFrame:
        """Multiply what is worked out with the next factor; closures are seeded."""
        if isinstance(e, (Plus, Star)):
            self._note("seeded closure", e, None, None)
            out = cl.closure_apply(self._factors(e.inner), done, side, isinstance(e, Star), leaf_ones=self.leaf_ones)
            return m.restrict(out, col=line) if side == "left" else m.restrict(out, row=line)
        if isinstance(e, Opt):
            inner = self._step(done, e.inner, side, line)
            kept = m.restrict(done, col=line) if side == "left" else m.restrict(done, row=line)
            return m.union(kept, inner)
        self._note("product with", e, None, None)
        if side == "left":
            return m.product(done, self.matrix(e, col=line, side="right"))
        return m.product(self.matrix(e, row=line, side="left"), done)

    def _emptier_end(self, parts: tuple[Expr, ...], row: int, col: int) -> bool:
        """Whether the right end of a chain has fewer ones than the left one; closures count as full."""
        ends = [p for p in (parts[0], parts[-1]) if isinstance(p, (Label, Neg, Alt))]
        if len(ends) < 2:
            return not isinstance(parts[0], (Label, Neg, Alt)) and bool(ends)
        left, right = self._sizes([self.matrix(parts[0], row=row), self.matrix(parts[-1], col=col)])
        self.notes.append(f"ends: {left} ones in the row, {right} in the column")
        return right < left

    def _chain(self, parts: tuple[Expr, ...], whole: Expr, row: int | None, col: int | None) -> DataFrame:
        if self.plan == "naive":
            out = self.matrix(parts[0])
            for p in parts[1:]:
                out = m.product(out, self.matrix(p))
            return out
        if row is not None and (col is None or not self._emptier_end(parts, row, col)):
            out = self.matrix(parts[0], row=row)
            for k, p in enumerate(parts[1:], 1):
                out = self._step(out, p, "left", col if k == len(parts) - 1 else None)
            return out
        if col is not None:
            out = self.matrix(parts[-1], col=col)
            for k, p in enumerate(parts[-2::-1], 1):
                out = self._step(out, p, "right", row if k == len(parts) - 1 else None)
            return out
        return self._ordered(parts, whole)

    def _ordered(self, parts: tuple[Expr, ...], whole: Expr) -> DataFrame:
        """A chain without a constant: first closures and options with the smaller neighbour, then products by size."""
        bound = [k for k, p in enumerate(parts) if isinstance(p, (Plus, Star, Opt))]
        if len(parts) == 2 and not bound:
            return m.product(self.matrix(parts[0], side="left"), self.matrix(parts[1], side="right"))
        factors: list[DataFrame | None] = [None if k in bound else self.matrix(p) for k, p in enumerate(parts)]
        known = [k for k, a in enumerate(factors) if a is not None]
        if not known:  # nothing but closures and options
            out = self.matrix(parts[0])
            for p in parts[1:]:
                out = self._step(out, p, "left", None)
            return out
        # Leaves are counted by one job; what is worked out is kept and counted in turn.
        sizes = dict(zip(known, self._sizes([factors[k] for k in known]), strict=True))
        self.notes.append("sizes " + ", ".join(f"{text_of(parts[k])}: {sizes[k]}" for k in known))
        chain: list[tuple[int, DataFrame]] = []  # closures are taken up by what stands beside them
        waiting: list[Expr] = []
        for k, p in enumerate(parts):
            if factors[k] is None:
                following = next((j for j in known if j > k), None)
                if not chain or (following is not None and not waiting and sizes[following] < chain[-1][0]) or waiting:
                    waiting.append(p)
                else:
                    a = checkpointed(self._step(chain[-1][1], p, "left", None))
                    chain[-1] = (self._sizes([a])[0], a)
                continue
            size, a = sizes[k], factors[k]
            while waiting:
                a = checkpointed(self._step(a, waiting.pop(), "right", None))
                size = self._sizes([a])[0]
            chain.append((size, a))
        if waiting:
            raise AssertionError("a closure was left over")
        if len(chain) < 3:
            out = chain[0][1]
            for _, a in chain[1:]:
                out = m.product(out, a)
            return out
        plain = [a for _, a in chain]

        def multiply(i: int, j: int) -> int:
            plain.append(checkpointed(m.product(plain[i], plain[j])))
            size = self._sizes(plain[-1:])[0]
            self.notes.append(f"multiply {i} and {j}: {size} ones")
            return size

        order_products([n for n, _ in chain], multiply)
        self._note("ordered products", whole, None, None)
        return plain[-1]


def mirrored(e: Expr) -> Expr | None:
    """The first half of a path that goes there and back the same way, else nothing."""
    if not isinstance(e, Seq) or len(e.parts) % 2:
        return None
    half = len(e.parts) // 2
    there = e.parts[0] if half == 1 else Seq(e.parts[:half])
    back = e.parts[half] if half == 1 else Seq(e.parts[half:])
    return there if push_inverse(there, flip=True) == back else None


def _bindings(pairs: DataFrame, query: PathQuery) -> DataFrame:
    if isinstance(query.source, str) and query.source == query.target:
        pairs = pairs.where("r = c")
    return pairs.select(F.col("r").alias("x"), F.col("c").alias("y"))


def answer(graph: Graph, query: PathQuery | str, engine: str = "matrix", plan: str = "optimized", notes: list[str] | None = None, **options) -> DataFrame:
    """All bindings (x, y) of a query; constants appear in their column.

    ``engine``: ``matrix``; ``joins``, the same without planning and with linear
    closures; ``automaton``, which walks the product of graph and expression;
    ``tiles``, the matrix algebra on quadtree tiles.
    """
    if isinstance(query, str):
        query = parse_query(query)
    e = normalise(query.path)
    row = query.source if isinstance(query.source, int) else None
    col = query.target if isinstance(query.target, int) else None
    if engine == "automaton":
        from pathalgebra.plans.automaton import walk

        return _bindings(walk(graph, e, row, col), query)
    if engine == "tiles":
        from pathalgebra.plans.tile_engine import TileEngine

        tiles = TileEngine(graph, **options)
        pairs = tiles.matrix(e, row, col)
        if notes is not None:
            notes += tiles.notes
        return _bindings(pairs, query)
    if engine == "joins":
        worker = Engine(graph, "naive", "linear", **options)
    elif engine == "matrix":
        worker = Engine(graph, plan, **options)
    else:
        raise ValueError(f"no engine {engine!r}")
    pairs = worker.matrix(e, row, col)
    if notes is not None:
        notes += worker.notes
    return _bindings(pairs, query)


def explain(graph: Graph, query: PathQuery | str, **options) -> str:
    """The steps of a query with the sizes that decided about their order, its cost, and Spark's plan."""
    if isinstance(query, str):
        query = parse_query(query)
    worker = Engine(graph, **options)
    ends = [x if isinstance(x, int) else None for x in (query.source, query.target)]
    pairs = worker.matrix(normalise(query.path), *ends)
    plan = pairs._jdf.queryExecution().explainString(pairs.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))
    return "\n".join([*worker.notes, f"cost {worker.cost} ones", plan])


def count_pairs(graph: Graph, query: PathQuery | str, **options) -> int:
    """Number of bindings; a closure of a path there and back is counted without writing its pairs out."""
    if isinstance(query, str):
        query = parse_query(query)
    e = normalise(query.path)
    free = isinstance(query.source, str) and isinstance(query.target, str) and query.source != query.target
    if free and isinstance(e, Plus) and "engine" not in options:
        half = mirrored(e.inner)
        worker = Engine(graph, **options)
        factored = mirrored_closure(worker.matrix(half)) if half is not None else factored_closure(worker.matrix(e.inner))
        return int(factored.count_pairs())
    return answer(graph, query, **options).count()


def targets(graph: Graph, query: PathQuery | str, **options) -> DataFrame:
    """The nodes that the query's target takes."""
    return answer(graph, query, **options).select("y").distinct()


def ask(graph: Graph, query: PathQuery | str, **options) -> bool:
    return not answer(graph, query, **options).isEmpty()


def too_many_answers(df: DataFrame, most: int = 10**6) -> bool:
    """Whether there are more than ``most``, without counting further."""
    return df.limit(most + 1).count() > most


__all__ = ["Engine", "answer", "ask", "count_pairs", "explain", "nullable", "targets", "too_many_answers"]
