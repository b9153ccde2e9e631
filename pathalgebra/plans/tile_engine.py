"""Path expressions over quadtree tiles: the same algebra on the other layout.

Nodes are numbered densely once; every label becomes a table of tiles when it is
first asked for.  Constants restrict sums and products by the tiles' keys and inside
the tiles; a closure beside a restricted factor is walked from that factor.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import cached_property, reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathalgebra.operators import tiles as t
from pathalgebra.plans.paths import Alt, Eps, Expr, Label, Neg, Opt, Plus, Seq, Star, text_of
from pathalgebra.runtime import checkpointed, stored
from pathalgebra.sources.graphs import Graph, dense_numbers


def labels_of(e: Expr) -> frozenset[str] | None:
    """The labels of an expression; None if it speaks of nodes or labels that it doesn't name."""
    match e:
        case Label():
            return frozenset([e.name])
        case Plus(inner):
            return labels_of(inner)
        case Alt(parts) | Seq(parts):
            found = [labels_of(p) for p in parts]
            return None if None in found else frozenset().union(*found)
    return None


@dataclass
class TileEngine:
    """Evaluates path expressions over one graph; ``notes`` gets one line per step."""

    graph: Graph
    tile_bits: int = 10
    notes: list[str] = field(default_factory=list)
    _made: dict[str, DataFrame] = field(default_factory=dict)
    _labels: frozenset[str] | None = None  # labels whose ends are numbered; None: all nodes are

    @cached_property
    def names(self) -> DataFrame:
        """(term, id): nodes and their dense numbers."""
        nodes = self.graph.nodes() if self._labels is None else self.graph.nodes_of(sorted(self._labels))
        return stored(dense_numbers(nodes, "id"), "names")

    def _number_for(self, e: Expr) -> None:
        """Sees that the nodes of ``e`` are numbered: the ends of its labels, or all if a node alone may answer."""
        need = labels_of(e)
        if "names" in self.__dict__ and (self._labels is None or (need is not None and need <= self._labels)):
            return
        if "names" in self.__dict__:
            del self.names
            self._made.clear()
            need = None
        self._labels = need

    def number(self, node: int) -> int | None:
        found = self.names.where(F.col("term") == node).first()
        return None if found is None else found["id"]

    def tiles(self, a: DataFrame) -> DataFrame:
        left, right = self.names.select(F.col("term").alias("r"), F.col("id").alias("nr")), self.names.select(F.col("term").alias("c"), F.col("id").alias("nc"))
        numbered = a.join(left, "r").join(right, "c").select(F.col("nr").alias("r"), F.col("nc").alias("c"))
        return t.to_tiles(numbered, self.tile_bits)

    def _leaf(self, e: Label | Neg) -> DataFrame:
        key = text_of(Label(e.name) if isinstance(e, Label) else Neg(e.names))
        if key not in self._made:
            self._made[key] = checkpointed(self.tiles(self.graph.matrix(e.name) if isinstance(e, Label) else self.graph.without_labels(e.names)))
        return t.tile_transpose(self._made[key]) if e.inverse else self._made[key]

    def _identity(self, row: int | None, col: int | None) -> DataFrame:
        nodes = self.names.select("id")
        for line in (row, col):
            nodes = nodes if line is None else nodes.where(F.col("id") == line)
        return t.tile_identity(nodes, self.tile_bits)

    def work(self, e: Expr, row: int | None = None, col: int | None = None) -> DataFrame:
        """Tiles of ``e``, in one row or column (dense numbers) if asked."""
        self.notes.append(text_of(e) + f" row={row}" * (row is not None) + f" col={col}" * (col is not None))
        bits = self.tile_bits
        match e:
            case Eps():
                return self._identity(row, col)
            case Label() | Neg():
                return t.tile_restrict(self._leaf(e), row, col, bits)
            case Alt(parts):
                return reduce(t.tile_sum, [self.work(p, row, col) for p in parts])
            case Opt(inner):
                return t.tile_sum(self._identity(row, col), self.work(inner, row, col))
            case Plus(inner) | Star(inner):
                reflexive = isinstance(e, Star)
                if row is None and col is None and isinstance(inner, Seq):
                    first, rest = checkpointed(self.work(inner.parts[0])), self._chain(list(inner.parts[1:]), None, None)
                    closed = t.tile_round_trips(first, rest, bits)
                    if closed is None:
                        closed = t.tile_closure(t.tile_product(first, rest, tile_bits=bits))
                    return t.tile_sum(self._identity(None, None), closed) if reflexive else closed
                base = self.work(inner)
                if row is not None:
                    return t.tile_restrict(self._beside(base, self._identity(row, None), reflexive), None, col, bits)
                if col is not None:
                    return t.tile_transpose(self._beside(t.tile_transpose(base), self._identity(None, col), reflexive))
                closed = t.tile_closure(base)
                return t.tile_sum(self._identity(None, None), closed) if reflexive else closed
            case Seq(parts):
                return self._chain(list(parts), row, col)
        raise TypeError(e)

    def _beside(self, base: DataFrame, seed: DataFrame, reflexive: bool) -> DataFrame:
        return t.tile_reach(base, seed, reflexive)

    def _chain(self, parts: list[Expr], row: int | None, col: int | None) -> DataFrame:
        """From the restricted end inwards; closures are walked from what is worked out."""
        if row is None and col is not None:
            out = self.work(parts[-1], None, col)
            for p in reversed(parts[:-1]):
                if isinstance(p, (Plus, Star)):
                    base = t.tile_transpose(self.work(p.inner))
                    out = t.tile_transpose(self._beside(base, t.tile_transpose(out), isinstance(p, Star)))
                else:
                    out = t.tile_product(self.work(p), out, None, None, self.tile_bits)
            return out
        out = self.work(parts[0], row, None)
        for k, p in enumerate(parts[1:], 1):
            last = col if k == len(parts) - 1 else None
            if isinstance(p, (Plus, Star)):
                out = t.tile_restrict(self._beside(self.work(p.inner), out, isinstance(p, Star)), None, last, self.tile_bits)
            else:
                out = t.tile_product(out, self.work(p, None, last), None, last, self.tile_bits)
        return out

    def matrix(self, e: Expr, row: int | None = None, col: int | None = None) -> DataFrame:
        """Ones of ``e`` between the graph's own nodes."""
        near = self._reached(e, row, col)
        if near is not None:
            worker = TileEngine(near, self.tile_bits, self.notes)
            worker._number_for(e)
            return worker._pairs(e, row, col)
        self._number_for(e)
        return self._pairs(e, row, col)

    def _reached(self, e: Expr, row: int | None, col: int | None) -> Graph | None:
        """The graph with those ones of a chain's labels only that a walk from the constant meets; None for other expressions.

        Nodes are numbered and tiles made of these alone, as most of a large graph lies
        out of a constant's reach.
        """
        steps = [p.parts if isinstance(p, Alt) else (p,) for p in (e.parts if isinstance(e, Seq) else (e,))]
        if (row is None and col is None) or not all(isinstance(x, Label) for step in steps for x in step):
            return None
        backward, line = row is None, None
        cut: dict[str, list[DataFrame]] = {}
        for step in reversed(steps) if backward else steps:
            ends = []
            for x in step:
                start, end = ("c", "r") if x.inverse != backward else ("r", "c")
                own = self.graph.matrix(x.name)
                if line is None:
                    own = own.where(F.col(start) == (col if backward else row))
                else:
                    own = own.join(line.select(F.col("id").alias(start)), start, "left_semi")
                own = stored(own.select("r", "c"), "reached")
                cut.setdefault(x.name, []).append(own)
                ends.append(own.select(F.col(end).alias("id")))
            line = stored(reduce(DataFrame.unionByName, ends).distinct(), "line")
        return Graph(self.graph.spark, {k: (lambda v=v: reduce(DataFrame.unionByName, v).distinct()) for k, v in cut.items()})

    def _pairs(self, e: Expr, row: int | None, col: int | None) -> DataFrame:
        lines = [None if x is None else self.number(x) for x in (row, col)]
        if (row is not None and lines[0] is None) or (col is not None and lines[1] is None):
            return self.graph.matrix("")  # a constant that isn't a node
        if row is None and col is None and isinstance(e, Plus) and not isinstance(e.inner, Seq):
            self.notes.append(text_of(e))
            return t.closed_pairs(self.work(e.inner), self.tile_bits, self.names)
        return t.from_tiles(self.work(e, *lines), self.tile_bits, self.names)
