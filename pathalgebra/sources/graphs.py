"""Labeled graphs: one matrix per label, and graphs on the given tables."""

from __future__ import annotations

from collections.abc import Callable
from functools import cached_property, reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pathalgebra.plans.paths import KIND_STEP, KINDS
from pathalgebra.runtime import checkpointed, table


class Graph:
    """Labels and their matrices; nothing is read before a matrix is asked for."""

    def __init__(self, spark: SparkSession, matrices: dict[str, Callable[[], DataFrame]], ends: Callable[[list[str]], DataFrame] | None = None):
        self.spark, self._make = spark, matrices
        self._ends = ends  # labels -> ends of their ones in a column ``id``, repeated or not, without making the matrices
        self._made: dict[str, DataFrame] = {}
        self._all: DataFrame | None = None  # all triples in one frame, if the graph came as one

    @classmethod
    def from_triples(cls, triples: DataFrame) -> Graph:
        """From (s, p, o); labels are found, rows with a null are dropped, copies merge."""
        clean = checkpointed(triples.select("s", "p", "o").where("s is not null and p is not null and o is not null").distinct())
        names = [r[0] for r in clean.select("p").distinct().collect()]
        graph = cls(clean.sparkSession, {n: (lambda n=n: clean.where(F.col("p") == n).select(F.col("s").alias("r"), F.col("o").alias("c"))) for n in names})
        graph._all = clean
        return graph

    @property
    def labels(self) -> list[str]:
        return sorted(self._make)

    def matrix(self, label: str) -> DataFrame:
        """The label's matrix; an unknown label has no ones."""
        if label not in self._make:
            return self.spark.createDataFrame([], "r long, c long")
        if label not in self._made:
            self._made[label] = self._make[label]()
        return self._made[label]

    def view(self, label: str, by: str | None = None) -> DataFrame:
        """The label's matrix, laid out by its rows ("r") or columns ("c") where the graph has such views."""
        return self.matrix(label)

    def without_labels(self, names: tuple[str, ...]) -> DataFrame:
        if self._all is not None:
            return self._all.where(~F.col("p").isin(list(names))).select(F.col("s").alias("r"), F.col("o").alias("c")).distinct()
        rest = [self.matrix(x) for x in self.labels if x not in names]
        return reduce(lambda a, b: a.unionByName(b), rest).distinct() if rest else self.matrix("")

    @cached_property
    def _nodes(self) -> DataFrame:
        if self._all is not None:
            return self._all.select(F.explode(F.array("s", "o")).alias("id")).distinct()
        return self.nodes_of(self.labels)

    def nodes(self) -> DataFrame:
        return self._nodes

    def nodes_of(self, labels: list[str]) -> DataFrame:
        """The ends of the ones of some labels."""
        labels = [x for x in labels if x in self._make]
        if self._ends is not None and labels:
            return self._ends(labels).distinct()
        ends = [self.matrix(x).select(F.col(c).alias("id")) for x in labels for c in ("r", "c")]
        return reduce(lambda a, b: a.unionByName(b), ends).distinct() if ends else self.matrix("").select(F.col("r").alias("id"))

    def triples(self) -> DataFrame:
        if self._all is not None:
            return self._all
        parts = [self.matrix(x).select(F.col("r").alias("s"), F.lit(x).alias("p"), F.col("c").alias("o")) for x in self.labels]
        return reduce(lambda a, b: a.unionByName(b), parts)


def node_id(kind: str, key: str | Column) -> Column:
    key = F.col(key) if isinstance(key, str) else key
    return (F.lit(KINDS[kind] * KIND_STEP) + key).cast("long")


def _pairs(df: DataFrame, r, c) -> DataFrame:
    return df.select(r.alias("r"), c.alias("c")).where("r is not null and c is not null").distinct()


def _both_ends(df: DataFrame, r: Column, c: Column) -> DataFrame:
    return df.select(r.alias("r"), c.alias("c")).where("r is not null and c is not null").select(F.explode(F.array("r", "c")).alias("id"))


def dense_numbers(terms: DataFrame, column: str) -> DataFrame:
    """(term, id): distinct non-null terms, numbered from 0 in their order.

    A range-partitioned sort numbers each partition by itself; the counts of
    partitions, one row each, give the offsets.  No window covers all rows.
    """
    distinct = terms.select(F.col(column).alias("term")).where("term is not null").distinct()
    placed = distinct.repartitionByRange("term").sortWithinPartitions("term").withColumn("part", F.spark_partition_id())
    placed = checkpointed(placed)
    counts = placed.groupBy("part").agg(F.count("*").alias("n"))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select("part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("offset"))
    within = F.row_number().over(Window.partitionBy("part").orderBy("term")) - 1
    return placed.withColumn("k", within).join(F.broadcast(offsets), "part").select("term", (F.col("offset") + F.col("k")).cast("long").alias("id"))


def following(df: DataFrame, order: list[str], columns: list[str]) -> DataFrame:
    """Every row with the next row's ``columns`` as ``next_...`` in the order of all rows.

    Range-partitioned; a partition's last row gets the first row of the next
    partition that has any, one row for each partition.
    """
    placed = checkpointed(df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("part", F.spark_partition_id()))
    by = Window.partitionBy("part").orderBy(*order)
    here = placed.select("*", *(F.lead(c).over(by).alias(f"next_{c}") for c in columns), F.lead(F.lit(True)).over(by).alias("inner"))
    firsts = placed.groupBy("part").agg(F.min_by(F.struct(*columns), F.struct(*order)).alias("first"))
    firsts = firsts.select((F.lag("part").over(Window.orderBy("part"))).alias("part"), "first").where("part is not null")
    joined = here.join(F.broadcast(firsts), "part", "left")
    own = [F.when(F.col("inner"), F.col(f"next_{c}")).otherwise(F.col(f"first.{c}")).alias(f"next_{c}") for c in columns]
    return joined.select(*df.columns, *own)


def commerce(spark: SparkSession, sf: str) -> Graph:
    """Orders, parts, suppliers, customers, nations and regions."""

    def literal(column: str) -> tuple[DataFrame, Column, Column]:
        part = table(spark, sf, "part")
        names = dense_numbers(part, column)
        return part.join(names, part[column] == names["term"]), node_id("part", "p_partkey"), node_id("literal", "id")

    read = lambda name: table(spark, sf, name)
    rows = {
        "placed_by": lambda: (read("orders"), node_id("order", "o_orderkey"), node_id("customer", "o_custkey")),
        "contains": lambda: (read("lineitem"), node_id("order", "l_orderkey"), node_id("part", "l_partkey")),
        "shipped_from": lambda: (read("lineitem"), node_id("order", "l_orderkey"), node_id("supplier", "l_suppkey")),
        "sourced_from": lambda: (read("lineitem"), node_id("part", "l_partkey"), node_id("supplier", "l_suppkey")),
        "cust_in": lambda: (read("customer"), node_id("customer", "c_custkey"), node_id("nation", "c_nationkey")),
        "supp_in": lambda: (read("supplier"), node_id("supplier", "s_suppkey"), node_id("nation", "s_nationkey")),
        "in_region": lambda: (read("nation"), node_id("nation", "n_nationkey"), node_id("region", "n_regionkey")),
        "has_brand": lambda: literal("p_brand"),
        "has_type": lambda: literal("p_type"),
    }
    ends = lambda labels: reduce(DataFrame.unionByName, [_both_ends(*rows[x]()) for x in labels])
    return Graph(spark, {k: (lambda v=v: _pairs(*v())) for k, v in rows.items()}, ends)


def geography(spark: SparkSession, sf: str) -> Graph:
    return Graph(spark, {"in_region": lambda: _pairs(table(spark, sf, "nation"), node_id("nation", "n_nationkey"), node_id("region", "n_regionkey"))})


#: Types of events on the given tables.
EVENT_TYPES = ("click", "error", "purchase", "signup", "view")


def activity(spark: SparkSession, sf: str) -> Graph:
    """From a user to the user of the next event, by the type of the first one."""
    steps = following(table(spark, sf, "events").select("ts", "event_id", "user_id", "event_type"), ["ts", "event_id"], ["user_id"])
    # Repeated steps go before they are kept, not once for each label.
    steps = checkpointed(steps.select("event_type", "user_id", "next_user_id").where("user_id is not null and next_user_id is not null").distinct())
    edge = lambda t: _pairs(steps.where(F.col("event_type") == t), node_id("user", "user_id"), node_id("user", "next_user_id"))
    ends = lambda labels: _both_ends(steps.where(F.col("event_type").isin(labels)), node_id("user", "user_id"), node_id("user", "next_user_id"))
    return Graph(spark, {t: (lambda t=t: edge(t)) for t in EVENT_TYPES}, ends)


def succession(spark: SparkSession, sf: str) -> Graph:
    """From an event to the same user's next one, by the type of the first one."""
    by = Window.partitionBy("user_id").orderBy("ts", "event_id")
    steps = table(spark, sf, "events").select("event_id", "event_type", F.lead("event_id").over(by).alias("after"))
    edge = lambda t: _pairs(steps.where(F.col("event_type") == t), node_id("event", "event_id"), node_id("event", "after"))
    ends = lambda labels: _both_ends(steps.where(F.col("event_type").isin(labels)), node_id("event", "event_id"), node_id("event", "after"))
    return Graph(spark, {t: (lambda t=t: edge(t)) for t in EVENT_TYPES}, ends)


def dialog(spark: SparkSession, sf: str) -> Graph:
    """From a turn to the conversation's next one, by the role that speaks."""
    by = Window.partitionBy("conv_id").orderBy("turn")
    key = F.col("conv_id") * 1000 + F.col("turn")
    steps = table(spark, sf, "conversations").select("role", node_id("turn", key).alias("a"), F.lead(node_id("turn", key)).over(by).alias("b"))
    edge = lambda t: _pairs(steps.where(F.col("role") == t), F.col("a"), F.col("b"))
    return Graph(spark, {t: (lambda t=t: edge(t)) for t in ("assistant", "system", "user")})


def weblinks(spark: SparkSession, sf: str) -> Graph:
    """From a page to the addresses it links to and to its host; addresses are numbered densely."""
    pages = table(spark, sf, "pages")
    links = pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("term")).distinct()
    hosts = pages.select("page_id", F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("term")).distinct()
    names = checkpointed(dense_numbers(links.select("term").union(hosts.select("term")), "term"))
    edge = lambda d: _pairs(d.join(names, "term"), node_id("page", "page_id"), node_id("literal", "id"))
    return Graph(spark, {"links_to": lambda: edge(links), "on_host": lambda: edge(hosts)})


def corpus(spark: SparkSession, sf: str) -> Graph:
    """Documents: equal texts, source and language; literals are numbered densely."""
    docs = table(spark, sf, "documents")

    def literal(column: str) -> DataFrame:
        names = dense_numbers(docs, column)
        return _pairs(docs.select("doc_id", F.col(column).alias("term")).join(names, "term"), node_id("document", "doc_id"), node_id("literal", "id"))

    def copies() -> DataFrame:
        # Texts are compared by two hashes; each copy is linked with the least document of its
        # text and back, so a group of n copies has 2 (n - 1) links.
        keyed = checkpointed(docs.where("text is not null").select("doc_id", F.md5(F.col("text").cast("binary")).alias("k"), F.length("text").alias("n")))
        groups = keyed.groupBy("k", "n").agg(F.count("*").alias("m"), F.min("doc_id").alias("first")).where("m > 1").select("k", "n", "first")
        star = checkpointed(keyed.join(groups, ["k", "n"]).where("doc_id <> first").select("doc_id", "first"))
        both = star.unionByName(star.select(F.col("first").alias("doc_id"), F.col("doc_id").alias("first")))
        return _pairs(both, node_id("document", "doc_id"), node_id("document", "first"))

    return Graph(spark, {"copy_of": copies, "from_source": lambda: literal("source"), "in_lang": lambda: literal("lang")})


def grid(spark: SparkSession, sf: str, thin: int = 1, keep: int = 0) -> Graph:
    """Matrices of side 1000 from lineitem, one for each flag and status, thinned to a density."""
    items = table(spark, sf, "lineitem").where(F.pmod(F.round(F.col("l_extendedprice") * 100).cast("long"), F.lit(thin)) == keep)
    edge = lambda flag, status: _pairs(items.where((F.col("l_returnflag") == flag) & (F.col("l_linestatus") == status)), F.pmod("l_partkey", F.lit(1000)), F.pmod("l_orderkey", F.lit(1000)))
    return Graph(spark, {f"{a}{b}": (lambda a=a, b=b: edge(a, b)) for a in "ANR" for b in "FO"})


#: The small city of the worked example. Stations are 1 to 5, places 6 to 8.
_CITY = {"walk": [(1, 6), (3, 6), (4, 8), (5, 7)], "orange": [(1, 2), (2, 4)], "navy": [(3, 4)], "red": [(4, 5)]}


def city(spark: SparkSession) -> Graph:
    both = {k: v + [(b, a) for a, b in v] for k, v in _CITY.items()}
    return Graph(spark, {k: (lambda v=v: spark.createDataFrame(v, "r long, c long")) for k, v in both.items()})


def transit(spark: SparkSession, sf: str) -> Graph:
    """The city's lines on a given table: events that follow each other, walked both ways; the type of the first one is the line."""
    lines = succession(spark, sf)
    both = lambda t: lines.matrix(t).unionByName(lines.matrix(t).select(F.col("c").alias("r"), F.col("r").alias("c"))).distinct()
    return Graph(spark, {k: (lambda t=t: both(t)) for k, t in {"walk": "view", "orange": "signup", "navy": "click", "red": "purchase"}.items()})


def cells(spark: SparkSession, sf: str, keep: int) -> DataFrame:
    """Distinct cells of a matrix of side 1000 from a hundredth of lineitem, told by the price."""
    items = table(spark, sf, "lineitem").where(F.pmod(F.round(F.col("l_extendedprice") * 100).cast("long"), F.lit(100)) == keep)
    return _pairs(items, F.pmod("l_partkey", F.lit(1000)), F.pmod("l_orderkey", F.lit(1000)))


def uniform(spark: SparkSession, density: float, seed: int, side: int = 1000) -> DataFrame:
    """A matrix whose cells are ones with probability ``density``, the same on every engine."""
    prime = 2**31 - 1
    cell = F.col("id")
    h = (F.lit(48271) * cell + 1 + 1_000_003 * seed) % prime
    h = (h * h) % prime
    h = (h + 7919 * seed + cell) % prime
    h = (h * h) % prime
    cells = spark.range(side * side).where(h < int(density * prime))
    return cells.select(F.floor(cell / side).cast("long").alias("r"), (cell % side).alias("c"))


GRAPHS = {"commerce": commerce, "geography": geography, "activity": activity, "succession": succession, "dialog": dialog, "weblinks": weblinks, "corpus": corpus}
