"""Registered queries: path queries, matrix operations, closures, measures, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pathalgebra.functions.measures import alternation, label_stats
from pathalgebra.functions.zorder import zorder
from pathalgebra.operators import closure as cl
from pathalgebra.operators import components as comps
from pathalgebra.operators import matrix as m
from pathalgebra.operators import tiles
from pathalgebra.plans.evaluate import Engine, answer, mirrored
from pathalgebra.plans.paths import Label, node, normalise, parse_path
from pathalgebra.plans.to_sql import MATRICES, matrix_sql, query_sql
from pathalgebra.runtime import stored, table
from pathalgebra.sources import graphs
from pathalgebra.sources.store import DualGraph

Query = Callable[[SparkSession, str], DataFrame]

#: Key -> graph and query.
PATHS: dict[str, tuple[str, str]] = {
    "rpq_union_vv": ("commerce", "?x contains|shipped_from ?y"),
    "rpq_union_activity": ("activity", "?x click|view ?y"),
    "rpq_concat_vv": ("commerce", "?x cust_in/in_region ?y"),
    "rpq_chain_vv": ("commerce", "?x ^placed_by/shipped_from/supp_in ?y"),
    "rpq_chain_cv": ("commerce", "customer:7 ^placed_by/contains/sourced_from ?y"),
    "rpq_chain_vc": ("commerce", "?x cust_in/in_region region:0"),
    "rpq_chain4_vc": ("commerce", "?x ^placed_by/shipped_from/supp_in/in_region region:0"),
    "rpq_chain_cc": ("commerce", "customer:7 ^placed_by/shipped_from/supp_in nation:3"),
    "rpq_same_nation": ("commerce", "?x (supp_in/^supp_in)+ ?y"),
    "rpq_same_region": ("geography", "?x (in_region/^in_region)+ ?y"),
    "rpq_saturating_plus": ("activity", "?x error+ ?y"),
    "rpq_alt_plus": ("succession", "?x (click|view)+ ?y"),
    "rpq_long_chain_cv": ("succession", "event:0 (click|view|error|signup|purchase)+ ?y"),
    "rpq_mid_plus": ("succession", "?x signup/(click|view)+/purchase ?y"),
    "rpq_mid_star": ("succession", "?x signup/(click|view)*/purchase ?y"),
    "rpq_mid_optional": ("succession", "?x signup/click?/purchase ?y"),
    "rpq_turns": ("dialog", "?x (user/assistant)+ ?y"),
    "rpq_dialog_plus": ("dialog", "?x (user|assistant|system)+ ?y"),
    "rpq_copies": ("corpus", "?x copy_of+ ?y"),
    "rpq_copy_source": ("corpus", "?x copy_of/from_source ?y"),
    "rpq_web_cluster": ("weblinks", "?x (links_to/^links_to)+ ?y"),
    "rpq_customer_cluster": ("commerce", "customer:7 (^placed_by/contains/^contains/placed_by)+ ?y"),
    "rpq_loop": ("activity", "?x click+ ?x"),
    "rpq_neg": ("activity", "?x !(click|view) ?y"),
    "rpq_inverse_group": ("commerce", "?x ^(cust_in/in_region) ?y"),
    "rpq_brand_peers": ("commerce", "part:1 has_brand/^has_brand ?y"),
    "rpq_nested_star": ("geography", "?x ((in_region/^in_region)*)+ ?y"),
}

_ROW, _COL = node("user", 3), node("user", 5)


def _named(df: DataFrame) -> DataFrame:
    return df.select(F.col("r").alias("x"), F.col("c").alias("y"))


def path_query(key: str, **options) -> Query:
    graph, text = PATHS[key]
    return lambda spark, sf: answer(graphs.GRAPHS[graph](spark, sf), text, **options)


def _on_activity(f: Callable[[DataFrame, DataFrame], DataFrame]) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        g = graphs.activity(spark, sf)
        return f(g.matrix("click"), g.matrix("view"))

    return run


def _base(graph: str, path: str) -> Callable[[SparkSession, str], tuple[graphs.Graph, DataFrame]]:
    def make(spark: SparkSession, sf: str) -> tuple[graphs.Graph, DataFrame]:
        g = graphs.GRAPHS[graph](spark, sf)
        return g, Engine(g).matrix(normalise(parse_path(path)))

    return make


_clicks_views = _base("succession", "click|view")
_any_event = _base("succession", "click|view|error|signup|purchase")


def _closure(method: str, **options) -> Query:
    return lambda spark, sf: cl.closure(_clicks_views(spark, sf)[1], method, **options)


def _seeded(seed: str, side: str, reflexive: bool, **options) -> Query:
    """(click|view) closed beside a restricted factor; the constant is the least fitting event."""

    def run(spark: SparkSession, sf: str) -> DataFrame:
        g, base = _clicks_views(spark, sf)
        factor = g.matrix(seed)
        end = "c" if side == "right" else "r"
        line = factor.agg(F.min(end)).first()[0]
        return cl.closure_apply(base, factor.where(F.col(end) == line), side, reflexive, **options)

    return run


def _seeded_sql(seed: str, side: str, reflexive: bool) -> str:
    a, base = MATRICES["succession"][seed], matrix_sql("succession", "click|view")
    end = "c" if side == "right" else "r"
    step = "SELECT b.r, t.c FROM t JOIN b ON b.c = t.r" if side == "right" else "SELECT t.r, b.c FROM t JOIN b ON t.c = b.r"
    # The second member counts steps of the closure only as none or some.
    step = step.replace("SELECT ", "SELECT 1 AS k, ")
    own = "" if reflexive else " WHERE k = 1"
    return (
        f"WITH RECURSIVE a AS ({a}), s AS (SELECT r, c FROM a WHERE {end} = (SELECT min({end}) FROM a)), b AS ({base}), "
        f"t(k, r, c) AS (SELECT 0 AS k, r, c FROM s UNION {step}) SELECT DISTINCT r, c FROM t{own}"
    )


def _reach(kind: str) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        _, base = _any_event(spark, sf)
        zero = node("event", 0)
        if kind == "from":
            return cl.closure_from(base, zero)
        if kind == "from_reflexive":
            return cl.closure_from(base, zero, reflexive=True)
        last = base.agg(F.max("c")).first()[0]
        if kind == "to":
            return cl.closure_to(base, last)
        if kind == "to_reflexive":
            return cl.closure_to(base, last, reflexive=True)
        if kind == "cell_true":
            return cl.reachable(base, base.where(F.col("c") == last).agg(F.min("r")).first()[0], last)
        if kind == "cell_false":
            return cl.reachable(base, last, zero)
        return cl.closure_from(base, zero, most_steps=10)

    return run


def _reach_sql() -> dict[str, str]:
    base = matrix_sql("succession", "click|view|error|signup|purchase")
    zero = node("event", 0)
    head = f"WITH RECURSIVE b AS MATERIALIZED ({base}), "
    ahead = f"t(r, c) AS (SELECT r, c FROM b WHERE r = {zero} UNION SELECT t.r, b.c FROM t JOIN b ON t.c = b.r) "
    back = "t(r, c) AS (SELECT r, c FROM b WHERE c = (SELECT max(c) FROM b) UNION SELECT b.r, t.c FROM t JOIN b ON b.c = t.r) "
    bounded = f"t(r, c, k) AS (SELECT r, c, 1 FROM b WHERE r = {zero} UNION SELECT t.r, b.c, t.k + 1 FROM t JOIN b ON t.c = b.r WHERE t.k < 10) "
    return {
        "reach_from": f"{head}{ahead}SELECT r, c FROM t",
        "reach_from_reflexive": f"{head}{ahead}SELECT r, c FROM t UNION SELECT {zero}, {zero}",
        "reach_to": f"{head}{back}SELECT r, c FROM t",
        "reach_to_reflexive": f"{head}{back}SELECT r, c FROM t UNION SELECT max(c), max(c) FROM b",
        "reach_cell_true": f"{head}{back}SELECT r, c FROM t WHERE r = (SELECT min(r) FROM b WHERE c = (SELECT max(c) FROM b))",
        "reach_cell_false": f"{head}t(r, c) AS (SELECT r, c FROM b WHERE r = (SELECT max(c) FROM b) UNION SELECT t.r, b.c FROM t JOIN b ON t.c = b.r) SELECT r, c FROM t WHERE c = {zero}",
        "reach_within_k": f"{head}{bounded}SELECT DISTINCT r, c FROM t",
    }


def _numbered(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    """click and view over dense user numbers."""
    g = graphs.activity(spark, sf)
    names = stored(graphs.dense_numbers(g.nodes(), "id"), "names")
    left, right = names.select(F.col("term").alias("r"), F.col("id").alias("nr")), names.select(F.col("term").alias("c"), F.col("id").alias("nc"))

    def numbered(label: str) -> DataFrame:
        return g.matrix(label).join(left, "r").join(right, "c").select(F.col("nr").alias("r"), F.col("nc").alias("c"))

    return numbered("click"), numbered("view")


def _numbered_sql(label: str) -> str:
    nodes = " UNION ".join(f"SELECT {s} AS id FROM ({q}) AS m" for q in MATRICES["activity"].values() for s in "rc")
    names = f"(SELECT id, row_number() OVER (ORDER BY id) - 1 AS n FROM ({nodes}) AS v)"
    return f"SELECT x.n AS r, y.n AS c FROM ({MATRICES['activity'][label]}) AS e JOIN {names} AS x ON e.r = x.id JOIN {names} AS y ON e.c = y.id"


def _on_dual(key: str) -> Query:
    """A path query on the same graph in the dual layout."""

    def run(spark: SparkSession, sf: str) -> DataFrame:
        graph, text = PATHS[key]
        return answer(DualGraph.write(graphs.GRAPHS[graph](spark, sf)), text)

    return run


def _far_row(spark: SparkSession, sf: str) -> tuple[DataFrame, int]:
    """Clicks and views in succession, and the least event with one."""
    _, base = _clicks_views(spark, sf)
    return base, base.agg(F.min("r")).first()[0]


def reach_from_distributed(spark: SparkSession, sf: str) -> DataFrame:
    """A row of a closure by rounds over the cluster, whatever its size."""
    base, row = _far_row(spark, sf)
    return cl.closure_from(base, row, leaf_ones=0)


def reach_cell_distributed(spark: SparkSession, sf: str) -> DataFrame:
    base, row = _far_row(spark, sf)
    return cl.reachable(base, row, base.where(F.col("r") == row).agg(F.max("c")).first()[0], leaf_ones=0)


def _on_tiles(f: Callable[[DataFrame, DataFrame], DataFrame], bits: int = 5) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        a, b = _numbered(spark, sf)
        return tiles.from_tiles(f(tiles.to_tiles(a, bits), tiles.to_tiles(b, bits)), bits)

    return run


def quad_closure(spark: SparkSession, sf: str) -> DataFrame:
    a, _ = _numbered(spark, sf)
    return tiles.closed_pairs(tiles.to_tiles(a, 7), 7)


def zorder_codes(spark: SparkSession, sf: str) -> DataFrame:
    a, _ = _numbered(spark, sf)
    return a.select("r", "c", zorder(F.col("r"), F.col("c")).alias("z"))


def _zorder_sql() -> str:
    bits = " + ".join(f"(((r >> {k}) & 1) << {2 * k + 1}) + (((c >> {k}) & 1) << {2 * k})" for k in range(20))
    return f"SELECT r, c, CAST({bits} AS BIGINT) AS z FROM ({_numbered_sql('click')}) AS a"


def alternation_small(spark: SparkSession, sf: str) -> DataFrame:
    a, b = _numbered(spark, sf)
    rows = [(k, int(alternation(a, b, k))) for k in ("certificate", "switches")]
    return spark.createDataFrame(rows, "kind string, n long")


def _alternation_sql() -> str:
    z = _zorder_sql().replace("SELECT r, c, ", "SELECT ")
    both = f"SELECT z, 1 AS side FROM ({z}) AS p UNION ALL SELECT z, 2 FROM ({z.replace(_numbered_sql('click'), _numbered_sql('view'))}) AS q"
    tagged = f"SELECT z, sum(side) AS side FROM ({both}) AS u GROUP BY z"
    lagged = "SELECT side, lag(side) OVER (ORDER BY z) AS before FROM ({}) AS t"
    return (
        f"SELECT 'certificate' AS kind, CAST(sum(CASE WHEN side = 3 OR before <> side THEN 1 ELSE 0 END) AS BIGINT) AS n FROM ({lagged.format(tagged)}) AS a "
        f"UNION ALL SELECT 'switches', CAST(sum(CASE WHEN before <> side THEN 1 ELSE 0 END) AS BIGINT) FROM ({lagged.format(f'SELECT * FROM ({tagged}) AS w WHERE side <> 3')}) AS b"
    )


def density_by_label(spark: SparkSession, sf: str) -> DataFrame:
    """Ones of each label, and parts per million of all cells."""
    g = graphs.activity(spark, sf)
    side = g.nodes().agg(F.count("*").alias("v"))
    stats = label_stats(g.triples())
    return stats.crossJoin(F.broadcast(side)).select("p", "ones", "subjects", "objects", F.expr("1000000 * ones div (v * v)").alias("ppm"))


def closure_saturation(spark: SparkSession, sf: str) -> DataFrame:
    """Ones of each label's closure, counted without writing pairs out."""
    g = graphs.activity(spark, sf)
    rows = [(t, int(comps.factored_closure(g.matrix(t)).count_pairs())) for t in ("click", "error", "view")]
    return spark.createDataFrame(rows, "p string, ones long")


def components_query(spark: SparkSession, sf: str) -> DataFrame:
    return comps.components(graphs.corpus(spark, sf).matrix("copy_of"))


def components_distributed(spark: SparkSession, sf: str) -> DataFrame:
    return comps.components(graphs.corpus(spark, sf).matrix("copy_of"), leaf_ones=0)


def condensation(spark: SparkSession, sf: str) -> DataFrame:
    """Edges between components of clicks and views among users, with one component for each cycle."""
    g, a = _base("activity", "click|view")(spark, sf)
    dag, _ = comps.condense(a, comps.components(a))
    return dag


def component_expand(spark: SparkSession, sf: str) -> DataFrame:
    """Pages linked through addresses, expanded from components; the path there and back isn't built."""
    half = mirrored(normalise(parse_path("links_to/^links_to")))
    return comps.mirrored_closure(Engine(graphs.weblinks(spark, sf)).matrix(half)).pairs()


def star_const(spark: SparkSession, sf: str) -> DataFrame:
    g = graphs.succession(spark, sf)
    least = g.matrix("signup").agg(F.min("c")).first()[0]
    return answer(g, f"?x signup/(click|view)* event:{least - node('event', 0)}")


def _star_const_sql() -> str:
    return f"SELECT r AS x, c AS y FROM ({matrix_sql('succession', 'signup/(click|view)*')}) AS q WHERE c = (SELECT min(c) FROM ({MATRICES['succession']['signup']}) AS m)"


def latency_split(spark: SparkSession, sf: str) -> DataFrame:
    """The shape of a latency table, with order prices in place of seconds."""
    rows = table(spark, sf, "orders").select("o_orderstatus", (F.col("o_custkey") % 20 != 0).alias("has_const"), F.round(F.col("o_totalprice")).cast("long").alias("v"))
    out = rows.rollup("o_orderstatus", "has_const").agg(F.count("*").alias("n"), F.sum("v").alias("total"), F.expr("cast(round(percentile(v, 0.5)) as bigint)").alias("median_v"))
    return out.select(F.coalesce("o_orderstatus", F.lit("all")).alias("engine"), F.coalesce(F.col("has_const").cast("string"), F.lit("all")).alias("part"), "n", "total", "median_v")


def pattern_with_path(spark: SparkSession, sf: str) -> DataFrame:
    """Orders of customers whose nation shares a region with nation 3: a pattern with a path inside."""
    g = graphs.commerce(spark, sf)
    near = answer(g, "?n in_region/^in_region nation:3").select(F.col("x").alias("nation"))
    homes = g.matrix("cust_in").select(F.col("r").alias("customer"), F.col("c").alias("nation"))
    orders = g.matrix("placed_by").select(F.col("r").alias("order"), F.col("c").alias("customer"))
    return near.join(homes, "nation").join(orders, "customer").select("order", "customer", "nation")


def _pattern_sql() -> str:
    x = MATRICES["commerce"]
    near = query_sql("commerce", "?n in_region/^in_region nation:3")
    return f'SELECT o.r AS "order", h.r AS customer, h.c AS nation FROM ({near}) AS n JOIN ({x["cust_in"]}) AS h ON h.c = n.x JOIN ({x["placed_by"]}) AS o ON o.c = h.r'


def star_small(spark: SparkSession, sf: str) -> DataFrame:
    return _named(Engine(graphs.geography(spark, sf)).matrix(normalise(parse_path("(in_region/^in_region)*"))))


def grid_ones(spark: SparkSession, sf: str) -> DataFrame:
    """Ones of the grid's matrices at three densities."""
    parts = [label_stats(graphs.grid(spark, sf, thin).triples()).select("p", F.lit(thin).alias("thin"), "ones") for thin in (1, 10, 100)]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


_GRID = (
    "SELECT l_returnflag || l_linestatus AS p, {t} AS thin, count(DISTINCT (l_partkey % 1000) * 1000 + l_orderkey % 1000) AS ones "
    "FROM lineitem WHERE CAST(round(l_extendedprice * 100) AS BIGINT) % {t} = 0 GROUP BY ALL"
)


def encode_nodes(spark: SparkSession, sf: str) -> DataFrame:
    return graphs.dense_numbers(table(spark, sf, "part"), "p_type")


def city_query(spark: SparkSession, sf: str) -> DataFrame:
    """The worked example: places reached on foot, by one of two lines, and on foot again."""
    g = graphs.transit(spark, sf)
    e = normalise(parse_path("walk/(orange|red)+/walk"))
    return Engine(g).matrix(e)


_LINES = {k: f"SELECT r, c FROM ({MATRICES['succession'][t]}) AS a UNION SELECT c AS r, r AS c FROM ({MATRICES['succession'][t]}) AS b" for k, t in (("walk", "view"), ("orange", "signup"), ("red", "purchase"))}
_CITY_SQL = (
    f"WITH RECURSIVE w AS MATERIALIZED ({_LINES['walk']}), o AS MATERIALIZED ({_LINES['orange']} UNION {_LINES['red']}), t(r, c) AS (SELECT r, c FROM o UNION SELECT t.r, o.c FROM t JOIN o ON t.c = o.r) "
    "SELECT DISTINCT a.r, b.c FROM w AS a JOIN t ON a.c = t.r JOIN w AS b ON t.c = b.r"
)


def succession_edges(spark: SparkSession, sf: str) -> DataFrame:
    return graphs.succession(spark, sf).triples()


def top_out_degree(spark: SparkSession, sf: str) -> DataFrame:
    """The three nodes with most edges of each label; ties by node."""
    g = graphs.activity(spark, sf)
    degree = g.triples().groupBy("p", "s").agg(F.count("*").alias("n"))
    by = Window.partitionBy("p").orderBy(F.desc("n"), "s")
    return degree.withColumn("place", F.row_number().over(by).cast("long")).where("place <= 3").select("p", "s", "n", "place")


def _matrix_queries() -> dict[str, Query]:
    two = {
        "sum_basic": lambda a, b: m.union(a, b), "intersection_basic": lambda a, b: m.intersect(a, b), "difference_basic": lambda a, b: m.minus(a, b),
        "xor_basic": lambda a, b: m.xor(a, b), "xor_outer": lambda a, b: m.xor_outer(a, b), "sum_row": lambda a, b: m.union(a, b, row=_ROW), "sum_col": lambda a, b: m.union(a, b, col=_COL),
        "sum_cell": lambda a, b: m.union(a, b, _ROW, _COL), "intersection_row": lambda a, b: m.intersect(a, b, row=_ROW), "difference_col": lambda a, b: m.minus(a, b, col=_COL),
        "xor_row": lambda a, b: m.xor(a, b, row=_ROW), "product_basic": lambda a, b: m.product(a, b), "product_rowwise": lambda a, b: m.product(a, b, method="rowwise", heavy=150),
        "product_salted": lambda a, b: m.product(a, b, method="salted", heavy=10), "product_row": lambda a, b: m.product(a, b, row=_ROW), "product_col": lambda a, b: m.product(a, b, col=_COL),
        "product_cell": lambda a, b: m.product(a, b, _ROW, _COL), "product_counts": lambda a, b: m.product_counts(a, b), "transpose_basic": lambda a, b: m.transpose(a),
        "power2": lambda a, b: m.power(a, 2), "power3": lambda a, b: m.power(a, 3), "triangle_edges": lambda a, b: m.triangles(a),
        "adjacency_rows": lambda a, b: m.adjacency_rows(a).select("r", F.array_join("cols", ",").alias("cols")),
    }
    return {k: _on_activity(f) for k, f in two.items()}


def _matrix_sql() -> dict[str, str]:
    a, b = f"({MATRICES['activity']['click']})", f"({MATRICES['activity']['view']})"
    head = f"WITH a AS {a}, b AS {b} "

    def where(row: bool = False, col: bool = False) -> str:
        tests = [f"r = {_ROW}"] * row + [f"c = {_COL}"] * col
        return " WHERE " + " AND ".join(tests) if tests else ""

    def op(name: str, **line: bool) -> str:
        return f"{head}SELECT r, c FROM (SELECT r, c FROM a {name} SELECT r, c FROM b) AS q{where(**line)}"

    def product(x: str = "a", y: str = "b", **line: bool) -> str:
        return f"{head}SELECT * FROM (SELECT DISTINCT x.r, y.c FROM {x} AS x JOIN {y} AS y ON x.c = y.r) AS q{where(**line)}"

    xor = "SELECT r, c FROM (SELECT r, c FROM a UNION ALL SELECT r, c FROM b) AS u GROUP BY r, c HAVING count(*) = 1"
    return {
        "sum_basic": op("UNION"), "intersection_basic": op("INTERSECT"), "difference_basic": op("EXCEPT"), "xor_basic": head + xor, "xor_outer": head + xor,
        "sum_row": op("UNION", row=True), "sum_col": op("UNION", col=True), "sum_cell": op("UNION", row=True, col=True), "intersection_row": op("INTERSECT", row=True),
        "difference_col": op("EXCEPT", col=True), "xor_row": f"{head}SELECT * FROM ({xor}) AS q{where(row=True)}",
        "product_basic": product(), "product_rowwise": product(), "product_salted": product(), "product_row": product(row=True), "product_col": product(col=True), "product_cell": product(row=True, col=True),
        "product_counts": f"{head}SELECT a.r, b.c, count(*) AS walks FROM a JOIN b ON a.c = b.r GROUP BY a.r, b.c", "transpose_basic": f"{head}SELECT c AS r, r AS c FROM a",
        "power2": product("a", "a"), "power3": f"{head}SELECT DISTINCT x.r, z.c FROM (SELECT DISTINCT x.r, y.c FROM a AS x JOIN a AS y ON x.c = y.r) AS x JOIN a AS z ON x.c = z.r",
        "triangle_edges": f"{head}SELECT DISTINCT x.r, y.c FROM a AS x JOIN a AS y ON x.c = y.r JOIN a AS z ON z.r = y.c AND z.c = x.r",
        "adjacency_rows": f"{head}SELECT r, string_agg(CAST(c AS VARCHAR), ',' ORDER BY c) AS cols FROM a GROUP BY r",
    }


def within2(spark: SparkSession, sf: str) -> DataFrame:
    g = graphs.activity(spark, sf)
    return m.within(g.matrix("click"), 2, g.nodes())


def closure_inverse(spark: SparkSession, sf: str) -> DataFrame:
    return m.transpose(cl.closure(graphs.succession(spark, sf).matrix("click")))


def fused_cell(spark: SparkSession, sf: str) -> DataFrame:
    """Closure beside a factor, both ends fixed: the least signup and the least purchase after it."""
    g, base = _clicks_views(spark, sf)
    seed = g.matrix("signup")
    row = seed.agg(F.min("r")).first()[0]
    found = cl.closure_apply(base, seed.where(F.col("r") == row), "left", True)
    col = found.agg(F.max("c")).first()[0]
    return m.restrict(found, row, col)


def queries() -> dict[str, Query]:
    from pathalgebra import relational, streaming_queries, surface

    out: dict[str, Query] = {k: path_query(k) for k in PATHS}
    out |= {"rpq_star_const": star_const, "star_small": star_small, "within2": within2, "closure_inverse": closure_inverse, "fused_cell": fused_cell}
    out |= {f"automaton_{k}": path_query(f"rpq_{k}", engine="automaton") for k in ("mid_plus", "chain_cv", "mid_star", "web_cluster")}
    out |= {f"joins_{k}": path_query(f"rpq_{k}", engine="joins") for k in ("mid_plus", "chain_cv", "turns")}
    out |= {f"naive_{k}": path_query(f"rpq_{k}", plan="naive") for k in ("mid_star", "chain_vc")}
    out |= _matrix_queries()
    out |= {f"closure_{k}": _closure(k) for k in ("squaring", "linear", "components", "leaf")}
    out |= {"closure_bisect": _closure("bisect", leaf_ones=1500), "closure_bisect_alt": _closure("bisect", leaf_ones=1500, variant="right")}
    out |= {f"reach_{k}": _reach(k) for k in ("from", "from_reflexive", "to", "to_reflexive", "cell_true", "cell_false", "within_k")}
    out |= {"plus_then_const": _seeded("purchase", "right", False), "star_then_const": _seeded("purchase", "right", True), "const_then_plus": _seeded("signup", "left", False), "const_then_star": _seeded("signup", "left", True)}
    out |= {"components": components_query, "components_distributed": components_distributed, "condensation": condensation, "component_expand": component_expand, "closure_saturation": closure_saturation}
    out |= {"zorder_codes": zorder_codes, "alternation_small": alternation_small, "density_by_label": density_by_label, "grid_ones": grid_ones, "encode_nodes": encode_nodes}
    out |= {"quadtree_roundtrip": _on_tiles(lambda a, b: a), "tile_product": _on_tiles(tiles.tile_product), "tile_transpose": _on_tiles(lambda a, b: tiles.tile_transpose(a))}
    out |= {f"tile_{k}": _on_tiles(lambda a, b, op=op: tiles.tile_sum(a, b, op)) for k, op in (("sum", "or"), ("intersection", "and"), ("difference", "diff"), ("xor", "xor"))}
    out |= {"city_example": city_query, "latency_split": latency_split, "pattern_with_path": pattern_with_path, "succession_edges": succession_edges, "top_out_degree": top_out_degree}
    out |= {f"quad_{k}": path_query(f"rpq_{k}", engine="tiles", tile_bits=bits) for k, bits in (("saturating_plus", 7), ("same_nation", 10), ("turns", 10), ("chain_cv", 10), ("mid_star", 10), ("mid_optional", 10), ("nested_star", 10))}
    line = {"row": 3}, {"col": 5}, {"row": 3, "col": 5}
    for name, bound in zip(("row", "col", "cell"), line, strict=True):
        out |= {f"quad_product_{name}": _on_tiles(lambda a, b, bound=bound: tiles.tile_product(a, b, tile_bits=5, **bound)), f"quad_sum_{name}": _on_tiles(lambda a, b, bound=bound: tiles.tile_sum(a, b, tile_bits=5, **bound))}
        out |= {f"quad_difference_{name}": _on_tiles(lambda a, b, bound=bound: tiles.tile_sum(a, b, "diff", tile_bits=5, **bound))}
    out |= {"quad_flipped_sum": _on_tiles(lambda a, b: tiles.tile_sum(tiles.tile_transpose(a), b)), "quad_flipped_product": _on_tiles(lambda a, b: tiles.tile_product(tiles.tile_transpose(a), tiles.tile_transpose(b)))}
    out["quad_closure"] = quad_closure
    out |= {f"dual_{k}": _on_dual(f"rpq_{k}") for k in ("concat_vv", "chain_vc", "chain_vv")}
    out |= {"closure_bisect_parallel": _closure("bisect", leaf_ones=1500, parallel_levels=1), "reach_from_distributed": reach_from_distributed, "reach_cell_distributed": reach_cell_distributed}
    out |= {"const_then_star_distributed": _seeded("signup", "left", True, leaf_ones=0), "plus_then_const_distributed": _seeded("purchase", "right", False, leaf_ones=0)}
    out |= {"sum_by_size": lambda spark, sf: answer(graphs.activity(spark, sf), "?x click|view|error|purchase ?y", sums="by_size")}
    return out | relational.queries() | surface.queries() | streaming_queries.queries()


def oracle_sql() -> dict[str, str]:
    from pathalgebra import relational, streaming_queries, surface

    out = {k: query_sql(*v) for k, v in PATHS.items()}
    out |= {"rpq_star_const": _star_const_sql(), "star_small": f"SELECT r AS x, c AS y FROM ({matrix_sql('geography', '(in_region/^in_region)*')}) AS q"}
    out |= {"within2": f"SELECT r, c FROM ({matrix_sql('activity', 'click?/click?')}) AS q", "closure_inverse": f"SELECT r, c FROM ({matrix_sql('succession', '(^click)+')}) AS q"}
    out |= {f"automaton_{k}": out[f"rpq_{k}"] for k in ("mid_plus", "chain_cv", "mid_star", "web_cluster")}
    out |= {f"joins_{k}": out[f"rpq_{k}"] for k in ("mid_plus", "chain_cv", "turns")}
    out |= {f"naive_{k}": out[f"rpq_{k}"] for k in ("mid_star", "chain_vc")}
    out |= _matrix_sql()
    plus = f"SELECT r, c FROM ({matrix_sql('succession', '(click|view)+')}) AS q"
    out |= {f"closure_{k}": plus for k in ("squaring", "linear", "components", "leaf", "bisect", "bisect_alt")}
    out |= _reach_sql()
    out |= {"plus_then_const": _seeded_sql("purchase", "right", False), "star_then_const": _seeded_sql("purchase", "right", True), "const_then_plus": _seeded_sql("signup", "left", False), "const_then_star": _seeded_sql("signup", "left", True)}
    first = _seeded_sql("signup", "left", True)
    out["fused_cell"] = f"SELECT r, c FROM ({first}) AS q WHERE c = (SELECT max(c) FROM ({first}) AS w)"
    mutual = "WITH RECURSIVE e AS MATERIALIZED ({e}), t(r, c) AS (SELECT r, c FROM e UNION SELECT t.r, e.c FROM t JOIN e ON t.c = e.r), v AS (SELECT r AS id FROM e UNION SELECT c FROM e), k AS (SELECT v.id, least(v.id, coalesce(min(x.c), v.id)) AS comp FROM v LEFT JOIN (SELECT a.r, a.c FROM t AS a JOIN t AS b ON a.r = b.c AND a.c = b.r) AS x ON x.r = v.id GROUP BY v.id) "
    out["components"] = out["components_distributed"] = mutual.format(e=MATRICES["corpus"]["copy_of"]) + "SELECT id, comp FROM k"
    out["condensation"] = mutual.format(e=matrix_sql("activity", "click|view")) + "SELECT DISTINCT x.comp AS r, y.comp AS c FROM e JOIN k AS x ON e.r = x.id JOIN k AS y ON e.c = y.id WHERE x.comp <> y.comp"
    out["component_expand"] = f"SELECT r, c FROM ({matrix_sql('weblinks', '(links_to/^links_to)+')}) AS q"
    out["closure_saturation"] = " UNION ALL ".join(f"SELECT '{t}' AS p, count(*) AS ones FROM ({matrix_sql('activity', t + '+')}) AS q" for t in ("click", "error", "view"))
    a, b = _numbered_sql("click"), _numbered_sql("view")
    out |= {"zorder_codes": _zorder_sql(), "alternation_small": _alternation_sql(), "quadtree_roundtrip": a, "tile_transpose": f"SELECT c AS r, r AS c FROM ({a}) AS q"}
    out |= {f"tile_{k}": f"SELECT r, c FROM ({a}) AS x {op} SELECT r, c FROM ({b}) AS y" for k, op in (("sum", "UNION"), ("intersection", "INTERSECT"), ("difference", "EXCEPT"))}
    out["tile_xor"] = f"SELECT r, c FROM (SELECT r, c FROM ({a}) AS x UNION ALL SELECT r, c FROM ({b}) AS y) AS u GROUP BY r, c HAVING count(*) = 1"
    out["tile_product"] = f"SELECT DISTINCT x.r, y.c FROM ({a}) AS x JOIN ({b}) AS y ON x.c = y.r"
    every = " UNION ALL ".join(f"SELECT '{t}' AS p, r, c FROM ({q}) AS m" for t, q in MATRICES["activity"].items())
    out["density_by_label"] = f"WITH e AS ({every}), v AS (SELECT count(*) AS n FROM (SELECT r FROM e UNION SELECT c FROM e) AS u) SELECT p, count(*) AS ones, count(DISTINCT r) AS subjects, count(DISTINCT c) AS objects, CAST(1000000 * count(*) // (max(v.n) * max(v.n)) AS BIGINT) AS ppm FROM e, v GROUP BY p"
    out["grid_ones"] = " UNION ALL ".join(f"({_GRID.format(t=t)})" for t in (1, 10, 100))
    out["encode_nodes"] = "SELECT term, row_number() OVER (ORDER BY term) - 1 AS id FROM (SELECT DISTINCT p_type AS term FROM part WHERE p_type IS NOT NULL) AS t"
    out["city_example"], out["pattern_with_path"] = _CITY_SQL, _pattern_sql()
    out["latency_split"] = (
        "SELECT coalesce(o_orderstatus, 'all') AS engine, coalesce(CAST(has_const AS VARCHAR), 'all') AS part, count(*) AS n, CAST(sum(v) AS BIGINT) AS total, CAST(round(quantile_cont(v, 0.5)) AS BIGINT) AS median_v "
        "FROM (SELECT o_orderstatus, o_custkey % 20 <> 0 AS has_const, CAST(round(o_totalprice) AS BIGINT) AS v FROM orders) AS o GROUP BY ROLLUP (o_orderstatus, has_const)"
    )
    out["succession_edges"] = " UNION ALL ".join(f"SELECT r AS s, '{t}' AS p, c AS o FROM ({q}) AS m" for t, q in MATRICES["succession"].items())
    out["top_out_degree"] = f"SELECT p, s, n, place FROM (SELECT *, row_number() OVER (PARTITION BY p ORDER BY n DESC, s) AS place FROM (SELECT p, r AS s, count(*) AS n FROM ({every}) AS e GROUP BY p, r) AS d) AS k WHERE place <= 3"
    out |= {f"quad_{k}": out[f"rpq_{k}"] for k in ("saturating_plus", "same_nation", "turns", "chain_cv", "mid_star", "mid_optional", "nested_star")}
    for name, where in (("row", "r = 3"), ("col", "c = 5"), ("cell", "r = 3 AND c = 5")):
        out |= {f"quad_product_{name}": f"SELECT * FROM ({out['tile_product']}) AS q WHERE {where}", f"quad_sum_{name}": f"SELECT * FROM ({out['tile_sum']}) AS q WHERE {where}"}
        out[f"quad_difference_{name}"] = f"SELECT * FROM ({out['tile_difference']}) AS q WHERE {where}"
    out |= {"quad_flipped_sum": f"SELECT c AS r, r AS c FROM ({a}) AS x UNION SELECT r, c FROM ({b}) AS y", "quad_flipped_product": f"SELECT DISTINCT x.c AS r, y.r AS c FROM ({a}) AS x JOIN ({b}) AS y ON x.r = y.c"}
    out |= {"quad_closure": f"WITH RECURSIVE e AS MATERIALIZED ({a}), t(r, c) AS (SELECT r, c FROM e UNION SELECT t.r, e.c FROM t JOIN e ON t.c = e.r) SELECT r, c FROM t"}
    out |= {f"dual_{k}": out[f"rpq_{k}"] for k in ("concat_vv", "chain_vc", "chain_vv")}
    base = matrix_sql("succession", "click|view")
    far = f"WITH RECURSIVE b AS MATERIALIZED ({base}), t(r, c) AS (SELECT r, c FROM b WHERE r = (SELECT min(r) FROM b) UNION SELECT t.r, b.c FROM t JOIN b ON t.c = b.r) "
    out |= {"closure_bisect_parallel": plus, "reach_from_distributed": far + "SELECT r, c FROM t", "reach_cell_distributed": far + "SELECT r, c FROM t WHERE c = (SELECT max(c) FROM b WHERE r = (SELECT min(r) FROM b))"}
    out |= {"const_then_star_distributed": out["const_then_star"], "plus_then_const_distributed": out["plus_then_const"], "sum_by_size": query_sql("activity", "?x click|view|error|purchase ?y")}
    return out | relational.oracle_sql() | surface.oracle_sql() | streaming_queries.oracle_sql()


__all__ = ["PATHS", "Label", "oracle_sql", "queries"]
