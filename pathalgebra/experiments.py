"""The experiments: density grids, mixed densities, a query log over engines, space and speedup.

    python -m pathalgebra.experiments grid|mixed|codec|log|space|speedup [sf_dir] [size]

``size`` is the number of matrices (grid, mixed, codec, speedup) or of constants drawn
for a path (log).

Every table is printed as JSON lines.  Times are elapsed seconds of actions whose
rows are counted by Spark and thrown away.
"""

from __future__ import annotations

import itertools
import json
import subprocess
import sys
import time
import uuid
from collections.abc import Callable, Iterator

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathalgebra.functions.measures import bytes_per_triple, latency_table, raw_pair_bytes, stored_bytes
from pathalgebra.operators import closure as cl
from pathalgebra.operators import matrix as m
from pathalgebra.operators import quadtree as qt
from pathalgebra.operators import tiles
from pathalgebra.plans.evaluate import answer, too_many_answers
from pathalgebra.plans.paths import KIND_STEP, KINDS, parse_query
from pathalgebra.runtime import checkpointed, fresh_path
from pathalgebra.sources import graphs, store
from pathalgebra.workloads import PATHS

DENSITIES = (1e-1, 1e-2, 1e-3, 1e-4)


def timed(df: Callable[[], DataFrame]) -> tuple[float, int]:
    began = time.perf_counter()
    n = df().count()
    return time.perf_counter() - began, n


def _operations(a: DataFrame, b: DataFrame) -> dict[str, Callable[[], DataFrame]]:
    return {"sum": lambda: m.union(a, b), "intersection": lambda: m.intersect(a, b), "product": lambda: m.product(a, b), "numeric": lambda: m.product_counts(a, b)}


def _mean(density: float, other: float, name: str, runs: list[tuple[float, int]], side: int) -> dict:
    n = len(runs)
    return {"operation": name, "density": density, "other": other, "seconds": round(sum(t for t, _ in runs) / n, 4), "ones": sum(k for _, k in runs) / n, "expected_product": side**3 * density * other}


def density_grid(spark: SparkSession, matrices: int = 20, side: int = 1000, disjoint: bool = False) -> Iterator[dict]:
    """Mean seconds and ones of operations on consecutive uniform matrices of equal density."""
    for d in DENSITIES:
        made = [checkpointed(graphs.uniform(spark, d, seed, side)) for seed in range(matrices)]
        pairs = list(itertools.batched(made, 2)) if disjoint else list(itertools.pairwise(made))
        for name in _operations(made[0], made[0]):
            yield _mean(d, d, name, [timed(_operations(a, b)[name]) for a, b in pairs], side)
        yield _mean(d, d, "closure", [timed(lambda a=a: cl.closure(a)) for a in made], side)


def mixed_density(spark: SparkSession, matrices: int = 20, side: int = 1000) -> Iterator[dict]:
    """Every density against one dense and one sparse matrix."""
    for fixed in (1e-1, 1e-4):
        other = checkpointed(graphs.uniform(spark, fixed, 99, side))
        for d in DENSITIES:
            made = [checkpointed(graphs.uniform(spark, d, seed, side)) for seed in range(matrices)]
            for name in ("sum", "intersection", "product"):
                yield _mean(d, fixed, name, [timed(_operations(a, other)[name]) for a in made], side)


def codec_grid(matrices: int = 20, side: int = 1000, densities: tuple[float, ...] = DENSITIES) -> Iterator[dict]:
    """Mean seconds of the quadtree codec by itself, one thread and no Spark: merges in runs, node by node and by quadrants."""
    levels = qt.levels_for(side)

    def make(density: float, seed: int) -> qt.QuadTree:
        rng = np.random.default_rng(seed)
        return qt.encode(*np.nonzero(rng.random((side, side)) < density), levels)

    binary: dict[str, Callable] = {
        "sum, runs": lambda a, b: qt.merge_sum(a, b), "sum, node by node": lambda a, b: qt.merge_sum(a, b, batch_copies=False), "sum, quadrants": lambda a, b: qt.combine("or", a, b),
        "intersection": lambda a, b: qt.combine("and", a, b), "product": lambda a, b: qt.times(a, b),
    }
    for d in densities:
        made = [make(d, seed) for seed in range(matrices)]
        pairs = list(itertools.pairwise(made))
        for name, op in binary.items():
            began, ones = time.perf_counter(), 0
            for a, b in pairs:
                ones += op(a, b).ones
            yield {"operation": name, "density": d, "seconds": round((time.perf_counter() - began) / len(pairs), 4), "ones": ones / len(pairs)}
        began = time.perf_counter()
        ones = sum(qt.closed(a).ones for a in made)
        yield {"operation": "closure", "density": d, "seconds": round((time.perf_counter() - began) / matrices, 4), "ones": ones / matrices}


def logged_queries(spark: SparkSession, sf: str, keys: list[str] | None = None, constants: int = 19) -> list[tuple[str, str, str]]:
    """(name, graph, query): every path once without a constant and ``constants`` times with one, so 95 % have one.

    Constants are starts and ends of the path in turn, taken in the order of a hash.
    Paths with more than 10^6 answers are left out, as are copies of a query.
    """
    out: dict[tuple[str, str], str] = {}
    for key in keys or [k for k, (_, text) in PATHS.items() if text.startswith("?x") and text.endswith("?y")]:
        graph, text = PATHS[key]
        g = graphs.GRAPHS[graph](spark, sf)
        pairs = checkpointed(answer(g, text))
        if too_many_answers(pairs):
            continue
        out.setdefault((graph, text), key)
        path = text[len("?x") : -len("?y")].strip()
        names = {v: k for k, v in KINDS.items()}
        for side, share in (("x", constants - constants // 2), ("y", constants // 2)):
            for r in pairs.select(side).distinct().orderBy(F.xxhash64(side), side).limit(share).collect():
                end = f"{names[r[0] // KIND_STEP]}:{r[0] % KIND_STEP}"
                out.setdefault((graph, f"{end} {path} ?y" if side == "x" else f"?x {path} {end}"), key)
    return [(f"{key}-{n}", graph, text) for n, ((graph, text), key) in enumerate(out.items())]


def query_log(
    spark: SparkSession, sf: str, keys: list[str] | None = None, budget_s: float = 60.0, engines: tuple[str, ...] = ("matrix", "joins", "automaton"), queries: list[tuple[str, str, str]] | None = None
) -> DataFrame:
    """(query, engine, has_const, seconds, timed_out) of path queries on several engines.

    ``queries``: (name, graph, text), by default the registered ones (``keys``).
    Engines are those of ``answer`` and ``dual``, the matrix engine on stored views.

    A query over the budget is cancelled through its job tag and counts as timed out.
    """
    import threading

    rows = []
    stored: dict[str, graphs.Graph] = {}

    def graph_of(name: str, engine: str) -> graphs.Graph:
        if engine != "dual":
            return graphs.GRAPHS[name](spark, sf)
        if name not in stored:
            stored[name] = store.DualGraph.write(graphs.GRAPHS[name](spark, sf))
        return stored[name]

    for key, graph, text in queries or [(k, *PATHS[k]) for k in keys or list(PATHS)]:
        q = parse_query(text)
        const = isinstance(q.source, int) or isinstance(q.target, int)
        for engine in engines:
            graph_of(graph, engine)  # views are stored once, outside of the times
            tag = f"{key}-{engine}"
            spark.addTag(tag)
            stop = threading.Timer(budget_s, lambda tag=tag: spark.interruptTag(tag))
            stop.start()
            try:
                seconds, _ = timed(lambda g=graph, t=text, e=engine: answer(graph_of(g, e), t, engine="matrix" if e == "dual" else e))
                late = seconds > budget_s
            except Exception:
                if not stop.finished.is_set():
                    raise
                seconds, late = budget_s, True
            finally:
                stop.cancel()
                spark.removeTag(tag)
            rows.append((key, engine, const, seconds, late))
    return spark.createDataFrame(rows, "query string, engine string, has_const boolean, seconds double, timed_out boolean")


def space(spark: SparkSession, sf: str, graph: str = "commerce", label: str = "contains") -> dict:
    """Bytes of an edge and seconds to build, by layout, for one label over dense numbers."""
    edges = graphs.GRAPHS[graph](spark, sf).matrix(label)
    ends = edges.selectExpr("r as id").union(edges.selectExpr("c as id"))
    names = checkpointed(graphs.dense_numbers(ends, "id"))
    left, right = names.selectExpr("term as r", "id as nr"), names.selectExpr("term as c", "id as nc")
    a = checkpointed(edges.join(left, "r").join(right, "c").selectExpr("nr as r", "nc as c"))
    n = a.count()
    out: dict = {"edges": n, "raw_pairs": raw_pair_bytes(n) / max(1, n)}
    triples = a.selectExpr("r as s", f"'{label}' as p", "c as o")
    for name, write in (("rows", lambda p: store.write_pairs(triples, p)), ("tiles", lambda p: store.write_tiles(a, p))):
        path, began = fresh_path(spark, f"space-{name}"), time.perf_counter()
        write(path)
        out[name] = {"bytes": round(bytes_per_triple(spark, path, n), 3), "seconds": round(time.perf_counter() - began, 2)}
    began, name = time.perf_counter(), f"space_{uuid.uuid4().hex}"
    store.write_dual(triples, name)
    seconds = time.perf_counter() - began
    files = [f for t in ("by_s", "by_o") for f in spark.table(f"{name}_{t}").inputFiles()]
    out["dual"] = {"bytes": round(sum(stored_bytes(spark, f) for f in files) / max(1, n), 3), "seconds": round(seconds, 2)}
    store.drop_dual(spark, name)
    return out


def speedup(matrices: int = 4, cores: tuple[int, ...] = (1, 8), densities: tuple[float, ...] = (1e-1, 1e-2, 1e-3)) -> Iterator[dict]:
    """Mean seconds of operations on tiles by the number of cores, each in a session of its own."""
    script = "import json, sys; from pathalgebra import experiments as e; [print(json.dumps(r), flush=True) for r in e.tile_times(int(sys.argv[1]), int(sys.argv[2]), float(sys.argv[3]))]"
    for d in densities:
        for n in cores:
            done = subprocess.run([sys.executable, "-c", script, str(n), str(matrices), str(d)], stdout=subprocess.PIPE, check=True, text=True)
            yield from (json.loads(line) for line in done.stdout.splitlines() if line.startswith("{"))


def tile_times(cores: int, matrices: int, density: float, side: int = 1000, tile_bits: int = 8) -> Iterator[dict]:
    spark = SparkSession.builder.master(f"local[{cores}]").config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    made = [checkpointed(tiles.to_tiles(graphs.uniform(spark, density, seed, side), tile_bits)) for seed in range(matrices)]
    pairs = list(itertools.pairwise(made))
    for name, op in (("sum", tiles.tile_sum), ("product", tiles.tile_product)):
        op(*pairs[0]).count()  # starts the workers
        yield {"operation": name, "density": density, "cores": cores, "seconds": round(sum(timed(lambda p=p, op=op: op(*p))[0] for p in pairs) / len(pairs), 3)}
    yield {"operation": "closure", "density": density, "cores": cores, "seconds": round(timed(lambda: tiles.tile_closure(made[0]))[0], 3)}


def main() -> None:
    kind, sf = sys.argv[1], (sys.argv[2:] or ["/root/testdata/sf0.01"])[0]
    size = int(sys.argv[3]) if len(sys.argv) > 3 else None
    if kind in ("codec", "speedup"):
        for row in codec_grid(size or 20) if kind == "codec" else speedup(size or 4):
            print(json.dumps(row), flush=True)
        return
    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    if kind in ("grid", "mixed"):
        for row in (density_grid if kind == "grid" else mixed_density)(spark, size or 20):
            print(json.dumps(row), flush=True)
    elif kind == "log":
        queries = logged_queries(spark, sf, constants=size or 19)
        for row in latency_table(query_log(spark, sf, engines=("matrix", "dual", "tiles", "joins", "automaton"), queries=queries)).collect():
            print(json.dumps(row.asDict()), flush=True)
    else:
        print(json.dumps(space(spark, sf)))


if __name__ == "__main__":
    main()
