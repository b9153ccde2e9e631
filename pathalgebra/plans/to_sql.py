"""Path expressions as plain SQL with recursion, for engines that deduplicate recursive unions.

Used as an independent check: it shares the parser with the matrix engine and
nothing else.
"""

from __future__ import annotations

from itertools import count

from pathalgebra.plans.paths import KIND_STEP, KINDS, Alt, Eps, Expr, Label, Neg, Opt, Plus, Seq, Star, labels_of, normalise, parse_query


def _id(kind: str, key: str) -> str:
    return f"CAST({KINDS[kind] * KIND_STEP} + {key} AS BIGINT)"


def _pairs(source: str, r: str, c: str) -> str:
    return f"SELECT DISTINCT r, c FROM (SELECT {r} AS r, {c} AS c FROM {source}) AS e WHERE r IS NOT NULL AND c IS NOT NULL"


def _steps(order: str, part: str, key: str) -> str:
    return f"lead({key}) OVER ({part} ORDER BY {order})"


_EVENTS = ("click", "error", "purchase", "signup", "view")
_DENSE = "(SELECT term, row_number() OVER (ORDER BY term) - 1 AS id FROM (SELECT DISTINCT {col} AS term FROM {table} WHERE {col} IS NOT NULL) AS t)"


def _activity(t: str) -> str:
    source = f"(SELECT event_type, user_id AS u, {_steps('ts, event_id', '', 'user_id')} AS w FROM events) AS s WHERE event_type = '{t}'"
    return _pairs(f"(SELECT * FROM {source}) AS s", _id("user", "u"), _id("user", "w"))


def _succession(t: str) -> str:
    source = f"(SELECT event_type, event_id AS u, {_steps('ts, event_id', 'PARTITION BY user_id', 'event_id')} AS w FROM events) AS s WHERE event_type = '{t}'"
    return _pairs(f"(SELECT * FROM {source}) AS s", _id("event", "u"), _id("event", "w"))


def _dialog(t: str) -> str:
    source = f"(SELECT role, conv_id * 1000 + turn AS u, {_steps('turn', 'PARTITION BY conv_id', 'conv_id * 1000 + turn')} AS w FROM conversations) AS s WHERE role = '{t}'"
    return _pairs(f"(SELECT * FROM {source}) AS s", _id("turn", "u"), _id("turn", "w"))


def _literal(table: str, kind: str, key: str, column: str) -> str:
    dense = _DENSE.format(col=column, table=table)
    return _pairs(f"{table} JOIN {dense} AS n ON {table}.{column} = n.term", _id(kind, key), _id("literal", "n.id"))


_STAR = "SELECT d.doc_id AS r, g.f AS c FROM documents AS d JOIN (SELECT text, min(doc_id) AS f FROM documents WHERE text IS NOT NULL GROUP BY text) AS g ON d.text = g.text AND d.doc_id <> g.f"
_COPIES = f"({_STAR} UNION SELECT c AS r, r AS c FROM ({_STAR}) AS s)"
_LINKS = "(SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS term FROM pages)"
_HOSTS = "(SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS term FROM pages)"
_WEB = f"(SELECT term, row_number() OVER (ORDER BY term) - 1 AS id FROM (SELECT term FROM {_LINKS} AS a UNION SELECT term FROM {_HOSTS} AS b) AS t)"

MATRICES: dict[str, dict[str, str]] = {
    "commerce": {
        "placed_by": _pairs("orders", _id("order", "o_orderkey"), _id("customer", "o_custkey")),
        "contains": _pairs("lineitem", _id("order", "l_orderkey"), _id("part", "l_partkey")),
        "shipped_from": _pairs("lineitem", _id("order", "l_orderkey"), _id("supplier", "l_suppkey")),
        "sourced_from": _pairs("lineitem", _id("part", "l_partkey"), _id("supplier", "l_suppkey")),
        "cust_in": _pairs("customer", _id("customer", "c_custkey"), _id("nation", "c_nationkey")),
        "supp_in": _pairs("supplier", _id("supplier", "s_suppkey"), _id("nation", "s_nationkey")),
        "in_region": _pairs("nation", _id("nation", "n_nationkey"), _id("region", "n_regionkey")),
        "has_brand": _literal("part", "part", "p_partkey", "p_brand"),
        "has_type": _literal("part", "part", "p_partkey", "p_type"),
    },
    "geography": {"in_region": _pairs("nation", _id("nation", "n_nationkey"), _id("region", "n_regionkey"))},
    "activity": {t: _activity(t) for t in _EVENTS},
    "succession": {t: _succession(t) for t in _EVENTS},
    "dialog": {t: _dialog(t) for t in ("assistant", "system", "user")},
    "weblinks": {
        "links_to": _pairs(f"{_LINKS} AS l JOIN {_WEB} AS n ON l.term = n.term", _id("page", "page_id"), _id("literal", "n.id")),
        "on_host": _pairs(f"{_HOSTS} AS l JOIN {_WEB} AS n ON l.term = n.term", _id("page", "page_id"), _id("literal", "n.id")),
    },
    "corpus": {
        "copy_of": _pairs(f"{_COPIES} AS a", _id("document", "a.r"), _id("document", "a.c")),
        "from_source": _literal("documents", "document", "doc_id", "source"),
        "in_lang": _literal("documents", "document", "doc_id", "lang"),
    },
}


class SqlWriter:
    def __init__(self, graph: str):
        self.graph, self.number = graph, count()

    def label(self, name: str) -> str:
        return MATRICES[self.graph].get(name, "SELECT CAST(0 AS BIGINT) AS r, CAST(0 AS BIGINT) AS c WHERE false")

    def nodes(self) -> str:
        return " UNION ".join(f"SELECT {side} AS id FROM ({sql}) AS m" for sql in MATRICES[self.graph].values() for side in "rc")

    def identity(self) -> str:
        return f"SELECT id AS r, id AS c FROM ({self.nodes()}) AS v"

    def write(self, e: Expr, row: int | None = None, col: int | None = None) -> str:
        """SELECT of distinct r, c."""
        match e:
            case Eps():
                return self.limited(self.identity(), row, col)
            case Label(name, inverse):
                return self.limited(self.turned(self.label(name), inverse), row, col)
            case Neg(names, inverse):
                rest = [x for x in MATRICES[self.graph] if x not in names]
                both = " UNION ".join(f"SELECT r, c FROM ({self.label(x)}) AS m" for x in rest)
                return self.limited(self.turned(both, inverse), row, col)
            case Alt(parts):
                return " UNION ".join(f"SELECT r, c FROM ({self.write(p, row, col)}) AS a" for p in parts)
            case Opt(inner):
                return f"SELECT r, c FROM ({self.write(Eps(), row, col)}) AS i UNION SELECT r, c FROM ({self.write(inner, row, col)}) AS a"
            case Star(inner):
                return f"SELECT r, c FROM ({self.write(Eps(), row, col)}) AS i UNION SELECT r, c FROM ({self.write(Plus(inner), row, col)}) AS a"
            case Plus(inner):
                t, base = f"t{next(self.number)}", self.write(inner)
                b = f"b{next(self.number)}"
                if row is None and col is not None:
                    step = f"SELECT {b}.r, {t}.c FROM {t} JOIN {b} ON {b}.c = {t}.r"
                else:
                    step = f"SELECT {t}.r, {b}.c FROM {t} JOIN {b} ON {t}.c = {b}.r"
                start = f"SELECT r, c FROM {b}"
                start += f" WHERE r = {row}" if row is not None else f" WHERE c = {col}" if col is not None else ""
                whole = f"WITH RECURSIVE {b} AS MATERIALIZED ({base}), {t}(r, c) AS ({start} UNION {step}) SELECT r, c FROM {t}"
                return self.limited(f"SELECT r, c FROM ({whole}) AS p", row, col)
            case Seq(parts):
                out = self.write(parts[0], row, col if len(parts) == 1 else None)
                for k, p in enumerate(parts[1:], 1):
                    right = self.write(p, None, col if k == len(parts) - 1 else None)
                    out = f"SELECT DISTINCT x.r, y.c FROM ({out}) AS x JOIN ({right}) AS y ON x.c = y.r"
                return out
        raise TypeError(e)

    @staticmethod
    def turned(sql: str, inverse: bool) -> str:
        return f"SELECT c AS r, r AS c FROM ({sql}) AS m" if inverse else sql

    @staticmethod
    def limited(sql: str, row: int | None, col: int | None) -> str:
        tests = [f"r = {row}"] * (row is not None) + [f"c = {col}"] * (col is not None)
        return f"SELECT r, c FROM ({sql}) AS m WHERE {' AND '.join(tests)}" if tests else sql


def matrix_sql(graph: str, path: str, row: int | None = None, col: int | None = None) -> str:
    from pathalgebra.plans.paths import parse_path

    return SqlWriter(graph).write(normalise(parse_path(path)), row, col)


def query_sql(graph: str, text: str) -> str:
    q = parse_query(text)
    row = q.source if isinstance(q.source, int) else None
    col = q.target if isinstance(q.target, int) else None
    same = " WHERE r = c" if isinstance(q.source, str) and q.source == q.target else ""
    return f"SELECT r AS x, c AS y FROM ({SqlWriter(graph).write(normalise(q.path), row, col)}) AS q{same}"


__all__ = ["MATRICES", "SqlWriter", "labels_of", "matrix_sql", "query_sql"]
