"""DuckDB SQL of the graphs and searches that queries are compared with."""

from __future__ import annotations

from .sources.synth import QUADRANTS

_C = "CAST(round({} * 100) AS BIGINT)"
_PAIR = "SELECT least({l} * 2, {r} * 2 + 1) AS a, greatest({l} * 2, {r} * 2 + 1) AS b, min({w}) AS w FROM {t} GROUP BY 1, 2"
_OL = "lineitem JOIN orders ON l_orderkey = o_orderkey"
_ID = "CAST('0x' || substr(md5({}), 1, 15) AS BIGINT)"
_CANON = "SELECT least(a, b) AS a, greatest(a, b) AS b, min(w) AS w FROM ({}) WHERE a <> b GROUP BY 1, 2"
_WORDS = "SELECT {k} * 2 AS a, " + _ID.format("word") + " * 2 + 1 AS b, CAST(floor(1000000 / count(*)) AS BIGINT) AS w FROM (SELECT {k}, unnest(regexp_extract_all(lower(text), '\\p{{L}}+')) AS word FROM {t}) GROUP BY {k}, word"
_HOST = "'host ' || regexp_extract(url, '^[a-z]+://([^/]+)', 1)"
_S = "CAST(floor(epoch(ts)) AS BIGINT)"

EDGES = {
    "part_supplier_price": _PAIR.format(l="l_partkey", r="l_suppkey", w=_C.format("l_extendedprice"), t="lineitem"),
    "part_supplier_qty": _PAIR.format(l="l_partkey", r="l_suppkey", w="CAST(l_quantity AS BIGINT)", t="lineitem"),
    "customer_part": _PAIR.format(l="o_custkey", r="l_partkey", w=_C.format("l_extendedprice"), t=_OL),
    "customer_supplier": _PAIR.format(l="o_custkey", r="l_suppkey", w=_C.format("l_extendedprice"), t=_OL),
    "user_action": _PAIR.format(l="user_id", r="(list_position(['click', 'error', 'purchase', 'signup', 'view'], event_type) - 1)", w=_C.format("value"), t="events"),
    "geo_tree": "SELECT n_regionkey * 4 AS a, n_nationkey * 4 + 1 AS b, 1 AS w FROM nation UNION ALL SELECT c_nationkey * 4 + 1, c_custkey * 4 + 2, 1 FROM customer UNION ALL SELECT s_nationkey * 4 + 1, s_suppkey * 4 + 3, 1 FROM supplier",
    "event_chain": _CANON.format(
        f"SELECT x.event_id AS a, y.event_id AS b, abs(y.s - x.s) AS w FROM (SELECT event_id, {_S} AS s FROM events) x JOIN (SELECT event_id, {_S} AS s FROM events) y ON y.event_id = x.event_id + 1"
        f" UNION ALL SELECT * FROM (SELECT event_id, lead(event_id) OVER u AS b, lead({_S}) OVER u - {_S} AS w FROM events WINDOW u AS (PARTITION BY user_id ORDER BY {_S}, event_id)) WHERE b IS NOT NULL"
    ),
    "page_link": _CANON.format("SELECT " + _ID.format("url") + " AS a, " + _ID.format("target") + " AS b, CAST(1 AS BIGINT) AS w FROM (SELECT url, unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) AS target FROM pages)"),
    "host_page": _CANON.format("SELECT " + _ID.format(_HOST) + " AS a, " + _ID.format("url") + " AS b, CAST(1 AS BIGINT) AS w FROM pages"),
    "doc_word": _CANON.format(_WORDS.format(k="doc_id", t="documents")),
    "turn_word": _CANON.format(_WORDS.format(k="conv_id", t="conversations")),
    "knn_vectors": _CANON.format(
        "SELECT a, b, w FROM (SELECT x.vec_id AS a, y.vec_id AS b, CAST(round(list_distance(x.e, y.e) * 1000000) AS BIGINT) AS w, row_number() OVER (PARTITION BY x.vec_id ORDER BY CAST(round(list_distance(x.e, y.e) * 1000000) AS BIGINT), y.vec_id) AS r"
        " FROM (SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS e FROM embeddings) x JOIN (SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS e FROM embeddings) y ON x.label = y.label AND x.vec_id <> y.vec_id) WHERE r <= 8"
    ),
}


def unit(*parts: str) -> str:
    """The number in [0, 1) that ``synth.unit_hash`` draws."""
    return f"(CAST('0x' || substr(md5(concat_ws(',', {', '.join(parts)})), 1, 10) AS BIGINT) / 1099511627776.0)"


def _weighted(pairs: str, seed: int) -> str:
    w = unit("'w'", str(seed), "a", "b")
    return f"SELECT a, b, CAST(1 - {w} AS DOUBLE) AS w FROM (SELECT DISTINCT least(a, b) AS a, greatest(a, b) AS b FROM ({pairs}) WHERE a <> b)"


def kron(scale: int, factor: int, seed: int = 1, ids: str | None = None) -> str:
    p, q, r, _ = QUADRANTS
    u = unit(str(seed), "bit", "id")
    right = f"CASE WHEN (u >= {p!r} AND u < {p + q!r}) OR u >= {p + q + r!r} THEN 1 ELSE 0 END"
    side = lambda bit: f"CAST(sum(({bit}) * (1 << ({scale - 1} - bit))) AS BIGINT)"
    down = side(f"CASE WHEN u >= {p + q!r} THEN 1 ELSE 0 END")
    return _weighted(f"SELECT {down} AS a, {side(right)} AS b FROM (SELECT id, CAST(bit AS INTEGER) AS bit, CAST({u} AS DOUBLE) AS u FROM {ids or f'range({factor << scale})'} t(id), range({scale}) s(bit)) GROUP BY id", seed)


def unif(scale: int, factor: int, seed: int = 1, ids: str | None = None) -> str:
    end = lambda salt: f"CAST(floor({unit(repr(salt), str(seed), 'id')} * {1 << scale}) AS BIGINT)"
    return _weighted(f"SELECT {end('a')} AS a, {end('b')} AS b FROM {ids or f'range({factor << scale})'} t(id)", seed)


def lattice(rows: int, columns: int, brick: bool = False, seed: int = 1) -> str:
    down = f"id // {columns} < {rows - 1}" + (f" AND (id // {columns} + id % {columns}) % 2 = 0" if brick else "")
    return _weighted(f"SELECT id AS a, id + 1 AS b FROM range({rows * columns}) t(id) WHERE id % {columns} < {columns - 1} UNION ALL SELECT id, id + {columns} FROM range({rows * columns}) t(id) WHERE {down}", seed)


SYNTHETIC = {
    "kron_10_4": kron(10, 4), "kron_10_8": kron(10, 8), "kron_10_16": kron(10, 16), "kron_10_32": kron(10, 32), "unif_10_16": unif(10, 16),
    "lattice_30_30": lattice(30, 30), "brick_wall_30_30": lattice(30, 30, True),
    "star_200": _weighted("SELECT CAST(0 AS BIGINT) AS a, id AS b FROM range(1, 201) t(id)", 1), "path_300": _weighted("SELECT id AS a, id + 1 AS b FROM range(300) t(id)", 1),
}



def _draws(each: int) -> str:
    return f"(SELECT CAST(c_custkey * {each} + i AS BIGINT) FROM customer, range({each}) r(i))"


def table_lattice(columns: int, brick: bool = False) -> str:
    step = "SELECT CAST(x.p_partkey AS BIGINT) AS a, CAST(y.p_partkey AS BIGINT) AS b FROM part x JOIN part y ON y.p_partkey = x.p_partkey + {}"
    down = step.format(columns) + (f" WHERE (x.p_partkey // {columns} + x.p_partkey % {columns}) % 2 = 0" if brick else "")
    return _weighted(f"{step.format(1)} WHERE x.p_partkey % {columns} < {columns - 1} UNION ALL {down}", 1)


# The same families over the keys of given tables.
TABLED = {
    **{f"kron_10_{k}": kron(10, k, ids=_draws(k)) for k in (4, 8, 16, 32)}, "unif_10_16": unif(10, 16, ids=_draws(16)),
    "lattice_30_30": table_lattice(30), "brick_wall_30_30": table_lattice(30, True),
    "star_200": _weighted("SELECT CAST(0 AS BIGINT) AS a, CAST(c_custkey AS BIGINT) AS b FROM customer", 1),
    "path_300": _weighted("SELECT CAST(x.event_id AS BIGINT) AS a, CAST(y.event_id AS BIGINT) AS b FROM events x JOIN events y ON y.event_id = x.event_id + 1", 1),
}

# The vertex of the largest degree, the least of them.
HUB = "(SELECT src FROM arc GROUP BY src ORDER BY count(*) DESC, src LIMIT 1)"
# The vertex of the least degree, the last of them.
EDGE = "(SELECT src FROM arc GROUP BY src ORDER BY count(*), src DESC LIMIT 1)"


def search(edges: str, source, tail: str = "SELECT CAST(v AS BIGINT) AS v, d AS dist FROM t", kind: str = "BIGINT", more: str = "") -> str:
    """Distances by a recursion that keeps one row a vertex and improves it; ``more``: further common tables."""
    return f"""WITH RECURSIVE e AS MATERIALIZED ({edges}),
arc AS MATERIALIZED (SELECT a AS src, b AS dst, w FROM e UNION ALL SELECT b, a, w FROM e),
t(v, d) USING KEY (v) AS (SELECT CAST({source} AS BIGINT), CAST(0 AS {kind}) UNION
  SELECT n.v, n.d FROM (SELECT CAST(arc.dst AS BIGINT) AS v, CAST(min(t.d + arc.w) AS {kind}) AS d FROM t JOIN arc ON arc.src = t.v GROUP BY arc.dst) n
  LEFT JOIN recurring.t r ON r.v = n.v WHERE r.d IS NULL OR n.d < r.d){more}
{tail}"""
