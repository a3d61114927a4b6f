"""DuckDB SQL for the registered queries, made of common table expressions.

The SQL pads explicitly, joins long code tables and buckets directly; the Spark
side uses staircases, Arrow signatures and prefix tables.  Only constants are
shared.
"""

from __future__ import annotations

from overlapix.functions import hashing as H

P = H.P


def fp(x: str) -> str:
    return f"(CAST('0x' || substr(md5({x}), 1, 15) AS BIGINT) % {P})"


WORDS = r"list_filter(string_split_regex(lower(coalesce({}, '')), '[^\p{{L}}\p{{N}}]+'), lambda w: w <> '')"


def _words(table: str, key: str, column: str = "text") -> str:
    return f"SELECT {key} AS id, {fp('tok')} AS e FROM (SELECT {key}, unnest({WORDS.format(column)}) AS tok FROM {table})"


def _shingles(table: str, key: str, k: int, column: str = "text") -> str:
    return f"SELECT id, {fp('tok')} AS e FROM (SELECT id, unnest(list_transform(range(1, len(w) - {k - 2}), lambda i: array_to_string(list_slice(w, i, i + {k - 1}), ' '))) AS tok FROM (SELECT {key} AS id, {WORDS.format(column)} AS w FROM {table}) WHERE len(w) >= {k})"


BOUGHT = "SELECT o_custkey AS id, l_partkey AS part, l_quantity AS w FROM lineitem JOIN orders ON l_orderkey = o_orderkey"
INCIDENCE = {
    "docs_w": _words("documents", "doc_id"),
    "docs_s3": _shingles("documents", "doc_id", 3),
    "pages_w": _words("(SELECT page_id, regexp_replace(html, '<[^>]*>', ' ', 'g') AS text FROM pages)", "page_id"),
    "conv_w": _words("conversations", "conv_id"),
    "turn_w": _words("(SELECT conv_id * 1000 + turn AS tid, text FROM conversations)", "tid"),
    "cust_parts": f"SELECT id, {fp('CAST(part AS VARCHAR)')} AS e FROM ({BOUGHT})",
    "order_parts": f"SELECT l_orderkey AS id, {fp('CAST(l_partkey AS VARCHAR)')} AS e FROM lineitem",
    "part_supps": f"SELECT l_partkey AS id, {fp('CAST(l_suppkey AS VARCHAR)')} AS e FROM lineitem",
    "user_hours": f"SELECT user_id AS id, {fp(chr(39).join(['strftime(ts, ', '%Y-%m-%d %H', ')']))} AS e FROM events",
    "emb_bin": f"SELECT vec_id AS id, {fp('CAST(i AS VARCHAR)')} AS e FROM (SELECT vec_id, unnest(range(len(embedding))) AS i, unnest(embedding) AS v FROM embeddings) WHERE v > 0",
    "bench_w": _words("benchmark", "item_id"),
    "bench_s3": _shingles("benchmark", "item_id", 3),
}
BIG = "BIGINT"


def query(ctes: list[str], select: str) -> str:
    return "WITH " + ",\n".join(ctes) + "\n" + select


def base(coll: str, pre: str = "") -> list[str]:
    return [f"{pre}inc AS MATERIALIZED (SELECT DISTINCT id, e FROM ({INCIDENCE[coll]}))", f"{pre}sets AS MATERIALIZED (SELECT id, count(*) AS f FROM {pre}inc GROUP BY id)"]


def is_query(key: str = "id") -> str:
    return f"{fp(chr(39) + 'q:' + chr(39) + ' || CAST(' + key + ' AS VARCHAR)')} % 10 = 0"


def split(coll: str) -> list[str]:
    """inc, sets; qsets, xsets, qinc, xinc of the hash split."""
    return [*base(coll), f"qsets AS MATERIALIZED (SELECT * FROM sets WHERE {is_query()})", f"xsets AS MATERIALIZED (SELECT * FROM sets WHERE NOT ({is_query()}))", "qinc AS (SELECT * FROM inc SEMI JOIN qsets USING (id))", "xinc AS (SELECT * FROM inc SEMI JOIN xsets USING (id))"]


def pair(xcoll: str, qcoll: str) -> list[str]:
    """The same names for two collections."""
    return base(xcoll, "x") + base(qcoll, "q")


OV = "ov AS MATERIALIZED (SELECT q.id AS q_id, x.id AS x_id, count(*) AS a, any_value(qs.f) AS fq, any_value(xs.f) AS fx FROM qinc q JOIN xinc x USING (e) JOIN qsets qs ON qs.id = q.id JOIN xsets xs ON xs.id = x.id GROUP BY q.id, x.id)"
TIE = f"{fp('CAST(x_id AS VARCHAR)')}, x_id"


def top(source: str, score: str, t: int, extra: str = "") -> str:
    return f"SELECT q_id, CAST(rn AS BIGINT) AS rank, x_id, CAST(a AS BIGINT) AS a FROM (SELECT *, row_number() OVER (PARTITION BY q_id ORDER BY {score} DESC, {TIE}) AS rn FROM {source} {extra}) WHERE rn <= {t}"


def draws(h: int, seed: int, name: str = "hp") -> str:
    rows = ", ".join(f"({t},{a},{b},{c},{d},{g},{u!r}::DOUBLE)" for t, (a, b, c, d, g, u) in enumerate(H.draws(h, seed)))
    return f"{name}(t,a1,b1,c1,d1,g1,u1) AS (VALUES {rows})"


def hashed(source: str, family: str = "poly", hp: str = "hp") -> str:
    """Rows of ``source`` (with column e) for each hash, with value ``h``."""
    if family == "affine":
        return f"(SELECT *, (a1 * e + b1) % {P} AS h FROM {source} CROSS JOIN {hp})"
    return f"(SELECT *, (g1 * (y3 * y3 % {P}) + (c1 * e) % {P}) % {P} AS h FROM (SELECT *, (c1 * y2 + d1 + e) % {P} AS y3 FROM (SELECT *, (y1 * y1) % {P} AS y2 FROM (SELECT *, (a1 * e + b1) % {P} AS y1 FROM {source} CROSS JOIN {hp}))))"


def raw(source: str, family: str = "poly") -> str:
    return f"SELECT id, t, min(h) AS code FROM {hashed(source, family)} GROUP BY id, t"


def bound(qs: str = "qsets", xs: str = "xsets") -> str:
    return f"mm AS MATERIALIZED (SELECT max(f) AS m FROM (SELECT f FROM {xs} UNION ALL SELECT f FROM {qs}))"


def pads(block: str, name: str, family: str = "poly") -> str:
    own = f"(SELECT i, {fp(repr(block) + ' || CAST(i AS VARCHAR)')} AS e FROM (SELECT unnest(range(m)) AS i FROM mm))"
    return f"{name} AS MATERIALIZED (SELECT t, i + 1 AS n, min(h) OVER (PARTITION BY t ORDER BY i) AS low FROM {hashed(own, family)})"


CELLS = "cells AS MATERIALIZED (SELECT [" + ",".join(map(str, H.gaussian_cells())) + "] AS g)"
W = f"(g[h % {H.CELLS} + 1])"


def sums(source: str) -> str:
    """Integer projections ``id, t, s``."""
    return f"SELECT id, t, CAST(sum({W}) AS BIGINT) AS s FROM {hashed(source)}, cells GROUP BY id, t"


def aux(n: int, name: str = "aux") -> str:
    own = "(SELECT * FROM (VALUES " + ", ".join(f"({j}, {fp(repr(H.AUX + str(j)))})" for j in range(n)) + ") AS v(j, e))"
    cols = ", ".join(f"max(CASE WHEN j = {j} THEN {W}::DOUBLE / {H.UNIT} END) AS w{j}" for j in range(n))
    return f"{name} AS MATERIALIZED (SELECT t, {cols} FROM {hashed(own)}, cells GROUP BY t)"


def codes(kind: str, side: str, params: dict) -> tuple[list[str], str]:
    """Further expressions and the SELECT of ``id, t, code`` (and ``from_pad``) for one side."""
    inc, sets = ("xinc", "xsets") if side == "data" else ("qinc", "qsets")
    block = {("opm1", "data"): "padA", ("opm2", "data"): "padA", ("opm2", "query"): "padB"}.get((kind, side))
    if kind in ("minhash", "opm1", "opm2"):
        if block is None:
            return [], f"SELECT *, false AS from_pad FROM ({raw(inc)})"
        return [], f"SELECT r.id, r.t, least(r.code, coalesce(p.low, 9223372036854775807)) AS code, coalesce(p.low < r.code, false) AS from_pad FROM ({raw(inc)}) r JOIN {sets} s USING (id) CROSS JOIN mm LEFT JOIN {block} p ON p.t = r.t AND p.n = m - s.f"
    proj = f"({sums(inc)})"
    if kind == "srp":
        return [], f"SELECT id, t, CAST(s >= 0 AS BIGINT) AS code FROM {proj}"
    if kind == "srp2":
        w = f"{params['width']}::DOUBLE * sqrt(f)"
        return [], f"SELECT p.id, t, CAST(s::DOUBLE / {H.UNIT} >= -({w}) AS BIGINT) + CAST(s >= 0 AS BIGINT) + CAST(s::DOUBLE / {H.UNIT} >= {w} AS BIGINT) AS code FROM {proj} p JOIN {sets} USING (id)"
    if kind == "l2lsh":
        r = f"{params['r']}::DOUBLE"
        return [], f"SELECT id, p.t, CAST(floor((s::DOUBLE / {H.UNIT} + u1 * {r}) / {r}) AS BIGINT) AS code FROM {proj} p JOIN hp USING (t)"
    if kind == "normsign":
        mine = "w0" if side == "data" else "w1"
        return [], f"SELECT p.id, p.t, CAST(s::DOUBLE / {H.UNIT} / sqrt(m) + sqrt(greatest(0.0::DOUBLE, 1 - f / (sqrt(m) * sqrt(m)))) * {mine} >= 0 AS BIGINT) AS code FROM {proj} p JOIN {sets} USING (id) JOIN aux USING (t) CROSS JOIN mm"
    m, scale = params["m"], f"({params['u']}::DOUBLE / sqrt(m))"
    pw = [f"f * ({scale} * {scale})"]
    for _ in range(m - 1):
        pw.append(f"({pw[-1]}) * ({pw[-1]})")
    flip = kind == "signalsh"
    extra = [f"(0.5::DOUBLE - {x})" if flip else f"({x})" for x in pw]
    still = ["0.0::DOUBLE" if flip else "0.5::DOUBLE"] * m
    parts = extra + still if side == "data" else still + extra
    total = f"s::DOUBLE / {H.UNIT} * {scale}" + "".join(f" + {x} * w{j}" for j, x in enumerate(parts))
    if flip:
        return [], f"SELECT p.id, p.t, CAST({total} >= 0 AS BIGINT) AS code FROM {proj} p JOIN {sets} USING (id) JOIN aux USING (t) CROSS JOIN mm"
    r = f"{params['r']}::DOUBLE"
    return [], f"SELECT p.id, p.t, CAST(floor(({total} + u1 * {r}) / {r}) AS BIGINT) AS code FROM {proj} p JOIN {sets} USING (id) JOIN aux USING (t) JOIN hp USING (t) CROSS JOIN mm"


def coded(kind: str, params: dict, h: int, seed: int, x: str = "xcode", q: str = "qcode") -> list[str]:
    """Code tables of both sides; wants xinc, xsets, qinc, qsets before it."""
    out = [draws(h, seed), bound()]
    if kind in ("opm1", "opm2"):
        out.append(pads(H.PAD_A, "padA"))
    if kind == "opm2":
        out.append(pads(H.PAD_B, "padB"))
    if kind not in ("minhash", "opm1", "opm2"):
        out.append(CELLS)
    if kind in ("l2alsh", "signalsh"):
        out.append(aux(2 * params["m"]))
    if kind == "normsign":
        out.append(aux(2))
    return [*out, f"{x} AS MATERIALIZED ({codes(kind, 'data', params)[1]})", f"{q} AS MATERIALIZED ({codes(kind, 'query', params)[1]})"]


def matches(k: int) -> str:
    """``q_id, x_id, matches`` over all pairs, zero included."""
    return f"SELECT qs.id AS q_id, xs.id AS x_id, coalesce(n, 0) AS matches FROM qsets qs CROSS JOIN xsets xs LEFT JOIN (SELECT q.id AS q_id, x.id AS x_id, count(*) AS n FROM qcode q JOIN xcode x ON q.t = x.t AND q.code = x.code WHERE q.t < {k} GROUP BY q.id, x.id) ON q_id = qs.id AND x_id = xs.id"


def buckets(k: int, l: int, code: str, live: bool) -> str:  # noqa: E741
    dead = "AND NOT bool_or(from_pad)" if live else ""
    return f"SELECT t // {k} AS j, string_agg(CAST(code AS VARCHAR), '-' ORDER BY t) AS key, id FROM {code} WHERE t < {k * l} GROUP BY id, t // {k} HAVING true {dead}"


def gold(t: int, name: str = "gold") -> str:
    return f"{name} AS MATERIALIZED ({top('ov', 'a', t)})"


def ranked(k: int) -> str:
    return f"ranked AS MATERIALIZED (SELECT *, row_number() OVER (PARTITION BY q_id ORDER BY matches DESC, {TIE}) AS p FROM ({matches(k)}))"


WALK = "walk AS MATERIALIZED (SELECT r.q_id, p, CAST(hit IS NOT NULL AS INT) AS is_gold, CAST(sum(CASE WHEN hit IS NULL THEN 0 ELSE 1 END) OVER (PARTITION BY r.q_id ORDER BY p) AS BIGINT) AS relevant_seen, n.g FROM ranked r JOIN (SELECT q_id, count(*) AS g FROM gold GROUP BY q_id) n ON n.q_id = r.q_id LEFT JOIN (SELECT q_id, x_id, 1 AS hit FROM gold) h ON h.q_id = r.q_id AND h.x_id = r.x_id)"
AP = "SELECT CAST(count(*) AS BIGINT) AS n_queries, round(avg(ap), 6) AS ap FROM (SELECT q_id, sum(relevant_seen::DOUBLE / p) / max(g) AS ap FROM walk WHERE is_gold = 1 GROUP BY q_id)"
