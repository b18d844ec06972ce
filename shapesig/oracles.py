"""The same methods as plain SQL for DuckDB, built from common table expressions.

Independent of the DataFrame code: vertices are rows, geometry is joins and sums.
"""

from __future__ import annotations

import math

from shapesig.sources.layers import ALPHABET, LETTERS, SIZED, TEXTS

MOST = 1 << 16  # attempts that the SQL draws; the searches draw until a point hits
QUERY_STEP = 50  # a search's queries: every shape whose id is divisible by this

_POINTS = {
    "cust": ("orders", "o_custkey", "4 * datediff('day', DATE '1995-01-01', o_orderdate::DATE)", "2 * floor(o_totalprice / 100)"),
    "flag": ("lineitem", "l_partkey * 4 + CASE l_returnflag WHEN 'A' THEN 0 WHEN 'N' THEN 1 ELSE 2 END", "2 * floor(l_quantity * 40)", "2 * floor(l_extendedprice / 50)"),
    "supp": ("lineitem", "l_suppkey * 2 + CASE l_linestatus WHEN 'F' THEN 0 ELSE 1 END", "4 * datediff('day', DATE '1995-01-01', l_shipdate::DATE)", "2 * floor(l_extendedprice / 50)"),
    "user": ("events", "user_id", "8 * (hour(ts) * 60 + minute(ts))", "2 * floor(least(greatest(value, 0.0), 500.0) * 10)"),
    "order": ("lineitem", "l_orderkey", "2 * floor(l_quantity * 40)", "2 * floor(l_extendedprice / 50)"),
    "part": ("lineitem", "l_partkey", "2 * floor(l_quantity * 40)", "2 * floor(l_extendedprice / 50)"),
}
_PERCENT = {
    "cust_sized": "SELECT c_custkey AS pid, round(100 * pow(1.1, c_nationkey))::BIGINT AS pct FROM customer",
    "cust_bal": "SELECT c_custkey AS pid, round(15 + 85 * greatest(c_acctbal, 0.0) / 10000)::BIGINT AS pct FROM customer",
    "supp_sized": "SELECT unnest([s_suppkey * 2, s_suppkey * 2 + 1]) AS pid, round(100 * pow(1.1, s_nationkey))::BIGINT AS pct FROM supplier",
    "doc_sized": "SELECT doc_id AS pid, round(100 * pow(n_chars::DOUBLE, 0.25))::BIGINT AS pct FROM documents",
    "emb_sized": "SELECT vec_id AS pid, round(100 * pow(1.25, label))::BIGINT AS pct FROM embeddings",
    "flag_sized": "SELECT DISTINCT l_partkey * 4 + k AS pid, round(100 * pow(1.1, l_partkey % 25))::BIGINT AS pct FROM lineitem, range(3) r(k)",
}

Cte = list[tuple[str, str]]


def _radial(source: str, radii: int) -> str:
    """Vertices of radii r0..: ``source`` has pid and a list ``r``."""
    cos = "[" + ", ".join(repr(math.cos(2 * math.pi * t / radii)) + "::DOUBLE" for t in range(radii)) + "]"
    sin = "[" + ", ".join(repr(math.sin(2 * math.pi * t / radii)) + "::DOUBLE" for t in range(radii)) + "]"
    return f"SELECT pid, i AS idx, (2 * round(r[i + 1] * {cos}[i + 1] / 2))::BIGINT AS x, (2 * round(r[i + 1] * {sin}[i + 1] / 2))::BIGINT AS y FROM ({source}), range({radii}) t(i)"


def vertices(name: str, p: str = "") -> Cte:
    """``{p}v``: (pid, idx, x, y) of a layer as built."""
    if name in SIZED:
        base = vertices(SIZED[name], p + "b_")
        return [*base, (f"{p}pct", _PERCENT[name]), (f"{p}low", f"SELECT pid, min(x) AS x0, min(y) AS y0 FROM {p}b_v GROUP BY pid"), (f"{p}v", f"SELECT pid, idx, 2 * ((x - x0) * pct // 200) AS x, 2 * ((y - y0) * pct // 200) AS y FROM {p}b_v JOIN {p}low USING (pid) JOIN {p}pct USING (pid)")]
    if name in _POINTS:
        t, pid, x, y = _POINTS[name]
        return [
            (f"{p}pt", f"SELECT DISTINCT ({pid})::BIGINT AS pid, ({x})::BIGINT AS x, ({y})::BIGINT AS y FROM {t}"),
            (f"{p}off", f"SELECT pid, x, y, count(*) OVER w * x - sum(x) OVER w AS dx, count(*) OVER w * y - sum(y) OVER w AS dy FROM {p}pt WINDOW w AS (PARTITION BY pid)"),
            (f"{p}v", f"SELECT pid, row_number() OVER (PARTITION BY pid ORDER BY round(atan2(dy::DOUBLE, dx::DOUBLE), 9), dx * dx + dy * dy, x, y) - 1 AS idx, x, y FROM {p}off"),
        ]
    if name in TEXTS:
        t, key, text = TEXTS[name]
        n = ", ".join(f"sum(length(t) - length(replace(t, '{c}', '')))::BIGINT AS n_{c}" for c in ALPHABET)
        total = " + ".join(f"n_{c}" for c in ALPHABET)
        r = ", ".join(f"400.0::DOUBLE + 3600 * sqrt(n_{c} / greatest({total}, 1))" for c in LETTERS)
        return [(f"{p}n", f"SELECT {key} AS pid, {n} FROM (SELECT {key}, lower(coalesce({text}, '')) AS t FROM {t}) GROUP BY {key}"), (f"{p}v", _radial(f"SELECT pid, [{r}] AS r FROM {p}n", 24))]
    if name == "emb":
        return [(f"{p}v", _radial("SELECT vec_id AS pid, [2000 * greatest(0.05::DOUBLE, 0.4::DOUBLE + e::DOUBLE) FOR e IN embedding] AS r FROM embeddings", 64))]
    if name == "box_part":
        halves = "SELECT p_partkey AS pid, 20 * p_size::BIGINT AS hx, 2 * floor((p_retailprice - 899) / 2)::BIGINT + 2 AS hy FROM part"
    else:
        halves = "SELECT pid, 2 * floor(abs(bal) / 10)::BIGINT + 2 AS hx, 2 * floor(abs(bal) / 10)::BIGINT + 2 AS hy FROM (SELECT s_suppkey * 2 AS pid, s_acctbal AS bal FROM supplier UNION ALL SELECT c_custkey * 2 + 1, c_acctbal FROM customer)"
    return [(f"{p}v", f"SELECT pid, i AS idx, [-1, 1, 1, -1][i + 1] * hx AS x, [-1, -1, 1, 1][i + 1] * hy AS y FROM ({halves}), range(4) t(i)")]


def _edges(of: str) -> str:
    w = "OVER (PARTITION BY pid ORDER BY idx)"
    return f"SELECT pid, idx, x AS x1, y AS y1, coalesce(lead(x) {w}, first_value(x) {w}) AS x2, coalesce(lead(y) {w}, first_value(y) {w}) AS y2 FROM {of}"


def prepared(name: str, p: str = "") -> Cte:
    """``{p}c``: centred vertices; ``{p}ce``: edges; ``{p}s``: area2, centre, box of each shape."""
    return [
        *vertices(name, p),
        (f"{p}ok", f"SELECT pid, min(x) AS x0, min(y) AS y0 FROM {p}v GROUP BY pid HAVING count(DISTINCT (x, y)) >= 3"),
        (f"{p}e0", _edges(f"(SELECT pid, idx, x - x0 AS x, y - y0 AS y FROM {p}v JOIN {p}ok USING (pid))")),
        (f"{p}m", f"SELECT pid, abs(sum(x1 * y2 - x2 * y1)) AS area2, abs(sum((x1 * y2 - x2 * y1) * (x1 + x2))) AS mx, abs(sum((x1 * y2 - x2 * y1) * (y1 + y2))) AS my FROM {p}e0 GROUP BY pid HAVING sum(x1 * y2 - x2 * y1) <> 0"),
        (f"{p}mid", f"SELECT pid, area2, x0, y0, 2 * (mx // (6 * area2)) AS gx, 2 * (my // (6 * area2)) AS gy FROM {p}m JOIN {p}ok USING (pid)"),
        (f"{p}c", f"SELECT v.pid, idx, (x - x0 - gx)::BIGINT AS x, (y - y0 - gy)::BIGINT AS y FROM {p}v v JOIN {p}mid USING (pid)"),
        (f"{p}ce", _edges(f"{p}c")),
        (f"{p}s", f"SELECT pid, any_value(area2)::BIGINT AS area2, any_value(x0 + gx)::BIGINT AS cx, any_value(y0 + gy)::BIGINT AS cy, min(x) AS xmin, max(x) AS xmax, min(y) AS ymin, max(y) AS ymax, count(*) AS n FROM {p}c JOIN {p}mid USING (pid) GROUP BY pid"),
        (f"{p}frame", f"SELECT min(xmin) AS xmin, max(xmax) AS xmax, min(ymin) AS ymin, max(ymax) AS ymax FROM {p}s"),
    ]


def drawn(slots: list[int], cap: int, frame: str = "frame", base: int = 42) -> Cte:
    """``smp``: (slot, attempt, px, py)."""
    u = lambda a: f"('0x' || substr(md5('{base}:' || slot || ':{a}:' || attempt), 1, 8))::BIGINT"
    return [("smp", f"SELECT slot, attempt, (f.xmin + 2 * (({u('x')} * ((f.xmax - f.xmin) // 2)) >> 32) + 1)::BIGINT AS px, (f.ymin + 2 * (({u('y')} * ((f.ymax - f.ymin) // 2)) >> 32) + 1)::BIGINT AS py FROM (SELECT unnest({slots}) AS slot), range(1, {cap + 1}) r(attempt), {frame} f")]


def _odd(e: str, extra: str = "") -> str:
    return f"(e.y1 > b.py) <> (e.y2 > b.py) AND ((e.x2 - e.x1) * (b.py - e.y1) - (e.y2 - e.y1) * (b.px - e.x1)) * (CASE WHEN e.y2 > e.y1 THEN 1 ELSE -1 END) > 0{extra}"


def hits(slots: list[int], cap: int, p: str = "", frame: str = "frame", base: int = 42, smp: bool = True, most: int = MOST) -> Cte:
    """``{p}h``: (pid, slot, h) with a row for each shape and slot, h null where nothing up to ``most`` hits.

    ``cap`` attempts are drawn for all shapes (``{p}near``), the rest for open slots only (``{p}near2``).
    """
    within = "b.px > s.xmin AND b.px < s.xmax AND b.py > s.ymin AND b.py < s.ymax"
    parity = lambda near: f"SELECT b.pid, b.slot, b.attempt FROM {near} b JOIN {p}ce e ON e.pid = b.pid AND {_odd('e')} GROUP BY b.pid, b.slot, b.attempt HAVING count(*) % 2 = 1"
    first = f"SELECT s.pid, k.slot, min(i.attempt)::INT AS h FROM {p}s s CROSS JOIN (SELECT unnest({slots}) AS slot) k LEFT JOIN {p}ins i ON i.pid = s.pid AND i.slot = k.slot GROUP BY s.pid, k.slot"
    out = [
        *(drawn(slots, cap, frame, base) if smp else []),
        (f"{p}near", f"SELECT s.pid, b.slot, b.attempt, b.px, b.py FROM {p}s s JOIN smp b ON {within}"),
        (f"{p}ins", parity(f"{p}near")),
    ]
    if most <= cap:
        return [*out, (f"{p}h", first)]
    far = drawn(slots, most, frame, base)[0][1].replace(f"(SELECT unnest({slots}) AS slot)", f"(SELECT DISTINCT slot FROM {p}open)").replace("range(1, ", f"range({cap + 1}, ")
    return [
        *out,
        (f"{p}h1", first),
        (f"{p}open", f"SELECT pid, slot FROM {p}h1 WHERE h IS NULL"),
        (f"{p}far", far),
        (f"{p}near2", f"SELECT s.pid, b.slot, b.attempt, b.px, b.py FROM {p}open o JOIN {p}s s USING (pid) JOIN {p}far b ON b.slot = o.slot AND {within}"),
        (f"{p}ins2", parity(f"{p}near2")),
        (f"{p}h", f"SELECT a.pid, a.slot, coalesce(a.h, min(i.attempt))::INT AS h FROM {p}h1 a LEFT JOIN {p}ins2 i ON i.pid = a.pid AND i.slot = a.slot GROUP BY a.pid, a.slot, a.h"),
    ]


def codes(m: int, bands: int, p: str = "") -> Cte:
    """``{p}code``: (band, code, pid)."""
    return [(f"{p}code", f"SELECT (slot // 16)::INT AS band, string_agg(h::VARCHAR, '-' ORDER BY slot) AS code, pid FROM {p}h WHERE slot % 16 < {m} AND slot // 16 < {bands} GROUP BY pid, slot // 16 HAVING count(h) = {m}")]


def pairs_of_codes(p: str = "", q: str = "", name: str = "pair", queries: str = f"q.pid % {QUERY_STEP} = 0", distinct_self: bool = True) -> Cte:
    return [(name, f"SELECT DISTINCT q.pid AS qid, c.pid FROM {q}code q JOIN {p}code c USING (band, code) WHERE {queries}" + (" AND q.pid <> c.pid" if distinct_self else ""))]


def all_pairs(p: str = "", q: str = "", name: str = "pair", queries: str = f"q.pid % {QUERY_STEP} = 0", distinct_self: bool = True) -> Cte:
    return [(name, f"SELECT q.pid AS qid, c.pid FROM {q}s q, {p}s c WHERE {queries}" + (" AND q.pid <> c.pid" if distinct_self else ""))]


def distance(pair: str = "pair", p: str = "", q: str = "", name: str = "jd") -> Cte:
    """``name``: (qid, pid, jd) of pairs, from signed sums over edge pairs."""
    signed = lambda k, s: f"SELECT e.pid, least(x1, x2)::DOUBLE AS a, greatest(x1, x2)::DOUBLE AS b, (CASE WHEN x1 < x2 THEN y1 ELSE y2 END)::DOUBLE AS ya, (CASE WHEN x1 < x2 THEN y2 ELSE y1 END)::DOUBLE AS yb, (CASE WHEN x1 < x2 THEN -1 ELSE 1 END) * o.s AS s FROM {k}ce e JOIN {s} o USING (pid) WHERE x1 <> x2"
    return [
        (f"{name}_op", f"SELECT pid, sign(sum(x1 * y2 - x2 * y1)) AS s FROM {p}ce GROUP BY pid"),
        (f"{name}_oq", f"SELECT pid, sign(sum(x1 * y2 - x2 * y1)) AS s FROM {q}ce GROUP BY pid"),
        (f"{name}_p", signed(p, f"{name}_op")),
        (f"{name}_q", signed(q, f"{name}_oq")),
        (f"{name}_x", f"SELECT t.qid, t.pid, greatest(e.a, f.a) AS lo, least(e.b, f.b) AS hi, e.ya + (greatest(e.a, f.a) - e.a) * ((e.yb - e.ya) / (e.b - e.a)) AS p0, e.ya + (least(e.b, f.b) - e.a) * ((e.yb - e.ya) / (e.b - e.a)) AS p1, f.ya + (greatest(e.a, f.a) - f.a) * ((f.yb - f.ya) / (f.b - f.a)) AS q0, f.ya + (least(e.b, f.b) - f.a) * ((f.yb - f.ya) / (f.b - f.a)) AS q1, e.s * f.s AS s FROM {pair} t JOIN {name}_p e ON e.pid = t.pid JOIN {name}_q f ON f.pid = t.qid AND e.a < f.b AND f.a < e.b"),
        (f"{name}_i", f"SELECT qid, pid, greatest(0, sum(s * (hi - lo) * ((p0 + p1 + q0 + q1) / 4 - (CASE WHEN (p0 - q0) * (p1 - q1) >= 0 THEN abs(p0 - q0 + p1 - q1) / 2 ELSE ((p0 - q0) * (p0 - q0) + (p1 - q1) * (p1 - q1)) / (2 * (abs(p0 - q0) + abs(p1 - q1))) END) / 2))) AS i FROM {name}_x GROUP BY qid, pid"),
        (name, f"SELECT t.qid, t.pid, round(greatest(0.0::DOUBLE, 1 - coalesce(i, 0) / (a.area2 / 2.0 + b.area2 / 2.0 - coalesce(i, 0))), 6) + 0.0 AS jd FROM {pair} t LEFT JOIN {name}_i USING (qid, pid) JOIN {p}s a ON a.pid = t.pid JOIN {q}s b ON b.pid = t.qid"),
    ]


def ranked(k: int, jd: str = "jd", name: str = "knn") -> Cte:
    return [(name, f"SELECT qid, rank, pid, jd FROM (SELECT *, (row_number() OVER (PARTITION BY qid ORDER BY jd, pid))::INT AS rank FROM {jd}) WHERE rank <= {k}")]


def text(ctes: Cte, select: str) -> str:
    return "WITH " + ",\n".join(f"{n} AS MATERIALIZED ({q})" for n, q in ctes) + "\n" + select
