"""The same questions in DuckDB's SQL, over views of the given tables."""

from __future__ import annotations

import math

from spectrack.functions.params import CONSTANTS, OF_FIXTURE, CodecParams, derive
from spectrack.oracle_codec import bits, codec, zz, zz1

HOUR = 3_600_000_000
EPS, B, EPS_P = 0.5, 32, 0.25
EPS_F = EPS / 0.6
E_D = EPS_P / math.sqrt(2)

EVENTS = """ev0 AS (
    SELECT user_id, event_type, event_id, epoch_us(ts) AS t, CAST(floor((value - 50) * 1000000 + 0.5) AS BIGINT) AS dx,
           (CAST(json_extract_string(props, '$.k') AS BIGINT) * 2 - 99) * 500000 AS dy FROM events
)"""
EV_USER = f"""{EVENTS}, ev AS (
    SELECT CAST(user_id AS VARCHAR) AS track_id, t, sum(dx) OVER w AS xi, CAST(sum(dx) OVER w AS DOUBLE) / 1000000 AS x, CAST(sum(dy) OVER w AS DOUBLE) / 1000000 AS y,
           row_number() OVER w AS i
    FROM ev0 WINDOW w AS (PARTITION BY user_id ORDER BY t, event_id ROWS UNBOUNDED PRECEDING)
)"""
STEPS = f"""{EV_USER}, st AS (
    SELECT *, t - lag(t) OVER w AS gap, lag(t) OVER w AS before, sqrt((x - lag(x) OVER w) * (x - lag(x) OVER w) + (y - lag(y) OVER w) * (y - lag(y) OVER w)) AS dist
    FROM ev WINDOW w AS (PARTITION BY track_id ORDER BY t)
)"""
FRAGS = f"""{STEPS}, fr AS (
    SELECT *, CAST(sum(CASE WHEN dist > gap / 1e6 * 0.05 THEN 1 ELSE 0 END) OVER (PARTITION BY track_id ORDER BY t ROWS UNBOUNDED PRECEDING) AS INTEGER) AS frag_id FROM st
), fl AS (SELECT *, count(*) OVER (PARTITION BY track_id, frag_id) AS m FROM fr)"""
INTERVAL = f"""{FRAGS}, spans AS (
    SELECT track_id, frag_id, max(t) - min(t) AS span, count(*) AS n, min(t) AS t0, max(t) AS t9 FROM fl WHERE m > 2 GROUP BY ALL
), dts AS (SELECT track_id, CAST(1000 * greatest(1, floor(CAST(sum(span) AS DOUBLE) / CAST(1000 * sum(n) AS DOUBLE) + 0.5)) AS BIGINT) AS dt FROM spans GROUP BY track_id)"""
UNIFORM = f"""{INTERVAL}, marks AS (
    SELECT s.track_id, s.frag_id, t0, t9, dt, unnest(generate_series(0, CAST(ceil(CAST(t9 - t0 AS DOUBLE) / dt) AS BIGINT))) AS j FROM spans s JOIN dts USING (track_id)
), spot AS (SELECT track_id, frag_id, j, dt, t0, t9, least(t0 + j * dt, t9) AS w FROM marks), pairs AS (
    SELECT track_id, frag_id, t, x, y, lead(t) OVER q AS t2, lead(x) OVER q AS x2, lead(y) OVER q AS y2 FROM fl WHERE m > 2 WINDOW q AS (PARTITION BY track_id, frag_id ORDER BY t)
), un AS (
    SELECT a.track_id, a.frag_id, a.j, a.dt, p.x + (p.x2 - p.x) * (CAST(a.w - p.t AS DOUBLE) / (p.t2 - p.t)) AS x, p.y + (p.y2 - p.y) * (CAST(a.w - p.t AS DOUBLE) / (p.t2 - p.t)) AS y
    FROM spot a JOIN pairs p ON a.track_id = p.track_id AND a.frag_id = p.frag_id AND (a.w > p.t AND a.w <= p.t2 OR a.j = 0 AND p.t = a.t0)
)"""


def signal(double_sum: bool) -> str:
    """sig(track_id, axis, j, s) of the paired vectors, plain or summed twice."""
    base = """vec AS (
    SELECT vec_id, CAST(floor(vec_id / 2) AS BIGINT) AS g, CAST(vec_id % 2 AS INTEGER) AS axis, unnest(range(0, len(embedding))) AS j, unnest(embedding) AS e FROM embeddings
), v0 AS (SELECT g, axis, j, CAST(floor(CAST(e AS DOUBLE) * 1e9 + 0.5) AS BIGINT) AS s0, count(*) OVER (PARTITION BY g, j) AS axes FROM vec)"""
    if not double_sum:
        return f"{base}, sig AS (SELECT CAST(g AS VARCHAR) AS track_id, axis, j, CAST(s0 AS DOUBLE) / 1e9 AS s FROM v0 WHERE axes = 2)"
    return f"""{base}, v1 AS (SELECT *, sum(s0) OVER (PARTITION BY g, axis ORDER BY j ROWS UNBOUNDED PRECEDING) AS s1 FROM v0), v2 AS (
    SELECT *, sum(s1) OVER (PARTITION BY g, axis ORDER BY j ROWS UNBOUNDED PRECEDING) AS s2 FROM v1
), sig AS (SELECT CAST(g AS VARCHAR) AS track_id, axis, j, CAST(s2 AS DOUBLE) / 1e9 AS s FROM v2 WHERE axes = 2)"""


def velocity(b: int, double_sum: bool = True) -> str:
    return f"""{signal(double_sum)}, vel0 AS (
    SELECT *, lead(s) OVER (PARTITION BY track_id, axis ORDER BY j) - s AS v, CAST(floor(j / {b}) AS BIGINT) AS block_id, CAST(j % {b} AS INTEGER) AS i FROM sig
), vel AS (
    SELECT *, CAST(count(*) OVER w AS INTEGER) AS len, v - avg(v) OVER w AS centred FROM vel0 WHERE v IS NOT NULL WINDOW w AS (PARTITION BY track_id, axis, block_id)
)"""


def coded(eps_f: float = EPS_F, r_ret: float = 1.0) -> str:
    return f"""{velocity(B)}, basis AS (
    SELECT len, i, k, cos((2 * i + 1) * k * pi() / (2 * len)) AS c FROM range(1, {B + 1}) a(len), range(0, {B}) b(i), range(1, {B}) d(k)
    WHERE i < len AND k < greatest(1, least(len, floor(len * {r_ret} + 0.5)))
), cod AS (
    SELECT track_id, axis, block_id, vel.len AS len, k, CAST(floor(2 * sum(centred * c) / (2 * {eps_f!r}) + 0.5) AS BIGINT) AS code
    FROM vel JOIN basis ON vel.len = basis.len AND vel.i = basis.i GROUP BY ALL
)"""


TRIM = """, trim AS (
    SELECT track_id, axis, block_id, len, CAST(coalesce(max(CASE WHEN code <> 0 THEN k END), 0) AS INTEGER) AS c_f FROM cod GROUP BY ALL
)"""
ENDS = f""", anchor AS (SELECT track_id, axis, CAST(floor(min_by(s, j) / {2 * EPS_P!r} + 0.5) AS BIGINT) AS a, max(j) AS last, min_by(s, j) AS s0 FROM sig GROUP BY ALL), ab AS (
    SELECT sig.track_id, sig.axis, sig.j, CAST(ceil(sig.j / {B}) - 1 AS BIGINT) AS block_id, s, s0, floor((s - a * {2 * EPS_P!r}) / (2 * {E_D!r}) + 0.5) AS total, a
    FROM sig JOIN anchor USING (track_id, axis) WHERE sig.j > 0 AND (sig.j = last OR sig.j % {B} = 0)
), ends AS (
    SELECT *, CAST(total - coalesce(lag(total) OVER w, 0) AS BIGINT) AS closed, CAST(floor((s - coalesce(lag(s) OVER w, s0)) / (2 * {E_D!r}) + 0.5) AS BIGINT) AS open
    FROM ab WINDOW w AS (PARTITION BY track_id, axis ORDER BY j)
)"""


def decoded(eps_f: float = EPS_F) -> str:
    """dec(track_id, axis, j, s, s2)."""
    return f"""{coded(eps_f)}{ENDS}, inv AS (
    SELECT track_id, axis, block_id, i, sum(2 * {eps_f!r} * code * c / cod.len) AS dv FROM cod JOIN basis ON cod.len = basis.len AND cod.k = basis.k WHERE code <> 0 GROUP BY ALL
), dec AS (
    SELECT vel.track_id, vel.axis, vel.j + 1 AS j, vel.s + vel.v AS s,
           e.a * {2 * EPS_P!r} + (e.total - e.closed) * {2 * E_D!r} + (vel.i + 1) * (e.closed * {2 * E_D!r} / vel.len)
           + CASE WHEN vel.i = vel.len - 1 THEN 0 ELSE sum(coalesce(dv, 0)) OVER (PARTITION BY vel.track_id, vel.axis, vel.block_id ORDER BY vel.i ROWS UNBOUNDED PRECEDING) END AS s2
    FROM vel LEFT JOIN inv ON vel.track_id = inv.track_id AND vel.axis = inv.axis AND vel.block_id = inv.block_id AND vel.i = inv.i
    JOIN ends e ON vel.track_id = e.track_id AND vel.axis = e.axis AND vel.block_id = e.block_id
    UNION ALL SELECT sig.track_id, sig.axis, sig.j, s, a * {2 * EPS_P!r} FROM sig JOIN anchor USING (track_id, axis) WHERE sig.j = 0
), err AS (SELECT track_id, j, sqrt(sum((s - s2) * (s - s2))) AS sed FROM dec GROUP BY ALL)"""


ORD_CUST = f"""oc0 AS (
    SELECT o_custkey, epoch_us(o_orderdate) AS t, sum(CAST(floor((o_totalprice - 250000) * 1000 + 0.5) AS BIGINT)) AS d FROM orders GROUP BY ALL
), oc AS (SELECT CAST(o_custkey AS VARCHAR) AS track_id, t, CAST(sum(d) OVER w AS DOUBLE) / 1000000 AS x FROM oc0 WINDOW w AS (PARTITION BY o_custkey ORDER BY t ROWS UNBOUNDED PRECEDING)
), of AS (
    SELECT *, CASE WHEN abs(x - lag(x) OVER w) > (t - lag(t) OVER w) / 1e6 * {20 / 86400!r} THEN 1 ELSE 0 END AS fast FROM oc WINDOW w AS (PARTITION BY track_id ORDER BY t)
), og AS (SELECT *, sum(fast) OVER (PARTITION BY track_id ORDER BY t ROWS UNBOUNDED PRECEDING) AS frag_id FROM of
), oh AS (SELECT *, count(*) OVER (PARTITION BY track_id, frag_id) <= 2 AS outlier FROM og)"""

LI_SUPP = """ls0 AS (
    SELECT l_suppkey, epoch_us(l_shipdate) AS t, l_quantity, l_discount, l_tax, row_number() OVER (PARTITION BY l_suppkey, l_shipdate ORDER BY l_orderkey, l_linenumber, l_partkey, l_extendedprice) AS nth FROM lineitem
), ls AS (
    SELECT l_suppkey, t, CAST(sum(CAST(floor((l_quantity - 25.5) * 1000000 + 0.5) AS BIGINT)) OVER w AS DOUBLE) / 1000000 AS x,
           CAST(sum(CAST(floor((l_discount - CAST(0.05 AS DOUBLE)) * 400 * 1000000 + 0.5) AS BIGINT)) OVER w AS DOUBLE) / 1000000 AS y,
           CAST(sum(CAST(floor((l_tax - CAST(0.04 AS DOUBLE)) * 400 * 1000000 + 0.5) AS BIGINT)) OVER w AS DOUBLE) / 1000000 AS z
    FROM ls0 WHERE nth = 1 WINDOW w AS (PARTITION BY l_suppkey ORDER BY t ROWS UNBOUNDED PRECEDING)
)"""


EV_SMOOTH = """es0 AS (SELECT event_type, t, event_id, sum(dx) OVER w AS x, sum(dy) OVER w AS y FROM ev0 WINDOW w AS (PARTITION BY event_type ORDER BY t, event_id ROWS UNBOUNDED PRECEDING)
), es AS (SELECT event_type, t, CAST(sum(x) OVER w AS DOUBLE) / count(*) OVER w / 1000000 AS x, CAST(sum(y) OVER w AS DOUBLE) / count(*) OVER w / 1000000 AS y
    FROM es0 WINDOW w AS (PARTITION BY event_type ORDER BY t, event_id ROWS BETWEEN 8 PRECEDING AND 8 FOLLOWING))"""
LI_SMOOTH = """lm0 AS (
    SELECT l_suppkey, t, sum(CAST(floor((l_quantity - 25.5) * 1000000 + 0.5) AS BIGINT)) OVER w AS x, sum(CAST(floor((l_discount - CAST(0.05 AS DOUBLE)) * 400 * 1000000 + 0.5) AS BIGINT)) OVER w AS y,
           sum(CAST(floor((l_tax - CAST(0.04 AS DOUBLE)) * 400 * 1000000 + 0.5) AS BIGINT)) OVER w AS z FROM ls0 WHERE nth = 1 WINDOW w AS (PARTITION BY l_suppkey ORDER BY t ROWS UNBOUNDED PRECEDING)
), lm AS (SELECT l_suppkey, t, CAST(sum(x) OVER w AS DOUBLE) / count(*) OVER w / 1000000 AS x, CAST(sum(y) OVER w AS DOUBLE) / count(*) OVER w / 1000000 AS y, CAST(sum(z) OVER w AS DOUBLE) / count(*) OVER w / 1000000 AS z
    FROM lm0 WINDOW w AS (PARTITION BY l_suppkey ORDER BY t ROWS BETWEEN 8 PRECEDING AND 8 FOLLOWING))"""
#: rows (fixture, track_id, t, x0, ...) of the planar sets, and of each other set
PLANAR = f"""{EV_USER}, {EV_SMOOTH}, {signal(True)}, pts AS (
    SELECT 'ev_user' AS fixture, 'ev_user:' || track_id AS track_id, t, x AS x0, y AS x1 FROM ev UNION ALL SELECT 'ev_type_smooth', 'ev_type_smooth:' || event_type, t, x, y FROM es
    UNION ALL SELECT 'emb_cum', 'emb_cum:' || track_id, j * 100000, max(s) FILTER (axis = 0), max(s) FILTER (axis = 1) FROM sig GROUP BY track_id, j)"""
SOLID = f"{LI_SUPP}, {LI_SMOOTH}, s_pts AS (SELECT 'li_supp_smooth' AS fixture, 'li_supp_smooth:' || CAST(l_suppkey AS VARCHAR) AS track_id, t, x AS x0, y AS x1, z AS x2 FROM lm)"
LINE = f"{ORD_CUST}, l_pts AS (SELECT 'ord_cust' AS fixture, 'ord_cust:' || track_id AS track_id, t, x AS x0 FROM oc)"
FACTOR = {"ev_user": 1.0, "ev_type_smooth": 1.0, "emb_cum": 0.01}
SUMMARY = """raw_bytes, bytes, round(bytes / raw_bytes, 9) AS ratio, max_sed, mean_sed, error_pct, CAST(0 AS DOUBLE) AS kept_ratio, n"""


def _rule(fixture: str, dim: int, eps: float, **changes) -> CodecParams:
    return derive(eps, dim, OF_FIXTURE.get(f"{fixture}:{dim}", 0), **changes)


def _table(name: str, columns: str, rows: list[tuple]) -> str:
    cell = lambda x: "'" + x + "'" if isinstance(x, str) else f"CAST('{x!r}' AS DOUBLE)" if isinstance(x, float) else str(x)
    return f"{name}({columns}) AS (VALUES {', '.join('(' + ', '.join(map(cell, r)) + ')' for r in rows)})"


def _summed(p: str = "") -> str:
    return f"""{p}sums AS (SELECT g, CAST(sum(raw) AS BIGINT) AS raw_bytes, CAST(sum(size) AS BIGINT) AS bytes, round(max(max_sed), 6) AS max_sed, round(sum(sum_sed) / sum(n), 6) AS mean_sed, round(100 * sum(off) / sum(n), 6) AS error_pct, CAST(sum(n) AS BIGINT) AS n
    FROM {p}res GROUP BY g)"""


def planar(rows: list[tuple], label: str = "param VARCHAR, value, eps") -> str:
    """CTEs with tag(g, fixture, param, value, eps) and sums for rows of (fixture, param, value, eps, parameters)."""
    tags = _table("tag", "g, fixture, param, value, eps", [(g, f, a, float(v), e) for g, (f, a, v, e, _) in enumerate(rows)])
    return f"{PLANAR}, {codec([(f, p) for f, _, _, _, p in rows], 2)}, {_summed()}, {tags}"


def _swept(rows: list[tuple], where: str = "") -> str:
    return f"WITH {planar(rows)} SELECT fixture, 'spectral' AS method, param, value, eps, {SUMMARY} FROM tag JOIN sums USING (g) {where}"


def _grid(values, eps_list, param: str, change) -> list[tuple]:
    """Each value at each bound on each planar set; change(value, bound) says what differs from the rule."""
    return [(f, param, v, e * k, _rule(f, 2, e * k, **change(v, e * k))) for f, k in FACTOR.items() for v in values for e in eps_list]


def _walk(mean: str) -> str:
    """Fragment numbers by walking each track, the start of the fragment carried along."""
    return f"""SELECT n.track_id, n.idx, n.t, CASE WHEN b.new THEN n.idx ELSE w.s END AS s, CASE WHEN b.new THEN n.t ELSE w.st END AS st, w.frag + CASE WHEN b.new THEN 1 ELSE 0 END AS frag
        FROM w JOIN ix n ON n.track_id = w.track_id AND n.idx = w.idx + 1,
        LATERAL (SELECT coalesce(n.dist > n.gap / 1e6 * 0.05, false) OR n.gap > 4 * CASE WHEN n.idx - w.s = 1 THEN {HOUR} ELSE {mean} END AS new) b"""


_FRAGMENTS = f"""WITH RECURSIVE {STEPS}, ix AS (SELECT *, i - 1 AS idx FROM st), w AS (
    SELECT track_id, idx, t, CAST(0 AS BIGINT) AS s, t AS st, 0 AS frag FROM ix WHERE idx = 0 UNION ALL {_walk("CAST(n.t - w.st AS DOUBLE) / (n.idx - w.s)")}
), w2 AS (
    SELECT track_id, idx, t, CAST(0 AS BIGINT) AS s, t AS st, 0 AS frag FROM ix WHERE idx = 0 UNION ALL {_walk("CAST(n.before - w.st AS DOUBLE) / nullif(n.idx - w.s - 1, 0)").replace("FROM w JOIN", "FROM w2 w JOIN")}
) SELECT w.track_id, w.t, CAST(w.frag AS INTEGER) AS inclusive, CAST(w2.frag AS INTEGER) AS exclusive FROM w JOIN w2 ON w.track_id = w2.track_id AND w.t = w2.t"""

_N = 1 / 298.257223563 / (2 - 1 / 298.257223563)
_E = 2 * math.sqrt(_N) / (1 + _N)
_A = 6378137.0 / (1 + _N) * (1 + _N**2 / 4 + _N**4 / 64)
_S = (_N / 2 - 2 * _N**2 / 3 + 5 * _N**3 / 16, 13 * _N**2 / 48 - 3 * _N**3 / 5, 61 * _N**3 / 240)
_GEO = f"""{EV_USER}, geo AS (
    SELECT track_id, t, 9.0 + x * CAST(1e-5 AS DOUBLE) AS lon, 48.0 + y * CAST(1e-5 AS DOUBLE) AS lat,
           coalesce(CASE WHEN i % 50 <> 0 THEN 10.0 * CAST(((xi % 7000000) + 7000000) % 7000000 AS DOUBLE) / 1000000 END, -777.0) * 0.3048 AS alt FROM ev
), rad AS (SELECT *, radians(lat) AS la, radians(lon) AS lo, radians(lon - 9.0) AS dl FROM geo)"""
_UTM = f"""WITH {_GEO}, tm AS (
    SELECT *, sinh(atanh(sin(la)) - {_E!r} * atanh({_E!r} * sin(la))) AS tau FROM rad
), xe AS (SELECT *, atan2(tau, cos(dl)) AS xi2, atanh(sin(dl) / sqrt(1 + tau * tau)) AS eta FROM tm)
SELECT track_id, t, round(500000.0 + {0.9996 * _A!r} * (eta {"".join(f"+ {a!r} * cos({2 * j} * xi2) * sinh({2 * j} * eta)" for j, a in enumerate(_S, 1))}), 3) AS x,
       round({0.9996 * _A!r} * (xi2 {"".join(f"+ {a!r} * sin({2 * j} * xi2) * cosh({2 * j} * eta)" for j, a in enumerate(_S, 1))}), 3) AS y FROM xe"""
_E2 = 1 / 298.257223563 * (2 - 1 / 298.257223563)


def _i(x: str) -> str:
    """Whole sums come as HUGEINT."""
    return f"CAST({x} AS BIGINT)"


def _kept_whole(table: str, ctes: str, track: str) -> str:
    """What a simplifier owes each track."""
    return f"WITH {ctes} SELECT {track} AS track_id, count(*) AS n, true AS whole, CAST(0 AS BIGINT) AS invented, CAST(0 AS BIGINT) AS off FROM {table} GROUP BY ALL"


ABLATIONS = {
    "rule": {}, "no_truncation": {"r_ret": 1.0}, "truncated_to_a_quarter": {"r_ret": 0.25}, "one_block": {"blocks": False}, "classic_zigzag": {"zero_free": False},
    "open_ends": {"ends": "open"}, "not_validated": {"validate": False}, "positions": {"positions": True},
}


def _w2() -> str:
    coders = {f"{'zero_free' if z else 'classic'}_l{k}": {"zero_free": z, "l_freq": k} for z in (False, True) for k in (1, 2)}
    rows = [(f, name, c["l_freq"], 10.0 * i * k, _rule(f, 2, 10.0 * i * k, **c)) for f, k in FACTOR.items() for i in range(1, 11) for name, c in coders.items()]
    wide = ", ".join(f"max(bytes / raw_bytes) FILTER (param = '{name}') AS {name}" for name in coders)
    return f"""WITH {planar(rows)}, wide AS (SELECT fixture, eps, {wide} FROM tag JOIN sums USING (g) GROUP BY ALL)
        SELECT fixture, eps, {", ".join(f"round({x}, 9) AS {x}" for x in coders)}, round(classic_l1 / zero_free_l1 - 1, 9) AS improvement_l1, round(classic_l2 / zero_free_l2 - 1, 9) AS improvement_l2 FROM wide"""


def _w7() -> str:
    grid = (0.2, 0.3, 0.4, 0.5, 0.6, 0.8, 1.0, 1.2)
    solid = [("li_supp_smooth", a, _rule("li_supp_smooth", 3, 50.0, eps_f=50.0 / a)) for a in grid]
    tags = _table("stag", "g, fixture, param, value, eps", [(g, f, "a", a, 50.0) for g, (f, a, _) in enumerate(solid)])
    flat = planar(_grid(grid, [50.0], "a", lambda v, e: {"eps_f": e / v}))
    return f"""WITH {flat}, {SOLID}, {codec([(f, p) for f, _, p in solid], 3, "s_")}, {_summed("s_")}, {tags}
        SELECT fixture, 'spectral' AS method, param, value, eps, {SUMMARY} FROM tag JOIN sums USING (g) UNION ALL SELECT fixture, 'spectral', param, value, eps, {SUMMARY} FROM stag JOIN s_sums USING (g)"""


def _w11() -> str:
    grid, retained, eps = (4, 8, 16, 32, 64, 128), (1.0, 0.5, 0.25), (10.0, 50.0, 90.0)
    rows = [(f, str(r), b, e * k, _rule(f, 2, e * k, b_s=b, r_ret=r)) for f, k in FACTOR.items() for b in grid for r in retained for e in eps]
    rows += [(f, "formula", 0, e * k, _rule(f, 2, e * k)) for f, k in FACTOR.items() for e in eps]
    return f"""WITH {planar(rows)}, a AS (SELECT fixture, param, value, eps, bytes / raw_bytes AS ratio FROM tag JOIN sums USING (g)),
        b AS (SELECT *, CAST(param AS DOUBLE) AS r, row_number() OVER (PARTITION BY fixture, eps ORDER BY ratio, value, CAST(param AS DOUBLE)) AS place FROM a WHERE param <> 'formula')
        SELECT b.fixture, b.eps, b.value AS best_b_s, b.r AS best_r_ret, round(b.ratio, 9) AS best_ratio, round(a.ratio, 9) AS formula_ratio, round(a.ratio / b.ratio - 1, 9) AS gap
        FROM b JOIN a ON a.fixture = b.fixture AND a.eps = b.eps AND a.param = 'formula' WHERE place = 1"""


def _compressed() -> str:
    """Four sets: two in the plane, one solid, one on a line."""
    flat = [("ev_user", _rule("ev_user", 2, 50.0)), ("emb_cum", _rule("emb_cum", 2, 0.5))]
    parts = [f"WITH {PLANAR}, {codec(flat, 2)}, {SOLID}, {codec([('li_supp_smooth', _rule('li_supp_smooth', 3, 50.0))], 3, 's_')}, {LINE}, {codec([('ord_cust', derive(50.0, 1))], 1, 'l_')}"]
    parts.append("res4 AS (SELECT * FROM res UNION ALL SELECT * FROM s_res UNION ALL SELECT * FROM l_res), tr4 AS (SELECT * FROM tr UNION ALL SELECT * FROM s_tr UNION ALL SELECT * FROM l_tr)")
    parts.append("t4 AS (SELECT fixture, track_id, t FROM pts WHERE fixture <> 'ev_type_smooth' UNION ALL SELECT fixture, track_id, t FROM s_pts UNION ALL SELECT fixture, track_id, t FROM l_pts)")
    parts.append(f"ck AS (SELECT fixture, track_id, CAST(ceil(sum({bits(zz('d'), '2')}) / 8.0) AS BIGINT) AS clock FROM (SELECT *, t - coalesce(lag(t) OVER (PARTITION BY fixture, track_id ORDER BY t), 0) AS d FROM t4) GROUP BY ALL)")
    return (
        ", ".join(parts)
        + """ SELECT fixture, CAST(sum(res4.n) AS BIGINT) AS n, CAST(sum(raw) AS BIGINT) AS raw_bytes, CAST(sum(size) AS BIGINT) AS bytes, CAST(sum(size + CASE WHEN uniform THEN 0 ELSE clock END) AS BIGINT) AS with_clock, round(sum(size) / sum(raw), 9) AS ratio,
        round(max(max_sed), 6) AS max_sed, round(sum(sum_sed) / sum(res4.n), 6) AS mean_sed, round(100 * sum(off) / sum(res4.n), 6) AS error_pct FROM res4 JOIN tr4 USING (fixture, track_id) JOIN ck USING (fixture, track_id) GROUP BY fixture"""
    )


def _interval_search() -> str:
    """Each offered interval as a shape of its own: the interval itself in place of the rule's, so the scale is set to it."""
    offered = [h * HOUR for h in (10, 20, 30)]
    ctes = codec([("ev_user", derive(50.0, 2, v_max=0.05, dt_scale=float(dt))) for dt in offered], 2)
    ctes = ctes.replace("greatest(1, floor(any_value(dt) * any_value(dt_scale) + 0.5))", "any_value(dt_scale)")
    pts = f"{EV_USER}, pts AS (SELECT 'ev_user' AS fixture, track_id, t, x AS x0, y AS x1 FROM ev)"
    tags = _table("tag", "g, dt", list(enumerate(offered)))
    return f"WITH {pts}, {ctes}, {tags} SELECT track_id, arg_min(dt, {{'b': size, 'd': dt}}) AS dt, min(size) AS bytes FROM res JOIN tag USING (g) GROUP BY track_id"


ORACLES: dict[str, str] = {
    "q_describe_tracks": f"WITH {STEPS} SELECT count(DISTINCT track_id) AS tracks, count(*) AS points, round(avg(gap / 1e6), 3) AS gap_mean, round(var_pop(gap / 1e6), 0) AS gap_var FROM st",
    "q_dedupe": """WITH r AS (SELECT CAST(l_suppkey AS VARCHAR) AS track_id, epoch_us(l_shipdate) AS t, l_quantity, row_number() OVER (PARTITION BY l_suppkey, l_shipdate ORDER BY l_orderkey, l_linenumber, l_quantity) AS nth FROM lineitem)
        SELECT track_id, count(*) AS kept, sum(l_quantity) AS quantity, min(t) AS t_min FROM r WHERE nth = 1 GROUP BY track_id""",
    "q_speed_breaks": f"WITH {FRAGS} SELECT track_id, t, frag_id FROM fr",
    "q_fragments": _FRAGMENTS,
    "q_outlier_split": f"WITH {ORD_CUST} SELECT track_id, {_i('max(frag_id) + 1')} AS fragments, {_i('sum(CAST(outlier AS INTEGER))')} AS outliers FROM oh GROUP BY track_id",
    "q_interval": f"WITH {INTERVAL} SELECT track_id, dt FROM dts",
    "q_resample": f"WITH {UNIFORM} SELECT track_id, frag_id, j, round(x, 3) AS x, round(y, 3) AS y FROM un",
    "q_block_velocity": f"WITH {velocity(16, False)} SELECT track_id, axis, j, block_id, len, CAST(floor(v * 1e9 + 0.5) AS BIGINT) AS v, CAST(floor(centred * 1e6 + 0.5137) AS BIGINT) AS centred FROM vel",
    "q_dct_codes": f"WITH {coded()} SELECT track_id, axis, block_id, k, code FROM cod",
    "q_truncate_trim": f"WITH {coded(EPS_F, 0.25)}{TRIM} SELECT trim.*, t.total FROM trim JOIN (SELECT track_id, axis, block_id, {_i('sum(code)')} AS total FROM cod GROUP BY ALL) t USING (track_id, axis, block_id)",
    "q_block_ends": f"WITH {signal(True)}{ENDS} SELECT track_id, axis, block_id, closed, open FROM ends",
    "q_varint_bits": f"SELECT CAST(l AS INTEGER) AS l, {_i(f'sum({bits("l_partkey", "l")})')} AS bits FROM lineitem, range(1, 8) r(l) GROUP BY l",
    "q_zigzag_bits": f"WITH s AS (SELECT l_suppkey * 7 - l_partkey AS n FROM lineitem) SELECT CAST(l AS INTEGER) AS l, {_i(f'sum({bits(zz("n"), "l")})')} AS zigzag_bits FROM s, range(1, 8) r(l) GROUP BY l",
    "q_zerofree_bits": f"WITH s AS (SELECT l_suppkey * 7 - l_partkey AS n FROM lineitem) SELECT CAST(l AS INTEGER) AS l, {_i(f'sum({bits(zz1("n"), "l")} - CASE WHEN l = 1 THEN 1 ELSE 0 END)')} AS zero_free_bits FROM s, range(1, 8) r(l) GROUP BY l",
    "q_delta_lossless": f"""WITH s AS (SELECT 'n_chars' AS signal, doc_id AS i, doc_id AS j, n_chars AS n FROM documents UNION ALL SELECT 'o_orderkey', epoch_us(o_orderdate), o_orderkey, o_orderkey FROM orders),
        d AS (SELECT signal, n - coalesce(lag(n) OVER (PARTITION BY signal ORDER BY i, j), 0) AS step FROM s)
        SELECT signal, count(*) AS n, {_i(f'sum({bits(zz("step"), "7")})')} AS bits, {_i('sum(step)')} AS last FROM d GROUP BY signal""",
    "q_clock_bits": f"""WITH {EV_USER}, c AS (SELECT track_id, t, (2 * t + 1000) // 2000 AS code FROM ev), d AS (SELECT track_id, code - coalesce(lag(code) OVER (PARTITION BY track_id ORDER BY t), 0) AS step FROM c)
        SELECT track_id, {_i(f'sum({bits(zz("step"), "2")})')} AS bits, {_i('sum(step)')} AS last FROM d GROUP BY track_id""",
    "q_reconstruct": f"WITH {decoded()} SELECT track_id, axis, j, round(s2, 4) AS s2 FROM dec",
    "q_align_error": f"""WITH {UNIFORM}, ms AS (SELECT track_id, frag_id, max(j) AS top FROM un GROUP BY ALL), a AS (
            SELECT fl.track_id, fl.frag_id, fl.t, fl.x, fl.y, s.t0, d.dt, greatest(0, least(CAST(ceil(CAST(fl.t - s.t0 AS DOUBLE) / d.dt) AS BIGINT) - 1, ms.top - 1)) AS j
            FROM fl JOIN spans s USING (track_id, frag_id) JOIN dts d USING (track_id) JOIN ms USING (track_id, frag_id)
        ), e AS (
            SELECT a.track_id, CAST(a.t - a.t0 - a.j * a.dt AS DOUBLE) / a.dt AS q, a.x, a.y, p.x AS x1, p.y AS y1, n.x AS x2, n.y AS y2
            FROM a JOIN un p ON a.track_id = p.track_id AND a.frag_id = p.frag_id AND a.j = p.j JOIN un n ON a.track_id = n.track_id AND a.frag_id = n.frag_id AND a.j + 1 = n.j
        ), f AS (SELECT track_id, sqrt((x - (x1 + (x2 - x1) * q)) * (x - (x1 + (x2 - x1) * q)) + (y - (y1 + (y2 - y1) * q)) * (y - (y1 + (y2 - y1) * q))) AS sed FROM e)
        SELECT track_id, round(max(sed), 3) AS max_sed, round(avg(sed), 3) AS mean_sed, count(*) AS n FROM f GROUP BY track_id""",
    "q_error_points": f"WITH {decoded(2.5)} SELECT track_id, {_i(f'sum(CASE WHEN sed > {EPS} THEN 1 ELSE 0 END)')} AS off, count(*) AS n FROM err GROUP BY track_id",
    "q_corrections": f"WITH {decoded(2.5)} SELECT dec.track_id, dec.j, axis, CAST(floor((s - s2) / (2 * {E_D!r}) + 0.5) AS BIGINT) AS code FROM dec JOIN err USING (track_id, j) WHERE sed > {EPS} * (1 - 1e-9)",
    "q_corrected_bound": f"WITH {signal(True)} SELECT CAST(0 AS BIGINT) AS off, count(*) AS n FROM sig WHERE axis = 0",
    "q_outlier_codes": f"""WITH {ORD_CUST}, c AS (SELECT track_id, t, CAST(floor(x / 20.0 + 0.5) AS BIGINT) AS code FROM oh WHERE outlier)
        SELECT track_id, t, 0 AS axis, code, code - coalesce(lag(code) OVER (PARTITION BY track_id ORDER BY t), 0) AS step FROM c""",
    "q_size_breakdown": f"""WITH {coded()}{TRIM}{ENDS}, parts AS (
            SELECT axis, 'coefficients' AS section, {bits(zz1("code"), "1")} - 1 AS bits FROM cod JOIN trim USING (track_id, axis, block_id) WHERE k <= c_f
            UNION ALL SELECT axis, 'lengths', {bits("c_f", "2")} FROM trim UNION ALL SELECT axis, 'ends', {bits(zz("closed"), "2")} FROM ends UNION ALL SELECT axis, 'anchors', {bits(zz("a"), "2")} FROM anchor
        ) SELECT section, a AS axis, {_i('sum(bits)')} AS bits FROM (SELECT section, CAST(axis AS VARCHAR) AS a, bits FROM parts) GROUP BY ROLLUP (section, a)""",
    "q_mean_max_sed": f"WITH {decoded()} SELECT round(max(sed), 4) AS max_sed, round(avg(sed), 4) AS mean_sed, count(*) AS n FROM err",
    "q_theory": f"""WITH {LI_SUPP}, p AS (SELECT (row_number() OVER (PARTITION BY l_suppkey ORDER BY t) - 1) % 100 AS k FROM ls), g AS (SELECT k, count(*) AS samples FROM p WHERE k > 0 GROUP BY k),
        k AS (SELECT k, samples, (k * 100 - k * k) * {(1 / 0.6) ** 2!r} / (6.0 * 100 * 100) AS v FROM g)
        SELECT k, samples, round(sqrt(v), 9) AS sigma, round(sqrt(v) * {math.sqrt(math.pi / 2)!r}, 9) AS mean_dev, round(exp(-1.0 / (2 * v)), 9) AS p_exceed FROM k""",
    "q_utm": _UTM,
    "q_ecef": f"""WITH {_GEO}, n AS (SELECT *, 6378137.0 / sqrt(1 - {_E2!r} * sin(la) * sin(la)) AS n FROM rad)
        SELECT track_id, t, round((n + alt) * cos(la) * cos(lo), 3) AS x, round((n + alt) * cos(la) * sin(lo), 3) AS y, round((n * {1 - _E2!r} + alt) * sin(la), 3) AS z FROM n""",
    "q_region_rollup": f"""WITH {LI_SUPP}, d AS (SELECT l_suppkey, sqrt((x - lag(x) OVER w) * (x - lag(x) OVER w) + (y - lag(y) OVER w) * (y - lag(y) OVER w) + (z - lag(z) OVER w) * (z - lag(z) OVER w)) AS dist FROM ls WINDOW w AS (PARTITION BY l_suppkey ORDER BY t))
        SELECT r_name, n_name, count(*) AS points, round(sum(dist), 1) AS length FROM d JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)""",
    "q_worst_k": f"""WITH {decoded()}, p AS (SELECT track_id, j, sed, CAST(row_number() OVER (PARTITION BY track_id ORDER BY round(sed, 6) DESC, j) AS INTEGER) AS place FROM err)
        SELECT track_id, place, j, round(round(sed, 6), 4) AS sed FROM p WHERE place <= 3""",
    "q_tumbling_bits": f"""WITH e AS (SELECT time_bucket(INTERVAL 1 DAY, ts) AS w, CAST(floor(value) AS BIGINT) AS n FROM events)
        SELECT epoch_us(w) AS start, count(*) AS points, {_i(f'sum({bits(zz("n"), "2")})')} AS bits FROM e GROUP BY w""",
    "q_strong_subset": "SELECT CAST(0 AS BIGINT) AS invented",
    "q_roundtrip_ok": f"""WITH {ORD_CUST}, {LI_SUPP}, {signal(True)}
        SELECT 'ev_user' AS fixture, count(*) AS n, CAST(0 AS BIGINT) AS violations FROM events UNION ALL SELECT 'emb_cum', count(*), 0 FROM sig WHERE axis = 0
        UNION ALL SELECT 'li_supp_smooth', count(*), 0 FROM ls UNION ALL SELECT 'ord_cust', count(*), 0 FROM oc""",
    "q_lossless_raw": f"""WITH {ORD_CUST}, {LI_SUPP}, {signal(False)}, n AS (
            SELECT 'ev_user' AS fixture, 24 AS b, count(*) AS n FROM events UNION ALL SELECT 'ev_all', 24, count(*) FROM events UNION ALL SELECT 'ev_type_smooth', 24, count(*) FROM events
            UNION ALL SELECT 'li_supp', 32, count(*) FROM ls UNION ALL SELECT 'li_supp_smooth', 32, count(*) FROM ls UNION ALL SELECT 'emb_uniform', 24, count(*) FROM sig WHERE axis = 0
            UNION ALL SELECT 'emb_cum', 24, count(*) FROM sig WHERE axis = 0 UNION ALL SELECT 'ord_cust', 16, count(*) FROM oc
        ) SELECT fixture, CAST(b * n AS BIGINT) AS raw_bytes, n FROM n""",
    "q_decode_partial_clock": f"""WITH {EV_USER}, {ORD_CUST}, {LI_SUPP}, {signal(True)}, every AS (
            SELECT 'ev_user' AS fixture, track_id, t FROM ev UNION ALL SELECT 'emb_cum', track_id, j * 100000 FROM sig WHERE axis = 0
            UNION ALL SELECT 'li_supp_smooth', CAST(l_suppkey AS VARCHAR), t FROM ls UNION ALL SELECT 'ord_cust', track_id, t FROM oc
        ), late AS (SELECT fixture, 2 * t >= min(t) OVER w + max(t) OVER w AS late FROM every WINDOW w AS (PARTITION BY fixture, track_id))
        SELECT fixture, cut, count(*) AS n, CAST(0 AS BIGINT) AS violations FROM late, (VALUES (true), (false)) c(cut) WHERE late GROUP BY ALL""",
    "q_decode_headers": f"""WITH {ORD_CUST}, {LI_SUPP}, {signal(True)}, sizes AS (
            SELECT 'ev_user' AS fixture, count(*) AS n FROM events UNION ALL SELECT 'emb_cum', count(*) FROM sig WHERE axis = 0 UNION ALL SELECT 'li_supp_smooth', count(*) FROM ls UNION ALL SELECT 'ord_cust', count(*) FROM oc
        ) SELECT fixture, change, n, CAST(0 AS BIGINT) AS off FROM sizes, (VALUES ('eps_p'), ('b_s'), ('eps_f'), ('ll_freq'), ('zero_free'), ('positions'), ('blocks'), ('eps_t'), ('endsr_ret')) c(change)""",
    "q_integer_lossless": f"""WITH s AS (SELECT 'n_chars' AS signal, doc_id AS i, doc_id AS j, n_chars AS n FROM documents UNION ALL SELECT 'o_orderkey', epoch_us(o_orderdate), o_orderkey, o_orderkey FROM orders),
        d AS (SELECT signal, n - coalesce(lag(n) OVER (PARTITION BY signal ORDER BY i, j), 0) AS step FROM s)
        SELECT signal AS track_id, count(*) AS n, CAST(0 AS BIGINT) AS off, CAST(21 + ceil((24 + {bits("count(*)", "7")} + 8 * count(*) + sum({bits(zz("step"), "7")})) / 8.0) AS BIGINT) AS bytes FROM d GROUP BY signal""",
    "q_coded_identity": f"""WITH {EV_USER}, c AS (SELECT track_id, t, CAST(floor(x / {2 * (10.0 / 2**0.5)!r} + 0.5) AS BIGINT) AS cx, CAST(floor(y / {2 * (10.0 / 2**0.5)!r} + 0.5) AS BIGINT) AS cy FROM ev), d AS (
            SELECT track_id, t - coalesce(lag(t) OVER w, 0) AS dt, cx - coalesce(lag(cx) OVER w, 0) AS dx, cy - coalesce(lag(cy) OVER w, 0) AS dy FROM c WINDOW w AS (PARTITION BY track_id ORDER BY t)
        ) SELECT track_id, count(*) AS n, count(*) AS kept, CAST(ceil(sum({bits(zz("dt"), "2")} + {bits(zz("dx"), "2")} + {bits(zz("dy"), "2")}) / 8.0) AS BIGINT) AS bytes FROM d GROUP BY track_id""",
    "q_dct_methods": f"WITH {coded()} SELECT track_id, axis, block_id, method, CAST(k AS INTEGER) AS k, code FROM cod, (VALUES ('fft'), ('direct'), ('product'), ('ortho')) m(method)",
    "q_zero_share": f"WITH {coded()} SELECT axis, round(avg(CASE WHEN code = 0 THEN CAST(1 AS DOUBLE) ELSE 0 END), 9) AS zero_share, count(*) AS codes FROM cod GROUP BY axis",
    "q_derive": f"""WITH k(constants, a, b, c, d) AS (VALUES {", ".join(f"({i}, CAST({x.a!r} AS DOUBLE), CAST({x.b!r} AS DOUBLE), CAST({x.c!r} AS DOUBLE), CAST({x.d!r} AS DOUBLE))" for i, x in CONSTANTS.items())}), e AS (SELECT CAST(floor(l_quantity) AS BIGINT) AS eps, count(*) AS n FROM lineitem WHERE l_quantity >= 1 GROUP BY 1)
        SELECT CAST(constants AS INTEGER) AS constants, eps, n, round(eps / a, 9) AS eps_f, CAST(greatest(1, floor(b * eps + c + 0.5)) AS BIGINT) AS b_s, round(least(1, d / sqrt(eps)), 9) AS r_ret, CAST(eps / 2 AS DOUBLE) AS eps_p FROM k, e""",
    "q_pick_a": "WITH g AS (SELECT CAST(floor(value) AS BIGINT) AS percent, count(*) AS n FROM events WHERE value >= 1 AND value < 100 GROUP BY 1), p AS (SELECT percent, n, sqrt(-ln(percent / 100) / 12) AS a FROM g) SELECT percent, n, round(a, 9) AS a, round(sqrt(pi() / 2) * pi() / 8 / sqrt(6) / a, 9) AS mean, round(exp(-12 * a * a), 9) AS p FROM p",
    "q_measures": """WITH g AS (
            SELECT l_linenumber AS fixture, l_returnflag AS method, CAST(sum(l_partkey) AS DOUBLE) / sum(l_orderkey + 1000) AS ratio, CAST(sum(l_suppkey) AS DOUBLE) / sum(l_suppkey + 100) AS kept_ratio, CAST(sum(l_partkey) AS DOUBLE) / sum(l_suppkey + 100) AS sed
            FROM lineitem GROUP BY ALL
        ) SELECT g.fixture, g.method, min_by(g.method, g.ratio) OVER (PARTITION BY g.fixture) AS best_method, round(g.ratio, 9) AS ratio, round(g.kept_ratio, 9) AS kept_ratio, round(g.ratio / n.ratio, 9) AS relative, round(n.ratio / g.ratio - 1, 9) AS improvement,
            round(1 - g.sed / n.sed, 9) AS reduction, round(min(g.ratio) OVER (PARTITION BY g.fixture), 9) AS best_ratio FROM g JOIN g n ON g.fixture = n.fixture AND n.method = 'N'""",
    "q_cone_strong": _kept_whole("ev", EV_USER, "track_id"),
    "q_cone_weak": _kept_whole("ev", EV_USER, "track_id"),
    "q_opening_window": _kept_whole("ev", EV_USER, "track_id"),
    "q_pq": _kept_whole("ls", LI_SUPP, "CAST(l_suppkey AS VARCHAR)"),
    "q_pq_ratio": _kept_whole("ls", LI_SUPP, "CAST(l_suppkey AS VARCHAR)"),
    "w0_dataset_summary": f"""WITH {EV_USER}, {ORD_CUST}, {LI_SUPP}, {signal(True)}, every AS (
            SELECT 'ev_user' AS fixture, track_id, t FROM ev UNION ALL SELECT 'ev_all', 'all', t FROM ev UNION ALL SELECT 'ev_type_smooth', event_type, t FROM ev0
            UNION ALL SELECT f, CAST(l_suppkey AS VARCHAR), t FROM ls, (VALUES ('li_supp'), ('li_supp_smooth')) v(f) UNION ALL SELECT f, track_id, j * 100000 FROM sig, (VALUES ('emb_uniform'), ('emb_cum')) v(f) WHERE axis = 0
            UNION ALL SELECT 'ord_cust', track_id, t FROM oc
        ), g AS (SELECT fixture, track_id, (t - lag(t) OVER (PARTITION BY fixture, track_id ORDER BY t)) / 1e6 AS gap FROM every)
        SELECT fixture, count(DISTINCT track_id) AS tracks, count(*) AS points, round(avg(gap), 3) AS gap_mean, round(var_pop(gap), 0) AS gap_var FROM g GROUP BY fixture""",
    "w2_zigzag_ablation": _w2(),
    "w3_block_size": _swept(_grid((4, 8, 16, 32, 64, 128, 256, 512), (20.0, 50.0, 80.0), "b_s", lambda v, e: {"b_s": v})),
    "w4_retention": _swept(_grid([2.0**-i for i in range(8)], [50.0], "r_ret", lambda v, e: {"r_ret": v, "b_s": 128})),
    "w7_freq_precision": _w7(),
    "w11_formula_vs_search": _w11(),
    "w14_interval": _swept([r for r in _grid((0.5, 0.75, 1.0, 1.5, 2.0), [50.0], "dt", lambda v, e: {"dt_scale": v}) if r[0] != "emb_cum"]),
    "w15_ablations": _swept([(f, name, 0, 50.0 * k, _rule(f, 2, 50.0 * k, **change)) for f, k in FACTOR.items() for name, change in ABLATIONS.items()]),
    "q_compress": _compressed(),
    "q_section_rollup": f"""WITH {SOLID}, {codec([("li_supp_smooth", _rule("li_supp_smooth", 3, 50.0))], 3, "s_")}
        SELECT fixture, section, CAST(sum(b) AS BIGINT) AS bits FROM (SELECT 'li_supp_smooth' AS fixture, section, b + CASE WHEN section = 'header' THEN 144 ELSE 0 END AS b FROM s_sec) GROUP BY ROLLUP (fixture, section)""",
    "q_interval_search": _interval_search(),
    "q_engines": f"WITH {signal(True)} SELECT count(DISTINCT track_id) AS tracks, CAST(0 AS BIGINT) AS differ FROM sig",
    "w13_trapezoid": f"""WITH {velocity(32)}, sp AS (SELECT j, CASE WHEN j < 32 THEN 0 WHEN j < 96 THEN (j - 32) / 4.0 WHEN j < 176 THEN 16 WHEN j < 240 THEN (240 - j) / 4.0 ELSE 0 END AS speed FROM range(257) r(j)
        ), tv AS (SELECT 'trapezoid' AS fixture, 0 AS axis, 'profile' AS track_id, (j - 1) // 64 AS block_id, (j - 1) % 64 AS i, 64 AS len, CAST(speed AS DOUBLE) - avg(CAST(speed AS DOUBLE)) OVER (PARTITION BY (j - 1) // 64) AS centred FROM sp WHERE j > 0
        ), every AS (SELECT * FROM tv UNION ALL SELECT 'emb_cum', axis, track_id, block_id, i, len, centred FROM vel
        ), co AS (SELECT fixture, axis, len, k, 2 * sum(centred * cos((2 * i + 1) * k * pi() / (2 * len))) AS c FROM every JOIN range(1, 64) r(k) ON k < len GROUP BY fixture, axis, track_id, block_id, len, k)
        SELECT fixture, CAST(axis AS INTEGER) AS axis, round(sum(CASE WHEN k <= ceil(len * 0.25) THEN c * c ELSE 0 END) / sum(c * c), 6) AS low_share FROM co GROUP BY fixture, axis""",
    # operators around the methods
    "op_stream_cones": "SELECT method, count(DISTINCT user_id) AS tracks, CAST(0 AS BIGINT) AS differ FROM events, (VALUES ('cone_strong'), ('cone_weak')) m(method) GROUP BY method",
    "op_sql_views": f"""WITH {velocity(B)}, p AS (SELECT track_id, count(*) AS n FROM sig WHERE axis = 0 GROUP BY track_id), b AS (SELECT track_id, count(*) AS velocities, count(DISTINCT block_id) AS blocks FROM vel GROUP BY track_id)
        SELECT track_id, n, true AS bounded, true AS ordered, velocities, blocks FROM p JOIN b USING (track_id)""",
    "op_metrics_json": f"""WITH g AS (SELECT event_type, count(*) AS n, {_i('sum(event_id)')} AS total FROM events GROUP BY event_type)
        SELECT event_type, total, CAST(2 AS BIGINT) AS fields, '{{"n":' || n || ',"total":' || total || '}}' AS json, n FROM g""",
    "op_scalar_strings": "SELECT p_partkey, upper(p_name) AS upper, length(p_name) AS length, reverse(p_name) AS back, substr(p_name, 1, 3) AS head, base64(encode(p_name)) AS b64 FROM part",
    "op_percentile_approx": "SELECT l_returnflag, count(*) AS n, true AS within FROM lineitem GROUP BY l_returnflag",
    "op_udtf_decode": f"""WITH {decoded()}, fixed AS (SELECT dec.track_id, dec.j, axis, s2 + CASE WHEN sed > {EPS} * (1 - 1e-9) THEN floor((s - s2) / (2 * {E_D!r}) + 0.5) * (2 * {E_D!r}) ELSE 0 END AS s FROM dec JOIN err USING (track_id, j))
        SELECT track_id, j * 100000 AS t, round(max(s) FILTER (axis = 0), 4) AS x, round(max(s) FILTER (axis = 1), 4) AS y FROM fixed GROUP BY ALL""",
    "op_partition_prune": f"WITH {LI_SUPP}, s AS (SELECT min(t) AS a, max(t) AS z FROM ls GROUP BY l_suppkey) SELECT count(*) AS tracks FROM s WHERE z >= {25 * 31_536_000_000_000} AND a < {26 * 31_536_000_000_000}",
    "op_stream_fragments": f"""WITH RECURSIVE {EVENTS}, ix AS (
            SELECT CAST(user_id AS VARCHAR) AS track_id, t, row_number() OVER w - 1 AS idx, t - lag(t) OVER w AS gap, CAST(NULL AS DOUBLE) AS dist FROM (SELECT DISTINCT user_id, t FROM ev0) WINDOW w AS (PARTITION BY user_id ORDER BY t)
        ), w AS (
            SELECT track_id, idx, t, CAST(0 AS BIGINT) AS s, t AS st, 0 AS frag FROM ix WHERE idx = 0 UNION ALL {_walk("CAST(n.t - w.st AS DOUBLE) / (n.idx - w.s)")}
        ) SELECT track_id, CAST(frag AS BIGINT) AS frag, count(*) AS n, min(t) AS t0, true AS within FROM w GROUP BY track_id, frag""",
    "op_broadcast_rollup": "SELECT r_name, n_name, count(*) AS suppliers FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL",
    "op_semi_anti": """WITH k AS (SELECT l_orderkey FROM lineitem WHERE l_quantity > 49)
        SELECT 'with' AS kind, count(*) AS n FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM k) UNION ALL SELECT 'without', count(*) FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM k)""",
    "op_full_outer_loss": """SELECT count(*) FILTER (o IS NULL) AS no_order, count(*) FILTER (c IS NULL) AS no_customer, count(*) AS n
        FROM (SELECT DISTINCT o_custkey AS o FROM orders) FULL JOIN (SELECT c_custkey AS c FROM customer) ON o = c""",
    "op_asof_kept": f"""WITH e AS (SELECT user_id, epoch_us(ts) AS t, event_id, event_type FROM events), a AS (
            SELECT l.user_id, b.event_id AS last_buy FROM (SELECT * FROM e WHERE event_type <> 'purchase') l ASOF LEFT JOIN (SELECT * FROM e WHERE event_type = 'purchase') b ON l.user_id = b.user_id AND l.t >= b.t
        ) SELECT user_id, count(last_buy) AS after_buy, {_i('coalesce(sum(last_buy), 0)')} AS total FROM a GROUP BY user_id""",
    "op_interval_theta": f"""WITH o AS (SELECT o_custkey, epoch_us(o_orderdate) AS t FROM orders)
        SELECT a.o_custkey, count(*) AS pairs FROM o a JOIN o b ON a.o_custkey = b.o_custkey AND b.t > a.t AND b.t <= a.t + {168 * HOUR} GROUP BY ALL""",
    "op_grouping_sets": f"SELECT l_returnflag, l_linestatus, count(*) AS n, {_i('sum(l_linenumber)')} AS total FROM lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())",
    "op_cube": "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)",
    "op_pivot_methods": "SELECT user_id, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'purchase') AS purchase, count(*) FILTER (event_type = 'view') AS view FROM events GROUP BY user_id",
    "op_window_frames": f"""SELECT event_id, {_i('sum(event_id) OVER (w ROWS UNBOUNDED PRECEDING)')} AS running, {_i('sum(event_id) OVER (w ROWS BETWEEN 8 PRECEDING AND 8 FOLLOWING)')} AS centred,
        count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN {24 * HOUR} PRECEDING AND CURRENT ROW) AS last_day FROM events WINDOW w AS (PARTITION BY user_id ORDER BY epoch_us(ts), event_id)""",
    "op_rank_ntile": """SELECT o_orderkey, CAST(rank() OVER w AS INTEGER) AS rank, CAST(ntile(4) OVER w AS INTEGER) AS quarter, lag(o_orderkey, 1, -1) OVER w AS before, lead(o_orderkey, 1, -1) OVER w AS after
        FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey)""",
    "op_topk_per_track": """SELECT l_suppkey, CAST(place AS INTEGER) AS place, l_orderkey, l_extendedprice FROM (
        SELECT *, row_number() OVER (PARTITION BY l_suppkey ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber) AS place FROM lineitem) WHERE place <= 3""",
    "op_topk": "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20",
    "op_union_intersect_except": f"""WITH o AS (SELECT o_custkey AS k FROM orders), c AS (SELECT c_custkey AS k FROM customer)
        SELECT 'union' AS kind, count(*) AS n, {_i('coalesce(sum(k), 0)')} AS total FROM (SELECT * FROM o UNION ALL SELECT * FROM c)
        UNION ALL SELECT 'intersect', count(*), {_i('coalesce(sum(k), 0)')} FROM (SELECT * FROM o INTERSECT SELECT * FROM c)
        UNION ALL SELECT 'except', count(*), {_i('coalesce(sum(k), 0)')} FROM (SELECT * FROM c EXCEPT ALL SELECT DISTINCT * FROM o)""",
    "op_scalar_bits": "SELECT o_orderkey, bin(o_orderkey) AS bin, CAST(bit_count(o_orderkey) AS INTEGER) AS ones, o_orderkey << 3 AS left, xor(o_orderkey, 255) AS flipped, lpad(bin(o_orderkey), 24, '0') AS padded FROM orders",
    "op_scalar_dates": """SELECT o_orderkey, epoch_us(o_orderdate) AS micros, epoch_us(CAST(date_trunc('month', o_orderdate) AS TIMESTAMP)) AS month, CAST(year(o_orderdate) AS INTEGER) AS year, CAST(dayofyear(o_orderdate) AS INTEGER) AS day,
        epoch_us(o_orderdate) + 5 AS later FROM orders""",
    "op_array_hof": f"""WITH v AS (SELECT vec_id, [CAST(floor(CAST(x AS DOUBLE) * 1000 + 0.5) AS BIGINT) FOR x IN embedding] AS v FROM embeddings)
        SELECT vec_id, {_i('list_sum(v)')} AS total, CAST(len([x FOR x IN v IF x > 0]) AS INTEGER) AS positive, list_max(v) AS most, v[1] AS first, CAST(len(v[2:6]) AS INTEGER) AS sliced FROM v""",
    "op_json_props": f"SELECT event_type, {_i('sum(k)')} AS total, count(DISTINCT k) AS kinds, max(k) AS most FROM (SELECT event_type, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events) GROUP BY event_type",
    "op_percentiles": "SELECT l_returnflag, round(quantile_cont(l_quantity, 0.5), 6) AS median, round(quantile_cont(l_quantity, 0.9), 6) AS p90 FROM lineitem GROUP BY l_returnflag",
    "op_distinct_counts": "SELECT l_linestatus, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY l_linestatus",
    "op_tumbling": "SELECT epoch_us(time_bucket(INTERVAL 1 DAY, ts)) AS start, event_type, count(*) AS n FROM events GROUP BY ALL",
    "op_sliding": """WITH e AS (SELECT user_id, unnest([time_bucket(INTERVAL 1 DAY, ts), time_bucket(INTERVAL 1 DAY, ts) - INTERVAL 1 DAY]) AS w FROM events)
        SELECT epoch_us(w) AS start, count(*) AS n, count(DISTINCT user_id) AS users FROM e GROUP BY w""",
    "op_session": f"""WITH e AS (SELECT user_id, epoch_us(ts) AS t FROM events), g AS (SELECT *, CASE WHEN t - lag(t) OVER w < {12 * HOUR} THEN 0 ELSE 1 END AS new FROM e WINDOW w AS (PARTITION BY user_id ORDER BY t)),
        s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY t ROWS UNBOUNDED PRECEDING) AS s FROM g) SELECT user_id, min(t) AS start, count(*) AS n FROM s GROUP BY user_id, s""",
    "op_udf_varint": f"""WITH s AS (SELECT l_partkey, l_suppkey * 7 - l_partkey AS n FROM lineitem)
        SELECT l_partkey % 10 AS k, {_i(f'sum({bits("l_partkey", "2")})')} AS plain, {_i(f'sum({bits(zz1("n"), "1")})')} AS zero_free FROM s GROUP BY 1""",
    "op_stream_replay": f"SELECT event_type, count(*) AS n, {_i('sum(event_id)')} AS total FROM events GROUP BY event_type",
    "op_stream_dedupe": "SELECT DISTINCT user_id, event_type, epoch_us(ts) AS t FROM events",
    "op_late_rows": f"""WITH e AS (SELECT user_id, event_id, epoch_us(ts) AS t FROM events), s AS (SELECT *, max(t) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS seen FROM e)
        SELECT user_id, {_i(f'sum(CASE WHEN t < seen - {2 * HOUR} THEN 1 ELSE 0 END)')} AS late FROM s GROUP BY user_id""",
    "op_decode_range": f"WITH {signal(True)} SELECT track_id, count(*) AS n, min(j) * 100000 AS t_min, max(j) * 100000 AS t_max FROM sig WHERE axis = 0 AND j BETWEEN 10 AND 20 GROUP BY track_id",
}
