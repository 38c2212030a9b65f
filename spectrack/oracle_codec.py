"""The whole codec in DuckDB's SQL: fragments, resampling, blocks, codes, decoding, corrections and sizes, for a grid of
parameters over several sets of tracks. Written from the definitions, so that it shares nothing with the kernels."""

from __future__ import annotations

import math

from spectrack.functions.params import CodecParams

Cell = tuple[str, CodecParams]  # fixture and parameters


def bits(u: str, l: str) -> str:  # noqa: E741
    return f"CAST(ceil(length(bin(CAST({u} AS BIGINT))) / CAST({l} AS DOUBLE)) * ({l} + 1) AS BIGINT)"


def zz(n: str) -> str:
    return f"(CASE WHEN {n} >= 0 THEN 2 * {n} ELSE -2 * {n} - 1 END)"


def zz1(n: str) -> str:
    return f"(CASE WHEN {n} >= 0 THEN 2 * {n} + 1 ELSE -2 * {n} END)"


def _d(x: float) -> str:
    return f"CAST('{x!r}' AS DOUBLE)"


def codec(cells: list[Cell], dim: int, p: str = "") -> str:
    """CTEs up to {p}res(g, fixture, track_id, n, raw, size, corr, off, max_sed, sum_sed, sections) from
    {p}pts(fixture, track_id, t, x0, x1, ...), whose track ids no two fixtures share; g numbers the cells. Time precision 1; no speed rule, or the same for all."""
    shapes = list(dict.fromkeys((f, c.b_s, c.dt_scale, c.blocks, c.positions) for f, c in cells))
    v_max = {c.v_max for _, c in cells}
    if len(v_max) > 1 or {c.eps_t for _, c in cells} != {1} or {c.gap_mean for _, c in cells} != {"inclusive"}:
        raise ValueError("one speed limit, microseconds and inclusive means only")
    (v_max,) = v_max
    root = math.sqrt(dim)
    grid = ", ".join(
        f"({g}, {shapes.index((f, c.b_s, c.dt_scale, c.blocks, c.positions))}, '{f}', {_d(c.eps)}, {_d(c.eps_f)}, {_d(c.r_ret)}, {_d(c.eps_p)}, {_d(c.eps_p / root)}, {_d(2 * c.eps / root)}, {str(c.zero_free).lower()}, {c.l}, {c.l_freq}, "
        f"{str(c.ends == 'closed').lower()}, {str(c.validate).lower()}, {str(c.positions).lower()})"
        for g, (f, c) in enumerate(cells)
    )
    shape = ", ".join(f"({i}, '{f}', {b}, {_d(s)}, {b if blocks else 1 << 40}, {str(pos).lower()})" for i, (f, b, s, blocks, pos) in enumerate(shapes))
    xs = [f"x{a}" for a in range(dim)]
    fast = "false" if v_max is None else "coalesce(sqrt(" + " + ".join(f"pow({x} - lag({x}) OVER w, 2)" for x in xs) + f") > (t - lag(t) OVER w) / 1e6 * {_d(v_max)}, false)"
    new = "(e.f OR (e.t - e.b) > b_s * CASE WHEN e.i - a.at = 1 THEN first ELSE (e.t - a.t) / (e.i - a.at) END)"
    lerp = ", ".join(f"q.{x} + (q.n{x} - q.{x}) * (CAST(m.at - q.t AS DOUBLE) / (q.t2 - q.t)) AS {x}" for x in xs)
    key, own = "g, track_id, frag, axis", "s, track_id, frag, axis"
    return f"""
{p}grid(g, sh, fixture, eps, eps_f, r_ret, eps_p, e_d, o_step, zero_free, l, l_freq, closed, validate, pos) AS (VALUES {grid}),
{p}shape(sh, fixture, b_s, dt_scale, block, pos) AS (VALUES {shape}),
{p}pt AS (SELECT *, row_number() OVER w - 1 AS i, t - lag(t) OVER w AS gap, lag(t) OVER w AS before, {fast} AS fast FROM {p}pts WINDOW w AS (PARTITION BY fixture, track_id ORDER BY t)),
{p}tr AS (SELECT fixture, track_id, count(*) AS n, min(t) AS ta, min(gap) AS least, trunc(median(gap)) AS first, {"count(*) > 2 AND min(gap) = max(gap)" if v_max is None else "false"} AS uniform FROM {p}pt GROUP BY ALL),
{p}bs AS (SELECT DISTINCT fixture, b_s FROM {p}shape),
{p}sus AS (SELECT fixture, track_id, b_s, ta, first, list({{'i': i, 't': t, 'b': before, 'f': fast}} ORDER BY i) AS es FROM {p}pt JOIN {p}tr USING (fixture, track_id) JOIN {p}bs USING (fixture)
    WHERE NOT uniform AND (fast OR gap > b_s * least(first, least)) GROUP BY ALL),
{p}brk AS (SELECT fixture, track_id, b_s, unnest(list_reduce(es, lambda a, e: {{'at': CASE WHEN {new} THEN e.i ELSE a.at END, 't': CASE WHEN {new} THEN e.t ELSE a.t END, 'found': CASE WHEN {new} THEN list_append(a.found, e.i) ELSE a.found END}},
    {{'at': CAST(0 AS BIGINT), 't': ta, 'found': CAST([] AS BIGINT[])}}).found) AS i FROM {p}sus),
{p}fr AS (SELECT p.*, b_s, sum(CASE WHEN k.i IS NULL THEN 0 ELSE 1 END) OVER (PARTITION BY p.fixture, p.track_id, b_s ORDER BY p.i ROWS UNBOUNDED PRECEDING) AS frag FROM {p}pt p JOIN {p}bs USING (fixture) LEFT JOIN {p}brk k USING (fixture, track_id, b_s, i)),
{p}fs AS (SELECT fixture, track_id, b_s, frag, count(*) AS m, min(t) AS t0, max(t) AS t9 FROM {p}fr GROUP BY ALL),
{p}dts AS (SELECT sh AS s, track_id, CASE WHEN any_value(uniform) OR any_value(dt_scale) = 1 THEN any_value(dt) ELSE greatest(1, floor(any_value(dt) * any_value(dt_scale) + 0.5)) END AS dt FROM {p}shape JOIN (
    SELECT fixture, track_id, b_s, any_value(uniform) AS uniform, CASE WHEN any_value(uniform) THEN any_value(least) ELSE greatest(1, floor(coalesce(CAST(sum(t9 - t0) FILTER (m > 2) AS DOUBLE) / sum(m) FILTER (m > 2), 0) + 0.5)) END AS dt
    FROM {p}fs JOIN {p}tr USING (fixture, track_id) GROUP BY ALL) USING (fixture, b_s) GROUP BY ALL),
{p}sp AS (SELECT sh AS s, d.track_id, frag, t0, t9, CAST(dt AS BIGINT) AS dt, CAST(ceil(CAST(t9 - t0 AS DOUBLE) / dt) AS BIGINT) + 1 AS m2, b_s, block, pos FROM {p}shape JOIN {p}fs USING (fixture, b_s) JOIN {p}dts d ON d.s = sh AND d.track_id = {p}fs.track_id WHERE m > 2),
{p}mk AS (SELECT *, least(t0 + j * dt, t9) AS at, CASE WHEN j = 0 THEN t0 + 1 ELSE least(t0 + j * dt, t9) END AS ak FROM (SELECT *, unnest(range(0, m2)) AS j FROM {p}sp)),
{p}pr AS (SELECT * FROM (SELECT track_id, b_s, frag, t, {", ".join(xs)}, lead(t) OVER w AS t2, {", ".join(f"lead({x}) OVER w AS n{x}" for x in xs)} FROM {p}fr WINDOW w AS (PARTITION BY track_id, b_s, frag ORDER BY t)) WHERE t2 IS NOT NULL),
{p}us AS (SELECT m.s, m.track_id, m.frag, m.j, m.block, m.pos, {lerp} FROM {p}mk m ASOF JOIN {p}pr q ON m.track_id = q.track_id AND m.b_s = q.b_s AND m.frag = q.frag AND m.ak > q.t),
{p}ul AS ({" UNION ALL ".join(f"SELECT s, track_id, frag, j, block, pos, {a} AS axis, x{a} AS x FROM {p}us" for a in range(dim))}),
{p}vd AS (SELECT *, x - lag(x) OVER (PARTITION BY {own} ORDER BY j) AS v FROM {p}ul),
{p}vl AS (SELECT *, count(*) OVER w AS len, x - v AS xa, first_value(x - v) OVER wo AS start, last_value(x) OVER wo AS finish FROM (SELECT *, (j - 1) // block AS blk, (j - 1) % block AS i FROM {p}vd WHERE j > 0)
    WINDOW w AS (PARTITION BY {own}, blk), wo AS (PARTITION BY {own}, blk ORDER BY j ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)),
{p}bl AS (SELECT {own}, blk, any_value(len) AS len, any_value(start) AS start, any_value(finish) AS finish FROM {p}vl GROUP BY ALL),
{p}in0 AS (SELECT {own}, blk, i, len, pos, CASE WHEN pos THEN xa - start - (finish - start) / len * i ELSE v - (finish - start) / len END AS u FROM {p}vl),
{p}co AS (SELECT {own}, blk, len, k, 2 * sum(u * cos((2 * i + 1) * k * pi() / (2 * len))) AS c FROM {p}in0, LATERAL (SELECT unnest(range(CASE WHEN pos THEN 0 ELSE 1 END, len)) AS k) GROUP BY {own}, blk, len, k),
{p}cd AS (SELECT g, track_id, frag, axis, blk, len, k, CAST(floor(c / (2 * eps_f) + 0.5) AS BIGINT) AS code FROM {p}co JOIN {p}grid ON s = sh WHERE k < greatest(1, least(len, floor(len * r_ret + 0.5)))),
{p}nz AS (SELECT * FROM {p}cd WHERE code <> 0),
{p}cf AS (SELECT b.*, coalesce(c_f, 0) AS c_f FROM (SELECT g, track_id, frag, axis, blk, len, start, finish, pos, closed, eps_p, e_d, l FROM {p}bl JOIN {p}grid ON s = sh) b LEFT JOIN (SELECT {key}, blk, max(k) AS top FROM {p}nz GROUP BY ALL) z USING (g, track_id, frag, axis, blk),
    LATERAL (SELECT CASE WHEN top IS NULL THEN 0 WHEN pos THEN top + 1 ELSE top END AS c_f)),
{p}an AS (SELECT g, track_id, frag, axis, CAST(floor(x / (2 * eps_p) + 0.5) AS BIGINT) AS a, x, l FROM {p}ul u JOIN {p}grid ON s = sh WHERE j = 0),
{p}e0 AS (SELECT cf.*, a, CASE WHEN closed THEN floor((finish - a * (2 * eps_p)) / (2 * e_d) + 0.5) ELSE floor((finish - start) / (2 * e_d) + 0.5) END AS raw FROM {p}cf cf JOIN {p}an USING (g, track_id, frag, axis)),
{p}en AS (SELECT *, CAST(CASE WHEN closed THEN raw - coalesce(lag(raw) OVER w, 0) ELSE raw END AS BIGINT) AS code, CASE WHEN closed THEN raw ELSE sum(raw) OVER (w ROWS UNBOUNDED PRECEDING) END AS total FROM {p}e0 WINDOW w AS (PARTITION BY {key} ORDER BY blk)),
{p}iv AS (SELECT z.g, track_id, frag, axis, blk, i, sum(CASE WHEN k = 0 THEN 0.5 ELSE 1 END * code * (2 * eps_f) * cos((2 * i + 1) * k * pi() / (2 * z.len)) / z.len) AS dv FROM {p}nz z JOIN {p}grid USING (g), LATERAL (SELECT unnest(range(0, z.len)) AS i) GROUP BY ALL),
{p}dc AS (SELECT v.g, v.track_id, v.frag, v.axis, v.j, CASE WHEN v.i = v.len - 1 THEN e.a * (2 * eps_p) + e.total * (2 * e_d)
        WHEN v.pos THEN e.a * (2 * eps_p) + (e.total - e.code) * (2 * e_d) + e.code * (2 * e_d) * ((v.i + 1) / CAST(v.len AS DOUBLE)) + coalesce(n.dv, 0)
        ELSE e.a * (2 * eps_p) + (e.total - e.code) * (2 * e_d) + (v.i + 1) * (e.code * (2 * e_d) / v.len) + sum(coalesce(d.dv, 0)) OVER (PARTITION BY v.g, v.track_id, v.frag, v.axis, v.blk ORDER BY v.i ROWS UNBOUNDED PRECEDING) END AS y
    FROM (SELECT g, track_id, frag, axis, blk, i, j, len, {p}vl.pos AS pos FROM {p}vl JOIN {p}grid ON s = sh) v JOIN {p}en e USING (g, track_id, frag, axis, blk) LEFT JOIN {p}iv d USING (g, track_id, frag, axis, blk, i)
    LEFT JOIN {p}iv n ON v.pos AND n.g = v.g AND n.track_id = v.track_id AND n.frag = v.frag AND n.axis = v.axis AND n.blk = v.blk AND n.i = v.i + 1
    UNION ALL SELECT g, track_id, frag, axis, 0, a * (2 * eps_p) FROM {p}an JOIN {p}grid USING (g)),
{p}pl AS (SELECT * FROM ({" UNION ALL ".join(f"SELECT fixture, track_id, b_s, frag, i, t, {a} AS axis, x{a} AS x FROM {p}fr" for a in range(dim))}) JOIN {p}shape USING (fixture, b_s)),
{p}al AS (SELECT sh AS s, f.track_id, f.frag, i, t, axis, x, greatest(0, least(CAST(ceil(CAST(t - t0 AS DOUBLE) / dt) AS BIGINT) - 1, m2 - 2)) AS j, t - t0 AS rest, dt FROM {p}pl JOIN (SELECT s, track_id, frag, t0, dt, m2 FROM {p}sp) f ON f.s = sh AND f.track_id = {p}pl.track_id AND f.frag = {p}pl.frag),
{p}bk AS (SELECT a.g, a.track_id, a.i, a.t, a.axis, a.x, d1.y + (d2.y - d1.y) * least(1, greatest(0, CAST(rest - a.j * dt AS DOUBLE) / dt)) AS y FROM (SELECT g, {p}al.* FROM {p}al JOIN {p}grid ON s = sh) a
    JOIN {p}dc d1 ON d1.g = a.g AND d1.track_id = a.track_id AND d1.frag = a.frag AND d1.axis = a.axis AND d1.j = a.j JOIN {p}dc d2 ON d2.g = a.g AND d2.track_id = a.track_id AND d2.frag = a.frag AND d2.axis = a.axis AND d2.j = a.j + 1),
{p}ol AS (SELECT g, track_id, i, t, axis, x, CAST(floor(x / o_step + 0.5) AS BIGINT) AS code, o_step, l FROM {p}pl JOIN {p}fs USING (fixture, track_id, b_s, frag) JOIN {p}grid ON {p}grid.sh = {p}pl.sh WHERE m <= 2),
{p}ba AS (SELECT * FROM {p}bk UNION ALL SELECT g, track_id, i, t, axis, x, code * o_step FROM {p}ol),
{p}er AS (SELECT b.*, sqrt(sum((x - y) * (x - y)) OVER (PARTITION BY g, track_id, i)) AS sed, CAST(floor((x - y) / (2 * e_d) + 0.5) AS BIGINT) AS fix, eps, e_d, l, validate FROM {p}ba b JOIN {p}grid USING (g)),
{p}fx AS (SELECT *, sed > eps * (1 - CAST('1e-09' AS DOUBLE)) AS off FROM {p}er),
{p}pe AS (SELECT g, track_id, i, any_value(off) AS off, sqrt(sum(pow(x - y - CASE WHEN off AND validate THEN fix * (2 * e_d) ELSE 0 END, 2))) AS sed FROM {p}fx GROUP BY g, track_id, i),
{p}ag AS (SELECT g, track_id, count(*) AS n, count(*) FILTER (off) AS off, max(sed) AS max_sed, sum(sed) AS sum_sed FROM {p}pe GROUP BY g, track_id),
{p}sec AS (
    SELECT g, track_id, 'header' AS section, {bits("any_value(dt)", "any_value(l)")} + {bits("count(t0)", "any_value(l)")} AS b FROM (SELECT g, d.track_id, d.dt, l, p.t0 FROM {p}dts d JOIN {p}grid ON d.s = sh LEFT JOIN {p}sp p ON p.s = d.s AND p.track_id = d.track_id) GROUP BY g, track_id
    UNION ALL SELECT a.g, a.track_id, 'outliers', {bits("count(t)", "any_value(gr.l)")} FROM {p}ag a JOIN {p}grid gr USING (g) LEFT JOIN (SELECT g, track_id, t FROM {p}ol WHERE axis = 0) o USING (g, track_id) GROUP BY a.g, a.track_id
    UNION ALL SELECT g, track_id, 'outliers', sum({bits(zz("dt"), "l")}) FROM (SELECT g, track_id, l, t - coalesce(lag(t) OVER (PARTITION BY g, track_id ORDER BY t), 0) AS dt FROM {p}ol WHERE axis = 0) GROUP BY ALL
    UNION ALL SELECT g, track_id, 'outliers', sum({bits(zz("dc"), "l")}) FROM (SELECT g, track_id, l, code - coalesce(lag(code) OVER (PARTITION BY g, track_id, axis ORDER BY t), 0) AS dc FROM {p}ol) GROUP BY ALL
    UNION ALL SELECT g, track_id, 'corrections', {bits("any_value(CASE WHEN validate THEN off ELSE 0 END)", "any_value(l)")} FROM {p}ag JOIN {p}grid USING (g) GROUP BY g, track_id
    UNION ALL SELECT g, track_id, 'corrections', sum({bits(zz("dt"), "l")}) FROM (SELECT g, track_id, l, t - coalesce(lag(t) OVER (PARTITION BY g, track_id ORDER BY t), 0) AS dt FROM {p}fx WHERE off AND validate AND axis = 0) GROUP BY ALL
    UNION ALL SELECT g, track_id, 'corrections', sum({bits(zz1("fix"), "l")}) FROM {p}fx WHERE off AND validate GROUP BY ALL
    UNION ALL SELECT g, track_id, 'fragments', sum({bits(zz("dt"), "l")} + {bits("m2", "l")}) FROM (SELECT g, track_id, l, m2, t0 - coalesce(lag(t0) OVER (PARTITION BY g, track_id ORDER BY t0), 0) AS dt FROM {p}sp JOIN {p}grid ON s = sh) GROUP BY ALL
    UNION ALL SELECT g, track_id, 'anchors', sum({bits(zz("a"), "l")}) FROM {p}an GROUP BY ALL
    UNION ALL SELECT g, track_id, 'ends', sum({bits(zz("code"), "l")}) FROM {p}en GROUP BY ALL
    UNION ALL SELECT g, track_id, 'lengths', sum({bits("c_f", "l")}) FROM {p}cf GROUP BY ALL
    UNION ALL SELECT g, track_id, 'coefficients', sum(CASE WHEN zero_free THEN {bits(zz1("code"), "l_freq")} - CASE WHEN l_freq = 1 THEN 1 ELSE 0 END ELSE {bits(zz("code"), "l_freq")} END)
        FROM {p}cd JOIN {p}cf USING (g, track_id, frag, axis, blk) JOIN {p}grid USING (g) WHERE k <= c_f - CASE WHEN {p}cf.pos THEN 1 ELSE 0 END GROUP BY ALL
),
{p}res AS (SELECT g, fixture, track_id, n, {8 * (dim + 1)} * n AS raw, 18 + CAST(ceil(b / 8.0) AS BIGINT) AS size, off, max_sed, sum_sed FROM {p}ag JOIN (SELECT g, track_id, sum(b) AS b FROM {p}sec GROUP BY ALL) USING (g, track_id) JOIN {p}grid USING (g))"""
