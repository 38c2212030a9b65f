"""The experiments, each one job a fixture: a grid of parameters against tracks."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from functools import partial, reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spectrack.functions import lanes, many
from spectrack.functions import numbers as N
from spectrack.functions import simplify as S
from spectrack.functions import theory
from spectrack.functions.params import CONSTANTS, OF_FIXTURE, CodecParams, derive
from spectrack.operators import blocks
from spectrack.plans import codec
from spectrack.plans import measures as M
from spectrack.sources import tables as D

METHODS = ("spectral", "cone_strong", "cone_weak", "pq")
#: what stands for the planar sets, and the factor of the error bounds on each
PLANAR = {"ev_user": 1.0, "ev_type_smooth": 1.0, "emb_cum": 0.01}
EPS = [10.0 * i for i in range(1, 11)]
ROW = "track_id string, n long, raw_bytes long, fixture string, method string, param string, value double, eps double, bytes long, kept long, n_corr long, max_sed double, sum_sed double"

# (method, param, value, eps, what to run), or with lists of params, values and bounds where one encoding serves several rows
Run = tuple[str, str | list[str], float | list[float], float | list[float], Callable]


def params(fixture: str, dim: int, eps: float, method: str = "spectral", **changes) -> CodecParams:
    """The fixture's own constants; a point precision of half the bound, or of a fifth for simplifiers."""
    return derive(eps, dim, OF_FIXTURE.get(f"{fixture}:{dim}", 0), **{"eps_p": (0.5 if method == "spectral" else 0.2) * eps, **changes})


class Spectral:
    """Sizes and errors of tracks by the codec; with coders, a list of one encoding's, its integers written with each."""

    def __init__(self, p: CodecParams, coders: list[dict] | None = None):
        self.variants, self.one = [p.with_(**c) for c in coders or [{}]], coders is None

    def many(self, tracks: list[tuple[np.ndarray, np.ndarray]], shared: dict | None = None) -> list:
        made = many.sized(tracks, self.variants, shared)
        return [x[0] for x in made] if self.one else made

    def __call__(self, t: np.ndarray, pos: np.ndarray) -> dict | list[dict]:
        return self.many([(t, pos)])[0]


class Baseline:
    """The same of tracks by a simplifier; of several (parameters, whether by the integer coder), each a row, one run of the
    priority queue serves all."""

    def __init__(self, method: str, variants: list[tuple[CodecParams, bool]], m: int = 16, one: bool = False):
        self.method, self.variants, self.m, self.one = method, variants, m, one

    def many(self, tracks: list[tuple[np.ndarray, np.ndarray]], shared: dict | None = None) -> list:
        made = lanes.simplified(self.method, tracks, self.variants, self.m)
        return [x[0] for x in made] if self.one else made

    def __call__(self, t: np.ndarray, pos: np.ndarray) -> dict | list[dict]:
        return self.many([(t, pos)])[0]


def _lengths(method: str, p: CodecParams, lengths: list[int], t: np.ndarray, pos: np.ndarray) -> list[dict]:
    """One path, its integers written with each chunk length."""
    return [{"n_corr": 0, **x} for x in S.coded(method, t, pos, p, lengths)]


def _run(fixture: str, method: str, eps: float, dim: int, encoded: bool = True, m: int = 16, **changes) -> Callable:
    p = params(fixture, dim, eps, method, **changes)
    return Spectral(p) if method == "spectral" else Baseline(method, [(p, encoded)], m, True)


def _over(fixture: str, methods: Sequence[str], param: str, values: Sequence[float], eps: list[float], dim: int, change: Callable[[float, float], dict] = lambda v, e: {}) -> list[Run]:
    """Runs of the methods over values of a parameter, at a bound each; a simplifier goes through its tracks once for all."""
    each = [(v, e, change(v, e)) for v, e in zip(values, eps, strict=True)]
    runs: list[Run] = [("spectral", param, v, e, _run(fixture, "spectral", e, dim, **c)) for v, e, c in each if "spectral" in methods]
    for m in methods:
        if m != "spectral":
            runs.append((m, [param] * len(each), list(values), eps, Baseline(m, [(params(fixture, dim, e, m, **c), True) for _, e, c in each])))
    return runs


def _sweep(spark: SparkSession, sf_dir: str, fixtures: dict[str, float], runs: Callable[[str, float], list[Run]], dim: int = 2) -> DataFrame:
    """runs(fixture, factor) for each fixture, one job a fixture."""
    made = []
    for name, factor in fixtures.items():
        grid = []
        for m, param, value, e, f in runs(name, factor):
            bounds = e if isinstance(e, list) else [e] * len(param)
            tags = [{"fixture": name, "method": m, "param": x, "value": float(v), "eps": y} for x, v, y in zip(param, value, bounds, strict=True)] if isinstance(param, list) else {"fixture": name, "method": m, "param": param, "value": float(value), "eps": e}
            grid.append((tags, f))
        points = D.FIXTURES[name](spark, sf_dir)
        if dim == 2 and name.startswith("li_"):
            points = points.withColumn("pos", F.slice("pos", 1, 2))
        made.append(codec.sweep(points, grid, ROW))
    return reduce(DataFrame.unionByName, made)


def summary(rows: DataFrame) -> DataFrame:
    """Sums over all tracks; errors and shares to six digits, and ratios to nine."""
    return rows.groupBy("fixture", "method", "param", "value", "eps").agg(
        F.sum("raw_bytes").alias("raw_bytes"), F.sum("bytes").alias("bytes"), F.round(M.compression_ratio(), 9).alias("ratio"), F.round(M.max_sed(), 6).alias("max_sed"), F.round(M.mean_sed(), 6).alias("mean_sed"),
        F.round(M.error_point_pct(), 6).alias("error_pct"), F.round(M.kept_ratio(), 6).alias("kept_ratio"), F.sum("n").alias("n"),
    )


def w0_dataset_summary(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = [M.describe(f(spark, sf_dir)).withColumn("fixture", F.lit(name)) for name, f in D.FIXTURES.items()]
    return reduce(DataFrame.unionByName, rows).withColumns({"gap_mean": F.round("gap_mean", 3), "gap_var": F.round("gap_var", 0)})


def w1_encode_ablation(spark: SparkSession, sf_dir: str, grid=EPS) -> DataFrame:
    """Baselines with and without the integer coder."""
    each = [(on, e) for on in (0, 1) for e in grid]
    runs = lambda n, f: [(m, ["encoded"] * len(each), [on for on, _ in each], [e * f for _, e in each], Baseline(m, [(params(n, 2, e * f, m), bool(on)) for on, e in each])) for m in METHODS[1:]]
    s = summary(_sweep(spark, sf_dir, PLANAR, runs))
    both = s.groupBy("fixture", "method", "eps").pivot("value", [0.0, 1.0]).agg(F.first("ratio"))
    both = both.withColumnRenamed("0.0", "plain_ratio").withColumnRenamed("1.0", "encoded_ratio")
    return both.withColumn("improvement", M.improvement(F.col("encoded_ratio") / F.col("plain_ratio")))


def w2_zigzag_ablation(spark: SparkSession, sf_dir: str, grid=EPS) -> DataFrame:
    """Classic against zero-free codes of the coefficients, at chunk lengths 1 and 2: the same integers, coded four times."""
    coders = [{"zero_free": z, "l_freq": k} for z in (False, True) for k in (1, 2)]
    names = [f"{'zero_free' if c['zero_free'] else 'classic'}_l{c['l_freq']}" for c in coders]
    runs = lambda n, f: [("spectral", names, [c["l_freq"] for c in coders], e * f, Spectral(params(n, 2, e * f), coders)) for e in grid]
    s = summary(_sweep(spark, sf_dir, PLANAR, runs))
    both = s.groupBy("fixture", "eps").pivot("param", sorted(names)).agg(F.first(F.col("bytes") / F.col("raw_bytes")))
    both = both.withColumn("improvement_l1", M.improvement(F.col("zero_free_l1") / F.col("classic_l1"))).withColumn("improvement_l2", M.improvement(F.col("zero_free_l2") / F.col("classic_l2")))
    return both.withColumns({c: F.round(c, 9) for c in both.columns[2:]})


def w3_block_size(spark: SparkSession, sf_dir: str, grid=(4, 8, 16, 32, 64, 128, 256, 512), eps=(20.0, 50.0, 80.0)) -> DataFrame:
    runs = lambda n, f: [("spectral", "b_s", b, e * f, _run(n, "spectral", e * f, 2, b_s=b)) for b in grid for e in eps]
    return summary(_sweep(spark, sf_dir, PLANAR, runs))


def w4_retention(spark: SparkSession, sf_dir: str, grid=tuple(2.0**-i for i in range(8)), eps: float = 50.0) -> DataFrame:
    runs = lambda n, f: [("spectral", "r_ret", r, eps * f, _run(n, "spectral", eps * f, 2, r_ret=r, b_s=128)) for r in grid]
    return summary(_sweep(spark, sf_dir, PLANAR, runs))


def w5_ratio_vs_eps(spark: SparkSession, sf_dir: str, grid=EPS) -> DataFrame:
    """All methods over the bounds; `relative` is the spectral codec's ratio over the method's."""
    runs = lambda n, f: _over(n, METHODS, "eps", grid, [e * f for e in grid], 2)
    s = summary(_sweep(spark, sf_dir, PLANAR, runs))
    return M.relative(s, "ratio", "spectral", ["fixture", "eps"]).withColumn("relative", 1 / F.col("relative")).withColumn("improvement", M.improvement(F.col("relative")))


def w6_chunk_length(spark: SparkSession, sf_dir: str, grid=tuple(range(1, 8)), eps: float = 50.0) -> DataFrame:
    """Chunk lengths of all methods; a track is encoded, or simplified, once a method."""
    k = list(grid)
    runs = lambda n, f: [(m, ["l"] * len(k), k, eps * f, Spectral(params(n, 2, eps * f, m), [{"l": x, "l_freq": x} for x in k]) if m == "spectral" else partial(_lengths, m, params(n, 2, eps * f, m), k)) for m in METHODS]
    return summary(_sweep(spark, sf_dir, PLANAR, runs))


def w7_freq_precision(spark: SparkSession, sf_dir: str, grid=(0.2, 0.3, 0.4, 0.5, 0.6, 0.8, 1.0, 1.2), eps: float = 50.0) -> DataFrame:
    planar = _sweep(spark, sf_dir, PLANAR, lambda n, f: [("spectral", "a", a, eps * f, _run(n, "spectral", eps * f, 2, eps_f=eps * f / a)) for a in grid])
    solid = _sweep(spark, sf_dir, {"li_supp_smooth": 1.0}, lambda n, f: [("spectral", "a", a, eps * f, _run(n, "spectral", eps * f, 3, eps_f=eps * f / a)) for a in grid], 3)
    return summary(planar.unionByName(solid))


def w8_point_precision(spark: SparkSession, sf_dir: str, grid=(0.05, 0.1, 0.2, 0.3, 0.4, 0.5, 0.6), eps: float = 50.0) -> DataFrame:
    runs = lambda n, f: _over(n, METHODS, "eps_p", grid, [eps * f] * len(grid), 2, lambda x, e: {"eps_p": x * e})
    return summary(_sweep(spark, sf_dir, PLANAR, runs))


def w9_mean_error(spark: SparkSession, sf_dir: str, grid=EPS) -> DataFrame:
    """Mean errors over the bounds, and what the theory expects of the spectral codec at its frequency precision."""
    runs = lambda n, f: _over(n, METHODS, "eps", grid, [e * f for e in grid], 2)
    s = summary(_sweep(spark, sf_dir, PLANAR, runs))
    wide = s.groupBy("fixture", "eps").pivot("method", list(METHODS)).agg(F.first("mean_sed"))
    share = F.create_map(*[F.lit(x) for n in PLANAR for x in (n, theory.mean_track_error(CONSTANTS[OF_FIXTURE.get(f"{n}:2", 0)].a, 2))])
    wide = wide.withColumn("theory", share[F.col("fixture")] * F.col("eps"))
    return wide.withColumn("reduction", M.error_reduction(F.col("spectral"), F.col("cone_weak")))


def w10_three_d(spark: SparkSession, sf_dir: str, grid=EPS) -> DataFrame:
    runs = lambda n, f: _over(n, ("spectral", "pq"), "eps", grid, [e * f for e in grid], 3)
    s = summary(_sweep(spark, sf_dir, {"li_supp_smooth": 1.0, "li_supp": 1.0}, runs, 3))
    return M.relative(s, "ratio", "pq", ["fixture", "eps"])


def w11_formula_vs_search(spark: SparkSession, sf_dir: str, grid=(4, 8, 16, 32, 64, 128), retained=(1.0, 0.5, 0.25), eps=(10.0, 50.0, 90.0)) -> DataFrame:
    """How far the formulas' block size and retention are from the best of a grid over both, at each bound."""

    def runs(n: str, f: float) -> list[Run]:
        searched = [("search", f"r_ret={r}", b, e * f, _run(n, "spectral", e * f, 2, b_s=b, r_ret=r)) for b in grid for r in retained for e in eps]
        return searched + [("formula", "", 0, e * f, _run(n, "spectral", e * f, 2)) for e in eps]

    s = summary(_sweep(spark, sf_dir, PLANAR, runs)).withColumn("ratio", F.col("bytes") / F.col("raw_bytes"))
    r = F.regexp_extract("param", "r_ret=(.*)", 1).try_cast("double")
    found = M.best(s.filter("method = 'search'").withColumn("best", F.struct(F.col("value").alias("b_s"), r.alias("r_ret"))), ["fixture", "eps"], "best", "ratio")
    formula = s.filter("method = 'formula'").select("fixture", "eps", F.col("ratio").alias("formula_ratio"))
    both = found.join(formula, ["fixture", "eps"]).select("fixture", "eps", F.col("best_best.b_s").alias("best_b_s"), F.col("best_best.r_ret").alias("best_r_ret"), "best_ratio", "formula_ratio")
    return both.withColumn("gap", F.col("formula_ratio") / F.col("best_ratio") - 1).withColumns({c: F.round(c, 9) for c in ("best_ratio", "formula_ratio", "gap")})


def w12_polygon_sides(spark: SparkSession, sf_dir: str, grid=(4, 8, 16, 32), eps: float = 50.0) -> DataFrame:
    runs = lambda n, f: [(c, "m", m, eps * f, _run(n, c, eps * f, 2, True, m)) for c in ("cone_strong", "cone_weak") for m in grid]
    return summary(_sweep(spark, sf_dir, PLANAR, runs))


def w13_trapezoid(spark: SparkSession, sf_dir: str, n: int = 257, b_s: int = 64) -> DataFrame:
    """Rest, accelerate, cruise, brake: energy in the low quarter of the spectrum, by DataFrame functions only;
    then the same of a smooth track set."""
    j = F.col("id")
    speed = F.when(j < 32, 0.0).when(j < 96, (j - 32) / 4.0).when(j < 176, 16.0).when(j < 240, (240 - j) / 4.0).otherwise(0.0)
    from pyspark.sql.window import Window as W

    made = spark.range(n).select(F.lit("profile").alias("track_id"), F.lit(0).alias("frag_id"), F.lit(0).alias("axis"), j.alias("j"), F.sum(speed).over(W.orderBy("id").rowsBetween(W.unboundedPreceding, 0)).alias("s"))
    profile = M.energy(blocks.coefficients(blocks.velocities(made, b_s), b_s)).withColumn("fixture", F.lit("trapezoid"))
    cum = blocks.axes(blocks.from_clock(D.emb_cum(spark, sf_dir), 100_000))
    smooth = M.energy(blocks.coefficients(blocks.velocities(cum, 32), 32)).withColumn("fixture", F.lit("emb_cum"))
    return profile.unionByName(smooth).withColumn("low_share", F.round("low_share", 6))


def w14_interval(spark: SparkSession, sf_dir: str, grid=(0.5, 0.75, 1.0, 1.5, 2.0), eps: float = 50.0) -> DataFrame:
    """The resampling interval as a multiple of the rule's."""
    some = {k: v for k, v in PLANAR.items() if k != "emb_cum"}
    runs = lambda n, f: [("spectral", "dt", s, eps * f, _run(n, "spectral", eps * f, 2, dt_scale=s)) for s in grid]
    return summary(_sweep(spark, sf_dir, some, runs))


#: what each variant changes; truncation against none, since the rule's own retention may keep everything
ABLATIONS = {
    "rule": {}, "no_truncation": {"r_ret": 1.0}, "truncated_to_a_quarter": {"r_ret": 0.25}, "one_block": {"blocks": False}, "classic_zigzag": {"zero_free": False},
    "open_ends": {"ends": "open"}, "not_validated": {"validate": False}, "positions": {"positions": True},
}


def w15_ablations(spark: SparkSession, sf_dir: str, eps: float = 50.0) -> DataFrame:
    """The codec without one of its parts at a time: sizes and errors. Only the variant that is not validated may
    pass the bound."""
    runs = lambda n, f: [("spectral", name, 0, eps * f, _run(n, "spectral", eps * f, 2, **change)) for name, change in ABLATIONS.items()]
    return summary(_sweep(spark, sf_dir, PLANAR, runs))


def bit_table(codes: DataFrame, code: str) -> DataFrame:
    """Bits of all codes at every chunk length, from one pass over the codes."""
    spark = codes.sparkSession
    lengths = F.broadcast(spark.range(1, 8).select(F.col("id").cast("int").alias("l")))
    n = F.col(code)
    return codes.crossJoin(lengths).groupBy("l").agg(
        F.sum(N.bits(N.zz(n), F.col("l"))).alias("zigzag_bits"), F.sum(N.bits(N.zz1(n), F.col("l")) - F.when(F.col("l") == 1, 1).otherwise(0)).alias("zero_free_bits")
    )


ALL = {
    f.__name__: f
    for f in (
        w0_dataset_summary, w1_encode_ablation, w2_zigzag_ablation, w3_block_size, w4_retention, w5_ratio_vs_eps, w6_chunk_length, w7_freq_precision,
        w8_point_precision, w9_mean_error, w10_three_d, w11_formula_vs_search, w12_polygon_sides, w13_trapezoid, w14_interval, w15_ablations,
    )
}
