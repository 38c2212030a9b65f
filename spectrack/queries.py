"""Named queries over the given tables: methods, baselines, measures, workloads and the operators around them."""

from __future__ import annotations

import math
from collections.abc import Callable
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from spectrack.functions import many
from spectrack.functions import numbers as N
from spectrack.functions import simplify as S
from spectrack.functions import sqlfuncs, theory
from spectrack.functions import track as K
from spectrack.functions.params import CONSTANTS, OF_FIXTURE, CodecParams, derive
from spectrack.functions.spectral import dct
from spectrack.operators import blocks as B
from spectrack.operators import points as P
from spectrack.plans import codec, expr, workloads
from spectrack.plans import measures as M
from spectrack.sources import tables as D
from spectrack.sources.stage import staged
from spectrack.streaming import streams

HOUR = 3_600_000_000
V_MAX = 0.05
DAY_SPEED = 20 / 86_400
EPS, B_S = 0.5, 32
EPS_F, EPS_P = EPS / 0.6, 0.25
STEP = 100_000


def r(x, digits: int):
    return F.round(x, digits)


def xy(df: DataFrame, *keep: str, digits: int = 3, dim: int = 2) -> DataFrame:
    return df.select(*keep, *[r(F.col("pos")[i], digits).alias("xyz"[i]) for i in range(dim)])


def _cum(spark, d) -> DataFrame:
    return B.axes(B.from_clock(D.emb_cum(spark, d), STEP))


def _decoded(spark, d, eps_f: float = EPS_F) -> DataFrame:
    return B.reconstructed(_cum(spark, d), B_S, eps_f, EPS_P, 2)


def _user_fragments(spark, d) -> DataFrame:
    return P.split_outliers(P.speed_breaks(D.ev_user(spark, d), V_MAX))


def q_describe_tracks(spark, d):
    m = M.describe(D.ev_user(spark, d))
    return m.select("tracks", "points", r("gap_mean", 3).alias("gap_mean"), r("gap_var", 0).alias("gap_var"))


def q_dedupe(spark, d):
    raw = D.table(spark, d, "lineitem").select(F.col("l_suppkey").cast("string").alias("track_id"), D.micros("l_shipdate").alias("t"), F.array(F.col("l_quantity")).alias("pos"), "l_orderkey", "l_linenumber")
    one = P.dedupe(raw, 86_400_000_000, [F.col("l_orderkey"), F.col("l_linenumber"), F.col("pos")])
    return one.groupBy("track_id").agg(F.count(F.lit(1)).alias("kept"), F.sum(F.col("pos")[0]).alias("quantity"), F.min("t").alias("t_min"))


def q_speed_breaks(spark, d):
    return P.speed_breaks(D.ev_user(spark, d), V_MAX).select("track_id", "t", "frag_id")


def q_fragments(spark, d):
    pts = D.ev_user(spark, d)
    a = P.fragments(pts, 4, HOUR, V_MAX).select("track_id", "t", F.col("frag_id").alias("inclusive"))
    b = P.fragments(pts, 4, HOUR, V_MAX, "exclusive").select("track_id", "t", F.col("frag_id").alias("exclusive"))
    return a.join(b, ["track_id", "t"])


def q_outlier_split(spark, d):
    f = P.split_outliers(P.speed_breaks(D.ord_cust(spark, d), DAY_SPEED))
    return f.groupBy("track_id").agg((F.max("frag_id") + 1).alias("fragments"), F.sum(F.col("outlier").cast("int")).alias("outliers"))


def q_interval(spark, d):
    return P.interval(_user_fragments(spark, d), 1000)


def _resampled(spark, d) -> tuple[DataFrame, DataFrame]:
    f = _user_fragments(spark, d).filter("NOT outlier")
    f = f.join(P.interval(f, 1000), "track_id")
    return f, P.to_uniform(f, F.col("dt"))


def q_resample(spark, d):
    return xy(_resampled(spark, d)[1], "track_id", "frag_id", "j")


def q_block_velocity(spark, d):
    v = B.velocities(B.axes(B.from_clock(D.emb_uniform(spark, d), STEP)), 16)
    return v.select("track_id", "axis", "j", "block_id", "len", F.floor(F.col("v") * 1e9 + 0.5).alias("v"), F.floor(F.col("centred") * 1e6 + 0.5137).alias("centred"))


def q_dct_codes(spark, d):
    return B.codes(B.coefficients(B.velocities(_cum(spark, d), B_S), B_S), EPS_F).select("track_id", "axis", "block_id", "k", "code")


def q_truncate_trim(spark, d):
    t = B.trimmed(B.codes(B.coefficients(B.velocities(_cum(spark, d), B_S), B_S, 0.25), EPS_F))
    return t.select("track_id", "axis", "block_id", "len", "c_f", F.aggregate("codes", F.lit(0).cast("long"), lambda a, x: a + x).alias("total"))


def q_block_ends(spark, d):
    s = _cum(spark, d)
    a = B.block_ends(s, B_S, EPS_P, 2).select("track_id", "axis", "block_id", F.col("code").alias("closed"))
    b = B.block_ends(s, B_S, EPS_P, 2, "open").select("track_id", "axis", "block_id", F.col("code").alias("open"))
    return a.join(b, ["track_id", "axis", "block_id"])


def _lengths(spark) -> DataFrame:
    return F.broadcast(spark.range(1, 8).select(F.col("id").cast("int").alias("l")))


def _signed(spark, d) -> DataFrame:
    return D.table(spark, d, "lineitem").select("l_partkey", (F.col("l_suppkey") * 7 - F.col("l_partkey")).alias("n"))


def q_varint_bits(spark, d):
    return _signed(spark, d).crossJoin(_lengths(spark)).groupBy("l").agg(F.sum(N.bits(F.col("l_partkey"), F.col("l"))).alias("bits"))


def q_zigzag_bits(spark, d):
    return workloads.bit_table(_signed(spark, d), "n").select("l", "zigzag_bits")


def q_zerofree_bits(spark, d):
    return workloads.bit_table(_signed(spark, d), "n").select("l", "zero_free_bits")


def q_delta_lossless(spark, d):
    s = D.int_signal(spark, d)
    w = W.partitionBy("signal").orderBy("i", "j")
    step = s.withColumn("step", F.col("n") - F.coalesce(F.lag("n").over(w), F.lit(0)))
    return step.groupBy("signal").agg(F.count(F.lit(1)).alias("n"), F.sum(N.bits(N.zz(F.col("step")), 7)).alias("bits"), F.sum("step").alias("last"))


def q_clock_bits(spark, d):
    return B.clock_codes(D.ev_user(spark, d), 1000).groupBy("track_id").agg(F.sum("bits").alias("bits"), F.sum("step").alias("last"))


def q_reconstruct(spark, d):
    return _decoded(spark, d).select("track_id", "axis", "j", r("s2", 4).alias("s2"))


def q_align_error(spark, d):
    f, u = _resampled(spark, d)
    e = B.align(f, u, F.col("dt")).withColumn("sed", P.distance(F.col("pos"), F.col("pos2")))
    return e.groupBy("track_id").agg(r(F.max("sed"), 3).alias("max_sed"), r(F.avg("sed"), 3).alias("mean_sed"), F.count(F.lit(1)).alias("n"))


def q_error_points(spark, d):
    e = B.errors(_decoded(spark, d, 2.5))
    return e.groupBy("track_id").agg(F.sum((F.col("sed") > EPS).cast("int")).alias("off"), F.count(F.lit(1)).alias("n"))


def q_corrections(spark, d):
    return B.corrections(_decoded(spark, d, 2.5), EPS, EPS_P, 2).select("track_id", "j", "axis", "code")


def q_corrected_bound(spark, d):
    """Samples beyond the bound once corrected: none."""
    dec = _decoded(spark, d, 2.5)
    e = B.errors(B.with_corrections(dec, B.corrections(dec, EPS, EPS_P, 2), EPS_P, 2))
    return e.agg(F.sum((F.col("sed") > EPS).cast("int")).alias("off"), F.count(F.lit(1)).alias("n"))


def q_outlier_codes(spark, d):
    f = P.split_outliers(P.speed_breaks(D.ord_cust(spark, d), DAY_SPEED))
    return B.outlier_codes(f, 10.0, 1).select("track_id", "t", "axis", "code", "step")


def q_size_breakdown(spark, d):
    s = _cum(spark, d)
    coded = B.trimmed(B.codes(B.coefficients(B.velocities(s, B_S), B_S), EPS_F))
    one = F.aggregate("codes", F.lit(0).cast("long"), lambda a, x: a + N.bits(N.zz1(x), 1) - 1)
    parts = [
        coded.select("axis", F.lit("coefficients").alias("section"), one.alias("bits")),
        coded.select("axis", F.lit("lengths").alias("section"), N.bits(F.col("c_f"), 2).alias("bits")),
        B.block_ends(s, B_S, EPS_P, 2).select("axis", F.lit("ends").alias("section"), N.bits(N.zz(F.col("code")), 2).alias("bits")),
        B.anchors(s, EPS_P).select("axis", F.lit("anchors").alias("section"), N.bits(N.zz(F.col("anchor")), 2).alias("bits")),
    ]
    return reduce(DataFrame.unionByName, parts).withColumn("axis", F.col("axis").cast("string")).rollup("section", "axis").agg(F.sum("bits").alias("bits"))


def q_mean_max_sed(spark, d):
    e = B.errors(_decoded(spark, d))
    return e.agg(r(F.max("sed"), 4).alias("max_sed"), r(F.avg("sed"), 4).alias("mean_sed"), F.count(F.lit(1)).alias("n"))


def q_theory(spark, d):
    """What the theory expects at each place within a block of 100 samples, and how many samples of the tracks stand there."""
    b, e_f = 100, 1 / 0.6
    k = F.col("k")
    var = (k * b - k * k) * (e_f * e_f) / (6.0 * b * b)
    nth = F.row_number().over(W.partitionBy("track_id").orderBy("t"))
    s = D.li_supp(spark, d).select(((nth - 1) % b).cast("long").alias("k")).filter("k > 0").groupBy("k").agg(F.count(F.lit(1)).alias("samples"))
    return s.select("k", "samples", r(F.sqrt(var), 9).alias("sigma"), r(F.sqrt(var) * math.sqrt(math.pi / 2), 9).alias("mean_dev"), r(F.exp(-1.0 / (2 * var)), 9).alias("p_exceed"))


def q_utm(spark, d):
    g = D.ev_geo(spark, d)
    return xy(g.select("track_id", "t", P.to_utm(F.col("lon"), F.col("lat"), 32).alias("pos")), "track_id", "t")


def q_ecef(spark, d):
    g = D.ev_geo(spark, d)
    return xy(g.select("track_id", "t", P.to_ecef(F.col("lon"), F.col("lat"), P.fill_altitude()).alias("pos")), "track_id", "t", dim=3)


def q_region_rollup(spark, d):
    path = P.steps(D.li_supp(spark, d)).groupBy("track_id").agg(F.sum("dist").alias("length"), F.count(F.lit(1)).alias("n"))
    s = D.table(spark, d, "supplier").select(F.col("s_suppkey").cast("string").alias("track_id"), F.col("s_nationkey").alias("n_nationkey"))
    n, g = D.table(spark, d, "nation"), D.table(spark, d, "region")
    # 25 nations and 5 regions whatever the scale
    j = path.join(s, "track_id").join(F.broadcast(n), "n_nationkey").join(F.broadcast(g), F.col("n_regionkey") == F.col("r_regionkey"))
    return j.rollup("r_name", "n_name").agg(F.sum("n").alias("points"), r(F.sum("length"), 1).alias("length"))


def q_worst_k(spark, d):
    e = B.errors(_decoded(spark, d)).withColumn("sed", r("sed", 6))
    w = W.partitionBy("track_id").orderBy(F.desc("sed"), "j")
    return e.withColumn("place", F.row_number().over(w)).filter("place <= 3").select("track_id", "place", "j", r("sed", 4).alias("sed"))


def q_tumbling_bits(spark, d):
    e = D.table(spark, d, "events").select(F.col("ts").cast("timestamp").alias("ts"), N.bits(N.zz(F.floor("value").cast("long")), 2).alias("bits"))
    return e.groupBy(F.window("ts", "1 day")).agg(F.count(F.lit(1)).alias("points"), F.sum("bits").alias("bits")).select(F.unix_micros("window.start").alias("start"), "points", "bits")


def q_lossless_raw(spark, d):
    """Identity: bytes of the raw doubles."""
    rows = [f(spark, d).select(F.lit(n).alias("fixture"), F.size("pos").alias("dim")) for n, f in D.FIXTURES.items()]
    return reduce(DataFrame.unionByName, rows).groupBy("fixture").agg(F.sum(8 * (F.col("dim") + 1)).cast("long").alias("raw_bytes"), F.count(F.lit(1)).alias("n"))


def _bounded(method: str, fixture: str, dim: int = 2, eps: float | None = 50.0, **how):
    """A simplifier's contract, a row a track: how many points the track has, whether the path starts and ends where
    the track does, points invented, and points off by more than the bound (without one: kept points too many or too few)."""

    def query(spark, d):
        pts = D.FIXTURES[fixture](spark, d)
        if dim == 2:
            pts = pts.withColumn("pos", F.slice("pos", 1, 2))

        def checked(t, pos):
            times, path = S.kept(method, t, pos, eps, **how)
            own = set(zip(t.tolist(), map(tuple, pos.tolist()), strict=True))
            made = sum(x not in own for x in zip(times.tolist(), map(tuple, path.tolist()), strict=True))
            if eps is None:
                off = abs(len(times) - min(len(t), max(2, math.ceil(len(t) * how["ratio"]))))
            else:
                off = int((np.linalg.norm(S.reconstruct(times, path, t) - pos, axis=1) > eps * (1 + 1e-9)).sum())
            whole = bool(times[0] == t[0] and times[-1] == t[-1] and (np.diff(times) > 0).all() and len(times) <= len(t))
            return {"whole": whole, "invented": 0 if method == "cone_weak" else made, "off": off}

        return codec.sweep(pts, [({}, checked)], "track_id string, n long, whole boolean, invented long, off long")

    return query


def q_strong_subset(spark, d):
    """Kept points that are not samples: none. Set difference of rows."""
    pts = D.ev_user(spark, d).select("track_id", "t", "pos")
    kept = codec.kept_points(pts, "cone_strong", 50.0).select("track_id", "t", "pos")
    return kept.exceptAll(pts).agg(F.count(F.lit(1)).alias("invented"))


def _rule(name: str, e: float, dim: int, **changes) -> CodecParams:
    """Parameters by the constants found for the set, if any were."""
    return derive(e, dim, OF_FIXTURE.get(f"{name}:{dim}", 0), **changes)


def q_compress(spark, d):
    rows = [codec.compress(D.FIXTURES[n](spark, d), _rule(n, e, dim)).withColumn("fixture", F.lit(n)) for n, e, dim in TRIPS]
    c = reduce(DataFrame.unionByName, rows)
    return c.groupBy("fixture").agg(
        F.sum("n").alias("n"), F.sum("raw_bytes").alias("raw_bytes"), F.sum("bytes_paper").alias("bytes"), F.sum("bytes_with_clock").alias("with_clock"), r(F.sum("bytes_paper") / F.sum("raw_bytes"), 9).alias("ratio"),
        r(F.max("max_sed"), 6).alias("max_sed"), r(F.sum("sum_sed") / F.sum("n"), 6).alias("mean_sed"), r(100 * F.sum("n_corr") / F.sum("n"), 6).alias("error_pct"),
    )


#: fixture, bound and dimension of the round trips
TRIPS = (("ev_user", 50.0, 2), ("emb_cum", 0.5, 2), ("li_supp_smooth", 50.0, 3), ("ord_cust", 50.0, 1))


def _stored(pts: DataFrame, name: str, e: float, dim: int, chunk_points: int | None = codec.CHUNK) -> DataFrame:
    """Their containers as a stored table."""
    return staged(codec.compress(pts, _rule(name, e, dim), chunk_points), "container")


def _off(pts: DataFrame, back: DataFrame, e: float) -> DataFrame:
    """Points lost, invented or off by more than the bound."""
    both = pts.join(back.select("track_id", "t", F.col("pos").alias("pos2")), ["track_id", "t"], "full_outer")
    off = F.coalesce(P.distance(F.col("pos"), F.col("pos2")) > e, F.lit(True))
    return both.agg(F.count("pos").alias("n"), F.coalesce(F.sum(off.cast("int")), F.lit(0)).cast("long").alias("violations"))


def q_roundtrip_ok(spark, d):
    """Points lost, invented or off by more than the bound after compress, store and decompress: none."""
    out = []
    for name, e, dim in TRIPS:
        pts = staged(D.FIXTURES[name](spark, d).select("track_id", "t", "pos"), "points")
        c = _stored(pts, name, e, dim)
        out.append(_off(pts, codec.decompress(c, pts), e).withColumn("fixture", F.lit(name)))
    return reduce(DataFrame.unionByName, out)


def q_decode_partial_clock(spark, d):
    """The later half of each track's time asked for alone, of whole containers and of tracks cut in chunks: nothing lost, invented or off."""
    out = []
    half = W.partitionBy("track_id")
    for name, e, dim in TRIPS:
        pts = D.FIXTURES[name](spark, d).withColumn("__mid", F.min("t").over(half) + F.max("t").over(half))
        pts = staged(pts.select("track_id", "t", "pos", (2 * F.col("t") >= F.col("__mid")).alias("late")), "points")
        late = pts.filter("late").select("track_id", "t", "pos")
        for chunk_points in (None, 20):
            c = _stored(pts, name, e, dim, chunk_points)
            out.append(_off(late, codec.decompress(c, late), e).select(F.lit(name).alias("fixture"), F.lit(chunk_points is not None).alias("cut"), "n", "violations"))
    return reduce(DataFrame.unionByName, out)


#: parameters off the rule, each of which a container must say by itself
ODD = ({"eps_p": 10.0}, {"b_s": 64}, {"eps_f": 10.0}, {"l": 5, "l_freq": 3}, {"zero_free": False}, {"positions": True}, {"blocks": False}, {"eps_t": 1000}, {"r_ret": 0.125, "ends": "open"})


def q_decode_headers(spark, d):
    """Containers made with parameters off the rule and decoded from their bytes alone: points off by more than the bound, none."""

    def trip(p):
        def run(tracks, _):
            clocks = [t for t, _ in tracks]
            backs = many.decode([(*made, None) for made in many.unpack([data for data, *_ in many.packed(tracks, p)])], clocks)
            return [{"off": int((np.linalg.norm(back - pos, axis=1) > p.eps).sum())} for back, (_, pos) in zip(backs, tracks, strict=True)]

        run.many = run
        return run

    out = []
    for name, e, dim in TRIPS:
        runs = [({"fixture": name, "change": "".join(sorted(x))}, trip(_rule(name, e, dim, **{k: v * e / 50 if k in ("eps_p", "eps_f") else v for k, v in x.items()}))) for x in ODD]
        out.append(codec.sweep(D.FIXTURES[name](spark, d), runs, "track_id string, n long, fixture string, change string, off long"))
    return reduce(DataFrame.unionByName, out).groupBy("fixture", "change").agg(F.sum("n").alias("n"), F.sum("off").alias("off"))


def q_integer_lossless(spark, d):
    """Whole-number tracks through the codec's exact path and back from their bytes: values that changed, none; and the bytes taken."""
    s = D.int_signal(spark, d)
    pts = s.select(F.col("signal").alias("track_id"), F.row_number().over(W.partitionBy("signal").orderBy("i", "j")).cast("long").alias("t"), F.array(F.col("n").cast("double")).alias("pos"))
    return _lossless(pts)


def _lossless(pts: DataFrame, chunk_points: int | None = codec.CHUNK) -> DataFrame:
    """A row a track. A long one goes through in chunks; its bytes are those of one container, in which a chunk's first
    differences are taken from the row before, as the chunks' ends tell."""
    p = derive(1.0, 1, integer_input=True, l=7)

    def trip(t, pos):
        made = K.encode(t, pos, p)
        e, own = K.unpack(K.pack(made, p))
        steps = [N.zigzag(np.diff(x.ravel())) for x in (made.out_t, made.out)]
        # every code but those of the differences and of their number
        rest = 8 * len(K.head(made, p)) + sum(int(N.bit_cost(u, l, elide).sum()) for s, u, l, elide in K._sections(made, p) if s != "outliers")
        ends = {"t0": int(made.out_t[0]), "x0": int(made.out[0, 0]), "t1": int(made.out_t[-1]), "x1": int(made.out[-1, 0])}
        return {"off": int((K.decode(e, t, own) != pos).sum()), "rest": rest, "bits": sum(int(N.bit_cost(x, p.l).sum()) for x in steps), **ends}

    each = codec.sweep(pts, [({}, trip)], "track_id string, n long, off long, rest long, bits long, t0 long, x0 long, t1 long, x1 long", p.eps_t, chunk_points)
    # one row a chunk
    w = W.partitionBy("track_id").orderBy("t0")
    first = [N.bits(N.zz(F.col(a) - F.coalesce(F.lag(b).over(w), F.lit(0))), p.l) for a, b in (("t0", "t1"), ("x0", "x1"))]
    whole = each.withColumn("bits", F.col("bits") + first[0] + first[1]).groupBy("track_id").agg(F.sum("n").alias("n"), F.sum("off").alias("off"), F.max("rest").alias("rest"), F.sum("bits").alias("bits"))
    return whole.select("track_id", "n", "off", F.ceil((F.col("rest") + N.bits(F.col("n"), p.l) + F.col("bits")) / 8).alias("bytes"))


def q_coded_identity(spark, d):
    """The integer coder on all samples, as it is added to a simplifier's kept points: bytes a track."""
    p = derive(50.0, eps_p=10.0)
    return codec.sweep(D.ev_user(spark, d), [({}, lambda t, pos: S.simplified("identity", t, pos, p))], "track_id string, n long, kept long, bytes long")


def q_dct_methods(spark, d):
    """Codes by the fast transform, the direct sum, the product, and the orthonormal scaling undone: all the same."""
    v = B.velocities(_cum(spark, d), B_S)
    rows = v.groupBy("track_id", "axis", "block_id", "len").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "centred"))), lambda x: x["centred"]).alias("v"))
    methods = ("fft", "direct", "product", "ortho")

    @F.pandas_udf("array<array<long>>")
    def by_all(blocks: pd.Series) -> pd.Series:
        out = []
        for x in blocks:
            c = [dct(x, method=m)[0] for m in methods[:3]]
            c.append(dct(x, scaling="ortho")[0] * math.sqrt(2 * len(x)))
            out.append([N.quantize(y[1:], EPS_F).tolist() for y in c])
        return pd.Series(out)

    each = rows.withColumn("codes", by_all("v")).select("track_id", "axis", "block_id", F.posexplode("codes").alias("m", "codes"))
    named = F.array(*map(F.lit, methods))[F.col("m")].alias("method")
    return each.select("track_id", "axis", "block_id", named, F.posexplode("codes").alias("k0", "code")).select("track_id", "axis", "block_id", "method", (F.col("k0") + 1).alias("k"), "code")


def q_zero_share(spark, d):
    """Share of zeros among the codes, which truncation and trimming live on."""
    z = M.zero_share(B.codes(B.coefficients(B.velocities(_cum(spark, d), B_S), B_S), EPS_F))
    return z.select("axis", r("zero_share", 9).alias("zero_share"), "codes")


def q_derive(spark, d):
    """Parameters of each bound by each set of constants; the bounds are the lines' quantities, with how many lines have each."""

    def run(batches):
        for b in batches:
            for e, n in zip(b["eps"].tolist(), b["n"].tolist(), strict=True):
                rows = [(k, e, n, p.eps_f, p.b_s, p.r_ret, p.eps_p) for k in sorted(CONSTANTS) for p in [derive(float(e), 2, k)]]
                yield pd.DataFrame(rows, columns=["constants", "eps", "n", "eps_f", "b_s", "r_ret", "eps_p"])

    bounds = D.table(spark, d, "lineitem").select(F.floor("l_quantity").cast("long").alias("eps")).filter("eps > 0").groupBy("eps").agg(F.count(F.lit(1)).alias("n"))
    made = bounds.mapInPandas(run, "constants int, eps long, n long, eps_f double, b_s long, r_ret double, eps_p double")
    return made.select("constants", "eps", "n", r("eps_f", 9).alias("eps_f"), "b_s", r("r_ret", 9).alias("r_ret"), "eps_p")


def q_pick_a(spark, d):
    """The precision constant for a chance of passing the bound in mid-block, in the plane, and the mean error it brings. The chances are
    the events' values in percent, with how many events have each."""

    def run(batches):
        for b in batches:
            for i, n in zip(b["percent"].tolist(), b["n"].tolist(), strict=True):
                a = theory.pick_a(i / 100, 2)
                yield pd.DataFrame([(i, n, a, theory.mean_track_error(a, 2), theory.p_exceed(1.0, 50, 100, 1 / a, 2))], columns=["percent", "n", "a", "mean", "p"])

    percent = D.table(spark, d, "events").select(F.floor("value").cast("long").alias("percent")).filter("percent BETWEEN 1 AND 99").groupBy("percent").agg(F.count(F.lit(1)).alias("n"))
    made = percent.mapInPandas(run, "percent long, n long, a double, mean double, p double")
    return made.select("percent", "n", *[r(c, 9).alias(c) for c in ("a", "mean", "p")])


def q_measures(spark, d):
    """Ratio of sums, kept ratio, relative ratio, improvement, error reduction and argmin, on rows that any engine can add up."""
    rows = D.table(spark, d, "lineitem").select(
        F.col("l_linenumber").alias("fixture"), F.col("l_returnflag").alias("method"), F.col("l_partkey").alias("bytes"), F.col("l_suppkey").alias("kept"),
        (F.col("l_orderkey") + 1000).alias("raw_bytes"), (F.col("l_suppkey") + 100).alias("n"), F.col("l_partkey").cast("double").alias("sum_sed"),
    )
    s = rows.groupBy("fixture", "method").agg(M.compression_ratio().alias("ratio"), M.kept_ratio().alias("kept_ratio"), M.mean_sed().alias("mean_sed"))
    best = M.best(s, ["fixture"], "method", "ratio")
    own = M.relative(s, "ratio", "N", ["fixture"]).join(s.filter("method = 'N'").select("fixture", F.col("mean_sed").alias("base_sed")), "fixture").join(best, "fixture")
    made = own.withColumn("improvement", M.improvement(F.col("relative"))).withColumn("reduction", M.error_reduction(F.col("mean_sed"), F.col("base_sed")))
    return made.select("fixture", "method", "best_method", *[r(c, 9).alias(c) for c in ("ratio", "kept_ratio", "relative", "improvement", "reduction", "best_ratio")])


def q_engines(spark, d):
    """Containers by DataFrame functions alone and by the Arrow kernel: tracks whose bytes differ, or that only one of
    them has, none."""
    pts, p = staged(D.emb_cum(spark, d), "points"), _rule("emb_cum", EPS, 2)
    mine = expr.compress(pts, p, STEP, 2).select("track_id", "payload")
    both = mine.join(codec.compress(pts, p).select("track_id", F.col("payload").alias("other")), "track_id", "full_outer")
    differ = F.coalesce(F.col("payload") != F.col("other"), F.lit(True)).cast("int")
    return both.agg(F.count(F.lit(1)).alias("tracks"), F.sum(differ).alias("differ"))


def q_section_rollup(spark, d):
    return M.size_breakdown(codec.compress(D.li_supp_smooth(spark, d), _rule("li_supp_smooth", 50.0, 3)).withColumn("fixture", F.lit("li_supp_smooth")), "fixture")


def q_interval_search(spark, d):
    """Target interval by grid: the one whose container, corrections included, takes the fewest bytes."""
    p = derive(50.0, v_max=V_MAX)

    def offered(dt: int):
        def measure(t, pos):
            e = K.encode(t, pos, p.with_(dt_scale=dt / K.common_interval(t, K.fragment_starts(t, pos, p), p.eps_t)))
            return {"bytes": len(K.pack(e, p))}

        return {"dt": dt}, measure

    runs = [offered(h * HOUR) for h in (10, 20, 30)]
    return P.search_interval(codec.sweep(D.ev_user(spark, d), runs, "track_id string, n long, raw_bytes long, dt long, bytes long"))


# ---- operators around the methods


def op_broadcast_rollup(spark, d):
    s, n, g = (D.table(spark, d, x) for x in ("supplier", "nation", "region"))
    j = s.join(F.broadcast(n), F.col("s_nationkey") == F.col("n_nationkey")).join(F.broadcast(g), F.col("n_regionkey") == F.col("r_regionkey"))
    return j.groupBy("r_name", "n_name").agg(F.count(F.lit(1)).alias("suppliers"))


def op_semi_anti(spark, d):
    o, li = D.table(spark, d, "orders"), D.table(spark, d, "lineitem").filter("l_quantity > 49").select(F.col("l_orderkey").alias("o_orderkey"))
    a = o.join(li, "o_orderkey", "left_semi").agg(F.lit("with").alias("kind"), F.count(F.lit(1)).alias("n"))
    return a.unionByName(o.join(li, "o_orderkey", "left_anti").agg(F.lit("without").alias("kind"), F.count(F.lit(1)).alias("n")))


def op_full_outer_loss(spark, d):
    o, c = D.table(spark, d, "orders").select(F.col("o_custkey").alias("k")).distinct(), D.table(spark, d, "customer").select(F.col("c_custkey").alias("k"), F.lit(1).alias("c"))
    j = o.withColumn("o", F.lit(1)).join(c, "k", "full_outer")
    return j.agg(F.sum(F.col("o").isNull().cast("int")).alias("no_order"), F.sum(F.col("c").isNull().cast("int")).alias("no_customer"), F.count(F.lit(1)).alias("n"))


def asof(left: DataFrame, right: DataFrame, key: str, at: str, value: str, to: str) -> DataFrame:
    """The latest right value at or before each left time: one union, one shuffle, one ordered window."""
    rows = left.select(key, at, F.lit(1).alias("__left"), F.lit(None).cast(right.schema[value].dataType).alias(to)).unionByName(right.select(key, at, F.lit(0).alias("__left"), F.col(value).alias(to)))
    w = W.partitionBy(key).orderBy(at, "__left").rowsBetween(W.unboundedPreceding, 0)
    return rows.withColumn(to, F.last(to, True).over(w)).filter("__left = 1").drop("__left")


def op_asof_kept(spark, d):
    e = D.table(spark, d, "events").select("user_id", D.micros("ts").alias("t"), "event_id", "event_type")
    buys = e.filter("event_type = 'purchase'").select("user_id", "t", F.col("event_id").alias("last_buy"))
    return asof(e.filter("event_type <> 'purchase'"), buys, "user_id", "t", "last_buy", "last_buy").groupBy("user_id").agg(F.count("last_buy").alias("after_buy"), F.coalesce(F.sum("last_buy"), F.lit(0)).alias("total"))


def op_interval_theta(spark, d):
    """Range join by bucket: orders within a week after the customer's earlier one, no theta join."""
    o = D.table(spark, d, "orders").select("o_custkey", "o_orderkey", D.micros("o_orderdate").alias("t"))
    week = 7 * 24 * HOUR
    a = o.withColumn("cell", F.explode(F.array(F.floor(F.col("t") / week), F.floor(F.col("t") / week) + 1)))
    b = o.select("o_custkey", F.col("o_orderkey").alias("other"), F.col("t").alias("t2"), F.floor(F.col("t") / week).alias("cell"))
    j = a.join(b, ["o_custkey", "cell"]).filter(f"t2 > t AND t2 <= t + {week}")
    return j.groupBy("o_custkey").agg(F.count(F.lit(1)).alias("pairs"))


def op_grouping_sets(spark, d):
    D.table(spark, d, "lineitem").createOrReplaceTempView("op_lines")
    return spark.sql("SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_linenumber) AS total FROM op_lines GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())")


def op_cube(spark, d):
    return D.table(spark, d, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


def op_pivot_methods(spark, d):
    return D.table(spark, d, "events").groupBy("user_id").pivot("event_type", ["click", "purchase", "view"]).agg(F.count(F.lit(1))).na.fill(0).select("user_id", "click", "purchase", "view")


def op_window_frames(spark, d):
    e = D.table(spark, d, "events").select("event_id", "user_id", D.micros("ts").alias("t"))
    w = W.partitionBy("user_id").orderBy("t", "event_id")
    near = W.partitionBy("user_id").orderBy("t").rangeBetween(-24 * HOUR, 0)
    return e.select("event_id", F.sum("event_id").over(w.rowsBetween(W.unboundedPreceding, 0)).alias("running"), F.sum("event_id").over(w.rowsBetween(-8, 8)).alias("centred"), F.count(F.lit(1)).over(near).alias("last_day"))


def op_rank_ntile(spark, d):
    w = W.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return D.table(spark, d, "orders").select("o_orderkey", F.rank().over(w).alias("rank"), F.ntile(4).over(w).alias("quarter"), F.lag("o_orderkey", 1, -1).over(w).alias("before"), F.lead("o_orderkey", 1, -1).over(w).alias("after"))


def op_topk_per_track(spark, d):
    w = W.partitionBy("l_suppkey").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber")
    return D.table(spark, d, "lineitem").withColumn("place", F.row_number().over(w)).filter("place <= 3").select("l_suppkey", "place", "l_orderkey", "l_extendedprice")


def op_topk(spark, d):
    return D.table(spark, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20).select("o_orderkey", "o_totalprice")


def op_union_intersect_except(spark, d):
    o, c = D.table(spark, d, "orders").select(F.col("o_custkey").alias("k")), D.table(spark, d, "customer").select(F.col("c_custkey").alias("k"))
    rows = [("union", o.union(c)), ("intersect", o.intersect(c)), ("except", c.exceptAll(o.distinct()))]
    return reduce(DataFrame.unionByName, [x.agg(F.lit(n).alias("kind"), F.count(F.lit(1)).alias("n"), F.coalesce(F.sum("k"), F.lit(0)).alias("total")) for n, x in rows])


def op_scalar_bits(spark, d):
    k = F.col("o_orderkey")
    return D.table(spark, d, "orders").select(k, F.bin(k).alias("bin"), F.bit_count(k).cast("int").alias("ones"), F.shiftleft(k, 3).alias("left"), k.bitwiseXOR(F.lit(255)).alias("flipped"), F.lpad(F.bin(k), 24, "0").alias("padded"))


def op_scalar_dates(spark, d):
    t = F.col("o_orderdate").cast("timestamp")
    return D.table(spark, d, "orders").select("o_orderkey", F.unix_micros(t).alias("micros"), F.unix_micros(F.date_trunc("month", t)).alias("month"), F.year(t).alias("year"), F.dayofyear(t).alias("day"), F.unix_micros(F.timestamp_micros(F.unix_micros(t) + 5)).alias("later"))


def op_scalar_strings(spark, d):
    s = F.col("p_name")
    return D.table(spark, d, "part").select("p_partkey", F.upper(s).alias("upper"), F.length(s).cast("long").alias("length"), F.reverse(s).alias("back"), F.substring(s, 1, 3).alias("head"), F.base64(s.cast("binary")).alias("b64"))


def op_array_hof(spark, d):
    v = F.transform("embedding", lambda x: F.floor(x.cast("double") * 1000 + 0.5))
    e = D.table(spark, d, "embeddings").select("vec_id", v.alias("v"))
    positive = F.filter("v", lambda x: x > 0)
    return e.select("vec_id", F.aggregate("v", F.lit(0).cast("long"), lambda a, x: a + x).alias("total"), F.size(positive).alias("positive"), F.array_max("v").alias("most"), F.element_at("v", 1).alias("first"), F.size(F.slice("v", 2, 5)).alias("sliced"))


def op_json_props(spark, d):
    e = D.table(spark, d, "events").select(F.from_json("props", "k int").alias("p"), "event_type")
    return e.groupBy("event_type").agg(F.sum("p.k").alias("total"), F.count_distinct("p.k").alias("kinds"), F.max("p.k").alias("most"))


def op_percentiles(spark, d):
    q = F.percentile("l_quantity", F.array(F.lit(0.5), F.lit(0.9)))
    return D.table(spark, d, "lineitem").groupBy("l_returnflag").agg(q.alias("q")).select("l_returnflag", r(F.col("q")[0], 6).alias("median"), r(F.col("q")[1], 6).alias("p90"))


def op_percentile_approx(spark, d):
    """The approximate median's true rank lies within the accuracy asked for."""
    li = D.table(spark, d, "lineitem").select("l_returnflag", "l_extendedprice")
    found = li.groupBy("l_returnflag").agg(F.percentile_approx("l_extendedprice", 0.5, 10_000).alias("median"))
    # three flags whatever the scale
    both = li.join(F.broadcast(found), "l_returnflag").groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("l_extendedprice") < F.col("median")).alias("below"), F.count_if(F.col("l_extendedprice") <= F.col("median")).alias("upto"))
    slack = F.col("n") / 10_000 + 1
    return both.select("l_returnflag", "n", ((F.col("below") <= F.col("n") / 2 + slack) & (F.col("upto") >= F.col("n") / 2 - slack)).alias("within"))


def op_distinct_counts(spark, d):
    return D.table(spark, d, "lineitem").groupBy("l_linestatus").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"))


def op_tumbling(spark, d):
    return streams.tumbling(D.table(spark, d, "events"), "1 day")


def op_sliding(spark, d):
    return streams.sliding(D.table(spark, d, "events"), "2 days", "1 day")


def op_session(spark, d):
    return streams.sessions(D.table(spark, d, "events"), "12 hours")


def op_udf_varint(spark, d):
    sqlfuncs.register(spark)
    _signed(spark, d).createOrReplaceTempView("op_signed")
    return spark.sql("SELECT l_partkey % 10 AS k, sum(varint_bits(l_partkey, 2)) AS plain, sum(varint_bits(zz1(n), 1)) AS zero_free FROM op_signed GROUP BY 1")


def op_udtf_decode(spark, d):
    """Decode containers in SQL with a lateral table function."""
    sqlfuncs.register(spark)
    codec.compress(D.emb_cum(spark, d), derive(EPS, 2, b_s=B_S)).select("track_id", "payload", "t_min").createOrReplaceTempView("op_container")
    return spark.sql("SELECT c.track_id, p.t, round(p.pos[0], 4) AS x, round(p.pos[1], 4) AS y FROM op_container c, LATERAL decode_track(c.payload, c.t_min) p")


def op_stream_replay(spark, d):
    return streams.replay(spark, d, "count")


def op_stream_dedupe(spark, d):
    return streams.replay(spark, d, "dedupe")


def op_stream_fragments(spark, d):
    """Fragments put out by the stream and those open at its end, and whether each keeps the bound."""
    return streams.replay(spark, d, "fragments").select("track_id", "frag", "n", "t0", (F.col("max_sed") <= 10.0).alias("within"))


def _stream_of_steps(spark, d) -> DataFrame:
    """Events as points that follow from the row alone, so that the stream needs no window before it."""
    e = streams.events_stream(spark, d)
    return e.select(F.col("user_id").cast("string").alias("track_id"), "ts", F.unix_micros("ts").alias("t"), F.array("value", F.get_json_object("props", "$.k").cast("double")).alias("pos"))


def op_stream_cones(spark, d):
    """Paths of the strong and the weak cone from a stream against those of the batch: points of either that the other lacks, none."""
    out = []
    e = D.table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    pts = e.select(F.col("user_id").cast("string").alias("track_id"), F.unix_micros("ts").alias("t"), F.array("value", F.get_json_object("props", "$.k").cast("double")).alias("pos"))
    for name in ("cone_strong", "cone_weak"):
        of = lambda df, i: df.select("track_id", "t", "generated", F.transform("pos", lambda x: F.round(x, 4)).alias("pos"), F.lit(i).alias("side"))
        both = of(streams.path_of(_stream_of_steps(spark, d), 30.0, name == "cone_weak"), 1).unionByName(of(codec.kept_points(pts, name, 30.0), -1))
        each = both.groupBy("track_id", "t", "generated", "pos").agg(F.sum("side").alias("side"))
        out.append(each.agg(F.lit(name).alias("method"), F.count_distinct("track_id").alias("tracks"), F.coalesce(F.sum(F.abs("side")), F.lit(0)).alias("differ")))
    return out[0].unionByName(out[1])


def op_sql_views(spark, d):
    """Named views, the grouped function of errors, and the table function, in one statement."""
    sqlfuncs.register(spark)
    pts = D.emb_cum(spark, d)
    sqlfuncs.views(pts, staged(codec.compress(pts, derive(EPS, 2)), "container"), B_S, STEP)
    return spark.sql("""
        WITH back AS (SELECT c.track_id, p.t, p.pos FROM container c, LATERAL decode_track(c.payload, c.t_min) p),
             off AS (SELECT a.track_id, sqrt(pow(a.pos[0] - b.pos[0], 2) + pow(a.pos[1] - b.pos[1], 2)) AS sed FROM points a JOIN back b ON a.track_id = b.track_id AND a.t = b.t),
             e AS (SELECT track_id, sed_stats(sed) AS s FROM off GROUP BY track_id),
             v AS (SELECT track_id, count(*) AS velocities, count(DISTINCT block_id) AS blocks FROM blocks GROUP BY track_id)
        SELECT e.track_id, CAST(s[0] AS BIGINT) AS n, s[1] <= 0.5 AS bounded, s[2] <= s[1] AS ordered, velocities, blocks FROM e JOIN v ON e.track_id = v.track_id
    """)


def op_metrics_json(spark, d):
    """Run metrics as a map, a struct and JSON, and back."""
    m = D.table(spark, d, "events").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("event_id").alias("total"))
    m = m.withColumn("metrics", F.map_from_arrays(F.array(F.lit("n"), F.lit("total")), F.array("n", "total"))).withColumn("json", F.to_json(F.struct("n", "total")))
    return m.select("event_type", F.element_at("metrics", "total").alias("total"), F.size("metrics").cast("long").alias("fields"), "json", F.from_json("json", "n long, total long")["n"].alias("n"))


def op_late_rows(spark, d):
    return streams.late_rows(D.table(spark, d, "events"), 2 * HOUR)


def op_partition_prune(spark, d):
    """Containers that may hold samples of one year: the side columns decide, no payload is opened."""
    c = codec.compress(D.li_supp_smooth(spark, d), derive(50.0, 3))
    year = 31_536_000_000_000
    return c.filter((F.col("t_max") >= 25 * year) & (F.col("t_min") < 26 * year)).agg(F.count(F.lit(1)).alias("tracks"))


def op_decode_range(spark, d):
    """Decode only the samples of a time range; containers outside it are not opened."""
    c = codec.compress(D.emb_cum(spark, d), derive(EPS, 2))
    return codec.decompress_regular(c, None, 1_000_000, 2_000_000).groupBy("track_id").agg(F.count(F.lit(1)).alias("n"), F.min("t").alias("t_min"), F.max("t").alias("t_max"))


_OWN = {name: f for name, f in list(globals().items()) if name.startswith(("q_", "op_")) and callable(f)}

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    **_OWN,
    "q_cone_strong": _bounded("cone_strong", "ev_user"),
    "q_cone_weak": _bounded("cone_weak", "ev_user"),
    "q_pq": _bounded("pq", "li_supp_smooth", 3),
    "q_pq_ratio": _bounded("pq", "li_supp_smooth", 3, None, ratio=0.1),
    "q_opening_window": _bounded("opening_window", "ev_user"),
    **workloads.ALL,
}
