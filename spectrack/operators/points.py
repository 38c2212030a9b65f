"""Preparing, fragmenting and resampling tracks with DataFrame functions."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

# WGS84 (fixed values)
MAJOR, FLAT = 6378137.0, 1 / 298.257223563
DEFAULT_ALTITUDE_FT, FOOT = -777.0, 0.3048


def _track():
    return W.partitionBy("track_id").orderBy("t")


def _fragment():
    return W.partitionBy("track_id", "frag_id")


def distance(a: Column, b: Column) -> Column:
    return F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x))


def dedupe(points: DataFrame, eps_t: int = 1, tie: list[Column] | None = None) -> DataFrame:
    """One sample a quantized time, the first by time, then tie."""
    code = F.floor((F.col("t") * 2 + eps_t) / (2 * eps_t))
    keyed = points.withColumn("__t", code)
    nth = F.row_number().over(W.partitionBy("track_id", "__t").orderBy("t", *(tie or [F.col("pos")])))
    return keyed.withColumn("__n", nth).filter("__n = 1").drop("__t", "__n")


def fill_altitude(col: str = "alt_ft", default_ft: float = DEFAULT_ALTITUDE_FT) -> Column:
    """Metres; a missing altitude takes the sentinel."""
    return F.coalesce(F.col(col), F.lit(default_ft)) * FOOT


def to_ecef(lon: Column, lat: Column, alt: Column) -> Column:
    """Geodetic degrees and metres to Cartesian metres."""
    la, lo, e2 = F.radians(lat), F.radians(lon), FLAT * (2 - FLAT)
    n = MAJOR / F.sqrt(1 - e2 * F.sin(la) * F.sin(la))
    return F.array((n + alt) * F.cos(la) * F.cos(lo), (n + alt) * F.cos(la) * F.sin(lo), (n * (1 - e2) + alt) * F.sin(la))


def to_utm(lon: Column, lat: Column, zone: int) -> Column:
    """Easting and northing by the transverse Mercator series in the third flattening."""
    n = FLAT / (2 - FLAT)
    big = MAJOR / (1 + n) * (1 + n**2 / 4 + n**4 / 64)
    series = (n / 2 - 2 * n**2 / 3 + 5 * n**3 / 16, 13 * n**2 / 48 - 3 * n**3 / 5, 61 * n**3 / 240)
    e = 2 * math.sqrt(n) / (1 + n)
    la, dl = F.radians(lat), F.radians(lon - F.lit(float(zone * 6 - 183)))
    tau = F.sinh(F.atanh(F.sin(la)) - e * F.atanh(e * F.sin(la)))
    xi, eta = F.atan2(tau, F.cos(dl)), F.atanh(F.sin(dl) / F.sqrt(1 + tau * tau))
    north, east = xi, eta
    for j, a in enumerate(series, 1):
        north = north + a * F.sin(2 * j * xi) * F.cosh(2 * j * eta)
        east = east + a * F.cos(2 * j * xi) * F.sinh(2 * j * eta)
    return F.array(500_000.0 + 0.9996 * big * east, 0.9996 * big * north)


def steps(points: DataFrame) -> DataFrame:
    """Add idx (from 0), gap (microseconds) and dist to the sample before."""
    return (
        points.withColumn("idx", F.row_number().over(_track()) - 1)
        .withColumn("gap", F.col("t") - F.lag("t").over(_track()))
        .withColumn("dist", distance(F.col("pos"), F.lag("pos").over(_track())))
    )


def speed_breaks(points: DataFrame, v_max: float) -> DataFrame:
    """Add frag_id: a new fragment after each step faster than v_max a second."""
    fast = F.coalesce(F.col("dist") > F.col("gap") / 1e6 * v_max, F.lit(False)).cast("int")
    return steps(points).withColumn("frag_id", F.sum(fast).over(_track().rowsBetween(W.unboundedPreceding, 0)).cast("int"))


def fragments(points: DataFrame, b_s: int, default_dt: int, v_max: float | None = None, gap_mean: str = "inclusive") -> DataFrame:
    """Add frag_id by the speed rule and the gap rule (a pause over b_s times the fragment's mean gap).

    The gap rule looks at the fragment so far, so it runs in order; but only pauses over b_s times the
    track's least gap (or the default) can break, and those few go through a fold a track. The breaks it finds come back
    as rows of their own between the points, and a running sum counts them: no point carries a list."""
    fast = F.lit(False) if v_max is None else F.coalesce(F.col("dist") > F.col("gap") / 1e6 * v_max, F.lit(False))
    whole = W.partitionBy("track_id")
    rows = steps(points)
    marked = rows.select("track_id", "t", "idx", "gap", fast.alias("fast"), F.lag("t").over(_track()).alias("before"), F.least(F.min("gap").over(whole), F.lit(default_dt)).alias("least"), F.min("t").over(whole).alias("t0"))
    suspects = marked.filter((F.col("gap") > b_s * F.col("least")) | F.col("fast")).groupBy("track_id", "t0").agg(F.array_sort(F.collect_list(F.struct("idx", "t", "before", "fast"))).alias("suspects"))

    def step(a: Column, x: Column) -> Column:
        k = x["idx"] - a["at"]
        if gap_mean == "inclusive":
            mean = (x["t"] - a["t"]) / k
        else:
            mean = (x["before"] - a["t"]) / F.nullif(k - 1, F.lit(0))
        mean = F.when(k == 1, F.lit(float(default_dt))).otherwise(mean)
        new = x["fast"] | ((x["t"] - x["before"]) > b_s * mean)
        return F.struct(
            F.when(new, x["idx"]).otherwise(a["at"]).alias("at"), F.when(new, x["t"]).otherwise(a["t"]).alias("t"), F.when(new, F.concat(a["found"], F.array(x["t"]))).otherwise(a["found"]).alias("found")
        )

    start = F.struct(F.lit(0).alias("at"), F.col("t0").alias("t"), F.array().cast("array<bigint>").alias("found"))
    breaks = suspects.select("track_id", F.explode(F.aggregate("suspects", start, step, lambda a: a["found"])).alias("t"), F.lit(1).alias("__new"))
    both = rows.withColumn("__new", F.lit(0)).unionByName(breaks, allowMissingColumns=True)
    running = W.partitionBy("track_id").orderBy("t", F.desc("__new")).rowsBetween(W.unboundedPreceding, 0)
    return both.withColumn("frag_id", F.sum("__new").over(running).cast("int")).filter("__new = 0").drop("__new")


def split_outliers(frags: DataFrame, max_len: int = 2) -> DataFrame:
    """Add outlier: whether the fragment is too short to be coded as one."""
    return frags.withColumn("outlier", F.count(F.lit(1)).over(_fragment()) <= max_len)


def interval(frags: DataFrame, eps_t: int, scope: str = "track", max_len: int = 2) -> DataFrame:
    """track_id and dt: spans over point counts of its longer fragments; or one dt for all."""
    per = frags.groupBy("track_id", "frag_id").agg((F.max("t") - F.min("t")).alias("span"), F.count(F.lit(1)).alias("n")).filter(F.col("n") > max_len)
    dt = eps_t * F.greatest(F.lit(1), F.floor(F.sum("span") / (eps_t * F.sum("n")) + 0.5))
    return per.groupBy("track_id").agg(dt.alias("dt")) if scope == "track" else per.agg(dt.alias("dt"))


def to_uniform(frags: DataFrame, dt: Column) -> DataFrame:
    """track_id, frag_id, j, pos: samples every dt from each fragment's start, each made by the pair of
    samples around it (no join); the sample beyond the end holds the last position."""
    w = _fragment().orderBy("t")
    t0 = F.min("t").over(_fragment())
    rows = frags.select("track_id", "frag_id", "t", "pos", dt.alias("dt"), t0.alias("t0"), F.lead("t").over(w).alias("t2"), F.lead("pos").over(w).alias("pos2"))
    first = F.when(F.col("t") == F.col("t0"), 0).otherwise(F.floor((F.col("t") - F.col("t0")) / F.col("dt")) + 1)
    last_t = F.when(F.lead("t2").over(w).isNull(), F.ceil((F.col("t2") - F.col("t0")) / F.col("dt"))).otherwise(F.floor((F.col("t2") - F.col("t0")) / F.col("dt")))
    rows = rows.withColumn("a", first.cast("bigint")).withColumn("b", last_t.cast("bigint")).filter("t2 IS NOT NULL AND b >= a")
    each = rows.withColumn("j", F.explode(F.sequence("a", "b")))
    at = F.least(F.col("t0") + F.col("j") * F.col("dt"), F.col("t2"))
    share = (at - F.col("t")) / (F.col("t2") - F.col("t"))
    return each.withColumn("share", share).select("track_id", "frag_id", "j", F.zip_with("pos", "pos2", lambda p, n: p + (n - p) * F.col("share")).alias("pos"))


def search_interval(costs: DataFrame) -> DataFrame:
    """The interval of least cost for each track of costs(track_id, dt, bytes); of equal costs the smallest interval."""
    return costs.groupBy("track_id").agg(F.min_by("dt", F.struct("bytes", "dt")).alias("dt"), F.min("bytes").alias("bytes"))
