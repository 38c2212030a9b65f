"""Blocks, transform and integer codes with DataFrame functions: the transparent engine.

SIGNAL rows (track_id, frag_id, axis, j, s) become velocities in blocks, coefficients by a join with a small
basis, and integers. Windows share the hash on track_id."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from spectrack.functions import numbers as N

AXIS = ["track_id", "frag_id", "axis"]
BLOCK = [*AXIS, "block_id"]


def axes(uniform: DataFrame) -> DataFrame:
    frag = F.col("frag_id") if "frag_id" in uniform.columns else F.lit(0)
    return uniform.select("track_id", frag.alias("frag_id"), "j", F.posexplode("pos").alias("axis", "s"))


def from_clock(points: DataFrame, dt: int) -> DataFrame:
    """Uniform points as samples j."""
    return points.select("track_id", F.lit(0).alias("frag_id"), F.floor(F.col("t") / dt).alias("j"), "pos")


def velocities(signal: DataFrame, b_s: int) -> DataFrame:
    """Velocity j belongs to block j / b_s, so neighbouring blocks share a sample and no row is doubled."""
    v = signal.withColumn("v", F.lead("s").over(W.partitionBy(*AXIS).orderBy("j")) - F.col("s")).filter("v IS NOT NULL")
    v = v.withColumn("block_id", F.floor(F.col("j") / b_s)).withColumn("i", (F.col("j") % b_s).cast("int"))
    whole = W.partitionBy(*BLOCK)
    return v.withColumn("len", F.count(F.lit(1)).over(whole).cast("int")).withColumn("centred", F.col("v") - F.avg("v").over(whole))


def basis(spark: SparkSession, b_s: int, r_ret: float) -> DataFrame:
    """len, i, k, cos for every block length up to b_s and every kept coefficient but the first."""
    lens = spark.range(1, b_s + 1).select(F.col("id").cast("int").alias("len"))
    kept = F.greatest(F.lit(1), F.least(F.col("len"), F.floor(F.col("len") * r_ret + 0.5).cast("int")))
    rows = lens.withColumn("kept", kept).filter("kept > 1").withColumn("k", F.explode(F.expr("sequence(1, kept - 1)"))).withColumn("i", F.explode(F.expr("sequence(0, len - 1)")))
    return rows.select("len", "i", "k", F.cos((2 * F.col("i") + 1) * F.col("k") * math.pi / (2 * F.col("len"))).alias("cos"))


def coefficients(v: DataFrame, b_s: int, r_ret: float = 1.0) -> DataFrame:
    """c of each block and k. The basis is at most b_s^3 / 3 rows, whatever the data, and broadcast."""
    made = v.join(F.broadcast(basis(v.sparkSession, b_s, r_ret)), ["len", "i"])
    return made.groupBy(*BLOCK, "len", "k").agg((2 * F.sum(F.col("centred") * F.col("cos"))).alias("c"))


def codes(c: DataFrame, eps_f: float) -> DataFrame:
    return c.withColumn("code", N.q(F.col("c"), eps_f))


def trimmed(coded: DataFrame) -> DataFrame:
    """c_f and the codes without trailing zeros, a row a block."""
    arr = F.transform(F.array_sort(F.collect_list(F.struct("k", "code"))), lambda x: x["code"])
    last = F.coalesce(F.array_max(F.transform("all", lambda x, i: F.when(x != 0, i + 1).otherwise(0))), F.lit(0))
    rows = coded.groupBy(*BLOCK, "len").agg(arr.alias("all")).withColumn("c_f", last)
    return rows.select(*BLOCK, "len", "c_f", F.slice("all", 1, F.col("c_f")).alias("codes"))


def anchors(signal: DataFrame, eps_p: float) -> DataFrame:
    first = signal.groupBy(*AXIS).agg(F.min_by("s", "j").alias("s0"))
    return first.select(*AXIS, N.q(F.col("s0"), eps_p).alias("anchor"))


def block_ends(signal: DataFrame, b_s: int, eps_p: float, dim: int, ends: str = "closed") -> DataFrame:
    """The integer of each block's end. Closed loop: the code of the end minus that of the end before,
    both against the decoded anchor, so no error adds up; shifting by whole steps commutes with the
    quantizer, so it needs a lag and no recursion. Open: the code of the difference itself."""
    e_d = eps_p / math.sqrt(dim)
    whole = W.partitionBy(*AXIS)
    rows = signal.withColumn("last", F.max("j").over(whole)).withColumn("s0", F.min_by("s", "j").over(whole))
    at = rows.filter((F.col("j") == F.col("last")) & (F.col("last") > 0) | (F.col("j") % b_s == 0) & (F.col("j") > 0))
    order = W.partitionBy(*AXIS).orderBy("j")
    block = (F.ceil(F.col("j") / b_s) - 1).alias("block_id")
    if ends == "closed":
        code = N.q(F.col("s") - N.q(F.col("s0"), eps_p) * (2 * eps_p), e_d)
        at = at.withColumn("abs", code)
        return at.select(*AXIS, block, (F.col("abs") - F.coalesce(F.lag("abs").over(order), F.lit(0))).alias("code"))
    return at.select(*AXIS, block, N.q(F.col("s") - F.coalesce(F.lag("s").over(order), F.col("s0")), e_d).alias("code"))


def reconstructed(signal: DataFrame, b_s: int, eps_f: float, eps_p: float, dim: int, r_ret: float = 1.0) -> DataFrame:
    """Decoded samples s2 beside the true ones: inverse transform by the same basis join, running sums inside the block."""
    v = velocities(signal, b_s)
    coded = codes(coefficients(v, b_s, r_ret), eps_f).filter("code <> 0")
    table = F.broadcast(basis(v.sparkSession, b_s, r_ret))
    back = coded.join(table, ["len", "k"]).groupBy(*BLOCK, "i").agg(F.sum(2 * eps_f * F.col("code") * F.col("cos") / F.col("len")).alias("dv"))
    step = 2 * eps_p / math.sqrt(dim)
    order = W.partitionBy(*AXIS).orderBy("block_id").rowsBetween(W.unboundedPreceding, 0)
    ends = block_ends(signal, b_s, eps_p, dim).withColumn("total", F.sum("code").over(order)).withColumn("before", F.col("total") - F.col("code"))
    frame = ends.join(anchors(signal, eps_p), AXIS)
    inside = W.partitionBy(*BLOCK).orderBy("i").rowsBetween(W.unboundedPreceding, 0)
    rows = v.join(back, [*BLOCK, "i"], "left").join(frame, BLOCK)
    moved = F.col("anchor") * (2 * eps_p) + F.col("before") * step + (F.col("i") + 1) * (F.col("code") * step / F.col("len"))
    wave = F.sum(F.coalesce("dv", F.lit(0.0))).over(inside)
    made = rows.select(*AXIS, (F.col("j") + 1).alias("j"), (F.col("s") + F.col("v")).alias("s"), (moved + F.when(F.col("i") == F.col("len") - 1, 0.0).otherwise(wave)).alias("s2"))
    start = signal.filter("j = 0").join(anchors(signal, eps_p), AXIS).select(*AXIS, "j", "s", (F.col("anchor") * (2 * eps_p)).alias("s2"))
    return made.unionByName(start)


def errors(decoded: DataFrame) -> DataFrame:
    """Synchronized distance of each sample."""
    return decoded.groupBy("track_id", "frag_id", "j").agg(F.sqrt(F.sum(F.pow(F.col("s") - F.col("s2"), 2))).alias("sed"))


def corrections(decoded: DataFrame, eps: float, eps_p: float, dim: int) -> DataFrame:
    """Codes of the differences at samples that are off by more than eps."""
    e_d = eps_p / math.sqrt(dim)
    off = F.sqrt(F.sum(F.pow(F.col("s") - F.col("s2"), 2)).over(W.partitionBy("track_id", "frag_id", "j")))
    return decoded.withColumn("sed", off).filter(F.col("sed") > eps * (1 - 1e-9)).select("track_id", "j", "axis", N.q(F.col("s") - F.col("s2"), e_d).alias("code"))


def with_corrections(decoded: DataFrame, corr: DataFrame, eps_p: float, dim: int) -> DataFrame:
    step = 2 * eps_p / math.sqrt(dim)
    both = decoded.join(corr, ["track_id", "j", "axis"], "left")
    return both.withColumn("s2", F.col("s2") + F.coalesce("code", F.lit(0)) * step).drop("code")


def outlier_codes(frags: DataFrame, eps: float, dim: int) -> DataFrame:
    """Outliers' codes (step 2 eps / sqrt(dim)) and their differences along time, a row an axis."""
    single = frags.filter("outlier").select("track_id", "t", F.posexplode("pos").alias("axis", "s"))
    coded = single.withColumn("code", N.q(F.col("s"), eps / math.sqrt(dim)))
    w = W.partitionBy("track_id", "axis").orderBy("t")
    return coded.withColumn("step", F.col("code") - F.coalesce(F.lag("code").over(w), F.lit(0)))


def clock_codes(points: DataFrame, eps_t: int) -> DataFrame:
    """Time codes, their differences and bits (chunks of 2)."""
    w = W.partitionBy("track_id").orderBy("t")
    coded = points.select("track_id", "t", F.floor((F.col("t") * 2 + eps_t) / (2 * eps_t)).alias("code"))
    coded = coded.withColumn("step", F.col("code") - F.coalesce(F.lag("code").over(w), F.lit(0)))
    return coded.withColumn("bits", N.bits(N.zz(F.col("step")), 2))


def align(frags: DataFrame, uniform: DataFrame, dt: Column) -> DataFrame:
    """Uniform samples back at the original times by two equi-joins on the computed index of the interval."""
    n = uniform.groupBy("track_id", "frag_id").agg((F.max("j") + 1).alias("m"))
    rest = (F.col("t") - F.min("t").over(W.partitionBy("track_id", "frag_id"))).alias("rest")
    rows = frags.select("track_id", "frag_id", "t", "pos", dt.alias("dt"), rest).join(n, ["track_id", "frag_id"])
    rows = rows.withColumn("j", F.greatest(F.lit(0), F.least(F.ceil(F.col("rest") / F.col("dt")) - 1, F.col("m") - 2)))
    left = uniform.withColumnRenamed("pos", "p1")
    right = uniform.select("track_id", "frag_id", (F.col("j") - 1).alias("j"), F.col("pos").alias("p2"))
    both = rows.join(left, ["track_id", "frag_id", "j"]).join(right, ["track_id", "frag_id", "j"])
    share = ((F.col("rest") - F.col("j") * F.col("dt")) / F.col("dt")).alias("share")
    both = both.select("track_id", "frag_id", "t", "pos", "p1", "p2", share)
    return both.select("track_id", "frag_id", "t", "pos", F.zip_with("p1", "p2", lambda a, b: a + (b - a) * F.col("share")).alias("pos2"))
