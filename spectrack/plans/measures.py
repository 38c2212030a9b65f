"""Cost and accuracy measures over rows of tracks."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from spectrack.functions.track import SECTIONS


def compression_ratio(size: str = "bytes", raw: str = "raw_bytes") -> Column:
    """Sums over the whole set, not a mean of ratios."""
    return F.sum(size) / F.sum(raw)


def max_sed() -> Column:
    return F.max("max_sed")


def mean_sed() -> Column:
    return F.sum("sum_sed") / F.sum("n")


def error_point_pct() -> Column:
    return 100 * F.sum("n_corr") / F.sum("n")


def kept_ratio() -> Column:
    return F.sum("kept") / F.sum("n")


def improvement(ratio: Column) -> Column:
    return 1 / ratio - 1


def error_reduction(ours: Column, theirs: Column) -> Column:
    return 1 - ours / theirs


def size_breakdown(container: DataFrame, *by: str) -> DataFrame:
    """Bits a section, and in total, for each group and overall."""
    each = container.select(*by, F.explode(F.array(*[F.struct(F.lit(s).alias("section"), F.col(f"bits_{s}").alias("bits")) for s in SECTIONS])).alias("x"))
    return each.select(*by, "x.section", "x.bits").rollup(*by, "section").agg(F.sum("bits").alias("bits"))


def relative(rows: DataFrame, value: str, base: str, keys: list[str], method: str = "method") -> DataFrame:
    """Each method's value over the base method's, for equal keys."""
    own = rows.filter(F.col(method) == base).select(*keys, F.col(value).alias("__base"))
    return rows.join(own, keys).withColumn("relative", F.col(value) / F.col("__base")).drop("__base")


def best(rows: DataFrame, keys: list[str], param: str, value: str) -> DataFrame:
    """The parameter of least value for equal keys; of equal values the least parameter."""
    return rows.groupBy(*keys).agg(F.min_by(param, F.struct(value, param)).alias(f"best_{param}"), F.min(value).alias(f"best_{value}"))


def describe(points: DataFrame) -> DataFrame:
    """tracks, points, mean and variance of the gap in seconds."""
    gap = (F.col("t") - F.lag("t").over(W.partitionBy("track_id").orderBy("t"))) / 1e6
    return points.withColumn("gap", gap).agg(
        F.count_distinct("track_id").alias("tracks"), F.count(F.lit(1)).alias("points"), F.avg("gap").alias("gap_mean"), F.var_pop("gap").alias("gap_var")
    )


def zero_share(coded: DataFrame) -> DataFrame:
    """Share of zeros among the coefficients' codes, on each axis."""
    return coded.groupBy("axis").agg(F.avg(F.when(F.col("code") == 0, 1.0).otherwise(0.0)).alias("zero_share"), F.count(F.lit(1)).alias("codes"))


def energy(coefficients: DataFrame, share: float = 0.25) -> DataFrame:
    """Share of the energy in the lowest part of each block's spectrum, over all blocks."""
    e = F.col("c") * F.col("c")
    low = F.sum(F.when(F.col("k") <= F.ceil(F.col("len") * share), e).otherwise(0.0))
    return coefficients.groupBy("axis").agg((low / F.sum(e)).alias("low_share"))
