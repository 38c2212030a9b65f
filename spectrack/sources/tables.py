"""Readers, sinks, and tracks derived from the given tables.

POINTS: track_id string, t bigint (microseconds), pos array<double>. Running sums are kept in integer
millionths, so every engine gets the same doubles."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window as W

POINTS = T.StructType([T.StructField("track_id", T.StringType(), False), T.StructField("t", T.LongType(), False), T.StructField("pos", T.ArrayType(T.DoubleType(), False), False)])
MILLION = 1_000_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def micros(c: str) -> Column:
    return F.unix_micros(F.col(c).cast("timestamp"))


def whole(x: Column) -> Column:
    return F.floor(x + 0.5).cast("bigint")


def read_gps_csv(spark: SparkSession, path: str, header: bool = True) -> DataFrame:
    """Logs of track, time in microseconds, and two or three coordinates, as many as the header (or the first row)
    has. A row with a field missing or unreadable keeps a null there, so `usable` refuses it and `refused` counts it."""
    df = spark.read.csv(path, header=header)
    names = ["track_id", "t", "x", "y", "z"]
    if not header:
        df = df.toDF(*names[: len(df.columns)])
    return df.select("track_id", F.col("t").try_cast("long").alias("t"), F.array(*[F.col(c).try_cast("double") for c in names[2:] if c in df.columns]).alias("pos"))


def read_gps_json(spark: SparkSession, path: str) -> DataFrame:
    """The same as JSON lines; a row without z is planar."""
    df = spark.read.schema("track_id string, t long, x double, y double, z double").json(path)
    return df.select("track_id", "t", F.when(F.col("z").isNull(), F.array("x", "y")).otherwise(F.array("x", "y", "z")).alias("pos"))


def write_container(container: DataFrame, path: str, buckets: int = 64) -> None:
    """Containers partitioned by a hash of the track, sorted by start: readers prune by bucket, track and time."""
    made = container.withColumn("track_bucket", F.pmod(F.xxhash64("track_id"), F.lit(buckets)).cast("int"))
    made.repartition("track_bucket").sortWithinPartitions("track_id", "t_min").write.partitionBy("track_bucket").parquet(path)


def read_container(spark: SparkSession, path: str, track: str | None = None, t_from: int | None = None, t_to: int | None = None, buckets: int = 64) -> DataFrame:
    """Only what may overlap the time range; every condition reaches the scan."""
    df = spark.read.parquet(path)
    if track is not None:
        bucket = spark.range(1).select(F.pmod(F.xxhash64(F.lit(track)), F.lit(buckets))).first()[0]
        df = df.filter((F.col("track_bucket") == bucket) & (F.col("track_id") == track))
    if t_from is not None:
        df = df.filter(F.col("t_max") >= t_from)
    return df if t_to is None else df.filter(F.col("t_min") <= t_to)


def usable(points: DataFrame) -> DataFrame:
    """Rows with a track, a time and finite coordinates."""
    fine = F.forall("pos", lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf"))) & (F.size("pos") > 0)
    return points.filter(F.col("track_id").isNotNull() & F.col("t").isNotNull() & fine)


def refused(points: DataFrame) -> int:
    return points.count() - usable(points).count()


def _scaled(*sums: str) -> Column:
    return F.array(*[F.col(s) / MILLION for s in sums]).alias("pos")


def _events(spark: SparkSession, sf_dir: str, track: Column) -> DataFrame:
    e = table(spark, sf_dir, "events").select(track.cast("string").alias("track_id"), "event_id", micros("ts").alias("t"), "value", "props")
    return e.select(
        "track_id", "event_id", "t", whole((F.col("value") - 50) * MILLION).alias("dx"), (F.get_json_object("props", "$.k").cast("bigint") * 2 - 99).alias("k2")
    ).withColumn("dy", F.col("k2") * 500_000)


def _running(df: DataFrame, order: list[str], **sums: str) -> DataFrame:
    w = W.partitionBy("track_id").orderBy(*order).rowsBetween(W.unboundedPreceding, W.currentRow)
    return df.withColumns({k: F.sum(v).over(w) for k, v in sums.items()})


def _smooth(df: DataFrame, order: list[str], *sums: str) -> Column:
    w = W.partitionBy("track_id").orderBy(*order).rowsBetween(-8, 8)
    return F.array(*[F.sum(s).over(w).cast("double") / F.count(s).over(w) / MILLION for s in sums]).alias("pos")


def ev_user(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = _running(_events(spark, sf_dir, F.col("user_id")), ["t", "event_id"], x="dx", y="dy")
    return df.select("track_id", "t", _scaled("x", "y"))


def ev_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = _running(_events(spark, sf_dir, F.lit("all")), ["t", "event_id"], x="dx", y="dy")
    return df.select("track_id", "t", _scaled("x", "y"))


def ev_type_smooth(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = _running(_events(spark, sf_dir, F.col("event_type")), ["t", "event_id"], x="dx", y="dy")
    return df.select("track_id", "t", _smooth(df, ["t", "event_id"], "x", "y"))


def ev_geo(spark: SparkSession, sf_dir: str) -> DataFrame:
    """track_id, t, lon, lat (degrees, about one UTM zone) and alt_ft (each 50th missing)."""
    w = W.partitionBy("track_id").orderBy("t", "event_id")
    df = _running(_events(spark, sf_dir, F.col("user_id")), ["t", "event_id"], x="dx", y="dy").withColumn("i", F.row_number().over(w))
    x, y = F.col("x") / MILLION, F.col("y") / MILLION
    alt = F.when(F.col("i") % 50 != 0, 10.0 * F.pmod(F.col("x"), F.lit(7 * MILLION)) / MILLION)
    return df.select("track_id", "t", (9.0 + x * 1e-5).alias("lon"), (48.0 + y * 1e-5).alias("lat"), alt.alias("alt_ft"))


def _suppliers(spark: SparkSession, sf_dir: str) -> DataFrame:
    order = ["l_orderkey", "l_linenumber", "l_partkey", "l_extendedprice"]
    rows = table(spark, sf_dir, "lineitem").select(
        F.col("l_suppkey").cast("string").alias("track_id"), micros("l_shipdate").alias("t"), *order, "l_quantity", "l_discount", "l_tax"
    )
    one = rows.withColumn("nth", F.row_number().over(W.partitionBy("track_id", "t").orderBy(*order))).filter("nth = 1")
    moves = one.select(
        "track_id", "t",
        whole((F.col("l_quantity") - 25.5) * MILLION).alias("dx"),
        whole((F.col("l_discount") - 0.05) * 400 * MILLION).alias("dy"),
        whole((F.col("l_tax") - 0.04) * 400 * MILLION).alias("dz"),
    )
    return _running(moves, ["t"], x="dx", y="dy", z="dz")


def li_supp(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _suppliers(spark, sf_dir).select("track_id", "t", _scaled("x", "y", "z"))


def li_supp_smooth(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = _suppliers(spark, sf_dir)
    return df.select("track_id", "t", _smooth(df, ["t"], "x", "y", "z"))


def _vectors(spark: SparkSession, sf_dir: str, dim: int) -> DataFrame:
    """Vectors as axes, `dim` neighbours a track; neighbours that aren't that many, at the table's end, are no track."""
    e = table(spark, sf_dir, "embeddings").select("vec_id", F.posexplode("embedding").alias("j", "e"))
    return e.select(
        F.floor(F.col("vec_id") / dim).cast("string").alias("track_id"), (F.col("vec_id") % dim).cast("int").alias("axis"), "j", whole(F.col("e").cast("double") * 1e9).alias("s0")
    )


def _bundled(df: DataFrame, s: str, dim: int) -> DataFrame:
    axes = [F.max(F.when(F.col("axis") == a, F.col(s))).alias(f"a{a}") for a in range(dim)]
    rows = df.groupBy("track_id", "j").agg(*axes).dropna(subset=[f"a{a}" for a in range(dim)])
    return rows.select("track_id", (F.col("j") * 100_000).cast("bigint").alias("t"), F.array(*[F.col(f"a{a}") / 1e9 for a in range(dim)]).alias("pos"))


def emb_uniform(spark: SparkSession, sf_dir: str, dim: int = 2) -> DataFrame:
    return _bundled(_vectors(spark, sf_dir, dim), "s0", dim)


def emb_cum(spark: SparkSession, sf_dir: str, dim: int = 2) -> DataFrame:
    w = W.partitionBy("track_id", "axis").orderBy("j").rowsBetween(W.unboundedPreceding, W.currentRow)
    df = _vectors(spark, sf_dir, dim).withColumn("s1", F.sum("s0").over(w)).withColumn("s2", F.sum("s1").over(w))
    return _bundled(df, "s2", dim)


def ord_cust(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = table(spark, sf_dir, "orders").select(F.col("o_custkey").cast("string").alias("track_id"), micros("o_orderdate").alias("t"), whole((F.col("o_totalprice") - 250_000) * 1000).alias("d"))
    days = o.groupBy("track_id", "t").agg(F.sum("d").alias("dx"))
    return _running(days, ["t"], x="dx").select("track_id", "t", _scaled("x"))


def int_signal(spark: SparkSession, sf_dir: str) -> DataFrame:
    """signal, i, n: integers in order, for the lossless path."""
    d = table(spark, sf_dir, "documents").select(F.lit("n_chars").alias("signal"), F.col("doc_id").alias("i"), F.col("doc_id").alias("j"), F.col("n_chars").alias("n"))
    o = table(spark, sf_dir, "orders").select(F.lit("o_orderkey").alias("signal"), micros("o_orderdate").alias("i"), F.col("o_orderkey").alias("j"), F.col("o_orderkey").alias("n"))
    return d.unionByName(o)


FIXTURES = {"ev_user": ev_user, "ev_all": ev_all, "ev_type_smooth": ev_type_smooth, "li_supp": li_supp, "li_supp_smooth": li_supp_smooth, "emb_uniform": emb_uniform, "emb_cum": emb_cum, "ord_cust": ord_cust}
