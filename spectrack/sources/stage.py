"""Tables written into the shared folder of the session."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

_own_dir: str | None = None


def stage_dir(spark: SparkSession) -> str:
    """The folder that spark.checkpoint.dir names. Without one, a temporary folder of this machine, which only a local
    master shares with its executors; any other master is refused."""
    global _own_dir
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if _own_dir is None:
        _own_dir = "file://" + tempfile.mkdtemp(prefix="spectrack-stage-")
    return _own_dir


def new_path(spark: SparkSession, name: str) -> str:
    return f"{stage_dir(spark)}/spectrack/{uuid.uuid4().hex}/{name}"


def staged(df: DataFrame, name: str, compression: str | None = None) -> DataFrame:
    """Write df as Parquet into the shared folder and read it back: lineage ends here, so a lost
    executor costs a re-read and no work is done twice."""
    spark = df.sparkSession
    path = new_path(spark, name)
    df.write.parquet(path, compression=compression)
    schema = T.StructType([T.StructField(f.name, f.dataType, True) for f in df.schema.fields])
    out = spark.read.schema(schema).parquet(path)
    out._staged_path = path
    return out


def discard(df: DataFrame | None) -> None:
    """Delete a table made by staged() that nothing reads any more."""
    path = getattr(df, "_staged_path", None)
    if path is None:
        return
    jvm, sc = df.sparkSession._jvm, df.sparkSession.sparkContext
    target = jvm.org.apache.hadoop.fs.Path(path).getParent()
    target.getFileSystem(sc._jsc.hadoopConfiguration()).delete(target, True)
