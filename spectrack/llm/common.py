"""Shared pieces: staged tables, distributed ranks, row keys."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from spectrack.sources.stage import discard, stage_dir, staged

__all__ = ["SPACES", "discard", "keep_rows", "lean", "numbered", "ranked", "row_key", "stage_dir", "staged", "text_or_empty"]

# the six ASCII white space characters that separate words
SPACES = " \t\n\x0b\x0c\r"

def lean(batches: Iterator[pa.RecordBatch], rows: int = 1000) -> Iterator[pa.RecordBatch]:
    """The batches in smaller slices; what Arrow's pool keeps of the ones before goes back to the system."""
    for b in batches:
        for at in range(0, b.num_rows, rows):
            yield b.slice(at, rows)
        del b
        pa.default_memory_pool().release_unused()


def text_or_empty(col: str = "text") -> Column:
    return F.coalesce(F.col(col), F.lit(""))


def row_key(id_col: str = "doc_id", text_col: str = "text") -> Column:
    """A non-null key that only rows with the same id and the same text share."""
    return F.concat_ws(
        ":",
        F.coalesce(F.col(id_col).cast("string"), F.lit("-")),
        F.hex(F.xxhash64(F.col(text_col))),
        F.coalesce(F.octet_length(F.col(text_col)).cast("string"), F.lit("-")),
    )


def keep_rows(docs: DataFrame, kept: DataFrame, key: Column) -> DataFrame:
    """Rows of docs whose key is in kept (column `row_key`, unique); of rows sharing a key one stays.

    Rows of one key are brought down to one a task before the shuffle, so any share of the rows may have the same one;
    the join runs on that shuffle's partitioning and sort, so texts cross the network once."""
    once = docs.withColumn("__row_key", key).dropDuplicates(["__row_key"])
    return once.join(kept.select(F.col("row_key").alias("__row_key")), "__row_key").select(*docs.columns)


def ranked(df: DataFrame, keys: list[str], order: list[Column], total: int, to: str, rows_per_bucket: int = 100_000, spread: Column | None = None) -> DataFrame:
    """Add `to`: the gapless rank from 0 of each row within its key, with no key in a single task.

    Rows of a key are dealt by hash to buckets; bucket counts give each bucket its first rank, and the
    rank inside a bucket comes from a window on (key, bucket). The rank is an order by bucket, then by
    `order`, so it needs no global sort and a key may hold any share of the rows. `spread`, a number that equal rows don't
    share, deals those too; df is read twice, so it must be a stored column."""
    buckets = max(64, -(-total // rows_per_bucket))
    dealt = df.withColumn("__bucket", F.pmod(F.xxhash64(*order, *([] if spread is None else [spread])), F.lit(buckets)).cast("int"))
    cell = [*keys, "__bucket"]
    before = W.partitionBy(*keys).orderBy("__bucket").rowsBetween(W.unboundedPreceding, -1)
    first = dealt.groupBy(*cell).agg(F.count(F.lit(1)).alias("__n")).select(*cell, F.coalesce(F.sum("__n").over(before), F.lit(0)).alias("__first"))
    within = dealt.withColumn("__at", F.row_number().over(W.partitionBy(*cell).orderBy(*order)) - 1)
    return within.join(first, cell).withColumn(to, (F.col("__first") + F.col("__at")).cast("long")).drop("__bucket", "__first", "__at")


def numbered(df: DataFrame, order: list[Column], to: str) -> DataFrame:
    """Add `to`: each row's place from 0 in the order, which has no ties. A sort by ranges, and the ranges' counts, which
    are as many as the session has shuffle partitions; the rows stay where the sort put them."""
    parts = max(1, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    placed = staged(df.repartitionByRange(parts, *order).sortWithinPartitions(*order).withColumn("__id", F.monotonically_increasing_id()), "sorted")
    part, at = F.shiftright("__id", 33), F.col("__id").bitwiseAND(F.lit((1 << 33) - 1))
    n = {r["p"]: r["n"] for r in placed.groupBy(part.alias("p")).agg(F.count(F.lit(1)).alias("n")).collect()}
    first = [0]
    for i in range(max([*n, parts])):
        first.append(first[-1] + n.get(i, 0))
    return placed.withColumn(to, F.array(*[F.lit(x).cast("long") for x in first])[part.cast("int")] + at).drop("__id")
