"""Exact de-duplication by a heavy-hitter split, in DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from spectrack.llm.common import SPACES, row_key, staged, text_or_empty


def digests(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One narrow row per document: a row number, its id, the SHA-256 of the text without white space,
    the length in code points, and the row key. Written once, since three short passes follow."""
    text = text_or_empty(text_col)
    return staged(
        docs.select(
            F.monotonically_increasing_id().alias("rid"),
            F.col(id_col).alias("doc_id"),
            F.sha2(F.translate(text, SPACES, ""), 256).alias("text_sha256"),
            F.length(text).cast("long").alias("n_points"),
            row_key(id_col, text_col).alias("row_key"),
        ),
        "digests",
    )


def exact_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", heavy: int = 1024, tracked: int = 16384, least: int = 64) -> DataFrame:
    """Decide for every row whether it stays.

    Misra-Gries summaries (`tracked` counters a task, merged) name up to `heavy` digests that look frequent
    (at least `least` rows). Exact counts and winners of those are found with map-side aggregation,
    and broadcast: at most `heavy` rows, whatever the input. All other digests are shuffled once. Every
    digest passes through exactly one of both ways (one that isn't named has under a `heavy`th of the rows), so a digest missed or wrongly named by the summary
    changes the cost and not the result.

    Result: doc_id, keep_id, group_size, kept, text_sha256, row_key. Null text counts as empty. The
    longest original text stays, then the smallest doc_id (a null one last), then the first row: of fully
    equal rows exactly one is kept. An empty table gives an empty result; further columns are ignored."""
    rows = digests(docs, id_col, text_col)
    named = rows.agg(F.expr(f"approx_top_k(text_sha256, {int(heavy)}, {int(tracked)})").alias("top")).select(F.explode("top").alias("t"))
    names = F.broadcast(named.filter(F.col("t.count") >= least).select(F.col("t.item").alias("text_sha256")))

    best = F.struct((-F.col("n_points")).alias("a"), F.col("doc_id").isNull().alias("b"), F.col("doc_id").alias("c"), F.col("rid").alias("d"))
    winners = rows.join(names, "text_sha256").groupBy("text_sha256").agg(F.min(best).alias("best"), F.count(F.lit(1)).alias("group_size"))
    frequent = rows.join(F.broadcast(winners), "text_sha256").select(
        "doc_id", F.col("best.c").alias("keep_id"), "group_size", (F.col("rid") == F.col("best.d")).alias("kept"), "text_sha256", "row_key"
    )

    group = W.partitionBy("text_sha256")
    by_rank = group.orderBy(F.col("n_points").desc(), F.col("doc_id").asc_nulls_last(), F.col("rid"))
    others = rows.join(names, "text_sha256", "left_anti").select(
        "doc_id",
        F.first("doc_id").over(by_rank).alias("keep_id"),
        F.count(F.lit(1)).over(group).alias("group_size"),
        (F.row_number().over(by_rank) == 1).alias("kept"),
        "text_sha256",
        "row_key",
    )
    return frequent.unionByName(others)
