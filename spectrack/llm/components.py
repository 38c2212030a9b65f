"""Connected components of a large graph, and joins that survive hot keys."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spectrack.llm.common import discard, staged

# keys with more than one part in SHARE of all rows are joined by broadcast; there are fewer than SHARE of them
SHARE = 512


def skew_join(rows: DataFrame, per_key: DataFrame, keys: list[str], total: int, n: str = "n") -> DataFrame:
    """Inner join of rows with per_key (unique keys; `n` counts the rows of each key, `total` all rows).

    Keys holding over total/SHARE rows number fewer than SHARE, so that part of per_key is broadcast and
    their rows never move; all other keys are shuffled as usual."""
    hot = F.col(n) > total / SHARE
    few = F.broadcast(per_key.filter(hot))
    others = rows.join(few.select(*keys), keys, "left_anti").join(per_key.filter(~hot), keys)
    return rows.join(few, keys).unionByName(others)


def components(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(node, root) for every node of the undirected edges (a, b); root is the component's least node.

    Alternating large-star and small-star steps, each a map-side minimum and a skew-proof join; one table
    in the shared folder a round. Ends when a round changes nothing, which takes about log(nodes) rounds."""
    high, low = F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")
    now = staged(edges.filter("a <> b").select(high, low).distinct(), "edges")
    state = _state(now)
    for _ in range(most_rounds):
        if state[0] == 0:
            break
        both = now.select(F.col("a").alias("u"), F.col("b").alias("v")).unionByName(now.select(F.col("b").alias("u"), F.col("a").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m"), F.count(F.lit(1)).alias("n")).withColumn("m", F.least("u", "m"))
        large = skew_join(both.filter("v > u"), least, ["u"], 2 * state[0]).select(F.col("v").alias("a"), F.col("m").alias("b")).distinct()
        large = staged(large, "large")
        total = large.count()
        least = large.groupBy("a").agg(F.min("b").alias("m"), F.count(F.lit(1)).alias("n"))
        small = skew_join(large, least, ["a"], total)
        # to the minimum from the node itself and from its other smaller neighbours
        small = small.select(F.explode(F.array(F.col("a"), F.col("b"))).alias("a"), F.col("m").alias("b")).filter("a <> b").distinct()
        after = staged(small, "edges")
        discard(large)
        discard(now)
        last, state, now = state, _state(after), after
        if state == last:
            break
    else:
        raise RuntimeError("components did not settle")
    return now.select(F.col("a").alias("node"), F.col("b").alias("root"))


def _state(edges: DataFrame) -> tuple[int, int, int]:
    h = F.xxhash64("a", "b")
    r = edges.agg(F.count(F.lit(1)), F.coalesce(F.bit_xor(h), F.lit(0)), F.coalesce(F.sum(F.shiftright(h, 24)), F.lit(0))).first()
    return r[0], r[1], r[2]
