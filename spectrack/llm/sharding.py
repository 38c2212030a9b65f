"""Placement in shards by a tree of weighted hash draws, in DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spectrack.llm.common import ranked, staged, text_or_empty

# regions -> racks -> weights of the shards
Tree = list[list[list[float]]]


def even_tree(shards: int, racks: int = 4, per_rack: int = 2) -> Tree:
    """Regions of `racks` racks of `per_rack` shards of weight 1; what is left over gets a smaller region."""
    tree: Tree = []
    left = shards
    while left > 0:
        region = []
        for _ in range(racks):
            if left > 0:
                region.append([1.0] * min(per_rack, left))
                left -= len(region[-1])
        tree.append(region)
    return tree


def grown(tree: Tree, weight: float = 1.0) -> Tree:
    """One more shard, in a region of its own: no other subtree's weight changes, so documents move
    into the new shard only."""
    return [*tree, [[weight]]]


def shard_count(tree: Tree) -> int:
    return sum(len(rack) for region in tree for rack in region)


def _pick(key: Column, weights: list[Column], parent: Column, level: int) -> Column:
    """Index of the child that wins. Each child draws ln(u) / weight from its own hash of the key, so a
    change of one weight can only move keys to or from that child. No child, or one without weight, draws minus infinity;
    of equal draws the first child's counts."""

    def draw(w: Column, i: int) -> Column:
        bits = F.shiftrightunsigned(F.xxhash64(key, F.lit(level), parent, F.lit(i)), 11)
        return F.when(w > 0, F.log((bits.cast("double") + 0.5) / F.lit(float(1 << 53))) / w).otherwise(F.lit(float("-inf")))

    draws = [draw(w, i) for i, w in enumerate(weights)]
    best = F.greatest(*draws) if len(draws) > 1 else draws[0]
    at = F.lit(0)
    for i in reversed(range(len(draws))):
        at = F.when(draws[i] == best, i).otherwise(at)
    return at


def _level(at: Column, table: list[list[float]]) -> list[Column]:
    """Row `at` of a table of weights, a column a child; rows end where their parent's children do."""
    most = max(map(len, table))
    return [F.coalesce(F.get(F.array(*[F.lit(float(row[i]) if i < len(row) else 0.0) for row in table]), at), F.lit(0.0)) for i in range(most)]


def place(rows: DataFrame, key: Column, tree: Tree, to: str) -> DataFrame:
    """Add `to`: the shard number (in the tree's order) that the key descends to: region, then rack, then shard. Plain
    expressions of literals, a projection a level, so that all of it is generated code."""
    racks = [(a, b, rack) for a, region in enumerate(tree) for b, rack in enumerate(region)]
    first, n = [], 0
    for _, _, rack in racks:
        first.append(n)
        n += len(rack)
    rank_of = {(a, b): i for i, (a, b, _) in enumerate(racks)}
    base = F.array(*[F.lit(rank_of[a, 0] if region else 0) for a, region in enumerate(tree)])
    region, rack = f"__region_{to}", f"__rack_{to}"
    # a region's weight is its racks', a rack's its shards'
    rows = rows.withColumn(region, _pick(key, [F.lit(float(sum(map(sum, x)))) for x in tree], F.lit(0), 1))
    rows = rows.withColumn(rack, _pick(key, _level(F.col(region), [[float(sum(x)) for x in y] for y in tree]), F.col(region), 2))
    at = F.get(base, F.col(region)) + F.col(rack)
    leaf = _pick(key, _level(at, [x for _, _, x in racks]), F.col(region) * 4096 + F.col(rack), 3)
    return rows.withColumn(to, (F.get(F.array(*map(F.lit, first)), at) + leaf).cast("int")).drop(region, rack)


def shard(docs: DataFrame, tree: Tree, more: Tree | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Place every row by its id and the tree (law `key`).

    Result: doc_id, size (UTF-8 bytes of the text plus 16), text_crc32, law, shard, slot (gapless from 0 in
    each shard), grown_shard (place in the tree `more`). Null text has no bytes and CRC 0. Rows with equal
    ids share a shard; a null id is a key like any other. Texts are read once and not shuffled: the narrow
    row is written, and its ranks are dealt over many tasks a shard. An empty table gives an empty result; further
    columns are ignored."""
    text = text_or_empty(text_col)
    kind = "long" if dict(docs.dtypes)[id_col].endswith("int") else "string"
    rows = docs.select(
        F.col(id_col).alias("doc_id"), (F.octet_length(text).cast("long") + 16).alias("size"), F.crc32(text).alias("text_crc32"), F.monotonically_increasing_id().alias("rid")
    )
    rows = place(rows, F.col("doc_id").cast(kind), tree, "shard")
    rows = rows.withColumn("grown_shard", F.lit(None).cast("int")) if more is None else place(rows, F.col("doc_id").cast(kind), more, "grown_shard")
    rows = staged(rows.withColumn("law", F.lit("key")), "placed")
    order = [F.col("doc_id"), F.col("text_crc32"), F.col("size")]
    return ranked(rows, ["shard"], order, rows.count(), "slot", spread=F.col("rid")).select("doc_id", "size", "text_crc32", "law", "shard", "slot", "grown_shard")
