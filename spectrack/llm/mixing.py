"""Mixing sources to target weights by Sainte-Lague apportionment of equal blocks of words."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from spectrack.llm.common import numbered, ranked, row_key, staged, text_or_empty
from spectrack.llm.components import SHARE, skew_join

WORD = r"[^\x20\x09-\x0D]+"
SOURCE = ["src", "src_null"]
PORTION = 256  # copies of a text made in one place


def targets(sources: DataFrame, weights: list[float], share: float, limit: float) -> DataFrame:
    """Add weight and target: `share` of all words dealt by weight; a source stops at `limit` times its
    size and its excess is dealt again. Two sums a round; no source leaves the executors."""
    given = F.array(*[F.lit(float(w)) for w in weights])
    placed = numbered(sources, [F.col("src_null"), F.col("src")], "__place")
    sources = staged(placed.withColumn("weight", given[(F.col("__place") % len(weights)).cast("int")]).drop("__place"), "sources")
    whole = share * (sources.agg(F.sum("source_size")).first()[0] or 0)
    top = F.col("source_size") * F.lit(float(limit))
    rate, last = 0.0, -1
    while True:
        full = top <= F.col("weight") * F.lit(rate)
        used, left, n = sources.agg(F.sum(F.when(full, top)), F.sum(F.when(~full, F.col("weight"))), F.sum(full.cast("int"))).first()
        if not left or n == last:
            break
        rate, last = (whole - (used or 0.0)) / left, n
    return sources.withColumn("target", F.when(full, top).otherwise(F.col("weight") * F.lit(rate)))


def _quotients(parts: DataFrame, votes: str, seats: str) -> DataFrame:
    """Of parts with `__all` votes and `__n` parts in their group: `__sure` seats, and up to `__most` a row for each
    further quotient that may win one.

    All quotients down to the deciding divisor count, and that divisor is known within n/2 seats of n parts,
    so of each part only the few quotients about its proportional share are listed; the ones above are certain."""
    fair = F.col(votes) * F.col(seats) / F.col("__all")
    about = F.floor(fair + 0.5)
    slack = F.ceil(fair * F.col("__n") / (2 * F.col(seats))) + 1
    some = (F.col(votes) > 0) & (F.col(seats) > 0)
    zero = F.lit(0).cast("long")
    return parts.withColumn("__sure", F.when(some, F.greatest(zero, about - slack)).otherwise(zero)).withColumn("__most", F.when(some, about + slack).otherwise(zero))


def _listed(parts: DataFrame, votes: str) -> DataFrame:
    some = F.col("__most") > 0
    return parts.withColumn("__k", F.explode(F.expr("sequence(__sure, __most)"))).withColumn("__q", F.when(some, F.col(votes) / (2 * F.col("__k") + 1)))


def apportion(parts: DataFrame, group: list[str], votes: str, seats: str, out: str) -> DataFrame:
    """Add `out`: the seats each part gets of its group's `seats` by highest quotients votes / (2k + 1). Equal
    quotients go to the smaller part key. A group's parts meet in one window, so their number is for the caller to
    bound; without a group all parts, however many, are ordered by ranges over the executors, and `seats` is one number."""
    names = parts.columns
    keys = [c for c in names if c not in (votes, seats)]
    if group:
        w = W.partitionBy(*group)
        sure = _quotients(parts.withColumn("__all", F.sum(votes).over(w)).withColumn("__n", F.count(F.lit(1)).over(w)), votes, seats)
        listed = _listed(sure.withColumn("__open", F.col(seats) - F.sum("__sure").over(w)), votes)
        won = (F.row_number().over(w.orderBy(F.col("__q").desc_nulls_last(), *keys)) <= F.col("__open")) & F.col("__q").isNotNull()
    else:
        every, n, whole = parts.agg(F.sum(votes), F.count(F.lit(1)), F.max(seats)).first()
        sure = _quotients(parts.withColumn("__all", F.lit(every)).withColumn("__n", F.lit(n)), votes, seats)
        taken = sure.agg(F.sum("__sure")).first()[0] or 0
        listed = numbered(_listed(sure, votes), [F.col("__q").desc_nulls_last(), *map(F.col, keys), F.col("__k")], "__place")
        won = (F.col("__place") < (whole or 0) - taken) & F.col("__q").isNotNull()
    return listed.withColumn("__won", won.cast("long")).groupBy(*names, "__sure").agg(F.sum("__won").alias("__more")).select(*names, (F.col("__sure") + F.col("__more")).alias(out))


def _told_apart(rows: DataFrame, total: int) -> DataFrame:
    """Add nth: 0 for the first row of a row key, 1 for its next and so on, over as many tasks as a key has rows for. Which
    of equal rows is which makes no difference to the table."""
    per_key = staged(rows.groupBy("row_key").agg(F.count(F.lit(1)).alias("n")).filter("n > 1"), "repeated")
    if not per_key.count():
        return rows.withColumn("nth", F.lit(0).cast("long"))
    hot = F.col("n") > total / SHARE
    one = rows.join(F.broadcast(per_key.filter(hot)), "row_key", "left_anti").join(per_key.filter(~hot), "row_key", "left_anti")
    more = staged(skew_join(rows, per_key, ["row_key"], total).drop("n"), "copies")
    return one.withColumn("nth", F.lit(0).cast("long")).unionByName(ranked(more, ["row_key"], [F.col("rid")], total, "nth"))


def _edge(block: Column) -> Column:
    """First word of a block: a shard's words are cut into blocks that are equal to within a word."""
    return F.floor(block.cast("decimal(38,0)") * F.col("shard_size") / F.col("blocks")).cast("long")


def mix(
    docs: DataFrame,
    weights: list[float] = [5, 2, 1],  # noqa: B006
    share: float = 1.5,
    limit: int = 2,
    block: int = 16,
    seed: int = 11,
    rows_per_shard: int = 500,
    most_shards: int = 4096,
    id_col: str = "doc_id",
    text_col: str = "text",
    source_col: str = "source",
) -> DataFrame:
    """What the mix takes of every row: doc_id, size, source_size, target, taken, and how: `passes` whole
    copies, then the words [from_1, to_1) and [from_2, to_2) of the text; row_key.

    Sources in code point order (null last) get the weights in turn. Their targets, in blocks of `block`
    words, are apportioned to sources and then to a source's shards by highest quotients. A shard's rows
    stand in seeded hash order; its blocks are taken whole as often as the quota allows, and the rest of
    the quota is a seeded run of neighbouring blocks, so that only the run's two ends cut a text. Everything is a function of the rows: reruns agree.
    Null text has no words; repeated rows each count; an empty table gives an empty result. A source
    may hold any share of the rows: it has many shards, and its row is broadcast when it is hot."""
    rows = staged(
        docs.select(
            F.col(id_col).alias("doc_id"),
            F.coalesce(F.col(source_col), F.lit("")).alias("src"),
            F.col(source_col).isNull().alias("src_null"),
            F.size(F.regexp_extract_all(text_or_empty(text_col), F.lit(WORD), F.lit(0))).cast("long").alias("size"),
            row_key(id_col, text_col).alias("row_key"),
            F.monotonically_increasing_id().alias("rid"),
        ),
        "sizes",
    )
    rows = _told_apart(rows, rows.count())
    sources = rows.groupBy(*SOURCE).agg(F.sum("size").alias("source_size"), F.count(F.lit(1)).alias("n"))
    aimed = staged(targets(sources, weights, share, limit), "targets")
    total, whole = aimed.agg(F.coalesce(F.sum("n"), F.lit(0)), F.coalesce(F.sum("target"), F.lit(0.0))).first()
    quota = apportion(aimed.select(*SOURCE, "target").withColumn("all_seats", F.lit(round(whole / block)).cast("long")), [], "target", "all_seats", "source_seats")
    shards = F.least(F.lit(most_shards), F.ceil(F.col("n") / rows_per_shard)).cast("int")
    per_source = staged(aimed.join(quota.select(*SOURCE, "source_seats"), SOURCE).withColumn("shards", shards), "quotas")

    h = F.xxhash64("row_key", "nth", F.lit(seed))
    dealt = skew_join(rows, per_source, SOURCE, total).withColumn("shard", F.pmod(h, F.col("shards")).cast("int"))
    cell = [*SOURCE, "shard"]
    order = W.partitionBy(*cell).orderBy(F.xxhash64("row_key", "nth", F.lit(seed + 1)), "row_key", "nth")
    dealt = dealt.withColumn("end", F.sum("size").over(order.rowsBetween(W.unboundedPreceding, W.currentRow)))
    cells = dealt.groupBy(*cell, "source_seats").agg(F.sum("size").alias("shard_size"), F.count(F.lit(1)).alias("n"))
    cells = apportion(cells.select(*cell, "shard_size", "source_seats"), SOURCE, "shard_size", "source_seats", "seats")
    blocks = F.greatest(F.lit(1).cast("long"), F.floor(F.col("shard_size") / block + 0.5))
    cells = cells.withColumn("blocks", blocks).withColumn("seats", F.least("seats", limit * F.col("blocks")))
    cells = cells.withColumn("passes", F.floor(F.col("seats") / F.col("blocks"))).withColumn("run", F.col("seats") % F.col("blocks"))
    start = F.pmod(F.xxhash64(*cell, F.lit(seed + 2)), F.col("blocks"))
    cells = cells.withColumn("run_from", start).withColumn("run_to", F.col("run_from") + F.col("run"))
    # a run that passes the shard's end goes on at its start
    cells = cells.select(
        *cell,
        "passes",
        _edge(F.col("run_from")).alias("a1"),
        _edge(F.least("run_to", "blocks")).alias("b1"),
        _edge(F.greatest(F.lit(0).cast("long"), F.col("run_to") - F.col("blocks"))).alias("b2"),
    )
    out = dealt.join(cells, cell).withColumn("begin", F.col("end") - F.col("size"))

    def inside(word: Column) -> Column:
        return F.greatest(F.lit(0).cast("long"), F.least(F.col("size"), word - F.col("begin")))

    out = out.withColumn("from_1", inside(F.col("a1"))).withColumn("to_1", inside(F.col("b1"))).withColumn("from_2", F.lit(0).cast("long")).withColumn("to_2", inside(F.col("b2")))
    taken = F.col("passes") * F.col("size") + F.col("to_1") - F.col("from_1") + F.col("to_2")
    return out.select("doc_id", "size", "source_size", "target", taken.cast("long").alias("taken"), "passes", "from_1", "to_1", "from_2", "to_2", "row_key")


def mixed_texts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", **how) -> DataFrame:
    """The mix itself, in docs' columns: a row for each whole copy taken, and one for each run of words,
    joined by spaces, where a text is cut. Rows that share id and text are taken together."""
    key = row_key(id_col, text_col)
    per_row = mix(docs, id_col=id_col, text_col=text_col, source_col=source_col, **how).filter("taken > 0")
    spans = F.array(
        F.struct(F.col("from_1").alias("a"), F.col("to_1").alias("b")),
        F.struct(F.col("from_2").alias("a"), F.col("to_2").alias("b")),
    )
    whole = F.array_repeat(F.struct(F.lit(0).cast("long").alias("a"), F.col("size").alias("b")), F.col("passes").cast("int"))
    parts = per_row.select("row_key", "size", F.explode(F.concat(whole, spans)).alias("s")).filter("s.b > s.a")
    parts = parts.groupBy("row_key", "s.a", "s.b", (F.col("s.b") - F.col("s.a") == F.col("size")).alias("all")).agg(F.count(F.lit(1)).alias("n"))
    portion = F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("n") - 1) / PORTION)))
    parts = parts.withColumn("portion", portion).withColumn("copies", F.least(F.lit(PORTION), F.col("n") - F.col("portion") * PORTION).cast("int"))
    parts = staged(parts.select(F.col("row_key").alias("__row_key"), F.struct("a", "b", "all").alias("__s"), "portion", "copies").withColumnsRenamed({"portion": "__portion", "copies": "__copies"}), "parts")
    once = docs.withColumn("__row_key", key).dropDuplicates(["__row_key"])
    each = once.join(parts.filter("__portion = 0"), "__row_key")
    if parts.filter("__portion > 0").count():  # a text with more copies than a portion has the others made elsewhere
        each = each.unionByName(once.join(parts.filter("__portion > 0"), "__row_key").repartition("__row_key", "__portion"))
    each = each.withColumn("__copy", F.explode(F.array_repeat(F.lit(0), F.col("__copies"))))
    words = F.regexp_extract_all(F.col(text_col), F.lit(WORD), F.lit(0))
    cut = F.array_join(F.slice(words, (F.col("__s.a") + 1).cast("int"), (F.col("__s.b") - F.col("__s.a")).cast("int")), " ")
    text = F.when(F.col("__s.all"), F.col(text_col)).otherwise(cut)
    columns = [text.alias(c) if c == text_col else F.col(c) for c in docs.columns]
    return each.select(*columns)
