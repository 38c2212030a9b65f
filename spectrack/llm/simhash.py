"""Near-duplicates by SimHash fingerprints and covering locality-sensitive hashing."""

from __future__ import annotations

import random
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from spectrack.llm.common import lean, row_key, staged
from spectrack.llm.components import components, skew_join

SEED = 42


def fingerprint(text: str | None, width: int = 3) -> int:
    """64-bit SimHash over the text's word shingles, repeats included; 0 without words. A bit is set if
    it is in more than half of the shingles' XXH64 values."""
    # both bytes.lower and bytes.split know ASCII only
    words = (text or "").encode("utf-8").lower().split()
    if not words:
        return 0
    joined, h = b" ".join(words), xxhash.xxh64_intdigest
    if len(words) <= width:
        return h(joined, SEED)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))
    from_, to = starts[: 1 - width].tolist(), ends[width - 1 :].tolist()
    n, ones = len(to), np.zeros(64, np.int64)
    for at in range(0, n, 1 << 16):
        part = [h(joined[s:e], SEED) for s, e in zip(from_[at : at + (1 << 16)], to[at : at + (1 << 16)], strict=True)]
        bits = np.unpackbits(np.array(part, "<u8").view(np.uint8), bitorder="little").reshape(-1, 64)
        ones += bits.sum(axis=0, dtype=np.int32)
    return int(np.packbits(ones * 2 > n, bitorder="little").view("<u8")[0])


def covering_masks(radius: int = 2, bits: int = 64, seed: int = 7) -> list[int]:
    """2**(radius+1) - 1 masks such that any two words differing in at most `radius` bits agree under one.

    Every bit position gets a non-zero vector of radius+1 bits; mask v keeps the positions whose vector
    has odd inner product with v. The vectors of `radius` positions cannot span the space, so some v is
    orthogonal to all of them, and its mask keeps none of the differing positions."""
    k = radius + 1
    vectors = [1 + i % ((1 << k) - 1) for i in range(bits)]
    random.Random(seed).shuffle(vectors)
    return [sum(1 << i for i, x in enumerate(vectors) if (x & v).bit_count() & 1) for v in range(1, 1 << k)]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 3) -> DataFrame:
    """doc_id, row_key and fp (the fingerprint as a signed long) for every row, written once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in lean(batches):
            fp = np.array([fingerprint(t.as_py(), width) for t in b.column("text")], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("row_key"), pa.array(fp)], ["doc_id", "row_key", "fp"])

    rows = docs.select(F.col(id_col).alias("doc_id"), row_key(id_col, text_col).alias("row_key"), F.col(text_col).alias("text"))
    schema = T.StructType([rows.schema["doc_id"], T.StructField("row_key", T.StringType()), T.StructField("fp", T.LongType())])
    return staged(rows.mapInArrow(run, schema), "fingerprints")


def links(fps: DataFrame, radius: int = 2) -> DataFrame:
    """Edges (a, b) between distinct fingerprints, connecting just what pairs within `radius` 2 connect.

    Each fingerprint goes into one bucket a mask. A bucket of two is its least and greatest member, and is
    compared at once. A larger one is not paired off: each member names itself and its one-bit changes
    in the bits the mask leaves free as centres. Members within two bits share a centre; members that
    share one are within two bits; and a centre has at most 65 members, so its star is bounded. No
    bucket size brings more than 65 rows a fingerprint and table."""
    if radius != 2:
        raise ValueError("centres hold for radius 2")
    masks = covering_masks(radius)
    tables = F.array(*[F.struct(F.lit(i).alias("t"), F.col("fp").bitwiseAND(F.lit(_signed(m))).alias("key")) for i, m in enumerate(masks)])
    dealt = fps.select("fp", F.explode(tables).alias("x")).select("fp", "x.t", "x.key")
    total = fps.count() * len(masks)
    buckets = dealt.groupBy("t", "key").agg(F.count(F.lit(1)).alias("n"), F.min("fp").alias("a"), F.max("fp").alias("b"))
    pairs = buckets.filter(F.col("n") == 2).filter(F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= radius).select("a", "b")
    large = skew_join(dealt, buckets.filter("n > 2").select("t", "key", "n"), ["t", "key"], total)
    free = F.array(*[F.array(F.lit(0).cast("long"), *[F.lit(_signed(1 << i)) for i in range(64) if not m >> i & 1]) for m in masks])
    centres = large.select("fp", F.explode(free[F.col("t")]).alias("flip")).select("fp", F.col("fp").bitwiseXOR(F.col("flip")).alias("centre"))
    stars = centres.groupBy("centre").agg(F.collect_set("fp").alias("fps")).filter(F.size("fps") > 1)
    spokes = stars.select(F.explode("fps").alias("a"), F.array_min("fps").alias("b")).filter("a <> b")
    return pairs.unionByName(spokes).distinct()


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id, kept, row_key for every row.

    component_id is the least doc_id among all documents reachable over links of fingerprints that differ
    in two bits or fewer (null if all of them have a null id). Texts without words, null ones among them,
    share fingerprint zero. `kept` marks one row a component: its least id, then least row_key; rows with the
    same id and text share a row_key and are all marked. Copies are one fingerprint with a count: no pair
    of copies is ever made."""
    rows = fingerprints(docs, id_col, text_col)
    total = rows.count()
    first = F.min(F.when(F.col("doc_id").isNotNull(), F.struct("doc_id", "row_key")))
    per_fp = staged(rows.groupBy("fp").agg(first.alias("first"), F.min("row_key").alias("any_key"), F.count(F.lit(1)).alias("n")), "distinct")
    roots = components(links(per_fp.select("fp")))
    rooted = staged(
        per_fp.join(roots.withColumnRenamed("node", "fp"), "fp", "left").select("fp", F.coalesce("root", "fp").alias("root"), "first", "any_key", F.col("n").alias("rows_of_fp")), "rooted"
    )
    whole = rooted.groupBy("root").agg(F.min("first").alias("least"), F.min("any_key").alias("any_least"), F.count(F.lit(1)).alias("n"))
    named = skew_join(rooted.select("fp", "root", "rows_of_fp"), whole, ["root"], rooted.count()).select(
        "fp", F.col("least.doc_id").alias("component_id"), F.coalesce("least.row_key", "any_least").alias("kept_key"), F.col("rows_of_fp").alias("n")
    )
    out = skew_join(rows, staged(named, "named"), ["fp"], total)
    return out.select(
        "doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id", (F.col("row_key") == F.col("kept_key")).alias("kept"), "row_key"
    )
