"""Token counting and bulk-synchronous best-fit packing."""

from __future__ import annotations

import json
import re
import zlib
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import tiktoken
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window as W
from tokenizers import Tokenizer

from spectrack.llm.common import discard, lean, ranked, staged, text_or_empty

# how byte-level BPE splits a text before merging (fixed value of files whose pre-tokenizer is BYTE_LEVEL)
SPLIT = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""

BYTE_LEVEL = {"type": "ByteLevel", "add_prefix_space": False, "use_regex": True}
# of the model, what would change how words are merged
PLAIN_BPE = {"type": "BPE", "dropout": None, "unk_token": None, "continuing_subword_prefix": None, "end_of_word_suffix": None, "byte_fallback": False, "ignore_merges": False}
# longer parts go to the library, whose split doesn't recurse over white space
LONG = 5000

# a space with white space, or an end of the text, beside it
_ODD_SPACE = re.compile(r" (?:(?!\S)|(?<!\S ))")
_CUT = re.compile(r"(?<=\S) (?=\S)")


def _bytes_of(vocabulary: dict[str, int]) -> dict[bytes, int]:
    """Tokens as bytes: byte-level BPE writes unprintable bytes as characters from U+0100 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    back = {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(b for b in range(256) if b not in set(plain))}
    return {bytes(back[c] for c in token): i for token, i in vocabulary.items()}


class _Pieces(dict):
    """Token ids, as bytes, of the strings seen so far, each with `prefix` before it. A string of more than
    64 characters, and any string once `most` are held, is encoded anew each time: memory stays bounded."""

    def __init__(self, encode, prefix: str, most: int):
        self.encode, self.prefix, self.most = encode, prefix, most

    def __missing__(self, part: str) -> bytes:
        ids = np.array(self.encode(self.prefix + part), "<u4").tobytes()
        if len(part) <= 64 and len(self) < self.most:
            self[part] = ids
        return ids


class Ids:
    """A text's ids for a byte-level BPE tokenizer file, the same as the tokenizers library gives.

    A single space between two other characters always starts a new pre-token, so a text falls apart
    there and the parts, which repeat a lot, are looked up. Texts with added tokens or a part of over LONG characters in
    them go to the library, and so does every text where the file normalises, splits or merges in another way."""

    def __init__(self, path: str, most: int = 250_000):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.path, self.whole = path, None  # the library's own tokenizer is loaded when a text needs it
        self.added = [x["content"] for x in spec["added_tokens"]]
        split, model = spec.get("pre_tokenizer") or {}, spec["model"]
        self.fast = not spec.get("normalizer") and {k: split.get(k) for k in BYTE_LEVEL} == BYTE_LEVEL and all((model.get(k) or None) == (v or None) for k, v in PLAIN_BPE.items())
        if self.fast:
            ranks = _bytes_of({k: v for k, v in model["vocab"].items() if k not in set(self.added)})
            encode = tiktoken.Encoding("file", pat_str=SPLIT, mergeable_ranks=ranks, special_tokens={}).encode_ordinary
            self.head, self.tail = _Pieces(encode, "", most // 8), _Pieces(encode, " ", most)

    def by_library(self, text: str) -> bytes:
        self.whole = self.whole or Tokenizer.from_file(self.path)
        return np.array(self.whole.encode(text, add_special_tokens=False).ids, "<u4").tobytes()

    def __call__(self, text: str) -> bytes:
        if not self.fast or any(token in text for token in self.added):
            return self.by_library(text)
        parts = _CUT.split(text) if _ODD_SPACE.search(text) else text.split(" ")
        if max(map(len, parts)) > LONG:
            return self.by_library(text)
        return self.head[parts[0]] + b"".join(map(self.tail.__getitem__, parts[1:]))


_loaded: dict[str, Ids] = {}


def pieces(docs: DataFrame, tokenizer: str, capacity: int = 1024, end: int = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 for every piece of every document's ids; written once.

    A document is its ids and then `end`. One longer than capacity is cut into pieces of capacity, the
    first of which takes what is left over. Null text is the empty text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids_of = _loaded.get(tokenizer) or _loaded.setdefault(tokenizer, Ids(tokenizer))
        stop = np.array([end], "<u4").tobytes()
        for b in lean(batches):
            row, piece, start, length, crc = [], [], [], [], []
            for i, text in enumerate(b.column("text")):
                data = memoryview(ids_of(text.as_py()) + stop)
                n = len(data) // 4
                cuts = [0, *range(n % capacity or capacity, n, capacity), n]
                for k in range(len(cuts) - 1):
                    row.append(i)
                    piece.append(k)
                    start.append(cuts[k])
                    length.append(cuts[k + 1] - cuts[k])
                    crc.append(zlib.crc32(data[4 * cuts[k] : 4 * cuts[k + 1]]))
            yield pa.RecordBatch.from_arrays(
                [b.column("doc_id").take(pa.array(row, pa.int64())), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64())],
                ["doc_id", "piece", "start", "length", "ids_crc32"],
            )

    rows = docs.select(F.col(id_col).alias("doc_id"), text_or_empty(text_col).alias("text"))
    schema = T.StructType([rows.schema["doc_id"], *[T.StructField(n, T.IntegerType() if n == "piece" else T.LongType()) for n in ("piece", "start", "length", "ids_crc32")]])
    return staged(rows.mapInArrow(run, schema).withColumn("rid", F.monotonically_increasing_id()), "pieces")


# kind 0: `n` gaps of `size` in the sequences from `first` on; kind 1: `n` pieces of length `size` from rank `first` on;
# kind 2: such pieces, placed: `each` a sequence, from `sequence` on, in gaps of size `gap`; kind 3: gaps left by those
MADE = "kind int, size int, first long, n long, each int, sequence long, gap int"
BLOCK_BITS = 16

Item = tuple[int, int, int, int, int, int, int]


def _item(kind: int, size: int, first: int, n: int, each: int = 0, sequence: int = 0, gap: int = 0) -> Item:
    return kind, size, first, n, each, sequence, gap


def matched(items: list[Item]) -> list[Item]:
    """One sweep over gaps and pieces: from the greatest size down, each piece takes its successor, the smallest gap passed so
    far that no longer piece or lower rank has taken, and as many of its equals as fit beside it. What is left of a gap
    is for the next sweep."""
    open_gaps: list[tuple[int, int, int]] = []
    out: list[Item] = []
    for kind, size, first, n, *_ in sorted(items, key=lambda x: (-x[1], x[0], x[2])):
        if kind == 0:
            open_gaps.append((size, first, n))
            continue
        while n and open_gaps:
            gap, sequence, many = open_gaps.pop()
            each = gap // size
            used = min(many, -(-n // each))
            if used < many:
                open_gaps.append((gap, sequence + used, many - used))
            placed = min(n, used * each)
            full, rest = divmod(placed, each)
            out.append(_item(2, size, first, placed, each, sequence, gap))
            if full and gap > each * size:
                out.append(_item(3, gap - each * size, sequence, full))
            if rest:
                out.append(_item(3, gap - rest * size, sequence + full, 1))
            first, n = first + placed, n - placed
        if n:
            out.append(_item(1, size, first, n))
    return out + [_item(0, *g) for g in open_gaps]


def merged(items: list[Item]) -> list[Item]:
    """Gaps of kind 3 become gaps; equal gaps of neighbouring sequences become one item."""
    out: list[Item] = []
    for size, first, n in sorted(x[1:4] for x in items if x[0] in (0, 3)):
        if out and out[-1][1] == size and out[-1][2] + out[-1][3] == first:
            out[-1] = _item(0, size, out[-1][2], out[-1][3] + n)
        else:
            out.append(_item(0, size, first, n))
    return out + [x for x in items if x[0] in (1, 2)]


def sweep(items: DataFrame, ranges: int = 8) -> DataFrame:
    """One sweep over gaps and pieces that stand sorted by ranges of size. A range matches its own pieces and gaps first:
    a gap of its own is closer than one of a greater range. What a range couldn't match meets what the greater ones left, in
    the same order, at their boundary: a few items a range, as lengths and gaps are kept as runs of equal ones."""

    def rows(made: list[Item]) -> pa.RecordBatch:
        names, kinds = zip(*(x.split() for x in MADE.split(", ")), strict=True)
        return pa.RecordBatch.from_arrays([pa.array([x[i] for x in made], pa.int32() if k == "int" else pa.int64()) for i, k in enumerate(kinds)], list(names))

    def inside(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield rows(matched([tuple(r.values()) for b in batches for r in b.to_pylist()]))

    def between(table: pa.Table) -> pa.Table:
        made = [tuple(r[n] for n in rows([]).schema.names) for r in table.to_pylist()]
        return pa.Table.from_batches([rows(merged([x for x in made if x[0] > 1] + matched([x for x in made if x[0] < 2])))])

    local = items.repartitionByRange(ranges, "size").mapInArrow(inside, MADE)
    return local.withColumn("__all", F.lit(0)).groupBy("__all").applyInArrow(between, MADE)


def planned(lengths: DataFrame, capacity: int) -> DataFrame:
    """Runs (length, first, n, each, sequence, gap) for lengths(length, n): sweeps until no piece is left.

    New sequences are opened when no gap holds the shortest piece: nine tenths of what the rest of the tokens needs, so
    that the sweeps show how well they fit, and all of it near the end; and never fewer than the pieces that
    can't share one. The driver sees four numbers a sweep."""
    spark = lengths.sparkSession
    state = staged(lengths.select(F.lit(1).alias("kind"), F.col("length").cast("int").alias("size"), F.lit(0).cast("long").alias("first"), "n", *[F.lit(0).cast(k).alias(c) for c, k in (("each", "int"), ("sequence", "long"), ("gap", "int"))]), "sweep")
    done, opened, whole = [], 0, None
    piece, gap = F.col("kind") == 1, F.col("kind") == 0
    while True:
        tokens, large, shortest, widest = state.agg(
            F.sum(F.when(piece, F.col("size") * F.col("n"))), F.sum(F.when(piece & (F.col("size") > capacity // 2), F.col("n"))), F.min(F.when(piece, F.col("size"))), F.max(F.when(gap, F.col("size")))
        ).first()
        if not tokens:
            break
        whole = whole or tokens
        items = state.filter("kind < 2")
        if widest is None or widest < shortest:
            need = -(-tokens // capacity)
            more = max(need if 50 * tokens < whole else -(-9 * need // 10), large or 0)
            items = items.unionByName(spark.createDataFrame([_item(0, capacity, opened, more)], MADE))
            opened += more
        state = staged(sweep(items), "sweep")
        done.append(state)
    runs = [x.filter("kind = 2").select(F.col("size").cast("long").alias("length"), "first", "n", "each", "sequence", "gap") for x in done]
    empty = spark.createDataFrame([], "length long, first long, n long, each int, sequence long, gap int")
    out = staged(reduce(DataFrame.unionByName, runs, empty), "runs")
    for x in done:
        discard(x)
    return out


def pack(docs: DataFrame, tokenizer: str, capacity: int = 1024, end: int = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Pieces with their place: doc_id, piece, start, length, ids_crc32, sequence_id, offset.

    Pieces of one length are interchangeable, so the sweeps match runs of them, which are at most `capacity` lengths
    whatever the rows; then each row finds its run by its rank within its length. Ranks are dealt over many tasks and
    looked up in blocks of them, so a length may hold any share of the rows and no list of runs is broadcast.
    An empty table gives an empty result; repeated rows are packed each; further columns are ignored."""
    cut = pieces(docs, tokenizer, capacity, end, id_col, text_col)
    runs = planned(cut.groupBy("length").agg(F.count(F.lit(1)).alias("n")), capacity)
    order = [F.col("doc_id"), F.col("piece"), F.col("ids_crc32")]
    rows = ranked(cut, ["length"], order, cut.count(), "at", spread=F.col("rid"))
    own = ["doc_id", "piece", "start", "ids_crc32"]
    run = F.struct("first", "each", "sequence", "gap")
    block = F.shiftright("at", BLOCK_BITS)
    rows = rows.select("length", block.alias("block"), "at", F.lit(1).alias("kind"), *own, F.lit(None).cast("struct<first:bigint,each:int,sequence:bigint,gap:int>").alias("run"))
    blocks = F.explode(F.sequence(F.shiftright("first", BLOCK_BITS), F.shiftright(F.col("first") + F.col("n") - 1, BLOCK_BITS)))
    heads = runs.withColumn("block", blocks).select("length", "block", F.greatest("first", F.shiftleft("block", BLOCK_BITS)).alias("at"), F.lit(0).alias("kind"), run.alias("run"))
    w = W.partitionBy("length", "block").orderBy("at", "kind").rowsBetween(W.unboundedPreceding, 0)
    both = rows.unionByName(heads, allowMissingColumns=True).withColumn("run", F.last("run", ignorenulls=True).over(w)).filter("kind = 1")
    nth = F.col("at") - F.col("run.first")
    sequence = (F.col("run.sequence") + F.floor(nth / F.col("run.each"))).cast("long").alias("sequence_id")
    offset = (F.lit(capacity) - F.col("run.gap") + (nth % F.col("run.each")) * F.col("length")).cast("long").alias("offset")
    return both.select("doc_id", "piece", "start", "length", "ids_crc32", sequence, offset)
