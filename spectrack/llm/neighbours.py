"""Approximate nearest neighbours: an inverted file of product-quantised residuals, exactly reranked."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spectrack.llm.common import staged


def _kmeans(x: np.ndarray, k: int, rounds: int, rng: np.random.Generator) -> np.ndarray:
    c = x[rng.choice(len(x), min(k, len(x)), replace=False)].copy()
    for _ in range(rounds):
        own = (x @ c.T - 0.5 * (c * c).sum(axis=1)).argmax(axis=1)
        n = np.bincount(own, minlength=len(c))
        sums = np.zeros_like(c)
        np.add.at(sums, own, x)
        c = np.where(n[:, None] > 0, sums / np.maximum(n, 1)[:, None], x[rng.choice(len(x), len(c))])
    return c


@dataclass
class Index:
    """Coarse centroids, codebooks of the residuals' parts, how many lists a query visits, and how many of a block's
    vectors it scores exactly."""

    coarse: np.ndarray  # lists x dims
    books: list[np.ndarray]  # per part: codes x width
    cuts: list[int]
    probes: int
    short: int

    def lists(self, x: np.ndarray) -> np.ndarray:
        return (x @ self.coarse.T - 0.5 * (self.coarse * self.coarse).sum(axis=1)).argmax(axis=1)

    def codes(self, x: np.ndarray, own: np.ndarray) -> np.ndarray:
        rest = x - self.coarse[own]
        out = np.empty((len(x), len(self.books)), np.uint8)
        for m, book in enumerate(self.books):
            part = rest[:, self.cuts[m] : self.cuts[m + 1]]
            out[:, m] = (part @ book.T - 0.5 * (book * book).sum(axis=1)).argmax(axis=1)
        return out

    def tables(self, q: np.ndarray) -> list[np.ndarray]:
        """Inner products of each query's parts with every code: what an unquantised query needs."""
        return [q[:, self.cuts[m] : self.cuts[m + 1]] @ book.T for m, book in enumerate(self.books)]


def train(x: np.ndarray, lists: int, parts: int, short: int, seed: int = 5) -> Index:
    """Fit on a sample; every list is visited until the index is calibrated."""
    rng = np.random.default_rng(seed)
    dims = x.shape[1]
    coarse = _kmeans(x, lists, 12, rng)
    index = Index(coarse, [], [dims * i // parts for i in range(parts + 1)], len(coarse), short)
    rest = x - coarse[index.lists(x)]
    index.books = [_kmeans(rest[:, a:b], 256, 8, rng) for a, b in zip(index.cuts, index.cuts[1:], strict=False)]
    return index


def _matrix(column: pa.ChunkedArray | pa.Array, dims: int) -> np.ndarray:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return np.asarray(column.flatten()).astype(np.float64, copy=False).reshape(-1, dims)


def _single(x: np.ndarray, scale: float) -> np.ndarray:
    return (x * scale if scale != 1.0 else x).astype(np.float32)


def _top(score: np.ndarray, k: int) -> np.ndarray:
    """Columns of the k greatest of each row, equal ones by column."""
    n = score.shape[1]
    if n <= max(4 * k, 512):
        return np.argsort(-score, axis=1, kind="stable")[:, :k]
    edge = np.partition(score, n - k, axis=1)[:, n - k]
    out = np.empty((len(score), k), np.int64)
    for i, (row, e) in enumerate(zip(score, edge, strict=True)):
        over = np.flatnonzero(row > e)
        out[i] = np.concatenate((over, np.flatnonzero(row == e)[: k - len(over)]))
    return out


def search(index: Index, ids, x, own, codes, query_ids, q, scale: float, visits, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query row, vector row, exact score) of each query's k best in one block of vectors, which come
    sorted by id. x and q are the original vectors in double precision; scaled, in single precision, they are looked up in
    the index. visits: the lists of each query, as the bytes of 16-bit numbers."""
    present, where = np.unique(own, return_inverse=True)
    columns = [np.flatnonzero(where == j) for j in range(len(present))]
    rows_out, cols_out, score_out = [], [], []
    short = min(index.short, len(x))
    step = max(1, min(256, 256 * 200 * 64 // (short * x.shape[1])))
    for at in range(0, len(q), step):
        part = _single(q[at : at + step], scale)
        score = np.full((len(part), len(x)), -np.inf, np.float32)
        wants = np.zeros((len(part), len(index.coarse)), bool)
        for r, held in enumerate(visits[at : at + step]):
            wants[r, np.frombuffer(held, np.int16)] = True
        tables = index.tables(part)
        base = part @ index.coarse[present].T
        for j, cols in enumerate(columns):
            rows = np.flatnonzero(wants[:, present[j]])
            if len(rows):
                near = np.repeat(base[rows, j : j + 1], len(cols), axis=1)
                for m, table in enumerate(tables):
                    near += table[rows][:, codes[cols, m]]
                score[np.ix_(rows, cols)] = near
        score[ids[None, :] == query_ids[at : at + step, None]] = -np.inf
        few = _top(score, short)
        few.sort(axis=1)  # by id again, so that equal exact scores stay in id order
        ok = np.take_along_axis(score, few, axis=1) > -np.inf
        exact = np.einsum("rcd,rd->rc", x[few], q[at : at + step])
        exact[~ok] = -np.inf
        best = np.argsort(-exact, axis=1, kind="stable")[:, :k]
        value = np.take_along_axis(exact, best, axis=1)
        i, j = np.nonzero(value > -np.inf)
        rows_out.append(at + i)
        cols_out.append(few[i, best[i, j]])
        score_out.append(value[i, j])
    return np.concatenate(rows_out), np.concatenate(cols_out), np.concatenate(score_out)


def calibrate(index: Index, indexed: DataFrame, placed: Callable[[DataFrame], DataFrame], ids: np.ndarray, q: np.ndarray, scale: float, k: int, wanted: float) -> None:
    """Set how many lists a query visits, and how many of a block's vectors it scores exactly, to the least that find the
    share `wanted` of the true neighbours of these queries among all rows: queries need not be like the other vectors."""
    single, dims = _single(q, scale), q.shape[1]
    # computed once, so that equal vectors get equal bits wherever they are scored
    base, tables = (single @ index.coarse.T).astype(float), index.tables(single)

    def best(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """The task's k nearest of each query, by the exact product."""
        score, vec, own, near = np.full((len(q), 0), 0.0), np.zeros((len(q), 0), np.int64), np.zeros((len(q), 0), np.int32), np.zeros((len(q), 0))
        for b in batches:
            if not b.num_rows:
                continue
            x, vec_id, lists = _matrix(b.column("v"), dims), np.asarray(b.column("vec_id")), np.asarray(b.column("list"))
            codes = np.frombuffer(b"".join(b.column("codes").to_pylist()), np.uint8).reshape(len(x), -1)
            product = q @ x.T
            product[vec_id[None, :] == ids[:, None]] = -np.inf
            order = np.argsort(vec_id, kind="stable")
            few = order[_top(product[:, order], k)]
            approx = np.take_along_axis(base, lists[few], axis=1)
            for m, table in enumerate(tables):
                approx += np.take_along_axis(table, codes[few, m].astype(np.int64), axis=1)
            more = np.take_along_axis(product, few, axis=1), vec_id[few], lists[few], approx
            score, vec, own, near = (np.concatenate(pair, axis=1) for pair in zip((score, vec, own, near), more, strict=True))
            keep = np.lexsort((vec, -score), axis=1)[:, :k]
            score, vec, own, near = (np.take_along_axis(y, keep, axis=1) for y in (score, vec, own, near))
        i, j = np.nonzero(score > -np.inf)
        yield pa.RecordBatch.from_arrays([pa.array(i), *(pa.array(y[i, j]) for y in (score, vec, own, near))], ["query", "score", "vec_id", "list", "near"])

    found = indexed.select("vec_id", "list", "codes", "v").mapInArrow(best, "query long, score double, vec_id long, list int, near double")
    x = F.slice(F.array_sort(F.collect_list(F.struct((-F.col("score")).alias("s"), "vec_id", "list", "near"))), 1, k)
    # at most k rows a query
    truth = placed(found.groupBy("query").agg(x.alias("x")).select("query", F.inline("x"))).toArrow()
    if not truth.num_rows:
        return
    of, vec, own, near, home = (np.asarray(truth[c].combine_chunks()) for c in ("query", "vec_id", "list", "near", "block"))
    place = np.argsort(np.argsort(-base, axis=1, kind="stable"), axis=1)  # of each list, for each query

    def least(x: np.ndarray, share: float) -> int:
        return int(np.sort(x)[math.ceil(share * len(x)) - 1])

    index.probes = least(place[of, own], wanted) + 1
    visited, probes = place < index.probes, index.probes

    def ahead(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """How many vectors of its block the tables put before each true neighbour."""
        n = np.zeros(len(of), np.int64)
        for b in batches:
            vec_id, lists, at = (np.asarray(b.column(c)) for c in ("vec_id", "list", "block"))
            codes = np.frombuffer(b"".join(b.column("codes").to_pylist()), np.uint8).reshape(len(lists), -1)
            for z in np.unique(at).tolist():
                rows = np.flatnonzero(at == z)
                pairs = np.flatnonzero(home == z)
                for y in np.unique(of[pairs]).tolist():
                    mine = rows[visited[y, lists[rows]]]
                    score = base[y, lists[mine]]
                    for m, table in enumerate(tables):
                        score += table[y, codes[mine, m]]
                    for i in pairs[of[pairs] == y].tolist():
                        n[i] += np.count_nonzero((score > near[i]) | ((score == near[i]) & (vec_id[mine] < vec[i]) & (vec_id[mine] != ids[y])))
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(n))), pa.array(n)], ["pair", "n"])

    counted = placed(indexed.select("vec_id", "list", "codes")).mapInArrow(ahead, "pair long, n long")
    n = np.zeros(len(of), np.int64)
    # one number for each pair
    for r in counted.groupBy("pair").agg(F.sum("n").alias("n")).collect():
        n[r["pair"]] = r["n"]
    index.short = max(index.short, least(n[place[of, own] < probes], 1 - (1 - wanted) / 3) + 1)


def nearest(
    vectors: DataFrame, every: int = 20, k: int = 20, short: int = 200, wanted: float = 0.97, sample: int = 20_000, most_lists: int = 4096, block: int = 20_000, query_block: int = 200_000, tests: int = 256,
    id_col: str = "vec_id", vector_col: str = "embedding",
) -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest by inner product of the vectors whose id is divisible by `every`.

    The index is fitted on about `sample` vectors, or 16 a list (a bound of the fit; every vector is indexed), and calibrated
    by the true neighbours of `tests` of the queries. Vectors are
    dealt to blocks of about `block`: small lists share one, a large list gets several. A query goes once
    to each block that holds a list it visits, is scored there by asymmetric tables, and its `short` best (more, if the calibration needs them) are scored
    exactly, in double precision, from the original vectors in the same place; k a block move on to the last ranking. It visits
    further lists until they hold k candidates. Equal scores go to the smaller id. A block that more than `query_block`
    queries visit is searched in as many parts as that takes, by the exact number of its visits.

    Vectors that are null, zero, or hold null or non-finite components take no part, nor do null ids. Vectors of different
    lengths have no inner product: each length has an index of its own. A repeated id is a candidate once a row, but never
    of its own query. An empty table gives an empty result; further columns are ignored."""
    v = F.col(vector_col)
    fine = F.coalesce(F.forall(v, lambda e: e.isNotNull() & ~F.isnan(e) & (F.abs(e) < float("inf"))) & F.exists(v, lambda e: e != 0), F.lit(False))
    # single-precision vectors stay so on their way; any other numbers go as doubles
    kind = "array<float>" if vectors.schema[vector_col].dataType.simpleString() == "array<float>" else "array<double>"
    rows = vectors.filter(F.col(id_col).isNotNull() & fine).select(F.col(id_col).cast("long").alias("vec_id"), v.cast(kind).alias("v"))
    spark, out = vectors.sparkSession, "query_id long, rank int, vec_id long, score double"
    size = F.size("v")
    sizes = rows.groupBy(size.alias("d")).agg(F.count(F.lit(1)).alias("n"), F.max(F.array_max(F.transform("v", F.abs))).cast("double").alias("most")).collect()
    made = spark.createDataFrame([], out)
    for d, n, most in sorted(sizes):
        # exponents that single precision lacks are moved to where it has them; exact scores don't see the scale
        scale = 1.0 if 1e-15 < most < 1e15 else 2.0 ** -math.frexp(most)[1]
        found = _of_length(rows if len(sizes) == 1 else rows.filter(size == d), d, n, scale, kind, every, k, short, wanted, sample, most_lists, block, query_block, tests)
        made = found if len(sizes) == 1 else made.unionByName(found)
    return made


def _of_length(
    rows: DataFrame, dims: int, n: int, scale: float, kind: str, every: int, k: int, short: int, wanted: float, sample: int, most_lists: int, block: int, query_block: int, tests: int
) -> DataFrame:
    """nearest() for n vectors of one length."""
    spark = rows.sparkSession
    lists = max(1, min(most_lists, round(math.sqrt(n))))
    sample = max(sample, 16 * lists)
    u = F.shiftrightunsigned(F.xxhash64("vec_id", F.lit(9)), 11) / F.lit(float(1 << 53))
    some = rows.filter(u < sample / n).orderBy(F.xxhash64("vec_id"), "vec_id").limit(2 * sample).toArrow()
    if some.num_rows == 0:
        some = rows.orderBy("vec_id").limit(sample).toArrow()
    index = train(_single(_matrix(some["v"], dims), scale), lists, max(1, dims // 4), short)

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = _single(_matrix(b.column("v"), dims), scale)
            own = index.lists(x) if len(x) else np.zeros(0, int)
            codes = index.codes(x, own) if len(x) else np.zeros((0, 1), np.uint8)
            yield pa.RecordBatch.from_arrays([b.column("vec_id"), pa.array(own.astype(np.int32)), pa.array([c.tobytes() for c in codes], pa.binary()), b.column("v")], ["vec_id", "list", "codes", "v"])

    indexed = staged(rows.mapInArrow(encode, f"vec_id long, list int, codes binary, v {kind}"), "index")
    held = np.zeros(len(index.coarse), np.int64)
    for r in indexed.groupBy("list").count().collect():  # as many rows as lists
        held[r["list"]] = r["count"]
    first, last, blocks, room = np.zeros(len(held), np.int64), np.zeros(len(held), np.int64), 0, 0
    for i, c in enumerate(held.tolist()):
        if c > room or not blocks:
            first[i], need = blocks, max(1, -(-c // block))
            blocks += need
            room = block - c if need == 1 else 0
        else:
            first[i], room = blocks - 1, room - c
        last[i] = blocks

    span = spark.createDataFrame([(i, int(first[i]), int(last[i] - first[i])) for i in range(len(held))], "list int, first int, many int")

    def placed(df: DataFrame) -> DataFrame:
        """Rows with the block of their list and id."""
        part = (F.col("first") + F.pmod(F.xxhash64("vec_id", F.lit(1)), F.col("many"))).cast("int")
        return df.join(F.broadcast(span), "list").select(*df.columns, part.alias("block"))

    queries = indexed.filter(F.col("vec_id") % every == 0).select("vec_id", "v")
    tried = queries.orderBy(F.xxhash64("vec_id", F.lit(7)), "vec_id").limit(tests).toArrow()
    if tried.num_rows:
        calibrate(index, indexed, placed, np.asarray(tried["vec_id"].combine_chunks()), _matrix(tried["v"], dims), scale, k, wanted)

    def visits(x: np.ndarray) -> Iterator[dict[int, list[int]]]:
        """For each query the blocks it goes to, with its lists there."""
        order = np.argsort(-(x @ index.coarse.T), axis=1, kind="stable")
        enough = (np.cumsum(held[order], axis=1) <= k).sum(axis=1) + 1
        for i in range(len(x)):
            goes: dict[int, list[int]] = {}
            for y in order[i, : max(index.probes, enough[i])].tolist():
                for z in range(first[y], last[y]):
                    goes.setdefault(z, []).append(y)
            yield goes

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(blocks, np.int64)
        for b in batches:
            for goes in visits(_single(_matrix(b.column("v"), dims), scale)):
                total[list(goes)] += 1
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at, pa.int64()), pa.array(total[at])], ["block", "n"])

    # one number for each block of vectors
    asking = np.ones(blocks, np.int64)
    for r in queries.mapInArrow(count, "block long, n long").groupBy("block").agg(F.sum("n").alias("n")).collect():
        asking[r["block"]] = -(-r["n"] // query_block)
    crowded = {i: int(c) for i, c in enumerate(asking.tolist()) if c > 1}
    parts = F.lit(1)
    if crowded:
        parts = F.coalesce(F.create_map(*[F.lit(x) for pair in crowded.items() for x in pair])[F.col("block")], F.lit(1))
    dealt = placed(indexed)
    dealt = dealt.withColumn("query_block", F.explode(F.sequence(F.lit(0), parts - 1)))

    def route(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            row, to, lists = [], [], []
            for i, goes in enumerate(visits(_single(_matrix(b.column("v"), dims), scale))):
                row += [i] * len(goes)
                to += goes.keys()
                lists += [np.array(x, np.int16).tobytes() for x in goes.values()]
            at = pa.array(row, pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(to, pa.int32()), b.column("vec_id").take(at), pa.array(lists, pa.binary()), b.column("v").take(at)], ["block", "query_id", "visits", "v"])

    asked = queries.mapInArrow(route, f"block int, query_id long, visits binary, v {kind}")
    asked = asked.withColumn("query_block", F.pmod(F.xxhash64("query_id"), parts).cast("int"))

    def find(left: pa.Table, right: pa.Table) -> pa.Table:
        left = left.sort_by("vec_id")
        ids, query_ids = np.asarray(left["vec_id"]), np.asarray(right["query_id"])
        empty = np.zeros(0, np.int64)
        i, j, score = empty, empty, np.zeros(0)
        if len(ids) and len(query_ids):
            wanted_lists = right["visits"].to_pylist()
            codes = np.frombuffer(b"".join(left["codes"].to_pylist()), np.uint8).reshape(len(ids), -1)
            i, j, score = search(index, ids, _matrix(left["v"], dims), np.asarray(left["list"]), codes, query_ids, _matrix(right["v"], dims), scale, wanted_lists, k)
        return pa.table({"query_id": query_ids[i].astype(np.int64), "vec_id": ids[j].astype(np.int64), "score": score})

    by = ["block", "query_block"]
    best = dealt.groupBy(*by).cogroup(asked.groupBy(*by)).applyInArrow(find, "query_id long, vec_id long, score double")
    # at most k rows a query and block come here
    ranked = best.groupBy("query_id").agg(F.slice(F.array_sort(F.collect_list(F.struct((-F.col("score")).alias("s"), F.col("vec_id").alias("i")))), 1, k).alias("r"))
    each = ranked.select("query_id", F.posexplode("r").alias("at", "x"))
    return each.select("query_id", (F.col("at") + 1).cast("int").alias("rank"), F.col("x.i").alias("vec_id"), (-F.col("x.s")).alias("score"))
