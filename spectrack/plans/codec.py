"""Compress, decompress and simplify on Spark: one shuffle of points, one hop into Arrow.

Every kernel reads a stream of points sorted by track and time (`over_tracks`), so small tracks share a batch, and
a task holds no more of a track than one chunk."""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from spectrack.functions import many as M
from spectrack.functions import simplify as S
from spectrack.functions import track as K
from spectrack.functions.params import CodecParams
from spectrack.sources.tables import usable

CONTAINER = (
    "track_id string, chunk long, cut boolean, payload binary, n long, dim int, t_min long, t_max long, raw_bytes long, bytes_paper long, bytes_with_clock long, regular boolean, "
    "n_corr long, n_out long, n_frag long, max_sed double, sum_sed double, " + ", ".join(f"bits_{s} long" for s in K.SECTIONS)
)
POINTS = "track_id string, t long, pos array<double>"
KEPT = POINTS + ", generated boolean"
CHUNK = 1_000_000

# track, number of its chunk (None for a whole track), times, positions
Piece = tuple[str, int | None, np.ndarray, np.ndarray]

_TYPES = {"string": pa.string(), "long": pa.int64(), "int": pa.int32(), "double": pa.float64(), "binary": pa.binary(), "boolean": pa.bool_(), "array<double>": pa.list_(pa.float64())}


def arrow_schema(ddl: str) -> pa.Schema:
    return pa.schema([(name, _TYPES[kind]) for name, kind in (x.split() for x in ddl.split(", "))])


def _positions(column: pa.ListArray, a: int, b: int) -> np.ndarray:
    """Rows a to b as a matrix."""
    part = column.slice(a, b - a)
    flat = np.asarray(part.flatten())
    if len(flat) % (b - a) or (np.diff(part.offsets.to_numpy()) != len(flat) // (b - a)).any():
        raise ValueError("points of one track differ in dimension")
    return flat.reshape(b - a, -1)


def pieces(batches: Iterator[pa.RecordBatch], eps_t: int = 1, most: int | None = None) -> Iterator[Piece]:
    """Tracks of rows (track_id, t, pos) that come sorted by track and time, of repeated time codes the first. With
    `most`, a track's rows go out in chunks of that many, numbered by the time of their first."""
    track, ts, xs, held, last = None, [], [], 0, None

    def out() -> Piece:
        t = np.concatenate(ts)
        return track, int(t[0]) if most else None, t, np.concatenate(xs)

    for batch in batches:
        if not batch.num_rows:
            continue
        ids, t, pos = batch.column(0), np.asarray(batch.column(1)), batch.column(2)
        codes = np.asarray(ids.dictionary_encode().indices)
        edges = [0, *(np.flatnonzero(np.diff(codes)) + 1).tolist(), len(codes)]
        for a, b in zip(edges, edges[1:], strict=False):
            name = ids[a].as_py()
            if name != track:
                if held:
                    yield out()
                track, ts, xs, held, last = name, [], [], 0, None
            when, where = t[a:b], _positions(pos, a, b)
            code = K.time_code(when, eps_t)
            new = np.concatenate(([last is None or code[0] != last], code[1:] != code[:-1]))
            when, where, last = when[new], where[new], code[-1]
            while most and held + len(when) > most:
                room = most - held
                ts.append(when[:room])
                xs.append(where[:room])
                yield out()
                when, where, ts, xs, held = when[room:], where[room:], [], [], 0
            if len(when):
                ts.append(when)
                xs.append(where)
                held += len(when)
    if held:
        yield out()


def rows_of(made: Iterator[dict], schema: pa.Schema, rows: int = 1000, size: int = 8_000_000) -> Iterator[pa.RecordBatch]:
    """Batches of so many rows, or of so many bytes of payload."""
    held, n = [], 0
    for row in made:
        held.append(row)
        n += len(row.get("payload") or b"")
        if len(held) == rows or n > size:
            yield pa.RecordBatch.from_pylist(held, schema)
            held, n = [], 0
    if held:
        yield pa.RecordBatch.from_pylist(held, schema)


def over_tracks(points: DataFrame, kernel: Callable[[Iterator[Piece]], Iterator[pa.RecordBatch]], ddl: str, eps_t: int = 1, chunk_points: int | None = CHUNK) -> DataFrame:
    """kernel over the pieces of all usable points: whole tracks, or chunks of those beyond `chunk_points` points.

    Whole tracks are dealt by a hash of the track; where points already are (after a window over tracks), they
    aren't shuffled again. A longer track is dealt by range of time, as many ranges as it needs, so that not even a track with
    most of the rows meets in one task. Whether there is one is asked first, by counts: of all points, which Parquet
    footers answer, and only above `chunk_points` of each track."""
    every = points.select("track_id", "t", "pos")
    points = usable(every)

    def run(most: int | None):
        return lambda batches: kernel(pieces(batches, eps_t, most))

    def dealt(df: DataFrame) -> DataFrame:
        return df.withColumn("__n", F.row_number().over(W.partitionBy("track_id").orderBy("t", "pos"))).select("track_id", "t", "pos", "__n").mapInArrow(run(None), ddl)

    if chunk_points is None or every.count() <= chunk_points:
        return dealt(points)
    long = every.groupBy("track_id").agg(F.count(F.lit(1)).alias("__m")).filter(F.col("__m") > chunk_points)
    tracks, rows = long.agg(F.count(F.lit(1)), F.sum("__m")).first()
    if not tracks:
        return dealt(points)
    long = long.select("track_id")
    # a task streams, so small chunks need no more tasks than large ones
    parts = max(int(points.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-rows // (16 * max(chunk_points, CHUNK))))
    code = F.floor((F.col("t") * 2 + eps_t) / (2 * eps_t))
    ranges = points.join(long, "track_id", "left_semi").withColumn("__c", code).repartitionByRange(parts, "track_id", "__c").sortWithinPartitions("track_id", "t", "pos")
    return dealt(points.join(long, "track_id", "left_anti")).unionByName(ranges.select("track_id", "t", "pos").mapInArrow(run(chunk_points), ddl))


def together(made: Iterator[Piece], points: int = 20_000) -> Iterator[list[Piece]]:
    """Pieces in groups of about so many points, each group of one dimension."""
    held, n = [], 0
    for piece in made:
        if held and (n + len(piece[2]) > points or piece[3].shape[1] != held[0][3].shape[1]):
            yield held
            held, n = [], 0
        held.append(piece)
        n += len(piece[2])
    if held:
        yield held


def _containers(group: list[Piece], p: CodecParams) -> Iterator[dict]:
    tracks = [piece[2:] for piece in group]
    for piece, clock, made in zip(group, M.clock_bits(tracks, p.eps_t, p.l), M.packed(tracks, p), strict=True):
        yield _container(piece, clock, *made)


def _container(piece: Piece, clock: int, payload: bytes, bits: dict, uniform: bool, stats: dict) -> dict:
    track, chunk, t, pos = piece
    n, dim = pos.shape
    size = len(payload)
    return {
        "track_id": track, "chunk": chunk or 0, "cut": chunk is not None, "payload": payload, "n": n, "dim": dim, "t_min": int(t[0]), "t_max": int(t[-1]), "raw_bytes": K.raw_bytes(n, dim),
        "bytes_paper": size, "bytes_with_clock": size if uniform else size + -(-clock // 8), "regular": uniform,
        "n_corr": stats["error_points"], "n_out": stats["outliers"], "n_frag": stats["fragments"], "max_sed": stats["max_sed"], "sum_sed": stats["sum_sed"],
        **{f"bits_{s}": bits[s] for s in K.SECTIONS},
    }


def compress(points: DataFrame, p: CodecParams, chunk_points: int | None = CHUNK) -> DataFrame:
    """One container row a track, or a track and chunk of about `chunk_points` points where a track has more.

    Chunks are containers of their own (`cut`), and the cut costs a fragment's start each."""
    schema = arrow_schema(CONTAINER)
    return over_tracks(points, lambda made: rows_of((row for group in together(made) for row in _containers(group, p)), schema), CONTAINER, p.eps_t, chunk_points)


#: this many of a track's containers, one after the other, and their times meet in a task
BESIDE = 16


def _groups(container: DataFrame) -> DataFrame:
    """Of tracks cut in more than BESIDE chunks: where each further group of them starts."""
    starts = container.filter("cut").groupBy("track_id").agg(F.array_sort(F.collect_list("t_min")).alias("__starts")).filter(F.size("__starts") > BESIDE)
    return starts.select("track_id", F.filter("__starts", lambda _, i: (i > 0) & (i % BESIDE == 0)).alias("__heads"))


def decompress(container: DataFrame, clock: DataFrame, p: CodecParams | None = None) -> DataFrame:
    """track_id, t, pos at the clock's times (track_id, t): any part of the original times, repeated ones once.

    Each time goes to the container whose own time span holds it, and parameters come from the headers (with p, a container
    made with others is refused). Times outside all of a track's containers, and tracks without one, give no row; times that
    were not in the track give interpolated positions without a bound. Containers and times are sorted together, so that the last
    container before a time is its own; a track of many is dealt in groups of neighbours. The container table is read three times:
    twice for the starts of tracks that are cut, so it should be stored and not computed here."""
    times = clock.select("track_id", "t", F.lit(1).alias("kind")).withColumns({"t_max": F.lit(None).cast("long"), "payload": F.lit(None).cast("binary")})
    boxes = container.select("track_id", F.col("t_min").alias("t"), F.lit(0).alias("kind"), "t_max", "payload")
    group = F.coalesce(F.size(F.filter("__heads", lambda x: x <= F.col("t"))), F.lit(0))
    heads = _groups(container)
    both = [df.join(heads, "track_id", "left").select("track_id", F.when(F.col("__heads").isNull(), 0).otherwise(group).alias("group"), "t", "kind", "t_max", "payload") for df in (boxes, times)]
    both = both[0].unionByName(both[1]).repartition("track_id", "group").sortWithinPartitions("track_id", "group", "t", "kind")
    schema = arrow_schema(POINTS)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        track = box = last = None
        for batch in batches:
            if not batch.num_rows:
                continue
            ids, t, kind, end = batch.column(0), np.asarray(batch.column(2)), np.asarray(batch.column(3)), batch.column(4)
            names, asked, at = [], [], []
            codes, first = np.asarray(ids.dictionary_encode().indices), kind == 0
            opened = iter(M.unpack(batch.column(5).filter(pa.array(first)).to_pylist(), p))
            # a container is a piece of its own, and so are the times up to the next one
            edges = np.flatnonzero((np.diff(codes) != 0) | first[1:] | first[:-1]) + 1
            edges = [0, *edges.tolist(), len(codes)]
            for a, b in zip(edges, edges[1:], strict=False):
                own = ids[a].as_py()
                if own != track:
                    track, box, last = own, None, None
                if first[a]:
                    e, found = next(opened)
                    # a long container's times may come in many batches
                    samples = K.decode_uniform(e, found) if e.counts.sum() > 2000 else None
                    box, last = (e, found, samples, end[a].as_py()), None
                elif box is not None:
                    *made, upto = box
                    when = t[a:b]
                    when = when[(when <= upto) & np.concatenate(([when[0] != last], when[1:] != when[:-1]))]
                    last = t[b - 1]
                    if len(when):
                        names += [own] * len(when)
                        at.append(when)
                        asked.append(made)
            if at:
                yield points_batch(names, np.concatenate(at), M.decode(asked, at), schema)

    return both.mapInArrow(run, POINTS)


def points_batch(names: list[str], t: np.ndarray, made: Sequence[np.ndarray], schema: pa.Schema, *more: pa.Array) -> pa.RecordBatch:
    """Rows (track_id, t, pos) of matrices one after the other."""
    size = np.concatenate([np.full(len(x), x.shape[1], np.int32) for x in made])
    flat = np.concatenate([x.ravel() for x in made])
    pos = pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(size))).astype(np.int32)), pa.array(flat))
    return pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.array(t, pa.int64()), pos, *more], schema=schema)


def decompress_regular(container: DataFrame, p: CodecParams | None = None, t_from: int | None = None, t_to: int | None = None) -> DataFrame:
    """Samples of uniform tracks, whose times the container implies. Rows outside the time range are
    skipped by the side columns before any payload is opened."""
    rows = container.filter("regular")
    if t_from is not None:
        rows = rows.filter(F.col("t_max") >= t_from)
    if t_to is not None:
        rows = rows.filter(F.col("t_min") <= t_to)
    schema = arrow_schema(POINTS)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for track, payload, first in zip(b.column(0).to_pylist(), b.column(1), b.column(2).to_pylist(), strict=True):
                e, made = K.unpack(payload.as_py(), p)
                t = first + e.dt * np.arange(int(e.counts[0]))
                t = t[(t >= (t_from if t_from is not None else t[0])) & (t <= (t_to if t_to is not None else t[-1]))]
                if len(t):
                    yield points_batch([track] * len(t), t, [K.decode(e, t, made)], schema)

    return rows.select("track_id", "payload", "t_min").mapInArrow(run, POINTS)


def simplify(points: DataFrame, method: str, p: CodecParams, encoded: bool = True, m: int = 16, chunk_points: int | None = CHUNK) -> DataFrame:
    """Kept counts, bytes and errors of a baseline, a row a track (and chunk of a long one)."""
    ddl = "track_id string, n long, raw_bytes long, kept long, bytes long, max_sed double, sum_sed double"
    return sweep(points, [({}, lambda t, pos: S.simplified(method, t, pos, p, encoded, m))], ddl, p.eps_t, chunk_points)


def kept_points(points: DataFrame, method: str, eps: float, m: int = 16, ratio: float | None = None, chunk_points: int | None = CHUNK) -> DataFrame:
    """KEPT: track_id, t, pos, generated."""
    schema = arrow_schema(KEPT)

    def run(made: Iterator[Piece]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0

        def out() -> pa.RecordBatch:
            names, ts, paths = zip(*held, strict=True)
            size = [len(x) for x in ts]
            return points_batch(np.repeat(np.array(names, object), size).tolist(), np.concatenate(ts), paths, schema, pa.array(np.full(sum(size), method == "cone_weak")))

        for track, _, t, pos in made:
            held.append((track, *S.kept(method, t, pos, eps, m, ratio)))
            n += len(held[-1][1])
            if n > 50_000:
                yield out()
                held, n = [], 0
        if held:
            yield out()

    return over_tracks(points, run, KEPT, 1, chunk_points)


def sweep(points: DataFrame, runs: Sequence[tuple[dict | list[dict], Callable]], ddl: str, eps_t: int = 1, chunk_points: int | None = CHUNK) -> DataFrame:
    """Each run's rows for each track (and chunk of a long one, whose rows add up to the track's).

    The grid goes to the data: points are shuffled once, and a task does all runs of its tracks. A run is (labels, function
    of (t, pos) giving the rest of the row), or (list of labels, function giving as many), where one encoding
    serves several rows. A function with an attribute `many` is given a list of tracks there, for as many results, and a dict
    that keeps what runs over the same tracks share."""
    schema = arrow_schema(ddl)

    def rows(made: Iterator[Piece]) -> Iterator[dict]:
        for group in together(made):
            tracks = [piece[2:] for piece in group]
            shared: dict = {}
            same = [{"track_id": track, "n": len(t), "raw_bytes": K.raw_bytes(*pos.shape)} for track, _, t, pos in group]
            for labels, f in runs:
                many = f.many(tracks, shared) if hasattr(f, "many") else (f(t, pos) for t, pos in tracks)
                for own, got in zip(same, many, strict=True):
                    for tag, x in [(labels, got)] if isinstance(labels, dict) else zip(labels, got, strict=True):
                        yield {**own, **tag, **x}

    return over_tracks(points, lambda made: rows_of(rows(made), schema), ddl, eps_t, chunk_points)
