"""Event-time windows, and on Structured Streaming the incremental fragmenter and the one-pass simplifiers."""

from __future__ import annotations

import json
import uuid
from collections.abc import Iterator, Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.streaming.query import StreamingQuery
from pyspark.sql.window import Window as W

from spectrack.functions import track as K
from spectrack.functions.params import CodecParams
from spectrack.functions.simplify import Cone
from spectrack.sources.stage import new_path


def _timed(events: DataFrame) -> DataFrame:
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling(events: DataFrame, size: str) -> DataFrame:
    g = _timed(events).groupBy(F.window("ts", size), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return g.select(F.unix_micros("window.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame, size: str, step: str) -> DataFrame:
    g = _timed(events).groupBy(F.window("ts", size, step)).agg(F.count(F.lit(1)).alias("n"), F.count_distinct("user_id").alias("users"))
    return g.select(F.unix_micros("window.start").alias("start"), "n", "users")


def sessions(events: DataFrame, gap: str) -> DataFrame:
    """Runs of a user's events with pauses below the gap: the fixed-gap cousin of the fragment rule."""
    g = _timed(events).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return g.select("user_id", F.unix_micros("w.start").alias("start"), "n")


def late_rows(events: DataFrame, delay: int) -> DataFrame:
    """Rows that would arrive behind a watermark of this delay, if rows arrived by id, a user at a time."""
    e = events.select("user_id", "event_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    seen = F.max("t").over(W.partitionBy("user_id").orderBy("event_id").rowsBetween(W.unboundedPreceding, -1))
    return e.withColumn("seen", seen).groupBy("user_id").agg(F.sum(F.coalesce(F.col("t") < F.col("seen") - delay, F.lit(False)).cast("int")).alias("late"))


BLOCK = "track_id string, frag long, n long, t0 long, payload binary, max_sed double, error_points long"
# times and flattened positions of the open fragment, and of rows that wait for the watermark
STATE = "frag long, dim int, open_t array<long>, open_pos array<double>, held_t array<long>, held_pos array<double>"
PATH = "track_id string, t long, pos array<double>, generated boolean"
CONE_STATE = "dim int, cone string, held_t array<long>, held_pos array<double>"


def _close(track: str, frag: int, rows: list, p: CodecParams) -> pd.DataFrame:
    t = np.array([r[0] for r in rows], np.int64)
    pos = np.array([r[1] for r in rows], float)
    e = K.encode(t, pos, p.with_(v_max=None))
    return pd.DataFrame({"track_id": [track], "frag": [frag], "n": [len(t)], "t0": [int(t[0])], "payload": [K.pack(e, p)], "max_sed": [e.stats["max_sed"]], "error_points": [e.stats["error_points"]]})


def _breaks(rows: list, t: int, pos: list, p: CodecParams) -> bool:
    """Whether (t, pos) starts a fragment after these rows: the rule of track.fragment_starts, in order."""
    k, gap = len(rows), t - rows[-1][0]
    if p.v_max is not None and float(np.linalg.norm(np.subtract(pos, rows[-1][1]))) > gap / 1e6 * p.v_max:
        return True
    if k == 1:
        mean = p.default_dt
    elif p.gap_mean == "inclusive":
        mean = (t - rows[0][0]) / k
    else:
        mean = (rows[-1][0] - rows[0][0]) / (k - 1)
    return gap > p.b_s * mean


def _idle(rows: list, p: CodecParams) -> int | None:
    """The time after which any further point starts a fragment; None if a pause of any length is within the mean."""
    k, first, last = len(rows), rows[0][0], rows[-1][0]
    if k == 1:
        return last + p.b_s * p.default_dt
    if p.gap_mean != "inclusive":
        return last + p.b_s * -(-(last - first) // (k - 1))
    return -(-(k * last - p.b_s * first) // (k - p.b_s)) if k > p.b_s else None


def _advance(track: str, frag: int, rows: list, due: list, p: CodecParams, most: int) -> tuple[int, list, list[pd.DataFrame]]:
    """Add due (t, pos), in time order, to the open fragment: (number, rows of the open one, those closed)."""
    closed = []
    for t, pos in due:
        if rows and t == rows[-1][0]:
            continue  # of repeated times the first
        if rows and (len(rows) == most or _breaks(rows, t, pos, p)):
            closed.append(_close(track, frag, rows, p))
            frag, rows = frag + 1, []
        rows.append((t, pos))
    return frag, rows, closed


def _pairs(t: Sequence[int], pos: Sequence[float], dim: int) -> list[tuple[int, list[float]]]:
    return [(int(x), [float(v) for v in pos[i * dim : (i + 1) * dim]]) for i, x in enumerate(t)]


def _flat(rows: list) -> tuple[list[int], list[float]]:
    return [t for t, _ in rows], [v for _, pos in rows for v in pos]


def _arrived(batches: Iterator[pd.DataFrame], held: list, mark: int) -> tuple[list, list]:
    """(rows that the watermark has passed, in time order, and those that still wait)."""
    for b in batches:
        held += [(t, [float(x) for x in pos]) for t, pos in zip(b["t"].tolist(), b["pos"].tolist(), strict=True)]
    held.sort()
    n = sum(r[0] <= mark * 1000 for r in held)
    return held[:n], held[n:]


def fragmenter(p: CodecParams, most: int = 100_000):
    """State function: holds the open fragment of a track and puts out a container for each closed one.

    Rows wait until the watermark has passed them, so disorder within its delay does not matter. A step too fast,
    or a pause too long for the fragment so far, closes it; so does the watermark, once any later point would, and so does
    `most` points, the bound of the state. The interval of a fragment of one point must be given, since the rule for it
    needs all of a track."""
    if p.default_dt is None:
        raise ValueError("a stream needs default_dt")

    def run(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        frag, dim, open_t, open_pos, held_t, held_pos = state.get if state.exists else (0, 0, [], [], [], [])
        rows, mark = _pairs(open_t, open_pos, dim), state.getCurrentWatermarkMs()
        due, held = _arrived(iter(()) if state.hasTimedOut else batches, _pairs(held_t, held_pos, dim), mark)
        frag, rows, closed = _advance(key[0], frag, rows, due, p, most)
        yield from closed
        if rows and (idle := _idle(rows, p)) is not None and idle <= mark * 1000:
            yield _close(key[0], frag, rows, p)
            frag, rows = frag + 1, []
        some = rows or held
        state.update((frag, len(some[0][1]) if some else dim, *_flat(rows), *_flat(held)))
        wait = [held[0][0]] if held else []
        if rows and (idle := _idle(rows, p)) is not None:
            wait.append(idle)
        if wait:
            state.setTimeoutTimestamp(max(mark, min(wait) // 1000) + 1)

    return run


def _once(points: DataFrame, delay: str) -> DataFrame:
    return points.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["track_id", "t"])


def compress_stream(points: DataFrame, p: CodecParams, delay: str = "1 hour", most: int = 100_000) -> DataFrame:
    """Containers of closed fragments of a stream (track_id, ts, t, pos). Repeated times within the delay go once."""
    return _once(points, delay).groupBy("track_id").applyInPandasWithState(fragmenter(p, most), BLOCK, STATE, "append", GroupStateTimeout.EventTimeTimeout)


def _path(track: str, made: list, weak: bool) -> pd.DataFrame:
    return pd.DataFrame({"track_id": [track] * len(made), "t": [t for t, _ in made], "pos": [list(x) for _, x in made], "generated": [weak] * len(made)})


def cone_simplifier(eps: float, weak: bool, m: int = 16):
    """State function of a one-pass simplifier: the state is a cone, and the rows that wait for the watermark."""

    def run(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        dim, cone, held_t, held_pos = state.get if state.exists else (0, "null", [], [])
        due, held = _arrived(iter(()) if state.hasTimedOut else batches, _pairs(held_t, held_pos, dim), mark := state.getCurrentWatermarkMs())
        c = Cone(eps, weak, m, json.loads(cone))
        made = [x for t, pos in due if c.last is None or t != c.last[0] for x in c.add(t, pos)]
        if made:
            yield _path(key[0], made, weak)
        state.update((len(held[0][1]) if held else dim, json.dumps(c.state), *_flat(held)))
        if held:
            state.setTimeoutTimestamp(max(mark, held[0][0] // 1000) + 1)

    return run


def simplify_stream(points: DataFrame, eps: float, weak: bool = False, m: int = 16, delay: str = "1 hour") -> DataFrame:
    """KEPT rows of a planar stream (track_id, ts, t, pos) by the strong or the weak cone, as far as they are settled."""
    return _once(points, delay).groupBy("track_id").applyInPandasWithState(cone_simplifier(eps, weak, m), PATH, CONE_STATE, "append", GroupStateTimeout.EventTimeTimeout)


def _left(spark: SparkSession, checkpoint: str) -> DataFrame:
    """track_id and the state that an ended stream still holds."""
    kept = spark.read.format("statestore").option("operatorId", 0).load(checkpoint)
    return kept.select(F.col("key").getField(kept.schema["key"].dataType[0].name).alias("track_id"), "value.groupState.*")


def leftover(spark: SparkSession, checkpoint: str, p: CodecParams, most: int = 100_000) -> DataFrame:
    """Containers of what an ended stream of compress_stream still holds: waiting rows and open fragments."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            for r in b.itertuples():
                frag, rows, closed = _advance(r.track_id, r.frag, _pairs(r.open_t, r.open_pos, r.dim), sorted(_pairs(r.held_t, r.held_pos, r.dim)), p, most)
                yield from closed
                if rows:
                    yield _close(r.track_id, frag, rows, p)

    return _left(spark, checkpoint).mapInPandas(run, BLOCK)


def leftover_path(spark: SparkSession, checkpoint: str, eps: float, weak: bool = False, m: int = 16) -> DataFrame:
    """The end of each path of an ended stream of simplify_stream."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            for r in b.itertuples():
                c = Cone(eps, weak, m, json.loads(r.cone))
                made = [x for t, pos in sorted(_pairs(r.held_t, r.held_pos, r.dim)) if c.last is None or t != c.last[0] for x in c.add(t, pos)]
                yield _path(r.track_id, made + c.finish(), weak)

    return _left(spark, checkpoint).mapInPandas(run, PATH)


#: state on the executors' disks and in bounded memory, since a stream of one file holds all its keys at once
STATE_STORE = {
    "spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider",
    "spark.sql.streaming.stateStore.rocksdb.boundedMemoryUsage": "true",
    "spark.sql.streaming.stateStore.rocksdb.maxMemoryUsageMB": "256",
}


def _ended(out: DataFrame, mode: str = "append") -> tuple[DataFrame, str, StreamingQuery]:
    """Run a stream over what its source holds now: (its rows, its checkpoint, the query). Appended rows go to files in the
    shared folder; the few of a complete result to a table in memory."""
    spark, name = out.sparkSession, f"replay_{uuid.uuid4().hex}"
    checkpoint = new_path(spark, name)
    writer = out.writeStream.queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True)
    path = new_path(spark, "rows") if mode == "append" else None
    usual = {k: spark.conf.get(k, None) for k in STATE_STORE}
    try:
        for k, v in STATE_STORE.items():
            spark.conf.set(k, v)
        query = writer.format("parquet").start(path) if path else writer.format("memory").start()
    finally:  # a started query has its own copy
        for k, v in usual.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)
    query.awaitTermination()
    return (spark.read.schema(out.schema).parquet(path) if path else spark.table(name)), checkpoint, query


def late_dropped(query: StreamingQuery) -> int:
    """Rows that came behind the watermark and were dropped, by the query's own reports."""
    return sum(o["numRowsDroppedByWatermark"] for p in query.recentProgress for o in p["stateOperators"][-1:])


def events_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events' file, or files, as a stream."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    path = f"{sf_dir}/events.parquet"
    fs = spark._jvm.org.apache.hadoop.fs.Path(path)
    single = fs.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(fs).isFile()
    reader = spark.readStream.schema(schema)
    events = reader.option("pathGlobFilter", "events.parquet").parquet(sf_dir) if single else reader.parquet(path)
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def replay(spark: SparkSession, sf_dir: str, what: str) -> DataFrame:
    """Stream the events once (available-now) and return what came of them."""
    events = events_stream(spark, sf_dir)
    if what == "count":
        out, mode = events.groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("event_id").alias("total")), "complete"
    elif what == "dedupe":
        out, mode = events.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["user_id", "event_type", "ts"]).select("user_id", "event_type", F.unix_micros("ts").alias("t")), "append"
    else:
        pts = events.select(F.col("user_id").cast("string").alias("track_id"), "ts", F.unix_micros("ts").alias("t"), F.array("value").alias("pos"))
        return fragments_of(pts, CodecParams(eps=10.0, eps_f=10 / 0.6, b_s=4, r_ret=1.0, eps_p=5.0, default_dt=3_600_000_000))
    return _ended(out, mode)[0]


def fragments_of(points: DataFrame, p: CodecParams) -> DataFrame:
    """All fragments of a stream that ends: those put out on the way, then what it held at its end."""
    made, checkpoint, _ = _ended(compress_stream(points, p))
    return made.unionByName(leftover(points.sparkSession, checkpoint, p)).select("track_id", "frag", "n", "t0", "max_sed", "error_points")


def path_of(points: DataFrame, eps: float, weak: bool = False) -> DataFrame:
    """The whole path of a stream that ends."""
    made, checkpoint, _ = _ended(simplify_stream(points, eps, weak))
    return made.unionByName(leftover_path(points.sparkSession, checkpoint, eps, weak))
