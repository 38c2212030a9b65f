"""The streaming fragmenter against the batch kernel's rule."""

import collections

import numpy as np
from pyspark.sql import functions as F

from spectrack import queries
from spectrack.functions import track as K
from spectrack.functions.params import CodecParams
from spectrack.sources import tables as D
from spectrack.streaming import streams

MINUTE = 60_000_000


def test_stream_fragments_equal_the_batch_rule(spark, tmp_path):
    """Three micro-batches, with rows of an earlier time in a later one, and all fragments to the last."""
    r = np.random.default_rng(3)
    p = CodecParams(eps=10.0, eps_f=10 / 0.6, b_s=4, r_ret=1.0, eps_p=5.0, default_dt=MINUTE)
    tracks = {}
    for name in "abc":
        gaps = np.where(r.random(240) < 0.04, r.integers(20, 90, 240), r.integers(1, 4, 240)) * MINUTE
        tracks[name] = np.cumsum(gaps) + 10**12
    rows = [(n, int(t), [float(i % 7)]) for n, ts in tracks.items() for i, t in enumerate(ts)]
    late = {(n, t) for n, t, _ in rows if r.random() < 0.1}  # comes up to 40 minutes after its time
    rows.sort(key=lambda x: x[1] + (40 * MINUTE if x[:2] in late else 0))
    schema = "track_id string, t long, pos array<double>"
    for i in range(3):
        part = rows[len(rows) * i // 3 : len(rows) * (i + 1) // 3]
        spark.createDataFrame(part, schema).coalesce(1).write.parquet(str(tmp_path / f"in{i}"))
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in*"))
    got = collections.defaultdict(list)
    for x in streams.fragments_of(stream.withColumn("ts", F.timestamp_micros("t")), p).collect():
        got[x.track_id].append((x.frag, x.n, x.t0))
    for name, t in tracks.items():
        start = K.fragment_starts(t, np.zeros((len(t), 1)), p)
        assert sorted(got[name]) == [(i, int(n), int(t[a])) for i, (a, n) in enumerate(zip(start, np.diff(np.append(start, len(t))), strict=True))]


def test_registered_stream_loses_nothing(spark, sf_dir):
    n = queries.op_stream_fragments(spark, sf_dir).agg(F.sum("n")).first()[0]
    assert n == D.table(spark, sf_dir, "events").select("user_id", "ts").distinct().count()


def _files(spark, tmp_path, parts, schema):
    for i, rows in enumerate(parts):
        spark.createDataFrame(rows, schema).coalesce(1).write.parquet(str(tmp_path / f"in{i}"))
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in*"))
    return stream.withColumn("ts", F.timestamp_micros("t"))


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    """A batch moves the watermark; what comes behind it in later batches is dropped, and the query says how much."""
    schema = "track_id string, t long, pos array<double>"
    hour = 60 * MINUTE
    on_time = [("a", 10**12 + i * MINUTE, [float(i)]) for i in range(300)]
    parts = [on_time[:200], on_time[200:250], on_time[250:] + [("a", 10**12 - 9 * hour, [0.0]), ("a", 10**12 - 8 * hour, [0.0])]]
    p = CodecParams(eps=10.0, eps_f=10 / 0.6, b_s=4, r_ret=1.0, eps_p=5.0, default_dt=MINUTE)
    made, checkpoint, query = streams._ended(streams.compress_stream(_files(spark, tmp_path, parts, schema), p))
    assert streams.late_dropped(query) == 2
    rows = made.unionByName(streams.leftover(spark, checkpoint, p)).collect()
    assert sum(x.n for x in rows) == 300


def test_open_fragments_are_bounded(spark, tmp_path):
    schema = "track_id string, t long, pos array<double>"
    rows = [("a", 10**12 + i * MINUTE, [float(i)]) for i in range(250)]
    p = CodecParams(eps=10.0, eps_f=10 / 0.6, b_s=4, r_ret=1.0, eps_p=5.0, default_dt=MINUTE)
    made, checkpoint, _ = streams._ended(streams.compress_stream(_files(spark, tmp_path, [rows[:120], rows[120:]], schema), p, most=50))
    assert sorted(x.n for x in made.unionByName(streams.leftover(spark, checkpoint, p, 50)).collect()) == [50] * 5


def test_appended_rows_and_state_stay_off_the_heap(spark, sf_dir):
    """Rows of a stream are files that Spark reads, not a table on the driver; its state is in RocksDB, for the stream alone."""
    key = "spark.sql.streaming.stateStore.providerClass"
    usual = spark.conf.get(key)
    out = streams.replay(spark, sf_dir, "dedupe")
    assert out.inputFiles() and out.count() == spark.read.parquet(f"{sf_dir}/events.parquet").select("user_id", "event_type", "ts").distinct().count()
    made, checkpoint, query = streams._ended(streams.simplify_stream(streams.events_stream(spark, sf_dir).selectExpr("string(user_id) AS track_id", "ts", "unix_micros(ts) AS t", "array(value, value) AS pos"), 30.0))
    assert any("rocksdb" in k for p in query.recentProgress for o in p["stateOperators"] for k in o["customMetrics"]) and spark.conf.get(key) == usual
