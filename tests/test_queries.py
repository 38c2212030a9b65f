"""Spark queries against DuckDB, the two engines against each other, plans and streams."""

import collections

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from spectrack import oracles, queries
from spectrack.functions import track as K
from spectrack.functions.params import CodecParams, derive
from spectrack.operators import blocks as B
from spectrack.plans import codec
from spectrack.sources import tables as D
from spectrack.streaming import streams

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck(sf_dir):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    return con


def plain(rows, names):
    order = sorted(range(len(names)), key=lambda i: names[i])
    value = lambda x: list(x) if isinstance(x, (list, tuple)) else x
    return sorted(repr([value(r[i]) for i in order]) for r in rows)


@pytest.mark.parametrize("name", sorted(oracles.ORACLES))
def test_oracle(name, spark, sf_dir, duck):
    df = queries.QUERIES[name](spark, sf_dir)
    want = duck.execute(oracles.ORACLES[name])
    columns = [c[0] for c in want.description]
    assert sorted(df.columns) == sorted(columns)
    assert plain(map(tuple, df.collect()), df.columns) == plain(want.fetchall(), columns)


def test_entry(spark):
    rows = entry.entry(spark).collect()
    assert rows and max(r.max_sed for r in rows) <= 0.5 and set(oracles.ORACLES) <= set(entry.queries())


def test_engines_agree(spark, sf_dir):
    """Codes of the transparent engine and of the kernel are the same integers."""
    pts = D.emb_cum(spark, sf_dir).filter("track_id < '2'")
    p = derive(0.5, 2, eps_p=0.25)
    sig = B.axes(B.from_clock(pts, 100_000))
    coded = B.trimmed(B.codes(B.coefficients(B.velocities(sig, p.b_s), p.b_s, p.r_ret), p.eps_f))
    mine = {(r.track_id, r.block_id, r.axis): list(r.codes) for r in coded.collect()}
    ends = {(r.track_id, r.block_id, r.axis): r.code for r in B.block_ends(sig, p.b_s, p.eps_p, 2).collect()}
    for r in codec.compress(pts, p).collect():
        e, _ = K.unpack(r.payload, p)
        at = 0
        for block in range(len(e.lengths)):
            for axis in range(2):
                n = int(e.lengths[block, axis])
                assert mine[r.track_id, block, axis] == e.coefficients[at : at + n].tolist() and ends[r.track_id, block, axis] == e.ends[block, axis]
                at += n


def beyond(pts, back, eps):
    """Points lost, invented or further off than eps."""
    both = pts.join(back.withColumnRenamed("pos", "q"), ["track_id", "t"], "full_outer")
    return both.filter(F.col("q").isNull() | F.col("pos").isNull() | (F.sqrt(F.pow(F.col("pos")[0] - F.col("q")[0], 2) + F.pow(F.col("pos")[1] - F.col("q")[1], 2)) > eps)).count()


def test_chunks_bound_a_task_and_keep_the_bound(spark, sf_dir):
    pts = D.ev_all(spark, sf_dir)
    p = derive(50.0)
    c = codec.compress(pts, p, 300).cache()
    assert c.count() >= 4 and max(r.n for r in c.collect()) <= 300 and all(r.cut for r in c.collect())
    assert beyond(pts, codec.decompress(c, pts, p), 50.0) == 0


def test_chunks_hold_points_and_not_spans(spark):
    """Nearly all points in a hundredth of the time; then only the last of them asked for, and some of them twice."""
    r = np.random.default_rng(2)
    t = np.sort(np.concatenate((r.choice(10_000, 990, replace=False), 10**6 + np.arange(10) * 10**5))) * 1000
    rows = [(name, int(x), [float(x % 977), float(x % 13)]) for name in "ab" for x in t]
    pts = spark.createDataFrame(rows + [("short", int(x), [1.0, float(i)]) for i, x in enumerate(t[:50])], "track_id string, t long, pos array<double>")
    c = codec.compress(pts, derive(1.0), 300).cache()
    n = {k: [x.n for x in c.collect() if x.track_id == k] for k in ("a", "b", "short")}
    assert all(max(n[k]) <= 300 and sum(n[k]) == 1000 for k in "ab") and n["short"] == [50]
    late = pts.filter(F.col("t") >= int(t[700]))
    assert beyond(late, codec.decompress(c, late.unionByName(late)), 1.0) == 0
    outside = spark.createDataFrame([("a", -5), ("a", int(t[-1]) + 1), ("unknown", 5)], "track_id string, t long")
    assert codec.decompress(c, outside).count() == 0


def test_containers_made_otherwise_are_refused(spark):
    pts = spark.createDataFrame([("a", i * 10, [float(i * i % 31)]) for i in range(50)], "track_id string, t long, pos array<double>")
    c = codec.compress(pts, derive(2.0, 1, b_s=8)).cache()
    with pytest.raises(Exception, match="other parameters"):
        codec.decompress(c, pts, derive(2.0, 1)).collect()
    assert codec.decompress(c, pts, derive(2.0, 1, b_s=8)).count() == 50


def test_plans(spark, sf_dir):
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    assert plan(queries.q_fragments(spark, sf_dir)).count("Python") == 0 and "CartesianProduct" not in plan(queries.q_resample(spark, sf_dir))
    one = plan(codec.compress(D.table(spark, sf_dir, "events").select(F.col("user_id").cast("string").alias("track_id"), D.micros("ts").alias("t"), F.array("value").alias("pos")), derive(50.0, 1), None))
    assert one.count("Exchange hashpartitioning") == 1 and "props" not in one


def test_unusable_points_are_counted(spark):
    rows = [("a", 1, [1.0]), ("a", 2, [float("nan")]), ("a", 3, [None]), (None, 4, [1.0]), ("a", None, [1.0]), ("a", 5, [])]
    assert D.refused(spark.createDataFrame(rows, "track_id string, t long, pos array<double>")) == 5
    empty = spark.createDataFrame([], "track_id string, t long, pos array<double>")
    assert codec.compress(empty, derive(1.0)).count() == 0


def test_workload_shapes(spark, sf_dir):
    from spectrack.plans import workloads as X

    rows = X.w5_ratio_vs_eps(spark, sf_dir, [20.0, 50.0, 100.0]).collect()
    by = collections.defaultdict(dict)
    for r in rows:
        assert r.max_sed <= r.eps * (1 + 1e-9)
        by[r.fixture, r.method][r.eps] = (r.ratio, r.mean_sed)
    for series in by.values():
        ratios = [series[e][0] for e in sorted(series)]
        assert ratios == sorted(ratios, reverse=True)  # every method's ratio falls with the bound
    assert all(r.encoded_ratio < r.plain_ratio for r in X.w1_encode_ablation(spark, sf_dir, [50.0]).collect())
    zero = X.w2_zigzag_ablation(spark, sf_dir, [50.0]).collect()
    assert all(r.zero_free_l1 < r.classic_l1 for r in zero)
    kept = {(r.fixture, r.value): r for r in X.w4_retention(spark, sf_dir, (1.0, 2**-7)).collect()}
    assert all(kept[f, 2**-7].error_pct >= kept[f, 1.0].error_pct for f, _ in kept)
    coarse = {(r.fixture, r.value): r.error_pct for r in X.w7_freq_precision(spark, sf_dir, (0.2, 1.2)).collect()}
    assert all(coarse[f, 0.2] > coarse[f, 1.2] for f, _ in coarse)
    low = X.w13_trapezoid(spark, sf_dir).filter("fixture = 'trapezoid'").first().low_share
    assert low > 0.9


def test_stream_equals_batch(spark, sf_dir):
    """Fragments put out by the stream, and those open at its end, are those of one pass in order, each with the
    batch kernel's error."""
    got = collections.defaultdict(list)
    for r in streams.replay(spark, sf_dir, "fragments").collect():
        got[r.track_id].append((r.frag, r.n, r.t0))
        assert r.max_sed <= 10.0
    p = CodecParams(eps=10.0, eps_f=10 / 0.6, b_s=4, r_ret=1.0, eps_p=5.0, default_dt=3_600_000_000)
    rows = collections.defaultdict(set)
    for r in D.table(spark, sf_dir, "events").select(F.col("user_id").cast("string").alias("u"), D.micros("ts").alias("t")).collect():
        rows[r.u].add(r.t)
    assert set(got) == set(rows)
    for track, times in rows.items():
        t = np.array(sorted(times))
        start = K.fragment_starts(t, np.zeros((len(t), 1)), p)
        assert sorted(got[track]) == [(i, int(n), int(t[a])) for i, (a, n) in enumerate(zip(start, np.diff(np.append(start, len(t))), strict=True))]


def test_sinks_and_logs(spark, sf_dir, tmp_path):
    c = codec.compress(D.li_supp_smooth(spark, sf_dir), derive(50.0, 3))
    D.write_container(c, str(tmp_path / "c"))
    all_rows = D.read_container(spark, str(tmp_path / "c"))
    track = all_rows.first()
    assert all_rows.count() == c.count() and D.read_container(spark, str(tmp_path / "c"), track.track_id).count() == 1
    assert D.read_container(spark, str(tmp_path / "c"), t_from=track.t_max + 10**15).count() == 0
    pts = spark.createDataFrame([("a", 1, 2.0, 3.0), ("a", 2, 4.0, 5.0)], "track_id string, t long, x double, y double")
    pts.write.csv(str(tmp_path / "csv"), header=True)
    pts.write.json(str(tmp_path / "json"))
    want = [("a", 1, [2.0, 3.0]), ("a", 2, [4.0, 5.0])]
    assert sorted(map(tuple, D.read_gps_json(spark, str(tmp_path / "json")).collect())) == want
    assert sorted(map(tuple, D.read_gps_csv(spark, str(tmp_path / "csv")).collect())) == want
    (tmp_path / "solid.csv").write_text("b,1,1.5,2.5,3.5\nb,2,1.5,oops,3.5\nb,3,1.5\nb,x,1,2,3\nb,4,1,2,3\n")
    solid = D.read_gps_csv(spark, str(tmp_path / "solid.csv"), header=False)
    assert sorted(map(tuple, D.usable(solid).collect())) == [("b", 1, [1.5, 2.5, 3.5]), ("b", 4, [1.0, 2.0, 3.0])] and D.refused(solid) == 3


def test_whole_numbers_of_a_long_signal_are_one_row(spark, sf_dir):
    pts = D.int_signal(spark, sf_dir).filter("signal = 'n_chars'").select(F.col("signal").alias("track_id"), F.col("i").alias("t"), F.array(F.col("n").cast("double")).alias("pos"))
    whole, cut = queries._lossless(pts, None).collect(), queries._lossless(pts, 30).collect()
    assert len(cut) == 1 and cut == whole and cut[0]["off"] == 0


def test_theory_and_parameters_read_a_table(spark, sf_dir):
    for name, table in (("q_theory", "lineitem"), ("q_derive", "lineitem"), ("q_pick_a", "events")):
        assert any(f.endswith(f"{table}.parquet") for f in queries.QUERIES[name](spark, sf_dir).inputFiles())


def test_small_chunks_need_few_tasks(spark):
    """A task streams its chunks, so their number follows from the points and not from the size of a chunk; times past many chunks are found."""
    n = 3_000
    pts = spark.range(n).select(F.lit("a").alias("track_id"), (F.col("id") * 1_000_000 + F.col("id") % 7).alias("t"), F.array(F.col("id") % 90 * 1.0, F.col("id") * 1.0).alias("pos"))
    made = codec.compress(pts, derive(5.0), 20)
    assert made.rdd.getNumPartitions() <= 16
    c = queries.staged(made, "container")
    assert c.count() >= n // 20
    late = pts.filter(F.col("t") > 400_000_000)
    assert queries._off(late, codec.decompress(c, late.unionByName(late.limit(5))), 5.0).first()["violations"] == 0
    gone = pts.limit(5).select(F.lit("b").alias("track_id"), "t")
    assert codec.decompress(c, gone).count() == 0
