"""Exact and near de-duplication, against brute force."""

import hashlib
import random
import re

import pytest
import xxhash
from pyspark.sql import types as T

from spectrack.llm import queries
from spectrack.llm.common import keep_rows, row_key, stage_dir
from spectrack.llm.components import components
from spectrack.llm.exact_dedup import exact_dedup
from spectrack.llm.simhash import covering_masks, fingerprint, links, near_duplicates

DOCS = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("kept", T.StringType()), T.StructField("n", T.IntegerType())])


def docs(spark, rows):
    return spark.createDataFrame([(i, t, "x", 1) for i, t in rows], DOCS)


def slow_fingerprint(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 3]) for i in range(len(words) - 2)] or [" ".join(words)]
    h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def slow_components(fps):
    root = {f: f for f in fps}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    items = list(fps)
    for i, a in enumerate(items):
        for b in items[:i]:
            if (a ^ b).bit_count() <= 2:
                root[max(find(a), find(b))] = min(find(a), find(b))
    return {f: find(f) for f in items}


def test_fingerprint_is_the_plain_one():
    for text in ["", None, " \t", "One", "one two", "A b c", "a b c d", "É é A\x0bb  c\n\nd a b c d é", "x " * 70000 + "y z"]:
        assert fingerprint(text) == slow_fingerprint(text), text


def test_masks_cover_every_pair():
    masks = covering_masks(2)
    assert len(masks) == 7
    for i in range(64):
        for j in range(64):
            assert any(not m >> i & 1 and not m >> j & 1 for m in masks)


def test_links_give_the_components_of_all_pairs(spark):
    r = random.Random(1)
    fps = set()
    for _ in range(12):  # balls and chains, some of them dense
        x = r.getrandbits(64)
        for _ in range(r.choice([1, 3, 40])):
            fps.add(x)
            for _ in range(r.choice([0, 1, 2, 3])):
                x ^= 1 << r.randrange(64 if r.random() < 0.5 else 6)
    fps = {f - (1 << 64) if f >> 63 else f for f in fps}
    df = spark.createDataFrame([(f,) for f in fps], "fp long")
    got = dict(components(links(df)).collect())
    unsigned = {f & (1 << 64) - 1: f for f in fps}
    want = {}
    for f, root in slow_components(unsigned).items():
        want.setdefault(root, set()).add(unsigned[f])
    found = {}
    for f in fps:
        found.setdefault(got.get(f, f), set()).add(f)
    assert sorted(map(sorted, want.values())) == sorted(map(sorted, found.values()))
    assert all(min(group) == root for root, group in found.items())


def test_components_of_a_path_and_a_star(spark):
    edges = [(i, i + 1) for i in range(0, 70)] + [(200, i) for i in range(201, 240)] + [(5, 5)]
    got = dict(components(spark.createDataFrame(edges, "a long, b long")).collect())
    assert all(got[i] == 0 for i in range(1, 71)) and all(got[i] == 200 for i in range(201, 240))
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_near_duplicates_query(spark, sf_dir):
    rows = {r.doc_id: r for r in queries.op1_simhash(spark, sf_dir).collect()}
    texts = dict(queries.table(spark, sf_dir, "documents").select("doc_id", "text").collect())
    fps = {i: slow_fingerprint(t) for i, t in texts.items()}
    root = slow_components(set(fps.values()))
    least = {}
    for i, f in fps.items():
        least[root[f]] = min(i, least.get(root[f], i))
    assert rows.keys() == texts.keys()
    for i, f in fps.items():
        assert rows[i].fingerprint == f"{f:016x}" and rows[i].component_id == least[root[f]]


def test_near_duplicates_odd_rows(spark):
    rows = [(1, None), (2, ""), (None, " \n"), (4, "a b c d"), (4, "a b c d"), (None, "z y x w v"), (7, "word " * 300000)]
    got = near_duplicates(docs(spark, rows)).collect()
    assert len(got) == 7
    zero = [r for r in got if r.fingerprint == "0" * 16]
    assert len(zero) == 3 and {r.component_id for r in zero} == {1} and sum(r.kept for r in zero) == 1
    assert [r.component_id for r in got if r.doc_id is None and r.fingerprint != "0" * 16] == [None]
    assert sum(r.kept for r in got) == 5  # both equal rows of 4 share a key
    assert near_duplicates(docs(spark, [])).count() == 0


def brute_exact(rows):
    strip = [re.sub(r"[\x20\x09-\x0D]", "", t or "") for _, t in rows]
    out = []
    for k, (i, _) in enumerate(rows):
        same = [j for j, s in enumerate(strip) if s == strip[k]]
        best = min(same, key=lambda j: (-len(rows[j][1] or ""), rows[j][0] is None, rows[j][0] or 0, j))
        out.append((i, rows[best][0], len(same), k == best, hashlib.sha256(strip[k].encode()).hexdigest()))
    return out


def test_exact_dedup_both_ways(spark):
    rows = [(i, "hot text " + " " * (i % 3)) for i in range(200, 0, -1)] + [(i, f"t{i % 40}") for i in range(300, 400)]
    rows += [(None, None), (901, ""), (902, " \x0b"), (903, "é\u00a0x"), (903, "é\u00a0x"), (904, "é x"), (None, "t3 "), (905, "q" * 200000)]
    order = lambda x: sorted(map(repr, x))
    for least in (10, 10**9):  # heavy digests broadcast; all shuffled
        got = exact_dedup(docs(spark, rows), least=least).drop("row_key").collect()
        assert order(map(tuple, got)) == order(brute_exact(rows))
    assert exact_dedup(docs(spark, [])).count() == 0


def test_one_of_equal_rows_stays(spark):
    rows = docs(spark, [(1, "same")] * 2000 + [(2, "other"), (3, "gone"), (None, None), (None, None)])
    kept = rows.filter("text IS NULL OR text <> 'gone'").select(row_key().alias("row_key")).distinct()
    got = keep_rows(rows, kept, row_key())
    assert got.columns == rows.columns and sorted(map(repr, got.select("doc_id", "text").collect())) == sorted(map(repr, spark.createDataFrame([(1, "same"), (2, "other"), (None, None)], "doc_id long, text string").collect()))
    assert keep_rows(rows.limit(0), kept, row_key()).count() == 0


def test_staging_needs_a_shared_folder():
    class Conf(dict):
        def get(self, key, default=None):
            return dict.get(self, key, default)

    class Session:
        conf = Conf()
        sparkContext = type("C", (), {"master": "spark://host:7077"})

    with pytest.raises(RuntimeError, match="checkpoint"):
        stage_dir(Session())
    Session.conf["spark.checkpoint.dir"] = "hdfs:///shared"
    assert stage_dir(Session()) == "hdfs:///shared"
