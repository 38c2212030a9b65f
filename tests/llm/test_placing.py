"""Sharding, URL rules and packing."""

import collections
import json
import math
import zlib

import numpy as np
import public_tokenizers
import xxhash
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from spectrack.llm import queries
from spectrack.llm.common import numbered, ranked
from spectrack.llm.packing import MADE, Ids, matched, merged, pack, planned, sweep
from spectrack.llm.sharding import even_tree, grown, shard, shard_count
from spectrack.llm.url_filter import Rules, build, split_url, url_filter

BPE = public_tokenizers.path("byte_bpe_50k.json")


def spark_hash(*values):
    """XXH64 chained over (value, width) pairs, as Spark's xxhash64 does."""
    seed = 42
    for v, width in values:
        seed = xxhash.xxh64_intdigest(int(v).to_bytes(width, "little", signed=True), seed)
    return seed


def brute_place(doc_id, tree):
    def pick(weights, parent, level):
        def draw(i):
            u = ((spark_hash((doc_id, 8), (level, 4), (parent, 4), (i, 4)) >> 11) + 0.5) / (1 << 53)
            return math.log(u) / weights[i] if weights[i] > 0 else -math.inf

        return max(range(len(weights)), key=lambda i: (draw(i), -i))

    a = pick([sum(map(sum, r)) for r in tree], 0, 1)
    b = pick([sum(x) for x in tree[a]], a, 2)
    c = pick(tree[a][b], a * 4096 + b, 3)
    return sum(len(x) for r in tree[:a] for x in r) + sum(map(len, tree[a][:b])) + c


def test_placement_is_the_plain_one_and_growth_moves_only_into_the_new_shard(spark):
    tree = even_tree(40)
    tree[0][1] = [3.0, 0.0]
    more = grown(tree)
    ids = range(3000)
    df = spark.createDataFrame([(i, f"text {i}") for i in ids], "doc_id long, text string")
    got = shard(df, tree, more).collect()
    for r in got:
        assert r.shard == brute_place(r.doc_id, tree) and r.grown_shard in (r.shard, 40)
    counts = collections.Counter(r.shard for r in got)
    assert counts[2] > 150 and counts[3] == 0 and shard_count(more) == 41
    assert 30 < sum(r.grown_shard == 40 for r in got) < 130


def test_a_weight_change_stays_in_its_subtree(spark):
    tree, lighter = even_tree(40), even_tree(40)
    lighter[1][2] = [0.5, 1.0]
    df = spark.createDataFrame([(i, "") for i in range(3000)], "doc_id long, text string")
    moved = [(r.shard, r.grown_shard) for r in shard(df, tree, lighter).collect() if r.shard != r.grown_shard]
    assert moved and all(a // 8 == 1 for a, _ in moved)  # nothing comes out of another region


def test_slots_sizes_and_odd_rows(spark):
    rows = [(1, None, 7), (None, "é", 7), (1, None, 7), (3, "x" * 300000, 7)] + [(i, "same", 7) for i in range(10, 400)]
    got = shard(spark.createDataFrame(rows, "doc_id long, text string, shard int"), even_tree(5), None).collect()
    by = collections.defaultdict(list)
    for r in got:
        by[r.shard].append(r.slot)
        assert r.grown_shard is None and r.law == "key"
    assert all(sorted(x) == list(range(len(x))) for x in by.values()) and sum(map(len, by.values())) == len(rows)
    assert {(r.size, r.text_crc32) for r in got if r.doc_id is None} == {(18, zlib.crc32("é".encode()))}
    assert {(r.size, r.text_crc32) for r in got if r.doc_id == 1} == {(16, 0)}
    assert shard(spark.createDataFrame([], "doc_id long, text string"), even_tree(5)).count() == 0


def test_urls(spark):
    urls = ["http://A.Example.org/es/1", "https://example.org", "x", None, "", "a://com/fr/", "a://xcom/fr/", "a://b.com:80/fr/", "://.org/?/", "h://example.org/en/12#q", "h://EXAMPLE.org?/es/", "h://com/de/" + "x" * 100000]
    rows = [(i, u, "r") for i, u in enumerate(urls)] + [(None, urls[0], "r")]
    df = spark.createDataFrame(rows, "page_id long, url string, rule string")
    got = {(r.page_id, r.host, r.path[:9]): (r.rule, r.verdict) for r in url_filter(df, queries.URL_RULES).collect()}
    assert got[0, "a.example.org", "/es/1"] == ("example.org/es/", "block") == got[None, "a.example.org", "/es/1"]
    assert got[1, "example.org", ""] == (None, "allow") == got[2, "", ""] == got[3, "", ""] == got[6, "xcom", "/fr/"]
    assert got[5, "com", "/fr/"] == ("com/fr/", "allow") and got[7, "b.com:80", "/fr/"] == (None, "allow")
    assert got[8, ".org", "/"] == ("org/", "allow") and got[9, "example.org", "/en/12"] == ("example.org/en/1", "block")
    assert got[10, "example.org", ""] == (None, "allow") and got[11, "com", "/de/xxxxx"] == ("com/de/", "block")
    assert url_filter(df.limit(0), queries.URL_RULES).count() == 0
    hostile = spark.createDataFrame([(1, "h://" + "a." * 500_000 + "example.org/es/"), (2, "h://" + "." * 1_000_000), (3, "h://" + "x" * 1_000_000 + "org/")], "page_id long, url string")
    assert {r.page_id: r.verdict for r in url_filter(hostile, queries.URL_RULES).select("page_id", "verdict").collect()} == {1: "block", 2: "allow", 3: "allow"}
    assert split_url("HTTP://ÄB.C/D?e") == ("Äb.c", "/D")


def test_equal_digests_are_told_apart(tmp_path, monkeypatch):
    import spectrack.llm.url_filter as u

    monkeypatch.setattr(u, "_digest", lambda text: 5)
    (tmp_path / "r").write_bytes(build([("allow", "a", "/"), ("block", "b", "/"), ("block", "c", "")]))
    got = Rules(str(tmp_path / "r")).probe([("b", "/x"), ("a", "/"), ("d", "/"), ("c", "")])
    assert got == [("b/", False), ("a/", True), (None, None), ("c", False)]
    (tmp_path / "e").write_bytes(build([]))
    assert Rules(str(tmp_path / "e")).probe([("a", "/")]) == [(None, None)]


def test_ids_are_the_librarys(spark, sf_dir):
    plain, fast = Tokenizer.from_file(BPE), Ids(BPE, 1000)
    odd = ["", " ", "  a", "a  b", "a \n b", "a\n b", "a \nb", "x ", "\u00a0 a \u2003b", "it's we'LL 'tis", "1 22 三 𝒳 ñ e\u0301", "a<|endoftext|> b", "\x1c \x1d", "\t a", "a" * 500, "a b" * 3000]
    texts = [r.text for r in queries.table(spark, sf_dir, "documents").select("text").collect()]
    long = [" " * 1_000_000, "\n" * 1_000_000, "a " + "\t" * 700_000 + "b", "a" * 1_000_000, "x" + " " * 6000 + "y  z"]
    for t in odd + texts + long:
        assert fast(t) == np.array(plain.encode(t, add_special_tokens=False).ids, "<u4").tobytes(), t[:80]


def test_other_tokenizer_files_go_to_the_library(tmp_path):
    spec = json.loads(open(BPE, encoding="utf-8").read())
    for change in ({"normalizer": {"type": "Lowercase"}}, {"pre_tokenizer": {"type": "ByteLevel", "add_prefix_space": True, "trim_offsets": True, "use_regex": True}}, {"pre_tokenizer": None}):
        path = tmp_path / "other.json"
        path.write_text(json.dumps(spec | change))
        plain, own = Tokenizer.from_file(str(path)), Ids(str(path))
        assert not own.fast
        for t in ("Some Text, it's", "a  b\n"):
            assert own(t) == np.array(plain.encode(t, add_special_tokens=False).ids, "<u4").tobytes()


def check_packing(rows, capacity):
    by = collections.defaultdict(list)
    for r in rows:
        by[r.sequence_id].append((r.offset, r.length))
    for spans in by.values():
        at = 0
        for offset, length in sorted(spans):
            assert offset == at
            at += length
        assert at <= capacity
    return len(by)


def best_fit(lengths, capacity):
    gaps = []
    for x in sorted(lengths, reverse=True):
        fit = [g for g in gaps if g >= x]
        if fit:
            gaps.remove(min(fit))
            gaps.append(min(fit) - x)
        else:
            gaps.append(capacity - x)
    return len(gaps)


def row_sweeps(lengths, capacity):
    """The sweeps a piece at a time: number of sequences and what each holds."""
    pieces, open_gaps, held, whole = sorted(lengths, reverse=True), [], [], sum(lengths)
    while pieces:
        tokens = sum(pieces)
        if not open_gaps or max(g for g, _ in open_gaps) < pieces[-1]:
            need = -(-tokens // capacity)
            for _ in range(max(need if 50 * tokens < whole else -(-9 * need // 10), sum(x > capacity // 2 for x in pieces))):
                open_gaps.append((capacity, len(held)))
                held.append([])
        waiting, touched, left = sorted(open_gaps, key=lambda g: (g[0], -g[1])), {}, []
        for x in pieces:
            # its equals stay beside it as long as they fit; else the smallest untouched gap
            mine = next((i for i, (gap, length) in touched.items() if length == x and gap >= x), None)
            if mine is None:
                fit = next((g for g in waiting if g[0] >= x), None)
                if fit is None:
                    left.append(x)
                    continue
                waiting.remove(fit)
                mine = fit[1]
                touched[mine] = (fit[0], x)
            held[mine].append(x)
            touched[mine] = (touched[mine][0] - x, x)
        open_gaps = waiting + [(gap, i) for i, (gap, _) in touched.items() if gap]
        pieces = left
    return held


def run_sweeps(lengths, capacity):
    """matched() until no piece is left: the pieces of each sequence, with their offsets."""
    items = [(1, x, 0, n, 0, 0, 0) for x, n in collections.Counter(lengths).items()]
    held, whole, opened = collections.defaultdict(list), sum(lengths), 0
    while any(x[0] == 1 for x in items):
        pieces = [x for x in items if x[0] == 1]
        tokens, least = sum(x[1] * x[3] for x in pieces), min(x[1] for x in pieces)
        if max((x[1] for x in items if x[0] == 0), default=0) < least:
            need = -(-tokens // capacity)
            more = max(need if 50 * tokens < whole else -(-9 * need // 10), sum(x[3] for x in pieces if x[1] > capacity // 2))
            items.append((0, capacity, opened, more, 0, 0, 0))
            opened += more
        made = merged(matched(items))
        for kind, size, _, n, each, sequence, gap in made:
            if kind == 2:
                for i in range(n):
                    held[sequence + i // each].append((capacity - gap + i % each * size, size))
        items = [x for x in made if x[0] < 2]
    return held


def test_sweeps_are_the_plain_ones_and_nearly_best_fit():
    r = np.random.default_rng(3)
    for _ in range(30):
        lengths = r.integers(1, r.choice([12, 60, 101]), r.integers(1, 300)).tolist()
        held = run_sweeps(lengths, 100)
        assert sorted(x for spans in held.values() for _, x in spans) == sorted(lengths)
        for spans in held.values():
            at = 0
            for offset, x in sorted(spans):
                assert offset == at
                at += x
            assert at <= 100
        # equal gaps may change places, so what is left of each is compared
        assert sorted(sum(x) for x in row_sweeps(lengths, 100) if x) == sorted(sum(x for _, x in spans) for spans in held.values())
        assert len(held) <= best_fit(lengths, 100) * 1.01 + 1


def test_ranges_and_their_boundary_match_as_one_list_does(spark):
    r = np.random.default_rng(5)
    items = [(0, int(x), i * 100, int(r.integers(1, 9)), 0, 0, 0) for i, x in enumerate(r.integers(1, 1025, 60))]
    items += [(1, int(x), 0, int(r.integers(1, 9)), 0, 0, 0) for x in np.unique(r.integers(1, 1025, 90))]
    want = sorted(merged(matched(items)))
    for ranges in (1, 3, 8):
        got = sweep(spark.createDataFrame(items, MADE), ranges).collect()
        assert sorted(map(tuple, got)) == want


def test_planned_runs_cover_every_rank(spark):
    lengths = np.minimum(64, np.random.default_rng(8).geometric(0.1, 500))
    count = collections.Counter(lengths.tolist())
    rows = planned(spark.createDataFrame(list(count.items()), "length long, n long"), 64).collect()
    for x, n in count.items():
        spans = sorted((r["first"], r["n"]) for r in rows if r["length"] == x)
        assert [a for a, _ in spans] == [sum(m for _, m in spans[:i]) for i in range(len(spans))] and sum(m for _, m in spans) == n
    used = {r["sequence"] + i // r["each"] for r in rows for i in range(r["n"])}
    assert len(used) <= best_fit(lengths.tolist(), 64) * 1.01 + 1


def test_equal_rows_are_ranked_apart(spark):
    df = spark.range(5000).select((F.col("id") * 0).alias("k"), F.lit("same").alias("v"), F.col("id").alias("rid")).cache()
    got = ranked(df, ["k"], [F.col("v")], 5000, "at", rows_per_bucket=50, spread=F.col("rid")).collect()
    assert sorted(r["at"] for r in got) == list(range(5000))
    one = numbered(spark.range(1000).select((F.col("id") * 7919 % 1000).alias("x")), [F.col("x").desc()], "at")
    assert all(r["at"] == 999 - r["x"] for r in one.collect())
    assert numbered(spark.range(0), [F.col("id")], "at").count() == 0


def test_packing_query(spark, sf_dir):
    rows = queries.op10_pack(spark, sf_dir).collect()
    plain = Tokenizer.from_file(BPE)
    found = collections.defaultdict(list)
    for r in rows:
        found[r.doc_id].append(r)
    texts = dict(queries.table(spark, sf_dir, "documents").select("doc_id", "text").collect())
    assert found.keys() == texts.keys()
    for i, text in texts.items():
        ids, at = [*plain.encode(text, add_special_tokens=False).ids, 2], 0
        for k, r in enumerate(sorted(found[i], key=lambda r: r.piece)):
            assert (r.piece, r.start) == (k, at) and (r.length == 1024 or k == 0)
            assert r.ids_crc32 == zlib.crc32(np.array(ids[at : at + r.length], "<u4").tobytes())
            at += r.length
        assert at == len(ids) and (len(found[i]) == 1 or len(ids) > 1024)
    n = check_packing(rows, 1024)
    assert n <= math.ceil(sum(r.length for r in rows) / 1024) * 1.01 + 1


def test_packing_odd_rows(spark):
    rows = [(1, None, 0), (None, "", 0), (2, "a b c", 0), (2, "a b c", 0), (3, "word " * 50000, 0), (4, " " * 1_000_000, 0), (5, "a" * 300_000, 0)] + [(i, "same text", 0) for i in range(10, 600)]
    got = pack(spark.createDataFrame(rows, "doc_id long, text string, length int"), BPE).collect()
    assert sum(r.piece == 0 for r in got) == len(rows) and check_packing(got, 1024)
    assert pack(spark.createDataFrame([], "doc_id long, text string"), BPE).count() == 0
