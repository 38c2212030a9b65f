"""Language, toxicity, neighbours, language model and mixing: brute force and held-out rows."""

import collections
import functools
import math
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest

from spectrack.llm import language, queries, scoring, toxicity
from spectrack.llm.mixing import apportion, mix, mixed_texts
from spectrack.llm.neighbours import nearest


def out(i, mod, rest):
    return zlib.crc32(str(i).encode()) % mod == rest


def test_language_of_held_out_rows(spark, sf_dir):
    lang = dict(queries.table(spark, sf_dir, "documents").select("doc_id", "lang").collect())
    rows = queries.op6_language(spark, sf_dir).collect()
    assert len(rows) == len(lang) and all(r.held_out == out(r.doc_id, 5, 0) and 0 <= r.score <= 1 for r in rows)
    held = [r for r in rows if r.held_out]
    assert np.mean([r.lang_pred == lang[r.doc_id] for r in held]) >= 0.95


def test_language_odd_texts(spark):
    docs = [(i, f"the cat and the dog number {i}", "en", "x") for i in range(30)] + [(i, f"der Hund und die Katze {i}", "de", "x") for i in range(30, 60)] + [(None, "the dog and", None, "x")]
    df = spark.createDataFrame(docs, "doc_id long, text string, lang string, score string")
    model = language.fit(df)
    assert set(model.langs) == {"de", "en"}
    texts = [None, "", "12 !?", "é", "the dog " * 400_000, "Das ist der Hund und die Katze"]
    ask = spark.createDataFrame([(i, t) for i, t in enumerate(texts)] + [(None, "the dog and the cat")], "doc_id long, text string")
    got = {r.doc_id: r for r in language.identify(ask, model).collect()}
    assert [got[i].lang_pred for i in range(3)] == ["und"] * 3 and all(got[i].rejected and got[i].score == 0 for i in range(3))
    assert got[3].lang_pred in model.langs and [got[4].lang_pred, got[5].lang_pred, got[None].lang_pred] == ["en", "de", "en"]
    assert language.identify(ask.limit(0), model).count() == 0
    assert {r.lang_pred for r in language.identify(ask, language.fit(df.limit(0))).collect()} == {"und"}


def plain_grams(text, dims):
    """Hashed grams of one, two and three characters, one at a time."""
    mask, out = (1 << 64) - 1, collections.Counter()
    squeezed = re.sub(r" +", " ", "".join(c if c.isalpha() else " " for c in f" {text.lower()} "))
    for n in (1, 2, 3):
        for i in range(len(squeezed) - n + 1):
            gram = squeezed[i : i + n]
            if n == 1 and not gram.isalpha():
                continue
            h = 0
            for c in gram:
                h = (h * 0x1F123BB5 + ord(c)) & mask
            out[(((h + n - 1) * 0x9E3779B97F4A7C15 & mask) >> 40) % dims] += 1
    return out


def test_language_is_the_plain_nearest_centroid(spark, sf_dir):
    """Document frequencies, weights, similarities and the best centroid, text by text."""
    docs = queries.table(spark, sf_dir, "documents").select("doc_id", "text", "lang").collect()
    grams = {r.doc_id: plain_grams(r.text, 4096) for r in docs}
    train = [r for r in docs if not out(r.doc_id, 5, 0) and r.lang is not None]
    df = collections.Counter(g for r in train for g in grams[r.doc_id])
    idf = {g: math.log((1 + len(train)) / (1 + df[g])) + 0.1 for g in range(4096)}
    table = queries.table(spark, sf_dir, "documents")
    model = language.fit(table.filter(~language.held_out("doc_id", 5, 0)))
    assert all(abs(model.idf[g] - idf[g]) < 1e-5 for g in range(4096))
    got = {r.doc_id: r for r in queries.op6_language(spark, sf_dir).collect()}
    for r in docs:
        v = {g: math.sqrt(n) * idf[g] for g, n in grams[r.doc_id].items()}
        norm = math.sqrt(sum(x * x for x in v.values())) or 1.0
        sims = [sum(x * c[g] for g, x in v.items()) / norm for c in model.centroids.astype(float)]
        if not any(c.isalpha() for c in r.text):
            assert (got[r.doc_id].lang_pred, got[r.doc_id].score) == ("und", 0.0)
            continue
        best = max(sims)
        assert got[r.doc_id].score == pytest.approx(min(1.0, best), abs=1e-4)
        assert got[r.doc_id].lang_pred in {lang for lang, s in zip(model.langs, sims, strict=True) if s > best - 1e-4}


def test_language_learns_from_repeated_rows_once(spark):
    """Any number of equal rows is one in the sample, and rare languages count as much as common ones."""
    rows = [(1, "the cat and the dog are here", "en")] * 5000 + [(i, f"der Hund und die Katze {'abc'[i % 3]}", "de") for i in range(100, 104)]
    letters = [chr(i) for i in range(0x400, 0x1000) if chr(i).isalpha()]
    rows += [(1000 + i, " ".join(letters[(i * 7 + j) % len(letters)] * 4 for j in range(6)), f"l{i}") for i in range(300)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = language.fit(df, sample=5000)
    assert len(set(model.langs)) == 302 and model.langs.count("en") == 1
    assert language.identify(df.filter("doc_id = 1"), model).filter("lang_pred = 'en'").count() == 5000


def test_gram_counts_do_not_depend_on_the_block():
    texts = ["Ein Haus, ein Hund! " * 50, "x", "", "1 2", "añb çd 𝒳", "", "", "sehr lang " * 120_000, "", "y"]
    together = language.counts(texts, 512)
    for i, t in enumerate(texts):
        alone = language.counts([t], 512)
        assert (together[0][i] == alone[0][0]).all() and together[1][i] == alone[1][0] == sum(c.isalpha() for c in t)


def distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a):
        row, old = [i + 1], row
        for j, y in enumerate(b):
            row.append(min(row[j] + 1, old[j + 1] + 1, old[j] + (x != y)))
    return row[-1]


def test_trie_walk_finds_what_distances_say():
    r = np.random.default_rng(2)
    terms = ["idiot", "moron", "clown", "pathetic", "disgusting", "scum", "loser"]
    trie = toxicity.Trie(terms)
    for _ in range(3000):
        w = list(terms[r.integers(len(terms))])
        for _ in range(r.integers(0, 4)):
            at = r.integers(0, len(w) + 1)
            w[at : at + r.integers(0, 2)] = [chr(97 + r.integers(26))] * int(r.integers(0, 2))
        w = "".join(w)
        want = min(((distance(w, t), t) for t in terms if distance(w, t) <= toxicity.allowed(len(t))), default=None)
        assert trie.near(w) == (want and (want[1], want[0])), w


def test_toxicity_of_held_out_rows(spark, sf_dir):
    labels = dict(queries.table(spark, sf_dir, "labels").select("doc_id", "toxic").collect())
    rows = queries.op8_toxicity(spark, sf_dir).collect()
    assert all(r.held_out == out(r.doc_id, 5, 0) and 0 <= r.score <= 1 and r.predicted == (r.score >= 0.5) for r in rows)
    known = [(r.score, labels[r.doc_id]) for r in rows if r.doc_id in labels]
    assert len(rows) >= len(labels) and np.mean([s for s, y in known if y] or [1]) > np.mean([s for s, y in known if not y])


def test_misspelling_and_quotation(spark):
    words = "alpha bravo charlie delta echo foxtrot golf hotel india juliet kilo lima mike november oscar papa quebec romeo sierra tango".split()
    r = np.random.default_rng(4)
    docs, labels = [], []
    for i in range(600):
        w = r.choice(words, 30).tolist()
        if i % 5 == 0:
            w[3:3], w[20:20] = ["idiot"], ["pathetic"]
        docs.append((i, " ".join(w), "x"))
        labels.append((i, int(i % 5 == 0), 1))
    docs.append((9000, None, "x"))
    labels += [(9000, 1, 1), (None, 1, 1), (8, None, 1)]
    d = spark.createDataFrame(docs, "doc_id long, text string, score string")
    model = toxicity.fit(d, spark.createDataFrame(labels, "doc_id long, toxic int, quality int"))
    assert set(model.terms) == {"idiot", "pathetic"}
    s = model.score
    assert s("alpha idiot bravo") > 0.5 and s("you idi0t and pathetik alpha") > 0.5 and s("alpha bravo") < 0.1 and s(None) == s("") < 0.1
    assert s('He said "idiot" once') < s("what an idiot once") and s("the word idiot is rude") < 0.5
    assert toxicity.toxicity(d, model).count() == 601 and toxicity.toxicity(d.limit(0), model).count() == 0
    assert toxicity.fit(d.limit(0), spark.createDataFrame(labels, "doc_id long, toxic int, quality int")).terms == {}


@functools.cache
def nearest_term(word, terms):
    near = [(distance(word, t), t) for t in terms if abs(len(t) - len(word)) <= 2]
    return min(((d, t) for d, t in near if d <= toxicity.allowed(len(t))), default=None)


def plain_toxicity(model, text):
    """The score by full distances to every term, word by word."""
    lower = (text or "").lower()
    weight = {"plain": 0.0, "fuzzy": 0.0, "quoted": 0.0}
    words = [(m[0], m.start(), m.end()) for m in toxicity.TOKEN.finditer(lower)]
    for i, (w, a, z) in enumerate(words):
        if w in model.terms:
            best = (0, w)
        elif w in model.clean:
            continue
        else:
            best = nearest_term(w, tuple(model.terms))
        if best:
            said = any(x in model.reporting for x, _, _ in words[max(0, i - 6) : i])
            line = lower[max(0, a - 40) : a].rpartition("\n")[2], lower[z : z + 40].partition("\n")[0]
            opened = [j for j, c in enumerate(line[0]) if c in toxicity.OPENING and (j == 0 or not line[0][j - 1].isalnum())]
            closed = [j for j, c in enumerate(line[1]) if c in toxicity.CLOSING and (j + 1 == len(line[1]) or not line[1][j + 1].isalnum())]
            marked = opened and closed and line[0].count('"') % 2 == ('"' in line[0])
            weight["quoted" if said or marked else "fuzzy" if best[0] else "plain"] += model.terms[best[1]]
    hits = weight["plain"] + toxicity.FUZZY * weight["fuzzy"] + toxicity.QUOTED * weight["quoted"]
    return 1 / (1 + math.exp(-(model.coef[0] + model.coef[1] * math.log1p(hits))))


def test_toxicity_is_the_plain_one(spark, sf_dir):
    """Every document's score by terms that occur in them, plain, misspelled and after a cue."""
    docs = queries.table(spark, sf_dir, "documents")
    texts = dict(docs.select("doc_id", "text").collect())
    common = [w for w, _ in collections.Counter(w for t in texts.values() for w in set(toxicity.TOKEN.findall(t.lower())) if len(w) >= 5).most_common(60)]
    model = toxicity.Model({w: 0.5 + i / 10 for i, w in enumerate(common[20:60:6])}, frozenset(common[:20]), toxicity.REPORTING | {common[21]}, (-3.0, 1.0))
    got = {r.doc_id: r.score for r in toxicity.toxicity(docs, model).collect()}
    assert got.keys() == texts.keys() and len({round(s, 6) for s in got.values()}) > 20
    for i, t in texts.items():
        assert got[i] == pytest.approx(plain_toxicity(model, t), abs=1e-9), i


def test_toxicity_odd_texts(spark):
    """Repeated rows, very long texts, ties of terms: each row its own score, the same one for the same text."""
    model = toxicity.Model({"idiot": 1.0, "idiom": 0.5, "pathetic": 1.5})
    texts = ["idiox"] * 300 + ["x " * 500_000 + "idiot", "a" * 1_000_000, "", None, "\0", "IDIOT!"]
    df = spark.createDataFrame([(i // 2, t) for i, t in enumerate(texts)], "doc_id long, text string")
    rows = toxicity.toxicity(df, model).collect()
    assert len(rows) == len(texts) and len({r.score for r in rows if r.doc_id < 150}) == 1
    for t in texts:
        if t is None or len(t) < 100:
            assert model.score(t) == pytest.approx(plain_toxicity(model, t))
    assert model.find("idiox") == (0.5, 1)  # of equal distances the first term
    assert model.score(texts[300]) == model.score("idiot") and model.score("a" * 1_000_000) == model.score("")


def test_cues_of_a_report_are_learned_in_any_language(spark):
    words = "alfa bravo charlie delta eco foxtrot golf hotel india julieta kilo lima mike oscar papa quebec romeo sierra tango uniforme".split()
    r = np.random.default_rng(9)
    docs, labels = [], []
    for i in range(900):
        w = r.choice(words, 24).tolist()
        if i % 3 == 0:
            w[10:10] = ["cretino"]
        elif i % 30 == 1:  # a clean text names the word
            w[10:10] = ["dijo", "cretino"]
        docs.append((i, " ".join(w)))
        labels.append((i, int(i % 3 == 0)))
    model = toxicity.fit(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, toxic int"))
    assert set(model.terms) == {"cretino"} and "dijo" in model.reporting and not set(words) & model.reporting
    assert model.score("alfa dijo cretino bravo") < model.score("alfa bravo cretino")


def brute_nearest(rows, every, k):
    good = [(i, np.array(v, float)) for i, v in rows if i is not None and v and all(x is not None and math.isfinite(x) for x in v) and any(v)]
    for i, q in good:
        if i % every == 0:
            yield i, sorted((-float(np.dot(q, x)), j) for j, x in good if j != i)[:k]


def test_neighbours_recall(spark, sf_dir):
    rows = [(r.vec_id, r.embedding) for r in queries.table(spark, sf_dir, "embeddings").select("vec_id", "embedding").collect()]
    got = collections.defaultdict(list)
    for r in queries.op3_nearest(spark, sf_dir).collect():
        got[r.query_id].append((r["rank"], r.vec_id, r.score))
    hit = total = 0
    vectors = {i: np.array(v, float) for i, v in rows}
    for q, want in brute_nearest(rows, 20, 20):
        mine = sorted(got.pop(q))
        assert [x for x, _, _ in mine] == list(range(1, len(want) + 1))
        assert all(abs(s - vectors[q] @ vectors[i]) < 1e-12 for _, i, s in mine)
        assert [(-s, i) for _, i, s in mine] == sorted((-s, i) for _, i, s in mine)
        hit += len({i for _, i, _ in mine} & {i for _, i in want})
        total += len(want)
    assert not got and hit >= 0.9 * total


def test_neighbours_odd_vectors_and_ties(spark):
    nan, inf = float("nan"), float("inf")
    rows = [(0, [1.0, 0.0]), (20, [0.0, 2.0]), (None, [1.0, 1.0]), (3, None), (4, [0.0, 0.0]), (5, [nan, 1.0]), (6, [inf, 1.0]), (7, [None, 1.0]), (8, [1.0, 0.0, 0.0]), (9, [-1.0, -0.5])]
    rows += [(100 + i, [1.0, 0.5]) for i in range(1, 19)] + [(200 + i, [0.5, 0.25]) for i in range(1, 9)]
    df = spark.createDataFrame([(i, v, 1) for i, v in rows], "vec_id long, embedding array<float>, rank int")
    usable = [(i, v) for i, v in rows if v is None or len(v) == 2]
    for k, block in ((20, 20_000), (3, 4)):
        got = collections.defaultdict(list)
        for r in nearest(df, k=k, block=block, wanted=1.0).orderBy("query_id", "rank").collect():
            got[r.query_id].append((-r.score, r.vec_id))
        assert dict(got) == dict(brute_nearest(usable, 20, k))
    assert nearest(df.limit(0)).count() == 0 and nearest(df.filter("vec_id = 0")).count() == 0


def test_neighbours_in_double_precision_and_of_any_length(spark):
    """Scores are those of the original doubles, beyond single precision's range too; lengths don't mix."""
    r = np.random.default_rng(11)
    for size in (1.0, 1e100, 1e-60):
        rows = [(i, (r.normal(size=6) * size).tolist()) for i in range(120)] + [(1000 + i, (r.normal(size=3) * size).tolist()) for i in range(0, 60, 5)]
        got = collections.defaultdict(list)
        df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
        for x in nearest(df, k=5, wanted=1.0).collect():
            got[x.query_id].append((-x.score, x.vec_id))
        vectors = dict(rows)
        for q, v in rows:
            if q % 20 == 0:
                own = [(i, np.array(x)) for i, x in rows if i != q and len(x) == len(v)]
                want = sorted((-float(np.dot(v, x)), i) for i, x in own)[:5]
                assert sorted(i for _, i in got[q]) == sorted(i for _, i in want)
                assert all(-s == pytest.approx(float(np.dot(vectors[q], vectors[i])), rel=1e-13) for s, i in got[q])


def test_neighbours_recall_over_full_blocks(spark):
    """Several blocks of clustered vectors, groups of over 200 equal ones among them, and crowded blocks split by queries."""
    r = np.random.default_rng(12)
    centres = r.normal(size=(40, 16)) * 3
    x = centres[r.integers(0, 40, 12_000)] + r.normal(size=(12_000, 16))
    x[5000:5300] = x[5000]
    x[7000:7250] = x[7001]
    x = x.astype(np.float32)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>")
    hit = total = 0
    got = collections.defaultdict(set)
    for y in nearest(df, every=100, k=20, sample=3000, block=2500, query_block=40).collect():
        got[y.query_id].add((y.vec_id, y.score))
    for q in range(0, 12_000, 100):
        s = x.astype(float) @ x[q].astype(float)
        s[q] = -np.inf
        edge = np.sort(s)[-20]
        assert len(got[q]) == 20
        hit += sum(v >= edge - 1e-9 for _, v in got[q])  # any of equal ones counts
        total += 20
    assert hit >= 0.9 * total


def test_neighbours_recall_of_queries_unlike_the_other_vectors(spark):
    """The queries lie elsewhere than the clusters of the other vectors: opposite them, or anywhere."""
    r = np.random.default_rng(13)
    n = 6000
    x = (r.normal(size=(50, 32))[r.integers(0, 50, n)] + r.normal(size=(n, 32)) * 0.3).astype(np.float32)
    x[::40] = -x[::40]
    x[20::40] = r.normal(size=(n // 40, 32))
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>")
    got = collections.defaultdict(set)
    for y in nearest(df, every=20, k=20, short=40).collect():
        got[y.query_id].add(y.vec_id)
    s = x[::20].astype(float) @ x.T.astype(float)
    s[np.arange(len(s)), np.arange(0, n, 20)] = -np.inf
    best = np.argsort(-s, axis=1, kind="stable")[:, :20]
    assert sum(len(got[20 * i] & set(b.tolist())) for i, b in enumerate(best)) >= 0.95 * best.size


def test_language_model_odd_texts(spark):
    """Very long texts, one unbroken run, repeated rows: each row its own score."""
    docs = [(i, f"some words of text {i % 5}") for i in range(40)]
    model, vocab = scoring.fit(spark.createDataFrame(docs, "doc_id long, text string"), rounds=2)
    odd = [(1, "of text " * 200_000), (2, "x" * 1_000_000), (3, " " * 1_000_000)] + [(4, "unseen word")] * 200
    rows = scoring.score(spark.createDataFrame(odd, "doc_id long, text string"), model, vocab).collect()
    assert len(rows) == len(odd) and {r.n_tokens for r in rows if r.doc_id == 1} == {400_001}
    assert {(r.n_tokens, r.n_known) for r in rows if r.doc_id == 4} == {(3, 1)} and len({r.score for r in rows if r.doc_id == 4}) == 1
    assert {(r.n_tokens, r.n_known) for r in rows if r.doc_id == 2} == {(2, 1)} and {r.n_tokens for r in rows if r.doc_id == 3} == {1}


def test_language_model(spark, sf_dir):
    texts = dict(queries.table(spark, sf_dir, "documents").select("doc_id", "text").collect())
    split = {i: [*re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t)), ""] for i, t in texts.items()}
    seen = collections.Counter(w for i, ws in split.items() if not out(i, 7, 2) for w in ws)
    n, v = sum(seen.values()), len(seen)
    rows = queries.op4_lm_score(spark, sf_dir).collect()
    assert len(rows) == len(texts)
    for r in rows:
        ws = split[r.doc_id]
        assert (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == (out(r.doc_id, 7, 2), len(ws), sum(w in seen for w in ws), n)
        assert r.base_score == pytest.approx(sum(math.log10((seen[w] + 1) / (n + v + 1)) for w in ws), abs=1e-6 * len(ws))
    held = [r for r in rows if r.held_out]
    assert sum(r.score for r in held) > sum(r.base_score for r in held)


def test_language_model_is_a_distribution(spark):
    r = np.random.default_rng(0)
    docs = [(i, " ".join(r.choice(["a", "b", "cc", "longerword", "é.", "x!"], 20))) for i in range(60)] + [(99, "only once here"), (None, None)]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    model, vocab = scoring.fit(df, lexicon=4, rounds=4)
    counts = {bytes(w): c for w, c in vocab.collect()}
    # the next word after "a b": every known word, and for each shape one that is not known
    inside = {bytes(w) for w in model.lexicon}
    odd = {s: w for w in [b"zz", b"z!", b"zzzzzzzzzz", b"zzzzzzzzz!", "ý".encode(), "ý!".encode(), "ýzzzzzzzzz".encode(), "ýzzzzzzzz!".encode()] for s in [scoring.shape(w)]}
    assert len(odd) == 8
    words = [w for w in counts if w != scoring.END] + list(odd.values())
    ask = spark.createDataFrame([(i, "a b " + w.decode(), None) for i, w in enumerate(words)] + [(-1, "a b", None)], "doc_id long, text string, n long")
    got = {r.doc_id: r for r in scoring.score(ask, model, vocab).collect()}
    first, uni, sums = model.tables()
    ids, before, one, two = model.encode([scoring.words("a b")])

    def log_end(text):  # log10 of the end after the text
        ids, before, one, two = model.encode([scoring.words(text)])
        c = model.classes[ids[-1]]
        return first[one[-1] * 256 + two[-1], c] + uni[ids[-1]] + model.slots[scoring._slot(model.classes[before[-1:]], ids[-1:], model.featured)][0] / math.log(10) - sums[model.classes[before[-1]], c]

    start = got[-1].score - log_end("a b")
    total = 10 ** log_end("a b") + sum(10 ** (got[i].score - log_end("a b " + w.decode()) - start) for i, w in enumerate(words))
    assert total == pytest.approx(1, abs=1e-3) and inside
    assert scoring.score(ask.limit(0), model, vocab).count() == 0
    empty, none = scoring.fit(df.limit(0), rounds=1)
    assert {(x.n_known, x.train_tokens, round(x.base_score, 9)) for x in scoring.score(ask.limit(1), empty, none).collect()} == {(0, 0, 0.0)}


def test_rare_words_have_features_of_their_own(spark):
    """Outside the lexicon too, a word is likelier after the class it was seen after; no two features share a slot."""
    fill = " ".join(f"f{i}" for i in range(40))
    docs = [(i, f"{fill} aa rareone") for i in range(30)] + [(100 + i, f"{fill} bb raretwo") for i in range(30)] + [(200, "aa bb " * 200)]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    model, vocab = scoring.fit(df, lexicon=42)
    assert b"rareone" not in model.lexicon and b"aa" in model.lexicon
    size = len(model.lexicon)
    a, b = (int(model.classes[model.lexicon.index(w)]) for w in (b"aa", b"bb"))
    assert a != b and len(model.slots) == scoring.CLASSES * size and model.featured == size
    rest = {bytes(r.word): r.slots for r in model.rest.collect()}
    assert set(rest[b"rareone"]) == {a} and rest[b"rareone"][a] > 0 and set(rest[b"raretwo"]) == {b}
    ask = spark.createDataFrame([(0, "aa rareone"), (1, "aa raretwo")], "doc_id long, text string")
    got = {r.doc_id: r for r in scoring.score(ask, model, vocab).collect()}
    assert got[0].base_score == pytest.approx(got[1].base_score) and got[0].score > got[1].score + 0.1
    one, two = np.divmod(np.arange(scoring.BUCKETS**2), scoring.BUCKETS)
    assert len(np.unique(scoring._pair(one, two))) == scoring.BUCKETS**2


def test_shapes_agree_in_sql(spark):
    words = ["a", "a!", "ab1", "É", "aé", "é.", "abcdefghi", "abcdefghi?", "слово", "x_", "{", "9", "A"]
    df = spark.createDataFrame([(bytearray(w.encode()),) for w in words], "word binary")
    got = [r[0] for r in df.select(scoring._shape(df.word)).collect()]
    assert got == [scoring.shape(w.encode()) for w in words]


def brute_seats(votes, seats):
    got = [0] * len(votes)
    for _ in range(seats if any(votes) else 0):
        best = max(range(len(votes)), key=lambda i: (votes[i] / (2 * got[i] + 1), -i))
        got[best] += 1
    return got


def test_apportionment_is_by_highest_quotients(spark):
    r = np.random.default_rng(6)
    for n, seats in [(1, 5), (7, 3), (20, 400), (60, 25), (30, 1000), (4, 0)]:
        votes = np.concatenate((r.integers(0, 1000, n - n // 3), r.integers(0, 30000, n // 3))).tolist()
        df = spark.createDataFrame([(i, float(v), seats) for i, v in enumerate(votes)], "k int, v double, s long")
        got = {x.k: x.got for x in apportion(df, [], "v", "s", "got").collect()}
        assert [got[i] for i in range(n)] == brute_seats(votes, seats)


def test_mix_odd_rows_and_reruns(spark):
    rows = [(i, "word " * (i % 9), ["b", "a", None][i % 3], 1) for i in range(300)] + [(None, None, "a", 1), (7, "w " * 20000, "hot", 1), (7, "w " * 20000, "hot", 1), (8, "", "none", 1)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string, size int")
    got = mix(df, block=4, rows_per_shard=40).collect()
    size, taken, target = collections.Counter(), collections.Counter(), {}
    for r in got:
        assert 0 <= r.taken <= 2 * r.size
        size[r.source_size] += r.size
        taken[r.source_size] += r.taken
        target[r.source_size] = r.target
    assert len(got) == len(rows) and sum(target.values()) == pytest.approx(1.5 * sum(size.values()))
    assert all(abs(taken[s] - t) <= 0.03 * t + 16 for s, t in target.items())
    again = mix(df.repartition(3), block=4, rows_per_shard=40).collect()
    assert sorted(map(repr, got)) == sorted(map(repr, again))
    assert mix(df.limit(0)).count() == 0


def test_mix_of_one_repeated_row(spark):
    """All rows equal: their copies are told apart, so that they share shards and tasks, and the texts come out as counted."""
    text = " ".join(f"w{i}" for i in range(40))
    df = spark.createDataFrame([(5, text, "s")] * 3000, "doc_id long, text string, source string")
    got = mix(df, rows_per_shard=100).collect()
    assert len(got) == 3000 and all(0 <= r.taken <= 80 for r in got)
    assert sum(r.taken for r in got) == pytest.approx(1.5 * 40 * 3000, rel=0.01)
    words = [r.text.split(" ") for r in mixed_texts(df, rows_per_shard=100).collect()]
    assert sum(map(len, words)) == sum(r.taken for r in got) and all(f" {' '.join(w)} " in f" {text} " for w in words)
    assert mixed_texts(df.limit(0)).count() == 0


def test_language_model_reads_texts_twice(spark, sf_dir, monkeypatch):
    """Once for the vocabulary and once to store them as numbers; later passes read those."""
    docs = queries.table(spark, sf_dir, "documents")
    rows, read = docs.count(), spark.sparkContext.accumulator(0)

    def counted(batches):
        for b in batches:
            read.add(b.num_rows)
            yield b

    monkeypatch.setattr(queries, "table", lambda *_: docs.mapInArrow(counted, docs.schema))
    assert len(queries.op4_lm_score(spark, sf_dir).collect()) == rows
    assert rows < read.value <= 2 * rows


def test_fit_and_score_is_fit_then_score(spark):
    """The same rows, where marks are null too, and repeated ones."""
    r = np.random.default_rng(5)
    names = [f"w{i}" for i in range(60)] + ["É!", "averylongword", "x."]
    docs = [(i % 70, " ".join(r.choice(names, r.integers(0, 30))), [True, True, False, None][i % 4]) for i in range(120)] + [(None, None, True), (7, None, None), (8, "never seen", False)]
    df = spark.createDataFrame(docs, "doc_id long, text string, learn boolean")
    model, vocab = scoring.fit(df.filter("learn"), lexicon=20, rounds=4)
    plain = lambda d: sorted((str(x.doc_id), x.n_tokens, x.n_known, x.train_tokens, round(x.base_score, 8), round(x.score, 8)) for x in d.collect())
    got = plain(scoring.fit_and_score(df, df.learn, lexicon=20, rounds=4))
    assert got == plain(scoring.score(df, model, vocab)) and len(got) == len(docs)


def test_slots_of_rare_words_pair_by_pair(spark):
    """The rounds over kinds of pairs give each (class before, word) what rounds over all pairs give."""
    r = np.random.default_rng(6)
    names = [f"w{i}" for i in range(200)] + ["É!", "averylongword", "x."]
    texts = [" ".join(names[int(i)] for i in np.minimum(r.pareto(0.6, 40) * 3, len(names) - 1)) for _ in range(80)]
    model, vocab = scoring.fit(spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string"), lexicon=15, rounds=3)
    inside, counts = {w: i for i, w in enumerate(model.lexicon)}, {bytes(w): c for w, c in vocab.collect()}
    pairs, whole = collections.Counter(), np.ones(scoring.SHAPES)
    for t in texts:
        ws = scoring.words(t)
        for before, w in zip([scoring.END, *ws], ws, strict=False):
            if w not in inside:
                pairs[int(model.classes[inside.get(before, len(inside) + scoring.shape(before) if before else 0)]), w] += 1
    for w, c in counts.items():
        whole[scoring.shape(w) if w else 0] += c + 1 if w not in inside else 0
    u = {w: (c + 1) / whole[scoring.shape(w)] for w, c in counts.items() if w not in inside}
    slots, follows = dict.fromkeys(pairs, 0.0), collections.Counter()
    for (b, w), n in pairs.items():
        follows[b, scoring.shape(w)] += n
    for _ in range(3):
        z = collections.defaultdict(lambda: 1.0)
        for (b, w), s in slots.items():
            z[b, scoring.shape(w)] += u[w] * math.expm1(s)
        for (b, w), n in pairs.items():
            key = b, scoring.shape(w)
            slots[b, w] = scoring._step(slots[b, w], n, follows[key] * u[w] * math.exp(slots[b, w]) / z[key])
    rest = {(b, bytes(x.word)): s * math.log(10) for x in model.rest.collect() for b, s in x.slots.items()}
    assert len(pairs) > 100 and rest.keys() == slots.keys() and all(rest[k] == pytest.approx(slots[k], abs=1e-9) for k in slots)


def test_packed_counts_add_up():
    r = np.random.default_rng(7)
    a, b = np.zeros((2, scoring.PARTS * 300), np.int64)
    a[r.integers(0, len(a), 900)] = r.integers(1, 1 << 40, 900)
    b[:700] = 3
    rows = [x for t in (a, b, a * 0) for x in scoring._packed_rows(t)]
    got = scoring._summed_parts([pa.RecordBatch.from_arrays([pa.array(x) for x in zip(*rows, strict=True)], ["part", "n", "v"])], 300)
    assert {p for p, _, _ in rows} == set(got) and len(got) < scoring.PARTS + 1
    assert (np.concatenate([got.get(p, np.zeros(300, np.int64)) for p in range(scoring.PARTS)]) == a + b).all()


def test_codes_are_read_in_bounded_parts(monkeypatch):
    """Parts end with the text that reaches the bound, also where a batch is a slice of another."""
    monkeypatch.setattr(scoring, "BLOCK", 10)
    texts = [np.arange(n, dtype="<i4") + 100 * n for n in (1, 3, 25, 1, 9, 4, 2, 10, 1)]
    b = pa.RecordBatch.from_pydict({"codes": pa.array([t.tobytes() for t in texts], pa.binary())})
    for at in (0, 2, len(texts)):
        parts = list(scoring._read([b.slice(at)]))
        assert [x.as_py() for p, _, _ in parts for x in p.column("codes")] == [t.tobytes() for t in texts[at:]]
        assert all(len(c) == n.sum() and n[:-1].sum() < 10 for _, c, n in parts)
        assert [c.tolist() for _, c, _ in parts] == [np.concatenate([np.frombuffer(x.as_py(), "<i4") for x in p.column("codes")]).tolist() for p, _, _ in parts]
