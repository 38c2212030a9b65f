"""Toxicity: a lexicon trie intersected with Levenshtein automata, and the context of each hit."""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from spectrack.llm.common import lean

TOKEN = re.compile(r"\w+(?:[@$*!'’.-]\w+)*")

# fixed word list: English words that report or name a word instead of using it; labelled texts add those of any language
REPORTING = frozenset("said says called calling word words term terms quote quoted quotes wrote writes slur insult insults named spelled means meaning definition".split())
# what a misspelled and a quoted hit count for, against one used plainly
FUZZY, QUOTED = 0.8, 0.2
OPENING, CLOSING = "\"“„«‘'", "\"”“»’'"


FAR = 3  # one edit more than any term allows
ALLOWED = "\0"  # no character of a word: a key of its own among a node's


def allowed(length: int) -> int:
    """Edits allowed for a term of this length."""
    return 0 if length < 5 else 1 if length < 9 else 2


class Automaton:
    """Levenshtein automata of words. A state is the row of distances to the word's prefixes, cut off beyond what any term
    allows; where it leads depends on it and on the places at which the word has the character, so words share their steps,
    which are remembered up to a bound."""

    def __init__(self, most: int = 200_000):
        self.steps: dict[tuple[tuple[int, ...], int], tuple[tuple[int, ...], int]] = {}
        self.most = most

    def step(self, state: tuple[int, ...], places: int) -> tuple[tuple[int, ...], int]:
        """The next state, and the least distance in it."""
        got = self.steps.get((state, places))
        if got is None:
            now = [min(state[0] + 1, FAR)]
            for j in range(len(state) - 1):
                now.append(min(now[j] + 1, state[j + 1] + 1, state[j] + (not places >> j & 1), FAR))
            got = tuple(now), min(now)
            if len(self.steps) < self.most:
                self.steps[state, places] = got
        return got


class Trie:
    """Terms as nested dicts; '' marks an end and holds the term, ALLOWED the most edits of a term below."""

    def __init__(self, terms):
        self.root: dict = {}
        self.automaton = Automaton()
        self.parts: dict[int, set[str]] = {}
        self.ends: dict[int, set[str]] = {}
        self.middles: set[str] = set()
        for t in terms:
            node = self.root
            for c in t:
                node = node.setdefault(c, {ALLOWED: 0})
                node[ALLOWED] = max(node[ALLOWED], allowed(len(t)))
            node[""] = t
            # k edits leave one of k+1 parts of the term untouched: only words that have one are worth a walk
            k = allowed(len(t)) + 1
            cuts = [len(t) * i // k for i in range(k + 1)]
            self.parts.setdefault(cuts[1], set()).add(t[: cuts[1]])
            self.ends.setdefault(len(t) - cuts[-2], set()).add(t[cuts[-2] :])
            self.middles.update(t[cuts[i] : cuts[i + 1]] for i in range(1, k - 1))
        self.longest = max(map(len, terms), default=0)
        self.middle = re.compile("|".join(map(re.escape, sorted(self.middles)))) if self.middles else None

    def near(self, word: str) -> tuple[str, int] | None:
        """The term of least distance within its allowance, and the distance."""
        if not (any(word[:n] in s for n, s in self.parts.items()) or any(word[-n:] in s for n, s in self.ends.items()) or self.middle and self.middle.search(word)):
            return None
        if len(word) > self.longest + 2:
            return None
        return self.walk(word)

    def walk(self, word: str) -> tuple[str, int] | None:
        """Depth-first over the product of the trie and the word's Levenshtein automaton. A branch ends where no term
        below allows the least distance in the state."""
        best: tuple[int, str] | None = None
        places: dict[str, int] = {}
        for j, c in enumerate(word):
            places[c] = places.get(c, 0) | 1 << j
        step = self.automaton.step
        stack = [(self.root, tuple(min(j, FAR) for j in range(len(word) + 1)))]
        while stack:
            node, state = stack.pop()
            for c, child in node.items():
                if c == "":
                    d = state[-1]
                    if d <= allowed(len(child)) and (best is None or (d, child) < best):
                        best = (d, child)
                elif c != ALLOWED:
                    now, least = step(state, places.get(c, 0))
                    if least <= child[ALLOWED]:
                        stack.append((child, now))
        return (best[1], best[0]) if best else None


@dataclass
class Model:
    """Weights of the terms, words near a term that clean texts use, and the score's coefficients."""

    terms: dict[str, float] = field(default_factory=dict)
    clean: frozenset[str] = frozenset()
    reporting: frozenset[str] = REPORTING
    coef: tuple[float, float] = (-4.0, 6.0)
    seen: dict = field(default_factory=dict, repr=False)
    trie: Trie | None = field(default=None, repr=False)

    def __getstate__(self):
        return {"terms": self.terms, "clean": self.clean, "reporting": self.reporting, "coef": self.coef}

    def __setstate__(self, state):
        self.__dict__.update(state, seen={}, trie=None)

    def find(self, word: str) -> tuple[float, int] | None:
        """(weight, edits) of the term that the word stands for; what was found is remembered, up to a bound."""
        try:
            return self.seen[word]
        except KeyError:
            pass
        if self.trie is None:
            self.trie = Trie(list(self.terms))
        if word in self.terms:
            hit = (self.terms[word], 0)
        elif word in self.clean or not (near := self.trie.near(word)):
            hit = None
        else:
            hit = (self.terms[near[0]], near[1])
        if len(self.seen) < 400_000:
            self.seen[word] = hit
        return hit

    def features(self, text: str | None) -> tuple[float, float, float]:
        """Weight of the hits used as abuse, of misspelled ones, and of quoted ones."""
        if not text:
            return 0.0, 0.0, 0.0
        lower = text.lower()
        find = self.find
        hits = {w for w in set(TOKEN.findall(lower)) if find(w)}
        if not hits:
            return 0.0, 0.0, 0.0
        plain = fuzzy = quoted = 0.0
        before: list[str] = []
        for m in TOKEN.finditer(lower):
            w = m[0]
            if w in hits:
                weight, edits = find(w)
                if self._quoted(lower, m.start(), m.end(), before):
                    quoted += weight
                elif edits:
                    fuzzy += weight
                else:
                    plain += weight
            before.append(w)
            if len(before) > 6:
                del before[0]
        return plain, fuzzy, quoted

    def _quoted(self, text: str, start: int, end: int, before: list[str]) -> bool:
        """Quotation marks around it within 40 characters on one line, or a reporting word among the six before."""
        if any(w in self.reporting for w in before):
            return True
        left, right = text[max(0, start - 40) : start], text[end : end + 40]
        left, right = left[left.rfind("\n") + 1 :], right.partition("\n")[0]
        marks = [i for i, c in enumerate(left) if c in OPENING and (i == 0 or not left[i - 1].isalnum())]
        return bool(marks) and any(c in CLOSING and (i + 1 == len(right) or not right[i + 1].isalnum()) for i, c in enumerate(right)) and sum(left.count(c) for c in '"') % 2 == ('"' in left)

    def score(self, text: str | None) -> float:
        plain, fuzzy, quoted = self.features(text)
        z = self.coef[0] + self.coef[1] * math.log1p(plain + FUZZY * fuzzy + QUOTED * quoted)
        return 1 / (1 + math.exp(-z)) if z > -700 else 0.0


def _shape(text: str) -> int:
    """Least hash of the text's five-word shingles: copies and most near copies share it."""
    words = TOKEN.findall(text.lower())
    if len(words) < 5:
        return xxhash.xxh64_intdigest(" ".join(words)) >> 1
    return min(xxhash.xxh64_intdigest(" ".join(words[i : i + 5])) for i in range(len(words) - 4)) >> 1


def fit(docs: DataFrame, labels: DataFrame, sample: int = 30_000, most_terms: int = 5000, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic") -> Model:
    """Learn terms and coefficients from about `sample` labelled rows (the bound of the classifier's
    sample, chosen by a hash of the id), near copies taken once.

    A term is a word whose texts are toxic far more often than chance allows given the number of words
    tried, and which stands beside at least eight kinds of neighbours (63 hashed kinds) in toxic texts: words of a
    passage that was copied a lot do not. Of those the `most_terms` that tell most are kept (the bound of the lexicon; equal
    ones by the word). What the driver gets is bounded by the sample and its vocabulary."""
    marked = labels.filter(F.col(label_col).isNotNull() & F.col(id_col).isNotNull()).groupBy(id_col).agg(F.max(label_col).alias("toxic"))
    rate = sample / max(1, marked.count())
    marked = marked.filter(F.shiftrightunsigned(F.xxhash64(id_col, F.lit(3)), 11) / F.lit(float(1 << 53)) < rate)
    rows = docs.select(id_col, F.col(text_col).alias("text")).join(F.broadcast(marked), id_col).filter("text IS NOT NULL").select("text", F.col("toxic").cast("int").alias("toxic"))

    def shapes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array([_shape(t.as_py()) for t in b.column("text")], pa.int64())], ["text", "toxic", "shape"])

    once = rows.mapInArrow(shapes, "text string, toxic int, shape long").groupBy("shape").agg(F.min(F.struct("text", "toxic")).alias("r")).select("r.*").persist()

    def words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            seen, beside = [Counter(), Counter()], Counter()
            for text, toxic in zip(b.column("text").to_pylist(), b.column("toxic").to_pylist(), strict=True):
                tokens = TOKEN.findall(text.lower())
                seen[toxic > 0].update(set(tokens))
                if toxic > 0:
                    for before, w, after in zip(["", *tokens], tokens, [*tokens[1:], ""], strict=False):
                        beside[w] |= 1 << xxhash.xxh32_intdigest(f"{before} {after}") % 63
            both = list(seen[0] | seen[1])
            columns = {"word": pa.array(both, pa.string()), "clean": [seen[0][w] for w in both], "toxic": [seen[1][w] for w in both], "beside": [beside[w] for w in both]}
            yield pa.RecordBatch.from_pydict({k: v if k == "word" else pa.array(v, pa.int64()) for k, v in columns.items()})

    n = {bool(r["toxic"]): r["n"] for r in once.groupBy(F.expr("toxic > 0").alias("toxic")).agg(F.count(F.lit(1)).alias("n")).collect()}
    bad, good = n.get(True, 0), n.get(False, 0)
    if not bad or not good:
        once.unpersist()
        return Model()
    table = once.mapInArrow(words, "word string, clean long, toxic long, beside long").groupBy("word")
    table = table.agg(F.sum("clean").alias("clean"), F.sum("toxic").alias("toxic"), F.bit_or("beside").alias("beside"))
    table = table.filter(F.length("word") >= 3).persist()
    share = bad / (bad + good)
    total = F.col("clean") + F.col("toxic")
    gain = F.col("toxic") * F.log((F.col("toxic") + 0.01) / (total * share)) + F.col("clean") * F.log((F.col("clean") + 0.01) / (total * (1 - share)))
    least = math.log(max(1, table.count()) / 0.01)
    odds = F.log((F.col("toxic") + 0.5) / bad) - F.log((F.col("clean") + 0.5) / good)
    varied = F.bit_count("beside") >= 8
    chosen = table.filter((gain > least) & (odds > 2.0) & varied).select("word", odds.alias("odds"), gain.alias("gain")).orderBy(F.desc("gain"), "word").limit(most_terms).collect()
    model = Model({r["word"]: float(min(r["odds"], 8.0)) / 4 for r in chosen})

    def neighbours(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            near = [w for w in b.column("word").to_pylist() if w not in model.terms and model.find(w)]
            yield pa.RecordBatch.from_pydict({"word": pa.array(near, pa.string())})

    # words of the sample that are near a term: fewer than its vocabulary
    def cues(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = [Counter(), Counter()]
        for b in batches:
            for text, toxic in zip(b.column("text").to_pylist(), b.column("toxic").to_pylist(), strict=True):
                tokens = TOKEN.findall(text.lower())
                near = {w for i, t in enumerate(tokens) if t in model.terms for w in tokens[max(0, i - 6) : i]}
                if near:
                    seen[toxic > 0].update(near | {""})
        both = list(seen[0] | seen[1])
        yield pa.RecordBatch.from_pydict({"word": pa.array(both, pa.string()), "clean": pa.array([seen[0][w] for w in both], pa.int64()), "toxic": pa.array([seen[1][w] for w in both], pa.int64())})

    # words among the six before a term; the empty one stands for each text that has any
    before = once.mapInArrow(cues, "word string, clean long, toxic long").groupBy("word").agg(F.sum("clean").alias("clean"), F.sum("toxic").alias("toxic"))
    reporting = REPORTING | _learned_cues({r["word"]: (r["clean"], r["toxic"]) for r in before.filter("clean >= 8 OR word = ''").collect()}, model.terms)
    benign = table.filter("clean > 0").select("word").mapInArrow(neighbours, "word string").collect()
    model = Model(model.terms, frozenset(r["word"] for r in benign), reporting)

    def describe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = np.array([model.features(t) for t in b.column("text").to_pylist()], float).reshape(-1, 3)
            yield pa.RecordBatch.from_pydict({"a": x[:, 0], "b": x[:, 1], "c": x[:, 2], "toxic": b.column("toxic")})

    seen = once.mapInArrow(describe, "a double, b double, c double, toxic int").toPandas()
    once.unpersist()
    table.unpersist()
    x = np.log1p(seen[["a", "b", "c"]].to_numpy() @ np.array([1.0, FUZZY, QUOTED]))[:, None]
    return Model(model.terms, model.clean, reporting, _logistic(x, (seen["toxic"] > 0).to_numpy(float), np.array(Model.coef)))


def _learned_cues(before: dict[str, tuple[int, int]], terms) -> frozenset[str]:
    """Words that stand before a term in clean texts far more often than in toxic ones, beyond chance given their number: what
    marks a report in the language of those texts. Needs clean texts that have terms at all."""
    good, bad = before.pop("", (0, 0))
    if good < 8 or not bad:
        return frozenset()
    share, least, out = good / (good + bad), math.log(max(1, len(before)) / 0.01), set()
    for word, (clean, toxic) in before.items():
        total = clean + toxic
        gain = clean * math.log((clean + 0.01) / (total * share)) + toxic * math.log((toxic + 0.01) / (total * (1 - share)))
        odds = math.log((clean + 0.5) / good) - math.log((toxic + 0.5) / bad)
        if gain > least and odds > 2.0 and word not in terms:
            out.add(word)
    return frozenset(out)


def _logistic(x: np.ndarray, y: np.ndarray, prior: np.ndarray, pull: float = 2.0) -> tuple[float, ...]:
    """Newton steps on the likelihood with a Gaussian pull to the prior, which decides where labels say nothing;
    a hit never lowers a score."""
    order = np.lexsort((y, *x.T))  # the same sums whatever order the rows came in
    x, y = np.column_stack((np.ones(len(x)), x))[order], y[order]
    w = prior.astype(float)
    for _ in range(40):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        h = (x * (p * (1 - p))[:, None]).T @ x + pull * np.eye(x.shape[1])
        step = np.linalg.solve(h, x.T @ (y - p) - pull * (w - prior))
        w += np.clip(step, -1, 1)
    return (float(w[0]), *(float(max(0.0, v)) for v in w[1:]))


def toxicity(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, score (0 to 1), predicted (score >= 0.5) for every row, from its text alone.

    Null and empty texts get the score of a text without hits. Further columns are ignored."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in lean(batches):
            score = np.array([model.score(t.as_py()) for t in b.column("text")], float)
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(score), pa.array((score >= 0.5).astype(np.int32))], ["doc_id", "score", "predicted"])

    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    schema = T.StructType([rows.schema["doc_id"], T.StructField("score", T.DoubleType()), T.StructField("predicted", T.IntegerType())])
    return rows.mapInArrow(run, schema)
