"""Language-model scores from a hashed maximum-entropy model with a class-factored softmax.

P(word | two words before) = P(class | before) * P(word | class, before).

The first factor sums features of the word before (n-gram), of the one before that (skip), both by bucket, and of
the pair of buckets. The second one reweights a class's unigram by a feature of each word and class of the word
before. Words outside the lexicon belong to classes of word shapes, in which they have an add-one
unigram over the whole vocabulary; their features of the second factor are a distributed table that grows
with the types. All sums over the corpus are exact counts of all training texts; the gradient rounds run over
those counts, spread over the executors.

Texts are split twice: for the vocabulary, and to be stored as numbers, which all later passes read. Counts of
a bounded number of keys travel as packed arrays, a row for a task and part of the keys."""

from __future__ import annotations

import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spectrack.llm.common import discard, lean, staged

END = b""  # no word is empty
SHAPES = 8
BUCKETS, OWN = 256, 180  # buckets of a word as context; this many words have one alone
CLASSES = 64
PAIRS = BUCKETS * BUCKETS  # features of both words before
PULL = 0.5  # weight of the prior
TASKS = 8  # of a gradient round of the first factor, whose counts have a fixed size
PARTS = 64  # of the keys of a packed count; contexts and classes before are dealt by them
BLOCK = 300_000  # words held at a time, beside those of one text
_LOG10 = float(np.log(10.0))


def words(text: str | bytes | None) -> list[bytes]:
    """Lower-cased (A-Z only) words between ASCII white space, then the end."""
    out = (text.encode("utf-8") if isinstance(text, str) else text or b"").lower().split()
    out.append(END)
    return out


def shape(word: bytes) -> int:
    return (not word.isascii()) * 4 + (len(word) > 8) * 2 + (not word[-1:].isalnum() and word[-1:] < b"\x80")


class _Codes(dict):
    """word -> id * BUCKETS + bucket; ids from `size` on are the shapes. Unlisted words are not kept."""

    def __init__(self, lexicon: list[bytes]):
        super().__init__((w, i * BUCKETS + self._bucket(w, i)) for i, w in enumerate(lexicon))
        self.size = len(lexicon)

    @staticmethod
    def _bucket(word: bytes, i: int) -> int:
        return i if i < OWN else OWN + zlib.crc32(word[-3:]) % (BUCKETS - OWN)

    def __missing__(self, word: bytes) -> int:
        return (self.size + shape(word)) * BUCKETS + self._bucket(word, OWN)


@dataclass
class Model:
    lexicon: list[bytes]
    counts: np.ndarray  # of the lexicon's words
    tokens: int
    types: int
    classes: np.ndarray | None = None  # of the lexicon's words and of the shapes
    bias: np.ndarray | None = None
    one: np.ndarray | None = None
    two: np.ndarray | None = None
    both: np.ndarray | None = None
    slots: np.ndarray | None = None
    featured: int = 0  # words of a row of slots: all of the lexicon
    tails: np.ndarray | None = None  # class before x shape: log10 of what divides count + 1 of a word outside the lexicon
    rest: DataFrame | None = field(default=None, repr=False)  # word, c, slots by class before: the words outside the lexicon
    made: dict = field(default_factory=dict, repr=False)

    def __getstate__(self):
        return {**self.__dict__, "made": {}, "rest": None}

    @property
    def codes(self) -> _Codes:
        if "codes" not in self.made:
            self.made["codes"] = _Codes(self.lexicon)
        return self.made["codes"]

    def encode(self, texts: list[list[bytes]]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Ids, the ids before, and the buckets of the one and the two before. Every text starts after ends."""
        return _contexts(self.code(texts), np.array([len(t) for t in texts], np.int64))

    def code(self, texts: list[list[bytes]]) -> np.ndarray:
        return np.fromiter(map(self.codes.__getitem__, chain.from_iterable(texts)), np.int64, sum(map(len, texts)))

    def class_logits(self, one: np.ndarray, two: np.ndarray) -> np.ndarray:
        return self.bias + self.one[one] + self.two[two] + self.both[_pair(one, two)]

    def unigram(self) -> np.ndarray:
        """Each lexicon word's share of its class."""
        own = self.classes[: len(self.lexicon)]
        return self.counts / np.bincount(own, self.counts, CLASSES)[own]

    def tables(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """log10 P(class | contexts), log10 unigram within the class, log10 of the second factor's sums."""
        if "tables" not in self.made:
            first = np.empty((BUCKETS * BUCKETS, CLASSES), np.float32)
            for a in range(BUCKETS):
                z = self.class_logits(np.full(BUCKETS, a), np.arange(BUCKETS))
                z = z - z.max(axis=1, keepdims=True)
                first[a * BUCKETS : (a + 1) * BUCKETS] = (z - np.log(np.exp(z).sum(axis=1, keepdims=True))) / _LOG10
            u, own, ids = self.unigram(), self.classes[: len(self.lexicon)], np.arange(len(self.lexicon))
            sums = np.stack([np.bincount(own, u * np.exp(self.slots[_slot(np.full(len(ids), c), ids, self.featured)]), CLASSES) for c in range(CLASSES)])
            self.made["tables"] = first, np.log10(u), np.log10(np.maximum(sums, 1e-300))
        return self.made["tables"]


def _contexts(code: np.ndarray, length: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Ids, the ids before, and the buckets of the one and the two before, of texts of these lengths (1 at least)."""
    ids, bucket = code >> 8, code & 255
    at = np.cumsum(length) - length
    before, one, two = np.zeros_like(ids), np.zeros_like(ids), np.zeros_like(ids)
    before[1:], one[1:] = ids[:-1], bucket[:-1]
    before[at], one[at] = 0, 0
    two[1:] = one[:-1]
    two[at] = 0
    return ids, before, one, two


def _pair(one: np.ndarray, two: np.ndarray) -> np.ndarray:
    return one * BUCKETS + two


def _slot(before: np.ndarray, ids: np.ndarray, featured: int) -> np.ndarray:
    """Slot of each (class before, word of the lexicon)."""
    return before * featured + ids


def vocabulary(docs: DataFrame, id_col: str, text_col: str, flush: int = 300_000) -> DataFrame:
    """(word, c) of all texts; partial counts are made in the workers and merged by one shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def out() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(list(seen), pa.binary()), pa.array(list(seen.values()), pa.int64())], ["word", "n"])

        seen: Counter[bytes] = Counter()
        for b in batches:
            for t in b.column("text").cast(pa.binary()):
                seen.update(words(t.as_py()))
                if len(seen) > flush:
                    yield out()
                    seen.clear()
        yield out()

    return staged(docs.select(F.col(text_col).alias("text")).mapInArrow(run, "word binary, n long").groupBy("word").agg(F.sum("n").alias("c")), "vocabulary")


def _coded(docs: DataFrame, model: Model, id_col: str, text_col: str, learn: Column | None = None) -> DataFrame:
    """(rid, doc_id, learn, codes, rare) of every row: the words of its text as codes of four bytes, and those outside the
    lexicon as they are, between spaces. Rows are told apart by a row number. `learn` marks the rows to learn from."""
    edge = len(model.lexicon) * BUCKETS
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for b in lean(batches):
            at, text = 0, b.column("text").cast(pa.binary())
            while at < b.num_rows:
                part, n = [], 0
                while at + len(part) < b.num_rows and n < BLOCK:
                    part.append(words(text[at + len(part)].as_py()))
                    n += len(part[-1])
                code = m.code(part)
                edges = np.concatenate(([0], np.cumsum([len(t) for t in part])))
                out = np.flatnonzero(code >= edge)
                cuts = np.searchsorted(out, edges).tolist()
                flat = list(chain.from_iterable(part))
                unlisted = [flat[i] for i in out.tolist()]
                rare = [b" ".join(unlisted[i:j]) if j > i else None for i, j in zip(cuts, cuts[1:], strict=False)]
                # the codes of a part are one buffer, cut at the texts' edges
                codes = pa.BinaryArray.from_buffers(pa.binary(), len(part), [None, pa.py_buffer((edges * 4).astype(np.int32)), pa.py_buffer(code.astype("<i4"))])
                kept = b.slice(at, len(part))
                yield pa.RecordBatch.from_arrays([kept.column("rid"), kept.column("doc_id"), kept.column("learn"), codes, pa.array(rare, pa.binary())], ["rid", "doc_id", "learn", "codes", "rare"])
                at += len(part)

    # a mark that is null is no mark
    rows = docs.select(
        F.monotonically_increasing_id().alias("rid"),
        F.col(id_col).alias("doc_id"),
        F.lit(True).alias("learn") if learn is None else F.coalesce(learn, F.lit(False)).alias("learn"),
        F.col(text_col).alias("text"),
    )
    kind = rows.schema["doc_id"].dataType.simpleString()
    return staged(rows.mapInArrow(run, f"rid long, doc_id {kind}, learn boolean, codes binary, rare binary"), "coded", "zstd")


def _read(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """Rows of a coded table, a bounded number of words at a time, their codes and the texts' lengths."""
    for b in lean(batches):
        at, codes = 0, b.column("codes").cast(pa.binary())
        edges = np.frombuffer(codes.buffers()[1], np.int32, len(codes) + 1, codes.offset * 4).astype(np.int64) // 4 if len(codes) else ()
        while at < b.num_rows:
            upto = min(b.num_rows, int(np.searchsorted(edges, edges[at] + BLOCK)))
            yield b.slice(at, upto - at), np.frombuffer(codes.buffers()[2], "<i4", edges[upto] - edges[at], edges[at] * 4).astype(np.int64), np.diff(edges[at : upto + 1])
            at = upto


def _unlisted(rare: pa.Array) -> list[bytes]:
    """The words of a column `rare`, in order."""
    return b" ".join(rare.drop_null().to_pylist()).split()


def _packed(part: int, key: np.ndarray, n: np.ndarray) -> tuple[int, int, bytes]:
    """(part, how many, bytes) of ascending keys and their counts: gaps and counts by planes of bytes, compressed."""
    both = np.stack((np.diff(key, prepend=0), n)).astype("<i8")
    return part, len(key), pa.compress(both.view(np.uint8).reshape(2, len(key), 8).transpose(0, 2, 1).tobytes(), codec="zstd", asbytes=True)


def _unpacked(n: int, v: pa.Scalar) -> tuple[np.ndarray, np.ndarray]:
    raw = pa.decompress(v.as_buffer(), n * 16, codec="zstd")
    gap, count = np.frombuffer(raw, np.uint8).reshape(2, 8, n).transpose(0, 2, 1).copy().view("<i8").reshape(2, n)
    return np.cumsum(gap), count


def _packed_rows(total: np.ndarray) -> Iterator[tuple[int, int, bytes]]:
    """Counts by key, packed: the parts that have any."""
    for part, t in enumerate(total.reshape(PARTS, -1)):
        key = np.flatnonzero(t)
        if len(key):
            yield _packed(part, key, t[key])


def _summed_parts(batches: Iterator[pa.RecordBatch], width: int) -> dict[int, np.ndarray]:
    """Rows (part, n, v) of packed counts, added up by part."""
    total: dict[int, np.ndarray] = {}
    for b in batches:
        for part, n, v in zip(b.column("part").to_pylist(), b.column("n").to_pylist(), b.column("v"), strict=True):
            key, count = _unpacked(n, v)
            if part not in total:
                total[part] = np.zeros(width, np.int64)
            total[part][key] += count
    return total


def _tallied(coded: DataFrame, sizes: list[int], keys, flush: int = 100_000) -> DataFrame:
    """(kind, part, word, n, v): how often each key occurs. keys(codes, lengths, rare words) gives an array of keys
    a kind, each below its bound in sizes, and (word, key) pairs of a last kind. The first are dense counters of a task, packed:
    v holds n keys of the part. The pairs are partial counts: n times the word with the key `part`."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = [np.zeros(n, np.int64) for n in sizes]
        pairs: Counter[tuple[bytes, int]] = Counter()

        def row(kind: int, part: list, word: pa.Array, n: list, v: pa.Array) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(np.full(len(part), kind, np.int32)), pa.array(part, pa.int64()), word, pa.array(n, pa.int64()), v], ["kind", "part", "word", "n", "v"])

        def spill() -> pa.RecordBatch:
            out = row(len(sizes), [k for _, k in pairs], pa.array([w for w, _ in pairs], pa.binary()), list(pairs.values()), pa.nulls(len(pairs), pa.binary()))
            pairs.clear()
            return out

        for b, code, length in _read(batches):
            *dense, more = keys(code, length, b.column("rare"))
            for t, k in zip(total, dense, strict=True):
                np.add.at(t, k, 1)
            pairs.update(more)
            if len(pairs) > flush:
                yield spill()
        yield spill()
        for kind, t in enumerate(total):
            for part, n, v in _packed_rows(t):
                yield row(kind, [part], pa.nulls(1, pa.binary()), [n], pa.array([v], pa.binary()))

    return coded.select("codes", "rare").mapInArrow(run, "kind int, part long, word binary, n long, v binary")


def _induce(model: Model, cells: pa.Table, contexts: int) -> np.ndarray:
    """Classes of the lexicon's words by what stands before them: spherical k-means on square roots of shares."""
    size = len(model.lexicon)
    x = np.zeros((size, contexts), np.float32)
    by_part = x.reshape(PARTS, -1)
    for part, n, v in zip(cells["part"].to_pylist(), cells["n"].to_pylist(), cells["v"], strict=True):
        key, count = _unpacked(n, v)
        by_part[part, key] = count
    total = x.sum(axis=1, keepdims=True) + np.float32(0.02)
    x += (0.02 * x.sum(axis=0) / max(1, x.sum())).astype(np.float32)
    x /= total
    np.sqrt(x, out=x)
    x /= np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-9)
    k = CLASSES - SHAPES - 1
    seeds = np.unique(np.linspace(1, max(1, size - 1), k).astype(int) ** 2 // max(1, size - 1)) % size
    c = x[np.unique(np.concatenate((seeds, np.arange(1, min(size, k)))))[:k]] if size > 1 else x
    weight = np.sqrt(model.counts).astype(np.float32)
    nearest = lambda: np.concatenate([(x[at : at + 16_384] @ c.T).argmax(axis=1) for at in range(0, size, 16_384)])
    for _ in range(10):
        own = nearest()
        sums = np.zeros_like(c)
        for j in range(len(c)):
            sums[j] = weight[own == j] @ x[own == j]
        norm = np.linalg.norm(sums, axis=1, keepdims=True)
        c = np.where(norm > 0, sums / np.maximum(norm, 1e-9), c)
    classes = np.concatenate((nearest() + 1, CLASSES - SHAPES + np.arange(SHAPES)))
    classes[0] = 0  # the end is a class of its own
    return classes


def _summed(parts: DataFrame, n: int) -> np.ndarray:
    """The sum of the arrays in parts(part, v), a row a task. An executor adds them up, since together they are
    TASKS times what the driver needs; their number and size are fixed."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = sorted(((b.column("part")[i].as_py(), b.column("v")[i].as_buffer()) for b in batches for i in range(b.num_rows)), key=lambda r: r[0])
        total = np.zeros(n)
        for _, v in rows:
            total += np.frombuffer(v, np.float64)
        yield pa.RecordBatch.from_pydict({"v": pa.array([total.tobytes()], pa.binary())})

    got = parts.repartition(1).mapInArrow(run, "v binary").toArrow()
    return np.frombuffer(got["v"][0].as_buffer(), np.float64) if got.num_rows else np.zeros(n)


def fit(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lexicon: int = 131_072, rounds: int = 12) -> tuple[Model, DataFrame]:
    """Learn from all rows of docs: (model, vocabulary). `lexicon` bounds what the driver and each worker hold."""
    model, vocab = _listed(docs, id_col, text_col, lexicon)
    coded = _coded(docs, model, id_col, text_col)
    _learn(model, vocab, coded, rounds)
    discard(coded)
    return model, vocab


def fit_and_score(docs: DataFrame, learn: Column, id_col: str = "doc_id", text_col: str = "text", lexicon: int = 131_072, rounds: int = 12) -> DataFrame:
    """score() of all rows by fit() of those that `learn` marks; each text is turned into numbers once."""
    model, vocab = _listed(docs.filter(learn), id_col, text_col, lexicon)
    coded = _coded(docs, model, id_col, text_col, learn)
    _learn(model, vocab, coded.filter("learn"), rounds)
    discard(vocab)
    return _scored(coded, model)


def _listed(docs: DataFrame, id_col: str, text_col: str, lexicon: int) -> tuple[Model, DataFrame]:
    """A model that knows the words of docs, and nothing of their order; (word, c) of all of them."""
    vocab = vocabulary(docs, id_col, text_col)
    tokens, types = vocab.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count(F.lit(1))).first()
    top = vocab.filter(F.octet_length("word") > 0).orderBy(F.desc("c"), "word").limit(lexicon).toArrow()
    ends = vocab.filter(F.octet_length("word") == 0).collect()
    model = Model([END, *top["word"].to_pylist()], np.array([ends[0]["c"] if ends else 1, *top["c"].to_pylist()], float), tokens, types)
    model.featured = len(model.lexicon)
    return model, vocab


def _learn(model: Model, vocab: DataFrame, coded: DataFrame, rounds: int) -> None:
    spark, size, contexts, tokens = vocab.sparkSession, len(model.lexicon), 64, model.tokens

    def beside(code: np.ndarray, length: np.ndarray, rare: pa.Array) -> list[np.ndarray]:
        ids, before, _, _ = _contexts(code, length)
        known = ids < size
        return [ids[known] * contexts + np.minimum(before[known], contexts - 1), ()]

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, t in _summed_parts(batches, size * contexts // PARTS).items():
            key = np.flatnonzero(t)
            yield pa.RecordBatch.from_arrays([pa.array([x]) for x in _packed(part, key, t[key])], ["part", "n", "v"])

    cells = _tallied(coded, [size * contexts], beside).filter("kind = 0").select("part", "n", "v").repartition(PARTS, "part").mapInArrow(add, "part long, n long, v binary").toArrow()
    model.classes = _induce(model, cells, contexts)
    del cells
    pa.default_memory_pool().release_unused()

    grown = spark.sparkContext.broadcast(model.classes)

    def contexts_of(code: np.ndarray, length: np.ndarray, rare: pa.Array) -> list[np.ndarray]:
        classes = grown.value
        ids, before, one, two = _contexts(code, length)
        known, behind = ids < size, classes[before]
        return [(one * BUCKETS + two) * CLASSES + classes[ids], behind[known] * size + ids[known], zip(_unlisted(rare), behind[~known].tolist(), strict=True)]

    # the parts of the first kind are ranges of contexts, those of the second are the classes before
    tallies = staged(_tallied(coded, [BUCKETS * BUCKETS * CLASSES, CLASSES * size], contexts_of), "tallies")
    grown.destroy()
    first, second = (tallies.filter(F.col("kind") == k).select("part", "n", "v").repartition(PARTS, "part") for k in (0, 1))

    mass = np.bincount(model.classes[:size], model.counts, CLASSES)
    mass[-SHAPES:] = max(1.0, (tokens - mass.sum()) / SHAPES)
    # a class without words gets no probability
    model.bias = np.where(mass > 0, np.log(np.maximum(mass, 1e-9)), -1e4)
    model.one, model.two, model.both = np.zeros((BUCKETS, CLASSES)), np.zeros((BUCKETS, CLASSES)), np.zeros((PAIRS, CLASSES), np.float32)
    _rounds_of_classes(model, first, rounds)
    _rounds_of_words(model, second, rounds)
    _rounds_of_rest(model, vocab, tallies.filter("kind = 2").select("word", F.col("part").alias("before"), "n"), rounds)
    discard(tallies)


def _columns(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, ...]]:
    for b in batches:
        if b.num_rows:
            yield tuple(np.asarray(b.column(i)) for i in range(b.num_columns))


def _part(at: int, v: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_pydict({"part": pa.array([at], pa.int64()), "v": pa.array([v.astype(np.float64).tobytes()], pa.binary())})


def _in_rounds(at: np.ndarray, seen: np.ndarray, past: list[tuple[np.ndarray, ...]]) -> tuple[np.ndarray, np.ndarray]:
    """Of contexts and their counts a class: the pair features after a step for each (bias, one, two) in past,
    and what the last step expected. A pair belongs to one context, so no other context's counts are needed."""
    one, two, both = at // BUCKETS, at % BUCKETS, np.zeros(seen.shape)
    total, p = seen.sum(axis=1), both
    for bias, w1, w2 in past:
        z = bias + w1[one] + w2[two] + both
        p = np.exp(z - z.max(axis=1, keepdims=True))
        p *= (total / p.sum(axis=1))[:, None]
        both = both + 0.5 * _pull(both, seen, p)
    return both, p


def _pull(now: np.ndarray, seen: np.ndarray, expected: np.ndarray) -> np.ndarray:
    """The gradient, scaled feature by feature so that a step stays below one."""
    return (seen - expected - PULL * now) / (np.maximum(seen, expected) + 3.0 + PULL)


def _rounds_of_classes(model: Model, first: DataFrame, rounds: int) -> None:
    """Gradient rounds of the first factor over first(part, n, v), counts of (context, class). A task returns what it expects of the bias and of both
    words alone; the pair features follow from those of the rounds before and are gathered once, at the end."""
    spark, rows, small = first.sparkSession, BUCKETS * CLASSES, (1 + 2 * BUCKETS) * CLASSES

    def gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        width = PAIRS // PARTS
        for part, t in sorted(_summed_parts(batches, width * CLASSES).items()):
            seen = t.reshape(width, CLASSES).astype(float)
            own = np.flatnonzero(seen.any(axis=1))
            yield pa.RecordBatch.from_arrays([pa.array(part * width + own), pa.array([v.tobytes() for v in seen[own]], pa.binary())], ["at", "v"])

    gathered = staged(first.mapInArrow(gather, "at long, v binary"), "contexts")
    contexts = gathered.coalesce(TASKS)

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        for b in batches:
            if b.num_rows:
                yield np.asarray(b.column("at")), np.frombuffer(b"".join(b.column("v").to_pylist()), np.float64).reshape(-1, CLASSES)

    def summed(past: list[tuple[np.ndarray, ...]] | None) -> np.ndarray:
        """Observed counts of the features (None), or those expected after these rounds."""
        shared = spark.sparkContext.broadcast(past)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            sums, start = [np.zeros((r, CLASSES)) for r in (1, BUCKETS, BUCKETS)], 0
            for at, seen in read(batches):
                start = start or int(at[0]) + 1
                p = seen if shared.value is None else _in_rounds(at, seen, shared.value)[1]
                for s, f in zip(sums, (np.zeros(len(at), np.int64), at // BUCKETS, at % BUCKETS), strict=True):
                    np.add.at(s, f, p)
            yield _part(start, np.concatenate([s.ravel() for s in sums]))

        out = _summed(contexts.mapInArrow(run, "part long, v binary"), small)
        shared.destroy()
        return out

    seen, past = summed(None), []
    for _ in range(rounds):
        past.append((model.bias, model.one, model.two))
        now = np.concatenate([np.zeros(CLASSES), model.one.ravel(), model.two.ravel()])
        step = 0.5 * _pull(now, seen, summed(past))
        model.bias = model.bias + step[:CLASSES]
        model.one = model.one + step[CLASSES : CLASSES + rows].reshape(model.one.shape)
        model.two = model.two + step[CLASSES + rows :].reshape(model.two.shape)

    def pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for at, counts in read(batches):
            both = _in_rounds(at, counts, past)[0].astype(np.float32)
            yield pa.RecordBatch.from_arrays([pa.array(at), pa.array([v.tobytes() for v in both], pa.binary())], ["at", "v"])

    got = contexts.mapInArrow(pairs, "at long, v binary").toArrow()
    for b in got.to_batches():
        if b.num_rows:
            model.both[np.asarray(b.column("at"))] = np.frombuffer(b"".join(b.column("v").to_pylist()), np.float32).reshape(-1, CLASSES)
    discard(gathered)


def _step(slots: np.ndarray, seen: np.ndarray, expected: np.ndarray) -> np.ndarray:
    """The next values; a Gaussian prior keeps features that were hardly seen near zero."""
    return slots + 0.8 * (seen - expected - PULL * slots) / (np.maximum(seen, expected) + 2.0 + PULL)


def _rounds_of_words(model: Model, second: DataFrame, rounds: int) -> None:
    """Gradient rounds of the second factor for the lexicon over second(part, n, v), counts of the words behind the class
    `part`. No two classes before share a slot, so each goes through all its rounds in one task."""
    size = len(model.lexicon)
    shared = second.sparkSession.sparkContext.broadcast((model.unigram(), model.classes[:size]))

    def solve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        u, own = shared.value
        for at, seen in _summed_parts(batches, size).items():
            slots = np.zeros(size)
            total = np.bincount(own, seen, CLASSES)
            for _ in range(rounds):
                e = u * np.exp(slots)
                e *= (total / np.maximum(np.bincount(own, e, CLASSES), 1e-300))[own]
                slots = _step(slots, seen, e)
            yield pa.RecordBatch.from_arrays([pa.array([at]), pa.array([slots.astype(np.float32).tobytes()])], ["at", "v"])

    model.slots = np.zeros(CLASSES * size, np.float32)
    got = second.mapInArrow(solve, "at long, v binary").toArrow()
    for at, v in zip(got["at"].to_pylist(), got["v"], strict=True):
        model.slots[at * size : (at + 1) * size] = np.frombuffer(v.as_buffer(), np.float32)
    shared.destroy()


def _rest_slots(before: np.ndarray, shapes: np.ndarray, u: np.ndarray, n: np.ndarray, follows: np.ndarray, past: list[np.ndarray]) -> np.ndarray:
    """Slots of seen (class before, word) after a round for each array of sums in past."""
    slots, expected = np.zeros(len(n)), follows[before, shapes] * u
    for z in past:
        slots = _step(slots, n, expected * np.exp(slots) / z[before, shapes])
    return slots


def _rounds_of_rest(model: Model, vocab: DataFrame, tail: DataFrame, rounds: int) -> None:
    """Gradient rounds of the second factor for the words outside the lexicon over tail(word, before, n), partial counts.
    Each pair that was seen is a feature; the table stays distributed, a row a word. A slot follows from its own counts and
    the sums of the rounds before, which are all that the driver holds: one number a class before and shape. So pairs of
    equal counts have equal slots, and the rounds go over `kinds` of pairs, m of each."""
    in_lexicon = vocab.sparkSession.createDataFrame(pa.table({"word": pa.array(model.lexicon, pa.binary())}))
    dealt = tail.repartition("word").groupBy("word", "before").agg(F.sum("n").cast("double").alias("n")).groupBy("word").agg(F.collect_list(F.struct("before", "n")).alias("seen"))
    out = vocab.join(F.broadcast(in_lexicon), "word", "left_anti").withColumn("shape", _shape(F.col("word")).cast("long"))
    listed = [F.coalesce(F.col(f"seen.{x}"), F.array().cast(f"array<{t}>")).alias(x) for x, t in (("before", "bigint"), ("n", "double"))]
    rest = staged(out.join(dealt, "word", "left").select("word", "c", "shape", *listed), "rest")
    whole = np.ones(SHAPES)  # of each shape: tokens, types and one for all unseen words
    for r in rest.groupBy("shape").agg(F.sum("c").alias("n"), F.count(F.lit(1)).alias("v")).collect():
        whole[r["shape"]] += r["n"] + r["v"]
    pair = F.explode(F.arrays_zip("before", "n")).alias("pair")
    each = rest.select("c", "shape", pair).groupBy(F.col("pair.before").alias("before"), "shape", "c", F.col("pair.n").alias("n")).agg(F.count(F.lit(1)).alias("m"))
    u = (F.col("c") + 1) / F.array(*[F.lit(float(x)) for x in whole])[F.col("shape").cast("int")]
    kinds = staged(each.select("before", "shape", u.alias("u"), "n", "m"), "kinds")

    def cells(df: DataFrame) -> np.ndarray:
        out = np.zeros((CLASSES, SHAPES))
        for r in df.groupBy("before", "shape").agg(F.sum("n").alias("n")).collect():
            out[r["before"], r["shape"]] = r["n"]
        return out

    follows, past = cells(kinds.select("before", "shape", (F.col("n") * F.col("m")).alias("n"))), [np.ones((CLASSES, SHAPES))]
    for _ in range(rounds):

        def grown(batches: Iterator[pa.RecordBatch], past=tuple(past)) -> Iterator[pa.RecordBatch]:
            more = np.zeros(CLASSES * SHAPES)
            for before, shapes, u, n, m in _columns(batches):
                more += np.bincount(before * SHAPES + shapes, m * u * np.expm1(_rest_slots(before, shapes, u, n, follows, past)), len(more))
            at = np.flatnonzero(more)
            yield pa.RecordBatch.from_arrays([pa.array(at // SHAPES), pa.array(at % SHAPES), pa.array(more[at])], ["before", "shape", "n"])

        past.append(1 + cells(kinds.mapInArrow(grown, "before long, shape long, n double")))
    discard(kinds)
    done, last = past[:-1], past[-1]
    model.tails = np.log10(whole * last)

    def slots(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            before, n = b.column("before"), b.column("n")
            length = np.asarray(before.value_lengths())
            shapes = np.asarray(b.column("shape"))
            u = (np.asarray(b.column("c")) + 1) / whole[shapes]
            at = before.flatten()
            v = _rest_slots(np.asarray(at), np.repeat(shapes, length), np.repeat(u, length), np.asarray(n.flatten()), follows, done)
            edges = pa.array(np.concatenate(([0], np.cumsum(length))).astype(np.int32))
            yield pa.RecordBatch.from_arrays([b.column("word"), b.column("c"), pa.MapArray.from_arrays(edges, at, pa.array(v / _LOG10))], ["word", "c", "slots"])

    model.rest = rest.mapInArrow(slots, "word binary, c long, slots map<bigint, double>")


def score(docs: DataFrame, model: Model, vocab: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_tokens, n_known, train_tokens, base_score, score for every row (null text: empty).

    Words of the lexicon, which hold all frequent ones, are scored in the workers. The others, each far
    below a thousandth of the tokens, are joined with the table of their counts and features, one row a text, word and
    class before, and their logarithms summed by text; an unseen word has count 0. Rows are told apart by a row number, so repeated ids
    and rows are kept. Further columns are ignored."""
    return _scored(_coded(docs, model, id_col, text_col), model)


def _scored(coded: DataFrame, model: Model) -> DataFrame:
    size = len(model.lexicon)
    shared = coded.sparkSession.sparkContext.broadcast(model)
    floor = float(np.log10(model.tokens + model.types + 1))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        first, unigram, sums = m.tables()
        base = np.concatenate((np.log10(m.counts + 1) - floor, np.zeros(SHAPES)))
        if not m.tokens:
            base[0] = -floor
        inside = np.concatenate((unigram, np.zeros(SHAPES)))
        for b, code, length in _read(batches):
            ids, before, one, two = _contexts(code, length)
            own = m.classes[ids]
            known = ids < size
            value = first[one * BUCKETS + two, own] + inside[ids]
            behind = m.classes[before]
            value[known] += m.slots[_slot(behind[known], ids[known], m.featured)] / _LOG10 - sums[behind[known], own[known]]
            value[~known] -= m.tails[behind[~known], ids[~known] - size]
            row = np.repeat(np.arange(len(length)), length)
            yield pa.RecordBatch.from_arrays(
                [
                    b.column("rid"),
                    b.column("doc_id"),
                    pa.array(length),
                    pa.array(np.bincount(row[known], minlength=len(length)) - (0 if m.tokens else 1)),
                    pa.array(np.bincount(row, base[ids], len(length))),
                    pa.array(np.bincount(row, value, len(length))),
                ],
                ["rid", "doc_id", "n_tokens", "known", "base", "model"],
            )

    kind = coded.schema["doc_id"].dataType.simpleString()
    scored = coded.select("rid", "doc_id", "codes").mapInArrow(run, f"rid long, doc_id {kind}, n_tokens long, known long, base double, model double")

    # classes are all that the words outside the lexicon need of the model
    classes = coded.sparkSession.sparkContext.broadcast(model.classes)

    def occurring(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b, code, length in _read(batches):
            ids, before, _, _ = _contexts(code, length)
            out = np.flatnonzero(ids >= size)
            rid = np.repeat(np.asarray(b.column("rid")), length)[out].tolist()
            met = Counter(zip(rid, _unlisted(b.column("rare")), classes.value[before[out]].tolist(), strict=True))
            rid, word, behind = zip(*met, strict=True) if met else ((), (), ())
            yield pa.RecordBatch.from_arrays([pa.array(rid, pa.int64()), pa.array(word, pa.binary()), pa.array(behind, pa.int64()), pa.array(list(met.values()), pa.int64())], ["rid", "word", "before", "n"])

    each = coded.filter("rare IS NOT NULL").select("rid", "codes", "rare").mapInArrow(occurring, "rid long, word binary, before long, n long")
    met = each.join(model.rest, "word", "left")
    log = F.log10(F.coalesce("c", F.lit(0)) + 1)
    tails = met.groupBy("rid").agg(
        F.sum(F.col("n") * (log - floor)).alias("tail_base"),
        F.sum(F.col("n") * (log + F.coalesce(F.try_element_at("slots", F.col("before")), F.lit(0.0)))).alias("tail_model"),
        F.sum(F.when(F.col("c") > 0, F.col("n")).otherwise(0)).alias("tail_known"),
    )
    both = scored.join(tails, "rid", "left")
    nought = lambda c: F.coalesce(F.col(c), F.lit(0.0))
    return both.select(
        "doc_id",
        "n_tokens",
        (F.col("known") + F.coalesce("tail_known", F.lit(0))).cast("long").alias("n_known"),
        F.lit(int(model.tokens)).cast("long").alias("train_tokens"),
        (F.col("base") + nought("tail_base")).alias("base_score"),
        (F.col("model") + nought("tail_model")).alias("score"),
    )


def _shape(word: Column) -> Column:
    """shape() in SQL."""
    last = F.hex(F.substring(word, -1, 1))
    ascii_only = ~F.hex(word).rlike("^(..)*[89A-F]")
    plain = last.rlike("^(3[0-9]|[46][1-9A-F]|[57][0-9A])$")
    return F.when(ascii_only, 0).otherwise(4) + F.when(F.octet_length(word) > 8, 2).otherwise(0) + F.when(~plain & (last < "80"), 1).otherwise(0)
