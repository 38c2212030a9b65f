"""Language identification by nearest centroids of TF-IDF character n-grams."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from spectrack.llm.common import lean

UNKNOWN = "und"
_BLOCK = 500_000  # characters handled at once

_letters: np.ndarray | None = None


def _is_letter() -> np.ndarray:
    """Which code points are letters, all planes; made once a process."""
    global _letters
    if _letters is None:
        _letters = np.fromiter((chr(i).isalpha() for i in range(0x110000)), bool, 0x110000)
    return _letters


def counts(texts: list[str], dims: int) -> tuple[np.ndarray, np.ndarray]:
    """Counts of hashed character 2- and 3-grams and single letters (texts x dims), and the number of letters.

    Letters are lower-cased; runs of anything else are one space each; whole texts are read, in blocks."""
    out, letters = np.zeros((len(texts), dims), np.float32), np.zeros(len(texts), np.int64)
    table, at = _is_letter(), 0
    while at < len(texts):
        upto, size = at, 0
        while upto < len(texts) and (upto == at or size + len(texts[upto]) < _BLOCK):
            size += len(texts[upto])
            upto += 1
        if size > 2 * _BLOCK:  # one very long text, block by block
            text = texts[at]
            for i in range(0, len(text), _BLOCK):
                part, n = counts([text[i : i + _BLOCK]], dims)
                out[at] += part[0]
                letters[at] += n[0]
            at = upto
            continue
        lower = [t.lower() for t in texts[at:upto]]
        code = np.frombuffer("".join(f" {t} " for t in lower).encode("utf-32-le"), "<u4").astype(np.uint64)
        row = np.repeat(np.arange(upto - at), [len(t) + 2 for t in lower])
        keep = table[code.astype(np.int64)]
        letters[at:upto] = np.bincount(row[keep], minlength=upto - at)
        code = np.where(keep, code, np.uint64(32))
        stay = np.ones(len(code), bool)
        stay[1:] = keep[1:] | keep[:-1] | (row[1:] != row[:-1])
        code, row, keep = code[stay], row[stay], keep[stay]
        total = np.zeros((upto - at) * dims, np.int64)
        gram = np.zeros(len(code), np.uint64)
        for n in range(3):
            # a rolling polynomial over the last n+1 characters, mixed down to dims
            gram = code if n == 0 else np.concatenate((code[:n], gram[:-1][n - 1 :] * np.uint64(0x1F123BB5) + code[n:]))
            mixed = (gram + np.uint64(n)) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(40)
            whole = np.ones(len(code), bool) if n else keep
            if n:
                whole = np.zeros(len(code), bool)
                whole[n:] = row[n:] == row[:-n]
            total += np.bincount(row[whole] * dims + (mixed[whole] % np.uint64(dims)).astype(np.int64), minlength=len(total))
        out[at:upto] = total.reshape(-1, dims)
        at = upto
    return out, letters


def weighted(tf: np.ndarray, idf: np.ndarray) -> np.ndarray:
    v = np.sqrt(tf) * idf
    return v / np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-12)


@dataclass
class Model:
    """Unit centroids (several a language), their languages, and the least similarity each accepts."""

    dims: int
    idf: np.ndarray
    langs: list[str] = field(default_factory=list)
    centroids: np.ndarray = None
    least: np.ndarray = None

    def predict(self, texts: list[str | None]) -> tuple[list[str], np.ndarray, np.ndarray]:
        """(language, similarity, rejected) of each text."""
        tf, letters = counts([t or "" for t in texts], self.dims)
        if not self.langs:
            return [UNKNOWN] * len(texts), np.zeros(len(texts)), np.ones(len(texts), bool)
        sims = weighted(tf, self.idf) @ self.centroids.T
        best = sims.argmax(axis=1)
        score = np.clip(sims[np.arange(len(texts)), best], 0.0, 1.0).astype(float)
        none = letters == 0
        lang = [UNKNOWN if none[i] else self.langs[b] for i, b in enumerate(best)]
        # short texts share few n-grams with anything: their bar is lower, as the square root of their length
        bar = self.least[best] * np.sqrt(np.minimum(1.0, letters / 400))
        return lang, np.where(none, 0.0, score), none | (score < bar)


def held_out(id_col: str, mod: int, rest: int) -> Column:
    return F.coalesce(F.crc32(F.col(id_col).cast("string")), F.lit(0)) % mod == rest


def _cluster(v: np.ndarray, k: int, rounds: int = 12) -> tuple[np.ndarray, np.ndarray]:
    """Spherical k-means from far-apart starting rows: (unit centroids, each row's best similarity)."""
    k = min(k, len(v))
    first = v.mean(axis=0)
    chosen = [int((v @ first).argmax())]
    while len(chosen) < k:
        chosen.append(int((v @ v[chosen].T).max(axis=1).argmin()))
    c = v[chosen]
    for _ in range(rounds):
        own = (v @ c.T).argmax(axis=1)
        sums = np.stack([v[own == j].sum(axis=0) if (own == j).any() else c[j] for j in range(k)])
        c = sums / np.maximum(np.linalg.norm(sums, axis=1, keepdims=True), 1e-12)
    return c, (v @ c.T).max(axis=1)


def fit(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", dims: int = 4096, centroids: int = 4, sample: int = 400, slack: float = 0.5
) -> Model:
    """Learn from the rows of docs with a language.

    Document frequencies cover all rows. Centroids are clustered, a language a task, from about `sample`
    rows of each language (the bound of the classifier's sample), chosen by a hash of id and text; of rows equal in both
    one counts. Every language that occurs is learned: the model takes 16 kB a centroid. A centroid rejects what is less similar than `slack` times the first percentile of its own sample
    (texts under 400 letters have a lower bar)."""
    rows = docs.filter(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull()).select(
        F.col(lang_col).alias("lang"), F.col(text_col).alias("text"), F.xxhash64(F.col(id_col), F.col(text_col)).alias("h")
    )

    def frequencies(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, n = np.zeros(dims, np.int64), 0
        for b in lean(batches, 256):
            total += (counts(b.column("text").to_pylist(), dims)[0] > 0).sum(axis=0)
            n += b.num_rows
        yield pa.RecordBatch.from_pydict({"dim": np.arange(-1, dims), "n": np.concatenate(([n], total))})

    df = dict(rows.select("text").mapInArrow(frequencies, "dim long, n long").groupBy("dim").agg(F.sum("n")).collect())
    n = df.pop(-1, 0)
    idf = np.log((1 + n) / (1 + np.array([df.get(i, 0) for i in range(dims)]))).astype(np.float32) + 0.1
    model = Model(dims, idf)

    sizes = rows.groupBy("lang").agg(F.count(F.lit(1)).alias("n"))
    u = F.shiftrightunsigned("h", 11) / F.lit(float(1 << 53))
    # a row a language, of which the model itself holds far more; rows of equal id and text, which share h, go once
    some = rows.join(F.broadcast(sizes), "lang").filter(u < F.lit(float(sample)) / F.col("n")).select("lang", "h", "text").dropDuplicates(["lang", "h"])

    def centre(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("h")
        tf, letters = counts(pdf["text"].tolist(), dims)
        v = weighted(tf, idf)[letters > 0]
        if not len(v):
            return pd.DataFrame({"lang": [None], "least": [None], "v": [None]})
        c, sims = _cluster(v, centroids)
        return pd.DataFrame({"lang": pdf["lang"].iloc[0], "least": slack * float(np.quantile(sims, 0.01)), "v": list(c.astype(np.float32))})

    found = some.groupBy("lang").applyInPandas(centre, "lang string, least double, v array<float>").filter("v IS NOT NULL").collect()
    found.sort(key=lambda r: (r["lang"], r["v"]))
    if found:
        model.langs = [r["lang"] for r in found]
        model.centroids = np.array([r["v"] for r in found], np.float32)
        model.least = np.array([r["least"] for r in found])
    return model


def identify(docs: DataFrame, model: Model, keep: bool = False, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, lang_pred, score, rejected for every row; with keep, the rows of docs that are not rejected, as they are.

    The nearest centroid's language; `und` (score 0, rejected) for null texts and texts without a letter. Only the
    text is looked at. The model is a few hundred centroids at most and goes along with the function."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in lean(batches, 256):
            lang, score, rejected = model.predict(part.column(text_col).to_pylist())
            if keep:
                yield part.filter(pa.array(~rejected))
            else:
                yield pa.RecordBatch.from_arrays([part.column(id_col), pa.array(lang, pa.string()), pa.array(score), pa.array(rejected)], ["doc_id", "lang_pred", "score", "rejected"])

    if keep:
        return docs.mapInArrow(run, docs.schema)
    ids = T.StructField("doc_id", docs.schema[id_col].dataType)
    schema = T.StructType([ids, T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType()), T.StructField("rejected", T.BooleanType())])
    return docs.select(id_col, text_col).mapInArrow(run, schema)
