"""URL rules looked up in a memory-mapped, sorted array of 64-bit digests."""

from __future__ import annotations

import hashlib
import mmap
import os
import re
import tempfile
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import SparkFiles
from pyspark.sql import DataFrame

_MAGIC = b"URLRULE2"
_PATH_END = re.compile(r"[?#]")
_HOST_END = re.compile(r"[/?#]")
_LOWER = {i: i + 32 for i in range(65, 91)}


def _digest(text: str) -> int:
    return xxhash.xxh64_intdigest(text.encode("utf-8", "surrogatepass"))


def build(rules: Iterable[tuple[str, str, str]]) -> bytes:
    """The file's bytes: header (with the length of the longest host), sorted digests, offsets of the strings, distinct
    path lengths, verdicts, then the full rule strings in the digests' order. rules: (verdict, host, path)."""
    made = {(host.translate(_LOWER), path): verdict == "allow" for verdict, host, path in rules}
    items = sorted((_digest(f"{h}\0{p}"), h, p, ok) for (h, p), ok in made.items())
    texts = [f"{h}\0{p}".encode() for _, h, p, _ in items]
    lengths = sorted({len(p) for _, _, p, _ in items})
    ends = np.cumsum([0, *map(len, texts)], dtype=np.uint64)
    head = np.array([len(items), len(lengths), max((len(h) for _, h, _, _ in items), default=0)], dtype=np.uint64)
    return b"".join(
        [_MAGIC, head.tobytes(), np.array([d for d, *_ in items], np.uint64).tobytes(), ends.tobytes(), np.array(lengths, np.uint64).tobytes(), np.array([ok for *_, ok in items], np.uint8).tobytes(), *texts]
    )


class Rules:
    """The array, read through a memory map: workers on a machine share its pages."""

    def __init__(self, path: str):
        with open(path, "rb") as f:
            self.map = mmap.mmap(f.fileno(), 0, access=mmap.ACCESS_READ)
        if self.map[:8] != _MAGIC:
            raise ValueError("not a rule file")
        n, k, self.longest = (int(x) for x in np.frombuffer(self.map, np.uint64, 3, 8))
        at = 32
        self.keys = np.frombuffer(self.map, np.uint64, n, at)
        self.ends = np.frombuffer(self.map, np.uint64, n + 1, at + 8 * n)
        self.lengths = [int(x) for x in np.frombuffer(self.map, np.uint64, k, at + 16 * n + 8)]
        self.allow = np.frombuffer(self.map, np.uint8, n, at + 16 * n + 8 + 8 * k)
        self.heap = at + 17 * n + 8 + 8 * k

    def text(self, i: int) -> str:
        return self.map[self.heap + int(self.ends[i]) : self.heap + int(self.ends[i + 1])].decode()

    def probe(self, pages: list[tuple[str, str]]) -> list[tuple[str | None, bool | None]]:
        """For each (host, path) the longest rule that fits and whether it allows; on equal length the
        one with the longer host. Of a host's suffixes only those no longer than a rule's host are probed, so a long
        one costs no more than a short one."""
        owner, wanted = [], []
        for at, (host, path) in enumerate(pages):
            hosts = [host] if len(host) <= self.longest else []
            dot = host.find(".", max(0, len(host) - self.longest - 1))
            while dot >= 0:
                hosts.append(host[dot + 1 :])
                dot = host.find(".", dot + 1)
            for n in self.lengths:
                if n <= len(path):
                    start = path[:n]
                    for h in hosts:
                        owner.append(at)
                        wanted.append(f"{h}\0{start}")
        out: list[tuple[str | None, bool | None]] = [(None, None)] * len(pages)
        if not wanted or not len(self.keys):
            return out
        digests = np.fromiter((_digest(w) for w in wanted), np.uint64, len(wanted))
        left = np.searchsorted(self.keys, digests)
        size: dict[int, tuple[int, int]] = {}
        hit = np.flatnonzero(self.keys[np.minimum(left, len(self.keys) - 1)] == digests)
        for j in hit.tolist():
            i = int(left[j])
            while i < len(self.keys) and self.keys[i] == digests[j]:  # equal digests stand together
                if self.text(i) == wanted[j]:
                    host, _, path = wanted[j].partition("\0")
                    rank = (len(host) + len(path), len(host))
                    if rank > size.get(owner[j], (-1, -1)):
                        size[owner[j]] = rank
                        out[owner[j]] = (host + path, bool(self.allow[i]))
                    break
                i += 1
        return out


def split_url(url: str | None) -> tuple[str, str]:
    """(host, path): the host is what follows the first `://` up to `/`, `?` or `#`, A-Z in lower case; the
    path goes on up to `?` or `#`. Both are empty for null and where there is no `://`."""
    if url is None or (at := url.find("://")) < 0:
        return "", ""
    rest = url[at + 3 :]
    end = m.start() if (m := _HOST_END.search(rest)) else len(rest)
    tail = rest[end:]
    return rest[:end].translate(_LOWER), tail[: m.start()] if (m := _PATH_END.search(tail)) else tail


_open: dict[str, Rules] = {}


def url_filter(pages: DataFrame, rules: Iterable[tuple[str, str, str]], id_col: str = "page_id", url_col: str = "url", default: str = "allow") -> DataFrame:
    """Judge every url: page_id, host, path, rule, verdict.

    A rule fits its host and all subdomains if the path starts with the rule's; the longest wins; without
    one, `default` holds. The rule file goes to the executors once as a Spark file. Null ids stay null; an
    empty table gives an empty result; of other columns none is read."""
    data = build(rules)
    name = f"url-rules-{hashlib.sha256(data).hexdigest()[:16]}.bin"
    local = os.path.join(tempfile.mkdtemp(prefix="url-rules-"), name)
    with open(local, "wb") as f:
        f.write(data)
    sc = pages.sparkSession.sparkContext
    if not any(x.endswith(name) for x in sc.listFiles):
        sc.addFile(local)

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if name not in _open:
            _open[name] = Rules(SparkFiles.get(name))
        for b in batches:
            parts = [split_url(u) for u in b.column("url").to_pylist()]
            found = _open[name].probe(parts)
            columns = {
                "page_id": b.column("page_id"),
                "host": [h for h, _ in parts],
                "path": [p for _, p in parts],
                "rule": pa.array([r for r, _ in found], pa.string()),
                "verdict": pa.array([default if ok is None else "allow" if ok else "block" for _, ok in found], pa.string()),
            }
            columns |= {k: pa.array(columns[k], pa.string()) for k in ("host", "path")}
            yield pa.RecordBatch.from_pydict(columns)

    ids = pages.schema[id_col].dataType.simpleString()
    two = pages.selectExpr(f"`{id_col}` AS page_id", f"`{url_col}` AS url")
    return two.mapInArrow(judge, f"page_id {ids}, host string, path string, rule string, verdict string")
