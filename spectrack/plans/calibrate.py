"""Constants of the parameter rule for a set of tracks, found on a sample of it."""

from __future__ import annotations

import math
from collections import defaultdict

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spectrack.functions import track as K
from spectrack.functions.params import Constants, derive
from spectrack.plans import codec

ROW = "track_id string, n long, raw_bytes long, eps double, b_s long, r_ret double, a double, bytes long"


def sizes(points: DataFrame, dim: int, cells: list[tuple[float, int, float, float]], share: float) -> dict[tuple[float, int, float, float], int]:
    """Bytes of the sampled tracks for each (bound, block size, retention, a). Tracks are chosen by a hash of their id."""
    u = F.shiftrightunsigned(F.xxhash64("track_id", F.lit(17)), 11) / F.lit(float(1 << 53))

    def run(eps: float, b: int, r: float, a: float):
        p = derive(eps, dim, b_s=b, r_ret=r, eps_f=eps / a)
        return {"eps": eps, "b_s": b, "r_ret": r, "a": a}, lambda t, pos: {"bytes": K.size_of(K.encode(t, pos, p), p)}

    rows = codec.sweep(points.filter(u < share), [run(*c) for c in cells], ROW).groupBy("eps", "b_s", "r_ret", "a").agg(F.sum("bytes").alias("bytes")).collect()
    return {(r["eps"], r["b_s"], r["r_ret"], r["a"]): r["bytes"] for r in rows}


def _nearest(x: float, grid) -> float:
    return min(grid, key=lambda g: abs(math.log(g / x)))


def calibrate(
    points: DataFrame, dim: int, eps: list[float], share: float = 0.1, blocks=(4, 6, 8, 12, 16, 24, 32, 48, 64, 96, 128), retained=(1.0, 0.7, 0.5, 0.35, 0.25), precision=(0.4, 0.5, 0.6, 0.7, 0.8)
) -> tuple[Constants, dict[str, float]]:
    """(constants, figures): block size and retention are searched together at the usual precision, the lines b * eps + c and
    d / sqrt(eps) are those that lose least against the best cell of each bound, in logarithms; then the precision.
    The figures: `gap`, the mean loss of the lines against the best cells, and `untruncated`, the same with nothing cut."""
    cells = [(e, b, r, 0.6) for e in eps for b in blocks for r in retained]
    found = sizes(points, dim, cells, share)
    best = {e: min(v for k, v in found.items() if k[0] == e) for e in eps}
    top = max(eps)

    def loss(b: float, c: float, d: float) -> float:
        at = lambda e: found[e, int(_nearest(max(1.0, b * e + c), blocks)), _nearest(min(1.0, d / math.sqrt(e)), retained), 0.6]
        return sum(math.log(at(e) / best[e]) for e in eps) / len(eps)

    # retention that never cuts, and lines that reach each grid value at some bound
    kept = [math.sqrt(top)] + [r * math.sqrt(e) for r in retained[1:] for e in eps]
    slopes = [0.0] + [x / top for x in (4, 8, 16, 32, 64)]
    options = [(loss(b, float(c), d), b, float(c), d) for b in slopes for c in (2, *blocks) for d in kept]
    gap, b, c, d = min(options, key=lambda x: (round(x[0], 6), x[1], x[2], -x[3]))
    whole = min(x[0] for x in options if x[3] == kept[0])
    cells = [(e, max(1, math.floor(b * e + c + 0.5)), min(1.0, d / math.sqrt(e)), a) for e in eps for a in precision]
    found = sizes(points, dim, cells, share)
    per_a = defaultdict(float)
    for (_, _, _, a), size in found.items():
        per_a[a] += math.log(size)
    return Constants(min(per_a, key=lambda a: (per_a[a], a)), b, c, d), {"gap": math.expm1(gap), "untruncated": math.expm1(whole)}
