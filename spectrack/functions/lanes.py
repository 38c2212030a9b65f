"""Many tracks simplified at many bounds at once: the paths of simplify.py, with one numpy call a sample of all tracks and
bounds where simplify.py needs several a sample of each. A track at a bound is a lane."""

from __future__ import annotations

from functools import lru_cache

import numpy as np

from spectrack.functions import numbers as N
from spectrack.functions import simplify as S
from spectrack.functions.params import CodecParams

Track = tuple[np.ndarray, np.ndarray]

#: so many samples of lanes are tested at a time
COLUMNS = 4096
#: tracks of no more points go through the priority queue together: a removal looks at all of a track's costs
SHORT = 512
#: points times bounds whose paths are held at once
HELD = 5_000_000


class Flat:
    """Tracks one after the other: times in seconds from each one's start, axes, and where tracks begin."""

    def __init__(self, tracks: list[Track]):
        self.n = np.array([len(t) for t, _ in tracks])
        self.begin = np.cumsum(self.n) - self.n
        self.own = np.repeat(np.arange(len(tracks)), self.n)
        self.first = np.array([int(t[0]) for t, _ in tracks])
        self.t = np.concatenate([(t - t[0]) / 1e6 for t, _ in tracks])
        self.axes = np.ascontiguousarray(np.concatenate([np.asarray(pos, float) for _, pos in tracks]).T)


def _empty(proofs: np.ndarray, h: np.ndarray) -> np.ndarray:
    """Which columns of supports leave no velocity; some hundreds at a time, which stay in the cache."""
    out = np.empty(h.shape[1], bool)
    for a in range(0, len(out), 512):
        out[a : a + 512] = (proofs @ h[:, a : a + 512]).min(axis=0) < 0
    return out


@lru_cache(maxsize=16)
def _edges(m: int) -> tuple[np.ndarray, ...]:
    """Normals and directions of the m-gon's edges; cosine and sine of the turns of less than a half from one, and which edges are
    that far ahead and behind."""
    normals, _, _ = S._polygon(m)
    k, edge = np.arange(1, (m + 1) // 2)[:, None], np.arange(m)
    turn = (2 * np.pi * k / m)[:, :, None]
    return normals, np.column_stack((-normals[:, 1], normals[:, 0])), np.cos(turn), np.sin(turn), (edge + k) % m, (edge - k) % m


def centres(h: np.ndarray, m: int) -> np.ndarray:
    """simplify._centre of each column of supports. On a half-plane's edge every other one leaves an interval; what is left of
    the edges bounds the polygon."""
    if h.shape[1] > 512:  # what stays in the cache
        return np.concatenate([centres(h[:, a : a + 512], m) for a in range(0, h.shape[1], 512)], axis=1)
    normals, along, cosine, sine, ahead, behind = _edges(m)
    own = h * cosine
    up, down = (((h[j] - own) / sine).min(axis=0) for j in (ahead, behind))
    size = np.maximum(up + down, 0)
    middle = (up - down) / 2
    x, y = (h * normals[:, d : d + 1] + middle * along[:, d : d + 1] for d in (0, 1))
    with np.errstate(divide="ignore", invalid="ignore"):
        total = size.sum(axis=0)
        x0, y0 = (x * size).sum(axis=0) / total, (y * size).sum(axis=0) / total
        area = (h - normals[:, :1] * x0 - normals[:, 1:] * y0) * size
        whole = 1.5 * area.sum(axis=0)
        out = np.array([x0 + ((x - x0) * area).sum(axis=0) / whole, y0 + ((y - y0) * area).sum(axis=0) / whole])
    for i in np.flatnonzero(~(whole > 1e-300) | ~np.isfinite(out).all(axis=0)).tolist():
        out[:, i] = S._centre(h[:, i], m)
    return out


def _walk(f: Flat, lines: np.ndarray, start: np.ndarray, end: np.ndarray, limit: np.ndarray, radius: np.ndarray, m: int, kept: np.ndarray, path: np.ndarray | None = None, known: np.ndarray | None = None) -> np.ndarray:
    """Lanes from the samples `start` on: marks what each keeps before `limit` behind its place in `lines`, and returns the last that it kept, the
    first not before the limit or marked as known, or its track's last. With a path the cone is the weak one.

    All lanes go on by a window of samples at a time, those that a sample leaves nothing to no further than that. The window follows
    the lanes: short where segments are, long where few lanes are left to share a call."""
    normals, inner, proofs = S._polygon(m)
    base = np.column_stack((normals, np.ones(m)))
    out, lane = start.copy(), np.arange(len(start))
    anchor, radius = np.concatenate((f.t[None, start], f.axes[:, start])), radius * inner
    i = start + 1
    h, fresh, alive = np.full((m, len(i)), np.inf), np.ones(len(i), bool), i < end
    width = 1
    while left := int(np.count_nonzero(alive)):
        if left <= 0.9 * len(i):
            some = np.flatnonzero(alive)
            lane, lines, i, end, limit, radius, fresh, alive = (v[some] for v in (lane, lines, i, end, limit, radius, fresh, alive))
            anchor, h = anchor[:, some], h[:, some]
        size = len(i)
        # beyond its end a lane sees its last sample again, which changes nothing
        at = np.minimum(i + np.arange(width)[:, None], end - 1)
        dt = f.t[at] - anchor[0]
        if left < size:
            dt[:, ~alive] = 1.0
        v = np.empty((3, width, size))
        np.subtract(f.axes[:, at], anchor[1:, None], out=v[:2])
        v[2] = radius
        v /= dt
        s = (base @ v.reshape(3, -1)).reshape(m, width, size)
        held = h
        np.minimum(s[:, 0], held, out=s[:, 0])
        step = 1
        while step < width:
            s[:, step:] = np.minimum(s[:, step:], s[:, :-step])
            step *= 2
        empty = _empty(proofs, s.reshape(m, -1)).reshape(width, size)
        failed = empty.any(axis=0) & alive
        close = np.flatnonzero(alive & (failed | (i + width >= end)))
        share = np.count_nonzero(failed) / left
        h = s[:, -1]
        if len(close):
            first = i[close]
            j = np.where(failed[close], empty[:, close].argmax(axis=0), width)
            stuck = (j == 0) & fresh[close]  # not even one sample fits: it is kept itself
            last = np.minimum(first + j - 1 + stuck, end[close] - 1)
            where = f.axes[:, last]
            to = lines[close] + last
            if path is not None:
                fits = slice(None) if not stuck.any() else np.flatnonzero(~stuck)
                some, before = close[fits], j[fits] - 1
                supports = s[:, np.maximum(before, 0), some]
                early = np.flatnonzero(before < 0)  # its window's first sample ends such a lane
                supports[:, early] = held[:, some[early]]
                where[:, fits] = anchor[1:, some] + centres(supports, m) * (f.t[last[fits]] - anchor[0, some])
                path[:, to] = where
            on = last < limit[close]
            kept[to[on]] = True
            if known is not None:
                on &= ~known[to]
            out[lane[close]] = last
            anchor[0, close], anchor[1:, close] = f.t[last], where
            on &= last + 1 < end[close]
            alive[close[~on]] = False
        i = i + width
        fresh[:] = False
        if len(close):
            i[close] = last + 1
            h[:, close] = np.inf
            fresh[close] = True
        few = width * size < 512
        if share < (0.9 if few else 0.2) and 2 * width * size <= COLUMNS:
            width *= 2
        elif width > 1 and (share > (0.97 if few else 0.6) or width * size > COLUMNS):
            width //= 2
    return out


def _cut(f: Flat, lanes: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(start, limit, end of the track) of ranges of the tracks, so many that `lanes` at each make some hundreds of lanes, but of 128
    samples at least."""
    size = max(128, -(-len(f.t) * lanes // 2048))
    many = -(-f.n // size)
    which = np.repeat(np.arange(len(f.n)), many)
    nth = np.arange(len(which)) - np.repeat(np.cumsum(many) - many, many)
    end = (f.begin + f.n)[which]
    start = f.begin[which] + nth * size
    return start, np.minimum(start + size, end), end


def _strong(f: Flat, bounds: list[float], m: int, kept: np.ndarray) -> None:
    """Marks what S.cone_strong keeps. Which sample follows a kept one depends on that alone, so ranges of a long track are walked at once as
    if their first samples were kept, and then from where the range before really comes out, until the walk meets what is marked."""
    points = len(f.t)
    start, limit, end = _cut(f, len(bounds))
    lines = np.repeat(np.arange(len(bounds)) * points, len(start))
    start, limit, end = (np.tile(x, len(bounds)) for x in (start, limit, end))
    radius = np.repeat(np.asarray(bounds, float) / 2, len(start) // len(bounds))
    kept[lines + start] = True
    out = _walk(f, lines, start, end, limit, radius, m, kept)
    inner = np.flatnonzero((lines[1:] == lines[:-1]) & (end[1:] == end[:-1])) + 1
    entry = start.copy()
    while len(inner):
        todo = inner[out[inner - 1] != entry[inner]]
        if not len(todo):
            return
        entry[todo] = out[todo - 1]
        come = entry[todo]
        place = lines[todo] + come
        fresh = (come < limit[todo]) & ~kept[np.minimum(place, len(kept) - 1)]
        upto = np.minimum(come, limit[todo])
        out[todo[come >= limit[todo]]] = come[come >= limit[todo]]
        walk = todo[fresh]
        if len(walk):
            marks = np.zeros(len(kept), bool)
            marks[place[fresh]] = True
            met = _walk(f, lines[walk], come[fresh], end[walk], limit[walk], radius[walk], m, marks, known=kept)
            over = (met >= limit[walk]) | ~kept[lines[walk] + np.minimum(met, limit[walk] - 1)]
            upto[fresh] = np.where(over, limit[walk], met)
            out[walk[over]] = met[over]
        for k, (r, b) in enumerate(zip(todo.tolist(), upto.tolist(), strict=True)):
            a = lines[r] + start[r]
            kept[a : lines[r] + b] = marks[a : lines[r] + b] if fresh[k] else False


def cones(f: Flat, bounds: list[float], weak: bool, m: int = 16) -> tuple[np.ndarray, np.ndarray | None]:
    """(which samples' times the path of each bound has, its positions there or None where they are the samples): S.cone_strong or
    S.cone_weak of every track within each bound."""
    points, tracks = len(f.t), len(f.n)
    kept = np.zeros(len(bounds) * points, bool)
    if not weak:
        _strong(f, bounds, m, kept)
        return kept.reshape(len(bounds), points), None
    path = np.empty((2, len(bounds) * points))
    lines, start, end = np.repeat(np.arange(len(bounds)) * points, tracks), np.tile(f.begin, len(bounds)), np.tile(f.begin + f.n, len(bounds))
    kept[lines + start], path[:, lines + start] = True, f.axes[:, start]
    _walk(f, lines, start, end, end, np.repeat(np.asarray(bounds, float), tracks), m, kept, path)
    return kept.reshape(len(bounds), points), path.reshape(2, len(bounds), points)


def queue(f: Flat, eps: float) -> np.ndarray:
    """S.pq_costs of every track. Of short ones the least cost of each is removed at once."""
    out = np.full(len(f.t), np.inf)
    short = f.n <= SHORT
    for i in np.flatnonzero(~short | (f.n < 3) | (np.count_nonzero(short) < 8)).tolist():
        a, b = f.begin[i], f.begin[i] + f.n[i]
        if b - a > 2:
            out[a:b] = S.pq_costs(f.t[a:b], f.axes[:, a:b].T, eps)
    if np.count_nonzero(short) < 8:
        return out
    some = np.flatnonzero(short & (f.n >= 3))
    some = some[np.argsort(f.n[some], kind="stable")]
    cuts = np.arange(0, len(some), 512).tolist()
    for a in cuts:
        _queue_short(f, some[a : a + 512], eps, out)
    return out


def _queue_short(f: Flat, which: np.ndarray, eps: float, out: np.ndarray) -> None:
    """The same of these tracks, into their places of `out`."""
    n, begin = f.n[which], f.begin[which]
    most = int(n.max())
    place = np.minimum(np.arange(most), n[:, None] - 1) + begin[:, None]
    t, axes = f.t[place].ravel(), [x[place].ravel() for x in f.axes]
    carried = np.zeros(len(t))

    def costs(i: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        s, far = (t[i] - t[a]) / (t[b] - t[a]), 0.0
        for x in axes:
            d = x[i] - (x[a] + (x[b] - x[a]) * s)
            far = far + d * d
        return np.sqrt(far) + carried[i]

    grid = np.arange(len(t)).reshape(-1, most)
    before, after = np.arange(-1, len(t) - 1), np.arange(1, len(t) + 1)
    cost = np.full((len(n), most), np.inf)
    inner = (np.arange(most) > 0) & (np.arange(most) < n[:, None] - 1)
    at = grid[inner]
    cost[inner] = costs(at, at - 1, at + 1)
    flat, rows = cost.ravel(), np.arange(len(n))
    head, tail = grid[:, 0], grid[rows, n - 1]
    gone = np.full(len(t), np.inf)
    while len(rows):
        i = cost[rows].argmin(axis=1) + rows * most if len(rows) < len(n) else cost.argmin(axis=1) + rows * most
        c = flat[i]
        on = c <= eps
        if not on.all():
            rows, i, c = rows[on], i[on], c[on]
        gone[i], flat[i] = c, np.inf
        a, b = before[i], after[i]
        after[a], before[b] = b, a
        for k, ends in ((a, head), (b, tail)):
            carried[k] = np.maximum(carried[k], c)
            free = k != ends[rows]
            k = k[free]
            flat[k] = costs(k, before[k], after[k])
    fine = np.arange(most) < n[:, None]
    out[place[fine]] = gone[grid[fine]]


def _sized(f: Flat, kept: np.ndarray, path: np.ndarray, p: CodecParams, encoded: bool) -> list[dict]:
    """simplify.coded, or without the integer coder, of each track by its path: kept samples' times and positions there (axes x points kept)."""
    m, dim = len(f.n), len(f.axes)
    index = np.flatnonzero(kept)
    own, times = f.own[index], f.t[index]
    many = np.bincount(own, minlength=m)
    if encoded:
        step = p.eps_p / dim**0.5
        codes = N.quantize(path, step)
        clock = (np.rint(times * 1e6).astype(np.int64) + f.first[own] + p.eps_t // 2) // p.eps_t
        bits = np.zeros(len(index), np.int64)
        for x in (clock, *codes):
            moves = x.copy()
            same = own[1:] == own[:-1]
            moves[1:][same] -= x[:-1][same]
            bits += N.bit_cost(N.zigzag(moves), p.l)
        size = -(-np.add.reduceat(bits, np.cumsum(many) - many) // 8)
        path = N.dequantize(codes, step)
    else:
        size = 8 * (dim + 1) * many
    segment = np.cumsum(kept) - 1
    after = np.minimum(segment + 1, len(index) - 1)
    far = 0.0
    with np.errstate(divide="ignore", invalid="ignore"):
        passed = f.t - times[segment]
        for x, y in zip(path, f.axes, strict=True):
            slope = np.diff(x, append=0.0) / np.diff(times, append=0.0)
            d = np.where(kept, x[segment], slope[segment] * passed + x[segment]) - y
            far = far + d * d
    error = np.sqrt(far)
    worst, total = np.maximum.reduceat(error, f.begin), np.add.reduceat(error, f.begin)
    return [{"n_corr": 0, "kept": k, "max_sed": x, "sum_sed": s, "bytes": b} for k, x, s, b in zip(many.tolist(), worst.tolist(), total.tolist(), size.tolist(), strict=True)]


def simplified(method: str, tracks: list[Track], variants: list[tuple[CodecParams, bool]], m: int = 16) -> list[list[dict]]:
    """For each track, with each (parameters, whether by the integer coder): simplify.simplified and no corrections."""
    f = Flat(tracks)
    bounds = [p.eps - p.eps_p if encoded else p.eps for p, encoded in variants]
    made: list[list[dict]] = []
    if method == "pq":
        costs = queue(f, max(bounds))
        for (p, encoded), bound in zip(variants, bounds, strict=True):
            kept = costs > bound
            made.append(_sized(f, kept, f.axes[:, kept], p, encoded))
    else:
        weak, some = method == "cone_weak", max(1, HELD // len(f.t))
        for a in range(0, len(bounds), some):
            flags, paths = cones(f, bounds[a : a + some], weak, m)
            for b, (p, encoded) in enumerate(variants[a : a + some]):
                made.append(_sized(f, flags[b], (f.axes if paths is None else paths[:, b])[:, flags[b]], p, encoded))
    return [list(x) for x in zip(*made, strict=True)]
