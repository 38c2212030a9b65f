"""Line simplifiers bounded in synchronized distance, for one track in memory.

Times are seconds as doubles (from the track's start), positions n x dim. Results are the indices kept,
or for the weak cone the times and invented positions."""

from __future__ import annotations

import heapq
import math
from functools import lru_cache
from itertools import combinations

import numpy as np

from spectrack.functions import numbers as N
from spectrack.functions.params import CodecParams


@lru_cache(maxsize=16)
def _polygon(m: int) -> tuple[np.ndarray, float, np.ndarray]:
    """Edge normals of the m-gon, its inner radius, and the weights that prove emptiness.

    Half-planes n_i v <= h_i have no common point just if two opposite or three spanning normals with positive
    weights summing to a zero vector have a negative weighted sum of h; the rows list all such weights."""
    angle = 2 * np.pi * np.arange(m) / m
    normals = np.column_stack((np.cos(angle), np.sin(angle)))
    rows = []
    for i, j in combinations(range(m), 2):
        if (j - i) * 2 == m:
            row = np.zeros(m)
            row[[i, j]] = 0.5
            rows.append(row)
    for i, j, k in combinations(range(m), 3):
        if max(j - i, k - j, m - k + i) * 2 < m:
            w = np.linalg.solve(np.vstack((normals[[i, j, k]].T, np.ones(3))), [0, 0, 1])
            row = np.zeros(m)
            row[[i, j, k]] = w
            rows.append(row)
    return normals, float(np.cos(np.pi / m)), np.array(rows)


def _reach(t, pos, start_t, start, first, radius, m):
    """How far one constant velocity from the anchor stays within radius of each sample: (index of the first
    sample that leaves nothing, or n; supports after the last one that left something)."""
    normals, inner, proofs = _polygon(m)
    h, at, size, n = np.full(m, np.inf), first, 16, len(t)
    while at < n:
        upto = min(n, at + size)
        dt = (t[at:upto] - start_t)[:, None]
        support = (pos[at:upto] - start) / dt @ normals.T + radius * inner / dt
        all_h = np.minimum(np.minimum.accumulate(support, axis=0), h)
        empty = (all_h @ proofs.T).min(axis=1) < 0
        if empty.any():
            j = int(empty.argmax())
            return at + j, h if j == 0 else all_h[j - 1]
        h, at, size = all_h[-1], upto, min(size * 2, 4096)
    return n, h


def cone_strong(t, pos, eps: float, m: int = 16) -> np.ndarray:
    """Indices of a subset of the samples. With half the radius both a sample and the segment's end stay
    within eps/2 of one motion, so the segment between them stays within eps of every sample."""
    n, kept, anchor = len(t), [0], 0
    while anchor < n - 1:
        stop, _ = _reach(t, pos, t[anchor], pos[anchor], anchor + 1, eps / 2, m)
        anchor = max(anchor + 1, stop - 1)
        kept.append(anchor)
    return np.array(kept)


def _centre(h: np.ndarray, m: int) -> np.ndarray:
    """Centroid of the polygon that the half-planes leave."""
    normals, _, _ = _polygon(m)
    finite = np.abs(h[np.isfinite(h)]).max(initial=1.0)
    big = 4 * float(finite) + 1
    points = [(-big, -big), (big, -big), (big, big), (-big, big)]
    for (a, b), limit in zip(normals.tolist(), h.tolist(), strict=True):
        if limit == math.inf:
            continue
        inside = [a * x + b * y - limit for x, y in points]
        if max(inside) <= 0:
            continue
        cut = []
        for i, ((x, y), d) in enumerate(zip(points, inside, strict=True)):
            e = inside[i - 1]
            if (d <= 0) != (e <= 0):
                share, (u, v) = e / (e - d), points[i - 1]
                cut.append((u + (x - u) * share, v + (y - v) * share))
            if d <= 0:
                cut.append((x, y))
        if len(cut) < 3:
            return np.mean(cut or points, axis=0)
        points = cut
    n = len(points)
    x0, y0 = sum(x for x, _ in points) / n, sum(y for _, y in points) / n
    whole = cx = cy = 0.0
    for i, (x, y) in enumerate(points):
        u, v = points[i - 1]
        area = (u - x0) * (y - y0) - (v - y0) * (x - x0)
        whole += area
        cx += (u + x - 2 * x0) * area
        cy += (v + y - 2 * y0) * area
    if abs(whole) < 1e-300:
        return np.array([x0, y0])
    return np.array([x0 + cx / (3 * whole), y0 + cy / (3 * whole)])


def cone_weak(t, pos, eps: float, m: int = 16) -> tuple[np.ndarray, np.ndarray]:
    """(times, positions) of a path that may go through invented points; the full radius holds since each
    segment is one of the motions that pass all its samples."""
    n, times, path = len(t), [t[0]], [np.array(pos[0])]
    i = 1
    while i < n:
        stop, h = _reach(t, pos, times[-1], path[-1], i, eps, m)
        if stop == i:  # cannot happen at a shared sample; keep the sample itself
            times.append(t[i])
            path.append(np.array(pos[i]))
            i += 1
            continue
        v = _centre(h, m)
        path.append(path[-1] + v * (t[stop - 1] - times[-1]))
        times.append(t[stop - 1])
        i = stop
    return np.array(times), np.array(path)


def pq(t, pos, eps: float | None = None, ratio: float | None = None) -> np.ndarray:
    """Indices left after removing samples in order of least cost: the distance to the segment between
    the neighbours, plus the largest cost carried over from removed neighbours. Stops above eps, or when ratio of
    the samples is left."""
    return np.flatnonzero(pq_costs(t, pos, eps, ratio) == np.inf)


def pq_costs(t, pos, eps: float | None = None, ratio: float | None = None) -> np.ndarray:
    """What each removed sample cost, infinity for those left. Costs never fall from one removal to the next, since a
    neighbour carries them on, so the samples left by a smaller bound are those that cost more than it."""
    n = len(t)
    # plain lists: single items of arrays cost several times as much
    left, right = list(range(-1, n - 1)), list(range(1, n + 1))
    carried, alive, version = [0.0] * n, [True] * n, [0] * n
    x, t = list(map(tuple, np.asarray(pos, float).tolist())), np.asarray(t).tolist()

    def cost(i: int) -> float:
        a, b = left[i], right[i]
        s = (t[i] - t[a]) / (t[b] - t[a])
        return sum((p - (q + (r - q) * s)) ** 2 for p, q, r in zip(x[i], x[a], x[b], strict=True)) ** 0.5 + carried[i]

    gone = [math.inf] * n
    heap = [(cost(i), i, 0) for i in range(1, n - 1)]
    heapq.heapify(heap)
    rest, least = n, max(2, int(np.ceil(n * ratio))) if ratio is not None else 2
    while heap and rest > least:
        c, i, v = heapq.heappop(heap)
        if not alive[i] or v != version[i]:
            continue
        if eps is not None and c > eps:
            break
        alive[i], gone[i] = False, c
        rest -= 1
        a, b = left[i], right[i]
        right[a], left[b] = b, a
        for k in (a, b):
            carried[k] = max(carried[k], c)
            if 0 < k < n - 1:
                version[k] += 1
                heapq.heappush(heap, (cost(k), k, version[k]))
    return np.array(gone)


def opening_window(t, pos, eps: float) -> np.ndarray:
    """The longest segment from each kept sample that rechecking every sample allows growing to: quadratic, for tests."""
    n, kept, a = len(t), [0], 0
    while a < n - 1:
        b = a + 1
        while b + 1 < n:
            share = ((t[a : b + 2] - t[a]) / (t[b + 1] - t[a]))[:, None]
            if np.linalg.norm(pos[a] + (pos[b + 1] - pos[a]) * share - pos[a : b + 2], axis=1).max() > eps:
                break
            b += 1
        kept.append(b)
        a = b
    return np.array(kept)


def reconstruct(kept_t, kept, clock) -> np.ndarray:
    """Positions at the clock's times on the path."""
    return np.column_stack([np.interp(clock, kept_t, kept[:, d]) for d in range(kept.shape[1])])


def path_of(method: str, t, pos, eps: float | None, m: int = 16, ratio: float | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(times, positions) of the simplified path."""
    if method == "identity" or len(t) < 3 and method != "cone_weak" or len(t) == 1:
        return t, pos.copy()
    if method == "cone_weak":
        return cone_weak(t, pos, eps, m)
    run = {"cone_strong": lambda: cone_strong(t, pos, eps, m), "pq": lambda: pq(t, pos, None if ratio else eps, ratio), "opening_window": lambda: opening_window(t, pos, eps)}
    index = run[method]()
    return t[index], pos[index]


def kept(method: str, t_us: np.ndarray, pos: np.ndarray, eps: float | None, m: int = 16, ratio: float | None = None) -> tuple[np.ndarray, np.ndarray]:
    """The path with its times in microseconds."""
    times, path = path_of(method, (t_us - t_us[0]) / 1e6, pos, eps, m, ratio)
    return np.rint(times * 1e6).astype(np.int64) + t_us[0], path


def coded(method: str, t_us: np.ndarray, pos: np.ndarray, p: CodecParams, lengths: list[int], m: int = 16, path: tuple[np.ndarray, np.ndarray] | None = None) -> list[dict]:
    """Run a baseline on a track with the integer coder: kept points, errors at the samples, and bytes with each chunk
    length, which changes nothing else.

    The path is sought within eps - eps_p, unless it is given, and its points are rounded within eps_p, so eps holds; times
    and points go through the same integer coder as the spectral codec's ends."""
    step = p.eps_p / pos.shape[1] ** 0.5
    t = (t_us - t_us[0]) / 1e6
    times, path = path or path_of(method, t, pos, p.eps - p.eps_p, m)
    codes = N.quantize(path, step)
    clock = N.zigzag(N.delta((np.rint(times * 1e6).astype(np.int64) + t_us[0] + p.eps_t // 2) // p.eps_t))
    moves = N.zigzag(N.delta(codes))
    same = _measured(times, N.dequantize(codes, step), t, pos)
    return [{**same, "bytes": -(-(int(N.bit_cost(clock, k).sum()) + int(N.bit_cost(moves, k).sum())) // 8)} for k in lengths]


def queued(t_us: np.ndarray, pos: np.ndarray, ps: list[CodecParams]) -> list[dict]:
    """coded() by the priority queue with each of the parameters, from one run down to the widest bound."""
    t = (t_us - t_us[0]) / 1e6
    if len(t) < 3:
        return [coded("pq", t_us, pos, p, [p.l])[0] for p in ps]
    costs = pq_costs(t, pos, max(p.eps - p.eps_p for p in ps))
    return [coded("pq", t_us, pos, p, [p.l], path=(t[left], pos[left]))[0] for p in ps for left in [costs > p.eps - p.eps_p]]


def _measured(times, path, t, pos) -> dict:
    error = np.linalg.norm(reconstruct(times, path, t) - pos, axis=1)
    return {"kept": len(times), "max_sed": float(error.max(initial=0)), "sum_sed": float(error.sum())}


def simplified(method: str, t_us: np.ndarray, pos: np.ndarray, p: CodecParams, encoded: bool = True, m: int = 16) -> dict:
    """Run a baseline on a track: kept points, bytes, and errors at the samples; with the integer coder or as plain doubles."""
    if encoded:
        return coded(method, t_us, pos, p, [p.l], m)[0]
    t = (t_us - t_us[0]) / 1e6
    times, path = path_of(method, t, pos, p.eps, m)
    return {**_measured(times, path, t, pos), "bytes": 8 * (pos.shape[1] + 1) * len(times)}


class Cone:
    """The cone simplifiers a sample at a time, for streams: the state is an anchor, the sample before and the
    supports of the velocities still allowed."""

    def __init__(self, eps: float, weak: bool, m: int = 16, state: list | None = None):
        self.radius, self.weak, self.m = (eps if weak else eps / 2), weak, m
        self.anchor, self.last, self.h = state if state is not None else (None, None, None)

    @property
    def state(self) -> list:
        """Plain lists, which JSON can hold."""
        return [self.anchor, self.last, self.h]

    def _allowed(self, t: int, pos: list[float], h: list[float] | None) -> list[float] | None:
        """The supports with this sample; None if they leave nothing."""
        normals, inner, proofs = _polygon(self.m)
        dt = (t - self.anchor[0]) / 1e6
        now = (np.subtract(pos, self.anchor[1]) / dt) @ normals.T + self.radius * inner / dt
        now = now if h is None else np.minimum(now, h)
        return None if (proofs @ now).min() < 0 else now.tolist()

    def _close(self) -> tuple[int, list[float]]:
        """The point at which the open segment ends: the sample before, or where the polygon's centre leads by then."""
        t, pos = self.last
        if self.weak:
            pos = (np.array(self.anchor[1]) + _centre(np.array(self.h), self.m) * ((t - self.anchor[0]) / 1e6)).tolist()
        return t, pos

    def add(self, t: int, pos: list[float]) -> list[tuple[int, list[float]]]:
        """Points of the path that are settled by this sample, which comes after all others."""
        if self.anchor is None:
            self.anchor = self.last = (t, pos)
            return [(t, pos)]
        now, out = self._allowed(t, pos, self.h), []
        if now is None and self.h is not None:
            self.anchor, self.h = self._close(), None
            out.append(self.anchor)
            now = self._allowed(t, pos, None)
        self.last, self.h = (t, pos), now
        if now is None:  # not even one sample fits: it becomes a point itself
            self.anchor, self.h = self.last, None
            out.append(self.anchor)
        return out

    def finish(self) -> list[tuple[int, list[float]]]:
        """The last point of the path."""
        return [] if self.anchor is None or self.last[0] == self.anchor[0] else [self._close()]
