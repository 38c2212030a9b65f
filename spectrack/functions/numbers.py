"""Quantizer, delta and integer codes: as numpy functions and as Spark columns."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

# ---- numpy


def quantize(x, e: float) -> np.ndarray:
    """The multiple of 2e nearest to x, as an integer; the error lies in [-e, e)."""
    return np.floor(np.asarray(x, float) / (2 * e) + 0.5).astype(np.int64)


def dequantize(code, e: float) -> np.ndarray:
    return np.asarray(code) * (2 * e)


def delta(codes: np.ndarray) -> np.ndarray:
    return np.diff(codes, prepend=np.zeros_like(codes[:1]), axis=0)


def undelta(steps: np.ndarray) -> np.ndarray:
    return np.cumsum(steps, axis=0)


def zigzag(n) -> np.ndarray:
    n = np.asarray(n, np.int64)
    return np.where(n >= 0, 2 * n, -2 * n - 1)


def unzigzag(u) -> np.ndarray:
    u = np.asarray(u, np.int64)
    return np.where(u % 2 == 0, u // 2, -(u + 1) // 2)


def zigzag1(n) -> np.ndarray:
    """Zero-free: every code starts with a binary one."""
    n = np.asarray(n, np.int64)
    return np.where(n >= 0, 2 * n + 1, -2 * n)


def unzigzag1(u) -> np.ndarray:
    u = np.asarray(u, np.int64)
    return np.where(u % 2 == 1, u // 2, -(u // 2))


def bit_length(u) -> np.ndarray:
    """Binary digits, 1 for zero."""
    u = np.asarray(u, np.int64)
    if u.size and u.max() < 1 << 53:  # exact as doubles, whose exponent says it
        return np.maximum(np.frexp(u.astype(float))[1], 1).astype(np.int64)
    out = np.ones(u.shape, np.int64)
    for s in (32, 16, 8, 4, 2, 1):
        more = u >> s > 0
        out += s * more
        u = np.where(more, u >> s, u)
    return out


def bit_cost(u, l: int, elide: bool = False) -> np.ndarray:  # noqa: E741
    """Bits of the variable-length code with chunks of l bits and a flag each."""
    return -(-bit_length(u) // l) * (l + 1) - int(elide)


SLICE = 2_000_000  # bits


def spread(u: np.ndarray, l, n: np.ndarray) -> np.ndarray:  # noqa: E741
    """The first n bits of each code, one byte each: low chunk first, its flag (more follow) before its l bits."""
    ends = np.cumsum(n)
    if len(n) and ends[-1] > SLICE and len(n) > 1:  # a few arrays of eight bytes a bit are held at a time
        cuts = [0, *np.searchsorted(ends, np.arange(SLICE, int(ends[-1]), SLICE)).tolist(), len(n)]
        cuts = sorted(set(cuts))
        pairs = zip(cuts, cuts[1:], strict=False)
        return np.concatenate([_spread(u[a:b], l[a:b] if isinstance(l, np.ndarray) else l, n[a:b]) for a, b in pairs])
    return _spread(u, l, n)


def _spread(u: np.ndarray, l, n: np.ndarray) -> np.ndarray:  # noqa: E741
    code = np.repeat(np.arange(len(u)), n)
    l = l[code] if isinstance(l, np.ndarray) else l  # noqa: E741
    place = np.arange(len(code)) - np.repeat(np.cumsum(n) - n, n)
    chunk = place // (l + 1)
    inside = place - chunk * (l + 1)
    held = u[code]
    # beyond the highest digit there are zeros
    bit = held >> np.minimum(chunk * l + l - inside, 63) & 1
    more = held >> np.minimum(chunk * l + l, 63) > 0
    return np.where(inside == 0, more, bit).astype(np.uint8)


def to_bits(u, l: int, elide: bool = False) -> np.ndarray:  # noqa: E741
    """The codes' bits, one byte each: low chunk first, its flag (more follow) before its l bits."""
    u = np.asarray(u, np.int64).ravel()
    return spread(u, l, bit_cost(u, l, elide))


def codes_of(bits: np.ndarray, l: int) -> tuple[np.ndarray, np.ndarray]:  # noqa: E741
    """All codes from the first bit on that end, and the position behind each."""
    whole = bits[: len(bits) // (l + 1) * (l + 1)].reshape(-1, l + 1)
    last = np.flatnonzero(whole[:, 0] == 0)
    whole = whole[: last[-1] + 1]
    value = whole[:, 1:].astype(np.int64) @ (1 << np.arange(l - 1, -1, -1, dtype=np.int64))
    first = np.concatenate(([0], last[:-1] + 1))
    place = np.arange(len(whole)) - np.repeat(first, last - first + 1)
    return np.add.reduceat(value << np.minimum(place * l, 62), first), (last + 1) * (l + 1)


def from_bits(bits: np.ndarray, at: int, n: int, l: int, elide: bool = False) -> tuple[np.ndarray, int]:  # noqa: E741
    """n codes from position `at`, and the position behind them."""
    if n == 0:
        return np.zeros(0, np.int64), at
    if elide:  # l is 1 and the final one of each code was left out: flag and bit by turns, then a flag of zero
        data = bits[at : at + 128 * n]
        stop = np.where(data == 0, np.arange(len(data)), len(data) + 1)
        for odd in (0, 1):  # the next zero flag from here on
            stop[odd::2] = np.minimum.accumulate(stop[odd::2][::-1])[::-1]
        last, start, first = stop.tolist(), 0, np.empty(n, np.int64)
        for i in range(n):
            first[i] = start
            start = last[start] + 1
        m = (stop[first] - first) // 2
        where = np.repeat(first + 1, m) + 2 * (place := np.arange(m.sum()) - np.repeat(np.cumsum(m) - m, m))
        low = np.zeros(n, np.int64)
        np.add.at(low, np.repeat(np.arange(n), m), data[where].astype(np.int64) << place)
        return low | 1 << m, at + start
    whole = bits[at : at + (len(bits) - at) // (l + 1) * (l + 1)].reshape(-1, l + 1)
    last = np.flatnonzero(whole[:, 0] == 0)[:n]
    whole = whole[: last[-1] + 1]
    value = whole[:, 1:].astype(np.int64) @ (1 << np.arange(l - 1, -1, -1, dtype=np.int64))
    first = np.concatenate(([0], last[:-1] + 1))
    place = np.arange(len(whole)) - np.repeat(first, last - first + 1)
    return np.add.reduceat(value << np.minimum(place * l, 62), first), at + len(whole) * (l + 1)


# ---- columns


def q(x: Column, e: Column | float) -> Column:
    return F.floor(x / (2 * (F.lit(e) if isinstance(e, float) else e)) + 0.5)


def zz(n: Column) -> Column:
    return F.when(n >= 0, 2 * n).otherwise(-2 * n - 1)


def unzz(u: Column) -> Column:
    return F.when(u % 2 == 0, F.floor(u / 2)).otherwise(-F.floor((u + 1) / 2))


def zz1(n: Column) -> Column:
    return F.when(n >= 0, 2 * n + 1).otherwise(-2 * n)


def unzz1(u: Column) -> Column:
    return F.when(u % 2 == 1, F.floor(u / 2)).otherwise(-F.floor(u / 2))


def bits(u: Column, l: Column | int) -> Column:  # noqa: E741
    l = F.lit(l) if isinstance(l, int) else l  # noqa: E741
    return (F.ceil(F.length(F.bin(u)) / l) * (l + 1)).cast("long")
