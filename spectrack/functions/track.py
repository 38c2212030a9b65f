"""One track in memory: fragments, resampling, encoding, decoding, corrections, container bytes.

The encoder's check and the decoder run the same function on the same integers, so what was checked
is what comes back, whichever of the original times it is asked for. Times are microseconds, positions an
array n x dim."""

from __future__ import annotations

import math
import struct
from dataclasses import dataclass, field

import numpy as np

from spectrack.functions import numbers as N
from spectrack.functions.params import DECODER, CodecParams, derive
from spectrack.functions.spectral import dct, idct

SLACK = 1 - 1e-9  # of the bound, for the last bits of sums
SECTIONS = ("header", "fragments", "anchors", "ends", "lengths", "coefficients", "corrections", "outliers")


def time_code(t: np.ndarray, eps_t: int) -> np.ndarray:
    return (2 * np.asarray(t, np.int64) + eps_t) // (2 * eps_t)


def fragment_starts(t: np.ndarray, pos: np.ndarray, p: CodecParams) -> np.ndarray:
    """Indices at which a fragment starts: after a step too fast or a pause too long for the fragment so far."""
    n = len(t)
    gap = np.diff(t)
    breaks = np.zeros(n, bool)
    breaks[:1] = True
    if p.v_max is not None:
        breaks[1:] = np.linalg.norm(np.diff(pos, axis=0), axis=1) > gap / 1e6 * p.v_max
    first = p.default_dt or (int(np.median(gap)) if len(gap) else 1)
    # only pauses over b_s times the least possible mean can be breaks
    least = min(first, int(gap.min()) if len(gap) else first)
    if p.gap_mean == "inclusive" and len(gap):
        least = min(first, least)
    suspects = np.flatnonzero(breaks[1:] | (gap > p.b_s * least)) + 1
    start = 0
    for j in suspects.tolist():
        k = j - start
        if k == 1:
            mean = first
        elif p.gap_mean == "inclusive":
            mean = (t[j] - t[start]) / k
        else:
            mean = (t[j - 1] - t[start]) / (k - 1)
        if breaks[j] or t[j] - t[j - 1] > p.b_s * mean:
            breaks[j] = True
            start = j
    return np.flatnonzero(breaks)


def common_interval(t: np.ndarray, starts: np.ndarray, eps_t: int) -> int:
    """Time spans over point counts of the fragments of more than two points, in steps of eps_t."""
    ends = np.append(starts[1:], len(t))
    long = ends - starts > 2
    if not long.any():
        return eps_t
    span = int((t[ends[long] - 1] - t[starts[long]]).sum())
    count = int((ends - starts)[long].sum())
    return eps_t * max(1, math.floor(span / (eps_t * count) + 0.5))


@dataclass
class Encoded:
    """The integers of a container, by section."""

    dim: int
    dt: int
    starts: np.ndarray  # time code of each fragment's first point
    counts: np.ndarray  # uniform samples of each fragment
    anchors: np.ndarray  # fragments x dim
    ends: np.ndarray  # blocks x dim
    lengths: np.ndarray  # blocks x dim: stored coefficients
    coefficients: np.ndarray
    corr_t: np.ndarray
    corr: np.ndarray
    out_t: np.ndarray
    out: np.ndarray
    uniform: bool = False
    stats: dict = field(default_factory=dict)


def _grid(counts: np.ndarray, b: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For fragments of these many samples: each block's fragment, first sample, and length in velocities."""
    per = -(-(counts - 1) // b)
    frag = np.repeat(np.arange(len(counts)), per)
    first_block = np.repeat(np.cumsum(per) - per, per)
    within = np.arange(len(frag)) - first_block
    length = np.minimum(b, counts[frag] - 1 - within * b)
    offset = np.cumsum(counts) - counts
    return frag, offset[frag] + within * b, length


def _size(p: CodecParams, counts: np.ndarray) -> int:
    return p.b_s if p.blocks else int(max(counts.max(initial=2) - 1, 1))


def _stored(at: np.ndarray, lengths: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray]:
    """Where the k-th coefficient of each block and axis stands in the list of all, and whether there is one."""
    k = np.arange(most)
    return at[:, :, None] + k, k < lengths[:, :, None]


def decode_uniform(e: Encoded, p: CodecParams) -> np.ndarray:
    """Samples of all fragments, one after the other."""
    dim = e.dim
    out = np.zeros((int(e.counts.sum()), dim))
    offset = np.cumsum(e.counts) - e.counts
    anchors = N.dequantize(e.anchors, p.eps_p)
    out[offset] = anchors
    frag, first, length = _grid(e.counts, _size(p, e.counts))
    if not len(frag):
        return out
    step = 2 * p.eps_p / math.sqrt(dim)
    total = np.cumsum(e.ends, axis=0)
    new = np.concatenate(([True], frag[1:] != frag[:-1]))
    before = np.where(new[:, None], 0, np.roll(total, 1, axis=0))
    base = np.maximum.accumulate(np.where(new, np.arange(len(frag)), 0))
    zero = (total - e.ends)[base]
    end = anchors[frag] + step * (total - zero)
    start = np.where(new[:, None], anchors[frag], anchors[frag] + step * (before - zero))
    at = (np.cumsum(e.lengths.ravel()) - e.lengths.ravel()).reshape(-1, dim)
    for size in np.unique(length).tolist():
        rows = np.flatnonzero(length == size)
        most = int(e.lengths[rows].max(initial=0))
        codes = np.zeros((len(rows), dim, most + 1))
        place, has = _stored(at[rows], e.lengths[rows], most)
        # the 0th is stored for positions only
        (codes[:, :, :most] if p.positions else codes[:, :, 1:])[has] = e.coefficients[place[has]]
        v = idct((codes * (2 * p.eps_f)).reshape(-1, most + 1), size).reshape(len(rows), dim, size)
        if p.positions:
            s = start[rows][:, :, None] + (end - start)[rows][:, :, None] * (np.arange(size) / size) + v
            s = np.concatenate((s, end[rows][:, :, None]), axis=2)[:, :, 1:]
        else:
            mean = (end - start)[rows][:, :, None] / size
            s = start[rows][:, :, None] + np.cumsum(v + mean, axis=2)
        where = first[rows][:, None] + 1 + np.arange(size)
        out[where] = s.transpose(0, 2, 1)
    # a block ends where its decoded end is
    out[first + length] = end
    return out


def encode_uniform(x: np.ndarray, counts: np.ndarray, p: CodecParams) -> tuple[np.ndarray, ...]:
    """(anchors, ends, lengths, coefficients) of uniform samples x of fragments with these counts."""
    dim = x.shape[1]
    offset = np.cumsum(counts) - counts
    anchors = N.quantize(x[offset], p.eps_p)
    frag, first, length = _grid(counts, _size(p, counts))
    start, end = x[first], x[first + length]
    e_d = p.eps_p / math.sqrt(dim)
    if p.ends == "closed":
        code = N.quantize(end - N.dequantize(anchors, p.eps_p)[frag], e_d)
        new = np.concatenate(([True], frag[1:] != frag[:-1])) if len(frag) else np.zeros(0, bool)
        ends = code - np.where(new[:, None], 0, np.roll(code, 1, axis=0))
    else:
        ends = N.quantize(end - start, e_d)
    lengths = np.zeros((len(frag), dim), np.int64)
    parts: list[tuple[np.ndarray, np.ndarray]] = []
    for size in np.unique(length).tolist():
        rows = np.flatnonzero(length == size)
        keep = p.kept(size)
        s = x[first[rows][:, None] + np.arange(size + 1)].transpose(0, 2, 1)  # rows x dim x size+1
        mean = (s[:, :, -1:] - s[:, :, :1]) / size
        if p.positions:
            v = s[:, :, :-1] - s[:, :, :1] - mean * np.arange(size)
        else:
            v = np.diff(s, axis=2) - mean
        c = N.quantize(dct(v.reshape(-1, size), keep), p.eps_f).reshape(len(rows), dim, keep)
        if not p.positions:
            c = c[:, :, 1:]
        else:
            c[:, :, 0] = N.quantize(2 * v.sum(axis=2), p.eps_f)
        last = np.where(c != 0, np.arange(1, c.shape[2] + 1), 0).max(axis=2, initial=0)
        lengths[rows] = last
        parts.append((rows, c))
    at = (np.cumsum(lengths.ravel()) - lengths.ravel()).reshape(-1, dim)
    flat = np.zeros(int(lengths.sum()), np.int64)
    for rows, c in parts:
        place, has = _stored(at[rows], lengths[rows], c.shape[2])
        flat[place[has]] = c[has]
    return anchors, ends, lengths, flat


def align(e: Encoded, samples: np.ndarray, clock: np.ndarray, p: CodecParams) -> np.ndarray:
    """Positions at the clock's times by interpolation between the uniform samples of each time's fragment; a time on
    a sample belongs to the interval before it, one beyond a fragment's samples to the nearest of them.

    Fragments start where the container says, so a time's position doesn't depend on which others are asked for."""
    f = np.maximum(np.searchsorted(e.starts, time_code(clock, p.eps_t), "right") - 1, 0)
    rest = clock - e.starts[f] * p.eps_t
    j = np.clip(-(-rest // e.dt) - 1, 0, e.counts[f] - 2)
    share = np.clip((rest - j * e.dt) / e.dt, 0.0, 1.0)[:, None]
    at = (np.cumsum(e.counts) - e.counts)[f] + j
    return samples[at] + (samples[at + 1] - samples[at]) * share


def _found(keys: np.ndarray, code: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Which codes are among the ordered keys, and their places there."""
    at = np.minimum(np.searchsorted(keys, code), max(0, len(keys) - 1))
    hit = keys[at] == code if len(keys) else np.zeros(len(code), bool)
    return hit, at[hit]


def decode(e: Encoded, clock: np.ndarray, p: CodecParams, samples: np.ndarray | None = None) -> np.ndarray:
    """Positions at these times, corrections and outliers applied: any of the original times, in any order. `samples`
    are those of decode_uniform, for a caller that asks more than once."""
    clock = np.asarray(clock, np.int64)
    code = time_code(clock, p.eps_t)
    if len(e.starts):
        out = align(e, decode_uniform(e, p) if samples is None else samples, clock, p)
    else:
        out = np.full((len(clock), e.dim), np.nan)
    hit, at = _found(e.out_t, code)
    out[hit] = e.out[at] * (1.0 if p.integer_input else 2 * p.eps / math.sqrt(e.dim))
    hit, at = _found(e.corr_t, code)
    out[hit] += e.corr[at] * (2 * p.eps_p / math.sqrt(e.dim))
    return out


def _exactly(t: np.ndarray, pos: np.ndarray, p: CodecParams) -> Encoded:
    """Whole numbers: differences along time of the numbers themselves."""
    whole = np.rint(pos)
    if (whole != pos).any() or np.abs(whole).max(initial=0) >= 2.0**53:
        raise ValueError("integer_input takes whole numbers below 2**53")
    dim, none = pos.shape[1], np.zeros(0, np.int64)
    empty = np.zeros((0, dim), np.int64)
    stats = {"error_points": 0, "max_sed": 0.0, "sum_sed": 0.0, "outliers": len(t), "fragments": 0, "blocks": 0}
    return Encoded(dim, p.eps_t, none, none, empty, empty, empty, none, none, empty, time_code(t, p.eps_t), whole.astype(np.int64), stats=stats)


def encode(t: np.ndarray, pos: np.ndarray, p: CodecParams) -> Encoded:
    """Fragments, uniform samples, blocks, then the points whose decoded position is off by more than eps."""
    t, pos = np.asarray(t, np.int64), np.asarray(pos, float)
    n, dim = pos.shape
    if p.integer_input:
        return _exactly(t, pos, p)
    gap = np.diff(t)
    # the container counts time in steps of eps_t
    uniform = n > 2 and p.v_max is None and bool((gap == gap[0]).all()) and gap[0] % p.eps_t == 0 and t[0] % p.eps_t == 0
    starts = np.zeros(1, np.int64) if uniform else fragment_starts(t, pos, p)
    dt = int(gap[0]) if uniform else common_interval(t, starts, p.eps_t)
    if p.dt_scale != 1.0 and not uniform:
        dt = p.eps_t * max(1, math.floor(dt * p.dt_scale / p.eps_t + 0.5))
    ends = np.append(starts[1:], n)
    long = ends - starts > 2
    single = np.concatenate([np.arange(a, b) for a, b in zip(starts[~long], ends[~long], strict=True)] or [np.zeros(0, np.int64)]).astype(np.int64)
    counts, samples = [], []
    for a, b in zip(starts[long].tolist(), ends[long].tolist(), strict=True):
        if uniform:
            counts.append(n)
            samples.append(pos)
            continue
        m = -(-int(t[b - 1] - t[a]) // dt) + 1
        at = np.minimum(t[a] + dt * np.arange(m), t[b - 1])
        i = np.clip(np.searchsorted(t[a:b], at, "left") - 1, 0, b - a - 2) + a
        share = ((at - t[i]) / (t[i + 1] - t[i]))[:, None]
        counts.append(m)
        samples.append(pos[i] + (pos[i + 1] - pos[i]) * share)
    counts = np.array(counts, np.int64)
    x = np.concatenate(samples) if samples else np.zeros((0, dim))
    empty = np.zeros((0, dim), np.int64)
    anchors, end_codes, lengths, coefficients = encode_uniform(x, counts, p) if len(counts) else (empty, empty, empty, np.zeros(0, np.int64))
    code = time_code(t, p.eps_t)
    out = N.quantize(pos[single], p.eps / math.sqrt(dim)) if len(single) else empty
    e = Encoded(dim, dt, code[starts[long]], counts, anchors, end_codes, lengths, coefficients, np.zeros(0, np.int64), empty, code[single], out, uniform)
    back = decode(e, t, p)
    error = np.linalg.norm(back - pos, axis=1)
    wrong = np.flatnonzero(error > p.eps * SLACK)
    e.stats["error_points"] = len(wrong)
    if p.validate and len(wrong):
        e.corr_t, e.corr = code[wrong], N.quantize(pos[wrong] - back[wrong], p.eps_p / math.sqrt(dim))
        back[wrong] += e.corr * (2 * p.eps_p / math.sqrt(dim))
        error = np.linalg.norm(back - pos, axis=1)
    e.stats |= {"max_sed": float(error.max(initial=0)), "sum_sed": float(error.sum()), "outliers": len(single), "fragments": len(counts), "blocks": len(end_codes)}
    return e


# ---- container


def _sections(e: Encoded, p: CodecParams) -> list[tuple[str, np.ndarray, int, bool]]:
    """(section, unsigned codes, chunk length, elided) in the order they are written."""
    maps = N.zigzag1 if p.zero_free else N.zigzag
    elide = p.zero_free and p.l_freq == 1
    zz, l = N.zigzag, p.l  # noqa: E741
    return [
        ("header", np.array([e.dt // p.eps_t, len(e.starts)]), l, False),
        ("outliers", np.array([len(e.out_t)]), l, False),
        ("outliers", zz(N.delta(e.out_t)), l, False),
        ("outliers", zz(N.delta(e.out)), l, False),
        ("corrections", np.array([len(e.corr_t)]), l, False),
        ("corrections", zz(N.delta(e.corr_t)), l, False),
        ("corrections", N.zigzag1(e.corr), l, False),
        ("fragments", zz(N.delta(e.starts)), l, False),
        ("fragments", e.counts, l, False),
        ("anchors", zz(e.anchors), l, False),
        ("ends", zz(e.ends), l, False),
        ("lengths", e.lengths, l, False),
        ("coefficients", maps(e.coefficients), p.l_freq, elide),
    ]


def _rule(p: CodecParams, dim: int) -> CodecParams:
    """What a container says by its bound and the number of its constants alone."""
    return derive(p.eps, dim, p.constants, eps_t=p.eps_t)


FLAGS = ("zero_free", "positions", "blocks", "integer_input")
#: fields that a header holds where they differ from the rule, with their formats
HELD = {"eps_f": "d", "b_s": "I", "eps_p": "d", "l": "B", "l_freq": "B", "flags": "B"}


def held_bytes(mask: int) -> int:
    """Length of the fields that a header's mask names."""
    return sum(struct.calcsize("<" + kind) for i, kind in enumerate(HELD.values()) if mask >> i & 1)


def _flags(p: CodecParams) -> int:
    return sum(getattr(p, name) << i for i, name in enumerate(FLAGS))


def head(e: Encoded, p: CodecParams) -> bytes:
    """Number of the constants, dimension, bound and time precision; then a mask and whatever differs from the rule."""
    rule, own, mask = _rule(p, e.dim), b"", 0
    for i, (name, kind) in enumerate(HELD.items()):
        value, usual = (_flags(p), _flags(rule)) if name == "flags" else (getattr(p, name), getattr(rule, name))
        if value != usual:
            mask |= 1 << i
            own += struct.pack("<" + kind, value)
    first = struct.pack("<BBdd", p.constants | (mask > 0) << 7, e.dim | (e.uniform << 7), p.eps, float(p.eps_t))
    return first + (bytes([mask]) + own if mask else b"")


def _unhead(data: bytes) -> tuple[CodecParams, int, bool, int]:
    """(parameters, dimension, whether uniform, length of the header)."""
    constants, kind, eps, eps_t = struct.unpack_from("<BBdd", data)
    p, at = derive(eps, kind & 127, constants & 127, eps_t=int(eps_t)), 18
    if constants >> 7:
        mask, at = data[at], at + 1
        for i, (name, form) in enumerate(HELD.items()):
            if mask >> i & 1:
                (value,) = struct.unpack_from("<" + form, data, at)
                at += struct.calcsize("<" + form)
                p = p.with_(**({n: bool(value >> j & 1) for j, n in enumerate(FLAGS)} if name == "flags" else {name: value}))
    return p, kind & 127, bool(kind >> 7), at


def bits_of(e: Encoded, p: CodecParams) -> dict[str, int]:
    """Bits of each section."""
    out = dict.fromkeys(SECTIONS, 0)
    out["header"] = 8 * len(head(e, p))
    for name, codes, l, elide in _sections(e, p):  # noqa: E741
        out[name] += int(N.bit_cost(codes, l, elide).sum())
    return out


def size_of(e: Encoded, p: CodecParams) -> int:
    """Bytes of the container if its parameters were a rule of the whole set, as an experiment on them supposes: the
    fields that differ from our own rule are not counted."""
    return 18 + -(-sum(int(N.bit_cost(codes, l, elide).sum()) for _, codes, l, elide in _sections(e, p)) // 8)  # noqa: E741


def pack(e: Encoded, p: CodecParams) -> bytes:
    bits = np.concatenate([N.to_bits(codes, l, elide) for _, codes, l, elide in _sections(e, p)])
    return head(e, p) + np.packbits(bits).tobytes()


def unpack(data: bytes, p: CodecParams | None = None) -> tuple[Encoded, CodecParams]:
    """The container's integers and its parameters, which it holds itself. With p, a container made with other
    parameters is refused."""
    made, dim, uniform, at = _unhead(data)
    if p is not None and any(getattr(made, name) != getattr(p, name) for name in DECODER):
        raise ValueError(f"the container was made with other parameters: {made}")
    p = made
    bits, at = np.unpackbits(np.frombuffer(data, np.uint8, offset=at)), 0

    # all but the coefficients are written alike, so of a small container they are read at once; what follows is read again
    values, edges = N.codes_of(bits, p.l) if len(bits) <= N.SLICE else (None, None)

    def take(n: int) -> np.ndarray:
        nonlocal at
        if values is None:
            got, at = N.from_bits(bits, at, n, p.l)
            return got
        at += n
        return values[at - n : at]

    def signed(*shape: int) -> np.ndarray:
        return N.unzigzag(take(math.prod(shape))).reshape(shape)

    dt, fragments = take(2)
    n = int(take(1)[0])
    out_t, out = N.undelta(signed(n)), N.undelta(signed(n, dim))
    n = int(take(1)[0])
    corr_t = N.undelta(signed(n))
    corr = N.unzigzag1(take(n * dim)).reshape(-1, dim)
    starts, counts = N.undelta(signed(int(fragments))), take(int(fragments))
    anchors = signed(len(counts), dim)
    blocks = len(_grid(counts, _size(p, counts))[0])
    ends, lengths = signed(blocks, dim), take(blocks * dim).reshape(-1, dim)
    raw, _ = N.from_bits(bits, at if values is None else int(edges[at - 1]), int(lengths.sum()), p.l_freq, p.zero_free and p.l_freq == 1)
    coefficients = (N.unzigzag1 if p.zero_free else N.unzigzag)(raw)
    return Encoded(dim, int(dt) * p.eps_t, starts, counts, anchors, ends, lengths, coefficients, corr_t, corr, out_t, out, uniform), p


def clock_bits(t: np.ndarray, eps_t: int, l: int = 2) -> int:  # noqa: E741
    """Bits of all the times, as differences of their codes."""
    return int(N.bit_cost(N.zigzag(N.delta(time_code(t, eps_t))), l).sum())


def raw_bytes(n: int, dim: int) -> int:
    return 8 * (dim + 1) * n
