"""Many tracks encoded at once: the same integers and bytes as track.py makes of each, with one numpy call for all of them
where track.py needs one a track. Small tracks cost little more than their points."""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import lru_cache

import numpy as np

from spectrack.functions import numbers as N
from spectrack.functions import track as K
from spectrack.functions.params import CodecParams

Track = tuple[np.ndarray, np.ndarray]
NAMES = ("header", "outliers", "outliers", "outliers", "corrections", "corrections", "corrections", "fragments", "fragments", "anchors", "ends", "lengths", "coefficients")


#: a track of no more points is encoded from samples that encoders share
ALONE = 100_000


def _fits(tracks: list[Track], p: CodecParams, least: int = 2) -> bool:
    """Whether these tracks, so many at least, can go together; others go one by one."""
    if p.integer_input or len(tracks) < least or len({x.shape[1] for _, x in tracks}) > 1:
        return False
    if p.eps_t != 1 and any((np.diff(K.time_code(t, p.eps_t)) == 0).any() for t, _ in tracks):
        return False
    return sum(int(t[-1]) - int(t[0]) + 2 for t, _ in tracks) < 1 << 62


@dataclass
class Batch:
    """Encoded tracks: statistics of each, and the codes of their sections with the track that each code belongs to."""

    heads: list[K.Encoded]  # what a header says: dimension and whether uniform
    stats: dict[str, np.ndarray]
    sections: list[tuple[np.ndarray, np.ndarray]]  # unsigned codes (the last section's still signed), tracks


def _segments(n: np.ndarray) -> np.ndarray:
    return np.cumsum(n) - n


def _starts(t: np.ndarray, pos: np.ndarray, own: np.ndarray, at: np.ndarray, n: np.ndarray, gap: np.ndarray, inside: np.ndarray, least_gap: np.ndarray, whole: np.ndarray, p: CodecParams) -> np.ndarray:
    """Where fragments start in all tracks: the rule of track.fragment_starts. Tracks marked whole have one."""
    breaks = np.zeros(len(t), bool)
    if p.v_max is not None:
        breaks[1:] = (np.linalg.norm(np.diff(pos, axis=0), axis=1) > gap / 1e6 * p.v_max) & inside
    if p.default_dt:
        first = np.full(len(n), p.default_dt, np.int64)
    else:  # the median pause
        which = own[1:][inside]
        ordered = gap[inside][np.lexsort((gap[inside], which))]
        size = n - 1
        base = _segments(size)
        first = np.ones(len(n), np.int64)
        some = np.flatnonzero(size > 0)
        low, high = ordered[base[some] + (size[some] - 1) // 2], ordered[base[some] + size[some] // 2]
        first[some] = ((low + high) / 2).astype(np.int64)
    least = np.minimum(first, least_gap)
    suspect = np.zeros(len(t), bool)
    suspect[1:] = inside & ((gap > p.b_s * least[own[1:]]) | breaks[1:])
    suspect &= ~whole[own]
    breaks &= ~whole[own]
    breaks[at] = True
    where = np.flatnonzero(suspect)
    inclusive, track, start, mean0 = p.gap_mean == "inclusive", -1, 0, 0
    for j, i, now, before, fast in zip(where.tolist(), own[where].tolist(), t[where].tolist(), t[where - 1].tolist(), breaks[where].tolist(), strict=True):
        if i != track:
            track, start = i, int(at[i])
            begun, mean0 = int(t[start]), int(first[i])
        k = j - start
        if k == 1:
            mean = mean0
        elif inclusive:
            mean = (now - begun) / k
        else:
            mean = (before - begun) / (k - 1)
        if fast or now - before > p.b_s * mean:
            breaks[j] = True
            start, begun = j, now
    return np.flatnonzero(breaks)


def _deltas(x: np.ndarray, own: np.ndarray) -> np.ndarray:
    """Differences along each track's rows; the first is itself."""
    out = x.copy()
    same = own[1:] == own[:-1]
    out[1:][same] -= x[:-1][same]
    return out


@dataclass
class Sampled:
    """Fragments and uniform samples of tracks: what an encoder's bound and precisions don't change."""

    n: np.ndarray
    t: np.ndarray
    pos: np.ndarray
    uniform: np.ndarray
    dt: np.ndarray
    starts: np.ndarray
    long: np.ndarray  # of the fragments, those with samples
    ends: np.ndarray
    counts: np.ndarray
    x: np.ndarray


#: parameters that Sampled depends on
SAMPLING = ("eps_t", "v_max", "b_s", "gap_mean", "default_dt", "dt_scale")


def sample(tracks: list[Track], p: CodecParams) -> Sampled:
    """Fragments of tracks of one dimension, and the long ones at their tracks' common intervals."""
    n = np.array([len(t) for t, _ in tracks])
    at, t, pos = _segments(n), np.concatenate([t for t, _ in tracks]).astype(np.int64), np.concatenate([x for _, x in tracks]).astype(float)
    dim, own, m = pos.shape[1], np.repeat(np.arange(len(n)), n), len(n)
    gap, inside = np.diff(t), own[1:] == own[:-1]
    first_gap, least_gap, most_gap = np.zeros(m, np.int64), np.full(m, np.iinfo(np.int64).max), np.full(m, -1)
    if len(gap):
        some = n > 1
        first_gap[some] = gap[at[some]]
        np.minimum.at(least_gap, own[1:][inside], gap[inside])
        np.maximum.at(most_gap, own[1:][inside], gap[inside])
    uniform = (n > 2) & (least_gap == most_gap) & (first_gap % p.eps_t == 0) & (t[at] % p.eps_t == 0)
    if p.v_max is not None:
        uniform[:] = False
    starts = _starts(t, pos, own, at, n, gap, inside, least_gap, uniform, p)
    ends = np.append(starts[1:], len(t))
    of = own[starts]
    long = ends - starts > 2
    span, count = np.zeros(m, np.int64), np.zeros(m, np.int64)
    np.add.at(span, of[long], t[ends[long] - 1] - t[starts[long]])
    np.add.at(count, of[long], (ends - starts)[long])
    dt = p.eps_t * np.maximum(1, np.floor(span / (p.eps_t * np.maximum(count, 1)) + 0.5).astype(np.int64))
    dt = np.where(count > 0, dt, p.eps_t)
    if p.dt_scale != 1.0:
        dt = p.eps_t * np.maximum(1, np.floor(dt * p.dt_scale / p.eps_t + 0.5).astype(np.int64))
    dt = np.where(uniform, first_gap, dt)
    # uniform samples of the long fragments
    a, b, of = starts[long], ends[long], of[long]
    counts, x = np.zeros(0, np.int64), np.zeros((0, dim))
    if len(a):
        step, spans = dt[of], t[b - 1] - t[a]
        counts = -(-spans // step) + 1
        f = np.repeat(np.arange(len(a)), counts)
        passed = np.minimum(step[f] * (np.arange(len(f)) - _segments(counts)[f]), spans[f])
        # one axis of time on which fragments follow each other
        size = b - a
        points = np.repeat(a, size) + np.arange(size.sum()) - np.repeat(_segments(size), size)
        line = _segments(spans + 1)
        i = np.searchsorted(np.repeat(line - t[a], size) + t[points], line[f] + passed, "left") - 1 - _segments(size)[f]
        i = np.clip(i, 0, size[f] - 2) + a[f]
        share = ((t[a][f] + passed - t[i]) / (t[i + 1] - t[i]))[:, None]
        x = pos[i] + (pos[i + 1] - pos[i]) * share
        exact = uniform[of[f]]
        x[exact] = pos[(a[f] + np.arange(len(f)) - _segments(counts)[f])[exact]]
    return Sampled(n, t, pos, uniform, dt, starts, long, ends, counts, x)


def encode(tracks: list[Track], p: CodecParams, shared: dict | None = None) -> Batch:
    """track.encode of tracks of one dimension. `shared` keeps these tracks' samples for encoders that differ in other parameters."""
    key = tuple(getattr(p, name) for name in SAMPLING)
    shared = {} if shared is None else shared
    if key not in shared:
        shared[key] = sample(tracks, p)
    s = shared[key]
    n, t, pos, uniform, dt, starts, long, ends, counts = s.n, s.t, s.pos, s.uniform, s.dt, s.starts, s.long, s.ends, s.counts
    dim, m, at = pos.shape[1], len(n), _segments(n)
    own = np.repeat(np.arange(m), n)
    a, of = starts[long], own[starts][long]
    code = K.time_code(t, p.eps_t)
    if len(a):
        anchors, end_codes, lengths, coefficients = K.encode_uniform(s.x, counts, p)
    else:
        none = np.zeros((0, dim), np.int64)
        anchors, end_codes, lengths, coefficients = none, none, none, np.zeros(0, np.int64)
    single = np.repeat(~long, ends - starts)
    out = N.quantize(pos[single], p.eps / math.sqrt(dim))
    # what the decoder makes of it
    e = K.Encoded(dim, 0, code[a], counts, anchors, end_codes, lengths, coefficients, code[:0], out[:0], code[:0], out[:0])
    back = np.full(pos.shape, np.nan)
    if len(a):
        samples = K.decode_uniform(e, p)
        begins = np.zeros(len(t), np.int64)
        begins[a] = 1
        held = np.bincount(of, minlength=m)
        f = np.maximum(np.cumsum(begins) - 1, _segments(held)[own])
        inner = np.flatnonzero(held[own] > 0)
        f = f[inner]
        rest, step = t[inner] - e.starts[f] * p.eps_t, dt[own[inner]]
        j = np.clip(-(-rest // step) - 1, 0, counts[f] - 2)
        share = np.clip((rest - j * step) / step, 0.0, 1.0)[:, None]
        where = _segments(counts)[f] + j
        back[inner] = samples[where] + (samples[where + 1] - samples[where]) * share
    back[single] = out * (2 * p.eps / math.sqrt(dim))
    error = np.linalg.norm(back - pos, axis=1)
    wrong = np.flatnonzero(error > p.eps * K.SLACK)
    stats = {"error_points": np.bincount(own[wrong], minlength=m)}
    corr_at, corr = wrong[:0], out[:0]
    if p.validate and len(wrong):
        corr_at, corr = wrong, N.quantize(pos[wrong] - back[wrong], p.eps_p / math.sqrt(dim))
        back[wrong] += corr * (2 * p.eps_p / math.sqrt(dim))
        error[wrong] = np.linalg.norm(back[wrong] - pos[wrong], axis=1)
    frag_of = of[K._grid(counts, K._size(p, counts))[0]] if len(a) else of
    stats |= {"max_sed": np.maximum.reduceat(error, at), "sum_sed": np.add.reduceat(error, at), "outliers": np.bincount(own[single], minlength=m), "fragments": np.bincount(of, minlength=m)}
    heads = [K.Encoded(dim, int(dt[i]), *(code[:0],) * 10, uniform=bool(uniform[i])) for i in range(m)]
    every, os, oc = np.arange(m), own[single], own[corr_at]
    zz, wide = N.zigzag, lambda x: np.repeat(x, dim)
    sections = [
        (np.column_stack((dt // p.eps_t, stats["fragments"])).ravel(), np.repeat(every, 2)),
        (stats["outliers"], every),
        (zz(_deltas(code[single], os)), os),
        (zz(_deltas(out, os)).ravel(), wide(os)),
        (np.bincount(oc, minlength=m), every),
        (zz(_deltas(code[corr_at], oc)), oc),
        (N.zigzag1(corr).ravel(), wide(oc)),
        (zz(_deltas(e.starts, of)), of),
        (counts, of),
        (zz(anchors).ravel(), wide(of)),
        (zz(end_codes).ravel(), wide(frag_of)),
        (lengths.ravel(), wide(frag_of)),
        (coefficients, np.repeat(wide(frag_of), lengths.ravel())),
    ]
    return Batch(heads, stats, sections)


def _coded(made: Batch, p: CodecParams) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(codes, tracks, sections, chunk lengths, bits) of all codes, a section after the other."""
    last = len(made.sections) - 1
    codes = [u for u, _ in made.sections]
    codes[last] = (N.zigzag1 if p.zero_free else N.zigzag)(codes[last])
    u, own = np.concatenate(codes), np.concatenate([x for _, x in made.sections])
    section = np.repeat(np.arange(last + 1), [len(x) for x in codes])
    l = np.where(section == last, p.l_freq, p.l)  # noqa: E741
    bits = -(-N.bit_length(u) // l) * (l + 1)
    if p.zero_free and p.l_freq == 1:
        bits[section == last] -= 1
    return u, own, section, l, bits


def sizes(made: Batch, p: CodecParams) -> np.ndarray:
    """track.size_of of each track."""
    _, own, _, _, bits = _coded(made, p)
    return 18 + -(-np.bincount(own, bits, len(made.heads)).astype(np.int64) // 8)


def pack(made: Batch, p: CodecParams) -> tuple[list[bytes], dict[str, np.ndarray]]:
    """(containers, bits of each section) of the tracks: track.pack and track.bits_of of each."""
    m = len(made.heads)
    u, own, section, l, bits = _coded(made, p)
    kinds = {e.uniform: e for e in made.heads}
    kinds = {u: K.head(e, p) for u, e in kinds.items()}
    heads = [kinds[e.uniform] for e in made.heads]
    table = np.bincount(own * len(NAMES) + section, bits, m * len(NAMES)).astype(np.int64).reshape(m, -1)
    by = {s: sum((table[:, i] for i, x in enumerate(NAMES) if x == s), np.zeros(m, np.int64)) for s in K.SECTIONS}
    by["header"] = by["header"] + 8 * np.array([len(h) for h in heads])
    total = table.sum(axis=1)
    size = -(-total // 8)
    begin = _segments(size)
    order = np.argsort(own, kind="stable")
    u, l, bits = u[order], l[order], bits[order]  # noqa: E741
    to = _segments(bits) + np.repeat(8 * begin - _segments(total), np.bincount(own, minlength=m))
    flat = np.zeros(8 * int(size.sum()), np.uint8)
    flat[np.repeat(to - _segments(bits), bits) + np.arange(int(bits.sum()))] = N.spread(u, l, bits)
    data = np.packbits(flat).tobytes()
    return [h + data[a : a + k] for h, a, k in zip(heads, begin.tolist(), size.tolist(), strict=True)], by


def sized(tracks: list[Track], variants: list[CodecParams], shared: dict | None = None) -> list[list[dict]]:
    """For each track, with each variant of how the same integers are written: bytes and errors, as an experiment sums them up."""
    p = variants[0]
    # of a long track alone, as it is encoded singly, less is held at a time
    alone = len(tracks) == 1 and len(tracks[0][0]) <= ALONE
    if not _fits(tracks, p, 1 if alone else 2):
        out = []
        for t, pos in tracks:
            e = K.encode(t, pos, p)
            out.append([{"bytes": K.size_of(e, v), "kept": 0, "n_corr": e.stats["error_points"], "max_sed": e.stats["max_sed"], "sum_sed": e.stats["sum_sed"]} for v in variants])
        return out
    made = encode(tracks, p, shared)
    same = list(zip(*(made.stats[k].tolist() for k in ("error_points", "max_sed", "sum_sed")), strict=True))
    each = [sizes(made, v).tolist() for v in variants]
    return [[{"bytes": s[i], "kept": 0, "n_corr": c, "max_sed": x, "sum_sed": y} for s in each] for i, (c, x, y) in enumerate(same)]


def packed(tracks: list[Track], p: CodecParams) -> list[tuple[bytes, dict[str, int], bool, dict]]:
    """For each track: its container, bits of each section, whether it is uniform, and its statistics."""
    if not _fits(tracks, p):
        return [(K.pack(e, p), K.bits_of(e, p), e.uniform, e.stats) for t, pos in tracks for e in [K.encode(t, pos, p)]]
    made = encode(tracks, p)
    data, bits = pack(made, p)
    bits, stats = ({k: v.tolist() for k, v in x.items()} for x in (bits, made.stats))
    return [(x, {k: v[i] for k, v in bits.items()}, made.heads[i].uniform, {k: v[i] for k, v in stats.items()}) for i, x in enumerate(data)]


@lru_cache(maxsize=1024)
def _head(data: bytes) -> tuple[CodecParams, int, bool, int]:
    return K._unhead(data)


def _heads(payloads: list[bytes]) -> list[tuple[CodecParams, int, bool, int]]:
    """track._unhead of each; the few different heads are read once."""
    return [_head(x[:18] if x[0] < 128 else x[: 19 + K.held_bytes(x[18])]) for x in payloads]


def unpack(payloads: list[bytes], p: CodecParams | None = None) -> list[tuple[K.Encoded, CodecParams]]:
    """track.unpack of each container."""
    out: list = [None] * len(payloads)
    alike: dict = {}
    for i, (made, dim, uniform, at) in enumerate(_heads(payloads)):
        if p is not None and any(getattr(made, name) != getattr(p, name) for name in K.DECODER):
            raise ValueError(f"the container was made with other parameters: {made}")
        alike.setdefault((made, dim), []).append((i, uniform, at))
    for (made, dim), which in alike.items():
        size = np.cumsum([8 * len(payloads[i]) for i, _, _ in which])
        cuts = np.flatnonzero(np.diff(size // N.SLICE, prepend=0)).tolist()
        for a, b in zip([0, *cuts], [*cuts, len(which)], strict=True):
            part = which[a:b]
            if len(part) == 1:
                out[part[0][0]] = K.unpack(payloads[part[0][0]])
            elif part:
                for (i, _, _), e in zip(part, _unpacked([payloads[i][at:] for i, _, at in part], [u for _, u, _ in part], made, dim), strict=True):
                    out[i] = e, made
    return out


def _within(n: np.ndarray) -> np.ndarray:
    return np.arange(int(n.sum())) - np.repeat(_segments(n), n)


def _codes(bits: np.ndarray, begin: np.ndarray, end: np.ndarray, l: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:  # noqa: E741
    """numbers.codes_of of each piece of bits: (codes, position behind each, number of each piece's). What stands at a piece's end
    unfinished counts as a code, so no code reaches into the next piece."""
    n = (end - begin) // (l + 1)
    rows = np.repeat(begin, n) + _within(n) * (l + 1)
    stop = bits[rows] == 0
    stop[np.cumsum(n)[n > 0] - 1] = True
    last = np.flatnonzero(stop)
    first = np.concatenate(([0], last[:-1] + 1))[: len(last)]
    place = np.arange(len(rows)) - np.repeat(first, last - first + 1)
    value = np.zeros(len(rows), np.int64)
    for k in range(l):
        value = value << 1 | bits[rows + 1 + k]
    codes = np.add.reduceat(value << np.minimum(place * l, 62), first) if len(first) else value
    return codes, rows[last] + l + 1, np.bincount(np.repeat(np.arange(len(n)), n)[last], minlength=len(n))


def _elided(bits: np.ndarray, begin: np.ndarray, end: np.ndarray, n: np.ndarray) -> np.ndarray:
    """n codes of each piece, written a bit at a time without the last one: numbers.from_bits with `elide`."""
    stop = np.where(bits == 0, np.arange(len(bits)), len(bits) + 1)
    for odd in (0, 1):  # the next zero flag from here on
        stop[odd::2] = np.minimum.accumulate(stop[odd::2][::-1])[::-1]
    after, first = (stop + 1).tolist(), []
    for start, k in zip(begin.tolist(), n.tolist(), strict=True):
        for _ in range(k):
            first.append(start)
            start = after[start]
    first = np.array(first, np.int64)
    m = (stop[first] - first) // 2 if len(first) else first
    place, low = _within(m), np.zeros(len(first), np.int64)
    np.add.at(low, np.repeat(np.arange(len(first)), m), bits[np.repeat(first + 1, m) + 2 * place].astype(np.int64) << place)
    return low | 1 << m


def _undeltas(steps: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Sums along each track's n rows."""
    total = np.concatenate((np.zeros_like(steps[:1]) if len(steps) else np.zeros((1, *steps.shape[1:]), np.int64), np.cumsum(steps, axis=0)))
    return total[1:] - np.repeat(total[_segments(n)], n, axis=0)


def _unpacked(bodies: list[bytes], uniform: list[bool], p: CodecParams, dim: int) -> list[K.Encoded]:
    """Containers of one kind of head, read together: where a section begins follows for all of them from the counts before it."""
    m = len(bodies)
    size = 8 * np.array([len(x) for x in bodies])
    bits, begin = np.unpackbits(np.frombuffer(b"".join(bodies), np.uint8)), _segments(size)
    codes, behind, many = _codes(bits, begin, begin + size, p.l)
    at = _segments(many)

    def take(n: np.ndarray) -> np.ndarray:
        nonlocal at
        got = codes[np.repeat(at, n) + _within(n)]
        at = at + n
        return got

    signed = lambda n: N.unzigzag(take(n))
    one = np.ones(m, np.int64)
    dt, fragments, n_out = take(one), take(one), take(one)
    out_t, out = _undeltas(signed(n_out), n_out), _undeltas(signed(n_out * dim).reshape(-1, dim), n_out)
    n_corr = take(one)
    corr_t, corr = _undeltas(signed(n_corr), n_corr), N.unzigzag1(take(n_corr * dim)).reshape(-1, dim)
    starts, counts = _undeltas(signed(fragments), fragments), take(fragments)
    anchors = signed(fragments * dim).reshape(-1, dim)
    blocks = np.zeros(m, np.int64)
    np.add.at(blocks, np.repeat(np.arange(m), fragments), -(-(counts - 1) // K._size(p, counts)))
    ends, lengths = signed(blocks * dim).reshape(-1, dim), take(blocks * dim).reshape(-1, dim)
    n_coef = np.zeros(m, np.int64)
    np.add.at(n_coef, np.repeat(np.arange(m), blocks), lengths.sum(axis=1))
    begin, end = behind[at - 1], begin + size
    if p.zero_free and p.l_freq == 1:
        raw = _elided(bits, begin, end, n_coef)
    else:
        every, _, found = _codes(bits, begin, end, p.l_freq)
        raw = every[np.repeat(_segments(found), n_coef) + _within(n_coef)]
    coefficients = (N.unzigzag1 if p.zero_free else N.unzigzag)(raw)
    cut = lambda x, n: [x[a:b] for a, b in zip(_segments(n).tolist(), np.cumsum(n).tolist(), strict=True)]
    parts = [cut(starts, fragments), cut(counts, fragments), cut(anchors, fragments), cut(ends, blocks), cut(lengths, blocks), cut(coefficients, n_coef), cut(corr_t, n_corr), cut(corr, n_corr), cut(out_t, n_out), cut(out, n_out)]
    return [K.Encoded(dim, step, *each) if not u else K.Encoded(dim, step, *each, uniform=True) for step, u, *each in zip((dt * p.eps_t).tolist(), uniform, *parts, strict=True)]


def decode(boxes: list[tuple[K.Encoded, CodecParams, np.ndarray | None]], clocks: list[np.ndarray]) -> list[np.ndarray]:
    """track.decode of each container, with its samples where they are known, at its clock's times."""
    out: list = [None] * len(boxes)
    alike: dict = {}
    for i, (e, p, samples) in enumerate(boxes):
        # without blocks a fragment is one, whatever the longest of its track
        alike.setdefault((e.dim, p, samples is None), []).append(i)
    for (dim, p, unknown), which in alike.items():
        es, n = [boxes[i][0] for i in which], [np.asarray(clocks[i], np.int64) for i in which]
        both = _decoded(es, n, p, dim) if unknown and len(which) > 1 and not p.integer_input else None
        for j, i in enumerate(which):
            out[i] = K.decode(es[j], n[j], p, boxes[i][2]) if both is None else both[j]
    return out


def _decoded(es: list[K.Encoded], clocks: list[np.ndarray], p: CodecParams, dim: int) -> list[np.ndarray] | None:
    """Of containers of one kind; None where their times don't fit on one axis on which tracks follow each other."""
    m = len(es)
    joined = {name: np.concatenate([getattr(e, name) for e in es]) for name in ("starts", "counts", "anchors", "ends", "lengths", "coefficients", "corr_t", "corr", "out_t", "out")}
    size = {name: np.array([len(getattr(e, name)) for e in es]) for name in ("starts", "corr_t", "out_t")}
    n = np.array([len(x) for x in clocks])
    own, clock = np.repeat(np.arange(m), n), np.concatenate(clocks)
    code = K.time_code(clock, p.eps_t)
    low, high = np.full(m, np.iinfo(np.int64).max), np.full(m, np.iinfo(np.int64).min)
    for name, times in [(None, code), *((k, joined[k]) for k in size)]:
        of = own if name is None else np.repeat(np.arange(m), size[name])
        np.minimum.at(low, of, times)
        np.maximum.at(high, of, times)
    low, high = np.minimum(low, high), np.maximum(low, high)
    spans = [b - a + 1 for a, b in zip(low.tolist(), high.tolist(), strict=True)]
    if sum(spans) >= 1 << 62:
        return None
    shift = _segments(np.array(spans)) - low
    line = code + shift[own]

    def keys(name: str) -> np.ndarray:
        return joined[name] + np.repeat(shift, size[name])

    out = np.full((len(clock), dim), np.nan)
    some = np.flatnonzero(size["starts"][own] > 0)
    if len(some):
        starts, counts = joined["starts"], joined["counts"]
        samples = K.decode_uniform(K.Encoded(dim, 0, *(joined[k] for k in ("starts", "counts", "anchors", "ends", "lengths", "coefficients")), *(starts[:0],) * 4), p)
        keyed = keys("starts")
        # of the track's fragments the last that starts by then, or the first
        f = np.maximum(np.searchsorted(keyed, line[some], "right") - 1, _segments(size["starts"])[own[some]])
        step = np.array([e.dt for e in es])[own[some]]
        rest = clock[some] - starts[f] * p.eps_t
        j = np.clip(-(-rest // step) - 1, 0, counts[f] - 2)
        share = np.clip((rest - j * step) / step, 0.0, 1.0)[:, None]
        i = _segments(counts)[f] + j
        out[some] = samples[i] + (samples[i + 1] - samples[i]) * share
    for name, value, unit in (("out_t", "out", 2 * p.eps / math.sqrt(dim)), ("corr_t", "corr", 2 * p.eps_p / math.sqrt(dim))):
        keyed = keys(name)
        if len(keyed):
            at = np.minimum(np.searchsorted(keyed, line), len(keyed) - 1)
            hit = np.flatnonzero(keyed[at] == line)
            out[hit] = (out[hit] if name == "corr_t" else 0) + joined[value][at[hit]] * unit
    return [out[a:b] for a, b in zip(_segments(n).tolist(), np.cumsum(n).tolist(), strict=True)]


def clock_bits(tracks: list[Track], eps_t: int, l: int = 2) -> list[int]:  # noqa: E741
    """track.clock_bits of each track."""
    n = np.array([len(t) for t, _ in tracks])
    own = np.repeat(np.arange(len(n)), n)
    steps = _deltas(K.time_code(np.concatenate([t for t, _ in tracks]), eps_t), own)
    return np.bincount(own, N.bit_cost(N.zigzag(steps), l), len(n)).astype(np.int64).tolist()
