"""Numbers, transform, theory, container and simplifiers, without Spark."""

import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from spectrack.functions import many
from spectrack.functions import numbers as N
from spectrack.functions import simplify as S
from spectrack.functions import spectral, theory
from spectrack.functions import track as K
from spectrack.functions.params import CONSTANTS, derive

INTS = st.lists(st.integers(-(1 << 40), 1 << 40), max_size=40)


def test_worked_examples():
    assert N.quantize(3.824, 0.03) == 64 and N.dequantize(64, 0.03) == pytest.approx(3.84)
    assert N.zigzag(227) == 454 and N.zigzag1(227) == 455 and N.bit_cost(454, 1) == 18 and N.bit_cost(455, 1, True) == 17
    assert N.bit_cost(N.zigzag(0), 1) == 2 and N.bit_cost(N.zigzag1(0), 1, True) == 1
    assert np.packbits(N.to_bits(227, 7)).tolist() == [0xE3, 0x01]


@given(INTS, st.integers(1, 7))
@settings(max_examples=60, deadline=None)
def test_integer_codes_come_back(xs, l):  # noqa: E741
    x = np.array(xs, np.int64)
    assert (N.unzigzag(N.zigzag(x)) == x).all() and (N.unzigzag1(N.zigzag1(x)) == x).all() and (N.undelta(N.delta(x)) == x).all()
    for u, elide in ((N.zigzag(x), False), (N.zigzag1(x), l == 1)):
        bits = N.to_bits(u, l, elide)
        assert len(bits) == N.bit_cost(u, l, elide).sum()
        back, at = N.from_bits(bits, 0, len(u), l, elide)
        assert (back == u).all() and at == len(bits)


@given(st.floats(-1e6, 1e6), st.floats(1e-3, 1e3))
def test_quantizer_stays_in_its_interval(x, e):
    d = x - N.dequantize(N.quantize(x, e), e)
    assert -e * (1 + 1e-6) - 1e-9 <= d < e * (1 + 1e-6) + 1e-9


def test_transforms_agree():
    v = np.random.default_rng(0).normal(size=(3, 40))
    centred = v - v.mean(axis=1, keepdims=True)
    for m in ("fft", "product"):
        assert np.allclose(spectral.dct(v, method=m), spectral.dct(v, method="direct"))
    assert np.abs(spectral.dct(centred)[:, 0]).max() < 1e-9
    assert np.allclose(spectral.dct(v, 7)[:, 1:], spectral.dct(centred)[:, 1:7])  # centring changes nothing else
    assert np.allclose(spectral.idct(spectral.dct(v), 40), v) and np.allclose(spectral.idct(spectral.dct(v, scaling="ortho"), 40, "ortho"), v)


def test_theory_against_simulation():
    assert theory.mean_track_error(0.6, 2) == pytest.approx(0.335, abs=5e-4) and theory.mean_track_error(0.6, 3) == pytest.approx(0.426, abs=5e-4)
    assert theory.p_exceed(1, 50, 100, 1 / 0.6, 2) == pytest.approx(0.013, abs=5e-4) and theory.p_exceed(1, 50, 100, 1 / 0.8, 2) == pytest.approx(0.0005, abs=5e-5)
    for dim in (1, 2, 3, 4, 5):
        r = np.linalg.norm(np.random.default_rng(dim).normal(0, 2, (200_000, dim)), axis=1)
        assert theory.mean_dev(2, dim) == pytest.approx(r.mean(), rel=0.01) and theory.cdf(3, 2, dim) == pytest.approx((r <= 3).mean(), abs=0.005)
    assert theory.pick_a(theory.p_exceed(1, 50, 100, 1 / 0.7, 3), 3) == pytest.approx(0.7, abs=1e-3) and theory.pick_a(math.exp(-12 * 0.36), 2) == pytest.approx(0.6)
    g, b, e = np.random.default_rng(9), 100, 1.0
    noise = np.concatenate((np.zeros((4000, 1)), g.uniform(-e, e, (4000, b - 1))), axis=1)
    s = np.cumsum(spectral.idct(noise, b), axis=1)
    for k in (25, 50):
        assert s[:, k - 1].var() == pytest.approx(theory.var_s(k, b, e), rel=0.12)


def made(n, dim, seed, regular=False, jump=False):
    r = np.random.default_rng(seed)
    t = np.arange(n) * 100_000 if regular else np.cumsum(r.integers(1, 50, n) * 1_000_000)
    pos = np.cumsum(np.cumsum(r.normal(0, 1, (n, dim)), axis=0), axis=0) + np.cumsum(r.normal(0, 20, (n, dim)), axis=0)
    if jump:
        pos[n // 2 :] += 1e5
    return t, pos


CHANGES = [{}, {"v_max": 100.0}, {"ends": "open"}, {"positions": True}, {"blocks": False}, {"l_freq": 2, "l": 5}, {"zero_free": False}, {"eps_f": 1000.0, "r_ret": 2**-7}, {"gap_mean": "exclusive", "b_s": 4}, {"dt_scale": 2.0}, {"eps_t": 1000}, {"b_s": 64}, {"eps_p": 10.0}, {"eps_f": 10.0}]


@pytest.mark.parametrize("dim", [1, 2, 3, 5])
@pytest.mark.parametrize("n", [1, 2, 3, 33, 34, 400])
def test_bound_holds_through_bytes(dim, n):
    for i, change in enumerate(CHANGES):
        t, pos = made(n, dim, n + i, regular=i % 3 == 0, jump=i % 4 == 1)
        p = derive(50.0, dim, **change)
        e = K.encode(t, pos, p)
        data = K.pack(e, p)
        assert len(data) == -(-sum(K.bits_of(e, p).values()) // 8)
        back = K.decode(K.unpack(data, p)[0], t, p)
        assert np.linalg.norm(back - pos, axis=1).max() <= 50.0
        own, found = K.unpack(data)  # the bytes alone are enough
        assert (K.decode(own, t, found) == back).all() and K.head(own, found) == K.head(e, p)
        some = np.arange(n)[n // 3 :: 2][::-1]  # and each time's position doesn't depend on the others asked for
        assert (K.decode(own, t[some], found) == back[some]).all()


def test_times_off_the_precision():
    """Uniform gaps that the time precision doesn't divide, and starts off it, still keep the bound from the bytes."""
    for first, gap, eps_t in ((0, 1500, 1000), (333, 2000, 1000), (7, 100_003, 100)):
        t = first + np.arange(300) * gap
        pos = np.cumsum(np.random.default_rng(gap).normal(0, 5, (300, 2)), axis=0)
        p = derive(10.0, eps_t=eps_t)
        e, found = K.unpack(K.pack(K.encode(t, pos, p), p))
        assert np.linalg.norm(K.decode(e, t, found) - pos, axis=1).max() <= 10.0


def test_whole_numbers_come_back_exactly():
    r = np.random.default_rng(4)
    t, pos = np.cumsum(r.integers(1, 9, 500)), np.cumsum(r.integers(-9, 10, (500, 3)), axis=0).astype(float) * 12345
    p = derive(3.0, 3, integer_input=True)
    e, found = K.unpack(K.pack(K.encode(t, pos, p), p))
    assert (K.decode(e, t, found) == pos).all()
    with pytest.raises(ValueError):
        K.encode(t, pos + 0.5, p)


def test_cone_by_samples_is_the_batch_cone():
    for seed in range(4):
        t, pos = made(300, 2, seed)
        for method in ("cone_strong", "cone_weak"):
            c = S.Cone(50.0, method == "cone_weak")
            steps = [x for a, b in zip(t.tolist(), pos.tolist(), strict=True) for x in c.add(a, b)] + c.finish()
            times, path = S.kept(method, t, pos, 50.0)
            assert [a for a, _ in steps] == times.tolist() and np.allclose([b for _, b in steps], path, atol=1e-6)


def test_straight_line_stores_nothing():
    t = np.arange(200) * 100_000
    e = K.encode(t, np.outer(np.arange(200.0), [3.0, -1.0]), derive(1.0))
    assert not len(e.coefficients) and not len(e.corr_t) and (e.lengths == 0).all()


def test_gap_rule_needs_more_points_than_a_block():
    p = derive(50.0, 1, b_s=8, default_dt=1_000_000)
    for n, breaks in ((6, 1), (20, 2)):
        t = np.arange(n) * 1_000_000
        t[-3:] += 10**12
        got = K.fragment_starts(t, np.zeros((n, 1)), p)
        assert len(got) == breaks
    assert len(K.fragment_starts(np.array([0, 10**9]), np.zeros((2, 1)), p)) == 2


def test_wild_coefficients_mean_many_corrections():
    t, pos = made(400, 2, 5)
    coarse = K.encode(t, pos, derive(20.0, eps_f=2000.0)).stats
    fine = K.encode(t, pos, derive(20.0)).stats
    assert coarse["error_points"] > 3 * fine["error_points"] and coarse["max_sed"] <= 20
    assert K.encode(t, pos, derive(20.0, eps_f=2000.0, validate=False)).stats["max_sed"] > 20


@pytest.mark.parametrize("eps", [5.0, 50.0, 500.0])
def test_simplifiers_keep_the_bound(eps):
    t, pos = made(400, 2, 8)
    s = t / 1e6
    far = lambda kt, kp: np.linalg.norm(S.reconstruct(kt, kp, s) - pos, axis=1).max()
    strong, weak, heap, best = S.cone_strong(s, pos, eps), S.cone_weak(s, pos, eps), S.pq(s, pos, eps), S.opening_window(s, pos, eps)
    for index in (strong, heap, best):
        assert far(s[index], pos[index]) <= eps * (1 + 1e-9) and index[0] == 0 and index[-1] == 399
    assert far(*weak) <= eps * (1 + 1e-9) and len(weak[0]) <= len(strong)
    p = derive(eps, eps_p=0.2 * eps)
    for m in ("cone_strong", "cone_weak", "pq"):
        on, off = S.simplified(m, t, pos, p), S.simplified(m, t, pos, p, False)
        assert max(on["max_sed"], off["max_sed"]) <= eps * (1 + 1e-9) and on["bytes"] < off["bytes"]
    assert len(S.pq(s, pos, ratio=0.25)) == 100


def test_derived_parameters():
    p = derive(100.0)
    assert (p.eps_f, p.b_s, p.r_ret, p.eps_p) == (100 / CONSTANTS[0].a, 16, 1.0, 50.0) and derive(400.0).r_ret == 0.5
    assert p.kept(31) == 31 and derive(100.0, r_ret=2**-7).kept(32) == 1


def test_many_tracks_at_once_give_the_same_containers():
    """Byte for byte what each track gives alone, and so do their sizes, statistics and decoded positions."""
    r = np.random.default_rng(21)
    tracks = [(np.array([5]), np.zeros((1, 2))), (np.array([5, 9]), np.ones((2, 2))), (np.arange(3, 30), r.normal(size=(27, 2)).cumsum(axis=0) * 40)]
    for n in (1, 3, 8, 40, 700):
        t = np.cumsum(r.integers(1, 9, n) ** 4) * 1000 - 500_000
        tracks.append((t, (r.normal(size=(n, 2)) * 30).cumsum(axis=0)))
    changes = ({}, {"v_max": 5000.0}, {"blocks": False}, {"positions": True}, {"eps_t": 1000}, {"zero_free": False, "l": 5, "l_freq": 3}, {"ends": "open", "r_ret": 0.125}, {"validate": False, "gap_mean": "exclusive", "dt_scale": 0.5})
    for change in changes:
        p = derive(20.0, 2, 3, **change)
        made = many.packed(tracks, p)
        sized = many.sized(tracks, [p, p.with_(zero_free=False)])
        boxes = [(*K.unpack(x[0]), None) for x in made]
        backs = many.decode(boxes, [t for t, _ in tracks])
        for (t, pos), (data, bits, uniform, stats), (s, z), box, back in zip(tracks, made, sized, boxes, backs, strict=True):
            e = K.encode(t, pos, p)
            assert data == K.pack(e, p) and bits == K.bits_of(e, p) and uniform == e.uniform
            assert stats["error_points"] == e.stats["error_points"] == s["n_corr"] and stats["max_sed"] == pytest.approx(e.stats["max_sed"], abs=1e-9)
            assert stats["outliers"] == e.stats["outliers"] and stats["fragments"] == e.stats["fragments"]
            assert s["bytes"] == K.size_of(e, p) and z["bytes"] == K.size_of(e, p.with_(zero_free=False))
            assert np.allclose(back, K.decode(box[0], t, box[1]), rtol=0, atol=1e-9)
    assert many.clock_bits(tracks, 1, 2) == [K.clock_bits(t, 1, 2) for t, _ in tracks]


def test_one_block_of_a_long_track_needs_no_basis():
    """A block of 30,000: the basis of its product would take 7 GB, or 200 MB of a hundredth of it."""
    import tracemalloc

    c = np.random.default_rng(22).normal(size=(1, 30_000))
    tracemalloc.start()
    back = spectral.dct(spectral.idct(c, 30_000))
    few = spectral.dct(spectral.idct(c[:, :300], 30_000), 300)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert np.allclose(back, c, atol=1e-6) and np.allclose(few, c[:, :300], atol=1e-6) and peak < 50_000_000
    assert np.allclose(spectral.idct(c[:, :90], 600), (c[:, :90] * np.where(np.arange(90) == 0, 0.5, 1.0)) @ spectral.basis(600, 90).T / 600, atol=1e-9)


def test_many_containers_opened_at_once():
    """The same integers as one by one: of several kinds of header, tracks of one point, no coefficients, and a part of the clock."""
    r = np.random.default_rng(23)
    tracks = []
    for n in (1, 2, 3, 3, 40, 170, 61, 5):
        t = np.cumsum(r.integers(1, 4, n) * np.where(r.random(n) < 0.05, 90_000_000, 1_000_000))
        tracks.append((t, (r.normal(size=(n, 2)) * 30).cumsum(axis=0)))
    tracks.append((np.arange(50) * 1_000_000, np.zeros((50, 2))))
    data, ps = [], []
    for change in ({}, {"blocks": False}, {"positions": True}, {"zero_free": False, "l": 5, "l_freq": 3}, {"eps_t": 1000}, {"r_ret": 0.01}):
        p = derive(20.0, 2, 3, **change)
        data += [x[0] for x in many.packed(tracks, p)]
        ps += [p] * len(tracks)
    made = many.unpack(data)
    for x, (e, p) in zip(data, made, strict=True):
        one, own = K.unpack(x)
        assert own == p and (e.dim, e.dt, e.uniform) == (one.dim, one.dt, one.uniform)
        for name in ("starts", "counts", "anchors", "ends", "lengths", "coefficients", "corr_t", "corr", "out_t", "out"):
            assert np.array_equal(getattr(e, name), getattr(one, name)), name
    clocks = [t[::-2] for t, _ in tracks] * 6
    for (e, p), t, back in zip(made, clocks, many.decode([(*x, None) for x in made], clocks), strict=True):
        assert np.allclose(back, K.decode(e, t, p), rtol=0, atol=1e-9)
    with pytest.raises(ValueError):
        many.unpack(data[:2], ps[-1].with_(eps=7.0))
    assert many.unpack([]) == []


def test_encoders_share_samples_of_the_same_tracks():
    """Cells of a sweep that differ in bound, retention or precision cut fragments and resample once; sizes are those of encoders alone."""
    r = np.random.default_rng(24)
    tracks = [(np.cumsum(r.integers(1, 4, n) * 1_000_000), (r.normal(size=(n, 2)) * 30).cumsum(axis=0)) for n in (1, 30, 200)]
    for some in (tracks, tracks[2:]):
        shared = {}
        for b in (8, 16):
            for change in ({}, {"r_ret": 0.25}, {"eps": 5.0}, {"positions": True}):
                p = derive(20.0, 2, 3, b_s=b).with_(**change)
                got = [x[0] for x in many.sized(some, [p], shared)]
                one = [K.encode(t, pos, p) for t, pos in some]
                assert [x["bytes"] for x in got] == [K.size_of(e, p) for e in one] and [x["n_corr"] for x in got] == [e.stats["error_points"] for e in one]
        assert len(shared) == 2


def test_one_run_of_the_queue_serves_all_bounds():
    r = np.random.default_rng(25)
    for n, dim in ((1, 2), (2, 3), (3, 2), (90, 3), (300, 1)):
        t = np.cumsum(r.integers(1, 4, n) * 1_000_000)
        # repeated steps make ties
        pos = r.integers(-2, 3, (n, dim)).cumsum(axis=0) * 10.0
        ps = [derive(e, dim, eps_p=0.2 * e) for e in (40.0, 5.0, 12.5, 90.0)] + [derive(40.0, dim, eps_p=3.0)]
        assert S.queued(t, pos, ps) == [S.simplified("pq", t, pos, p) for p in ps]
