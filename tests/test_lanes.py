"""Tracks simplified at many bounds at once against simplify.py one by one."""

import time

import numpy as np
import pytest

from spectrack.functions import lanes
from spectrack.functions import simplify as S
from spectrack.functions.params import derive
from spectrack.plans import workloads as X

METHODS = X.METHODS[1:]


def made(sizes, seed, smooth=False, dim=2):
    r = np.random.default_rng(seed)
    out = []
    for n in sizes:
        steps = r.normal(0, 30, (n, dim))
        if smooth:
            steps = np.cumsum(steps, axis=0) / 20
        out.append((np.cumsum(r.integers(1, 50, n)) * 1_000_000 + 10**15, np.cumsum(steps, axis=0)))
    return out


def same(got, want):
    assert (got["kept"], got["bytes"], got["n_corr"]) == (want["kept"], want["bytes"], 0)
    assert got["max_sed"] == pytest.approx(want["max_sed"], rel=1e-9, abs=1e-9) and got["sum_sed"] == pytest.approx(want["sum_sed"], rel=1e-9, abs=1e-9)


@pytest.mark.parametrize("method", METHODS)
@pytest.mark.parametrize("m", [4, 5, 16])
def test_lanes_are_the_tracks_one_by_one(method, m):
    variants = [(derive(e, 2, eps_p=0.2 * e), on) for e in (10.0, 50.0, 1e4) for on in (True, False)]
    straight = [(np.arange(40) * 1_000_000, np.outer(np.arange(40.0), [3.0, -1.0])), (np.arange(30) * 1_000_000, np.zeros((30, 2)))]
    far = [(np.arange(20) * 1_000_000, np.cumsum(np.full((20, 2), 1e17), axis=0))]  # not even one sample fits, but for rounding, which invented points follow
    for tracks in (made([1, 2, 3, 4, 60, 70, 71, 1, 2, 80, 90, 64], 1) + straight, made([700, 5, 2, 1], 2, True), made([1], 3), made([2], 4), straight + far * (method != "cone_weak")):
        for track, got in zip(tracks, lanes.simplified(method, tracks, variants, m), strict=True):
            for (p, on), x in zip(variants, got, strict=True):
                same(x, S.simplified(method, *track, p, on, m))


def test_the_queue_takes_any_dimension_and_equal_costs():
    step = np.random.default_rng(5).integers(-1, 2, (60, 2))
    lattice = [(np.arange(60) * 1_000_000, np.cumsum(np.roll(step, k, axis=0), axis=0) * 1.0) for k in range(9)]
    for tracks in (lattice, made([9] * 12, 6, dim=1), made([50, 3, 7, 40, 4, 6, 33, 8, 600], 7, dim=3)):
        dim = tracks[0][1].shape[1]
        ps = [derive(e, dim, eps_p=0.2 * e) for e in (1.0, 30.0, 100.0)]
        for track, got in zip(tracks, lanes.simplified("pq", tracks, [(p, True) for p in ps]), strict=True):
            for p, x in zip(ps, got, strict=True):
                same(x, S.simplified("pq", *track, p))


def test_simplifiers_take_all_bounds_and_tracks_of_a_group_at_once():
    """Of the experiments over bounds: a run a method, several times as fast as a track and a bound at a time."""
    runs = X._over("ev_user", METHODS, "eps", X.EPS, X.EPS, 2)
    assert [x[0] for x in runs] == list(METHODS) and all(x[3] == X.EPS for x in runs)
    tracks = made([66] * 200, 8)
    for method, _, _, eps, f in runs:
        begin = time.perf_counter()
        got = f.many(tracks)
        at_once = time.perf_counter() - begin
        assert len(got) == 200 and all(len(x) == len(eps) for x in got)
        if method != "pq":
            begin = time.perf_counter()
            for track in tracks[:40]:
                for e in eps:
                    S.simplified(method, *track, derive(e, 2, eps_p=0.2 * e))
            assert at_once < 5 * (time.perf_counter() - begin) / 3


def test_ranges_of_a_long_track_are_walked_at_once():
    """A strong cone's path is found from many places of a track; more lanes than tracks and bounds, the same path."""
    tracks = made([9_000, 3, 2_500], 9, True)
    f = lanes.Flat(tracks)
    start, limit, end = lanes._cut(f, 3)
    assert len(start) > 20 and (limit[:-1][end[1:] == end[:-1]] == start[1:][end[1:] == end[:-1]]).all() and limit[-1] == end[-1] == len(f.t)
    for bounds in ([1.0, 20.0, 300.0], [3000.0, 30000.0]):
        kept, _ = lanes.cones(f, bounds, False)
        for a, (t, pos) in zip(f.begin.tolist(), tracks, strict=True):
            for eps, own in zip(bounds, kept, strict=True):
                assert np.flatnonzero(own[a : a + len(t)]).tolist() == S.cone_strong((t - t[0]) / 1e6, pos, eps).tolist()
