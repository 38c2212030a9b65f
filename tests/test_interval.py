"""The interval search against brute force."""

import collections

import numpy as np

from spectrack import queries
from spectrack.functions import track as K
from spectrack.functions.params import derive
from spectrack.operators import points as P
from spectrack.sources import tables as D


def test_interval_search_equals_brute_force(spark, sf_dir):
    p = derive(50.0, v_max=queries.V_MAX)
    want = {}
    rows = collections.defaultdict(list)
    for r in D.ev_user(spark, sf_dir).collect():
        rows[r.track_id].append((r.t, *r.pos))
    for track, points in rows.items():
        t, pos = np.array([x[0] for x in sorted(points)]), np.array([x[1:] for x in sorted(points)])
        common = K.common_interval(t, K.fragment_starts(t, pos, p), p.eps_t)
        sizes = []
        for dt in (10, 20, 30):
            e = K.encode(t, pos, p.with_(dt_scale=dt * queries.HOUR / common))
            assert e.dt == dt * queries.HOUR and e.stats["max_sed"] <= 50.0
            sizes.append((len(K.pack(e, p)), e.dt))
        want[track] = min(sizes)
    got = {r.track_id: (r.bytes, r.dt) for r in queries.q_interval_search(spark, sf_dir).collect()}
    assert got == want


def test_ties_go_to_the_smaller_interval(spark):
    costs = spark.createDataFrame([("a", 30, 5), ("a", 10, 5), ("a", 20, 6)], "track_id string, dt long, bytes long")
    assert [tuple(r) for r in P.search_interval(costs).collect()] == [("a", 10, 5)]
