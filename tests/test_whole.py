"""Registered queries that once left rows out, against every row."""

import numpy as np

from warpspan.functions import kernels
from warpspan.plans import QUERIES
from warpspan.plans import experiments as E
from warpspan.plans import methods as M
from warpspan.sources import series as S
from warpspan.sources import tables


def test_pattern_watch_compares_every_window(spark, sf):
    found = {(r.user_id, r.event_id, r.pattern, r.dist) for r in QUERIES["stream_pattern_watch"](spark, sf).collect()}
    users: dict = {}
    for r in sorted(tables.table(spark, sf, "events").collect(), key=lambda r: (r.ts, r.event_id)):
        users.setdefault(r.user_id, []).append((r.event_id, float(np.floor(r.value * 100 + 0.5))))
    patterns, wanted = E._patterns(spark, sf), set()
    for user, rows in users.items():
        for end in range(E.PATTERN_N, len(rows) + 1):
            x = np.array([[c for _, c in rows[end - E.PATTERN_N : end]]])
            for pattern, y in patterns.items():
                dist = kernels.dtw_pow(x, np.array([y], dtype=float), 2)[0]
                if dist <= E.PATTERN_EPS:
                    wanted.add((user, rows[end - 1][0], pattern, int(dist)))
    assert found == wanted and len({p for _, p, _, _ in wanted}) > 0


def test_self_join_takes_every_page(spark):
    sf = "/root/testdata/sf0.01"
    rows = S.fixture(spark, sf, M.JOIN_FIX).select("series_id", "v").orderBy("series_id").collect()
    assert len(rows) > 60
    x, wanted = np.array([r.v for r in rows], dtype=float), set()
    for k, r in enumerate(rows[:-1]):
        y = np.repeat(x[k : k + 1], len(rows) - k - 1, axis=0)
        for other, dist in zip(rows[k + 1 :], kernels.dtw_pow(x[k + 1 :], y, M.JOIN_W), strict=True):
            if dist <= M.JOIN_EPS:
                wanted.add((r.series_id, other.series_id, int(dist)))
    assert {tuple(r) for r in QUERIES["warp_self_join"](spark, sf).collect()} == wanted and wanted
