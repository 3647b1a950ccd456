"""Nearest vectors of tight groups, which a quantiser's codes hardly tell apart, against brute force."""

import numpy as np

from docprofile.llm import ann


def test_tight_groups(spark):
    rng = np.random.default_rng(3)
    far = rng.standard_normal((4, 24))
    rows = [(k, (far[k % 4] + rng.standard_normal(24) * 1e-3).tolist()) for k in range(2000)]
    got = {}
    for r in ann.nearest(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), lambda i: i % 50 == 0).collect():
        got.setdefault(r.query_id, {})[r["rank"]] = r.vec_id
    x = np.array([v for _, v in rows])
    u = x / np.linalg.norm(x, axis=1)[:, None]
    for q in range(0, 2000, 50):
        s = u @ u[q]
        s[q] = -2
        assert [got[q][k] for k in range(1, 6)] == np.lexsort((np.arange(2000), -s))[:5].tolist()


def test_very_large_and_small_components(spark):
    rows = [(0, [1e200, 1e200]), (1, [1e-200, 0.0]), (2, [3e180, 3e180]), (3, [0.0, -1.0])]
    got = {r["rank"]: (r.vec_id, round(r.score, 6)) for r in ann.nearest(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), lambda i: i % 50 == 0).collect()}
    assert got == {1: (2, 1.0), 2: (1, 0.707107), 3: (3, -0.707107)}
