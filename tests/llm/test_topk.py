import numpy as np
import pytest
from pyspark.sql import functions as F

from viewsize.llm import topk

from .conftest import clashing


def brute(vectors, queries, k):
    ids = np.array([i for i, _ in vectors])
    out = []
    for q, v in queries:
        scored = sorted(((-max(-(2**63), min(2**63 - 1, sum(int(a) * int(b) for a, b in zip(v, x)))), i) for i, x in vectors if i != q))[:k]
        out += [(q, r + 1, i, -s) for r, (s, i) in enumerate(scored)]
    assert len(ids) >= 0
    return sorted(out)


def integer(v, scale=256):
    return [int(np.floor(max(-1.7976931348623157e308, min(1.7976931348623157e308, scale * x)))) for x in v]


def run(spark, rows, k=5, every=5, kind="float", **how):
    df = clashing(spark.createDataFrame(rows, f"vec_id long, embedding array<{kind}>"))
    own = topk.prepare(df)
    got = topk.top_k(own, own.where(f"vec_id % {every} = 0"), k, **how).collect()
    sound = [(i, integer(v)) for i, v in rows if i is not None and v is not None and all(x is not None and np.isfinite(x) for x in v)]
    assert sorted(tuple(r) for r in got) == brute(sound, [q for q in sound if q[0] % every == 0], k)


def test_clusters_and_ties(spark):
    rng = np.random.default_rng(0)
    centers = rng.normal(size=(6, 16))
    rows = [(i, [float(np.float32(x)) for x in centers[i % 6] + 0.05 * rng.normal(size=16)]) for i in range(600)]
    rows += [(1000 + i, rows[3][1]) for i in range(150)]  # one very common vector
    run(spark, rows, block=32, first=2)
    run(spark, rows, block=10_000, every=50)


def test_random_directions(spark):
    rng = np.random.default_rng(1)
    run(spark, [(i, [float(np.float32(x)) for x in v]) for i, v in enumerate(rng.normal(size=(300, 8)) * rng.lognormal(size=(300, 1)))], block=16)


def test_messy_vectors(spark):
    rows = [
        (0, [1.0, 2.0]), (5, [1.0, None]), (10, None), (15, [float("nan"), 1.0]), (20, [float("inf"), 0.0]), (25, []), (30, [0.5]), (None, [1.0, 1.0]), (1, [-0.001, 3.0]), (2, [0.0, 0.0, 7.0]),
    ]
    run(spark, rows)
    run(spark, rows[:1])


def test_large_finite_values(spark):
    """Products beyond a double's and a long's exact range, up to the largest double."""
    rng = np.random.default_rng(5)
    rows = [(i, [float(np.float32(x)) for x in rng.normal(size=4) * s]) for s, ids in ((1, range(0, 40)), (1e5, range(40, 80)), (1e8, range(80, 120)), (1e30, range(120, 140))) for i in ids]
    rows += [(200 + i, [1e8, -1e8, 1e8, float(i % 3)]) for i in range(12)]
    run(spark, rows, block=16)
    run(spark, rows[:100], block=8)
    run(spark, [(i, [x * (1e300 if i % 4 else 1e307) for x in v]) for i, v in rows[:40]] + rows[40:60] + [(300, [1.7e308, -1.7e308])], kind="double", block=16)


def test_empty(spark):
    own = topk.prepare(spark.createDataFrame([], "vec_id long, embedding array<float>"))
    assert topk.top_k(own, own).collect() == []
    some = topk.prepare(spark.createDataFrame([(3, [1.0])], "vec_id long, embedding array<float>"))
    assert topk.top_k(some, some.where(F.lit(False))).collect() == []


def test_ceilings_hold():
    rng = np.random.default_rng(2)
    x = rng.integers(-200, 200, (400, 12)).astype(float)
    top = float((x * x).sum(axis=1).max())
    ix = topk.Index(12, top, topk.choose_pivots(topk._lift(x, top), 7))
    p, d = ix.key(x)
    ring = p * 10 + np.minimum(9, (d / d.max() * 10).astype(int))
    ix.cells = np.array([(c, c // 10, d[ring == c].min(), d[ring == c].max()) for c in np.unique(ring)])
    q = rng.integers(-200, 200, (30, 12)).astype(float)
    ceil = ix.ceilings(q)
    for j, c in enumerate(ix.cells[:, 0]):
        assert ((q @ x[ring == c].T).max(axis=1) <= ceil[:, j]).all()


@pytest.mark.parametrize("n", [1, 3, 50])
def test_pivots_are_distinct(n):
    x = np.repeat(np.arange(5.0)[:, None], 4, axis=0)
    assert len(topk.choose_pivots(x, n)) == min(n, 5)
