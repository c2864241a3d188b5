import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from lattice_pages.llm import ann
from lattice_pages.llm.queries import QUERIES


def brute(rows, asked, k=10):
    ids = np.array([i for i, _ in rows])
    x = np.array([v for _, v in rows], float)
    out = {}
    for i, v in rows:
        if asked(i):
            d = np.sqrt(((x - np.array(v, float)) ** 2).sum(axis=1))
            order = [j for j in np.lexsort((ids, d)) if ids[j] != i][:k]
            out[i] = [(int(ids[j]), float(d[j])) for j in order]
    return out


def test_curve_is_a_path():
    for axes, bits in ((2, 3), (3, 2)):
        grid = np.stack(np.meshgrid(*[np.arange(1 << bits)] * axes, indexing="ij"), axis=-1).reshape(-1, axes)
        key = ann.hilbert(grid, bits)
        path = grid[np.argsort(key)]
        assert sorted(key) == list(range(len(grid))) and (np.abs(np.diff(path, axis=0)).sum(axis=1) == 1).all()


def test_orthogonal_and_sketch():
    r = np.random.default_rng(3)
    t = ann._orthogonal(r.normal(size=(5, 9)))
    assert np.allclose(t.T @ t, np.eye(5))
    x = r.normal(size=(50, 9)) * 10.0 ** r.integers(-3, 4, (50, 1)) + 5
    y, scale = ann.unsketch(ann.sketch(x, np.full(9, 5.0)), 9)
    assert np.allclose(scale * 127, np.abs(x - 5).max(axis=1)) and (np.abs(y - (x - 5)) <= scale[:, None] * 0.51).all()


def table(spark, sf):
    df = spark.read.parquet(f"{sf}/embeddings.parquet")
    return df, [(r.vec_id, r.embedding) for r in df.collect()]


def recall(got, want):
    return np.mean([len(got[q] & {i for i, _ in want[q]}) / 10 for q in want])


@pytest.mark.parametrize("size", ["0.001", "0.01", "0.1"])
def test_recall_of_the_query(spark, sf, size):
    sf = sf.replace("0.001", size)
    rows = table(spark, sf)[1]
    want = brute(rows, lambda i: i % 100 == 0)
    got, scores = {}, {}
    for r in QUERIES["op10_ann"](spark, sf).orderBy("query_id", "rank").collect():
        got.setdefault(r.query_id, set()).add(r.vec_id)
        scores[r.query_id, r.vec_id] = r.score
    assert set(got) == set(want) and all(len(v) == 10 for v in got.values())
    assert all(scores[q, i] == d for q in want for i, d in want[q] if i in got[q])
    assert recall(got, want) >= 0.88  # ten queries at most here; check_l has 513


def test_exact_way(spark, sf):
    df, rows = table(spark, sf)
    got = ann.search(df, F.pmod("id", F.lit(100)) == 0, exact=True).orderBy("query_id", "rank").collect()
    want = brute(rows, lambda i: i % 100 == 0)
    assert [(r.query_id, r.vec_id, r.score) for r in got] == [(q, i, d) for q in sorted(want) for i, d in want[q]]


def candidates(spark, df, dim):
    """(window, mean share of the rows within it on some curve, for every tenth row)."""
    good = ann.clean(df, "vec_id", "embedding")
    reps = good.selectExpr("id AS rep", "v").cache()
    n, moments = ann._moments(reps, dim)
    order = ann._order(reps, ann.CURVES, dim, *moments).toPandas()
    w = ann.calibrate(reps, spark.createDataFrame(order), dim, 10)
    place = order.pivot(index="rep", columns="curve", values="pos").to_numpy()
    return w, np.mean([(np.abs(place - place[i]) <= w).any(axis=1).mean() for i in range(0, n, 10)])


def test_curves_leave_rows_out(spark, sf):
    """Noise is the worst case: about half of 2,000 rows. Clusters need a small part."""
    noise = candidates(spark, spark.read.parquet(f"{sf.replace('0.001', '0.1')}/embeddings.parquet"), 64)
    assert noise[1] < 0.6
    r = np.random.default_rng(1)
    centers = r.normal(size=(40, 8))
    rows = [(i, (centers[i % 40] + 0.1 * r.normal(size=8)).tolist()) for i in range(4000)]
    assert candidates(spark, spark.createDataFrame(rows, "vec_id long, embedding array<double>"), 8)[1] < 0.08


def test_windows_reach_recall(spark):
    r = np.random.default_rng(1)
    centers = r.normal(size=(40, 8))
    rows = [(i, (centers[i % 40] + 0.1 * r.normal(size=8)).tolist()) for i in range(4000)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    want = brute(rows, lambda i: i % 100 == 0)
    for window in (None, 30):
        got = {}
        for x in ann.search(df, F.col("id") % 100 == 0, window=window).collect():
            got.setdefault(x.query_id, set()).add(x.vec_id)
        assert recall(got, want) >= 0.9


def test_odd_rows(spark):
    nan = float("nan")
    rows = [(i, [1.0, 2.0]) for i in range(300)] + [(300, [0.0, 0.0]), (301, None), (302, [nan, 1.0]), (303, [None, 1.0]), (304, [1.0]), (305, []), (400, [1.0, 2.5]), (401, [-0.0, 1.0]), (500, [0.0, 1.0]), (400, [1.0, 2.5]), (None, [1.0, 1.0])]
    df = spark.createDataFrame([(a, b, "x", 1) for a, b in rows], "vec_id long, embedding array<double>, id string, rep int")
    got = {}
    for x in ann.search(df, F.col("id") % 100 == 0).orderBy("query_id", "rank").collect():
        got.setdefault(x.query_id, []).append((x.vec_id, x.score))
    assert [i for i, _ in got[0]] == list(range(1, 11)) and [i for i, _ in got[100]] == list(range(10))
    assert [i for i, _ in got[400]] == list(range(10)) and got[400][0][1] == 0.5
    assert got[500][0] == (401, 0.0) and got[500][1] == (0, math.sqrt(2)) and set(got) == {0, 100, 200, 400, 500}
    assert ann.search(df.limit(0), F.lit(True)).count() == 0
