"""Shorter ways to the same results: matrix products before exact sums, kept distances, one walk for several measures."""
import numpy as np
import pytest
from pyspark.sql import functions as F

from signgraph import analysis, kernels
from signgraph.operators import exact
from signgraph.plans import code_queries, index_queries
from signgraph.workloads import split, workload

SF = "/root/testdata/sf0.001"


def rows(df):
    return sorted(map(tuple, df.collect()))


def odd(n=400, dim=24):
    """Rows with copies, opposites, a zero row, and ones whose angle lies on the edge of a bucket."""
    x = np.random.default_rng(3).normal(size=(n, dim))
    x[10:40], x[40:50], x[60] = x[9], -x[9], 0
    x[70:90] = 0
    x[70:90, 0], x[71:90, 1] = 1, np.tan(np.radians(5 * np.arange(1, 20)))
    return x


def test_a_product_only_finds_what_is_then_summed_in_order(monkeypatch):
    x = odd()
    ids = np.arange(len(x)) * 3
    d = -exact.Unit(x).cosines(exact.Unit(x))
    d[np.isnan(d)] = 2.0
    np.fill_diagonal(d, np.inf)
    monkeypatch.setattr(exact.Unit, "dots", None)  # no sum over all pairs
    best = exact.Best("cos", ids, x, 7, True, {})
    for lo in range(0, len(x), 90):
        best.add(ids[lo : lo + 90], x[lo : lo + 90], 50)
    for i in range(len(x)):
        want = np.lexsort((ids, d[i]))[:7]
        assert best.ids[i].tolist() == ids[want].tolist() and best.d[i].tolist() == d[i][want].tolist()


def test_buckets_and_moments_of_angles_equal_those_of_single_pairs(spark, monkeypatch):
    x = odd()
    v = spark.createDataFrame([(i, r.tolist()) for i, r in enumerate(x)], "vec_id long, embedding array<double>")
    every = [analysis._degrees(np.arange(0, 400, 10), x[::10], np.arange(400), x)[2] for _ in range(1)][0]
    at, n = np.unique(np.floor(every / 5).astype(int), return_counts=True)
    monkeypatch.setattr(analysis, "_degrees", None)  # not by every pair
    assert rows(analysis.angle_hist(v, every=10)) == list(zip(at.tolist(), n.tolist(), strict=True))
    got = analysis.angle_stats(v, every=10).first()
    assert got[0] == len(every) and np.allclose(got[1:], [every.mean(), every.std()], atol=1e-9)


def test_full_nodes_leave_the_rest_as_it_is(monkeypatch):
    x = np.random.default_rng(2).normal(size=(60, 16))
    m = kernels.Metric.of("bq2", x)
    nbrs = np.concatenate([[(i + 1) % 30, (i + 2) % 30] for i in range(30)] + [[30, 31]] * 30).reshape(60, 2)
    monkeypatch.setattr(kernels, "beam", None)  # no search for each of them
    assert (kernels.connected(m, nbrs.copy(), np.zeros((60, 2), np.int64))[0] == nbrs).all()
    nbrs[7, 1] = -1
    got, d = kernels.connected(m, nbrs.copy(), np.zeros((60, 2), np.int64))
    assert set(got[7]) == {8, 30} or 30 in got[7]


def test_distances_to_kept_candidates_only(monkeypatch):
    x = np.random.default_rng(6).normal(size=(200, 80))
    m = kernels.Metric.of("bq2", x)
    assert (m.among(np.arange(200)) == kernels.bq_block(kernels.levels(x), kernels.levels(x))).all()
    monkeypatch.setattr(kernels.Metric, "within", None)
    nbrs, nd = kernels.link(m, 4, 32, 120)
    assert (nbrs[:, 0] >= 0).all() and kernels.reached(nbrs, np.array([0])).mean() > 0.9


def test_a_sweep_ranks_each_set_once(spark, monkeypatch):
    n = []
    real = index_queries.ranked
    monkeypatch.setattr(index_queries, "ranked", lambda df: n.append(1) or real(df))
    got = index_queries._sweep([4, 8], "m", lambda v: {"m": v}, ("W0",), (64,))(spark, SF)
    assert n == [1] and got.where("metric = 'recall' and value > 0.8").count() == 2 and got.count() == 2 * 7


def test_grid_measures_what_a_search_returns(spark):
    i, q, t = index_queries.build(spark, SF)
    got = {r[2]: r[3] for r in index_queries.grid(i, q, t, "W0", "x", [32])}
    assert got["recall"] == index_queries.recall_of(i.search(q, ef=32), t)


def test_words_are_hashed_once_in_a_task(spark, monkeypatch):
    import xxhash

    from signgraph import workloads

    texts = ["a b a C", "", None, "b b c d e", "x y"]
    want = np.zeros((5, 8))
    for r, t in enumerate(texts):
        for w in (t or "").lower().split():
            h = xxhash.xxh64_intdigest(w, 7)
            want[r, h % 8] += 1 if h >> 63 else -1
    n = np.linalg.norm(want, axis=1, keepdims=True)
    want = want / np.where(n > 0, n, 1)
    monkeypatch.setattr(workloads, "MET", 3)  # what is remembered is dropped in between
    df = spark.createDataFrame(list(enumerate(texts)), "id long, t string").coalesce(1)
    got = {r[0]: r[1] for r in workloads.text_vectors(df, "id", "t", dim=8, dense=False).collect()}
    assert np.allclose([got[i] for i in range(5)], want, atol=1e-6)


def test_best_of_the_pools_leave_the_tasks(spark):
    i, q, _ = index_queries.build(spark, SF)
    c = i.best(q, ef=32).persist()
    assert c.count() == 10 * q.count()  # no pool of 32
    assert rows(c.select("qid", "vec_id", "sim")) == rows(i.search(q, ef=32).select("qid", "vec_id", "sim"))
    assert rows(c.select("qid", "evals", "touched").distinct()) == rows(i.candidates(q, ef=32).select("qid", "evals", "touched").distinct())
