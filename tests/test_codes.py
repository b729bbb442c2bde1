"""Codes, distances, selection and measures against brute force and worked values."""
import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from signgraph import analysis, kernels, memory, metrics
from signgraph.functions import codec, distance
from signgraph.plans.table_queries import curve


def brute(a, b):
    a, b = np.asarray(a, float), np.asarray(b, float)
    sa, sb = np.abs(a) > np.abs(a).mean(), np.abs(b) > np.abs(b).mean()
    return int((((a > 0) != (b > 0)) * (1 + sa) * (1 + sb)).sum())


def dist(x):
    m = kernels.Metric.of("bq2", x)
    return m.among(np.arange(len(x)))


@pytest.mark.parametrize("dim", [4, 63, 64, 65, 130])
def test_columns_equal_brute_force(spark, dim):
    x = np.random.default_rng(dim).normal(size=(12, dim)).astype(np.float32)
    x[0, :] = -1
    x[0, -1] = 1
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>")
    p = analysis.pairs(codec.encode_sm(df, dim))
    rows = p.select("a_vec_id", "b_vec_id", distance.bq(F.col("a_p"), F.col("a_s"), F.col("b_p"), F.col("b_s"), codec.words_of(dim)).alias("d"), distance.hamming(F.col("a_p"), F.col("b_p"), codec.words_of(dim)).alias("h")).collect()
    for r in rows:
        assert r.d == brute(x[r.a_vec_id], x[r.b_vec_id])
        assert r.h <= r.d <= 4 * r.h


@given(st.integers(2, 90), st.integers(0, 10_000))
@settings(max_examples=30, deadline=None)
def test_kernel_is_symmetric_bounded_and_equals_products(dim, seed):
    x = np.random.default_rng(seed).normal(size=(8, dim))
    d = dist(x)
    assert (d == d.T).all() and (np.diag(d) == 0).all() and d.max() <= 4 * dim
    y = kernels.levels(x)
    assert (d == kernels.bq_block(y, y)).all()
    assert (d == dist(x * 7.5)).all()
    both = np.concatenate([x[:1], -x[:1]])
    strong = int((np.abs(x[0]) > np.abs(x[0]).mean()).sum())
    assert dist(both)[0, 1] == dim + 3 * strong


def test_two_coordinates_share_signs_but_not_strengths():
    p, s, tau = kernels.sm_codes(np.array([[0.01, 0.99], [0.99, 0.01]]))
    assert p[0] == p[1] and s[0] != s[1] and tau.tolist() == [0.5, 0.5]
    assert dist(np.array([[0.01, 0.99], [0.99, 0.01]]))[0, 1] == 0


def test_it_is_not_a_metric():
    m = kernels.Metric("bq2", p=np.array([[1], [1], [0]], np.uint64), s=np.array([[1], [0], [1]], np.uint64))
    e = m.among(np.arange(3))
    assert e[0, 2] == 4 and e[0, 1] == 0 and e[1, 2] == 2


def test_selection_keeps_the_nearest_and_obeys_its_rule():
    r = np.random.default_rng(0)
    x = r.normal(size=(60, 64))
    m = kernels.Metric.of("bq2", x)
    d, ids = m.among(np.arange(60))[0, 1:], np.arange(1, 60)
    among = m.among(ids)
    sizes = []
    for a in (100, 110, 120, 150):
        kept = kernels.select_edges(d, ids, among, 16, a)
        assert kept[0] == np.lexsort((ids, d))[0]
        for k, i in enumerate(kept):
            assert all(100 * d[i] <= a * among[i, j] for j in kept[:k])
        sizes.append(len(kept))
    assert len(kernels.select_edges(d, ids, among, 16, 100, "coverage", m.a["p"][1:] ^ m.a["p"][0])) >= 1


def test_whole_beam_is_an_exact_scan():
    r = np.random.default_rng(1)
    m = kernels.Metric.of("bq2", r.normal(size=(200, 64)))
    nbrs, _ = kernels.link(m, 8, 64, 100)
    q = kernels.Metric.of("bq2", r.normal(size=(5, 64)))
    ids, d, _ = kernels.beam(m, nbrs, q, np.array([0]), 200)
    full = q.to(m, np.broadcast_to(np.arange(200), (5, 200)))
    for i in range(5):
        assert (np.sort(d[i][ids[i] >= 0]) == np.sort(full[i])).all()
    assert (nbrs != np.arange(200)[:, None]).all()


def test_theory_values():
    assert abs(analysis.gaussian_sqnr(1) - 4.40) < 0.05 and abs(analysis.gaussian_sqnr(2) - 9.03) < 0.05
    assert abs(distance.hoeffding(768, 0.05) - 0.043) < 0.001
    assert memory.compression_ratio(768) == 16
    assert abs(2 * (1 - 0.5 * (1 + math.erf(math.sqrt(2 / math.pi) / math.sqrt(2)))) - 0.4249) < 1e-3


def test_matched_recall_of_published_points(spark):
    got = {r.level: round(r.qps) for r in metrics.at_recall(curve(spark), [95.0, 97.0, 99.0]).where("system = 'float-vamana'").collect()}
    assert got == {95.0: 11557, 97.0: 8047, 99.0: 3538}  # as published


def test_bad_vectors_are_rejected_and_zero_is_degenerate(spark):
    df = spark.createDataFrame([(1, [0.0, 0.0]), (2, None), (3, [1.0]), (4, [float("nan"), 1.0]), (5, [1.0, 1.0])], "vec_id long, embedding array<float>")
    ok, bad = codec.split_rejects(df, "embedding", 2)
    assert sorted(r.vec_id for r in bad.collect()) == [2, 3, 4]
    rows = {r.vec_id: r for r in codec.encode_sm(ok, 2).collect()}
    assert rows[1].is_degenerate and not rows[5].is_degenerate and rows[5].s == [0]


def test_scan_reads_only_what_it_needs_and_limits_below_the_exchange(spark):
    from signgraph.plans.code_queries import bq_top

    plan = bq_top(spark, "/root/testdata/sf0.001")._jdf.queryExecution().toString()
    assert "WindowGroupLimit" in plan and "label" not in plan.split("ReadSchema")[-1].split("\n")[0]


def test_measured_facts(spark):
    v = spark.read.parquet("/root/testdata/sf0.01/embeddings.parquet")
    r = analysis.strong_rate(codec.encode_sm(v, 64), 64).first()
    assert round(r.p_s, 6) == 0.424563 and round(r.nu2, 4) == 5.1697
    assert analysis.compatibility(v).first().verdict == "no-go"
