"""Beams that start from a node of each query's own."""
import numpy as np
import pytest

from signgraph import kernels
from signgraph.baselines import layered, quantized
from signgraph.operators import exact
from signgraph.workloads import split, workload


@pytest.mark.parametrize("ef", [1, 4, 12, 120])
def test_each_query_starts_at_its_own_entry(ef):
    r = np.random.default_rng(3)
    base, q = kernels.Metric.of("float", r.normal(size=(120, 8))), kernels.Metric.of("float", r.normal(size=(30, 8)))
    nbrs, _ = kernels.link(base, 3, 16, 100)
    nbrs[60:] = -1  # what a query meets depends on where it starts
    entry = r.integers(0, 120, (30, 1))
    got = kernels.beam(base, nbrs, q, entry, ef)
    for k in range(30):
        one = kernels.beam(base, nbrs, q.take(np.array([k])), entry[k], ef)
        assert all((a[k] == b[0]).all() for a, b in zip(got, one, strict=True))


def test_layers_are_searched_by_more_queries_than_the_beam_is_wide(spark):
    q, b = split(workload(spark, "/root/testdata/sf0.001", "W1"))
    t = exact.float_topk(q, b, 10)
    got = [layered.search(q, b, ef=12, shards=n).select("qid", "vec_id") for n in (1, 3)]
    near = [x.join(t, ["qid", "vec_id"], "left_semi").count() / t.count() for x in got]
    assert near[0] > 0.7 and near[1] > 0.7


@pytest.mark.parametrize("band", [4, 8])
def test_narrow_bands_are_compared_without_a_row_for_each_pair(spark, monkeypatch, band):
    q, b = split(workload(spark, "/root/testdata/sf0.001", "W1"))
    code = [{r["vec_id"]: r["code"] for r in quantized.hyperplane_codes(v, 128).collect()} for v in (q, b)]
    mask = (1 << band) - 1
    agree = lambda x, y: any(not (u ^ v) >> j & mask for u, v in zip(x, y, strict=True) for j in range(0, 64, band))
    met = spark.createDataFrame([(i, j) for i, x in code[0].items() for j, y in code[1].items() if agree(x, y)], "qid long, vec_id long")
    want = sorted(map(tuple, exact.rerank(met, b, q).collect()))
    monkeypatch.setattr(exact, "rerank", None)
    assert sorted(map(tuple, quantized.hyperplane_search(q, b, 128, band).collect())) == want
