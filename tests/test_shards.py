"""Shards whose number grows with the rows: no task builds or searches a whole table."""
import pytest
from pyspark.sql import functions as F

from signgraph.operators import exact
from signgraph.plans import index_queries as iq
from signgraph.workloads import split, workload

SF = "/root/testdata/sf0.001"


@pytest.fixture
def built(monkeypatch):
    """Shards of each index that is built."""
    n, real = [], iq.Index.build
    monkeypatch.setattr(iq.Index, "build", staticmethod(lambda *a, **k: n.append(k["shards"]) or real(*a, **k)))
    return n


def rows(df):
    return sorted(map(tuple, df.collect()))


@pytest.mark.parametrize("name", ["index_exhaustive", "filtered_index", "stream_search"])
def test_exhaustive_searches_use_shards_and_no_second_ranking(spark, monkeypatch, built, name):
    q, b = split(workload(spark, SF, "W0"))
    want = exact.float_topk(q, b.where("label = 3") if name == "filtered_index" else b, 10)
    monkeypatch.setattr(iq, "SPREAD", 100, raising=False)
    monkeypatch.setattr(iq, "ranked", None)
    assert rows(iq.QUERIES[name](spark, SF)) == rows(want.select("qid", "rank", "vec_id", F.round("sim", 6)))
    assert built[0] > 3


def test_sizes_of_wide_rows_are_those_of_shards(spark, monkeypatch, built):
    monkeypatch.setattr(iq, "FLOATS", 1 << 20, raising=False)
    got = {(r[0], r[1], r[2]): r[3] for r in iq.QUERIES["exp_memory"](spark, SF).collect()}
    assert len(got) == 32 and max(built) > 3 and min(built) == 1
    assert abs(got["D=1536", "files", "cold_mb"] / got["D=1536", "model", "cold_mb"] - 1) < 0.2


def test_orders_and_probe_index_every_row_in_shards(spark, monkeypatch, built):
    monkeypatch.setattr(iq, "PER", 100, raising=False)
    monkeypatch.setattr(iq, "workload", lambda s, d, n, base=None: workload(s, d, "W1").where("vec_id < 400"))
    got = {r["workload"]: r for r in iq.exp_probe(spark, SF).collect()}
    assert len(got) == 11 and set(built) == {4} and min(r["recall"] for r in got.values()) >= 0.9
    assert iq.order_stability(spark, SF).first()["recall"] >= 0.9 and set(built) == {4}


def test_every_row_is_walked_alone_in_every_shard(spark):
    v = workload(spark, SF, "W1")
    i = iq.Index.build(v, m=8, ef_c=64, alpha=1.0, shards=3)
    want = i.candidates(v, ef=64).select("qid", "evals").distinct()  # the work of a shard, of those in the best 64 of all
    got = i.walks(64).persist()
    assert got.groupBy("qid").count().where("count = 3").count() == v.count() == 500
    assert want.join(got, ["qid", "evals"], "left_anti").count() == 0 and got.where("took <= 0").count() == 0


def test_tails_are_those_of_all_rows(spark, monkeypatch, built):
    small = lambda s, d, n, size=0: workload(s, d, "W1").where("vec_id < 200")
    monkeypatch.setattr(iq, "WALKED", 100, raising=False)
    monkeypatch.setattr(iq.quantized, "sample", None)
    monkeypatch.setattr(iq, "large", small)
    monkeypatch.setattr(iq, "order_stability", lambda s, d: s.createDataFrame([(1.0, 0.0)], "recall double, rsd double"))
    asked, real = [], iq.Index.walks
    monkeypatch.setattr(iq.Index, "walks", lambda i, ef: asked.append((w := real(i, ef)).groupBy("qid").count().collect()) or w)
    got = {(r["setting"], r["metric"]): r["value"] for r in iq.exp_robust(spark, SF).collect()}
    assert len(got) == 8 and built == [5, 4] and len(asked[0]) == 500 and {r["count"] for r in asked[0]} == {5}
    assert got["one query", "p50_ms"] > 0 and 1 <= got["one query", "p99/p50"] <= got["one query", "p999/p50"]
