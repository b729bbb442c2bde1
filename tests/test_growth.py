"""Queries on larger and oddly stored tables: folders of part files, deep graphs, pools of all nodes."""
import numpy as np
import pytest
from pyspark.sql import functions as F

from signgraph import analysis, kernels, metrics
from signgraph import index as index_module
from signgraph.functions import codec, distance
from signgraph.index import Index
from signgraph.operators import exact
from signgraph.plans import code_queries, index_queries, table_queries
from signgraph.streaming import log
from signgraph.workloads import split, workload

SF = "/root/testdata/sf0.001"


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_streams_read_a_folder_of_part_files(spark, tmp_path):
    v = spark.read.parquet(f"{SF}/embeddings.parquet")
    v.repartition(3).write.parquet(f"file://{tmp_path}/embeddings.parquet")
    assert rows(log.encode(spark, f"file://{tmp_path}")) == rows(log.encode(spark, SF)) and log.encode(spark, SF).count() == v.count()


def test_streams_leave_their_rows_in_files(spark):
    assert log.encode(spark, SF).inputFiles() and log.tumbling(spark, SF).inputFiles()
    e = spark.read.parquet(f"{SF}/events.parquet")
    assert rows(log.once_each(spark, SF)) == rows(e.groupBy("event_type").agg(F.count_distinct("event_id")))


def test_searched_stream_of_part_files(spark, tmp_path):
    v = spark.read.parquet(f"{SF}/embeddings.parquet")
    v.repartition(3).write.parquet(f"file://{tmp_path}/embeddings.parquet")
    q, b = split(v)
    i = Index.build(b, m=8, ef_c=64, alpha=1.0)
    got = log.searched(spark, f"file://{tmp_path}", i, "vec_id % 10 = 0", f"file://{tmp_path}/out", ef=64)
    assert got.select("qid").distinct().count() == q.count()


@pytest.mark.parametrize("kind", ["bq2", "bq1", "sq2", "float", "adc"])
def test_a_pool_of_all_nodes_ranks_what_is_reached(kind):
    x = np.random.default_rng(5).normal(size=(300, 32))
    m = kernels.Metric.of(kind, x)
    nbrs, _ = kernels.link(kernels.Metric.of("bq2", x), 6, 32, 100)
    nbrs[:, :][nbrs == 7] = -1  # no path meets node 7
    q = kernels.Metric.of(kind, x[:20] + 0.1)
    ids, d, work = kernels.beam(m, nbrs, q, np.array([0]), 300)
    seen = kernels.reached(nbrs, np.array([0]))
    every = q.to(m, np.broadcast_to(np.arange(300), (20, 300)))
    assert (q.cross(m) == every).all() and not seen[7]
    for i in range(20):
        want = [v for v in np.lexsort((np.arange(300), every[i])) if seen[v]]
        assert ids[i][ids[i] >= 0].tolist() == want and (work[i, :3] == seen.sum()).all()


@pytest.mark.parametrize("ties", ["id", "coverage", "adc"])
def test_many_targets_choose_as_one_does(ties):
    x = np.random.default_rng(6).normal(size=(200, 16))
    m, fine = kernels.Metric.of("bq2", x), kernels.Metric.of("adc", x)
    t = np.arange(0, 200, 9)
    d = m.among(np.arange(200))
    ids = np.stack([np.lexsort((np.arange(200), d[i]))[1:41] for i in t])
    near = np.take_along_axis(d[t], ids, 1)
    for refill in (False, True):
        got, gd = kernels.chosen(m, t, ids, near, 8, 110, ties, fine, refill)
        for k, i in enumerate(t.tolist()):
            cover = m.a["p"][ids[k]] ^ m.a["p"][i]
            want = kernels.select_edges(near[k], ids[k], m.among(ids[k]), 8, 110, ties, cover, fine.take(np.array([i])).to(fine, ids[k][None])[0], refill)
            assert got[k][got[k] >= 0].tolist() == ids[k][want].tolist()


def test_every_node_is_reached_after_linking():
    x = np.random.default_rng(7).normal(size=(200, 16))
    m = kernels.Metric.of("bq2", x)
    nbrs, nd = kernels.link(m, 4, 16, 100)
    nbrs[np.isin(nbrs, [11, 12, 150])] = -1
    assert kernels.reached(nbrs, np.array([0])).sum() < 200
    before = {(i, j) for i in range(200) for j in nbrs[i][nbrs[i] >= 0].tolist()}
    nbrs, nd = kernels.connected(m, nbrs, nd, 16)
    after = {(i, j) for i in range(200) for j in nbrs[i][nbrs[i] >= 0].tolist()}
    assert kernels.reached(nbrs, np.array([0])).all() and before < after


def test_wide_pools_are_reranked_and_filtered_in_the_task(spark, monkeypatch):
    monkeypatch.setattr(index_module, "WIDE", 20)
    q, b = split(workload(spark, SF, "W0"))
    i = Index.build(b, m=8, ef_c=64, alpha=1.0, shards=2)
    n = i.hot.count()
    cut = lambda df: rows(df.select("qid", "rank", "vec_id", F.round("sim", 9)))
    assert cut(i.search(q, ef=n)) == cut(exact.float_topk(q, b))
    few = b.where("label = 3")
    assert cut(i.search(q, ef=n, where=few)) == cut(exact.float_topk(q, few))
    assert "sim" not in i.candidates(q, ef=32).columns


def test_code_ranking_of_all_nodes_breaks_ties_by_id(spark):
    got, want = index_queries.beam_exhaustive(spark, SF), index_queries.bq_top(spark, SF)
    assert rows(got) == rows(want)


def test_breadth_first_search_of_a_long_path(spark):
    e = spark.createDataFrame([(k, k + 1) for k in range(16)], "src long, dst long")
    got = metrics.reachable(e, 0)
    assert rows(got) == [(k, k) for k in range(17)]


def test_walks_hold_no_plan_of_earlier_steps(spark):
    df = index_queries.margin_walk(spark, SF)
    assert df.count() == 50 and df._jdf.queryExecution().optimizedPlan().toString().count("Join") <= 2


@pytest.mark.parametrize("limit", [None, 600])
def test_angles_by_blocks_equal_the_expression(spark, monkeypatch, limit):
    if limit:
        monkeypatch.setattr(exact, "SIDE_BYTES", limit)  # the queries go in several passes
    zero = spark.createDataFrame([(5000, [0.0] * 64, 0)], "vec_id long, embedding array<float>, label int")
    v = code_queries.vectors(spark, SF).where("vec_id < 120").unionByName(zero)
    c = distance.cosine(F.col("a_embedding"), F.col("b_embedding"))
    p = analysis.pairs(v).select("a_vec_id", "b_vec_id", c.alias("c")).persist()
    deg = F.degrees(F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), F.col("c")))))
    got = analysis.angle_estimates(v, 64)
    want = p.select("a_vec_id", "b_vec_id", F.round(F.degrees(F.acos("c")), 6))
    assert rows(got.where("true_deg is not null").select("a", "b", "true_deg")) == rows(want.where("c is not null")) and got.count() == want.count()
    a, b = analysis.angle_stats(v).first(), p.agg(F.count("*"), F.avg(deg), F.stddev_pop(deg)).first()
    assert a[0] == b[0] and np.allclose(a[1:], b[1:], atol=1e-9)
    assert rows(analysis.angle_hist(v)) == rows(p.groupBy(F.floor(deg / 5).cast("int")).count())


def angle_rows(v):
    """Brute force over all ordered pairs: the angle by signs, and by cosines summed in the order of the coordinates."""
    x = {r.vec_id: np.array(r.embedding, float) for r in v.collect()}
    out = {}
    for a, y in x.items():
        for b, z in x.items():
            if a != b:
                dot, n = 0.0, [0.0, 0.0]
                for p, q in zip(y, z, strict=True):
                    dot, n = dot + p * q, [n[0] + p * p, n[1] + q * q]
                out[a, b] = int(((y > 0) != (z > 0)).sum()) * 180.0 / len(y), np.degrees(np.arccos(dot / (np.sqrt(n[0]) * np.sqrt(n[1]))))
    return out


@pytest.mark.parametrize("cell", [4096, 17])
def test_angles_are_estimated_for_every_pair(spark, monkeypatch, cell):
    monkeypatch.setattr(exact, "CELL", cell, raising=False)
    v = code_queries.vectors(spark, SF).where("vec_id % 50 <> 0 and vec_id < 60")  # no id is divisible by 50
    monkeypatch.setattr(code_queries, "vectors", lambda s, d: v)
    got = code_queries.QUERIES["angle_estimate"](spark, SF).collect()
    want = angle_rows(v)
    assert len(got) == len(want) == 58 * 57 and {(r.a, r.b) for r in got} == set(want)
    assert max(abs(r[k] - want[r.a, r.b][k - 2]) for r in got for k in (2, 3)) <= 5.1e-7


def test_cells_of_many_batches_and_odd_rows(spark, monkeypatch):
    monkeypatch.setattr(exact, "CELL", 40, raising=False)
    monkeypatch.setattr(exact, "DEALT", 2, raising=False)  # several cells of a task, one behind another
    held = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "7")
    try:
        odd = spark.createDataFrame([(None, [1.0] * 64, 0), (900, None, 0), (901, [], 0), (-3, [0.0] * 64, 0)], "vec_id long, embedding array<float>, label int")
        v = code_queries.vectors(spark, SF).where("vec_id < 100")
        got = rows(analysis.angle_estimates(v.unionByName(odd), 64, every=1).where("true_deg is not null"))
        n = analysis.angle_estimates(v.unionByName(odd), 64, every=1).count()
        none = analysis.angle_estimates(v.where("vec_id < 0"), 64, every=1).count()
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", held)
    monkeypatch.setattr(exact, "CELL", 4096, raising=False)
    assert got == rows(analysis.angle_estimates(v, 64, every=1)) and len(got) == 100 * 99
    assert n == 101 * 100 and none == 0  # a zero row has an angle by signs only; rows without an id or coordinates have none


def test_no_pair_leaves_a_block_of_angle_statistics(spark):
    v = code_queries.vectors(spark, SF)
    for df in (analysis.angle_stats(v), analysis.angle_hist(v)):
        assert "Cartesian" not in (p := df._jdf.queryExecution().optimizedPlan().toString()) and "acos" not in p.lower()


def test_misranking_bound_of_brute_force(spark):
    v = code_queries.vectors(spark, SF).where("vec_id < 200")
    codes = code_queries.sm(spark, SF).where("vec_id < 200")
    trip = analysis.triplets(v)
    y = {r.vec_id: kernels.levels(np.array([r.embedding], float))[0] for r in v.collect()}
    z = np.array([np.where(y[r.q] * y[r.w] < 0, abs(y[r.q] * y[r.w]), 0) - np.where(y[r.q] * y[r.v] < 0, abs(y[r.q] * y[r.v]), 0) for r in trip.collect()])
    got = analysis.misrank_bound(codes, trip, 64).first()
    assert np.allclose([got.mu, got.v], [z.mean(0).sum(), z.var(0).sum()])


def test_scalar_codes_rank_as_the_expression_does(spark):
    q, b = code_queries.halves(codec.encode_sq2(code_queries.vectors(spark, SF), span="global"))
    want = exact.code_topk(code_queries.q_side(q, "code"), b, distance.l1(F.col("q_code"), F.col("code")), 10)
    assert rows(code_queries.sq2_top(spark, SF)) == rows(want)


def test_timed_totals_are_those_of_all_pairs(spark):
    got = {r.setting: r.value for r in index_queries.exp_kernel(spark, SF).where("metric = 'total'").collect()}
    assert len(got) == 4 and len(set(got.values())) == 1


def test_distances_are_timed_in_tasks(spark):
    x = np.random.default_rng(8).normal(size=(700, 64))
    m = kernels.Metric.of("bq2", x)
    got = index_queries.nanoseconds(spark, x, {"bq2": lambda a, b: index_queries._distances("bq2", a, b)})["bq2"]
    assert got[0] > 0 and got[1] == m.cross(m).sum()


@pytest.mark.parametrize("name", ["matched_recall", "pareto_front", "ef_for_recall", "scale_delta", "rsd", "tier_table", "memory_model"])
def test_series_come_from_a_table(spark, name):
    df = (table_queries.QUERIES | code_queries.QUERIES)[name](spark, SF)
    assert df.count() and any(SF in f for f in df.inputFiles())


def test_equal_points_of_a_front_stay_together(spark):
    c = spark.createDataFrame([("a", 90.0, 5.0), ("b", 90.0, 5.0), ("c", 90.0, 4.0), ("d", 80.0, 5.0), ("e", 80.0, 6.0)], "system string, recall double, qps double")
    assert sorted(r.system for r in metrics.pareto(c).collect()) == ["a", "b", "e"]
