"""Registered queries on graphs, searches, baselines and experiments: (workload, setting, metric, value) tables and rankings."""
from __future__ import annotations

import time
from concurrent.futures import ThreadPoolExecutor
from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .. import analysis, kernels, memory, metrics
from ..baselines import layered, quantized
from ..functions import codec, distance
from ..index import Index
from ..operators import exact
from ..sources.shared import drop, scratch, settled
from ..workloads import generated, split, text_vectors, workload
from .code_queries import BQ, EXACT, K, LISTS, ORACLES as CODE_SQL, SPLIT, adc_top, bq_expr, bq_top, exact_top, ham_top, halves, q_side, s_bq, s_cos, s_rank, sm, sq2_top, vectors

QUERIES: dict = {}
ORACLES: dict = {}
EFS = (16, 32, 64, 128, 256)


def add(name: str, sql: str | None = None):
    def put(run):
        QUERIES[name] = run
        if sql:
            ORACLES[name] = sql
        return run

    return put


def ranked(df: DataFrame) -> DataFrame:
    """The exact ranking of a set's queries."""
    truth = exact.float_topk(*split(df.persist()), 10).persist()
    truth.count()
    return truth


def indexed(df: DataFrame, truth: DataFrame | None = None, **how) -> tuple[Index, DataFrame, DataFrame, list[tuple[str, float]]]:
    """Index on the base half of a set, its queries, the exact ranking (unless given), and what the build cost."""
    q, b = split(df.persist())
    truth = ranked(df) if truth is None else truth
    t = time.perf_counter()
    i = Index.build(b, **({"m": 8, "ef_c": 64, "alpha": "auto", "shards": 1} | how))
    one = i.hot.agg(F.count("*").alias("n"), F.sum((F.size("p") + F.size("s")) * 8).alias("code"), F.sum(F.size("nbrs") * 4 + 4).alias("adj"), F.avg(F.size("nbrs")).alias("degree")).first()
    took = time.perf_counter() - t
    return i, q, truth, [("build_s", took), ("hot_mb", ((one["code"] or 0) + (one["adj"] or 0)) / (1 << 20)), ("degree", one["degree"] or 0.0), ("rows", one["n"])]


def build(s: SparkSession, d: str, name: str = "W0", **how) -> tuple[Index, DataFrame, DataFrame]:
    return indexed(workload(s, d, name), **how)[:3]


#: Nodes of a shard where many are built at once, those of a shard whose rows are all ranked, and the bytes of a shard's floats.
PER, SPREAD, FLOATS = 8_000, 2_000, 32 << 20
#: Nodes of a shard whose single walks are timed: a query walks every shard, and a walk hardly grows with its shard.
WALKED = 1 << 16


def shards_of(b: DataFrame, dim: int = 64, per: int | None = None) -> int:
    """Shards of about `per` nodes, fewer where rows are wide: a task holds one, and their number grows with the rows."""
    return max(1, -(-b.count() // max(1, min(per or PER, FLOATS // (8 * dim)))))


def every_row(df: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Queries (ids divisible by 50), all rows, and the exact ranking of the other rows for each query."""
    df = df.persist()
    q = df.where(F.col("vec_id") % analysis.EVERY == 0)
    truth = exact.float_topk(q, df, 10, skip_self=True).persist()
    truth.count()
    return q, df, truth


def others(i: Index, q: DataFrame, ef: int) -> DataFrame:
    """The ten best of each query's pool, itself left out."""
    return exact.top(i.best(q, 11, ef).where("qid <> vec_id"), 10, "qid", F.col("sim").desc(), F.col("vec_id")).select("qid", "rank", "vec_id", "sim")


def spread(s: SparkSession, d: str) -> tuple[Index, DataFrame]:
    """Small shards for searches that rank all rows, and the queries; no exact ranking is made."""
    q, b = split(workload(s, d, "W0").persist())
    return Index.build(b, m=8, ef_c=64, alpha="auto", shards=shards_of(b, per=SPREAD)), q


def table(s: SparkSession, rows: list[tuple]) -> DataFrame:
    return s.createDataFrame([(a, str(b), c, float(v)) for a, b, c, v in rows], "workload string, setting string, metric string, value double")


def recall_of(got: DataFrame, truth: DataFrame) -> float:
    return round(metrics.recall(got, truth).first()["recall"] or 0.0, 6)


def timed(got: DataFrame, truth: DataFrame, n: int) -> tuple[float, float]:
    """Recall, and queries a second of the whole batch with its rerank."""
    t = time.perf_counter()
    held = got.persist()
    held.count()
    took = time.perf_counter() - t
    r = recall_of(held, truth)
    held.unpersist()
    return r, n / took


def grid(index: Index, q: DataFrame, truth: DataFrame, name: str, label: str, efs=EFS, **how) -> list[tuple]:
    """Recall, queries a second and touched share for each beam width."""
    out = []
    n = q.count()
    for ef in efs:
        c = index.best(q, ef=ef, **how).persist()  # walked once for its ranking and its work
        r, qps = timed(exact.top(c, 10, "qid", F.col("sim").desc(), F.col("vec_id")).select("qid", "rank", "vec_id", "sim"), truth, n)
        w = c.groupBy("qid").agg(F.max("evals").alias("e"), F.max("touched").alias("n")).agg(F.avg(F.col("e") / F.col("n"))).first()[0]
        c.unpersist()
        out += [(name, f"{label} ef={ef}", "recall", r), (name, f"{label} ef={ef}", "qps", qps), (name, f"{label} ef={ef}", "touched", w or 0.0)]
    return out


@add("build_graph_edges")
def build_graph_edges(s, d):
    return build(s, d)[0].edges()


@add("build_degree_hist")
def build_degree_hist(s, d):
    i = build(s, d)[0]
    return metrics.graph_health(i.edges(), i.hot.count())


def _metric(kind: str):
    def run(s, d):
        return build(s, d, metric=kind)[0].edges()

    return run


for _k in ("bq1", "sq2", "float"):
    QUERIES[f"build_metric_{_k}"] = _metric(_k)


@add("build_metric_pq")
def build_metric_pq(s, d):
    q, b = split(workload(s, d, "W0"))
    return Index.build(b, m=8, ef_c=64, alpha=1.0, metric="pq", book=kernels.pq_fit(quantized.sample(b), 8)).edges()


@add("build_batched")
def build_batched(s, d):
    rows = []
    for batch in ("sequential", "chunk:1000", "doubling"):
        i, q, t, cost = indexed(workload(s, d, "W1"), batch=batch)
        rows += grid(i, q, t, "W1", batch, [32]) + [("W1", batch, *c) for c in cost]
    return table(s, rows)


@add("beam_search")
def beam_search(s, d):
    i, q, _ = build(s, d)
    return i.candidates(q, ef=32).select("qid", "vec_id", "d")


@add("beam_exhaustive", f"{SPLIT}, {BQ} SELECT * FROM bq")
def beam_exhaustive(s, d):
    """A pool of all nodes: the beam ranks as the code scan does, so every node is reached and every distance right."""
    i, q, _ = build(s, d)
    return i.search(q, ef=i.hot.count(), rerank=False).select("qid", "rank", "vec_id", F.col("value").cast("int").alias("value"))


@add("index_exhaustive", f"{SPLIT}, {EXACT} SELECT qid, rank, vec_id, round(value, 6) AS sim FROM ex")
def index_exhaustive(s, d):
    i, q = spread(s, d)
    return i.search(q, ef=i.hot.count()).select("qid", "rank", "vec_id", F.round("sim", 6).alias("sim"))


@add("filtered_index", f"{SPLIT}, {s_rank('ex', s_cos('q', 'b'), desc=True, join='b.label = 3')} SELECT qid, rank, vec_id, round(value, 6) AS sim FROM ex")
def filtered_index(s, d):
    """Search among the rows of one label, with a pool that holds all nodes in the end."""
    i, q = spread(s, d)
    return i.search(q, ef=i.hot.count(), where=vectors(s, d).where("label = 3")).select("qid", "rank", "vec_id", F.round("sim", 6).alias("sim"))


@add("index_search")
def index_search(s, d):
    i, q, _ = build(s, d)
    return i.search(q, ef=64).select("qid", "rank", "vec_id", F.round("sim", 6).alias("sim"))


@add("search_work")
def search_work(s, d):
    i, q, _ = build(s, d)
    return i.candidates(q, ef=32).groupBy("qid").agg(*[F.max(c).alias(c) for c in ("evals", "expanded", "hops", "touched")], (F.count("*") * 4 * i.dim).alias("cold_bytes"))


@add("reachability")
def reachability(s, d):
    i, _, _ = build(s, d)
    e = settled(i.edges())
    entry = i.hot.where("place = 0").first()["node"]
    return metrics.reachable(e, entry).groupBy("hops").agg(F.count("*").alias("nodes"))


@add("reciprocal_edges")
def reciprocal_edges(s, d):
    return metrics.reciprocal(build(s, d)[0].edges())


@add("incremental_insert")
def incremental_insert(s, d):
    q, b = split(workload(s, d, "W1").persist())
    i = Index.build(b.where("vec_id % 2 = 0"), m=8, ef_c=64, alpha=1.0).insert(b.where("vec_id % 2 = 1"), ef_c=64).delete(b.where("vec_id % 50 = 7").select("vec_id"))
    return i.search(q, ef=64).select("qid", "rank", "vec_id", F.round("sim", 6).alias("sim"))


@add("order_stability")
def order_stability(s, d):
    q, b, t = every_row(workload(s, d, "W1"))
    n = shards_of(b)
    rows = together([lambda k=k: (float(recall_of(others(Index.build(b, m=8, ef_c=64, alpha="auto", shards=n, seed=k), q, 32), t)),) for k in range(5)], 5)
    r = s.createDataFrame(rows, "recall double")
    return r.agg(F.count("*").alias("builds"), F.avg("recall").alias("recall"), (F.stddev_samp("recall") / F.avg("recall")).alias("rsd"))


@add("margin_walk")
def margin_walk(s, d):
    """Greedy walks on the built graph: from the entry to the neighbour nearest to the query until none is nearer; each step's exact
    distance and its code estimate, judged by the margin rule."""
    i, q, _ = build(s, d, "W1")
    v = i.vectors.select("vec_id", "embedding")
    e = settled(i.edges().select("src", "dst"))
    far = lambda a, b: 1 - distance.cosine(F.col(a), F.col(b))
    code = codec.encode_sm(v.unionByName(q.select("vec_id", "embedding")), i.dim).select("vec_id", "p", "s").persist()
    entry = i.hot.where("place = 0").first()["node"]
    qs = q.select(F.col("vec_id").alias("qid"), F.col("embedding").alias("qe")).persist()
    step = qs.select("qid", "qe", F.lit(entry).cast("long").alias("at"), F.lit(0).alias("pos")).join(v.select(F.col("vec_id").alias("at"), "embedding"), "at").select("qid", "at", "pos", far("qe", "embedding").alias("d"))
    step = settled(step)  # each step has a plan of its own
    walk = step
    while not step.isEmpty():
        out = step.join(e, step["at"] == e["src"]).join(qs, "qid").join(v.select(F.col("vec_id").alias("dst"), "embedding"), "dst")
        near = out.select("qid", F.col("dst").alias("at"), (F.col("pos") + 1).alias("pos"), far("qe", "embedding").alias("nd"), "d").where("nd < d")
        step = settled(exact.top(near, 1, "qid", F.col("nd"), F.col("at")).select("qid", "at", "pos", F.col("nd").alias("d")))
        walk = walk.unionByName(step)
    est = walk.join(code.select(F.col("vec_id").alias("qid"), F.col("p").alias("q_p"), F.col("s").alias("q_s")), "qid").join(code.withColumnRenamed("vec_id", "at"), "at")
    est = est.select(F.col("qid").alias("path"), "pos", "d", (distance.bq(F.col("q_p"), F.col("q_s"), F.col("p"), F.col("s"), codec.words_of(i.dim)) / (4.0 * i.dim)).alias("est"))
    return analysis.margin_path(est, 0.01, 0.25, 0.25)


# -- baselines ---------------------------------------------------------------------------------------------------------------


def _ranked(df: DataFrame) -> DataFrame:
    return df.select("qid", "rank", "vec_id", F.round("sim" if "sim" in df.columns else "value", 6).alias("sim"))


def _hnsw(h: str):
    def run(s, d):
        q, b = split(workload(s, d, "W1"))
        return _ranked(layered.search(q, b, heuristic=h))

    return run


for _h in layered.VARIANTS:
    QUERIES["hnsw_search" if _h == "diverse" else f"hnsw_search_{_h}"] = _hnsw(_h)
_U = "(('0x' || substr(md5('42:' || CAST(vec_id AS VARCHAR)), 1, 8))::BIGINT + 1) / 4294967296.0"


@add("hnsw_levels", f"SELECT CAST(floor(-ln({_U}) / ln(16)) AS INTEGER) AS level, count(*) AS n FROM embeddings GROUP BY 1")
def hnsw_levels(s, d):
    return layered.levels(vectors(s, d), 16).groupBy("level").agg(F.count("*").alias("n"))


@add("vamana_float")
def vamana_float(s, d):
    i, q, _ = build(s, d, "W1", m=16, metric="float")
    return _ranked(i.search(q, ef=64))


def _pq(rerank: bool, width: int = 1):
    def run(s, d):
        q, b = split(workload(s, d, "W1").persist())
        book = kernels.pq_fit(quantized.sample(b), 8)
        i = Index.build(b, m=16, ef_c=64, alpha=1.0, metric="float").coded("pq", book=book)
        return _ranked(i.search(q, ef=64, nav="pq", rerank=rerank, width=width))

    return run


QUERIES |= {"pq_graph_search": _pq(True), "pq_only_search": _pq(False)}


@add("pq_codes")
def pq_codes(s, d):
    _, b = split(workload(s, d, "W1"))
    return quantized.pq_codes(b, kernels.pq_fit(quantized.sample(b), 8)).select("vec_id", F.hex("code").alias("code"))


def disk_search(i: Index, q: DataFrame, ef: int, cache: int, k: int = 10) -> tuple[DataFrame, DataFrame]:
    """Byte codes navigate with beam width 4; expanding a node that is not cached reads its row from storage, which also holds its
    floats, so the rerank of expanded nodes reads nothing more. (ranking, reads a query)."""
    c = i.candidates(q, ef=ef, nav="pq", width=4, cache=cache).persist()
    work = c.groupBy("qid").agg(F.sum("expanded").alias("expanded"), F.max("hops").alias("rounds"), F.sum("reads").alias("reads")) if i.shards > 1 else c.groupBy("qid").agg(F.max("expanded").alias("expanded"), F.max("hops").alias("rounds"), F.max("reads").alias("reads"))
    return exact.rerank(c, i.vectors, q, k), work


@add("disk_graph_search")
def disk_graph_search(s, d):
    """Ranking, and the counted work and reads of each query; the cache holds the tenth of the nodes nearest to the entry."""
    q, b = split(workload(s, d, "W1").persist())
    i = Index.build(b, m=16, ef_c=64, alpha=1.0, metric="float").coded("pq", book=kernels.pq_fit(quantized.sample(b), 8))
    got, work = disk_search(i, q, 64, max(1, i.hot.count() // 10))
    return got.join(work, "qid").select("qid", "rank", "vec_id", F.round("sim", 6).alias("sim"), "expanded", "rounds", "reads")


def given_centres(s, d, n: int = 16) -> np.ndarray:
    """The base rows of least id as centres."""
    x = halves(vectors(s, d))[1].orderBy("vec_id").limit(n).select(F.col("embedding").cast("array<double>")).collect()
    c = np.array([r[0] for r in x])
    return c / np.linalg.norm(c, axis=1, keepdims=True)


S_LISTS = f"{SPLIT}, ce AS (SELECT vec_id AS cid, e, row_number() OVER (ORDER BY vec_id) - 1 AS l FROM b ORDER BY vec_id LIMIT 16), sb AS (SELECT x.vec_id, l, row_number() OVER (PARTITION BY x.vec_id ORDER BY round({s_cos('x', 'ce')}, 9) DESC, l) AS r FROM k x, ce)"


@add("ivf_assign", f"{S_LISTS} SELECT CAST(l AS INTEGER) AS list_id, count(*) AS n FROM sb JOIN b USING (vec_id) WHERE r = 1 GROUP BY 1")
def ivf_assign(s, d):
    return quantized.assign(halves(vectors(s, d))[1], given_centres(s, d)).groupBy("list_id").agg(F.count("*").alias("n"))


@add("ivf_search_given_centroids", f"{S_LISTS}, pr AS (SELECT x.vec_id AS qid, y.vec_id FROM sb x JOIN sb y ON x.l = y.l AND x.r <= 4 AND y.r = 1 WHERE x.vec_id % 10 = 0 AND y.vec_id % 10 <> 0), z AS (SELECT pr.qid, pr.vec_id, {s_cos('q', 'b')} AS sim FROM pr JOIN q ON q.vec_id = pr.qid JOIN b ON b.vec_id = pr.vec_id), rk AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY round(sim, 12) DESC, vec_id) AS rank FROM z) SELECT qid, CAST(rank AS INTEGER) AS rank, vec_id, round(sim, 6) AS sim FROM rk WHERE rank <= 10")
def ivf_search_given_centroids(s, d):
    q, b = halves(vectors(s, d))
    return _ranked(quantized.ivf_search(q, b, given_centres(s, d), 4))


@add("ivf_probe")
def ivf_probe(s, d):
    q, b = split(workload(s, d, "W1"))
    return _ranked(quantized.ivf_search(q, b, kernels.kmeans(quantized.sample(b), 16), 4))


@add("opq_ivfpq")
def opq_ivfpq(s, d):
    q, b = split(workload(s, d, "W1"))
    return _ranked(quantized.opq_ivfpq(q, b, 16, 4, 8, 40))


_HAD = "WITH u AS (SELECT vec_id, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) - 1 AS i FROM embeddings), n AS (SELECT vec_id, sqrt(sum(x * x)) AS n FROM u GROUP BY vec_id), y AS (SELECT u.vec_id, j, sum(x / n * CASE WHEN (7 * i + 3) % 11 % 2 = 0 THEN 1 ELSE -1 END * CASE WHEN bit_count(i & j) % 2 = 0 THEN 1 ELSE -1 END) / 8 AS y FROM u JOIN n USING (vec_id), (SELECT unnest(range(64)) AS j) GROUP BY 1, 2) SELECT vec_id, CAST(sum(CASE WHEN y > 0 THEN 1 ELSE 0 END) AS INTEGER) AS ones, CAST(sum(CASE WHEN y > 0 THEN j ELSE 0 END) AS INTEGER) AS places, round(sum(abs(y)) / 8, 6) AS factor FROM y GROUP BY vec_id"


@add("rot1bit_codes", _HAD)
def rot1bit_codes(s, d):
    """Codes under the fixed rotation: how many bits are set, the sum of their places, and the factor."""
    c = quantized.rot1bit_codes(vectors(s, d), turn=quantized.hadamard(64))
    set_ = F.filter(F.sequence(F.lit(0), F.lit(63)), lambda i: F.call_function("shiftrightunsigned", F.col("code")[0], i).bitwiseAND(F.lit(1).cast("long")) == 1)
    return c.select("vec_id", F.size(set_).alias("ones"), F.aggregate(set_, F.lit(0), lambda a, x: a + x).alias("places"), F.round("factor", 6).alias("factor"))


@add("rot1bit_search")
def rot1bit_search(s, d):
    q, b = split(workload(s, d, "W1"))
    return _ranked(quantized.rot1bit_search(q, b, quantized.list_count(b.count()), 6, 6))


@add("rot1bit_bound_search")
def rot1bit_bound_search(s, d):
    """The error bound decides which rows are refined."""
    q, b = split(workload(s, d, "W1"))
    return _ranked(quantized.rot1bit_search(q, b, quantized.list_count(b.count()), 6, None))


@add("lsh_hyperplane_codes")
def lsh_hyperplane_codes(s, d):
    return quantized.hyperplane_codes(vectors(s, d)).select("vec_id", F.col("code")[0].alias("c0"))


@add("lsh_hyperplane_search")
def lsh_hyperplane_search(s, d):
    q, b = split(workload(s, d, "W1"))
    return _ranked(quantized.hyperplane_search(q, b))


@add("posthoc_bq_search")
def posthoc_bq_search(s, d):
    i, q, _ = build(s, d, "W1", m=16, metric="float")
    return _ranked(i.search(q, ef=64, nav="bq2"))


# -- streams and the SQL front end -----------------------------------------------------------------------------------------------


@add("stream_search", f"{SPLIT}, {EXACT} SELECT qid, rank, vec_id, round(value, 6) AS sim FROM ex")
def stream_search(s, d):
    """Query vectors as a stream, searched on a static index with a pool of all nodes."""
    from ..streaming import log

    i, _ = spread(s, d)
    return log.searched(s, d, i, "vec_id % 10 = 0", scratch(s), ef=i.hot.count()).select("qid", "rank", "vec_id", F.round("sim", 6).alias("sim"))


@add("stream_recall", "SELECT CAST(count(*) * 10 AS BIGINT) AS hits FROM embeddings WHERE vec_id % 10 = 0")
def stream_recall(s, d):
    """Hits of a stream of rankings against the static truth; with a pool of all nodes every one is a hit."""
    from ..streaming import log

    i, q, t = build(s, d)
    path = scratch(s)
    i.search(q, ef=i.hot.count()).write.parquet(path)
    return log.running_recall(s, path, t).select("hits")


@add("stream_dedup", "SELECT event_type, count(DISTINCT event_id) AS n FROM events GROUP BY event_type")
def stream_dedup(s, d):
    from ..streaming import log

    return log.once_each(s, d)


@add("sql_topk_merge", f"{SPLIT}, {BQ} SELECT qid, rank, vec_id, CAST(value AS DOUBLE) AS value FROM bq")
def sql_topk_merge(s, d):
    """The table function over all pairs of queries and rows."""
    from ..functions import table as fn

    fn.register(s)
    q, b = halves(sm(s, d))
    exact.paired(q_side(q, "p", "s"), b).select("qid", "vec_id", bq_expr().alias("value")).createOrReplaceTempView("sg_pairs")
    return s.sql("SELECT * FROM topk_merge(TABLE(SELECT * FROM sg_pairs) PARTITION BY qid ORDER BY (value, vec_id), 10)")


@add("sql_ann_search", f"{SPLIT}, {BQ} SELECT qid, rank, vec_id, CAST(value AS BIGINT) AS d FROM bq")
def sql_ann_search(s, d):
    """The table function on a saved index, with a pool of all nodes."""
    from ..functions import table as fn

    fn.register(s)
    q, b = split(workload(s, d, "W0"))
    path = scratch(s)
    i = Index.build(b, m=8, ef_c=64, alpha=1.0, shards=1, path=path)
    q.select(F.col("vec_id").alias("qid"), F.col("embedding").cast("array<double>").alias("v"), F.pmod("vec_id", F.lit(8)).alias("part")).createOrReplaceTempView("sg_queries")
    return s.sql(f"SELECT * FROM ann_search(TABLE(SELECT * FROM sg_queries) PARTITION BY (part), '{path}', 10, {i.hot.count()})")


@add("sql_sm_encode", CODE_SQL["sm_planes"])
def sql_sm_encode(s, d):
    from ..functions import table as fn

    fn.register(s)
    vectors(s, d).createOrReplaceTempView("sg_vectors")
    return s.sql("SELECT vec_id, c.p[0] AS p0, c.s[0] AS s0 FROM (SELECT vec_id, sm_encode(cast(embedding AS array<double>)) AS c FROM sg_vectors)")


@add("vecs_round_trip", "SELECT count(*) AS n, round(sum(s), 3) AS total FROM (SELECT vec_id, list_sum(embedding::DOUBLE[]) AS s FROM embeddings)")
def vecs_round_trip(s, d):
    """Vectors written as a binary vector file and read back."""
    import pyarrow as pa

    from ..sources import vecs

    v = vectors(s, d).select("vec_id", F.col("embedding").cast("array<double>"))
    path = scratch(s)

    def run(batches):
        for k, b in enumerate(batches):
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([vecs.to_fvecs(exact.matrix(b.column(1)).astype(np.float32))], pa.binary())], names=["k", "content"])

    v.mapInArrow(run, "k int, content binary").write.parquet(path)
    return vecs.parsed(s.read.parquet(path).select("content", F.lit(0).cast("long").alias("h"))).agg(F.count("*").alias("n"), F.round(F.sum(F.aggregate(F.col("embedding").cast("array<double>"), F.lit(0.0), lambda a, x: a + x)), 3).alias("total"))


# -- text ---------------------------------------------------------------------------------------------------------------------


def doc_vectors(s, d) -> DataFrame:
    return text_vectors(s.read.parquet(f"{d}/documents.parquet"), "doc_id", "text")


@add("hashvec_documents")
def hashvec_documents(s, d):
    return codec.encode_sm(doc_vectors(s, d), 64).select("vec_id", F.round("tau", 5).alias("tau"), F.col("p")[0].alias("p0"), F.col("s")[0].alias("s0"))


def near_codes(c: DataFrame, radius: int = 2) -> DataFrame:
    """(a, b, d, kind) of codes (vec_id, p, s) of one word. 'copy': b has the code of a, the least id with that code.
    'near': a < b are such least ids and their sign words differ in at most radius (2 at most) bits; d is the two-bit distance."""
    if radius > 2:
        raise ValueError("the cells are made for a radius of 2 at most")
    own = c.groupBy("p", "s").agg(F.min("vec_id").alias("a"))
    copies = c.join(own, ["p", "s"]).where("vec_id <> a").select("a", F.col("vec_id").alias("b"), F.lit(0).alias("d"), F.lit("copy").alias("kind"))
    w = F.col("p")[0]
    block = [F.shiftrightunsigned(w, 16 * k).bitwiseAND(F.lit(0xFFFF)) for k in range(4)]
    # Two differing bits leave two of the four blocks whole.
    cells = F.array(*[F.struct(F.lit(4 * i + j).alias("t"), F.shiftleft(block[i], 16).bitwiseOR(block[j]).alias("k")) for i in range(4) for j in range(i + 1, 4)])
    dealt = own.select("a", "p", "s", F.explode(cells).alias("cell"))
    x, y = (dealt.select("cell", F.col("a").alias(n), F.col("p").alias(f"{n}_p"), F.col("s").alias(f"{n}_s")) for n in "ab")
    met = x.join(y, "cell").where("a < b").where(distance.hamming(F.col("a_p"), F.col("b_p"), 1) <= radius)
    near = met.select("a", "b", distance.bq(F.col("a_p"), F.col("a_s"), F.col("b_p"), F.col("b_s"), 1).alias("d"), F.lit("near").alias("kind")).distinct()
    return copies.unionByName(near)


@add("near_dup_docs")
def near_dup_docs(s, d):
    """Documents with equal codes as members of their least id, and pairs of such ids whose signs differ in two bits at most."""
    return near_codes(codec.encode_sm(doc_vectors(s, d), 64).select("vec_id", "p", "s"))


@add("benchmark_leak_nn")
def benchmark_leak_nn(s, d):
    q = text_vectors(s.read.parquet(f"{d}/benchmark.parquet"), "item_id", "text")
    return _ranked(exact.float_topk(q, doc_vectors(s, d), 3))


# -- experiments ----------------------------------------------------------------------------------------------------------------

SETS = ("W0", "W1", "W1b", "W2", "W3d", "W5")
#: Rows of the generated sets: enough that a beam of 64 is a small share of them.
LARGE = 8_000


def together(tasks, threads: int = 4) -> list:
    """Independent driver-side tasks, a few at a time: their jobs share the cluster."""
    with ThreadPoolExecutor(threads) as pool:
        return list(pool.map(lambda f: f(), tasks))


@add("exp_main")
def exp_main(s, d):
    def one(n):
        i, q, t, cost = indexed(workload(s, d, n))
        return grid(i, q, t, n, "bq2") + [(n, "build", *c) for c in cost]

    return table(s, sum(together([lambda n=n: one(n) for n in SETS]), []))


def curves(s, d) -> DataFrame:
    """(system, setting, recall in per cent, qps) of every system on W1. Graphs stand in shards of about PER nodes, and all are built at
    once; searches are timed four at a time, and one job at the end compares their rankings with the exact one."""
    df = workload(s, d, "W1").persist()
    t, (q, b) = ranked(df), split(df)
    n, rows, at = q.count(), b.count(), t.select("qid").distinct().count()
    shards, lists, x = shards_of(b), quantized.list_count(rows), quantized.sample(b)
    make = lambda **how: Index.build(b, m=16, ef_c=64, alpha="auto", shards=shards, **how)

    def held(g):
        (g.rows if isinstance(g, layered.Layered) else g.hot).count()
        return g

    def floats():
        f, book = held(make(metric="float")), kernels.pq_fit(x, 8)
        c = f.coded("pq", book=book)
        return f, held(replace(c, hot=c.hot.persist()))

    tasks = [floats, lambda: held(make()), *[lambda h=h: held(layered.Layered.build(b, heuristic=h, shards=shards)) for h in layered.VARIANTS]]
    tasks += [lambda: quantized.opq_fitted(b, lists, 8, x=x), lambda: quantized.rot1bit_fitted(b, lists, x=x), lambda: kernels.kmeans(x, lists)]
    (f, coded), i, *done = together(tasks, len(tasks))
    graphs, (opq, rot, centres) = dict(zip(layered.VARIANTS, done, strict=False)), done[len(layered.VARIANTS) :]
    cache = max(1, rows // shards // 10)
    probes, efs = [p for p in (1, 2, 4, 8, 16) if p <= lists], (12, 16, 32, 64, 128)
    best = lambda g, ef, nav=None: exact.top(g.best(q, 10, ef, nav), 10, "qid", F.col("sim").desc(), F.col("vec_id"))
    runs = [("sm-graph", ef, lambda ef=ef: best(i, ef)) for ef in efs]
    runs += [("float-graph", ef, lambda ef=ef: best(f, ef)) for ef in efs]
    runs += [("posthoc-codes", ef, lambda ef=ef: best(f, ef, "bq2")) for ef in efs]
    runs += [("pq-graph-float", ef, lambda ef=ef: best(coded, ef, "pq")) for ef in efs]
    runs += [("pq-graph", ef, lambda ef=ef: coded.search(q, ef=ef, nav="pq", rerank=False)) for ef in efs]
    runs += [("disk-graph", ef, lambda ef=ef: disk_search(coded, q, ef, cache)[0]) for ef in efs]
    for h, g in graphs.items():
        runs += [(f"layered-{h}", ef, lambda ef=ef, g=g: g.search(q, ef)) for ef in efs]
    runs += [("ivf-float", p, lambda p=p: quantized.ivf_search(q, b, centres, p)) for p in probes]
    runs += [("opq-ivfpq", p, lambda p=p: quantized.opq_ivfpq(q, b, lists, p, 8, 40, fitted=opq)) for p in probes]
    runs += [("rotated-1bit", f"{p}x{k}", lambda p=p, k=k: quantized.rot1bit_search(q, b, lists, p, k, fitted=rot)) for p in probes for k in (2, 8)]
    runs += [("hyperplanes", w, lambda w=w: quantized.hyperplane_search(q, b, 128, w)) for w in (16, 8, 4)]

    path = scratch(s)

    def one(k, run):
        began = time.perf_counter()
        run().select("qid", "rank", "vec_id").write.parquet(f"{path}/run={k}")
        return time.perf_counter() - began

    took = together([lambda k=k, r=r: one(k, r) for k, (*_, r) in enumerate(runs)])
    found = s.read.schema("qid long, rank int, vec_id long, run int").parquet(path).where("rank <= 10")
    hits = dict(found.join(t.select("qid", "vec_id"), ["qid", "vec_id"]).groupBy("run").count().collect())
    drop(s, path)
    for got in (i.hot, f.hot, coded.hot, *[g.rows for g in graphs.values()]):
        got.unpersist()
    out = [(name, str(setting), 100 * round(hits.get(k, 0) / max(1, 10 * at), 6), n / took[k]) for k, (name, setting, _) in enumerate(runs)]
    return s.createDataFrame(out, "system string, setting string, recall double, qps double")


@add("exp_matched")
def exp_matched(s, d):
    """Every system's curve, its rate at 95, 97 and 99 per cent recall by interpolation, our lead there, and the Pareto points."""
    c = curves(s, d).persist()
    best = c.groupBy("system", "recall").agg(F.max("qps").alias("qps"))
    x = metrics.at_recall(best, [95.0, 97.0, 99.0]).persist()
    own = x.where("system = 'sm-graph'").select("level", F.col("qps").alias("own"))
    at = x.select("system", F.concat(F.lit("at "), F.col("level").cast("int").cast("string")).alias("setting"), F.lit("qps").alias("metric"), F.col("qps").alias("value"))
    lead = x.join(F.broadcast(own), "level").select("system", F.concat(F.lit("at "), F.col("level").cast("int").cast("string")).alias("setting"), F.lit("lead").alias("metric"), (F.col("own") / F.col("qps")).alias("value"))
    front = metrics.pareto(c.select("recall", "qps", "system")).select("system", F.format_number("recall", 2).alias("setting"), F.lit("pareto qps").alias("metric"), F.col("qps").alias("value"))
    points = c.select("system", "setting", F.explode(F.array(F.struct(F.lit("recall").alias("metric"), (F.col("recall") / 100).alias("value")), F.struct(F.lit("qps").alias("metric"), F.col("qps").alias("value")))).alias("p")).select("system", "setting", "p.metric", "p.value")
    return points.unionByName(at).unionByName(lead).unionByName(front).withColumnRenamed("system", "workload")


def _sweep(values, label, how, sets=("W0", "W1"), efs=(16, 64, 256)):
    def run(s, d):
        held = {n: workload(s, d, n).persist() for n in sets}
        truth = dict(zip(sets, together([lambda v=v: ranked(v) for v in held.values()]), strict=True))

        def one(n, v):
            i, q, t, cost = indexed(held[n], truth[n], **how(v))
            rows = [*grid(i, q, t, n, f"{label}={v}", efs), *[(n, f"{label}={v}", *c) for c in cost]]
            i.hot.unpersist()
            return rows

        # The values stand in the order of their work: the longest builds come first.
        return table(s, sum(together([lambda n=n, v=v: one(n, v) for v in reversed(values) for n in sets], 8), []))

    return run


QUERIES |= {
    "exp_m": _sweep([4, 8, 16, 24, 32, 48, 64], "m", lambda v: {"m": v, "alpha": 1.2}),
    "exp_efc": _sweep([16, 32, 64, 128, 256, 512], "ef_c", lambda v: {"ef_c": v}),
    "exp_alpha": _sweep([(8, 1.0), (8, 1.05), (8, 1.1), (8, 1.2), (8, 1.25), (8, 10**7), (16, 1.0), (16, 1.2), (32, 1.0), (32, 1.2)], "m,alpha", lambda v: {"m": v[0], "alpha": v[1]}),
    "exp_ties": _sweep(["id", "coverage", "adc"], "ties", lambda v: {"ties": v}),
    "exp_lowrank": _sweep(["bq2"], "metric", lambda v: {"metric": v}, ("W0", "W1", "W6_768", "W7"), (64,)),
}


def nanoseconds(s: SparkSession, queries: np.ndarray, ways: dict, base: DataFrame | None = None) -> dict[str, tuple[float, int]]:
    """Nanoseconds a distance and the total of all distances of each way, over all queries with all rows of base (or with themselves):
    taken in the tasks, block by block. A way prepares a side once by way(x, None) and measures two prepared blocks by way(a, b)."""
    import pyarrow as pa

    held, given = s.sparkContext.broadcast(queries), base is not None

    def run(batches):
        q = held.value
        mine = {n: [f(q[lo : lo + 512], None) for lo in range(0, len(q), 512)] for n, f in ways.items()}
        took, total, pairs = dict.fromkeys(ways, 0.0), dict.fromkeys(ways, 0), 0
        for t in batches:
            x = exact.matrix(t.column(1)) if given else q[t.column(0).to_numpy()]
            for lo in range(0, len(x), 256):
                pairs += len(q) * len(x[lo : lo + 256])
                for n, f in ways.items():
                    began = time.perf_counter()
                    own = f(x[lo : lo + 256], None)
                    total[n] += sum(f(a, own) for a in mine[n])
                    took[n] += time.perf_counter() - began
        yield pa.RecordBatch.from_arrays([pa.array(list(ways)), pa.array([took[n] for n in ways], pa.float64()), pa.array([int(total[n]) for n in ways], pa.int64()), pa.array([pairs] * len(ways), pa.int64())], names=["way", "took", "total", "pairs"])

    src = base.select("vec_id", F.col("embedding").cast("array<double>")) if given else s.range(len(queries))
    out = src.mapInArrow(run, "way string, took double, total long, pairs long").groupBy("way").agg(F.sum("took").alias("took"), F.sum("total").alias("total"), F.sum("pairs").alias("pairs"))
    return {r["way"]: (r["took"] / max(1, r["pairs"]) * 1e9, r["total"]) for r in out.collect()}


def _distances(kind: str, a, b):
    """A block's codes (b None), or the sum of all distances of two blocks."""
    if b is None:
        return kernels.Metric.of(kind, a, **({"span": (-1.0, 1.0)} if kind == "sq2" else {}))
    step = 16
    return sum(int((m := a.take(np.arange(lo, min(lo + step, a.n)))).to(b, np.broadcast_to(np.arange(b.n), (m.n, b.n))).sum()) for lo in range(0, a.n, step))


def _bits(count):
    def way(a, b):
        if b is None:
            return kernels.sm_codes(a)[:2]
        total = 0
        for lo in range(0, len(a[0]), 64):
            x = a[0][lo : lo + 64, None] ^ b[0][None]
            l, r = x & a[1][lo : lo + 64, None], x & b[1][None]
            total += int((count(x) + count(l) + count(r) + count(l & r)).sum())
        return total

    return way


def _product(a, b):
    return kernels.levels(a) if b is None else int(kernels.bq_block(a, b).sum(dtype=np.int64))


@add("exp_encoding")
def exp_encoding(s, d):
    """Overlap, nanoseconds a distance and graph recall of the three codes on one set, W1."""
    v = workload(s, d, "W1").persist()
    truth = exact.float_topk(v, v, 10, skip_self=True).persist()
    x = quantized.sample(v)
    rows = []
    for kind in ("bq1", "bq2", "sq2"):
        got = exact.float_topk(v, v, 10, kind=kind, skip_self=True, **({"span": (float(x.min()), float(x.max()))} if kind == "sq2" else {}))
        took = nanoseconds(s, x, {kind: lambda a, b, kind=kind: _distances(kind, a, b)})[kind][0]
        rows += [("W1", kind, "overlap", recall_of(got, truth)), ("W1", kind, "ns", took)]
        i, q, tr, cost = indexed(v, metric=kind)
        rows += grid(i, q, tr, "W1", kind, [32, 64, 128, 256]) + [("W1", kind, *c) for c in cost]
    return table(s, rows)


def large(s, d, name: str, n: int = LARGE) -> DataFrame:
    return workload(s, d, name, generated(s, n, 64))


def boundary(s, d, ef: int = 64) -> DataFrame:
    """(workload, rows, recall, qps, tier, overlap, verdict): large generated sets and the sets of the given tables."""
    def one(n, df, rows):
        i, q, t, cost = indexed(df, shards=max(1, rows // LARGE))
        r, qps = timed(i.search(q, ef=ef), t, q.count())
        p = analysis.compatibility(df, 2_000).first()
        return (n, int(dict(cost)["rows"]), r, qps, p["overlap"], p["verdict"])

    tasks = [lambda n=n: one(f"{n} large", large(s, d, n), LARGE) for n in ("W0", "W1", "W1b", "W2", "W2_2", "W5", "W6_256", "W7")]
    tasks += [lambda n=n: one(n, workload(s, d, n), LARGE) for n in ("W0", "W1", "W1b", "W1c", "W2_0.5", "W2", "W2_2", "W3", "W3d", "W4", "W5", "W5b", "W6_256", "W7", "W8", "W8c")]
    tasks += [lambda: one("W8b", workload(s, d, "W8b"), workload(s, d, "W8b").count())]
    out = s.createDataFrame(together(tasks, 8), "workload string, rows long, recall double, qps double, overlap double, verdict string")
    return out.withColumn("tier", metrics.tier(100 * F.col("recall")))


@add("exp_boundary")
def exp_boundary(s, d):
    return boundary(s, d).select("workload", "rows", "recall", "qps", "tier")


@add("exp_probe")
def exp_probe(s, d):
    """The probe's verdict beside the tier that the graph reached; queries are the ids divisible by 50, every row is indexed."""
    def one(n, df):
        q, b, t = every_row(df)
        i = Index.build(b, m=8, ef_c=64, alpha="auto", shards=shards_of(b))
        p = analysis.compatibility(b, 2_000).first()
        out = (n, p["n"], p["overlap"], p["verdict"], recall_of(others(i, q, 64), t))
        for held in (i.hot, t, b):
            held.unpersist()
        return out

    sets = [(n, workload(s, d, n)) for n in ("W0", "W1", "W1b", "W1c", "W2", "W3", "W5", "W8")] + [(f"{n} large", large(s, d, n, 4_000)) for n in ("W0", "W1", "W6_256")]
    out = s.createDataFrame(together([lambda n=n, v=v: one(n, v) for n, v in reversed(sets)])[::-1], "workload string, n long, overlap double, verdict string, recall double")
    return out.withColumn("tier", metrics.tier(100 * F.col("recall")))


@add("exp_scale")
def exp_scale(s, d):
    """One query set against a clustered set of growing size: the smaller sets are parts of the larger ones."""
    sizes = (2_000, 4_000, 8_000, 16_000)
    every = workload(s, d, "W1", generated(s, sizes[-1] * 10 // 9, 64)).persist()
    q, base = split(every)
    q = q.where("vec_id < 2000").persist()
    rows = []
    for n in sizes:
        b = base.orderBy("vec_id").limit(n).persist()
        t = exact.float_topk(q, b, 10).persist()
        began = time.perf_counter()
        i = Index.build(b, m=8, ef_c=64, alpha=1.0, shards=1)
        i.hot.count()
        rows += [(f"n={n}", "build", "build_s", time.perf_counter() - began), *grid(i, q, t, f"n={n}", "bq2", [16, 64, 256])]
    return table(s, rows)


@add("exp_ps")
def exp_ps(s, d):
    rows = []
    for n in ("W0", "W1", "W1b", "W2", "W3", "W3d", "W4", "W5", "W6_256", "W7", "W8", "W8b", "W8c"):
        v = workload(s, d, n)
        k = codec.dimension(v)
        r = analysis.strong_rate(codec.encode_sm(v, k), k).first()
        rows += [(n, f"D={k}", "p_s", round(r["p_s"], 6)), (n, f"D={k}", "nu2", round(r["nu2"], 6))]
    return table(s, rows)


@add("exp_memory")
def exp_memory(s, d):
    """Hot and cold megabytes at three widths: by formula, and of the saved files."""
    ids = split(workload(s, d, "W0").select("vec_id"))[1]
    n = ids.count()

    def one(dim):
        path = scratch(s)
        i = Index.build(split(workload(s, d, f"W6_{dim}"))[1], m=8, ef_c=32, alpha=1.0, shards=shards_of(ids, dim), path=path)
        got, file = memory.estimate(s, n, [dim], 8, 4).first(), memory.measure(path)
        drop(s, path)
        return [(f"D={dim}", "model", c, got[c]) for c in ("code_mb", "adj_mb", "cold_mb", "ratio")] + [(f"D={dim}", "files", k, v) for k, v in file.items()]

    return table(s, sum(reversed(together([lambda k=k: one(k) for k in (1536, 768, 384, 64)], 2)), []))


@add("exp_cold")
def exp_cold(s, d):
    """Hot table and floats in memory, floats on storage, everything on storage: equal recall, other rates."""
    path = scratch(s)
    i, q, t = build(s, d, "W1")
    i.save(path)
    disk = Index.load(s, path)
    ram = Index(i.vectors.persist(), i.hot, i.dim, i.m, i.metric, i.seed, i.shards, i.more)
    ram.vectors.count()
    warm = Index(disk.vectors, i.hot, i.dim, i.m, i.metric, i.seed, i.shards, i.more)
    rows = []
    for name, x in (("memory", ram), ("floats on storage", warm), ("all on storage", disk)):
        timed(x.search(q, ef=16), t, 1)  # code is compiled before a rate is taken
        for ef in (32, 64, 128, 256):
            r, qps = timed(x.search(q, ef=ef), t, q.count())
            rows += [("W1", f"{name} ef={ef}", "recall", r), ("W1", f"{name} ef={ef}", "qps", qps)]
    drop(s, path)
    return table(s, rows)


@add("exp_adc")
def exp_adc(s, d):
    rows = []
    for n in ("W0", "W1"):
        i, q, t = build(s, d, n)
        rows += grid(i, q, t, n, "symmetric", [32, 64]) + grid(i, q, t, n, "adc", [32, 64], nav="adc")
    return table(s, rows)


@add("exp_robust")
def exp_robust(s, d):
    """Five insertion orders; the tail of single-query kernel times, every row a query of all rows; rates of one and of several tasks."""
    def linked():
        b = workload(s, d, "W1").persist()
        i = Index.build(b, m=8, ef_c=64, alpha=1.0, shards=shards_of(b, per=WALKED))
        i.hot.count()
        return i

    # All rows are linked here while the orders build; what is timed comes after both.
    r, i = together([lambda: order_stability(s, d).first(), linked], 2)
    rows = [("W1", "5 orders", "recall", r["recall"]), ("W1", "5 orders", "rsd", r["rsd"])]
    took = i.walks(64).groupBy("qid").agg(F.round(1e6 * F.sum("took")).alias("us"))  # whole microseconds: few values to count
    p50, p99, p999 = took.agg(F.percentile("us", [0.5, 0.99, 0.999])).first()[0]
    i.hot.unpersist()
    rows += [("W1", "one query", "p50_ms", 1e-3 * p50), ("W1", "one query", "p99/p50", p99 / p50), ("W1", "one query", "p999/p50", p999 / p50)]
    q, b = split(large(s, d, "W1", 4_000).persist())
    i = Index.build(b, m=8, ef_c=64, alpha=1.0, shards=4)
    i.hot.count()
    for tasks in (1, 2, 4):
        c = q.select(F.explode(F.sequence(F.lit(0), F.lit(3))).alias("shard"), "vec_id", "embedding").coalesce(1).count() and i
        t = time.perf_counter()
        got = Index(c.vectors, c.hot.coalesce(tasks), c.dim, c.m, c.metric, c.seed, c.shards, c.more, c.alpha100).candidates(q, ef=64).count()
        rows.append(("W1 large", f"{tasks} tasks", "qps", q.count() / (time.perf_counter() - t) if got else 0.0))
    return table(s, rows)


BUDGET_SQL = CODE_SQL["recall_at_budget"].replace("rank <= 64", "rank <= 256").replace("[10, 16, 32, 64]", "[10, 16, 32, 64, 128, 256]")


@add("exp_budget", BUDGET_SQL)
def exp_budget(s, d):
    truth = exact_top(s, d).persist()
    g = metrics.recall_at_budget(bq_top(s, d, 256), truth, [10, 16, 32, 64, 128, 256])
    return g.select("budget", F.round("recall", 6).alias("recall"), F.round("precision", 6).alias("precision"))


@add("exp_kernel")
def exp_kernel(s, d):
    """Nanoseconds a distance of four ways over the query set against all rows; the totals must agree."""
    v = vectors(s, d)
    q = v.where("vec_id % 10 = 0").select(F.col("embedding").cast("array<double>").alias("v")).toArrow().combine_chunks()
    q = exact.matrix(q.column("v").combine_chunks())
    pairs = len(q) * v.count()
    table8 = np.array([bin(k).count("1") for k in range(256)], np.uint8)
    ways = {"bitwise_count": _bits(lambda m: np.bitwise_count(m).sum(-1, dtype=np.int64)), "byte table": _bits(lambda m: table8[m.view(np.uint8).reshape(*m.shape, 8)].sum((-1, -2), dtype=np.int64)), "gemm": _product}
    rows = [("W0", n, m, x) for n, got in nanoseconds(s, q, ways, v).items() for m, x in zip(("ns", "total"), got, strict=True)]
    c = sm(s, d).select("vec_id", "p", "s").persist()
    c.count()
    t = time.perf_counter()
    total = exact.paired(q_side(c.where("vec_id % 10 = 0"), "p", "s"), c).agg(F.sum(bq_expr())).first()[0]
    rows += [("W0", "generated code", "ns", (time.perf_counter() - t) / pairs * 1e9), ("W0", "generated code", "total", total)]
    return table(s, rows)


@add("exp_angles")
def exp_angles(s, d):
    """Spread of pair angles beside the overlap, and their correlation over the sets."""
    def one(n):
        v = workload(s, d, n).persist()  # made once: those of documents read all texts
        a, p = analysis.angle_stats(v).first(), analysis.compatibility(v, 2_000).first()
        v.unpersist()
        return n, a["sd"], a["mean"], p["overlap"]

    # The longest come first; the rows stand in the order of the names.
    names = ("W0", "W1", "W1b", "W2", "W2_2", "W3d", "W5", "W6_256", "W7", "W8")
    done = dict(together([lambda n=n: (n, one(n)) for n in reversed(names)]))
    got = [done[n] for n in names]
    rows = [(n, "pairs", m, round(v, 6)) for n, sd, mean, o in got for m, v in (("sd_angle", sd), ("mean_angle", mean), ("overlap", o))]
    r = np.corrcoef([g[1] for g in got], [g[3] for g in got])[0, 1]
    return table(s, [*rows, ("all", "sd_angle, overlap", "correlation", round(float(r), 6))])


@add("exp_dim")
def exp_dim(s, d):
    def one(k):
        i, q, t, cost = indexed(generated(s, 1_000, k))
        return [*grid(i, q, t, f"D={k}", "bq2", [64]), *[(f"D={k}", "build", *c) for c in cost]]

    return table(s, sum([one(k) for k in (64, 128, 256, 512, 1024)], []))
