"""Registered queries on codes, distances, rankings and measures, with SQL on coordinates beside each."""
from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import analysis, memory, metrics
from ..functions import codec, distance
from ..operators import exact

DIM, W, K = 64, 1, 10

# -- SQL parts ----------------------------------------------------------------------------------------------------------

U = "u AS (SELECT vec_id, label, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) - 1 AS i FROM embeddings)"
T = "t AS (SELECT vec_id, sum(abs(x)) / count(*) AS tau FROM u GROUP BY vec_id)"
C = "c AS (SELECT u.vec_id, u.label, u.i, u.x, tau, CASE WHEN x > 0 THEN 1 ELSE 0 END AS p, CASE WHEN abs(x) > tau THEN 1 ELSE 0 END AS s FROM u JOIN t USING (vec_id))"
L = "k AS (SELECT vec_id, any_value(label) AS label, list(((2 * p - 1) * (1 + s))::DOUBLE ORDER BY i) AS y, list((1 + s)::DOUBLE ORDER BY i) AS ay, list((2 * p - 1)::DOUBLE ORDER BY i) AS h, list(x ORDER BY i) AS e FROM c GROUP BY vec_id)"
Q = "q AS (SELECT * FROM k WHERE vec_id % 10 = 0), b AS (SELECT * FROM k WHERE vec_id % 10 <> 0)"
CODES, LISTS, SPLIT = f"WITH {U}, {T}, {C}", f"WITH {U}, {T}, {C}, {L}", f"WITH {U}, {T}, {C}, {L}, {Q}"


def s_bq(a: str, b: str) -> str:
    return f"CAST((list_dot_product({a}.ay, {b}.ay) - list_dot_product({a}.y, {b}.y)) / 2 AS INTEGER)"


def s_ham(a: str, b: str) -> str:
    return f"CAST(({DIM} - list_dot_product({a}.h, {b}.h)) / 2 AS INTEGER)"


def s_cos(a: str, b: str) -> str:
    return f"(list_dot_product({a}.e, {b}.e) / (sqrt(list_dot_product({a}.e, {a}.e)) * sqrt(list_dot_product({b}.e, {b}.e))))"


def s_rank(name: str, score: str, k: int = K, desc: bool = False, join: str = "true", left: str = "q", right: str = "b") -> str:
    return f"{name} AS (SELECT qid, rank, vec_id, value FROM (SELECT {left}.vec_id AS qid, {right}.vec_id AS vec_id, {score} AS value, CAST(row_number() OVER (PARTITION BY {left}.vec_id ORDER BY {score} {'DESC' if desc else ''}, {right}.vec_id) AS INTEGER) AS rank FROM {left} JOIN {right} ON {join}) WHERE rank <= {k})"


EXACT = s_rank("ex", s_cos("q", "b"), desc=True)
BQ = s_rank("bq", s_bq("q", "b"))


# -- frames -------------------------------------------------------------------------------------------------------------


def vectors(spark: SparkSession, d: str) -> DataFrame:
    return spark.read.parquet(f"{d}/embeddings.parquet").select("vec_id", "embedding", "label")


def sm(spark: SparkSession, d: str, tau: str = "mean") -> DataFrame:
    return codec.encode_sm(vectors(spark, d), DIM, tau=tau, keep=("vec_id", "label", "embedding"))


def halves(df: DataFrame) -> tuple[DataFrame, DataFrame]:
    return df.where("vec_id % 10 = 0"), df.where("vec_id % 10 <> 0")


def q_side(df: DataFrame, *cols: str) -> DataFrame:
    return df.select(F.col("vec_id").alias("qid"), *[F.col(c).alias(f"q_{c}") for c in cols])


def bq_expr():
    return distance.bq(F.col("q_p"), F.col("q_s"), F.col("p"), F.col("s"), W)


def ham_expr():
    return distance.hamming(F.col("q_p"), F.col("p"), W)


def bq_top(spark, d, k=K) -> DataFrame:
    q, b = halves(sm(spark, d))
    return exact.code_topk(q_side(q, "p", "s"), b, bq_expr(), k)


def exact_top(spark, d, k=K) -> DataFrame:
    q, b = halves(vectors(spark, d))
    return exact.float_topk(q, b, k)


def adc_top(spark, d, k=K) -> DataFrame:
    q, b = halves(sm(spark, d))
    b = b.withColumn("y", distance.levels(F.col("p"), F.col("s"), DIM))
    return exact.code_topk(q_side(q, "embedding"), b, distance.adc(F.col("q_embedding"), F.col("y")), k, descending=True)


def sq2_top(spark, d, k=K) -> DataFrame:
    v = vectors(spark, d)
    lo, hi = v.select(F.min(F.array_min("embedding")), F.max(F.array_max("embedding"))).first()
    q, b = halves(v)
    return exact.float_topk(q, b, k, kind="sq2", span=(float(lo or 0), float(hi or 0))).select("qid", "rank", "vec_id", F.col("sim").cast("int").alias("value"))


def ham_top(spark, d, k=K) -> DataFrame:
    q, b = halves(sm(spark, d))
    return exact.code_topk(q_side(q, "p"), b, ham_expr(), k)


def reranked(spark, d, ef: int) -> DataFrame:
    q, b = halves(vectors(spark, d))
    return exact.rerank(bq_top(spark, d, ef), b, q, K)


def knn_exact(spark, d, k=K) -> DataFrame:
    v = vectors(spark, d)
    return exact.float_topk(v, v, k, skip_self=True)


def knn_bq(spark, d, k=K) -> DataFrame:
    v = vectors(spark, d)
    return exact.float_topk(v, v, k, kind="bq2", skip_self=True).select("qid", "rank", "vec_id", F.col("sim").cast("int").alias("value"))


ADC_S = "list_dot_product(q.e, b.y)"
ALL_PAIRS = "a AS (SELECT * FROM k), o AS (SELECT * FROM k)"
SQ2 = "g AS (SELECT min(x) AS lo, max(x) AS hi FROM u), z AS (SELECT vec_id, i, CASE WHEN hi > lo THEN greatest(0, least(3, floor((x - lo) * 4 / (hi - lo)))) ELSE 0 END AS v FROM u, g)"
KNN_EX = s_rank("ex", s_cos("a", "o"), desc=True, join="a.vec_id <> o.vec_id", left="a", right="o")
KNN_BQ = s_rank("bq", s_bq("a", "o"), join="a.vec_id <> o.vec_id", left="a", right="o")


def ranked6(df: DataFrame, name: str = "sim") -> DataFrame:
    return df.withColumn(name, F.round(name, 6))


def overlap_by(spark, d) -> DataFrame:
    truth = exact_top(spark, d)
    out = None
    for name, got in (("1-bit", ham_top(spark, d)), ("2-bit", bq_top(spark, d)), ("sq2", sq2_top(spark, d)), ("adc", adc_top(spark, d))):
        r = metrics.recall(got, truth).select(F.lit(name).alias("method"), F.round("recall", 6).alias("recall"))
        out = r if out is None else out.unionByName(r)
    return out


S_RECALL = "SELECT count(DISTINCT ex.qid) AS queries, round(count(r.vec_id) / (count(DISTINCT ex.qid) * 10.0), 6) AS recall FROM ex LEFT JOIN {r} r ON ex.qid = r.qid AND ex.vec_id = r.vec_id"

QUERIES, ORACLES = {}, {}


def add(name: str, run, sql: str | None = None) -> None:
    QUERIES[name] = run
    if sql:
        ORACLES[name] = sql


i32 = lambda c, n: c.cast("int").alias(n)
one = lambda c: codec.ones(F.col(c), W)

add("encode_sign", lambda s, d: codec.encode_sign(vectors(s, d), DIM).select("vec_id", i32(one("p"), "ones")), f"{CODES} SELECT vec_id, CAST(sum(p) AS INTEGER) AS ones FROM c GROUP BY vec_id")
add("encode_sm", lambda s, d: sm(s, d).select("vec_id", F.round("tau", 6).alias("tau"), i32(one("p"), "ones"), i32(one("s"), "strong"), i32(F.bit_count(F.col("p")[0].bitwiseAND(F.col("s")[0])), "both")), f"{CODES} SELECT vec_id, round(any_value(tau), 6) AS tau, CAST(sum(p) AS INTEGER) AS ones, CAST(sum(s) AS INTEGER) AS strong, CAST(sum(p * s) AS INTEGER) AS both FROM c GROUP BY vec_id")
_word = "CAST(CASE WHEN w >= 9223372036854775808 THEN w - 18446744073709551616 ELSE w END AS BIGINT)"
add("sm_planes", lambda s, d: sm(s, d).select("vec_id", F.col("p")[0].alias("p0"), F.col("s")[0].alias("s0")), f"{CODES}, pw AS (SELECT vec_id, sum(p * (CAST(1 AS HUGEINT) << CAST(i AS INTEGER))) AS a, sum(s * (CAST(1 AS HUGEINT) << CAST(i AS INTEGER))) AS bb FROM c GROUP BY vec_id) SELECT vec_id, {_word.replace('w', 'a')} AS p0, {_word.replace('w', 'bb')} AS s0 FROM pw".replace("CaSE", "CASE"))


def tau_variants(s, d) -> DataFrame:
    out = None
    for t in codec.TAUS:
        r = analysis.strong_rate(codec.encode_sm(vectors(s, d), DIM, tau=t), DIM).select(F.lit(t).alias("variant"), F.round("p_s", 6).alias("p_s"))
        out = r if out is None else out.unionByName(r)
    return out


_half = f"(list_sort(list(abs(x)))[{DIM // 2}] + list_sort(list(abs(x)))[{DIM // 2 + 1}]) / 2"
add("encode_tau_variants", tau_variants, f"WITH {U}, g AS (SELECT avg(abs(x)) AS ga FROM u), m AS (SELECT vec_id, sum(abs(x)) / count(*) AS mean, {_half} AS median, 0.98 * sqrt(sum(x * x) / {DIM}) AS lloyd FROM u GROUP BY vec_id), r AS (SELECT avg(CASE WHEN abs(x) > mean THEN 1.0 ELSE 0 END) AS a, avg(CASE WHEN abs(x) > {math.sqrt(2 / math.pi) / math.sqrt(DIM)!r} THEN 1.0 ELSE 0 END) AS b, avg(CASE WHEN abs(x) > ga THEN 1.0 ELSE 0 END) AS c, avg(CASE WHEN abs(x) > median THEN 1.0 ELSE 0 END) AS d, avg(CASE WHEN abs(x) > lloyd THEN 1.0 ELSE 0 END) AS e FROM u JOIN m USING (vec_id), g) SELECT 'mean' AS variant, round(a, 6) AS p_s FROM r UNION ALL SELECT 'gauss', round(b, 6) FROM r UNION ALL SELECT 'global', round(c, 6) FROM r UNION ALL SELECT 'median', round(d, 6) FROM r UNION ALL SELECT 'lloyd', round(e, 6) FROM r")
add("encode_sq2", lambda s, d: codec.encode_sq2(vectors(s, d), span="global").select("vec_id", F.aggregate("code", F.lit(0), lambda a, v: a + v).alias("total"), i32(F.array_min("code"), "lo"), i32(F.array_max("code"), "hi")), f"WITH {U}, {SQ2} SELECT vec_id, CAST(sum(v) AS INTEGER) AS total, CAST(min(v) AS INTEGER) AS lo, CAST(max(v) AS INTEGER) AS hi FROM z GROUP BY vec_id")
add("encode_sq8", lambda s, d: codec.encode_sq8(vectors(s, d)).select("vec_id", F.aggregate("code", F.lit(0), lambda a, v: a + v).alias("total"), i32(F.array_min("code"), "lo"), i32(F.array_max("code"), "hi")), f"WITH {U}, g AS (SELECT i, min(x) AS lo, max(x) AS hi FROM u GROUP BY i), z AS (SELECT vec_id, CASE WHEN hi > lo THEN round((x - lo) * 255 / (hi - lo)) ELSE 0 END AS v FROM u JOIN g USING (i)) SELECT vec_id, CAST(sum(v) AS INTEGER) AS total, CAST(min(v) AS INTEGER) AS lo, CAST(max(v) AS INTEGER) AS hi FROM z GROUP BY vec_id")


def code_pairs(s, d) -> DataFrame:
    return analysis.pairs(sm(s, d).select("vec_id", "p", "s", "embedding"))


def _ab() -> list:
    return [F.col(c) for c in ("a_p", "a_s", "b_p", "b_s")]


def _names() -> list:
    return [F.col("a_vec_id").alias("a"), F.col("b_vec_id").alias("b")]


S_AB = f"{LISTS}, a AS (SELECT * FROM k WHERE vec_id % 50 = 0), o AS (SELECT * FROM k)"
S_ON = "FROM a JOIN o ON a.vec_id <> o.vec_id"
add("bq_distance_pairs", lambda s, d: code_pairs(s, d).select(*_names(), distance.bq(*_ab(), W).alias("d")), f"{S_AB} SELECT a.vec_id AS a, o.vec_id AS b, {s_bq('a', 'o')} AS d {S_ON}")
add("bq_categories", lambda s, d: code_pairs(s, d).select(*_names(), *distance.categories(*_ab(), W, DIM)), f"{CODES}, j AS (SELECT a.vec_id AS a, o.vec_id AS b, a.p = o.p AS e, a.s + o.s AS t FROM c a JOIN c o ON a.i = o.i AND a.vec_id <> o.vec_id AND a.vec_id % 50 = 0) SELECT a, b, " + ", ".join(f"CAST(count(*) FILTER ({'e' if same else 'NOT e'} AND t = {t}) AS INTEGER) AS {'same' if same else 'diff'}_{n}" for same in (True, False) for t, n in ((2, "both"), (1, "one"), (0, "none"))) + " FROM j GROUP BY a, b")
add("hamming_pairs", lambda s, d: code_pairs(s, d).select(*_names(), distance.hamming(F.col("a_p"), F.col("b_p"), W).alias("h")), f"{S_AB} SELECT a.vec_id AS a, o.vec_id AS b, {s_ham('a', 'o')} AS h {S_ON}")
add("angle_estimate", lambda s, d: analysis.angle_estimates(vectors(s, d), DIM, every=1), f"{LISTS}, {ALL_PAIRS} SELECT a.vec_id AS a, o.vec_id AS b, round({s_ham('a', 'o')} * 180.0 / {DIM}, 6) AS est_deg, round(degrees(acos({s_cos('a', 'o')})), 6) AS true_deg {S_ON}")
add("exact_topk", lambda s, d: ranked6(exact_top(s, d)), f"{SPLIT}, {EXACT} SELECT qid, rank, vec_id, round(value, 6) AS sim FROM ex")
add("bq_topk", lambda s, d: bq_top(s, d), f"{SPLIT}, {BQ} SELECT * FROM bq")
add("hamming_topk", lambda s, d: ham_top(s, d), f"{SPLIT}, {s_rank('hm', s_ham('q', 'b'))} SELECT * FROM hm")
add("adc_topk", lambda s, d: ranked6(adc_top(s, d), "value"), f"{SPLIT}, {s_rank('ad', ADC_S, desc=True)} SELECT qid, rank, vec_id, round(value, 6) AS value FROM ad")
add("adc_scores", lambda s, d: analysis.pairs(sm(s, d).select("vec_id", "embedding", distance.levels(F.col("p"), F.col("s"), DIM).alias("y"))).select(*_names(), F.round(distance.adc(F.col("a_embedding"), F.col("b_y")), 6).alias("score")), f"{LISTS} SELECT a.vec_id AS a, o.vec_id AS b, round(list_dot_product(a.e, o.y), 6) AS score FROM k a JOIN k o ON a.vec_id <> o.vec_id AND a.vec_id % 50 = 0")
S_SQ = f"WITH {U}, {SQ2}, w AS (SELECT vec_id, list(v ORDER BY i) AS v FROM z GROUP BY vec_id), q AS (SELECT * FROM w WHERE vec_id % 10 = 0), b AS (SELECT * FROM w WHERE vec_id % 10 <> 0), {s_rank('sq', 'CAST(list_sum(list_transform(list_zip(q.v, b.v), lambda x: abs(x[1] - x[2]))) AS INTEGER)')}"
add("sq2_topk", lambda s, d: sq2_top(s, d), f"{S_SQ} SELECT * FROM sq")
BQ64 = s_rank("bq", s_bq("q", "b"), k=64)


def s_rerank(ef: int, name: str = "rr") -> str:
    return f"{s_rank('c' + str(ef), s_bq('q', 'b'), k=ef)}, {name} AS (SELECT qid, rank, vec_id, sim FROM (SELECT c.qid, c.vec_id, {s_cos('q', 'b')} AS sim, CAST(row_number() OVER (PARTITION BY c.qid ORDER BY {s_cos('q', 'b')} DESC, c.vec_id) AS INTEGER) AS rank FROM c{ef} c JOIN q ON c.qid = q.vec_id JOIN b ON c.vec_id = b.vec_id) WHERE rank <= {K})"


add("scan_rerank", lambda s, d: ranked6(reranked(s, d, 64)), f"{SPLIT}, {s_rerank(64)} SELECT qid, rank, vec_id, round(sim, 6) AS sim FROM rr")
add("rerank_topk", lambda s, d: ranked6(reranked(s, d, 16)).withColumn("ef", F.lit(16)).unionByName(ranked6(reranked(s, d, 32)).withColumn("ef", F.lit(32))), f"{SPLIT}, {s_rerank(16, 'r16')}, {s_rerank(32, 'r32')} SELECT qid, rank, vec_id, round(sim, 6) AS sim, 16 AS ef FROM r16 UNION ALL SELECT qid, rank, vec_id, round(sim, 6), 32 FROM r32")
r6 = lambda df: df.select("queries", F.round("recall", 6).alias("recall"))
add("recall_at_k", lambda s, d: r6(metrics.recall(reranked(s, d, 64), exact_top(s, d))), f"{SPLIT}, {EXACT}, {s_rerank(64)} " + S_RECALL.format(r="rr"))
add("overlap_at_k", lambda s, d: r6(metrics.recall(bq_top(s, d), exact_top(s, d))), f"{SPLIT}, {EXACT}, {BQ} " + S_RECALL.format(r="bq"))
add("overlap_by_encoding", overlap_by, f"{SPLIT}, {EXACT}, {BQ}, {s_rank('hm', s_ham('q', 'b'))}, {s_rank('ad', ADC_S, desc=True)}, {S_SQ.split('WITH ' + U + ', ')[1].replace('q AS', 'q2 AS').replace('b AS', 'b2 AS').replace('q.v', 'q2.v').replace('b.v', 'b2.v').replace('FROM q JOIN b', 'FROM q2 JOIN b2')} " + " UNION ALL ".join("SELECT '" + n + "' AS method, recall FROM (" + S_RECALL.format(r=r) + ")" for n, r in (("1-bit", "hm"), ("2-bit", "bq"), ("sq2", "sq2"), ("adc", "ad"))))
BUDGETS = [10, 16, 32, 64]
add("recall_at_budget", lambda s, d: metrics.recall_at_budget(bq_top(s, d, 64), exact_top(s, d), BUDGETS).select("budget", F.round("recall", 6).alias("recall"), F.round("precision", 6).alias("precision")), f"{SPLIT}, {EXACT}, {BQ64}, n AS (SELECT count(DISTINCT qid) AS n FROM ex), g AS (SELECT unnest([10, 16, 32, 64]) AS budget) SELECT CAST(budget AS INTEGER) AS budget, round(count(ex.vec_id) / (any_value(n) * 10.0), 6) AS recall, round(count(ex.vec_id) / count(*)::DOUBLE, 6) AS precision FROM g JOIN bq ON bq.rank <= budget LEFT JOIN ex ON ex.qid = bq.qid AND ex.vec_id = bq.vec_id, n GROUP BY budget")
add("compat_probe", lambda s, d: analysis.compatibility(vectors(s, d)), f"{LISTS}, {ALL_PAIRS}, {KNN_EX}, {KNN_BQ}, r AS (SELECT (SELECT count(*) FROM k) AS n, round((SELECT count(*) FROM ex JOIN bq ON ex.qid = bq.qid AND ex.vec_id = bq.vec_id) / ((SELECT count(*) FROM k) * 10.0), 6) AS overlap) SELECT n, 10 AS k, overlap, CASE WHEN overlap < 0.5 THEN 'no-go' WHEN overlap >= 0.6 THEN 'go' ELSE 'inconclusive' END AS verdict FROM r")
_pr = lambda: [F.round("p_s", 6).alias("p_s"), F.round("nu2", 6).alias("nu2")]
add("strong_rate", lambda s, d: analysis.strong_rate(sm(s, d), DIM).select("n", *_pr()), f"{CODES} SELECT count(DISTINCT vec_id) AS n, round(avg(s), 6) AS p_s, round((1 + 3 * avg(s)) * (1 + 3 * avg(s)), 6) AS nu2 FROM c")
add("strong_rate_by_label", lambda s, d: analysis.strong_rate(sm(s, d), DIM, "label").select("label", "n", *_pr()), f"{CODES} SELECT label, count(DISTINCT vec_id) AS n, round(avg(s), 6) AS p_s, round((1 + 3 * avg(s)) * (1 + 3 * avg(s)), 6) AS nu2 FROM c GROUP BY label")
S_DEG = f"{LISTS}, g AS (SELECT degrees(acos(greatest(-1, least(1, {s_cos('a', 'o')})))) AS deg FROM k a JOIN k o ON a.vec_id <> o.vec_id AND a.vec_id % 50 = 0)"
add("angle_stats", lambda s, d: analysis.angle_stats(vectors(s, d)).select("pairs", F.round("mean", 6).alias("mean"), F.round("sd", 6).alias("sd")), f"{S_DEG} SELECT count(*) AS pairs, round(avg(deg), 6) AS mean, round(stddev_pop(deg), 6) AS sd FROM g")
add("angle_hist", lambda s, d: analysis.angle_hist(vectors(s, d)), f"{S_DEG} SELECT CAST(floor(deg / 5) AS INTEGER) AS bucket, count(*) AS n FROM g GROUP BY 1")
S_TRIP = f"{LISTS}, m AS (SELECT * FROM k), rk AS (SELECT a.vec_id AS q, o.vec_id AS v, row_number() OVER (PARTITION BY a.vec_id ORDER BY {s_cos('a', 'o')} DESC, o.vec_id) AS r FROM m a JOIN m o ON a.vec_id <> o.vec_id AND a.vec_id % 50 = 0), tr AS (SELECT x.q, x.v, y.v AS w FROM rk x JOIN rk y ON x.q = y.q AND x.r <= 10 AND y.r > 10 AND y.r <= 50)"
trip = lambda s, d: (sm(s, d), analysis.triplets(vectors(s, d)))
add("misrank_rate", lambda s, d: analysis.misrank_rate(*trip(s, d), DIM).select("triplets", F.round("rate", 6).alias("rate")), f"{S_TRIP} SELECT count(*) AS triplets, round(avg(CASE WHEN {s_bq('a', 'n')} >= {s_bq('a', 'o')} THEN 1.0 ELSE 0 END), 6) AS rate FROM tr JOIN m a ON a.vec_id = tr.q JOIN m n ON n.vec_id = tr.v JOIN m o ON o.vec_id = tr.w")
add("misrank_bound", lambda s, d: analysis.misrank_bound(*trip(s, d), DIM).select(F.round("mu", 6).alias("mu"), F.round("v", 6).alias("v"), F.round("bound", 6).alias("bound")), f"{S_TRIP}, z AS (SELECT a.i, CASE WHEN a.p <> o.p THEN (1 + a.s) * (1 + o.s) ELSE 0 END - CASE WHEN a.p <> n.p THEN (1 + a.s) * (1 + n.s) ELSE 0 END AS z FROM tr JOIN c a ON a.vec_id = tr.q JOIN c n ON n.vec_id = tr.v AND n.i = a.i JOIN c o ON o.vec_id = tr.w AND o.i = a.i), g AS (SELECT sum(mz) AS mu, sum(vz) AS v FROM (SELECT avg(z) AS mz, var_pop(z) AS vz FROM z GROUP BY i)) SELECT round(mu, 6) AS mu, round(v, 6) AS v, round(exp(-(mu * mu) / (2 * v + 2.0 / 3.0 * 8 * mu)), 6) AS bound FROM g")
add("angle_concentration", lambda s, d: analysis.angle_concentration(sm(s, d), vectors(s, d), DIM, [0.05, 0.1, 0.15]).select("eps", F.round("share", 6).alias("share"), F.round("bound", 6).alias("bound")), f"{LISTS}, g AS (SELECT abs({s_ham('a', 'o')} / {DIM}.0 - acos(greatest(-1, least(1, {s_cos('a', 'o')}))) / pi()) AS dev FROM k a JOIN k o ON a.vec_id <> o.vec_id AND a.vec_id % 50 = 0) SELECT eps, round(avg(CASE WHEN dev > eps THEN 1.0 ELSE 0 END), 6) AS share, round(least(1.0, 2 * exp(-2.0 * {DIM} * eps * eps)), 6) AS bound FROM g, (SELECT unnest([0.05::DOUBLE, 0.1::DOUBLE, 0.15::DOUBLE]) AS eps) GROUP BY eps")
add("sqnr_by_code", lambda s, d: analysis.sqnr_by_code(vectors(s, d), DIM).select("code", F.round("sqnr_db", 5).alias("sqnr_db")), f"{CODES}, r AS (SELECT '1-bit' AS code, p AS cell, x FROM c UNION ALL SELECT '2-bit', 2 * p + s, x FROM c), m AS (SELECT code, cell, avg(x) AS mx FROM r GROUP BY code, cell) SELECT code, round(10 * log10(sum(x * x) / sum((x - mx) * (x - mx))), 5) AS sqnr_db FROM r JOIN m USING (code, cell) GROUP BY code")
add("coord_stats", lambda s, d: analysis.coord_stats(vectors(s, d)).select(i32(F.col("dim"), "dim"), *[F.round(c, 6).alias(c) for c in ("mean", "sd", "skew", "kurt")]), f"WITH {U}, m AS (SELECT i, avg(x) AS mean, stddev_pop(x) AS sd FROM u GROUP BY i) SELECT CAST(u.i AS INTEGER) AS dim, round(any_value(mean), 6) AS mean, round(any_value(sd), 6) AS sd, round(avg(pow((x - mean) / sd, 3)), 6) AS skew, round(avg(pow((x - mean) / sd, 4)) - 3, 6) AS kurt FROM u JOIN m ON u.i = m.i GROUP BY u.i")
add("tie_rate", lambda s, d: metrics.ties(bq_top(s, d, 11), 10).select("queries", F.round("share", 6).alias("share")), f"{SPLIT}, {s_rank('bq', s_bq('q', 'b'), k=11)} SELECT count(*) AS queries, round(avg(CASE WHEN x = y THEN 1.0 ELSE 0 END), 6) AS share FROM (SELECT qid, min(value) FILTER (rank = 10) AS x, min(value) FILTER (rank = 11) AS y FROM bq GROUP BY qid)")


def rank_ties(s, d) -> DataFrame:
    from pyspark.sql import Window

    q, b = halves(sm(s, d))
    w = Window.partitionBy("qid").orderBy("value")
    w2 = Window.partitionBy("qid").orderBy("value", "vec_id")
    v = b.crossJoin(F.broadcast(q_side(q.where("vec_id = 0"), "p", "s"))).select("qid", "vec_id", bq_expr().alias("value"))
    return v.select("vec_id", "value", F.row_number().over(w2).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"))


add("rank_ties", rank_ties, f"{SPLIT}, v AS (SELECT b.vec_id, {s_bq('q', 'b')} AS value FROM q JOIN b ON q.vec_id = 0) SELECT vec_id, value, CAST(row_number() OVER (ORDER BY value, vec_id) AS INTEGER) AS rn, CAST(rank() OVER (ORDER BY value) AS INTEGER) AS rk, CAST(dense_rank() OVER (ORDER BY value) AS INTEGER) AS dr FROM v")
_mm = "code_mb adj_mb cold_mb ratio".split()
add("memory_model", lambda s, d: memory.estimated(vectors(s, d).groupBy("label", F.size("embedding").alias("d")).agg(F.count("*").alias("n"))).select("label", "n", "d", "m", *[F.round(c, 6).alias(c) for c in _mm]), "SELECT label, n, d, 32 AS m, round(n * 1.0::DOUBLE * d / 4 / 1048576.0, 6) AS code_mb, round(n * 1.0::DOUBLE * 65 * 4 / 1048576.0, 6) AS adj_mb, round(n * 1.0::DOUBLE * d * 4 / 1048576.0, 6) AS cold_mb, round((n * 1.0::DOUBLE * d / 4 + n * 1.0::DOUBLE * 65 * 4) / (n * 1.0::DOUBLE * d * 4), 6) AS ratio FROM (SELECT label, CAST(len(embedding) AS INTEGER) AS d, count(*) AS n FROM embeddings GROUP BY 1, 2)")


def gemm_pairs(s, d) -> DataFrame:
    """The pairs of bq_distance_pairs by two matrix products a block: the queries' levels go to every task behind the size check."""
    import numpy as np
    import pyarrow as pa

    from .. import kernels

    v = vectors(s, d).select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    q = v.where(F.col("vec_id") % analysis.EVERY == 0)
    if exact.side_blocks(q) > 1:
        raise ValueError("too many queries for one block: raise analysis.EVERY")
    got = q.toArrow().combine_chunks()
    held = s.sparkContext.broadcast((got.column("vec_id").to_numpy(), kernels.levels(exact.matrix(got.column("v").combine_chunks()))))

    def run(batches):
        qid, y = held.value
        for b in batches:
            for lo in range(0, b.num_rows, 1024):
                t = b.slice(lo, 1024)
                ids = t.column(0).to_numpy()
                dist = kernels.bq_block(y, kernels.levels(exact.matrix(t.column(1))))
                i, j = np.nonzero(qid[:, None] != ids[None, :])
                yield pa.RecordBatch.from_arrays([pa.array(qid[i]), pa.array(ids[j]), pa.array(dist[i, j])], names=["a", "b", "d"])

    return v.mapInArrow(run, "a long, b long, d int")


add("bq_distance_gemm", gemm_pairs, ORACLES["bq_distance_pairs"])
add("normal_share", lambda s, d: analysis.normal_share(vectors(s, d)).select(F.round("share", 6).alias("share")), f"WITH {U}, m AS (SELECT i, avg(x) AS mean, stddev_pop(x) AS sd, count(*) AS n FROM u GROUP BY i), g AS (SELECT u.i, any_value(n) AS n, avg(pow((x - mean) / sd, 3)) AS g, avg(pow((x - mean) / sd, 4)) - 3 AS k FROM u JOIN m ON u.i = m.i GROUP BY u.i) SELECT round(avg(CASE WHEN n / 6.0 * (g * g + k * k / 4) <= 5.991 THEN 1.0 ELSE 0 END), 6) AS share FROM g")
add("effective_rank", lambda s, d: analysis.effective_rank(vectors(s, d)).select(F.round("rank", 4).alias("rank")), f"WITH {U}, g AS (SELECT a.i, b.i AS j, sum(a.x * b.x) AS v FROM u a JOIN u b ON a.vec_id = b.vec_id GROUP BY 1, 2) SELECT round(pow(sum(CASE WHEN i = j THEN v ELSE 0 END), 2) / sum(v * v), 4) AS rank FROM g")

# -- k-NN and set operators around the codes ------------------------------------------------------------------------------

add("knn_graph_exact", lambda s, d: ranked6(knn_exact(s, d)), f"{LISTS}, {ALL_PAIRS}, {KNN_EX} SELECT qid, rank, vec_id, round(value, 6) AS sim FROM ex")
add("knn_graph_bq", lambda s, d: knn_bq(s, d), f"{LISTS}, {ALL_PAIRS}, {KNN_BQ} SELECT * FROM bq")


def mutual(s, d) -> DataFrame:
    g = knn_bq(s, d).select("qid", "vec_id")
    return g.join(g.select(F.col("vec_id").alias("qid"), F.col("qid").alias("vec_id")), ["qid", "vec_id"]).where("qid < vec_id")


add("mutual_knn", mutual, f"{LISTS}, {ALL_PAIRS}, {KNN_BQ} SELECT x.qid, x.vec_id FROM bq x JOIN bq y ON x.qid = y.vec_id AND x.vec_id = y.qid WHERE x.qid < x.vec_id")


def vote(s, d) -> DataFrame:
    v = vectors(s, d)
    n = knn_exact(s, d).join(v.select("vec_id", "label"), "vec_id").groupBy("qid", "label").agg(F.count("*").alias("c"))
    return n.groupBy("qid").agg(F.max(F.struct("c", -F.col("label"))).alias("b")).select("qid", (-F.col("b.col2")).cast("int").alias("label"))


add("knn_vote", vote, f"{LISTS}, {ALL_PAIRS}, {KNN_EX} SELECT qid, label FROM (SELECT qid, k.label, row_number() OVER (PARTITION BY qid ORDER BY count(*) DESC, k.label) AS r FROM ex JOIN k ON ex.vec_id = k.vec_id GROUP BY qid, k.label) WHERE r = 1")


def filtered(s, d) -> DataFrame:
    q, b = halves(sm(s, d))
    return exact.code_topk(q_side(q, "p", "s"), b.where("label = 3"), bq_expr(), K)


add("filtered_topk", filtered, f"{SPLIT}, {s_rank('bq', s_bq('q', 'b'), join='b.label = 3')} SELECT * FROM bq")


def range_join(s, d, radius: int = 36) -> DataFrame:
    c = sm(s, d).select("vec_id", "p", "s")
    return exact.within(q_side(c, "p", "s"), c, bq_expr(), radius).where("qid < vec_id").select(F.col("qid").alias("a"), F.col("vec_id").alias("b"), F.col("value").alias("d"))


add("bq_range_join", range_join, f"{LISTS} SELECT a.vec_id AS a, o.vec_id AS b, {s_bq('a', 'o')} AS d FROM k a JOIN k o ON a.vec_id < o.vec_id WHERE {s_bq('a', 'o')} <= 36")


def near(s, d, how: str, radius: int = 36) -> DataFrame:
    """Queries with (left_semi) or without (left_anti) a base row within the radius."""
    q, b = halves(sm(s, d))
    hit = exact.within(q_side(q, "p", "s"), b.select("vec_id", "p", "s"), bq_expr(), radius).select(F.col("qid").alias("vec_id")).distinct()
    return q.select("vec_id").join(hit, "vec_id", how)


add("semi_near", lambda s, d: near(s, d, "left_semi"), f"{SPLIT} SELECT q.vec_id FROM q WHERE EXISTS (SELECT 1 FROM b WHERE {s_bq('q', 'b')} <= 36)")
add("anti_isolated", lambda s, d: near(s, d, "left_anti"), f"{SPLIT} SELECT q.vec_id FROM q WHERE NOT EXISTS (SELECT 1 FROM b WHERE {s_bq('q', 'b')} <= 36)")
add("distinct_codes", lambda s, d: sm(s, d).agg(F.count("*").alias("n"), F.countDistinct("p").alias("signs"), F.countDistinct("p", "s").alias("codes")), f"{LISTS} SELECT count(*) AS n, count(DISTINCT h) AS signs, count(DISTINCT y) AS codes FROM k")
add("distance_cube", lambda s, d: sm(s, d).select("label", i32(one("s") / 4, "bucket")).cube("label", "bucket").agg(F.count("*").alias("n"), F.grouping_id().alias("g")), f"{CODES}, w AS (SELECT vec_id, any_value(label) AS label, CAST(floor(sum(s) / 4.0) AS INTEGER) AS bucket FROM c GROUP BY vec_id) SELECT label, bucket, count(*) AS n, CAST(grouping(label, bucket) AS BIGINT) AS g FROM w GROUP BY CUBE (label, bucket)")


def setops(s, d) -> DataFrame:
    a, b = bq_top(s, d, 16).select("qid", "vec_id"), ham_top(s, d, 16).select("qid", "vec_id")
    parts = {"union": a.union(b).distinct(), "intersect": a.intersect(b), "except": a.exceptAll(b)}
    out = None
    for n, x in parts.items():
        r = x.agg(F.count("*").alias("n")).select(F.lit(n).alias("op"), "n")
        out = r if out is None else out.unionByName(r)
    return out


add("cand_setops", setops, f"{SPLIT}, {s_rank('bq', s_bq('q', 'b'), k=16)}, {s_rank('hm', s_ham('q', 'b'), k=16)} SELECT 'union' AS op, count(*) AS n FROM (SELECT qid, vec_id FROM bq UNION SELECT qid, vec_id FROM hm) UNION ALL SELECT 'intersect', count(*) FROM (SELECT qid, vec_id FROM bq INTERSECT SELECT qid, vec_id FROM hm) UNION ALL SELECT 'except', count(*) FROM (SELECT qid, vec_id FROM bq EXCEPT SELECT qid, vec_id FROM hm)")
add("plane_bitaggs", lambda s, d: sm(s, d).groupBy("label").agg(*[i32(F.bit_count(f(F.col("p")[0])), n) for f, n in ((F.bit_or, "any_bits"), (F.bit_and, "all_bits"), (F.bit_xor, "odd_bits"))]), f"{CODES}, w AS (SELECT label, i, max(p) AS o, min(p) AS a, sum(p) % 2 AS x FROM c GROUP BY label, i) SELECT label, CAST(sum(o) AS INTEGER) AS any_bits, CAST(sum(a) AS INTEGER) AS all_bits, CAST(sum(x) AS INTEGER) AS odd_bits FROM w GROUP BY label")


def nearest_one(s, d) -> DataFrame:
    q, b = halves(sm(s, d))
    return b.crossJoin(F.broadcast(q_side(q.where("vec_id = 10"), "p", "s"))).select("vec_id", bq_expr().alias("value")).orderBy("value", "vec_id").limit(5)


add("nearest_one", nearest_one, f"{SPLIT} SELECT b.vec_id, {s_bq('q', 'b')} AS value FROM q JOIN b ON q.vec_id = 10 ORDER BY 2, 1 LIMIT 5")
add("l2_normalize", lambda s, d: codec.l2_normalize(vectors(s, d).withColumn("embedding", F.transform("embedding", lambda v: (v * 3).cast("float")))).select("vec_id", F.round(distance.dot(F.col("embedding"), F.col("embedding")), 5).alias("norm")), f"WITH {U} SELECT vec_id, round(sum(x * x) / sum(x * x), 5) AS norm FROM u GROUP BY vec_id")


def sql_scan(s, d) -> DataFrame:
    """The SQL front end: ORDER BY bq_dist(...) LIMIT k."""
    distance.register(s, W)
    sm(s, d).createOrReplaceTempView("sg_codes")
    return s.sql("SELECT c.vec_id, bq_dist(q.p, q.s, c.p, c.s) AS d FROM sg_codes c CROSS JOIN (SELECT p, s FROM sg_codes WHERE vec_id = 20) q WHERE c.vec_id <> 20 ORDER BY d, c.vec_id LIMIT 10")


add("sql_bq_dist", sql_scan, f"{LISTS} SELECT o.vec_id, {s_bq('a', 'o')} AS d FROM k a JOIN k o ON a.vec_id = 20 AND o.vec_id <> 20 ORDER BY 2, 1 LIMIT 10")
