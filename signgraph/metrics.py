"""Accuracy and cost measures over rankings, curves and series."""
from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def recall(result: DataFrame, truth: DataFrame, k: int = 10) -> DataFrame:
    """One row: share of the true top k that was returned, averaged over the queries of truth."""
    t = truth.where(F.col("rank") <= k).select("qid", "vec_id")
    r = result.where(F.col("rank") <= k).select("qid", "vec_id", F.lit(1).alias("hit"))
    per = t.join(r, ["qid", "vec_id"], "left").groupBy("qid").agg((F.count("hit") / k).alias("r"))
    return per.agg(F.count("*").alias("queries"), F.avg("r").alias("recall"))


def recall_at_budget(cands: DataFrame, truth: DataFrame, budgets: list[int], k: int = 10) -> DataFrame:
    """(budget, recall, precision): the true top k inside the first K candidates, and the candidates' share in it."""
    t = truth.where(F.col("rank") <= k).select("qid", "vec_id", F.lit(1).alias("hit"))
    c = cands.join(t, ["qid", "vec_id"], "left")
    n = truth.select("qid").distinct().count()
    b = c.withColumn("budget", F.explode(F.array(*[F.lit(x) for x in budgets]))).where(F.col("rank") <= F.col("budget"))
    return b.groupBy("budget").agg((F.count("hit") / (n * k)).alias("recall"), (F.count("hit") / F.count("*")).alias("precision"))


def ties(ranked: DataFrame, k: int, value: str = "value") -> DataFrame:
    """(queries, share): queries whose k-th and next value are equal; ranked holds k + 1 rows a query."""
    at = ranked.where(F.col("rank").isin(k, k + 1)).groupBy("qid").agg(F.count("*").alias("n"), (F.min(value) == F.max(value)).alias("tie"))
    return at.agg(F.count("*").alias("queries"), F.avg(((F.col("n") == 2) & F.col("tie")).cast("double")).alias("share"))


def at_recall(curve: DataFrame, levels: list[float]) -> DataFrame:
    """(system, level, qps) by linear interpolation between neighbouring points of (system, recall, qps)."""
    w = Window.partitionBy("system").orderBy("recall")
    seg = curve.select("system", F.col("recall").alias("r1"), F.col("qps").alias("q1"), F.lead("recall").over(w).alias("r2"), F.lead("qps").over(w).alias("q2")).where("r2 is not null")
    x = seg.withColumn("level", F.explode(F.array(*[F.lit(float(v)) for v in levels]))).where((F.col("level") >= F.col("r1")) & (F.col("level") < F.col("r2")))
    return x.select("system", "level", (F.col("q1") + (F.col("level") - F.col("r1")) * (F.col("q2") - F.col("q1")) / (F.col("r2") - F.col("r1"))).alias("qps"))


def pareto(curve: DataFrame) -> DataFrame:
    """Points that no other point beats in both recall and qps; equal points stay together."""
    w = Window.orderBy(F.col("recall").desc()).rowsBetween(Window.unboundedPreceding, -1)
    top = curve.groupBy("recall").agg(F.max("qps").alias("qps")).withColumn("best", F.max("qps").over(w)).where("best is null or qps > best").drop("best")
    return curve.join(top, ["recall", "qps"], "left_semi")


def rsd(series: DataFrame, group: str, value: str) -> DataFrame:
    return series.groupBy(group).agg((F.stddev_samp(value) / F.avg(value)).alias("rsd"))


def tail(df: DataFrame, group: str, value: str, exact: bool = True) -> DataFrame:
    """(group, p50, p99, p999, r99); exact percentiles hold a group's distinct values, the others a bounded sketch."""
    f = F.percentile if exact else (lambda c, p: F.percentile_approx(c, p, 10_000))
    ps = df.groupBy(group).agg(*[f(F.col(value), F.lit(p)).alias(a) for p, a in ((0.5, "p50"), (0.99, "p99"), (0.999, "p999"))])
    return ps.withColumn("r99", F.col("p99") / F.col("p50"))


def scale_delta(series: DataFrame, small: str, large: str) -> DataFrame:
    """(ef, delta_recall, qps_ratio) between two sizes of a series (size, ef, recall, qps)."""
    a, b = series.where(F.col("size") == small), series.where(F.col("size") == large)
    return a.select("ef", F.col("recall").alias("ra"), F.col("qps").alias("qa")).join(b.select("ef", F.col("recall").alias("rb"), F.col("qps").alias("qb")), "ef").select("ef", (F.col("rb") - F.col("ra")).alias("delta_recall"), (F.col("qb") / F.col("qa")).alias("qps_ratio"))


def tier(recall_pct: Column) -> Column:
    """The band of a recall at ef=64 in per cent; gaps between the published bands are split in the middle."""
    return F.when(recall_pct > 83, "competitive").when(recall_pct > 56.5, "high").when(recall_pct > 23.5, "usable").otherwise("collapse")


def ef_for(curve: DataFrame, target: float) -> DataFrame:
    """(ef): the least ef that reaches the recall, interpolated between points of (ef, recall)."""
    w = Window.orderBy("ef")
    seg = curve.select("ef", "recall", F.lag("ef").over(w).alias("e0"), F.lag("recall").over(w).alias("r0")).where(F.col("recall") >= target)
    first = seg.orderBy("ef").limit(1)
    return first.select(F.when(F.col("r0").isNull() | (F.col("r0") >= target), F.col("ef").cast("double")).otherwise(F.col("e0") + (target - F.col("r0")) * (F.col("ef") - F.col("e0")) / (F.col("recall") - F.col("r0"))).alias("ef"))


def graph_health(edges: DataFrame, nodes: int) -> DataFrame:
    """(degree, nodes): how many nodes have each out-degree; nodes without an edge count as degree 0."""
    d = edges.groupBy("src").agg(F.count("*").alias("degree"))
    full = d.groupBy("degree").agg(F.count("*").alias("nodes"))
    rest = d.agg((F.lit(nodes) - F.count("*")).alias("nodes")).where("nodes > 0").select(F.lit(0).cast("long").alias("degree"), "nodes")
    return full.unionByName(rest)


def reciprocal(edges: DataFrame) -> DataFrame:
    back = edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.lit(1).alias("back"))
    return edges.join(back, ["src", "dst"], "left").agg(F.count("*").alias("edges"), F.avg(F.coalesce("back", F.lit(0)).cast("double")).alias("share"))


def reachable(edges: DataFrame, entry: int, rounds: int = 10_000) -> DataFrame:
    """(node, hops): breadth-first from the entry by joins, until a round adds nothing. Each round is written and read back, so that
    its plan is that of one join."""
    from .sources.shared import settled

    spark = edges.sparkSession
    front = settled(spark.range(1).select(F.lit(entry).cast("long").alias("node"), F.lit(0).alias("hops")))
    seen = front
    for hop in range(1, rounds):
        out = edges.join(front, edges["src"] == front["node"]).select(F.col("dst").alias("node")).distinct()
        front = settled(out.join(seen.select("node"), "node", "left_anti").withColumn("hops", F.lit(hop)))
        if front.isEmpty():
            break
        seen = seen.unionByName(front)
    return seen
