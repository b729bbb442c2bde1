"""Streams of vectors and of the query log: file sources, run to the end of what is there and returned as tables."""
from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import codec
from ..sources.shared import scratch


def source(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    """A stream over one table: a file, or a folder of part files with any names."""
    path = f"{sf_dir}/{table}.parquet"
    # A pattern, as a stream takes no path of a single file.
    return spark.readStream.schema(spark.read.parquet(path).schema).parquet(f"{path[:-1]}[t]")


def queries(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The query log with event times that can carry a watermark."""
    return source(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))


def drained(stream: DataFrame, mode: str) -> DataFrame:
    """What the stream has produced once all present input is read, as a table in the shared folder: no row reaches the driver. Each
    batch writes its own folder, so a repeated one replaces itself; in mode complete the last batch holds everything."""
    spark, path = stream.sparkSession, scratch(stream.sparkSession)
    last = [-1]

    def sink(df: DataFrame, i: int) -> None:
        df.write.mode("overwrite").parquet(f"{path}/batch={i}")
        last[0] = i

    stream.writeStream.foreachBatch(sink).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    if last[0] < 0:
        return spark.createDataFrame([], stream.schema)
    if mode == "complete":
        return spark.read.schema(stream.schema).parquet(f"{path}/batch={last[0]}")
    return spark.read.schema(stream.schema).option("basePath", path).parquet(path).select(*stream.columns)


def tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = queries(spark, sf_dir).withWatermark("ts", "1 hour")
    g = e.groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("v"))
    return drained(g.select(F.col("window.start").cast("timestamp_ntz").alias("start"), "event_type", "n", "v"), "complete")


def sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = queries(spark, sf_dir).withWatermark("ts", "1 hour")
    return drained(e.groupBy(F.window("ts", "1 hour", "30 minutes")).agg(F.count("*").alias("n")).select(F.col("window.start").cast("timestamp_ntz").alias("start"), "n"), "complete")


def session(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = queries(spark, sf_dir).withWatermark("ts", "6 hours")
    return drained(e.groupBy(F.session_window("ts", "6 hours"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("session_window.start").cast("timestamp_ntz").alias("start"), "n"), "complete")


def encode(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vectors encoded as they arrive: no state, nothing learnt."""
    v = source(spark, sf_dir, "embeddings")
    return drained(codec.encode_sign(v, 64).select("vec_id", F.bit_count(F.col("p")[0]).cast("int").alias("ones")), "append")


def search(stream: DataFrame, index, sink, k: int = 10, ef: int = 64):
    """Each micro-batch of query vectors searched on a static index; sink gets (frame, batch id)."""
    return stream.writeStream.foreachBatch(lambda df, i: sink(index.search(df, k=k, ef=ef), i)).trigger(availableNow=True).start()


def once_each(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events of the log, read twice, each counted once: repeats within the watermark are dropped by their id."""
    e = queries(spark, sf_dir)
    twice = e.unionByName(e).withWatermark("ts", "30 days").dropDuplicatesWithinWatermark(["event_id"])
    return drained(twice.select("event_id", "event_type"), "append").groupBy("event_type").agg(F.count("*").alias("n"))


def late(stream: DataFrame, delay: str, by: str = "ts") -> DataFrame:
    """Rows behind the greatest time seen before their batch by more than delay are kept apart, not dropped: (row columns, late)."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    limit = pd.Timedelta(delay)

    def run(key, frames, state: GroupState):
        top = pd.Timestamp(state.get[0]) if state.exists else None
        for f in frames:
            yield f.assign(late=False if top is None else f[by] < top - limit)
            best = f[by].max()
            top = best if top is None or best > top else top
        if top is not None:
            state.update((top.isoformat(),))

    schema = stream.schema.add("late", "boolean")
    return stream.groupBy("event_type").applyInPandasWithState(run, schema, "top string", "append", GroupStateTimeout.NoTimeout)


def running_recall(spark: SparkSession, results: str, truth: DataFrame, k: int = 10) -> DataFrame:
    """Recall of a stream of (qid, rank, vec_id) rows below a folder against a static truth: a stream-static join, counts as state."""
    s = spark.readStream.schema("qid long, rank int, vec_id long, sim double").parquet(results)
    t = truth.where(F.col("rank") <= k).select("qid", "vec_id", F.lit(1).alias("hit"))
    hit = s.where(F.col("rank") <= k).join(F.broadcast(t), ["qid", "vec_id"], "left")
    return drained(hit.groupBy().agg(F.count("hit").alias("hits"), F.approx_count_distinct("qid", 0.01).alias("queries")), "complete")


def searched(spark: SparkSession, sf_dir: str, index, queries_: str, path: str, **how) -> DataFrame:
    """A stream of query vectors searched on a static index batch by batch; rankings are appended below path."""
    q = source(spark, sf_dir, "embeddings").where(queries_)

    def sink(df: DataFrame, i: int) -> None:
        df.write.mode("overwrite").parquet(f"{path}/batch={i}")  # a repeated batch replaces itself

    search(q, index, sink, **how).awaitTermination()
    return spark.read.parquet(path).drop("batch")
