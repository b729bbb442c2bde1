"""Tables in a folder that driver and executors share."""
from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession


def scratch(s: SparkSession) -> str:
    """A new path in that folder."""
    place = s.conf.get("spark.checkpoint.dir", None) or s.conf.get("spark.sql.warehouse.dir")
    return f"{place.rstrip('/')}/signgraph-index-{uuid.uuid4().hex}"


def drop(s: SparkSession, path: str) -> None:
    p = s.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(s.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def settled(df: DataFrame) -> DataFrame:
    """df written once and read back: what follows has no plan behind it, which loops of joins need."""
    path = scratch(df.sparkSession)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
