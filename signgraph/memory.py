"""Bytes of codes, adjacency and vectors."""
from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def estimate(spark: SparkSession, n: int, dims: list[int], m: int = 32, id_bytes: int = 4) -> DataFrame:
    """(d, m, code_mb, adj_mb, cold_mb, ratio): ratio is hot to cold."""
    return estimated(spark.createDataFrame([(x, n) for x in dims], "d int, n long"), m, id_bytes).drop("n")


def estimated(sets: DataFrame, m: int = 32, id_bytes: int = 4) -> DataFrame:
    """sets (n, d, any others) with m, code_mb, adj_mb, cold_mb and ratio."""
    mb = float(1 << 20)
    rows = F.col("n").cast("double")
    out = sets.withColumns({"m": F.lit(m), "code_mb": F.col("d") * rows / 4 / mb, "adj_mb": rows * (2 * m + 1) * id_bytes / mb, "cold_mb": F.col("d") * rows * 4 / mb})
    return out.withColumn("ratio", (F.col("code_mb") + F.col("adj_mb")) / F.col("cold_mb"))


def compression_ratio(dim: int) -> float:
    """Float bits over code bits; words are whole, so odd dimensions lose a little."""
    return 32 * dim / (2 * 64 * -(-dim // 64))


def measure(path: str) -> dict[str, float]:
    """Megabytes on disk of a saved index, from the Parquet footers: codes, adjacency, names (ids, shards, places) and cold vectors."""
    import pyarrow.parquet as pq
    from pyarrow import fs

    store, base = fs.FileSystem.from_uri(path if "://" in path or path.startswith("file:") else "file://" + path)
    out = {"code_mb": 0.0, "adj_mb": 0.0, "name_mb": 0.0, "cold_mb": 0.0}
    group = {"p": "code_mb", "s": "code_mb", "code": "code_mb", "nbrs": "adj_mb", "nd": "adj_mb", "embedding": "cold_mb"}
    for table in ("hot", "vectors"):
        for f in store.get_file_info(fs.FileSelector(f"{base}/{table}")):
            if f.path.endswith(".parquet"):
                with store.open_input_file(f.path) as src:
                    meta = pq.ParquetFile(src).metadata
                for r in range(meta.num_row_groups):
                    for c in range(meta.num_columns):
                        col = meta.row_group(r).column(c)
                        out[group.get(col.path_in_schema.split(".")[0], "name_mb")] += col.total_compressed_size / (1 << 20)
    return out
