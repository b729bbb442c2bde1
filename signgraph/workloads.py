"""Vector workloads of other structure, derived from the given tables; deterministic."""
from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import exact


def _map(df: DataFrame, make) -> DataFrame:
    """(vec_id, embedding, label): make(ids, x, labels) gives the new matrix of a batch."""

    def run(batches):
        for b in batches:
            ids, labels = b.column(0).to_numpy(), b.column(2).to_numpy(zero_copy_only=False)
            x = make(ids, exact.matrix(b.column(1)), labels) if len(ids) else np.zeros((0, 1))
            n = np.linalg.norm(x, axis=1, keepdims=True)
            x = (x / np.where(n > 0, n, 1)).astype(np.float32)
            flat = pa.ListArray.from_arrays(pa.array(np.arange(len(ids) + 1, dtype=np.int32) * x.shape[1]), pa.array(x.ravel()))
            yield pa.RecordBatch.from_arrays([b.column(0), flat, b.column(2)], names=["vec_id", "embedding", "label"])

    return df.select(F.col("vec_id").cast("long"), F.col("embedding").cast("array<double>"), F.coalesce(F.col("label").cast("int"), F.lit(0)).alias("label")).mapInArrow(run, "vec_id long, embedding array<float>, label int")


def _gauss(seed: int, *shape: int) -> np.ndarray:
    return np.random.default_rng(seed).normal(size=shape)


def _rows(ids: np.ndarray, seed: int, dim: int) -> np.ndarray:
    """A normal row for each id, whatever the batch."""
    return np.stack([np.random.default_rng([seed, int(i)]).normal(size=dim) for i in ids]) if len(ids) else np.zeros((0, dim))


#: Words whose features a task remembers.
MET = 1 << 19


def text_vectors(df: DataFrame, id_col: str, text_col: str, dim: int = 64, seed: int = 5, dense: bool = True) -> DataFrame:
    """Words hashed to signed features and, if dense, turned by a seeded projection, so that no coordinate is exactly zero."""
    turn = _gauss(seed, 256, dim) / 16

    def run(batches):
        import xxhash

        width = 256 if dense else dim
        met: dict[str, int] = {}  # of words met in this task: their feature, from `width` on those that count as -1

        def feature(w: str) -> int:
            h = xxhash.xxh64_intdigest(w, 7)
            met[w] = i = h % width + (0 if h >> 63 else width)
            return i

        for b in batches:
            out = np.zeros((b.num_rows, width))
            for r, t in enumerate(b.column(1).to_pylist()):
                if len(met) > MET:
                    met.clear()
                n = np.bincount([met[w] if w in met else feature(w) for w in (t or "").lower().split()], minlength=2 * width)
                out[r] = n[:width] - n[width:]
            x = out @ turn if dense else out
            n = np.linalg.norm(x, axis=1, keepdims=True)
            x = (x / np.where(n > 0, n, 1)).astype(np.float32)
            flat = pa.ListArray.from_arrays(pa.array(np.arange(b.num_rows + 1, dtype=np.int32) * dim), pa.array(x.ravel()))
            yield pa.RecordBatch.from_arrays([b.column(0), flat], names=["vec_id", "embedding"])

    return df.select(F.col(id_col).cast("long").alias("vec_id"), F.col(text_col).cast("string").alias("t")).mapInArrow(run, "vec_id long, embedding array<float>").withColumn("label", F.lit(0))


def workload(spark: SparkSession, sf_dir: str, name: str, base: DataFrame | None = None) -> DataFrame:
    """One of NAMES as (vec_id, embedding, label). base takes the place of the table of embeddings (see generated)."""
    if base is None:
        base = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding", "label")
    if name == "W0":
        return base
    if name == "W1":
        centre, lift = _gauss(1, 10, 64) / 8, _gauss(2, 10, 8, 64) / 8
        return _map(base, lambda i, x, y: centre[y % 10] + 0.5 * np.einsum("nk,nkd->nd", x[:, :8] * 8, lift[y % 10]))
    if name in ("W1b", "W1c"):
        k = 64 if name == "W1b" else 10
        centre = _gauss(3, k, 64)
        centre /= np.linalg.norm(centre, axis=1, keepdims=True)
        return _map(base, lambda i, x, y: centre[i // 10 % k] + x)  # not i % k: queries are the ids divisible by ten
    if name.split("_")[0] == "W2":  # W2_0.5, W2, W2_2: two modalities, apart by an offset
        far = float(name.split("_")[1]) if "_" in name else 1.0
        off = _gauss(4, 64)
        off *= far / np.linalg.norm(off)
        return _map(workload(spark, sf_dir, "W1", base), lambda i, x, y: x + np.where(i % 2 == 0, 1.0, -1.0)[:, None] * off)
    if name in ("W3", "W3d"):
        return text_vectors(spark.read.parquet(f"{sf_dir}/documents.parquet").dropDuplicates(["text"]), "doc_id", "text", dense=name == "W3d")
    if name == "W4":
        c = spark.read.parquet(f"{sf_dir}/conversations.parquet").select((F.col("conv_id") * 1000 + F.col("turn")).alias("id"), "text")
        p = spark.read.parquet(f"{sf_dir}/pages.parquet").select((F.col("page_id") + 10**9).alias("id"), F.regexp_replace("html", "<[^>]*>", " ").alias("text"))
        return text_vectors(c.unionByName(p), "id", "text")
    if name in ("W5", "W5b"):
        r = 8 if name == "W5" else 16
        lift = _gauss(6, r, 64)
        return _map(base, lambda i, x, y: x[:, :r] @ lift)
    if name.startswith("W6"):
        d = int(name.split("_")[1]) if "_" in name else 64
        return _map(base, lambda i, x, y: _rows(i, 8, d))
    if name.split("_")[0] == "W7":
        d = int(name.split("_")[1]) if "_" in name else 768
        centre, turn = _gauss(9, 256, 64), np.linalg.qr(_gauss(10, d, 64))[0].T
        share = 1 / np.arange(1, 257)
        edge = np.cumsum(share / share.sum())
        return _map(base, lambda i, x, y: (centre[np.searchsorted(edge, (i * 0.6180339887498949) % 1).clip(0, 255)] / 8 + 0.3 * x) @ turn + 0.05 / math.sqrt(d) * _rows(i, 12, d))
    if name == "W8":
        d = spark.read.parquet(f"{sf_dir}/documents.parquet").dropDuplicates(["text"])

        def bins(batches):
            for b in batches:
                x = np.stack([np.bincount(np.frombuffer((t or " ").encode(), np.uint8) >> 1, minlength=128) for t in b.column(1).to_pylist()]).astype(np.float64) if b.num_rows else np.zeros((0, 128))
                n = np.linalg.norm(x, axis=1, keepdims=True)
                x = (x / np.where(n > 0, n, 1)).astype(np.float32)
                yield pa.RecordBatch.from_arrays([b.column(0), pa.ListArray.from_arrays(pa.array(np.arange(b.num_rows + 1, dtype=np.int32) * 128), pa.array(x.ravel()))], names=["vec_id", "embedding"])

        return d.select(F.col("doc_id").alias("vec_id"), "text").mapInArrow(bins, "vec_id long, embedding array<float>").withColumn("label", F.lit(0))
    if name == "W8b":
        li = spark.read.parquet(f"{sf_dir}/lineitem.parquet")
        cols = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]
        return li.select((F.col("l_orderkey") * 10 + F.col("l_linenumber")).cast("long").alias("vec_id"), F.array(*[((F.col(c) + 1) / m).cast("float") for c, m in zip(cols, (51, 100_001, 1.1, 1.1), strict=True)], F.lit(0.5).cast("float")).alias("embedding"), F.lit(0).alias("label")).dropDuplicates(["vec_id"])
    if name == "W8c":  # W8 less the mean of each coordinate
        v = workload(spark, sf_dir, "W8")
        e = v.select(F.posexplode("embedding").alias("i", "x")).groupBy("i").agg(F.avg("x").alias("m")).orderBy("i").collect()
        mean = np.array([r["m"] for r in e])
        return _map(v, lambda i, x, y: x - mean)
    raise ValueError(name)


NAMES = ["W0", "W1", "W1b", "W1c", "W2_0.5", "W2", "W2_2", "W3", "W3d", "W4", "W5", "W5b", "W6_64", "W6_256", "W7", "W8", "W8b", "W8c"]


def split(df: DataFrame, mod: int = 10) -> tuple[DataFrame, DataFrame]:
    """Queries (ids divisible by mod) and base (the rest)."""
    return df.where(F.col("vec_id") % mod == 0), df.where(F.col("vec_id") % mod != 0)


def generated(spark: SparkSession, n: int, dim: int, seed: int = 13) -> DataFrame:
    """A structureless sphere of any size."""
    src = spark.range(n).select(F.col("id").alias("vec_id"), F.array(F.lit(0.0)).alias("embedding"), F.expr("cast(pmod(id div 10, 10) as int)").alias("label"))
    return _map(src, lambda i, x, y: _rows(i, seed, dim) / math.sqrt(dim))
