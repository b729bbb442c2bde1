"""Layered small-world graphs: levels drawn from the id, a graph for each level, a descent that ends on the lowest.

Built once into a table (a row a node, its lists of all its levels), one task a shard; searched from that table.
"""
from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import kernels
from ..index import _matrix, _scatter
from ..operators import exact

_ROWS = "shard int, place int, node long, level int, lists array<array<int>>, v array<double>"
#: alpha in hundredths and refill of each variant: mutually distant neighbours; the nearest; distant ones, then the nearest of the rest.
VARIANTS = {"diverse": (100, False), "nearest": (10**9, False), "refill": (100, True)}


def levels(vectors: DataFrame, m: int, seed: int = 42) -> DataFrame:
    """(vec_id, level): floor(-ln U / ln m), U from eight hex digits of the MD5 of seed and id."""
    u = (F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.col("vec_id").cast("string"))), 1, 8), 16, 10).cast("long") + 1) / float(1 << 32)
    return vectors.select("vec_id", F.floor(-F.log(u) / np.log(m)).cast("int").alias("level"))


def _level(t: pa.Table, level: int, n: int) -> np.ndarray:
    """Neighbours of the first n nodes on a level, padded by -1."""
    outer = t.column("lists").combine_chunks()
    inner = outer.flatten()
    held, size = (v.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64) for v in (outer, inner))
    at = (np.cumsum(held) - held)[:n] + level
    first, size = (np.cumsum(size) - size)[at], size[at]
    row, col = np.repeat(np.arange(n), size), np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
    out = np.full((n, max(1, int(size.max()))), -1, np.int64)
    out[row, col] = inner.flatten().to_numpy(zero_copy_only=False)[first[row] + col]
    return out


@dataclass(frozen=True)
class Layered:
    rows: DataFrame
    vectors: DataFrame
    shards: int

    @staticmethod
    def build(base: DataFrame, m: int = 16, ef_c: int = 64, heuristic: str = "diverse", seed: int = 42, shards: int = 1) -> Layered:
        alpha, refill = VARIANTS[heuristic]
        b = base.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("v"))
        b = b.join(levels(b, m, seed), "vec_id").withColumn("shard", F.pmod(F.xxhash64("vec_id", F.lit(seed)), F.lit(shards)).cast("int"))

        def run(t: pa.Table) -> pa.Table:
            ids, lev = t.column("vec_id").to_numpy(), t.column("level").to_numpy()
            o = np.lexsort((ids, _scatter(ids, seed), -lev))  # nodes of a level are a prefix
            ids, lev, x = ids[o], lev[o], _matrix(t, "v")[o]
            base = kernels.Metric.of("float", x)
            lists: list[list[list[int]]] = [[] for _ in ids]
            for level in range(int(lev.max()) + 1):
                n = int((lev >= level).sum())
                nbrs, _ = kernels.link(base.take(np.arange(n)), m if level == 0 else max(2, m // 2), ef_c, alpha, refill=refill)
                for i in range(n):
                    lists[i].append(nbrs[i][nbrs[i] >= 0].tolist())
            flat = pa.ListArray.from_arrays(pa.array(np.arange(len(ids) + 1, dtype=np.int32) * x.shape[1]), pa.array(x.ravel()))
            return pa.table([pa.array(np.full(len(ids), t.column("shard")[0].as_py(), np.int32)), pa.array(np.arange(len(ids), dtype=np.int32)), pa.array(ids), pa.array(lev.astype(np.int32)), pa.array(lists, pa.list_(pa.list_(pa.int32()))), flat], names=[c.split()[0] for c in _ROWS.split(", ")])

        return Layered(b.select("shard", "vec_id", "level", "v").groupBy("shard").applyInArrow(run, _ROWS).persist(), base, shards)

    def candidates(self, queries: DataFrame, ef: int = 64) -> DataFrame:
        """(qid, vec_id, d, evals, expanded, touched); the queries of a shard are dealt to as many tasks as run at once."""
        parts = max(1, queries.sparkSession.sparkContext.defaultParallelism // self.shards)
        q = queries.select(F.explode(F.sequence(F.lit(0), F.lit(self.shards - 1))).alias("shard"), F.col("vec_id").cast("long").alias("qid"), F.col("embedding").cast("array<double>").alias("v")).withColumn("part", F.pmod(F.xxhash64("qid"), F.lit(parts)).cast("int"))
        names = ["qid", "vec_id", "d", "evals", "expanded", "touched"]

        def run(qt: pa.Table, t: pa.Table) -> pa.Table:
            if not qt.num_rows or not t.num_rows:
                return pa.table([pa.array([], pa.int64()) for _ in names], names=names)
            t = t.sort_by("place")
            ids, lev = t.column("node").to_numpy(), t.column("level").to_numpy()
            base, mine = kernels.Metric.of("float", _matrix(t, "v")), kernels.Metric.of("float", _matrix(qt, "v"))
            work = np.zeros((mine.n, 2), np.int64)
            entry = np.zeros((mine.n, 1), np.int64)
            for level in range(int(lev.max()), -1, -1):
                n = int((lev >= level).sum())
                got, d, w = kernels.beam(base.take(np.arange(n)), _level(t, level, n), mine, entry, min(n, ef if level == 0 else 1))
                entry = np.maximum(got[:, :1], 0)
                work += w[:, :2]
            r, c = np.nonzero(got >= 0)
            return pa.table([pa.array(qt.column("qid").to_numpy()[r]), pa.array(ids[got[r, c]]), pa.array(d[r, c]), pa.array(work[r, 0]), pa.array(work[r, 1]), pa.array(np.full(len(r), len(ids)))], names=names)

        rows = self.rows.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(parts - 1))))
        got = q.groupBy("shard", "part").cogroup(rows.groupBy("shard", "part")).applyInArrow(run, ", ".join(f"{n} long" for n in names))
        return exact.top(got, ef, "qid", F.col("d"), F.col("vec_id")).drop("rank") if self.shards > 1 else got

    def search(self, queries: DataFrame, ef: int = 64, k: int = 10) -> DataFrame:
        """(qid, rank, vec_id, sim)."""
        return exact.rerank(self.candidates(queries, ef), self.vectors, queries, k)


def search(queries: DataFrame, base: DataFrame, m: int = 16, ef_c: int = 64, ef: int = 64, k: int = 10, heuristic: str = "diverse", seed: int = 42, shards: int = 1) -> DataFrame:
    return Layered.build(base, m, ef_c, heuristic, seed, shards).search(queries, ef, k)
