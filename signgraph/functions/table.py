"""The SQL front end: table functions ann_search and topk_merge, and the scalar function sm_encode."""
from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Row, SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="qid bigint, rank int, vec_id bigint, value double")
class TopkMerge:
    """topk_merge(TABLE(c) PARTITION BY qid ORDER BY (value, vec_id), k): the first k rows of each query of (qid, vec_id, value, k)."""

    def __init__(self):
        self.n = 0

    def eval(self, row: Row, k: int) -> Iterator[tuple]:
        if self.n < k:
            self.n += 1
            yield row["qid"], self.n, row["vec_id"], float(row["value"])


@udtf(returnType="qid bigint, rank int, vec_id bigint, d bigint")
class AnnSearch:
    """ann_search(TABLE(q), path, k, ef): the k nearest by code of each query row (qid, v) in an index saved at path. The rows of a
    partition are held and searched together, shard by shard, from the hot table alone."""

    def __init__(self):
        self.qid, self.v, self.how = [], [], None

    def eval(self, row: Row, path: str, k: int, ef: int) -> None:
        self.qid.append(row["qid"])
        self.v.append(list(row["v"]))
        self.how = (path, k, ef)

    def terminate(self) -> Iterator[tuple]:
        if not self.qid:
            return
        import pyarrow.parquet as pq
        from pyarrow import fs

        from ..index import _search_shard

        path, k, ef = self.how
        store, base = fs.FileSystem.from_uri(path if "://" in path or path.startswith("file:") else "file://" + path)
        q = pa.table([pa.array(self.qid, pa.int64()), pa.array(self.v, pa.list_(pa.float64()))], names=["qid", "v"])
        shards: dict[int, list[pa.Table]] = {}
        for f in store.get_file_info(fs.FileSelector(f"{base}/hot")):
            if f.path.endswith(".parquet") and f.size:
                with store.open_input_file(f.path) as src:
                    t = pq.read_table(src, columns=["shard", "place", "node", "p", "s", "nbrs"])
                for s in np.unique(t.column("shard").to_numpy()).tolist():
                    shards.setdefault(s, []).append(t.filter(pa.compute.equal(t.column("shard"), s)))
        found: dict[int, list[tuple[int, int]]] = {i: [] for i in self.qid}
        for parts in shards.values():
            got = _search_shard("bq2", len(self.v[0]), ef, 1, 1, 0, {}, keep=k)(q, pa.concat_tables(parts))
            for i, v, d in zip(*(got.column(n).to_pylist() for n in ("qid", "vec_id", "d")), strict=True):
                found[i].append((d, v))
        for i, c in found.items():
            for r, (d, v) in enumerate(sorted(c)[:k], 1):
                yield i, r, v, d


def register(spark: SparkSession, dim: int = 64) -> None:
    spark.udtf.register("topk_merge", TopkMerge)
    spark.udtf.register("ann_search", AnnSearch)
    word = lambda test, w: f"aggregate(sequence({64 * w}, {min(dim, 64 * w + 64) - 1}), 0L, (a, i) -> a | shiftleft(if({test}, 1L, 0L), i - {64 * w}))"
    mean = f"(aggregate(x, 0D, (a, v) -> a + abs(v)) / {dim})"
    words = range(-(-dim // 64))
    p, s = (", ".join(word(t, w) for w in words) for t in ("x[i] > 0", f"abs(x[i]) > {mean}"))
    spark.sql(f"create or replace temporary function sm_encode(x array<double>) returns struct<p: array<bigint>, s: array<bigint>> return named_struct('p', array({p}), 's', array({s}))")
