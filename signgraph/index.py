"""The sharded graph index: one hot table (codes and adjacency) that stage 1 reads, one cold table (vectors) for reranking.

hot: shard, place, node, p, s (planes), nbrs (places within the shard), nd (distances), code (bytes of another code, or null).
A search on codes reads no float: it broadcasts nothing and joins nothing but the encoded queries, dealt to the shards.
"""
from __future__ import annotations

import json
import time
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernels
from .functions import codec
from .operators import exact

#: Nodes of a shard: its arrays take some hundred bytes a node in one task.
SHARD = 1_000_000
_HOT = "shard int, place int, node long, p array<long>, s array<long>, nbrs array<int>, nd array<long>, code binary"
_WORK = ["evals", "expanded", "hops", "reads", "touched"]
_FOUND = "qid long, vec_id long, d long, " + ", ".join(f"{w} long" for w in _WORK) + ", sim double"
#: A pool of so many ids is reranked in the task that finds it: the floats of the shard come with it, and only the best leave.
WIDE = 1_000
#: Places of the pools that a task holds at a time.
POOLS = 4 << 20
#: Navigation on planes, on the byte code, on floats.
_PLANES, _BYTES = ("bq2", "bq1", "adc"), ("sq2", "pq")


def alpha_for(m: int) -> float:
    """Strict selection for small degrees, slack for large ones."""
    return 1.0 if m <= 16 else 1.2


def _matrix(t: pa.Table, name: str) -> np.ndarray:
    return exact.matrix(t.column(name).combine_chunks())


def _words(t: pa.Table, name: str) -> np.ndarray:
    c = t.column(name).combine_chunks()
    return np.ascontiguousarray(c.flatten().to_numpy(zero_copy_only=False).reshape(len(c), -1)).view(np.uint64)


def _padded(t: pa.Table, name: str, width: int, fill: int) -> np.ndarray:
    c = t.column(name).combine_chunks()
    size = c.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
    flat = c.flatten().to_numpy(zero_copy_only=False)
    out = np.full((len(c), max(1, width, int(size.max()) if len(size) else 1)), fill, np.int64)
    row = np.repeat(np.arange(len(c)), size)
    out[row, np.arange(len(flat)) - np.repeat(np.cumsum(size) - size, size)] = flat
    return out


def _lists(x: np.ndarray, keep: np.ndarray, kind: pa.DataType) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(keep.sum(1))]).astype(np.int32)), pa.array(x[keep]).cast(kind))


def _bytes_of(kind: str, x: np.ndarray, more: dict) -> pa.Array:
    """The byte code of floats, for the metrics that navigate on one."""
    if kind == "sq2":
        c = kernels.Metric.of("sq2", x, **more).a["c"].astype(np.uint8)
    elif kind == "pq":
        c = kernels.pq_encode(x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12), more["book"])
    else:
        return pa.nulls(len(x), pa.binary())
    return pa.array([r.tobytes() for r in c], pa.binary())


def _hot(shard: int, ids: np.ndarray, p: np.ndarray, s: np.ndarray, nbrs: np.ndarray, nd: np.ndarray, code: pa.Array) -> pa.Table:
    every = np.ones(p.shape, bool)
    planes = [_lists(v.view(np.int64), every, pa.int64()) for v in (p, s)]
    return pa.table([pa.array(np.full(len(ids), shard, np.int32)), pa.array(np.arange(len(ids), dtype=np.int32)), pa.array(ids), *planes, _lists(nbrs, nbrs >= 0, pa.int32()), _lists(nd, nbrs >= 0, pa.int64()), code], names=[c.split()[0] for c in _HOT.split(", ")])


def _scatter(ids: np.ndarray, seed: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        h = (ids.astype(np.uint64) + np.uint64(seed)) * np.uint64(0x9E3779B97F4A7C15)
        return h ^ (h >> np.uint64(29))


def _build_shard(metric: str, m: int, ef_c: int, alpha100: int, batch: str, ties: str, seed: int, more: dict):
    def run(t: pa.Table) -> pa.Table:
        ids, x = t.column("vec_id").to_numpy(), _matrix(t, "v")
        order = np.lexsort((ids, _scatter(ids, seed)))  # the order of insertion does not depend on the layout of the input
        ids, x = ids[order], x[order]
        p, s, _ = kernels.sm_codes(x)
        fine = kernels.Metric.of("adc", x) if ties == "adc" else None
        base = kernels.Metric.of(metric, x, **more)
        nbrs, nd = kernels.connected(base, *kernels.link(base, m, ef_c, alpha100, batch, ties, fine))
        return _hot(t.column("shard")[0].as_py(), ids, p, s, nbrs, nd, _bytes_of(metric, x, more))

    return run


def _base(t: pa.Table, kind: str, dim: int, more: dict) -> kernels.Metric:
    if kind in _PLANES:
        return kernels.Metric.of_planes(kind, _words(t, "p"), _words(t, "s"), dim)
    if kind in _BYTES:
        return kernels.Metric.of_codes(kind, np.frombuffer(b"".join(t.column("code").to_pylist()), np.uint8).reshape(t.num_rows, -1), **more)
    return kernels.Metric.of(kind, _matrix(t, "v"), **more)


def _search_shard(nav: str, dim: int, ef: int, width: int, entries: int, cache: int, more: dict, keep: int | None = None, where: bool = False, rerank: bool = False):
    """One task's search of a shard. where: only nodes marked ok leave the pools; rerank: pools are ordered by exact cosine with the
    floats of the shard; keep: so many of each pool leave the task."""

    def run(q: pa.Table, t: pa.Table) -> pa.Table:
        names = [c.split()[0] for c in _FOUND.split(", ")]
        if not q.num_rows or not t.num_rows:
            return pa.table([pa.array([], pa.float64() if n == "sim" else pa.int64()) for n in names], names=names)
        t = t.sort_by("place")
        ids, nbrs = t.column("node").to_numpy(), _padded(t, "nbrs", 1, -1)
        base = _base(t, nav, dim, more)
        ok = t.column("ok").to_numpy(zero_copy_only=False) if where else None
        x = exact.Unit(_matrix(t, "v")) if rerank else None
        qids, qx = q.column("qid").to_numpy(), _matrix(q, "v")
        out = [[] for _ in names]
        entry = np.arange(min(entries, len(ids)))
        cached = kernels.near_entry(nbrs, 0, cache) if cache else None
        most = min(ef, len(ids))
        step = max(1, min(256, (64 << 20) // len(ids), POOLS // most))  # the visited bits of a batch of queries take 64 MB at most
        for lo in range(0, len(qids), step):
            mine = qx[lo : lo + step]
            got, d, work = kernels.beam(base, nbrs, kernels.Metric.of(nav, mine, **more), entry, most, width, cached=cached)
            live = got >= 0
            if where:
                live &= ok[got]
            sim = exact.Unit(mine).at(x, got) if rerank else None
            by = np.where(np.isnan(sim), 2.0, -sim) if rerank else d.astype(np.float64)
            r, c = exact.first(np.where(live, by, np.inf), ids[got], keep) if keep else np.nonzero(live)
            for col, v in zip(out, (qids[lo + r], ids[got[r, c]], d[r, c], *work[r].T, np.full(len(r), len(ids)), sim[r, c] if rerank else np.full(len(r), np.nan)), strict=True):
                col.append(v)
        cols = [np.concatenate(c) for c in out]
        return pa.table([pa.array(c.astype(np.int64)) for c in cols[:-1]] + [pa.array(cols[-1], from_pandas=True)], names=names)

    return run


def _walk_shard(metric: str, dim: int, ef: int, more: dict):
    """One task's walks of a shard by one query at a time, with the seconds of each."""

    def run(q: pa.Table, t: pa.Table) -> pa.Table:
        t = t.sort_by("place")
        qids, took, evals = q.column("qid").to_numpy(), np.zeros(q.num_rows), np.zeros(q.num_rows, np.int64)
        if q.num_rows and t.num_rows:
            base, mine, nbrs = _base(t, metric, dim, more), _base(q, metric, dim, more), _padded(t, "nbrs", 1, -1)
            for k in [0, *range(q.num_rows)]:  # the first walk of a task finds nothing in its caches: it is done again
                began = time.perf_counter()
                _, _, work = kernels.beam(base, nbrs, mine.take(np.array([k])), np.array([0]), min(ef, base.n))
                took[k], evals[k] = time.perf_counter() - began, work[0, 0]
        keep = np.arange(q.num_rows if t.num_rows else 0)
        return pa.table([pa.array(v[keep]) for v in (qids, took, evals)], names=["qid", "took", "evals"])

    return run


def _insert_shard(metric: str, dim: int, m: int, ef_c: int, alpha100: int, batch: str, seed: int, more: dict):
    def run(t: pa.Table, new: pa.Table) -> pa.Table:
        if not new.num_rows:
            t = t.sort_by("place")
            return t.select([c.split()[0] for c in _HOT.split(", ")])
        ids, x = new.column("vec_id").to_numpy(), _matrix(new, "v")
        order = np.lexsort((ids, _scatter(ids, seed)))
        ids, x = ids[order], x[order]
        p, s, _ = kernels.sm_codes(x)
        fresh, code = kernels.Metric.of(metric, x, **more), _bytes_of(metric, x, more)
        if not t.num_rows:
            nbrs, nd = kernels.connected(fresh, *kernels.link(fresh, m, ef_c, alpha100, batch))
            return _hot(new.column("shard")[0].as_py(), ids, p, s, nbrs, nd, code)
        t = t.sort_by("place")
        old = _base(t, metric, dim, more)
        every = kernels.Metric.joined(old, kernels.Metric(metric, **{k: fresh.a[k] for k in old.a}))
        if metric == "pq":  # both sides are met by their reconstruction, as stored
            every.a["x"] = every.a["r"]
        grown = (_padded(t, "nbrs", 2 * m, -1), _padded(t, "nd", 2 * m, 0))
        nbrs, nd = kernels.connected(every, *kernels.link(every, m, ef_c, alpha100, batch, grown=grown))
        planes = [np.concatenate([_words(t, n), v]) for n, v in (("p", p), ("s", s))]
        codes = pa.concat_arrays([t.column("code").combine_chunks().cast(pa.binary()), code])
        return _hot(t.column("shard")[0].as_py(), np.concatenate([t.column("node").to_numpy(), ids]), *planes, nbrs, nd, codes)

    return run


def _delete_shard(metric: str, dim: int, m: int, alpha100: int, more: dict):
    def run(t: pa.Table, dead: pa.Table) -> pa.Table:
        names = [c.split()[0] for c in _HOT.split(", ")]
        if not dead.num_rows or not t.num_rows:
            return t.select(names)
        t = t.sort_by("place")
        ids = t.column("node").to_numpy()
        base = _base(t, metric, dim, more)
        if metric == "pq":
            base.a["x"] = base.a["r"]
        stay, nbrs, nd = kernels.repair(base, _padded(t, "nbrs", 2 * m, -1), _padded(t, "nd", 2 * m, 0), np.isin(ids, dead.column("vec_id").to_numpy()), m, alpha100)
        if not len(stay):
            return t.select(names).slice(0, 0)
        nbrs, nd = kernels.connected(base.take(stay), nbrs, nd)
        kept = t.take(pa.array(stay))
        return _hot(t.column("shard")[0].as_py(), ids[stay], _words(kept, "p"), _words(kept, "s"), nbrs, nd, kept.column("code").combine_chunks().cast(pa.binary()))

    return run


@dataclass(frozen=True)
class Index:
    vectors: DataFrame
    hot: DataFrame
    dim: int
    m: int
    metric: str
    seed: int
    shards: int
    more: dict = field(default_factory=dict)
    alpha100: int = 120

    @staticmethod
    def build(vectors: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", m: int = 32, ef_c: int = 128, alpha: float | str = 1.2, metric: str = "bq2", shards: int | str = "auto", seed: int = 42, batch: str = "doubling", ties: str = "id", path: str | None = None, **more) -> Index:
        """One task builds one shard; alpha='auto' follows the degree. With a path the tables are written once and read back."""
        dim = codec.dimension(vectors, vec_col)
        ok, _ = codec.split_rejects(vectors, vec_col, dim)
        n = ok.count() if shards == "auto" else 0
        shards = max(1, -(-n // SHARD)) if shards == "auto" else shards
        alpha100 = round((alpha_for(m) if alpha == "auto" else alpha) * 100)
        v = ok.select(_shard(F.col(id_col).cast("long"), seed, shards), F.col(id_col).cast("long").alias("vec_id"), F.col(vec_col).alias("embedding"))
        if metric == "sq2" and "span" not in more:
            x = v.select(F.min(F.array_min("embedding")), F.max(F.array_max("embedding"))).first()
            more = more | {"span": (float(x[0] or 0), float(x[1] or 0))}
        # Floats are widened in the tasks: half the bytes move.
        single = v.schema["embedding"].dataType.simpleString() == "array<float>"
        src = v.select("shard", "vec_id", (F.col("embedding") if single else F.col("embedding").cast("array<double>")).alias("v"))
        hot = src.groupBy("shard").applyInArrow(_build_shard(metric, m, ef_c, alpha100, batch, ties, seed, more), _HOT)
        out = Index(v, hot, dim, m, metric, seed, shards, more, alpha100)
        if path:
            out.save(path)
            return Index.load(vectors.sparkSession, path)
        return replace(out, hot=hot.persist())  # evicted or lost parts are built again: the build is deterministic

    def search(self, queries: DataFrame, k: int = 10, ef: int = 64, nav: str | None = None, rerank: bool = True, id_col: str = "vec_id", vec_col: str = "embedding", width: int = 1, entries: int = 1, where: DataFrame | None = None, **more) -> DataFrame:
        """(qid, rank, vec_id, sim), or value instead of sim without rerank. All shards are searched; pools meet in a window.

        where: allowed ids. Pools are filtered; while a query has fewer than k of min(k, allowed) ids, the beam is widened four
        times, up to all nodes that can be reached."""
        # Few ids are reranked by a join that reads their floats alone; a wide pool holds most of its shard.
        near = queries.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vec_col).alias("embedding"))
        ok = need = None
        if where is not None:
            ok = where.select(F.col(id_col).cast("long").alias("vec_id")).distinct().persist()
            need = min(k, ok.join(self.hot.select(F.col("node").alias("vec_id")), "vec_id", "left_semi").count())
            n, asked = self.hot.count(), queries.count()
        while True:
            wide = rerank and ef > WIDE
            c = self._found(queries, ef, nav, id_col, vec_col, width, entries, 0, k if wide or not rerank else None, ok, wide, **more)
            if where is None:
                break
            c = c.persist()
            full = c.groupBy("qid").agg(F.count("*").alias("c")).where(F.col("c") >= need).count()
            if full >= asked or ef >= n:
                break
            c.unpersist()
            ef = min(4 * ef, n)
        if wide:
            return exact.top(c.select("qid", "vec_id", "sim"), k, "qid", F.col("sim").desc(), F.col("vec_id")).select("qid", "rank", "vec_id", "sim")
        if rerank:
            return exact.rerank(c, self.vectors, near, k)
        return exact.top(c.select("qid", "vec_id", F.col("d").alias("value")), k, "qid", F.col("value"), F.col("vec_id")).select("qid", "rank", "vec_id", "value")

    def best(self, queries: DataFrame, k: int = 10, ef: int = 64, nav: str | None = None) -> DataFrame:
        """(qid, vec_id, sim, evals, touched): of each query's pool in a shard the k first by exact cosine, with the work of the walk; with one
        shard, what search() ranks. Many queries name most rows of a shard: its floats come to the task, and no pool leaves it."""
        return self._found(queries, ef, nav, "vec_id", "embedding", 1, 1, 0, k, None, True).select("qid", "vec_id", "sim", "evals", "touched")

    def candidates(self, queries: DataFrame, ef: int = 64, nav: str | None = None, id_col: str = "vec_id", vec_col: str = "embedding", width: int = 1, entries: int = 1, cache: int = 0, **more) -> DataFrame:
        """(qid, vec_id, d, evals, expanded, hops, reads, touched): each query's pool of ef and its work, a row a shard.

        Stage 1: planes navigate for bq2, bq1 and adc, the byte code for sq2 and pq; only 'float' reads vectors."""
        return self._found(queries, ef, nav, id_col, vec_col, width, entries, cache, None, None, False, **more).drop("sim")

    def walks(self, ef: int = 64) -> DataFrame:
        """(qid, took, evals), a row a shard: every node as a query of its own on the planes, in every shard, with the seconds of the kernel. The
        queries of a shard are dealt to a few tasks a core, each with a copy of the shard."""
        if self.metric not in ("bq2", "bq1"):
            raise ValueError("only planes tell a node's code as a query")
        parts = max(1, 4 * self.hot.sparkSession.sparkContext.defaultParallelism // self.shards)
        every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
        own = [F.col(c).alias(c) for c in ("p", "s")]  # columns of their own: a cogroup of a table with itself may take one side's for the other's
        q = self.hot.select(F.col("node").alias("qid"), *own, every(self.shards).alias("shard"), F.pmod(F.xxhash64("node"), F.lit(parts)).cast("int").alias("part"))
        base = self.hot.select("shard", "place", "p", "s", "nbrs", every(parts).alias("part"))
        q, base = (df.repartition(parts * self.shards, "shard", "part").groupBy("shard", "part") for df in (q, base))  # their rows are few, their work is not
        return q.cogroup(base).applyInArrow(_walk_shard(self.metric, self.dim, ef, self.more), "qid long, took double, evals long")

    def _found(self, queries: DataFrame, ef: int, nav: str | None, id_col: str, vec_col: str, width: int, entries: int, cache: int, keep: int | None, where: DataFrame | None, rerank: bool, **more) -> DataFrame:
        """The pools; the queries of a shard are dealt to as many tasks as run at once, each with a copy of the shard."""
        nav, more = nav or self.metric, self.more | more
        parts = max(1, queries.sparkSession.sparkContext.defaultParallelism // self.shards)
        q = queries.select(F.explode(F.sequence(F.lit(0), F.lit(self.shards - 1))).alias("shard"), F.col(id_col).cast("long").alias("qid"), F.col(vec_col).cast("array<double>").alias("v")).withColumn("part", F.pmod(F.xxhash64("qid"), F.lit(parts)).cast("int"))
        own = {"float": ["v"], "sq2": ["code"], "pq": ["code"]}.get(nav, ["p", "s"])
        base = self.coded(nav, **more).hot if nav in _BYTES and nav != self.metric else self.hot
        if nav == "float" or rerank:
            base = base.join(self.vectors.select(F.col("vec_id").alias("node"), F.col("embedding").cast("array<double>").alias("v")), "node")
        cols = ["shard", "node", "place", "nbrs", *own, *(["v"] if rerank and "v" not in own else [])]
        if where is not None:
            base = base.join(where.select(F.col("vec_id").alias("node"), F.lit(True).alias("hit")), "node", "left").withColumn("ok", F.col("hit").isNotNull())
            cols.append("ok")
        base = base.select(*cols, F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("part"))
        run = _search_shard(nav, self.dim, ef, width, entries, cache, more, keep, where is not None, rerank)
        got = q.groupBy("shard", "part").cogroup(base.groupBy("shard", "part")).applyInArrow(run, _FOUND)
        return exact.top(got, ef, "qid", F.col("d"), F.col("vec_id")) if self.shards > 1 and keep is None else got

    def _with_floats(self) -> DataFrame:
        return self.hot.join(self.vectors.select(F.col("vec_id").alias("node"), F.col("embedding").cast("array<double>").alias("v")), "node")

    def coded(self, kind: str, **more) -> Index:
        """The index with the byte code of another metric beside its planes: one pass over the vectors."""
        def run(batches):
            for b in batches:
                yield pa.RecordBatch.from_arrays([b.column(0), _bytes_of(kind, exact.matrix(b.column(1)), more)], names=["node", "code"])

        c = self.vectors.select("vec_id", F.col("embedding").cast("array<double>")).mapInArrow(run, "node long, code binary")
        return replace(self, hot=self.hot.drop("code").join(c, "node"), more=self.more | more)

    def edges(self) -> DataFrame:
        """(src, dst, pos, d)."""
        e = self.hot.select("shard", F.col("node").alias("src"), F.posexplode(F.arrays_zip("nbrs", "nd")).alias("pos", "e")).select("shard", "src", "pos", F.col("e.nbrs").alias("place"), F.col("e.nd").alias("d"))
        return e.join(self.hot.select("shard", "place", F.col("node").alias("dst")), ["shard", "place"]).select("src", "dst", "pos", "d")

    def insert(self, more: DataFrame, ef_c: int = 128, batch: str = "doubling") -> Index:
        """The index with more rows: each shard links the new ones into the graph it has. Codes need no training, so for plane
        metrics no old vector is read."""
        new = more.select(_shard(F.col("vec_id").cast("long"), self.seed, self.shards), F.col("vec_id").cast("long").alias("vec_id"), "embedding")
        old = self._with_floats().select("shard", "place", "node", "p", "s", "nbrs", "nd", "code", "v") if self.metric == "float" else self.hot
        grown = old.groupBy("shard").cogroup(new.select("shard", "vec_id", F.col("embedding").cast("array<double>").alias("v")).groupBy("shard"))
        hot = grown.applyInArrow(_insert_shard(self.metric, self.dim, self.m, ef_c, self.alpha100, batch, self.seed, self.more), _HOT)
        return replace(self, hot=hot.persist(), vectors=self.vectors.unionByName(new))

    def delete(self, ids: DataFrame) -> Index:
        """The index without some ids: nodes that lose neighbours select anew among theirs and those of the lost ones."""
        gone = ids.select(F.col("vec_id").cast("long").alias("vec_id")).distinct()
        old = self._with_floats().select("shard", "place", "node", "p", "s", "nbrs", "nd", "code", "v") if self.metric == "float" else self.hot
        dead = gone.select(_shard(F.col("vec_id"), self.seed, self.shards), "vec_id")
        hot = old.groupBy("shard").cogroup(dead.groupBy("shard")).applyInArrow(_delete_shard(self.metric, self.dim, self.m, self.alpha100, self.more), _HOT)
        return replace(self, hot=hot.persist(), vectors=self.vectors.join(gone, "vec_id", "left_anti").select("shard", "vec_id", "embedding"))

    def save(self, path: str) -> None:
        """hot and vectors as two tables by shard, and a line of parameters."""
        self.hot.write.mode("overwrite").parquet(f"{path}/hot")
        self.vectors.write.mode("overwrite").parquet(f"{path}/vectors")
        more = {k: (v.tolist() if isinstance(v, np.ndarray) else v) for k, v in self.more.items()}
        line = json.dumps({"dim": self.dim, "m": self.m, "metric": self.metric, "seed": self.seed, "shards": self.shards, "alpha100": self.alpha100, "more": more})
        self.hot.sparkSession.createDataFrame([(line,)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/meta")

    @staticmethod
    def load(spark: SparkSession, path: str) -> Index:
        x = json.loads(spark.read.text(f"{path}/meta").first()["value"])
        x["more"] = {k: (np.array(v) if k == "book" else tuple(v) if k == "span" else v) for k, v in x["more"].items()}
        vectors = spark.read.schema("shard int, vec_id long, embedding array<float>").parquet(f"{path}/vectors")
        return Index(vectors, spark.read.schema(_HOT).parquet(f"{path}/hot"), **x)


def _shard(key, seed: int, shards: int):
    return F.pmod(F.xxhash64(key, F.lit(seed)), F.lit(shards)).cast("int").alias("shard")
