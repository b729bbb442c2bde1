"""Inverted lists, product codes with and without a fitted rotation, rotated one-bit codes, hyperplane signs.

Models are fitted on a bounded sample (the rows of least id hash); every row is encoded. Queries meet the rows of their lists in
one task a list (a list of many rows is split in parts), which keeps the best of each query; no pair leaves it otherwise.
"""
from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import kernels
from ..operators import exact

SAMPLE = 20_000
PART = 100_000  # rows of a list that one task holds


def _unit(x: np.ndarray) -> np.ndarray:
    return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)


def sample(vectors: DataFrame, n: int = SAMPLE) -> np.ndarray:
    s = vectors.orderBy(F.xxhash64("vec_id"), "vec_id").limit(n).select(F.col("embedding").cast("array<double>").alias("v")).toArrow().combine_chunks()
    return _unit(exact.matrix(s.column("v").chunk(0))) if s.num_rows else np.zeros((0, 1))


def list_count(n: int) -> int:
    """Lists that grow as the root of the rows: 1024 at a million."""
    return max(1, round(math.sqrt(n) * 1.024))


def _lists(x: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * x.shape[1]), pa.array(x.ravel()))


def _mapped(vectors: DataFrame, make, kind: str, names: list[str]) -> DataFrame:
    def run(batches):
        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([b.column(0), *make(_unit(exact.matrix(b.column(1))))], names=["vec_id", *names])

    return vectors.select(F.col("vec_id").cast("long"), F.col("embedding").cast("array<double>")).mapInArrow(run, f"vec_id long, {kind}")


def _nearest(x: np.ndarray, centres: np.ndarray, probe: int) -> np.ndarray:
    return np.argsort((centres * centres).sum(1)[None, :] - 2 * x @ centres.T, 1, kind="stable")[:, :probe].astype(np.int32)


def assign(vectors: DataFrame, centres: np.ndarray, probe: int = 1) -> DataFrame:
    """(vec_id, list_id): the probe nearest centres of each vector."""
    return _mapped(vectors, lambda x: [_lists(_nearest(x, centres, probe))], "lists array<int>", ["lists"]).select("vec_id", F.explode("lists").alias("list_id"))


def probed(queries: DataFrame, base: DataFrame, centres: np.ndarray, probe: int, keep: int, make, kind: str, names: list[str], score) -> DataFrame:
    """(qid, vec_id, value, scanned): of each query the rows of its probed lists that score(qx, table, list) ranks first, `keep`
    of each list part (or, where it returns a mask too, all that the mask keeps). base rows carry make's columns."""
    own = _mapped(base, lambda x: [pa.array(_nearest(x, centres, 1)[:, 0]), *make(x)], f"list_id int, {kind}", ["list_id", *names])
    parts = own.groupBy("list_id").agg(F.count("*").alias("n")).select("list_id", F.ceil(F.col("n") / PART).cast("int").alias("parts"))
    b = own.join(parts, "list_id").withColumn("part", F.expr("cast(pmod(xxhash64(vec_id), parts) as int)"))
    q = _mapped(queries, lambda x: [_lists(_nearest(x, centres, probe)), _lists(x)], "lists array<int>, q array<double>", ["lists", "q"])
    q = q.select(F.col("vec_id").alias("qid"), "q", F.explode("lists").alias("list_id")).join(parts.withColumnRenamed("parts", "dealt"), "list_id").withColumn("part", F.explode(F.expr("sequence(0, dealt - 1)")))
    out = ["qid", "vec_id", "value", "scanned"]

    def run(tq: pa.Table, tb: pa.Table) -> pa.Table:
        if not tq.num_rows or not tb.num_rows:
            return pa.table([pa.array([], k) for k in (pa.int64(), pa.int64(), pa.float64(), pa.int64())], names=out)
        ids, which = tb.column("vec_id").to_numpy(), tq.column("list_id")[0].as_py()
        held = []
        for lo in range(0, tq.num_rows, 256):
            t = tq.slice(lo, 256)
            value, live = score(exact.matrix(t.column("q").combine_chunks()), tb, which)
            o = np.lexsort((np.broadcast_to(ids, value.shape), value), axis=1)
            o = o[:, :keep] if live is None else o
            r = np.repeat(np.arange(len(value)), o.shape[1])
            c = o.ravel()
            if live is not None:
                r, c = r[live[r, c]], c[live[r, c]]
            held.append((t.column("qid").to_numpy()[r], ids[c], value[r, c]))
        qid, vec, val = (np.concatenate(v) for v in zip(*held, strict=True))
        return pa.table([pa.array(qid), pa.array(vec), pa.array(val), pa.array(np.full(len(qid), len(ids)))], names=out)

    return q.groupBy("list_id", "part").cogroup(b.groupBy("list_id", "part")).applyInArrow(run, "qid long, vec_id long, value double, scanned long")


def _best(c: DataFrame, k: int) -> DataFrame:
    return exact.top(c, k, "qid", F.col("value"), F.col("vec_id"))


def ivf_search(queries: DataFrame, base: DataFrame, centres: np.ndarray, probe: int, k: int = 10) -> DataFrame:
    """(qid, rank, vec_id, sim): exact cosine within the probed lists."""
    c = probed(queries, base, centres, probe, k, lambda x: [_lists(x)], "v array<double>", ["v"], lambda qx, t, _: (-qx @ exact.matrix(t.column("v").combine_chunks()).T, None))
    return _best(c, k).select("qid", "rank", "vec_id", (-F.col("value")).alias("sim"))


def pq_codes(vectors: DataFrame, book: np.ndarray, turn: np.ndarray | None = None) -> DataFrame:
    """(vec_id, code binary)."""
    return _mapped(vectors, lambda x: [pa.array([r.tobytes() for r in kernels.pq_encode(x if turn is None else x @ turn, book)], pa.binary())], "code binary", ["code"])


def opq_ivfpq(queries: DataFrame, base: DataFrame, lists: int, probe: int, parts: int, refine: int, k: int = 10, seed: int = 42, fitted=None) -> DataFrame:
    """Rotation and books from the sample; rows of probed lists ranked by their product codes; the best `refine` reranked by floats."""
    turn, book, centres = fitted or opq_fitted(base, lists, parts, seed)

    def score(qx, t, _):
        c = np.frombuffer(b"".join(t.column("code").to_pylist()), np.uint8).reshape(t.num_rows, -1)
        return -(qx @ turn) @ kernels.pq_decode(c, book).T, None

    c = probed(queries, base, centres, probe, refine, lambda x: [pa.array([r.tobytes() for r in kernels.pq_encode(x @ turn, book)], pa.binary())], "code binary", ["code"], score)
    return exact.rerank(_best(c, refine), base, queries, k)


def opq_fitted(base: DataFrame, lists: int, parts: int, seed: int = 42, x: np.ndarray | None = None):
    """x: the sample, where it is at hand."""
    x = sample(base) if x is None else x
    return *kernels.opq_fit(x, parts, seed=seed), kernels.kmeans(x, lists, seed=seed)


# -- rotated one-bit codes ---------------------------------------------------------------------------------------------------


def hadamard(dim: int) -> np.ndarray:
    """A fixed orthogonal matrix for powers of two: signs of coordinates ((7 i + 3) mod 11 even), then the Walsh-Hadamard transform."""
    i = np.arange(dim)
    flip = np.where((7 * i + 3) % 11 % 2 == 0, 1.0, -1.0)
    return flip[:, None] * np.where(np.bitwise_count(i[:, None] & i[None]) % 2 == 0, 1.0, -1.0) / math.sqrt(dim)


def _signs(y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sign words, and the inner product of the unit sign vector with each unit row."""
    s = np.where(y > 0, 1.0, -1.0) / math.sqrt(y.shape[1])
    return kernels.pack(y > 0).view(np.int64), np.einsum("nd,nd->n", s, y)


def rot1bit_codes(vectors: DataFrame, seed: int = 42, turn: np.ndarray | None = None) -> DataFrame:
    """(vec_id, code, factor): signs after a rotation, and the inner product of the unit sign vector with the vector."""
    if turn is None:
        turn = kernels.rotation(vectors.select(F.size("embedding")).first()[0], seed)

    def make(x):
        w, f = _signs(x @ turn)
        return [_lists(w), pa.array(f)]

    return _mapped(vectors, make, "code array<long>, factor double", ["code", "factor"])


def error_bound(factor: np.ndarray, dim: int, eps: float = 1.9) -> np.ndarray:
    """Half-width of the estimate of an inner product of unit vectors from a one-bit code: eps standard deviations."""
    return np.sqrt(np.maximum(1 - factor**2, 0)) / np.maximum(factor, 1e-9) * eps / math.sqrt(max(1, dim - 1))


def rot1bit_fitted(base: DataFrame, lists: int, seed: int = 42, x: np.ndarray | None = None):
    """Rotation, centres and the ranges of the byte codes; the ranges cover all rows. x: the sample, where it is at hand."""
    x = sample(base) if x is None else x
    e = base.select(F.posexplode(F.col("embedding").cast("array<double>")).alias("i", "v")).groupBy("i").agg(F.min("v").alias("lo"), F.max("v").alias("hi")).orderBy("i").collect()
    return kernels.rotation(x.shape[1], seed), kernels.kmeans(x, lists, seed=seed), np.array([r["lo"] for r in e]), np.array([r["hi"] for r in e])


def rot1bit_search(queries: DataFrame, base: DataFrame, lists: int, probe: int, factor: int | None, k: int = 10, seed: int = 42, refine: str = "sq8", fitted=None) -> DataFrame:
    """(qid, rank, vec_id, sim). Rows of a probed list are coded relative to its centre: one sign bit a rotated coordinate, the
    residual's norm, and its inner product with the signs, which makes the estimate unbiased. factor: the best factor * k go on;
    None: all that the error bound cannot rule out. They are refined by byte codes ('sq8') or floats ('float')."""
    turn, centres, lo, hi = fitted or rot1bit_fitted(base, lists, seed)
    dim = len(turn)
    step = np.maximum(hi - lo, 1e-12) / 255

    def make(x):
        r = x - centres[_nearest(x, centres, 1)[:, 0]]
        n = np.linalg.norm(r, axis=1)
        w, f = _signs(r / np.maximum(n, 1e-12)[:, None] @ turn)
        return [_lists(w), pa.array(np.maximum(f, 1e-9)), pa.array(n)]

    def score(qx, t, which):
        c = centres[which]
        words = np.ascontiguousarray(t.column("code").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(t.num_rows, -1))
        bits = np.unpackbits(words.view(np.uint8), axis=1, bitorder="little")[:, :dim]
        f, n = t.column("factor").to_numpy(), t.column("norm").to_numpy()
        qr = qx - c
        qn = np.linalg.norm(qr, axis=1, keepdims=True)
        turned = qr / np.maximum(qn, 1e-12) @ turn
        # Squared distance from its three parts; for unit vectors it orders as the cosine does.
        est = turned @ ((2.0 * bits - 1) / math.sqrt(dim)).T / f[None]
        value = n[None] ** 2 + qn**2 - 2 * n[None] * qn * est
        if factor is not None:
            return value, None
        half = 2 * n[None] * qn * error_bound(f, dim)[None]
        upper = np.sort(value + half, axis=1)[:, min(k, value.shape[1]) - 1 : min(k, value.shape[1])]
        return value, value - half <= upper

    c = probed(queries, base, centres, probe, (factor or 0) * k, make, "code array<long>, factor double, norm double", ["code", "factor", "norm"], score)
    c = _best(c, factor * k) if factor is not None else c
    if refine == "float":
        return exact.rerank(c, base, queries, k)

    def coarse(batches):
        for b in batches:
            if b.num_rows:
                x = exact.matrix(b.column(1))
                yield pa.RecordBatch.from_arrays([b.column(0), _lists(np.rint((x - lo) / step).clip(0, 255) * step + lo)], names=["vec_id", "embedding"])

    bytes_ = base.select(F.col("vec_id").cast("long"), F.col("embedding").cast("array<double>")).mapInArrow(coarse, "vec_id long, embedding array<double>")
    return exact.rerank(c, bytes_, queries, k)


# -- hyperplanes ---------------------------------------------------------------------------------------------------------------


def hyperplane_codes(vectors: DataFrame, bits: int = 64, seed: int = 42) -> DataFrame:
    """(vec_id, code): signs of products with seeded random directions."""
    plane = np.random.default_rng(seed).normal(size=(vectors.select(F.size("embedding")).first()[0], bits))
    return _mapped(vectors, lambda x: [_lists(kernels.pack(x @ plane > 0).view(np.int64))], "code array<long>", ["code"])


def hyperplane_search(queries: DataFrame, base: DataFrame, bits: int = 128, band: int = 8, k: int = 10, seed: int = 42) -> DataFrame:
    """(qid, rank, vec_id, sim): rows that agree with a query in all bits of some band, reranked. Bands are equi-join keys; narrow ones,
    where over a row in a hundred agrees by chance, are compared block by block instead, and only the best of a block leave it."""
    if bits % 64 or 64 % band:
        raise ValueError("whole words, and bands that divide a word")
    if bits // band > 0.01 * (1 << band):
        first = queries.select(F.size("embedding")).first()
        plane = np.random.default_rng(seed).normal(size=(first[0] if first else 1, bits))
        keys = lambda x: (_unit(x) @ plane > 0).reshape(len(x), -1, band) @ (1 << np.arange(band))

        def make(qids, qx, ids, x):
            a, b = keys(qx), keys(x)
            met = np.zeros((len(qx), len(x)), bool)
            for i, j in zip(a.T.astype(np.uint16), b.T.astype(np.uint16), strict=True):
                met |= i[:, None] == j[None]
            sim = exact.Unit(qx).cosines(exact.Unit(x))
            r, c = exact.first(np.where(met, np.where(np.isnan(sim), 2.0, -sim), np.inf), ids, k)
            return pa.RecordBatch.from_arrays([pa.array(qids[r]), pa.array(ids[c]), pa.array(sim[r, c], from_pandas=True)], names=["qid", "vec_id", "sim"])

        met = exact.blocks(queries, base, make, "qid long, vec_id long, sim double")
        return exact.top(met, k, "qid", F.col("sim").desc(), F.col("vec_id")).select("qid", "rank", "vec_id", "sim")

    def keyed(df: DataFrame, name: str) -> DataFrame:
        c = hyperplane_codes(df, bits, seed)
        keys = [F.struct(F.lit(w * 64 // band + j).alias("t"), F.shiftrightunsigned(F.col("code")[w], j * band).bitwiseAND((1 << band) - 1 if band < 63 else -1).alias("k")) for w in range(bits // 64) for j in range(64 // band)]
        return c.select(F.col("vec_id").alias(name), F.explode(F.array(*keys)).alias("b")).select(name, "b.t", "b.k")

    met = keyed(queries, "qid").join(keyed(base, "vec_id"), ["t", "k"]).select("qid", "vec_id").distinct()
    return exact.rerank(met, base, queries, k)
