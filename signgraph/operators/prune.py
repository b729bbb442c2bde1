"""Edge selection on frames: each target's candidates stream past in order, and only the kept ones are held."""
from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import codec, distance

_OUT = "t long, pos int, nbr long, d int"


def _words(col: pa.Array) -> np.ndarray:
    return np.ascontiguousarray(col.flatten().to_numpy(zero_copy_only=False).reshape(len(col), -1)).view(np.uint64)


def _apart(p: np.ndarray, s: np.ndarray, kp: np.ndarray, ks: np.ndarray) -> np.ndarray:
    x = p ^ kp
    return (np.bitwise_count(x).astype(np.int64) + np.bitwise_count(x & s) + np.bitwise_count(x & ks) + np.bitwise_count(x & s & ks)).sum(-1)


class _Walk:
    """One target's walk: candidates come nearest first."""

    def __init__(self, t: int, most: int, alpha100: int, cover: bool):
        self.t, self.most, self.alpha, self.cover = t, most, alpha100, cover
        self.ids, self.d, self.p, self.s, self.same = [], [], [], [], []
        self.seen = None

    def fits(self, d: int, p: np.ndarray, s: np.ndarray) -> bool:
        return not self.ids or bool((100 * d <= self.alpha * _apart(p, s, np.stack(self.p), np.stack(self.s))).all())

    def keep(self, i: int, d: int, p, s) -> None:
        self.ids.append(i)
        self.d.append(d)
        self.p.append(p)
        self.s.append(s)

    def add(self, i: int, d: int, p, s, tp) -> None:
        if len(self.ids) >= self.most:
            return
        if not self.cover:
            if self.fits(d, p, s):
                self.keep(i, d, p, s)
            return
        if self.same and self.same[0][1] != d:
            self.settle()
        self.same.append((i, d, p, s, p ^ tp))

    def settle(self) -> None:
        """Among candidates of one distance, the one that disagrees in most bits not covered so far comes first."""
        live, self.same = [c for c in self.same if self.fits(*c[1:4])], []
        while live and len(self.ids) < self.most:
            if self.seen is None:
                self.seen = np.zeros_like(live[0][4])
            c = live.pop(int(np.argmax([int(np.bitwise_count(c[4] & ~self.seen).sum()) for c in live])))
            self.keep(*c[:4])
            self.seen = self.seen | c[4]
            live = [o for o in live if self.fits(*o[1:4])]

    def rows(self) -> list[tuple]:
        if self.same:
            self.settle()
        return [(self.t, k + 1, i, d) for k, (i, d) in enumerate(zip(self.ids, self.d, strict=True))]


def _selected(most: int, alpha100: int, cover: bool):
    def emit(rows):
        cols = list(zip(*rows, strict=True)) or [[]] * 4
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, (pa.int64(), pa.int32(), pa.int64(), pa.int32()), strict=True)], names=["t", "pos", "nbr", "d"])

    def run(batches):
        walk, out = None, []
        for b in batches:
            t, nbr, d = (b.column(i).to_numpy() for i in range(3))
            p, s = _words(b.column(3)), _words(b.column(4))
            tp = _words(b.column(5)) if cover else p
            for k in range(b.num_rows):
                if walk is None or walk.t != t[k]:
                    if walk is not None:
                        out += walk.rows()
                    walk = _Walk(int(t[k]), most, alpha100, cover)
                walk.add(int(nbr[k]), int(d[k]), p[k], s[k], tp[k])
            if len(out) > 10_000:
                yield emit(out)
                out = []
        if walk is not None:
            out += walk.rows()
        yield emit(out)

    return run


def select(cands: DataFrame, vectors: DataFrame, most: int, alpha100: int, ties: str = "id") -> DataFrame:
    """(t, pos, nbr, d) of candidates (qid, vec_id, value): the kept neighbours of each target, nearest first.

    ties: 'id'; 'coverage' (see kernels.select_edges); 'adc' orders equal distances by the target's floats against the code.
    A target may have any number of candidates: they are sorted by Spark and stream through one pass."""
    dim = codec.dimension(vectors)
    v = codec.encode_sm(vectors, dim, keep=("vec_id", "embedding"))
    rows = cands.select(F.col("qid").alias("t"), F.col("vec_id").alias("nbr"), F.col("value").cast("long").alias("d")).join(v.select(F.col("vec_id").alias("nbr"), "p", "s"), "nbr")
    order = ["t", "d", "nbr"]
    if ties != "id":
        rows = rows.join(v.select(F.col("vec_id").alias("t"), F.col("p").alias("tp"), F.col("embedding").alias("te")), "t")
    if ties == "adc":
        rows = rows.withColumn("fine", -distance.adc(F.col("te"), distance.levels(F.col("p"), F.col("s"), dim)))
        order = ["t", "d", "fine", "nbr"]
    if ties != "coverage":
        rows = rows.withColumn("tp", F.lit(None).cast("array<long>"))
    sorted_ = rows.select("t", "nbr", "d", "p", "s", "tp", *[c for c in order if c == "fine"]).repartition("t").sortWithinPartitions(*order)
    return sorted_.select("t", "nbr", "d", "p", "s", "tp").mapInArrow(_selected(most, alpha100, ties == "coverage"), _OUT)


def add_reverse(edges: DataFrame, vectors: DataFrame, most: int, alpha100: int) -> DataFrame:
    """(t, pos, nbr, d): every edge proposes its reverse; each node selects anew among all its own and proposed neighbours."""
    both = edges.select(F.col("src").alias("qid"), F.col("dst").alias("vec_id"), F.col("d").alias("value")).union(edges.select("dst", "src", "d")).distinct()
    return select(both, vectors, most, alpha100)
