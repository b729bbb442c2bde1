"""Statistics of codes, angles and coordinates; the go / no-go probe; theory values."""
from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels
from .functions import codec, distance
from .operators import exact


def strong_rate(codes: DataFrame, dim: int, *group: str) -> DataFrame:
    """(group, n, p_s, nu2): share of strong bits, and the second moment of the pair weight for independent bits."""
    p = F.sum(codec.ones(F.col("s"), codec.words_of(dim))) / (F.count("*") * dim)
    out = codes.groupBy(*group).agg(F.count("*").alias("n"), p.alias("p_s"))
    return out.withColumn("nu2", F.pow(1 + 3 * F.col("p_s"), 2))


#: One row in so many is a query of the pair statistics; each meets all rows.
EVERY = 50


def pairs(df: DataFrame, id_col: str = "vec_id", every: int = EVERY) -> DataFrame:
    """The stated query set (ids divisible by `every`) with all other rows; columns prefixed a_ (query) and b_."""
    a = df.where(F.col(id_col) % every == 0).select(*[F.col(c).alias(f"a_{c}") for c in df.columns])
    b = df.select(*[F.col(c).alias(f"b_{c}") for c in df.columns])
    return exact.paired(a, b, f"a_{id_col}", f"b_{id_col}").where(F.col(f"a_{id_col}") != F.col(f"b_{id_col}"))


def _degrees(qids: np.ndarray, x: np.ndarray, ids: np.ndarray, y: np.ndarray, least: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Places (query, row) of the pairs of a block, and their angles in degrees; a zero row has none, or 0 if least."""
    i, j = np.nonzero(qids[:, None] != ids[None])
    c = exact.Unit(x).cosines(exact.Unit(y))[i, j]
    if least:
        c = np.clip(np.where(np.isnan(c), 1.0, c), -1.0, 1.0)
    with np.errstate(invalid="ignore"):
        return i, j, np.degrees(np.arccos(c))


def _cosines(qids: np.ndarray, x: np.ndarray, ids: np.ndarray, y: np.ndarray):
    """Cosines of a block by one matrix product (1 for zero rows), the mask of rows with themselves, and exact(i, j): the angles in
    degrees of some of the pairs, as _degrees has them."""
    a, b = exact.Unit(x), exact.Unit(y)
    c = a.near(b)
    c[np.isnan(c)] = 1.0

    def degrees(i, j):
        e = a.pairs(b, i, j)
        return np.degrees(np.arccos(np.clip(np.where(np.isnan(e), 1.0, e), -1.0, 1.0)))

    return c, qids[:, None] == ids[None], degrees, a.slack()


def _queries(df: DataFrame, every: int) -> DataFrame:
    return df.where(F.col("vec_id") % every == 0)


def rounded(x: np.ndarray, digits: int = 6) -> np.ndarray:
    """Half away from zero."""
    y = x * 10.0**digits
    low = np.trunc(y)
    return (low + np.where(np.abs(y - low) >= 0.5, np.sign(y), 0)) / 10.0**digits


def angle_estimates(df: DataFrame, dim: int, every: int = EVERY) -> DataFrame:
    """(a, b, est_deg, true_deg): the angle by differing signs and by cosine (null for a zero row or a cosine above 1); with every = 1 of
    each row with all others."""
    step = rounded(np.arange(dim + 1) * (180.0 / dim))

    def make(qids, x, ids, y):
        i, j, deg = _degrees(qids, x, ids, y, least=False)
        signs = [np.where(v > 0, 1, -1).astype(np.float32) for v in (x, y)]
        h = np.rint((dim - signs[0] @ signs[1].T) / 2).astype(np.int64)[i, j]
        return pa.RecordBatch.from_arrays([pa.array(qids[i]), pa.array(ids[j]), pa.array(step[h]), pa.array(rounded(deg), pa.float64(), from_pandas=True)], names=["a", "b", "est_deg", "true_deg"])

    return exact.cells(_queries(df, every), df, make, "a long, b long, est_deg double, true_deg double")


def angle_stats(df: DataFrame, every: int = EVERY) -> DataFrame:
    """(pairs, mean, sd): a row of sums leaves a block, not its pairs."""

    def make(qids, x, ids, y):
        c, same, sharp, _ = _cosines(qids, x, ids, y)
        i, j = np.nonzero(np.abs(c) > 1 - 1e-6)  # here an angle feels the last bits of its cosine
        deg = np.degrees(np.arccos(np.clip(c, -1.0, 1.0)))
        deg[i, j] = sharp(i, j)
        deg = deg[~same] if same.any() else deg.ravel()
        m = float(deg.mean()) if len(deg) else 0.0
        return pa.RecordBatch.from_arrays([pa.array([len(deg)], pa.int64()), pa.array([m]), pa.array([float(((deg - m) ** 2).sum())])], names=["n", "m", "s"])

    part = exact.blocks(_queries(df, every), df, make, "n long, m double, s double").persist()
    n, m = F.sum("n"), F.sum(F.col("n") * F.col("m")) / F.sum("n")
    one = part.agg(F.coalesce(n, F.lit(0)).cast("long").alias("pairs"), m.alias("mean"))
    return part.crossJoin(F.broadcast(one)).groupBy("pairs", "mean").agg(F.sum(F.col("s") + F.col("n") * (F.col("m") - F.col("mean")) ** 2).alias("s")).select("pairs", "mean", F.sqrt(F.col("s") / F.col("pairs")).alias("sd"))


def angle_hist(df: DataFrame, width: float = 5.0, every: int = EVERY) -> DataFrame:
    """(bucket, n): pairs are counted at the edges of the buckets; those within rounding of an edge are judged by their exact angle."""

    def make(qids, x, ids, y):
        c, same, sharp, slack = _cosines(qids, x, ids, y)
        c[same] = 2.0  # beyond every edge
        n, slack = c.size - int(same.sum()), slack + 1e-14
        least, over = (c.min() if n else 2.0), [n]  # over[k]: pairs whose angle is k widths at least
        while over[-1]:
            k = len(over)
            edge = math.cos(math.radians(min(180.0, k * width)))
            if k * width > 180.0 or edge + slack < least:
                over.append(0)
                continue
            sure, may = np.count_nonzero(c <= edge - slack), np.count_nonzero(c <= edge + slack)
            if may > sure:
                i, j = np.nonzero((c > edge - slack) & (c <= edge + slack))
                sure += int((np.floor(sharp(i, j) / width) >= k).sum())
            over.append(int(sure))
        n = -np.diff(over)
        at = np.flatnonzero(n)
        return pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(n[at].astype(np.int64))], names=["bucket", "n"])

    return exact.blocks(_queries(df, every), df, make, "bucket int, n long").groupBy("bucket").agg(F.sum("n").alias("n"))


def coord_stats(df: DataFrame, col: str = "embedding") -> DataFrame:
    """(dim, mean, sd, skew, kurt): population moments of each coordinate."""
    e = df.select(F.posexplode(codec.as_double(col)).alias("dim", "x"))
    return e.groupBy("dim").agg(F.avg("x").alias("mean"), F.stddev_pop("x").alias("sd"), F.skewness("x").alias("skew"), F.kurtosis("x").alias("kurt"))


def normal_share(df: DataFrame, col: str = "embedding", limit: float = 5.991) -> DataFrame:
    """Share of coordinates that pass a Jarque-Bera test."""
    e = df.select(F.posexplode(codec.as_double(col)).alias("dim", "x")).groupBy("dim").agg(F.count("*").alias("n"), F.skewness("x").alias("g"), F.kurtosis("x").alias("k"))
    return e.agg(F.avg((F.col("n") / 6 * (F.col("g") ** 2 + F.col("k") ** 2 / 4) <= limit).cast("double")).alias("share"))


def effective_rank(df: DataFrame, col: str = "embedding") -> DataFrame:
    """(rank): participation ratio of the Gram matrix, (sum of its eigenvalues)^2 over the sum of their squares, that is trace^2
    over the sum of squared entries; one D x D partial sum a task."""

    def run(batches):
        total = None
        for b in batches:
            if b.num_rows:
                x = exact.matrix(b.column(0))
                total = x.T @ x if total is None else total + x.T @ x
        if total is not None:
            d = len(total)
            yield pa.RecordBatch.from_arrays([pa.array([k // d for k in range(d * d)], pa.int32()), pa.array([k % d for k in range(d * d)], pa.int32()), pa.array(total.ravel())], names=["i", "j", "v"])

    g = df.select(F.col(col).cast("array<double>")).mapInArrow(run, "i int, j int, v double").groupBy("i", "j").agg(F.sum("v").alias("v"))
    return g.agg((F.pow(F.sum(F.when(F.col("i") == F.col("j"), F.col("v")).otherwise(0.0)), 2) / F.sum(F.col("v") * F.col("v"))).alias("rank"))


def triplets(vectors: DataFrame, near: int = 10, far: int = 50, every: int = EVERY) -> DataFrame:
    """(q, v, w): q a query, v among its `near` nearest of all rows, w among those behind them up to `far`."""
    ranked = exact.float_topk(_queries(vectors, every), vectors, far, kind="cos", skip_self=True).withColumnRenamed("qid", "q").persist()
    a = ranked.where(F.col("rank") <= near).select("q", F.col("vec_id").alias("v"))
    b = ranked.where(F.col("rank") > near).select("q", F.col("vec_id").alias("w"))
    return a.join(b, "q")


def _gaps(codes: DataFrame, trip: DataFrame, dim: int) -> DataFrame:
    """trip with _z: per coordinate, how much more w differs from q than v does."""
    y = codes.select("vec_id", distance.levels(F.col("p"), F.col("s"), dim).alias("y"))
    for c in ("q", "v", "w"):
        trip = trip.join(y.select(F.col("vec_id").alias(c), F.col("y").alias(f"_{c}")), c)
    part = lambda a, b: F.when(a * b < 0, F.abs(a * b)).otherwise(0.0)
    z = F.zip_with(F.arrays_zip("_q", "_v"), "_w", lambda t, w: part(t["_q"], w) - part(t["_q"], t["_v"]))
    return trip.withColumn("_z", z)


def misrank_rate(codes: DataFrame, trip: DataFrame, dim: int) -> DataFrame:
    z = _gaps(codes, trip, dim).withColumn("d", F.aggregate("_z", F.lit(0.0), lambda a, v: a + v))
    return z.agg(F.count("*").alias("triplets"), F.avg((F.col("d") <= 0).cast("double")).alias("rate"))


def misrank_bound(codes: DataFrame, trip: DataFrame, dim: int, span: float = 8.0) -> DataFrame:
    """(mu, v, bound): mean of the summed gap, summed variances of the coordinates' gaps, and the exponential bound."""
    names = ["p", "s"]
    c = codes.select("vec_id", *names)
    for k in ("q", "v", "w"):
        trip = trip.join(c.select(F.col("vec_id").alias(k), *[F.col(n).alias(f"{k}_{n}") for n in names]), k)

    def run(batches):
        n, one, two = 0, np.zeros(dim), np.zeros(dim)
        for b in batches:
            if not b.num_rows:
                continue
            y = [kernels.unpack_levels(*[exact.words(b.column(3 + 2 * k + i)) for i in range(2)], dim) for k in range(3)]
            part = lambda o: np.where(y[0] * o < 0, np.abs(y[0] * o), 0.0)  # noqa: B023, E731
            z = part(y[2]) - part(y[1])
            n, one, two = n + len(z), one + z.sum(0), two + (z * z).sum(0)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(dim, dtype=np.int32)), pa.array(np.full(dim, n)), pa.array(one), pa.array(two)], names=["i", "n", "one", "two"])

    sums = trip.select("q", "v", "w", *[f"{k}_{n}" for k in ("q", "v", "w") for n in names]).mapInArrow(run, "i int, n long, one double, two double")  # whole numbers: sums are exact
    z = sums.groupBy("i").agg((F.sum("one") / F.sum("n")).alias("m"), (F.sum("two") / F.sum("n")).alias("mm")).select("m", (F.col("mm") - F.col("m") ** 2).alias("var"))
    return z.agg(F.sum("m").alias("mu"), F.sum("var").alias("v")).withColumn("bound", F.exp(-(F.col("mu") ** 2) / (2 * F.col("v") + F.lit(2.0 / 3.0) * span * F.col("mu"))))


def angle_concentration(codes: DataFrame, vectors: DataFrame, dim: int, eps: list[float], every: int = EVERY) -> DataFrame:
    """(eps, share, bound): pairs whose share of differing signs is further than eps from angle / pi."""
    d = codes.select("vec_id", "p").join(vectors.select("vec_id", "embedding"), "vec_id")
    h = distance.hamming(F.col("a_p"), F.col("b_p"), codec.words_of(dim)) / F.lit(float(dim))
    t = F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), distance.cosine(F.col("a_embedding"), F.col("b_embedding"))))) / math.pi
    dev = pairs(d, every=every).select(F.abs(h - t).alias("dev"))
    e = dev.withColumn("eps", F.explode(F.array(*[F.lit(x) for x in eps])))
    bound = F.least(F.lit(1.0), 2 * F.exp(-2.0 * dim * F.col("eps") * F.col("eps")))
    return e.groupBy("eps").agg(F.avg((F.col("dev") > F.col("eps")).cast("double")).alias("share")).withColumn("bound", bound)


def sqnr_by_code(vectors: DataFrame, dim: int) -> DataFrame:
    """(code, sqnr_db): signal to quantisation noise with the mean of each cell as its level, for one and two bits."""
    x = codec.threshold(vectors, dim, "embedding", "mean").select("tau", F.explode("_x").alias("x"))
    sign = (F.col("x") > 0).cast("int")
    two = sign * 2 + (F.abs("x") > F.col("tau")).cast("int")
    cells = x.select(F.col("x"), F.explode(F.array(F.struct(F.lit("1-bit").alias("code"), sign.alias("cell")), F.struct(F.lit("2-bit").alias("code"), two.alias("cell")))).alias("c")).groupBy("c.code", "c.cell").agg(F.count("*").alias("n"), F.sum("x").alias("sx"), F.sum(F.col("x") * F.col("x")).alias("sxx"))
    noise = F.sum(F.col("sxx") - F.col("sx") * F.col("sx") / F.col("n"))
    return cells.groupBy("code").agg((10 * F.log10(F.sum("sxx") / noise)).alias("sqnr_db"))


def gaussian_sqnr(bits: int) -> float:
    """Signal to noise in dB of the codes on a normal source: best levels on either side of sqrt(2 / pi)."""
    if bits == 1:
        return -10 * math.log10(1 - 2 / math.pi)
    t = math.sqrt(2 / math.pi)
    phi = lambda z: math.exp(-z * z / 2) / math.sqrt(2 * math.pi)
    upper = 0.5 * math.erfc(t / math.sqrt(2))
    inner = 0.5 - upper
    return -10 * math.log10(1 - 2 * ((phi(0) - phi(t)) ** 2 / inner + phi(t) ** 2 / upper))


def margin_path(path: DataFrame, gamma: float, eps: float, scale: float = 1.0) -> DataFrame:
    """(path, steps, margin_ok, preserved): path rows (path, pos, d, est). Each step nears the target by gamma; the estimate is
    within eps of scale * d everywhere and eps < scale * gamma / 2; then it falls along the path too (falls is measured)."""
    from pyspark.sql import Window

    w = Window.partitionBy("path").orderBy("pos")
    s = path.select("path", "d", "est", F.lag("d").over(w).alias("d0"), F.lag("est").over(w).alias("e0"))
    g = s.groupBy("path").agg(F.count("d0").alias("steps"), F.min(F.coalesce(F.col("d0") - F.col("d") >= gamma, F.lit(True))).alias("margin_ok"), (F.max(F.abs(F.col("est") - scale * F.col("d"))) <= eps).alias("near"), F.min(F.coalesce(F.col("est") < F.col("e0"), F.lit(True))).alias("falls"))
    return g.select("path", "steps", "margin_ok", (F.col("margin_ok") & F.col("near") & F.lit(eps < scale * gamma / 2)).alias("preserved"), "falls")


def overlap(vectors: DataFrame, dim: int, k: int = 10) -> DataFrame:
    """(n, overlap): share of the exact top k of each vector among its top k by code, itself left out."""
    truth = exact.float_topk(vectors, vectors, k, skip_self=True)
    codes = exact.float_topk(vectors, vectors, k, kind="bq2", skip_self=True)
    hit = truth.select("qid", "vec_id").join(codes.select("qid", "vec_id"), ["qid", "vec_id"], "left_semi").agg(F.count("*").alias("hits"))
    return vectors.agg(F.count("*").alias("n")).crossJoin(hit).select("n", (F.col("hits") / (F.col("n") * k)).alias("overlap"))


def compatibility(vectors: DataFrame, n: int = 10_000, k: int = 10, threshold: float = 0.5, seed: int = 42) -> DataFrame:
    """One row (n, k, overlap, verdict). The sample is the n rows of least id hash. Overlap falls with n, so below the threshold is
    no-go at any n; above it a small sample must clear a margin of 0.1, or the answer is inconclusive."""
    from .functions.codec import dimension

    s = vectors.orderBy(F.xxhash64(F.col("vec_id"), F.lit(seed)), "vec_id").limit(n).select("vec_id", "embedding").persist()
    o = overlap(s, dimension(s), k)
    v = F.when(F.col("overlap") < threshold, "no-go").when((F.col("n") >= 10_000) | (F.col("overlap") >= threshold + 0.1), "go").otherwise("inconclusive")
    return o.select("n", F.lit(k).alias("k"), F.round("overlap", 6).alias("overlap"), v.alias("verdict"))
