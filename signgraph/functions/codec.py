"""Codes of vectors as Column expressions: sign plane, strength plane, scalar codes.

Planes are arrays of 64-bit words; coordinate i is bit i % 64 of word i // 64, and bits beyond the dimension are 0.
"""
from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def words_of(dim: int) -> int:
    return -(-dim // 64)


def as_double(col: str | Column) -> Column:
    return F.col(col).cast("array<double>") if isinstance(col, str) else col.cast("array<double>")


def usable(df: DataFrame, col: str, dim: int) -> Column:
    """Vectors of the index's dimension without nulls or NaN."""
    x = F.col(col)
    return x.isNotNull() & (F.size(x) == dim) & ~F.exists(x, lambda v: v.isNull() | F.isnan(v))


def split_rejects(df: DataFrame, col: str, dim: int) -> tuple[DataFrame, DataFrame]:
    """Rows that can be encoded, and those that cannot."""
    ok = F.coalesce(usable(df, col, dim), F.lit(False))
    return df.where(ok), df.where(~ok)


def dimension(df: DataFrame, col: str = "embedding") -> int:
    """The longest vector's length; an index has one dimension."""
    return df.agg(F.max(F.size(col))).first()[0] or 0


def mean_abs(x: Column) -> Column:
    return F.aggregate(F.transform(x, F.abs), F.lit(0.0), lambda a, v: a + v) / F.size(x)


def plane(x: Column, dim: int, test) -> Column:
    """A plane with bit i set where test(x_i); each word is a fold over its 64 coordinates."""
    words = []
    for w in range(words_of(dim)):
        part = F.slice(x, 64 * w + 1, 64)
        bits = F.transform(part, lambda v, i: F.when(test(v), F.call_function("shiftleft", F.lit(1).cast("long"), i)).otherwise(F.lit(0).cast("long")))
        words.append(F.aggregate(bits, F.lit(0).cast("long"), lambda a, b: a.bitwiseOR(b)))
    return F.array(*words)


def encode_sign(df: DataFrame, dim: int, col: str = "embedding", keep: tuple[str, ...] = ("vec_id",)) -> DataFrame:
    """keep, p."""
    return df.select(*keep, plane(as_double(col), dim, lambda v: v > 0).alias("p"))


TAUS = ("mean", "gauss", "global", "median", "lloyd")


def threshold(df: DataFrame, dim: int, col: str, tau: str) -> DataFrame:
    """df with _x (doubles) and tau; 'global' is one number over all rows, the rest belong to each vector."""
    x = df.withColumn("_x", as_double(col))
    if tau == "mean":
        return x.withColumn("tau", mean_abs(F.col("_x")))
    if tau == "gauss":
        return x.withColumn("tau", F.lit(math.sqrt(2 / math.pi) / math.sqrt(dim)))
    if tau == "global":
        one = x.select(F.explode(F.transform("_x", F.abs)).alias("a")).agg(F.avg("a").alias("tau"))
        return x.crossJoin(F.broadcast(one))  # one row
    if tau == "median":
        s = F.sort_array(F.transform("_x", F.abs))
        return x.withColumn("_s", s).withColumn("tau", (F.element_at("_s", (dim + 1) // 2) + F.element_at("_s", dim // 2 + 1)) / 2).drop("_s")
    if tau == "lloyd":
        rms = F.sqrt(F.aggregate("_x", F.lit(0.0), lambda a, v: a + v * v) / dim)
        return x.withColumn("tau", 0.98 * rms)
    raise ValueError(tau)


def encode_sm(df: DataFrame, dim: int, col: str = "embedding", tau: str = "mean", keep: tuple[str, ...] = ("vec_id",)) -> DataFrame:
    """keep, tau, p, s, is_degenerate. tau stays in the output, so that it is made once a vector and not once a coordinate."""
    x = threshold(df, dim, col, tau)
    return x.select(*keep, "tau", plane(F.col("_x"), dim, lambda v: v > 0).alias("p"), plane(F.col("_x"), dim, lambda v: F.abs(v) > F.col("tau")).alias("s"), (~F.exists("_x", lambda v: v != 0)).alias("is_degenerate"))


def ones(p: Column, words: int) -> Column:
    return sum((F.bit_count(p[w]) for w in range(1, words)), F.bit_count(p[0]))


def encode_sq2(df: DataFrame, col: str = "embedding", span: str = "vector", keep: tuple[str, ...] = ("vec_id",)) -> DataFrame:
    """keep, code: four equal buckets between a vector's (or all vectors') least and greatest coordinate."""
    x = df.withColumn("_x", as_double(col))
    if span == "vector":
        x = x.withColumn("_lo", F.array_min("_x")).withColumn("_hi", F.array_max("_x"))
    elif span == "global":
        one = x.agg(F.min(F.array_min("_x")).alias("_lo"), F.max(F.array_max("_x")).alias("_hi"))
        x = x.crossJoin(F.broadcast(one))  # one row
    elif span == "sigma":
        c = x.select(F.explode("_x").alias("v")).agg(F.avg("v").alias("m"), F.stddev_pop("v").alias("d"))
        x = x.crossJoin(F.broadcast(c.select((F.col("m") - 3 * F.col("d")).alias("_lo"), (F.col("m") + 3 * F.col("d")).alias("_hi"))))
    else:
        raise ValueError(span)
    width = F.col("_hi") - F.col("_lo")
    code = F.transform("_x", lambda v: F.when(width > 0, F.greatest(F.lit(0), F.least(F.lit(3), F.floor((v - F.col("_lo")) * 4 / width)))).otherwise(0).cast("tinyint"))
    return x.select(*keep, code.alias("code"))


def sq8_ranges(df: DataFrame, col: str = "embedding") -> DataFrame:
    """(dim, lo, hi) of each coordinate."""
    return df.select(F.posexplode(as_double(col)).alias("dim", "v")).groupBy("dim").agg(F.min("v").alias("lo"), F.max("v").alias("hi"))


def encode_sq8(df: DataFrame, col: str = "embedding", keep: tuple[str, ...] = ("vec_id",)) -> DataFrame:
    """keep, code: per coordinate 256 even steps between its least and greatest value. The ranges are one row of D pairs."""
    r = sq8_ranges(df, col).agg(F.transform(F.sort_array(F.collect_list(F.struct("dim", "lo", "hi"))), lambda t: F.struct(t["lo"].alias("lo"), t["hi"].alias("hi"))).alias("_r"))
    x = df.withColumn("_x", as_double(col)).crossJoin(F.broadcast(r))
    code = F.zip_with("_x", "_r", lambda v, t: F.when(t["hi"] > t["lo"], F.round((v - t["lo"]) * 255 / (t["hi"] - t["lo"]))).otherwise(0).cast("int"))
    return x.select(*keep, code.alias("code"))


def l2_normalize(df: DataFrame, col: str = "embedding") -> DataFrame:
    """df with col at unit length; zero vectors become null."""
    n = F.sqrt(F.aggregate(as_double(col), F.lit(0.0), lambda a, v: a + v * v))
    return df.withColumn("_n", n).withColumn(col, F.when(F.col("_n") > 0, F.transform(as_double(col), lambda v: (v / F.col("_n")).cast("float")))).drop("_n")
