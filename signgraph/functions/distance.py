"""Distances between codes as unrolled Column expressions, so that they stay inside generated code."""
from __future__ import annotations

import math

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def _sum(parts: list[Column]) -> Column:
    return sum(parts[1:], parts[0])


def bq(pa: Column, sa: Column, pb: Column, sb: Column, words: int) -> Column:
    """Symmetric two-bit distance: over differing signs, (1 + strong_a)(1 + strong_b). Four counts a word."""
    out = []
    for w in range(words):
        x = pa[w].bitwiseXOR(pb[w])
        a, b = x.bitwiseAND(sa[w]), x.bitwiseAND(sb[w])
        out += [F.bit_count(x), F.bit_count(a), F.bit_count(b), F.bit_count(a.bitwiseAND(sb[w]))]
    return _sum(out).cast("int")


def categories(pa: Column, sa: Column, pb: Column, sb: Column, words: int, dim: int) -> list[Column]:
    """same/diff sign by both, one, none strong."""
    x = [pa[w].bitwiseXOR(pb[w]) for w in range(words)]
    both = [sa[w].bitwiseAND(sb[w]) for w in range(words)]
    either = [sa[w].bitwiseOR(sb[w]) for w in range(words)]
    count = lambda masks: _sum([F.bit_count(m) for m in masks]).cast("int")
    db = count([m.bitwiseAND(v) for m, v in zip(both, x, strict=True)])
    de = count([m.bitwiseAND(v) for m, v in zip(either, x, strict=True)])
    dx, nb, ne = count(x), count(both), count(either)
    return [(nb - db).alias("same_both"), (ne - nb - de + db).alias("same_one"), (dim - ne - dx + de).cast("int").alias("same_none"), db.alias("diff_both"), (de - db).alias("diff_one"), (dx - de).alias("diff_none")]


def hamming(pa: Column, pb: Column, words: int) -> Column:
    return _sum([F.bit_count(pa[w].bitwiseXOR(pb[w])) for w in range(words)]).cast("int")


def angle_from_hamming(h: Column, dim: int) -> Column:
    """Degrees."""
    return h * (180.0 / dim)


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a.cast("array<double>"), b.cast("array<double>"), lambda x, y: x * y), F.lit(0.0), lambda t, v: t + v)


def cosine(a: Column, b: Column) -> Column:
    """Null where a vector is zero."""
    n = F.sqrt(dot(a, a)) * F.sqrt(dot(b, b))
    return F.when(n > 0, dot(a, b) / n)


def l1(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: F.abs(x.cast("int") - y.cast("int"))), F.lit(0), lambda t, v: t + v)


def adc(query: Column, y: Column) -> Column:
    """Float query against levels sign * (1 + strong): a similarity."""
    return dot(query, y)


def levels(p: Column, s: Column, dim: int) -> Column:
    """sign * (1 + strong) of each coordinate, from the planes."""
    def one(i: Column) -> Column:
        w, b = (i / 64).cast("int"), (i % 64).cast("int")
        bit = lambda plane: F.call_function("shiftrightunsigned", F.element_at(plane, w + 1), b).bitwiseAND(F.lit(1).cast("long"))
        return ((2 * bit(p) - 1) * (1 + bit(s))).cast("double")

    return F.transform(F.sequence(F.lit(0), F.lit(dim - 1)), one)


def hoeffding(dim: int, eps: float) -> float:
    """Two-sided tail of the share of differing signs around its mean."""
    return min(1.0, 2 * math.exp(-2 * dim * eps * eps))


def register(spark: SparkSession, words: int = 1) -> None:
    """SQL: bq_dist(pa, sa, pb, sb), hamming_dist(pa, pb), sm_tau(x), adc_score(x, y) as temporary SQL functions (no Python)."""
    term = "+".join(f"bit_count(pa[{w}]^pb[{w}])+bit_count((pa[{w}]^pb[{w}])&sa[{w}])+bit_count((pa[{w}]^pb[{w}])&sb[{w}])+bit_count((pa[{w}]^pb[{w}])&sa[{w}]&sb[{w}])" for w in range(words))
    arr = "array<bigint>"
    spark.sql(f"create or replace temporary function bq_dist(pa {arr}, sa {arr}, pb {arr}, sb {arr}) returns int return cast({term} as int)")
    spark.sql(f"create or replace temporary function hamming_dist(pa {arr}, pb {arr}) returns int return cast({'+'.join(f'bit_count(pa[{w}]^pb[{w}])' for w in range(words))} as int)")
    spark.sql("create or replace temporary function sm_tau(x array<double>) returns double return aggregate(transform(x, v -> abs(v)), 0D, (a, v) -> a + v) / size(x)")
    spark.sql("create or replace temporary function adc_score(q array<double>, y array<double>) returns double return aggregate(zip_with(q, y, (a, b) -> a * b), 0D, (t, v) -> t + v)")
