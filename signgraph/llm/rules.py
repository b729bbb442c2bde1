"""Quality rules: robust multivariate outliers, with DataFrame functions only.

Base rules come first (too few words, too many words in repeated three-word windows). The texts that pass are described by
a vector of transformed statistics; per language and source a minimum-covariance-determinant estimate is found: several starts,
concentration steps (mean and covariance of the three quarters of the rows with the least distances) until the determinant no
longer falls, the least determinant wins, and one reweighting. Covariances carry a fixed floor (a regularised determinant), as
statistics that are constant among clean texts have none of their own. A text is kept when its squared Mahalanobis distance stays
below the CUT_AT quantile of the chi-square law. Groups of fewer than `small` rows use the estimate of all rows.

A subset's limit is read from counts of distances in fine logarithmic steps, so that no group is gathered in one place: each
step is two partial aggregations over (group) and (group, step), however large a group is; parameters go to the rows.

Null text: no words, so base_failed. Null language or source: a group of its own. Repeated rows get equal verdicts; an
empty table gives an empty result; extra columns are ignored.
"""
from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import documents, release, settle

SPACES = " \t\n\x0b\x0c\r"
SYMBOLS = "#*$%&|<>"
DIMS = 4
COUNTS = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]
#: Squared distances in steps of a 32th of a doubling.
FINE = 32


def statistics(docs: DataFrame, text: str = "text") -> DataFrame:
    """docs plus n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words (all long).

    Each array is a column of its own before a lambda reads it, so it is made once a row.
    """
    t = F.coalesce(F.col(text).cast("string"), F.lit(""))
    w = docs.withColumn("_t", t).withColumn("_w", F.filter(F.split("_t", "[ \\t-\\r]+"), lambda x: x != ""))
    rest2, rest3 = F.expr("slice(_w, 2, greatest(size(_w) - 2, 0))"), F.expr("slice(_w, 3, greatest(size(_w) - 2, 0))")
    w = w.withColumn("_h", F.transform(F.arrays_zip(F.expr("slice(_w, 1, greatest(size(_w) - 2, 0))").alias("a"), rest2.alias("b"), rest3.alias("c")), lambda x, i: F.struct(F.xxhash64(x["a"], x["b"], x["c"]).alias("h"), i.alias("i"))))
    w = w.withColumn("_s", F.sort_array("_h"))
    w = w.withColumn("_n", F.size("_s"))
    none = F.lit(None).cast("struct<h:bigint,i:int>")
    before = F.concat(F.array(none), F.expr("slice(_s, 1, greatest(_n - 1, 0))"))
    after = F.concat(F.expr("slice(_s, 2, greatest(_n - 1, 0))"), F.array(none))
    trio = F.arrays_zip(F.col("_s").alias("x"), before.alias("p"), after.alias("q"))
    w = w.withColumn("_d", F.when(F.col("_n") < 2, F.array().cast("array<int>")).otherwise(F.sort_array(F.transform(F.filter(trio, lambda r: (r["x"]["h"] == r["p"]["h"]) | (r["x"]["h"] == r["q"]["h"])), lambda r: r["x"]["i"]))))
    # Words covered by windows that start at sorted places: each adds the gap to the next start, three at most.
    gaps = F.zip_with("_d", F.expr("slice(_d, 2, greatest(size(_d) - 1, 0))"), lambda a, b: F.least(F.lit(3), F.coalesce(b - a, F.lit(3))))
    lines = F.filter(F.split("_t", "\n"), lambda x: F.translate(x, SPACES, "") != "")
    return (
        w.withColumn("_l", lines)
        .withColumn("n_words", F.size("_w").cast("long"))
        .withColumn("word_chars", F.char_length(F.translate("_t", SPACES, "")).cast("long"))
        .withColumn("n_symbols", (F.char_length("_t") - F.char_length(F.translate("_t", SYMBOLS, ""))).cast("long"))
        .withColumn("n_dup_lines", (F.size("_l") - F.size(F.array_distinct("_l"))).cast("long"))
        .withColumn("n_repeat_words", F.aggregate(gaps, F.lit(0), lambda a, x: a + x).cast("long"))
        .drop("_t", "_w", "_h", "_s", "_n", "_d", "_l")
    )


def vector() -> list[Column]:
    """Word length, shares of symbols, repeated lines and repeated words, on scales where clean text is about even."""
    n = F.greatest(F.col("n_words"), F.lit(1)).cast("double")
    return [
        F.log(F.greatest(F.col("word_chars"), F.lit(1)) / n),
        F.log1p(1000 * F.col("n_symbols") / F.greatest(F.col("word_chars"), F.lit(1))),
        F.log1p(100 * F.col("n_dup_lines") / n),
        F.log1p(20 * F.col("n_repeat_words") / n),
    ]


#: Least spread that a dimension is given, so that a statistic that is constant among clean texts still has a scale.
FLOOR = (0.05, 0.35, 0.25, 0.25)


def _factor(g: DataFrame, *key: str) -> DataFrame:
    """Lower triangle l_ij of the Cholesky factor, column by column, beside mu_i and the log determinant; g has n, s_i and s_ij sums."""
    for i in range(DIMS):
        g = g.withColumn(f"mu{i}", F.col(f"s{i}") / F.col("n"))
    for j in range(DIMS):
        for i in range(j, DIMS):
            c = F.col(f"s{j}_{i}") / F.col("n") - F.col(f"mu{i}") * F.col(f"mu{j}")
            if i == j:
                c = F.greatest(c, F.lit(0.0)) + FLOOR[i] ** 2
            for k in range(j):
                c = c - F.col(f"l{i}{k}") * F.col(f"l{j}{k}")
            g = g.withColumn(f"l{i}{j}", F.sqrt(F.greatest(c, F.lit(1e-9))) if i == j else c / F.col(f"l{j}{j}"))
    det = sum((2 * F.log(F.col(f"l{i}{i}")) for i in range(1, DIMS)), 2 * F.log(F.col("l00")))
    return g.select(*key, det.alias("det"), *PARAMS)


def _distance(x: DataFrame) -> DataFrame:
    """x with mu_i, l_ij and x_i: adds d2 by forward substitution."""
    for i in range(DIMS):
        z = F.col(f"x{i}") - F.col(f"mu{i}")
        for k in range(i):
            z = z - F.col(f"l{i}{k}") * F.col(f"z{k}")
        x = x.withColumn(f"z{i}", z / F.col(f"l{i}{i}"))
    return x.withColumn("d2", sum((F.col(f"z{i}") * F.col(f"z{i}") for i in range(1, DIMS)), F.col("z0") * F.col("z0")))


def _step() -> Column:
    return F.floor(F.log2(F.greatest(F.col("d2"), F.lit(1e-12))) * FINE).cast("int")


def _moments(x: DataFrame, *key: str) -> DataFrame:
    sums = [F.sum(f"x{i}").alias(f"s{i}") for i in range(DIMS)]
    sums += [F.sum(F.col(f"x{j}") * F.col(f"x{i}")).alias(f"s{j}_{i}") for j in range(DIMS) for i in range(j, DIMS)]
    return x.groupBy(*key).agg(F.count("*").alias("n"), *sums)


def _first_full(need: Column) -> Column:
    """The step of h, sorted (step, count) pairs, at which `need` rows are reached."""
    run = lambda a, r: F.struct((a["n"] + r["c"]).alias("n"), F.coalesce(a["b"], F.when(a["n"] + r["c"] >= need, r["b"])).alias("b"))
    return F.aggregate("h", F.struct(F.lit(0).cast("long").alias("n"), F.lit(None).cast("int").alias("b")), run)["b"]


def _counted(x: DataFrame, step: Column, *key: str) -> DataFrame:
    """(key, h, all): one row of (step, count) pairs a key, at most some thousand steps, whatever the number of texts."""
    counts = x.groupBy(*key, step.alias("b")).agg(F.count("*").alias("c"))
    return counts.groupBy(*key).agg(F.sort_array(F.collect_list(F.struct("b", "c"))).alias("h"), F.sum("c").alias("all"))


def _limits(x: DataFrame, share: float, *key: str) -> DataFrame:
    """(key, top): the distance step at which each subset of the given share is full."""
    return _counted(x, _step(), *key).select(*key, _first_full(F.ceil(F.col("all") * share)).alias("top"))


def _with_params(rows: DataFrame, params: DataFrame, groups: int) -> DataFrame:
    """Rows beside their group's parameters: broadcast while the groups, counted, are few; else a join that may split a hot group."""
    return rows.join(F.broadcast(params) if groups <= FEW else params, "g")


def _concentrated(rows: DataFrame, now: DataFrame, groups: int, share: float, *key: str) -> DataFrame:
    """One concentration step: the estimate of the rows that are nearest by the last one. Parameters of the last one stay where
    theirs has the lesser determinant (the subset is cut at a step of the distance, so it may hold a few rows more)."""
    d = _distance(_with_params(rows, now.drop("det"), groups)).select(*key, *[f"x{i}" for i in range(DIMS)], "d2")
    near = d.join(F.broadcast(_limits(d, share, *key)) if groups <= FEW else _limits(d, share, *key), list(key)).where(_step() <= F.col("top"))
    both = now.withColumn("new", F.lit(0)).unionByName(_factor(_moments(near, *key), *key).withColumn("new", F.lit(1)))
    return both.groupBy(*key).agg(F.min_by(F.struct("det", *PARAMS), F.struct("det", "new")).alias("p")).select(*key, "p.*")


def robust(x: DataFrame, most: int = 20, share: float = 0.75, small: int = 200, starts: int = 3) -> DataFrame:
    """Estimates (g, mu_i, l_ij, k) by the least determinant; x: g and x_i. Group '*' is all rows; it serves small groups.

    Starts: each dimension's median with the floor as spread, and the moments of an eighth of the rows, named by hash, for each
    other start. All take two concentration steps; the start of least determinant goes on until no group's determinant falls.
    Then rows beyond the 0.975 quantile are left out once and the estimate is taken anew from the others."""
    rows = settle(x.select("g", *[f"x{i}" for i in range(DIMS)]).withColumn("g", F.explode(F.array(F.col("g"), F.lit("*")))), "mcd-rows")
    groups = starts * (rows.select("g").distinct().count())
    cells = None
    for i in range(DIMS):
        one = _counted(rows, F.floor(F.col(f"x{i}") * 256).cast("int"), "g").select("g", (_first_full(F.ceil(F.col("all") / 2)) / 256.0).alias(f"mu{i}"))
        cells = one if cells is None else cells.join(one, "g")
    for i in range(DIMS):
        for j in range(i + 1):
            cells = cells.withColumn(f"l{i}{j}", F.lit(2 * FLOOR[i] if i == j else 0.0))
    first = [cells.select("g", F.lit(0).alias("s"), F.lit(float("inf")).alias("det"), *PARAMS)]
    for k in range(1, starts):
        part = rows.where(F.pmod(F.xxhash64(*[f"x{i}" for i in range(DIMS)], F.lit(k)), F.lit(8)) == 0)
        first.append(_factor(_moments(part, "g"), "g").select("g", F.lit(k).alias("s"), F.lit(float("inf")).alias("det"), *PARAMS))
    now = first[0]
    for f in first[1:]:
        now = now.unionByName(f)
    now = settle(now, "mcd")
    for _ in range(2):
        after = settle(_concentrated(rows, now, groups, share, "g", "s"), "mcd")
        release(now)
        now = after
    best = settle(now.groupBy("g").agg(F.min_by(F.struct("det", *PARAMS), F.struct("det", "s")).alias("p")).select("g", "p.*"), "mcd")
    release(now)
    now = best
    for _ in range(most):
        after = settle(_concentrated(rows, now, groups, share, "g"), "mcd")
        fall = now.select("g", F.col("det").alias("d0")).join(after.select("g", "det"), "g").agg(F.max(F.col("d0") - F.col("det"))).first()[0]
        release(now)
        now = after
        if fall is None or fall < 1e-4:
            break
    # The subset is narrower than the whole: widen so that its limit is where the chi-square law has it.
    d = _distance(_with_params(rows, now.drop("det"), groups)).select("g", *[f"x{i}" for i in range(DIMS)], "d2")
    wide = _limits(d, share, "g").select("g", (F.pow(F.lit(2.0), (F.col("top") + 1) / F.lit(float(FINE))) / CHI_SHARE).alias("k"))
    inner = d.join(F.broadcast(wide) if groups <= FEW else wide, "g").where(F.col("d2") <= CHI_INNER * F.greatest(F.col("k"), F.lit(1.0)))
    size = rows.groupBy("g").agg(F.count("*").alias("m"))
    out = _factor(_moments(inner, "g"), "g").join(size, "g").where((F.col("m") >= small) | (F.col("g") == "*"))
    out = settle(out.select("g", *PARAMS, F.lit(WIDEN).alias("k")), "mcd")
    release(now)
    release(rows)
    return out


#: Fixed values of the chi-square law with four degrees of freedom: its quantiles at 0.75, 0.975 and CUT_AT; and what a normal
#: covariance loses when rows beyond the second are left out.
CHI_SHARE, CHI_INNER, CUT_AT, CHI_CUT, WIDEN = 5.385, 11.143, 0.999999, 33.377, 1.0645
PARAMS = [f"mu{i}" for i in range(DIMS)] + [f"l{i}{j}" for i in range(DIMS) for j in range(i + 1)]
#: Groups up to which parameters, of some 150 bytes each, are broadcast.
FEW = 100_000


def judged(docs: DataFrame) -> DataFrame:
    """doc_id, the statistics, base_failed, kept, and d2 where a vector was judged."""
    x = docs.select("doc_id", F.col("text").cast("string").alias("text"), F.concat_ws("\x01", F.coalesce(F.col("lang").cast("string"), F.lit("\x02")), F.coalesce(F.col("source").cast("string"), F.lit("\x02"))).alias("g"))
    s = statistics(x).drop("text")
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    s = s.withColumn("base_failed", failed)
    base = settle(s.select("*", *[v.alias(f"x{i}") for i, v in enumerate(vector())]), "rules")
    fit = robust(base.where("not base_failed"))
    own, whole = fit.where("g <> '*'").withColumn("own", F.lit(True)), fit.where("g = '*'").drop("g")
    mine = base.join(F.broadcast(own) if own.count() <= FEW else own, "g", "left")
    # The group of all rows is one row.
    both = mine.join(F.broadcast(whole.select(F.lit(True).alias("one"), *[F.col(c).alias(f"w_{c}") for c in whole.columns])), F.col("one"), "left")
    both = both.select("doc_id", *COUNTS, "base_failed", *[f"x{i}" for i in range(DIMS)], *[F.when(F.col("own"), F.col(p)).otherwise(F.col(f"w_{p}")).alias(p) for p in [*PARAMS, "k"]])
    d2 = F.when(~F.col("base_failed"), F.col("d2") / F.greatest(F.col("k"), F.lit(1.0)))
    return _distance(both).withColumn("d2", d2).select("doc_id", *COUNTS, "base_failed", (~F.col("base_failed") & F.coalesce(F.col("d2") <= CHI_CUT, F.lit(True))).alias("kept"), F.round("d2", 6).alias("d2"))


def op8_robust_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judged(documents(spark, sf_dir, F.col("doc_id").cast("long").alias("doc_id"), "text", "lang", "source"))
