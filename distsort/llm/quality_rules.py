"""Quality rules: base rules, then robust multivariate outliers, with DataFrame functions only.

Each document has a vector of five transformed statistics.  For each language and source, the minimum-covariance-determinant
estimate is the mean and covariance of the share H of the rows whose covariance has the least determinant.  It is
found by concentration steps from two starts (medians and deviations, plain moments): the rows nearest by the last estimate give the
next.  A step is one aggregation: rows fall into fine classes of distance, each with its moments; the nearest
classes that hold H of the rows are summed.  The inverse is a Cholesky factor written out in columns, so that
no estimate passes through the driver and the number of languages and sources doesn't matter.  The vector is in fixed point, sums are exact, and reruns agree.

A cell of under LEAST rows shares one with the other small cells of its language, and this one, if small again, with
those of all languages; what is left under LEAST is not judged.  A ridge is added to each covariance, so that statistics which are
mostly constant don't reject their first deviation.

Defined results: a null or empty text has no words and fails the base rules; null lang and source are values of their own; a
null doc_id is judged as any other; repeated rows are judged each; an empty table gives an empty result; only
doc_id, text, lang and source are read.
"""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import rows_of, small, unused, words, written

SYMBOLS = "[#*$%&|<>]"
WINDOW = 8
SCALE = 1024
DIMS = 5
H = 0.75
#: Variances that are added, by statistic: log words, log mean word length, log symbols, log repeated lines, log repeated words.
RIDGE = (0.05, 0.0225, 0.5, 1.0, 1.0)
#: Concentration steps at most; they end where no determinant changes by more than a share of STILL.
STEPS, STILL = 10, 1e-3
LEAST = 50
REWEIGH, REJECT = 0.975, 1 - 1e-6


def chi2_cdf(x: float, d: int) -> float:
    """Distribution of the sum of d squared normals, by the series of the incomplete gamma function."""
    a, x = d / 2, x / 2
    if x <= 0:
        return 0.0
    term = total = 1 / a
    k = a
    while term > total * 1e-16:
        k += 1
        term *= x / k
        total += term
    return min(1.0, total * math.exp(-x + a * math.log(x) - math.lgamma(a)))


def chi2_quantile(p: float, d: int) -> float:
    low, high = 0.0, 1000.0
    for _ in range(200):
        middle = (low + high) / 2
        low, high = (middle, high) if chi2_cdf(middle, d) < p else (low, middle)
    return high


def consistency(h: float, d: int = DIMS) -> float:
    """What the covariance of the nearest share h of normal rows has to be multiplied by."""
    return h / chi2_cdf(chi2_quantile(h, d), d + 2)


def base_statistics(docs: DataFrame) -> DataFrame:
    """doc_id, lang, source, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed."""
    text = F.coalesce(F.col("text"), F.lit(""))
    a = docs.select("doc_id", "lang", "source", text.alias("text"), words("text").alias("w"))
    lines = F.filter(F.split("text", "\n"), lambda x: x.rlike("[^\\x20\\x09-\\x0D]"))
    b = a.select(
        "doc_id", "lang", "source",
        F.size("w").cast("long").alias("n_words"),
        F.length(F.array_join("w", "")).cast("long").alias("word_chars"),
        (F.length("text") - F.length(F.regexp_replace("text", SYMBOLS, ""))).cast("long").alias("n_symbols"),
        lines.alias("lines"),
        F.transform("w", lambda w: F.xxhash64(w)).alias("h"),
    )
    window = lambda i: F.xxhash64(*[F.get("h", i + k) for k in range(WINDOW)])
    c = b.select(
        "doc_id", "lang", "source", "n_words", "word_chars", "n_symbols",
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        F.when(F.col("n_words") >= WINDOW, F.transform(F.sequence(F.lit(0), F.size("h") - WINDOW), window)).otherwise(F.array().cast("array<long>")).alias("g"),
    )
    # windows that occur again: sorted by hash, they stand beside an equal one
    by_hash = F.sort_array(F.transform("g", lambda x, i: F.struct(x.alias("g"), i.alias("i"))))
    d = c.withColumn("s", F.when(F.size(F.array_distinct("g")) < F.size("g"), by_hash)).drop("g")
    again = F.filter("s", lambda x, i: F.coalesce((x["g"] == F.get("s", i - 1)["g"]), F.lit(False)) | F.coalesce((x["g"] == F.get("s", i + 1)["g"]), F.lit(False)))
    e = d.withColumn("at", F.sort_array(F.transform(again, lambda x: x["i"]))).drop("s")
    gaps = F.transform("at", lambda p, j: F.least(F.lit(WINDOW), F.coalesce(F.get("at", j + 1) - p, F.lit(WINDOW))))
    n_repeat = F.coalesce(F.aggregate(gaps, F.lit(0), lambda x, y: x + y), F.lit(0)).cast("long")
    out = e.withColumn("n_repeat_words", n_repeat).drop("at")
    return out.withColumn("base_failed", (F.col("n_words") < 20) | (F.col("n_repeat_words") * 100 > F.col("n_words") * 30))


def vector() -> list[Column]:
    """The transformed statistics in fixed point."""
    n, chars = F.greatest(F.col("n_words"), F.lit(1)), F.greatest(F.col("word_chars"), F.lit(1))
    raw = (
        F.log1p(F.col("n_words")),
        F.log(chars / n),
        F.log1p(F.col("n_symbols") * 1000 / chars),
        F.log1p(F.col("n_dup_lines") * 1000 / n),
        F.log1p(F.col("n_repeat_words") * 100 / n),
    )
    return [F.round(x * SCALE).cast("long").alias(f"x{i}") for i, x in enumerate(raw)]


X = [f"x{i}" for i in range(DIMS)]
M = [f"m{i}" for i in range(DIMS)]
PAIRS = [(i, j) for i in range(DIMS) for j in range(i + 1)]


def _sums() -> list[Column]:
    return [F.count(F.lit(1)).alias("n"), *[F.sum(x).alias(f"s{x}") for x in X], *[F.sum(F.col(X[i]) * F.col(X[j])).alias(f"p{i}{j}") for i, j in PAIRS]]


def _estimate(sums: DataFrame, keys: list[str], factor: float) -> DataFrame:
    """keys, m0 .., l00 .., logdet: mean and the Cholesky factor of factor * covariance + ridge."""
    n = F.col("n").cast("double")
    a = sums.select(*keys, *[(F.col(f"sx{i}") / n / SCALE).alias(M[i]) for i in range(DIMS)], *[(F.col(f"p{i}{j}") / n / SCALE / SCALE).alias(f"p{i}{j}") for i, j in PAIRS])
    a = a.select(*keys, *M, *[(F.greatest(F.col(f"p{i}{j}") - F.col(M[i]) * F.col(M[j]), F.lit(0.0 if i == j else -1e300)) * factor + (RIDGE[i] if i == j else 0.0)).alias(f"c{i}{j}") for i, j in PAIRS])
    for j in range(DIMS):
        known = lambda i: reduce(Column.__sub__, [F.col(f"l{i}{k}") * F.col(f"l{j}{k}") for k in range(j)], F.col(f"c{i}{j}"))  # noqa: B023,E731
        a = a.withColumn(f"l{j}{j}", F.sqrt(F.greatest(known(j), F.lit(1e-9))))
        a = a.withColumns({f"l{i}{j}": known(i) / F.col(f"l{j}{j}") for i in range(j + 1, DIMS)}) if j + 1 < DIMS else a
    logdet = reduce(Column.__add__, [F.log(F.col(f"l{i}{i}")) for i in range(DIMS)])
    return a.select(*keys, *M, *[f"l{i}{j}" for i, j in PAIRS], logdet.alias("logdet"))


def _distances(rows: DataFrame, estimates: DataFrame, keys: list[str]) -> DataFrame:
    """rows with d2, the squared Mahalanobis distance; estimates' columns go."""
    a = rows.join(small(estimates), keys)
    for i in range(DIMS):
        above = reduce(Column.__sub__, [F.col(f"l{i}{k}") * F.col(f"z{k}") for k in range(i)], F.col(X[i]) / SCALE - F.col(M[i]))
        a = a.withColumn(f"z{i}", above / F.col(f"l{i}{i}"))
    d2 = reduce(Column.__add__, [F.col(f"z{i}") * F.col(f"z{i}") for i in range(DIMS)])
    return a.withColumn("d2", d2).drop("logdet", *M, *[f"l{i}{j}" for i, j in PAIRS], *[f"z{i}" for i in range(DIMS)])


def cells(rows: DataFrame) -> DataFrame:
    """lang, source, cell, for every cell that has enough rows."""
    name = lambda c: F.coalesce(F.concat(F.lit("="), F.col(c)), F.lit("~"))
    counts = rows.groupBy("lang", "source").agg(F.count(F.lit(1)).alias("n"))
    own = F.col("n") >= LEAST
    counts = counts.withColumn("one", F.when(own, F.concat_ws("/", name("lang"), name("source"))).otherwise(name("lang")))
    counts = counts.withColumn("m", F.sum("n").over(Window.partitionBy("one"))).withColumn("cell", F.when(F.col("m") >= LEAST, F.col("one")).otherwise("*"))
    counts = counts.withColumn("m", F.sum("n").over(Window.partitionBy("cell"))).where(F.col("m") >= LEAST)
    return counts.select("lang", "source", "cell")


def determinant_estimates(rows: DataFrame, most: int | None = None) -> DataFrame:
    """cell, m0 .., l00 ..: reweighed minimum-covariance-determinant estimates of rows (cell, x0 ..); most: cells at most, if known."""
    middle = rows.groupBy("cell").agg(*[F.percentile(x, F.lit(0.5)).alias(f"q{x}") for x in X])
    middle = written(middle, "medians", most)
    spread = rows.join(small(middle), "cell").groupBy("cell").agg(*[F.first(f"q{x}").alias(f"q{x}") for x in X], *[F.percentile(F.abs(F.col(x) - F.col(f"q{x}")), F.lit(0.5)).alias(f"d{x}") for x in X])
    deviation = lambda i: F.sqrt(F.pow(F.col(f"dx{i}") * 1.4826 / SCALE, 2) + RIDGE[i])
    robust = spread.select(
        "cell", F.lit(0).alias("start"), *[(F.col(f"qx{i}") / SCALE).alias(M[i]) for i in range(DIMS)], *[(deviation(i) if i == j else F.lit(0.0)).alias(f"l{i}{j}") for i, j in PAIRS], F.lit(0.0).alias("logdet")
    )
    plain = _estimate(rows.groupBy("cell").agg(*_sums()), ["cell"], 1.0).withColumn("start", F.lit(1))
    now = written(robust.unionByName(plain), "estimates", most)
    keys = ["cell", "start"]
    both = rows.select("cell", *X, F.explode(F.array(F.lit(0), F.lit(1))).alias("start"))
    for _ in range(STEPS):
        step = F.least(F.lit(4096), F.greatest(F.lit(-2048), F.floor(F.log(F.greatest(F.col("d2"), F.lit(1e-9))) * 128))).cast("int")
        sums = _distances(both, now, keys).withColumn("step", step).groupBy(*keys, "step").agg(*_sums())
        order = Window.partitionBy(*keys)
        near = sums.withColumn("before", F.sum("n").over(order.orderBy("step")) - F.col("n")).withColumn("all", F.sum("n").over(order)).where(F.col("before") < F.col("all") * H)
        names = ["n", *[f"s{x}" for x in X], *[f"p{i}{j}" for i, j in PAIRS]]
        before = now.select(*keys, F.col("logdet").alias("was"))
        now = written(_estimate(near.groupBy(*keys).agg(*[F.sum(c).alias(c) for c in names]), keys, consistency(H)), "estimates", rows_of(now))
        if now.join(small(before, rows_of(now)), keys).where(F.abs(F.col("logdet") - F.col("was")) > STILL).isEmpty():
            break
    best = now.groupBy("cell").agg(F.min_by("start", F.struct("logdet", "start")).alias("start"))
    now = now.join(best, keys)
    inside = _distances(rows, now.drop("start"), ["cell"]).where(F.col("d2") <= chi2_quantile(REWEIGH, DIMS))
    return written(_estimate(inside.groupBy("cell").agg(*_sums()), ["cell"], consistency(REWEIGH)), "estimates", most)


def judge(docs: DataFrame) -> DataFrame:
    """doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept, distance."""
    stats = base_statistics(docs)
    stats = written(stats.select("*", *vector()), "statistics")
    passed = stats.where(~F.col("base_failed"))
    cell = written(cells(passed), "cells", rows_of(stats))
    same = lambda s: F.col("lang").eqNullSafe(F.col("l2")) & F.col("source").eqNullSafe(F.col("s2"))
    cell2 = cell.select(F.col("lang").alias("l2"), F.col("source").alias("s2"), "cell")
    rows = passed.join(small(cell2), same(0)).select("cell", *X)
    estimates = determinant_estimates(rows, rows_of(cell))
    judged = stats.join(small(cell2), same(0), "left").drop("l2", "s2")
    known = judged.where("cell is not null and not base_failed")
    far = _distances(known, estimates, ["cell"]).withColumn("kept", F.col("d2") <= chi2_quantile(REJECT, DIMS))
    rest = judged.where("cell is null or base_failed").withColumn("d2", F.lit(None).cast("double")).withColumn("kept", ~F.col("base_failed"))
    names = ["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", F.round("d2", 6).alias("distance")]
    return far.select(*names).unionByName(rest.select(*names))


def drop_rejected(docs: DataFrame) -> DataFrame:
    """docs without the rejected documents; rows of one doc_id go together."""
    (id_,) = unused(docs, "id")
    gone = judge(docs).where("not kept").select(F.col("doc_id").alias(id_)).distinct()
    return docs.join(small(written(gone, "rejected")), F.col("doc_id").eqNullSafe(F.col(id_)), "left_anti")
