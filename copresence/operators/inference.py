"""Non-artificial content of transactions and exploratory tests over clusters.

The measures and the cluster labels come from the same transactions, so the tests describe and don't confirm."""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from copresence.model import Classes

from .agreement import average_rank

MEASURES = ("mean_other", "share_any", "share_only")


def content(patterns: DataFrame, classes: Classes) -> DataFrame:
    """grp, mean number of non-artificial classes a transaction, share with any, share with nothing else."""
    other = F.col("mask").bitwiseAND(F.lit(classes.other))
    w = F.col("weight")
    share = lambda test: F.sum(F.when(test, w).otherwise(0)) / F.sum(w)
    return patterns.groupBy("grp").agg((F.sum(F.bit_count(other) * w) / F.sum(w)).alias("mean_other"), share(other != 0).alias("share_any"), share((other != 0) & (other == F.col("mask"))).alias("share_only"))


def long_measures(measures: DataFrame) -> DataFrame:
    return measures.unpivot(["grp"], list(MEASURES), "measure", "value")


def medians(measures: DataFrame, labelled: DataFrame, value: str = "share_any") -> DataFrame:
    return measures.join(labelled, "grp").groupBy("cluster").agg(F.percentile(value, F.lit(0.5)).alias("median"))


def kruskal(values: DataFrame) -> DataFrame:
    """values(measure, grp, value, cluster) -> measure, h (corrected for ties), df. Values are tied at 10 places."""
    v = values.withColumn("v", F.round("value", 10)).withColumn("r", average_rank("v", ("measure",)))
    n = v.groupBy("measure").agg(F.count(F.lit(1)).cast("double").alias("n"), F.count_distinct("cluster").alias("c"))
    per = v.groupBy("measure", "cluster").agg(F.sum("r").alias("s"), F.count(F.lit(1)).alias("m")).groupBy("measure").agg(F.sum(F.col("s") * F.col("s") / F.col("m")).alias("q"))
    ties = v.groupBy("measure", "v").agg(F.count(F.lit(1)).cast("double").alias("t")).groupBy("measure").agg(F.sum(F.col("t") * F.col("t") * F.col("t") - F.col("t")).alias("ties"))
    j = n.join(per, "measure").join(ties, "measure")
    size = F.col("n")
    raw = 12 / (size * (size + 1)) * F.col("q") - 3 * (size + 1)
    even = 1 - F.col("ties") / (size * size * size - size)
    return j.select("measure", F.when(even > 0, raw / even).otherwise(F.lit(0.0)).alias("h"), (F.col("c") - 1).cast("long").alias("df"))


def gamma_tail(a: float, x: float) -> float:
    """Upper regularised incomplete gamma function: a series below a + 1, a continued fraction above."""
    if x <= 0:
        return 1.0
    front = math.exp(-x + a * math.log(x) - math.lgamma(a))
    if x < a + 1:
        term = total = 1 / a
        k = a
        while abs(term) > abs(total) * 1e-16:
            k += 1
            term *= x / k
            total += term
        return max(0.0, 1 - total * front)
    tiny = 1e-300
    b = x + 1 - a
    c, d = 1 / tiny, 1 / b
    h = d
    for i in range(1, 10_000):
        an = -i * (i - a)
        b += 2
        d = an * d + b
        d = 1 / (d if abs(d) > tiny else tiny)
        c = b + an / c
        c = c if abs(c) > tiny else tiny
        h *= d * c
        if abs(d * c - 1) < 1e-15:
            break
    return front * h


def chi2_tail(x: float, df: int) -> float:
    return gamma_tail(df / 2, x / 2)


def chi2_p(stat: str | Column = "h", df: str | Column = "df") -> Column:
    @F.pandas_udf("double")
    def tail(x: pd.Series, n: pd.Series) -> pd.Series:
        return pd.Series([chi2_tail(float(a), int(b)) for a, b in zip(x, n, strict=True)])

    return tail(stat, df)


def holm(tests: DataFrame, p: str = "p", by: tuple[str, ...] = ()) -> DataFrame:
    """Step-down adjustment within one family: running greatest of (family - rank + 1) * p, at most 1."""
    family = W.partitionBy(*(by or (F.lit(0),)))
    place = F.row_number().over(family.orderBy(p, *[c for c in ("measure",) if c in tests.columns]))
    t = tests.withColumn("__i", place).withColumn("__m", F.count(F.lit(1)).over(family))
    t = t.withColumn("__s", F.least(F.lit(1.0), (F.col("__m") - F.col("__i") + 1) * F.col(p)))
    return t.withColumn("adjusted", F.max("__s").over(family.orderBy("__i").rowsBetween(W.unboundedPreceding, W.currentRow))).drop("__i", "__m", "__s")


def eta_squared(values: DataFrame) -> DataFrame:
    """measure, share of the values' variation that lies between clusters."""
    mean = values.groupBy("measure").agg(F.avg("value").alias("m"))
    per = values.groupBy("measure", "cluster").agg(F.avg("value").alias("c"), F.count(F.lit(1)).alias("n"))
    between = per.join(mean, "measure").groupBy("measure").agg(F.sum(F.col("n") * (F.col("c") - F.col("m")) * (F.col("c") - F.col("m"))).alias("b"))
    total = values.join(mean, "measure").groupBy("measure").agg(F.sum((F.col("value") - F.col("m")) * (F.col("value") - F.col("m"))).alias("t"))
    return between.join(total, "measure").select("measure", F.when(F.col("t") > 0, F.col("b") / F.col("t")).otherwise(F.lit(0.0)).alias("eta2"))


def cramers_v(pairs: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """pairs([by...], u, v) -> V."""
    by = list(by)
    cells = pairs.groupBy(*by, "u", "v").agg(F.count(F.lit(1)).cast("double").alias("c"))
    rows, cols = cells.groupBy(*by, "u").agg(F.sum("c").alias("r")), cells.groupBy(*by, "v").agg(F.sum("c").alias("q"))
    n = cells.groupBy(*by).agg(F.sum("c").alias("n"), F.count_distinct("u").alias("nu"), F.count_distinct("v").alias("nv"))
    j = cells.join(rows, [*by, "u"]).join(cols, [*by, "v"])
    # chi2 / n = sum of c^2 / (r q) - 1; cells of 0 add nothing
    s = j.groupBy(*by).agg(F.sum(F.col("c") * F.col("c") / (F.col("r") * F.col("q"))).alias("s"))
    both = s.join(n, by) if by else s.crossJoin(n)
    least = F.least("nu", "nv") - 1
    return both.select(*by, F.when(least > 0, F.sqrt(F.greatest(F.lit(0.0), F.col("s") - 1) / least)).otherwise(F.lit(0.0)).alias("v"))


def cramers_v_permutation(pairs: DataFrame, reps: int = 5000, seed: int = 0) -> DataFrame:
    """pairs(grp, u, v) -> v, p: v is dealt anew over the groups in each repetition, in digest order, and
    p = (1 + repetitions that reach the V at hand) / (1 + repetitions)."""
    spark = pairs.sparkSession
    place = pairs.select("u", "v", F.row_number().over(W.partitionBy(F.lit(0)).orderBy("grp")).alias("i"), "grp")
    each = place.crossJoin(spark.range(reps).select(F.col("id").cast("int").alias("rep")))
    key = F.md5(F.concat_ws("|", F.lit(str(seed)), F.col("rep").cast("string"), F.col("grp")))
    dealt = each.withColumn("j", F.row_number().over(W.partitionBy("rep").orderBy(key, "grp")))
    new = dealt.select("rep", "i", "u").join(dealt.select("rep", F.col("j").alias("i"), "v"), ["rep", "i"])
    seen = cramers_v(pairs).select(F.round("v", 10).alias("seen"))
    runs = cramers_v(new, ("rep",)).crossJoin(F.broadcast(seen))
    return runs.groupBy("seen").agg(((1 + F.sum(F.when(F.round("v", 10) >= F.col("seen"), 1).otherwise(0))) / F.lit(reps + 1)).alias("p")).select(F.col("seen").alias("v"), "p")
