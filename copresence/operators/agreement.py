"""Agreement of two partitions or two sets of distances."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from copresence.plans.shared import cut, running_total


def _cells(a: DataFrame, b: DataFrame, by: list[str]) -> DataFrame:
    """a(by..., grp, u), b([by...], grp, v) -> counts of (u, v)."""
    on = ["grp", *[c for c in by if c in b.columns]]
    return a.join(b, on).groupBy(*by, "u", "v").agg(F.count(F.lit(1)).cast("double").alias("c"))


def _pairs_of(x: Column) -> Column:
    return x * (x - 1) / 2


def ari(a: DataFrame, b: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Chance-corrected share of pairs on which two partitions agree; 1 where the chance term is all there is.

    a(grp, u), b(grp, v); by: columns of a that name several partitions at once."""
    by = list(by)
    cells = _cells(a, b, by)
    side = lambda c: cells.groupBy(*by, c).agg(F.sum("c").alias("c")).groupBy(*by).agg(F.sum(_pairs_of(F.col("c"))).alias(f"p{c}"), F.sum("c").alias(f"n{c}"))
    both = cells.groupBy(*by).agg(F.sum(_pairs_of(F.col("c"))).alias("p"))
    j = _on(_on(both, side("u"), by), side("v"), by)
    expected = F.col("pu") * F.col("pv") / _pairs_of(F.col("nu"))
    top, low = (F.col("pu") + F.col("pv")) / 2, F.when(F.col("nu") > 1, expected).otherwise(F.lit(0.0))
    return j.select(*by, F.when(top == low, F.lit(1.0)).otherwise((F.col("p") - low) / (top - low)).alias("ari"))


def _on(x: DataFrame, y: DataFrame, by: list[str]) -> DataFrame:
    return x.join(y, by) if by else x.crossJoin(y)


def nmi(a: DataFrame, b: DataFrame, by: tuple[str, ...] = (), mean: str = "arithmetic") -> DataFrame:
    """Mutual information over the mean of the two entropies; 1 where both partitions are one cluster."""
    by = list(by)
    cells = _cells(a, b, by)
    u, v = (cells.groupBy(*by, c).agg(F.sum("c").alias(f"c{c}")) for c in "uv")
    n = cells.groupBy(*by).agg(F.sum("c").alias("n"))
    j = _on(cells.join(u, [*by, "u"]).join(v, [*by, "v"]), n, by)
    mi = j.groupBy(*by).agg(F.sum(F.col("c") / F.col("n") * F.log(F.col("c") * F.col("n") / (F.col("cu") * F.col("cv")))).alias("mi"))
    h = lambda t, c: _on(t, n, by).groupBy(*by).agg(F.sum(-F.col(f"c{c}") / F.col("n") * F.log(F.col(f"c{c}") / F.col("n"))).alias(f"h{c}"))
    j = _on(_on(mi, h(u, "u"), by), h(v, "v"), by)
    hu, hv = F.col("hu"), F.col("hv")
    norm = {"arithmetic": (hu + hv) / 2, "min": F.least(hu, hv), "max": F.greatest(hu, hv), "geometric": F.sqrt(hu * hv)}[mean]
    return j.select(*by, F.when(norm <= 1e-15, F.when((hu <= 1e-15) & (hv <= 1e-15), 1.0).otherwise(0.0)).otherwise(F.col("mi") / norm).alias("nmi"))


def average_rank(order: str, by: tuple[str, ...]) -> Column:
    """Rank with ties averaged, within each of `by`."""
    return F.rank().over(W.partitionBy(*by).orderBy(order)) + (F.count(F.lit(1)).over(W.partitionBy(*by, order)) - 1) / 2


def average_ranks(values: DataFrame, order: str, name: str) -> DataFrame:
    """values(order, ...) with its rank over all rows, ties averaged: distinct values are counted, their counts are
    prefixed over ranges of values, and the ranks go back to the rows."""
    counts = values.groupBy(order).agg(F.count(F.lit(1)).alias("__n"))
    ranks = running_total(counts, order, "__n", "__before").select(order, (F.col("__before") + (F.col("__n") + 1) / 2).alias(name))
    return values.join(ranks, order)


def distance_spearman(x: DataFrame, y: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Rank correlation of two sets of pair distances; distances are rounded to 10 places so that ties are ties.

    x([by...], a, b, d), y(a, b, d)."""
    j = x.select(*by, "a", "b", F.round("d", 10).alias("dx")).join(y.select("a", "b", F.round("d", 10).alias("dy")), ["a", "b"])
    if by:
        j = j.withColumn("rx", average_rank("dx", by)).withColumn("ry", average_rank("dy", by))
    else:
        j = average_ranks(average_ranks(cut(j), "dx", "rx"), "dy", "ry")
    return j.groupBy(*by).agg(F.corr("rx", "ry").alias("spearman"))
