"""Mixing sources to target weights, with DataFrame functions only.

A document's size is its number of words. Sources in code point order (null last) get the weights in turn; the target
of each is its weight's share of all words, at most `repeat` times its own words, and what is over is shared again by
weight among the others. Within a source, documents stand in the order of a hash-random key. Whole epochs of a source
are taken while its budget lasts; the rest is cut out of that order at the exact word by prefix sums.

Prefix sums are distributed: the key's leading bits give a range; ranges are summed first (partial aggregation), their
sums are prefixed within a source, and rows are then prefixed within (source, range), so no source meets in one task.

Defined cases: null text has size 0 and takes 0; null source is a source of its own; a null doc_id is keyed as the
empty string; rows alike are told apart only by position and share the source's budget; a source without words has
target 0; an empty table gives no rows; other columns of the input are not read.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import cut, hex_number

WORD = r"[^\x20\x09-\x0D]+"
WEIGHTS = (1, 2, 3)
REPEAT = 3
RANGES = 4096  # key ranges a source at least
RANGE_ROWS = 4096  # rows a range, beyond RANGES times as many: ranges double with the rows, the result is the same
SEED = "mix-1"


def words_in(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def _sized(docs: DataFrame, seed: str, *more: Column) -> DataFrame:
    """no_source, src, size and key of each row, and more columns of it."""
    key = F.md5(F.concat(F.lit(seed + "|"), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))))
    return docs.select(
        F.col("source").isNull().alias("no_source"), F.coalesce("source", F.lit("")).alias("src"), words_in(F.col("text")).alias("size"), hex_number(key, 1, 15).alias("key"), *more,
    )


def _in_range(rows: DataFrame, wide: int) -> DataFrame:
    return rows.withColumn("range", F.floor(F.col("key") / F.lit((1 << 60) // wide)).cast("int"))


def ranges_for(rows: int) -> int:
    """A power of two of key ranges, so that no range of a source has many rows."""
    return max(RANGES, 1 << min(24, (rows // RANGE_ROWS).bit_length()))


def targets(sums: DataFrame, weights: Sequence[int] = WEIGHTS, repeat: int = REPEAT) -> DataFrame:
    """sums(no_source, src, total) -> with target double. One row a source, so one task suffices.

    Sources fill up in the order of limit / weight. With the first f of them full, the level of the rest is
    (all - limits of the full) / weights of the rest; the f sought is the least whose next source isn't over the level.
    """
    listed = W.orderBy("no_source", "src")
    w = F.element_at(F.array(*[F.lit(int(x)) for x in weights]), (F.pmod(F.row_number().over(listed) - 1, F.lit(len(weights))) + 1).cast("int")).cast("double")
    by_fill = W.orderBy("fill", "no_source", "src")
    t = sums.withColumn("w", w).withColumn("limit", F.col("total").cast("double") * repeat).withColumn("fill", F.col("limit") / F.col("w"))
    t = t.withColumn("before", F.coalesce(F.sum("limit").over(by_fill.rowsBetween(W.unboundedPreceding, -1)), F.lit(0.0)))
    t = t.withColumn("rest", F.sum("w").over(by_fill.rowsBetween(W.currentRow, W.unboundedFollowing)))
    t = t.withColumn("level", (F.sum(F.col("total").cast("double")).over(W.partitionBy()) - F.col("before")) / F.col("rest"))
    t = t.withColumn("open_level", F.min(F.when(F.col("level") <= F.col("fill"), F.struct("fill", "no_source", "src", "level"))).over(W.partitionBy())["level"])
    return t.withColumn("target", F.when(F.col("level") > F.col("fill"), F.col("limit")).otherwise(F.least("limit", F.col("w") * F.coalesce("open_level", F.lit(0.0))))).select("no_source", "src", "total", "target")


def _taken(rows: DataFrame, light: DataFrame, wide: int, order: list[str], weights: Sequence[int], repeat: int) -> DataFrame:
    """rows (as light, and more columns) with total, target, epochs and taken. The rows meet once, by (source, range)."""
    ranges = cut(_in_range(light, wide).groupBy("no_source", "src", "range").agg(F.sum("size").alias("words")))
    plan = targets(ranges.groupBy("no_source", "src").agg(F.sum("words").alias("total")), weights, repeat)
    up_to = W.partitionBy("no_source", "src").orderBy("range").rowsBetween(W.unboundedPreceding, -1)
    starts = ranges.withColumn("start", F.coalesce(F.sum("words").over(up_to), F.lit(0))).drop("words").join(plan, ["no_source", "src"])
    within = W.partitionBy("no_source", "src", "range").orderBy(*order).rowsBetween(W.unboundedPreceding, W.currentRow)
    budget = F.floor("target").cast("long")
    out = _in_range(rows, wide).join(starts, ["no_source", "src", "range"]).withColumn("before", F.col("start") + F.sum("size").over(within) - F.col("size"))
    out = out.withColumn("epochs", F.when(F.col("total") > 0, F.expr("CAST(floor(target) AS BIGINT) DIV total")).otherwise(F.lit(0)).cast("long"))
    part = F.greatest(F.lit(0), F.least(F.col("size"), budget - F.col("epochs") * F.col("total") - F.col("before")))
    return out.withColumn("taken", (F.col("epochs") * F.col("size") + part).cast("long"))


def mix(docs: DataFrame, weights: Sequence[int] = WEIGHTS, repeat: int = REPEAT, seed: str = SEED) -> DataFrame:
    """docs(doc_id, text, source) -> one row per document: doc_id, source, size, source_size, target, epochs, taken."""
    rows = cut(_sized(docs, seed, F.col("doc_id")))
    out = _taken(rows, rows, ranges_for(rows.count()), ["key", "doc_id", "size"], weights, repeat)
    return out.select("doc_id", F.when(F.col("no_source"), None).otherwise(F.col("src")).alias("source"), "size", F.col("total").alias("source_size"), "target", "epochs", "taken")


def mixed_documents(docs: DataFrame, weights: Sequence[int] = WEIGHTS, repeat: int = REPEAT, seed: str = SEED) -> DataFrame:
    """The mix as documents: a row for each epoch that a document is in; where the budget ends inside a document, its
    leading words up to there. Documents without words have no part in a mix. Repeated rows, and texts of one id, source
    and size (in the order of their digests), have each its own part: whole rows go through the prefix sums, and no join
    by id follows. Columns are those of docs."""
    light = cut(_sized(docs, seed))
    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row")
    rows = _sized(docs, seed, F.md5("text").alias("digest"), row)
    taken = _taken(rows, light, ranges_for(light.count()), ["key", "row.doc_id", "size", "digest"], weights, repeat).filter("taken > 0")
    rows = taken.select(*[F.col("row").getField(c).alias(c) for c in docs.columns], F.col("size").alias("__size"), F.col("taken").alias("__taken"))
    rows = rows.withColumn("__full", F.expr("__taken DIV __size")).withColumn("__left", F.expr("__taken % __size"))
    rows = rows.withColumn("__copy", F.explode(F.sequence(F.lit(1), (F.col("__full") + F.when(F.col("__left") > 0, 1).otherwise(0)).cast("int"))))
    part = F.regexp_extract("text", r"^[\x20\x09-\x0D]*+", 0)
    cut_text = F.concat(part, F.array_join(F.slice(F.regexp_extract_all("text", F.lit(r"[^\x20\x09-\x0D]++[\x20\x09-\x0D]*+"), F.lit(0)), F.lit(1), F.col("__left").cast("int")), ""))
    short = F.col("__copy") > F.col("__full")
    rows = rows.withColumn("__text", F.when(short, cut_text).otherwise(F.col("text")))
    out = {"text": F.col("__text"), "n_chars": F.when(short, F.length("__text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars")) if "n_chars" in docs.columns else None}
    return rows.select(*[(out[c] if out.get(c) is not None else F.col(f"`{c}`")).alias(c) for c in docs.columns])
