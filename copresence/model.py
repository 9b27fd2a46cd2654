"""Data contracts: column names and types of what operators take and give, class dictionaries, checks.

A transaction is the set of distinct classes of a focal unit and of the units its buffer meets. It forgets how many
neighbours share a class, areas, shapes, contacts, distances and order; it keeps one row for each focal unit.
"""

from __future__ import annotations

from dataclasses import dataclass
from fractions import Fraction

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from copresence.functions import masks
from copresence.plans.shared import cut

SPAN = "grp string, part long, unit_id long, lo long, hi long, bit int"
RECT = "grp string, unit_id long, x0 long, x1 long, y0 long, y1 long, bit int"
RING = "grp string, unit_id long, ring array<struct<x:double,y:double>>, bit int"
VEC = "grp string, unit_id long, vec array<float>, bit int"
TX = "grp string, unit_id long, mask long"
PATTERNS = "grp string, mask long, weight long"
ITEMSETS = "grp string, itemset long, k int, sup long, n long, rel double"
PROFILE = "grp string, feature long, value double"
DIST = "a string, b string, d double"
MERGES = "step int, left int, right int, left_leaf int, right_leaf int, height double, size int"
LABELS = "k int, grp string, cluster int"
LAYOUT = "run int, grp string, x double, y double"


@dataclass(frozen=True)
class Classes:
    """A class dictionary: bit b has theme themes[b] and code theme*10000 + (b+10)*100; bits are stored in code order
    only within a theme, so codes are looked up by bit."""

    themes: tuple[int, ...]
    labels: tuple[str, ...] = ()

    @property
    def codes(self) -> list[int]:
        return [t * 10000 + (b + 10) * 100 for b, t in enumerate(self.themes)]

    def theme_mask(self, *themes: int) -> int:
        return masks.mask_of([b for b, t in enumerate(self.themes) if t in themes])

    @property
    def artificial(self) -> int:
        return self.theme_mask(1)

    @property
    def other(self) -> int:
        return self.theme_mask(2, 3, 4, 5)

    def frame(self, spark: SparkSession) -> DataFrame:
        """bit, code, label, theme: at most 63 rows."""
        rows = [(b, c, self.labels[b] if self.labels else f"class {c}", t) for b, (c, t) in enumerate(zip(self.codes, self.themes, strict=True))]
        return spark.createDataFrame(rows, "bit int, code int, label string, theme int")

    def code(self, bit: str | Column) -> Column:
        return F.get(F.array(*[F.lit(c) for c in self.codes]), F.col(bit) if isinstance(bit, str) else bit)

    def items(self, mask: str | Column) -> Column:
        """Ascending codes of a mask."""
        return F.sort_array(F.transform(masks.bits(mask), lambda b: self.code(b)))

    def key(self, mask: str | Column) -> Column:
        return F.array_join(F.transform(self.items(mask), lambda c: c.cast("string")), "|")


def coarser(code: str | Column, level: int) -> Column:
    """A five-digit class code cut to its first `level` digits, filled with zeros."""
    step = 10 ** (5 - level)
    c = F.col(code) if isinstance(code, str) else code
    return (F.floor(c / step) * step).cast("int")


def remap_units(units: DataFrame, classes: Classes, level: int) -> tuple[DataFrame, Classes]:
    """Units with the classes of a coarser level, and the dictionary of these: to be done before transactions are built,
    since a set of coarse classes doesn't follow from frequent sets of fine ones."""
    step = 10 ** (5 - level)
    coarse = sorted({c // step * step for c in classes.codes})
    new = [coarse.index(c // step * step) for c in classes.codes]
    themes = tuple(c // 10000 for c in coarse)
    return units.withColumn("bit", F.get(F.array(*[F.lit(b) for b in new]), F.col("bit"))), Classes(themes, tuple(str(c) for c in coarse))


@dataclass(frozen=True)
class Threshold:
    """A minimum support as an exact share of the transactions, or as an absolute count."""

    share: Fraction | None = None
    count: int | None = None

    @staticmethod
    def relative(text: str | float | Fraction) -> Threshold:
        if isinstance(text, str) and text.endswith("%"):
            return Threshold(share=Fraction(text[:-1].strip()) / 100)
        return Threshold(share=Fraction(str(text)))

    @staticmethod
    def absolute(count: int) -> Threshold:
        return Threshold(count=count)

    def min_count(self, n: int) -> int:
        """Least support that is frequent among n transactions; never by floating point."""
        if self.count is not None:
            return self.count
        return -(-self.share.numerator * n // self.share.denominator)

    def passes(self, sup: str = "sup", n: str = "n") -> Column:
        if self.count is not None:
            return F.col(sup) >= self.count
        return F.col(sup) * F.lit(self.share.denominator) >= F.col(n) * F.lit(self.share.numerator)

    @property
    def label(self) -> str:
        return f"n>={self.count}" if self.count is not None else f"{float(self.share * 100):g}%"


def validate_units(units: DataFrame, classes: Classes) -> DataFrame:
    """problem, n for each kind of problem: unknown classes, null groups, ids that stand for several units."""
    unknown = units.filter(F.col("bit").isNull() | ~F.col("bit").between(0, len(classes.themes) - 1)).agg(F.lit("unknown class").alias("problem"), F.count(F.lit(1)).alias("n"))
    nowhere = units.filter("grp IS NULL").agg(F.lit("no group").alias("problem"), F.count(F.lit(1)).alias("n"))
    twice = units.groupBy("unit_id").agg(F.count(F.lit(1)).alias("c")).filter("c > 1").agg(F.lit("repeated unit").alias("problem"), F.count(F.lit(1)).alias("n"))
    return unknown.unionByName(nowhere).unionByName(twice)


BLOCK = 5  # unit ids are counted by blocks of two to this power


def unit_blocks(rows: DataFrame, *more: Column) -> DataFrame:
    """rows(unit_id, ...) -> a row a block of ids: block, rows, ids (a bit each), and further aggregates. Written to the shared
    folder. In a block with as many rows as bits every id has one row; the others have to be looked at row by row."""
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), F.col("unit_id").bitwiseAND(F.lit((1 << BLOCK) - 1)).cast("int"))
    return cut(rows.groupBy(F.shiftright("unit_id", BLOCK).alias("block")).agg(F.count(F.lit(1)).alias("rows"), F.bit_or(bit).alias("ids"), *more))


_UNIQUE = "`rows` <=> CAST(bit_count(ids) AS BIGINT)"


def _looked_at(rows: DataFrame, blocks: DataFrame) -> DataFrame | None:
    """Ids of the rows in blocks where some id is null or has several rows, if there are any."""
    unsure = blocks.filter(f"NOT ({_UNIQUE})").select(F.col("block").alias("unsure"))
    if not unsure.limit(1).count():
        return None
    return rows.select("unit_id").join(unsure, F.shiftright("unit_id", BLOCK).eqNullSafe(F.col("unsure")), "left_semi")


def repeated_units(rows: DataFrame, blocks: DataFrame) -> int:
    """Ids with several rows."""
    unsure = _looked_at(rows, blocks)
    return 0 if unsure is None else unsure.groupBy("unit_id").count().filter("count > 1").count()


def missing_units(units: DataFrame, blocks: DataFrame, tx: DataFrame, tx_blocks: DataFrame) -> int:
    """Rows of units whose id no transaction has."""
    held = tx_blocks.select("block", F.col("ids").alias("held"))
    lacking = F.bit_count(F.expr("ids & ~coalesce(held, 0L)"))
    found = blocks.filter(_UNIQUE).join(held, "block", "left").agg(F.sum(lacking)).first()[0] or 0
    unsure = _looked_at(units, blocks)
    return found if unsure is None else found + unsure.join(tx.select("unit_id"), "unit_id", "left_anti").count()


def validate_transactions(tx: DataFrame, units: DataFrame, classes: Classes) -> DataFrame:
    """problem, n: empty sets, classes outside the dictionary, units without or with several transactions."""
    known = (1 << len(classes.themes)) - 1
    unknown = F.col("mask").bitwiseAND(F.lit(~known & ((1 << 63) - 1))) != 0
    made, given = unit_blocks(tx, F.count_if(F.col("mask") == 0).alias("empty"), F.count_if(unknown).alias("unknown")), unit_blocks(units)
    sums = made.agg(F.coalesce(F.sum("empty"), F.lit(0)).alias("empty"), F.coalesce(F.sum("unknown"), F.lit(0)).alias("unknown"))
    several, missing = repeated_units(tx, made), missing_units(units, given, tx, made)
    counts = {"empty": F.col("empty"), "unknown class": F.col("unknown"), "several transactions": F.lit(several).cast("long"), "no transaction": F.lit(missing).cast("long")}
    return sums.select(F.explode(F.array(*[F.struct(F.lit(k).alias("problem"), n.alias("n")) for k, n in counts.items()])).alias("r")).select("r.problem", "r.n")
