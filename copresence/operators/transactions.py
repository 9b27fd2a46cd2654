"""From neighbours to transactions to patterns, and what is known of them.

Union of classes is idempotent, commutative and associative, so pairs are folded by bit_or in the map tasks and are never
stored. A pattern row (group, mask, weight) is the exact, mergeable summary that all miners work from.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from copresence.functions.masks import bit_mask, fold, size
from copresence.model import Classes, missing_units, unit_blocks
from copresence.plans.shared import cut

from . import neighborhoods as near

HASHED = 300_000  # places that a task holds to look units up, where they needn't be sorted


def from_neighbours(units: DataFrame, pairs: DataFrame) -> DataFrame:
    """units(grp, unit_id, bit), pairs(grp, unit_id, other_bit), taken as given (they need not be symmetric)."""
    own = units.select("grp", "unit_id", F.col("bit").alias("b"))
    return own.unionByName(pairs.select("grp", "unit_id", F.col("other_bit").alias("b"))).groupBy("grp", "unit_id").agg(fold(bit_mask("b")).alias("mask"))


def neighbour_columns(units: DataFrame, pairs: DataFrame) -> DataFrame:
    """The steps of the worked example: all neighbours, without repeats, final set (class numbers, ascending). For small data."""
    listed = pairs.groupBy("grp", "unit_id").agg(F.array_sort(F.collect_list("other_bit")).alias("every"))
    j = units.join(listed, ["grp", "unit_id"], "left").withColumn("every", F.coalesce("every", F.array().cast("array<int>")))
    return j.select("grp", "unit_id", "bit", "every", F.array_distinct("every").alias("single"), F.array_sort(F.array_union(F.array("bit"), "every")).alias("final"))


def _fold_pairs(pairs: DataFrame) -> DataFrame:
    """A focal unit is its own neighbour at 0, so it always has a row and its own class."""
    return pairs.groupBy("grp", F.col("focal_id").alias("unit_id")).agg(fold(bit_mask("other_bit")).alias("mask"))


def buffer_span(units: DataFrame, d: int) -> DataFrame:
    return _fold_pairs(near.span_pairs(units, d))


def buffer_instant(units: DataFrame, d: int) -> DataFrame:
    """Instants (lo = hi): a range frame instead of a join; one sort, no pairs."""
    frame = W.partitionBy("grp", "part").orderBy("lo").rangeBetween(-d, d)
    return units.select("grp", "unit_id", fold(bit_mask("bit")).over(frame).alias("mask"))


def buffer_rect(units: DataFrame, d: int, same_group: bool = True, salts: int = 1) -> DataFrame:
    return _fold_pairs(near.rect_pairs(units, d, same_group=same_group, salts=salts))


def buffer_rect_by_places(units: DataFrame, d: int) -> DataFrame:
    """buffer_rect for data with many equal rectangles: those of a group are one place, joined once with all classes found there."""
    box = ["grp", "x0", "x1", "y0", "y1"]
    places = units.groupBy(*box).agg(fold(bit_mask("bit")).alias("bit"))
    places = cut(places.select(*box, "bit", F.monotonically_increasing_id().alias("unit_id")))
    met = near.rect_pairs(places, d).groupBy("focal_id").agg(fold("other_bit").alias("mask"))
    known = places.join(met, F.col("unit_id") == F.col("focal_id")).select(*box, "mask")
    return units.select("unit_id", *box).join(known, box).groupBy("grp", "unit_id").agg(fold("mask").alias("mask"))


def buffer_ring(units: DataFrame, d: float, side: float | None = None) -> DataFrame:
    """units(grp, unit_id, bit, rings), or with the text of the rings, wkt, in their place.

    What a unit meets follows from its place: equal rings of a group are one place, tested once, with all classes found
    there. A unit without rings meets itself only."""
    shape = "wkt" if "wkt" in units.columns else "rings"
    rings = near.parse_rings("wkt") if shape == "wkt" else F.col("rings")
    own = units.select("grp", "unit_id", "bit", shape)
    places = own.groupBy("grp", shape).agg(fold(bit_mask("bit")).alias("classes"))
    places = cut(places.select("grp", F.monotonically_increasing_id().alias("place"), shape, "classes"))
    met = near.ring_masks(places.select("grp", "place", "classes", rings.alias("rings")), d, side)
    # a place with rings meets itself at least, so rings are looked at again only where nothing was met
    mask = F.when(F.col("mask").isNotNull(), F.col("mask")).when(F.coalesce(F.size(rings), F.lit(0)) <= 0, F.lit(0).cast("long"))
    known = places.select("grp", shape, "place").join(met, "place", "left").select("grp", F.col(shape).alias("s"), mask.alias("met")).filter("met IS NOT NULL")
    by_digest = shape == "wkt" and digests_differ(places)
    if by_digest:
        own = own.select("grp", "unit_id", "bit", F.xxhash64("wkt").alias(shape))
        known = known.withColumn("s", F.xxhash64("s"))
        if places.count() <= HASHED * int(own.sparkSession.conf.get("spark.sql.shuffle.partitions")):
            known = known.hint("shuffle_hash")
    both = own.join(known.withColumnRenamed("grp", "g"), F.col("grp").eqNullSafe(F.col("g")) & F.col(shape).eqNullSafe(F.col("s")))
    return both.groupBy("grp", "unit_id").agg(fold(F.col("met").bitwiseOR(bit_mask("bit"))).alias("mask"))


def digests_differ(places: DataFrame) -> bool:
    """Whether no two texts of a group have the same digest. Every unit's text is a place's, so digests then join as texts do."""
    return not places.groupBy("grp", F.xxhash64("wkt").alias("digest")).count().filter("count > 1").limit(1).count()


def buffer_metric(units: DataFrame, eps: float) -> DataFrame:
    return _fold_pairs(near.metric_pairs(units, eps))


def buffer_rect_by_tiles(units: DataFrame, d: int, cell: int | None = None, dense_above: int = 5000) -> DataFrame:
    """buffer_rect for data with dense areas. Focal units whose buffer meets no tile of over `dense_above` units are
    joined plainly. For the others classes are first folded by small cell; cells wholly within reach give their folded
    mask at once, and units in the other cells are tested only for classes that the focal unit has not met yet.

    A unit is listed in every cell that its box covers; a cell lies wholly within reach if its farthest corner does, and
    any unit listed there then meets the buffer. The small-cell side costs about (4d / cell)**2 rows a focal unit, which
    pays only where a tile holds many more units than that."""
    side = max(2 * d, 64)
    on = lambda grow: units.withColumn("tx", near._tiles(F.col("x0") - grow, F.col("x1") + grow, side)).withColumn("ty", near._tiles(F.col("y0") - grow, F.col("y1") + grow, side))
    dense = cut(on(0).groupBy("grp", "tx", "ty").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > dense_above).drop("n"))
    if not dense.limit(1).count():
        return buffer_rect(units, d)
    among = cut(on(d).join(dense, ["grp", "tx", "ty"], "left_semi").select("unit_id").distinct())
    plain = _fold_pairs(near.rect_pairs(units, d, side, focal=units.join(among, "unit_id", "left_anti")))
    return plain.unionByName(_buffer_by_cells(units, units.join(among, "unit_id", "left_semi"), d, cell or max(1, d // 3)))


def _buffer_by_cells(units: DataFrame, focal: DataFrame, d: int, cell: int) -> DataFrame:
    listed = units.withColumn("cx", near._tiles(F.col("x0"), F.col("x1"), cell)).withColumn("cy", near._tiles(F.col("y0"), F.col("y1"), cell))
    cells = listed.groupBy("grp", "cx", "cy").agg(fold(bit_mask("bit")).alias("all"))
    a = focal.select("grp", "unit_id", F.col("bit").alias("own"), "x0", "x1", "y0", "y1")
    a = a.withColumn("cx", near._tiles(F.col("x0") - d, F.col("x1") + d, cell)).withColumn("cy", near._tiles(F.col("y0") - d, F.col("y1") + d, cell))
    far = lambda c, lo, hi: F.greatest(F.lit(0), F.col(lo) - F.col(c) * cell, (F.col(c) + 1) * cell - 1 - F.col(hi))
    near_ = lambda c, lo, hi: F.greatest(F.lit(0), F.col(lo) - ((F.col(c) + 1) * cell - 1), F.col(c) * cell - F.col(hi))
    sq = lambda f: f("cx", "x0", "x1") * f("cx", "x0", "x1") + f("cy", "y0", "y1") * f("cy", "y0", "y1")
    met = a.filter(sq(near_) <= d * d).join(cells, ["grp", "cx", "cy"]).withColumn("inner", sq(far) <= d * d)
    seed = cut(met.groupBy("grp", "unit_id").agg(fold(F.when(F.col("inner"), F.col("all")).otherwise(bit_mask("own"))).alias("known")))
    rim = met.filter(~F.col("inner")).join(seed, ["grp", "unit_id"]).filter(F.expr("all & ~known") != 0).select("grp", "unit_id", "cx", "cy", "x0", "x1", "y0", "y1", "known")
    b = listed.select("grp", "cx", "cy", F.col("x0").alias("bx0"), F.col("x1").alias("bx1"), F.col("y0").alias("by0"), F.col("y1").alias("by1"), bit_mask("bit").alias("class"))
    gap = lambda p, q: F.greatest(F.lit(0), F.col(f"b{p}") - F.col(q), F.col(p) - F.col(f"b{q}"))
    hit = rim.join(b, ["grp", "cx", "cy"]).filter((F.expr("class & ~known") != 0) & (gap("x0", "x1") * gap("x0", "x1") + gap("y0", "y1") * gap("y0", "y1") <= d * d))
    return seed.withColumnRenamed("known", "mask").unionByName(hit.select("grp", "unit_id", F.col("class").alias("mask"))).groupBy("grp", "unit_id").agg(fold("mask").alias("mask"))


def patterns(tx: DataFrame) -> DataFrame:
    return tx.groupBy("grp", "mask").agg(F.count(F.lit(1)).alias("weight"))


def one_per_unit(units: DataFrame, tx: DataFrame) -> DataFrame:
    """units, transactions, units without a transaction: the first two equal and the third 0, whatever the distance."""
    given, made = unit_blocks(units), unit_blocks(tx)
    missing = missing_units(units, given, tx, made)
    total = lambda blocks, name: blocks.agg(F.coalesce(F.sum("rows"), F.lit(0)).alias(name))
    return total(given, "units").crossJoin(total(made, "transactions")).select("*", F.lit(missing).cast("long").alias("missing"))


def lengths(per: DataFrame, distances: list[int]) -> DataFrame:
    """per(d<distance> mask, ...), a row a focal unit -> count, mean, median and greatest length for each distance; null
    masks aren't transactions."""
    each = F.explode(F.array(*[F.struct(F.lit(d).cast("long").alias("d"), F.bit_count(f"d{d}").cast("long").alias("len")) for d in distances])).alias("r")
    long = per.select(each).select("r.d", "r.len").filter("len IS NOT NULL")
    return long.groupBy("d").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("len"), 6).alias("mean_len"), F.percentile("len", F.lit(0.5)).alias("median_len"), F.max("len").alias("max_len"))


def calibration(pairs: DataFrame, distances: list[int], dist: str = "dist", squared: bool = False) -> DataFrame:
    """`lengths` from one join at the greatest distance."""
    folds = [fold(F.when(F.col(dist) <= (d * d if squared else d), bit_mask("other_bit"))).alias(f"d{d}") for d in distances]
    return lengths(pairs.groupBy("grp", "focal_id").agg(*folds), distances)


def calibration_instant(units: DataFrame, distances: list[int], scale: int = 1) -> DataFrame:
    """`lengths` for instants from one sort; distances times scale are in the units of lo."""
    frame = lambda d: W.partitionBy("grp", "part").orderBy("lo").rangeBetween(-d * scale, d * scale)
    return lengths(units.select(*[fold(bit_mask("bit")).over(frame(d)).alias(f"d{d}") for d in distances]), distances)


def set_bag_audit(pairs: DataFrame) -> DataFrame:
    """Per group: transactions, neighbours (without the unit itself), classes in all sets, members of the same class that
    the sets collapsed, and transactions in which any was."""
    per = pairs.groupBy("grp", "focal_id").agg(F.count(F.lit(1)).alias("m"), F.bit_count(fold(bit_mask("other_bit"))).cast("long").alias("c"))
    return per.groupBy("grp").agg(F.count(F.lit(1)).alias("transactions"), F.sum(F.col("m") - 1).alias("neighbours"), F.sum("c").alias("classes"), F.sum(F.col("m") - F.col("c")).alias("collapsed"), F.count_if(F.col("m") > F.col("c")).alias("affected"))


def size_histogram(tx: DataFrame) -> DataFrame:
    return tx.groupBy(size("mask").cast("long").alias("len")).agg(F.count(F.lit(1)).alias("n"))


def recurrence(pats: DataFrame) -> DataFrame:
    """Per group: transactions, distinct patterns, repeats, classes observed. The last row (grp null) is for all groups."""
    per = pats.groupBy("grp").agg(F.sum("weight").alias("transactions"), F.count(F.lit(1)).alias("patterns"), fold("mask").alias("seen"))
    every = per.agg(F.lit(None).cast("string").alias("grp"), F.sum("transactions").alias("transactions"), F.sum("patterns").alias("patterns"), fold("seen").alias("seen"))
    return per.unionByName(every).select("grp", "transactions", "patterns", (F.col("transactions") - F.col("patterns")).alias("repeats"), F.bit_count("seen").cast("long").alias("classes"))


def dichotomous(tx: DataFrame, classes: Classes, keep: tuple[str, ...] = ("grp", "unit_id")) -> DataFrame:
    """A 0/1 column for each class; projections of the mask, no pivot."""
    return tx.select(*keep, *[F.bit_get("mask", F.lit(b)).cast("int").alias(f"c{c}") for b, c in enumerate(classes.codes)])


def undo_dichotomous(wide: DataFrame, classes: Classes) -> DataFrame:
    """Wide 0/1 rows back to (grp, unit_id, code) rows."""
    columns = [f"c{c}" for c in classes.codes]
    return wide.unpivot(["grp", "unit_id"], columns, "code", "present").filter("present = 1").select("grp", "unit_id", F.substring("code", 2, 5).cast("int").alias("code"))


def transaction_text(tx: DataFrame, classes: Classes, sep: str = " ") -> DataFrame:
    """One line per transaction, codes ascending, no unit id."""
    return tx.select("grp", F.array_join(F.transform(classes.items("mask"), lambda c: c.cast("string")), sep).alias("line"))


def select_groups(tx: DataFrame, low: int, high: int) -> DataFrame:
    """Transactions of the groups whose number of transactions is between low and high."""
    chosen = tx.groupBy("grp").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n").between(low, high)).select("grp")
    return tx.join(chosen, "grp", "left_semi")


def clip_units(units: DataFrame, extents: DataFrame) -> DataFrame:
    """RECT units that meet their group's extent(grp, ex0, ex1, ey0, ey1)."""
    j = units.join(extents, "grp")
    return j.filter("x1 >= ex0 AND x0 <= ex1 AND y1 >= ey0 AND y0 <= ey1").select(*units.columns)
