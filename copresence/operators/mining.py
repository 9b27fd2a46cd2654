"""All frequent itemsets of every group at an exact minimum support: four miners that must agree, and their comparison.

All start from PATTERNS(grp, mask, weight). Classes that aren't frequent by themselves are dropped from the masks and
equal masks are merged again, which is exact for what is frequent (n stays the number of transactions). Supports are
whole numbers and thresholds are tested by whole numbers.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from copresence.functions import masks
from copresence.model import Threshold
from copresence.plans.shared import bounded, cut
from copresence.ship import arrow_parts

TAIL = 16  # classes whose subsets are settled at once
PART = 1 << 16  # sets that a task holds before they leave it
MOST_TASKS = 256
SHARD_ABOVE = 200_000  # patterns of a group that one task mines
MOST_GROUPS = 500  # runs of the library's tree
MOST_SETS = 1 << 20  # distinct sets that are sent to every task
FOUND_OF = "grp string, itemset long, sup long, n long"


def totals(patterns: DataFrame) -> DataFrame:
    """Transactions of each group."""
    return patterns.groupBy("grp").agg(F.sum("weight").alias("n"))


def singles(patterns: DataFrame, n_bits: int = masks.MAX_BITS) -> DataFrame:
    """grp, bit, sup of each class: one pass, partial sums."""
    each = patterns.select("grp", "weight", F.explode(masks.bits("mask")).alias("bit"))
    return each.groupBy("grp", "bit").agg(F.sum("weight").alias("sup"))


def prefilter(patterns: DataFrame, threshold: Threshold) -> DataFrame:
    """grp, n, mask (frequent classes only), weight; groups without any frequent class go."""
    n = totals(patterns)
    keep = singles(patterns).join(n, "grp").filter(threshold.passes()).groupBy("grp", "n").agg(masks.fold(masks.bit_mask("bit")).alias("keep"))
    cut = patterns.join(keep, "grp").select("grp", "n", F.expr("mask & keep").alias("mask"), "weight").filter("mask <> 0")
    return cut.groupBy("grp", "n", "mask").agg(F.sum("weight").alias("weight"))


def _finish(found: DataFrame, n: DataFrame | None, threshold: Threshold) -> DataFrame:
    """n: transactions of each group, if found has none."""
    out = (found if n is None else found.join(n, "grp")).filter(threshold.passes())
    return out.select("grp", "itemset", F.bit_count("itemset").cast("int").alias("k"), "sup", "n", (F.col("sup") / F.col("n")).alias("rel"))


# ---- negative node sets


Sets = tuple[np.ndarray, np.ndarray]  # itemsets and their supports


def nodeset_parts(mask: np.ndarray, weight: np.ndarray, least: int, absorb: bool = True, last: int | None = None) -> Iterator[Sets]:
    """Frequent itemsets of one group, part by part, so that they are never held together.

    Classes are ordered by falling support, which makes the patterns a prefix tree whose nodes are known by their path:
    the nodes of class y are the distinct paths down to y. Extending {y} by an earlier class x loses the y-nodes whose
    path lacks x; extending further by z loses those that have x but lack z. So a prefix carries a shrinking list of
    nodes, supports fall by its sum, and each step is one bit test over an array.

    The lost nodes of all extensions are one array, a bit an extension; below a prefix with at most TAIL of them all
    supports come from that array at once.

    absorb: an extension that loses nothing is added to every set below the prefix instead of being searched.
    last: only sets with this class."""
    bits = [b for b in range(masks.MAX_BITS) if (mask >> b & 1).any()]
    support = {b: int(weight[(mask >> b & 1) == 1].sum()) for b in bits}
    order = sorted((b for b in bits if support[b] >= least), key=lambda b: (b == last, -support[b], b))

    def grow(prefix: int, sup: int, free: list[int], ext: list[int], lost: np.ndarray, count: np.ndarray) -> Iterator[Sets]:
        # ext: classes that may be added, all of them frequent; lost: which of them (by place in ext) each path lacks
        sums = [int(count[(lost >> k & 1) == 1].sum()) for k in range(len(ext))]
        searched = [k for k, s in enumerate(sums) if s or not absorb]
        own_free = [*free, *(ext[k] for k in range(len(ext)) if absorb and not sums[k])]
        if len(searched) <= TAIL:
            yield from _with_any_of(*_tail(prefix, sup, [ext[k] for k in searched], _moved(lost, searched), count, least), own_free)
            return
        yield from _with_any_of(np.array([prefix], np.int64), np.array([sup], np.int64), own_free)
        for at, k in enumerate(searched):
            has = (lost >> k & 1) == 0
            left, later = sup - sums[k], searched[at + 1 :]
            path, number = lost[has], count[has]
            below = [k2 for k2 in later if left - int(number[(path >> k2 & 1) == 1].sum()) >= least]
            path = _moved(path, below)
            yield from grow(prefix | 1 << ext[k], left, own_free, [ext[k2] for k2 in below], path[path != 0], number[path != 0])

    for rank, y in enumerate(order):
        if last is not None and y != last:
            continue
        earlier = order[:rank]
        has = (mask >> y & 1) == 1
        own, number = mask[has], weight[has]
        ext = [x for x in reversed(earlier) if int(number[(own >> x & 1) == 1].sum()) >= least]
        lost, at = np.unique(_moved(~own, ext), return_inverse=True)
        count = np.bincount(at, number, len(lost)).astype(np.int64)
        yield from grow(1 << y, support[y], [], ext, lost[lost != 0], count[lost != 0])


def _together(parts: Iterator[Sets]) -> Sets:
    every = [(np.zeros(0, np.int64), np.zeros(0, np.int64)), *parts]
    return np.concatenate([x for x, _ in every]), np.concatenate([x for _, x in every])


def nodeset_search(mask: np.ndarray, weight: np.ndarray, least: int, absorb: bool = True) -> Sets:
    """All that `nodeset_parts` finds."""
    return _together(nodeset_parts(mask, weight, least, absorb))


def _with_any_of(sets: np.ndarray, sups: np.ndarray, free: list[int]) -> Iterator[Sets]:
    """The sets with every subset of the free classes, about PART of them at a time."""
    free = list(free)
    while free and len(sets) < PART:
        sets, sups = np.concatenate([sets, sets | 1 << free.pop()]), np.concatenate([sups, sups])
    rest = sum(1 << b for b in free)
    more = 0
    while True:
        yield sets | more, sups
        more = more - rest & rest  # the next subset
        if not more:
            return


def _moved(sets: np.ndarray, places: list[int]) -> np.ndarray:
    """Sets with the bits at `places` moved to 0, 1, ... and the others left out."""
    out = np.zeros(len(sets), np.int64)
    for k, p in enumerate(places):
        out |= (sets >> p & 1) << k
    return out


def _tail(prefix: int, sup: int, ext: list[int], lost: np.ndarray, count: np.ndarray, least: int) -> tuple[np.ndarray, np.ndarray]:
    """The prefix with every subset of a few classes: what a subset loses are the paths that lack any of its classes, so
    counts by what a path lacks are summed over all subsets of what the set leaves out."""
    every = (1 << len(ext)) - 1
    kept = np.bincount(lost, count, every + 1).astype(np.int64)
    for k in range(len(ext)):
        halves = kept.reshape(-1, 2, 1 << k)
        halves[:, 1] += halves[:, 0]
    sups = sup - int(count.sum()) + kept[::-1]  # the set s leaves out every - s
    sets = np.full(1, prefix, np.int64)
    for b in ext:
        sets = np.concatenate([sets, sets | 1 << b])
    frequent = sups >= least
    return sets[frequent], sups[frequent]


def mine_groups(patterns: DataFrame, keys: list[str], search: Callable[[np.ndarray, np.ndarray, int, int], Iterator[Sets]], tasks: int) -> DataFrame:
    """patterns(grp, n, mask, weight), dealt by `keys` to so many tasks, whatever their bytes: a few patterns may hold
    millions of sets -> grp, itemset, sup, n. search(mask, weight, n, y) gives the sets in parts, which leave as they come;
    y is the group's class where that is among the keys."""
    y_at = patterns.columns.index("y") if "y" in keys else None

    def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(list(batches))
        mask, weight = (table.column(c).to_numpy() for c in ("mask", "weight"))
        grp, n, y = table.column("grp")[0], table.column("n")[0], None if y_at is None else table.column(y_at)[0].as_py()
        del table
        for sets, sups in _gathered(search(mask, weight, n.as_py(), y)):
            yield pa.RecordBatch.from_arrays([pa.repeat(grp, len(sets)), pa.array(sets), pa.array(sups), pa.repeat(n, len(sets))], names=["grp", "itemset", "sup", "n"])

    dealt = patterns.repartition(max(1, min(tasks, MOST_TASKS)), *keys)
    return arrow_parts(dealt, keys, run, FOUND_OF)


def _gathered(parts: Iterator[Sets]) -> Iterator[Sets]:
    """Small parts together, large ones cut: PART sets at most."""
    held: list[Sets] = []
    many = 0
    for sets, sups in parts:
        if many + len(sets) > PART and held:
            yield _together(held)
            held, many = [], 0
        for k in range(0, len(sets), PART):
            held.append((sets[k : k + PART], sups[k : k + PART]))
            many += len(held[-1][0])
            if many >= PART:
                yield _together(held)
                held, many = [], 0
    if many:
        yield _together(held)


def mine_nodeset(patterns: DataFrame, threshold: Threshold, absorb: bool = True, shard_above: int = SHARD_ABOVE) -> DataFrame:
    """The negative-nodeset miner, a group to an Arrow task.

    shard_above: groups with more distinct patterns are split by the last class of a set in the group's order: the
    task for class y only gets the patterns with y, cut to y and what comes before it, so that one group's work is dealt
    over as many tasks as it has classes."""
    kept = cut(prefilter(patterns, threshold))
    most, groups = kept.groupBy("grp").count().agg(F.max("count"), F.count(F.lit(1))).first()
    if (most or 0) > shard_above:
        return _mine_sharded(kept, threshold, absorb, shard_above)

    def search(mask: np.ndarray, weight: np.ndarray, n: int, _: int | None) -> Iterator[Sets]:
        return nodeset_parts(mask, weight, threshold.min_count(n), absorb)

    return _finish(mine_groups(kept, ["grp"], search, 2 * groups), None, threshold)


def _mine_sharded(kept: DataFrame, threshold: Threshold, absorb: bool, shard_above: int) -> DataFrame:
    size = kept.groupBy("grp").agg(F.count(F.lit(1)).alias("patterns"))
    rank = W.partitionBy("grp").orderBy(F.desc("sup"), "bit").rowsBetween(W.unboundedPreceding, W.currentRow)
    order = singles(kept.select("grp", "mask", "weight")).withColumn("upto", F.bit_or(masks.bit_mask("bit")).over(rank)).select("grp", "bit", "upto")
    parts = kept.join(size, "grp")
    small = parts.filter(F.col("patterns") <= shard_above).select("grp", F.lit(-1).alias("y"), "n", "mask", "weight")
    large = parts.filter(F.col("patterns") > shard_above).join(order, "grp").filter(F.expr("bit_get(mask, bit) = 1"))
    large = large.groupBy("grp", F.col("bit").alias("y"), "n", F.expr("mask & upto").alias("mask")).agg(F.sum("weight").alias("weight"))

    def search(mask: np.ndarray, weight: np.ndarray, n: int, y: int) -> Iterator[Sets]:
        return nodeset_parts(mask, weight, threshold.min_count(n), absorb, y if y >= 0 else None)

    return _finish(mine_groups(small.unionByName(large.select("grp", "y", "n", "mask", "weight")), ["grp", "y"], search, MOST_TASKS), None, threshold)


# ---- level by level, joins only


def mine_levelwise(patterns: DataFrame, threshold: Threshold, max_levels: int = masks.MAX_BITS) -> DataFrame:
    """All groups at once, one level a round: join sets that share all but their highest class, drop candidates with an
    infrequent subset, count the rest. Levels are written to the shared folder, so plans don't grow."""
    kept = cut(prefilter(patterns, threshold))
    n = cut(totals(patterns))
    level = singles(kept.select("grp", "mask", "weight")).join(n, "grp").filter(threshold.passes()).select("grp", masks.bit_mask("bit").alias("itemset"), "sup")
    level = cut(level)
    levels = [level]
    for k in range(2, max_levels + 1):
        top = level.withColumn("high", F.expr("shiftleft(1L, CAST(length(bin(itemset)) - 1 AS INT))"))
        top = top.withColumn("rest", F.expr("itemset ^ high"))
        a, b = top.select("grp", "rest", F.col("itemset").alias("s"), F.col("high").alias("h")), top.select("grp", "rest", F.col("high").alias("h2"))
        cand = a.join(b, ["grp", "rest"]).filter("h2 > h").select("grp", F.expr("s | h2").alias("itemset"))
        if k > 2:
            subs = cand.select("grp", "itemset", F.explode(F.transform(masks.bits("itemset"), lambda x: F.col("itemset").bitwiseXOR(F.call_function("shiftleft", F.lit(1).cast("long"), x)))).alias("sub"))
            lacking = subs.join(level.select("grp", F.col("itemset").alias("sub")), ["grp", "sub"], "left_anti").select("grp", "itemset").distinct()
            cand = cand.join(lacking, ["grp", "itemset"], "left_anti")
        level = cut(support(kept, cand).join(n, "grp").filter(threshold.passes()).select("grp", "itemset", "sup"))
        if not level.limit(1).count():
            break
        levels.append(level)
    return _finish(reduce(DataFrame.unionByName, levels), n, threshold)


def support(patterns: DataFrame, itemsets: DataFrame, salts: int = 8) -> DataFrame:
    """Support of given sets(grp, itemset); sets that no transaction holds have none and no row.

    A group's patterns are dealt over `salts` keys, and its sets go to each of them; sums are combined in the tasks."""
    p = patterns.select("grp", "mask", "weight", F.pmod(F.xxhash64("mask"), F.lit(salts)).cast("int").alias("salt"))
    sets = itemsets.select("grp", "itemset", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("salt"))
    return p.join(sets, ["grp", "salt"]).filter(masks.contains("mask", "itemset")).groupBy("grp", "itemset").agg(F.sum("weight").alias("sup"))


def exact_support(patterns: DataFrame, itemsets: DataFrame) -> DataFrame:
    """Support of every distinct set in every group, zeros included: what the zeros of a profile hide."""
    n = totals(patterns)
    every = n.select("grp").crossJoin(bounded(itemsets.select("itemset").distinct(), MOST_SETS, "distinct sets"))
    found = support(patterns, every)
    return every.join(found, ["grp", "itemset"], "left").join(n, "grp").select("grp", "itemset", F.coalesce("sup", F.lit(0)).alias("sup"), "n")


# ---- the library's tree, and plain enumeration


def mine_library(patterns: DataFrame, threshold: Threshold) -> DataFrame:
    """The FP-tree of the machine learning library, a run for each group (for tens of groups), counted again exactly.

    Its minimum support is a double: half a transaction below the least count can't be mistaken for another count."""
    from pyspark.ml.fpm import FPGrowth

    n = totals(patterns)
    runs = []
    groups = [(r["grp"], r["n"]) for r in n.limit(MOST_GROUPS + 1).collect()]
    if len(groups) > MOST_GROUPS:
        raise ValueError(f"the library's tree is for {MOST_GROUPS} groups at most")
    for grp, count in groups:
        own = patterns.filter(F.col("grp") == grp)
        each = own.select(masks.bits("mask").alias("items"), F.explode(F.sequence(F.lit(1).cast("long"), "weight")).alias("copy")).select("items")
        found = FPGrowth(itemsCol="items", minSupport=(threshold.min_count(count) - 0.5) / count).fit(each).freqItemsets
        mask = F.aggregate("items", F.lit(0).cast("long"), lambda a, b: a.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("long"), b)))
        runs.append(found.select(F.lit(grp).alias("grp"), mask.alias("itemset"), F.col("freq").alias("sup")))
    return _finish(reduce(DataFrame.unionByName, runs), n, threshold)


def submasks(mask: int) -> np.ndarray:
    """All non-empty subsets of a set."""
    out = np.zeros(1, np.int64)
    while mask:
        low = mask & -mask
        out = np.concatenate([out, out | low])
        mask ^= low
    return out[1:]


DENSE = 16  # classes whose subsets are counted at once, in an array


def enumerate_parts(mask: np.ndarray, weight: np.ndarray, least: int) -> Iterator[Sets]:
    """Frequent itemsets of one group by counting every subset of its classes: for each choice among the higher classes that is
    frequent, one array over all subsets of the lowest DENSE ones, summed over supersets class by class. Memory is that
    array and the group's patterns."""
    bits = [b for b in range(masks.MAX_BITS) if (mask >> b & 1).any()]
    low, high = bits[:DENSE], bits[DENSE:]
    place = np.zeros(len(mask), np.int64)
    for j, b in enumerate(low):
        place |= (mask >> b & 1) << j
    subset = np.zeros(1, np.int64)
    for b in low:
        subset = np.concatenate([subset, subset | 1 << b])

    def walk(rows: np.ndarray, k: int, chosen: int) -> Iterator[Sets]:
        if int(weight[rows].sum()) < least:
            return
        if k < len(high):
            yield from walk(rows, k + 1, chosen)
            yield from walk(rows[(mask[rows] >> high[k] & 1) == 1], k + 1, chosen | 1 << high[k])
            return
        sums = np.zeros(1 << len(low), np.int64)
        np.add.at(sums, place[rows], weight[rows])
        for j in range(len(low)):
            halves = sums.reshape(-1, 2, 1 << j)
            halves[:, 0] += halves[:, 1]
        found = np.flatnonzero(sums >= least)
        if not chosen:
            found = found[found != 0]
        yield subset[found] | chosen, sums[found]

    yield from walk(np.arange(len(mask)), 0, 0)


def enumerate_sets(mask: np.ndarray, weight: np.ndarray, least: int) -> Sets:
    """All that `enumerate_parts` finds."""
    return _together(enumerate_parts(mask, weight, least))


def mine_enumerate(patterns: DataFrame, threshold: Threshold) -> DataFrame:
    """Every subset of a group's frequent classes is counted, a group to an Arrow task."""
    kept = cut(prefilter(patterns, threshold))

    def search(mask: np.ndarray, weight: np.ndarray, n: int, _: int | None) -> Iterator[Sets]:
        return enumerate_parts(mask, weight, max(1, threshold.min_count(n)))

    return _finish(mine_groups(kept, ["grp"], search, 2 * kept.select("grp").distinct().count()), None, threshold)


METHODS = {"nodeset": mine_nodeset, "levelwise": mine_levelwise, "library": mine_library, "enumerate": mine_enumerate}


def mine(patterns: DataFrame, threshold: Threshold, method: str = "nodeset", **how) -> DataFrame:
    return METHODS[method](patterns, threshold, **how)


# ---- on itemsets


def mine_many(patterns: DataFrame, shares: list[str], method: str = "nodeset") -> DataFrame:
    """Itemsets at several thresholds from one mining at the least: filtered upwards, exactly. Adds threshold (text)."""
    limits = [Threshold.relative(s) for s in shares]
    low = mine(patterns, min(limits, key=lambda t: t.share), method)
    each = low.withColumn("threshold", F.explode(F.array(*[F.when(t.passes(), F.lit(t.label)) for t in limits])))
    return each.filter("threshold IS NOT NULL")


def unique_votes(patterns: DataFrame) -> DataFrame:
    """One vote for each distinct pattern of a group."""
    return patterns.withColumn("weight", F.lit(1).cast("long"))


def compare_itemsets(a: DataFrame, b: DataFrame) -> DataFrame:
    """Rows in which two minings differ: a set that only one has, or another support."""
    x, y = a.select("grp", "itemset", F.col("sup").alias("sup_a")), b.select("grp", "itemset", F.col("sup").alias("sup_b"))
    return x.join(y, ["grp", "itemset"], "full_outer").filter(~F.col("sup_a").eqNullSafe(F.col("sup_b")))


def monotone_violations(itemsets: DataFrame) -> DataFrame:
    """Sets that lack a frequent subset with one class less, or have more support than it: there must be none."""
    bit = F.explode(masks.bits("itemset")).alias("b")
    subs = itemsets.filter("k > 1").select("grp", "itemset", "sup", bit).select("grp", "itemset", "sup", F.expr("itemset ^ shiftleft(1L, b)").alias("sub"))
    j = subs.join(itemsets.select("grp", F.col("itemset").alias("sub"), F.col("sup").alias("sub_sup")), ["grp", "sub"], "left")
    return j.filter("sub_sup IS NULL OR sub_sup < sup").select("grp", "itemset", "sub", "sup", "sub_sup")


def top_itemsets(itemsets: DataFrame, min_k: int = 2, hide: int = 0, n: int = 11) -> DataFrame:
    """Per group the n sets of highest support with at least min_k classes, for display; sets with a hidden class are
    left out here and nowhere else."""
    shown = itemsets.filter((F.col("k") >= min_k) & (F.col("itemset").bitwiseAND(F.lit(hide)) == 0))
    rank = F.row_number().over(W.partitionBy("grp").orderBy(F.desc("sup"), "itemset"))
    return shown.withColumn("rank", rank).filter(F.col("rank") <= n)


def union_features(itemsets: DataFrame) -> DataFrame:
    return itemsets.select("itemset").distinct()


def common_features(itemsets: DataFrame) -> DataFrame:
    """Sets that are frequent in every group."""
    groups = itemsets.select("grp").distinct().agg(F.count(F.lit(1)).alias("g"))  # one row
    return itemsets.groupBy("itemset").agg(F.count(F.lit(1)).alias("c")).join(F.broadcast(groups)).filter("c = g").select("itemset")


# ---- alphabets over 63 classes


def encode_items(tx: DataFrame, threshold: Threshold) -> tuple[DataFrame, DataFrame]:
    """tx(grp, unit_id, items array<string>) -> PATTERNS and dictionary(grp, bit, item).

    Each group numbers its own frequent items; all transactions count in n, those without a frequent item as mask 0.
    A group with more than 63 frequent items is refused: `mine_wide` takes any number."""
    n = tx.groupBy("grp").agg(F.count(F.lit(1)).alias("n"))
    each = tx.select("grp", "unit_id", F.explode(F.array_distinct("items")).alias("item"))
    freq = each.groupBy("grp", "item").agg(F.count(F.lit(1)).alias("sup")).join(n, "grp").filter(threshold.passes())
    book = freq.withColumn("bit", F.row_number().over(W.partitionBy("grp").orderBy("item")) - 1).select("grp", "bit", "item")
    book = book.withColumn("bit", F.when(F.col("bit") < masks.MAX_BITS, F.col("bit")).otherwise(F.raise_error(F.lit("a group has more than 63 frequent items")).cast("int")))
    hit = each.join(book, ["grp", "item"]).groupBy("grp", "unit_id").agg(masks.fold(masks.bit_mask("bit")).alias("mask"))
    tx_masks = tx.select("grp", "unit_id").join(hit, ["grp", "unit_id"], "left").select("grp", F.coalesce("mask", F.lit(0).cast("long")).alias("mask"))
    return tx_masks.groupBy("grp", "mask").agg(F.count(F.lit(1)).alias("weight")), book


def mine_wide(tx: DataFrame, threshold: Threshold, max_items: int) -> DataFrame:
    """tx(grp, unit_id, items array<string>) -> grp, items (sorted array), k, sup, n, rel for any number of items: the
    frequent sets of up to `max_items` items, level by level.

    A unit's sets of k items grow from its frequent sets of k - 1 by its greater frequent items, so nothing is counted
    that holds an infrequent set; levels are written to the shared folder."""
    n = cut(tx.groupBy("grp").agg(F.count(F.lit(1)).alias("n")))
    each = tx.select("grp", "unit_id", F.explode(F.array_distinct("items")).alias("item")).filter("item IS NOT NULL")

    def frequent(rows: DataFrame) -> DataFrame:
        return cut(rows.groupBy("grp", "items").agg(F.count(F.lit(1)).alias("sup")).join(n, "grp").filter(threshold.passes()))

    held = each.select("grp", "unit_id", F.array("item").alias("items"))
    levels = [frequent(held)]
    single = cut(each.join(levels[0].select("grp", F.get("items", F.lit(0)).alias("item")), ["grp", "item"]))
    for _ in range(1, max_items):
        held = cut(held.join(levels[-1].select("grp", "items"), ["grp", "items"], "left_semi"))
        held = held.join(single, ["grp", "unit_id"]).filter(F.col("item") > F.element_at("items", -1)).select("grp", "unit_id", F.concat("items", F.array("item")).alias("items"))
        levels.append(frequent(held))
    out = reduce(DataFrame.unionByName, levels)
    return out.select("grp", "items", F.size("items").alias("k"), "sup", "n", (F.col("sup") / F.col("n")).alias("rel"))


def level_sizes(itemsets: DataFrame) -> DataFrame:
    """Frequent sets and their supports by number of classes: what the levels of a mining cost."""
    return itemsets.groupBy(F.col("k").cast("long").alias("k")).agg(F.count(F.lit(1)).alias("sets"), F.sum("sup").alias("total"))
