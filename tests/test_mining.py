from __future__ import annotations

import itertools
import random
from fractions import Fraction

import numpy as np
import pytest
from pyspark.sql import functions as F

from copresence.model import Threshold
from copresence.operators import mining, transactions
from copresence.sources import workloads as data

from .reference import brute


@pytest.fixture(scope="module")
def village(spark):
    units, pairs = data.village(spark)
    return transactions.from_neighbours(units, pairs).persist()


def names(mask: int) -> str:
    return "".join(c for b, c in enumerate(data.VILLAGE.labels) if mask >> b & 1)


def test_worked_example_transactions(village):
    got = {r["unit_id"]: names(r["mask"]) for r in village.collect()}
    assert got == {1: "CBG", 2: "CBW", 3: "CB", 4: "CBGW", 5: "CB", 6: "CBW", 7: "CG"}


@pytest.mark.parametrize("method", list(mining.METHODS))
def test_worked_example_itemsets(village, method):
    got = {names(r["itemset"]): r["sup"] for r in mining.mine(transactions.patterns(village), Threshold.absolute(3), method).collect()}
    assert got == {"C": 7, "B": 6, "CB": 6, "G": 3, "CG": 3, "W": 3, "BW": 3, "CW": 3, "CBW": 3}


def test_thresholds_are_exact():
    assert Threshold.relative("10%").min_count(1185) == 119
    assert Threshold.relative("7%").min_count(100) == 7  # 0.07 * 100 is over 7 in floating point
    assert Threshold.relative("12.5%").min_count(80) == 10
    assert Threshold.relative("7.5%").share == Fraction(3, 40)


@pytest.mark.parametrize("seed", range(4))
def test_nodeset_search_against_enumeration(seed):
    r = random.Random(seed)
    rows = {r.getrandbits(9) & r.getrandbits(9) | 1 << r.randrange(9): r.randint(1, 9) for _ in range(60)}
    masks, weights = np.array(list(rows), np.int64), np.array(list(rows.values()), np.int64)
    for least in (1, 5, 40, 120):
        want = brute.frequent(list(rows.items()), least)
        for absorb in (True, False):
            sets, sups = mining.nodeset_search(masks, weights, least, absorb)
            assert len(sets) == len(set(sets)) and dict(zip(sets, sups, strict=True)) == want


def test_miners_agree_on_random_groups(spark):
    r = random.Random(5)
    rows = [(g, r.getrandbits(10) & r.getrandbits(10) | 1, 1 + r.randrange(4)) for g in "abc" for _ in range(80)]
    pats = spark.createDataFrame(rows, "grp string, mask long, weight long").groupBy("grp", "mask").sum("weight").withColumnRenamed("sum(weight)", "weight").persist()
    t = Threshold.relative("12.5%")
    base = mining.mine(pats, t).persist()
    for method in ("levelwise", "library", "enumerate"):
        assert mining.compare_itemsets(base, mining.mine(pats, t, method)).count() == 0
    assert mining.compare_itemsets(base, mining.mine(pats, t, shard_above=5)).count() == 0
    assert mining.monotone_violations(base).count() == 0
    many = mining.mine_many(pats, ["12.5%", "30%"])
    assert mining.compare_itemsets(many.filter("threshold = '30%'"), mining.mine(pats, Threshold.relative("30%"))).count() == 0


def test_wide_alphabet(spark):
    tx = spark.createDataFrame([("g", i, [f"item{j}" for j in range(100) if (i + j) % 50 == 0] + ["all"] * (i % 2 == 0)) for i in range(50)], "grp string, unit_id long, items array<string>")
    pats, book = mining.encode_items(tx, Threshold.relative("10%"))
    assert [r["item"] for r in book.collect()] == ["all"]
    assert {(r["mask"], r["weight"]) for r in pats.collect()} == {(0, 25), (1, 25)}


def test_any_number_of_items(spark):
    r = random.Random(21)
    rows = [(f"g{i % 2}", i, r.sample([f"t{j:03d}" for j in range(80)], r.randrange(0, 76)) + ["same", "same"]) for i in range(40)] + [("g0", 99, []), ("g1", 98, None)]
    tx = spark.createDataFrame(rows, "grp string, unit_id long, items array<string>")
    got = {(x["grp"], tuple(x["items"])): (x["sup"], x["n"]) for x in mining.mine_wide(tx, Threshold.relative("15%"), 3).collect()}
    want = {}
    for g in ("g0", "g1"):
        own = [set(items or []) for grp, _, items in rows if grp == g]
        for k in (1, 2, 3):
            for s in itertools.combinations(sorted(set().union(*own)), k):
                sup = sum(set(s) <= t for t in own)
                if sup * 100 >= 15 * len(own):
                    want[g, s] = (sup, len(own))
    assert got == want and any(len(s) == 3 for _, s in want) and len({x for _, s in want for x in s}) > 5


def test_salted_support_and_default_split(spark):
    r = random.Random(22)
    rows = [("g", r.randrange(1, 256), r.randrange(1, 9)) for _ in range(300)]
    pats = spark.createDataFrame(rows, "grp string, mask long, weight long").groupBy("grp", "mask").agg(F.sum("weight").alias("weight"))
    sets = spark.createDataFrame([("g", s) for s in (1, 3, 7, 255, 256)], "grp string, itemset long")
    want = {s: sum(w for _, m, w in rows if m & s == s) for s in (1, 3, 7, 255, 256)}
    assert {x["itemset"]: x["sup"] for x in mining.support(pats, sets, salts=5).collect()} == {s: n for s, n in want.items() if n}
    one, split = (sorted(map(tuple, mining.mine(pats, Threshold.relative("10%"), shard_above=a).collect())) for a in (10**6, 20))
    assert one == split


def test_enumeration_of_large_sets_is_bounded():
    """Forty patterns of some 24 classes have 2**24 subsets each, which don't fit beside each other."""
    import resource

    r = np.random.default_rng(5)
    mask = np.array([sum(1 << int(b) for b in r.choice(27, 24, replace=False)) for _ in range(40)] + [1 << 62], np.int64)
    weight = r.integers(1, 5, len(mask))
    least = int(weight.sum() * 0.93)
    before = resource.getrusage(resource.RUSAGE_SELF).ru_maxrss
    sets, sups = mining.enumerate_sets(mask, weight, least)
    assert resource.getrusage(resource.RUSAGE_SELF).ru_maxrss - before < 500_000
    assert dict(zip(sets.tolist(), sups.tolist(), strict=True)) == dict(zip(*mining.nodeset_search(mask, weight, least), strict=True))
    assert len(sets) and all(int(weight[(mask & s) == s].sum()) == c for s, c in zip(sets.tolist(), sups.tolist(), strict=True))


@pytest.mark.parametrize("absorb", [True, False])
def test_nodeset_search_beyond_the_tail(monkeypatch, absorb):
    """Every split between single steps and sets that are settled at once gives the same, with classes that all patterns have."""
    r = np.random.default_rng(8)
    mask = np.unique(np.array([sum(1 << int(b) for b in r.choice(15, 11, replace=False)) | 1 << 20 | 1 << 62 for _ in range(50)], np.int64))
    weight = r.integers(1, 6, len(mask))
    least = int(weight.sum() * 0.2)
    want = dict(zip(*(x.tolist() for x in mining.enumerate_sets(mask, weight, least)), strict=True))
    for tail in (0, 1, 5, 12, 20):
        monkeypatch.setattr(mining, "TAIL", tail)
        sets, sups = mining.nodeset_search(mask, weight, least, absorb)
        assert len(sets) == len(want) and dict(zip(sets.tolist(), sups.tolist(), strict=True)) == want


def test_nodeset_search_of_many_sets_takes_seconds():
    """Some four hundred thousand frequent sets in one group."""
    import time

    r = np.random.default_rng(9)
    mask = np.unique(np.array([sum(1 << int(b) for b in np.flatnonzero(r.random(20) < 0.84)) for _ in range(3000)], np.int64))
    weight = np.ones(len(mask), np.int64)
    begin = time.process_time()
    sets, sups = mining.nodeset_search(mask, weight, len(mask) // 10)
    assert time.process_time() - begin < 8
    assert len(sets) == len(np.unique(sets)) > 300_000
    for k in r.integers(0, len(sets), 50):
        assert int(((mask & sets[k]) == sets[k]).sum()) == sups[k]


def test_small_groups_are_dealt_to_tasks(spark):
    """A dozen groups of few patterns hold many sets: they aren't put together because their bytes are few."""
    r = random.Random(31)
    rows = [(f"g{i % 12}", r.getrandbits(12) | 1, 1) for i in range(600)]
    pats = spark.createDataFrame(rows, "grp string, mask long, weight long").groupBy("grp", "mask").agg(F.sum("weight").alias("weight"))
    for method in ("nodeset", "enumerate"):
        mined = mining.mine(pats, Threshold.relative("10%"), method)
        assert mined.select(F.spark_partition_id().alias("task")).distinct().count() > 4


@pytest.mark.parametrize("parts", ["nodeset_parts", "enumerate_parts"])
def test_sets_leave_in_parts(parts):
    """Two patterns of 22 and 21 classes have four million frequent sets, which are never held together."""
    import tracemalloc

    mask, weight, found, total = np.array([(1 << 22) - 1, (1 << 21) - 1], np.int64), np.array([5, 3], np.int64), 0, 0
    tracemalloc.start()
    for sets, sups in mining._gathered(getattr(mining, parts)(mask, weight, 1)):
        assert 0 < len(sets) <= mining.PART
        found, total = found + len(sets), total + int(sups.sum())
    assert tracemalloc.get_traced_memory()[1] < 20_000_000
    tracemalloc.stop()
    assert found == (1 << 22) - 1 and total == 5 * ((1 << 22) - 1) + 3 * ((1 << 21) - 1)


@pytest.mark.parametrize("absorb", [True, False])
def test_sets_with_a_given_last_class(absorb):
    r = np.random.default_rng(12)
    mask = np.unique(np.array([sum(1 << int(b) for b in r.choice(12, 7, replace=False)) for _ in range(60)], np.int64))
    weight = r.integers(1, 6, len(mask))
    want = {s: c for s, c in zip(*(x.tolist() for x in mining.enumerate_sets(mask, weight, 20)), strict=True) if s >> 5 & 1}
    sets, sups = mining._together(mining.nodeset_parts(mask, weight, 20, absorb, 5))
    assert want and len(sets) == len(want) and dict(zip(sets.tolist(), sups.tolist(), strict=True)) == want
