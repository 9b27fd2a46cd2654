"""Near-duplicate documents by weighted minimum hashing with darts.

A document is a weighted set: its five-word shingles with their multiplicities (`signature` takes any weights). Each
element owns a region of weight by rank; hashing throws darts into that region at rate one, the same darts wherever the
region is. Each dart names one of K coordinates, and a coordinate keeps its dart of least rank: two documents agree in
a coordinate with probability equal to their weighted Jaccard similarity. Ranks go as far as about K ln K darts of the
whole document, and further until every coordinate has one, so the work grows with the number of elements and the
logarithm of their weights.

Steps. (1) One scan gives each document a content digest, its bands and a bit sketch of its signature; no text is
moved. (2) Equal texts are one node. (3) Each band bucket has a centre, its member that meets most others in all its
buckets; every member is compared with it exactly. Those that aren't alike to it are compared with a second centre among
them and with their kin: the member that has a change against the centre in common with them and fewest changes in all.
(4) Around a centre whose members still lie in several components, members at least half like the centre are known by
their changes against it (shingles that came or went), and the similarity of any two follows exactly from the changes
they share; this is worked in blocks of bounded size, those apart from the centre against all, and one link a component
is kept. Members less than half like the centre are paired by bucket, sketch, length and the triangle inequality of the
distance, then compared exactly. Only the sketch could drop a true pair, with a margin of over five standard deviations
(`slack` None: no pair is dropped by it).
(5) Components of the links are the classes. No step makes a row for each pair of a group.

Defined cases: null and empty texts (no words) are copies of each other if their bytes are the same and have no other
links; null counts as empty; repeated rows are copies; null ids are documents of the same table and join by digest;
texts under five words are one shingle; a class is numbered by its least id that stands for one text only, or, without
such an id, by a negative number from a digest, so that no two classes share a number; ties of the least id go to the
smaller digest; extra columns are kept by `keep_one` and not read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from copresence.ship import arrow_map, pandas_groups

from .common import components, cut, whole
from .words import MIX1, STEP, hash_texts, mix, shingles, text_hashes

SIMILARITY = 0.8
HALF = 0.5  # from this similarity to a centre on, changes against the centre are listed
MEMBERS = 256  # about so many members of a centre are worked at once
BANDS, ROWS = 28, 5
K = BANDS * ROWS
SKETCH_WORDS = (K + 63) // 64
SKETCH_SLACK = 32  # differing bits: texts 0.8 alike have 14 of 140 (deviation 3.5)
FRACTION = 40  # bits of a rank below 1
_PIECES = mix(np.arange(64, dtype=np.uint64))
#: Darts in a cell, by the leading 16 bits of its number: Poisson with mean 1.
_DARTS = np.searchsorted(np.cumsum([math.exp(-1) / math.factorial(i) for i in range(12)]), (np.arange(1 << 16) + 0.5) / (1 << 16)).astype(np.int8)


def _darts(elements: np.ndarray, weights: np.ndarray, low: int, high: int) -> np.ndarray:
    """Darts in the elements' regions between two ranks (in units of 2**-FRACTION), each as a number: coordinate in the
    leading 8 bits, rank in the others.

    The weight axis is cut at 0, 1, 2, 4, 8 and so on. A cell is as wide as its piece of that axis and as high as makes
    its area 1, so one dart is expected in each, and a heavy element takes one row of cells a piece and not one a unit.
    Darts beyond the element's weight or the ranks asked for don't count."""
    out, piece, top = [], 0, float(weights.max())
    while piece == 0 or 2.0 ** (piece - 1) < top:
        shift = max(piece - 1, 0)
        base, width = (2.0**shift if piece else 0.0), float(1 << shift)
        held = np.flatnonzero(weights > base)
        cells = np.arange((low << shift) >> FRACTION, -(-(high << shift) >> FRACTION), dtype=np.uint64)
        seed = mix((mix(elements[held] ^ _PIECES[piece])[:, None] + (cells + np.uint64(1)) * STEP).ravel())
        count = _DARTS[seed >> np.uint64(48)]
        thrown = np.flatnonzero(count)
        again = count[thrown]
        cell = np.repeat(thrown, again)
        turn = np.ones(len(cell), np.uint64)
        for k in range(2, int(again.max(initial=0)) + 1):  # the k-th dart of a cell follows its (k-1)-th
            turn[1:][(cell[1:] == cell[:-1]) & (turn[:-1] == k - 1)] = k
        dart = mix(seed[cell] + turn * STEP)
        rank = (cells[cell % len(cells)] << np.uint64(FRACTION - shift)) + (dart >> np.uint64(64 - FRACTION + shift))
        counts = (rank >= np.uint64(low)) & (rank < np.uint64(high))
        if float(weights[held].min()) < base + width:
            counts &= base + width * ((mix(dart) >> np.uint64(11)).astype(np.float64) / (1 << 53)) < weights[held][cell // len(cells)]
        at = ((dart[counts] * MIX1) >> np.uint64(32)) * np.uint64(K) >> np.uint64(32)
        out.append(at << np.uint64(56) | rank[counts])
        piece += 1
    return np.concatenate(out)


def signature(elements: np.ndarray, weights: np.ndarray | None = None) -> np.ndarray:
    """K coordinates (uint64) of distinct element numbers with their weights (above 0), or of a multiset of elements."""
    if weights is None:
        elements, weights = np.unique(elements, return_counts=True)
    weights = np.asarray(weights, np.float64)
    if not len(weights) or weights.min() <= 0 or not 1 / 16 <= weights.sum() < 2.0**40:
        raise ValueError("weights must be above 0 and have a sum from 1/16 to 2**40")
    out, filled, low = np.zeros(K, np.uint64), np.zeros(K, bool), 0
    high = math.ceil(K * (math.log(K) + 1) / weights.sum() * (1 << FRACTION))
    more = max(1, high // 3)
    while not filled.all():  # a dart of an earlier round has the lesser rank
        dart = np.sort(_darts(elements, weights, low, high))
        at = (dart >> np.uint64(56)).astype(np.int64)
        first = np.flatnonzero(np.diff(at, prepend=-1))
        new = first[~filled[at[first]]]
        out[at[new]] = dart[new]
        filled[at[new]] = True
        low, high = high, high + more
    return out


def bands_of(sig: np.ndarray) -> np.ndarray:
    """A number for each band of ROWS coordinates; the band's place is part of it."""
    out = np.arange(BANDS, dtype=np.uint64) * STEP
    for r in range(ROWS):
        out = mix(out + sig.reshape(BANDS, ROWS)[:, r])
    return out.view(np.int64)


def sketch_of(sig: np.ndarray) -> np.ndarray:
    """A bit of each coordinate, packed."""
    bits = np.zeros(64 * SKETCH_WORDS, np.uint8)
    bits[:K] = (sig >> np.uint64(17)) & np.uint64(1)
    return np.packbits(bits).view(np.int64)


def _hashes(texts: pa.Array, at_once: int = 500) -> Iterator[np.ndarray]:
    """Word numbers of each text."""
    for k in range(0, len(texts), at_once):
        flat, counts = hash_texts(texts.slice(k, at_once).to_pylist())
        yield from np.split(flat, np.cumsum(counts)[:-1])


SIGNED = "doc_id long, digest string, weight long, bands array<long>, sketch array<long>"


def signed(docs: DataFrame) -> DataFrame:
    """doc_id, content digest, number of shingles, bands and sketch (both empty for texts without words)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            weight, bands, sketch = [], [], []
            for h in _hashes(b.column(2)):
                s = shingles(h)
                weight.append(len(s))
                sig = signature(s) if len(s) else None
                bands.append([] if sig is None else bands_of(sig))
                sketch.append([] if sig is None else sketch_of(sig))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1).cast(pa.string()), pa.array(weight, pa.int64()), pa.array(bands, pa.list_(pa.int64())), pa.array(sketch, pa.list_(pa.int64()))], names=["doc_id", "digest", "weight", "bands", "sketch"])

    return arrow_map(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.md5(whole("text")).alias("digest"), whole("text").alias("text")), run, SIGNED)


COMPARED = "a long, b long, wa long, wb long, common long, changes array<long>"


def _copies(values: np.ndarray, times: np.ndarray, sign: int) -> np.ndarray:
    """A number for each value and each of its copies."""
    values, times = values[times > 0], times[times > 0]
    if not len(times):
        return values
    copy = np.arange(times.sum()) - np.repeat(np.cumsum(times) - times, times)
    return mix(np.repeat(values, times) ^ mix((2 * copy + sign + 1).astype(np.uint64) * STEP))


def _compared(pairs: DataFrame, texts: DataFrame, listed: bool = False) -> DataFrame:
    """pairs(a, b) -> their numbers of shingles, how many they share, and (listed, from HALF on) the changes from a to b:
    a number for each shingle, copies told apart, that came or went. Exact; the text of b is sent once a pair, that of a once."""
    side = lambda name, text: texts.select(F.col("node").alias(name), F.col("text").alias(text))
    # `a` comes last: its text is sent once, not once a pair. Both sides grow with the data, so the joins are by shuffle at any size
    both = pairs.join(side("b", "tb").hint("merge"), "b").join(side("a", "ta").hint("merge"), "a")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last: tuple[str | None, np.ndarray, np.ndarray] = None, np.zeros(0, np.uint64), np.zeros(0)
        for batch in batches:
            rows = []
            for x, y in zip(batch.column(2), batch.column(3), strict=True):
                x = x.as_py()
                if x != last[0]:
                    last = x, *np.unique(shingles(text_hashes(x)), return_counts=True)
                _, u, k = last
                v, n = np.unique(shingles(text_hashes(y.as_py())), return_counts=True)
                at = np.minimum(np.searchsorted(u, v), len(u) - 1)
                same = u[at] == v
                held = np.where(same, k[at], 0)
                wa, wb, common = int(k.sum()), int(n.sum()), int(np.minimum(n, held).sum())
                changes = None
                if listed and common >= HALF * (wa + wb - common):
                    gone = k.copy()
                    gone[at[same]] -= np.minimum(n, held)[same]
                    changes = np.concatenate([_copies(v, n - np.minimum(n, held), 0), _copies(u, gone, 1)]).view(np.int64)
                rows.append((wa, wb, common, changes))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *[pa.array([r[i] for r in rows], pa.int64()) for i in range(3)], pa.array([r[3] for r in rows], pa.list_(pa.int64()))], names=["a", "b", "wa", "wb", "common", "changes"])

    return arrow_map(both.select("a", "b", "ta", "tb"), run, COMPARED)


def _is_alike(least: float) -> Column:
    return F.col("common") >= F.lit(least) * (F.col("wa") + F.col("wb") - F.col("common"))


def _nodes(every: DataFrame) -> DataFrame:
    """One row a text: digest, node (its least id; a number from the digest where that id stands for two texts or is
    null), named (whether node is an id), copies, weight, bands, sketch."""
    low = F.lit(-(1 << 62))
    nodes = every.groupBy("digest").agg(F.min(F.coalesce("doc_id", low)).alias("node"), F.count(F.lit(1)).alias("copies"), F.first("weight").alias("weight"), F.first("bands").alias("bands"), F.first("sketch").alias("sketch"))
    several = cut(nodes.groupBy("node").agg(F.count(F.lit(1)).alias("n")).filter((F.col("n") > 1) | (F.col("node") == low)).select("node", F.lit(False).alias("named")))
    named = nodes.join(several, "node", "left").withColumn("named", F.coalesce("named", F.lit(True)))
    return named.withColumn("node", F.when(F.col("named"), F.col("node")).otherwise(-F.abs(F.xxhash64("digest") % F.lit(1 << 61)) - 2))


def _links(docs: DataFrame, nodes: DataFrame, least: float, slack: int | None) -> tuple[DataFrame, DataFrame]:
    """Links between nodes, a row (a, b) each, that connect every class; and the components (id, root)."""
    buckets = nodes.filter("weight > 0").select("node", F.explode("bands").alias("bucket"))
    shared = buckets.groupBy("bucket").agg(F.count(F.lit(1)).alias("n")).filter("n > 1")
    met = cut(buckets.join(shared.hint("merge"), "bucket"))
    popular = met.groupBy("node").agg(F.sum("n").alias("met"))
    texts = _texts(docs, nodes, popular)
    center = lambda rows: rows.groupBy("bucket").agg(F.max(F.struct("met", (-F.col("node")).alias("minus"))).alias("m")).select("bucket", (-F.col("m.minus")).alias("center"))
    met = met.select("bucket", "node").join(popular.hint("merge"), "node")
    members = cut(met.join(center(met).hint("merge"), "bucket").select("bucket", "node", "met", "center"))
    star = cut(_compared(members.filter("node <> center").select(F.col("center").alias("a"), F.col("node").alias("b")).distinct(), texts, listed=True))

    # those that aren't alike to their centre: with a second centre among them, and with their kin
    far = members.hint("merge").join(star.filter(~_is_alike(least)).select(F.col("a").alias("center"), F.col("b").alias("node")), ["center", "node"])
    second = far.join(center(far).withColumnRenamed("center", "next"), "bucket").filter("node <> next").select(F.col("next").alias("a"), F.col("node").alias("b"))
    tried = second.unionByName(_kin(star.withColumn("out", ~_is_alike(least)))).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    tried = cut(_compared(tried, texts))
    links = star.filter(_is_alike(least)).select("a", "b").unionByName(tried.filter(_is_alike(least)).select("a", "b"))
    roots = components(links)

    rows = _around_centers(star, roots)
    far = cut(_compared(_far_pairs(nodes, members, rows, least, slack).join(tried.select("a", "b"), ["a", "b"], "left_anti"), texts).filter(_is_alike(least)).select("a", "b"))
    last = cut(far.unionByName(_near_links(rows, least)).distinct())
    if last.limit(1).count():
        links = links.unionByName(last)
        roots = components(links)
    return links, roots


def _kin(star: DataFrame) -> DataFrame:
    """Pairs of a text that isn't alike to its centre and, for each of its changes that other members have too, the one
    of these with fewest changes: a copy's source has what the copy has but the copy's last changes."""
    each = star.filter(F.col("changes").isNotNull()).select(F.col("a").alias("center"), F.col("b").alias("node"), "out", F.size("changes").alias("n"), F.explode("changes").alias("e"))
    plain = cut(each.groupBy("center", "e").agg(F.min(F.struct("n", "node")).alias("p"), F.count(F.lit(1)).alias("c")).filter("c > 1"))
    hit = each.filter("out").join(plain, ["center", "e"]).filter(F.col("node") != F.col("p.node"))
    return hit.select(F.col("p.node").alias("a"), F.col("node").alias("b")).distinct()


def _around_centers(star: DataFrame, roots: DataFrame) -> DataFrame:
    """Members of the centres that don't hold all their members in one component."""
    to = star.select(F.col("a").alias("center"), F.col("b").alias("node"), F.col("wa").alias("wc"), F.col("wb").alias("w"), "common", "changes", (F.col("common") / (F.col("wa") + F.col("wb") - F.col("common"))).alias("sim"))
    rows = _rooted(to, roots).withColumn("out", F.col("root") != F.col("center_root"))
    return cut(rows.join(cut(rows.filter("out").select("center").distinct()), "center"))


def _near_links(rows: DataFrame, least: float) -> DataFrame:
    """Links between members at least half like their centre, from their changes: with i in common with the centre c,
    two members x, y share i_x + i_y - |c| + (changes in common) shingles. For each x apart from the centre's component
    and each other component, one link."""
    near = rows.filter(F.col("changes").isNotNull())
    size = cut(near.groupBy("center").agg(F.ceil(F.count(F.lit(1)) / MEMBERS).cast("int").alias("blocks")))  # written, so that a hot centre's rows can be split
    near = near.join(size, "center").withColumn("y", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
    pack = lambda df, name: df.groupBy("center", "blocks", "wc", "y").agg(F.collect_list(F.struct("node", "root", "w", "common", "changes")).alias(name))
    own = pack(near.filter("out"), "px").withColumnRenamed("y", "x").withColumn("y", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    both = own.join(pack(near, "py").select("center", "y", "py"), ["center", "y"])

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        found = []
        for wc, px, py in zip(pdf["wc"], pdf["px"], pdf["py"], strict=True):
            flat_x, flat_y = (np.concatenate([np.asarray(r["changes"], np.int64) for r in p]) for p in (px, py))
            both_have = np.intersect1d(flat_x, flat_y)
            grids = []
            for p, flat in ((px, flat_x), (py, flat_y)):
                owner = np.repeat(np.arange(len(p)), [len(r["changes"]) for r in p])
                at = np.minimum(np.searchsorted(both_have, flat), max(len(both_have) - 1, 0))
                hit = both_have[at] == flat if len(both_have) else np.zeros(len(flat), bool)
                grid = np.zeros((len(p), len(both_have)), np.float32)
                grid[owner[hit], at[hit]] = 1
                grids.append(grid)
            w, common, root = (([np.array([r[c] for r in p], np.int64) for p in (px, py)]) for c in ("w", "common", "root"))
            shared = common[0][:, None] + common[1][None] - wc + np.rint(grids[0] @ grids[1].T).astype(np.int64)
            ok = (shared >= least * (w[0][:, None] + w[1][None] - shared)) & (root[0][:, None] != root[1][None])
            for i in np.flatnonzero(ok.any(1)):
                other = np.flatnonzero(ok[i])
                _, first = np.unique(root[1][other], return_index=True)
                found += [(px[i]["node"], py[k]["node"]) for k in other[first]]
        return pd.DataFrame(found, columns=["a", "b"]).astype("int64")

    return pandas_groups(both, ["center", "x", "y"], run, "a long, b long").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))


def _far_pairs(nodes: DataFrame, members: DataFrame, rows: DataFrame, least: float, slack: int | None) -> DataFrame:
    """Pairs (a < b) of different components, one of them less than half like their bucket's centre, that length,
    sketch and the triangle inequality allow to be alike."""
    facts = nodes.select("node", "weight", *[F.get("sketch", F.lit(i)).alias(f"s{i}") for i in range(SKETCH_WORDS)])
    placed = members.join(rows.filter(F.col("sim") < HALF + 1 - least + 1e-9).select("center", "node", "sim", "root"), ["center", "node"]).join(facts, "node")
    u, v = placed.filter(F.col("sim") < HALF).alias("u"), placed.alias("v")
    bits = " + ".join(f"bit_count(u.s{i} ^ v.s{i})" for i in range(SKETCH_WORDS))
    alike = F.expr(f"u.bucket = v.bucket AND u.root <> v.root AND abs(u.sim - v.sim) <= {1 - least + 1e-9} AND least(u.weight, v.weight) >= {least} * greatest(u.weight, v.weight)" + (f" AND {bits} <= {slack}" if slack is not None else ""))
    return u.join(v, alike).select(F.least("u.node", "v.node").alias("a"), F.greatest("u.node", "v.node").alias("b")).distinct()


def _texts(docs: DataFrame, nodes: DataFrame, wanted: DataFrame) -> DataFrame:
    """node, text of the wanted nodes. They are a share of all texts, so the join is by shuffle at any size."""
    wanted = wanted.select("node").join(nodes.select("node", "digest"), "node").hint("merge")
    return cut(docs.select(F.md5(whole("text")).alias("digest"), whole("text").alias("text")).join(wanted, "digest").groupBy("node").agg(F.first("text").alias("text")))


def _rooted(rows: DataFrame, roots: DataFrame) -> DataFrame:
    """rows(node, center) with the components of both."""
    m = rows.join(roots.select(F.col("id").alias("node"), "root"), "node", "left").join(roots.select(F.col("id").alias("center"), F.col("root").alias("center_root")), "center", "left")
    return m.withColumn("root", F.coalesce("root", "node")).withColumn("center_root", F.coalesce("center_root", "center"))


def classes(docs: DataFrame, least: float = SIMILARITY, slack: int | None = SKETCH_SLACK) -> DataFrame:
    """One row per document: doc_id, digest, class_id, copies (documents with its very text), links (other texts that
    were found alike to its text; the links connect every class)."""
    every = cut(signed(docs))
    nodes = cut(_nodes(every))
    links, roots = _links(docs, nodes, least, slack)
    degree = links.unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).groupBy(F.col("a").alias("node")).agg(F.count(F.lit(1)).alias("links"))
    placed = nodes.select("digest", "node", "named", "copies").join(roots.withColumnRenamed("id", "node"), "node", "left").join(degree, "node", "left").withColumn("root", F.coalesce("root", "node"))
    numbers = cut(placed.groupBy("root").agg(F.coalesce(F.min(F.when(F.col("named"), F.col("node"))), F.min("node")).alias("class_id")))
    placed = cut(placed.join(numbers, "root").select("digest", "class_id", "copies", F.coalesce("links", F.lit(0)).alias("links")))
    return every.select("doc_id", "digest").join(placed, "digest")


def near_duplicates(docs: DataFrame, least: float = SIMILARITY, slack: int | None = SKETCH_SLACK) -> DataFrame:
    """doc_id, class_id, copies, links."""
    return classes(docs, least, slack).select("doc_id", "class_id", F.col("copies").cast("long").alias("copies"), F.col("links").cast("long").alias("links"))


def keep_one(docs: DataFrame, least: float = SIMILARITY, slack: int | None = SKETCH_SLACK) -> DataFrame:
    """docs with one row of each class: that of the least doc_id (nulls last), then digest, then any of equal rows."""
    each = classes(docs, least, slack).groupBy("class_id", "doc_id", "digest").agg(F.count(F.lit(1)).alias("n"))
    least_of = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "digest", "n")).alias("m")
    chosen = cut(each.groupBy("class_id").agg(least_of).select(F.col("m.doc_id").alias("__id"), F.col("m.digest").alias("__d"), F.col("m.n").alias("__n")))
    keyed = docs.withColumn("__digest", F.md5(whole("text")))
    on = F.col("doc_id").cast("long").eqNullSafe(F.col("__id")) & (F.col("__digest") == F.col("__d"))
    once = keyed.join(chosen.filter("__n = 1").hint("merge"), on, "left_semi")  # nearly all documents are chosen, at any size
    if chosen.filter("__n > 1").limit(1).count():  # the same row more than once
        more = keyed.join(chosen.filter("__n > 1"), on, "left_semi")
        once = once.unionByName(more.dropDuplicates(["doc_id", "__digest"]))
    return once.drop("__digest")
