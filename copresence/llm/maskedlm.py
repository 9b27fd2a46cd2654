"""Masked pseudo-likelihood: every token is predicted from the tokens on both sides of it.

Tokens are words, each with a probability of its own: that of its class given the window, times that of the word in its
class. The commonest (counted over all documents) are classes of their own, the others share the class of their last
letters' bucket, where a word has its count over the bucket's count and one (the one is left for words never counted).
The network adds one vector a place of the window (two words to the left, two to the right), bends the sum and gives a
distribution over groups of classes and one over the classes of each group; a class has the product of the two. A
document's score is the sum of the log-probability of each of its tokens given its window: no token is left out of a
score, and no counted word is left out of the vocabulary, which grows with the corpus.

Words are hashed twice: for the counts, and for the class numbers of each document, which are written to the shared
folder with what doesn't hang on the network (the word-in-class part). Training and scoring read these numbers. Counts
of the KNOWN commonest words go to the tasks; the others are joined by hash. A word counted once adds the logarithm of
1, so it needs no row in that join.

Training goes over all positions of all documents (one in STRIDE a round, another set each round) and doesn't hang on
how the table is dealt: a document's shard follows from its text and id, shards are read in the order of digests, and
each shard runs gradient steps of fixed size from the round's common weights. The shards' weights are averaged by
number of targets in whole numbers, so the sum is the same in any order. What comes to the driver is one network. A
lost task is run again from the same weights.

Defined cases: null and empty texts have 0 tokens and score 0 (mean 0); windows at the ends hold a boundary number;
without any word in the table nothing is learned and nothing scored; repeated rows score alike; null ids are kept;
extra columns are not read.
"""

from __future__ import annotations

import ctypes
import math
from collections.abc import Iterator
from functools import lru_cache
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from copresence.ship import arrow_map

from .common import cut, whole
from .words import hash_words, text_hashes

GROUPS, MEMBERS = 32, 32
SIZE, HIDDEN, SIDE = GROUPS * MEMBERS, 16, 2
BUCKETS = 127  # classes of words that are not one of their own; number 0 is the boundary
STRIDE, ROUNDS, BATCH, RATE = 2, 2, 4096, 0.12
CHUNK = 32768  # positions of a shard read at once
SHARD_WORDS, FEW_SHARDS, MOST_SHARDS = 1 << 22, 16, 1 << 16
COUNTED = 300_000  # words a task holds before it hands its counts on
SCORED = 8192  # positions scored at once
KNOWN = 200_000  # counts that every task has at hand
SHARP = 1e9  # logarithms are added up as whole multiples of its inverse, in any order
FINE = 1 << 24  # so are weights
PLACES = [o for o in range(-SIDE, SIDE + 1) if o]

Net = dict[str, np.ndarray]


@lru_cache(maxsize=1)
def one_thread() -> None:
    """Keep numpy's matrix library to one thread a worker: the products are small, and tasks already fill the cores."""
    for path in (Path(np.__file__).parent.parent / "numpy.libs").glob("*openblas*"):
        library = ctypes.CDLL(str(path))
        for name in ("scipy_openblas_set_num_threads64_", "openblas_set_num_threads64_", "openblas_set_num_threads"):
            if hasattr(library, name):
                getattr(library, name)(1)


def bucket(tails: np.ndarray) -> np.ndarray:
    return 1 + (tails.astype(np.int64) * 40503 >> 7) % BUCKETS


def number_of(rank: np.ndarray) -> np.ndarray:
    """Class numbers by rank (boundary, buckets, common words): ranks are dealt over the groups in turn."""
    return rank % GROUPS * MEMBERS + rank // GROUPS


class Numbers:
    """The class of each word of texts: its own for a common word (given as text or hash), else that of its ending's bucket."""

    def __init__(self, common: list[str] | list[int]):
        hashes = np.array([text_hashes(w)[0] if isinstance(w, str) else w & (1 << 64) - 1 for w in common], np.uint64)
        order = np.argsort(hashes)
        self.hashes, self.own = hashes[order], number_of(1 + BUCKETS + order)

    def classes(self, words_of: np.ndarray, tails: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Class numbers, and the buckets of the words without a class of their own (0 for the others)."""
        kind = bucket(tails)
        out = number_of(kind)
        if len(self.hashes):
            at = np.minimum(np.searchsorted(self.hashes, words_of), len(self.hashes) - 1)
            met = self.hashes[at] == words_of
            out[met], kind[met] = self.own[at[met]], 0
        return out.astype(np.uint16), kind

    def of(self, texts: list[str | None]) -> list[np.ndarray]:
        words_of, counts, tails = hash_words(texts)
        return np.split(self.classes(words_of, tails)[0], np.cumsum(counts)[:-1])


def word_counts(docs: DataFrame) -> DataFrame:
    """word (hash), bucket, n over all documents; counts are combined in the tasks before the shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        size = 0

        def rows() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(held[0][0].view(np.int64)), pa.array(held[0][1], pa.int32()), pa.array(held[0][2], pa.int64())], names=["word", "bucket", "n"])

        def combine() -> None:
            word, kind, n = (np.concatenate(x) for x in zip(*held, strict=True))
            one, first, at = np.unique(word, return_index=True, return_inverse=True)
            held[:] = [(one, kind[first], np.bincount(at, n, len(one)).astype(np.int64))]

        for b in batches:
            words_of, _, tails = hash_words(b.column(0).to_pylist())
            held.append((words_of, bucket(tails), np.ones(len(words_of), np.int64)))
            size += len(words_of)
            if size > 2 * COUNTED:
                combine()
                if len(held[0][0]) > COUNTED:
                    yield rows()
                    held.clear()
                size = len(held[0][0]) if held else 0
        if held:
            combine()
            yield rows()

    return arrow_map(docs.select("text"), run, "word long, bucket int, n long").groupBy("word", "bucket").agg(F.sum("n").alias("n"))


# ---- the network


def start(common: list[tuple[str | int, int]], rest: int) -> Net:
    """Starting weights: small random vectors, and the logs of the counts as what is expected without a window."""
    rng = np.random.default_rng(7)
    share = np.full(SIZE, 1e-6)
    share[number_of(np.arange(1, 1 + BUCKETS))] = max(rest, 1) / BUCKETS
    share[number_of(1 + BUCKETS + np.arange(len(common)))] = [n for _, n in common]
    whole_of = share.reshape(GROUPS, MEMBERS).sum(1)
    return {
        "E": rng.normal(0, 0.1, (2 * SIDE, SIZE, HIDDEN)), "b": np.zeros(HIDDEN), "V": rng.normal(0, 0.1, (GROUPS, HIDDEN)), "d": np.log(whole_of / whole_of.sum()),
        "U": rng.normal(0, 0.1, (SIZE, HIDDEN)), "c": np.log(share / np.repeat(whole_of, MEMBERS)),
    }


def windows(numbers: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """All texts in one row with boundaries between; places of tokens; text of each token."""
    gap = np.zeros(SIDE, np.uint16)
    flat = np.concatenate([gap, *[x for n in numbers for x in (n, gap)]])
    sizes = np.array([len(n) for n in numbers], np.int64)
    text = np.repeat(np.arange(len(numbers)), sizes)
    return flat, np.arange(len(text)) + SIDE * (text + 1), text


def hidden(net: Net, flat: np.ndarray, at: np.ndarray) -> np.ndarray:
    h = net["E"][0].take(flat.take(at + PLACES[0]), 0)
    for k, o in enumerate(PLACES[1:], 1):
        h += net["E"][k].take(flat.take(at + o), 0)
    h += net["b"]
    return np.tanh(h, out=h)


def _spread(z: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """exp(z) below its column's greatest, as shares of the column's sum, and the log of the sum of exp(z); z is used up."""
    peak = z.max(0)
    z -= peak
    np.exp(z, out=z)
    total = z.sum(0)
    z /= total
    return z, peak + np.log(total)


def _by_group(target: np.ndarray) -> tuple[np.ndarray, list[tuple[slice, slice]]]:
    """Positions in the order of their target's group; and for each group met its weights and its part of that order."""
    group = (target // MEMBERS).astype(np.uint8)
    order = np.argsort(group, kind="stable")
    edges = np.searchsorted(group[order], np.arange(GROUPS + 1)).tolist()
    return order, [(slice(g * MEMBERS, (g + 1) * MEMBERS), slice(edges[g], edges[g + 1])) for g in range(GROUPS) if edges[g] < edges[g + 1]]


def log_probabilities(net: Net, flat: np.ndarray, at: np.ndarray) -> np.ndarray:
    target, h = flat.take(at), hidden(net, flat, at)
    z = net["V"] @ h.T
    z += net["d"][:, None]
    out = z[target // MEMBERS, np.arange(len(at))]
    out -= _spread(z)[1]
    order, parts = _by_group(target)
    h, member, more = h.take(order, 0), target.take(order) % MEMBERS, np.empty_like(out)
    for own, rows in parts:
        z = net["U"][own] @ h[rows].T
        z += net["c"][own, None]
        more[rows] = z[member[rows], np.arange(z.shape[1])]
        more[rows] -= _spread(z)[1]
    out[order] += more
    return out


def step(net: Net, memory: Net, flat: np.ndarray, at: np.ndarray) -> None:
    """One step down the gradient of the mean negative log-probability, with a rate that falls a weight by its past."""
    order, parts = _by_group(flat.take(at))
    at = at.take(order)  # the order of positions in a step doesn't matter
    target, h = flat.take(at), hidden(net, flat, at)
    each = np.arange(len(at))
    z = net["V"] @ h.T
    z += net["d"][:, None]
    p, _ = _spread(z)
    p[target // MEMBERS, each] -= 1
    grads = {"V": p @ h, "d": p.sum(1), "U": np.zeros_like(net["U"]), "c": np.zeros_like(net["c"]), "E": np.zeros_like(net["E"])}
    dh = p.T @ net["V"]
    member = target % MEMBERS
    for own, rows in parts:
        z = net["U"][own] @ h[rows].T
        z += net["c"][own, None]
        p, _ = _spread(z)
        p[member[rows], each[: z.shape[1]]] -= 1
        grads["U"][own], grads["c"][own] = p @ h[rows], p.sum(1)
        dh[rows] += p.T @ net["U"][own]
    dh *= 1 - h * h
    grads["b"] = dh.sum(0)
    for k, o in enumerate(PLACES):
        near = flat.take(at + o)
        order = np.argsort(near, kind="stable")
        near = near.take(order)
        first = np.append(0, np.flatnonzero(near[1:] != near[:-1]) + 1)
        grads["E"][k][near[first]] = np.add.reduceat(dh.take(order, 0), first, axis=0)
    for k, g in grads.items():
        g *= 1 / len(at)
        memory[k] += g * g
        net[k] -= RATE * g / (np.sqrt(memory[k]) + 1e-6)


def targets(at: np.ndarray, turn: int) -> np.ndarray:
    """The places trained on in a round, in mixed order."""
    at = at[turn % STRIDE :: STRIDE]
    return at[np.random.default_rng(len(at)).permutation(len(at))]


def single(net: Net) -> Net:
    return {k: v.astype(np.float32) for k, v in net.items()}


def fresh_memory(net: Net) -> Net:
    return {k: np.full_like(v, 1e-3) for k, v in net.items()}


def learn(net: Net, memory: Net, texts: list[np.ndarray], turn: int) -> int:
    """Steps over some texts of a shard; how many targets they had."""
    flat, at, _ = windows(texts)
    at = targets(at, turn)
    for k in range(0, len(at), BATCH):
        step(net, memory, flat, at[k : k + BATCH])
    return len(at)


# ---- over the corpus


def _known(counts: DataFrame, most: int) -> tuple[DataFrame, DataFrame]:
    """Words counted more than once: at most so many of the commonest, and all others."""
    counts = counts.filter("n > 1").withColumn("level", F.floor(F.log2("n") * 8))
    least, held = 1 << 30, 0
    for r in sorted(counts.groupBy("level").count().collect(), key=lambda r: -r["level"]):  # a few hundred at most
        held += r["count"]
        if held > most:
            break
        least = r["level"]
    return counts.filter(F.col("level") >= least).select("word", "n"), counts.filter(F.col("level") < least).select("word", "n")


def common_words(counts: DataFrame) -> list[tuple[int, int]]:
    """(hash, count) of the words with a class of their own."""
    return [(r["word"], r["n"]) for r in counts.orderBy(F.desc("n"), "word").limit(SIZE - 1 - BUCKETS).collect()]


def shards_for(words: int) -> int:
    return min(MOST_SHARDS, max(math.ceil(words / SHARD_WORDS), min(FEW_SHARDS, math.ceil(words / (SHARD_WORDS // 4))), 1))


NUMBERED = "row long, doc_id long, shard int, digest long, classes binary, part double, rest array<long>"


def numbered(docs: DataFrame, common: list[int] | list[str], counts: DataFrame, known: int = KNOWN) -> DataFrame:
    """A row per document, dealt by shard and in order: its class numbers, the sum of the logarithms of its words' shares
    in their classes as far as the counts are at hand, and the words whose counts aren't."""
    of = Numbers(common)
    table = _known(counts, known)[0].toArrow()
    at_hand = table.column("word").to_numpy().view(np.uint64)
    order = np.argsort(at_hand)
    at_hand, logs_at_hand = at_hand[order], np.log(table.column("n").to_numpy()[order])
    own = [w - (1 << 64) if w >= 1 << 63 else w for w in of.hashes.tolist()]
    all_of = np.zeros(1 + BUCKETS)
    words = 0
    for r in counts.groupBy("bucket").agg(F.sum(F.when(F.col("word").isin(own), 0).otherwise(F.col("n"))).alias("n"), F.sum("n").alias("words")).collect():
        all_of[r["bucket"]] = r["n"]
        words += r["words"]
    log_all = np.log(all_of + 1)
    log_all[0] = 0
    shards = shards_for(words)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            words_of, sizes, tails = hash_words(b.column(4).to_pylist())
            classes, kind = of.classes(words_of, tails)
            logs = -log_all[kind]
            text = np.repeat(np.arange(b.num_rows), sizes)
            shared = np.flatnonzero(kind)
            if len(at_hand):
                place = np.minimum(np.searchsorted(at_hand, words_of[shared]), len(at_hand) - 1)
                met = at_hand[place] == words_of[shared]
                logs[shared[met]] += logs_at_hand[place[met]]
                shared = shared[~met]
            ends = np.append(0, np.cumsum(np.bincount(text[shared], minlength=b.num_rows)))
            columns = [
                *b.columns[:4], pa.array([x.tobytes() for x in np.split(classes, np.cumsum(sizes)[:-1])], pa.binary()), pa.array(np.bincount(text, logs, minlength=b.num_rows)),
                pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(words_of[shared].view(np.int64))),
            ]
            yield pa.RecordBatch.from_arrays(columns, names=["row", "doc_id", "shard", "digest", "classes", "part", "rest"])

    digest, doc = F.xxhash64(whole("text")), F.col("doc_id").cast("long")
    rows = docs.select(F.monotonically_increasing_id().alias("row"), doc.alias("doc_id"), F.pmod(F.xxhash64(digest, doc), F.lit(shards)).cast("int").alias("shard"), digest.alias("digest"), "text")
    dealt = arrow_map(rows, run, NUMBERED).repartitionById(shards, F.col("shard")).sortWithinPartitions("shard", "digest", "doc_id")
    return cut(dealt)


def _round(rows: DataFrame, net: Net, turn: int) -> Net:
    """One round over all shards: their weights, averaged by number of targets."""
    sizes = {k: v.size for k, v in net.items()}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        one_thread()
        held: list[np.ndarray] = []
        shard, own, memory, done, size = None, single(net), {}, 0, 0

        def result() -> Iterator[pa.RecordBatch]:
            nonlocal done
            if held:
                done += learn(own, memory, held, turn)
                held.clear()
            if done:
                w = np.rint(np.concatenate([own[k].ravel() for k in sizes]).astype(np.float64) * FINE).astype(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(w))), pa.array(w), pa.array(np.full(len(w), done))], names=["place", "value", "done"])

        for b in batches:
            for s, data in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                if s != shard:
                    yield from result()
                    shard, own, done, size = s, single(net), 0, 0
                    memory = fresh_memory(own)
                x = np.frombuffer(data.as_py(), np.uint16)
                if len(x):
                    held.append(x)
                    size += len(x)
                if size >= CHUNK:
                    done += learn(own, memory, held, turn)
                    held.clear()
                    size = 0
        yield from result()

    whole_number = lambda c: F.col(c).cast("decimal(19,0)")
    sums = arrow_map(rows.select("shard", "classes"), run, "place long, value long, done long").groupBy("place").agg(F.sum(whole_number("value") * whole_number("done")).alias("value"), F.sum("done").alias("done"))
    got = sums.collect()  # one network
    if not got:
        return net
    flat = np.zeros(sum(sizes.values()))
    for r in got:
        flat[r["place"]] = int(r["value"]) / r["done"] / FINE
    parts = np.split(flat, np.cumsum(list(sizes.values()))[:-1])
    return {k: p.reshape(net[k].shape) for k, p in zip(sizes, parts, strict=True)}


Model = tuple[list[int] | list[str], Net]


def _trained(rows: DataFrame, common: list[tuple[int, int]], every: int, rounds: int) -> Model:
    net = start(common, every - sum(n for _, n in common))
    for turn in range(max(rounds, STRIDE) if common else 0):
        net = _round(rows, net, turn)
    return [w for w, _ in common], net


def train(docs: DataFrame, rounds: int = ROUNDS, counts: DataFrame | None = None) -> Model:
    """The hashes of the common words and the network, from all documents."""
    counts = cut(word_counts(docs)) if counts is None else counts
    common = common_words(counts)
    rows = numbered(docs, [w for w, _ in common], counts)
    return _trained(rows, common, counts.agg(F.sum("n")).first()[0] or 0, rounds)


def pseudo_likelihood(docs: DataFrame, model: Model | None = None, counts: DataFrame | None = None, known: int = KNOWN, rounds: int = ROUNDS) -> DataFrame:
    """One row per document: doc_id, n_tokens, pll (sum of log-probabilities), mean_pll.

    counts: those of the documents the model is from; docs are counted if they are not given."""
    counts = cut(word_counts(docs)) if counts is None else counts
    common = common_words(counts) if model is None else []
    rows = numbered(docs, model[0] if model else [w for w, _ in common], counts, known)
    _, net = model or _trained(rows, common, counts.agg(F.sum("n")).first()[0] or 0, rounds)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        one_thread()
        weights = single(net)
        for b in batches:
            classes = [np.frombuffer(x.as_py(), np.uint16) for x in b.column(2)]
            flat, at, text = windows(classes)
            logs = np.concatenate([log_probabilities(weights, flat, at[k : k + SCORED]) for k in range(0, len(at), SCORED)] or [np.zeros(0)])
            total = np.bincount(text, logs.astype(np.float64), minlength=b.num_rows) + b.column(3).to_numpy()
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([len(x) for x in classes], pa.int64()), pa.array(total)], names=["row", "doc_id", "n_tokens", "total"])

    scored = arrow_map(rows.select("row", "doc_id", "classes", "part"), run, "row long, doc_id long, n_tokens long, total double")
    rest = rows.select("row", F.explode("rest").alias("word")).join(_known(counts, known)[1], "word").groupBy("row").agg(F.sum(F.round(F.log("n") * SHARP).cast("long")).alias("more"))
    pll = F.col("total") + F.coalesce("more", F.lit(0)) / SHARP
    return scored.join(rest, "row", "left").select("doc_id", "n_tokens", F.round(pll, 4).alias("pll"), F.round(pll / F.greatest("n_tokens", F.lit(1)), 6).alias("mean_pll"))


def held_out_gain(docs: DataFrame, rounds: int = ROUNDS) -> DataFrame:
    """One row: tokens in the documents that the model hasn't seen (a fifth, by id), their mean log-probability with the
    window, and that by the counts alone."""
    unseen = F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0, F.lit(False))
    seen, other = docs.filter(~unseen), docs.filter(unseen)
    counts = cut(word_counts(seen))
    common, net = train(seen, rounds, counts)
    flat = start(common_words(counts), (counts.agg(F.sum("n")).first()[0] or 0) - sum(n for _, n in common_words(counts)))
    flat = {k: v * 0 if k in "UVE" else v for k, v in flat.items()}
    mean = lambda net, name: pseudo_likelihood(other, (common, net), counts).agg(F.sum("n_tokens").alias("n_tokens"), (F.sum("pll") / F.sum("n_tokens")).alias(name))
    return mean(net, "with_window").join(mean(flat, "by_counts"), "n_tokens")
