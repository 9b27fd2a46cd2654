from __future__ import annotations

import hashlib
import random
import re
import struct
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from copresence.llm import maskedlm, ogg, tokencount, toxicity
from copresence.llm.words import hash_texts


# ---- Ogg


def plain_checksum(data: bytes) -> int:
    crc = 0
    for byte in data:
        crc ^= byte << 24
        for _ in range(8):
            crc = (crc << 1 ^ 0x04C11DB7 if crc & 0x80000000 else crc << 1) & 0xFFFFFFFF
    return crc


def test_checksum_is_the_containers():
    for n in (0, 1, 27, 255, 1000):
        data = random.Random(n).randbytes(n)
        assert ogg.page_checksum(data) == plain_checksum(data)


@pytest.mark.parametrize("size", [0, 1, 63, 64, 65, 4096, 70_000, 300_000])
def test_round_trip(size):
    text = "".join(random.Random(size).choices("abcdé\n ", k=size))
    payload, n, stored = ogg.encode(text)
    media = ogg.decode(stored)
    assert media.damaged == 0 and b"".join(p for p, _ in media.streams[ogg.SAMPLES].packets[1:]) == payload
    assert payload[:n].decode() == text and len(payload) % 64 == 0 and len(payload) >= 64
    times = [t for t in ogg.timestamps(media.streams[ogg.SAMPLES].packets) if t is not None]
    assert times == sorted(times) and times[-1] == len(payload) / ogg.RATE


def test_sizes_whose_seconds_are_rounded():
    """64,064 samples at 8,000 a second: seconds times the rate aren't the samples again."""
    for n in (64_064, 64_065, 65_216):
        row = dict(zip([x.split()[0] for x in ogg.REPORT.split(", ")], ogg._report(1, "a" * n), strict=True))
        assert row["n_bytes"] == n and row["payload_bytes"] == -(-n // 64) * 64 and row["seconds"] == row["payload_bytes"] / ogg.RATE


def test_packets_of_all_sizes_cross_pages():
    sizes = [0, 1, 254, 255, 256, 510, 70_000, 3]
    packets = [(random.Random(n).randbytes(n), i) for i, n in enumerate(sizes)]
    for segments in (1, 2, 7, 255):
        data = b"".join(p for _, p in ogg.stream_pages(9, packets, segments))
        assert [p for p, _ in ogg.decode(data).streams[9].packets] == [p for p, _ in packets]


def test_damage_never_yields_wrong_packets():
    packets = [(random.Random(n).randbytes(700 * n), n) for n in range(1, 30)]
    pages = [p for _, p in ogg.stream_pages(5, packets, 4)]
    data = b"".join(pages)
    good = {p for p, _ in packets}
    for seed in range(30):
        r = random.Random(seed)
        broken = bytearray(data)
        for _ in range(3):
            broken[r.randrange(len(broken))] ^= 1 << r.randrange(8)
        media = ogg.decode(bytes(broken))
        found = media.streams[5].packets if 5 in media.streams else []
        assert media.damaged and all(p in good for p, _ in found)
    lost = ogg.decode(b"".join(pages[:10] + pages[11:]))
    assert all(p in good for p, _ in lost.streams[5].packets) and lost.streams[5].lost
    assert ogg.decode(None).streams == {} and ogg.decode(b"OggS").damaged == 1


def test_media_report(spark, odd_docs, empty_docs):
    rows = {(r["doc_id"], r["n_bytes"]): r for r in ogg.media_report(odd_docs).collect()}
    for d in odd_docs.collect():
        raw = (d["text"] or "").encode()
        payload = raw + bytes(-len(raw) % 64 or (64 if not raw else 0))
        r = rows[d["doc_id"], len(raw)]
        assert r["payload_sha256"] == hashlib.sha256(payload).hexdigest() and r["tail_crc32"] == zlib.crc32(payload[-64:]) and r["payload_bytes"] == len(payload)
    assert ogg.media_report(empty_docs).count() == 0
    packets = ogg.demultiplex(ogg.to_media(odd_docs.filter("doc_id = 8"))).collect()
    assert {p["stream"] for p in packets} == {ogg.SAMPLES, ogg.CHECKS}
    assert struct.unpack("<8sQ", next(p["data"] for p in packets if p["stream"] == ogg.CHECKS and p["packet"] == 0))[1] == 38


def test_every_packet_is_timed(spark):
    text = "x" * 40_000
    stored = ogg.encode(text)[2]
    packets = ogg.decode(stored).streams[ogg.SAMPLES].packets
    assert [p for p, g in packets if g < 0]  # packets that share a page with a later end
    assert ogg.granules(packets) == [0, *[min(i + ogg.PACKET, 40_000) for i in range(0, 40_000, ogg.PACKET)]]
    checks = ogg.decode(ogg.encode("y" * 200_000)[2]).streams[ogg.CHECKS].packets
    assert ogg.granules(checks) == [0, 65536, 131072, 196608, 200_000]
    first = stored[: ogg.HEADER.size + stored[26]]
    assert first[26] == 1 and first[27] == len(packets[0][0]) and stored[5] & ogg.FIRST  # the head has its page for itself
    rows = ogg.demultiplex(ogg.to_media(spark.createDataFrame([(1, text)], "doc_id long, text string"))).collect()
    assert all(r["seconds"] == r["granule"] / ogg.RATE for r in rows)


# ---- token counts

WORDS = ["don't", "naïve", "Straße", "ÉCOLE", "x1y2", "...", "—", "€5", "a\tb", "\r\n", "  ", "ſ", "it's", "I'LL", "¿qué?", "ĳ", "<|", "<|endoftext|>", "中文", "\xa0", " ", "😀", "1234567", "word" * 40]


def test_counts_are_those_of_the_files_library():
    path = tokencount.tokenizer_path()
    exact, fast = tokencount.plain_counter(path), tokencount.counter(path)
    r = random.Random(3)
    for _ in range(400):
        t = r.choice(["", " ", "\n"]).join(r.choices(WORDS, k=r.randrange(12)))
        assert fast(t) == exact(t), t
    for cp in [*range(1, 0x250), *range(0x2010, 0x2030), 0x20AC]:
        for t in (f"a{chr(cp)}b", f" {chr(cp)}{chr(cp)} ", chr(cp)):
            assert fast(t) == exact(t), hex(cp)


def test_cache_is_used_and_extended(spark, odd_docs, empty_docs, tmp_path):
    cache = f"{tmp_path}/cache"
    first = tokencount.count_tokens(odd_docs, cache).collect()
    texts = {(d["text"] or "") for d in odd_docs.collect()}
    assert spark.read.parquet(cache).count() == len(texts)
    exact = tokencount.plain_counter(tokencount.tokenizer_path())
    by_size = {len(t.encode()): exact(t) for t in texts}
    assert all(r["n_tokens"] == by_size[r["n_bytes"]] and r["over_limit"] == (r["n_tokens"] > 1024) for r in first) and len(first) == odd_docs.count()
    spark.createDataFrame([(hashlib.sha256(b"new text").hexdigest(), tokencount.version(tokencount.tokenizer_path()), 77)], tokencount.CACHE).write.mode("append").parquet(cache)
    again = tokencount.count_tokens(spark.createDataFrame([(1, "new text"), (2, "other")], "doc_id long, text string"), cache).collect()
    assert {r["doc_id"]: r["n_tokens"] for r in again} == {1: 77, 2: exact("other")}
    assert spark.read.parquet(cache).count() == len(texts) + 2
    assert tokencount.count_tokens(empty_docs, cache).count() == 0


def test_query_fills_and_then_joins_the_kept_cache(spark, tmp_path, monkeypatch):
    from copresence.llm import queries

    texts = ["some words here", "other words", "some words here", None]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(f"{tmp_path}/t/documents.parquet")
    cache, encoded = f"{tmp_path}/kept", []
    monkeypatch.setattr(tokencount, "_encoded", lambda misses, path, own=tokencount._encoded: (encoded.append(misses.count()), own(misses, path))[1])
    spark.conf.set(tokencount.CACHE_SETTING, cache)
    try:
        first = sorted(map(tuple, queries.op8_token_counts(spark, f"{tmp_path}/t").collect()))
        again = sorted(map(tuple, queries.op8_token_counts(spark, f"{tmp_path}/t").collect()))
    finally:
        spark.conf.unset(tokencount.CACHE_SETTING)
    exact = tokencount.plain_counter(tokencount.tokenizer_path())
    assert first == again == sorted((i, len((t or "").encode()), exact(t or ""), False) for i, t in enumerate(texts)) and encoded == [3, 0]
    assert sorted(map(tuple, queries.op8_token_counts(spark, f"{tmp_path}/t").collect())) == first and encoded == [3, 0, 3]  # its own cache


# ---- toxicity


def test_folding():
    assert toxicity.fold("1D10T m0r0n ѕtupіd $cum sc|um") == "idiot moron stupid $cum sclum"
    assert toxicity.fold("in 2024, 10 items; wow!!!") == "in 2024, 10 items; wow!!!"
    assert toxicity.fold("ｉｄｉｏｔ id​iot") == "idiot idiot"


def test_matching_and_exceptions():
    lex = toxicity.Lexicon({"clown": (2.0, True), "idio": (3.0, False), "idiot": (4.0, True)}, ("clown fish",))
    assert lex.measure("A CLOWN and idiots, cl0wn")[0] == 2 + 3 + 2
    assert lex.measure("a clown fish swims")[0] == 0 and lex.measure("clownish")[0] == 0 and lex.measure("theidiot")[0] == 0
    assert lex.measure("idiot")[0] == 4 and lex.measure(None) == (0.0, 0)


@pytest.fixture(scope="module")
def marked(spark):
    r = random.Random(1)
    plain = [f"w{chr(97 + i % 26)}{chr(97 + i // 26 % 26)}x" for i in range(300)]
    bad = ["nastyword", "vilething", "meanterm"]
    docs, labels = [], []
    for i in range(700):
        t = [r.choice(plain) for _ in range(r.randrange(5, 80))]
        toxic = i % 8 == 0
        if toxic:
            for _ in range(2):
                w = r.choice(bad)
                t.insert(r.randrange(len(t)), w.replace("i", "1").replace("e", "3") if r.random() < 0.3 else w)
        docs.append((i, " ".join(t)))
        labels.append((i, int(toxic)))
    return spark.createDataFrame(docs, "doc_id long, text string").persist(), spark.createDataFrame(labels, "doc_id long, toxic int").persist()


def test_held_out_accuracy(spark, marked):
    docs, labels = marked
    got = toxicity.score(docs, labels).join(labels, "doc_id").filter("held_out").collect()
    assert len(got) > 80 and sum(r["predicted"] == r["toxic"] for r in got) / len(got) > 0.98
    want = {i: zlib.crc32(str(i).encode()) % 5 == 0 for i in range(700)}
    assert all(want[r["doc_id"]] for r in got)
    flipped = labels.withColumn("toxic", F.when(toxicity.held_out(F.col("doc_id")), 1 - F.col("toxic")).otherwise(F.col("toxic")))
    assert toxicity.learn(docs, flipped) == toxicity.learn(docs, labels)  # held-out labels are never seen


def plain_measure(text, entries, exceptions):
    """Sum of weights by trying every entry at every place of the folded text."""
    t, total, spared = toxicity.fold(text or ""), 0.0, set()
    starts = [i for i in range(len(t)) if not (i and t[i - 1].isalpha())]
    ends_word = lambda e: e >= len(t) or not t[e].isalpha()
    for i in starts:
        for x in map(toxicity.fold, exceptions):
            if t.startswith(x, i) and ends_word(i + len(x)):
                spared.update(range(i, i + len(x)))
    for i in starts:
        met = [w for x, (w, whole) in entries.items() if t.startswith(x, i) and (not whole or ends_word(i + len(x)))]
        total += max([0, *met]) if i not in spared else 0
    return total, len(t)


def plain_lexicon(rows, halves):
    """rows (text, toxic, half) -> entries, by counting documents with each word and word head one by one."""
    seen = {}
    totals = [0, 0]
    for text, toxic, half in rows:
        if half not in halves:
            continue
        words = {w for w in re.findall(r"[^\W\d_]+", toxicity.fold(text or ""))}
        totals[toxic] += 1
        for entry in {(w, True) for w in words} | {(w[:n], False) for w in words for n in toxicity.HEADS if len(w) > n}:
            seen.setdefault(entry, [0, 0])[toxic] += 1
    out = {}
    for (entry, whole), (c, t) in sorted(seen.items()):
        weight = np.log((t + 0.5) / (totals[1] - t + 0.5)) - np.log((c + 0.5) / (totals[0] - c + 0.5))
        error = np.sqrt(1 / (t + 0.5) + 1 / (c + 0.5))
        z = weight / error
        if t >= toxicity.LEAST and z >= toxicity.LEAST_Z and weight - 2 * error >= toxicity.LEAST_WEIGHT:
            out.setdefault(entry, {})[whole] = (float(weight), z)
    return out


def test_lexicon_and_scores_against_plain_versions(spark, marked):
    docs, labels = marked
    label = {r["doc_id"]: r["toxic"] for r in labels.collect() if zlib.crc32(str(r["doc_id"]).encode()) % 5}
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    model = toxicity.learn(docs, labels)
    want = plain_lexicon([(texts[i], t, 0) for i, t in label.items()], (0,))
    assert set(model.entries) == set(want) and model.entries
    for entry, (weight, whole) in model.entries.items():
        assert weight == pytest.approx(want[entry][whole][0])
    got = {r["doc_id"]: r["score"] for r in toxicity.score(docs, labels).collect()}
    for i, t in texts.items():
        total, letters = plain_measure(t, model.entries, model.exceptions)
        z = sum(c * x for c, x in zip(model.curve, (1, np.log1p(total), np.log1p(1000 * total / max(letters, 200))), strict=True))
        assert got[i] == pytest.approx(1 / (1 + np.exp(-z)), abs=1e-9)
    r = random.Random(8)
    words = ["clown", "fish", "cl0wn", "clownish", "idiot", "id10t", "idiots", "a", "trash", "can", "xclown"]
    entries = {"clown": (2.0, True), "idio": (3.0, False), "idiot": (4.0, True), "trash": (1.5, True), "fish": (0.5, False)}
    for _ in range(300):
        t = r.choice([" ", "-", ""]).join(r.choices(words, k=r.randrange(9)))
        assert toxicity.Lexicon(entries).measure(t) == pytest.approx(plain_measure(t, entries, toxicity.EXCEPTIONS)), t


def test_copied_texts_make_no_lexicon(spark):
    """A group of copies, most of it toxic, has ordinary words of its own: clean documents with these are left alone."""
    r = random.Random(17)
    plain, own = [f"w{chr(97 + i % 26)}{chr(97 + i // 26)}y" for i in range(400)], [f"copy{chr(97 + i % 26)}{chr(97 + i // 26)}z" for i in range(60)]
    rows = [(i, " ".join(r.choices(plain, k=60) + (["nastyword"] if i % 9 == 0 else [])), int(i % 9 == 0)) for i in range(900)]
    rows += [(1000 + i, " ".join(own + (["vilething"] if i < 40 else [])), int(i < 40)) for i in range(64)]
    rows += [(2000 + i, " ".join(r.choices(plain, k=40) + r.choices(own, k=15)), 0) for i in range(600)]
    docs, labels = spark.createDataFrame([x[:2] for x in rows], "doc_id long, text string"), spark.createDataFrame([(x[0], x[2]) for x in rows], "doc_id long, toxic int")
    entries = toxicity.learn(docs, labels).entries
    assert {"nast", "vile"} <= {e[:4] for e in entries} and sum(w in entries for w in own) <= len(own) / 10
    assert toxicity.score(docs, labels).filter("doc_id >= 2000 AND predicted = 1").count() == 0


def test_toxicity_odd_rows(spark, odd_docs, empty_docs, marked):
    labels = marked[1].unionByName(spark.createDataFrame([(None, 1), (3, None)], "doc_id long, toxic int"))
    got = toxicity.score(odd_docs, labels)
    assert got.count() == odd_docs.count() and got.filter("score IS NULL OR score < 0 OR score > 1").count() == 0
    assert toxicity.reject(odd_docs, labels).columns == odd_docs.columns
    assert toxicity.score(empty_docs, labels).count() == 0
    assert toxicity.score(odd_docs, labels.limit(0)).filter("predicted = 1").count() == 0


# ---- language model


def test_pseudo_likelihood_by_hand():
    common = [("a", 5), ("b", 3)]
    net = {k: v.astype(np.float32) for k, v in maskedlm.start(common, 4).items()}
    numbers = maskedlm.Numbers([w for w, _ in common]).of(["a b zz a", "", None, "b"])
    flat, at, text = maskedlm.windows(numbers)
    got = maskedlm.log_probabilities(net, flat, at)
    assert list(np.bincount(text, minlength=4)) == [4, 0, 0, 1]
    assert got[:4] == pytest.approx(plain_logs(net, numbers[0]), abs=1e-4)


def plain_logs(net, classes):
    """Log-probability of each class number of a text, a position at a time."""
    padded, out = [0, 0, *map(int, classes), 0, 0], []
    for i in range(len(classes)):
        h = np.tanh(net["b"] + sum(net["E"][k][padded[2 + i + o]] for k, o in enumerate(maskedlm.PLACES)))
        group, member = divmod(padded[2 + i], maskedlm.MEMBERS)
        own = slice(group * maskedlm.MEMBERS, (group + 1) * maskedlm.MEMBERS)
        z, y = net["V"] @ h + net["d"], net["U"][own] @ h + net["c"][own]
        out.append(z[group] - np.log(np.exp(z).sum()) + y[member] - np.log(np.exp(y).sum()))
    return out


def test_whole_query_against_a_plain_version(spark):
    r = random.Random(6)
    words = [f"{a}{b}" for a in "bcdfg" for b in ("an", "ing", "ed", "o")]
    texts = [" ".join(r.choices(words, range(20, 0, -1), k=r.randrange(60))) for _ in range(30)] + [None, "", "zz only once"]
    rows = list(enumerate(texts))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    counts = maskedlm.word_counts(docs).persist()
    common, net = maskedlm.train(docs, counts=counts)
    n = {}
    for t in texts:
        for w in (t or "").split():
            n[w] = n.get(w, 0) + 1
    assert {x["word"]: x["n"] for x in counts.collect()} == {int(hash_texts([w])[0].view(np.int64)[0]): k for w, k in n.items()}
    number = {w: int(maskedlm.Numbers(common).of([w])[0][0]) for w in n}
    # training, a target at a time in double precision: one shard, documents by digest
    order = [x["doc_id"] for x in docs.orderBy(F.xxhash64(F.coalesce("text", F.lit("")).alias("t")), "doc_id").collect()]
    plain = maskedlm.start([(w, n_) for w, n_ in maskedlm.common_words(counts)], 0)
    for turn in range(maskedlm.ROUNDS):
        memory = maskedlm.fresh_memory(plain)
        flat, at, _ = maskedlm.windows([np.array([number[w] for w in (texts[i] or "").split()], np.uint16) for i in order if (texts[i] or "").split()])
        at = maskedlm.targets(at, turn)
        for k in range(0, len(at), maskedlm.BATCH):
            plain = plain_step(plain, memory, flat.astype(int), at[k : k + maskedlm.BATCH])
    for k in net:
        assert np.abs(net[k] - plain[k]).max() < 2e-3, k
    got = {x["doc_id"]: x for x in maskedlm.pseudo_likelihood(docs).collect()}
    assert len(got) == len(rows)
    for i, t in rows:
        own = (t or "").split()
        want = sum(plain_logs(net, [number[w] for w in own])) if own else 0.0  # every word here has a class of its own
        assert got[i]["n_tokens"] == len(own) and got[i]["pll"] == pytest.approx(want, abs=2e-3) and got[i]["mean_pll"] == pytest.approx(want / max(len(own), 1), abs=1e-3)


def plain_step(net, memory, flat, at):
    """A step by numerical care only: every position's gradient is written out and added."""
    grads = {k: np.zeros_like(v) for k, v in net.items()}
    for i in at:
        h = np.tanh(net["b"] + sum(net["E"][k][flat[i + o]] for k, o in enumerate(maskedlm.PLACES)))
        group, member = divmod(int(flat[i]), maskedlm.MEMBERS)
        own = slice(group * maskedlm.MEMBERS, (group + 1) * maskedlm.MEMBERS)
        dh = 0
        for vec, bias, rows, hit in (("V", "d", slice(None), group), ("U", "c", own, member)):
            z = net[vec][rows] @ h + net[bias][rows]
            p = np.exp(z - z.max())
            p /= p.sum()
            p[hit] -= 1
            grads[vec][rows] += np.outer(p, h) / len(at)
            grads[bias][rows] += p / len(at)
            dh = dh + p @ net[vec][rows]
        da = dh * (1 - h * h) / len(at)
        grads["b"] += da
        for k, o in enumerate(maskedlm.PLACES):
            grads["E"][k][flat[i + o]] += da
    for k, g in grads.items():
        memory[k] += g * g
    return {k: net[k] - maskedlm.RATE * grads[k] / (np.sqrt(memory[k]) + 1e-6) for k in net}


def test_partitioning_changes_nothing(spark, monkeypatch):
    monkeypatch.setattr(maskedlm, "SHARD_WORDS", 4000)  # several shards
    r = random.Random(11)
    texts = [" ".join(f"w{int(r.paretovariate(0.6))}" for _ in range(r.randrange(80))) for _ in range(150)]
    docs = spark.createDataFrame(list(enumerate(texts)) + [(3, texts[3]), (None, texts[4]), (None, texts[4])], "doc_id long, text string")
    runs = [sorted((x["doc_id"] or -1, x["n_tokens"], x["mean_pll"]) for x in maskedlm.pseudo_likelihood(d).collect()) for d in (docs.repartition(1), docs.repartition(7), docs.orderBy(F.desc("text")))]
    assert maskedlm.shards_for(sum(len(t.split()) for t in texts)) > 3
    for other in runs[1:]:
        assert [x[:2] for x in other] == [x[:2] for x in runs[0]]
        assert max(abs(a[2] - b[2]) for a, b in zip(runs[0], other, strict=True)) <= 2e-6


def test_gradient():
    net = maskedlm.start([("a", 5), ("b", 3)], 4)
    r = np.random.default_rng(0)
    flat = np.concatenate([[0, 0], r.integers(1, 60, 30), [0, 0]]).astype(np.uint16)
    at = np.arange(2, 32)
    loss = lambda n: -maskedlm.log_probabilities(n, flat, at).mean()
    memory = {k: np.ones_like(v) for k, v in net.items()}
    before = {k: v.copy() for k, v in net.items()}
    maskedlm.step(net, memory, flat, at)
    for name, index in (("V", (int(flat[4]) // maskedlm.MEMBERS, 2)), ("d", (1,)), ("U", (int(flat[5]), 3)), ("c", (int(flat[9]),)), ("b", (2,)), ("E", (1, int(flat[7]), 4))):
        grad = np.sqrt(memory[name][index] - 1)
        up = {k: v.copy() for k, v in before.items()}
        up[name][index] += 1e-5
        assert grad == pytest.approx(abs(loss(up) - loss(before)) / 1e-5, abs=1e-4)


def test_context_helps(spark):
    r = random.Random(2)
    docs = spark.createDataFrame([(i, " ".join(w for _ in range(40) for w in r.choice(["one two three", "red green blue"]).split())) for i in range(60)], "doc_id long, text string").repartition(2)
    common, net = maskedlm.train(docs, rounds=6)
    got = maskedlm.pseudo_likelihood(docs, (common, net))
    mean = got.agg(F.sum("pll") / F.sum("n_tokens")).first()[0]
    assert mean > -np.log(6) + 0.5  # six words, equally common
    shuffled = spark.createDataFrame([(1, "two blue one red green three " * 20), (2, "one two three red green blue " * 20)], "doc_id long, text string")
    s = {x["doc_id"]: x["mean_pll"] for x in maskedlm.pseudo_likelihood(shuffled, (common, net)).collect()}
    assert s[2] > s[1]


def test_lm_odd_rows(odd_docs, empty_docs):
    got = maskedlm.pseudo_likelihood(odd_docs).collect()
    assert len(got) == odd_docs.count() and all((r["n_tokens"] == 0) == (r["pll"] == 0) for r in got)
    assert maskedlm.pseudo_likelihood(empty_docs).count() == 0


def test_every_word_has_its_own_probability(spark):
    frequent = " ".join(f"w{i:03d}" for i in range(maskedlm.SIZE))  # takes all classes of single words
    texts = [frequent] * 20 + ["wording wording fording", "wording zzxing", "fording", None, ""]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    counts = maskedlm.word_counts(docs).persist()
    model = maskedlm.train(docs, counts=counts)
    probe = spark.createDataFrame([(0, "wording"), (1, "zzxing"), (2, "unseening")], "doc_id long, text string")
    p = {r["doc_id"]: r["pll"] for r in maskedlm.pseudo_likelihood(probe, model, counts).collect()}
    assert p[0] - p[1] == pytest.approx(np.log(3), abs=1e-3) and p[1] == pytest.approx(p[2], abs=1e-3)  # one ending, other counts
    number = maskedlm.Numbers(model[0]).of(["wording"])[0][0]
    alike = [r for r in counts.collect() if maskedlm.number_of(r["bucket"]) == number and r["word"] not in model[0]]
    net = {k: v.astype(np.float32) for k, v in model[1].items()}
    one = maskedlm.log_probabilities(net, np.array([0, 0, number, 0, 0], np.uint16), np.array([2]))[0]
    assert p[0] == pytest.approx(one + np.log(3 / (1 + sum(r["n"] for r in alike))), abs=1e-3)
    at_hand, joined = (sorted(map(tuple, maskedlm.pseudo_likelihood(docs, model, counts, known).collect())) for known in (maskedlm.KNOWN, 0))
    assert len(at_hand) == len(texts) and [x[:2] for x in at_hand] == [x[:2] for x in joined]
    assert [x[2] for x in at_hand] == pytest.approx([x[2] for x in joined], abs=2e-4)


def test_registered_rounds_visit_every_position(spark):
    at = np.arange(2, 1003)
    seen = np.concatenate([maskedlm.targets(at, turn) for turn in range(maskedlm.ROUNDS)])
    assert sorted(set(seen.tolist())) == at.tolist()
    r = random.Random(2)
    docs = spark.createDataFrame([(i, " ".join(w for _ in range(40) for w in r.choice(["one two three", "red green blue"]).split())) for i in range(600)], "doc_id long, text string").repartition(2)
    mean = maskedlm.pseudo_likelihood(docs).agg(F.sum("pll") / F.sum("n_tokens")).first()[0]
    assert mean > -np.log(6) + 0.5
