from __future__ import annotations

import random
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from copresence.llm import decontam, neardup
from copresence.llm.common import components
from copresence.llm.words import hash_words, mix, shingles, text_hashes, weighted_similarity, words


def counted(text):
    w = words(text)
    w = w if len(w) >= 5 or not w else w + ["\0"] * (5 - len(w))
    return Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))


def alike(a, b):
    low = sum((a & b).values())
    return low / (sum(a.values()) + sum(b.values()) - low) if a or b else 0.0


def brute_classes(rows, least=0.8):
    """rows (id, text) -> id: least id of its class."""
    parent = {i: i for i, _ in rows}

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    sets = [(i, t or "", counted(t)) for i, t in rows]
    for x, (i, t, c) in enumerate(sets):
        for j, u, d in sets[:x]:
            if t == u or alike(c, d) >= least:
                a, b = find(i), find(j)
                parent[max(a, b)] = min(a, b)
    return {i: find(i) for i in parent}


def vary(r, text, edits):
    w = text.split()
    for _ in range(edits):
        w[r.randrange(len(w))] = f"edit{r.randrange(10**6)}"
    return " ".join(w)


def test_word_numbers():
    texts = ["The  quick\tBROWN", None, "", "a\x1cb c　d é", " x "]
    h, n, tails = hash_words(texts)
    assert n.tolist() == [len(words(t)) for t in texts] == [3, 0, 0, 5, 1] and len(tails) == len(h)
    assert text_hashes("brown fox")[0] == h[2] and len(set(h.tolist())) == len(h)


def test_similarity_is_that_of_multisets():
    r = random.Random(1)
    for _ in range(50):
        a, b = (" ".join(r.choices("abc", k=r.randrange(1, 30))) for _ in range(2))
        assert weighted_similarity(shingles(text_hashes(a)), shingles(text_hashes(b))) == pytest.approx(alike(counted(a), counted(b)))


def test_signatures_agree_as_often_as_sets_are_alike():
    r = np.random.default_rng(2)
    gaps = []
    for _ in range(200):
        n, k = int(r.integers(3, 300)), float(r.random())
        a = mix(r.integers(0, 1 << 62, n).astype(np.uint64))
        b = np.concatenate([a[: int(k * n)], mix(r.integers(0, 1 << 62, n - int(k * n)).astype(np.uint64)), a[: n // 5]])
        gaps.append((neardup.signature(a) == neardup.signature(b)).mean() - weighted_similarity(a, b))
    assert abs(np.mean(gaps)) < 0.01 and np.std(gaps) < 0.06


def test_signatures_of_real_weights():
    r = np.random.default_rng(5)
    gaps = []
    for _ in range(200):
        n = int(r.integers(1, 120))
        e = mix(r.integers(0, 1 << 62, n).astype(np.uint64))
        a, b = (r.gamma(0.7, r.choice([0.5, 3, 40]), n) + 0.05 for _ in range(2))
        b = np.where(r.random(n) < 0.7, a, b)
        gaps.append((neardup.signature(e, a) == neardup.signature(e, b)).mean() - np.minimum(a, b).sum() / np.maximum(a, b).sum())
    assert abs(np.mean(gaps)) < 0.015 and np.std(gaps) < 0.06
    one, heavy = mix(np.arange(3, dtype=np.uint64)), np.array([1e6, 3.5, 0.25])
    assert (neardup.signature(one, heavy) == neardup.signature(one[::-1], heavy[::-1])).all()
    assert neardup._darts(one, heavy, 0, 1 << 21).size < 50  # a heavy element is a row of cells a piece, not one a unit
    for bad in ([], [0.0], [-1.0, 2.0]):
        with pytest.raises(ValueError):
            neardup.signature(one[: len(bad)], np.array(bad))


def test_class_numbers_are_unique(spark):
    rows = [(1, "text number one here again"), (1, "quite another text b"), (2, "text number one here again"), (3, "quite another text b"), (None, "no id for this text"), (None, "no id for this text"), (7, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = neardup.classes(docs).collect()
    assert len(got) == len(rows) and len({(r["class_id"], r["digest"]) for r in got}) == len({r["class_id"] for r in got}) == 4
    assert all(r["class_id"] is not None for r in got) and [r["class_id"] for r in got if r["doc_id"] == 7] == [7]
    kept = sorted((r["doc_id"] or 0, r["text"] or "") for r in neardup.keep_one(docs).collect())
    assert kept == [(0, "no id for this text"), (1, "quite another text b"), (1, "text number one here again"), (7, "")]


def test_without_the_sketch(spark):
    r = random.Random(3)
    shared = " ".join(f"p{i}" for i in range(60))
    rows = [(i, shared + " " + " ".join(f"u{r.randrange(30)}" for _ in range(r.choice([20, 60])))) for i in range(40)]
    got = {x["doc_id"]: x["class_id"] for x in neardup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), slack=None).collect()}
    assert got == brute_classes(rows)


@pytest.mark.parametrize("seed", [0, 1])
def test_classes_against_all_pairs(spark, seed):
    r = random.Random(seed)
    rows = []
    for g in range(12):
        base = " ".join(f"w{r.randrange(3000)}" for _ in range(r.choice([4, 12, 60, 150])))
        family = [base]
        for _ in range(r.choice([0, 3, 25])):
            family.append(vary(r, r.choice(family), r.choice([0, 1, 1, 2, 5])))  # copies of copies
        rows += family
    shared = " ".join(f"p{i}" for i in range(60))  # one passage in many documents
    rows += [shared + " " + " ".join(f"u{r.randrange(10**6)}" for _ in range(r.choice([20, 60]))) for _ in range(30)]
    rows = [(i, t) for i, t in enumerate(r.sample(rows, len(rows)))] + [(900, None), (901, ""), (902, "short one")]
    got = {x["doc_id"]: x["class_id"] for x in neardup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == brute_classes(rows)


def test_near_duplicates_odd_rows(spark, odd_docs, empty_docs):
    got = neardup.near_duplicates(odd_docs).collect()
    assert len(got) == odd_docs.count()
    assert [r["class_id"] for r in got if r["doc_id"] == 7] == [1] and {r["copies"] for r in got if r["doc_id"] == 1} == {3}
    kept = neardup.keep_one(odd_docs)
    assert kept.columns == odd_docs.columns
    ids = Counter(r["doc_id"] for r in kept.collect())
    assert ids[1] == 1 and 7 not in ids and ids[8] == 1 and 9 not in ids and ids[4] == 1 and sum(ids.values()) == len({r["text"] or "" for r in odd_docs.collect()})
    assert neardup.near_duplicates(empty_docs).count() == 0 and neardup.keep_one(empty_docs).count() == 0


def test_components(spark):
    r = random.Random(4)
    edges = [(i, i + 1) for i in range(40)] + [(100 + r.randrange(60), 100 + r.randrange(60)) for _ in range(40)] + [(500, 500 + i) for i in range(1, 30)]
    got = {x["id"]: x["root"] for x in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    parent = {n: n for e in edges for n in e}

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for a, b in edges:
        a, b = sorted((find(a), find(b)))
        parent[b] = a
    assert got == {n: find(n) for e in edges if e[0] != e[1] for n in e}


# ---- benchmark passages


def test_fingerprints_and_index_are_exact():
    r = np.random.default_rng(0)
    pairs = mix(r.integers(0, 1 << 62, 400).astype(np.uint64))
    sizes = [1, 2, 4, 7, 8, 12, 24, 44, 48, 96, 399, 400, 401]
    found = dict(decontam.fingerprints(pairs, sizes))
    assert sorted(found) == sizes[:-1]
    for n, got in found.items():
        assert len(got) == 400 - n + 1
        for k in {0, 5 % len(got), len(got) - 1}:
            bits = np.unpackbits(pairs[k : k + n].view(np.uint8).reshape(n, 8), axis=1).sum(0) > n // 2
            assert np.packbits(bits).view(np.uint64)[0] == got[k]
    vocabulary = [f"w{i}" for i in range(300)]
    rr = random.Random(1)
    index = decontam.Index([(i, " ".join(rr.choices(vocabulary, k=rr.randrange(9, 170)))) for i in range(60)])
    assert {b.radius for g in index.groups.values() for b, _, _ in g} == {decontam.EXACT, decontam.RADIUS}
    for group in index.groups.values():
        for blocks, _, _ in group:
            own = blocks.prints
            flipped = np.array([int(p) ^ sum(1 << b for b in rr.sample(range(64), rr.randrange(14))) for p in np.repeat(own, 5)], np.uint64)
            at, which = blocks.near(flipped)
            want = {(i, j) for i in range(len(flipped)) for j in range(len(own)) if int(flipped[i] ^ own[j]).bit_count() <= blocks.radius}
            assert set(zip(at.tolist(), which.tolist(), strict=True)) == want


def test_windows_are_of_the_items_size():
    for n in (5, 8, 40, 100, 1000, 10_000, 100_000):
        first, size, _ = decontam.windows_of(n, 0.8)[0]
        assert size + 1 >= 0.65 * n and 0 <= first and first + size < n
        runs = decontam.windows_of(n, 0.8)[1:]
        assert all(b[0] - a[0] - a[1] - 1 >= 4 for a, b in zip(runs, runs[1:], strict=False)) and all(f + s < n for f, s, _ in runs)
        assert not runs or 4 * len(runs) > decontam.allowed(n, 0.8)


def test_item_sized_windows_alone_find_most(monkeypatch):
    own = decontam.windows_of
    monkeypatch.setattr(decontam, "windows_of", lambda n, least: own(n, least)[:1])
    r, found = random.Random(3), []
    for n in (60, 100, 300, 1000):
        for _ in range(25):
            item = [f"w{r.randrange(50_000)}" for _ in range(n)]
            near = list(item)
            for p in range(7, n - 7, 48):  # as many changes as 0.8 leaves room for
                near[p + r.randrange(5)] = f"x{r.randrange(50_000)}"
            text = " ".join([f"a{r.randrange(9999)}" for _ in range(50)] + near)
            if alike(counted(" ".join(near)), counted(" ".join(item))) >= 0.8:
                found.append(bool(decontam.Index([(1, " ".join(item))]).search([text])))
    assert len(found) > 50 and sum(found) / len(found) > 0.9


def brute_contaminated(docs, items, least=0.8):
    out = {}
    for d, t in docs:
        w = words(t)
        for i, q in items:
            n = len(words(q))
            if n < 5:
                if n and any(w[s : s + n] == words(q) for s in range(len(w))):
                    out[d, i] = 1.0
                continue
            best = max([alike(counted(" ".join(w[s : s + n])), counted(q)) for s in range(max(1, len(w) - 4))])
            if best >= least:
                out[d, i] = best
    return out


def test_contamination_against_all_windows(spark):
    r = random.Random(7)
    word = lambda: f"w{r.randrange(500)}"
    items = [(i, " ".join(word() for _ in range(n))) for i, n in enumerate([5, 6, 9, 16, 20, 33, 49, 59, 80, 100, 130])] + [(50, "too short"), (51, None), (52, ""), (53, "w7"), (54, "w3 w4 w5")]
    docs = []
    for k in range(150):
        w = [word() for _ in range(r.randrange(0, 160))]
        if k % 2:
            q = r.choice(items[:11])[1].split()
            for _ in range(r.choice([0, 0, 1, 1, 2, 3])):
                p = r.choice([0, len(q) - 1, r.randrange(len(q))])
                q = r.choice([q[:p] + [word()] + q[p + 1 :], q[:p] + q[p + 1 :], q[:p] + [word()] + q[p:]])
            at = r.randrange(len(w) + 1)
            w[at:at] = q
        elif k % 10 == 0:
            w[len(w) // 2 : len(w) // 2] = ["w3", "w4", "w5"]
        docs.append((k, " ".join(w)))
    d, b = spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    got = {(x["doc_id"], x["item_id"]): x["similarity"] for x in decontam.contaminated(d, b).collect()}
    want = brute_contaminated(docs, items)
    assert len(want) > 60 and got == pytest.approx(want)
    assert {(x["doc_id"], x["item_id"]) for x in decontam.contaminated(d, b, at_once=4).collect()} == set(want)
    assert {(x["doc_id"], x["item_id"]) for x in decontam.contaminated(d, b, least_words=5).collect()} == {k for k in want if k[1] < 50}
    left = {x["doc_id"] for x in decontam.drop_contaminated(d, b, at_once=4).collect()}
    assert left == {k for k, _ in docs} - {x for x, _ in want}


def test_contamination_odd_rows(spark, odd_docs, empty_docs):
    b = spark.createDataFrame([(1, "plain text of several words here"), (None, "text without an id but words"), (3, None)], "item_id long, text string")
    got = sorted((x["doc_id"] or -1, x["item_id"] or -1) for x in decontam.contaminated(odd_docs, b).collect())
    assert got == [(-1, -1), (1, 1), (1, 1), (7, 1)]
    assert decontam.drop_contaminated(odd_docs, b).count() == odd_docs.count() - 4 and decontam.drop_contaminated(odd_docs, b).columns == odd_docs.columns
    assert decontam.contaminated(empty_docs, b).count() == 0 and decontam.contaminated(odd_docs, b.limit(0)).count() == 0


# ---- pipeline


def test_stages(spark, tmp_path):
    import corpus_pipeline

    r = random.Random(9)
    plain = [f"w{i}" for i in range(400)]
    item = " ".join(r.choices(plain, k=30))
    rows, toxic = [], set()
    for i in range(300):
        t = " ".join(r.choices(plain, k=r.randrange(30, 90)))
        if i % 10 == 0:
            t, _ = t + " " + " ".join(["nastyword", "vilething"]), toxic.add(i)
        elif i % 10 == 1:
            t = t + " " + item + " tail words"
        elif i % 10 == 2 and i > 20:
            t = rows[i - 9][1]
        rows.append((i, t, "en", f"s{i % 4}", len(t)))
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, int(i in toxic)) for i in range(300)], "doc_id long, toxic int").withColumn("quality", F.lit(1)).write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([(0, item)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "near_duplicates", "decontamination", "mixing", "sharding"]
    now = docs
    seen = []
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, now, str(tmp_path))
        out.write.parquet(f"{tmp_path}/{k}")
        now = spark.read.parquet(f"{tmp_path}/{k}")
        seen.append({x["doc_id"] for x in now.collect()})
        assert now.columns[:5] == docs.columns
    assert seen[0] == {i for i, *_ in rows} - toxic
    cls = brute_classes([(i, t) for i, t, *_ in rows if i in seen[0]])
    assert seen[1] == set(cls.values())
    assert seen[2] == {i for i in seen[1] if item not in rows[i][1]}
    assert seen[3] <= seen[2] and seen[4] == seen[3] and now.columns[5:] == ["slot", "shard"]
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == now.count()


def test_pipeline_odd_rows(spark, odd_docs, empty_docs, tmp_path):
    import corpus_pipeline

    labels = spark.createDataFrame([(None, 1), (3, None), (8, 0)], "doc_id long, toxic int")
    items = spark.createDataFrame([(1, "plain text of several words here"), (None, None)], "item_id long, text string")
    for name, docs, some_labels, some_items in (("odd", odd_docs, labels, items), ("none", empty_docs, labels.limit(0), items.limit(0)), ("bare", odd_docs, labels.limit(0), items.limit(0))):
        for table, rows in (("documents", docs), ("labels", some_labels), ("benchmark", some_items)):
            rows.write.parquet(f"{tmp_path}/{name}/{table}.parquet")
        out = corpus_pipeline.run(spark, f"{tmp_path}/{name}")
        got = out.collect()
        assert out.columns == [c for c in docs.columns if c not in ("slot", "shard")] + ["slot", "shard"]
        held = {r["text"] for r in got}
        if name == "none":
            assert not got
        else:
            assert ("plain text of several words here" in held) == (name == "bare") and None not in held and "" not in held
            assert all(r["slot"] is not None and r["shard"] is not None for r in got) and "é ü ñ 中文 \U0001f600" in held
