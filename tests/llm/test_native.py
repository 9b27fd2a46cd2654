from __future__ import annotations

import hashlib
import random
import re
from collections import Counter, defaultdict

import pytest

from copresence.llm import linededup, mixing, pii, sharding


# ---- sharding


def test_table_is_even_and_stable():
    names = [f"s{i}" for i in range(20)]
    before = sharding.lookup_table(names, 4099)
    share = Counter(before)
    assert max(share.values()) - min(share.values()) <= 1
    after = sharding.lookup_table(names[:-1], 4099)
    gone = sum(o == 19 for o in before) / 4099
    assert sharding.moved_slots(before, after) < 4 * gone
    assert Counter(sharding.lookup_table(["a", "b"], 1009, [1, 3]))[1] > 700
    for bad in ((["a", "a"], 11), ([], 11), (["a"], 12)):
        with pytest.raises(ValueError):
            sharding.lookup_table(*bad)


def test_placement(spark, odd_docs, empty_docs):
    got = sharding.assign_shards(odd_docs)
    assert got.count() == odd_docs.count() and got.filter("slot IS NULL OR shard IS NULL").count() == 0
    owner = sharding.lookup_table()
    for r in got.collect():
        want = int(hashlib.md5(("" if r["doc_id"] is None else str(r["doc_id"])).encode()).hexdigest()[:15], 16) % sharding.SLOTS
        assert r["slot"] == want and r["shard"] == owner[want]
    assert sharding.assign_shards(empty_docs).count() == 0


def test_written_shards(spark, odd_docs, tmp_path):
    sharding.write_shards(odd_docs, f"{tmp_path}/out", files_per_shard=2)
    assert spark.read.parquet(f"{tmp_path}/out").count() == odd_docs.count()


# ---- mixing


def brute_mix(rows):
    """rows (doc_id, text, source) -> source: (size, target)."""
    size = lambda t: len(re.findall(r"[^\x20\x09-\x0D]+", t or ""))
    total = defaultdict(int)
    for _, t, s in rows:
        total[s] += size(t)
    order = sorted(total, key=lambda s: (s is None, s or ""))
    w = {s: (1, 2, 3)[i % 3] for i, s in enumerate(order)}
    target, open_ = {}, set(order)
    left = float(sum(total.values()))
    while True:
        level = left / sum(w[s] for s in open_) if open_ else 0
        full = {s for s in open_ if level * w[s] > 3 * total[s]}
        if not full:
            break
        for s in full:
            target[s] = 3.0 * total[s]
            left -= target[s]
        open_ -= full
    return {s: (total[s], target.get(s, level * w[s])) for s in order}


@pytest.mark.parametrize("rows", [
    [(i, "w " * (i % 7), f"s{i % 5}") for i in range(60)],
    [(1, "a b c", "x"), (2, "d", "y"), (3, None, None), (4, "e " * 50, None)],
    [(1, "a", "x"), (2, "b " * 1000, "y"), (3, "c", "z")],
    [(1, "", "x"), (2, None, "y")],
])
def test_mix_meets_targets(spark, rows):
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = mixing.mix(docs).collect()
    want = brute_mix(rows)
    assert len(got) == len(rows)
    taken = defaultdict(int)
    for r in got:
        assert (r["source_size"], r["target"]) == (want[r["source"]][0], pytest.approx(want[r["source"]][1]))
        assert 0 <= r["taken"] <= 3 * r["size"]
        taken[r["source"]] += r["taken"]
    for s, (_, target) in want.items():
        assert taken[s] == int(target + 1e-9)
    out = mixing.mixed_documents(docs).collect()
    words = defaultdict(int)
    for r in out:
        words[r["source"]] += len((r["text"] or "").split())
    assert dict(words) == {s: n for s, n in taken.items() if n}


def test_mixed_documents_take_each_row_once(spark):
    rows = [(1, "a b c d", "x")] * 5 + [(2, "e f g h", "x"), (2, "i j k l", "x"), (None, "m n o", None), (None, "m n o", None), (9, " ".join("w" * 60), "y")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    plan = defaultdict(list)
    for r in mixing.mix(docs).collect():
        plan[r["doc_id"], r["source"], r["size"]].append(r["taken"])
    emitted = defaultdict(int)
    for r in mixing.mixed_documents(docs).collect():
        emitted[r["doc_id"], r["source"]] += len(r["text"].split())
    assert {k[:2]: sum(v) for k, v in plan.items() if sum(v)} == dict(emitted)
    both = [r["text"] for r in mixing.mixed_documents(docs).filter("doc_id = 2").collect()]
    assert len({t.split()[0] for t in both}) == sum(t > 0 for t in plan[2, "x", 4])  # texts of one id and size are told apart
    assert mixing.ranges_for(0) == mixing.RANGES and mixing.ranges_for(10**9) > 10**9 // mixing.RANGE_ROWS // 2


def test_mix_odd_rows(odd_docs, empty_docs):
    assert sorted(map(str, mixing.mix(odd_docs).collect())) == sorted(map(str, mixing.mix(odd_docs.repartition(3)).collect()))
    assert mixing.mix(odd_docs).count() == odd_docs.count()
    assert mixing.mixed_documents(odd_docs).columns == odd_docs.columns
    assert mixing.mix(empty_docs).count() == 0 and mixing.mixed_documents(empty_docs).count() == 0


# ---- personal data

BASE = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    "card": r"[0-9]([\x20-]?[0-9])+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}


def luhn(d):
    return sum(sum(divmod(2 * int(c), 10)) if i % 2 else int(c) for i, c in enumerate(reversed(d))) % 10 == 0


def base_spans(text):
    out = []
    for kind, pattern in BASE.items():
        for m in re.finditer(pattern, text):
            d = re.sub("[^0-9]", "", m[0])
            ok = {"email": True, "ip": kind != "ip" or all(int(p) <= 255 for p in m[0].split(".")), "card": 16 <= len(d) <= 19 and luhn(d), "phone": 8 <= len(d) <= 15}[kind]
            if ok:
                out.append(f"{kind}:{m.start()}:{m.end()}")
    return out


TEXTS = [
    "mail a.b@c.de and x@y.z.w, not @home", "a@b.c@d.e f%g@h-i.jk_x@l.m", "hosts 1.2.3.4.5.6.7.8 256.1.1.1 0001.2.3.4 1.2.3", "card 4111 1111 1111 1111 and 4111-1111-1111-1112 x", "12345678901234567890 4111111111111111 5500 0000 0000 0004-1",
    "+1 (555) 123-4567 +49 30 1234567890123456 +5 5 +1.2", "+12345678+87654321", "é 😀 a@b.co 😀 +4912345678", "", "IBAN GB82 WEST 1234 5698 7654 32 and DE89370400440532013000, bad GB82WEST12345698765433", "your ssn 078-05-1120 or 000-12-3456",
    "9" * 5000, "a" * 50_000, "1.1.1." * 2000, "a@b" + ".c" * 20_000, "4 1" * 1000,
]


def test_spans_against_plain_patterns(spark):
    docs = spark.createDataFrame(list(enumerate(TEXTS)), "doc_id long, text string")
    for r in pii.pii_report(docs).collect():
        want = base_spans(TEXTS[r["doc_id"]])
        own = [s for s in r["spans"].split(",") if s and s.split(":")[0] in BASE]
        assert own == want, r["doc_id"]
        assert r["base_sha256"] == hashlib.sha256(",".join(want).encode()).hexdigest()
        for kind in BASE:
            assert r[f"n_{kind}"] == sum(s.startswith(kind) for s in want)
        added = [TEXTS[r["doc_id"]][int(s.split(":")[1]) : int(s.split(":")[2])] for s in r["spans"].split(",") if s and s.split(":")[0] not in BASE]
        assert added == {9: ["GB82 WEST 1234 5698 7654 32", "DE89370400440532013000"], 10: ["078-05-1120"]}.get(r["doc_id"], [])


def test_pii_odd_rows(odd_docs, empty_docs):
    assert pii.pii_report(odd_docs).count() == odd_docs.count() and pii.pii_report(empty_docs).count() == 0
    assert pii.mask_pii(odd_docs).columns == odd_docs.columns


def test_masking(spark):
    docs = spark.createDataFrame([(1, "to a@b.co now"), (2, None)], "doc_id long, text string")
    assert {r["doc_id"]: r["text"] for r in pii.mask_pii(docs).collect()} == {1: "to ###### now", 2: None}


# ---- lines


def row_key(i, t):
    return (linededup.FIRST_ID if i is None else i, hashlib.md5((t or "").encode()).hexdigest())


def brute_lines(rows):
    """(id, text digest, line) of every line that goes, chunk by chunk and pair by pair."""
    chunks, pairs = defaultdict(list), defaultdict(list)
    for key, lines in sorted({row_key(i, t): (t or "").split("\n") for i, t in rows}.items()):
        h = [int(hashlib.md5(x.encode()).hexdigest()[:6], 16) for x in lines]
        falls = [((h[k - 1] * linededup.BASE if k else 0) + h[k]) % linededup.PRIME % linededup.DIVISOR == 0 for k in range(len(lines))]
        start = 0
        for k in range(len(lines)):
            if (k and falls[k] and not falls[k - 1]) or k == len(lines) - 1:
                if k > start:
                    chunks[tuple(lines[start : k + 1])].append((key, start))
                start = k + 1
        for k in range(len(lines) - 1):
            pairs[lines[k], lines[k + 1]].append((key, k))
    gone = {(*key, start + k) for text, places in chunks.items() for key, start in places[1:] for k in range(len(text))}
    met = {(*key, at + k) for places in pairs.values() if len(places) > 1 for key, at in places[1:] for k in (0, 1)}
    return gone | (met - {(*places[0][0], places[0][1] + k) for places in pairs.values() if len(places) > 1 for k in (0, 1)})


def gone_lines(docs):
    return {(r["doc_id"], r["row"], r["start"] + k) for r in linededup.lines_to_go(docs).collect() for k in range(r["n_lines"])}


def test_repeated_chunks_go_but_once(spark):
    block = "\n".join(f"shared line number {i}" for i in range(12))
    rows = [(i, "\n".join([f"own {i} {j}" for j in range(3)]) + "\n" + block + "\n" + f"end {i}") for i in range(6)] + [(6, block), (7, "one line"), (8, None), (9, "a\nb"), (10, "a\nb")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert gone_lines(docs) == brute_lines(rows) and linededup.removals(docs).count()
    kept = {r["doc_id"]: r["text"] for r in linededup.drop_repeats(docs).collect()}
    assert kept[0] == rows[0][1] and all(kept[i] == "\n".join([f"own {i} {j}" for j in range(3)] + [f"end {i}"]) for i in range(1, 6))
    assert kept[6] == "" and kept[8] is None and kept[7] == "one line" and (kept[9], kept[10]) == ("a\nb", "")


def test_repeated_runs_go_wholly(spark):
    r = random.Random(5)
    passage = "long line of a passage\nits second line"
    rows = [(i, "\n".join(r.choice("abcdef") for _ in range(r.randint(1, 6)))) for i in range(25)]
    rows += [(100 + i, f"before {i}\n{passage}\nafter {i}") for i in range(40)] + [(200, None), (201, ""), (202, "x\nx\nx\nx"), (203, "one line")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert gone_lines(docs) == brute_lines(rows)
    kept = {x["doc_id"]: x["text"] for x in linededup.line_dedup_report(docs).collect()}
    assert kept[100] == rows[25][1] and all(kept[100 + i] == f"before {i}\nafter {i}" for i in range(1, 40))
    assert kept[200] is None and len(kept) == len(rows)
    lines = {x for _, t in rows for x in (t or "").split("\n")}
    assert lines == {x for t in kept.values() for x in (t or "").split("\n")} | {""}  # of each line one stays


def test_texts_that_share_an_id_are_told_apart(spark):
    own = "\n".join(f"line {k} that stands nowhere else" for k in range(10))
    other = "\n".join(f"another line {k} of its own" for k in range(10))
    block = "\n".join(f"repeated line {k}" for k in range(8))
    rows = [(1, block), (2, "head\n" + block), (2, own), (None, block + "\ntail"), (None, other), (None, "a\nb"), (3, block), (3, block)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert gone_lines(docs) == brute_lines(rows)
    got = [(r["doc_id"], r["text"]) for r in linededup.line_dedup_report(docs).collect()]
    want = [(1, ""), (2, "head"), (2, own), (None, block + "\ntail"), (None, other), (None, "a\nb"), (3, ""), (3, "")]
    assert sorted(map(str, got)) == sorted(map(str, want))
    assert linededup.line_dedup_report(docs.filter("doc_id = 2")).filter("n_removed > 0").count() == 0


def test_lines_odd_rows(odd_docs, empty_docs):
    assert linededup.line_dedup_report(odd_docs).count() == odd_docs.count()
    assert linededup.line_dedup_report(empty_docs).count() == 0
    want = brute_lines([(r["doc_id"], r["text"]) for r in odd_docs.collect()])
    assert want and gone_lines(odd_docs) == want
    assert linededup.drop_repeats(odd_docs).columns[: len(odd_docs.columns)] == odd_docs.columns


def test_account_numbers_end_at_their_length(spark):
    one, two = "DE89370400440532013000", "GB82 WEST 1234 5698 7654 32"
    texts = [f"{one} 2024", f"{two} EUR 20", f"{one} {two} 7", f"IBAN {one}7"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: [texts[r["doc_id"]][int(a) : int(z)] for k, a, z in (x.split(":") for x in r["spans"].split(",") if x) if k == "iban"] for r in pii.pii_report(docs).collect()}
    assert got == {0: [one], 1: [two], 2: [one, two], 3: []}
