from __future__ import annotations

import random

import pytest
from pyspark.sql import functions as F

from copresence.model import Classes, validate_transactions
from copresence.operators import strips, transactions
from copresence.plans import queries
from copresence.plans.oracles import PATTERNS, chain, strip_tx_sql, words_sql
from copresence.plans.queries import QUERIES
from copresence.plans.shared import cut
from copresence.sources import workloads as data

SF = "/root/testdata/sf0.001"
DOCS = "doc_id long, text string, source string, lang string"


def odd_texts():
    r = random.Random(8)
    texts = [None, "", " \t\n", "a", " a\x0bb ", "É é zß 日本 a", "a" * 50 + " b", "x" * 21 + " " + "y" * 19 + " z"]
    texts += ["".join(r.choices("abcXYZ é日1.", k=r.randrange(300))).replace("1", r.choice(" \n\r\f")) for _ in range(60)]
    return texts + [" ".join(r.choices(["a", "bc", "def", "Ghij", "ü"], k=3000))]


def plain(text, core):
    out, at = [], 0
    for w in [w for w in __import__("re").split(r"[ \t\n\x0b\f\r]+", text or "") if w]:
        c = w[0].lower() if w[0].isascii() and w[0].isalpha() else None
        out.append((at, at + len(w), ord(c) - 96 if c else 0))
        at += len(w) + 1
    n = len(out)
    return [(i, *x) for i, x in enumerate(out) if not core or n <= i * 4 < 3 * n]


@pytest.mark.parametrize("core", [False, True])
@pytest.mark.parametrize("bytes_at_once", [1, 500, strips.BYTES])
def test_words_by_rows_against_plain_words(spark, monkeypatch, core, bytes_at_once):
    monkeypatch.setattr(strips, "BYTES", bytes_at_once)
    import pyarrow as pa

    texts = odd_texts()
    got = []
    for array in (pa.array(texts), pa.array(["odd", *texts])[1:]):
        for first, bytes_, offsets in strips._slices(array):
            row, number, lo, hi, bit = strips.words(bytes_, offsets, core)
            masks = {d: strips.row_masks(row, lo, hi, bit, d) for d in (0, 1, 20)}
            got += [(first + int(r), *map(int, x)) for r, *x in zip(row, number, lo, hi, bit, *masks.values(), strict=True)]
    want = []
    for i, t in enumerate(texts):
        own = plain(t, core)
        for j, (k, lo, hi, bit) in enumerate(own):
            near = own[max(0, j - 30) : j + 31]
            want.append((i, k, lo, hi, bit, *[sum(1 << b for b in {q[3] for q in near if q[1] <= hi + d and q[2] >= lo - d}) for d in (0, 1, 20)]))
    assert got == want * 2


def test_transactions_by_rows_are_those_of_the_join(spark):
    rows = [(i, t, f"s{i % 3}", "en") for i, t in enumerate(odd_texts())]
    twice = [(3, "once more a word", "s0", "en"), (3, "and yet", "s9", None)]
    for docs in (rows, [*rows, *twice, (None, "no id here", "s0", "en")]):
        df = spark.createDataFrame(docs, DOCS)
        for core in (False, True):
            units = data.word_strip(df, core)
            joined = transactions.buffer_span(units, 20)
            by_row = data.word_transactions(df, 20, core)
            listed = lambda x: sorted(map(tuple, x.collect()), key=str)
            if len(docs) == len(rows):  # places of words that share an id are open
                assert listed(by_row) == listed(joined)
                assert listed(data.word_patterns(df, 20, core)) == listed(transactions.patterns(joined))
            else:
                assert by_row.count() == joined.count() == data.word_patterns(df, 20, core).agg(F.sum("weight")).first()[0]


def test_texts_beyond_an_id_go_by_id(spark, monkeypatch):
    monkeypatch.setattr(strips, "IDS", 10)
    df = spark.createDataFrame([(1, "a " * 15, "s", "en"), (2, "b b", "s", "en")], DOCS)
    assert data._by_row_or_id(df)[0] is None


def shared_ids():
    r, texts = random.Random(3), odd_texts()
    rows = [(i // 3, t, f"s{i % 2}", "en") for i, t in enumerate(texts)]
    rows += [(900, t, f"s{i % 3}", "en") for i, t in enumerate(texts[8:40])]  # many texts of one id
    rows += [(901, "a b", "s0", "en"), (901, "cd " + "e" * 30 + " " + "f" * 19 + " g", "s0", "en"), (None, "no id here", "s0", "en"), (None, "nor here", "s0", "de")]
    return r.sample(rows, len(rows))


@pytest.mark.parametrize("sent, chars, bytes_at_once", [(data.SENT_IDS, data.ID_CHARS, strips.BYTES), (2, data.ID_CHARS, 300), (3, 1000, 1), (data.SENT_IDS, 0, 300)])
def test_texts_that_share_an_id_against_sql(spark, monkeypatch, sent, chars, bytes_at_once):
    import duckdb

    monkeypatch.setattr(data, "SENT_IDS", sent)
    monkeypatch.setattr(data, "ID_CHARS", chars)
    monkeypatch.setattr(strips, "BYTES", bytes_at_once)
    df = spark.createDataFrame(shared_ids(), DOCS)
    duck = duckdb.connect()
    duck.register("documents", df.toArrow())
    listed = lambda rows: sorted(map(tuple, rows), key=str)
    for core in (False, True):
        sql = lambda last: duck.execute(chain(words_sql(core=core), strip_tx_sql(), PATTERNS, last=last)).fetchall()
        columns = "grp, part, unit_id, lo, hi, bit"
        assert listed(data.word_strip(df, core).select(*columns.split(", ")).collect()) == listed(sql(f"SELECT {columns} FROM u"))
        want = sql("SELECT grp, unit_id, mask FROM tx")
        assert len(want) > 500
        assert listed(data.word_transactions(df.repartition(5), 20, core).collect()) == listed(want)
        assert listed(data.word_patterns(df, 20, core).collect()) == listed(sql("SELECT grp, mask, weight FROM pat"))


@pytest.mark.parametrize("sent", [data.SENT_IDS, 2])
def test_texts_that_share_an_id_are_shuffled_by_text(spark, monkeypatch, sent):
    monkeypatch.setattr(data, "SENT_IDS", sent)
    df = spark.createDataFrame(shared_ids(), DOCS)
    plan = data.word_patterns(df, 20)._jdf.queryExecution().executedPlan().toString()
    assert "Window" not in plan and "SortMergeJoin" not in plan and "Generate" not in plan and "MapInArrow" in plan


def test_words_are_neither_kept_nor_shuffled(spark):
    for name in ("strip_tx_d20", "approximate_patterns"):
        assert "SortMergeJoin" not in QUERIES[name](spark, SF)._jdf.queryExecution().toString()
    plan = data.strip_transactions(spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "MapInArrow" in plan


def test_checks_of_transactions_see_every_problem(spark):
    ids = [*range(-70, 70), *[7, 7, 40], None]
    units = spark.createDataFrame([(i,) for i in ids], "unit_id long")
    tx = spark.createDataFrame([(i, 1) for i in range(-60, 65)] + [(5, 0), (5, 8), (66, 2), (None, 1), (None, 1)], "unit_id long, mask long")
    known = {i for i in range(-60, 65)} | {66}
    got = {r["problem"]: r["n"] for r in validate_transactions(tx, units, Classes((1, 1, 1))).collect()}
    assert got == {"empty": 1, "unknown class": 1, "several transactions": 2, "no transaction": sum(i not in known for i in ids)}
    r = transactions.one_per_unit(units, tx).first()
    assert (r["units"], r["transactions"], r["missing"]) == (len(ids), tx.count(), got["no transaction"])
    none = tx.limit(0)
    assert {r["n"] for r in validate_transactions(none, units.limit(0), Classes((1,))).collect()} == {0}


@pytest.mark.parametrize("name", ["medoids", "degenerate_groups", "calinski_harabasz_by_k", "itemsets_unique_pattern_votes", "matrix_extract"])
def test_stages_of_queries_on_strips_hold_no_words(spark, monkeypatch, name):
    stages = []
    monkeypatch.setattr(queries, "cut", lambda df: stages.append(df) or cut(df))
    queries.forget()
    assert QUERIES[name](spark, SF).count() > 0
    assert stages and all("unit_id" not in df.columns for df in stages)
    made = next(df for df in stages if df.columns == ["grp", "mask", "weight"])
    plan = made._jdf.queryExecution().executedPlan().toString().split("== Initial Plan ==")[-1]
    below = plan[plan.index("Exchange ") :]  # the only exchange deals patterns that tasks have added up
    assert "MapInArrow" in below and "partial_sum" in below and below.count("Exchange ") == 1 and "Join" not in plan and "Window" not in plan


@pytest.mark.parametrize("name", ["calinski_harabasz_by_k", "degenerate_groups", "itemsets_unique_pattern_votes", "matrix_extract", "medoids"])
def test_queries_on_shared_ids_store_no_words(spark, monkeypatch, tmp_path, name):
    docs = spark.read.parquet(f"{SF}/documents.parquet").withColumn("doc_id", F.expr("doc_id DIV 3"))
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    stages = []
    monkeypatch.setattr(queries, "cut", lambda df: stages.append(df) or cut(df))
    queries.forget()
    assert QUERIES[name](spark, str(tmp_path)).count() > 0
    made = next(df for df in stages if df.columns == ["grp", "mask", "weight"])
    plan = made._jdf.queryExecution().executedPlan().toString().split("== Initial Plan ==")[-1]
    assert "MapInArrow" in plan and "Window" not in plan and "SortMergeJoin" not in plan and "posexplode" not in plan
