from __future__ import annotations

import os
import subprocess
import sys
import textwrap
from datetime import datetime, timedelta
from pathlib import Path

import pytest
from pyspark.sql import functions as F

from copresence.operators import transactions
from copresence.streaming import patterns as stream

ROOT = Path(__file__).resolve().parents[1]
START = datetime(2024, 1, 1)


def events(spark, hours, first=0):
    return spark.createDataFrame([("g", 1, first + i, START + timedelta(hours=h), i % 4) for i, h in enumerate(hours)], "grp string, part long, unit_id long, ts timestamp, bit int")


def test_rows_behind_the_watermark_are_dropped(spark, tmp_path):
    src = in_order(spark, tmp_path, [[0, 1, 100], [101, 102], [2, 103]])  # the third batch's event at hour 2 is late
    got = stream.to_memory(stream.tumbling_sets(src, "1 day", "1 hour"), "append")
    first = got.filter(F.col("start") == int(START.timestamp()) * 1_000_000).collect()
    assert [r["n"] for r in first] == [2]


def in_order(spark, folder, batches):
    """A stream that reads one batch of event hours after the other: a file each, with rising times."""
    path = f"{folder}/in"
    for i, hours in enumerate(batches):
        events(spark, hours, 100 * i).coalesce(1).write.mode("append").parquet(path)
        new = max(Path(path).glob("*.parquet"), key=lambda p: p.stat().st_ctime_ns)
        os.utime(new, (1_700_000_000 + i, 1_700_000_000 + i))
    return spark.readStream.schema(events(spark, [0]).schema).option("maxFilesPerTrigger", 1).parquet(path)


def test_late_rows_are_counted(spark, tmp_path):
    src = in_order(spark, tmp_path, [[0, 50], [51, 60], [1, 2, 61], [3, 62, 70]])
    assert stream.late_counts(src, "5 hours") == [(0, 2, 0), (1, 2, 0), (2, 3, 2), (3, 3, 1)]


def test_focal_units_close_after_their_reach(spark, tmp_path):
    path = f"{tmp_path}/in"
    hours = [0, 1, 2, 30, 31, 90, 200]
    events(spark, hours).coalesce(1).write.parquet(path)
    src = spark.readStream.schema(events(spark, [0]).schema).parquet(path)
    zone = spark.conf.get("spark.sql.session.timeZone")
    spark.conf.set("spark.sql.session.timeZone", "America/New_York")  # timers don't hang on the session's zone
    try:
        with stream.keyed_state(spark):
            got = {r["unit_id"]: r["mask"] for r in stream.to_memory(stream.closed_transactions(src, 6 * 3_600_000_000, "1 hour"), "append").collect()}
    finally:
        spark.conf.set("spark.sql.session.timeZone", zone)
    batch = transactions.buffer_instant(events(spark, hours).select("grp", "part", "unit_id", F.unix_micros("ts").alias("lo"), F.unix_micros("ts").alias("hi"), "bit"), 6 * 3_600_000_000)
    want = {r["unit_id"]: r["mask"] for r in batch.collect()}
    assert got == {k: want[k] for k in range(6)}  # the last event's reach is still open


def test_batches_merge_once(spark, tmp_path):
    write = stream.merge_into(f"{tmp_path}/out")
    part = spark.createDataFrame([("g", 1, 2), ("g", 3, 1)], "grp string, mask long, weight long")
    for batch in (0, 1, 1):  # batch 1 is written again after a failure
        write(part, batch)
    assert {(r["mask"], r["weight"]) for r in stream.merged(spark, f"{tmp_path}/out").collect()} == {(1, 4), (3, 2)}


@pytest.mark.parametrize("gone", ["corpus_pipeline copresence.llm", "ahocorasick"])
def test_entry_works_without_the_corpus_operators(gone):
    code = """
    import importlib.abc, sys
    class Gone(importlib.abc.MetaPathFinder):
        def find_spec(self, name, path=None, target=None):
            if any(name == g or name.startswith(g + ".") for g in gone):
                raise ModuleNotFoundError(f"No module named {name!r}", name=name)
    sys.meta_path.insert(0, Gone())
    import __spark_entry__ as e
    names = e.queries()
    assert "itemsets_nodeset_strip" in names and not any(n.startswith("op") and n[2].isdigit() for n in names) and "pipeline" not in names
    assert set(e.oracle_sql()) <= set(names)
    """
    subprocess.run([sys.executable, "-c", f"gone = {gone.split()!r}\n" + textwrap.dedent(code)], cwd=ROOT, check=True)


def test_nothing_else_imports_the_corpus_operators():
    for p in (ROOT / "copresence").rglob("*.py"):
        if "llm" not in p.relative_to(ROOT / "copresence").parts:
            assert "copresence.llm" not in p.read_text()


def test_results_of_streams_stay_off_the_driver(spark, monkeypatch):
    """The driver's memory would have to hold all windows."""
    from copresence.operators import transactions
    from copresence.plans.queries import QUERIES
    from copresence.sources import workloads as data

    sf = "/root/testdata/sf0.001"

    def refuse(*_):
        raise AssertionError("collected on the driver")

    monkeypatch.setattr(stream, "to_memory", refuse)
    rows = lambda df: sorted(map(tuple, df.collect()))
    events = data.event_columns(data.read(spark, sf, "events"))
    batch = stream.tumbling_sets(events, "6 hours", "400 days")
    assert rows(QUERIES["stream_patterns"](spark, sf)) == rows(transactions.patterns(batch)) != []
    n = QUERIES["stream_session_sets"](spark, sf).agg({"events": "sum"}).first()[0]
    assert n == events.filter("ts IS NOT NULL").count()
