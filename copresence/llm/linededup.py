"""Line dedup by content-defined chunks of lines, with DataFrame functions only.

Each line has a number from its digest; a polynomial rolling hash over the last WINDOW lines ends a chunk where it is 0
modulo DIVISOR and was not a line before (so that a chunk has two lines at least, but at a text's end). Boundaries move
with the content and an insertion shifts none behind it. Chunks of two or more lines that occur more than once in the
table are removed but for the first occurrence. Chunks are grouped by digest and by their bytes, so two texts with one
digest are never taken for each other.

A repeated passage may begin and end inside chunks that differ. So every two neighbour lines are compared too (by
SHA-256 of both): a run of lines is met earlier exactly where each of its pairs is, so a line goes as well if a pair
that it is in was met earlier and no pair that it is in occurs here for the first of several times. A line that goes
always has an earlier equal line that stays.

A document is its id and its text (by digest): what goes from a text never touches another text with the same id.
"Earlier" is by id (nulls first), digest of the text, line.

Shuffles: one of chunk texts (counts are combined before it), the rest carry ids, digests and numbers; a text is joined
once more with what is to go from it. What is joined to the rows of a hot chunk, pair or document is written before the
join, so that Spark may split these rows over tasks.

Defined cases: null and empty texts have no lines and stay as they are; rows with one id and one text are the same
document and get the same result; blank lines are lines; extra columns are kept by `drop_repeats` and not read; an
empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import cut, whole

FIRST_ID = -(1 << 62)  # stands for a null id in the order
KEY = ["doc_id", "row"]
WINDOW = 2
DIVISOR = 2
BASE, PRIME = 31, 1000003


def line_numbers(lines: Column) -> Column:
    return F.transform(lines, lambda x: F.conv(F.substring(F.md5(x), 1, 6), 16, 10).cast("long"))


def rolling(numbers: Column, window: int = WINDOW) -> Column:
    """Polynomial hash of the last `window` numbers at each place (fewer at the head)."""
    def at(_: Column, i: Column) -> Column:
        total = F.lit(0).cast("long")
        for back in range(window - 1, -1, -1):
            total = total * BASE + F.when(i >= back, F.get(numbers, i - back)).otherwise(0)
        return total % PRIME

    return F.transform(numbers, at)


def keyed(docs: DataFrame) -> DataFrame:
    """doc_id (null as FIRST_ID), row (digest of the text) and lines of the documents with two lines or more."""
    text = whole("text")
    return docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(FIRST_ID)).alias("doc_id"), F.md5(text).alias("row"), F.split(text, "\n", -1).alias("lines")).filter(F.size("lines") > 1)


def chunks(docs: DataFrame, window: int = WINDOW, divisor: int = DIVISOR) -> DataFrame:
    """Multi-line chunks: doc_id, row, start (line, from 0), n_lines, chunk (the text). One scan, no shuffle."""
    d = keyed(docs)
    d = d.withColumn("h", line_numbers(F.col("lines"))).withColumn("r", rolling(F.col("h"), window))
    last = F.size("lines") - 1
    falls = lambda i: F.get("r", i) % divisor == 0
    d = d.withColumn("ends", F.filter(F.sequence(F.lit(0), last), lambda i: ((i > 0) & falls(i) & ~falls(i - 1)) | (i == last)))
    d = d.withColumn("piece", F.explode(F.transform("ends", lambda e, j: F.struct(F.when(j > 0, F.get("ends", j - 1) + 1).otherwise(0).alias("start"), e.alias("end")))))
    d = d.filter("piece.end > piece.start")
    n = F.col("piece.end") - F.col("piece.start") + 1
    return d.select(*KEY, F.col("piece.start").cast("long").alias("start"), n.cast("long").alias("n_lines"), F.array_join(F.slice("lines", F.col("piece.start") + 1, n), "\n").alias("chunk"))


def removals(docs: DataFrame, window: int = WINDOW, divisor: int = DIVISOR) -> DataFrame:
    """Chunks to go: doc_id, row, start, n_lines."""
    every = chunks(docs, window, divisor).withColumn("digest", F.md5("chunk"))
    # bytes tell apart what shares a digest: `texts` is 1 but for a collision
    texts = every.groupBy("digest", "chunk").agg(F.count(F.lit(1)).alias("n"), F.min("doc_id").alias("first_doc"))
    known = cut(texts.groupBy("digest").agg(F.sum("n").alias("n"), F.min("first_doc").alias("first_doc"), F.count(F.lit(1)).alias("texts")).filter("n > 1").drop("n"))
    place = F.struct("row", "start")
    light = cut(every.drop("chunk").join(known, "digest"))
    plain = light.filter("texts = 1")
    first = cut(plain.filter("doc_id = first_doc").groupBy("digest").agg(F.min(place).alias("first")))
    gone = plain.join(first, "digest").filter((F.col("doc_id") != F.col("first_doc")) | (place != F.col("first"))).select(*KEY, "start", "n_lines")
    if light.filter("texts > 1").limit(1).count():  # a digest collision: compare these by text
        mixed = every.join(known.filter("texts > 1").select("digest"), "digest", "left_semi").withColumn("place", F.struct(*KEY, "start"))
        one = mixed.groupBy("digest", "chunk").agg(F.min("place").alias("first"))
        gone = gone.unionByName(mixed.join(one, ["digest", "chunk"]).filter(F.col("place") != F.col("first")).select(*KEY, "start", "n_lines"))
    return gone.distinct()


def line_pairs(docs: DataFrame) -> DataFrame:
    """Every two neighbour lines: doc_id, row, at (the first line, from 0), pair (digest of both). One scan, no shuffle."""
    both = F.transform(F.slice("lines", F.lit(1), F.size("lines") - 1), lambda x, i: F.unhex(F.sha2(F.concat(x, F.lit("\n"), F.get("lines", i + 1)), 256)))
    return keyed(docs).select(*KEY, F.posexplode(both).alias("at", "pair")).withColumn("at", F.col("at").cast("long"))


def run_lines(docs: DataFrame) -> DataFrame:
    """Lines to go since the run they are in was met earlier: doc_id, row, line."""
    every, place = line_pairs(docs), F.struct(*KEY, "at")
    known = cut(every.groupBy("pair").agg(F.count(F.lit(1)).alias("n"), F.min(place).alias("first")).filter("n > 1").drop("n"))
    lines = every.join(known, "pair").select(*KEY, F.explode(F.array("at", F.col("at") + 1)).alias("line"), (place == F.col("first")).alias("stays"))
    return lines.groupBy(*KEY, "line").agg(F.max("stays").alias("stays")).filter("NOT stays").drop("stays")


def lines_to_go(docs: DataFrame, window: int = WINDOW, divisor: int = DIVISOR) -> DataFrame:
    """Runs of lines to go: doc_id (null as FIRST_ID), row, start, n_lines."""
    of_chunks = removals(docs, window, divisor).select(*KEY, F.explode(F.expr("sequence(start, start + n_lines - 1)")).alias("line"))
    lines = of_chunks.unionByName(run_lines(docs)).distinct()
    island = lines.withColumn("island", F.col("line") - F.row_number().over(W.partitionBy(*KEY).orderBy("line")))
    return island.groupBy(*KEY, "island").agg(F.min("line").alias("start"), F.count(F.lit(1)).alias("n_lines")).drop("island")


def drop_repeats(docs: DataFrame, window: int = WINDOW, divisor: int = DIVISOR) -> DataFrame:
    """docs with the repeated lines cut out of the text, and __lines, __gone (array of start, n_lines)."""
    gone = cut(lines_to_go(docs, window, divisor).groupBy(F.col("doc_id").alias("__id"), F.col("row").alias("__row")).agg(F.sort_array(F.collect_list(F.struct("start", "n_lines"))).alias("__gone")))
    same = (F.coalesce(F.col("doc_id").cast("long"), F.lit(FIRST_ID)) == F.col("__id")) & (F.md5(whole("text")) == F.col("__row"))
    d = docs.join(gone, same, "left").drop("__id", "__row")
    lines = F.split(whole("text"), "\n", -1)
    out = F.filter(lines, lambda x, i: ~F.exists("__gone", lambda g: (i >= g["start"]) & (i < g["start"] + g["n_lines"])))
    return d.withColumn("__lines", F.size(lines).cast("long")).withColumn("text", F.when(F.col("__gone").isNull(), F.col("text")).otherwise(F.array_join(out, "\n")))


def line_dedup_report(docs: DataFrame, window: int = WINDOW, divisor: int = DIVISOR) -> DataFrame:
    """One row per document: doc_id, n_lines, n_removed, removed ("start+lines" joined), text (what stays)."""
    d = drop_repeats(docs.select("doc_id", "text"), window, divisor)
    return d.select(
        "doc_id", F.when((F.length(whole("text")) > 0) | F.col("__gone").isNotNull(), F.col("__lines")).otherwise(0).alias("n_lines"),
        F.coalesce(F.aggregate("__gone", F.lit(0).cast("long"), lambda a, g: a + g["n_lines"]), F.lit(0)).cast("long").alias("n_removed"),
        F.coalesce(F.array_join(F.transform("__gone", lambda g: F.concat_ws("+", g["start"].cast("string"), g["n_lines"].cast("string"))), ","), F.lit("")).alias("removed"), "text",
    )
