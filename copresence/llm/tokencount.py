"""Token counts through a digest cache.

A text's key is the digest of its normalised content (null read as empty; nothing else is changed, since any other
change could alter the count) and the digest of the tokenizer file. Documents join the stored counts on that key; only
distinct misses are encoded, and their counts are appended to the cache, a Parquet table in a folder that all executors
see. A count is a pure function of its key, so a lost task or a second writer can only append an equal row.

Counts are those of the library that reads the tokenizer file. For byte_bpe_50k.json, texts made only of characters
whose class is beyond doubt (SAFE: ASCII and Latin letters, digits, common punctuation, plain white space) and free
of "<|" are encoded by the other installed library from the same vocabulary, which gives the same tokens about five
times faster; every other text goes through the file's own library. Tests hold the two against each other.

Defined cases: null and empty texts count 0; a null id is kept; equal texts are encoded once; extra columns are not
read; an empty table gives no rows and appends none.
"""

from __future__ import annotations

import base64
import hashlib
import re
import uuid
from collections.abc import Callable, Iterator
from functools import lru_cache
from pathlib import Path

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from copresence.ship import arrow_map

from .common import cut, shared_dir, whole

TOKENIZER = "byte_bpe_50k.json"
TWIN = {"byte_bpe_50k.json": "byte_bpe_50k.tiktoken"}
LIMIT = 1024
CACHE_SETTING = "spark.copresence.tokenCache"  # folder of the cache that a session's calls share and leave to later ones
CACHE = "content string, tokenizer string, n_tokens long"
SAFE = re.compile(r"[^\t\n\r\x20-\x7EÀ-ÖØ-öø-ſ–—‘’“”…€]")


def tokenizer_path(name: str = TOKENIZER) -> str:
    import public_tokenizers

    return str(public_tokenizers.path(name))


@lru_cache(maxsize=4)
def version(path: str) -> str:
    return hashlib.sha256(Path(path).read_bytes()).hexdigest()


@lru_cache(maxsize=4)
def plain_counter(path: str) -> Callable[[str], int]:
    """Counts as the library for this file gives them."""
    if path.endswith(".model"):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        return lambda t: len(model.encode(t))
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(path)
    t.no_truncation()
    t.no_padding()
    return lambda text: len(t.encode(text, add_special_tokens=False))


@lru_cache(maxsize=4)
def counter(path: str) -> Callable[[str], int]:
    exact, twin = plain_counter(path), TWIN.get(Path(path).name)
    if not twin:
        return exact
    import public_tokenizers
    import tiktoken

    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, Path(tokenizer_path(twin)).read_bytes().splitlines())}
    fast = tiktoken.Encoding("twin", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    return lambda text: exact(text) if "<|" in text or SAFE.search(text) else len(fast.encode_ordinary(text))


def _encoded(misses: DataFrame, path: str) -> DataFrame:
    """misses(content, text) -> cache rows."""
    tag = version(path)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count = counter(path)
        for b in batches:
            n = [count(t.as_py()) for t in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0).cast(pa.string()), pa.array([tag] * len(n), pa.string()), pa.array(n, pa.int64())], names=["content", "tokenizer", "n_tokens"])

    return arrow_map(misses.select("content", "text"), run, CACHE)


def stored(spark: SparkSession, cache: str, tag: str, make: bool = True) -> DataFrame:
    """What the cache holds for a tokenizer version; a cache that isn't there yet is made, empty."""
    if make:
        spark.createDataFrame([], CACHE).coalesce(1).write.mode("append").parquet(cache)
    return spark.read.schema(CACHE).parquet(cache).filter(F.col("tokenizer") == tag).groupBy("content").agg(F.max("n_tokens").alias("n_tokens"))


def new_cache(spark: SparkSession) -> str:
    """A cache of its own in the shared folder, which goes when the session ends."""
    cache = f"{shared_dir(spark)}/token-counts-{uuid.uuid4().hex}"
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(cache)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(where)
    return cache


def count_tokens(docs: DataFrame, cache: str | None = None, path: str | None = None, limit: int = LIMIT) -> DataFrame:
    """docs(doc_id, text) -> doc_id, n_bytes, n_tokens, over_limit. cache: folder of the cache; None: the one that the
    session names in CACHE_SETTING and so keeps, or else a new one."""
    spark = docs.sparkSession
    path = path or tokenizer_path()
    cache = cache or spark.conf.get(CACHE_SETTING, None) or new_cache(spark)
    tag = version(path)
    keyed = docs.select("doc_id", whole("text").alias("text")).withColumn("content", F.sha2("text", 256))
    known = stored(spark, cache, tag)
    misses = keyed.join(known, "content", "left_anti").groupBy("content").agg(F.first("text").alias("text"))
    _encoded(misses, path).write.mode("append").parquet(cache)
    light = keyed.select("doc_id", "content", F.octet_length("text").cast("long").alias("n_bytes"))
    # written, so that Spark may split the rows of a content that very many documents have
    counts = cut(light.select("content").distinct().join(stored(spark, cache, tag, make=False), "content"))
    return light.join(counts, "content", "left").select("doc_id", "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))
