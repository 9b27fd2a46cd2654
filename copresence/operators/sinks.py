"""Transactions and results as files: text lines, 0/1 tables, Parquet, and back."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from copresence.functions.masks import bit_mask, fold
from copresence.model import Classes

from .transactions import dichotomous, transaction_text


def write_text(tx: DataFrame, classes: Classes, path: str) -> None:
    """A folder per group of lines with codes only."""
    transaction_text(tx, classes).write.mode("overwrite").partitionBy("grp").text(path)


def read_text(spark: SparkSession, path: str, classes: Classes) -> DataFrame:
    """Text lines back to PATTERNS (the files hold no unit ids)."""
    lines = spark.read.option("basePath", path).text(path).withColumn("row", F.monotonically_increasing_id())
    bit = F.create_map(*[x for b, c in enumerate(classes.codes) for x in (F.lit(str(c)), F.lit(b))])
    split = lines.select("grp", "row", F.explode(F.split("value", " ")).alias("code")).withColumn("bit", F.element_at(bit, F.col("code")))
    return split.groupBy("grp", "row").agg(fold(bit_mask("bit")).alias("mask")).groupBy(F.col("grp").cast("string").alias("grp"), "mask").agg(F.count(F.lit(1)).alias("weight"))


def write_dichotomous(tx: DataFrame, classes: Classes, path: str, form: str = "csv") -> None:
    dichotomous(tx, classes).write.mode("overwrite").format(form).option("header", True).save(path)


def read_dichotomous(spark: SparkSession, path: str, classes: Classes, form: str = "csv") -> DataFrame:
    schema = "grp string, unit_id long, " + ", ".join(f"c{c} int" for c in classes.codes)
    wide = spark.read.schema(schema).format(form).option("header", True).load(path)
    mask = sum((F.when(F.col(f"c{c}") == 1, F.lit(1 << b)).otherwise(F.lit(0)).cast("long") for b, c in enumerate(classes.codes)), F.lit(0).cast("long"))
    return wide.select("grp", "unit_id", mask.alias("mask"))


def write_json(df: DataFrame, path: str) -> None:
    """A JSON object a line; nulls are written."""
    df.write.mode("overwrite").option("ignoreNullFields", False).json(path)


def read_json(spark: SparkSession, path: str, schema: str) -> DataFrame:
    """JSON lines by a given schema; a line that doesn't fit stops the read."""
    return spark.read.schema(schema).option("mode", "FAILFAST").json(path)


def write_by_group(df: DataFrame, path: str, buckets: int = 64) -> None:
    """Parquet in folders by a hash of the group, so that one group is read from one folder."""
    df.withColumn("bucket", F.pmod(F.xxhash64("grp"), F.lit(buckets)).cast("int")).repartition("bucket").write.mode("overwrite").partitionBy("bucket").parquet(path)


def read_group(spark: SparkSession, path: str, grp: str, buckets: int = 64) -> DataFrame:
    bucket = F.pmod(F.xxhash64(F.lit(grp)), F.lit(buckets)).cast("int")
    return spark.read.parquet(path).filter((F.col("bucket") == bucket) & (F.col("grp") == grp)).drop("bucket")
