"""SQL surface: scalar functions on class sets, table functions for submasks and for mining."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StringType, StructField, StructType

from copresence.model import Threshold
from copresence.operators.mining import nodeset_search, submasks
from copresence.ship import ship


class Submasks:
    """TABLE(submask BIGINT) of all non-empty subsets of a set with at most max_k classes."""

    def eval(self, mask: int, max_k: int) -> Iterator[tuple[int]]:
        for s in submasks(mask).tolist():
            if s.bit_count() <= max_k:
                yield (s,)


class MineItemsets:
    """mine_itemsets(TABLE(patterns) PARTITION BY (grp), '10%'): grp, itemset, sup, n of each group."""

    def __init__(self):
        self.grp, self.share, self.masks, self.weights = None, None, [], []

    def eval(self, row, share: str) -> None:
        self.grp, self.share = row["grp"], share
        self.masks.append(row["mask"])
        self.weights.append(row["weight"])

    def terminate(self) -> Iterator[tuple[str, int, int, int]]:
        n = sum(self.weights)
        if n:
            sets, sups = nodeset_search(np.array(self.masks, np.int64), np.array(self.weights, np.int64), Threshold.relative(self.share).min_count(n))
            for s, c in zip(sets, sups, strict=True):
                yield self.grp, int(s), int(c), int(n)


def union_of(mask: pd.Series) -> int:
    """Grouped aggregate: union of the sets of a group."""
    return int(np.bitwise_or.reduce(mask.to_numpy(np.int64))) if len(mask) else 0


def register(spark: SparkSession) -> None:
    """Make the functions known to the session's SQL."""
    ship(spark)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION contains_items(mask BIGINT, items BIGINT) RETURNS BOOLEAN RETURN (mask & items) = items")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION set_size(mask BIGINT) RETURNS INT RETURN bit_count(mask)")
    spark.udf.register("union_of_sets", F.pandas_udf(union_of, "long", F.PandasUDFType.GROUPED_AGG))
    spark.udtf.register("submasks", F.udtf(Submasks, returnType="submask bigint"))
    mined = StructType([StructField("grp", StringType()), StructField("itemset", LongType()), StructField("sup", LongType()), StructField("n", LongType())])
    spark.udtf.register("mine_itemsets", F.udtf(MineItemsets, returnType=mined))
