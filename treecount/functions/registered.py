"""Functions for SQL users: ``register(spark)`` adds binomial, color_rank, color_splits, template_plan, median_of_means."""

from __future__ import annotations

from math import comb

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import DoubleType, IntegerType

from ..plans.templates import TreeTemplate, partition
from .colorsets import masks, split_arrays


@udtf(returnType="rank_s int, rank_a int, rank_p int, mask_s long, mask_a long, mask_p long")
class ColorSplits:
    def eval(self, k: int, s: int, p: int):
        for a, b, c in zip(*split_arrays(k, s, p), strict=True):
            yield int(a), int(b), int(c), int(masks(k, s)[a]), int(masks(k, s - p)[b]), int(masks(k, p)[c])


@udtf(returnType="step int, sub string, size int, active string, passive string")
class TemplatePlan:
    def eval(self, parents: list):
        for i, s in enumerate(partition(TreeTemplate(tuple(parents)))):
            yield i, s.key, s.size, s.active, s.passive


@pandas_udf(IntegerType())
def color_rank(colors: pd.Series) -> pd.Series:
    return colors.map(lambda c: sum(comb(int(x), i) for i, x in enumerate(sorted(c), 1)))


@pandas_udf(DoubleType())
def median_of_means(it: pd.Series, v: pd.Series) -> float:
    """Median of the means of about sqrt(n) groups of values; ``it`` mod the number of groups says which."""
    if not len(v):
        return float("nan")
    n = max(1, int(len(v) ** 0.5))
    means = v.astype(float).groupby(it.to_numpy(np.int64) % n).mean()
    return float(np.median(means))


def register(spark: SparkSession) -> None:
    spark.udtf.register("color_splits", ColorSplits)
    spark.udtf.register("template_plan", TemplatePlan)
    spark.udf.register("color_rank", color_rank)
    spark.udf.register("median_of_means", median_of_means)
    spark.sql("create or replace temporary function binomial(n int, k int) returns bigint return case when k < 0 or k > n then 0 else aggregate(sequence(1, greatest(k, 1)), 1L, (acc, i) -> case when k = 0 then acc else acc * (n - k + i) div i end) end")
