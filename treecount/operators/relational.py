"""Count tables as long rows (it, v, mask, cnt): only what is not zero is stored, and everything is a join or an aggregate."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.colorsets import disjoint_sets
from ..storage import merged, sent

TYPES = {"long": "long", "decimal": "decimal(38,0)", "double": "double", "float": "float"}
KEY = ["it", "v", "mask"]


def bit(color):
    """The mask of a single color column."""
    return F.call_function("shiftleft", F.lit(1).cast("long"), color)


def total_of(value, cnt_type: str):
    """A sum that keeps the count type; LONG overflow raises."""
    return F.sum(value).cast(TYPES[cnt_type])


def product(a, b, cnt_type: str):
    return (a * b).cast(TYPES[cnt_type])


def leaf_counts(coloring: DataFrame, cnt_type: str = "long") -> DataFrame:
    """One count for each vertex at its own color."""
    return coloring.select("it", "v", bit(F.col("color")).alias("mask"), F.lit(1).cast(TYPES[cnt_type]).alias("cnt"))


def neighbor_sum(edges: DataFrame, m: DataFrame, cnt_type: str = "long", broadcast: bool = False) -> DataFrame:
    """For each vertex and color set the sum of the neighbours' counts; a vertex's own count takes no part.

    Map-side combining flattens vertices with many edges on the receiving side. ``broadcast`` sends a small table to all tasks.
    """
    side = m.select("it", F.col("v").alias("dst"), "mask", "cnt")
    rows = edges.join(sent(side, 64) if broadcast else merged(side), "dst")
    return rows.groupBy("it", F.col("src").alias("v"), "mask").agg(total_of("cnt", cnt_type).alias("cnt"))


def multiply_add(a: DataFrame, s: DataFrame, cnt_type: str = "long", within: tuple[int, int] | None = None) -> DataFrame:
    """Pairs of an active count and a passive sum with disjoint colors, multiplied and added up by united colors; within: the
    range of masks that the united colors are to lie in."""
    x = a.select("it", "v", F.col("mask").alias("ma"), F.col("cnt").alias("ca"))
    y = s.select("it", "v", F.col("mask").alias("mp"), F.col("cnt").alias("cp"))
    both = merged(x).join(y, ["it", "v"]).where(F.col("ma").bitwiseAND(F.col("mp")) == 0)
    if within:
        union = F.col("ma").bitwiseOR(F.col("mp"))
        both = both.where((union >= within[0]) & (union < within[1]))
    return both.groupBy("it", "v", F.col("ma").bitwiseOR(F.col("mp")).alias("mask")).agg(total_of(product(F.col("ca"), F.col("cp"), cnt_type), cnt_type).alias("cnt"))


def split_rows(m: DataFrame, k: int, other: int, mine: str, theirs: str) -> DataFrame:
    """Each count once for every set of ``other`` colors disjoint from its own: the splits that it takes part in. They are
    made beside the row, so no table of splits is sent or joined."""
    rows = m.select("*", F.explode(disjoint_sets(k, other, F.col("mask"))).alias(theirs)).withColumnRenamed("mask", mine)
    return rows.withColumn("mask_s", F.col(mine).bitwiseOR(F.col(theirs)))


def per_split(edges: DataFrame, a: DataFrame, p: DataFrame, k: int, passive: int, cnt_type: str = "long") -> DataFrame:
    """The unpruned step: for every split of every color set all neighbours are walked again, and products are added up."""
    x = split_rows(a.select("it", F.col("v").alias("src"), "mask", F.col("cnt").alias("ca")), k, passive, "mask_a", "mask_p")
    y = p.select("it", F.col("v").alias("dst"), F.col("mask").alias("mask_p"), F.col("cnt").alias("cp"))
    rows = merged(x).join(edges, "src").join(merged(y), ["it", "dst", "mask_p"])
    return rows.groupBy("it", F.col("src").alias("v"), F.col("mask_s").alias("mask")).agg(total_of(product(F.col("ca"), F.col("cp"), cnt_type), cnt_type).alias("cnt"))


def factored(edges: DataFrame, a: DataFrame, p: DataFrame, k: int, active: int, cnt_type: str = "long") -> DataFrame:
    """The active factor leaves the neighbour sum, but each split still has a sum of its own."""
    y = split_rows(p.select("it", F.col("v").alias("dst"), "mask", F.col("cnt").alias("cp")), k, active, "mask_p", "mask_a")
    sums = edges.join(merged(y), "dst").groupBy("it", F.col("src").alias("v"), "mask_s", "mask_a", "mask_p").agg(total_of("cp", cnt_type).alias("cp"))
    x = a.select("it", "v", F.col("mask").alias("mask_a"), F.col("cnt").alias("ca"))
    return merged(x).join(sums, ["it", "v", "mask_a"]).groupBy("it", "v", F.col("mask_s").alias("mask")).agg(total_of(product(F.col("ca"), F.col("cp"), cnt_type), cnt_type).alias("cnt"))


def looked_up(a: DataFrame, s: DataFrame, k: int, passive: int, cnt_type: str = "long") -> DataFrame:
    """The combine loop without edges: each split looks up the active count and the sum made beforehand."""
    x = split_rows(a.select("it", "v", "mask", F.col("cnt").alias("ca")), k, passive, "mask_a", "mask_p")
    y = s.select("it", "v", F.col("mask").alias("mask_p"), F.col("cnt").alias("cp"))
    return merged(x).join(y, ["it", "v", "mask_p"]).groupBy("it", "v", F.col("mask_s").alias("mask")).agg(total_of(product(F.col("ca"), F.col("cp"), cnt_type), cnt_type).alias("cnt"))
