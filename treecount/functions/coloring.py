"""Random colors that depend on seed, iteration and vertex only, so a repeated task gives the same ones."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

METHODS = ("md5", "xxhash", "rand")


def color(v: Column, it: Column, k: int, seed: int, method: str = "md5") -> Column:
    """A color in 0..k-1. "md5" is the same in every engine, "xxhash" is faster, "rand" is not repeatable and only for comparison."""
    if method == "md5":
        text = F.concat_ws(":", F.lit(str(seed)), it.cast("string"), v.cast("string"))
        return (F.conv(F.substring(F.md5(text), 1, 7), 16, 10).cast("long") % k).cast("int")
    if method == "xxhash":
        return F.pmod(F.xxhash64(F.lit(seed), it.cast("long"), v.cast("long")), F.lit(k)).cast("int")
    if method == "rand":
        return F.floor(F.rand(seed) * k).cast("int")
    raise ValueError(f"method must be one of {METHODS}")


def color_vertices(vertices: DataFrame, k: int, seed: int = 42, iterations=(0,), method: str = "md5") -> DataFrame:
    """(it, v, color) for each vertex and iteration; narrow, no shuffle."""
    its = F.explode(F.array(*[F.lit(int(i)) for i in iterations]))
    return vertices.select(its.alias("it"), "v").select("it", "v", color(F.col("v"), F.col("it"), k, seed, method).alias("color"))


def color_in_python(seed: int, it: int, v: int, k: int) -> int:
    return int(hashlib.md5(f"{seed}:{it}:{v}".encode()).hexdigest()[:7], 16) % k
