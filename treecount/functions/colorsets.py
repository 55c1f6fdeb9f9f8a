"""Color sets as ranks in the combinatorial number system and as bit masks."""

from __future__ import annotations

from functools import lru_cache
from itertools import combinations
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def rank(colors) -> int:
    """The place of a set among all sets of its size; the i-th smallest color c adds C(c, i).

    >>> [rank(c) for c in ([0, 1], [0, 2], [1, 2])]
    [0, 1, 2]
    """
    return sum(comb(c, i) for i, c in enumerate(sorted(colors), 1))


def unrank(i: int, h: int) -> list[int]:
    """The set of size h with rank i.

    >>> unrank(2, 2)
    [1, 2]
    """
    out = []
    for j in range(h, 0, -1):
        c = j - 1
        while comb(c + 1, j) <= i:
            c += 1
        out.append(c)
        i -= comb(c, j)
    return out[::-1]


def mask_of(colors) -> int:
    return sum(1 << c for c in colors)


@lru_cache(maxsize=256)
def masks(k: int, h: int) -> np.ndarray:
    """Masks of all sets of h of k colors, by rank. Ascending masks are ascending ranks."""
    return np.array(sorted(mask_of(c) for c in combinations(range(k), h)), np.int64)


def sets_of(ranks: np.ndarray, k: int, h: int) -> np.ndarray:
    """Members, ascending, of the sets of size h with these ranks: one row each."""
    out, left = np.zeros((len(ranks), h), np.int64), ranks.astype(np.int64)
    for j in range(h, 0, -1):
        steps = np.array([comb(c, j) for c in range(k + 1)], np.int64)
        out[:, j - 1] = np.searchsorted(steps, left, side="right") - 1
        left = left - steps[out[:, j - 1]]
    return out


def ranks_of(sets: np.ndarray, k: int) -> np.ndarray:
    """The ranks of rows of ascending members."""
    steps = np.array([[comb(c, i) for i in range(1, sets.shape[1] + 1)] for c in range(k)], np.int64).reshape(k, -1)
    return steps[sets, np.arange(sets.shape[1])].sum(1)


def from_ranks(spark: SparkSession, n: int, make, schema: str) -> DataFrame:
    """Rows that tasks make of the numbers 0..n-1, an array of them at a time; nothing comes from the driver."""

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                yield make(batch.column(0).to_numpy())

    return spark.range(n).mapInArrow(run, schema)


def catalog(spark: SparkSession, k: int, h: int) -> DataFrame:
    """(h, rank, mask, members) of all sets of h of k colors."""

    def make(ranks):
        sets = sets_of(ranks, k, h)
        members = pa.ListArray.from_arrays(pa.array(np.arange(0, sets.size + 1, max(h, 1), dtype=np.int32)), pa.array(sets.ravel(), pa.int32()))
        return pa.RecordBatch.from_arrays([pa.array(np.full(len(ranks), h, np.int32)), pa.array(ranks, pa.int64()), pa.array((1 << sets).sum(1)), members], names=["h", "rank", "mask", "members"])

    return from_ranks(spark, comb(k, h), make, "h int, rank long, mask long, members array<int>").withColumn("rank", F.col("rank").cast("int"))


def rank_of(members, k: int):
    """The rank of an ascending array of some of k colors, in SQL functions."""
    table = F.array(*[F.array(*[F.lit(comb(c, i)).cast("long") for i in range(1, k + 1)]) for c in range(k)])
    placed = F.zip_with(members, F.sequence(F.lit(1), F.size(members)), lambda c, i: F.element_at(F.element_at(table, c + 1), i))
    return F.aggregate(placed, F.lit(0).cast("long"), lambda a, x: a + x)


def disjoint_sets(k: int, h: int, mask):
    """All sets of h of k colors that share none with the mask column, as an array column of masks."""
    return F.filter(F.array(*[F.lit(int(m)) for m in masks(k, h)]), lambda m: m.bitwiseAND(mask) == 0)


def first_superset(mask, more: int):
    """The set of lowest rank that holds the mask column and so many colors more: each step adds the lowest free color."""
    for _ in range(more):
        mask = mask.bitwiseOR(mask + 1)
    return mask


def split_ranks(numbers: np.ndarray, k: int, s: int, p: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Members of the whole, the active and the passive set of the splits with these numbers, and the whole's rank. Splits are
    numbered by the rank of the whole, then of the places that the passive part takes in it."""
    per = comb(s, p)
    whole, part = sets_of(numbers // per, k, s), sets_of(numbers % per, s, p)
    inside = np.zeros((len(numbers), s), bool)
    np.put_along_axis(inside, part, True, 1)
    return whole, whole[~inside].reshape(-1, s - p), whole[inside].reshape(-1, p), numbers // per


def split_arrays(k: int, s: int, p: int, low: int = 0, high: int | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ranks (of the whole, the active and the passive part) of all C(s, p) splits of the sets of s with ranks low to high, ordered by the whole."""
    per = comb(s, p)
    _, active, passive, whole = split_ranks(np.arange(low * per, (comb(k, s) if high is None else high) * per), k, s, p)
    return whole, ranks_of(active, k), ranks_of(passive, k)


def splits(spark: SparkSession, k: int, s: int, p: int) -> DataFrame:
    """(rank_s, rank_a, rank_p, mask_s, mask_a, mask_p) of all splits of all sets of s of k colors, made in tasks from ranks."""

    def make(numbers):
        whole, active, passive, rank_s = split_ranks(numbers, k, s, p)
        cols = [rank_s, ranks_of(active, k), ranks_of(passive, k), (1 << whole).sum(1), (1 << active).sum(1), (1 << passive).sum(1)]
        return pa.RecordBatch.from_arrays([pa.array(c, pa.int32() if i < 3 else pa.int64()) for i, c in enumerate(cols)], names=["rank_s", "rank_a", "rank_p", "mask_s", "mask_a", "mask_p"])

    return from_ranks(spark, comb(k, s) * comb(s, p), make, "rank_s int, rank_a int, rank_p int, mask_s long, mask_a long, mask_p long")
