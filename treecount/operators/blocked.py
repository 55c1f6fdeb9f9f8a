"""Count tables in blocks of Z color sets: (it, v, blk, x), x being an array of up to Z counts in rank order.

Two kernels work on them. The neighbour sum is a sparse matrix times Z columns at a time: a join and
Z sums in one aggregate. The multiply-add needs nearly all blocks of both children for any block of the
result, so these meet once for each vertex; it then runs over slices of vertices whose bytes are bounded,
an array of splits at a time, so no row is touched by itself.
"""

from __future__ import annotations

import warnings
from functools import reduce
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.colorsets import split_arrays
from ..storage import merged, sent

DTYPES = {"long": np.int64, "double": np.float64, "float": np.float32}
#: Up to this many splits "auto" writes the multiply-add as SQL expressions.
MOST_EXPRESSIONS = 64


def width(k: int, size: int, z: int) -> int:
    return min(z, comb(k, size))


def blocks(k: int, size: int, z: int) -> int:
    return -(-comb(k, size) // z)


def check_width(z: int) -> int:
    if z < 1:
        raise ValueError("the batch width must be positive")
    if z % 8 and z > 1:
        warnings.warn(f"a batch width of {z} is no multiple of 8, the counts in a vector register or cache line", stacklevel=2)
    return z


def leaf_blocks(coloring: DataFrame, k: int, z: int, cnt_type: str = "double") -> DataFrame:
    """One count of 1 at the vertex's own color."""
    w = width(k, 1, z)
    x = F.array(*[F.when(F.col("color") % w == i, 1).otherwise(0).cast(cnt_type) for i in range(w)])
    return coloring.select("it", "v", F.floor(F.col("color") / w).cast("int").alias("blk"), x.alias("x"))


def neighbor_sum(edges: DataFrame, m: DataFrame, w: int, cnt_type: str = "double", broadcast: bool = False) -> DataFrame:
    """Z columns in one pass over the edges. ``w`` sums stay below the field limit of generated code up to 64 or so.
    ``broadcast`` sends a small table to all tasks."""
    side = m.select("it", F.col("v").alias("dst"), "blk", "x")
    rows = edges.join(sent(side, 64 + 8 * w) if broadcast else merged(side), "dst")
    sums = rows.groupBy("it", F.col("src").alias("v"), "blk").agg(*[F.sum(F.get("x", F.lit(i))).alias(f"s{i}") for i in range(w)])
    return sums.select("it", "v", "blk", F.array(*[F.col(f"s{i}").cast(cnt_type) for i in range(w)]).alias("x"))


def whole_rows(m: DataFrame, count: int, z: int, name: str, cnt_type: str = "double") -> DataFrame:
    """All blocks of a vertex side by side in one array; absent blocks are zeros."""
    if count == 1:
        return m.select("it", "v", F.col("x").alias(name))
    zeros = F.array_repeat(F.lit(0).cast(cnt_type), z)
    byblk = m.groupBy("it", "v").agg(F.map_from_entries(F.collect_list(F.struct("blk", "x"))).alias("b"))
    parts = [F.coalesce(F.try_element_at("b", F.lit(i)), zeros) for i in range(count)]
    return byblk.select("it", "v", F.concat(*parts).alias(name))


def multiply_add(a: DataFrame, s: DataFrame, k: int, size: int, passive: int, z: int, cnt_type: str = "double", impl: str = "arrow", order: str = "by_vertex") -> DataFrame:
    """M_s[:, i] += M_a[:, j] * S_p[:, l] over all splits (i, j, l).

    impl: "arrow" (numpy columns), "expr" (generated sums), "hof" (higher-order functions), "auto". order: "by_vertex" has
    a task finish all color sets of its vertices, "by_color" goes through all vertices for one block of color sets after the other.
    """
    active = size - passive
    x = whole_rows(a, blocks(k, active, z), z, "xa", cnt_type)
    y = whole_rows(s, blocks(k, passive, z), z, "xp", cnt_type)
    both = merged(x).join(y, ["it", "v"]).select("it", "v", "xa", "xp")
    n, w = comb(k, size), width(k, size, z)
    if impl == "auto":
        impl = "expr" if n * comb(size, passive) <= MOST_EXPRESSIONS else "arrow"
    if order not in ("by_vertex", "by_color"):
        raise ValueError("order must be by_vertex or by_color")
    if impl == "arrow":
        if order == "by_vertex":
            return arrow_multiply_add(both, k, size, passive, w, cnt_type)
        parts = [arrow_multiply_add(both, k, size, passive, w, cnt_type, b) for b in range(blocks(k, size, z))]
        return reduce(DataFrame.union, parts)
    rs, ra, rp = split_arrays(k, size, passive)
    starts = np.searchsorted(rs, np.arange(n + 1))
    if impl == "expr":
        cells = [sum((F.get("xa", F.lit(int(ra[t]))) * F.get("xp", F.lit(int(rp[t]))) for t in range(starts[i] + 1, starts[i + 1])), F.get("xa", F.lit(int(ra[starts[i]]))) * F.get("xp", F.lit(int(rp[starts[i]])))) for i in range(n)]
        whole = F.array(*[c.cast(cnt_type) for c in cells])
    elif impl == "hof":
        per = comb(size, passive)
        js = F.array(*[F.lit(int(v)) for v in ra]) if n * per <= 4096 else None
        if js is None:
            raise ValueError("impl 'hof' is for up to 4,096 splits")
        ls = F.array(*[F.lit(int(v)) for v in rp])
        whole = F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda i: F.aggregate(F.sequence(i * per, i * per + per - 1), F.lit(0).cast(cnt_type), lambda acc, t: (acc + F.get("xa", F.get(js, t)) * F.get("xp", F.get(ls, t))).cast(cnt_type)))
    else:
        raise ValueError("impl must be arrow, expr, hof or auto")
    out = both.select("it", "v", whole.alias("whole"))
    count = blocks(k, size, z)
    pieces = F.array(*[F.struct(F.lit(b).alias("blk"), F.slice("whole", b * w + 1, w).alias("x")) for b in range(count)])
    return out.select("it", "v", F.explode(pieces).alias("p")).select("it", "v", "p.blk", "p.x").where(F.exists("x", lambda e: e != 0))


def arrow_multiply_add(both: DataFrame, k: int, size: int, passive: int, w: int, cnt_type: str, only: int | None = None) -> DataFrame:
    """only: the one block of the result to make."""
    kind = DTYPES[cnt_type]
    arrow = pa.from_numpy_dtype(kind)
    n, per = comb(k, size), comb(size, passive)
    some = range(-(-n // w)) if only is None else [only]

    def columns(array: pa.Array) -> np.ndarray:
        """A color set in each row, a vertex in each column. flatten() heeds a slice's offset, values doesn't."""
        flat = array.flatten().to_numpy(zero_copy_only=False)
        return np.ascontiguousarray(flat.reshape(len(array), -1).T).astype(kind, copy=False)

    def run(batches):
        for batch in batches:
            # Rows at a time, so that their counts stay below 64 MB and the products of one color set below 32 MB.
            rows = max(16, min((64 << 20) // (8 * (comb(k, size - passive) + comb(k, passive) + w)), (32 << 20) // (8 * per)))
            for at in range(0, batch.num_rows, rows):
                part = batch.slice(at, rows)
                xa, xp = columns(part.column(2)), columns(part.column(3))
                wide = kind is np.int64 and xa.size and float(xa.max()) * float(xp.max()) * per >= 2.0**63
                group = max(1, (32 << 20) // (8 * per * part.num_rows))
                for b in some:
                    low, high = b * w, min(n, b * w + w)
                    out = np.zeros((w, part.num_rows), kind)
                    for first in range(low, high, group):
                        last = min(high, first + group)
                        _, ra, rp = split_arrays(k, size, passive, first, last)
                        if wide and ((xa[ra].astype(float) * xp[rp]).reshape(last - first, per, -1).sum(1) >= 2.0**63).any():
                            raise OverflowError("counts exceed 64 bits; use cnt_type double, or decimal in the relational programs")
                        out[first - low : last - low] = (xa[ra] * xp[rp]).reshape(last - first, per, -1).sum(1)
                    keep = np.flatnonzero(out.any(0))
                    if len(keep):
                        flat = pa.array(np.ascontiguousarray(out[:, keep].T).ravel(), arrow)
                        lists = pa.ListArray.from_arrays(pa.array(np.arange(0, len(flat) + 1, w, dtype=np.int32)), flat)
                        pick = pa.array(keep)
                        yield pa.RecordBatch.from_arrays([part.column(0).take(pick), part.column(1).take(pick), pa.array(np.full(len(keep), b, np.int32)), lists], names=["it", "v", "blk", "x"])

    return both.mapInArrow(run, f"it int, v long, blk int, x array<{cnt_type}>")


def to_relational(m: DataFrame, k: int, size: int, w: int) -> DataFrame:
    """(it, v, mask, cnt) of the cells that are not zero."""
    from ..functions.colorsets import catalog

    cells = m.select("it", "v", (F.col("blk") * w).alias("base"), F.posexplode("x").alias("pos", "cnt")).where("cnt <> 0")
    ranks = catalog(m.sparkSession, k, size).select("rank", "mask")
    return cells.select("it", "v", (F.col("base") + F.col("pos")).alias("rank"), "cnt").join(ranks, "rank").select("it", "v", "mask", "cnt")


def to_wide(m: DataFrame, w: int) -> DataFrame:
    """One column for each count of a block; for comparing layouts."""
    return m.select("it", "v", "blk", *[F.get("x", F.lit(i)).alias(f"c{i}") for i in range(w)])


def neighbor_sum_wide(edges: DataFrame, wide: DataFrame, w: int) -> DataFrame:
    rows = edges.join(merged(wide.withColumnRenamed("v", "dst")), "dst")
    return rows.groupBy("it", F.col("src").alias("v"), "blk").agg(*[F.sum(f"c{i}").alias(f"c{i}") for i in range(w)])
