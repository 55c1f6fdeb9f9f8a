"""Other ways to sum over neighbours: on a grid of vertex ranges, and with hubs taken apart."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .blocked import DTYPES, neighbor_sum


def grid_parts(edge_rows: int, cells: float, most_bytes: int = 64 << 20) -> int:
    """Ranges for a grid whose cells hold at most so many bytes of edges (16 each) and of counts (8 each; ``cells`` in all)."""
    return max(2, math.ceil(max(math.sqrt(16 * edge_rows / most_bytes), 8 * cells / most_bytes)))


def grid_sum(edges: DataFrame, m: DataFrame, w: int, parts: int = 4, cnt_type: str = "double") -> DataFrame:
    """Vertices are dealt to ``parts`` ranges and edges to parts x parts cells; each cell meets the counts of its column once.

    A count then travels ``parts`` times and not once for each edge, which pays on networks whose average degree
    is above ``parts``; :func:`grid_parts` says how many a cell's memory takes. Partial sums of a row of cells are added at the end.
    """
    kind = DTYPES[cnt_type]
    cell = lambda c: F.pmod(F.xxhash64(c), F.lit(parts)).cast("int")
    e = edges.select(cell("src").alias("bi"), cell("dst").alias("bj"), "src", "dst")
    side = m.select(F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("bi"), cell("v").alias("bj"), "it", "v", "blk", "x")

    def meet(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        out = []
        src, rows = np.unique(left["src"].to_numpy(np.int64), return_inverse=True)
        for (it, blk), part in right.groupby(["it", "blk"]):
            ids = part["v"].to_numpy(np.int64)
            order = np.argsort(ids)
            x = np.array(part["x"].tolist(), kind).reshape(len(ids), -1)[order]
            at = np.searchsorted(ids[order], left["dst"].to_numpy(np.int64))
            at[at == len(ids)] = 0
            hit = ids[order][at] == left["dst"].to_numpy(np.int64)
            total = np.zeros((len(src), x.shape[1]), kind)
            np.add.at(total, rows[hit], x[at[hit]])
            used = np.flatnonzero(total.any(1))
            if len(used):
                out.append(pd.DataFrame({"it": np.int32(it), "v": src[used], "blk": np.int32(blk), "x": list(total[used])}))
        return pd.concat(out) if out else pd.DataFrame({"it": [], "v": [], "blk": [], "x": []}, dtype=object)

    part = e.groupBy("bi", "bj").cogroup(side.groupBy("bi", "bj")).applyInPandas(meet, f"it int, v long, blk int, x array<{cnt_type}>")
    sums = part.groupBy("it", "v", "blk").agg(*[F.sum(F.get("x", F.lit(i))).alias(f"s{i}") for i in range(w)])
    return sums.select("it", "v", "blk", F.array(*[F.col(f"s{i}").cast(cnt_type) for i in range(w)]).alias("x"))


def hub_sum(edges: DataFrame, m: DataFrame, w: int, most: int = 100_000, most_hubs: int = 1000, cnt_type: str = "double") -> DataFrame:
    """As the plain sum, with the counts of vertices that more than ``most`` edges lead to sent to all tasks.

    Those hubs would fill one partition of the join each. There are at most nE / ``most`` of them; beyond
    ``most_hubs`` only the largest are sent and the rest is left to the skew handling of adaptive execution. Where their
    counts have too many blocks and iterations to be sent, they are joined as all others are.
    """
    degree = edges.groupBy("dst").agg(F.count("*").alias("d")).where(F.col("d") > most)
    hubs = F.broadcast(degree.orderBy(F.desc("d"), "dst").limit(most_hubs).select("dst"))
    near = neighbor_sum(edges.join(hubs, "dst", "left_semi"), m.join(hubs.withColumnRenamed("dst", "v"), "v", "left_semi"), w, cnt_type, broadcast=True)
    far = neighbor_sum(edges.join(hubs, "dst", "left_anti"), m, w, cnt_type)
    sums = near.union(far).groupBy("it", "v", "blk").agg(*[F.sum(F.get("x", F.lit(i))).alias(f"s{i}") for i in range(w)])
    return sums.select("it", "v", "blk", F.array(*[F.col(f"s{i}").cast(cnt_type) for i in range(w)]).alias("x"))
