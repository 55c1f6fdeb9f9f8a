"""Edges packed by the parts of their ends, each undirected edge once: triangles, and walks of three edges.

Vertices fall into parts by a hash; a cell has the edges between two parts, or within one. A task has the three cells of three
parts and bounded bytes, so an edge travels as often as there are parts, in few bytes, and no pair of neighbours travels at all.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.graphs import Graph
from ..storage import settle
from .fused import squeezed, unsqueezed

WIDE = "decimal(38,0)"
#: Edges that a task holds, in a row of packed ones, and pairs and marks (bytes) that it looks at once.
MOST_EDGES, ROW_EDGES, MOST_PAIRS, MOST_MARKS = 1 << 23, 1 << 16, 1 << 20, 1 << 24


def packed(g: Graph) -> tuple[DataFrame, int]:
    """(i, j, e): the edges of the cell of two parts i <= j, those of one row following on those of the last; and the number of parts."""
    one = g.edges.where("src < dst") if g.rows is not None else settle(g.edges.where("src < dst"), "table", "edges")
    parts = max(1, math.ceil(math.sqrt(6 * (g.rows // 2 if g.rows is not None else one.count()) / MOST_EDGES)))
    part = lambda c: F.pmod(F.xxhash64(c), F.lit(parts)).cast("int")
    rows = one.select(F.least(part("src"), part("dst")).alias("i"), F.greatest(part("src"), part("dst")).alias("j"), "src", "dst")
    rows = rows.repartition(parts * (parts + 1) // 2, "i", "j").sortWithinPartitions("i", "j", "src", "dst")

    def run(batches):
        at, held, n = None, [], 0

        def row():
            src, dst = (np.concatenate(x) for x in zip(*held, strict=True))
            return pa.RecordBatch.from_arrays([pa.array([at[0]], pa.int32()), pa.array([at[1]], pa.int32()), pa.array([squeezed(src, dst)], pa.binary())], names=["i", "j", "e"])

        for batch in batches:
            if not batch.num_rows:
                continue
            i, j, src, dst = (batch.column(c).to_numpy(zero_copy_only=False) for c in range(4))
            starts = np.flatnonzero(np.concatenate([[True], (i[1:] != i[:-1]) | (j[1:] != j[:-1])]))
            for low, high in zip(starts, [*starts[1:], len(i)], strict=True):
                here = int(i[low]), int(j[low])
                if held and (here != at or n >= ROW_EDGES):
                    yield row()
                    held, n = [], 0
                at, n = here, n + high - low
                held.append((src[low:high], dst[low:high]))
        if held:
            yield row()

    return settle(rows.mapInArrow(run, "i int, j int, e binary"), "table", "cells"), parts


def grouped(batches, keys: int):
    """(key, batch of its rows) of batches in the order of their first columns, a batch of a key after the other."""
    for batch in batches:
        if batch.num_rows:
            cols = [batch.column(c).to_numpy(zero_copy_only=False) for c in range(keys)]
            starts = np.flatnonzero(np.concatenate([[True], np.any([c[1:] != c[:-1] for c in cols], axis=0)]))
            for low, high in zip(starts, [*starts[1:], batch.num_rows], strict=True):
                yield tuple(int(c[low]) for c in cols), batch.slice(low, high - low)


def closed(edges: list[np.ndarray]) -> int:
    """Triangles of undirected edges, given as sources and then targets. Edges point up in degree, so a vertex starts few pairs
    however many neighbours it has; a vertex's neighbours are marked, and its neighbours' neighbours looked up."""
    src, dst = (np.concatenate([e.reshape(2, -1)[i] for e in edges]) for i in range(2))
    edges.clear()
    ids = np.unique(np.concatenate([np.unique(src), np.unique(dst)]))
    s, d = np.searchsorted(ids, src).astype(np.int32), np.searchsorted(ids, dst).astype(np.int32)
    del src, dst
    n = len(ids)
    place = np.empty(n, np.int32)
    place[np.argsort(np.bincount(s, minlength=n) + np.bincount(d, minlength=n), kind="stable")] = np.arange(n, dtype=np.int32)
    s, d = place[s], place[d]
    key = np.minimum(s, d).astype(np.int64) * n + np.maximum(s, d)
    del s, d
    key.sort()
    u, v = key // n, key % n
    del key
    near = v.astype(np.int32)
    ends = np.concatenate([[0], np.cumsum(np.bincount(u, minlength=n))])
    step, found = max(1, MOST_MARKS // n), 0
    marks = np.zeros(step * n, bool)
    for first in range(0, n, step):
        low, high = ends[first], ends[min(first + step, n)]
        if low == high:
            continue
        row = (u[low:high] - first) * n
        marks[row + v[low:high]] = True
        many = ends[v[low:high] + 1] - ends[v[low:high]]
        done = np.cumsum(many)
        a = 0
        while a < len(row):
            b = max(a + 1, int(np.searchsorted(done, (done[a - 1] if a else 0) + MOST_PAIRS, side="right")))
            m = many[a:b]
            before = np.cumsum(m) - m
            at = np.arange(int(m.sum())) + np.repeat(ends[v[low + a : low + b]] - before, m)
            found += int(np.count_nonzero(marks[np.repeat(row[a:b], m) + near[at]]))
            a = b
        marks[row + v[low:high]] = False
    return found


def triangles(pack: DataFrame, parts: int) -> DataFrame:
    """(cnt). The task of three parts finds the triangles between them. Those within one part are found by its own task and by the
    tasks of it with each other part, so its own task takes them back."""
    k = F.explode(F.sequence(F.lit(0), F.lit(parts - 1)))
    rows = pack.select("i", "j", k.alias("k"), "e").withColumn("t", F.array_sort(F.array("i", "j", "k")))
    rows = rows.select(*[F.col("t")[n].alias(f"t{n}") for n in range(3)], "e")
    rows = rows.repartition(math.comb(parts + 2, 3), "t0", "t1", "t2").sortWithinPartitions("t0", "t1", "t2")

    def run(batches):
        at, edges = None, []

        def result():
            return pa.RecordBatch.from_arrays([pa.array([closed(edges) * (2 - parts if at[0] == at[2] else 1)])], names=["n"])

        for key, part in grouped(batches, 3):
            if edges and key != at:
                yield result()
                edges.clear()
            at = key
            edges += [unsqueezed(e) for e in part.column(3).to_pylist()]
        if edges:
            yield result()

    return rows.mapInArrow(run, "n long").agg(F.coalesce(F.sum(F.col("n").cast(WIDE)), F.lit(0)).cast(WIDE).alias("cnt"))


def degrees(pack: DataFrame) -> DataFrame:
    """(v, d)."""

    def run(batches):
        held, n = [], 0

        def counted():
            v, d = np.unique(np.concatenate(held), return_counts=True)
            for i in range(0, len(v), ROW_EDGES):
                yield pa.RecordBatch.from_arrays([pa.array(v[i : i + ROW_EDGES]), pa.array(d[i : i + ROW_EDGES])], names=["v", "n"])

        for batch in batches:
            for e in batch.column(0).to_pylist():
                held.append(unsqueezed(e))
                n += len(held[-1])
                if n >= MOST_EDGES:
                    yield from counted()
                    held, n = [], 0
        if held:
            yield from counted()

    return pack.select("e").mapInArrow(run, "v long, n long").groupBy("v").agg(F.sum("n").alias("d"))


def walks(pack: DataFrame, parts: int) -> DataFrame:
    """(cnt): over edges, the further neighbours of one end times those of the other. A task has a cell and the degrees of its parts."""
    d = settle(degrees(pack), "table", "degrees").select(F.pmod(F.xxhash64("v"), F.lit(parts)).cast("int").alias("i"), F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("j"), "v", "d")
    d = d.select(F.least("i", "j").alias("i"), F.greatest("i", "j").alias("j"), F.lit(0).alias("side"), "v", "d", F.lit(None).cast("binary").alias("e"))
    e = pack.select("i", "j", F.lit(1).alias("side"), F.lit(0).cast("long").alias("v"), F.lit(0).cast("long").alias("d"), "e")
    rows = d.union(e).repartition(parts * (parts + 1) // 2, "i", "j").sortWithinPartitions("i", "j", "side", "v")

    def run(batches):
        at, v, d = None, [], []
        total = 0
        for key, part in grouped(batches, 3):
            if key[:2] != at:
                at, v, d = key[:2], [], []
            if not key[2]:
                v.append(part.column(3).to_numpy())
                d.append(part.column(4).to_numpy())
                continue
            v, d = [np.concatenate(v)], [np.concatenate(d)]
            for x in part.column(5).to_pylist():
                a, b = (d[0][np.searchsorted(v[0], ends)] - 1 for ends in unsqueezed(x).reshape(2, -1))
                # Whole numbers of any size where 64 bits might not do.
                wide = float(a.max()) * float(b.max()) * len(a) >= 2.0**63
                total += int((a.astype(object) * b).sum()) if wide else int((a * b).sum())
        yield pa.RecordBatch.from_arrays([pa.array([str(total)])], names=["n"])

    return rows.mapInArrow(run, "n string").agg(F.coalesce(F.sum(F.col("n").cast(WIDE)), F.lit(0)).cast(WIDE).alias("cnt"))
