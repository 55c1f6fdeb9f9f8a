"""Packing documents into fixed windows: non-negative least squares over shallow length combinations.

Every document is cut into full windows and one tail shorter than a window. All that is planned
is planned on the histogram of tail lengths, which has a bin for each length below the window and
so does not grow with the data:

1. combinations of up to three tail lengths that fill a window exactly are enumerated;
2. non-negative least squares finds how often to repeat each so that the histogram is met best: an
   active-set search over all combinations, so few of them are used and each many times;
3. counts are rounded by largest remainder, as far as the histogram allows;
4. greedily, the longest tail left gets companions, of which the last three or fewer complete the window exactly;
5. what then is left, less than fills a few windows, is cut into powers of two, which fill windows without a gap.

A tail's place follows from its length and its number among the tails of that length.
"""

from __future__ import annotations

import struct
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import commit, raw_bytes, ready, slices
from .tokens import encoder, vocabulary

WINDOW = 2048


def combinations(present: np.ndarray, window: int) -> np.ndarray:
    """Pairs and triples of the lengths present that add up to the window, as rows of three lengths, 0 where unused."""
    there = np.zeros(window + 1, bool)
    there[present] = True
    pairs = present[(present <= window // 2) & there[window - present]]
    rows = [np.stack([np.zeros_like(pairs), pairs, window - pairs], 1)]
    for a in present[present <= window // 3]:
        b = present[(present >= a) & (present <= (window - a) // 2)]
        b = b[there[window - a - b]]
        rows.append(np.stack([np.full_like(b, a), b, window - a - b], 1))
    return np.concatenate(rows)


def nnls(combos: np.ndarray, histogram: np.ndarray, rounds: int = 40, batch: int = 256) -> tuple[np.ndarray, np.ndarray]:
    """Indices of combinations and their repeat counts x > 0 that minimise the squared distance to the histogram.

    An active set grows by the combinations with the largest gradient that share no length; least squares on the
    set is solved by conjugate gradients, and where a count would turn negative the step ends at the boundary and that
    combination leaves the set. It ends when no combination has a gradient left or the distance falls no more.
    """
    target = histogram.astype(float).copy()
    target[0] = 0
    active, x, last = np.zeros(0, np.int64), np.zeros(0), np.inf

    def met(rows, v):
        out = np.bincount(rows.ravel(), np.repeat(v, 3), len(target))
        out[0] = 0
        return out

    def solve(rows, v):
        v = v.copy()
        r = (target - met(rows, v))[rows].sum(1)
        d, rr = r.copy(), r @ r
        for _ in range(200):
            if rr < 1e-6 * len(v):
                break
            q = met(rows, d)[rows].sum(1) + 1e-7 * d
            step = rr / (d @ q)
            v += step * d
            r -= step * q
            rr, was = r @ r, rr
            d = r + rr / was * d
        return v

    for _ in range(rounds):
        gradient = (target - met(combos[active], x))[combos].sum(1)
        gradient[active] = 0
        new = disjoint(combos, gradient, batch, len(target))
        active, x = np.concatenate([active, new]), np.concatenate([x, np.zeros(len(new))])
        for inner in range(8):
            z = solve(combos[active], x)
            bad = z <= 1e-9
            if not bad.any():
                break
            moved = bad & (x > 0)
            step = (x[moved] / (x[moved] - z[moved])).min() if moved.any() and inner < 7 else 1.0
            x = x + step * (z - x)
            keep = ~bad | (x > 1e-9)
            active, x = active[keep], x[keep]
        else:
            z = x
        x = np.maximum(z, 0)
        distance = np.linalg.norm(target - met(combos[active], x))
        if not len(new) or distance > 0.999 * last:
            break
        last = distance
    return active, x


def disjoint(combos: np.ndarray, gradient: np.ndarray, most: int, size: int, least: float = 1e-3) -> np.ndarray:
    """At most so many combinations of positive gradient, the largest first, none sharing a length with an earlier one."""
    top = np.flatnonzero(gradient > least)
    if len(top) > 20 * most:
        top = top[np.argpartition(-gradient[top], 20 * most)[: 20 * most]]
    used, out = np.zeros(size, bool), []
    for k in top[np.argsort(-gradient[top], kind="stable")]:
        if not used[combos[k]].any():
            used[combos[k]] = True
            used[0] = False
            out.append(k)
            if len(out) == most:
                break
    return np.array(out, np.int64)


def companions(left: np.ndarray, rest: int) -> list[int] | None:
    """Lengths out of ``left`` (counts by length) that add up to ``rest``: the longest that fit, and at the end one, two or
    three that complete it exactly. None if there are none such."""
    left, chosen = left.copy(), []
    while True:
        if left[rest]:
            return [*chosen, rest]
        there = np.flatnonzero(left[:rest])

        def pair(rest, there):
            b = there[there <= rest // 2]
            b = b[(left[rest - b] > 0) & ((2 * b != rest) | (left[b] > 1))]
            return [int(b[-1]), int(rest - b[-1])] if len(b) else None

        found = pair(rest, there)
        if found:
            return chosen + found
        for c in there[there <= rest - 2][::-1].tolist():
            if rest > 3 * c:  # three of at most c each are too short
                break
            left[c] -= 1
            smaller = there[there <= c]
            found = pair(rest - c, smaller[smaller < rest - c])
            left[c] += 1
            if found and (c not in found or left[c] > found.count(c)):
                return [*chosen, c, *found]
        if not len(there):
            return None
        chosen.append(int(there[-1]))
        left[there[-1]] -= 1
        rest -= int(there[-1])


@dataclass
class Plan:
    """slots: rows (length, first tail number, tails, first sequence, offset); cut_from: for each length the number from
    which tails are cut; solved, greedy, cut: how many tails each way placed."""

    window: int
    slots: np.ndarray
    cut_from: np.ndarray
    cut_base: np.ndarray
    patterns: int
    sequences: int
    cut_tokens: int
    solved: int
    greedy: int
    cut: int


def parts_of(length: int) -> list[int]:
    """The powers of two that add up to a length, the largest first."""
    return [1 << j for j in range(length.bit_length() - 1, -1, -1) if length >> j & 1]


def plan_tails(histogram: np.ndarray, window: int = WINDOW) -> Plan:
    """histogram[length] = number of tails; the window is a power of two."""
    left = histogram.astype(np.int64).copy()
    left[0] = 0
    chosen: list[tuple[tuple[int, ...], int]] = []

    def take(combo: tuple[int, ...], most: int) -> None:
        need = {x: combo.count(x) for x in combo}
        n = min(most, *(int(left[x]) // k for x, k in need.items()))
        if n > 0:
            for x, k in need.items():
                left[x] -= n * k
            chosen.append((combo, n))

    combos = combinations(np.flatnonzero(left), window)
    if len(combos):
        active, x = nnls(combos, left)
        whole = np.floor(x + 1e-6).astype(np.int64)
        lengths = [tuple(int(v) for v in combos[k] if v) for k in active]
        for k in np.argsort(-x, kind="stable"):
            take(lengths[k], int(whole[k]))
        for k in np.argsort(whole - x, kind="stable"):
            take(lengths[k], 1)
    solved = sum(len(c) * n for c, n in chosen)
    for a in range(window - 1, 0, -1):
        while left[a]:
            left[a] -= 1
            found = companions(left, window - a)
            left[a] += 1
            if not found:
                break
            take((*sorted(found), a), 1 << 62)
    greedy = sum(len(c) * n for c, n in chosen) - solved
    slots, used, seq = [], np.zeros(window, np.int64), 0
    for combo, n in chosen:
        offset = 0
        for length in combo:
            slots.append((length, used[length], n, seq, offset))
            used[length] += n
            offset += length
        seq += n
    # The rest: part sizes from the largest, so that each part starts at a multiple of its own size.
    bits = window.bit_length() - 1
    cut_base = np.zeros((window, bits), np.int64)
    at = 0
    for j in range(bits - 1, -1, -1):
        for length in np.flatnonzero(left):
            if length >> j & 1:
                cut_base[length, j] = at
                at += int(left[length]) << j
    return Plan(window, np.array(sorted(slots), np.int64).reshape(-1, 5), used, cut_base, seq, seq + at // window + (at % window).bit_count(), at, solved, greedy, int(left.sum()))


def place(plan: Plan, length: int, number: int) -> list[tuple[int, int, int]]:
    """(length, sequence, offset) of each piece of a tail, in the order of its tokens."""
    if number < plan.cut_from[length]:
        a = np.searchsorted(plan.slots[:, 0], length)
        b = np.searchsorted(plan.slots[:, 0], length, side="right")
        k = a + np.searchsorted(plan.slots[a:b, 1], number, side="right") - 1
        _, first, _, seq, offset = (int(v) for v in plan.slots[k])
        return [(length, seq + number - first, offset)]
    out = []
    for size in parts_of(length):
        at = int(plan.cut_base[length, size.bit_length() - 1]) + (number - int(plan.cut_from[length])) * size
        seq, offset = divmod(at, plan.window)
        if seq == plan.cut_tokens // plan.window:  # the last window is several sequences, each a power of two long
            for step in parts_of(plan.cut_tokens % plan.window):
                if offset < step:
                    break
                seq, offset = seq + 1, offset - step
        out.append((size, plan.patterns + seq, offset))
    return out


LENGTHS = "pid int, doc_id long, doc_tokens long, full_crc array<long>, full_before long, tail int, tail_crc long, part_crc array<long>, rank long"
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


def pack(docs: DataFrame, path: str, kind: str = "words", end_id: int = 1, window: int = WINDOW) -> DataFrame:
    """One row per piece. Each text is encoded once; null text is empty and is packed as its end id.

    Sequences are numbered from 0: combinations, then cut tails, then full windows. All are full
    but for at most one of each smaller power of two at the end of the cut tails, so none takes padding.
    An empty table gives no rows; repeated rows are packed each.
    """
    if window & (window - 1):
        raise ValueError("window must be a power of two")

    def measure(batches):
        enc, pid, end = encoder(path, kind), TaskContext.get().partitionId(), struct.pack("<I", end_id)
        ranks, full = [0] * window, 0
        for batch in batches:
            for some in slices(batch, "text"):
                rows: list[tuple] = []
                for doc_id, ids in zip(some.column(0).to_pylist(), enc.encode(raw_bytes(some.column(1))), strict=True):
                    ids += end
                    n = len(ids) // 4
                    tail, size = n % window, 4 * window
                    edge = n // window * size
                    parts, at = [], edge
                    for p in parts_of(tail):
                        parts.append(zlib.crc32(ids[at : at + 4 * p]))
                        at += 4 * p
                    rows.append((pid, doc_id, n, [zlib.crc32(ids[a : a + size]) for a in range(0, edge, size)], full, tail, zlib.crc32(ids[edge:]), parts, ranks[tail]))
                    ranks[tail] += 1
                    full += n // window
                kinds = [pa.int32(), pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.int64(), pa.int32(), pa.int64(), pa.list_(pa.int64()), pa.int64()]
                yield pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=["pid", "doc_id", "doc_tokens", "full_crc", "full_before", "tail", "tail_crc", "part_crc", "rank"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    measured = commit(rows.mapInArrow(measure, LENGTHS), "packing")
    counts = commit(measured.groupBy("pid", "tail").agg(F.count("*").alias("n"), F.sum(F.size("full_crc")).alias("full")), "packing-counts")
    # At most one row for each length below the window.
    histogram = np.zeros(window, np.int64)
    for row in counts.groupBy("tail").agg(F.sum("n").alias("n")).collect():
        histogram[row.tail] = row.n
    plan = plan_tails(histogram, window)
    earlier = lambda *by: Window.partitionBy(*by).orderBy("pid").rowsBetween(Window.unboundedPreceding, -1)
    tails = counts.select("pid", "tail", F.coalesce(F.sum("n").over(earlier("tail")), F.lit(0)).alias("tails_before"))
    # One row for each task of the first pass.
    tasks = counts.groupBy("pid").agg(F.sum("full").alias("full")).select("pid", F.coalesce(F.sum("full").over(Window.orderBy("pid").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("task_before"))
    placed = measured.join(tails.join(tasks, "pid"), ["pid", "tail"])
    names = [f.split()[0] for f in PIECES.split(", ")]

    def lay(batches):
        for batch in batches:
            out: list[tuple] = []
            for r in batch.to_pylist():
                base = plan.sequences + r["task_before"] + r["full_before"]
                for k, crc in enumerate(r["full_crc"]):
                    out.append((r["doc_id"], k * window, window, crc, r["doc_tokens"], base + k, 0))
                at = len(r["full_crc"]) * window
                pieces = place(plan, r["tail"], r["tails_before"] + r["rank"]) if r["tail"] else []
                for (length, seq, offset), crc in zip(pieces, [r["tail_crc"]] if len(pieces) == 1 else r["part_crc"], strict=True):
                    out.append((r["doc_id"], at, length, crc, r["doc_tokens"], seq, offset))
                    at += length
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(list(c), pa.int64()) for c in zip(*out, strict=True)], names=names)

    return placed.mapInArrow(lay, PIECES)


def op10(spark: SparkSession, docs: DataFrame, path: str | None = None) -> DataFrame:
    """Every document packed with the given vocabulary, one row per piece; see :func:`pack`."""
    ready(spark)
    return pack(docs, path or vocabulary("word_bpe_49k.json"))
