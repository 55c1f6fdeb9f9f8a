"""The kernels on sparse blocks, with all children of a node multiplied at once: (it, v, blk, bits, x), bits saying which of up
to 64 color sets of the block x has counts of.

Only a table that neighbours sum up leaves its task. A vertex's own color lies in every set it counts and in none that it
takes from its neighbours, so it is left out: products run over sets of the other k - 1 colors.
"""

from __future__ import annotations

import math
from functools import lru_cache, reduce
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.coloring import color_in_python
from ..functions.colorsets import ranks_of, sets_of, split_arrays
from .blocked import DTYPES
from .relational import bit

#: Bytes of edges or of sums that a task of the neighbour sum holds, and vertices whose counts of a block it holds at once.
MOST_BYTES, MOST_ROWS = 64 << 20, 1 << 16
#: Edges in a row of packed ones.
PACKED_EDGES = 1 << 16
#: Edges that splits are gone through for at once, so that their counts stay in a cache.
WALKED_EDGES = 1 << 14
#: Tasks that share the blocks of a neighbour sum; each is sent the edges of its range.
GROUPS = 12


def leaf(coloring: DataFrame, cnt_type: str, w: int) -> DataFrame:
    return coloring.select("it", "v", F.floor(F.col("color") / w).cast("int").alias("blk"), bit(F.col("color") % w).alias("bits"), F.array(F.lit(1).cast(cnt_type)).alias("x"))


def ranges(edge_rows: int, vertices: int) -> int:
    """Ranges of receiving vertices, so that a task's edges and the sums of a block stay below the bound."""
    return max(1, math.ceil(max(16 * edge_rows, 512 * vertices) / MOST_BYTES))


def spread(parts: int, edge_rows: int, tasks: int, widest: int) -> int:
    """As many ranges as tasks where counts are one block a vertex, so that they are cheap to send and blocks give no tasks."""
    return max(parts, min(tasks, edge_rows >> 19)) if widest <= 64 else parts


def packed(edges: DataFrame, parts: int, rows: int) -> DataFrame:
    """(r, e): the edges of each range of receiving vertices, those of some vertices in each row, as :func:`squeezed` has them.
    Targets are dealt by their upper digits too, so that no hub's edges are one row."""
    near = F.shiftright("dst", 20)
    r, some = F.pmod(F.xxhash64("src"), F.lit(parts)).cast("int").alias("r"), F.pmod(F.xxhash64("src", near, F.lit(1)), F.lit(max(1, rows // (PACKED_EDGES * parts))))
    lists = edges.groupBy(r, some.alias("some")).agg(F.collect_list(F.struct("src", "dst")).alias("l")).select("r", F.col("l.src").alias("src"), F.col("l.dst").alias("dst"))

    def run(batches):
        for batch in batches:
            e = [squeezed(s.values.to_numpy(), d.values.to_numpy()) for s, d in zip(batch.column(1), batch.column(2), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(e, pa.binary())], names=["r", "e"])

    return lists.mapInArrow(run, "r int, e binary")


def squeezed(src: np.ndarray, dst: np.ndarray) -> bytes:
    """Edges in few bytes, as each task of a neighbour sum is sent them: differences of sources, then of targets, in the order of
    both, a byte of all numbers after the other, compressed."""
    order = np.lexsort((dst, src))
    steps = np.diff(np.stack([src[order], dst[order]]).astype("<i8"), axis=1, prepend=0)
    return len(src).to_bytes(8, "little") + pa.compress(np.ascontiguousarray(steps.view(np.uint8).reshape(-1, 8).T).tobytes(), codec="zstd", asbytes=True)


def unsqueezed(e: bytes) -> np.ndarray:
    """Sources, then targets."""
    n = int.from_bytes(e[:8], "little")
    planes = np.frombuffer(pa.decompress(e[8:], decompressed_size=16 * n, codec="zstd", asbytes=True), np.uint8)
    steps = np.ascontiguousarray(planes.reshape(8, -1).T).view("<i8").reshape(2, -1)
    return np.cumsum(steps, axis=1, dtype=np.int64).ravel()


def dense(bits: np.ndarray, values: np.ndarray, w: int) -> np.ndarray:
    """Blocks as rows of w counts."""
    on = np.unpackbits(np.ascontiguousarray(bits.astype("<i8")).view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").astype(bool)
    out = np.zeros(on.shape, values.dtype)
    out[on] = values
    return out[:, :w]


def sparse(rows: np.ndarray) -> tuple[np.ndarray, pa.Array]:
    """The bits of rows of up to 64 counts, and the lists of those that aren't zero."""
    on = np.zeros((len(rows), 64), bool)
    on[:, : rows.shape[1]] = rows != 0
    bits = np.packbits(on, axis=1, bitorder="little").view("<i8").ravel().astype(np.int64)
    ends = np.concatenate([[0], np.cumsum(on.sum(1))]).astype(np.int32)
    return bits, pa.ListArray.from_arrays(pa.array(ends), pa.array(rows[rows != 0]))


def table(it, v, blk, rows: np.ndarray) -> pa.RecordBatch:
    bits, x = sparse(rows)
    return pa.RecordBatch.from_arrays([pa.array(it, pa.int32()), pa.array(v, pa.int64()), pa.array(blk, pa.int32()), pa.array(bits), x], names=["it", "v", "blk", "bits", "x"])


def ints(column: pa.Array) -> np.ndarray:
    return column.to_numpy(zero_copy_only=False)


def fits(largest: float) -> None:
    if largest >= 2.0**63:
        raise OverflowError("counts exceed 64 bits; use cnt_type double, or decimal in the relational programs")


class Sums:
    """The neighbours' counts of one block after the other, for the edges of one range."""

    def __init__(self, edges: list[np.ndarray], w: int, kind, unread=None):
        """unread: says of an iteration, vertices and a block which of their sums nothing reads."""
        self.unread = unread
        src = np.concatenate([e[: len(e) // 2] for e in edges])
        dst = np.concatenate([e[len(e) // 2 :] for e in edges])
        self.src, s = np.unique(src, return_inverse=True)
        self.dst, d = np.unique(dst, return_inverse=True)
        order = np.lexsort((s, d // MOST_ROWS))
        self.s, self.d, self.w, self.kind = s[order], d[order], w, kind
        self.cut = np.searchsorted(self.d // MOST_ROWS, np.arange(-(-len(self.dst) // MOST_ROWS) + 1))
        self.clear()

    def clear(self):
        self.total, self.part, self.at = np.zeros((len(self.src), self.w), self.kind), None, 0
        self.check = np.zeros(self.total.shape) if self.kind is np.int64 else None

    def add(self, v: np.ndarray, x: np.ndarray):
        """Rows of ascending vertices."""
        place = np.searchsorted(self.dst, v)
        place[place == len(self.dst)] = 0
        here = self.dst[place] == v
        place, x = place[here], x[here]
        for c in np.unique(place // MOST_ROWS):
            if self.part is not None and c != self.at:
                self.flush()
            if self.part is None:
                self.part, self.at = np.zeros((min(MOST_ROWS, len(self.dst)), self.w), self.kind), c
            some = place // MOST_ROWS == c
            self.part[place[some] - c * MOST_ROWS] = x[some]

    def flush(self):
        if self.part is None:
            return
        low, high = self.cut[self.at], self.cut[self.at + 1]
        d = self.d[low:high] - self.at * MOST_ROWS
        used = self.part.any(1)[d]
        s, d = self.s[low:high][used], d[used]
        for at in range(0, len(s), MOST_ROWS):
            rows = s[at : at + MOST_ROWS]
            first = np.flatnonzero(np.concatenate([[True], rows[1:] != rows[:-1]]))
            near = self.part[d[at : at + MOST_ROWS]]
            self.total[rows[first]] += np.add.reduceat(near, first, axis=0)
            if self.check is not None:
                self.check[rows[first]] += np.add.reduceat(near.astype(float), first, axis=0)
                fits(self.check.max())
        self.part = None

    def result(self, it: int, blk: int):
        self.flush()
        if self.unread:
            self.total[self.unread(it, self.src, blk)] = 0
        used = np.flatnonzero(self.total.any(1))
        for at in range(0, len(used), 8192):
            some = used[at : at + 8192]
            yield table(np.full(len(some), it, np.int32), self.src[some], np.full(len(some), blk, np.int32), self.total[some])
        self.clear()


def with_own_color(k: int, size: int, w: int, seed: int):
    """Which sums of a block are for sets that hold their vertex's own color ("md5"); :func:`multiply_all` reads none of them."""
    known: dict[int, np.ndarray] = {}

    def unread(it: int, v: np.ndarray, blk: int) -> np.ndarray:
        if it not in known:
            known.clear()
            known[it] = np.array([color_in_python(seed, it, int(x), k) for x in v], np.int64)
        sets = sets_of(np.arange(blk * w, min(comb(k, size), blk * w + w)), k, size)
        holds = np.zeros((k, w), bool)
        holds[sets, np.arange(len(sets))[:, None]] = True
        return holds[known[it]]

    return unread


def neighbor_sum(pack: DataFrame, m: DataFrame, parts: int, blocks: int, w: int, cnt_type: str, unread=None) -> DataFrame:
    """The neighbours' counts of each vertex and color set; ``unread`` makes what :class:`Sums` takes for a range. Tasks take a few blocks of all vertices and the edges of a range of
    receiving vertices, so a count travels once for each range, whatever the degree, and sums are whole at once."""
    kind, groups = DTYPES[cnt_type], min(blocks, GROUPS)
    none, zero = F.lit(None), F.lit(0)
    every = lambda n: F.explode(F.sequence(zero, F.lit(n - 1)))
    e = pack.select(every(groups).alias("g"), "r", F.lit(-1).alias("it"), F.lit(-1).alias("blk"), zero.cast("long").alias("v"), zero.cast("long").alias("bits"), none.cast(f"array<{cnt_type}>").alias("x"), "e")
    c = m.select((F.col("blk") % groups).cast("int").alias("g"), every(parts).alias("r"), "it", "blk", "v", "bits", "x", none.cast("binary").alias("e"))
    key = ["g", "r", "it", "blk"]
    rows = e.union(c).repartition(parts * groups, "g", "r").sortWithinPartitions(*key, "v")

    def run(batches):
        at, sums, edges, block = None, None, [], None
        for batch in batches:
            if not batch.num_rows:
                continue
            cols = [ints(batch.column(i)) for i in range(4)]
            starts = np.flatnonzero(np.concatenate([[True], np.any([a[1:] != a[:-1] for a in cols], axis=0)]))
            for low, high in zip(starts, [*starts[1:], batch.num_rows], strict=True):
                g, r, it, blk = (int(a[low]) for a in cols)
                part = batch.slice(low, high - low)
                if block is not None and block != (g, r, it, blk):
                    yield from sums.result(*block[2:])
                    block = None
                if at != (g, r):
                    at, sums, edges = (g, r), None, []
                if blk < 0:
                    edges += [unsqueezed(x) for x in part.column(7).to_pylist()]
                    continue
                if not edges and sums is None:
                    continue  # no vertex of this range has an edge
                if sums is None:
                    sums, edges = Sums(edges, w, kind, unread and unread()), []
                block = (g, r, it, blk)
                for i in range(0, part.num_rows, MOST_ROWS):
                    some = part.slice(i, MOST_ROWS)
                    sums.add(ints(some.column(4)), dense(ints(some.column(5)), some.column(6).flatten().to_numpy(zero_copy_only=False), w))
        if block is not None:
            yield from sums.result(*block[2:])

    return rows.mapInArrow(run, f"it int, v long, blk int, bits long, x array<{cnt_type}>")


def walked(pack: DataFrame, a: DataFrame, p: DataFrame, parts: int, k: int, size: int, passive: int, z: int, cnt_type: str, variant: str) -> DataFrame:
    """A step that goes by single color sets. Tasks take the edges of a range of receiving vertices, the active counts of these
    and all passive counts, one block a vertex. As in :class:`Steps`, v0 and v1 walk all edges again for each split."""
    kind, active = DTYPES[cnt_type], size - passive
    n, na, np_, w = comb(k, size), comb(k, active), comb(k, passive), min(64, z, comb(k, size))
    wa, wp = min(64, z, na), min(64, z, np_)
    none, zero, place = F.lit(None), F.lit(0), lambda c: F.pmod(F.xxhash64(c), F.lit(parts)).cast("int")  # as in packed
    e = pack.select("r", F.lit(-1).alias("it"), zero.alias("side"), zero.alias("blk"), zero.cast("long").alias("v"), zero.cast("long").alias("bits"), none.cast(f"array<{cnt_type}>").alias("x"), "e")
    sides = [(a, place("v")), (p, F.explode(F.sequence(zero, F.lit(parts - 1))))]
    c = [m.select(r.alias("r"), "it", F.lit(i + 1).alias("side"), "blk", "v", "bits", "x", none.cast("binary").alias("e")) for i, (m, r) in enumerate(sides)]
    rows = e.union(c[0]).union(c[1]).repartition(2 * parts, "r").sortWithinPartitions("r", "it", "side", "v", "blk")

    def count(xa, xp, s, d, deepest):
        """Counts by column; s and d are the places of each edge's ends, s ascending. Edges are gone through a few at a time."""
        _, ra, rp = split_arrays(k, size, passive)
        out, per, sums = np.zeros((n, xa.shape[1]), kind), comb(size, passive), {}
        use = np.flatnonzero(xa.any(1)[ra] & xp.any(1)[rp])
        splits = list(zip((use // per).tolist(), ra[use].tolist(), rp[use].tolist(), strict=True))
        wide = kind is np.int64 and float(xa.max()) * float(xp.max()) * deepest * per >= 2.0**63
        check = np.zeros(out.shape) if wide else None
        each = variant in ("v0", "v1")
        for low in range(0, len(s), WALKED_EDGES):
            rows, near = s[low : low + WALKED_EDGES], d[low : low + WALKED_EDGES]
            first = np.flatnonzero(np.concatenate([[True], rows[1:] != rows[:-1]]))
            at = rows[first]
            for i, j, l in splits:
                if variant == "v0":
                    out[i, at] += np.add.reduceat(xa[j][rows] * xp[l][near], first)
                elif variant == "v1":
                    out[i, at] += xa[j, at] * np.add.reduceat(xp[l][near], first)
                if wide:
                    check[i, at] += np.add.reduceat(xa[j][rows].astype(float) * xp[l][near], first)
            if not each:
                for l in {l for _, _, l in splits}:
                    sums.setdefault(l, np.zeros(xa.shape[1], kind))[at] += np.add.reduceat(xp[l][near], first)
        if not each:
            for i, j, l in splits:
                out[i] += xa[j] * sums[l]
        if wide:
            fits(check.max())
        return out

    def run(batches):
        at, edges, own, x = None, [], None, None

        def ends():
            src, dst = np.concatenate([i[: len(i) // 2] for i in edges]), np.concatenate([i[len(i) // 2 :] for i in edges])
            src, s = np.unique(src, return_inverse=True)
            dst, d = np.unique(dst, return_inverse=True)
            order = np.argsort(s, kind="stable")
            return src, dst, s[order], d[order], int(np.bincount(s).max())

        def finish():
            out = count(*x, *own[2:]) if x[0].any() and x[1].any() else np.zeros((n, 1), kind)
            whole = np.zeros((out.shape[1], -(-n // w) * w), kind)
            whole[:, :n] = out.T
            whole = whole.reshape(len(whole), -1, w)
            who, blk = np.nonzero(whole.any(2))
            for i in range(0, len(who), 8192):
                j = slice(i, i + 8192)
                yield table(np.full(len(who[j]), at[1], np.int32), own[0][who[j]], blk[j].astype(np.int32), whole[who[j], blk[j]])

        for batch in batches:
            if not batch.num_rows:
                continue
            cols = [ints(batch.column(i)) for i in range(3)]
            starts = np.flatnonzero(np.concatenate([[True], np.any([c[1:] != c[:-1] for c in cols], axis=0)]))
            for low, high in zip(starts, [*starts[1:], batch.num_rows], strict=True):
                r, it, side = (int(c[low]) for c in cols)
                part = batch.slice(low, high - low)
                if x is not None and at != (r, it):
                    yield from finish()
                    x = None
                if at is None or at[0] != r:
                    edges, own = [], None
                at = (r, it)
                if not side:
                    edges += [unsqueezed(i) for i in part.column(7).to_pylist()]
                    continue
                if not edges and own is None:
                    continue  # no vertex of this range has an edge
                if own is None:
                    own, edges = ends(), []
                if x is None:
                    x = [np.zeros((na, len(own[0])), kind), np.zeros((np_, len(own[1])), kind)]
                ids, v, width = own[side - 1], ints(part.column(4)), (wa, wp)[side - 1]
                to = np.searchsorted(ids, v)
                to[to == len(ids)] = 0
                here = np.flatnonzero(ids[to] == v)
                cells, blk = dense(ints(part.column(5)), part.column(6).flatten().to_numpy(zero_copy_only=False), width), ints(part.column(3))
                for b in np.unique(blk[here]):
                    some, last = here[blk[here] == b], min(width, len(x[side - 1]) - b * width)
                    x[side - 1][b * width : b * width + last, to[some]] = cells[some, :last].T
        if x is not None:
            yield from finish()

    return rows.mapInArrow(run, f"it int, v long, blk int, bits long, x array<{cnt_type}>")


class Steps(Sums):
    """The counts of one step for the vertices of a range, a block of passive counts after the other. v0 walks all edges again for
    each split of each color set and adds products up edge by edge; v1 takes the active count out of that sum; the others walk
    once for each passive set, whose sums the splits look up."""

    def __init__(self, edges: list[np.ndarray], k: int, size: int, passive: int, z: int, kind, variant: str):
        super().__init__(edges, min(z, comb(k, passive)), kind)
        whole, ra, rp = split_arrays(k, size, passive)
        order = np.argsort(rp // self.w, kind="stable")
        self.splits, self.starts = (whole[order], ra[order], rp[order] % self.w), np.searchsorted(rp[order] // self.w, np.arange(comb(k, passive) // self.w + 2))
        self.active, self.out = np.zeros((comb(k, size - passive), len(self.src)), kind), np.zeros((comb(k, size), len(self.src)), kind)
        self.variant, self.per, self.most, self.blk = variant, comb(size, passive), int(np.bincount(self.s).max()), 0

    def of_block(self, has: np.ndarray):
        """Whole, active and passive columns of the splits of the block that both sides have counts for."""
        some = slice(self.starts[self.blk], self.starts[self.blk + 1])
        i, j, l = (x[some] for x in self.splits)
        use = self.active.any(1)[j] & has[l]
        return list(zip(i[use].tolist(), j[use].tolist(), l[use].tolist(), strict=True))

    def checked(self, largest: float):
        """Sums in floating point beside those that might exceed 64 bits, which are whole up to here."""
        wide = self.kind is np.int64 and float(self.out.max()) + float(self.active.max()) * largest * self.per >= 2.0**63
        return self.out.astype(float) if wide else None

    def flush(self):
        if self.variant not in ("v0", "v1") or self.part is None:
            return super().flush()
        low, high = self.cut[self.at], self.cut[self.at + 1]
        s, d, columns = self.s[low:high], self.d[low:high] - self.at * MOST_ROWS, np.ascontiguousarray(self.part.T)
        check, splits = self.checked(float(columns.max()) * self.most), self.of_block(columns.any(1))
        for at in range(0, len(s), WALKED_EDGES):
            rows, near = s[at : at + WALKED_EDGES], d[at : at + WALKED_EDGES]
            first = np.flatnonzero(np.concatenate([[True], rows[1:] != rows[:-1]]))
            to = rows[first]
            for i, j, l in splits:
                if self.variant == "v0":
                    self.out[i, to] += np.add.reduceat(self.active[j][rows] * columns[l][near], first)
                else:
                    self.out[i, to] += self.active[j, to] * np.add.reduceat(columns[l][near], first)
                if check is not None:
                    check[i, to] += np.add.reduceat(self.active[j][rows].astype(float) * columns[l][near], first)
        if check is not None:
            fits(check.max())
        self.part = None

    def end_block(self):
        self.flush()
        if self.variant not in ("v0", "v1"):
            columns = np.ascontiguousarray(self.total.T)
            check = self.checked(float(columns.max()))
            for i, j, l in self.of_block(columns.any(1)):
                self.out[i] += self.active[j] * columns[l]
                if check is not None:
                    check[i] += self.active[j].astype(float) * columns[l]
            if check is not None:
                fits(check.max())
            self.clear()

    def tables(self, it: int, w: int):
        """Blocks of w counts of the vertices that have any; the next iteration begins anew."""
        for low in range(0, len(self.src), 8192):
            some = self.out[:, low : low + 8192]
            whole = np.zeros((some.shape[1], -(-len(some) // w) * w), self.kind)
            whole[:, : len(some)] = some.T
            whole = whole.reshape(len(whole), -1, w)
            who, blk = np.nonzero(whole.any(2))
            for i in range(0, len(who), 8192):
                j = slice(i, i + 8192)
                yield table(np.full(len(who[j]), it, np.int32), self.src[low + who[j]], blk[j].astype(np.int32), whole[who[j], blk[j]])
        self.active[:], self.out[:] = 0, 0


def stepped(pack: DataFrame, a: DataFrame, p: DataFrame, parts: int, k: int, size: int, passive: int, z: int, cnt_type: str, variant: str) -> DataFrame:
    """A step that goes by single color sets, for counts of many blocks a vertex. Tasks take the edges of a range of receiving
    vertices, the active counts of these and all passive counts, of which they hold a block of some vertices at once."""
    kind, none, zero = DTYPES[cnt_type], F.lit(None), F.lit(0)
    e = pack.select("r", F.lit(-1).alias("it"), zero.alias("side"), zero.alias("blk"), zero.cast("long").alias("v"), zero.cast("long").alias("bits"), none.cast(f"array<{cnt_type}>").alias("x"), "e")
    sides = [(a, F.pmod(F.xxhash64("v"), F.lit(parts)).cast("int")), (p, F.explode(F.sequence(zero, F.lit(parts - 1))))]  # as in packed
    c = [m.select(r.alias("r"), "it", F.lit(i + 1).alias("side"), "blk", "v", "bits", "x", none.cast("binary").alias("e")) for i, (m, r) in enumerate(sides)]
    rows = e.union(c[0]).union(c[1]).repartition(2 * parts, "r").sortWithinPartitions("r", "it", "side", "blk", "v")
    wa, wp, w = (min(64, z, comb(k, n)) for n in (size - passive, passive, size))

    def run(batches):
        at, edges, steps = None, [], None  # at: range, iteration, side and block of the rows before
        for batch in batches:
            if not batch.num_rows:
                continue
            cols = [ints(batch.column(i)) for i in range(4)]
            starts = np.flatnonzero(np.concatenate([[True], np.any([c[1:] != c[:-1] for c in cols], axis=0)]))
            for low, high in zip(starts, [*starts[1:], batch.num_rows], strict=True):
                here, part = tuple(int(c[low]) for c in cols), batch.slice(low, high - low)
                r, it, side, blk = here
                if steps is not None and here != at:
                    if at[2] == 2:
                        steps.end_block()
                    if at[:2] != here[:2]:
                        yield from steps.tables(at[1], w)
                if at is None or at[0] != r:
                    edges, steps = [], None
                at = here
                if not side:
                    edges += [unsqueezed(i) for i in part.column(7).to_pylist()]
                    continue
                if not edges and steps is None:
                    continue  # no vertex of this range has an edge
                if steps is None:
                    steps, edges = Steps(edges, k, size, passive, wp, kind, variant), []
                for i in range(0, part.num_rows, MOST_ROWS):
                    some = part.slice(i, MOST_ROWS)
                    v, x = ints(some.column(4)), dense(ints(some.column(5)), some.column(6).flatten().to_numpy(zero_copy_only=False), (wa, wp)[side - 1])
                    if side == 2:
                        steps.blk = blk
                        steps.add(v, x)
                        continue
                    to = np.searchsorted(steps.src, v)
                    to[to == len(steps.src)] = 0
                    mine = np.flatnonzero(steps.src[to] == v)
                    last = min(wa, len(steps.active) - blk * wa)
                    steps.active[blk * wa : blk * wa + last, to[mine]] = x[mine, :last].T
        if steps is not None:
            if at[2] == 2:
                steps.end_block()
            yield from steps.tables(at[1], w)

    return rows.mapInArrow(run, f"it int, v long, blk int, bits long, x array<{cnt_type}>")


@lru_cache(maxsize=512)
def without(k: int, h: int, color: int) -> np.ndarray:
    """The ranks among k colors of the sets of h that lack one, in the order of their ranks among the others."""
    sets = sets_of(np.arange(comb(k - 1, h)), k - 1, h)
    return ranks_of(sets + (sets >= color), k)


@lru_cache(maxsize=512)
def with_own(k: int, h: int, color: int) -> np.ndarray:
    """The ranks among k colors of the sets of h others and one given color, in the order of their ranks among the others."""
    sets = sets_of(np.arange(comb(k - 1, h)), k - 1, h)
    return ranks_of(np.sort(np.concatenate([sets + (sets >= color), np.full((len(sets), 1), color)], axis=1), axis=1), k)


def product(xa: np.ndarray, xp: np.ndarray, k: int, size: int, passive: int) -> np.ndarray:
    """Sums over all splits of the sets of ``size`` of k colors; a color set in each row, a vertex in each column."""
    n, per, many = comb(k, size), comb(size, passive), xa.shape[1]
    wide = xa.dtype == np.int64 and xa.size and float(xa.max()) * float(xp.max()) * per >= 2.0**63
    out, group = np.empty((n, many), xa.dtype), max(1, MOST_BYTES // (16 * per * many))
    for low in range(0, n, group):
        high = min(n, low + group)
        _, ra, rp = split_arrays(k, size, passive, low, high)
        if wide:
            fits((xa[ra].astype(float) * xp[rp]).reshape(high - low, per, many).sum(1).max())
        out[low:high] = np.einsum("spv,spv->sv", xa[ra].reshape(high - low, per, many), xp[rp].reshape(high - low, per, many))
    return out


def multiply_all(sums: list[DataFrame], order: list[int], sizes: list[int], color, k: int, w: int, cnt_type: str, parts: int) -> DataFrame:
    """The table of a node and all its children: ``sums`` are the neighbour sums of the different children, ``sizes`` their nodes,
    ``order`` the children one after the other as places in both. ``color`` is a column over it and v. Vertices where a child has
    no count are dropped before any product."""
    kind, total = DTYPES[cnt_type], 1 + sum(sizes[i] for i in order)
    rows = reduce(DataFrame.union, [s.select("it", "v", F.lit(i).alias("child"), "blk", "bits", "x") for i, s in enumerate(sums)])
    rows = rows.repartition(parts, "it", "v").sortWithinPartitions("it", "v", "child", "blk").withColumn("color", color)
    whole = [comb(k, s) for s in sizes]
    # Rows at a time, so that their sums, and the widest table of the other colors, stay below the bound.
    done, widest = 0, 0
    for i in order:
        done += sizes[i]
        widest = max(widest, comb(k - 1, done))
    slice_rows = max(8, MOST_BYTES // (8 * (2 * sum(whole) + 2 * widest + comb(k, total))))

    def solve(ids, child, blk, bits, ends, values, colors):
        """ids: places of vertices, ascending, of all rows; colors: of the places."""
        wide = [min(64, w, n) for n in whole]
        has = np.zeros((len(colors), len(sizes)), bool)
        has[ids, child] = True
        live = np.flatnonzero(has.all(1))
        if not len(live):
            return live, np.zeros((0, 1, 1), kind)
        place = np.full(len(colors), -1)
        place[live] = np.arange(len(live))
        near = []
        for i, n in enumerate(whole):
            mine = np.flatnonzero((child == i) & (place[ids] >= 0))
            x = np.zeros((len(live), -(-n // wide[i]), wide[i]), kind)
            x[place[ids[mine]], blk[mine]] = dense(bits[mine], values[np.repeat((child == i) & (place[ids] >= 0), np.diff(ends))], wide[i])
            x, others = x.reshape(len(live), -1), np.empty((comb(k - 1, sizes[i]), len(live)), kind)
            for c in np.unique(colors[live]):
                some = np.flatnonzero(colors[live] == c)
                others[:, some] = x[np.ix_(some, without(k, sizes[i], int(c)))].T
            near.append(others)
        out, size = near[order[0]], sizes[order[0]]
        for i in order[1:]:
            size += sizes[i]
            out = product(out, near[i], k - 1, size, sizes[i])
        n, z = comb(k, total), min(64, w, comb(k, total))
        full = np.zeros((len(live), -(-n // z) * z), kind)
        for c in np.unique(colors[live]):
            some = np.flatnonzero(colors[live] == c)
            full[np.ix_(some, with_own(k, total - 1, int(c)))] = out[:, some].T
        return live, full.reshape(len(live), -1, z)

    def run(batches):
        rest = None

        def take(part: pa.RecordBatch):
            it, v = ints(part.column(0)), ints(part.column(1))
            first = np.flatnonzero(np.concatenate([[True], (v[1:] != v[:-1]) | (it[1:] != it[:-1])]))
            ends = [*first[1:], part.num_rows]
            for a in range(0, len(first), slice_rows):
                low, high = first[a], ends[min(a + slice_rows, len(first)) - 1]
                some, starts = part.slice(low, high - low), first[a : a + slice_rows] - low
                x = some.column(5)
                ids = np.searchsorted(starts, np.arange(high - low), side="right") - 1
                offsets = ints(x.offsets) - x.offsets[0].as_py()
                live, full = solve(ids, ints(some.column(2)), ints(some.column(3)), ints(some.column(4)), offsets, x.flatten().to_numpy(zero_copy_only=False), ints(some.column(6))[starts])
                at, blk = np.nonzero(full.any(2))
                who = live[at]
                for i in range(0, len(at), 8192):
                    j = slice(i, i + 8192)
                    yield table(it[low:high][starts][who[j]], v[low:high][starts][who[j]], blk[j].astype(np.int32), full[at[j], blk[j]])

        for batch in batches:
            if not batch.num_rows:
                continue
            whole_batch = batch if rest is None else pa.concat_batches([rest, batch])
            # The last vertex may go on in the next batch.
            it, v = ints(whole_batch.column(0)), ints(whole_batch.column(1))
            other = np.flatnonzero((it != it[-1]) | (v != v[-1]))
            cut = int(other[-1]) + 1 if len(other) else 0
            if cut:
                yield from take(whole_batch.slice(0, cut))
            rest = whole_batch.slice(cut)
        if rest is not None and rest.num_rows:
            yield from take(rest)

    return rows.mapInArrow(run, f"it int, v long, blk int, bits long, x array<{cnt_type}>")
