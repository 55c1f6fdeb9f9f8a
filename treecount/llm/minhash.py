"""Near-duplicate documents by b-bit MinHash: band candidates, packed low bits, exact confirmation, components."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import commit, discard, raw_bytes, ready, slices
from .components import components

U = np.uint64


@dataclass(frozen=True)
class Settings:
    """words in a shingle; a link needs 100 * common >= percent * union.

    With 32 bands of 5 minima a pair of similarity 0.80 shares no band with probability 3e-6.
    A pair of a band is confirmed unless its b-bit estimate is more than ``sigmas`` standard
    errors below the threshold. Pairs of a bucket meet in blocks of about ``block`` rows, or fewer
    where their full sets exceed ``block_bytes``.
    """

    words: int = 5
    percent: int = 80
    bands: int = 32
    rows: int = 5
    bits: int = 2
    sigmas: float = 5.0
    block: int = 256
    block_bytes: int = 16 << 20

    @property
    def minima(self) -> int:
        return self.bands * self.rows

    @property
    def longs(self) -> int:
        return -(-self.minima * self.bits // 64)

    def most_mismatches(self) -> int:
        """Of the packed minima, as many may differ at most; chance agreement is 1 / 2^bits."""
        c = 2.0**-self.bits
        p = c + (1 - c) * self.percent / 100
        return int(np.ceil(self.minima * (1 - p) + self.sigmas * np.sqrt(self.minima * p * (1 - p))))


#: The contract of op6; 26 bands of 6 minima miss a pair of similarity 0.85 with probability 4e-6.
OP6 = Settings(percent=85, bands=26, rows=6)


def mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> U(30))) * U(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> U(27))) * U(0x94D049BB133111EB)
    return h ^ (h >> U(31))


ODD = 0x9E3779B97F4A7C15
INVERSE = pow(ODD, -1, 1 << 64)
BYTE = mix(np.arange(1, 257, dtype=U) * U(0xD1B54A32D192ED03))
_POWERS: dict[str, np.ndarray] = {}


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_POWERS.get("up", ())) < n:
        size = 1 << max(16, n.bit_length())
        for name, base in (("up", ODD), ("down", INVERSE)):
            steps = np.full(size, base, U)
            steps[0] = 1
            _POWERS[name] = np.cumprod(steps, dtype=U)
    return _POWERS["up"], _POWERS["down"]


def shingles(text: bytes, words: int) -> tuple[bytes, np.ndarray]:
    """The word sequence with single spaces, and the sorted distinct 64-bit hashes of its shingles."""
    tokens = text.lower().split()
    if not tokens:
        return b"", np.zeros(0, U)
    line = b" ".join(tokens)
    raw = np.frombuffer(line, np.uint8)
    up, down = powers(len(raw))
    sums = np.concatenate([np.zeros(1, U), np.cumsum(BYTE[raw] * up[: len(raw)], dtype=U)])
    gaps = np.flatnonzero(raw == 32)
    begin, end = np.concatenate([[0], gaps + 1]), np.concatenate([gaps, [len(raw)]])
    k = min(words, len(begin))
    begin, end = begin[: len(begin) - k + 1], end[k - 1 :]
    return line, np.unique(mix((sums[end] - sums[begin]) * down[begin] + (end - begin).astype(U)))


def multipliers(n: int) -> tuple[np.ndarray, np.ndarray]:
    seeds = mix(np.arange(1, 2 * n + 1, dtype=U))
    return seeds[:n] | U(1), seeds[n:]


def minima(sets: list[np.ndarray], s: Settings) -> np.ndarray:
    """For each set (none empty) the ``minima`` smallest hashes, upper 32 bits of a multiply-add each."""
    a, b = multipliers(s.minima)
    flat, starts = np.concatenate(sets), np.concatenate([[0], np.cumsum([len(x) for x in sets])[:-1]])
    out = np.empty((len(sets), s.minima), np.uint32)
    for k in range(s.minima):
        out[:, k] = np.minimum.reduceat(((flat * a[k] + b[k]) >> U(32)).astype(np.uint32), starts)
    return out


def pack(low: np.ndarray, s: Settings) -> np.ndarray:
    """The low bits of each minimum, packed into 64-bit words."""
    per = 64 // s.bits
    out = np.zeros((len(low), s.longs), U)
    for k in range(s.minima):
        out[:, k // per] |= (low[:, k].astype(U) & U((1 << s.bits) - 1)) << U(k % per * s.bits)
    return out.view(np.int64)


def band_keys(low: np.ndarray, s: Settings) -> np.ndarray:
    keys = np.zeros((len(low), s.bands), U)
    for j in range(s.bands):
        h = np.full(len(low), j + 1, U)
        for r in range(s.rows):
            h = mix(h * U(ODD) + low[:, j * s.rows + r])
        keys[:, j] = h
    return keys.view(np.int64)


SKETCH = "doc_id long, text_key long, set_key string, n_shingles long, packed array<long>, bands array<long>"


def sketch(docs: DataFrame, s: Settings) -> DataFrame:
    """One row per document; documents without words have null set_key, packed and bands."""

    def run(batches):
        for batch in batches:
            for some in slices(batch, "text", 1 << 20):
                made = [shingles(t, s.words) for t in raw_bytes(some.column(2))]
                there = [k for k, (_, x) in enumerate(made) if len(x)]
                keys: list = [None] * len(made)
                packed, bands = list(keys), list(keys)
                if there:
                    low = minima([made[k][1] for k in there], s)
                    for k, p, b in zip(there, pack(low, s), band_keys(low, s), strict=True):
                        keys[k], packed[k], bands[k] = xxhash.xxh128_hexdigest(made[k][0]), p, b
                yield pa.RecordBatch.from_arrays([some.column(0), some.column(1), pa.array(keys, pa.string()), pa.array([len(x) for _, x in made], pa.int64()), pa.array(packed, pa.list_(pa.int64())), pa.array(bands, pa.list_(pa.int64()))], names=["doc_id", "text_key", "set_key", "n_shingles", "packed", "bands"])

    return plain(docs).mapInArrow(run, SKETCH)


def plain(docs: DataFrame) -> DataFrame:
    """doc_id, text_key (a hash of the text and of whether there is an id) and text."""
    text = F.col("text").cast("string")
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(text, F.col("doc_id").isNull()).alias("text_key"), text.alias("text"))


def full_sets(docs: DataFrame, wanted: DataFrame, s: Settings) -> DataFrame:
    """node and the sorted shingle hashes, as bytes, of the documents wanted (node, doc_id, text_key, set_key).

    One plan at every size: sent to all tasks, what is wanted would have to be bounded. Rows of a document that occurs
    often arrive one after the other, and all but the first are passed over.
    """

    def run(batches):
        last = None
        for batch in batches:
            for some in slices(batch, "text", 1 << 20):
                nodes, sets = [], []
                for node, key, text in zip(some.column(0).to_pylist(), some.column(1).to_pylist(), raw_bytes(some.column(2)), strict=True):
                    if node == last:
                        continue
                    line, hashes = shingles(text, s.words)
                    if xxhash.xxh128_hexdigest(line) == key:
                        nodes.append(node)
                        sets.append(hashes.tobytes())
                        last = node
                if nodes:
                    yield pa.RecordBatch.from_arrays([pa.array(nodes, pa.int64()), pa.array(sets, pa.binary())], names=["node", "hashes"])

    found = plain(docs).withColumn("doc_id", F.coalesce("doc_id", F.lit(0))).join(wanted.withColumn("doc_id", F.coalesce("doc_id", F.lit(0))).hint("merge"), ["doc_id", "text_key"])
    return found.select("node", "set_key", "text").mapInArrow(run, "node long, hashes binary")


def mismatches(x: Column, y: Column, s: Settings) -> Column:
    """How many packed minima differ: bits of the xor, folded to one for each minimum, counted."""
    fold = sum(1 << k for k in range(0, 64, s.bits))
    mask = F.lit(fold - (1 << 64) if fold >= 1 << 63 else fold).cast("long")

    def one(a, b):
        d = a.bitwiseXOR(b)
        spread = d
        for k in range(1, s.bits):
            spread = spread.bitwiseOR(F.shiftrightunsigned(d, k))
        return F.bit_count(spread.bitwiseAND(mask))

    return sum((one(F.get(x, F.lit(k)), F.get(y, F.lit(k))) for k in range(1, s.longs)), one(F.get(x, F.lit(0)), F.get(y, F.lit(0))))


def similar(u: np.ndarray, v: np.ndarray, s: Settings) -> bool:
    """Whether two sorted sets have 100 * common >= percent * union."""
    if len(u) > len(v):
        u, v = v, u
    if 100 * len(u) < s.percent * len(v) or not len(u):
        return False
    at = np.searchsorted(v, u)
    at[at == len(v)] = 0
    common = int(np.count_nonzero(v[at] == u))
    return 100 * common >= s.percent * (len(u) + len(v) - common)


def confirm(pairs: DataFrame, sets: DataFrame, s: Settings) -> DataFrame:
    """The pairs (a, b) whose full sets are similar enough."""
    both = pairs.join(sets.select(F.col("node").alias("a"), F.col("hashes").alias("x")), "a").join(sets.select(F.col("node").alias("b"), F.col("hashes").alias("y")), "b")

    def run(batches):
        for batch in batches:
            hit = []
            for x, y in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True):
                hit.append(similar(np.frombuffer(x, U), np.frombuffer(y, U), s))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], names=["a", "b"]).filter(pa.array(hit, pa.bool_()))

    return both.select("a", "b", "x", "y").mapInArrow(run, "a long, b long")


def near_duplicates(docs: DataFrame, s: Settings = Settings()) -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id, kept.

    Documents with the same word sequence form a class, and one of each class, that with the
    smallest id, is compared. In each band bucket all meet its first class there first; where
    that leaves a bucket in several components, the pairs between them follow, in blocks, so no
    candidate pair is left out unless its ends are connected anyhow. Candidates pass the b-bit
    estimate, then the comparison of full sets.

    A null or empty text, or one of white space, has no shingles and links with nothing. Fewer words
    than a shingle takes make one shingle of all. Rows that repeat a doc_id each are a document, and
    rows that repeat id and text are kept or dropped together. Documents without an id link as others do
    and rank last: their component_id is the smallest id that they reach, and null, with kept true, if they
    reach none. An empty table gives no rows; other columns are not looked at.
    """
    sketches = commit(sketch(docs, s), "sketches")
    first = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "text_key", "n_shingles", "packed", "bands")).alias("of")
    grouped = sketches.where("set_key is not null").groupBy("set_key").agg(first)
    # Ids may be null or repeat: classes go by a number of their own, fixed once the table is written.
    classes = commit(grouped.select("set_key", F.monotonically_increasing_id().alias("node"), "of.doc_id", "of.text_key", "of.n_shingles", "of.packed", "of.bands"), "classes")
    banded = classes.select("node", F.explode("bands").alias("band"))
    buckets = commit(banded.groupBy("band").agg(F.min("node").alias("first"), F.count("*").alias("n")).where("n > 1"), "buckets")
    members = commit(banded.join(buckets, "band").select("band", "first", "n", "node"), "bucket-members")
    known = classes.select("node", "n_shingles", "packed")
    most = s.most_mismatches()

    def likely(pairs: DataFrame) -> DataFrame:
        x = known.select(F.col("node").alias("a"), F.col("packed").alias("p"), F.col("n_shingles").alias("m"))
        y = known.select(F.col("node").alias("b"), F.col("packed").alias("q"), F.col("n_shingles").alias("n"))
        both = pairs.join(x, "a").join(y, "b")
        sized = 100 * F.least("m", "n") >= s.percent * F.greatest("m", "n")
        return both.where(sized & (mismatches(F.col("p"), F.col("q"), s) <= most)).select("a", "b").distinct()

    star = commit(likely(members.where("first <> node").select(F.col("first").alias("a"), F.col("node").alias("b")).distinct()), "pairs")
    sets = commit(full_sets(docs, members.select("node").distinct().join(classes.select("node", "doc_id", "text_key", "set_key"), "node"), s), "shingle-sets")
    links = commit(confirm(star, sets, s), "links")
    comp = components(links)
    labelled = members.where("n > 2").join(comp, "node", "left").select("band", "node", F.coalesce("component", "node").alias("component"))
    labelled = commit(labelled, "labelled")
    open_ = labelled.groupBy("band").agg(F.min("component").alias("lo"), F.max("component").alias("hi")).where("lo <> hi").select("band")
    rows = commit(labelled.join(open_, "band").join(known, "node"), "open-buckets")
    apart = commit(meetings(rows, lambda n, size: n / (8 * s.block)).groupBy("band", "low", "high").applyInPandas(candidates(s), "band long, node long").distinct(), "open-rows")
    doubtful = rows.join(apart, ["band", "node"]).join(sets, "node")
    more = commit(meetings(doubtful, lambda n, size: F.greatest(n / s.block, size * 8 / s.block_bytes), "hashes").groupBy("band", "low", "high").applyInPandas(across(s), "a long, b long"), "links")
    if more.limit(1).count():
        comp = components(links.union(more))
    names = comp.join(classes.select("node", "doc_id"), "node")
    names = names.join(names.groupBy("component").agg(F.min("doc_id").alias("lowest")), "component").select("node", "lowest")
    component = commit(classes.select("set_key", "node", "doc_id").join(names, "node", "left").select("set_key", F.coalesce("lowest", "doc_id").alias("component")), "class-components")
    discard(classes, buckets, members, star, sets, links, labelled, rows, apart, more)
    out = sketches.select("doc_id", "set_key", "n_shingles").join(component, "set_key", "left")
    cid = F.coalesce("component", "doc_id")
    return out.select("doc_id", "n_shingles", cid.alias("component_id"), F.col("doc_id").eqNullSafe(cid).alias("kept"))


def keep_one(docs: DataFrame, s: Settings = Settings()) -> DataFrame:
    """The documents, with all their columns, one of each component; of documents without an id, and of rows that repeat an
    id, all whose id is kept."""
    kept = near_duplicates(docs, s).where("kept").select(F.col("doc_id").alias("kept_id")).distinct()
    return docs.join(kept, docs["doc_id"].cast("long").eqNullSafe(F.col("kept_id")), "left_semi")


def meetings(rows: DataFrame, parts, *columns: str) -> DataFrame:
    """Rows (band, node, component, n_shingles, packed, ...) dealt to pairs of blocks of their bucket; ``parts`` gives the
    number of blocks from the bucket's rows and shingles."""
    blocks = rows.groupBy("band").agg(F.greatest(F.lit(1), F.ceil(parts(F.count("*"), F.sum("n_shingles")))).cast("int").alias("blocks"))
    placed = rows.join(blocks, "band").withColumn("block", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
    return placed.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).select("band", F.least("block", "other").alias("low"), F.greatest("block", "other").alias("high"), "block", "node", "component", "n_shingles", "packed", *columns)


class Tile:
    """The rows of two blocks of a bucket."""

    def __init__(self, key: tuple, part: pd.DataFrame, s: Settings):
        self.s, self.most, self.fold = s, s.most_mismatches(), U(sum(1 << k for k in range(0, 64, s.bits)))
        self.ids, self.n = part["node"].to_numpy(np.int64), part["n_shingles"].to_numpy(np.int64)
        self.comp = part["component"].to_numpy(np.int64).copy()
        self.packed = np.array(part["packed"].tolist(), np.int64).view(U).reshape(len(part), -1)
        block = part["block"].to_numpy()
        self.first, self.second = np.flatnonzero(block == key[1]), np.flatnonzero(block == key[2])

    def partners(self, x: int) -> np.ndarray:
        """Rows of the second block in other components that are likely to be similar to row x, the likeliest first."""
        y = self.second
        y = y[(self.comp[y] != self.comp[x]) & (100 * np.minimum(self.n[y], self.n[x]) >= self.s.percent * np.maximum(self.n[y], self.n[x]))]
        spread = self.packed[y] ^ self.packed[x]
        d = spread.copy()
        for k in range(1, self.s.bits):
            spread |= d >> U(k)
        differ = np.bitwise_count(spread & self.fold).sum(1)
        order = np.argsort(differ, kind="stable")
        return y[order[differ[order] <= self.most]]


def candidates(s: Settings):
    """Which rows of a tile have a likely partner in another component, so that full sets go out for these only."""

    def meet(key: tuple, part: pd.DataFrame) -> pd.DataFrame:
        t, hit = Tile(key, part, s), np.zeros(len(part), bool)
        for x in t.first:
            y = t.partners(x)
            hit[y] = True
            hit[x] |= len(y) > 0
        return pd.DataFrame({"band": key[0], "node": t.ids[hit]}, dtype="int64")

    return meet


def across(s: Settings):
    """Links (a, b) between different components of a bucket, from a tile.

    It confirms likely pairs, the likeliest first, and leaves out those whose ends it has connected meanwhile, so it
    gives fewer links than it has rows.
    """

    def meet(key: tuple, part: pd.DataFrame) -> pd.DataFrame:
        t, out = Tile(key, part, s), []
        sets = [np.frombuffer(x, U) for x in part["hashes"]]
        for x in t.first:
            for z in t.partners(x):
                if t.comp[z] != t.comp[x] and similar(sets[x], sets[z], s):
                    out.append((min(t.ids[x], t.ids[z]), max(t.ids[x], t.ids[z])))
                    t.comp[t.comp == t.comp[z]] = t.comp[x]
        return pd.DataFrame(out, columns=["a", "b"], dtype="int64")

    return meet


def op6(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """All documents at similarity 0.85 of sets of five words; see :func:`near_duplicates`."""
    ready(spark)
    return near_duplicates(docs, OP6)


ORACLE = r"""
with recursive words as (
  select doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') as w from documents),
cut as (
  select doc_id, unnest(case when len(w) = 0 then [] when len(w) < 5 then [array_to_string(w, ' ')]
         else list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) end) as shingle from words),
sets as (select distinct doc_id, shingle from cut),
sizes as (select doc_id, count(*) as n from sets group by doc_id),
common as (select a.doc_id as a, b.doc_id as b, count(*) as n from sets a join sets b on a.shingle = b.shingle and a.doc_id <> b.doc_id group by 1, 2),
links as (select c.a, c.b from common c join sizes x on x.doc_id = c.a join sizes y on y.doc_id = c.b where 100 * c.n >= 85 * (x.n + y.n - c.n)),
reach(a, b) as (select a, b from links union select r.a, l.b from reach r join links l on r.b = l.a),
low as (select a, least(a, min(b)) as component from reach group by a)
select d.doc_id, coalesce(s.n, 0)::bigint as n_shingles, coalesce(l.component, d.doc_id) as component_id, coalesce(l.component, d.doc_id) = d.doc_id as kept
from documents d left join sizes s on s.doc_id = d.doc_id left join low l on l.a = d.doc_id"""
