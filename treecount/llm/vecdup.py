"""Near-duplicate vectors: int8 tile products with an error bound, doubtful pairs again in double precision."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import commit, discard, ready
from .components import components

TILE = 1024


def scaled(v: np.ndarray) -> np.ndarray:
    """Rows times powers of two that bring their largest component below 1, so that no square overflows and no digit is lost."""
    return np.ldexp(v, -np.frexp(np.abs(v).max(1))[1][:, None])


def quantise(v: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Int8 codes of the rows at unit length, their scales, and for each the length of what rounding took away."""
    v = scaled(v)
    v = v / np.sqrt(np.einsum("ij,ij->i", v, v))[:, None]
    scale = np.abs(v).max(1) / 127
    codes = np.rint(v / scale[:, None]).astype(np.int8)
    return codes, scale, np.linalg.norm(v - codes * scale[:, None], axis=1)


def judge(x: tuple, y: tuple | None, threshold: float) -> tuple[np.ndarray, np.ndarray]:
    """Which pairs of quantised rows (codes, scales, errors) surely have cosine >= threshold, and which may have it; of pairs
    among x those with the first index smaller.

    For unit vectors u, v with codes p, q: u.v differs from the product of the scaled codes by at
    most e(u) + e(v) + e(u) e(v), e being the lengths lost to rounding. Products of int8 codes are
    whole numbers that float32 holds exactly up to 1,000 dimensions; beyond, float64 is used.
    """
    (px, sx, ex), (py, sy, ey) = x, y or x
    kind = np.float32 if px.shape[1] * 127 * 127 < 1 << 24 else np.float64
    about = (px.astype(kind) @ py.astype(kind).T).astype(np.float64) * sx[:, None] * sy[None, :]
    bound = ex[:, None] + ey[None, :] + ex[:, None] * ey[None, :] + 1e-9
    sure, maybe = about - bound >= threshold, about + bound >= threshold
    if y is None:
        sure, maybe = np.triu(sure, 1), np.triu(maybe, 1)
    return sure, maybe & ~sure


def exact(x: np.ndarray, y: np.ndarray, i: np.ndarray, j: np.ndarray, threshold: float, chunk: int = 16_384) -> np.ndarray:
    """Whether rows i of x and j of y have cosine >= threshold, in double precision."""
    x, y = scaled(x), scaled(y)
    nx, ny = np.sqrt(np.einsum("ij,ij->i", x, x)), np.sqrt(np.einsum("ij,ij->i", y, y))
    parts = [np.einsum("ij,ij->i", x[i[a : a + chunk]], y[j[a : a + chunk]]) / (nx[i[a : a + chunk]] * ny[j[a : a + chunk]]) >= threshold for a in range(0, len(i), chunk)]
    return np.concatenate(parts) if parts else np.zeros(0, bool)


def tile_pairs(x: np.ndarray, y: np.ndarray | None, threshold: float) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs with cosine >= threshold between rows of x and of y, or among x (first index the smaller)."""
    sure, maybe = judge(quantise(x), None if y is None else quantise(y), threshold)
    i, j = np.nonzero(maybe)
    keep = exact(x, x if y is None else y, i, j, threshold)
    sure[i[keep], j[keep]] = True
    return np.nonzero(sure)


def forest(n: int, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """The smallest index that each of n nodes reaches over the pairs."""
    root = np.arange(n)
    while True:
        before = root.copy()
        np.minimum.at(root, i, root[j])
        np.minimum.at(root, j, root[i])
        root = root[root]
        if np.array_equal(before, root):
            return root


def quantised(rows: DataFrame) -> DataFrame:
    """``rows`` with codes, scale and err of each embedding."""
    at, names = rows.columns.index("embedding"), [*rows.columns, "codes", "scale", "err"]

    def run(batches):
        for batch in batches:
            lists = batch.column(at)
            flat, sizes = lists.flatten().to_numpy(zero_copy_only=False), lists.value_lengths().to_numpy(zero_copy_only=False)
            starts = np.cumsum(sizes) - sizes
            codes: list = [None] * len(sizes)
            scale, err = np.zeros(len(sizes)), np.zeros(len(sizes))
            for dim in np.unique(sizes):
                own = np.flatnonzero(sizes == dim)
                c, scale[own], err[own] = quantise(flat[starts[own][:, None] + np.arange(dim)])
                for k, row in zip(own, c, strict=True):
                    codes[k] = row.tobytes()
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(codes, pa.binary()), pa.array(scale), pa.array(err)], names=names)

    return rows.mapInArrow(run, T.StructType([*rows.schema.fields, T.StructField("codes", T.BinaryType()), T.StructField("scale", T.DoubleType()), T.StructField("err", T.DoubleType())]))


def sides(key: tuple, part: pd.DataFrame) -> tuple:
    """A tile's rows in a fixed order, the places of its two blocks (the second None within one block) and their quantised rows."""
    part = part.sort_values("node", kind="stable")
    codes = np.frombuffer(b"".join(part["codes"]), np.int8).reshape(len(part), -1)
    block, scale, err = (part[c].to_numpy() for c in ("block", "scale", "err"))
    pick = [np.flatnonzero(block == b) for b in key[1:3]]
    q = [(codes[p], scale[p], err[p]) for p in pick]
    return part, pick[0], pick[1], q[0], None if key[1] == key[2] else q[1]


TILED = "gid long, low int, high int, a long, b long, links long, doubtful boolean"


def linked(key: tuple, part: pd.DataFrame, i: np.ndarray, j: np.ndarray, doubtful: np.ndarray) -> pd.DataFrame:
    """What a tile says of its rows that have links there, or doubtful pairs."""
    ids, copies = part["node"].to_numpy(np.int64), part["copies"].to_numpy(np.int64)
    links = np.bincount(i, copies[j], len(ids)).astype(np.int64) + np.bincount(j, copies[i], len(ids)).astype(np.int64)
    hit = np.flatnonzero((links > 0) | doubtful)
    return pd.DataFrame({"gid": np.int64(key[0]), "low": np.int32(key[1]), "high": np.int32(key[2]), "a": ids[hit], "b": ids[forest(len(ids), i, j)[hit]], "links": links[hit], "doubtful": doubtful[hit]})


def link_vectors(vectors: DataFrame, threshold: float = 0.98, tile: int = TILE) -> DataFrame:
    """One row per vector: vec_id, n_links, component_id, kept.

    Vectors meet only under equal, non-null labels and equal dimension. Null, empty and zero
    vectors and those with null or non-finite components link with nothing. Equal vectors are
    compared once and counted as often as they occur; a row that repeats another counts as another
    vector. Within a label all pairs are compared, in tiles of two blocks of about ``tile`` rows.

    Each vector is quantised once and only its codes, scale and error are dealt to the tiles. A tile settles what
    the bound settles; full vectors are sent after it only of rows that have doubtful pairs there.

    Rows without vec_id link as others do and rank last: their component_id is the smallest id that they reach, and
    null, with kept true, if they reach none. An empty table gives no rows; other columns are not looked at.
    """
    v = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("embedding"), F.col("label").alias("label"))
    fine = F.col("label").isNotNull() & F.col("embedding").isNotNull() & F.coalesce(F.forall("embedding", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))), F.lit(False)) & F.exists("embedding", lambda x: x != 0)
    rows = commit(v.select("vec_id", F.when(F.coalesce(fine, F.lit(False)), F.sha2(F.concat_ws("|", F.col("label").cast("string"), F.col("embedding").cast("string")), 256)).alias("same"), F.when(F.coalesce(fine, F.lit(False)), F.col("embedding")).alias("embedding"), "label"), "vectors")
    per = rows.where("same is not null").groupBy("same").agg(F.min("vec_id").alias("rep"), F.count("*").alias("copies"), F.min("label").alias("label"), F.min("embedding").alias("embedding"))
    # Ids may be null: classes go by a number of their own, fixed once the table is written.
    classes = commit(quantised(per.withColumn("dim", F.size("embedding")).withColumn("node", F.monotonically_increasing_id())), "vector-classes")
    blocks = commit(classes.groupBy("label", "dim").agg(F.ceil(F.count("*") / tile).cast("int").alias("blocks")).withColumn("gid", F.monotonically_increasing_id()), "vector-blocks")
    placed = classes.select("label", "dim", "node", "copies", "codes", "scale", "err").join(blocks, ["label", "dim"]).withColumn("block", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
    met = placed.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).select("gid", F.least("block", "other").alias("low"), F.greatest("block", "other").alias("high"), "block", "node", "copies", "codes", "scale", "err")

    def meet(key: tuple, part: pd.DataFrame) -> pd.DataFrame:
        part, first, second, x, y = sides(key, part)
        sure, maybe = judge(x, y, threshold)
        i, j = np.nonzero(sure)
        doubtful = np.zeros(len(part), bool)
        doubtful[first[maybe.any(1)]] = True
        doubtful[second[maybe.any(0)]] = True
        return linked(key, part, first[i], second[j], doubtful)

    def settle(key: tuple, part: pd.DataFrame) -> pd.DataFrame:
        part, first, second, x, y = sides(key, part)
        i, j = np.nonzero(judge(x, y, threshold)[1])
        i, j = first[i], second[j]
        full = np.array(part["embedding"].tolist(), np.float64).reshape(len(part), -1)
        keep = exact(full, full, i, j, threshold)
        return linked(key, part, i[keep], j[keep], np.zeros(len(part), bool))

    tiled = commit(met.groupBy("gid", "low", "high").applyInPandas(meet, TILED), "vector-tiles")
    doubt = tiled.where("doubtful").select("gid", "low", "high", F.col("a").alias("node"))
    again = doubt.join(placed.select("node", "block"), "node").join(classes.select("node", "copies", "codes", "scale", "err", "embedding"), "node")
    settled = commit(again.groupBy("gid", "low", "high").applyInPandas(settle, TILED), "vector-tiles")
    found = tiled.where("links > 0").union(settled).select("a", "b", "links")
    component = components(found)
    names = component.join(classes.select("node", "rep"), "node")
    names = names.join(names.groupBy("component").agg(F.min("rep").alias("lowest")), "component").select("node", "lowest")
    per_class = classes.select("same", "node", "rep", "copies").join(found.groupBy(F.col("a").alias("node")).agg(F.sum("links").alias("links")), "node", "left").join(names, "node", "left")
    per_class = commit(per_class.select("same", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("links"), F.coalesce("lowest", "rep").alias("component")), "vector-classes")
    discard(classes, blocks, tiled, settled)
    out = rows.select("vec_id", "same").join(per_class, "same", "left")
    cid = F.coalesce("component", "vec_id")
    return out.select("vec_id", F.coalesce("links", F.lit(0)).cast("long").alias("n_links"), cid.alias("component_id"), F.col("vec_id").eqNullSafe(cid).alias("kept"))


def op9(spark: SparkSession, vectors: DataFrame) -> DataFrame:
    """All rows of ``vectors`` (vec_id, embedding, label) at cosine 0.98; see :func:`link_vectors`."""
    ready(spark)
    return link_vectors(vectors)


ORACLE = """
with recursive given as (select row_number() over () as row, vec_id, label, embedding from embeddings),
fine as (
  select row, label, embedding::double[] as e from given
  where label is not null and embedding is not null and len(embedding) > 0
    and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0 and len(list_filter(embedding, lambda x: x <> 0)) > 0),
links as (
  select a.row as a, b.row as b from fine a join fine b on a.label = b.label and a.row <> b.row and len(a.e) = len(b.e)
  where list_cosine_similarity(a.e, b.e) >= 0.98),
reach(a, b) as (select a, b from links union select r.a, l.b from reach r join links l on r.b = l.a),
low as (select r.a, least(min(x.vec_id), min(y.vec_id)) as component from reach r join given x on x.row = r.a join given y on y.row = r.b group by r.a),
counts as (select a, count(*) as n from links group by a)
select v.vec_id, coalesce(c.n, 0)::bigint as n_links, coalesce(l.component, v.vec_id) as component_id, v.vec_id is not distinct from coalesce(l.component, v.vec_id) as kept
from given v left join counts c on c.a = v.row left join low l on l.a = v.row"""
