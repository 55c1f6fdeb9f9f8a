"""Token-id files: independent zstandard frames, a trailing seek table, a checksum per frame.

File layout, all integers little-endian:

* one or more zstandard frames, each the unsigned 32-bit ids of some consecutive documents;
* a skippable frame (magic ``DOC_MAGIC``) with the number of documents, their ids (signed 64-bit),
  their lengths in ids (unsigned 32-bit) and the number of documents in each frame (unsigned 32-bit);
* the seek table of the public zstandard seekable format: a skippable frame with, for each frame,
  compressed size, plain size and the low 32 bits of XXH64 of the plain bytes, then the footer.

A standard zstandard decoder therefore decompresses the whole file, and :class:`TokenFile`
decompresses only the frames that hold the documents asked for.
"""

from __future__ import annotations

import struct
import uuid
import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
import xxhash
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import commit, raw_bytes, ready, shared_dir, slices
from .tokens import encoder, vocabulary

#: Fixed values of the public seekable format.
SEEK_MAGIC, FOOTER_MAGIC, WITH_CHECKSUM = 0x184D2A5E, 0x8F92EAB1, 0x80
DOC_MAGIC = 0x184D2A50
#: The id that stands for a null doc_id inside a file.
NULL_ID = -(1 << 63)


def open_out(uri: str):
    fs, path = pafs.FileSystem.from_uri(uri)
    fs.create_dir(path.rpartition("/")[0], recursive=True)
    return fs.open_output_stream(path, compression=None)


def open_in(uri: str):
    fs, path = pafs.FileSystem.from_uri(uri)
    return fs.open_input_file(path)


class TokenFileWriter:
    """Appends documents to one file; memory holds one frame and twelve bytes for each document."""

    def __init__(self, sink, frame_ids: int = 16_384, level: int = 1):
        self.sink, self.frame_bytes, self.zip = sink, 4 * frame_ids, zstandard.ZstdCompressor(level=level)
        self.waiting: list[bytes] = []
        self.size = self.in_frame = 0
        self.frames: list[tuple[int, int, int]] = []
        self.ids: list[int] = []
        self.lengths: list[int] = []
        self.per_frame: list[int] = []

    def add(self, doc_id: int | None, ids: bytes) -> None:
        self.ids.append(NULL_ID if doc_id is None else doc_id)
        self.lengths.append(len(ids) // 4)
        self.waiting.append(ids)
        self.size += len(ids)
        self.in_frame += 1
        if self.size >= self.frame_bytes:
            self.flush()

    def flush(self) -> None:
        if self.in_frame:
            plain = b"".join(self.waiting)
            packed = self.zip.compress(plain)
            self.sink.write(packed)
            self.frames.append((len(packed), len(plain), xxhash.xxh64_intdigest(plain) & 0xFFFFFFFF))
            self.per_frame.append(self.in_frame)
            self.waiting, self.size, self.in_frame = [], 0, 0

    def close(self) -> None:
        self.flush()
        body = struct.pack("<Q", len(self.ids)) + np.array(self.ids, "<i8").tobytes() + np.array(self.lengths, "<u4").tobytes() + np.array(self.per_frame, "<u4").tobytes()
        self.sink.write(struct.pack("<II", DOC_MAGIC, len(body)) + body)
        table = b"".join(struct.pack("<III", *f) for f in self.frames) + struct.pack("<IBI", len(self.frames), WITH_CHECKSUM, FOOTER_MAGIC)
        self.sink.write(struct.pack("<II", SEEK_MAGIC, len(table)) + table)
        self.sink.close()


class TokenFile:
    """Reads a file by its seek table. Raises ValueError where a checksum or the layout doesn't hold."""

    def __init__(self, source):
        self.source = source
        end = source.size()
        frames, flags, magic = struct.unpack("<IBI", source.read_at(9, end - 9))
        if magic != FOOTER_MAGIC or flags != WITH_CHECKSUM:
            raise ValueError("no seek table")
        table = end - 9 - 12 * frames
        self.frames = np.frombuffer(source.read_at(12 * frames, table), "<u4").reshape(-1, 3).astype(np.int64)
        self.offsets = np.concatenate([[0], np.cumsum(self.frames[:, 0])])
        at = int(self.offsets[-1])
        magic, size = struct.unpack("<II", source.read_at(8, at))
        if magic != DOC_MAGIC:
            raise ValueError("no document index")
        body = source.read_at(size, at + 8)
        docs = struct.unpack_from("<Q", body)[0]
        self.doc_ids = np.frombuffer(body, "<i8", docs, 8)
        self.lengths = np.frombuffer(body, "<u4", docs, 8 + 8 * docs).astype(np.int64)
        per_frame = np.frombuffer(body, "<u4", frames, 8 + 12 * docs).astype(np.int64)
        self.first = np.concatenate([[0], np.cumsum(per_frame)])
        self.unzip = zstandard.ZstdDecompressor()

    def frame(self, k: int) -> bytes:
        packed, plain, check = (int(x) for x in self.frames[k])
        out = self.unzip.decompress(self.source.read_at(packed, int(self.offsets[k])), max_output_size=max(plain, 1))
        if len(out) != plain or xxhash.xxh64_intdigest(out) & 0xFFFFFFFF != check:
            raise ValueError(f"frame {k} is damaged")
        return out

    def documents(self, frames: Iterable[int] | None = None) -> Iterator[tuple[int, bytes]]:
        """(position in the file, ids) of all documents of the frames given, or of all frames."""
        for k in range(len(self.frames)) if frames is None else frames:
            plain, at = self.frame(k), 0
            for d in range(int(self.first[k]), int(self.first[k + 1])):
                size = 4 * int(self.lengths[d])
                yield d, plain[at : at + size]
                at += size

    def get(self, wanted: Iterable[int]) -> dict[int, list[bytes]]:
        """The ids of the documents asked for (a repeated doc_id gives several); other frames stay packed."""
        hit = np.flatnonzero(np.isin(self.doc_ids, np.fromiter(wanted, np.int64)))
        out: dict[int, list[bytes]] = {}
        keep = set(hit.tolist())
        for d, ids in self.documents(sorted(set((np.searchsorted(self.first, hit, side="right") - 1).tolist()))):
            if d in keep:
                out.setdefault(int(self.doc_ids[d]), []).append(ids)
        return out


MANIFEST = "part int, path string, docs long, ids long"


def write_tokens(docs: DataFrame, path: str, folder: str, kind: str = "words", end_id: int = 2, frame_ids: int = 16_384) -> DataFrame:
    """Encodes every whole text and writes the ids in ascending doc_id order, one file for each range of ids.

    Each task writes a file of its own name; the manifest, written once the tasks are done, lists
    the files that count, so the leftovers of lost or repeated tasks are never read. Null text is
    empty; null ids come first; rows with the same doc_id stay together in no stated order.
    """

    def write(batches):
        enc, part = encoder(path, kind), TaskContext.get().partitionId()
        end, out, name, total = struct.pack("<I", end_id), None, "", 0
        for batch in batches:
            for some in slices(batch, "text"):
                if out is None:
                    name = f"{folder}/tokens-{part:06d}-{uuid.uuid4().hex}.zst"
                    out = TokenFileWriter(open_out(name), frame_ids)
                for doc_id, ids in zip(some.column(0).to_pylist(), enc.encode(raw_bytes(some.column(1))), strict=True):
                    out.add(doc_id, ids + end)
                    total += len(ids) // 4 + 1
        if out is not None:
            out.close()
            yield pa.RecordBatch.from_pydict({"part": pa.array([part], pa.int32()), "path": [name], "docs": pa.array([len(out.ids)], pa.int64()), "ids": pa.array([total], pa.int64())})

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return commit(rows.repartitionByRange("doc_id").sortWithinPartitions("doc_id").mapInArrow(write, MANIFEST), "token-manifest")


def read_tokens(manifest: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of each document, read back from the files of a manifest."""

    def read(batches):
        for batch in batches:
            for path, base in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                with open_in(path) as source:
                    f = TokenFile(source)
                    crc = np.fromiter((zlib.crc32(ids) for _, ids in f.documents()), np.int64, len(f.doc_ids))
                    start = base + np.cumsum(f.lengths) - f.lengths
                    for at in range(0, len(crc), 65_536):
                        cut = slice(at, at + 65_536)
                        ids = f.doc_ids[cut]
                        yield pa.RecordBatch.from_arrays([pa.array(ids, mask=ids == NULL_ID), pa.array(start[cut]), pa.array(f.lengths[cut]), pa.array(crc[cut])], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    # One row for each file, so this window is over files and not documents.
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    placed = manifest.select("path", F.coalesce(F.sum("ids").over(before), F.lit(0)).alias("base"))
    files = max(1, manifest.count())
    return placed.repartition(files).mapInArrow(read, "doc_id long, start long, n_tokens long, ids_crc32 long")


def fetch(manifest: DataFrame, doc_ids: list[int]) -> dict[int, list[list[int]]]:
    """Ids of a few documents, from the frames that hold them. For a caller's lookups, not for bulk reads."""
    out: dict[int, list[list[int]]] = {}
    for row in manifest.toLocalIterator():
        with open_in(row.path) as source:
            for k, found in TokenFile(source).get(doc_ids).items():
                out.setdefault(k, []).extend(np.frombuffer(x, "<u4").tolist() for x in found)
    return out


def op5(spark: SparkSession, docs: DataFrame, path: str | None = None) -> DataFrame:
    ready(spark)
    folder = f"{shared_dir(spark)}/tokens-{uuid.uuid4().hex}"
    return read_tokens(write_tokens(docs, path or vocabulary("word_bpe_49k.json"), folder))
