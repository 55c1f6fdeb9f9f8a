"""Byte-level BPE encoding and decoding, long unsplit text by tree concatenation.

Pre-tokens of ordinary length go through :class:`~.tokens.ChunkEncoder`. A longer one is halved
down to leaves, the leaves are encoded in parallel by threads (the library works outside the interpreter's
lock), and neighbours are joined, again in parallel: a window of tokens around the seam is encoded again and
grows until its outermost tokens are those that both sides had there. A token sequence is the
encoding of its text exactly if every neighbouring pair is, and all pairs outside the window
were already neighbours, so agreement at both edges makes the joined sequence exact.
"""

from __future__ import annotations

import hashlib
import re
from array import array
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from .common import raw_bytes, ready, slices
from .tokens import BYTE_LETTERS, LONGEST_KEPT, ChunkEncoder, vocabulary


class TreeEncoder(ChunkEncoder):
    """leaf: most characters of the byte alphabet that are encoded in one go; threads share the leaves and joins of a long piece."""

    def __init__(self, path: str, leaf: int = 1024, window: int = 8, most: int = 300_000, threads: int = 4):
        super().__init__(path, "bytes", most)
        self.leaf, self.window, self.threads = leaf, window, threads
        self.plain = Tokenizer(self.tok.model)  # no pre-tokenizer: its input is one unsplit piece
        added = self.tok.get_added_tokens_decoder()
        self.added = {t.content: k for k, t in added.items()}
        self.added_cut = re.compile("(" + "|".join(re.escape(c) for c in sorted(self.added, key=len, reverse=True)) + ")") if self.added else None
        size = self.tok.get_vocab_size()
        back = {c: b for b, c in BYTE_LETTERS.items()}
        self.spelled = [self.tok.id_to_token(i) or "" for i in range(size)]
        self.bytes_of = [s.encode() if i in added else bytes(back[c] for c in s) for i, s in enumerate(self.spelled)]

    def encode_chunks(self, chunks: list[bytes]) -> list[bytes]:
        out = super().encode_chunks([c if len(c) <= 4 * LONGEST_KEPT else b"" for c in chunks])
        for at, c in enumerate(chunks):
            if len(c) > 4 * LONGEST_KEPT:
                out[at] = array("I", self.long(c.decode())).tobytes()
        return out

    def long(self, text: str) -> list[int]:
        ids: list[int] = []
        for piece in self.added_cut.split(text) if self.added_cut else [text]:
            if piece in self.added:
                ids.append(self.added[piece])
            elif piece:
                for pre, _ in self.tok.pre_tokenizer.pre_tokenize_str(piece):
                    ids += self.tree(pre)
        return ids

    def tree(self, pre: str) -> list[int]:
        """Ids of one unsplit piece, spelled in the byte alphabet."""
        if len(pre) <= self.leaf:
            return self.plain.encode(pre, add_special_tokens=False).ids
        cuts = [0, len(pre)]
        while max(b - a for a, b in zip(cuts, cuts[1:], strict=False)) > self.leaf:
            cuts = sorted({*cuts, *((a + b) // 2 for a, b in zip(cuts, cuts[1:], strict=False))})
        level = self.each(lambda some: [e.ids for e in self.plain.encode_batch_fast(some, add_special_tokens=False)], [pre[a:b] for a, b in zip(cuts, cuts[1:], strict=False)])
        while len(level) > 1:
            level = self.each(lambda some: [self.join(*p) if len(p) > 1 else p[0] for p in some], [level[k : k + 2] for k in range(0, len(level), 2)])
        return level[0]

    def each(self, work, items: list, share: int = 16) -> list:
        """What ``work`` makes of the items, a share of them at a time, in threads where there are several shares."""
        if len(items) <= share:
            return work(items)
        with ThreadPoolExecutor(self.threads) as pool:
            return [x for some in pool.map(work, [items[k : k + share] for k in range(0, len(items), share)]) for x in some]

    def join(self, left: list[int], right: list[int]) -> list[int]:
        w = self.window
        while True:
            a, b = left[-w:], right[:w]
            mid = self.plain.encode("".join(self.spelled[i] for i in a + b), add_special_tokens=False).ids
            if (len(a) == len(left) or mid[0] == a[0]) and (len(b) == len(right) or mid[-1] == b[-1]):
                return left[: len(left) - len(a)] + mid + right[len(b) :]
            w *= 2

    def decode(self, ids: list[int]) -> bytes:
        """UTF-8 of the decoded text; broken sequences become U+FFFD."""
        plain = b"".join(map(self.bytes_of.__getitem__, ids))
        return plain.decode("utf-8", "replace").encode()


_TREES: dict[str, TreeEncoder] = {}


def tree_encoder(path: str) -> TreeEncoder:
    if path not in _TREES:
        _TREES[path] = TreeEncoder(path)
    return _TREES[path]


def encode_texts(docs: DataFrame, path: str) -> DataFrame:
    """doc_id and the ids of each whole text; null text gives no ids, repeated rows are encoded each."""

    def run(batches):
        enc = tree_encoder(path)
        for batch in batches:
            for some in slices(batch, "text"):
                ids = [np.frombuffer(x, "<u4").astype(np.int32) for x in enc.encode(raw_bytes(some.column(1)))]
                yield pa.RecordBatch.from_arrays([some.column(0), pa.array(ids, pa.list_(pa.int32()))], names=["doc_id", "ids"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, ids array<int>")


def decode_ids(encoded: DataFrame, path: str) -> DataFrame:
    """doc_id and the text that the ids of each row decode to; null ids give an empty text."""

    def run(batches):
        enc = tree_encoder(path)
        for batch in batches:
            text = [enc.decode(ids or []).decode() for ids in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(text, pa.string())], names=["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")


def round_trip(docs: DataFrame, path: str) -> DataFrame:
    """Encodes and decodes each whole text in one pass and gives digests of both: doc_id, n_tokens, ids_sha256, decoded_sha256.

    A null text counts as empty and has no ids; repeated rows give a row each; a text of any length is encoded whole; an empty
    table gives no rows; other columns are not looked at.
    """

    def run(batches):
        enc = tree_encoder(path)
        decimal = [b"%d" % i for i in range(len(enc.spelled))]
        for batch in batches:
            for some in slices(batch, "text"):
                n, first, second = [], [], []
                for packed in enc.encode(raw_bytes(some.column(1))):
                    ids = np.frombuffer(packed, "<u4").tolist()
                    n.append(len(ids))
                    first.append(hashlib.sha256(b",".join(map(decimal.__getitem__, ids))).hexdigest())
                    second.append(hashlib.sha256(enc.decode(ids)).hexdigest())
                yield pa.RecordBatch.from_arrays([some.column(0), pa.array(n, pa.int64()), pa.array(first), pa.array(second)], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def op8(spark: SparkSession, docs: DataFrame, path: str | None = None) -> DataFrame:
    """Every text of ``docs`` with the given vocabulary; see :func:`round_trip`."""
    ready(spark)
    return round_trip(docs, path or vocabulary("byte_bpe_50k.json"))
