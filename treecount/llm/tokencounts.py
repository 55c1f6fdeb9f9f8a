"""Token counts by section: whole documents are encoded once and token spans meet section spans in an interval join."""

from __future__ import annotations

from array import array

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import raw_bytes, ready, slices
from .tokens import BYTE_LETTERS, LONGEST_KEPT, PARTS, ChunkEncoder, vocabulary

RULES = ("start", "end", "majority")


class SpanEncoder(ChunkEncoder):
    """As its base, but gives each chunk's token spans (start and end character, in pairs) in place of ids."""

    def __init__(self, path: str, most: int = 300_000):
        super().__init__(path, "bytes", most)

    def encode_chunks(self, chunks: list[bytes]) -> list[bytes]:
        if len(self.parts) > self.most:
            self.parts.clear()
        out: list[bytes | None] = []
        rest = []
        for at, c in enumerate(chunks):
            s = c.decode()
            if len(c) > 4 * LONGEST_KEPT or "<|" in s or not (s.isascii() or max(s) < "Ā"):
                rest.append((at, s))
                out.append(None)
                continue
            spans, base = array("I"), 0
            for p in PARTS["bytes"].findall(s):
                spans.extend([base + x for x in self.spans(p)])
                base += len(p)
            out.append(spans.tobytes())
        for (at, _), e in zip(rest, self.tok.encode_batch([s for _, s in rest], add_special_tokens=False), strict=True):
            out[at] = array("I", [x for pair in e.offsets for x in pair]).tobytes()
        return out

    def spans(self, p: str) -> list[int]:
        found = self.parts.get(p)
        if found is None:
            raw = p.encode()
            char = [k for k, c in enumerate(p) for _ in c.encode()]  # the character that each byte belongs to
            found, at = [], 0
            for t in self.tok.model.tokenize(raw.decode("latin-1").translate(BYTE_LETTERS)):
                n = len(t.value)
                found += [char[at], char[at + n - 1] + 1]
                at += n
            if len(p) <= LONGEST_KEPT:
                self.parts[p] = found
        return found

    def token_spans(self, texts: list[bytes]) -> list[np.ndarray]:
        """For each text an array of (start, end) rows, in characters of the whole text."""
        lists = [self.chunks(t) for t in texts]
        known = self.learn(lists)
        out = []
        for text, chunks in zip(texts, lists, strict=True):
            pieces = [known[c] for c in chunks]
            sizes = np.fromiter(map(len, chunks) if text.isascii() else (len(c.decode()) for c in chunks), np.int64, len(chunks))
            counts = np.fromiter(map(len, pieces), np.int64, len(pieces)) // 8
            spans = np.frombuffer(b"".join(pieces), "<u4").astype(np.int64).reshape(-1, 2)
            out.append(spans + np.repeat(np.cumsum(sizes) - sizes, counts)[:, None])
        return out


def owners(spans: np.ndarray, edges: np.ndarray, rule: str) -> tuple[np.ndarray, np.ndarray]:
    """Which section each token goes to, and whether it reaches over a section's end.

    edges: sorted section starts. "start": the section of the token's first character; "end": of
    its last; "majority": the one with most of its characters, the earliest of equals.
    """
    first = np.searchsorted(edges, spans[:, 0], side="right") - 1
    last = np.searchsorted(edges, np.maximum(spans[:, 1] - 1, spans[:, 0]), side="right") - 1
    crossing = first != last
    if rule == "end":
        return last, crossing
    owner = first.copy()
    if rule == "majority":
        for t in np.flatnonzero(crossing):
            a, b = spans[t]
            inner = np.concatenate([[a], edges[first[t] + 1 : last[t] + 1], [b]])
            owner[t] = first[t] + int(np.argmax(np.diff(inner)))
    return owner, crossing


def count_by_section(docs: DataFrame, path: str, starts: str | None = None, rule: str = "start") -> DataFrame:
    """One row per document and section: its span, its tokens, those of them that cross into another section, the document's tokens.

    starts names an array column of section starts in characters; without it sections are lines.
    Starts are sorted, repeated and null ones dropped, and 0 is added. Null text counts as empty; an
    empty text has one section without tokens. The counts of a document add up to its tokens by
    whatever rule.
    """
    if rule not in RULES:
        raise ValueError(f"rule must be one of {RULES}")

    def run(batches):
        enc = _spans(path)
        for batch in batches:
            for some in slices(batch, "text"):
                texts = raw_bytes(some.column(1))
                ids = some.column(0).to_pylist()
                given = some.column(2).to_pylist() if starts else [None] * len(texts)
                cols: list[list] = [[], [], [], [], [], [], []]
                for doc_id, text, spans, own in zip(ids, texts, enc.token_spans(texts), given, strict=True):
                    n = len(text) if text.isascii() else len(text.decode())
                    if starts:
                        edges = np.unique(np.array([0, *(x for x in own or [] if x is not None and 0 < x < n)], np.int64))
                    else:
                        edges = lines(text)
                    owner, crossing = owners(spans, edges, rule)
                    k = len(edges)
                    for c, v in zip(cols, ([doc_id] * k, range(k), edges.tolist(), [*edges[1:].tolist(), n], np.bincount(owner, minlength=k).tolist(), np.bincount(owner[crossing], minlength=k).tolist(), [len(spans)] * k), strict=True):
                        c.extend(v)
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64() if j != 1 else pa.int32()) for j, c in enumerate(cols)], names=NAMES)

    picked = [F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")]
    if starts:
        picked.append(F.col(starts).cast("array<long>").alias("starts"))
    return docs.select(*picked).mapInArrow(run, "doc_id long, section int, char_start long, char_end long, n_tokens long, n_crossing long, doc_tokens long")


NAMES = ["doc_id", "section", "char_start", "char_end", "n_tokens", "n_crossing", "doc_tokens"]


def lines(text: bytes) -> np.ndarray:
    raw = np.frombuffer(text, np.uint8)
    at = np.flatnonzero(raw == 10) + 1
    if not text.isascii():
        at = np.cumsum((raw & 0xC0) != 0x80)[at - 1]
    n = len(text) if text.isascii() else int(np.count_nonzero((raw & 0xC0) != 0x80))
    return np.concatenate([[0], at[at < n]]).astype(np.int64)


_ENCODERS: dict[str, SpanEncoder] = {}


def _spans(path: str) -> SpanEncoder:
    if path not in _ENCODERS:
        _ENCODERS[path] = SpanEncoder(path)
    return _ENCODERS[path]


def op7(spark: SparkSession, docs: DataFrame, path: str | None = None) -> DataFrame:
    ready(spark)
    return count_by_section(docs, path or vocabulary("byte_bpe_50k.json"))
