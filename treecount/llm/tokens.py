"""Whole-text encoding with the tokenizers library, each distinct chunk or pre-token once.

A text is cut only where its tokenizer's own pre-tokenizer always cuts, so the joined ids of
the pieces are the ids of the whole text. A worker keeps the ids of the pieces it has met.
"""

from __future__ import annotations

import os
import re
from array import array

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")

import public_tokenizers  # noqa: E402
from tokenizers import Tokenizer  # noqa: E402

#: Space and \t \n \v \f \r, white space to every pre-tokenizer here.
SPACED_CHUNK = re.compile(rb"[ \t-\r]*[^ \t-\r]+|[ \t-\r]+")
#: UTF-8 of the white space beyond ASCII; a text with any of it is not cut for the byte-level tokenizer.
WIDE_SPACE = re.compile(rb"\xc2[\x85\xa0]|\xe1\x9a\x80|\xe2\x80[\x80-\x8a\xa8\xa9\xaf]|\xe2\x81\x9f|\xe3\x80\x80")
#: Letters, digits and white space below U+0100, as the tokenizers' own patterns class them.
LETTER, DIGIT, SPACE = "a-zA-Zªµºß-öø-ÿÀ-ÖØ-Þ", "0-9²³¹¼-¾", " \\t-\\r\x85\xa0"
SHORT_FORM = "'(?:s|t|re|ve|m|ll|d)"
PARTS = {
    "words": re.compile(f"{SHORT_FORM}|[{LETTER}]+|[{DIGIT}]|[^{SPACE}{LETTER}{DIGIT}]+"),
    "bytes": re.compile(f"{SHORT_FORM}| ?[{LETTER}]+| ?[{DIGIT}]+| ?[^{SPACE}{LETTER}{DIGIT}]+|[{SPACE}]+(?![^{SPACE}])|[{SPACE}]+"),
}


def byte_letters() -> dict[int, str]:
    """The character that stands for each byte inside byte-level vocabularies: printable ones stand for themselves, the rest follow from U+0100."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    rest = iter(range(256, 512))
    return {b: chr(b if b in plain else next(rest)) for b in range(256)}


BYTE_LETTERS = byte_letters()
#: Chunks above this many bytes are encoded each time.
LONGEST_KEPT = 256


def load(path: str) -> Tokenizer:
    tok = Tokenizer.from_file(path)
    tok.no_truncation()
    tok.no_padding()
    return tok


def vocabulary(name: str) -> str:
    return public_tokenizers.path(name)


def narrow(s: str) -> bool:
    """Whether all characters are below U+0100."""
    if s.isascii():
        return True
    try:
        s.encode("latin-1")
    except UnicodeEncodeError:
        return False
    return True


class Parts(dict):
    """The ids of pre-tokens below U+0100, by the tokenizer's model when first asked for; long ones are not kept, and very long
    ones go to the whole tokenizer, which makes no object of each token."""

    def __init__(self, tok: Tokenizer):
        super().__init__()
        self.tok = tok

    def __missing__(self, p: str) -> bytes:
        if len(p) > 4 * LONGEST_KEPT:
            return array("I", self.tok.encode(p, add_special_tokens=False).ids).tobytes()
        spelled = p if p.isascii() and p.isalnum() else p.encode().decode("latin-1").translate(BYTE_LETTERS)
        found = array("I", [t.id for t in self.tok.model.tokenize(spelled)]).tobytes()
        if len(p) <= LONGEST_KEPT:
            self[p] = found
        return found


class ChunkEncoder:
    """Ids of whole texts as little-endian unsigned 32-bit bytes.

    kind "words": white space separates tokens and leaves none (word_bpe). kind "bytes": white space
    leads the word after it (byte_bpe). ``most`` bounds the chunks kept; past it only those of the
    current texts stay. No result depends on it.
    """

    def __init__(self, path: str, kind: str, most: int = 300_000):
        self.tok, self.kind, self.most = load(path), kind, most
        self.kept: dict[bytes, bytes] = {}
        self.parts = Parts(self.tok)

    def chunks(self, text: bytes) -> list[bytes]:
        if self.kind == "words":
            return text.split()
        if not text or WIDE_SPACE.search(text):
            return [text] if text else []
        return SPACED_CHUNK.findall(text)

    def encode_chunks(self, chunks: list[bytes]) -> list[bytes]:
        """Chunks below U+0100 are cut into pre-tokens here and those go to the tokenizer's model; all others to the whole tokenizer."""
        out: list[bytes | None] = []
        parts, cut, low, short = self.parts, PARTS[self.kind].findall, self.kind == "words", 4 * LONGEST_KEPT
        if len(parts) > self.most:
            parts.clear()
        rest = []
        for at, c in enumerate(chunks):
            s = c.decode()
            if len(c) > short or "<|" in s or not (s.isascii() or max(s) < "\u0100"):
                rest.append((at, s))
                out.append(None)
                continue
            out.append(b"".join([parts[p] for p in cut(s.lower() if low else s)]))
        for (at, _), e in zip(rest, self.tok.encode_batch_fast([s for _, s in rest], add_special_tokens=False), strict=True):
            out[at] = array("I", e.ids).tobytes()
        return out

    def learn(self, lists: list[list[bytes]]) -> dict[bytes, bytes]:
        """Makes sure that all chunks are known; gives the mapping to use for them."""
        met = set().union(*lists)
        kept = self.kept
        new = [c for c in met if c not in kept]
        if len(kept) + len(new) > self.most:
            kept = self.kept = {c: kept[c] for c in met if c in kept}
        known = kept
        for at in range(0, len(new), 4096):
            some = new[at : at + 4096]
            kept.update(zip(some, self.encode_chunks(some), strict=True))
        if any(len(c) > LONGEST_KEPT for c in new):
            known = dict(kept)
            self.kept = {c: v for c, v in kept.items() if len(c) <= LONGEST_KEPT}
        return known

    def encode_pieces(self, texts: list[bytes]) -> list[bytes]:
        lists = [self.chunks(t) for t in texts]
        known = self.learn(lists)
        return [b"".join(map(known.__getitem__, x)) for x in lists]

    def encode(self, texts: list[bytes]) -> list[bytes]:
        """Texts below U+0100 are cut into pre-tokens at once where white space leaves none; the others go by their chunks."""
        if self.kind != "words":
            return self.encode_pieces(texts)
        if len(self.parts) > self.most:
            self.parts.clear()
        out: list[bytes] = []
        rest, ids_of, cut = [], self.parts.__getitem__, PARTS[self.kind].findall
        for at, t in enumerate(texts):
            s = t.decode()
            if "<|" in s or not narrow(s):
                rest.append(at)
                out.append(b"")
            else:
                out.append(b"".join(map(ids_of, cut(s.lower()))))
        for at, ids in zip(rest, self.encode_pieces([texts[at] for at in rest]), strict=True):
            out[at] = ids
        return out


_ENCODERS: dict[tuple, ChunkEncoder] = {}


def encoder(path: str, kind: str) -> ChunkEncoder:
    """This worker's encoder for a file; tasks after the first find it warm."""
    if (path, kind) not in _ENCODERS:
        _ENCODERS[path, kind] = ChunkEncoder(path, kind)
    return _ENCODERS[path, kind]
