"""The pieces that need no Spark."""

import io
import random
from array import array

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from treecount.llm import bpe, minhash, packing, quality, tokencounts, tokenfile, toxicity, urlrules, vecdup
from treecount.llm.binfuse import BinaryFuse
from treecount.llm.tokens import ChunkEncoder, load, vocabulary

WORDS, BYTES = vocabulary("word_bpe_49k.json"), vocabulary("byte_bpe_50k.json")
ALPHABET = "aAbé ÀßçÿµªŸİKſ 'stSTrevmlLd<|endoftext|>0123²½¾$%…—\x1c\x85\xa0\n\t   漢字éi̇Σσς"


def texts(n, most, seed=1):
    r = random.Random(seed)
    return ["".join(r.choice(ALPHABET) for _ in range(r.randint(0, most))) for _ in range(n)]


@pytest.mark.parametrize("path,kind", [(WORDS, "words"), (BYTES, "bytes")])
def test_chunks_give_the_ids_of_whole_texts(path, kind):
    e, t = ChunkEncoder(path, kind, most=500), texts(1500, 60)
    t += ["", "   ", "\n", "a" * 3000, "x " * 500, "<|endoftext|>", "a<|ENDOFTEXT|>b"]
    for at in range(0, len(t), 100):
        some = t[at : at + 100]
        assert e.encode([x.encode() for x in some]) == [array("I", x.ids).tobytes() for x in e.tok.encode_batch(some, add_special_tokens=False)]


def test_words_below_u0100_take_no_chunks():
    """Such texts are cut into pre-tokens at once, each known one time; only others are cut into chunks first."""
    e, t = ChunkEncoder(WORDS, "words", most=40), ["It's can'T we'Re\x85ÉTÉ\xa0été 12²½ a_b--c, $$$x", "a" * 2000 + "é1 b", "\x1cx\x1d 'S", "ÀÉ " * 300]
    for _ in range(3):
        assert e.encode([x.encode() for x in t]) == [array("I", e.tok.encode(x, add_special_tokens=False).ids).tobytes() for x in t]
    assert not e.kept and 0 < len(e.parts) <= 60 and max(map(len, e.parts)) < 2000
    mixed = ["one two", "一 two", "a <|endoftext|> b"]
    assert e.encode([x.encode() for x in mixed]) == [array("I", x.ids).tobytes() for x in e.tok.encode_batch(mixed, add_special_tokens=False)]
    assert set(e.kept) == {c.encode() for c in ("一", "two", "a", "<|endoftext|>", "b")}


@settings(max_examples=60, deadline=None)
@given(st.text(alphabet=st.characters(codec="utf-8"), max_size=80))
def test_any_text(text):
    for path, kind in ((WORDS, "words"), (BYTES, "bytes")):
        e = ENC.setdefault(kind, ChunkEncoder(path, kind))
        assert e.encode([text.encode()])[0] == array("I", e.tok.encode(text, add_special_tokens=False).ids).tobytes()
    assert TREE.decode(TREE.tok.encode(text, add_special_tokens=False).ids) == text.encode()


ENC: dict = {}
TREE = bpe.TreeEncoder(BYTES, leaf=16, window=2)


@pytest.mark.parametrize("alphabet", ["ab", "theandingtion", "aàéü漢 ", "!?.-'", "=", " ", "0123456789", "ab<|endoftext|>"])
def test_tree_concatenation_is_exact(alphabet):
    r = random.Random(alphabet)
    for n in (1, 15, 17, 200, 1500, 4000):  # the longer ones in threads
        s = "".join(r.choice(alphabet) for _ in range(n))
        assert TREE.long(s) == TREE.tok.encode(s, add_special_tokens=False).ids
        assert array("I", TREE.long(s)).tobytes() == TREE.encode([s.encode()])[0]


def test_decode_replaces_broken_bytes():
    ids = TREE.tok.encode("漢", add_special_tokens=False).ids
    assert TREE.decode(ids[:1]).decode() == TREE.tok.decode(ids[:1], skip_special_tokens=False)


def test_token_spans():
    e = tokencounts.SpanEncoder(BYTES)
    t = texts(600, 60, 2) + ["", "a\n\n\nb", "é" * 700]
    for text, spans in zip(t, e.token_spans([x.encode() for x in t]), strict=True):
        assert spans.tolist() == [list(o) for o in e.tok.encode(text, add_special_tokens=False).offsets], text


def test_owners_by_rule():
    spans, edges = np.array([[0, 2], [2, 7], [7, 8]]), np.array([0, 3, 5])
    for rule, want in (("start", [0, 0, 2]), ("end", [0, 2, 2]), ("majority", [0, 1, 2])):
        owner, crossing = tokencounts.owners(spans, edges, rule)
        assert owner.tolist() == want and crossing.tolist() == [False, True, False]
    assert tokencounts.lines("é\n\nab\n".encode()).tolist() == [0, 2, 3]


def test_token_file_round_trip_and_damage():
    docs = {i: np.arange(i % 7, dtype="<u4").tobytes() for i in range(50)}

    class Keep:
        def __init__(self):
            self.raw = io.BytesIO()

        def write(self, b):
            self.raw.write(b)

        def close(self):
            pass

    keep = Keep()
    w = tokenfile.TokenFileWriter(keep, frame_ids=8)
    for k, v in docs.items():
        w.add(k, v)
    w.close()
    raw = keep.raw.getvalue()
    f = tokenfile.TokenFile(pa.BufferReader(raw))
    assert len(f.frames) > 5 and {int(f.doc_ids[d]): ids for d, ids in f.documents()} == docs
    read = []
    plain = f.frame
    f.frame = lambda k: read.append(k) or plain(k)
    assert f.get([13, 14, 999]) == {13: [docs[13]], 14: [docs[14]]} and len(read) <= 2
    import zstandard

    whole = b"".join(zstandard.ZstdDecompressor().decompress(raw[int(a) : int(a) + int(n)]) for a, n in zip(f.offsets, f.frames[:, 0], strict=False))
    assert whole == b"".join(docs.values())
    for spot in (5, len(raw) - 2):
        bad = bytearray(raw)
        bad[spot] ^= 255
        with pytest.raises(Exception):
            list(tokenfile.TokenFile(pa.BufferReader(bytes(bad))).documents())


@pytest.mark.parametrize("n", [0, 1, 2, 3, 10, 1000, 60_000])
def test_fuse_filter(n):
    rng = np.random.default_rng(n)
    keys = rng.integers(-(2**63), 2**63 - 1, n)
    f = BinaryFuse.from_bytes(BinaryFuse.build(np.concatenate([keys, keys])).to_bytes())
    assert f.contains(keys).all()
    other = rng.integers(-(2**63), 2**63 - 1, 50_000)
    assert f.contains(other).mean() < 0.01
    if n == 60_000:
        assert 8 * len(f.slots) / n < 10


def check_plan(h):
    plan = packing.plan_tails(h)
    filled: dict[int, list] = {}
    for length in np.flatnonzero(h).tolist():
        for k in range(int(h[length])):
            pieces = packing.place(plan, length, k)
            assert sum(p[0] for p in pieces) == length
            for n, seq, off in pieces:
                filled.setdefault(seq, []).append((off, n))
    padding = 0
    for seq, own in filled.items():
        at = 0
        for off, n in sorted(own):
            assert off == at
            at += n
        assert at <= packing.WINDOW
        padding += 0 if at & (at - 1) == 0 else packing.WINDOW - at
    assert sorted(filled) == list(range(plan.sequences)) and padding == 0
    return plan


def test_packing_plans():
    rng = np.random.default_rng(0)
    for n in (0, 1, 5, 400, 6000):
        h = np.bincount(rng.integers(1, packing.WINDOW, n), minlength=packing.WINDOW)
        plan = check_plan(h)
    assert plan.cut_tokens < 0.5 * (h * np.arange(packing.WINDOW)).sum()
    hot = np.bincount([700] * 3000 + rng.integers(1, packing.WINDOW, 1000).tolist(), minlength=packing.WINDOW)
    check_plan(hot)


def test_least_squares_place_most_tails():
    """Tails spread as those of documents: most are placed by the solved counts and few are cut."""
    rng = np.random.default_rng(5)
    h = np.bincount(np.clip(rng.gamma(1.9, 345, 10_000).astype(int), 1, packing.WINDOW - 1), minlength=packing.WINDOW)
    plan = check_plan(h)
    assert plan.solved + plan.greedy + plan.cut == h.sum()
    assert plan.solved > 0.8 * h.sum() and plan.cut < 0.05 * h.sum()


def test_nnls_meets_an_exact_histogram():
    h = np.zeros(packing.WINDOW, np.int64)
    h[[548, 1500]], h[[700, 648]] = 400, [600, 300]
    _, x = packing.nnls(packing.combinations(np.flatnonzero(h), packing.WINDOW), h)
    assert sorted(np.rint(x).tolist())[-2:] == [300, 400]


def test_nnls_leaves_no_gradient():
    rng = np.random.default_rng(2)
    h = np.bincount(rng.integers(1, 64, 900), minlength=64)
    h[0] = 0
    combos = packing.combinations(np.flatnonzero(h), 64)
    active, x = packing.nnls(combos, h, rounds=400, batch=8)
    rest = h - np.bincount(combos[active].ravel(), np.repeat(x, 3), 64)
    rest[0] = 0
    assert (x > 0).all() and rest[combos].sum(1).max() < 0.05 * h.max() and abs(rest[combos[active]].sum(1)).max() < 0.1


def test_rule_sweep_against_plain_matching():
    r = random.Random(4)
    part = lambda: r.choice(["a", "b", "ab", "x-y", ""])
    rules = [(r.choice(["allow", "block"]), ".".join(r.choice("ab") for _ in range(r.randint(1, 3))) + "/" + r.choice(["", "p/", "p/q", "q"])) for _ in range(25)]
    urls = sorted((".".join(reversed(h.split("."))) + "." if h else "", p, h) for h, p in ((".".join(part() for _ in range(r.randint(1, 5))), r.choice(["", "/", "/p/", "/p/q1", "/q"])) for _ in range(800)))
    keys = sorted((".".join(reversed(x.split("/")[0].split("."))) + ".", x[x.index("/") :], x, v) for v, x in rules)
    for start in (0, 333, 700):
        s = urlrules.Sweep()
        waiting = list(keys)
        for key, path, host in urls[start:]:
            while waiting and waiting[0][0] <= key:
                s.rule(*waiting.pop(0))
            fits = [(len(x), len(x.split("/")[0]), v == "block", x, v) for v, x in rules if (host == x.split("/")[0] or host.endswith("." + x.split("/")[0])) and path.startswith(x[x.index("/") :])]
            best = max(fits, default=None)
            assert s.judge(key, path) == ((best[3], best[4]) if best else (None, None)), (host, path)


def test_tiles_lose_no_link():
    rng = np.random.default_rng(3)
    base = rng.normal(size=(40, 16))
    x = np.concatenate([base, base + rng.normal(size=base.shape) * 0.1, base * 3, base + rng.normal(size=base.shape) * 0.05])
    n = np.linalg.norm(x, axis=1)
    cos = x @ x.T / n[:, None] / n[None]
    for t in (0.98, 0.9, 0.5, -1.0):
        i, j = vecdup.tile_pairs(x, None, t)
        assert set(zip(i.tolist(), j.tolist(), strict=True)) == {(a, b) for a in range(len(x)) for b in range(a + 1, len(x)) if cos[a, b] >= t}
        i, j = vecdup.tile_pairs(x[:50], x[50:], t)
        assert len(i) == (cos[:50, 50:] >= t).sum()
    assert vecdup.forest(5, np.array([3, 1]), np.array([1, 4])).tolist() == [0, 1, 2, 1, 1]


def test_shingle_sets():
    def plain(text):
        w = "".join(c.lower() if c.isascii() else c for c in text).split()
        return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()

    for t in ["", " \n ", "a b", "A b C d e", "a b c d e f a b c d e f a b c d e", "É é x y z É é x y z", "a  b\tc d e f"]:
        assert len(minhash.shingles(t.encode(), 5)[1]) == len(plain(t))
    a, b = "a b c d e f g h i j", "A b  c d e\nf g h i k"
    x, y = (set(minhash.shingles(t.encode(), 5)[1].tolist()) for t in (a, b))
    assert len(x & y) == len(plain(a) & plain(b)) == 5


def test_estimates_track_similarity():
    s, rng = minhash.Settings(), np.random.default_rng(0)
    base = rng.integers(0, 2**63, 2000).astype(np.uint64)
    for share in (0.5, 0.85, 0.95):
        other = np.concatenate([base[: int(4000 * share / (1 + share))], rng.integers(0, 2**63, 2000 - int(4000 * share / (1 + share))).astype(np.uint64)])
        low = minhash.minima([np.unique(base), np.unique(other)], s)
        match = ((low[0] ^ low[1]) & 3 == 0).mean()
        assert abs((match - 0.25) / 0.75 - share) < 0.12
        packed = minhash.pack(low, s)
        d = packed[0] ^ packed[1]
        fold = np.int64(0x5555555555555555)
        assert np.bitwise_count((d | (d.view(np.uint64) >> np.uint64(1)).view(np.int64)) & fold).sum() == round((1 - match) * s.minima)


def test_classifiers_learn_and_generalise():
    r = random.Random(2)
    word = lambda: "".join(r.choice("abcdefghij") for _ in range(r.randint(3, 7)))
    clean = [" ".join(word() for _ in range(40)) for _ in range(250)]
    bad = [" ".join(r.choice(["zzuckerl", "xxvoid"]) + r.choice(["", "s", "en"]) if i == 17 else word() for i in range(40)) for _ in range(250)]
    s = toxicity.Settings(bits=16)
    m = toxicity.train([t.encode() for t in clean[:200] + bad[:200]], np.array([0] * 200 + [1] * 200), s)
    assert (m.score([t.encode() for t in bad[200:]], s) >= 0.5).mean() > 0.9
    assert (m.score([t.encode() for t in clean[200:]], s) >= 0.5).mean() < 0.1
    unseen = m.score([b"this zzuckerling here", b"abc def"], s)
    assert unseen[0] > unseen[1] and len(m.score([], s)) == 0 and np.isfinite(m.score([b""], s)).all()
    q = quality.Settings(epochs=20, bits=10, dims=16)
    total = np.zeros((1 << q.bits) * q.dims, np.int64)
    junk = [" ".join(w.upper() + "!!" for w in t.split()) for t in clean]
    quality.contexts([t.encode() for t in clean + junk], q, total)
    table = np.concatenate([quality.index_table(q), total.reshape(-1, q.dims).astype(np.float32)], axis=1)
    x = quality.pool([t.encode() for t in clean + junk], table, q)
    y = np.array([1] * 250 + [0] * 250)
    pick = np.arange(500) % 5 > 0
    net = quality.train(x[pick], y[pick], 0.8, q)
    assert ((net.score(x[~pick]) >= 0.5) == y[~pick]).mean() > 0.95 and net.temperature > 0
    assert quality.pool([b"", b"  "], table, q).any() == False  # noqa: E712
    one = quality.train(x[:5], np.ones(5, np.int64), 0.8, q)
    assert np.isfinite(one.score(x[:2])).all()
    assert np.isfinite(toxicity.train([], np.array([], np.int64), s).score([b"a"], s)).all()
