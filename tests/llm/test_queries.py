"""Every operator on odd rows, on empty tables and against brute force."""

import hashlib
import random
import zlib
from collections import defaultdict

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from treecount.llm import bpe, common, exactdup, minhash, packing, quality, tokencounts, tokenfile, toxicity, urlrules, vecdup
from treecount.llm.components import components
from treecount.llm.tokens import load, vocabulary

SF = "/root/testdata/sf0.001"
LONG = " ".join(f"w{i}" for i in range(6000))
BASE = " ".join(f"v{i % 90}x{i}" for i in range(120))
ROWS = [(1, "Hello there, world"), (2, "hello there, WORLD"), (3, None), (4, ""), (5, "  \n "), (6, LONG), (7, LONG.upper()), (8, BASE), (9, BASE + " end"), (9, BASE + " end"), (None, "lone"), (11, "ÀB c"), (12, "Àb c"), (13, "a\n\nb\n"), (14, BASE.replace("v5x5 ", "zz ")), (15, "é" * 5000)]
SCHEMA = "doc_id long, text string, lang string, score double, n long, place long, text_sha256 string, kept boolean, label int"


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame([(i, t, "en", 0.5, 1, 2, "x", True, 1) for i, t in ROWS], SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def real(spark):
    return common.documents(spark, SF)


def rows(df):
    return sorted((r.asDict() for r in df.collect()), key=str)


def against_sql(df, sql, **frames):
    c = duckdb.connect()
    for name, frame in frames.items():
        c.register(name, frame.toArrow())
    r = c.sql(sql)
    cols = r.columns
    want = sorted((dict(zip(cols, x, strict=True)) for x in r.fetchall()), key=lambda d: str(sorted(d.items())))
    got = sorted(({k: x[k] for k in cols} for x in (y.asDict() for y in df.collect())), key=lambda d: str(sorted(d.items())))
    assert got == want


def test_url_rules(spark):
    urls = [None, "", "x.org/es/", "http://a.org", "http://a.org/", "HTTP://B.EXAMPLE.ORG/es/1?q#f", "http://example.org/en/15", "http://example.org/en/2", "http://xexample.org/es/", "http://q.com/de/1", "http://q.com/fr/#x", "a://b://c.org/d", "http://org/", "http://u@a.org:80/", "http://.org/x", "http://a.net?x=/es/", "http://a.org#é"]
    pages = spark.createDataFrame([(i, u, "<p>", "x", "y") for i, u in enumerate(urls)] + [(0, None, "", "", "")], "page_id long, url string, html string, host string, rule string")
    plain = pages.select("page_id", "url").distinct()
    against_sql(urlrules.op3(spark, plain), urlrules.oracle(), pages=plain)
    assert urlrules.op3(spark, pages).count() == len(urls) + 1 and urlrules.op3(spark, pages.limit(0)).count() == 0
    frame = spark.createDataFrame([*urlrules.RULES, ("block", None), (None, None), ("block", "/es/")], "verdict string, rule string")
    assert rows(urlrules.judge_urls(plain, frame)) == rows(urlrules.op3(spark, plain))


def test_rules_open_across_ranges(spark):
    """Many rules and one host with most urls, in more ranges than hosts, against plain matching."""
    r = random.Random(1)
    rules = [(r.choice(["allow", "block"]), f"{r.choice(['', 'x.', 'y.x.', 'A.', 'İ.'])}{r.choice(['com', 'org'])}/{r.choice(['', 'a', 'ab', 'ab/c', 'b/' + str(i)])}") for i in range(60)]
    urls = [(i, f"http://{r.choice(['x.com', 'x.com', 'x.com', 'y.x.com', 'com', 'a.org', 'z.org', 'İ.com', 'i̇.com'])}/{r.choice(['a', 'ab', 'ab/c', 'b/' + str(r.randrange(60)), ''])}{r.choice(['', '1', '?q'])}") for i in range(400)]
    fold = lambda t: "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t)
    want = {}
    for i, u in urls:
        host, _, path = u[7:].split("?")[0].partition("/")
        fits = [(len(x), len(x.split("/")[0]), v == "block", v) for v, x in rules if (h := fold(x.split("/")[0])) and (host == h or host.endswith("." + h)) and ("/" + path).startswith(x[x.index("/") :])]
        best = max(fits, default=None)
        want[i] = (best[0], best[3]) if best else (None, "allow")
    frame = spark.createDataFrame(rules, "verdict string, rule string")
    keep = spark.conf.get("spark.sql.adaptive.coalescePartitions.enabled")
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    try:
        got = urlrules.judge_urls(spark.createDataFrame(urls, "page_id long, url string"), frame).collect()
    finally:
        spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", keep)
    assert len(got) == 400 and {r.page_id: (r.rule and len(r.rule), r.verdict) for r in got} == want


def test_exact_dedup(spark, odd, none, real):
    for docs in (odd, real):
        against_sql(exactdup.op4(spark, docs), exactdup.ORACLE, documents=docs)
    assert exactdup.op4(spark, none).count() == 0
    for snapshot in ("null", "0", "cast(doc_id % 3 as int)"):
        against_sql(exactdup.dedup(odd, snapshot), exactdup.ORACLE, documents=odd)
    kept = exactdup.keep_one(odd, "null")
    assert sorted(r.doc_id or 0 for r in kept.collect()) == [0, 2, 4, 5, 7, 8, 9, 12, 13, 14, 15] and kept.columns == odd.columns


def test_filters_kept_with_a_snapshot(spark, odd, tmp_path, monkeypatch):
    """Written once, the filters of snapshot 0 serve later runs; only those of a new snapshot are built."""
    exactdup.snapshot_filters(odd, "case when doc_id < 5 then 0 end").write.parquet(str(tmp_path / "f"))
    kept, built, plain = spark.read.parquet(str(tmp_path / "f")), [], exactdup.build_filters
    monkeypatch.setattr(exactdup, "build_filters", lambda stored, shards: built.append({r.snapshot for r in stored.select("snapshot").distinct().collect()}) or plain(stored, shards))
    against_sql(exactdup.dedup(odd, "case when doc_id < 5 then 0 when doc_id < 9 then 1 end", kept), exactdup.ORACLE, documents=odd)
    assert built == [{1}]


def test_differing_bytes_stay_apart(spark, odd, monkeypatch):
    """A digest that meets another text of the same digest, as in a collision."""
    monkeypatch.setattr(exactdup, "compare", lambda docs, matched: matched.select("text_sha256"))
    got = {r.doc_id: r for r in exactdup.dedup(odd.where("doc_id in (1, 2)"), "case when doc_id = 1 then 0 end").collect()}
    assert got[1].kept and got[2].kept and got[1].group_size == 1


def brute_near(docs, words=5, percent=85):
    sets = {}
    for i, t in docs:
        w = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "").encode().split()
        sets[i] = {tuple(w[j : j + words]) for j in range(max(1, len(w) - words + 1))} if w else set()
    comp = {i: i for i in sets}

    def root(i):
        while comp[i] != i:
            i = comp[i]
        return i

    ids = sorted(sets)
    for a in ids:
        for b in ids:
            if a < b and sets[a] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                x, y = sorted((root(a), root(b)))
                comp[y] = x
    return {i: (len(sets[i]), root(i)) for i in ids}


def test_near_duplicates(spark, odd, none, real):
    for docs in (odd.where("doc_id is not null").dropDuplicates(["doc_id"]), real):
        want = brute_near([(r.doc_id, r.text) for r in docs.select("doc_id", "text").collect()])
        assert {r.doc_id: (r.n_shingles, r.component_id) for r in minhash.op6(spark, docs).collect()} == want
    assert minhash.op6(spark, odd).count() == len(ROWS) and minhash.op6(spark, none).count() == 0
    assert minhash.keep_one(odd).columns == odd.columns


def test_near_duplicates_without_ids(spark):
    """Documents without an id rank last in their group, whatever the order and however often they repeat."""
    a, b = " ".join(f"a{i}" for i in range(60)), " ".join(f"b{i}" for i in range(60))
    rows = [(None, a), (1, a), (2, a), (None, a), (3, a + " end"), (None, b), (None, b + " end"), (None, "lone"), (4, "one"), (4, "two"), (4, a), (None, None), (0, b.upper().replace("B", "c")), (5, b[:60] + " x y z")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    sets = [{tuple(w[j : j + 5]) for j in range(max(1, len(w) - 4))} if (w := (t or "").lower().split()) else set() for _, t in rows]
    root = list(range(len(rows)))
    for x in range(len(rows)):
        for y in range(x):
            if sets[x] and 100 * len(sets[x] & sets[y]) >= 85 * len(sets[x] | sets[y]):
                root = [root[y] if r == root[x] else r for r in root]
    low = {r: min((rows[k][0] for k in range(len(rows)) if root[k] == r and rows[k][0] is not None), default=None) for r in root}
    want = [(i, len(sets[k]), low[root[k]], low[root[k]] == i) for k, (i, _) in enumerate(rows)]
    assert sorted((tuple(r) for r in minhash.op6(spark, docs).collect()), key=str) == sorted(want, key=str)
    small = minhash.Settings(percent=85, bands=26, rows=6, block=2, block_bytes=64)
    assert sorted((tuple(r) for r in minhash.near_duplicates(docs, small).collect()), key=str) == sorted(want, key=str)


def test_chains_of_near_copies(spark):
    """Neighbours in the chain are alike, its ends are not; buckets then hold several components at first."""
    words = [f"q{i}" for i in range(200)]
    docs = []
    for k in range(40):
        docs.append((100 - k, " ".join(words)))
        words = [*words[4:], *(f"r{k}.{j}" for j in range(4))]
    docs += [(500 + i, " ".join(f"{i}.{j}" for j in range(50))) for i in range(5)]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    want = brute_near(docs)
    assert len({c for _, c in want.values()}) == 6
    for s in (minhash.Settings(), minhash.Settings(block=4), minhash.Settings(bits=4)):
        assert {r.doc_id: (r.n_shingles, r.component_id) for r in minhash.near_duplicates(df, s).collect()} == want


def test_components(spark):
    links = [(i, i + 1) for i in range(30)] + [(50, 40), (40, 45), (7, 7)]
    got = {r.node: r.component for r in components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == {i: 0 for i in range(31)} | {40: 40, 45: 40, 50: 40}
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def check_vectors(df, out, tiles=(1024, 16)):
    """The operator's rows against all pairs of rows; ids may be null or repeat."""
    e = {r: np.array(v, np.float64) for r, (_, v, lab) in enumerate(out) if v and None not in v and np.isfinite(v).all() and np.any(v) and lab is not None}
    e = {r: v / np.abs(v).max() for r, v in e.items()}
    links = defaultdict(set)
    for a in e:
        for b in e:
            if a != b and out[a][2] == out[b][2] and len(e[a]) == len(e[b]) and e[a] @ e[b] / np.linalg.norm(e[a]) / np.linalg.norm(e[b]) >= 0.98:
                links[a].add(b)
    want = []
    for r, (i, *_) in enumerate(out):
        seen, todo = {r}, [r]
        while todo:
            for b in links[todo.pop()] - seen:
                seen.add(b)
                todo.append(b)
        low = min((out[x][0] for x in seen if out[x][0] is not None), default=None)
        want.append((i, len(links[r]), low, i == low))
    for tile in tiles:
        got = [(r.vec_id, r.n_links, r.component_id, r.kept) for r in vecdup.link_vectors(df, tile=tile).collect()]
        assert sorted(got, key=str) == sorted(want, key=str)


def test_vectors_without_ids_and_of_any_size(spark):
    base = np.random.default_rng(3).normal(size=(4, 6))
    near = lambda k, by=1.0: (by * (base[k] + 0.01)).tolist()
    out = [(7, near(0), 1), (9, near(0, 2.0), 1), (None, near(0, 3.0), 1), (None, near(1), 1), (None, near(1), 1), (2**60, near(2), 1), (2**60 + 1, near(2, 1.5), 1), (5, near(3, 1e200), 1), (6, near(3, 1e-200), 1), (6, near(3, 1e300), 1), (None, None, 1), (8, [5e-324, 0.0], 1), (4, [1e-323, 0.0], 1)]
    check_vectors(spark.createDataFrame(out, "vec_id long, embedding array<double>, label long"), out)


def test_vectors(spark):
    rng = np.random.default_rng(1)
    base = rng.normal(size=(30, 8))
    data = [(i, base[i % 30] + (0.02 if i % 3 else 0.0) * rng.normal(size=8), i % 2) for i in range(120)]
    out = [(i, v.astype(np.float32).tolist(), lab) for i, v, lab in data]
    out += [(200, out[0][1], 0), (201, out[0][1], 1), (202, out[0][1], None), (203, None, 0), (204, [0.0] * 8, 0), (205, [float("nan")] * 8, 0), (206, [float("inf")] * 8, 0), (207, [None, *out[0][1][1:]], 0), (208, [], 0), (209, out[0][1][:4], 0), (210, [2 * x for x in out[0][1]], 0)]
    df = spark.createDataFrame(out, "vec_id long, embedding array<float>, label int")
    check_vectors(df, out)
    assert vecdup.op9(spark, df.limit(0)).count() == 0
    real = spark.read.parquet(f"{SF}/embeddings.parquet")
    against_sql(vecdup.op9(spark, real), vecdup.ORACLE, embeddings=real)


def test_token_files(spark, odd, none, real, tmp_path):
    tok = load(vocabulary("word_bpe_49k.json"))
    for docs in (odd, real):
        got = sorted(tokenfile.op5(spark, docs).collect(), key=lambda r: r.start)
        assert [r.doc_id for r in got] == sorted((r.doc_id for r in docs.select("doc_id").collect()), key=lambda x: (x is not None, x or 0))
        want = defaultdict(set)
        for r in docs.select("doc_id", "text").collect():
            want[r.doc_id].add(tuple(tok.encode(r.text or "", add_special_tokens=False).ids + [2]))
        at = 0
        for r in got:
            assert r.start == at and (r.n_tokens, r.ids_crc32) in {(len(x), zlib.crc32(np.array(x, "<u4").tobytes())) for x in want[r.doc_id]}
            at += r.n_tokens
    assert tokenfile.op5(spark, none).count() == 0
    m = tokenfile.write_tokens(odd, vocabulary("word_bpe_49k.json"), f"file://{tmp_path}/t", frame_ids=16)
    found = tokenfile.fetch(m, [1, 9, 99])
    assert set(found) == {1, 9} and len(found[9]) == 2 and found[1][0] == tok.encode("Hello there, world").ids + [2]


def test_bpe(spark, odd, none, real):
    tok = load(vocabulary("byte_bpe_50k.json"))
    got = {r.doc_id: (r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in bpe.op8(spark, real).collect()}
    for r in real.select("doc_id", "text").collect():
        ids = tok.encode(r.text or "", add_special_tokens=False).ids
        assert got[r.doc_id] == (len(ids), hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(tok.decode(ids, skip_special_tokens=False).encode()).hexdigest())
    got = defaultdict(set)
    for r in bpe.op8(spark, odd).collect():
        got[r.doc_id].add((r.n_tokens, r.ids_sha256, r.decoded_sha256))
    for i, t in ROWS:
        ids = tok.encode(t or "", add_special_tokens=False).ids
        sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
        assert (len(ids), sha(",".join(map(str, ids))), sha(tok.decode(ids, skip_special_tokens=False))) in got[i]
    assert bpe.op8(spark, none).count() == 0
    e = bpe.encode_texts(odd.where("doc_id = 15"), vocabulary("byte_bpe_50k.json"))
    assert bpe.decode_ids(e, vocabulary("byte_bpe_50k.json")).first().text == "é" * 5000


def test_token_counts(spark, odd, none, real):
    tok = load(vocabulary("byte_bpe_50k.json"))
    got = defaultdict(list)
    for r in tokencounts.op7(spark, real).collect():
        got[r.doc_id].append(r)
    for r in real.collect():
        offsets, own = tok.encode(r.text, add_special_tokens=False).offsets, sorted(got[r.doc_id], key=lambda x: x.section)
        assert "".join(r.text[x.char_start : x.char_end] for x in own) == r.text and all(x.doc_tokens == len(offsets) for x in own)
        assert [x.n_tokens for x in own] == [sum(x.char_start <= a < x.char_end for a, _ in offsets) for x in own]
    assert tokencounts.op7(spark, none).count() == 0
    empty = tokencounts.op7(spark, odd.where("doc_id in (3, 4)")).collect()
    assert [(r.section, r.n_tokens, r.char_end) for r in empty] == [(0, 0, 0)] * 2
    for rule in tokencounts.RULES:
        parts = tokencounts.count_by_section(odd.withColumn("cut", F.array(F.lit(4), F.lit(None).cast("int"), F.lit(1), F.lit(4), F.lit(-3), F.lit(10**9))), vocabulary("byte_bpe_50k.json"), "cut", rule)
        assert parts.where("doc_id <> 9").groupBy("doc_id", "doc_tokens").agg(F.sum("n_tokens").alias("s")).where("s <> doc_tokens").count() == 0
    with pytest.raises(ValueError):
        tokencounts.count_by_section(odd, "", rule="other")


def check_packed(docs, got):
    tok = load(vocabulary("word_bpe_49k.json"))
    ids = {r.doc_id: tok.encode(r.text or "", add_special_tokens=False).ids + [1] for r in docs}
    by_doc, by_seq = defaultdict(list), defaultdict(list)
    for r in got:
        x = ids[r.doc_id]
        assert r.doc_tokens == len(x) and r.ids_crc32 == zlib.crc32(np.array(x[r.start : r.start + r.length], "<u4").tobytes())
        by_doc[r.doc_id].append((r.start, r.length))
        by_seq[r.sequence_id].append((r.offset, r.length))
    assert set(by_doc) == set(ids)
    for k, v in by_doc.items():
        at = 0
        for a, n in sorted(v):
            assert a == at
            at += n
        assert at == len(ids[k])
    padding = 0
    for v in by_seq.values():
        at = 0
        for a, n in sorted(v):
            assert a == at
            at += n
        assert at <= 2048
        padding += 0 if at & (at - 1) == 0 else 2048 - at
    assert padding == 0


def test_packing(spark, odd, none, real):
    for docs in (odd.where("doc_id is not null").dropDuplicates(["doc_id"]), real):
        check_packed(docs.select("doc_id", "text").collect(), packing.op10(spark, docs).collect())
    assert packing.op10(spark, none).count() == 0 and packing.op10(spark, odd).where("doc_id = 9").count() >= 2
    with pytest.raises(ValueError):
        packing.pack(odd, "", window=1000)


def plain_toxicity(text, model, s):
    """Scores one text by words, strings and whole numbers."""
    words = "".join(c if c.isascii() and c.isalpha() or ord(c) > 127 else " " for c in (text or "").lower()).split(" ")
    means = []
    for w in (f" {w} " for w in words if w):
        z = []
        for n in range(s.shortest, s.longest + 1):
            for gram in (w[i : i + n] for i in range(len(w) - n + 1)):
                h = 0
                for c in gram:
                    h = (h * 0x01000193 + ord(c) + 1) % 2**32
                for shift, factor in ((15, 0x2C1B3C6D), (12, 0x297A2D39)):
                    h = (h ^ (h >> shift)) * factor % 2**32
                z.append(float(model.logits[h >> (32 - s.bits)]))
        means.append(sum(z) / len(z) if z else 0.0)
    top = sorted(means)[-s.top :]
    x = (sum(top) / len(top) if top else 0.0) + model.bias + model.slope * np.log1p(len(means))
    return 1 / (1 + np.exp(-x))


def test_toxicity_scores_as_a_plain_version_does(spark, odd):
    s = toxicity.Settings(bits=12, epochs=3)
    docs = odd.unionByName(spark.createDataFrame([(100 + i, t) for i, t in enumerate(["a", "ab", "Ünïcode wörds, ÉTÉ!", "x1y", "漢字 漢", "good vile good", "vile VILE"])], "doc_id long, text string"), allowMissingColumns=True)
    model = toxicity.train([b"vile words here", b"kind words here", b"more vile things", b"more kind things"] * 5, np.array([1, 0, 1, 0] * 5), s)
    got = sorted((r.doc_id or -1, round(r.score, 9), r.predicted) for r in toxicity.score_documents(docs, model, s).collect())
    want = [(r.doc_id or -1, plain_toxicity(r.text, model, s)) for r in docs.select("doc_id", "text").collect()]
    assert got == sorted((i, round(x, 9), int(x >= 0.5)) for i, x in want)
    assert toxicity.drop_toxic(docs, model, s).count() == sum(x < 0.5 for _, x in want)


def plain_quality(text, net, table, s):
    """Scores one text: rows of its words and of their shapes, means, and the network, each by itself."""
    words = (text or "").encode().split()
    low = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
    kind = bytes(65 if 65 <= c <= 90 else 97 if 97 <= c <= 122 or c > 127 else 48 if 48 <= c <= 57 else c for c in range(256))
    def hashed(raw, extra=0):
        h = sum(int(minhash.BYTE[c]) * pow(minhash.ODD, i, 2**64) for i, c in enumerate(raw)) + extra
        return int(minhash.mix(np.array([h % 2**64], np.uint64))[0]) >> (64 - s.bits)

    x = np.zeros(quality.width(table))
    if words:
        shapes = [bytes(c for i, c in enumerate(k) if not i or k[i - 1] != c) for k in (w.translate(kind) for w in words)]
        d = table.shape[1]
        for k, rows in enumerate(([hashed(w.translate(low)) for w in words], [hashed(b, 1) for b in shapes])):
            mean = np.mean([table[r] for r in rows], axis=0)
            x[k * d : (k + 1) * d], x[k - 3] = mean, np.log(np.linalg.norm(mean[: d // 2]) + 1e-3)
        x[-1] = np.log1p(len(words))
    z = float(np.tanh((x - net.mean) / net.scale @ net.w1 + net.b1) @ net.w2 + net.b2)
    return 1 / (1 + np.exp(-(z / net.temperature + net.shift)))


def test_quality_scores_as_a_plain_version_does(spark, odd):
    s = quality.Settings(bits=9, dims=8, epochs=5)
    docs = odd.unionByName(spark.createDataFrame([(100 + i, t) for i, t in enumerate(["One", "Two words", "AAA!! 12,5 bb", "ÉTÉ était 漢"])], "doc_id long, text string"), allowMissingColumns=True)
    table = quality.tables(docs, s)
    rng = np.random.default_rng(0)
    texts = [" ".join(rng.choice(["aa", "Bb", "C!", "12"], 9)) for _ in range(60)]
    net = quality.train(quality.pool([t.encode() for t in texts], table, s), np.arange(60) % 2, 0.7, s)
    got = sorted((r.doc_id or -1, r.score, r.predicted) for r in quality.score_documents(docs, net, table, s).collect())
    want = sorted((r.doc_id or -1, plain_quality(r.text, net, table, s)) for r in docs.select("doc_id", "text").collect())
    assert [g[0] for g in got] == [w[0] for w in want] and np.allclose([g[1] for g in got], [w[1] for w in want], atol=1e-5)
    assert all(g[2] == (w[1] >= 0.3) for g, w in zip(got, want, strict=True) if abs(w[1] - 0.3) > 1e-4)


@pytest.mark.parametrize("op,column,least", [(quality.op1, "quality", (0.95, 0.95)), (toxicity.op2, "toxic", (0.85, 0.85))])
def test_held_out_precision_and_recall(spark, op, column, least):
    """On the larger table; some labels of both kinds are wrong there, so neither can be 1."""
    sf = "/root/testdata/sf0.1"
    labels = common.labels(spark, sf)
    got = op(spark, common.documents(spark, sf), labels).where("held_out").join(labels, "doc_id").select("predicted", column).collect()
    hit = sum(r.predicted == 1 == r[column] for r in got)
    precision, recall = hit / sum(r.predicted for r in got), hit / sum(r[column] == 1 for r in got)
    assert precision > least[0] and recall > least[1], (precision, recall)


@pytest.mark.parametrize("op,column", [(quality.op1, "quality"), (toxicity.op2, "toxic")])
def test_classifiers(spark, odd, none, op, column):
    sf = "/root/testdata/sf0.01"
    docs, labels = common.documents(spark, sf), common.labels(spark, sf)
    got = op(spark, docs, labels).join(labels, "doc_id").select("held_out", "score", "predicted", column, "doc_id").collect()
    assert all(0 <= r.score <= 1 and r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in got)
    held = [r for r in got if r.held_out]
    pos, neg = ([r.score for r in held if r[column] == k] for k in (1, 0))
    auc = np.mean([(a > b) + 0.5 * (a == b) for a in pos for b in neg])
    assert auc > 0.75, auc
    clash = labels.withColumn("score", F.lit(1)).withColumn("text", F.lit("x"))
    out = op(spark, odd, clash).collect()
    assert len(out) == len(ROWS) and all(0 <= r.score <= 1 for r in out)
    assert op(spark, none, labels).count() == 0
    assert op(spark, odd, labels.limit(0)).count() == len(ROWS)


def test_pipeline(spark, tmp_path):
    docs = common.documents(spark, "/root/testdata/sf0.01").withColumn("extra", F.lit("x"))
    before = docs
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, "/root/testdata/sf0.01")
        out.write.parquet(str(tmp_path / name))
        before, docs = docs, spark.read.parquet(str(tmp_path / name))
        if name != "packing":
            assert docs.columns == before.columns and 0 < docs.count() <= before.count() and docs.exceptAll(before).count() == 0
        if name == "exact_dedup":
            assert before.select(common.lower_az(F.coalesce("text", F.lit("")))).distinct().count() == docs.count()
        if name == "near_dedup":
            want = brute_near([(r.doc_id, r.text) for r in before.select("doc_id", "text").collect()])
            assert {r.doc_id for r in docs.collect()} == {c for _, c in want.values()}
    check_packed(before.select("doc_id", "text").collect(), docs.collect())
    empty = before.limit(0)
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, empty, "/root/testdata/sf0.01").count() == 0


def test_registered():
    import __spark_entry__ as entry

    names = list(entry.queries())
    assert all(sum(n.startswith(f"op{k}_") for n in names) == 1 for k in range(1, 11)) and "pipeline" in names
    assert set(entry.oracle_sql()) <= set(names)


def test_pipeline_drops_copies_from_080(spark):
    """Pairs of similarity 0.80 to 0.85 link in the stage, and not in op6."""
    docs = []
    for k in range(6):
        words = [f"k{k}w{i}" for i in range(104)]
        docs += [(2 * k, " ".join(words)), (2 * k + 1, " ".join([*words[: 93 + (k == 5) * -1], *(f"z{i}" for i in range(11 + (k == 5)))]))]
    assert {100 * x / (200 - x) for x in (89, 88)} == {100 * 89 / 111, 100 * 88 / 112}  # shared of 100 shingles each: 80.2 and 78.6
    df = spark.createDataFrame(docs, "doc_id long, text string")
    assert brute_near(docs, percent=80) == {r.doc_id: (r.n_shingles, r.component_id) for r in minhash.near_duplicates(df).collect()}
    assert sorted(r.doc_id for r in corpus_pipeline.drop_near_copies(spark, df, None).collect()) == [0, 2, 4, 6, 8, 10, 11]
    assert minhash.op6(spark, df).where("kept").count() == 12


def test_toxicity_corrects_a_capped_sample(spark):
    """A sample of as many rows of each label gives the log odds of the whole; one without a cap is left alone."""
    docs = spark.createDataFrame([(i, f"{'vile' if i % 9 == 0 else 'kind'} words number {i}") for i in range(400)], "doc_id long, text string")
    known = spark.createDataFrame([(i, int(i % 9 == 0)) for i in range(400)], "doc_id long, toxic int")
    for most in (10, 4000):
        s = toxicity.Settings(bits=12, epochs=2, most_docs=most)
        sample = toxicity.labelled_sample(docs, known, "toxic", s.most_docs, s.most_chars)
        y = np.array([k for _, k in sample])
        odds = known.where(~common.held_out(F.col("doc_id"))).groupBy().agg(F.sum("toxic") / F.sum(1 - F.col("toxic"))).first()[0]
        got = toxicity.fit(docs, known, s).bias - toxicity.train([t for t, _ in sample], y, s).bias
        assert np.isclose(got, np.log(odds) - np.log(y.mean() / (1 - y.mean()))) and (got < -1 if most == 10 else np.isclose(got, 0))
