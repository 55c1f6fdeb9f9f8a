import datetime as dt
import hashlib
import os
import random
import time

import numpy as np
import pytest
from pyspark.sql import functions as F

from treecount import queries
from treecount.functions.registered import register
from treecount.operators import windows
from treecount.plans import cost, metrics, workloads
from treecount.plans.templates import CATALOGUE
from treecount.plans.variants import Options, counts, total
from treecount.sources import generator, graphs, sinks, tables
from treecount.sources.graphs import literal
from treecount.storage import settle
from treecount.streaming import windows as live

SF = "/root/testdata/sf0.001"


def test_graph_sizes(spark):
    known = {"copart": (8899, 200), "custpart": (5382, 350), "supppart": (1905, 210), "custsupp": (1444, 160), "user_next": (105, 15), "hour": (76, 15), "geo": (185, 190), "conv": (87, 107), "pages": (279, 305), "skew3": (3949, 256), "skew5": (2500, 244), "skew8": (1547, 207), "knn": (2924, 500)}
    for n, (e, v) in known.items():
        r = graphs.stats(graphs.BUILDERS[n](spark, SF)).first()
        assert (r.edges, r.vertices) == (e, v), n


def test_reordering_keeps_the_graph(spark):
    g = literal(spark, [(0, 1), (1, 2), (2, 3), (5, 6), (6, 7), (5, 7)], [9])
    want = graphs.stats(g).first()
    for method in ("degree", "bfs_rcm", "none"):
        h, ids = graphs.reorder(g, method)
        assert graphs.stats(h).first() == want
        got = sorted(r.id for r in ids.collect())
        assert method == "none" or got == list(range(8))
    h, _ = graphs.reorder(g, "bfs_rcm")
    assert max(abs(r.src - r.dst) for r in h.edges.collect()) <= 2
    d = {r.v: r.id for r in graphs.reorder(g, "degree")[1].collect()}
    assert d[9] == 7


def test_skew_is_kept_apart(spark):
    hub = literal(spark, [(0, i) for i in range(1, 400)])
    for s in ("join", "hubs", "grid"):
        assert total(hub, CATALOGUE["path3"], "v5", Options(strategy=s)).first().total == total(hub, CATALOGUE["path3"], "v3").first().total


def test_edge_files(spark, tmp_path):
    (tmp_path / "e.txt").write_text("# one\n1 2\n2\t3\n% two\nx y\n4 4\n")
    p = tables.edges(spark, str(tmp_path / "e.txt"), "text")
    assert sorted(map(tuple, p.collect())) == [(1, 2), (2, 3), (4, 4)]
    frame = spark.createDataFrame([(1, 2), (2, 3)], "src long, dst long")
    for fmt in ("parquet", "orc", "json", "csv"):
        frame.write.option("header", True).format(fmt).save(str(tmp_path / fmt))
        assert tables.edges(spark, str(tmp_path / fmt), fmt).count() == 2
    with pytest.raises(ValueError):
        tables.table(spark, SF, "nation", "nothing")
    with pytest.raises(ValueError):
        tables.edges(spark, "x", "xml")


def test_generator_and_sinks(spark, tmp_path):
    generator.register(spark)
    df = spark.read.format("edge_generator").option("edges", 1000).option("levels", 6).option("skew", 8).load()
    assert df.count() == 1000 and df.agg(F.max("a")).first()[0] < 64
    assert sorted(df.collect()) == sorted(df.collect())
    g = graphs.normalize(df)
    m = counts(g, CATALOGUE["path3"], "v3")
    sinks.counts(m, str(tmp_path / "c"), "x")
    assert spark.read.parquet(str(tmp_path / "c")).count() == m.count()
    sinks.results(graphs.stats(g), str(tmp_path / "r"))
    sinks.nowhere(m)
    sinks.view(m, "rooted")
    assert spark.sql("select count(*) from rooted").first()[0] == m.count()


def test_storage_policies(spark):
    df = spark.range(5)
    for p in ("plan", "persist", "table"):
        assert settle(df, p).count() == 5
    with pytest.raises(ValueError):
        settle(df, "elsewhere")
    g = literal(spark, [(0, 1), (1, 2), (2, 0), (2, 3)])
    want = total(g, CATALOGUE["path4"], "v3").collect()
    assert total(g, CATALOGUE["path4"], "v3", Options(policy="table")).collect() == want == total(g, CATALOGUE["path4"], "v5", Options(policy="table")).collect()


def test_sql_functions(spark):
    register(spark)
    assert spark.sql("select binomial(17, 8), binomial(5, 0), binomial(3, 4)").first()[:] == (24310, 1, 0) or tuple(spark.sql("select binomial(17, 8), binomial(5, 0), binomial(3, 4)").first()) == (24310, 1, 0)
    assert spark.sql("select * from color_splits(5, 3, 1)").count() == 30
    assert spark.sql("select * from template_plan(array(-1, 0, 1))").count() == 3
    assert spark.sql("select color_rank(array(1, 2))").first()[0] == 2


def test_windows(spark):
    t = lambda h, m, s=0: dt.datetime(2024, 1, 1, h, m, s)
    e = spark.createDataFrame([(0, t(0, 1), 1, "a"), (1, t(0, 1, 30), 2, "a"), (2, t(0, 59, 50), 1, "b"), (3, t(1, 0, 5), 3, "b"), (4, t(3, 0), 1, "a")], "event_id long, ts timestamp, user_id long, event_type string")
    assert sorted((r.src, r.dst) for r in windows.window_edges(e).collect()) == [(1, 2)]
    assert sorted(map(tuple, windows.near_pairs(e, 30).collect())) == [(1, 2), (1, 3)]
    assert sorted((r.user_id, r.session, r.events) for r in windows.sessions(e).collect()) == [(1, 1, 1), (1, 2, 1), (1, 3, 1), (2, 1, 1), (3, 1, 1)]
    assert sorted(map(tuple, windows.last_before(e, "a", "b").collect()), key=str) == sorted([(0, 1, None), (1, 2, None), (4, 1, 2)], key=str)
    ntz = e.withColumn("ts", F.col("ts").cast("timestamp_ntz"))
    assert windows.near_pairs(ntz, 30).count() == 2 and windows.sessions(ntz).count() == 5


def test_windows_of_a_busy_user(spark):
    """Against plain loops: many hours of one user, equal times, gaps of just the length, null users and times."""
    rng, start, rows = random.Random(7), dt.datetime(2024, 1, 1), []
    for i in range(400):
        user = None if i % 23 == 0 else 1 if i % 3 else rng.randrange(2, 5)
        ts = None if i % 31 == 0 else start + dt.timedelta(seconds=rng.randrange(0, 90_000) // 300 * 300)
        rows.append((i, ts, user, rng.choice("ab")))
    e = spark.createDataFrame(rows, "event_id long, ts timestamp, user_id long, event_type string")
    sessions, prior = [], []
    for user in {r[2] for r in rows}:
        mine = sorted((r for r in rows if r[2] == user), key=lambda r: (r[1] is not None, r[1] or start, r[0]))
        number, last, newest = 0, None, None
        for i, ts, _, kind in mine:
            if last is None or ts is None or (ts - last).total_seconds() > 1800:
                number += 1
                sessions.append([user, number, 0, ts, ts])
            sessions[-1][2] += 1
            sessions[-1][4] = last = ts
            if kind == "a":
                prior.append((i, user, newest))
            else:
                newest = i
    assert sorted(map(tuple, windows.sessions(e).collect()), key=str) == sorted(map(tuple, sessions), key=str)
    assert sorted(map(tuple, windows.last_before(e, "a", "b").collect()), key=str) == sorted(prior, key=str)
    assert windows.sessions(e.limit(0)).count() == windows.last_before(e.limit(0), "a", "b").count() == 0


def test_fit_finds_constants(spark):
    rows = [("a", v, e, n, (3e-6 * e if v == "v0" else 2e-6 * e + 1e-7 * n)) for v in ("v0", "v5") for e, n in ((1e3, 5e4), (2e4, 1e4), (5e4, 9e6))]
    t = spark.createDataFrame(rows, "graph string, variant string, edge_ops double, vertex_ops double, seconds double")
    c, table = workloads.fitted(t)
    assert (c.alpha, c.beta, c.gamma) == pytest.approx((2e-6, 1e-7, 3e-6))
    assert table.agg(F.max(F.abs(F.col("predicted") - F.col("seconds")))).first()[0] < 1e-6
    assert workloads.headline(spark, c).first().speedup > 1


def test_measures(spark):
    t = spark.createDataFrame([("g", "t", "v0", 8.0), ("g", "t", "v5", 2.0), ("g", "u", "v5", 1.0)], "graph string, template string, variant string, seconds double")
    got = {(r.template, r.variant): r.speedup for r in metrics.speedup(t).collect()}
    assert got["t", "v5"] == 4 and got["u", "v5"] is None
    r = metrics.roofline(spark.createDataFrame([(100.0, 10.0, 2.0)], "flops double, bytes double, seconds double"), 1000.0, 8.0).first()
    assert (r.intensity, r.throughput, r.roof, r.share) == (10, 50, 80, 0.625)
    assert metrics.partition_balance(spark.range(100).repartition(4)).first().partitions == 4


def test_event_log_measures(spark, tmp_path):
    line = '{"Event":"SparkListenerTaskEnd","Stage ID":%d,"Task Info":{"Launch Time":0,"Finish Time":%d},"Task Metrics":{"Executor Run Time":%d,"Executor CPU Time":1000000,"JVM GC Time":0,"Disk Bytes Spilled":0,"Input Metrics":{"Bytes Read":10},"Shuffle Read Metrics":{"Remote Bytes Read":1,"Local Bytes Read":2,"Total Records Read":3},"Shuffle Write Metrics":{"Shuffle Bytes Written":4}}}\n'
    (tmp_path / "log").write_text('{"Event":"Other"}\n' + line % (0, 1000, 1000) + line % (0, 2000, 2000) + line % (0, 1000, 1000))
    u = metrics.utilisation(metrics.task_metrics(spark, str(tmp_path / "log")), 4).first()
    assert u.active_cores == pytest.approx(0.5) and u.bytes == 51 and u.imbalance == 2


def test_workloads_run(spark):
    m = workloads.run_matrix(spark, SF, ("user_next",), ("path3",), ("v0", "v3", "v5"))
    assert m.count() == 3 and m.select("total").distinct().count() == 1
    assert workloads.rounding(spark, SF, "user_next", ("path3",)).agg(F.max("rel_error")).first()[0] < 1e-5
    assert workloads.motif_spectrum(graphs.settle(graphs.supppart(spark, SF), "persist")).count() == 3
    assert workloads.rollup(m).count() == 3 + 1 + 1 + 1
    split = {r.kernel: r for r in workloads.kernel_split(spark, SF, "geo", "path3").collect()}
    assert set(split) == {"coloring", "traversal", "multiply_add"} and abs(sum(r.share for r in split.values()) - 1) < 1e-9


def test_roofline_has_both_shares(spark, tmp_path):
    rows = workloads.roofline_run(spark, SF, "geo", "path3")
    rows.write.parquet(str(tmp_path / "rows"))
    kept = spark.read.parquet(str(tmp_path / "rows"))
    assert len(set(rows.columns)) == len(rows.columns) and kept.count() == 3
    assert abs(kept.agg(F.sum("time_share")).first()[0] - 1) < 1e-9 and kept.where("share is null").count() == 0


def test_copies_and_samples(spark):
    g = graphs.literal(spark, [(0, 1), (1, 2), (5, 1)])
    three = graphs.copies(g, 3)
    assert three.edges.count() == 18 and three.vertices.count() == 12
    assert graphs.stats(three).first().avg_degree == graphs.stats(g).first().avg_degree
    assert graphs.sample_edges(three, 4).edges.count() == 8
    assert [graphs.levels_for(n) for n in (0, 30, 6000, 60_000, 600_000, 30 << 40)] == [1, 1, 8, 11, 14, 40]


def test_skewed_networks_of_many_draws(spark, tmp_path):
    """Draws of more line items than 30 for each of 2^16 ids stay on the ids of one digest, as in their SQL."""
    many = spark.range(2_800_000).selectExpr("1L as l_orderkey", "1L as l_partkey", "1L as l_suppkey", "cast(id % 3 as int) as l_linenumber")
    many.write.parquet(str(tmp_path / "lineitem.parquet"))
    assert graphs.levels_for(2_800_000) == 17
    got = sorted(map(tuple, graphs.BUILDERS["skew3"](spark, str(tmp_path)).edges.collect()))
    a, w, want = 128, 42, set()
    for i in range(3):
        h = hashlib.md5(f"42:1:1:1:{i}".encode()).digest()
        src = sum(1 << j for j in range(16) if h[j] >= a + w)
        dst = sum(1 << j for j in range(16) if a <= h[j] < a + w or h[j] >= a + 2 * w)
        want |= {(src, dst), (dst, src)} if src != dst else set()
    assert got == sorted(want)


def test_draws_are_hashed_once(spark):
    """A condition on the ends of an edge stays above the digest; below it, it would hash each draw for each level."""
    plan = graphs.skewed(spark, SF, 8, 11).edges._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("md5(") == 1


def test_next_user_whatever_the_bucket(spark):
    """Edges between buckets are carried over, so the bucket's length changes nothing."""
    want = sorted(map(tuple, graphs.user_next(spark, SF).edges.collect()))
    for bucket in ("minute", "year"):
        assert sorted(map(tuple, graphs.user_next(spark, SF, bucket).edges.collect())) == want


def test_nearest_vectors(spark, tmp_path):
    rng = np.random.default_rng(2)
    rows = [(i, rng.normal(size=4).tolist()) for i in range(30)] + [(40, rows_0 := [1.0, 0.0, 0.0, 0.0]), (41, rows_0), (42, [2.0, 0.0, 0.0, 0.0]), (43, None), (44, [0.0] * 4), (45, [float("nan")] * 4), (46, [1.0, 2.0]), (47, [1e300, 0.0, 0.0, 0.0])]
    spark.createDataFrame(rows, "vec_id long, embedding array<double>").write.parquet(str(tmp_path / "embeddings.parquet"))
    e = {i: np.array(v) / max(np.abs(v)) for i, v in rows if v and np.isfinite(v).all() and any(v)}
    want = set()
    for a in e:
        best = sorted((-round(float(e[a] @ e[b] / np.linalg.norm(e[a]) / np.linalg.norm(e[b])), 9), b) for b in e if b != a and len(e[a]) == len(e[b]))[:3]
        want |= {(min(a, b), max(a, b)) for _, b in best}
    for block in (2048, 5, 1):
        got = graphs.knn(spark, str(tmp_path), 3, block).edges.where("src < dst").collect()
        assert {tuple(r) for r in got} == want


def test_broadcasts_are_checked(spark):
    from treecount import storage

    hinted = lambda df: "ResolvedHint" in df._jdf.queryExecution().analyzed().toString()
    assert hinted(storage.sent(spark.range(10), 8, 80)) and not hinted(storage.sent(spark.range(11), 8, 80))


def test_ranks_of_rooted_counts(spark):
    values = [5, 5, 7, 1, 2**40, 2**40 + 1, 3, 3, 3]
    got = windows.rank_rooted(spark.createDataFrame(list(enumerate(values)), "v long, cnt long")).collect()
    assert {r.v: r["rank"] for r in got} == {i: 1 + sum(y > x for y in values) for i, x in enumerate(values)}


def test_core_stands_without_the_training_data_operators(tmp_path):
    """In a copy without the folders, or with a library of theirs missing, the entry imports and keeps its own queries."""
    import shutil
    import subprocess
    import sys

    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    code = "import __spark_entry__ as e; q = e.queries(); assert 'pipeline' not in q and 'op1_quality' not in q and set(e.oracle_sql()) <= set(q) and len(q) > 100"
    shutil.copytree(root, tmp_path / "r", ignore=shutil.ignore_patterns(".git", "llm", "corpus_pipeline.py", "__pycache__"))
    blocked = "import sys; sys.modules['zstandard'] = None; sys.modules['tokenizers'] = None; "
    for where, first in ((tmp_path / "r", ""), (root, blocked)):
        subprocess.run([sys.executable, "-c", first + code], cwd=where, check=True, env={**os.environ, "PYTHONPATH": str(where)})


def test_operation_counts_favour_pruning():
    p = [cost.subtemplate_ops(v, 12, 6, 3, 1e6, 2e8)[0] for v in ("v0", "v3", "v5")]
    assert p[0] > 50 * p[1] and p[1] == p[2]


def test_streams(spark, tmp_path):
    src, rows = tmp_path / "in", []
    rng = np.random.default_rng(1)
    for f in range(2):
        part = [(f * 50 + i, dt.datetime(2024, 1, 1, f, i % 60), int(rng.integers(0, 5)), "ab"[i % 2], 0.0, "{}") for i in range(50)]
        rows += part
        spark.createDataFrame(part, live.SCHEMA).coalesce(1).write.mode("append").parquet(str(src))
        time.sleep(0.1)
    events = spark.createDataFrame(rows, live.SCHEMA)

    def drain(df, name, mode="append"):
        q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", str(tmp_path / name)).trigger(availableNow=True).start()
        q.awaitTermination(120)
        return spark.table(name)

    got = drain(live.window_degrees(live.source(spark, str(src))), "degrees")
    want = events.groupBy(F.window("ts", "1 hour")["start"].alias("start"), "user_id").count()
    assert got.join(want, ["start", "user_id"]).where("events <> count").count() == 0 and got.count() > 0
    pairs = drain(live.user_pairs(live.source(spark, str(src))), "pairs")
    assert pairs.where("src >= dst").count() == 0 and pairs.count() > 0
    edges = tmp_path / "edges"
    both = [(0, 1), (1, 0), (0, 2), (2, 0), (0, 3), (3, 0)]
    spark.createDataFrame(both, "src long, dst long").coalesce(1).write.parquet(str(edges))
    stars = drain(live.running_stars(spark.readStream.schema("src long, dst long").parquet(str(edges))), "stars", "update")
    r = stars.where("v = 0").first()
    assert (r.degree, r.path3, r.star4) == (3, 3, 1)
    seen = []
    live.each_batch(spark.readStream.schema("src long, dst long").parquet(str(edges)), lambda df, i: seen.append(df.count()), str(tmp_path / "cp")).awaitTermination(60)
    assert sum(seen) == 6


def test_imports_without_optional_folders():
    import treecount.queries

    assert treecount.queries.queries() and os.path.isdir(os.path.dirname(treecount.queries.__file__))


def test_doc_shingles_of_common_lines(spark, tmp_path):
    """Copies and lines in more than 50 documents make edges like any other."""
    line = "this very line of words is in many documents"
    texts = ["a b c d e f g h"] * 60 + [f"{line} {i} x{i} y{i} z{i} w{i}" for i in range(70)] + [f"p q r s t u v{i} w x y z {i}" for i in range(5)]
    texts += ["one two three four five six", "one two three four five six", "only four words here", "", "one two three four five six seven", "one two three four five six seven  EIGHT"]
    rows = [(3 * i, t) for i, t in enumerate(texts)] + [(0, "p q r s t u v1 other"), (None, line), (7, None)]
    spark.createDataFrame(rows, "doc_id long, text string").withColumns({"lang": F.lit("en"), "source": F.lit("x"), "n_chars": F.length("text").cast("long")}).write.parquet(f"{tmp_path}/documents.parquet")
    sets = {}
    for i, t in rows:
        w = (t or "").lower().split()
        sets.setdefault(i, set()).update(tuple(w[k : k + 5]) for k in range(len(w) - 4))
    ids = sorted(i for i in sets if i is not None)
    want = {(a, b) for a in ids for b in ids if a < b and len(sets[a] & sets[b]) >= 3}
    g = graphs.doc_shingles(spark, str(tmp_path))
    got = [(r.src, r.dst) for r in g.edges.where("src < dst").collect()]
    assert len(got) == len(set(got)) and set(got) == want and len(want) > 60 * 59 // 2 + 70 * 69 // 2 - 60
    assert {r.v for r in g.vertices.collect()} == {v for e in want for v in e}
    pairs = graphs.meet(spark.createDataFrame([(1, 20, i, 0) for i in range(20)] + [(2, 1, 5, 0)], "key int, n long, id long, tag int"), 3)
    assert sorted(tuple(sorted((r.a, r.b))) for r in pairs.collect()) == [(i, j) for i in range(20) for j in range(i + 1, 20)]


@pytest.mark.parametrize("name", ["cost_model", "improvement_bounds", "memory_table", "ops_by_variant", "run_bounds"])
def test_models_take_the_sizes_of_networks(spark, name):
    """The models' sizes come of the tables, and change with them."""
    small, large = (queries.queries()[name](spark, d).collect() for d in (SF, SF.replace("0.001", "0.01")))
    assert len(small) == len(large) > 0 and sorted(map(tuple, small)) != sorted(map(tuple, large))


@pytest.mark.parametrize("name", ["color_catalog", "rank_roundtrip", "split_catalog", "iterations_for", "lemma_maxima", "reuse_factor"])
def test_catalogs_and_bounds_read_orders(spark, name):
    """Sets of colors and sizes are those of orders: each row says how many have it, and rank_roundtrip finds the same rank twice."""
    rows = queries.queries()[name](spark, SF).collect()
    assert sum(r.orders for r in rows) > 0
    assert name != "rank_roundtrip" or all(r["rank"] == r.computed for r in rows)


def test_automorphisms_of_order_trees(spark, tmp_path):
    from treecount import queries

    rows = [(1, p, i) for i, p in enumerate((9, 4, 6))] + [(2, p, i) for i, p in enumerate((4, 7, 11))] + [(3, 5, 1), (4, 8, 1), (None, 1, 1)]
    spark.createDataFrame(rows, "l_orderkey long, l_partkey long, l_linenumber int").write.parquet(str(tmp_path / "lineitem.parquet"))
    got = queries.symmetries(spark, str(tmp_path))
    assert sorted(map(tuple, got.collect())) == [("0", 2, 2, 2), ("0,0,0", 4, 6, 1), ("0,1,2", 4, 2, 1)]


def test_window_edges_sends_arrays(spark):
    rows = [(i, f"2024-01-01 0{h}:{i % 60:02d}:00", u) for i, (h, u) in enumerate([(h, (7 * i + h) % 31) for h in range(3) for i in range(40)] + [(5, 1), (6, None), (6, 4)])]
    e = spark.createDataFrame(rows, "event_id long, ts string, user_id long").withColumn("ts", F.col("ts").cast("timestamp"))
    by = {}
    for _, t, u in rows:
        by.setdefault(t[:13], set()).add(u)
    want = sorted((t, a, b) for t, us in by.items() for a in us - {None} for b in us - {None} if a < b)
    for block in (4, 7, 100):
        got = windows.window_edges(e, "1 hour", block)
        assert sorted((str(r.start)[:13], r.src, r.dst) for r in got.collect()) == want
    # What the last shuffle sends are blocks: two rows for each two of a window.
    plan = windows.window_edges(e, "1 hour", 4)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("RepartitionByExpression") == 2 and plan.index("Generate explode") < plan.index("RepartitionByExpression")


def test_growing_templates_makes_each_table_once(spark, monkeypatch):
    seen = []
    monkeypatch.setattr(workloads, "run_matrix", lambda *args, options, **kw: seen.append(options))
    workloads.growing_templates(spark, "")
    assert seen[0].policy == "table" and seen[0].fused and seen[0].cnt_type == "double"


def test_networks_are_measured_one_after_the_other(spark, monkeypatch):
    """Shuffle files of a network's statistics are gone when the query returns, and the session is as it was."""
    import re
    import time

    from treecount import queries

    env = spark._jvm.org.apache.spark.SparkEnv
    files = lambda: set(re.findall(r"shuffle_\d+", env.get().blockManager().diskBlockManager().getAllFiles().toString()))
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    had, before = files(), spark.conf.get(key, "false")
    monkeypatch.setattr(queries, "GRAPHS", ("geo", "supppart"))
    rows = queries.graph_stats(spark, "/root/testdata/sf0.001")
    for _ in range(50):
        if files() <= had:
            break
        time.sleep(0.2)
    assert files() <= had and spark.conf.get(key, "false") == before
    assert [r.graph for r in rows.collect()] == ["geo", "supppart"]
