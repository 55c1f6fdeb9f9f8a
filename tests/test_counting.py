import random
import re
from dataclasses import replace
from itertools import combinations, product
from math import comb

import numpy as np
import pytest
from pyspark.sql import functions as F

from treecount.functions import colorsets
from treecount.functions.coloring import color_in_python, color_vertices
from treecount.operators import blocked, exact, fused, grid, relational
from treecount.plans import cost, estimator, metrics
from treecount.plans.templates import CATALOGUE, partition
from treecount.plans.variants import VARIANTS, Options, count_many, counts, tables, total
from treecount.sources import graphs
from treecount.sources.graphs import literal

FIVE = [(0, 1), (0, 3), (1, 2), (1, 3), (3, 4)]
EXACT = {"path3": 7, "path4": 5, "star4": 2, "path5": 1, "fork5": 2}


@pytest.fixture(scope="module")
def five(spark):
    return graphs.settle(literal(spark, FIVE), "persist")


def plain_total(pairs, n, template, colors):
    """Colorful maps by the recurrence, on dense arrays."""
    t = CATALOGUE[template]
    k = t.size
    a = np.zeros((n, n), dtype=object)
    for x, y in pairs:
        a[x, y] = a[y, x] = 1
    m = {}
    for s in partition(t):
        m[s.key] = np.zeros((n, 1 << k), dtype=object)
        if s.active is None:
            for v in range(n):
                m[s.key][v, 1 << colors[v]] = 1
        else:
            sums = a.dot(m[s.passive])
            for i, j in product(range(1 << k), repeat=2):
                if not i & j:
                    m[s.key][:, i | j] += m[s.active][:, i] * sums[:, j]
    return m[s.key].sum()


def test_worked_example(spark, five):
    colors = spark.createDataFrame([(0, v, c) for v, c in enumerate([0, 1, 2, 2, 1])], "it int, v long, color int")
    one = relational.leaf_counts(colors)
    s1 = relational.neighbor_sum(five.edges, one)

    def dense(m):
        out = [[0] * 8 for _ in range(5)]
        for r in m.collect():
            out[r.v][r["mask"]] = r["cnt"]
        return out

    got = dense(s1)
    assert [[r[1], r[2], r[4]] for r in got] == [[0, 1, 1], [1, 0, 2], [0, 1, 0], [1, 2, 0], [0, 0, 1]]
    two = relational.multiply_add(one, s1)
    assert [[r[3], r[5], r[6]] for r in dense(two)] == [[1, 1, 0], [1, 0, 2], [0, 0, 1], [0, 1, 2], [0, 0, 1]]
    s2 = relational.neighbor_sum(five.edges, two)
    assert [[r[3], r[5], r[6]] for r in dense(s2)] == [[1, 1, 4], [1, 2, 3], [1, 0, 2], [2, 1, 3], [0, 1, 2]]
    assert [r[7] for r in dense(relational.multiply_add(one, s2))] == [4, 2, 1, 2, 1]
    assert estimator.scale(10, 3, 2) == pytest.approx(22.5)


def test_mean_over_all_colorings_is_exact(spark, five):
    for t, n in EXACT.items():
        k = CATALOGUE[t].size
        if k > 4:
            continue
        rows = [(i, v, c) for i, cs in enumerate(product(range(k), repeat=5)) for v, c in enumerate(cs)]
        colors = spark.createDataFrame(rows, "it int, v long, color int")
        tables = {}
        for s in partition(CATALOGUE[t]):
            tables[s.key] = relational.leaf_counts(colors) if s.active is None else relational.multiply_add(tables[s.active], relational.neighbor_sum(five.edges, tables[s.passive]))
        whole = tables[s.key].agg(F.sum("cnt")).first()[0]
        assert estimator.scale(whole, k, cost_aut(t)) / k**5 == pytest.approx(n)


def cost_aut(t):
    from treecount.plans.templates import automorphisms

    return automorphisms(CATALOGUE[t])


@pytest.mark.parametrize("template", ["star4", "spider6"])
def test_variants_agree_with_dense_arrays(spark, template):
    rng = np.random.default_rng(5)
    pairs = sorted({tuple(sorted(p)) for p in rng.integers(0, 12, (30, 2)).tolist() if p[0] != p[1]})
    g = graphs.settle(literal(spark, pairs), "persist")
    k = CATALOGUE[template].size
    want = plain_total(pairs, 12, template, [color_in_python(42, 0, v, k) for v in range(12)])
    for v in VARIANTS:
        got = total(g, CATALOGUE[template], v, Options(width=4)).collect()
        assert sum(r.total for r in got) == want, v


def test_roots_cuts_and_sharing_do_not_matter(spark, five):
    base = total(five, CATALOGUE["path5"], "v3").collect()
    for o in (Options(root=2), Options(cut="smallest"), Options(cut="balanced", share=False), Options(groups=5)):
        for v in ("v2", "v5"):
            assert total(five, CATALOGUE["path5"], v, o).collect() == base


@pytest.mark.parametrize("strategy", ["join", "broadcast", "grid", "hubs"])
def test_strategies_and_implementations(spark, five, strategy):
    want = sorted(counts(five, CATALOGUE["path4"], "v3").collect())
    for impl, width in (("arrow", 4), ("arrow", 64), ("expr", 1), ("hof", 4)) if strategy == "join" else (("auto", 4),):
        assert sorted(counts(five, CATALOGUE["path4"], "v5", Options(strategy=strategy, impl=impl, width=width)).collect()) == want


def test_special_cases(spark, five):
    empty = literal(spark, [])
    assert total(empty, CATALOGUE["path3"], "v3").count() == 0 == total(empty, CATALOGUE["path3"], "v5").count()
    loop = literal(spark, [(1, 1), (2, 2)])
    assert loop.edges.count() == 0
    edge = literal(spark, [(1, 2), (2, 1), (1, 2)])
    assert edge.edges.count() == 2 and total(edge, CATALOGUE["path3"], "v5").count() == 0
    s = estimator.series(edge, CATALOGUE["path2"], 64, "v3").agg(F.avg("estimate")).first()[0]
    assert 0.4 < s < 1.6
    lonely = literal(spark, [(0, 1), (1, 2)], [7, 8])
    assert lonely.vertices.count() == 5 and graphs.isolated(lonely, lonely.vertices).count() == 2
    assert counts(lonely, CATALOGUE["path3"], "v5").where("v > 2").count() == 0
    assert estimator.series(lonely, CATALOGUE["path5"], 3, "v5").agg(F.sum("total")).first()[0] == 0


def test_disjoint_union_adds_and_labels_do_not_matter(spark):
    a = [(0, 1), (1, 2), (2, 0), (2, 3)]
    both = literal(spark, a + [(x + 10, y + 10) for x, y in a])
    colors = color_vertices(both.vertices, 3).withColumn("color", (F.col("v") % 10 % 3).cast("int"))
    t1 = relational.leaf_counts(colors)
    t3 = relational.multiply_add(t1, relational.neighbor_sum(both.edges, relational.multiply_add(t1, relational.neighbor_sum(both.edges, t1))))
    halves = t3.groupBy((F.col("v") >= 10).alias("h")).agg(F.sum("cnt").alias("n")).collect()
    assert len({r.n for r in halves}) == 1 and len(halves) == 2


def test_baseline_refuses_too_much(spark, five):
    big = graphs.Graph(five.edges, five.vertices, 10**9)
    with pytest.raises(ValueError):
        total(big, CATALOGUE["t12"], "v0")


def test_long_overflow_raises_and_decimal_holds(spark):
    hub = literal(spark, [(0, i) for i in range(1, 60)])
    assert total(hub, CATALOGUE["star5"], "v3", Options(cnt_type="decimal")).collect()[0].total > 0
    m = spark.createDataFrame([(0, 0, 1, 2**62)], "it int, v long, mask long, cnt long")
    s = spark.createDataFrame([(0, 0, 2, 4)], "it int, v long, mask long, cnt long")
    with pytest.raises(Exception, match="(?i)overflow"):
        relational.multiply_add(m, s).collect()


def test_float_and_double_stay_close(spark):
    rng = np.random.default_rng(2)
    g = graphs.settle(literal(spark, rng.integers(0, 40, (300, 2)).tolist()), "persist")
    true = total(g, CATALOGUE["spider6"], "v3", Options(cnt_type="decimal"))
    for kind, most in (("float", 1e-5), ("double", 1e-9)):
        e = metrics.relative_error(total(g, CATALOGUE["spider6"], "v5", Options(cnt_type=kind)), true, ["it"], "total").first().rel_error
        assert e <= most


def test_complete_graph_estimate_and_exact(spark):
    g = graphs.settle(literal(spark, [(i, j) for i in range(9) for j in range(i)]), "persist")
    for t in ("path3", "star4", "path4"):
        n = exact.in_complete_graph(9, CATALOGUE[t])
        assert exact.closed_form(g, t).first().cnt == n == exact.enumerate_count(g, CATALOGUE[t]).first().cnt
    est, err, its = estimator.estimate(g, CATALOGUE["path3"], 0.05, 128, 16, "v3")
    assert abs(est - exact.in_complete_graph(9, CATALOGUE["path3"])) < 5 * err + 1
    assert its <= 128


def test_colorful_enumeration(spark, five):
    for t in ("path3", "star4", "fork5"):
        colors = color_vertices(five.vertices, CATALOGUE[t].size).select("v", "color")
        want = exact.enumerate_count(five, CATALOGUE[t], colors).first().cnt
        assert sum(r.total for r in total(five, CATALOGUE[t], "v5").collect()) == want


def test_double_star(spark):
    g = literal(spark, [(0, 1), (0, 2), (0, 3), (1, 4), (1, 5)])
    assert exact.double_star(g, 2, 2).first().cnt == 1 and exact.double_star(g, 1, 1).first().cnt == exact.path4(g).first().cnt == 4


def test_many_templates_share(spark, five):
    got = {r.template: r.total for r in count_many(five, [CATALOGUE["path4"], CATALOGUE["star4"]]).collect()}
    for t in ("path4", "star4"):
        assert got.get(t, 0) == sum(r.total for r in total(five, CATALOGUE[t], "v3").collect())


def test_color_sets():
    for k in range(2, 9):
        for h in range(1, k + 1):
            sets = [colorsets.unrank(i, h) for i in range(comb(k, h))]
            assert [colorsets.rank(c) for c in sets] == list(range(comb(k, h)))
            assert [colorsets.mask_of(c) for c in sets] == colorsets.masks(k, h).tolist()
    rs, ra, rp = colorsets.split_arrays(6, 4, 2)
    assert len(rs) == comb(6, 4) * comb(4, 2)
    m = colorsets.masks(6, 2)
    assert all(m[a] & m[p] == 0 and m[a] | m[p] == colorsets.masks(6, 4)[s] for s, a, p in zip(rs, ra, rp, strict=True))


def test_catalogs_against_plain_sets(spark):
    for k, h in ((6, 3), (5, 5), (7, 1)):
        want = sorted((h, colorsets.rank(c), colorsets.mask_of(c), list(c)) for c in combinations(range(k), h))
        assert sorted(map(tuple, colorsets.catalog(spark, k, h).select("h", "rank", "mask", "members").collect())) == want
    for k, s, p in ((6, 4, 1), (5, 5, 2), (6, 3, 2)):
        want = sorted((colorsets.rank(w), colorsets.rank(set(w) - set(c)), colorsets.rank(c), colorsets.mask_of(w), colorsets.mask_of(set(w) - set(c)), colorsets.mask_of(c)) for w in combinations(range(k), s) for c in combinations(w, p))
        assert sorted(map(tuple, colorsets.splits(spark, k, s, p).collect())) == want
        assert sorted(zip(*(x.tolist() for x in colorsets.split_arrays(k, s, p)), strict=True)) == sorted(w[:3] for w in want)
    sets = np.array([[0, 5, 61], [1, 2, 3]])
    assert colorsets.ranks_of(sets, 62).tolist() == [colorsets.rank(c) for c in sets.tolist()]
    assert colorsets.sets_of(colorsets.ranks_of(sets, 62), 62, 3).tolist() == sets.tolist()


def test_groups_of_on_demand_sums(spark, five):
    """Each passive set is summed once, for the group of the first color set that asks for it."""
    for p, s in ((1, 3), (2, 4), (2, 5)):
        for c in combinations(range(5), p):
            first = min(colorsets.mask_of(w) for w in combinations(range(5), s) if set(c) <= set(w))
            assert spark.range(1).select(colorsets.first_superset(F.lit(colorsets.mask_of(c)).cast("long"), s - p)).first()[0] == first
    want = total(five, CATALOGUE["path5"], "v3").collect()
    for groups in (1, 3, 50):
        assert total(five, CATALOGUE["path5"], "v2", Options(groups=groups)).collect() == want


def test_kernel_options_agree(spark, five):
    want = [(r.it, r.total) for r in total(five, CATALOGUE["path4"], "v5").collect()]
    for o in (Options(order="by_color", width=2), Options(layout="wide", width=2), Options(strategy="grid"), Options(width=3), Options(strategy="broadcast", width=8)):
        assert [(r.it, r.total) for r in total(five, CATALOGUE["path4"], "v5", o).collect()] == want
    for bad in (Options(order="x"), Options(layout="x")):
        with pytest.raises(ValueError):
            total(five, CATALOGUE["path4"], "v5", bad)
    with pytest.warns(UserWarning):
        blocked.check_width(12)
    assert grid.grid_parts(10, 10) == 2 and grid.grid_parts(1 << 32, 1e9) > 100


def test_kernels_raise_on_overflow(spark):
    big = spark.createDataFrame([(0, 1, 0, [2**40, 2**40])], "it int, v long, blk int, x array<long>")
    with pytest.raises(Exception, match="exceed 64 bits"):
        blocked.multiply_add(big, big, 2, 2, 1, 2, "long").collect()


def test_colors_are_the_same_everywhere(spark, five):
    got = color_vertices(five.vertices, 7, 42, (0, 3)).collect()
    assert len(got) == 10 and all(r.color == color_in_python(42, r.it, r.v, 7) for r in got)
    assert color_in_python(42, 0, 5, 1 << 40) == 148519232
    assert color_vertices(five.vertices, 7, method="xxhash").where("color between 0 and 6").count() == 5


def test_blocks_and_grid(spark, five):
    m = blocked.leaf_blocks(color_vertices(five.vertices, 5), 5, 2, "long")
    rel = relational.leaf_counts(color_vertices(five.vertices, 5))
    want = sorted(map(tuple, relational.neighbor_sum(five.edges, rel).select("v", "mask", "cnt").collect()))
    for s in (blocked.neighbor_sum(five.edges, m, 2, "long"), grid.grid_sum(five.edges, m, 2, 3, "long"), grid.hub_sum(five.edges, m, 2, 2, 1, "long")):
        assert sorted(map(tuple, blocked.to_relational(s, 5, 1, 2).select("v", "mask", "cnt").collect())) == want


def test_pruned_plans_walk_less(spark, five):
    def touched(variant):
        rows = total(five, CATALOGUE["path4"], variant)
        return rows._jdf.queryExecution().optimizedPlan().toString().count("Aggregate")

    assert touched("v3") > touched("v0")  # the sum is taken apart from the product


def test_estimator_summary(spark, five):
    s = estimator.series(five, CATALOGUE["path3"], 40, "v5", Options(cnt_type="double"), 20)
    a, b = estimator.summary(s, CATALOGUE["path3"], 7).first(), estimator.summary(s, CATALOGUE["path3"], 7, "median_of_means").first()
    assert a.iterations == b.iterations == 40 and abs(a["mean"] - 7) < 4 * a.stderr + 0.5
    assert metrics.failure_rate(s, 7, 100).first().failure_rate == 0
    assert estimator.running_mean(s).orderBy(F.desc("it")).first()["mean"] == pytest.approx(a["mean"])
    assert estimator.count_trees(spark.createDataFrame(FIVE, "x long, y long"), CATALOGUE["path3"], 4).first().iterations == 4


def test_fork5_in_whole_graphs(spark, five):
    """The formula against the enumeration, with and without triangles; a registered query takes it over every vertex."""
    whole = literal(spark, [(a, b) for a in range(7) for b in range(a)])
    mixed = literal(spark, [(0, 1), (1, 2), (2, 0), (2, 3), (3, 4), (4, 5), (5, 2), (0, 6), (6, 7), (2, 7), (0, 20), (20, 21)])
    for g in (five, whole, mixed, literal(spark, [(0, 1)]), literal(spark, [])):
        assert exact.closed_form(g, "fork5").first().cnt == exact.enumerate_count(g, CATALOGUE["fork5"]).first().cnt
    assert exact.closed_form(five, "fork5").first().cnt == 2 and exact.closed_form(whole, "fork5").first().cnt == exact.in_complete_graph(7, CATALOGUE["fork5"])
    from treecount.queries import queries

    assert queries()["exact_fork5"](spark, "/root/testdata/sf0.01").first().cnt == "4065264500"


def test_peak_memory_by_hand():
    """What is alive at each step, from the plan alone."""
    for name in ("path4", "bin7", "t12", "t15a"):
        t = CATALOGUE[name]
        plan = partition(t)
        alive = []
        for i, s in enumerate(plan):
            later = {x for q in plan[i:] for x in (q.active, q.passive, q.key) if x}
            alive.append(sum(comb(t.size, q.size) for q in plan[: i + 1] if q.key in later or q.key == plan[-1].key))
        assert cost.memory(plan, t.size, 10, 8) == (80 * max(comb(t.size, q.size) for q in plan), 80 * max(alive))


def test_counted_leaves_agree_with_all_maps(spark, five):
    """Occurrences with the leaves of one node counted are those of all maps laid out, on networks with and without triangles."""
    rng = random.Random(5)
    some = graphs.literal(spark, [(rng.randrange(9), rng.randrange(9)) for _ in range(22)])
    for g in (five, some):
        for t in ("path3", "path4", "star4", "fork5", "path5", "spider6"):
            want = exact.enumerate_maps(g, CATALOGUE[t]).count()
            assert exact.counted_maps(g, CATALOGUE[t]).first().cnt == want, t


def test_large_stars_are_counted_not_laid_out(spark):
    """A hub of 3,000 vertices has 10^13 maps of fork5 and is counted all the same."""
    g = graphs.literal(spark, [(0, i) for i in range(1, 3001)] + [(1, 3001)])
    assert exact.enumerate_count(g, CATALOGUE["fork5"]).first().cnt == comb(2999, 2)
    assert exact.enumerate_count(g, CATALOGUE["star5"]).first().cnt == comb(3000, 4)


@pytest.mark.parametrize("variant", ["v0", "v1", "v3", "v5"])  # v2 writes its tables at once
def test_counts_are_not_sent_to_all_tasks(spark, five, variant):
    """Joins of edges and counts shuffle whatever Spark takes their sizes for; hashed tables of counts don't fit a driver."""
    plan = total(five, CATALOGUE["path4"], variant)._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" not in plan and "SortMergeJoin" in plan


@pytest.mark.parametrize("ranges", [1, 3])
def test_fused_kernels_count_the_same(spark, monkeypatch, ranges):
    from treecount.operators import fused

    monkeypatch.setattr(fused, "ranges", lambda rows, vertices: ranges)
    r = random.Random(5)
    g = graphs.settle(literal(spark, [(7 * r.randrange(40), 7 * r.randrange(40)) for _ in range(150)]), "table")
    for name, kind, its in (("star4", "long", (0, 1)), ("bin7", "double", (0,))):
        o = Options(cnt_type=kind, iterations=its, policy="table")
        want = {tuple(x) for x in counts(g, CATALOGUE[name], "v5", o).collect()}
        run, (key,) = tables(g, CATALOGUE[name], "v5", replace(o, fused=True))
        assert {tuple(x) for x in counts(g, CATALOGUE[name], "v5", replace(o, fused=True)).collect()} == want and want
        # Only whole templates and tables that neighbours sum up are made, and no count of zero is stored.
        assert set(run.tables) == {key} | {s.passive for s in partition(CATALOGUE[name]) if s.passive}
        assert not any(df.where(F.exists("x", lambda c: c == 0)).count() for df in [*run.tables.values(), *run.sums.values()])


def test_fused_sums_by_chunks(monkeypatch):
    from treecount.operators import fused

    monkeypatch.setattr(fused, "MOST_ROWS", 3)
    r = np.random.default_rng(1)
    src, dst, x = r.integers(0, 9, 60), r.integers(0, 11, 60), r.integers(0, 5, (11, 4))
    s = fused.Sums([np.concatenate([src, dst])], 4, np.int64)
    for at in (0, 5):
        ids = np.arange(at, min(at + 5 + at, 11))
        s.add(ids, x[ids])
    out = {int(v): fused.dense(np.array([bits]), np.array(c), 4)[0].tolist() for b in s.result(0, 0) for v, bits, c in zip(*(b.column(i).to_pylist() for i in (1, 3, 4)), strict=True)}
    want = {v: x[dst[src == v]].sum(0).tolist() for v in set(src.tolist())}
    assert out == {v: c for v, c in want.items() if any(c)}
    with pytest.raises(OverflowError):
        s.add(np.arange(11), np.full((11, 4), 1 << 61))
        list(s.result(0, 0))


def test_two_neighbours_meet_once(spark, five):
    r = random.Random(8)
    pairs = {tuple(sorted((r.randrange(25), r.randrange(25)))) for _ in range(120)}
    g = graphs.settle(literal(spark, [p for p in pairs if p[0] != p[1]]), "persist")
    want = sum(1 for x in combinations(range(25), 3) if all(p in pairs for p in combinations(x, 2)))
    found = exact.corners(g)
    assert found.count() == want > 0
    # Every two neighbours that meet are in the order of degrees, then ids; before, each two met in both orders.
    assert "<>" not in (plan := found._jdf.queryExecution().optimizedPlan().toString()) and not re.search(r"NOT \(x#\d+L = y#\d+L\)", plan)


@pytest.mark.parametrize("name", ["path4", "spider6"])
def test_column_kernels_on_blocks(spark, name):
    """v0 and v3 on sparse blocks, over several ranges, equal the relational programs vertex by vertex; one pack serves all."""
    rnd = random.Random(5)
    g = graphs.settle(literal(spark, list({tuple(sorted(rnd.sample(range(30), 2))) for _ in range(90)})), "table")
    o = Options(iterations=(0, 1), policy="table")
    want = {tuple(r) for r in counts(g, CATALOGUE[name], "v3", o).collect()}
    for v in ("v0", "v3", "v5"):
        for kind in ("long", "double"):
            rows = counts(g, CATALOGUE[name], v, replace(o, fused=True, cnt_type=kind, width=8)).collect()
            assert {(r.it, r.v, int(r.cnt)) for r in rows} == want and want
    assert len(g.packs) == 1


def test_settle_reads_its_tables_once(spark, tmp_path):
    """Vertices come of the kept edges, so the source may be gone by then; isolated ones are still there."""
    g = graphs.settle(literal(spark, FIVE), "table")
    assert not [x for x in g.vertices.inputFiles() if "edges" in x] and {r.v for r in g.vertices.collect()} == set(range(5))
    f = F.udf(lambda x: seen.add(1) or x, "long")
    seen = spark.sparkContext.accumulator(0)
    pairs = spark.range(20, numPartitions=1).select(F.col("id").alias("a"), f("id").alias("b")).withColumn("b", F.col("b") + 1)
    assert graphs.settle(graphs.normalize(pairs), "table").rows == 40
    assert seen.value <= 40  # once for the filter and once for the value; a second build would double it
    assert {r.v for r in graphs.settle(literal(spark, FIVE, [9]), "table").vertices.collect()} == {0, 1, 2, 3, 4, 9}


def test_sample_takes_the_smallest_hashes(spark, monkeypatch):
    import hashlib

    g = graphs.settle(literal(spark, [(a, b) for a in range(12) for b in range(a)]), "table")
    pairs = sorted(((r.src, r.dst) for r in g.edges.where("src < dst").collect()), key=lambda p: hashlib.md5(f"42:{p[0]}:{p[1]}".encode()).hexdigest())
    for digits in (1, 4):
        monkeypatch.setattr(graphs, "HASH_DIGITS", digits)
        for n in (1, 7, 30, 65):
            s = graphs.sample_edges(g, n)
            assert {(r.src, r.dst) for r in s.edges.where("src < dst").collect()} == set(pairs[:n])
    assert graphs.sample_edges(g, 66) is g


def test_v2_on_sparse_blocks(spark):
    """It makes the network once and walks packed edges, a passive set when a color set first asks for it."""
    g = graphs.settle(graphs.copart(spark, "/root/testdata/sf0.001"), "table")
    for kind in ("long", "double"):
        o = Options(policy="table", fused=True, cnt_type=kind)
        run, (key,) = tables(g, CATALOGUE["bin7"], "v2", o)
        assert "bits" in run.tables[key].columns and not run.sums and len(g.packs) == 1
        assert total(g, CATALOGUE["bin7"], "v2", o).first().total == total(g, CATALOGUE["bin7"], "relational", Options(policy="persist")).first().total


def test_sums_and_edges_travel_small(spark):
    """Packed edges take a few bytes each, and sums hold no set with their vertex's own color."""
    r = np.random.default_rng(3)
    src, dst = r.integers(-(1 << 62), 1 << 62, 500), r.integers(0, 900, 500)
    order = np.lexsort((dst, src))
    assert fused.unsqueezed(fused.squeezed(src, dst)).tolist() == [*src[order], *dst[order]]
    pairs = [(a, b) for a in range(60) for b in range(a + 1, 60) if (a * b) % 3]
    g = graphs.settle(literal(spark, pairs), "table")
    o = Options(policy="table", fused=True, cnt_type="long")
    run, _ = tables(g, CATALOGUE["t10"], "v5", o)
    pack = next(iter(g.packs.values()))
    assert sum(len(row.e) for row in pack.collect()) < 3 * g.rows
    k = 10
    for key, sums in run.sums.items():
        size = next(s.size for s in partition(CATALOGUE["t10"]) if s.key == key)
        w = blocked.width(k, size, 64)
        for row in sums.collect():
            ranks = [row.blk * w + i for i in range(64) if row.bits >> i & 1]
            assert all(color_in_python(42, row.it, row.v, k) not in s for s in colorsets.sets_of(np.array(ranks), k, size).tolist())
    assert total(g, CATALOGUE["t10"], "v5", o).first().total == total(g, CATALOGUE["t10"], "v3", Options(policy="table")).first().total


def test_every_run_is_made(spark, monkeypatch):
    """The baseline at ten nodes and more is neither left out nor given up after a slow run, in the query and in its SQL."""
    from treecount import queries
    from treecount.plans import workloads

    monkeypatch.setattr(workloads, "timed", lambda g, t, v, o: (1e6, 1))
    rows = workloads.growing_templates(spark, "/root/testdata/sf0.001").collect()
    assert {(r.template, r.variant) for r in rows} == {(t, v) for t in ("path3", "path5", "bin7", "t10", "t12") for v in ("v0", "v3", "v5")}
    assert "not (r.template" not in queries.oracle_sql()["growing_templates"]


def test_steps_of_many_blocks(spark, monkeypatch):
    """v0, v1 and v3 of templates whose counts are many blocks, with few vertices and edges held at once, and colorings apart."""
    g = graphs.settle(literal(spark, [(a, b) for a in range(30) for b in range(a) if (a * b) % 3 != 1]), "table")
    o = Options(policy="table", fused=True, iterations=(0, 3), width=8)
    want = {tuple(r) for r in counts(g, CATALOGUE["t10"], "v5", replace(o, width=64)).collect()}
    for kind, vs in (("long", ("v0", "v3")), ("double", ("v3", "v5"))):
        for v in vs:
            run, (key,) = tables(g, CATALOGUE["t10"], v, replace(o, cnt_type=kind))
            assert "bits" in run.tables[key].columns
            assert {tuple(r) for r in counts(g, CATALOGUE["t10"], v, replace(o, cnt_type=kind)).collect()} == want and want
    r = np.random.default_rng(5)
    src, dst = r.integers(0, 9, 60), r.integers(0, 9, 60)
    monkeypatch.setattr(fused, "MOST_ROWS", 4)
    monkeypatch.setattr(fused, "WALKED_EDGES", 7)
    xa, xp, found = r.integers(0, 5, (9, 15)), r.integers(0, 5, (9, 6)), []
    for v in ("v0", "v1", "v3"):
        steps = fused.Steps([np.concatenate([src, dst])], 6, 3, 1, 4, np.int64, v)
        steps.active[:] = xa[steps.src].T
        for steps.blk in (0, 1):
            x = np.zeros((9, 4), np.int64)
            x[:, : 6 - 4 * steps.blk] = xp[:, 4 * steps.blk : 4 * steps.blk + 4]
            steps.add(np.arange(9), x)
            steps.end_block()
        found.append(steps.out.tolist())
    sums = np.array([xp[dst[src == v]].sum(0) for v in np.unique(src)])
    want = np.zeros((20, len(sums)), int)
    for i, j, l in zip(*colorsets.split_arrays(6, 3, 1), strict=True):
        want[i] += xa[np.unique(src), j] * sums[:, l]
    assert found == [want.tolist()] * 3
    with pytest.raises(OverflowError):
        steps.active[:] = 1 << 62
        steps.add(np.arange(9), np.full((9, 4), 4))
        steps.end_block()


def test_triangles_send_no_pairs(spark, monkeypatch):
    """Cells of several parts, small rows and few marks at once, against the joins of neighbours; also where there are no edges."""
    from treecount.operators import cells

    r = random.Random(4)
    pairs = [(0, i) for i in range(1, 70)] + [(r.randrange(1, 70), r.randrange(1, 70)) for _ in range(500)]
    for most, row, pairs_at_once, marks in ((1 << 23, 1 << 16, 1 << 20, 1 << 24), (90, 16, 5, 100)):
        for name, value in (("MOST_EDGES", most), ("ROW_EDGES", row), ("MOST_PAIRS", pairs_at_once), ("MOST_MARKS", marks)):
            monkeypatch.setattr(cells, name, value)
        g = literal(spark, pairs)
        want = exact.corners(g).count()
        assert exact.triangles(g).first().cnt == want and want
        plan = exact.triangles(graphs.settle(g, "table"))._jdf.queryExecution().executedPlan().toString()
        assert "Join" not in plan
        assert exact.path4(g).first().cnt == exact.enumerate_count(g, CATALOGUE["path4"]).first().cnt
    assert exact.path4(literal(spark, [])).first().cnt == 0 == exact.triangles(literal(spark, [])).first().cnt


def test_steps_of_pruning_on_sparse_blocks(spark, monkeypatch):
    """Networks of degree_effect and pruning_steps are packed once for all programs, v1 too, and tables are made once."""
    from treecount.plans import workloads

    seen = []
    monkeypatch.setattr(workloads, "run_matrix", lambda *args: seen.append(args[-1]) or spark.createDataFrame([(1, 1)], "edges int, vertices int"))
    workloads.degree_effect(spark, ""), workloads.pruning(spark, "")
    assert all(o.policy == "table" and o.fused for o in seen) and len(seen) == 2
    monkeypatch.setattr(fused, "WALKED_EDGES", 5)
    g = graphs.settle(literal(spark, [(a, b) for a in range(9) for b in range(a) if (a * b) % 3 != 1]), "table")
    want = {tuple(r) for r in counts(g, CATALOGUE["path4"], "relational").collect()}
    for v in ("v0", "v1", "v2", "v3"):
        run, (key,) = tables(g, CATALOGUE["path4"], v, Options(policy="table", fused=True))
        m = run.tables[key]
        assert "bits" in m.columns and {(r.it, r.v, r.x[0]) for r in m.collect()} == want and want
    assert len(g.packs) == 1
