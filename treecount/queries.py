"""The registered queries over the given tables, and their SQL."""

from __future__ import annotations

from math import comb

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import sql
from .functions import colorsets
from .functions.coloring import color, color_vertices
from .operators import exact, grid, relational, windows
from .operators import blocked as blk
from .plans import cost, estimator, metrics, workloads
from .plans.templates import CATALOGUE, SHAPES, TreeTemplate, automorphisms, partition, plan_frame
from .plans.variants import VARIANTS, Options, count_many, counts, total
from .sources import graphs
from .sources.tables import table
from .storage import brief_shuffles

DECIMAL = Options(cnt_type="decimal")
GRAPHS = ("copart", "custpart", "supppart", "custsupp", "user_next", "hour", "geo", "conv", "pages", "skew3", "skew5", "skew8")
LARGE = ("t10", "t12", "t13", "t14", "t15a", "t15b", "t16", "t17")
SMALL = ("path3", "path4", "star4", "fork5", "path5")


def build(spark: SparkSession, d: str, name: str) -> graphs.Graph:
    return graphs.BUILDERS[name](spark, d)


#: The networks whose sizes the models of costs take.
SIZED = ("supppart", "custsupp")


def sizes(spark: SparkSession, d: str, names=SIZED) -> dict[str, tuple[float, float]]:
    """Vertices and stored edges of some networks."""
    rows = {n: graphs.stats(build(spark, d, n)).first() for n in names}
    return {n: (float(r.vertices), 2.0 * r.edges) for n, r in rows.items()}


def sizes_sql(names=SIZED) -> str:
    """CTE net (graph, v, e)."""
    return "net as (" + " union all ".join(f"select * from (with {sql.graph(n)} select '{n}' as graph, (select count(*) from verts)::double as v, (select count(*) from edges)::double as e)" for n in names) + ")"


def edge_list(name: str):
    return lambda spark, d: build(spark, d, name).edges.where("src < dst")


def colorful(graph: str, template: str, variant: str, options: Options = Options()):
    """The total of the first coloring: in full, or to nine digits where counts are doubles. Where tables are written, the
    network is made once and written too."""

    def run(spark, d):
        g = graphs.settle(build(spark, d, graph), options.policy)
        value = F.format_string("%.8e", "total") if options.cnt_type in ("double", "float") else F.col("total").cast("decimal(38,0)").cast("string")
        return total(g, CATALOGUE[template], variant, options).select(F.lit(template).alias("template"), "it", value.alias("total"))

    return run


def large(graph: str, template: str, variant: str):
    """As :func:`colorful` for templates of ten nodes and more, each of whose tables is made once: relational programs with
    decimals, kernels with doubles."""
    kind = "double" if variant in ("v4", "v5") else "decimal"

    def run(spark, d):
        g = graphs.settle(build(spark, d, graph), "table")
        return colorful_of(g, template, variant, Options(cnt_type=kind, policy="table", fused=True))

    return run


def colorful_of(g: graphs.Graph, template: str, variant: str, options: Options):
    return total(g, CATALOGUE[template], variant, options).select(F.lit(template).alias("template"), "it", F.format_string("%.8e", F.col("total").cast("double")).alias("total"))


def rooted(graph: str, template: str, variant: str = "v3"):
    """Rooted counts of the first coloring."""
    return lambda spark, d: counts(build(spark, d, graph), CATALOGUE[template], variant).select("v", F.col("cnt").cast("long").alias("cnt"))


def exactly(graph: str, name: str):
    """A closed form that reads the edges several times has them settled first; some pack them themselves."""
    policy = "plan" if name in ("path4", "triangles") else "table"
    return lambda spark, d: exact.closed_form(graphs.settle(build(spark, d, graph), policy), name).select(F.col("cnt").cast("string").alias("cnt"))


def graph_stats(spark, d):
    """Each network is built and measured by itself, so that no two of them are on disk for one query."""
    rows, schema = [], None
    with brief_shuffles(spark):
        for n in GRAPHS:
            part = graphs.stats(build(spark, d, n)).select(F.lit(n).alias("graph"), "*")
            schema = part.schema
            rows += map(tuple, part.collect())
    return spark.createDataFrame(rows, schema)


def stats_sql() -> str:
    parts = [f"select * from (with {sql.graph(n)}, deg as (select src, count(*) as d from edges group by 1) select '{n}' as graph, count(*) as vertices, (sum(d) // 2)::bigint as edges, round(avg(d), 4) as avg_degree, max(d) as max_degree, min(d) as min_degree from deg)" for n in GRAPHS]
    return "\nunion all\n".join(parts)


def series(graph: str, template: str, n: int):
    def run(spark, d):
        s = estimator.series(build(spark, d, graph), CATALOGUE[template], n, "v3")
        return s.select("it", F.col("estimate").alias("estimate"))

    return run


def rounded(x, digits: int = 9):
    """A double as text with so many significant digits, the same in both engines."""
    return F.format_string(f"%.{digits - 1}e", x)


def estimate_series(spark, d):
    return series("user_next", "path4", 4)(spark, d).select("it", rounded(F.col("estimate")).alias("estimate"))


def running(spark, d):
    return estimator.running_mean(series("user_next", "path4", 4)(spark, d)).select("it", rounded(F.col("mean")).alias("mean"))


def summary(combine: str):
    def run(spark, d):
        s = series("user_next", "path3", 9)(spark, d)
        return estimator.summary(s, CATALOGUE["path3"], None, combine).select("template", "iterations", rounded(F.col("mean")).alias("mean"))

    return run


SCI = "printf('%.8e', {})"
MEDIAN = sql.estimates("user_next", "path3", 9) + f"\nselect 'path3' as template, 9 as iterations, {SCI.format('median(m)')} as mean from (select avg(estimate) as m from est group by it % 3)"


def neighbor_unit(spark, d):
    g = build(spark, d, "user_next")
    m = relational.leaf_counts(color_vertices(g.vertices, 3))
    return relational.neighbor_sum(g.edges, m).select("v", "mask", "cnt")


def multiply_unit(spark, d):
    g = build(spark, d, "user_next")
    m = relational.leaf_counts(color_vertices(g.vertices, 3))
    return relational.multiply_add(m, relational.neighbor_sum(g.edges, m)).select("v", "mask", "cnt")


def blocked_unit(kernel: str):
    """The neighbour sum of single colors by a kernel on blocks, as long rows."""

    def run(spark, d):
        g = build(spark, d, "user_next")
        m = blk.leaf_blocks(color_vertices(g.vertices, 3), 3, 8, "long")
        if kernel == "grid":
            s = grid.grid_sum(g.edges, m, 3, 4, "long")
        elif kernel == "hubs":
            s = grid.hub_sum(g.edges, m, 3, 60, 20, "long")
        elif kernel == "wide":
            s = blk.neighbor_sum_wide(g.edges, blk.to_wide(m, 3), 3).select("it", "v", "blk", F.array("c0", "c1", "c2").alias("x"))
        else:
            s = blk.neighbor_sum(g.edges, m, 3, "long", kernel == "broadcast")
        return blk.to_relational(s, 3, 1, 3).select("v", "mask", "cnt")

    return run


UNIT = f"with {sql.graph('user_next')},\n{sql.coloring(3)},\nm0 as (select it, v, 1::bigint << color as mask, 1 as cnt from colors),\ns as (select e.src as v, m.mask, sum(m.cnt)::bigint as cnt from edges e join m0 m on e.dst = m.v group by all)"


def order_colors(spark, d, k: int) -> DataFrame:
    """(mask, members, orders): the sets of colors that the parts of orders have, by how many orders."""
    x = table(spark, d, "lineitem", "l_orderkey", "l_partkey").select("l_orderkey", color(F.col("l_partkey"), F.lit(0), k, 42).alias("c"))
    per = x.groupBy("l_orderkey").agg(F.bit_or(relational.bit(F.col("c"))).alias("mask"), F.array_sort(F.collect_set("c")).alias("members"))
    return per.groupBy("mask", "members").agg(F.count("*").alias("orders"))


def order_colors_sql(k: int) -> str:
    """CTE had (mask, orders)."""
    c = f"cast('0x' || substr(md5('42:0:' || l_partkey), 1, 7) as bigint) % {k}"
    return f"had as (select mask, count(*) as orders from (select l_orderkey, bit_or(1::bigint << ({c})::int) as mask from lineitem group by 1) group by 1)"


def catalog(spark, d):
    """All sets of 5 colors by rank, and how many orders have parts of just these colors."""
    out = None
    for h in range(1, 6):
        part = colorsets.catalog(spark, 5, h).select("h", "rank", "mask")
        out = part if out is None else out.union(part)
    return out.join(order_colors(spark, d, 5).select("mask", "orders"), "mask", "left").select("h", "rank", "mask", F.coalesce("orders", F.lit(0)).alias("orders"))


CATALOG_SQL = f"with {order_colors_sql(5)} select bit_count(m)::int as h, (row_number() over (partition by bit_count(m) order by m) - 1)::int as rank, m::bigint as mask, coalesce(orders, 0) as orders from range(1, 32) r(m) left join had on mask = m"


def round_trip(spark, d):
    """Ranks of the sets of 7 colors that parts of orders have, computed by SQL functions from their members, beside the catalog's."""
    out = None
    for h in range(1, 8):
        part = colorsets.catalog(spark, 7, h).select("h", "rank", "mask")
        out = part if out is None else out.union(part)
    had = order_colors(spark, d, 7)
    return out.join(had, "mask").select("h", "rank", colorsets.rank_of(F.col("members"), 7).cast("int").alias("computed"), "orders")


ROUND_TRIP_SQL = f"with {order_colors_sql(7)}, r as (select m, bit_count(m)::int as h, (row_number() over (partition by bit_count(m) order by m) - 1)::int as rank from range(1, 128) r(m)) select h, rank, rank as computed, orders from r join had on mask = m"


def split_catalog(spark, d):
    """All splits of sets of 3 of 5 colors, and how many orders have parts of just the colors of the whole."""
    had = order_colors(spark, d, 5).select(F.col("mask").alias("mask_s"), "orders")
    rows = colorsets.splits(spark, 5, 3, 1)
    return rows.join(had, "mask_s", "left").select(*rows.columns, F.coalesce("orders", F.lit(0)).alias("orders"))


SPLIT_SQL = f"""with {order_colors_sql(5)}, c as (select m::bigint as mask, bit_count(m) as h, (row_number() over (partition by bit_count(m) order by m) - 1)::int as rank from range(1, 32) r(m))
select s.rank as rank_s, a.rank as rank_a, p.rank as rank_p, s.mask as mask_s, a.mask as mask_a, p.mask as mask_p, coalesce(orders, 0) as orders
from c a join c p on a.h = 2 and p.h = 1 and a.mask & p.mask = 0 join c s on s.mask = a.mask | p.mask left join had on had.mask = s.mask"""


def order_sizes(spark, d) -> list[tuple[int, int]]:
    """Numbers of different parts that orders have, and how many orders have so many: the sizes that the counts below are taken at."""
    per = table(spark, d, "lineitem", "l_orderkey", "l_partkey").distinct().groupBy("l_orderkey").agg(F.count("*").alias("k"))
    return sorted(map(tuple, per.groupBy("k").agg(F.count("*").alias("orders")).collect()))


ORDER_SIZES = "had as (select k, count(*) as orders from (select count(distinct l_partkey)::int as k from lineitem group by l_orderkey) group by k)"


def enumerated(graph: str, template: str):
    """Every occurrence in a whole network, laid out by joins."""
    return lambda spark, d: exact.enumerate_count(graphs.settle(build(spark, d, graph), "table"), CATALOGUE[template])


COUNTED = ("path5", "bin7", "t10", "t12")


def operations(spark, d):
    v, e = sizes(spark, d, SIZED[:1])[SIZED[0]]
    return cost.cost_table(spark, [CATALOGUE[t] for t in COUNTED], ("v0", "v1", "v3", "v5"), v, e)


OPERATIONS_SQL = f"""with recursive {sql.parts(COUNTED)},
{sizes_sql(SIZED[:1])}
select template, sub, k, s, a, p, (e * case when variant in ('v0', 'v1') then {sql.SPLIT} else {sql.WALK} end)::double as edge_ops,
(net.v * case variant when 'v0' then 0 when 'v3' then {sql.SPLIT} + {sql.WALK} else {sql.SPLIT} end)::double as vertex_ops, variant from part, net, (values ('v0'), ('v1'), ('v3'), ('v5')) x(variant)"""


def reuse(spark, d):
    """For as many colors as orders have parts."""
    rows = [(k, s, p, cost.reuse_factor(k, s, p), comb(k, p) * cost.reuse_factor(k, s, p), comb(k, s) * comb(s, p), n) for k, n in order_sizes(spark, d) for s in range(2, k + 1) for p in range(1, s)]
    return spark.createDataFrame(rows, "k int, s int, p int, reuse long, walked long, splits long, orders long")


REUSE_SQL = f"""with {ORDER_SIZES}, t as (select k, s::int as s, p::int as p, orders from had, range(2, 34) b(s), range(1, 33) c(p) where s <= k and p < s)
select k, s, p, (factorial(k - p) // (factorial(s - p) * factorial(k - s)))::bigint as reuse,
(factorial(k) // (factorial(p) * factorial(k - p)) * (factorial(k - p) // (factorial(s - p) * factorial(k - s))))::bigint as walked,
(factorial(k) // (factorial(s) * factorial(k - s)) * (factorial(s) // (factorial(p) * factorial(s - p))))::bigint as splits, orders from t"""


def iterations(spark, d):
    """For templates of as many nodes as orders have parts."""
    return spark.createDataFrame([(k, estimator.iterations_for(0.1, 0.1, k), n) for k, n in order_sizes(spark, d)], "k int, iterations long, orders long")


ITERATIONS_SQL = f"with {ORDER_SIZES} select k, ceil(exp(k) * ln(10) / (0.1 * 0.1))::bigint as iterations, orders from had"
CONSTANTS = cost.Constants(2.0, 1.0, 3.0)


def bounds(spark, d):
    rows = []
    for n, (v, e) in sizes(spark, d).items():
        dg = e / v
        rows += [(n, k, dg, *cost.improvement_bounds(k, dg, CONSTANTS), cost.improvement_bounds(k, dg, CONSTANTS, True)[1], CONSTANTS.gamma * dg / CONSTANTS.beta) for k in range(5, 18)]
    return spark.createDataFrame(rows, "graph string, k int, d double, low double, high double, high_printed double, cap double").select("graph", "k", *[rounded(F.col(c)).alias(c) for c in ("d", "low", "high", "high_printed", "cap")])


BOUNDS_SQL = f"""with {sizes_sql()}, x as (select graph, e / v as d from net)
select graph, k::int as k, {', '.join(f"printf('%.8e', {x}) as {n}" for n, x in {
    "d": "d", "low": "3.0::double / (4.0::double / k + 1.0::double / d)", "high": "3.0::double / (2.0::double * sqrt(k) * pow(2.0::double / 3, k) + 1.0::double / d)",
    "high_printed": "3.0::double / (2.0::double * pow(2.0::double / 3, k) + 1.0::double / d)", "cap": "3.0::double * d"}.items())} from range(5, 18) r(k), x"""


def maxima(spark, d):
    """For as many colors as orders have parts."""
    return spark.createDataFrame([(n, *cost.binomial_maxima(n), orders) for n, orders in order_sizes(spark, d)], "n int, one long, two long, three long, orders long")


MAXIMA_SQL = f"""with {ORDER_SIZES}, c as (select n, m, orders, (factorial(n) // (factorial(m) * factorial(n - m)))::hugeint as one, (factorial(m) // (factorial(m // 2) * factorial(m - m // 2)))::hugeint as inner_max from (select k as n, orders from had), (select m::int as m from range(0, 34) b(m)) where m <= n)
select n::int as n, max(one)::bigint as one, max(one * inner_max)::bigint as two, sum(one * inner_max)::bigint as three, orders from c group by n, orders"""


def memory(spark, d):
    return workloads.memory_table(spark, {n: v for n, (v, _) in sizes(spark, d).items()}, LARGE, 4).select("graph", "template", "k", "widest")


MEMORY_SQL = f"""with recursive {sql.parts(LARGE)},
{sizes_sql()}
select graph, template, k, max({sql.choose('k', 's')}) * v * 4 as widest from part, net group by graph, template, k, v"""
MODEL = cost.Constants(2e-9, 1e-9, 4e-9)


def model(spark, d):
    """What the cost models say of the large templates, to seven digits."""
    out = None
    for n, (v, e) in sizes(spark, d).items():
        rows = cost.model_table(spark, [CATALOGUE[t] for t in LARGE], [e / v], MODEL, v)
        part = rows.select(F.lit(n).alias("graph"), "template", "k", rounded(F.col("d"), 7).alias("d"), "splits", "walked", *[rounded(F.col(c), 7).alias(c) for c in rows.columns[5:]])
        out = part if out is None else out.union(part)
    return out


MODEL_SQL = f"""with recursive {sql.parts(LARGE)},
{sizes_sql()},
f as (select template, k, sum({sql.SPLIT})::bigint as splits, sum({sql.WALK})::bigint as walked from part group by all),
m as (select f.*, graph, v, e, e / v as d, k * pow(2.0::double, k - 1) as splits_low, pow(3.0::double, k) / sqrt(k::double) as splits_high from f, net)
select graph, template, k, printf('%.6e', d) as d, splits, walked, {', '.join(f"printf('%.6e', {x}) as {n}" for n, x in {
    "splits_low": "splits_low", "splits_high": "splits_high", "baseline_growth": "e * splits_high", "kernel_growth": "e * pow(2.0::double, k) + v * splits_high",
    "baseline_s": "4e-9::double * e * splits", "kernel_s": "2e-9::double * e * walked + 1e-9::double * v * splits", "low": "4e-9::double / (2 * 2e-9::double / k + 1e-9::double / d)",
    "improvement": "4e-9::double / (2e-9::double * pow(2.0::double, k) / splits + 1e-9::double / d)", "high": "4e-9::double / (2e-9::double * sqrt(k::double) * pow(2.0::double / 3, k) + 1e-9::double / d)"}.items())} from m"""


def run_bounds(spark, d):
    v, e = sizes(spark, d, SIZED[:1])[SIZED[0]]
    rows = cost.bound_table(spark, list(range(3, 18)), 0.1, 0.05, v, e)
    return rows.select("k", "variant", rounded(F.col("iteration"), 7).alias("iteration"), rounded(F.col("whole"), 7).alias("whole"))


RUN_BOUNDS_SQL = f"""with {sizes_sql(SIZED[:1])},
b as (select k::int as k, variant, case variant when 'v0' then e * pow(3.0::double, k) / sqrt(k::double) else e * pow(2.0::double, k) + v * pow(3.0::double, k) / sqrt(k::double) end as one from net, range(3, 18) r(k), (values ('v0'), ('v5')) x(variant))
select k, variant, printf('%.6e', one) as iteration, printf('%.6e', one * exp(k::double) * ln(20.0::double) / 0.01::double) as whole from b"""


def plans(spark, d):
    """The different shapes of the partition of all templates of the catalogue."""
    out = None
    for n, t in CATALOGUE.items():
        part = plan_frame(spark, partition(t)).where("active is not null").select(F.lit(n).alias("template"), "sub", "size", "active", "passive")
        out = part if out is None else out.union(part)
    return out


PLANS_SQL = f"with recursive {sql.parts(tuple(SHAPES))} select template, sub, s as size, active, passive from part"


def order_trees(spark, d) -> DataFrame:
    """(tree, orders): the trees that orders make, by how many orders. An order is node 0 and its line items, by part and then
    line number, are the next nodes; one hangs on the earlier node that its part's number falls on modulo their number. tree is
    the nodes' parents after node 0."""
    x = table(spark, d, "lineitem", "l_orderkey", "l_partkey", "l_linenumber").where("l_orderkey is not null and l_partkey is not null")
    parts = x.groupBy("l_orderkey").agg(F.array_sort(F.collect_list(F.struct("l_partkey", "l_linenumber"))).alias("x"))
    tree = F.array_join(F.transform("x", lambda e, i: F.pmod(e["l_partkey"], i + 1).cast("string")), ",")
    return parts.groupBy(tree.alias("tree")).agg(F.count("*").alias("orders"))


def symmetries(spark, d):
    """Symmetries of the trees that orders make."""

    def run(batches):
        for f in batches:
            trees = [TreeTemplate((-1, *map(int, t.split(",")))) for t in f["tree"]]
            yield f.assign(k=[t.size for t in trees], automorphisms=[automorphisms(t) for t in trees])[["tree", "k", "automorphisms", "orders"]]

    return order_trees(spark, d).mapInPandas(run, "tree string, k int, automorphisms long, orders long")


ORDER_TREES_SQL = """had as (select tree, count(*) as orders from (
  select l_orderkey, string_agg(p, ',' order by i) as tree from (
    select l_orderkey, i, (l_partkey % i)::varchar as p from (
      select l_orderkey, l_partkey, row_number() over (partition by l_orderkey order by l_partkey, l_linenumber) as i from lineitem where l_orderkey is not null and l_partkey is not null))
  group by 1) group by 1)"""
#: Symmetries counted by laying each tree's nodes, one after the other, on its own nodes along its edges.
SYMMETRIES_SQL = f"""with recursive {ORDER_TREES_SQL},
kind as (select tree, orders, [-1] || string_split(tree, ',')::int[] as parents from had),
size as (select *, len(parents) as k from kind),
laid as (
  select tree, k, parents, 0 as node, [r.a] as image from size, range(0, 64) r(a) where r.a < k
  union all
  select l.tree, l.k, l.parents, l.node + 1, list_append(l.image, e.b) from laid l, range(0, 64) e(b)
  where l.node + 1 < l.k and e.b < l.k and (l.parents[e.b + 1] = l.image[l.parents[l.node + 2] + 1] or l.parents[l.image[l.parents[l.node + 2] + 1] + 1] = e.b) and not list_contains(l.image, e.b))
select tree, k::int as k, count(*) as automorphisms, any_value(orders) as orders from laid join had using (tree) where node = k - 1 group by tree, k"""


def variants_agree(spark, d):
    """Rooted counts of path5 by each program against the baseline's, cell by cell: cells, those that differ, their sum."""
    g = graphs.settle(build(spark, d, "user_next"), "table")
    base, out = counts(g, CATALOGUE["path5"], "v0"), None
    for v in VARIANTS:
        other = counts(g, CATALOGUE["path5"], v)
        error = metrics.relative_error(other, base, ["it", "v"], "cnt").agg(F.count("*").alias("cells"), F.count_if(F.col("rel_error") > 0).alias("differ"))
        part = other.agg(F.sum("cnt").alias("total")).crossJoin(error).select(F.lit(v).alias("variant"), "cells", "differ", "total")
        out = part if out is None else out.union(part)
    return out


def estimate_errors(spark, d):
    """How far eight estimates of each template lie from its exact count, to six digits."""
    g, out = graphs.settle(build(spark, d, "user_next"), "table"), None
    for t in ("path3", "path4", "star4"):
        true = float(exact.closed_form(g, t).first()[0])
        part = metrics.estimate_error(estimator.series(g, CATALOGUE[t], 8, "v3"), true).select(F.lit(t).alias("template"), "it", rounded(F.col("rel_error"), 6).alias("rel_error"))
        out = part if out is None else out.union(part)
    return out


def failures(spark, d):
    """The share of 16 estimates of path4 that miss the exact count by more than eps."""
    g = graphs.settle(build(spark, d, "user_next"), "table")
    true = float(exact.closed_form(g, "path4").first()[0])
    s, out = estimator.series(g, CATALOGUE["path4"], 16, "v3"), None
    for eps in (0.001, 0.005, 0.01, 0.05):
        part = metrics.failure_rate(s, true, eps).select(F.lit(eps).alias("eps"), "runs", "failure_rate")
        out = part if out is None else out.union(part)
    return out


def errors_sql(template: str, n: int) -> str:
    """One row for each estimate: it, rel_error."""
    return f"select it, abs(estimate - x) / x as rel_error from ({sql.estimates('user_next', template, n)} select * from est), (select cnt::hugeint::double as x from ({sql.closed_form('user_next', template)}))"


def stopped(spark, d):
    """Estimates of path4, four at a time, until the relative standard error is below half a percent."""
    g = graphs.settle(build(spark, d, "user_next"), "table")
    mean, _, n = estimator.estimate(g, CATALOGUE["path4"], 0.005, 32, 4, "v3")
    return spark.createDataFrame([(n, mean)], "iterations int, mean double").select("iterations", rounded(F.col("mean")).alias("mean"))


STOPPED_SQL = sql.estimates("user_next", "path4", 32) + """,
w as (select it + 1 as n, avg(estimate) over o as mean, stddev_samp(estimate) over o / sqrt(it + 1) as err from est window o as (order by it))
select n::int as iterations, printf('%.8e', mean) as mean from w where n % 4 = 0 and (err <= 0.005 * mean or n = 32) order by n limit 1"""

RUN = ("graph", "template", "variant", "vertices", "edges", "total", "edge_ops", "vertex_ops")
GROWING = ("path3", "path5", "bin7", "t10", "t12")
DEGREES = ("geo", "custpart", "supppart", "copart")
PRUNED = ("geo", "supppart", "user_next", "copart")
LEAST = "(select min(n) from (" + " union all ".join(f"select count(*) as n from (with {sql.graph(n)} select * from one)" for n in ("skew3", "skew5", "skew8")) + "))"


def stripped(make):
    """An experiment without its seconds, which no other engine can repeat."""
    return lambda spark, d: make(spark, d).select(*RUN)


def speedups(spark, d):
    """How many times fewer edge touches and operations each program has than the baseline, from runs of it."""
    runs = workloads.run_matrix(spark, d, ("user_next",), ("path4", "path5", "spider6"), ("v0", "v3", "v5"))
    touches = metrics.speedup(runs.withColumn("seconds", F.col("edge_ops"))).withColumnRenamed("speedup", "fewer_touches")
    return touches.select("graph", "template", "variant", rounded(F.col("fewer_touches")).alias("fewer_touches"))


SPEEDUP_SQL = f"""with r as ({sql.experiment({'user_next': sql.graph('user_next')}, ('path4', 'path5', 'spider6'), ('v0', 'v3', 'v5'))})
select a.graph, a.template, a.variant, printf('%.8e', b.edge_ops / a.edge_ops) as fewer_touches from r a join r b on a.graph = b.graph and a.template = b.template and b.variant = 'v0'"""


def totals_of(spark, d, kind: str):
    """Edge touches of runs of three templates: rolled up, or with the programs side by side."""
    runs = workloads.run_matrix(spark, d, ("user_next", "geo"), ("path4", "star4"), ("v0", "v3", "v5")).withColumn("seconds", F.col("edge_ops"))
    if kind == "rollup":
        return workloads.rollup(runs).withColumnRenamed("seconds", "edge_ops")
    if kind == "cube":
        return runs.cube("graph", "variant").agg(F.sum("edge_ops").alias("edge_ops"), F.grouping_id().cast("int").alias("level"))
    return metrics.pivoted(runs, ["v0", "v3", "v5"])


TOTALS_SQL = f"""with r as ({sql.experiment({n: sql.graph(n) for n in ('user_next', 'geo')}, ('path4', 'star4'), ('v0', 'v3', 'v5'))})"""


def fitted_line(spark, d):
    """A straight line through degrees and rooted counts of path3, and how well it fits: regression aggregates."""
    g = graphs.settle(build(spark, d, "user_next"), "table")
    deg = g.edges.groupBy(F.col("src").alias("v")).agg(F.count("*").cast("double").alias("x"))
    both = counts(g, CATALOGUE["path3"], "v3").join(deg, "v").withColumn("y", F.col("cnt").cast("double"))
    return both.agg(*[rounded(f("y", "x"), 6).alias(n) for n, f in (("slope", F.regr_slope), ("intercept", F.regr_intercept), ("r2", F.regr_r2), ("corr", F.corr))], F.count("*").alias("n"))


def rounding(spark, d):
    """Exact totals by template size, and whether float and double kernels stay within their rounding of them."""
    rows = workloads.rounding(spark, d)
    limit = F.when(F.col("cnt_type") == "float", 1e-5).otherwise(1e-12)
    return rows.select("template", "k", "cnt_type", rounded(F.col("total").cast("double")).alias("total"), (F.col("rel_error") <= limit).alias("within"))


ROUNDED = ("path5", "spider6", "bin7", "t10", "t12")
ROUNDING_SQL = "\nunion all\n".join(f"select '{t}' as template, {len(SHAPES[t])} as k, cnt_type, total, true as within from ({sql.total('user_next', t, digits=False)}), (values ('float'), ('double')) c(cnt_type)" for t in ROUNDED)


def kernels(spark, d):
    return workloads.vectorisation(spark, d).select("template", "variant", "width", "impl", "total")


KERNELS_SQL = f"select template, variant, width, impl, total from ({sql.total('user_next', 'path5')}), (select 'v3' as variant, 0 as width, '' as impl union all select 'v4', 1, 'arrow' union all select 'v5', w, i from (values (8), (16), (64), (128), (256)) a(w), (values ('arrow'), ('expr'), ('hof')) b(i))"


def skewed_runs(spark, d):
    return workloads.skew(spark, d).select(*RUN, "avg_degree", "max_degree")


def skewed_sql() -> str:
    names = ("skew3", "skew5", "skew8")
    runs = sql.experiment({n: sql.sampled(n, LEAST) for n in names}, ("path4",), ("v0", "v3", "v5"))
    degrees = " union all ".join(f"select '{n}' as graph, * from (with {sql.sampled(n, LEAST)} select round(avg(d), 4) as avg_degree, max(d) as max_degree from (select count(*) as d from edges group by src))" for n in names)
    return f"select r.*, avg_degree, max_degree from ({runs}) r join ({degrees}) g on g.graph = r.graph"


def predicted(spark, d):
    """Constants fitted to runs on two networks, predicted beside measured seconds, and the speedup the models promise for the largest template."""
    runs = workloads.run_matrix(spark, d, ("user_next", "copart"), ("path4", "path5", "spider6"), ("v0", "v5"), Options(cnt_type="double", policy="table", fused=True))
    c, rows = workloads.fitted(runs)
    far = workloads.headline(spark, c)
    return rows.select("graph", "template", "variant", "seconds", "predicted").crossJoin(far.select(F.col("speedup").alias("t17_speedup")))


def spectrum(spark, d):
    return workloads.motif_spectrum(build(spark, d, "user_next")).select("template", rounded(F.col("estimate")).alias("estimate"))


def spectrum_sql() -> str:
    heads = [sql.graph("user_next"), sql.coloring(5)]
    tails = []
    for i, t in enumerate(("path5", "fork5", "star5")):
        body, last = sql.program(t, prefix=f"t{i}_")
        heads.append(body)
        tails.append(f"select '{t}' as template, {SCI.format(f'sum(cnt)::double * {sql.scale(t)!r}')} as estimate from {last}")
    return "with " + ",\n".join(heads) + "\n" + "\nunion all\n".join(tails)


def many(spark, d):
    return count_many(build(spark, d, "user_next"), [CATALOGUE[t] for t in ("path4", "star4")]).select("template", "it", F.col("total").cast("string").alias("total"))


def events(spark, d):
    return table(spark, d, "events", "event_id", "ts", "user_id", "event_type")


def edge_difference(spark, d):
    g = build(spark, d, "user_next")
    return graphs.edge_diff(build(spark, d, "hour"), g)


def isolated(spark, d):
    all_parts = table(spark, d, "part", "p_partkey").select((2 * F.col("p_partkey") + 1).alias("v"))
    return graphs.isolated(build(spark, d, "custpart"), all_parts)


def induced(spark, d):
    c = table(spark, d, "customer", "c_custkey", "c_mktsegment").where("c_mktsegment = 'BUILDING'").select((2 * F.col("c_custkey")).alias("v"))
    p = table(spark, d, "part", "p_partkey", "p_size").where("p_size between 1 and 10").select((2 * F.col("p_partkey") + 1).alias("v"))
    return graphs.induced(build(spark, d, "custpart"), c.union(p)).edges


def reordered(spark, d):
    """The new id of each vertex by descending degree."""
    return graphs.reorder(build(spark, d, "user_next"), "degree")[1]


def queries() -> dict:
    out = {f"graph_{n}": edge_list(n) for n in GRAPHS}
    out |= {"graph_knn": edge_list("knn"), "graph_doc_shingles": edge_list("doc_shingles"), "graph_stats": graph_stats}
    out["degree_histogram"] = lambda spark, d: graphs.degree_histogram(build(spark, d, "skew5"))
    out |= {"coloring": lambda spark, d: color_vertices(build(spark, d, "user_next").vertices, 5, 42, (0, 1)), "color_catalog": catalog, "split_catalog": split_catalog, "rank_roundtrip": round_trip}
    out |= {"template_plans": plans, "template_automorphisms": symmetries}
    out |= {"neighbor_sum_unit": neighbor_unit, "multiply_add_unit": multiply_unit}
    out |= {f"neighbor_sum_{n}": blocked_unit(n) for n in ("blocked", "broadcast", "grid", "hubs", "wide")}
    for t in SMALL:
        for v in VARIANTS:
            out[f"colorful_{t}_{v}"] = colorful("user_next", t, v)
    for v in ("v2", "v3", "v5"):
        out[f"colorful_spider6_{v}"] = colorful("user_next", "spider6", v)
        out[f"colorful_bin7_{v}"] = colorful("copart", "bin7", v, Options(policy="table", fused=True) if v == "v2" else Options())
    for impl in ("expr", "hof"):
        out[f"colorful_path5_v5_{impl}"] = colorful("user_next", "path5", "v5", Options(impl=impl, width=4))
    for s in ("grid", "hubs", "broadcast"):
        out[f"colorful_path4_v5_{s}"] = colorful("user_next", "path4", "v5", Options(strategy=s))
    out["colorful_path5mid_unshared"] = colorful("user_next", "path5mid", "v3", Options(share=False, cut="smallest"))
    out["colorful_star4_decimal"] = colorful("custpart", "star4", "v3", DECIMAL)
    out |= {"rooted_counts_path3": rooted("user_next", "path3"), "rooted_counts_star4": rooted("user_next", "star4", "v5"), "rooted_counts_copart": rooted("copart", "path4", "v5"), "variants_agree": variants_agree}
    out |= {"estimate_series": estimate_series, "running_mean": running, "estimate_path3": summary("mean"), "mom": summary("median_of_means"), "iterations_for": iterations}
    for n in ("path3", "star4", "star5", "path4", "triangles"):
        out[f"exact_{n}"] = exactly("copart", n)
    out |= {"exact_path3_skew": exactly("skew8", "path3"), "exact_path4_geo": exactly("geo", "path4"), "exact_enum_fork5": enumerated("geo", "fork5"), "exact_enum_path4": enumerated("geo", "path4"), "exact_fork5": exactly("user_next", "fork5")}
    out |= {"ops_by_variant": operations, "reuse_factor": reuse, "lemma_maxima": maxima, "improvement_bounds": bounds, "memory_table": memory, "cost_model": model, "run_bounds": run_bounds}
    out |= {"motif_spectrum": spectrum, "count_many": many, "top_rooted": lambda spark, d: workloads.top_rooted(build(spark, d, "user_next"), "path4")}
    out |= {"rank_rooted": lambda spark, d: windows.rank_rooted(counts(build(spark, d, "user_next"), CATALOGUE["path3"], "v3")).select("v", "cnt", "rank")}
    out |= {"induced_subgraph": induced, "edge_diff": edge_difference, "common_edges": lambda spark, d: graphs.common_edges(build(spark, d, "hour"), build(spark, d, "user_next")), "isolated": isolated, "reorder_degree": reordered}
    out |= {"window_edges": lambda spark, d: windows.window_edges(events(spark, d), "1 hour"), "near_pairs": lambda spark, d: windows.near_pairs(events(spark, d), 60), "session_users": lambda spark, d: windows.sessions(events(spark, d)).select("user_id", "session", "events"), "last_before": lambda spark, d: windows.last_before(events(spark, d), "purchase", "click")}
    out |= {f"colorful_{t}_{v}": large("user_next", t, v) for t in LARGE[:3] for v in ("v3", "v5")}
    out |= {f"colorful_{t}_v5": large("user_next", t, "v5") for t in LARGE[3:]}
    out |= {"rooted_counts_t10": rooted("user_next", "t10", "v5"), "estimate_errors": estimate_errors, "failure_rate": failures, "early_stop": stopped, "degree_fit": fitted_line}
    out |= {"growing_templates": stripped(workloads.growing_templates), "size_scaling": stripped(workloads.size_scaling), "rising_skew": skewed_runs, "degree_effect": lambda spark, d: workloads.degree_effect(spark, d).select(*RUN, "avg_degree")}
    out |= {"pruning_steps": stripped(lambda spark, d: workloads.pruning(spark, d, PRUNED)), "kernel_variants": kernels, "rounding_by_size": rounding, "speedup_report": speedups}
    out |= {f"{n}_report": lambda spark, d, n=n: totals_of(spark, d, n) for n in ("rollup", "cube", "pivot")}
    out |= {"kernel_split": workloads.kernel_split, "roofline": workloads.roofline_run, "model_fit": predicted}
    return out


def oracle_sql() -> dict[str, str]:
    out = {f"graph_{n}": f"with {sql.graph(n)} select src, dst from edges where src < dst" for n in GRAPHS}
    out |= {"graph_stats": stats_sql()}
    out["degree_histogram"] = f"with {sql.graph('skew5')}, deg as (select src, count(*) as d from edges group by 1) select floor(log2(d))::int as bin, count(*) as vertices from deg group by 1"
    out |= {"coloring": f"with {sql.graph('user_next')}, {sql.coloring(5, 42, 2)} select * from colors", "color_catalog": CATALOG_SQL, "split_catalog": SPLIT_SQL, "rank_roundtrip": ROUND_TRIP_SQL}
    out |= {"template_automorphisms": SYMMETRIES_SQL, "template_plans": PLANS_SQL}
    out |= {"neighbor_sum_unit": UNIT + "\nselect v, mask, cnt from s", "multiply_add_unit": UNIT + "\nselect x.v, x.mask | y.mask as mask, sum(x.cnt * y.cnt)::bigint as cnt from m0 x join s y on x.v = y.v and x.mask & y.mask = 0 group by 1, 2"}
    out |= {f"neighbor_sum_{n}": UNIT + "\nselect v, mask, cnt from s" for n in ("blocked", "broadcast", "grid", "hubs", "wide")}
    for t in SMALL:
        for v in VARIANTS:
            out[f"colorful_{t}_{v}"] = sql.total("user_next", t)
    for v in ("v2", "v3", "v5"):
        out[f"colorful_spider6_{v}"] = sql.total("user_next", "spider6")
        out[f"colorful_bin7_{v}"] = sql.total("copart", "bin7")
    for impl in ("expr", "hof"):
        out[f"colorful_path5_v5_{impl}"] = sql.total("user_next", "path5")
    for s in ("grid", "hubs", "broadcast"):
        out[f"colorful_path4_v5_{s}"] = sql.total("user_next", "path4")
    out["colorful_path5mid_unshared"] = sql.total("user_next", "path5mid")
    out["colorful_star4_decimal"] = sql.total("custpart", "star4")
    out |= {"rooted_counts_path3": sql.rooted("user_next", "path3"), "rooted_counts_star4": sql.rooted("user_next", "star4"), "rooted_counts_copart": sql.rooted("copart", "path4"), "variants_agree": f"select variant, cells, differ, total from (select count(*) as cells, 0::bigint as differ, sum(cnt)::bigint as total from ({sql.rooted('user_next', 'path5')})), (values {', '.join(f"('{v}')" for v in VARIANTS)}) v(variant)"}
    est = sql.estimates("user_next", "path4", 4)
    out |= {"estimate_series": est + f"\nselect it, {SCI.format('estimate')} as estimate from est", "running_mean": est + f"\nselect it, {SCI.format('avg(estimate) over (order by it)')} as mean from est"}
    out |= {"estimate_path3": sql.estimates("user_next", "path3", 9) + f"\nselect 'path3' as template, 9 as iterations, {SCI.format('avg(estimate)')} as mean from est", "mom": MEDIAN, "iterations_for": ITERATIONS_SQL}
    for n in ("path3", "star4", "star5", "path4", "triangles"):
        out[f"exact_{n}"] = sql.closed_form("copart", n)
    out |= {"exact_path3_skew": sql.closed_form("skew8", "path3"), "exact_path4_geo": sql.closed_form("geo", "path4"), "exact_fork5": sql.closed_form("user_next", "fork5"), "exact_enum_fork5": sql.fork5_brute("geo"), "exact_enum_path4": f"select cnt::bigint as cnt from ({sql.closed_form('geo', 'path4')})"}
    out |= {"ops_by_variant": OPERATIONS_SQL, "reuse_factor": REUSE_SQL, "lemma_maxima": MAXIMA_SQL, "improvement_bounds": BOUNDS_SQL, "memory_table": MEMORY_SQL, "cost_model": MODEL_SQL, "run_bounds": RUN_BOUNDS_SQL}
    head, last = sql.whole("user_next", "path4", root=0)
    out |= {"motif_spectrum": spectrum_sql(), "count_many": f"select * from ({sql.total('user_next', 'path4')}) union all select * from ({sql.total('user_next', 'star4')})", "top_rooted": f"{head}\nselect v, cnt::bigint as cnt from {last} order by cnt desc, v limit 10"}
    head, last = sql.whole("user_next", "path3", root=0)
    out |= {"rank_rooted": f"{head}\nselect v, cnt::bigint as cnt, rank() over (order by cnt desc) as rank from {last}"}
    some = "picked as (select 2 * c_custkey as v from customer where c_mktsegment = 'BUILDING' union all select 2 * p_partkey + 1 from part where p_size between 1 and 10)"
    out |= {"induced_subgraph": f"with {sql.graph('custpart')}, {some} select src, dst from edges where src in (select v from picked) and dst in (select v from picked)"}
    two = f"with a as (with {sql.graph('hour')} select src, dst from edges), b as (with {sql.graph('user_next')} select src, dst from edges)"
    out |= {"edge_diff": f"{two} select * from a where src < dst except select * from b", "common_edges": f"{two} select * from a intersect select * from b"}
    out |= {"isolated": f"with {sql.graph('custpart')} select 2 * p_partkey + 1 as v from part where 2 * p_partkey + 1 not in (select v from verts)"}
    out |= {"reorder_degree": f"with {sql.graph('user_next')}, deg as (select src as v, count(*) as d from edges group by 1) select v, row_number() over (order by d desc, v) - 1 as id from deg"}
    out |= {"window_edges": "with s as (select distinct date_trunc('hour', ts) as start, user_id from events) select x.start, x.user_id as src, y.user_id as dst from s x join s y on x.start = y.start and x.user_id < y.user_id"}
    out |= {"near_pairs": "select distinct least(x.user_id, y.user_id) as src, greatest(x.user_id, y.user_id) as dst from events x join events y on x.event_type = y.event_type and x.user_id <> y.user_id and y.ts between x.ts - interval 60 second and x.ts + interval 60 second"}
    out |= {"session_users": "with g as (select user_id, ts, event_id, case when ts - lag(ts) over w > interval 1800 second or lag(ts) over w is null then 1 else 0 end as n from events window w as (partition by user_id order by ts, event_id)), s as (select user_id, sum(n) over (partition by user_id order by ts, event_id)::bigint as session from g) select user_id, session, count(*) as events from s group by all"}
    out |= {"last_before": "with b as (select *, last_value(case when event_type = 'click' then event_id end ignore nulls) over (partition by user_id order by ts, event_id rows between unbounded preceding and 1 preceding) as prior from events where event_type in ('purchase', 'click')) select event_id, user_id, prior from b where event_type = 'purchase'"}
    for t in LARGE:
        for v in ("v3", "v5") if t in LARGE[:3] else ("v5",):
            out[f"colorful_{t}_{v}"] = sql.total("user_next", t, digits=False)
    out |= {"rooted_counts_t10": sql.rooted("user_next", "t10")}
    out |= {"estimate_errors": "\nunion all\n".join(f"select '{t}' as template, it, printf('%.5e', rel_error) as rel_error from ({errors_sql(t, 8)})" for t in ("path3", "path4", "star4"))}
    out |= {"failure_rate": f"select eps, count(*) as runs, avg((rel_error > eps)::int::double) as failure_rate from ({errors_sql('path4', 16)}), (values (0.001::double), (0.005), (0.01), (0.05)) e(eps) group by eps", "early_stop": STOPPED_SQL}
    head, last = sql.whole("user_next", "path3", root=0)
    out |= {"degree_fit": f"{head}, deg as (select src as v, count(*)::double as x from edges group by 1), xy as (select x, cnt::double as y from {last} join deg using (v)) select " + ", ".join(f"printf('%.5e', {f}(y, x)) as {n}" for n, f in (("slope", "regr_slope"), ("intercept", "regr_intercept"), ("r2", "regr_r2"), ("corr", "corr"))) + ", count(*) as n from xy"}
    out |= {"growing_templates": sql.experiment({"user_next": sql.graph("user_next")}, GROWING, ("v0", "v3", "v5"), digits=False), "size_scaling": sql.experiment({f"custpartx{n}": sql.copied("custpart", n) for n in (1, 2, 4)}, ("path4",), ("v0", "v3", "v5")), "rising_skew": skewed_sql()}
    out |= {"degree_effect": f"select *, round(edges / vertices, 4) as avg_degree from ({sql.experiment({n: sql.graph(n) for n in DEGREES}, ('path4',), ('v0', 'v5'))})", "pruning_steps": sql.experiment({n: sql.graph(n) for n in PRUNED}, ("path4",), ("v0", "v1", "v2", "v3"))}
    out |= {"kernel_variants": KERNELS_SQL, "rounding_by_size": ROUNDING_SQL, "speedup_report": SPEEDUP_SQL}
    out |= {"rollup_report": f"{TOTALS_SQL} select graph, template, variant, sum(edge_ops) as edge_ops, count(*) as runs from r group by rollup(graph, template, variant)", "cube_report": f"{TOTALS_SQL} select graph, variant, sum(edge_ops) as edge_ops, grouping_id(graph, variant)::int as level from r group by cube(graph, variant)"}
    out |= {"pivot_report": f"{TOTALS_SQL} select graph, template, " + ", ".join(f"min(edge_ops) filter (variant = '{v}') as {v}" for v in ("v0", "v3", "v5")) + " from r group by all"}
    out |= {n: f"with {sql.graph(g)} select src, dst from edges where src < dst" for n, g in (("graph_knn", "knn"), ("graph_doc_shingles", "doc_shingles"))}
    return out


def entry(spark: SparkSession, d: str) -> DataFrame:
    """Rooted counts of path3 by the batched kernels, with the estimate that each vertex contributes."""
    g = build(spark, d, "user_next")
    t = CATALOGUE["path3"]
    return counts(g, t, "v5").select("v", "cnt", (F.col("cnt") * estimator.factor(t)).alias("estimate"))
