"""The experiments, as lists of runs and the tables made of them."""

from __future__ import annotations

import time
from collections.abc import Iterable
from math import comb

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import blocked
from ..operators.relational import total_of
from ..sources.graphs import BUILDERS, Graph, copies, sample_edges, settle, stats
from ..storage import settle as keep_table
from . import cost, metrics
from .estimator import factor
from .templates import CATALOGUE, partition
from .variants import Options, count_many, counts, prepare, start, tables, traverse

TIMING = "graph string, template string, variant string, vertices long, edges long, total string, edge_ops double, vertex_ops double, flops double, seconds double"


def timed(graph: Graph, template: str, variant: str, options: Options) -> tuple[float, float]:
    """Seconds of one run and its total for the first coloring; whatever the run kept in memory goes with it."""
    prepare(graph, CATALOGUE[template], variant, options)
    began = time.perf_counter()
    run, (key,) = tables(graph, CATALOGUE[template], variant, options)
    m = run.tables[key]
    cell = F.get("x", F.lit(0)) if "x" in m.columns else F.col("cnt")
    row = m.where(F.col("it") == options.iterations[0]).agg(total_of(cell, options.cnt_type).alias("total")).first()
    seconds = time.perf_counter() - began
    for kept in run.kept:
        kept.unpersist()
    return seconds, row.total or 0


def text_of(value) -> str:
    """Whole numbers in full, others to nine digits."""
    return f"{value:.8e}" if isinstance(value, float) else str(int(value))


def run_matrix(spark: SparkSession, sf_dir: str, graphs: Iterable[str], templates: Iterable[str], variants: Iterable[str], options: Options = Options(), repeat: int = 1) -> DataFrame:
    """Each graph, template and variant, all of them: the total, the operations that the model counts, and seconds (the best of ``repeat``)."""
    rows = []
    for name in graphs:
        rows += measure(name, settle(BUILDERS[name](spark, sf_dir), "table"), templates, variants, options, repeat)
    return spark.createDataFrame(rows, TIMING)


def measure(name: str, g: Graph, templates, variants, options: Options, repeat: int = 1) -> list[tuple]:
    """Rows of :func:`run_matrix` for one network."""
    rows, n = [], g.vertices.count()
    for variant in variants:
        for t in sorted(templates, key=lambda x: CATALOGUE[x].size):
            seconds, total = min(timed(g, t, variant, options) for _ in range(repeat))
            steps = [cost.subtemplate_ops(variant, CATALOGUE[t].size, s.size, s.passive_size, n, g.rows) for s in partition(CATALOGUE[t]) if s.active]
            e, v = (float(sum(x[i] for x in steps)) for i in range(2))
            rows.append((name, t, variant, n, g.rows, text_of(total), e, v, e + 2 * v, seconds))
    return rows


def growing_templates(spark, d, graphs=("user_next",), templates=("path3", "path5", "bin7", "t10", "t12"), **kw) -> DataFrame:
    """Three programs, growing templates, each table made once."""
    return run_matrix(spark, d, graphs, templates, ("v0", "v3", "v5"), **{"options": Options(cnt_type="double", policy="table", fused=True), **kw})


def size_scaling(spark, d, graph: str = "custpart", sizes=(1, 2, 4), template: str = "path4", options: Options = Options(policy="table", fused=True)) -> DataFrame:
    """The same network once, twice and four times over: larger, at equal average degree."""
    rows, once = [], settle(BUILDERS[graph](spark, d), "table")
    for n in sizes:
        rows += measure(f"{graph}x{n}", once if n == 1 else settle(copies(once, n), "table"), (template,), ("v0", "v3", "v5"), options)
    return spark.createDataFrame(rows, TIMING)


def skew(spark, d, template: str = "path4", options: Options = Options(policy="table", fused=True)) -> DataFrame:
    """Rising skew at the edge count of the network that has fewest, since skew also merges repeated draws; with degrees and balance beside the totals."""
    names = ("skew3", "skew5", "skew8")
    gs = {n: settle(BUILDERS[n](spark, d), "table") for n in names}
    least = min(g.rows for g in gs.values()) // 2
    out = None
    for n, g in gs.items():
        g = settle(sample_edges(g, least), "table")
        part = spark.createDataFrame(measure(n, g, (template,), ("v0", "v3", "v5"), options), TIMING).crossJoin(stats(g).select("avg_degree", "max_degree"))
        out = part if out is None else out.unionByName(part)
    return out


def degree_effect(spark, d, template: str = "path4", options: Options = Options(policy="table", fused=True)) -> DataFrame:
    """Networks of rising average degree, and how many times fewer edge touches the kernels have there."""
    runs = run_matrix(spark, d, ("geo", "custpart", "supppart", "copart"), (template,), ("v0", "v5"), options)
    return runs.withColumn("avg_degree", F.round(F.col("edges") / F.col("vertices"), 4))


def pruning(spark, d, graphs=("geo", "custpart", "supppart", "custsupp", "user_next", "copart"), templates=("path4",), options: Options = Options(policy="table", fused=True)) -> DataFrame:
    """The steps of pruning by themselves."""
    return run_matrix(spark, d, graphs, templates, ("v0", "v1", "v2", "v3"), options)


def vectorisation(spark, d, graph: str = "user_next", template: str = "path5", widths=(8, 16, 64, 128, 256), impls=("arrow", "expr", "hof")) -> DataFrame:
    """Pruned against column and batched kernels, by batch width and form of the multiply-add."""
    g = settle(BUILDERS[graph](spark, d), "table")
    runs = [("v3", 0, "", Options()), ("v4", 1, "arrow", Options())]
    runs += [("v5", w, i, Options(width=w, impl=i)) for w in widths for i in impls]
    rows = []
    for v, w, i, o in runs:
        seconds, total = timed(g, template, v, o)
        rows.append((template, v, w, i, text_of(total), seconds))
    return spark.createDataFrame(rows, "template string, variant string, width int, impl string, total string, seconds double")


def rounding(spark, d, graph: str = "user_next", templates=("path5", "spider6", "bin7", "t10", "t12"), exact: str = "decimal") -> DataFrame:
    """Relative difference of float and double kernels from the exact decimal program, by template size."""
    g = settle(BUILDERS[graph](spark, d), "table")
    rows = []
    for t in templates:
        true = int(timed(g, t, "v3", Options(cnt_type=exact))[1])
        for kind in ("float", "double"):
            found = float(timed(g, t, "v5", Options(cnt_type=kind))[1])
            rows.append((t, CATALOGUE[t].size, kind, str(true), abs(found - true) / true if true else 0.0))
    return spark.createDataFrame(rows, "template string, k int, cnt_type string, total string, rel_error double")


def kernel_split(spark, d, graph: str = "user_next", template: str = "bin7", options: Options = Options(cnt_type="double")) -> DataFrame:
    """Seconds, operations and bytes of the two kernels, step by step, in job groups of their names; shares of the time.

    bytes is what a kernel reads and writes at least: edges and Z counts an edge, and the sums; both children and the result.
    """
    g = settle(BUILDERS[graph](spark, d), "table")
    t, sc, n, rows = CATALOGUE[template], spark.sparkContext, g.vertices.count(), []
    run, leaf = start(g, t.size, "v5", options)

    def step(kernel: str, key: str, df: DataFrame, ops: float, moved: float) -> DataFrame:
        sc.setJobGroup(kernel, f"{kernel} of {key}")
        began = time.perf_counter()
        kept = keep_table(df, "persist")
        kept.count()
        rows.append((kernel, key, time.perf_counter() - began, float(ops), float(moved)))
        sc.setLocalProperty("spark.jobGroup.id", None)
        return kept

    for s in partition(t):
        if s.active is None:
            run.tables[s.key] = step("coloring", s.key, leaf, n, 16 * n)
            continue
        z, columns = options.width, comb(t.size, s.passive_size)
        if s.passive not in run.sums:
            run.sums[s.passive] = step("traversal", s.passive, traverse(run, run.tables[s.passive], s.passive_size, blocked.width(t.size, s.passive_size, z)), g.rows * columns, g.rows * (16 + 8 * columns) + 8 * n * columns)
        made, active = comb(t.size, s.size), comb(t.size, s.active_size)
        both = blocked.multiply_add(run.tables[s.active], run.sums[s.passive], t.size, s.size, s.passive_size, z, options.cnt_type)
        run.tables[s.key] = step("multiply_add", s.key, both, 2 * n * made * comb(s.size, s.passive_size), 8 * n * (active + columns + made))
    for kept in {**run.tables, **run.sums}.values():
        kept.unpersist()
    out = spark.createDataFrame(rows, "kernel string, sub string, seconds double, flops double, bytes double")
    per = out.groupBy("kernel").agg(F.sum("seconds").alias("seconds"), F.sum("flops").alias("flops"), F.sum("bytes").alias("bytes"))
    return per.withColumn("share", F.col("seconds") / sum(r[2] for r in rows)).withColumn("bytes_per_s", F.col("bytes") / F.col("seconds"))


def roofline_run(spark, d, graph: str = "user_next", template: str = "bin7") -> DataFrame:
    """The kernels of :func:`kernel_split` against roofs measured here: multiply-adds in memory and bytes of a copy, each per second of one task.
    share is of the roof, time_share of the time."""
    import numpy as np

    x = np.ones(1 << 20)
    began = time.perf_counter()
    for _ in range(50):
        x * x + x
    flops = 2 * 50 * len(x) / (time.perf_counter() - began)
    began = time.perf_counter()
    for _ in range(50):
        x.copy()
    moved = 16 * 50 * len(x) / (time.perf_counter() - began)
    split = kernel_split(spark, d, graph, template).withColumnRenamed("share", "time_share")
    return metrics.roofline(split, flops, moved)


def scaling(make_session, cores: Iterable[int], d: str, graph: str = "skew3", template: str = "path5", variants=("v3", "v5")) -> list[tuple[int, str, float]]:
    """(cores, variant, seconds); ``make_session(cores)`` gives a new session each, the caller stops the last."""
    out = []
    for n in cores:
        spark = make_session(n)
        g = settle(BUILDERS[graph](spark, d), "persist")
        for v in variants:
            timed(g, template, v, Options(cnt_type="double"))  # warm
            out.append((n, v, timed(g, template, v, Options(cnt_type="double"))[0]))
        spark.stop()
    return out


def fitted(timings: DataFrame) -> tuple[cost.Constants, DataFrame]:
    """The constants of the run-time models, and predicted beside measured seconds of each run."""
    c = cost.fit(timings)
    p = F.when(F.col("variant") == "v0", c.gamma * F.col("edge_ops")).otherwise(c.alpha * F.col("edge_ops") + c.beta * F.col("vertex_ops"))
    return c, timings.select("*", p.alias("predicted"))


def memory_table(spark: SparkSession, sizes: dict[str, float], templates: Iterable[str] = ("t10", "t12", "t13", "t14", "t15a", "t15b", "t16", "t17"), width: int = 8) -> DataFrame:
    """graph, template, widest, peak: bytes of dense tables; says the largest template that a memory holds."""
    rows = []
    for g, n in sizes.items():
        for t in templates:
            w, p = cost.memory(partition(CATALOGUE[t]), CATALOGUE[t].size, n, width)
            rows.append((g, t, CATALOGUE[t].size, float(w), float(p)))
    return spark.createDataFrame(rows, "graph string, template string, k int, widest double, peak double")


def headline(spark: SparkSession, c: cost.Constants, v: float = 1e6, e: float = 4e8, template: str = "t17") -> DataFrame:
    """Predicted seconds of the largest template on a network of a million vertices, by baseline and kernels."""
    t = CATALOGUE[template]
    p = partition(t)
    a, b = cost.predict("per_split", p, t.size, v, e, c), cost.predict("kernel", p, t.size, v, e, c)
    return spark.createDataFrame([(template, a, b, a / b if b else None)], "template string, per_split_s double, kernel_s double, speedup double")


def dataset_table(spark: SparkSession, d: str, names: Iterable[str] = tuple(BUILDERS)) -> DataFrame:
    out = None
    for n in names:
        part = stats(BUILDERS[n](spark, d)).select(F.lit(n).alias("graph"), "*")
        out = part if out is None else out.unionByName(part)
    return out


def motif_spectrum(graph: Graph, names=("path5", "fork5", "star5"), options: Options = Options()) -> DataFrame:
    """(it, template, estimate) of templates of one size on shared colorings: a network's profile."""
    scale = F.create_map(*[x for n in names for x in (F.lit(n), F.lit(factor(CATALOGUE[n])))])
    return count_many(graph, [CATALOGUE[n] for n in names], "v3", options).select("it", "template", (F.col("total").cast("double") * F.element_at(scale, F.col("template"))).alias("estimate"))


def top_rooted(graph: Graph, template: str, n: int = 10, options: Options = Options()) -> DataFrame:
    """The n vertices with most colorful maps rooted at them, by count and then id."""
    return counts(graph, CATALOGUE[template], "v3", options).orderBy(F.desc("cnt"), "v").limit(n).select("v", "cnt")


def rollup(timings: DataFrame) -> DataFrame:
    """Totals of seconds by graph, template and variant and all their prefixes."""
    return timings.rollup("graph", "template", "variant").agg(F.sum("seconds").alias("seconds"), F.count("*").alias("runs"))
