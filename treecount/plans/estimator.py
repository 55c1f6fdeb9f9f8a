"""From colorful totals to estimates of how often a template occurs."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.graphs import Graph
from .templates import TreeTemplate, automorphisms
from .variants import Options, total


def factor(t: TreeTemplate) -> float:
    """What a colorful total is multiplied by: all colorings over colorful ones, and one copy for each symmetry."""
    k = t.size
    return k**k / math.factorial(k) / automorphisms(t)


def scale(value: float, k: int, aut: int) -> float:
    return value * k**k / math.factorial(k) / aut


def iterations_for(eps: float, delta: float, k: int) -> int:
    """Colorings that bound the relative error by eps with probability 1 - delta in the worst case.

    >>> iterations_for(0.1, 0.1, 3)
    4625
    """
    if not (eps > 0 and 0 < delta < 1):
        raise ValueError("eps must be positive and delta between 0 and 1")
    return math.ceil(math.exp(k) * math.log(1 / delta) / eps**2)


def series(graph: Graph, t: TreeTemplate, iterations: int = 8, variant: str = "v5", options: Options = Options(), per_pass: int = 8) -> DataFrame:
    """(it, total, estimate) of each coloring; ``per_pass`` colorings share one walk over the edges. A coloring without any map has total 0."""
    out = None
    for at in range(0, iterations, per_pass):
        its = tuple(range(at, min(iterations, at + per_pass)))
        part = total(graph, t, variant, Options(**{**vars(options), "iterations": its}))
        all_its = graph.edges.sparkSession.range(at, at + len(its)).select(F.col("id").cast("int").alias("it"))
        part = all_its.join(F.broadcast(part), "it", "left").select("it", F.coalesce("total", F.lit(0)).alias("total"))
        out = part if out is None else out.unionByName(part)
    return out.select("it", "total", (F.col("total").cast("double") * factor(t)).alias("estimate"))


def summary(estimates: DataFrame, t: TreeTemplate, exact: float | None = None, combine: str = "mean") -> DataFrame:
    """template, iterations, mean, stderr, exact, rel_error. combine: "mean" or "median_of_means"."""
    if combine == "mean":
        value = F.avg("estimate")
    elif combine == "median_of_means":
        from ..functions.registered import median_of_means

        value = median_of_means("it", "estimate")
        means = estimates.agg(value.alias("mean"))
        spread = estimates.agg(F.count("*").cast("int").alias("iterations"), (F.stddev_samp("estimate") / F.sqrt(F.count("*"))).alias("stderr"))
        return finish(spread.crossJoin(means), t, exact)  # one row each
    else:
        raise ValueError("combine must be mean or median_of_means")
    return finish(estimates.agg(F.count("*").cast("int").alias("iterations"), value.alias("mean"), (F.stddev_samp("estimate") / F.sqrt(F.count("*"))).alias("stderr")), t, exact)


def finish(df: DataFrame, t: TreeTemplate, exact: float | None) -> DataFrame:
    e = F.lit(exact).cast("double")
    return df.select(F.lit(t.name).alias("template"), "iterations", "mean", "stderr", e.alias("exact"), (F.abs(F.col("mean") - e) / e).alias("rel_error"))


def running_mean(estimates: DataFrame) -> DataFrame:
    """(it, mean) over all colorings up to each. One row for each coloring, so one window holds them."""
    w = Window.orderBy("it").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return estimates.select("it", F.avg("estimate").over(w).alias("mean"))


def estimate(graph: Graph, t: TreeTemplate, target_rse: float, most: int = 512, per_pass: int = 8, variant: str = "v5", options: Options = Options()) -> tuple[float, float, int]:
    """Mean, standard error and number of colorings once the relative standard error is below the target, or ``most`` are done."""
    values: list[float] = []
    while len(values) < most:
        its = tuple(range(len(values), len(values) + per_pass))
        found = {r.it: float(r.total) for r in total(graph, t, variant, Options(**{**vars(options), "iterations": its})).collect()}
        values += [found.get(i, 0.0) * factor(t) for i in its]
        mean = sum(values) / len(values)
        err = (sum((v - mean) ** 2 for v in values) / max(1, len(values) - 1) / len(values)) ** 0.5
        if mean and err <= target_rse * mean or not mean and len(values) >= 4 * per_pass:
            break
    return mean, err, len(values)


def count_trees(edges: DataFrame, template: TreeTemplate, iterations: int = 8, variant: str = "v5", **options) -> DataFrame:
    """One call for users: pairs of any kind (first two columns) in, the summary of the estimate out."""
    from ..sources.graphs import normalize

    a, b = edges.columns[:2]
    g = normalize(edges.select(F.col(a).alias("a"), F.col(b).alias("b")))
    return summary(series(g, template, iterations, variant, Options(**{"cnt_type": "double", "policy": "table", **options})), template)
