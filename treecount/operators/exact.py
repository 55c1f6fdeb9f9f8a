"""Exact counts: closed forms from degrees and triangles, and enumeration by joins."""

from __future__ import annotations

from math import comb, factorial

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.templates import TreeTemplate, automorphisms
from ..sources.graphs import Graph
from ..storage import merged
from . import cells
from .relational import bit

WIDE = "decimal(38,0)"


def degrees(g: Graph) -> DataFrame:
    return g.edges.groupBy("src").agg(F.count("*").cast(WIDE).alias("d"))


def star(g: Graph, leaves: int) -> DataFrame:
    """(cnt): vertices with that many of their neighbours, a sum of binomials of degrees."""
    d = F.col("d")
    value = F.lit(1).cast(WIDE)
    for i in range(leaves):
        value = (value * (d - i)).cast(WIDE)
    return degrees(g).where(d >= leaves).agg(F.coalesce(F.sum((value / factorial(leaves)).cast(WIDE)), F.lit(0)).cast(WIDE).alias("cnt"))


def oriented(g: Graph) -> DataFrame:
    """Each edge once, from the vertex of smaller degree (then id) to the other; (a, b), and b's degree as db."""
    d = degrees(g).select("src", F.col("d").cast("long").alias("d"))
    e = g.edges.join(merged(d.select("src", F.col("d").alias("da"))), "src").join(merged(d.select(F.col("src").alias("dst"), F.col("d").alias("db"))), "dst")
    return e.where((F.col("da") < F.col("db")) | ((F.col("da") == F.col("db")) & (F.col("src") < F.col("dst")))).select(F.col("src").alias("a"), F.col("dst").alias("b"), "db")


def corners(g: Graph) -> DataFrame:
    """(a, x, y): each triangle once. Edges point up in degree, so a vertex starts few pairs however many neighbours it has."""
    e = oriented(g)
    # Two neighbours meet in the order of their edge, if there is one, so each two are sent once.
    wedge = e.select("a", F.col("b").alias("x"), F.col("db").alias("dx")).join(e.select("a", F.col("b").alias("y"), F.col("db").alias("dy")), "a").where("dx < dy or (dx = dy and x < y)").select("a", "x", "y")
    return wedge.join(e.select(F.col("a").alias("x"), F.col("b").alias("y")), ["x", "y"]).select("a", "x", "y")


def triangles(g: Graph) -> DataFrame:
    """(cnt)."""
    return cells.triangles(*cells.packed(g))


def path4(g: Graph) -> DataFrame:
    """(cnt): over edges, what both ends have besides, less three for each triangle."""
    pack, parts = cells.packed(g)
    walks = cells.walks(pack, parts).select(F.col("cnt").alias("w"))
    return walks.crossJoin(cells.triangles(pack, parts)).select((F.col("w") - 3 * F.col("cnt")).cast(WIDE).alias("cnt"))


def fork5(g: Graph) -> DataFrame:
    """(cnt): for each edge from a centre to the neighbour that goes on, two more neighbours of the centre and one of the other,
    less the cases where that one is among the two: for each triangle and each corner as the centre, twice its further neighbours."""
    d = degrees(g)
    e = g.edges.join(merged(d.select("src", F.col("d").alias("da"))), "src").join(merged(d.select(F.col("src").alias("dst"), F.col("d").alias("db"))), "dst")
    pick = ((F.col("da") - 1) * (F.col("da") - 2) / 2).cast(WIDE)
    free = e.agg(F.coalesce(F.sum((pick * (F.col("db") - 1)).cast(WIDE)), F.lit(0)).cast(WIDE).alias("w"))
    at = corners(g).select(F.explode(F.array("a", "x", "y")).alias("src")).groupBy("src").agg(F.count("*").cast(WIDE).alias("t"))
    shut = at.join(d, "src").agg(F.coalesce(F.sum((2 * F.col("t") * (F.col("d") - 2)).cast(WIDE)), F.lit(0)).cast(WIDE).alias("s"))
    return free.crossJoin(shut).select((F.col("w") - F.col("s")).cast(WIDE).alias("cnt"))


def double_star(g: Graph, left: int, right: int) -> DataFrame:
    """(cnt): two joined centres with ``left`` and ``right`` leaves of their own, on a network without triangles, where no leaf can be shared."""
    d = degrees(g)
    e = g.edges.join(merged(d.select("src", F.col("d").alias("da"))), "src").join(merged(d.select(F.col("src").alias("dst"), F.col("d").alias("db"))), "dst")

    def choose(c, n):
        v = F.lit(1).cast(WIDE)
        for i in range(n):
            v = (v * F.greatest(c - 1 - i, F.lit(0).cast(WIDE))).cast(WIDE)
        return (v / factorial(n)).cast(WIDE)

    both = e.agg(F.coalesce(F.sum((choose(F.col("da"), left) * choose(F.col("db"), right)).cast(WIDE)), F.lit(0)).alias("c"))
    return both.select((F.col("c") / (2 if left == right else 1)).cast(WIDE).alias("cnt"))


def closed_form(g: Graph, name: str) -> DataFrame:
    """path3, path4, fork5, triangles, and star with its number of vertices (star4 has three leaves)."""
    if name == "path3":
        return star(g, 2)
    if name == "path4":
        return path4(g)
    if name == "fork5":
        return fork5(g)
    if name == "triangles":
        return triangles(g)
    if name.startswith("star"):
        return star(g, int(name[4:]) - 1)
    raise ValueError(f"no closed form for {name}")


def enumerate_maps(g: Graph, t: TreeTemplate, coloring: DataFrame | None = None) -> DataFrame:
    """Every map of the template's nodes to different vertices along edges, one row each: joins, one for each node. With a coloring (v, color) only maps with different colors."""
    rows = g.vertices.select(F.col("v").alias("n0"))
    if coloring is not None:
        rows = rows.join(coloring.select(F.col("v").alias("n0"), bit(F.col("color")).alias("mask")), "n0")
    done, waiting = {0}, [i for i in range(1, t.size)]
    while waiting:
        i = next(j for j in waiting if t.parents[j] in done)
        step = g.edges.select(F.col("src").alias(f"n{t.parents[i]}"), F.col("dst").alias(f"n{i}"))
        rows = rows.join(step, f"n{t.parents[i]}")
        for j in done:
            rows = rows.where(F.col(f"n{i}") != F.col(f"n{j}"))
        if coloring is not None:
            c = coloring.select(F.col("v").alias(f"n{i}"), bit(F.col("color")).alias("m"))
            rows = rows.join(c, f"n{i}").where(F.col("mask").bitwiseAND(F.col("m")) == 0).withColumn("mask", F.col("mask").bitwiseOR(F.col("m"))).drop("m")
        done.add(i)
        waiting.remove(i)
    return rows


def enumerate_count(g: Graph, t: TreeTemplate, coloring: DataFrame | None = None) -> DataFrame:
    """(cnt): occurrences, or with a coloring colorful maps. Exponential: for small networks.

    Without a coloring the leaves of the node that has most of them aren't laid out: they are counted by its further neighbours.
    """
    if coloring is not None:
        return enumerate_maps(g, t, coloring).agg(F.count("*").alias("cnt"))
    n = counted_maps(g, t) if t.size > 2 else enumerate_maps(g, t).agg(F.count("*").cast(WIDE).alias("cnt"))
    return n.select((F.col("cnt") / automorphisms(t)).cast("long").alias("cnt"))


def counted_maps(g: Graph, t: TreeTemplate) -> DataFrame:
    """(cnt): maps of the template's nodes to different vertices along edges. Vertices with too few neighbours for their node are
    left out at once. The node with most leaves is laid out with all other nodes; its leaves then are any of its neighbours
    besides those laid out, in any order."""
    near = t.neighbours()
    leaves = [[j for j in near[i] if len(near[j]) == 1] for i in range(t.size)]
    hub = max(range(t.size), key=lambda i: len(leaves[i]))
    some = degrees(g)
    # Stars need no edges; in others the inner nodes come first, along the template from the hub.
    order = [i for i in walk(near, hub) if i not in leaves[hub]]
    order.sort(key=lambda i: len(near[i]) == 1)
    rows = some.where(F.col("d") >= len(near[hub])).select(F.col("src").alias(f"n{hub}"), "d")
    inner = {}
    for at, i in enumerate(order[1:], 1):
        above = next(j for j in near[i] if j in order[:at])
        need = len(near[i])
        if need not in inner:
            e = g.edges
            inner[need] = e if need == 1 else e.join(some.where(F.col("d") >= need).select(F.col("src").alias("dst")), "dst", "left_semi")
        rows = rows.join(inner[need].select(F.col("src").alias(f"n{above}"), F.col("dst").alias(f"n{i}")), f"n{above}")
        for j in order[:at]:
            if j != above:
                rows = rows.where(F.col(f"n{i}") != F.col(f"n{j}"))
    # Which of the nodes laid out are neighbours of the hub's vertex: those of the template for certain, others by a look at the edges.
    taken = F.lit(sum(i in near[hub] for i in order[1:])).cast(WIDE)
    for i in order[1:]:
        if i not in near[hub]:
            e = g.edges.select(F.col("src").alias(f"n{hub}"), F.col("dst").alias(f"n{i}"), F.lit(1).alias(f"t{i}"))
            rows = rows.join(e, [f"n{hub}", f"n{i}"], "left")
            taken = taken + F.coalesce(F.col(f"t{i}"), F.lit(0))
    value, free = F.lit(1).cast(WIDE), (F.col("d") - taken).cast(WIDE)
    for i in range(len(leaves[hub])):
        value = (value * F.greatest(free - i, F.lit(0).cast(WIDE))).cast(WIDE)
    return rows.agg(F.coalesce(F.sum(value), F.lit(0)).cast(WIDE).alias("cnt"))


def walk(near: list[list[int]], root: int) -> list[int]:
    """The nodes of a template from a root on, each after the one it hangs on."""
    out = [root]
    for i in out:
        out += [j for j in near[i] if j not in out]
    return out


def in_complete_graph(n: int, t: TreeTemplate) -> int:
    """Occurrences in a complete network of n vertices.

    >>> from treecount.plans.templates import CATALOGUE
    >>> in_complete_graph(15, CATALOGUE["path3"])
    1365
    """
    return comb(n, t.size) * factorial(t.size) // automorphisms(t)
