"""The counting programs, from the per-split baseline to the batched kernels.

All of them color the vertices, make the table of single nodes and then walk a partition of the
template; they differ in how one step makes a sub-template's table of those of its two children.
Tables are never changed in place: a table and its neighbour sum are two things, each made at most once.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field
from functools import partial, reduce
from math import comb

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import colorsets
from ..functions.coloring import color, color_vertices
from ..operators import blocked, fused, grid, relational
from ..sources.graphs import Graph
from ..storage import settle
from .templates import SubTemplate, TreeTemplate, merge, partition

VARIANTS = ("v0", "v1", "v2", "v3", "v4", "v5", "relational")
#: The baseline refuses plans that would make more rows than this before aggregation.
MOST_ROWS = 5e9


@dataclass(frozen=True)
class Options:
    """policy says where tables go (see storage.settle); width is the number Z of color sets in a block; layout is "blocked"
    (an array of Z counts) or "wide" (Z columns) in the neighbour sum; parts of the grid: by default what its cells' memory takes; fused: on sparse blocks
    (see operators.fused), in v5 with a node's children multiplied at once and only the tables made that neighbours sum up, in v0 to v3 a color set at a
    time, with long, double or float counts; v2 then fills its memo when a color set first asks, so each is a group of its own."""

    seed: int = 42
    iterations: tuple[int, ...] = (0,)
    cnt_type: str = "long"
    policy: str = "plan"
    method: str = "md5"
    cut: str = "largest"
    share: bool = True
    root: int = 0
    width: int = 64
    impl: str = "arrow"
    strategy: str = "join"
    layout: str = "blocked"
    order: str = "by_vertex"
    parts: int | None = None
    groups: int = 2
    force: bool = False
    fused: bool = False


@dataclass
class Run:
    """Tables of one counting run by sub-template; sums holds the neighbour sums by passive sub-template."""

    graph: Graph
    k: int
    options: Options
    tables: dict[str, DataFrame] = field(default_factory=dict)
    sums: dict[str, DataFrame] = field(default_factory=dict)
    kept: list[DataFrame] = field(default_factory=list)

    def keep(self, df: DataFrame, name: str) -> DataFrame:
        out = settle(df, self.options.policy, name)
        if self.options.policy == "persist":
            self.kept.append(out)
        return out

    def sum_of(self, key: str, make: Callable[[], DataFrame]) -> DataFrame:
        if key not in self.sums:
            self.sums[key] = self.keep(make(), "sum")
        return self.sums[key]


def step_v0(run: Run, s: SubTemplate) -> DataFrame:
    return relational.per_split(run.graph.edges, run.tables[s.active], run.tables[s.passive], run.k, s.passive_size, run.options.cnt_type)


def step_v1(run: Run, s: SubTemplate) -> DataFrame:
    return relational.factored(run.graph.edges, run.tables[s.active], run.tables[s.passive], run.k, s.active_size, run.options.cnt_type)


def step_v2(run: Run, s: SubTemplate) -> DataFrame:
    """Color sets come in groups, in the order of their ranks. A group has the neighbour sums made for those of its passive
    sets that no earlier group asked for, adds them to the memo, and then takes all its sums from there."""
    o = run.options
    masks = colorsets.masks(run.k, s.size)
    keep = (lambda df, name: settle(df, "table", name)) if o.policy == "plan" else run.keep  # the memo is read by every group
    # Ascending masks are ascending ranks, so a group is a range of masks.
    edge = [*(int(masks[i]) if (i := -(-g * len(masks) // o.groups)) < len(masks) else 1 << run.k for g in range(o.groups)), 1 << run.k]
    asked = colorsets.first_superset(F.col("mask"), s.size - s.passive_size)
    memo, out = run.sums.get(s.passive), None
    known = memo is not None
    for low, high in zip(edge, edge[1:], strict=False):
        if low == high:
            continue
        if not known:
            new = keep(relational.neighbor_sum(run.graph.edges, run.tables[s.passive].where((asked >= low) & (asked < high)), o.cnt_type), "sum")
            memo = new if memo is None else memo.union(new)
        part = relational.multiply_add(run.tables[s.active], memo, o.cnt_type, (low, high))
        out = part if out is None else out.union(part)
    run.sums[s.passive] = memo
    return keep(out, "count")


def step_v3(run: Run, s: SubTemplate) -> DataFrame:
    o = run.options
    sums = run.sum_of(s.passive, lambda: relational.neighbor_sum(run.graph.edges, run.tables[s.passive], o.cnt_type))
    return relational.looked_up(run.tables[s.active], sums, run.k, s.passive_size, o.cnt_type)


def step_relational(run: Run, s: SubTemplate) -> DataFrame:
    o = run.options
    sums = run.sum_of(s.passive, lambda: relational.neighbor_sum(run.graph.edges, run.tables[s.passive], o.cnt_type, o.strategy == "broadcast"))
    return relational.multiply_add(run.tables[s.active], sums, o.cnt_type)


def traverse(run: Run, table: DataFrame, size: int, w: int) -> DataFrame:
    o = run.options
    if o.strategy == "grid":
        parts = o.parts
        if parts is None:
            parts = grid.grid_parts(run.graph.rows or run.graph.edges.count(), run.graph.vertices.count() * len(o.iterations) * comb(run.k, size))
        return grid.grid_sum(run.graph.edges, table, w, parts, o.cnt_type)
    if o.strategy == "hubs":
        return grid.hub_sum(run.graph.edges, table, w, cnt_type=o.cnt_type)
    if o.layout == "wide":
        sums = blocked.neighbor_sum_wide(run.graph.edges, blocked.to_wide(table, w), w)
        return sums.select("it", "v", "blk", F.array(*[F.col(f"c{i}").cast(o.cnt_type) for i in range(w)]).alias("x"))
    return blocked.neighbor_sum(run.graph.edges, table, w, o.cnt_type, o.strategy == "broadcast")


def step_v4(run: Run, s: SubTemplate) -> DataFrame:
    """One pass over the edges for each passive column, then one multiply-add for each split."""

    def columns():
        table = settle(run.tables[s.passive], "table" if run.options.policy == "plan" else "plan", "columns")
        passes = [traverse(run, table.where(F.col("blk") == c), s.passive_size, 1) for c in range(comb(run.k, s.passive_size))]
        return reduce(DataFrame.union, passes)

    sums = run.sum_of(s.passive, columns)
    return blocked.multiply_add(run.tables[s.active], sums, run.k, s.size, s.passive_size, 1, run.options.cnt_type, run.options.impl, run.options.order)


def step_v5(run: Run, s: SubTemplate) -> DataFrame:
    z = run.options.width
    sums = run.sum_of(s.passive, lambda: traverse(run, run.tables[s.passive], s.passive_size, blocked.width(run.k, s.passive_size, z)))
    return blocked.multiply_add(run.tables[s.active], sums, run.k, s.size, s.passive_size, z, run.options.cnt_type, run.options.impl, run.options.order)


STEPS = {"v0": step_v0, "v1": step_v1, "v2": step_v2, "v3": step_v3, "v4": step_v4, "v5": step_v5, "relational": step_relational}


def start(graph: Graph, k: int, variant: str, o: Options) -> tuple[Run, DataFrame]:
    coloring = color_vertices(graph.vertices, k, o.seed, o.iterations, o.method)
    run = Run(graph, k, o)
    if variant in ("v4", "v5"):
        blocked.check_width(o.width)
        if o.layout not in ("blocked", "wide"):
            raise ValueError("layout must be blocked or wide")
        if o.cnt_type not in blocked.DTYPES:
            raise ValueError("blocks hold long, double or float counts")
        if o.fused and o.method == "rand":
            raise ValueError("fused kernels need repeatable colors")
        return run, blocked.leaf_blocks(coloring, k, 1 if variant == "v4" else o.width, o.cnt_type)
    return run, relational.leaf_counts(coloring, o.cnt_type)


def tables(graph: Graph, template: TreeTemplate | list[TreeTemplate], variant: str = "v5", options: Options = Options()) -> tuple[Run, list[str]]:
    """All tables of a run, and the keys of the whole templates. Templates of one run have the same size."""
    if variant not in STEPS:
        raise ValueError(f"variant must be one of {VARIANTS}")
    many = template if isinstance(template, list) else [template]
    k = many[0].size
    if any(t.size != k for t in many):
        raise ValueError("templates that share colors must have the same size")
    plans = [partition(t, options.root, options.cut, options.share or len(many) > 1) for t in many]
    plan = merge(plans)
    run, leaf = start(graph, k, variant, options)
    if takes_blocks(plan, variant, options):
        (fused_tables if variant == "v5" else walked_tables)(run, plan, [p[-1].key for p in plans], variant)
        return run, [p[-1].key for p in plans]
    if variant == "v0" and not options.force and graph.rows:
        rows = graph.rows * max(comb(k, s.size) * comb(s.size, s.passive_size) for s in plan if s.active) if k > 1 else 0
        if rows > MOST_ROWS:
            raise ValueError(f"the baseline would make about {rows:.2g} rows; pass force=True to run it")
    for s in plan:
        run.tables[s.key] = leaf if s.active is None else run.keep(STEPS[variant](run, s), "count")
    return run, [p[-1].key for p in plans]


def takes_blocks(plan: list[SubTemplate], variant: str, o: Options) -> bool:
    """Whether a program runs on sparse blocks: v0, v1, v3 and v5 at any size, v2 where counts of one size are one block, as its
    tasks hold all columns of a table for their vertices."""
    return o.fused and (variant == "v5" or variant in ("v0", "v1", "v2", "v3") and o.cnt_type in blocked.DTYPES and o.method != "rand" and (variant != "v2" or one_block(plan)))


def one_block(plan: list[SubTemplate]) -> bool:
    k = plan[-1].size
    return comb(k, k // 2) <= 64


def packed_edges(run: Run, plan: list[SubTemplate], variant: str) -> tuple[DataFrame, int, int]:
    """Edges in ranges of receiving vertices, the number of ranges, and of tasks. A table of them is made once for a network."""
    g = run.graph
    rows, tasks, vertices = g.rows or g.edges.count(), int(g.edges.sparkSession.conf.get("spark.sql.shuffle.partitions")), g.vertices.count()
    parts = fused.spread(fused.ranges(rows, vertices), rows, tasks, max((comb(run.k, s.passive_size) for s in plan), default=1))
    if variant != "v5" and not one_block(plan):
        # A task holds all active and whole counts of its vertices.
        widest = max(comb(run.k, s.size) + comb(run.k, s.active_size) for s in plan if s.active)
        parts = max(parts, min(tasks, vertices), -(-8 * widest * vertices // fused.MOST_BYTES))
    if run.options.policy != "table":
        return run.keep(fused.packed(g.edges, parts, rows), "packed"), parts, tasks
    if parts not in g.packs:
        g.packs[parts] = run.keep(fused.packed(g.edges, parts, rows), "packed")
    return g.packs[parts], parts, tasks


def prepare(graph: Graph, template: TreeTemplate, variant: str, options: Options) -> None:
    """Packs a network's edges where a run takes them so, to time the run without that."""
    plan = partition(template, options.root, options.cut, options.share)
    if options.policy == "table" and takes_blocks(plan, variant, options):
        packed_edges(Run(graph, template.size, options), plan, variant)


def fused_leaf(run: Run) -> DataFrame:
    o = run.options
    return fused.leaf(color_vertices(run.graph.vertices, run.k, o.seed, o.iterations, o.method), o.cnt_type, min(64, o.width, run.k))


def walked_tables(run: Run, plan: list[SubTemplate], whole: list[str], variant: str) -> None:
    """The tables of v0 to v3 on sparse blocks, one after the other."""
    o, z = run.options, min(64, run.options.width)
    pack, parts, _ = packed_edges(run, plan, variant)
    for s in plan:
        if s.active is None:
            run.tables[s.key] = fused_leaf(run)
            continue
        sides = pack, run.tables[s.active], run.tables[s.passive], parts, run.k, s.size, s.passive_size, z, o.cnt_type
        run.tables[s.key] = run.keep(fused.walked(*sides, variant) if one_block(plan) else fused.stepped(*sides, variant), "count")


def fused_tables(run: Run, plan: list[SubTemplate], whole: list[str], variant: str = "v5") -> None:
    """The tables of whole templates on sparse blocks; of the others only those that neighbours sum up are made."""
    o, k, by_key, z = run.options, run.k, {s.key: s for s in plan}, min(64, run.options.width)
    pack, parts, tasks = packed_edges(run, plan, variant)
    leaf = fused_leaf(run)
    own = color(F.col("v"), F.col("it"), k, o.seed, o.method)

    def children(key: str) -> list[str]:
        s = by_key[key]
        return [] if s.active is None else [*children(s.active), s.passive]

    made = {*whole, *(s.passive for s in plan if s.passive)}
    uses = [c for key in made for c in set(children(key))]

    def sum_of(key: str) -> DataFrame:
        if key not in run.sums:
            size = by_key[key].size
            w = blocked.width(k, size, z)
            unread = partial(fused.with_own_color, k, size, w, o.seed) if o.method == "md5" else None
            s = fused.neighbor_sum(pack, table_of(key), parts, blocked.blocks(k, size, z), w, o.cnt_type, unread)
            run.sums[key] = run.keep(s, "sum") if uses.count(key) > 1 else s  # read once, it need not be kept
        return run.sums[key]

    def table_of(key: str) -> DataFrame:
        if key not in run.tables:
            near = children(key)
            some = list(dict.fromkeys(near))
            run.tables[key] = fused.multiply_all([sum_of(c) for c in some], [some.index(c) for c in near], [by_key[c].size for c in some], own, k, z, o.cnt_type, tasks) if near else leaf
        return run.tables[key]

    for key in whole:
        table_of(key)


def counts(graph: Graph, template: TreeTemplate, variant: str = "v5", options: Options = Options()) -> DataFrame:
    """Rooted counts (it, v, cnt): colorful maps of the template whose root is v. Vertices without any are absent."""
    run, (key,) = tables(graph, template, variant, options)
    m = run.tables[key]
    if "x" in m.columns:
        return m.select("it", "v", F.get("x", F.lit(0)).alias("cnt")).where("cnt <> 0")
    return m.select("it", "v", "cnt")


def total(graph: Graph, template: TreeTemplate, variant: str = "v5", options: Options = Options()) -> DataFrame:
    """(it, total): colorful maps of the template for each coloring. Colorings without any are absent."""
    rows = counts(graph, template, variant, options)
    return rows.groupBy("it").agg(relational.total_of("cnt", options.cnt_type).alias("total"))


def count_many(graph: Graph, templates: list[TreeTemplate], variant: str = "v3", options: Options = Options()) -> DataFrame:
    """(it, template, total) of templates of equal size on the same colorings; shapes that they share are counted once."""
    run, keys = tables(graph, templates, variant, options)
    out = None
    for t, key in zip(templates, keys, strict=True):
        m = run.tables[key]
        cell = F.get("x", F.lit(0)) if "x" in m.columns else F.col("cnt")
        part = m.groupBy("it").agg(relational.total_of(cell, options.cnt_type).alias("total")).select("it", F.lit(t.name).alias("template"), "total")
        out = part if out is None else out.unionByName(part)
    return out
