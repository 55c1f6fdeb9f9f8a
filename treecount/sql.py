"""The same results as SQL for another engine: graphs, colorings and the mask dynamic program as common table expressions.

Nothing here comes of the library's own partitions or symmetries: programs go node by node along the parents of a
template, shapes of sub-templates are spelled in SQL, and symmetries are counted.
"""

from __future__ import annotations

import math
from itertools import permutations

from .plans.templates import SHAPES

#: Pairs (a, b) of each graph.
PAIRS = {
    "copart": "select x.l_partkey as a, y.l_partkey as b from (select distinct l_orderkey, l_partkey from lineitem) x join (select distinct l_orderkey, l_partkey from lineitem) y on x.l_orderkey = y.l_orderkey and x.l_partkey < y.l_partkey",
    "custpart": "select 2 * o_custkey as a, 2 * l_partkey + 1 as b from orders join lineitem on o_orderkey = l_orderkey",
    "supppart": "select 2 * l_suppkey as a, 2 * l_partkey + 1 as b from lineitem",
    "custsupp": "select 2 * o_custkey as a, 2 * l_suppkey + 1 as b from orders join lineitem on o_orderkey = l_orderkey",
    "user_next": "select user_id as a, lead(user_id) over (partition by event_type order by ts, event_id) as b from events",
    "hour": "select x.user_id as a, y.user_id as b from (select distinct date_trunc('hour', ts) as h, event_type, user_id from events) x join (select distinct date_trunc('hour', ts) as h, event_type, user_id from events) y on x.h = y.h and x.event_type = y.event_type and x.user_id < y.user_id",
    "geo": "select 4 * n_regionkey as a, 4 * n_nationkey + 1 as b from nation union all select 4 * c_nationkey + 1, 4 * c_custkey + 2 from customer union all select 4 * s_nationkey + 1, 4 * s_suppkey + 3 from supplier",
    "conv": "select 2 * conv_id as a, 2 * cast('0x' || substr(md5(text), 1, 13) as bigint) + 1 as b from conversations",
    "pages": """select 2 * page_id as a, 2 * cast('0x' || substr(md5(h), 1, 13) as bigint) + 1 as b from (select page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) as h from pages)""",
}


def skew_pairs(skew: int, deep: int = 16) -> str:
    """As sources.graphs.skewed, for tables of up to 30 * 2^deep line items."""
    a = 256 * skew // (skew + 3)
    w = (256 - a) // 3
    q = [f"cast('0x' || substr(h, {2 * i + 1}, 2) as int)" for i in range(deep)]
    src = " + ".join(f"case when {i} < lv and {x} >= {a + w} then {1 << i} else 0 end" for i, x in enumerate(q))
    dst = " + ".join(f"case when {i} < lv and (({x} >= {a} and {x} < {a + w}) or {x} >= {a + 2 * w}) then {1 << i} else 0 end" for i, x in enumerate(q))
    lv = "select greatest(1, floor(log2(count(*) / 30.0) + 0.5)) as lv from lineitem"
    return f"select cast({src} as bigint) as a, cast({dst} as bigint) as b from (select md5('42:' || l_orderkey || ':' || l_partkey || ':' || l_suppkey || ':' || l_linenumber) as h, lv from lineitem, ({lv}))"


for _k in (3, 5, 8):
    PAIRS[f"skew{_k}"] = skew_pairs(_k)
PAIRS["knn"] = """select a, b from (
  select x.vec_id as a, y.vec_id as b, row_number() over (partition by x.vec_id order by round(list_cosine_similarity(x.embedding::double[], y.embedding::double[]), 9) desc, y.vec_id) as place
  from embeddings x join embeddings y on x.vec_id <> y.vec_id and len(x.embedding) = len(y.embedding)
  where len(list_filter(x.embedding, lambda v: v <> 0)) > 0 and len(list_filter(y.embedding, lambda v: v <> 0)) > 0) where place <= 10"""
PAIRS["doc_shingles"] = """select x.doc_id as a, y.doc_id as b from (
  select distinct doc_id, unnest(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' '))) as s from (select doc_id, regexp_split_to_array(lower(text), '\\s+') as w from documents) where len(w) >= 5) x
  join (select distinct doc_id, unnest(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' '))) as s from (select doc_id, regexp_split_to_array(lower(text), '\\s+') as w from documents) where len(w) >= 5) y
  on x.s = y.s and x.doc_id < y.doc_id group by 1, 2 having count(*) >= 3"""


def graph(name: str) -> str:
    """CTEs edges (src, dst) and verts (v)."""
    return f"""pairs as ({PAIRS[name]}),
one as (select distinct cast(least(a, b) as bigint) as a, cast(greatest(a, b) as bigint) as b from pairs where a <> b),
edges as (select a as src, b as dst from one union all select b, a from one),
verts as (select distinct src as v from edges)"""


def coloring(k: int, seed: int = 42, iterations: int = 1) -> str:
    return f"colors as (select cast(it as int) as it, v, cast(cast('0x' || substr(md5('{seed}:' || it || ':' || v), 1, 7) as bigint) % {k} as int) as color from verts, range({iterations}) r(it))"


def program(template: str, prefix: str = "", root: int | None = None) -> tuple[str, str]:
    """CTEs of count tables (it, v, mask, cnt), and the name of the last: from the root on, node by node, the table of what is
    there joins the neighbour sums of the next child's. By default the root is the last node, a leaf in all templates."""
    near: dict[int, list[int]] = {}
    for node, parent in enumerate(SHAPES[template]):
        near.setdefault(node, [])
        if parent >= 0:
            near[node].append(parent)
            near[parent].append(node)
    out = [f"{prefix}m as (select it, v, 1::bigint << color as mask, 1::hugeint as cnt from colors)"]

    def visit(node: int, above: int) -> str:
        name = f"{prefix}m"
        for child in near[node]:
            if child != above:
                below = visit(child, node)
                out.append(f"{prefix}s{child} as (select m.it, e.src as v, m.mask, sum(m.cnt)::hugeint as cnt from edges e join {below} m on e.dst = m.v group by all)")
                out.append(f"{prefix}m{child} as (select x.it, x.v, x.mask | y.mask as mask, sum(x.cnt * y.cnt)::hugeint as cnt from {name} x join {prefix}s{child} y on x.it = y.it and x.v = y.v and x.mask & y.mask = 0 group by 1, 2, 3)")
                name = f"{prefix}m{child}"
        return name

    last = visit(len(near) - 1 if root is None else root, -1)
    return ",\n".join(out), last


def whole(graph_name: str, template: str, iterations: int = 1, root: int | None = None) -> tuple[str, str]:
    """The with clause up to a template's rooted counts, and the name of their table."""
    body, last = program(template, root=root)
    return f"with {graph(graph_name)},\n{coloring(len(SHAPES[template]), 42, iterations)},\n{body}", last


def total(graph_name: str, template: str, iterations: int = 1, digits: bool = True) -> str:
    """The total of each coloring as text; without digits to nine of them, as doubles have it."""
    head, last = whole(graph_name, template, iterations)
    cell = "sum(cnt)::varchar" if digits else "printf('%.8e', sum(cnt)::double)"
    return f"{head}\nselect '{template}' as template, it, {cell} as total from {last} group by it"


def rooted(graph_name: str, template: str) -> str:
    head, last = whole(graph_name, template, root=0)
    return f"{head}\nselect v, cnt::bigint as cnt from {last}"


def symmetries(template: str) -> int:
    """Permutations of the nodes that keep the edges, counted one by one; for up to seven nodes."""
    edges = {frozenset((i, p)) for i, p in enumerate(SHAPES[template]) if p >= 0}
    return sum(all(frozenset((q[i], q[p])) in edges for i, p in enumerate(SHAPES[template]) if p >= 0) for q in permutations(range(len(SHAPES[template]))))


def scale(template: str) -> float:
    k = len(SHAPES[template])
    return k**k / math.factorial(k) / symmetries(template)


def nodes(templates) -> str:
    """CTE node (template, k, node, parent)."""
    rows = [f"('{t}', {len(SHAPES[t])}, {i}, {p})" for t in templates for i, p in enumerate(SHAPES[t])]
    return f"node(template, k, node, parent) as (values {', '.join(rows)})"


def parts(templates) -> str:
    """CTEs up to part (template, k, sub, s, active, a, passive, p): the different shapes that cutting off the largest root child, one
    after the other, gives. A shape is spelled by its children's in brackets, smaller ones first. Needs ``with recursive``."""

    def deepest(t):
        depth = [0]
        for p in SHAPES[t][1:]:
            depth.append(depth[p] + 1)
        return max(depth)

    deep = max(map(deepest, templates))
    levels = [f"""spell{d} as (select n.template, n.node, n.parent, n.size, '(' || coalesce(string_agg(c.spell, '' order by c.size, c.spell), '') || ')' as spell
  from sized n left join {f"spell{d + 1}" if d < deep else "(select template, parent, size, '' as spell from sized where false)"} c on c.template = n.template and c.parent = n.node where n.depth = {d} group by all)""" for d in range(deep, -1, -1)]
    union = " union all ".join(f"select * from spell{d}" for d in range(deep + 1))
    return f"""{nodes(templates)},
up as (select template, node, node as above, parent as next from node union all select u.template, u.node, n.node, n.parent from up u join node n on n.template = u.template and n.node = u.next),
sized as (select n.template, n.node, n.parent, (select count(*) from up where up.template = n.template and up.above = n.node) as size, (select count(*) - 1 from up where up.template = n.template and up.node = n.node) as depth from node n),
{", ".join(levels)},
ranked as (select *, row_number() over (partition by template, parent order by size desc, spell) as ord from ({union}) where parent >= 0),
cuts as (select r.template, r.parent, r.ord, '(' || string_agg(q.spell, '' order by q.size, q.spell) || ')' as sub, (1 + sum(q.size))::int as s,
  '(' || coalesce(string_agg(q.spell, '' order by q.size, q.spell) filter (q.ord > r.ord), '') || ')' as active, (1 + coalesce(sum(q.size) filter (q.ord > r.ord), 0))::int as a, r.spell as passive, r.size::int as p
  from ranked r join ranked q on q.template = r.template and q.parent = r.parent and q.ord >= r.ord group by r.template, r.parent, r.ord, r.spell, r.size),
part as (select distinct c.template, n.k, c.sub, c.s, c.active, c.a, c.passive, c.p from cuts c join (select distinct template, k from node) n on n.template = c.template)"""


def choose(n: str, m: str) -> str:
    return f"(factorial({n}) // (factorial({m}) * factorial({n} - {m})))"


SPLIT, WALK = f"{choose('k', 's')} * {choose('s', 'p')}", choose("k", "p")


def work(variants) -> str:
    """CTE work (template, variant, edge_cells, vertex_cells): edge touches for each stored edge and vertex operations for each vertex, of all steps. Needs part."""
    values = ", ".join(f"('{v}')" for v in variants)
    return f"""work as (select template, variant, sum(case when variant in ('v0', 'v1') then {SPLIT} else {WALK} end) as edge_cells,
  sum(case when variant = 'v0' then 0 when variant in ('v2', 'v3') then {SPLIT} + {WALK} else {SPLIT} end) as vertex_cells from part, (values {values}) v(variant) group by all)"""


def experiment(runs: dict[str, str], templates, variants, digits: bool = True) -> str:
    """Rows of workloads.run_matrix without the seconds; runs has the CTEs edges and verts of each graph by name."""
    rows = []
    cell = "sum(cnt)::varchar" if digits else "printf('%.8e', sum(cnt)::double)"
    for name, ctes in runs.items():
        for t in templates:
            body, last = program(t)
            rows.append(f"select * from (with {ctes},\n{coloring(len(SHAPES[t]))},\n{body}\nselect '{name}' as graph, '{t}' as template, (select count(*) from verts) as vertices, (select count(*) from edges) as edges, coalesce((select {cell} from {last}), '0') as total)")
    return f"""with recursive {parts(templates)},
{work(variants)},
runs as ({" union all ".join(rows)})
select r.graph, r.template, w.variant, r.vertices, r.edges, r.total, (r.edges * w.edge_cells)::double as edge_ops, (r.vertices * w.vertex_cells)::double as vertex_ops
from runs r join work w on w.template = r.template"""


def copied(name: str, n: int) -> str:
    """CTEs edges and verts of a graph n times over."""
    return graph(name).replace("edges as (", "edges0 as (").replace("from edges)", "from edges0)").replace("verts as (", "verts0 as (") + f""",
edges as (select src * {n} + i as src, dst * {n} + i as dst from edges0, range({n}) r(i)),
verts as (select v * {n} + i as v from verts0, range({n}) r(i))"""


def sampled(name: str, least: str, seed: int = 42) -> str:
    """CTEs of a graph's edges with the smallest hash, as many as the scalar query ``least`` says."""
    return f"""pairs as ({PAIRS[name]}),
drawn as (select distinct cast(least(a, b) as bigint) as a, cast(greatest(a, b) as bigint) as b from pairs where a <> b),
one as (select a, b from (select a, b, row_number() over (order by md5('{seed}:' || a || ':' || b), a, b) as place from drawn) where place <= {least}),
edges as (select a as src, b as dst from one union all select b, a from one),
verts as (select distinct src as v from edges)"""


def estimates(graph_name: str, template: str, iterations: int) -> str:
    head, last = whole(graph_name, template, iterations)
    return f"{head},\nest as (select it, sum(cnt)::double * {scale(template)!r} as estimate from {last} group by it)"


def closed_form(graph_name: str, name: str) -> str:
    head = f"with {graph(graph_name)},\ndeg as (select src as v, count(*)::hugeint as d from edges group by 1),\ntri as (select count(*)::hugeint as n from one x join one y on x.b = y.a join one z on z.a = x.a and z.b = y.b)"
    if name.startswith("star") or name == "path3":
        m = 2 if name == "path3" else int(name[4:]) - 1
        product = " * ".join(f"(d - {i})" for i in range(m))
        return f"{head}\nselect coalesce(sum({product} // {math.factorial(m)}), 0)::varchar as cnt from deg where d >= {m}"
    if name == "fork5":
        return f"""{head},
ends as (select v, count(*)::hugeint as t from (select unnest([x.a, x.b, y.b]) as v from one x join one y on x.b = y.a join one z on z.a = x.a and z.b = y.b) group by v)
select ((select sum((x.d - 1) * (x.d - 2) // 2 * (y.d - 1)) from edges join deg x on x.v = src join deg y on y.v = dst)::hugeint - (select coalesce(sum(2 * t * (d - 2)), 0) from ends join deg using (v))::hugeint)::varchar as cnt"""
    if name == "triangles":
        return f"{head}\nselect n::varchar as cnt from tri"
    return f"{head}\nselect (coalesce(sum((x.d - 1) * (y.d - 1)), 0)::hugeint - 3 * (select n from tri))::varchar as cnt from one join deg x on x.v = a join deg y on y.v = b"


def fork5_brute(graph_name: str) -> str:
    """Occurrences of fork5 by joins: a centre with three neighbours, one of which has one more."""
    return f"""with {graph(graph_name)}
select count(*) // 2 as cnt from edges e1 join edges e2 on e1.src = e2.src and e1.dst <> e2.dst join edges e3 on e1.src = e3.src and e3.dst <> e1.dst and e3.dst <> e2.dst
join edges e4 on e4.src = e3.dst and e4.dst <> e1.src and e4.dst <> e1.dst and e4.dst <> e2.dst"""
