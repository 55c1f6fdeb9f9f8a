"""Tree templates, their partition into sub-templates and their symmetries. Everything here is tiny and stays on the driver."""

from __future__ import annotations

from dataclasses import dataclass
from math import factorial

#: A rooted tree is the sorted tuple of its children's trees.
Tree = tuple

CUTS = ("largest", "smallest", "first", "balanced")


def order(tree: Tree) -> int:
    return 1 + sum(order(c) for c in tree)


def spell(tree: Tree) -> str:
    return "(" + "".join(spell(c) for c in tree) + ")"


def sort_tree(children) -> Tree:
    return tuple(sorted(children, key=lambda c: (order(c), spell(c))))


@dataclass(frozen=True)
class TreeTemplate:
    """parents[i] is the parent of node i; node 0 is the root and has parent -1.

    >>> TreeTemplate((-1, 0, 1)).size
    3
    """

    parents: tuple[int, ...]
    name: str = ""

    def __post_init__(self):
        p = tuple(self.parents)
        object.__setattr__(self, "parents", p)
        if not p or p[0] != -1:
            raise ValueError("node 0 must be the root, with parent -1")
        for i, q in enumerate(p[1:], 1):
            if not 0 <= q < len(p) or q == i:
                raise ValueError(f"node {i} has no valid parent")
        for i in range(len(p)):
            seen = set()
            while i != -1:
                if i in seen:
                    raise ValueError("the parents form a cycle")
                seen.add(i)
                i = p[i]
        if len(p) > 62:
            raise ValueError("color masks are 64-bit: at most 62 nodes")

    @property
    def size(self) -> int:
        return len(self.parents)

    def edges(self) -> list[tuple[int, int]]:
        return [(p, i) for i, p in enumerate(self.parents) if p >= 0]

    def neighbours(self) -> list[list[int]]:
        out: list[list[int]] = [[] for _ in self.parents]
        for a, b in self.edges():
            out[a].append(b)
            out[b].append(a)
        return out

    def rooted(self, root: int = 0) -> Tree:
        near = self.neighbours()

        def build(node: int, above: int) -> Tree:
            return sort_tree(build(n, node) for n in near[node] if n != above)

        return build(root, -1)

    def centroids(self) -> list[int]:
        """The one or two nodes whose removal leaves no part above half the size."""
        near, k = self.neighbours(), self.size

        def weight(node: int, above: int) -> int:
            return 1 + sum(weight(n, node) for n in near[node] if n != above)

        return [v for v in range(k) if all(2 * weight(n, v) <= k for n in near[v])]

    def canonical(self) -> str:
        """Equal for two templates exactly if they are the same tree without a root."""
        return min(spell(self.rooted(c)) for c in self.centroids())


def rooted_automorphisms(tree: Tree) -> int:
    out = 1
    for c in set(tree):
        n = tree.count(c)
        out *= factorial(n) * rooted_automorphisms(c) ** n
    return out


def automorphisms(t: TreeTemplate) -> int:
    """Symmetries of the template as a tree without a root.

    >>> automorphisms(CATALOGUE["star5"])
    24
    """
    c = t.centroids()
    if len(c) == 1:
        return rooted_automorphisms(t.rooted(c[0]))
    # Two centroids share an edge; both halves may also change places.
    a, b = (t.rooted(x) for x in c)
    near = t.neighbours()

    def half(node: int, above: int) -> Tree:
        return sort_tree(half(n, node) for n in near[node] if n != above)

    left, right = half(c[0], c[1]), half(c[1], c[0])
    return rooted_automorphisms(left) * rooted_automorphisms(right) * (2 if left == right else 1)


@dataclass(frozen=True)
class SubTemplate:
    """key names it; active keeps the root, passive hangs on a neighbour. Both are None for a single node."""

    key: str
    size: int
    active: str | None = None
    passive: str | None = None
    active_size: int = 0
    passive_size: int = 0


def partition(t: TreeTemplate, root: int = 0, cut: str = "largest", share: bool = True) -> list[SubTemplate]:
    """Cuts one root edge after the other down to single nodes; children come before parents, the whole template last.

    cut says which root edge goes first: that of the largest, smallest or first child, or the one that
    halves the tree best. share keeps one entry for equal rooted shapes.
    """
    if cut not in CUTS:
        raise ValueError(f"cut must be one of {CUTS}")
    out: dict[str, SubTemplate] = {}

    def pick(tree: Tree) -> int:
        sizes = [order(c) for c in tree]
        if cut == "largest":
            return max(range(len(tree)), key=lambda i: sizes[i])
        if cut == "smallest":
            return min(range(len(tree)), key=lambda i: sizes[i])
        if cut == "balanced":
            return min(range(len(tree)), key=lambda i: abs(order(tree) - 2 * sizes[i]))
        return 0

    def visit(tree: Tree, path: str) -> str:
        key = spell(tree) if share else path
        if key not in out:
            if not tree:
                out[key] = SubTemplate(key, 1)
            else:
                i = pick(tree)
                a = visit(tree[:i] + tree[i + 1 :], path + "a")
                p = visit(tree[i], path + "p")
                out[key] = SubTemplate(key, order(tree), a, p, out[a].size, out[p].size)
        return key

    visit(t.rooted(root), "T")
    return list(out.values())


def last_use(plan: list[SubTemplate]) -> dict[str, int]:
    """For each sub-template the place in the plan after which its table may go."""
    out = {}
    for i, s in enumerate(plan):
        for k in (s.active, s.passive, s.key):
            if k:
                out[k] = i
    return out


def merge(plans: list[list[SubTemplate]]) -> list[SubTemplate]:
    """One plan for several templates of equal size; equal shapes appear once."""
    out: dict[str, SubTemplate] = {}
    for plan in plans:
        for s in plan:
            out.setdefault(s.key, s)
    return list(out.values())


def plan_frame(spark, plan: list[SubTemplate]):
    """The plan as rows (step, sub, size, active, passive), to look at or to join with costs."""
    return spark.createDataFrame([(i, s.key, s.size, s.active, s.passive) for i, s in enumerate(plan)], "step int, sub string, size int, active string, passive string")


#: Parents of each node. Fixed values.
SHAPES = {
    "path2": [-1, 0],
    "path3": [-1, 0, 1],
    "path4": [-1, 0, 1, 2],
    "star4": [-1, 0, 0, 0],
    "path5": [-1, 0, 1, 2, 3],
    "path5mid": [-1, 0, 0, 1, 2],
    "fork5": [-1, 0, 0, 0, 1],
    "star5": [-1, 0, 0, 0, 0],
    "spider6": [-1, 0, 0, 0, 1, 2],
    "bin7": [-1, 0, 0, 1, 1, 2, 2],
    "t10": [-1, 0, 0, 1, 1, 2, 2, 3, 4, 5],
    "t12": [-1, 0, 0, 0, 1, 1, 2, 2, 3, 3, 4, 6],
    "t13": [-1, 0, 0, 0, 1, 1, 1, 2, 2, 2, 3, 3, 3],
    "t14": [-1, 0, 0, 1, 1, 2, 2, 3, 3, 4, 5, 6, 6, 12],
    "t15a": [-1, 0, 0, 1, 1, 2, 2, 3, 3, 4, 4, 5, 5, 6, 6],
    "t15b": [-1, 0, 1, 2, 3, 4, 5, 6, 0, 1, 2, 3, 4, 5, 6],
    "t16": [-1, 0, 0, 0, 1, 1, 2, 2, 3, 3, 4, 5, 6, 7, 8, 9],
    "t17": [-1, 0, 0, 0, 0, 1, 1, 1, 2, 2, 2, 3, 3, 3, 4, 4, 4],
}
CATALOGUE = {name: TreeTemplate(tuple(p), name) for name, p in SHAPES.items()}
