"""Tree templates and how they are split.

A template is a rooted tree given by a parent array: node 0 is the root, its parent is -1, and every
other node names an earlier one.  All of this is driver-side and depends on the template's size only.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cached_property, lru_cache

#: Fixed parent arrays of the catalogue: trees that have the published memory and work terms.
CATALOGUE: dict[str, tuple[int, ...]] = {
    "u3-1": (-1, 0, 0),
    "u5-2": (-1, 0, 1, 2, 3),
    "u7-2": (-1, 0, 1, 2, 0, 4, 5),
    "u10-2": (-1, 0, 1, 1, 0, 4, 5, 5, 7, 7),
    "u12-1": (-1, 0, 1, 2, 3, 4, 5, 6, 7, 8, 9, 10),
    "u12-2": (-1, 0, 1, 1, 0, 4, 5, 6, 6, 5, 9, 9),
    "u13": (-1, 0, 1, 1, 3, 0, 5, 5, 7, 0, 9, 10, 10),
    "u14": (-1, 0, 0, 2, 2, 4, 4, 6, 7, 6, 9, 9, 11, 11),
    "u15-1": (-1, 0, 0, 2, 2, 4, 4, 6, 7, 7, 6, 10, 10, 12, 12),
    "u15-2": (-1, 0, 1, 1, 0, 4, 5, 6, 5, 8, 9, 9, 8, 12, 12),
    "edge2": (-1, 0),
    "path4": (-1, 0, 1, 2),
    "star4": (-1, 0, 0, 0),
    "star5": (-1, 0, 0, 0, 0),
    "fork5": (-1, 0, 1, 1, 0),
}
PUBLISHED = ("u3-1", "u5-2", "u7-2", "u10-2", "u12-1", "u12-2", "u13", "u14", "u15-1", "u15-2")

Shape = tuple  # nested tuples of branches, sorted; () is a single vertex


def size(shape: Shape) -> int:
    return 1 + sum(map(size, shape))


def _key(shape: Shape) -> tuple:
    return (size(shape), shape)


@dataclass(frozen=True)
class TreeTemplate:
    """A tree with k vertices."""

    parents: tuple[int, ...]

    def __post_init__(self):
        p = tuple(self.parents)
        if not p or p[0] != -1 or any(not 0 <= q < i for i, q in enumerate(p) if i):
            raise ValueError("a template is a connected tree: node 0 has parent -1, every other an earlier node")
        object.__setattr__(self, "parents", p)

    @classmethod
    def named(cls, name: str) -> TreeTemplate:
        return cls(CATALOGUE[name])

    @classmethod
    def path(cls, k: int) -> TreeTemplate:
        return cls(tuple(range(-1, k - 1)))

    @classmethod
    def star(cls, k: int) -> TreeTemplate:
        return cls((-1, *[0] * (k - 1)))

    @classmethod
    def from_edges(cls, edges: list[tuple[int, int]], root: int | None = None) -> TreeTemplate:
        """Any numbering; refuses graphs with a cycle or several components."""
        near: dict[int, list[int]] = {}
        for a, b in edges:
            near.setdefault(a, []).append(b)
            near.setdefault(b, []).append(a)
        if len(edges) != len(near) - 1:
            raise ValueError("the template has a cycle or several components")
        start = min(near) if root is None else root
        order, parent, at = [start], {start: -1}, 0
        while at < len(order):
            for u in sorted(near[order[at]]):
                if u not in parent:
                    parent[u] = order[at]
                    order.append(u)
            at += 1
        if len(order) != len(near):
            raise ValueError("the template has a cycle or several components")
        number = {v: i for i, v in enumerate(order)}
        return cls(tuple(number.get(parent[v], -1) for v in order))

    @property
    def k(self) -> int:
        return len(self.parents)

    @cached_property
    def edges(self) -> list[tuple[int, int]]:
        return [(p, i) for i, p in enumerate(self.parents) if p >= 0]

    @cached_property
    def near(self) -> list[list[int]]:
        out: list[list[int]] = [[] for _ in self.parents]
        for a, b in self.edges:
            out[a].append(b)
            out[b].append(a)
        return out

    def shape(self, root: int = 0, without: int = -1) -> Shape:
        """Canonical form of the tree seen from ``root``."""
        return tuple(sorted((self.shape(u, root) for u in self.near[root] if u != without), key=_key))

    @cached_property
    def automorphisms(self) -> int:
        """Symmetries of the free tree: those that fix the root times the images of the root."""
        return rooted_symmetries(self.shape()) * self.root_orbit

    @cached_property
    def root_orbit(self) -> int:
        """Vertices that some symmetry maps the root to."""
        own = self.shape()
        return sum(self.shape(v) == own for v in range(self.k))


def rooted_symmetries(shape: Shape) -> int:
    out = 1
    for s in set(shape):
        n = shape.count(s)
        out *= math.factorial(n) * rooted_symmetries(s) ** n
    return out


@dataclass(frozen=True)
class SplitStep:
    """``whole`` is ``keep`` (with the root) and ``cut`` (rooted at the cut edge's other end), counted ``d`` times."""

    whole: Shape
    keep: Shape
    cut: Shape
    d: int

    @property
    def sizes(self) -> tuple[int, int, int]:
        return size(self.whole), size(self.keep), size(self.cut)


def _split(shape: Shape, order: str) -> SplitStep:
    # the branches of a canonical shape are sorted by size, then form
    at = {"heavy": len(shape) - 1, "light": 0}[order]
    cut = shape[at]
    keep = shape[:at] + shape[at + 1 :]
    return SplitStep(shape, keep, cut, shape.count(cut))


def _steps(shape: Shape, order: str, share: bool) -> list[SplitStep]:
    out: list[SplitStep] = []

    def visit(s: Shape) -> None:
        if not s or (share and any(x.whole == s for x in out)):
            return
        step = _split(s, order)
        visit(step.keep)
        visit(step.cut)
        out.append(step)

    visit(shape)
    return out


@dataclass(frozen=True)
class SplitPlan:
    """Steps in the order of computation; with ``share`` equal sub-templates are computed once."""

    template: TreeTemplate
    steps: tuple[SplitStep, ...]
    root_orbit: int

    @property
    def top(self) -> Shape:
        return self.steps[-1].whole if self.steps else ()


def split_plan(template: TreeTemplate, root: int | None = None, order: str = "heavy", share: bool = True) -> SplitPlan:
    """Recursive split of a template; ``best`` tries all roots and both orders for the least work."""
    if order == "best":
        options = [(sum(math.comb(template.k, t) * math.comb(t, a) for t, a, _ in (s.sizes for s in _steps(template.shape(r), o, share))), r, o) for r in range(template.k) for o in ("heavy", "light")]
        _, root, order = min(options)
    r = root or 0
    own = template.shape(r)
    orbit = sum(template.shape(v) == own for v in range(template.k))
    return SplitPlan(template, tuple(_steps(own, order, share)), orbit)


def inner_sizes(template: TreeTemplate) -> Iterator[tuple[int, int]]:
    """(size, kept size) of every split sub-template but the whole, repeats counted again."""
    for s in split_plan(template, share=False).steps[:-1]:
        yield s.sizes[0], s.sizes[1]


def memory_terms(template: TreeTemplate) -> int:
    return sum(math.comb(template.k, t) for t, _ in inner_sizes(template))


def work_terms(template: TreeTemplate) -> int:
    return sum(math.comb(template.k, t) * math.comb(t, a) for t, a in inner_sizes(template))


def intensity(template: TreeTemplate) -> float:
    m = memory_terms(template)
    return work_terms(template) / m if m else 0.0


@lru_cache(maxsize=None)
def rooted_shapes(k: int) -> tuple[Shape, ...]:
    """All rooted trees with k vertices."""
    if k == 1:
        return ((),)
    out = set()

    def extend(left: int, least: tuple, branches: tuple) -> None:
        if not left:
            out.add(tuple(sorted(branches, key=_key)))
        for n in range(1, left + 1):
            for s in rooted_shapes(n):
                if _key(s) >= least:
                    extend(left - n, _key(s), (*branches, s))

    extend(k - 1, (0, ()), ())
    return tuple(sorted(out))


def from_shape(shape: Shape) -> TreeTemplate:
    parents = [-1]

    def add(s: Shape, at: int) -> None:
        for b in s:
            parents.append(at)
            add(b, len(parents) - 1)

    add(shape, 0)
    return TreeTemplate(tuple(parents))


@lru_cache(maxsize=None)
def all_free_trees(k: int) -> tuple[TreeTemplate, ...]:
    """One template for each free tree with k vertices."""
    seen = {}
    for s in rooted_shapes(k):
        t = from_shape(s)
        seen.setdefault(min((t.shape(v) for v in range(k)), key=_key), t)
    return tuple(seen.values())


def n_colorings(k: int, eps: float, delta: float, const: float = 1.0, cap: int | None = None) -> tuple[int, int]:
    """(number of colourings, number of groups): the number is a multiple of the odd number of groups."""
    t = max(1, math.ceil(math.log(1 / delta)))
    t += 1 - t % 2
    n = math.ceil(const * math.exp(k) * math.log(1 / delta) / eps**2)
    n = min(n, cap) if cap else n
    return math.ceil(n / t) * t, t


def scale_up(k: int, c: int | None = None) -> float:
    """Reciprocal of the probability that k vertices get different ones of c colours."""
    c = c or k
    return c**k * math.factorial(c - k) / math.factorial(c)
