"""Tree-shaped patterns: parsing, rooting, ordering, automorphisms, catalogue.  Driver-side only; patterns are tiny."""

from __future__ import annotations

import functools
import math
import re
import warnings
from dataclasses import dataclass


class NotSupported(ValueError):
    """What the methods do not cover: cyclic patterns, node-level privacy."""


@dataclass(frozen=True)
class RootedPattern:
    """A tree on vertices 0..k; ``parent[v]`` is None for the root alone."""

    parent: tuple[int | None, ...]

    def __post_init__(self) -> None:
        n = len(self.parent)
        roots = [v for v, p in enumerate(self.parent) if p is None]
        if len(roots) != 1 or any(p is not None and not 0 <= p < n for p in self.parent):
            raise ValueError("one vertex must be the root and every parent a vertex")
        for v in range(n):
            seen, x = 0, v
            while self.parent[x] is not None:
                x, seen = self.parent[x], seen + 1
                if seen > n:
                    raise ValueError("the parents form a cycle")
        if self.k > 12:
            warnings.warn(f"the rescaling factor {self.factor:.3g} is very large", stacklevel=2)

    @property
    def k(self) -> int:
        return len(self.parent) - 1

    @property
    def root(self) -> int:
        return self.parent.index(None)

    @property
    def factor(self) -> int:
        """What a count under random marks is multiplied by."""
        return (self.k + 1) ** (self.k + 1)

    @functools.cached_property
    def children(self) -> dict[int, list[int]]:
        return {v: [c for c, p in enumerate(self.parent) if p == v] for v in range(len(self.parent))}

    @property
    def leaves(self) -> list[int]:
        return [v for v, c in self.children.items() if not c and v != self.root]

    @property
    def internal(self) -> list[int]:
        return [v for v in range(len(self.parent)) if v not in self.leaves]

    def height(self, v: int) -> int:
        return 1 + max((self.height(c) for c in self.children[v]), default=-1)

    @property
    def levels(self) -> list[list[int]]:
        """Internal vertices by height: those of one level depend on lower ones only."""
        by: dict[int, list[int]] = {}
        for v in self.internal:
            by.setdefault(self.height(v), []).append(v)
        return [by[h] for h in sorted(by)]

    @property
    def rounds(self) -> int:
        """Protocol rounds, the marking included."""
        return self.k + 2 - len(self.leaves)

    @property
    def edges(self) -> list[tuple[int, int]]:
        return [(v, p) for v, p in enumerate(self.parent) if p is not None]

    def ordered(self) -> RootedPattern:
        """The same tree with children numbered before parents, siblings in their order, the root last."""
        order: list[int] = []

        def visit(v: int) -> None:
            for c in self.children[v]:
                visit(c)
            order.append(v)

        visit(self.root)
        at = {v: i for i, v in enumerate(order)}
        return RootedPattern(tuple(None if self.parent[v] is None else at[self.parent[v]] for v in order))  # type: ignore[index]

    def pattern(self) -> Pattern:
        return Pattern.of(self.edges, len(self.parent))


@dataclass(frozen=True)
class Pattern:
    """An unrooted tree on vertices 0..k."""

    n: int
    edges: tuple[tuple[int, int], ...]

    @staticmethod
    def of(edges, n: int | None = None) -> Pattern:
        e = tuple(sorted({(min(a, b), max(a, b)) for a, b in edges}))
        n = n if n is not None else 1 + max((b for _, b in e), default=0)
        if any(a == b for a, b in e):
            raise NotSupported("a pattern has no loops")
        group = list(range(n))
        for a, b in e:
            if group[a] == group[b]:
                raise NotSupported("the pattern has a cycle; only trees are supported")
            group = [group[a] if g == group[b] else g for g in group]
        if len(set(group)) > 1:
            raise ValueError("the pattern is not connected")
        return Pattern(n, e)

    @staticmethod
    def parse(text: str) -> Pattern:
        """From text such as ``0-1,1-2,1-3``; an empty text is the single vertex."""
        text = text.strip()
        if not text:
            return Pattern.of([], 1)
        if not re.fullmatch(r"\d+\s*-\s*\d+(\s*,\s*\d+\s*-\s*\d+)*", text):
            raise ValueError(f"not a pattern: {text!r}")
        return Pattern.of([tuple(map(int, p.split("-"))) for p in text.split(",")])

    @property
    def k(self) -> int:
        return self.n - 1

    def neighbours(self, v: int) -> list[int]:
        return sorted([b for a, b in self.edges if a == v] + [a for a, b in self.edges if b == v])

    def rooted_at(self, root: int) -> RootedPattern:
        parent: list[int | None] = [None] * self.n
        todo, seen = [root], {root}
        while todo:
            v = todo.pop()
            for w in self.neighbours(v):
                if w not in seen:
                    parent[w] = v
                    seen.add(w)
                    todo.append(w)
        return RootedPattern(tuple(parent))

    def all_rootings(self) -> list[RootedPattern]:
        return [self.rooted_at(v).ordered() for v in range(self.n)]

    def best_rooting(self) -> RootedPattern:
        """Least height, then fewest internal vertices: fewest shuffles; error and privacy do not depend on it."""
        return min(self.all_rootings(), key=lambda t: (len(t.levels), len(t.internal)))

    def _code(self, v: int, up: int | None = None) -> str:
        return "(" + "".join(sorted(self._code(w, v) for w in self.neighbours(v) if w != up)) + ")"

    def _symmetries(self, v: int, up: int | None = None) -> int:
        codes = [self._code(w, v) for w in self.neighbours(v) if w != up]
        own = math.prod(math.factorial(codes.count(c)) for c in set(codes))
        return own * math.prod(self._symmetries(w, v) for w in self.neighbours(v) if w != up)

    @functools.cached_property
    def automorphisms(self) -> int:
        """Ordered counts are this many times the unordered ones."""
        codes = [self._code(v) for v in range(self.n)]
        return codes.count(codes[0]) * self._symmetries(0)

    def same_shape(self, other: Pattern) -> bool:
        return self.n == other.n and {self._code(v) for v in range(self.n)} == {other._code(v) for v in range(other.n)}

    @staticmethod
    def path(k: int) -> Pattern:
        return Pattern.of([(i, i + 1) for i in range(k)], k + 1)

    @staticmethod
    def star(k: int) -> Pattern:
        return Pattern.of([(i, k) for i in range(k)], k + 1)

    @staticmethod
    def spider(*legs: int) -> Pattern:
        edges, at = [], 1
        for leg in legs:
            last = 0
            for _ in range(leg):
                edges.append((last, at))
                last, at = at, at + 1
        return Pattern.of(edges, at)

    @staticmethod
    def caterpillar(*legs: int) -> Pattern:
        """A spine with so many legs at each of its vertices."""
        edges = [(i, i + 1) for i in range(len(legs) - 1)]
        at = len(legs)
        for i, n in enumerate(legs):
            edges += [(i, at + j) for j in range(n)]
            at += n
        return Pattern.of(edges, at)

    @staticmethod
    def broom(handle: int, bristles: int) -> Pattern:
        return Pattern.spider(handle, *[1] * bristles)

    @staticmethod
    def free_trees(n: int) -> list[Pattern]:
        """One tree of each shape on ``n`` vertices, for small ``n``."""
        shapes = [Pattern.of([], 1)]
        for size in range(2, n + 1):
            grown: dict[frozenset, Pattern] = {}
            for t in shapes:
                for v in range(size - 1):
                    p = Pattern.of([*t.edges, (v, size - 1)], size)
                    grown.setdefault(frozenset(p._code(x) for x in range(size)), p)
            shapes = list(grown.values())
        return shapes


def path_tree(k: int) -> RootedPattern:
    """A path rooted at its last vertex but one: positions 0..k-1 are a chain, k hangs on k-1."""
    if k < 1:
        raise ValueError("a path has at least one edge")
    return RootedPattern(tuple([*range(1, k), None, k - 1])) if k > 1 else RootedPattern((None, 0))


# The rooted patterns of the experiments, children before parents, the root last.
ROOTED = {
    "fork": RootedPattern((1, 4, 4, 4, None)),
    "fork_alt": RootedPattern((4, 3, 3, 4, None)),
    "d22": RootedPattern((2, 2, 5, 5, 5, None)),
    "d22_alt": RootedPattern((2, 2, 4, 4, 5, None)),
    "spider2111": RootedPattern((1, 5, 5, 5, 5, None)),
    "d212": RootedPattern((2, 2, 6, 5, 5, 6, None)),
    "spider2211": RootedPattern((1, 6, 3, 6, 6, 6, None)),
    "spider3111": RootedPattern((1, 2, 6, 6, 6, 6, None)),
    "d22_leg": RootedPattern((1, 3, 3, 6, 6, 6, None)),
    "path4_end": RootedPattern((1, 2, 3, 4, None)),
    "path4_fold": RootedPattern((1, 4, 3, 4, None)),
    "star4_centre": RootedPattern((4, 4, 4, 4, None)),
    "star4_leaf": RootedPattern((3, 3, 3, 4, None)),
}
