"""A mechanism as a list of levels, before it becomes tables: what is summed, with which noise, and what it costs."""

from __future__ import annotations

from dataclasses import dataclass

from ..functions.pattern import Pattern, RootedPattern, path_tree


@dataclass(frozen=True)
class Level:
    vertices: tuple[int, ...]
    children: tuple[tuple[int, ...], ...]
    scale: str
    shuffles: int


@dataclass(frozen=True)
class MechanismPlan:
    name: str
    levels: tuple[Level, ...]
    rewrites: tuple[str, ...]
    rounds: int

    @property
    def shuffles(self) -> int:
        return sum(x.shuffles for x in self.levels)

    def explain(self) -> str:
        lines = [f"{self.name}: {self.rounds} rounds, {self.shuffles} shuffles by receiver"]
        lines += [f"  level {i + 1}: vertices {list(x.vertices)} from {[list(c) for c in x.children]}, noise {x.scale}" for i, x in enumerate(self.levels)]
        return "\n".join(lines + [f"  rewrite: {r}" for r in self.rewrites])


def walk_plan(k: int, variant: str = "rounds_k_minus_1") -> MechanismPlan:
    last = k if variant == "rounds_k" else k - 1
    levels = [Level((r,), ((r - 1,),), f"2k/eps * max|x{r - 1}|" if r > 1 else "2k/eps", 1) for r in range(1, last + 1)]
    rewrites = ["the first sum is the degree: no join", "the maximum is a one-row aggregate"]
    if variant != "rounds_k":
        rewrites.append("the last edge is the noisy degree: one round fewer")
    return MechanismPlan(f"walk {k}", tuple(levels), tuple(rewrites), max(1, last))


def tree_plan(tree: RootedPattern) -> MechanismPlan:
    levels = [Level(tuple(vs), tuple(tuple(tree.children[v]) for v in vs), "max|x_child|/eps, 1/eps for leaves", 1 + any(c not in tree.leaves for v in vs for c in tree.children[v])) for vs in tree.levels]
    return MechanismPlan(f"tree {tree.parent}", tuple(levels), ("arcs kept by marks before any shuffle", "leaves are literals: no join", "vertices of one height share a job", "no budget split"), tree.rounds)


def choose_rooting(pattern: Pattern) -> RootedPattern:
    return pattern.best_rooting()


def explain(kind: str, k: int = 0, tree: RootedPattern | None = None) -> str:
    if kind == "walk":
        return walk_plan(k).explain()
    return tree_plan(tree if tree is not None else path_tree(k)).explain()
