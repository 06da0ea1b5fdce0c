"""Privacy accounting: what a set of releases costs one edge."""

from __future__ import annotations

from dataclasses import dataclass, field
from enum import Enum

from ..functions.noise import check_epsilon
from ..functions.pattern import NotSupported, RootedPattern


class Neighbouring(Enum):
    EDGE = "graphs that differ in one edge"
    NODE = "graphs that differ in one node and its edges"


@dataclass
class PrivacyLedger:
    """Releases and their epsilon; ``total`` is what one edge pays."""

    neighbouring: Neighbouring = Neighbouring.EDGE
    entries: list[tuple[str, float]] = field(default_factory=list)

    def __post_init__(self) -> None:
        if self.neighbouring is not Neighbouring.EDGE:
            raise NotSupported("only neighbouring by one edge is supported; a node can change every round of its neighbours")

    def sequential(self, name: str, *eps: float) -> PrivacyLedger:
        """Releases that the same edge can enter: their epsilons add up."""
        self.entries.append((name, sum(check_epsilon(e) for e in eps)))
        return self

    def parallel(self, name: str, *eps: float) -> PrivacyLedger:
        """Releases of which any edge enters one: the largest epsilon counts.  Public marks give no discount."""
        self.entries.append((name, max(check_epsilon(e) for e in eps)))
        return self

    def post(self, name: str) -> PrivacyLedger:
        """A function of released values: free."""
        self.entries.append((name, 0.0))
        return self

    @property
    def total(self) -> float:
        return sum(e for _, e in self.entries)

    def demand(self, budget: float) -> PrivacyLedger:
        if self.total > budget * (1 + 1e-9):
            raise ValueError(f"the releases cost {self.total:g}, more than {budget:g}: {self.entries}")
        return self


def walk_ledger(k: int, eps: float, variant: str = "rounds_k_minus_1") -> PrivacyLedger:
    out = PrivacyLedger()
    per = eps / (2 * max(1, k))
    counted = k if variant == "rounds_k" else k - 1
    for r in range(counted):
        out.sequential(f"round {r + 1}, both endpoints", per, per)
    if variant != "rounds_k":
        out.sequential("noisy degrees of both endpoints", per, per)
    return out.post("maxima and the total")


def tree_ledger(tree: RootedPattern, eps: float) -> PrivacyLedger:
    return PrivacyLedger().parallel("child sums: an edge enters the one whose marks it has", *[eps] * max(1, tree.k)).post("maxima, products and the total")


def star_ledger(eps: float) -> PrivacyLedger:
    return PrivacyLedger().sequential("two noisy degrees", eps / 2, eps / 2).post("falling products")


def averaged_ledger(n_rep: int, eps: float) -> PrivacyLedger:
    return PrivacyLedger().sequential(f"{n_rep} runs", *[eps / n_rep] * n_rep)


def baseline_ledger(method: str, eps: float) -> PrivacyLedger:
    if method == "noisy_graph":
        return PrivacyLedger().parallel("the one noisy bit of the pair", eps).post("estimators")
    if method in ("clipped_walk", "capped_star"):
        return PrivacyLedger().sequential("noisy maximum degree", eps / 10).sequential("counting", 0.9 * eps)
    raise ValueError(f"unknown method {method!r}")


def window_ledger(windows: int, eps: float) -> PrivacyLedger:
    """Continual release: an edge present in so many windows pays for each."""
    return PrivacyLedger().sequential(f"{windows} windows", *[eps] * windows)
