import itertools

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from patternldp.functions.pattern import ROOTED, NotSupported, Pattern, RootedPattern, path_tree
from patternldp.plans.mechanism_plan import explain, tree_plan, walk_plan


def test_tree_shapes():
    assert [len(Pattern.free_trees(n)) for n in range(1, 8)] == [1, 1, 1, 2, 3, 6, 11]


@given(st.lists(st.integers(0, 100), min_size=1, max_size=5))
@settings(max_examples=30, deadline=None)
def test_automorphisms_by_brute_force(picks):
    edges = [(p % (i + 1), i + 1) for i, p in enumerate(picks)]
    t = Pattern.of(edges)
    want = {frozenset(e) for e in t.edges}
    brute = sum({frozenset((q[a], q[b])) for a, b in t.edges} == want for q in itertools.permutations(range(t.n)))
    assert t.automorphisms == brute


def test_rounds_and_divisors():
    facts = {"fork": (3, 2), "fork_alt": (3, 2), "d22": (3, 8), "d22_alt": (4, 8), "spider2111": (3, 6), "d212": (4, 8), "path4_end": (5, 2), "path4_fold": (4, 2), "star4_centre": (2, 24), "star4_leaf": (3, 24)}
    for name, (rounds, divisor) in facts.items():
        assert (ROOTED[name].rounds, ROOTED[name].pattern().automorphisms) == (rounds, divisor), name


def test_ordering_and_rootings():
    t = Pattern.parse("0-1,1-2,1-3,3-4")
    for r in t.all_rootings():
        assert r.root == r.k and all(p is None or c < p for c, p in enumerate(r.parent))
        assert r.pattern().same_shape(t)
    assert path_tree(4).parent == (1, 2, 3, None, 3)


@pytest.mark.parametrize("text", ["0-1,1-2,2-0", "0-0"])
def test_cycles_are_refused(text):
    with pytest.raises(NotSupported):
        Pattern.parse(text)


@pytest.mark.parametrize("text", ["0-1,2-3", "a-b", "0-1,"])
def test_bad_texts(text):
    with pytest.raises(ValueError):
        Pattern.parse(text)


def test_bad_parents():
    with pytest.raises(ValueError):
        RootedPattern((1, 0))
    with pytest.warns(UserWarning):
        RootedPattern(tuple([*range(1, 14), None]))


def test_plans():
    assert walk_plan(4).rounds == 3 and walk_plan(4, "rounds_k").shuffles == 4
    assert len(tree_plan(ROOTED["d22"]).levels) == 2 and "kept by marks" in explain("path", 3)
