import pytest

from huecount.catalogue import _TREES
from huecount.plans.plan import contractible_cycles, decompose, enumerate_plans, heuristic, plan_for, validate
from huecount.plans.query import CATALOGUE, automorphisms, build, check_tree_decomposition, is_bipartite, is_tree, is_treewidth_le2, parse


@pytest.mark.parametrize("name", _TREES)
def test_number_of_plans_and_automorphisms(name):
    q = CATALOGUE[name]
    plans = enumerate_plans(q)
    assert (len(plans), automorphisms(q)) == _TREES[name]
    for p in plans:
        assert validate(p) == (1 if is_tree(q) else 2)


def test_refused_queries():
    k4 = parse("ab ac ad bc bd cd")
    assert not is_treewidth_le2(k4)
    for f in (decompose, enumerate_plans):
        with pytest.raises(ValueError):
            f(k4)
    for bad in ("", "aa", "ab cd", "abc"):
        with pytest.raises(ValueError):
            parse(bad)


def test_worked_decomposition():
    p = plan_for(CATALOGUE["satellite11"])
    got = {(b.kind, frozenset(b.seq), frozenset(b.boundary)) for b in p.blocks}
    want = [("cycle", "abcde", "ac"), ("leaf", "fh", "f"), ("cycle", "acfg", "fg"), ("cycle", "fgi", "i"), ("cycle", "ijk", "")]
    assert got == {(k, frozenset(s), frozenset(b)) for k, s, b in want}
    assert "cycle i-j-k" in p.explain()


def test_heuristic_prefers_short_cycles():
    plans = enumerate_plans(CATALOGUE["satellite11"])
    assert {p.cost_key()[0] for p in plans} == {5, 6}
    assert heuristic(plans).cost_key()[0] == 5


def test_cycles_are_induced_and_found_once():
    near = parse("ab bc cd da ac").neighbours()
    assert {frozenset(m[1]) for m in contractible_cycles(near)} == {frozenset("abc"), frozenset("acd")}
    assert len(contractible_cycles(CATALOGUE["c8"].neighbours())) == 1


def test_tree_decomposition_properties():
    q = CATALOGUE["c4"]
    assert check_tree_decomposition(q, [set("abc"), set("acd")], [(0, 1)]) == 2
    with pytest.raises(ValueError):
        check_tree_decomposition(q, [set("ab"), set("bcd")], [(0, 1)])
    with pytest.raises(ValueError):
        check_tree_decomposition(CATALOGUE["path4"], [set("ab"), set("cd"), set("bc")], [(0, 1), (1, 2)])


def test_small_facts():
    assert is_bipartite(CATALOGUE["c6"]) and not is_bipartite(CATALOGUE["c5"])
    assert parse("n1-n2 n2-n1 n2-n3").edges == (("n1", "n2"), ("n2", "n3"))
    assert build("x", [("b", "a")]).nodes == ("a", "b")
