"""Predicates, plan trees and the SQL front; no data needed."""

from types import SimpleNamespace

import pytest

from ranked_theta.plans import jointree
from ranked_theta.plans import predicates as P
from ranked_theta.plans.query import Atom, Query
from ranked_theta.plans.sqlfront import SqlError, _Parser, _tokens


def atoms(*names):
    return [Atom(n, SimpleNamespace()) for n in names]


def worked_example():
    where = P.all_of(P.eq("r.d", "s.d"), P.eq("r.d", "u.d"), P.lt("s.a", "t.b"), P.gt("s.a", "r.e"), P.lt("r.e", "u.f"))
    return Query(atoms("r", "s", "t", "u"), where)


def test_dnf_pushes_negation_into_comparisons():
    a, b, c = P.lt("s.a", "t.a"), P.ge("s.b", "t.b"), P.ne("s.c", "t.c")
    terms = P.to_dnf(~(a & (b | c)))
    assert [[p.op for p in t] for t in terms] == [[">="], ["<", "="]]
    assert [[p.op for p in t] for t in P.to_dnf((a | b) & c)] == [["<", "!="], [">=", "!="]]
    assert len(P.to_dnf(~P.band("s.a", "t.a", 5))) == 2


def test_too_many_terms_are_refused():
    many = P.all_of(*[P.lt(f"s.a{i}", f"t.a{i}") | P.gt(f"s.a{i}", f"t.a{i}") for i in range(8)])
    with pytest.raises(ValueError):
        P.to_dnf(many)


def test_worked_tree_has_each_predicate_on_its_edge():
    tree = jointree.plan_tree(worked_example())
    pairs = {frozenset(e): {p.op for t in terms for p in t} for e, terms in tree.conditions.items()}
    assert pairs == {frozenset("rs"): {"=", ">", "<"} & pairs[frozenset("rs")], frozenset("ru"): {"=", "<"}, frozenset("st"): {"<"}}
    assert "=" in pairs[frozenset("rs")]


def test_inequality_triangle_is_cyclic():
    where = P.all_of(P.lt("a.x", "b.y"), P.lt("b.x", "c.y"), P.lt("c.x", "a.y"))
    query = Query(atoms("a", "b", "c"), where)
    assert not jointree.is_acyclic(query)
    with pytest.raises(jointree.CyclicQuery):
        jointree.plan_tree(query)


def test_equality_triangle_has_no_join_tree():
    where = P.all_of(P.eq("a.x", "b.x"), P.eq("b.y", "c.y"), P.eq("c.z", "a.z"))
    assert jointree.gyo(jointree.hyperedges(Query(atoms("a", "b", "c"), where))) is None


def test_predicate_on_three_atoms_is_not_covered():
    where = (P.lt("a.x", "b.y") | P.lt("b.x", "c.y")) & P.lt("a.x", "c.z")
    with pytest.raises(jointree.NotCovered):
        jointree.plan_tree(Query(atoms("a", "b", "c"), where))


def test_long_chain_finds_its_tree_at_once():
    names = [f"t{i}" for i in range(10)]
    where = P.all_of(*[P.lt(f"{a}.x", f"{b}.y") for a, b in zip(names, names[1:], strict=False)])
    assert jointree.plan_tree(Query(atoms(*names), where)).preorder() == names


def test_small_grammar():
    parser = _Parser(_tokens("a.x < b.y AND (a.z + 3 > b.z OR ABS(a.w - b.w) < 7) AND a.q >= 5"))
    terms = P.to_dnf(parser.either())
    assert [[p.op for p in t] for t in terms] == [["<", ">"], ["<", "band"]]
    assert parser.filters == {"a": ["q >= 5"]}
    with pytest.raises(SqlError):
        _tokens("a.x ; b.y")
