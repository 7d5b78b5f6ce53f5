from fractions import Fraction as Fr

import pytest

from motifjoin.operators.balanced import min_batch
from motifjoin.plans import rewrites as rw
from motifjoin.plans.agm import agm_bound, fractional_cover
from motifjoin.plans.ordering import attribute_order
from motifjoin.plans.query import PATTERNS, Atom, JoinQuery, parse_query
from motifjoin.plans.stages import compile_stages, delta_rules, describe


@pytest.mark.parametrize("name, power", [("triangle", Fr(3, 2)), ("cyclic_triangle", Fr(3, 2)), ("four_clique", 2), ("diamond", 2), ("house", Fr(5, 2)), ("five_clique", Fr(5, 2))])
def test_bound_exponents(name, power):
    b = agm_bound(PATTERNS[name], {"e": 1000})
    assert b.exponent == power and b.value == pytest.approx(1000.0 ** float(power))


def test_bound_uses_sizes():
    q = parse_query("q(a,b,c) := R(a,b), S(b,c), T(a,c)")
    assert agm_bound(q, {"R": 10, "S": 10, "T": 10**9}).value == pytest.approx(100)
    assert agm_bound(q, {"R": 10, "S": 0, "T": 10}).value == 0
    assert fractional_cover([frozenset("ab"), frozenset("bc"), frozenset("ca")], [Fr(1)] * 3) == (Fr(1, 2),) * 3


def test_parse():
    q = parse_query("tri(a, b, c) := e(a,b), e(a,c), e(b,c), a < b, b != c")
    assert q.atoms[1] == Atom("e", ("a", "c")) and q.filters == (("a", "<", "b"), ("b", "<>", "c")) and q.order == ("a", "b", "c")
    for bad in ("tri(a) = e(a,b)", "t(a) := e(a,b)", "t(a,b) := e(a,b) e(b,a)", "t(a,b) :="):
        with pytest.raises(ValueError):
            parse_query(bad)
    assert q.connected() and not parse_query("t(a,b,c,d) := e(a,b), e(c,d)").connected()


def test_stages_take_lists_by_the_definition():
    order = ("a1", "a2", "a3", "a4")
    s3, s4 = compile_stages(PATTERNS["diamond"], order, 2, seed_atoms=[0])
    assert [(u.key_attrs, u.key_pos, u.ext_pos) for u in s3.uses] == [(("a2",), (0,), 1)]
    # a4 is the source of its edges: values come from the incoming lists of a1 and a3
    assert [(u.key_attrs, u.key_pos, u.ext_pos) for u in s4.uses] == [(("a1",), (1,), 0), (("a3",), (1,), 0)]
    assert "a4: smallest of e.new[a1]->a4, e.new[a3]->a4" in describe([s4])


def test_ternary_atoms_take_part_by_projection():
    q = parse_query("t(o,p,s) := OPS(o,p,s), OP(o,p), PS(p,s)")
    stages = compile_stages(q, ("o", "p", "s"), 0)
    assert [[(u.relation, u.key_pos) for u in s.uses] for s in stages] == [[("OPS", ()), ("OP", ())], [("OPS", (0,)), ("OP", (0,)), ("PS", ())], [("OPS", (0, 1)), ("PS", (0,))]]


def test_orders():
    q = PATTERNS["diamond"]
    assert attribute_order(q, "lead", 2)[:2] == ("a4", "a1") and attribute_order(q, "edge_seed")[:2] == ("a1", "a2")
    assert set(attribute_order(q, "connected")) == set(q.attrs)
    with pytest.raises(ValueError):
        attribute_order(q, "none")


def test_delta_rules():
    rules = delta_rules(PATTERNS["triangle"])
    assert [r.versions for r in rules] == [("delta", "old", "old"), ("new", "delta", "old"), ("new", "new", "delta")]
    assert all(r.order[:2] == PATTERNS["triangle"].atoms[r.lead].attrs for r in rules)


@pytest.mark.parametrize("name, n", [("triangle", 6), ("four_clique", 24), ("five_clique", 120), ("diamond", 8), ("house", 4)])
def test_automorphisms(name, n):
    assert len(rw.automorphisms(PATTERNS[name])) == n


def test_symmetry_and_factors():
    assert rw.break_symmetry(PATTERNS["diamond"]) == (("a1", "<", "a2"), ("a1", "<", "a3"), ("a1", "<", "a4"), ("a2", "<", "a4"))
    plan = rw.factorize(PATTERNS["house"])
    assert plan.core.attrs == ("a1", "a2", "a3") and [a for a, _ in plan.tails] == ["a4", "a5"]
    tri = rw.rewrite_with_triangles(PATTERNS["house"])
    covered = {(t.attrs[i], t.attrs[j]) for t in tri.atoms for i in range(len(t.attrs)) for j in range(i + 1, len(t.attrs))}
    assert {a.attrs for a in PATTERNS["house"].atoms} <= covered


def test_min_batch_and_injective():
    assert min_batch(8, 1000, 1000**1.5) == 139 and min_batch(64, 10, 10) == 64 * 64
    assert len(PATTERNS["triangle"].injective().filters) == 3


def test_bind_checks(spark):
    e = spark.createDataFrame([(1, 2)], "a int, b long")
    s = spark.createDataFrame([("x", "y")], "a string, b string")
    with pytest.raises(TypeError):
        parse_query("q(a,b,c) := e(a,b), s(b,c)").bind({"e": e, "s": s})
    with pytest.raises(ValueError):
        JoinQuery("q", (Atom("e", ("a",)),)).bind({"e": e})
    with pytest.raises(KeyError):
        parse_query("q(a,b) := r(a,b)").bind({"e": e})
    assert dict(parse_query("q(a,b) := e(a,b)").bind({"e": e})["e"].dtypes) == {"c0": "bigint", "c1": "bigint"}
