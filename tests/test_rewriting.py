"""Rewriting against the bounded chase on random small instances, and the traps one by one."""

import random
from dataclasses import replace
from itertools import product

import pytest

from derivatrace.operators.finiteness import pumping_bodies
from derivatrace.operators.provenance import constrained_bodies
from derivatrace.plans.cq import blanked, canonical, parse_cq
from derivatrace.plans.ontology import Ontology, normalise_inverses, parse_axiom
from derivatrace.plans.rewrite import TooManyRewritings, atom_closure, by_shape, contained, foldings, pruned, rewrite_compute, rewrite_decide, rewrite_literal
from tests.brute import answers, chase, matches, random_instance


def by_rewriting(cq, ontology, facts):
    out = set()
    for r in rewrite_compute(cq, ontology.axioms):
        for env, monos in matches([a[:2] for a in r.atoms], facts):
            out.add((tuple(env[h] for h in cq.head), frozenset(r.labels).union(*monos)))
    return out


def by_literal(cq, ontology, facts):
    out = set()
    for body in rewrite_literal(cq, ontology.axioms):
        for env, monos in matches([a[:2] for a in body], facts):
            out.add((tuple(env[h] for h in cq.head), frozenset(x for a in body for x in a[2]).union(*monos)))
    return out


def by_foldings(cq, ontology, facts):
    out = set()
    for body, sets in foldings(cq, ontology.axioms).items():
        closures = [atom_closure(p, a, list(ontology.positive)) for p, a in body]
        for choice in product(*[[(atom, way) for atom, ways in c.items() for way in ways] for c in closures]):
            for env, monos in matches([atom for atom, _ in choice], facts):
                for labels in sets:
                    out.add((tuple(env[h] for h in cq.head), frozenset(labels).union(*monos, *[w for _, w in choice])))
    return out


def test_all_forms_equal_the_chase():
    rng, filled, more = random.Random(5), 0, 0
    for _ in range(250):
        ontology, facts, cq = random_instance(rng)
        if (closed := chase(facts, ontology, depth=4)) is None:
            continue
        want = answers(cq, closed)
        assert by_rewriting(cq, ontology, facts) == want
        assert by_foldings(cq, ontology, facts) == want
        literal = by_literal(cq, ontology, facts)
        assert literal <= want
        filled, more = filled + bool(want), more + (literal != want)
    assert filled > 40


def test_general_level_equals_the_bounded_chase():
    rng, filled = random.Random(8), 0
    for _ in range(250):
        ontology, facts, cq = random_instance(rng, axioms=2, atoms=2, facts=3)
        facts = {(p, a, tuple(sorted(m))) for p, a, m in facts}
        if (closed := chase(facts, ontology, depth=6, general=True, degree=5)) is None:
            continue
        want = {x for x in answers(cq, closed, general=True) if len(x[1]) <= 5}
        got = set()
        for r in rewrite_compute(cq, ontology.axioms, level="general", max_degree=5):
            for env, monos in matches([a[:2] for a in r.atoms], facts):
                mono = tuple(sorted([*r.labels, *(x for m, a in zip(monos, r.atoms, strict=True) for x in m * a[2])]))
                if len(mono) <= 5:
                    got.add((tuple(env[h] for h in cq.head), mono))
        assert got == want
        filled += bool(want)
    assert filled > 50


def test_native_inverses_equal_normalised_ones():
    rng = random.Random(13)
    for _ in range(150):
        ontology, facts, cq = random_instance(rng, axioms=2, atoms=2)
        flat, fresh = normalise_inverses(ontology)
        assert all(str(a).count("-") <= 1 for a in flat.axioms)
        got = {(row, mono - fresh) for row, mono in by_rewriting(cq, flat, facts)}
        assert got == by_rewriting(cq, ontology, facts)


CHAIN = Ontology.parse(["A <= exists p @v", "exists p- <= exists q @w"])
TWO = Ontology.parse(["A <= exists p @v", "p <= r @w", "p <= r @k"])
FACT = {("A", ("a",), frozenset("u"))}


def test_merging_needs_no_equal_labels():
    cq = parse_cq("q() :- p(x, y), q(y, z)")
    assert by_rewriting(cq, CHAIN, FACT) == {((), frozenset("uvw"))} and by_literal(cq, CHAIN, FACT) == set()
    cq = parse_cq("q() :- r(x, y), r(z, y)")
    assert by_rewriting(cq, TWO, FACT) == {((), frozenset("uvw")), ((), frozenset("uvk")), ((), frozenset("uvwk"))}
    assert by_literal(cq, TWO, FACT) == {((), frozenset("uvw")), ((), frozenset("uvk"))}


def test_equal_atoms_stay_two():
    cq = parse_cq("q() :- r(x, y), r(z, y)")
    facts = {("r", ("a", "b"), frozenset("1")), ("r", ("c", "b"), frozenset("2"))}
    assert by_rewriting(cq, Ontology(), facts) == {((), frozenset(m)) for m in ("1", "2", "12")}


def test_the_start_query_is_blanked():
    cq = parse_cq("q(x) :- p(x, y)")
    assert blanked(cq.atoms)[0].args[1] == ("b", "")
    assert by_rewriting(cq, CHAIN, FACT) == {(("a",), frozenset("uv"))}


def test_canonical_forms():
    a = canonical([("r", (("v", "x"), ("v", "y"))), ("r", (("v", "y"), ("v", "x"))), ("A", (("v", "x"),))])
    b = canonical([("A", (("v", "m"),)), ("r", (("v", "n"), ("v", "m"))), ("r", (("v", "m"), ("v", "n")))])
    assert a == b and len(canonical([("A", (("b", ""),)), ("A", (("b", ""),))])) == 2


def test_containment_pruning():
    small, large = parse_cq("q(x) :- A(x)"), parse_cq("q(x) :- A(x), r(x, y)")
    rows = lambda q: tuple((a.pred, a.args) for a in blanked(q.atoms))
    assert contained(rows(large), rows(small)) and not contained(rows(small), rows(large))
    assert pruned([rows(large), rows(small)]) == [rows(small)]


def test_parsing():
    assert str(parse_axiom("exists placedBy- <= Customer @a15")) == "exists placedBy- <= Customer @a15"
    assert parse_axiom("A <= not B").neg and parse_axiom("p <= q- @k").rhs.inv
    cq = parse_cq("""q(x) :- Order(o)@{r7*m1}, placedBy(o, x)@?p, A("c/1"), s(_, _)""")
    assert [a.mono for a in cq.atoms] == [("m1", "r7"), "?p", None, None] and cq.atoms[2].args == (("c", "c/1"),)
    for bad in ("A <= ", "A p", "p <= B"):
        with pytest.raises(ValueError):
            parse_axiom(bad)


def test_shapes_are_fewer_than_rewritings():
    found = rewrite_compute(parse_cq("q() :- r(x, y), r(z, y)"), TWO.axioms)
    assert len(by_shape(found)) < len(found)


def test_decide_consumes_labels():
    loop = Ontology.parse(["exists h <= M @s", "M <= exists h @t"])
    facts = {("h", ("r", "c"), ("n", "p"))}

    def holds(mono, level):
        cq = parse_cq("q() :- M('r')@{" + mono + "}")
        return any(all(m == a[2] for m, a in zip(monos, body, strict=True)) for body in rewrite_decide(cq, loop.axioms, level=level) for _, monos in matches([a[:2] for a in body], {(p, a, m) for p, a, m in facts}))

    assert holds("p*n*s", "general") and not holds("p*n*s*t", "general") and holds("p*n*s*s*t", "general")
    assert holds("p*n*s*t", "idempotent") and not holds("p*n*t", "idempotent")


def constrained_by_chase(cq, closed):
    """Answers of an annotated query over the universal model, by its definition."""
    out = set()
    for env, monos in matches([(a.pred, a.args) for a in cq.atoms], closed):
        named = {}
        if all(a.mono is None or (m == frozenset(a.mono) if isinstance(a.mono, tuple) else named.setdefault(a.mono, m) == m) for a, m in zip(cq.atoms, monos, strict=True)) and all(isinstance(env[h], str) for h in cq.head):
            out.add(tuple(env[h] for h in cq.head))
    return out


def constrained_by_folding(cq, ontology, facts):
    out = set()
    for body in constrained_bodies(cq, ontology.axioms):
        closures = [atom_closure(p, a, list(ontology.positive)) for p, a, _ in body]
        for choice in product(*[[(atom, way) for atom, ways in c.items() for way in ways] for c in closures]):
            for env, monos in matches([atom for atom, _ in choice], facts):
                got = {i: m.union(way, x) for (_, _, tag), m, (_, way) in zip(body, monos, choice, strict=True) for i, x in tag}
                named = {}
                if all(m == frozenset(cq.atoms[i].mono) if isinstance(cq.atoms[i].mono, tuple) else named.setdefault(cq.atoms[i].mono, m) == m for i, m in got.items()):
                    out.add(tuple(env[h] for h in cq.head))
    return out


def annotated(rng, cq, closed):
    """The query with conditions on its atoms: monomials that facts have, label variables that two atoms may share."""
    monos = sorted({tuple(sorted(m)) for p, _, m in closed if any(p == a.pred for a in cq.atoms)})
    pick = lambda: rng.choice([None, "?p", "?p", rng.choice(monos) if monos else None, rng.choice(monos) if monos else None])
    return replace(cq, atoms=tuple(replace(a, mono=pick()) for a in cq.atoms))


def test_constrained_queries_equal_the_chase():
    rng, filled, witnessed = random.Random(21), 0, 0
    for _ in range(1500):
        ontology, facts, cq = random_instance(rng, atoms=2, facts=2)
        if (closed := chase(facts, ontology, depth=4, most=300)) is None:
            continue
        cq = annotated(rng, cq, closed)
        want = constrained_by_chase(cq, closed)
        assert constrained_by_folding(cq, ontology, facts) == want, (cq, ontology, facts)
        filled += bool(want)
        known = {f for f in closed if all(isinstance(x, str) for x in f[1])}
        witnessed += want != constrained_by_chase(cq, known)
    assert filled > 100 and witnessed > 10


def test_atoms_merged_at_a_witness_keep_their_own_labels():
    facts = {("A", ("a",), frozenset("u"))}
    two = Ontology.parse(["A <= exists p @v", "p <= r @w", "p <= s @k"])
    for text, holds in (("q(x) :- p(x, y)@{u*v}", True), ("q(x) :- r(x, y)@{u*v*w}, s(x, y)@{u*v*k}", True), ("q(x) :- r(x, y)@{u*v*k}, s(x, y)", False), ("q(x) :- r(x, y)@?m, s(x, y)@?m", False), ("q(x) :- r(x, y)@?m, r(x, y)@?m, s(x, y)", True)):
        cq = parse_cq(text)
        assert constrained_by_folding(cq, two, facts) == constrained_by_chase(cq, chase(facts, two, 3)) == ({("a",)} if holds else set())


def general_monomials(cq, ontology, facts, degree):
    got = set()
    for r in rewrite_compute(cq, ontology.axioms, level="general", max_degree=degree):
        for env, monos in matches([a[:2] for a in r.atoms], facts):
            mono = tuple(sorted([*r.labels, *(x for m, a in zip(monos, r.atoms, strict=True) for x in sorted(m) * a[2])]))
            if len(mono) <= degree:
                got.add((tuple(env[h] for h in cq.head), mono))
    return got


def infinite_by_folding(cq, ontology, facts):
    return any(matches(choice, facts) for _, body in pumping_bodies(cq, ontology.axioms) for choice in product(*[nodes for _, nodes in body]))


def test_finiteness_equals_the_growth_of_the_enumeration():
    rng, infinite, finite = random.Random(31), 0, 0
    while infinite < 60 or finite < 200:
        ontology, facts, cq = random_instance(rng, axioms=3, atoms=2, facts=3)
        try:
            small, large = (general_monomials(cq, ontology, facts, d) for d in (11, 17))
        except TooManyRewritings:
            continue
        if not large:
            continue
        assert infinite_by_folding(cq, ontology, facts) == (large != small), (cq, ontology, facts)
        infinite, finite = infinite + (large != small), finite + (large == small)


def test_a_cycle_behind_a_fold_is_found():
    ontology = Ontology.parse(["A <= exists p @v", "exists p- <= exists q @w", "A <= B @s", "B <= A @t"])
    facts = {("A", ("a",), frozenset("u"))}
    cq = parse_cq("q() :- p(x, y), q(y, z)")
    assert infinite_by_folding(cq, ontology, facts) and not infinite_by_folding(cq, ontology, {("q", ("a", "b"), frozenset("u"))})
    assert not infinite_by_folding(cq, ontology.without("t"), facts)
