"""Chase and rewriting compared by factors."""

import pytest

from derivatrace.operators import factors
from derivatrace.plans.cq import parse_cq
from derivatrace.workloads import examples, queries

DATA = "/root/testdata/sf0.001"
CQ = parse_cq("q(x) :- p(x, y), r(y, z)")


def test_where_a_variable_parts_the_atoms():
    def cut(text):
        cq = parse_cq(text)
        return factors.parted([(a.pred, a.args) for a in cq.atoms], cq.head)

    assert cut("q(x) :- A(x), p(x, y), r(y, z)") == ("y", [0, 1], [2])
    assert cut("q(x, z) :- p(x, y), r(y, z)") is None and cut("q(x) :- p(x, y), A(x)") is None
    assert cut("q(x) :- p(x, y), r(y, z), s(z, y)") == ("y", [0], [1, 2])


def test_no_row_for_each_product(spark, monkeypatch):
    """Equal sides settle it: the polynomials themselves aren't made."""

    def never(*_):
        raise AssertionError("all rows were made")

    monkeypatch.setattr(factors, "answers_over", never)
    assert queries.queries()["chase_equals_rewriting"](spark, DATA).first()["value"]


@pytest.mark.parametrize(("dropped", "equal"), [(None, True), ("side", False), ("witness", False)])
def test_a_difference_in_any_part_shows(spark, monkeypatch, dropped, equal):
    facts = {"p": [(("a", "b"), ("u",)), (("c", "b"), ("v",))], "r": [(("b", "d"), ("w",))], "A": [(("e",), ("k",))]}
    instance = examples.given(spark, facts, ["A <= exists p @s", "exists p- <= exists r @t"])
    whole = factors.chase

    def partly(*args):
        closed = whole(*args)
        if dropped == "side":
            return closed.where("not (pred = 'r' and array_contains(mono, 'v'))")
        return closed.where("not (pred = 'r' and a0 like '~%')") if dropped else closed

    monkeypatch.setattr(factors, "chase", partly)
    assert factors.chase_agrees(instance, CQ, 3) is equal


def test_sides_that_differ_are_multiplied_out(spark, monkeypatch):
    """Sides may differ where their products don't: here a label is on the one side, or on the other."""
    facts = {"p": [(("a", "b"), ("u", "w"))], "r": [(("b", "d"), ("w",))]}
    other = {"p": [(("a", "b"), ("u",))], "r": [(("b", "d"), ("w",))]}
    monkeypatch.setattr(factors, "chase", lambda instance, depth, f=factors.chase: f(examples.given(spark, other, []), depth))
    assert factors.chase_agrees(examples.given(spark, facts, []), CQ, 3)
