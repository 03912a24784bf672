"""Polynomials kept apart as row keys and label sets, and compared by them."""

from dataclasses import replace

import pytest
from pyspark.sql import functions as F

from derivatrace.functions.monomials import canonical
from derivatrace.operators import keyed, measures
from derivatrace.operators.provenance import compute_provenance
from derivatrace.plans.instance import union
from derivatrace.workloads import fixture, queries
from derivatrace.workloads.mixes import DEEP

DATA = "/root/testdata/sf0.001"
CQ = DEEP["D01"].cq
FORMS = ("shape", "closure")


def spelled(instance, apart):
    """Answer columns and mono of the terms, for small tables."""
    out = []
    for t in apart.terms:
        text = lambda prefix, keys: f"concat('{prefix}/', " + ", '-', ".join(f"cast({k} as string)" for k in keys) + ")"
        rows = [f"concat('@', {text(instance.sources[table].prefix, [k for k, _ in keys])})" for table, keys in t.rows.items()]
        heads = [f"{text(prefix, columns)} as {h}" for h, (prefix, columns) in zip(CQ.head, t.heads, strict=True)]
        for holds, labels in t.sets:
            mono = canonical(F.array(*map(F.expr, rows), *map(F.lit, labels)))
            out.append(t.df.where(holds or "true").selectExpr("*", *heads).select(*CQ.head, mono.alias("mono")))
    return union(out).dropDuplicates()


def small(spark, change=lambda lines: lines):
    whole = fixture.instance(spark, DATA, "evaluation")
    lines = whole.tables["lineitem"].where("l_orderkey < 60")
    return replace(whole, tables={**{n: whole.tables[n] for n in ("supplier", "part", "orders", "customer", "nation", "region", "events")}, "lineitem": change(lines)})


@pytest.mark.parametrize("form", FORMS)
def test_terms_spell_the_polynomial(spark, form):
    instance = small(spark)
    apart = compute_provenance(instance, CQ, physical=form, apart=True)
    assert isinstance(apart, keyed.Apart) and measures.agree(spelled(instance, apart), apart.frame())


def test_no_monomial_is_spelled_to_compare_the_forms(spark, monkeypatch):
    """A row for each line and body, not for each monomial, and no round reads the tables again."""

    def never(*_):
        raise AssertionError("monomials were made")

    monkeypatch.setattr(measures, "_rounds", never)
    assert queries.queries()["shape_equals_closure"](spark, DATA).first()["value"]


def test_any_difference_is_told_as_by_the_texts(spark, monkeypatch):
    whole = small(spark)
    row = F.struct("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    first = whole.tables["lineitem"].where("l_quantity > 45").orderBy(row).select("l_orderkey", "l_linenumber").first()
    here = f"l_orderkey = {first[0]} and l_linenumber = {first[1]}"
    others = {
        "a way less": whole.with_ontology(whole.ontology.without("b02c")),
        "a row less": small(spark, lambda lines: lines.where(f"not ({here})")),
        "a row's condition": small(spark, lambda lines: lines.withColumn("l_quantity", F.expr(f"case when {here} then 1 else l_quantity end").cast(dict(lines.dtypes)["l_quantity"]))),
        "a row's key": small(spark, lambda lines: lines.withColumn("l_partkey", F.expr(f"case when {here} then -5 else l_partkey end").cast("bigint"))),
        "rows repeated": small(spark, lambda lines: lines.unionByName(lines)),
    }
    for word in (keyed.WORD, 3):
        monkeypatch.setattr(keyed, "WORD", word)
        for what, other in others.items():
            for a, b in ((whole, other), (other, whole)):
                one, two = compute_provenance(a, CQ, physical="shape", apart=True), compute_provenance(b, CQ, physical="closure", apart=True)
                assert keyed.same(one, two) is (what == "rows repeated"), (what, word)
    for what in ("a row less", "rows repeated"):
        assert measures.agree(compute_provenance(whole, CQ, physical="shape"), compute_provenance(others[what], CQ)) is (what == "rows repeated")


def test_a_row_label_with_a_null_part_is_null(spark):
    """Rows whose label is null are alike, whatever their other keys are; a row without the answer's key is none."""
    made = lambda **keys: small(spark, lambda lines: lines.where("l_orderkey < 8").withColumns({k: F.lit(v).cast(dict(lines.dtypes)[k]) for k, v in keys.items()}))
    one, other, whole = made(l_linenumber=None), made(l_linenumber=None, l_orderkey=5), made(l_linenumber=1)
    for a, b, equal in ((one, other, True), (one, whole, False), (made(l_suppkey=None), made(l_suppkey=None, l_orderkey=1), True)):
        polys = [(compute_provenance(i, CQ, physical=f, apart=True), compute_provenance(i, CQ, physical=f)) for i, f in ((a, "shape"), (b, "closure"))]
        assert keyed.same(polys[0][0], polys[1][0]) is equal and measures.agree(polys[0][1], polys[1][1]) is equal


def test_what_keys_cannot_tell_is_left_to_the_texts(spark):
    whole = small(spark)
    for instance in (whole.with_policy("relation"), replace(whole, hashed=True)):
        assert not isinstance(compute_provenance(instance, CQ, apart=True), keyed.Apart)
    terms = compute_provenance(whole, CQ, apart=True)
    odd = keyed.Apart([replace(t, sets=[(c, (*s, "@li/1-1-1-1")) for c, s in t.sets]) for t in terms.terms], terms.frame)
    assert keyed.same(odd, odd) is None and measures.agree(odd, terms)
