"""Joins without individuals of kinds that never meet, in orders that multiply few rows."""

from derivatrace.operators.joins import Facts, Key, few_products, meeting
from derivatrace.operators.provenance import _join_order, certain_answers
from derivatrace.workloads import queries
from derivatrace.workloads.mixes import DEEP

DATA = "/root/testdata/sf0.001"


def _facts(*prefixes):
    return Facts(None, [Key((f"k{i}",), p, True) if p else Key((f"k{i}",)) for i, p in enumerate(prefixes)])


def test_kinds_that_never_meet_are_left_out():
    c, n, s = ("h", "c"), ("v", "n"), ("h", "s")
    rows = [("deal", (c, s)), ("based", (c, n)), ("based", (s, n))]
    based = [_facts("cust", "nat"), _facts("supp", "nat")]
    left = meeting(rows, [[_facts("cust", "supp")], based, based])
    assert [[f.args[0].prefix for f in frames] for frames in left] == [["cust"], ["cust"], ["supp"]]
    # Texts may be of any kind, and a prefix with a slash may begin like another kind's text.
    assert len(meeting(rows[:2], [[_facts(None, "supp")], based])[1]) == 2
    assert len(meeting(rows[:2], [[_facts("cust/a", "supp")], based])[1]) == 1
    assert meeting([("deal", (c, c))], [[_facts("cust", "supp")]]) == [[]]


def test_order_multiplies_few_rows():
    c, n, s = ("h", "c"), ("v", "n"), ("h", "s")
    rows = [("based", (c, n)), ("based", (s, n)), ("deal", (c, s))]
    assert [i for i, _ in few_products(rows, [{c}, {s}, set()], _join_order)][0] == 2


def test_plain_deals_are_no_product_of_nations(spark):
    plan = certain_answers(queries.survey(spark, DATA), DEEP["D04"].cq)._jdf.queryExecution().optimizedPlan().toString()
    joins = [line for line in plan.splitlines() if "Join " in line]
    assert joins and not any(line.count("=") == 1 and "v000" in line for line in joins) and "concat" not in "".join(joins)


def test_answers_are_picked_without_a_shuffle_of_all(spark):
    from derivatrace.operators import explain

    rows = [("a",)] * 500 + [(f"k{i}",) for i in range(9)] + [("a",)] * 500
    df = spark.createDataFrame(rows, "x string").repartition(3)
    import hashlib

    want = sorted({r[0] for r in rows}, key=lambda x: hashlib.md5(x.encode()).hexdigest())
    assert [r["x"] for r in explain.sample_answers(df, 5)] == want[:5]
    assert [r["x"] for r in explain.sample_answers(df, 50)] == want
    assert [r["x"] for r in explain.sample_answers(df, 5, 0.5)] == [r["x"] for r in explain.sample_answers(df, 5, 1e-9)] == want[:5]
    plan = certain_answers(queries.survey(spark, DATA), DEEP["D06"].cq, distinct=False)._jdf.queryExecution().optimizedPlan().toString()
    assert not plan.startswith(("Aggregate", "Distinct"))
