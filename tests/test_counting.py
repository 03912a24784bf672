"""Numbers of plain answers by lists of a join's keys: no pair is shuffled, in one round or in several."""

from pyspark.sql import functions as F

from derivatrace.operators import counting
from derivatrace.operators.provenance import certain_answers
from derivatrace.plans.cq import parse_cq
from derivatrace.workloads import queries
from derivatrace.workloads.mixes import DEEP

DATA = "/root/testdata/sf0.001"


def test_pairs_are_counted_in_any_number_of_rounds(spark, monkeypatch):
    instance, cq = queries.survey(spark, DATA), DEEP["D06"].cq
    want = sorted(map(tuple, certain_answers(instance, cq).groupBy("x").agg(F.count(F.lit(1))).collect()))
    whole = queries.queries()["certain_D06"](spark, DATA)
    assert sorted(map(tuple, whole.collect())) == want and want
    assert "collect_list(_list" in whole._jdf.queryExecution().optimizedPlan().toString()
    monkeypatch.setattr(counting, "ROUND_BYTES", 1 << 18)
    monkeypatch.setattr(counting, "ROUND_SHARE", 0)
    several = counting.count_answers(instance, cq, ("x",))
    assert len({f.rsplit("/", 2)[1] for f in several.inputFiles()}) > 1
    assert sorted(map(tuple, several.collect())) == want


def test_other_bodies_are_counted_from_their_answers(spark):
    instance = queries.survey(spark, DATA)
    for text, by in (("q(x, y) :- offers(x, y)", ("x",)), ("q(x, y, z) :- bought(x, p), offers(y, p), Product(z)", ("y",)), ("q(x, y) :- bought(x, p), offers(y, p)", ("y",))):
        cq = parse_cq(text)
        want = sorted(map(tuple, certain_answers(instance, cq).groupBy(*by).agg(F.count(F.lit(1))).collect()))
        assert sorted(map(tuple, counting.count_answers(instance, cq, by).collect())) == want and want
