"""Equality of polynomials: either side is made once, in one round or in several."""

from derivatrace.operators import measures
from derivatrace.workloads import queries

DATA = "/root/testdata/sf0.001"


def test_one_row_more_or_less_is_told(spark, monkeypatch):
    made = lambda *rows: spark.createDataFrame(rows, "x string, mono array<string>").coalesce(1)
    some = [("a", ["m", "n"]), ("a", ["m"]), ("b", None), (None, ["m"])]
    assert measures._rounds(made(*some)) == 1
    for rounds in (1, 3):
        monkeypatch.setattr(measures, "_rounds", lambda df, rounds=rounds: rounds)
        assert measures.agree(made(*some), made(*some[::-1]), by=("x",))
        assert not measures.agree(made(*some), made(*some[:3]), by=("x",))
        assert not measures.agree(made(*some, some[0]), made(*some), by=("x",))
        assert not measures.agree(made(*some), made(*some[:3], (None, ["n"])), by=("x",))


def test_larger_tables_take_more_rounds(spark, monkeypatch):
    lines = spark.read.parquet(f"{DATA}/lineitem.parquet")
    assert measures._rounds(lines) == 1
    monkeypatch.setattr(measures, "ROUND_INPUT", 1 << 15)
    few = lines.select("l_orderkey", "l_linenumber")
    assert measures._rounds(few) > 1
    assert measures.agree(few, few.orderBy("l_linenumber"), by=("l_orderkey",)) and not measures.agree(few, few.where("l_orderkey <> 3"), by=("l_orderkey",))


def test_the_forms_are_compared_by_answer(spark, monkeypatch):
    monkeypatch.setattr(measures, "_rounds", lambda df: seen.append(df.columns) or 2)
    seen: list[list[str]] = []
    assert queries.queries()["unfold_equals_shape"](spark, DATA).first()["value"] and seen == [["r", "mono", "_n"]]
