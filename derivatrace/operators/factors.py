"""The rewriting's polynomials against those over the bounded universal model, by factors.

Where a variable that is no answer parts a body in two, its rows are for each individual there the products of either
side's. Equal sides have equal products, so that the sides are compared, and products are made for anonymous individuals
alone: rows grow with the sides, not with their product. Where sides differ, whose products may still be equal, all rows are made.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from derivatrace.functions.monomials import mul_idem, within
from derivatrace.operators.chase import answers_over, chase, facts_of
from derivatrace.operators.joins import joined
from derivatrace.operators.measures import agree
from derivatrace.operators.provenance import _join_order, compute_provenance, provenance_on
from derivatrace.plans.cq import CQ
from derivatrace.plans.instance import Instance, union
from derivatrace.plans.rewrite import foldings


def parted(rows: list[tuple[str, tuple]], head: tuple[str, ...]) -> tuple[str, list[int], list[int]] | None:
    """A variable without which no atom is linked to those of the answer variables, these atoms' numbers, and the others'."""
    terms = [{t for t in q if t[0] in "hv"} for _, q in rows]
    for v in sorted({t for own in terms for t in own if t[0] == "v"}):
        bound, left = {("h", h) for h in head}, set()
        while more := {i for i, own in enumerate(terms) if i not in left and own & (bound - {v})}:
            left |= more
            bound |= set().union(*(terms[i] for i in more))
        right = [i for i in range(len(rows)) if i not in left]
        if left and right and all(v in terms[i] for i in right) and bound >= {v}:
            return v[1], sorted(left), right
    return None


def chase_agrees(instance: Instance, cq: CQ, depth: int) -> bool:
    """Whether the bounded universal model gives the query's answers the monomials that rewriting gives."""
    closed = chase(instance, depth)
    parts = _model(closed, cq), _rewriting(instance, cq)
    if all(parts):
        (left, right, rest), (left_, right_, rest_) = parts
        if agree(left, left_) and agree(right, right_):
            return _within_products(_differing(rest, rest_), left, right, cq.head)
    return agree(answers_over(closed, cq), compute_provenance(instance, cq))


def _model(closed: DataFrame, cq: CQ) -> tuple[DataFrame, DataFrame, DataFrame] | None:
    """Either side for known individuals at the parting variable, and the products of those for anonymous ones."""
    rows = [(a.pred, a.args) for a in cq.atoms]
    if cq.where or not cq.head or (found := parted(rows, cq.head)) is None:
        return None
    v, *sides = found
    left, right = (provenance_on(CQ(head, tuple(cq.atoms[i] for i in side)), facts_of(closed, cq)).withColumnRenamed(v, "_at") for head, side in zip(((*cq.head, v), (v,)), sides, strict=True))
    for h in cq.head:
        left = left.where(~F.col(h).startswith("~"))
    known = ~F.col("_at").startswith("~")
    made = left.where(~known).join(right.where(~known).withColumnRenamed("mono", "_other"), "_at")
    return left.where(known), right.where(known), made.select(*cq.head, mul_idem(F.col("mono"), F.col("_other")).alias("mono")).dropDuplicates()


def _rewriting(instance: Instance, cq: CQ) -> tuple[DataFrame, DataFrame, DataFrame] | None:
    """Either side of the one folded body that is parted, and the rows of the others."""
    sides, rest = [], [compute_provenance(instance, cq).limit(0)]
    for body, labels in sorted(foldings(cq, instance.ontology.positive).items()):
        make = lambda rows, head, extra=(): joined(instance, rows, head, order=_join_order, extra=extra)
        if (found := parted(list(body), cq.head)) is None:
            rest += [df] if (df := make(list(body), cq.head, sorted(labels))) is not None else []
            continue
        v, left, right = found
        sides.append([make([body[i] for i in left], (*cq.head, v)), make([body[i] for i in right], (v,), sorted(labels)), v])
    if len(sides) != 1 or any(df is None for df in sides[0]):
        return None
    left, right, v = sides[0]
    return *(df.withColumnRenamed(v, "_at").dropDuplicates() for df in (left, right)), union(rest).dropDuplicates()


def _differing(one: DataFrame, other: DataFrame) -> DataFrame:
    both = one.withColumn("_n", F.lit(1)).unionByName(other.withColumn("_n", F.lit(-1)))
    return both.groupBy(*one.columns).agg(F.sum("_n").alias("_n")).where("_n <> 0").drop("_n")


def _within_products(rows: DataFrame, left: DataFrame, right: DataFrame, head: tuple[str, ...]) -> bool:
    """Whether all rows are products of the sides, looked for by the first label of the right one."""
    first = F.coalesce(F.get(F.col("_right"), F.lit(0)).cast("string"), F.lit(""))
    tried = rows.join(left.withColumnRenamed("mono", "_left"), list(head)).where(within(F.col("_left"), F.col("mono")))
    tried = tried.withColumn("_first", F.explode(F.array_append(F.col("mono").cast("array<string>"), F.lit(""))))
    found = tried.join(right.withColumnRenamed("mono", "_right").withColumn("_first", first), ["_at", "_first"]).where(mul_idem(F.col("_left"), F.col("_right")) == F.col("mono"))
    return rows.join(found.select(*rows.columns), rows.columns, "left_anti").isEmpty()
