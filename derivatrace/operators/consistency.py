"""Consistency of an instance, and whether a finite labelled interpretation is a model of an ontology."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from derivatrace.functions.monomials import mul, mul_idem
from derivatrace.operators.provenance import compute_provenance
from derivatrace.plans.cq import CQ, Atom
from derivatrace.plans.instance import Instance, union
from derivatrace.plans.ontology import Axiom, Concept, Ontology, Role, Some


def _atom(term: Concept | Some | Role, x: str, y: str, kind: str = "h") -> Atom:
    if isinstance(term, Concept):
        return Atom(term.name, ((kind, x),))
    if isinstance(term, Some):
        pair = (kind, x), ("v", f"_{y}")
        return Atom(term.role.name, pair[::-1] if term.role.inv else pair)
    pair = (kind, x), (kind, y)
    return Atom(term.name, pair[::-1] if term.inv else pair)


def violation_query(axiom: Axiom) -> CQ:
    """Who violates a negative inclusion."""
    head = ("x", "y") if isinstance(axiom.lhs, Role) else ("x",)
    return CQ(head, (_atom(axiom.lhs, "x", "y1" if len(head) == 1 else "y"), _atom(axiom.rhs, "x", "y2" if len(head) == 1 else "y")))


def conflicts(instance: Instance) -> DataFrame:
    """axiom, x, y, mono: every violation of a negative inclusion with the labels of its derivations."""
    frames = []
    for a in instance.ontology.negative:
        df = compute_provenance(instance, violation_query(a))
        y = F.col("y") if "y" in df.columns else F.lit(None).cast("string")
        frames.append(df.select(F.lit("*".join(a.label) or str(a)).alias("axiom"), F.col("x"), y.alias("y"), "mono"))
    if not frames:
        return instance.empty(1).select(F.lit("").alias("axiom"), F.col("a0").alias("x"), F.col("a0").alias("y"), "mono")
    return union(frames)


def check_consistency(instance: Instance) -> bool:
    """Labels have no influence: plain violation queries, each ended by its first answer."""
    from derivatrace.operators.provenance import certain_answers

    return all(certain_answers(instance, violation_query(a)).isEmpty() for a in instance.ontology.negative)


def _side(facts: dict[str, DataFrame], term, empty) -> DataFrame:
    """x, [y,] mono of a basic concept or role over an interpretation (facts: a0, [a1,] mono)."""
    name = term.name if not isinstance(term, Some) else term.role.name
    df = facts.get(name, empty(1 if isinstance(term, Concept) else 2))
    if isinstance(term, Concept):
        return df.select(F.col("a0").alias("x"), "mono")
    role = term.role if isinstance(term, Some) else term
    x, y = ("a1", "a0") if role.inv else ("a0", "a1")
    if isinstance(term, Some):
        return df.select(F.col(x).alias("x"), "mono").dropDuplicates()
    return df.select(F.col(x).alias("x"), F.col(y).alias("y"), "mono")


def violations(facts: dict[str, DataFrame], ontology: Ontology, instance: Instance, level: str = "general") -> DataFrame:
    """axiom, x, y, mono that the inclusions ask for and the interpretation lacks; for negative ones, that it has.

    One anti-join (for negative inclusions one semi-join) an axiom. The complement is over the interpretation itself.
    """
    times, frames = (mul if level == "general" else mul_idem), []
    for a in ontology.axioms:
        left, right = _side(facts, a.lhs, instance.empty), _side(facts, a.rhs, instance.empty)
        keys = [c for c in left.columns if c != "mono"]
        if a.neg:
            bad = left.join(right, keys, "left_semi")
        else:
            need = left.withColumn("mono", times(F.col("mono"), instance.constant(a.label)))
            bad = need.join(right, [*keys, "mono"], "left_anti")
        frames.append(bad.select(F.lit(str(a)).alias("axiom"), "x", (F.col("y") if "y" in keys else F.lit(None).cast("string")).alias("y"), "mono"))
    return union(frames)


def is_model(facts: dict[str, DataFrame], ontology: Ontology, instance: Instance, level: str = "general") -> bool:
    return violations(facts, ontology, instance, level).isEmpty()
