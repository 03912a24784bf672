"""Families whose polynomials grow by nature."""

from __future__ import annotations

from pyspark.sql import SparkSession

from derivatrace.plans.instance import Instance
from derivatrace.plans.ontology import Ontology


def _given(spark: SparkSession, pred: str) -> Instance:
    fact = spark.createDataFrame([("a", ["u"])], "s string, mono array<string>")
    return Instance(spark, {}, {}, (), given={pred: fact})


def diamonds(spark: SparkSession, depth: int) -> Instance:
    """Layered diamonds: A<depth>(a) has 2^depth monomials."""
    lines = []
    for i in range(depth):
        lines += [f"A{i} <= B{i} @b{i}", f"A{i} <= C{i} @c{i}", f"B{i} <= A{i + 1} @d{i}", f"C{i} <= A{i + 1} @e{i}"]
    return _given(spark, "A0").with_ontology(Ontology.parse(lines))


def complete_graph(spark: SparkSession, nodes: int) -> Instance:
    """All inclusions between N1..Nn: the monomials of Nn(a) are the label sets of walks from 1 to n."""
    lines = [f"N{i} <= N{j} @n{i}_{j}" for i in range(1, nodes + 1) for j in range(1, nodes + 1) if i != j]
    return _given(spark, "N1").with_ontology(Ontology.parse(lines))
