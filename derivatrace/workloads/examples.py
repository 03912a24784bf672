"""Tiny hand-made instances: facts given as frames, inclusions as text; and the same inclusions over the orders of a folder."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from derivatrace.plans.instance import Instance
from derivatrace.plans.ontology import Ontology
from derivatrace.sources.tables import load
from derivatrace.workloads import fixture

Fact = tuple[tuple[str, ...], tuple[str, ...]]


def given(spark: SparkSession, facts: dict[str, list[Fact]], axioms: list[str]) -> Instance:
    """facts: predicate -> [(arguments, labels)]."""
    frames: dict[str, DataFrame] = {}
    for pred, rows in facts.items():
        names = ("s", "o")[: len(rows[0][0])]
        frames[pred] = spark.createDataFrame([(*args, sorted(mono)) for args, mono in rows], ", ".join([*[f"{n} string" for n in names], "mono array<string>"]))
    return Instance(spark, {}, {}, (), Ontology.parse(axioms), given=frames)


def heads(spark: SparkSession, cyclic: bool = False) -> Instance:
    """Two rows p, q of people and their city; rules m (the city) and n (who heads it); whoever heads something is a Head."""
    facts = {"headOf": [(("first", "city"), ("p", "n")), (("second", "city"), ("q", "n"))], "City": [(("city",), ("p", "m")), (("city",), ("q", "m"))]}
    if cyclic:
        facts = {"headOf": [(("first", "city"), ("p", "n"))]}
    return given(spark, facts, ["exists headOf <= Head @s"] + ["Head <= exists headOf @t"] * cyclic)


def chain(spark: SparkSession) -> Instance:
    """Two witnesses in a row."""
    return given(spark, {"A": [(("a",), ("u",))]}, ["A <= exists p @v", "exists p- <= exists q @w"])


def two_supers(spark: SparkSession) -> Instance:
    """A witness by a role with two larger roles."""
    return given(spark, {"A": [(("a",), ("u",))]}, ["A <= exists p @v", "p <= r @w", "p <= r @k"])


def over_orders(spark: SparkSession, path: str, axioms: list[str], *, pred: str = "headOf", n: int = 2) -> Instance:
    """One rule n: every order is pred of its customer (of arity 1: an order alone)."""
    rule = fixture._one("n", pred, "orders", *(("ord", ("o_orderkey",)), ("cust", ("o_custkey",)))[:n])
    return Instance(spark, load(spark, path, ["orders"]), {"orders": fixture.SOURCES["orders"]}, (rule,), Ontology.parse(axioms))


def order_heads(spark: SparkSession, path: str) -> Instance:
    """The cycle of ``heads`` over all orders."""
    return over_orders(spark, path, ["exists headOf <= Head @s", "Head <= exists headOf @t"])
