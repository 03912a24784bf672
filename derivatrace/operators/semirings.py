"""A polynomial evaluated in concrete fully idempotent algebras, by a table of label values."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from derivatrace.operators.algebra import answer_columns


class NotIdempotent(ValueError):
    """The algebra's sum or product isn't idempotent, so an idempotent polynomial doesn't determine its value."""


IDEMPOTENT = ("trust", "access", "which", "why")
OTHERS = ("count", "cost", "probability", "confidence")


def specialise(poly: DataFrame, algebra: str, valuation: DataFrame | None = None, default=None) -> DataFrame:
    """answer, value.

    trust: some monomial has only labels of value true (valuation: label, value boolean).
    access: the least level from which some monomial can be seen, of each the highest of its labels (value int).
    which: all labels that take part. why: the monomials, as an array.
    Labels that the valuation lacks have the default (true, 0). The valuation is joined to the exploded labels; each
    monomial keeps its identity by its own value, so the two sums are plain aggregations with map-side combine.
    """
    keys = answer_columns(poly)
    if algebra in OTHERS:
        raise NotIdempotent(f"{algebra} isn't fully idempotent: compute at the general level")
    if algebra == "which":
        return poly.select(*keys, F.explode("mono").alias("_v")).groupBy(*keys).agg(F.sort_array(F.collect_set("_v")).alias("value"))
    if algebra == "why":
        return poly.groupBy(*keys).agg(F.sort_array(F.collect_set("mono")).alias("value"))
    if algebra not in IDEMPOTENT:
        raise ValueError(f"unknown algebra {algebra}")
    default = {"trust": True, "access": 0}[algebra] if default is None else default
    exploded = poly.select(*keys, "mono", F.explode_outer("mono").alias("label")).join(valuation, "label", "left")
    value = F.coalesce("value", F.lit(default))
    if algebra == "trust":
        inner = exploded.groupBy(*keys, "mono").agg(F.bool_and(value).alias("value"))
        return inner.groupBy(*keys).agg(F.bool_or("value").alias("value"))
    inner = exploded.groupBy(*keys, "mono").agg(F.max(value).alias("value"))
    return inner.groupBy(*keys).agg(F.min("value").alias("value"))


def depends_on(poly: DataFrame, label: str) -> DataFrame:
    """answer, survives: whether the answer still holds without the label (its deletion as false in the trust algebra)."""
    keys = answer_columns(poly)
    return poly.groupBy(*keys).agg(F.bool_or(~F.array_contains("mono", label)).alias("survives"))


def label_kind(label) -> F.Column:
    return F.when(label.startswith("@"), "row").when(label.startswith("m"), "rule").when(label.startswith("a"), "axiom").otherwise("other")


def label_use(poly: DataFrame) -> DataFrame:
    """label, kind, monomials and answers that it takes part in: which sources, rules and inclusions were used."""
    keys = answer_columns(poly)
    used = poly.select(F.struct(*keys).alias("_a") if keys else F.lit(1).alias("_a"), F.explode("mono").alias("label"))
    return used.groupBy("label").agg(F.count(F.lit(1)).alias("n_monomials"), F.count_distinct("_a").alias("n_answers")).withColumn("kind", label_kind(F.col("label")))


def label_rows(poly: DataFrame) -> DataFrame:
    """kind, source (table part of a row label) and length (of its monomial) of every label of every monomial."""
    used = poly.select(F.explode("mono").alias("label"), F.size("mono").alias("length"))
    return used.select(label_kind(F.col("label")).alias("kind"), F.when(F.col("label").startswith("@"), F.regexp_extract("label", "^@([A-Za-z]+)", 1)).otherwise(F.col("label")).alias("source"), "length")


def source_rollup(poly: DataFrame) -> DataFrame:
    """kind, source, n: how often each takes part, with subtotals."""
    return label_rows(poly).rollup("kind", "source").agg(F.count(F.lit(1)).alias("n"))


def label_cube(poly: DataFrame) -> DataFrame:
    """kind, length, level, n: labels by kind and by the length of their derivation, with all subtotals; level tells which columns are summed over."""
    return label_rows(poly).cube("kind", "length").agg(F.grouping_id().alias("level"), F.count(F.lit(1)).alias("n"))


def label_sets(poly: DataFrame) -> DataFrame:
    """kind, source, length, level, n: by kind and source, by length, and in all, in one pass."""
    names = ("kind", "source", "length")
    return label_rows(poly).groupingSets([["kind", "source"], ["length"], []], *names).agg(F.grouping_id().alias("level"), F.count(F.lit(1)).alias("n"))
