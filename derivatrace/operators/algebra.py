"""Polynomials as relations: one row for each (answer, monomial); the empty relation is "not entailed"."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from derivatrace.functions.monomials import canonical, mul_idem, text


def answer_columns(poly: DataFrame) -> list[str]:
    return [c for c in poly.columns if c not in ("mono", "coeff")]


def add_all(*polys: DataFrame) -> DataFrame:
    """Sum with multiplicities."""
    return reduce(DataFrame.unionByName, polys)


def add_idem(*polys: DataFrame) -> DataFrame:
    """Idempotent sum: every (answer, monomial) once."""
    return add_all(*polys).dropDuplicates()


def multiply(left: DataFrame, right: DataFrame, on: list[str]) -> DataFrame:
    """Product of the polynomials of answers that agree on the columns."""
    joined = left.withColumnRenamed("mono", "_a").join(right.withColumnRenamed("mono", "_b"), on)
    return joined.select(*[c for c in joined.columns if c not in ("_a", "_b")], mul_idem(F.col("_a"), F.col("_b")).alias("mono"))


def factorise(poly: DataFrame, static: Column) -> DataFrame:
    """answer, static, parts: monomials that share their static labels (those that fulfil ``static`` of label x) as one product.

    static is a column expression of the label column named ``x``.
    """
    keep = F.expr(f"filter(mono, x -> {static})") if isinstance(static, str) else static
    out = poly.withColumn("static", keep).withColumn("part", F.array_except("mono", "static"))
    return out.groupBy(*answer_columns(poly), "static").agg(F.sort_array(F.collect_set("part")).alias("parts"))


def expand(factorised: DataFrame) -> DataFrame:
    """Back to one row a monomial; a product of many sums grows exponentially by nature."""
    answer = [c for c in factorised.columns if c not in ("static", "parts")]
    return factorised.select(*answer, "static", F.explode("parts").alias("_p")).select(*answer, mul_idem(F.col("static"), F.col("_p")).alias("mono"))


def coerce(poly: DataFrame, level: str) -> DataFrame:
    """From general monomials to idempotent products (``mult_idempotent``), and to idempotent sums too (``idempotent``)."""
    out = poly.withColumn("mono", canonical(F.col("mono")))
    return out.dropDuplicates() if level == "idempotent" else out


def contains(poly: DataFrame, wanted: DataFrame, multiplicity: bool = False) -> DataFrame:
    """Rows of ``wanted`` that ``poly`` lacks (empty: wanted is a sub-polynomial); with counts where they matter."""
    keys = answer_columns(wanted)
    if not multiplicity:
        return wanted.join(poly, [*keys, "mono"], "left_anti")
    need = wanted.groupBy(*keys, "mono").agg(F.count(F.lit(1)).alias("_need"))
    have = poly.groupBy(*keys, "mono").agg(F.count(F.lit(1)).alias("_have"))
    return need.join(have, [*keys, "mono"], "left").where(F.coalesce("_have", F.lit(0)) < F.col("_need")).select(*keys, "mono")


def package(poly: DataFrame) -> DataFrame:
    """answer, poly: all monomials of an answer in one array. For answers one looks at: its size is that of the polynomial."""
    return poly.groupBy(*answer_columns(poly)).agg(F.sort_array(F.collect_list("mono")).alias("poly"))


def render(poly: DataFrame) -> DataFrame:
    """answer, text: ``a*b + c``."""
    lines = poly.withColumn("_t", text(F.col("mono"))).groupBy(*answer_columns(poly)).agg(F.sort_array(F.collect_list("_t")).alias("_ts"))
    return lines.select(*answer_columns(poly), F.array_join("_ts", " + ").alias("text"))


def minimal_only(poly: DataFrame) -> DataFrame:
    """Absorption: monomials without another one of the answer inside them (minimal causes).

    A monomial can only contain one that shares its first label or a later one, so candidates meet on (answer, label):
    each monomial offers its least label, and looks among its own labels.
    """
    keys = answer_columns(poly)
    small = poly.select(*keys, F.get("mono", F.lit(0)).alias("_k"), F.col("mono").alias("_s"))
    probe = poly.select(*keys, "mono", F.explode("mono").alias("_k"))
    inside = (F.size("_s") < F.size("mono")) & (F.size(F.array_except("_s", "mono")) == 0)
    absorbed = probe.join(small, [*keys, "_k"]).where(inside).select(*keys, "mono").distinct()
    out = poly.join(absorbed, [*keys, "mono"], "left_anti")
    # The empty monomial is inside every other.
    empty = poly.where(F.size("mono") == 0).select(*keys, F.lit(True).alias("_e"))
    return out.join(empty, keys, "left").where(F.col("_e").isNull() | (F.size("mono") == 0)).drop("_e") if keys else out


def difference(new: DataFrame, old: DataFrame) -> DataFrame:
    """change (+ or -) of each (answer, monomial) between two versions of a polynomial."""
    return add_all(new.exceptAll(old).withColumn("change", F.lit("+")), old.exceptAll(new).withColumn("change", F.lit("-")))


def common(left: DataFrame, right: DataFrame) -> DataFrame:
    return left.intersect(right)
