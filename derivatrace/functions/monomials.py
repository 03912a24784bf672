"""Monomials as array columns.

A monomial is a sorted array of labels: without repeats at the idempotent levels, with repeats (an exponent is a number
of equal neighbours) at the general level. Being canonical by construction, equal monomials are equal arrays, so they
group, join and compare as plain values. Labels are text, or their 64-bit hashes where the instance says so.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

SEP = "*"


def canonical(labels: Column) -> Column:
    """The idempotent monomial of an array of labels."""
    return F.sort_array(F.array_distinct(labels))


def mul_idem(*monos: Column) -> Column:
    """Idempotent product: the union of the label sets."""
    return canonical(F.concat(*monos))


def mul(*monos: Column) -> Column:
    """General product: exponents add up."""
    return F.sort_array(F.concat(*monos))


def power(mono: Column, exponent: int) -> Column:
    return mul(*[mono] * exponent) if exponent > 1 else mono


def product(level: str, *monos: Column) -> Column:
    return mul(*monos) if level == "general" else mul_idem(*monos)


def drop_once(mono: Column, label: Column) -> Column:
    """Without one occurrence of the label; null where it doesn't occur."""
    at = F.array_position(mono, label).cast("int")
    rest = F.concat(F.slice(mono, F.lit(1), F.greatest(at - 1, F.lit(0))), F.slice(mono, at + 1, F.size(mono)))
    return F.when(at > 0, rest)


def add_once(mono: Column, label: Column) -> Column:
    """With the label, unless it is there."""
    return F.sort_array(F.array_union(mono, F.array(label)))


def within(mono: Column, wanted: Column) -> Column:
    """All labels of the monomial are among those wanted."""
    return F.size(F.array_except(mono, wanted)) == 0


def text(mono: Column) -> Column:
    return F.array_join(mono, SEP)


def exponents(mono: Column) -> Column:
    """The general monomial as array<struct<var, exp>>."""
    return F.transform(F.array_distinct(mono), lambda v: F.struct(v.alias("var"), F.size(F.filter(mono, lambda x: x == v)).alias("exp")))


def mul_exponents(a: Column, b: Column) -> Column:
    """Product of two monomials in array<struct<var, exp>> form."""
    merged = F.map_zip_with(F.map_from_entries(a), F.map_from_entries(b), lambda _, x, y: F.coalesce(x, F.lit(0)) + F.coalesce(y, F.lit(0)))
    return F.sort_array(F.transform(F.map_entries(merged), lambda e: F.struct(e["key"].alias("var"), e["value"].alias("exp"))))
