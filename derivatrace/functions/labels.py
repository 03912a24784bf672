"""Label constants and row labels.

Row labels follow a policy: ``row`` (key template), ``relation`` (one label a table), ``column:<name>`` (a column's
value) or any SQL expression. Axiom and rule labels are constants. With ``hashed`` labels every label is the 64-bit hash
of its text, and ``dictionary`` gives the texts back.
"""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def keyed(prefix: str, columns: Iterable[str]) -> Column:
    """prefix/key-key-…; null if a key is null."""
    parts: list[Column] = []
    for c in columns:
        parts += [F.lit("-")] * bool(parts) + [F.col(c).cast("string")]
    return F.concat(F.lit(f"{prefix}/"), *parts)


def row_label(table: str, prefix: str, keys: Iterable[str], policy: str = "row") -> Column:
    if policy == "row":
        return F.concat(F.lit("@"), keyed(prefix, keys))
    if policy == "relation":
        return F.lit(f"@{table}")
    if policy.startswith("column:"):
        return F.concat(F.lit(f"@{table}:"), F.coalesce(F.col(policy[7:]).cast("string"), F.lit("null")))
    return F.expr(policy)


def encoded(label: Column, hashed: bool) -> Column:
    return F.xxhash64(label) if hashed else label


def constant(labels: Iterable[str], hashed: bool) -> Column:
    """A literal monomial; folded at planning time."""
    labels = sorted(labels)
    if not labels:
        return F.expr(f"cast(array() as array<{'bigint' if hashed else 'string'}>)")
    return F.sort_array(F.array(*[encoded(F.lit(x), hashed) for x in labels])) if hashed else F.array(*map(F.lit, labels))


def dictionary(spark: SparkSession, constants: Iterable[tuple[str, str]], rows: Iterable[DataFrame] = ()) -> DataFrame:
    """var, text, kind of every label: constants as (text, kind), rows as frames with a column ``label``."""
    out = spark.createDataFrame(sorted(constants), "text string, kind string").select(F.xxhash64("text").alias("var"), "text", "kind")
    for frame in rows:
        out = out.unionByName(frame.select(F.xxhash64("label").alias("var"), F.col("label").alias("text"), F.lit("row").alias("kind")).distinct())
    return out
