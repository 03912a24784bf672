"""Connected components of a link table, by alternating large and small stars; nothing reaches the driver but counts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from derivatrace.llm.common import cut, spread_join

SALTS = 16


def _stars(links: DataFrame, smaller: bool) -> DataFrame:
    """One round: each node's (larger or smaller) neighbours are linked to its least neighbour.

    The least neighbour is a pre-aggregated minimum joined back to the links; a node with very many links is dealt over
    ``SALTS`` tasks there.
    """
    both = links.select("u", "v") if smaller else links.select("u", "v").unionByName(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
    joined = spread_join(both, least, ["u"], SALTS, F.xxhash64("v"))
    if smaller:  # u > v holds for all links
        out = joined.select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(joined.select("u", F.col("m").alias("v")))
    else:
        out = joined.where(F.col("v") > F.col("u")).select(F.col("v").alias("u"), F.col("m").alias("v"))
    return out.where(F.col("u") != F.col("v")).select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))


def components(links: DataFrame) -> DataFrame:
    """u, root: the least node of its component, for every node that isn't its own root. links has columns u and v."""
    now = cut(links.where(F.col("u") != F.col("v")).select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "links")
    seen = None
    while True:
        mark = now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)"))).first()
        if mark == seen or not mark[0]:
            return now.select("u", F.col("v").alias("root"))
        seen = mark
        now = cut(_stars(_stars(now, smaller=False), smaller=True).distinct(), "stars")
