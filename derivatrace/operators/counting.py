"""How many plain answers there are for each value of some answer variables, without making the answers.

Where a body's last join brings the counted variable to the grouping ones, its values are listed once for each key of the
join. A row of the grouping side takes its key's list along, so that lists are shuffled and not pairs, and the distinct
values of a group's lists are counted. The groups are dealt over rounds, each written before the next one runs, so that the
lists on disk at a time stay in proportion to the two sides.
"""

from __future__ import annotations

import gc
import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from derivatrace.operators.joins import Halves, joined
from derivatrace.operators.provenance import _join_order, certain_answers
from derivatrace.plans.cq import CQ
from derivatrace.plans.instance import Instance
from derivatrace.plans.rewrite import foldings, pruned
from derivatrace.sources.tables import shared_folder

#: Bytes of lists that a round may shuffle at least, and as a multiple of the bytes of the two sides.
ROUND_BYTES, ROUND_SHARE = 3 << 29, 2


def count_answers(instance: Instance, cq: CQ, by: tuple[str, ...]) -> DataFrame:
    """The columns of ``by``, and n_answers: the number of distinct answers with these values."""
    bodies = pruned(list(foldings(cq, instance.ontology.positive)))
    if len(bodies) == 1 and not cq.where:
        sides = joined(instance, list(bodies[0]), cq.head, order=_join_order, labels=False, halves=True)
        if sides and (found := _listed(sides, by)):
            return _counted(sides, by, *found)
    return certain_answers(instance, cq).groupBy(*by).agg(F.count(F.lit(1)).alias("n_answers"))


def _listed(sides: Halves, by: tuple[str, ...]) -> tuple[DataFrame, DataFrame, str] | None:
    """The side of the grouping variables, the other side, and the one column there that is counted."""
    counted = [c for h, names in sides.columns.items() if h not in by for c in names]
    groups = {c for h in by for c in sides.columns[h]}
    for own, other in ((sides.left, sides.right), (sides.right, sides.left)):
        if len(counted) == 1 and counted[0] not in sides.on and counted[0] in other.columns and groups <= set(own.columns):
            return own, other, counted[0]
    return None


def _counted(sides: Halves, by: tuple[str, ...], own: DataFrame, other: DataFrame, value: str) -> DataFrame:
    spark, on = own.sparkSession, sides.on
    folder = f"{shared_folder(spark)}/derivatrace-counts-{uuid.uuid4().hex}"

    def written(df: DataFrame, name: str) -> DataFrame:
        df.write.parquet(f"{folder}/{name}")
        gc.collect()
        spark.sparkContext._jvm.System.gc()  # else shuffle files stay until the driver happens to collect its garbage
        return spark.read.schema(df.schema).parquet(f"{folder}/{name}")

    groups = [c for h in by for c in sides.columns[h]]
    own = written(own.select(*dict.fromkeys([*groups, *on])), "groups")
    lists = written(other.groupBy(*on).agg(F.sort_array(F.collect_set(value)).alias("_list")), "lists")
    sizes = own.groupBy(*on).agg(F.count(F.lit(1)).alias("_n")).join(lists.withColumn("_size", F.size("_list")), on)
    least, most, values = sizes.agg(F.min(F.element_at("_list", 1)), F.max(F.element_at("_list", -1)), F.sum(F.col("_n") * F.col("_size"))).first()
    width = {"array<bigint>": 8}.get(dict(lists.dtypes)["_list"], 16)
    if width == 8 and values and -(2**31) <= least and most < 2**31:
        lists, width = lists.withColumn("_list", F.col("_list").cast("array<int>")), 4
    size = sum(int(str(d._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())) for d in (own, lists))
    rounds = -(-(values or 0) * width // max(ROUND_BYTES, ROUND_SHARE * size)) or 1
    parts = []
    for k in range(rounds):
        some = own if rounds == 1 else own.where(F.pmod(F.xxhash64(*groups), F.lit(rounds)) == k)
        made = some.join(lists, on).groupBy(*groups).agg(F.size(F.array_distinct(F.flatten(F.collect_list("_list")))).cast("bigint").alias("n_answers"))
        made = made.selectExpr(*[f"{sides.texts[h]} as {h}" for h in by], "n_answers")
        parts.append(made if rounds == 1 else written(made, f"round-{k}"))
    out = parts[0]
    for df in parts[1:]:
        out = out.unionByName(df)
    return out
