"""Mixing sources to target weights by systematic sampling.

Within a source each document expects target / source_size copies. Documents stand in order of size, id and a hash of
the text; their expected copies are summed up, one random offset for each source is added, and a document is emitted
once for every whole number that its stretch of the sum crosses. As neighbours are of like size, the words taken come
near the target. The order is made by a range partitioning on (source, size, id, hash), so a hot source is dealt over
many tasks; only the counts of (partition, source) reach the driver, to start each partition's sum where the one
before ends.

Nulls and edges: a null text has size 0, a null source is a source of its own and comes last, an empty table gives an
empty result, equal rows are emitted each in its own right. A source of size 0 has target 0 and takes nothing. Sources
are the named parts of a mixture; their totals are held by the driver (``max_sources``, else an error is raised).
"""

from __future__ import annotations

import hashlib

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from derivatrace.llm.common import column, cut, free_prefix, only_keyed, row_key

#: The weights of the sources in order, and the mix's size against all sizes.
WEIGHTS = (3, 1, 2)
SHARE = 1.5
MOST = 2.0


def water_fill(sizes: dict[str | None, int], weights: tuple[int, ...] = WEIGHTS, share: float = SHARE, most: float = MOST) -> dict[str | None, float]:
    """Targets by weight; those above most x size stop there and the excess is shared anew until none is above."""
    order = sorted((s for s in sizes if s is not None), key=lambda s: s.encode()) + [None] * (None in sizes)
    weight = {s: weights[i % len(weights)] for i, s in enumerate(order)}
    target, rest, active = {}, share * sum(sizes.values()), list(order)
    while active:
        each = rest / sum(weight[s] for s in active)
        full = [s for s in active if each * weight[s] > most * sizes[s]]
        for s in full:
            target[s] = most * sizes[s]
        rest -= sum(target[s] for s in full)
        active = [s for s in active if s not in target]
        if not full:
            target |= {s: each * weight[s] for s in active}
            break
    return target


def offset(source: str | None, seed: int) -> float:
    """The random offset of a source: a fixed function of its name and the seed, so that reruns agree."""
    key = str(seed) if source is None else f"{seed}={source}"
    return int(hashlib.md5(key.encode()).hexdigest()[:12], 16) / 2**48


def word_sizes(text) -> F.Column:
    return F.coalesce(F.size(F.array_remove(F.split(text, r"[\x20\x09-\x0D]+"), "")), F.lit(0)).cast("long")


def mix(docs: DataFrame, *, id_col: str = "doc_id", text: str = "text", source: str = "source", weights: tuple[int, ...] = WEIGHTS, share: float = SHARE, most: float = MOST, seed: int = 7, max_sources: int = 1_000_000) -> tuple[DataFrame, str]:
    """<p>id, <p>key and, for every row, size, source_size, target, copies and taken, all under the prefix p; the frame and p."""
    p = free_prefix(docs, "m")
    spark, body = docs.sparkSession, column(docs, text)
    sized = cut(docs.select(column(docs, id_col).alias(f"{p}id"), row_key(docs, text, source).alias(f"{p}key"), column(docs, source).cast("string").alias(f"{p}source"), word_sizes(body).alias(f"{p}size")), "mix")
    totals = sized.groupBy(f"{p}source").agg(F.sum(f"{p}size").alias("size")).limit(max_sources + 1).collect()
    if len(totals) > max_sources:
        raise ValueError(f"more than {max_sources} sources: raise max_sources or group them")
    sizes = {r[0]: r["size"] for r in totals}
    targets = water_fill(sizes, weights, share, most)
    keys = [F.col(f"{p}source").asc_nulls_last(), F.col(f"{p}size"), F.col(f"{p}id"), F.col(f"{p}key")]
    order = sized.repartitionByRange(*keys).sortWithinPartitions(*keys)
    ordered = cut(order.withColumn(f"{p}part", F.spark_partition_id()).withColumn(f"{p}at", F.monotonically_increasing_id() % (1 << 33)), "mix-order")
    firsts = ordered.groupBy(f"{p}part", f"{p}source").agg(F.count(F.lit(1)).alias("n"), F.min(f"{p}at").alias("at")).collect()
    counts: dict[str | None, int] = {}
    starts = []
    name = lambda s: "" if s is None else f"={s}"
    for part, s, n, at in sorted(firsts, key=lambda r: r[0]):
        starts.append((part, name(s), counts.get(s, 0) - at))
        counts[s] = counts.get(s, 0) + n
    # Two small tables, a row for each source and for each (partition, source), joined by broadcast.
    plan = [(name(s), sizes[s], targets[s], targets[s] / sizes[s] if sizes[s] else 0.0, offset(s, seed)) for s in sizes]
    plans = spark.createDataFrame(plan, f"{p}name string, {p}source_size long, {p}target double, {p}rate double, {p}shift double")
    ranks = spark.createDataFrame(starts, f"{p}part int, {p}name string, {p}start long")
    named = ordered.withColumn(f"{p}name", F.coalesce(F.concat(F.lit("="), f"{p}source"), F.lit("")))
    rows = named.join(F.broadcast(plans), f"{p}name").join(F.broadcast(ranks), [f"{p}part", f"{p}name"])
    rank, rate, shift = F.col(f"{p}start") + F.col(f"{p}at"), F.col(f"{p}rate"), F.col(f"{p}shift")
    # Rounding must not add a copy beyond the next whole number.
    copies = F.least(F.floor(shift + (rank + 1) * rate) - F.floor(shift + rank * rate), F.ceil(rate)).cast("long")
    rows = rows.withColumn(f"{p}copies", copies)
    return rows.withColumn(f"{p}taken", F.col(f"{p}copies") * F.col(f"{p}size")), p


def mix_report(docs: DataFrame, **options) -> DataFrame:
    """doc_id, size, source_size, target, taken and copies of every document."""
    out, p = mix(docs, **options)
    return out.select(F.col(f"{p}id").alias("doc_id"), *[F.col(f"{p}{n}").alias(n) for n in ("size", "source_size", "target", "taken", "copies")])


def mixed(docs: DataFrame, *, id_col: str = "doc_id", text: str = "text", source: str = "source", **options) -> DataFrame:
    """The documents, each as many times as the mix takes it.

    Rows alike in id, source and text are one row here, taken as often as they are together.
    """
    out, p = mix(docs, id_col=id_col, text=text, source=source, **options)
    every = out.groupBy(f"{p}id", f"{p}key").agg(F.sum(f"{p}copies").alias(f"{p}copies"), F.count(F.lit(1)).alias(f"{p}n"))
    took = only_keyed(docs, every.where(F.col(f"{p}copies") > 0), id_col, (text, source), p, "inner")
    repeated = took.where(F.col(f"{p}n") > 1).dropDuplicates([f"{p}id", f"{p}key"])
    took = took.where(F.col(f"{p}n") == 1).unionByName(repeated) if not every.where(F.col(f"{p}n") > 1).isEmpty() else took
    return took.select(*[column(took, c) for c in docs.columns], F.explode(F.sequence(F.lit(1).cast("long"), F.col(f"{p}copies"))).alias(f"{p}copy")).drop(f"{p}copy")
