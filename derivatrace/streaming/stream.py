"""Derived facts and answers over append-only rows.

A positive polynomial is monotone in its rows, so appended rows only append monomials: the stream derives facts row by
row, multiplies the closure's label sets in by a stream-static join, and appends them; the store shows each fact once.
Late rows fall behind the watermark; a batch run over the same rows reconciles.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from derivatrace.functions.monomials import mul_idem
from derivatrace.plans.closure import classify
from derivatrace.plans.ontology import Ontology
from derivatrace.sources.tables import shared_folder

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
#: Rule labels by event type, as in the fixture.
TYPES = {"click": "m23a", "view": "m23b", "purchase": "m23c", "signup": "m23d", "error": "m23e"}


def event_stream(spark: SparkSession, folder: str, pattern: str = "events.parquet", per_trigger: int = 1) -> DataFrame:
    """The events of the folder's files as a stream."""
    rows = spark.readStream.schema(EVENTS).option("pathGlobFilter", pattern).option("maxFilesPerTrigger", per_trigger).parquet(folder)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def event_facts(rows: DataFrame) -> DataFrame:
    """pred, a0, a1, mono, ts: the facts of the event rules, two for each row; a narrow step for streams and batches."""
    ev, cust = F.concat(F.lit("ev/"), F.col("event_id").cast("string")), F.concat(F.lit("cust/"), F.col("user_id").cast("string"))
    row = F.concat(F.lit("@"), ev)
    rule = F.lit(None).cast("string")
    for kind, label in TYPES.items():
        rule = F.when(F.col("event_type") == kind, F.lit(label)).otherwise(rule)
    typed = F.struct(F.concat(F.initcap("event_type"), F.lit("Event")).alias("pred"), ev.alias("a0"), F.lit(None).cast("string").alias("a1"), F.sort_array(F.array(row, rule)).alias("mono"))
    by = F.struct(F.lit("performedBy").alias("pred"), ev.alias("a0"), cust.alias("a1"), F.sort_array(F.array(row, F.lit("m24"))).alias("mono"))
    facts = rows.select("ts", F.explode(F.array(typed, by)).alias("f")).select("f.*", "ts")
    return facts.where(F.col("a0").isNotNull() & ~F.exists("mono", lambda x: x.isNull()))


def closed(facts: DataFrame, ontology: Ontology) -> DataFrame:
    """Concept facts with all their consequences among concepts: a join with the static closure, small by the ontology."""
    spark = facts.sparkSession
    rows = [(a, b, list(w)) for a, b, w in classify(ontology) if " " not in a + b and "-" not in a + b and a[0].isupper() and b[0].isupper()]
    table = spark.createDataFrame(rows, "pred string, super string, way array<string>")
    joined = facts.where(F.col("a1").isNull()).join(F.broadcast(table), "pred")
    return joined.select(F.col("super").alias("pred"), "a0", mul_idem(F.col("mono"), F.col("way")).alias("mono"), "ts")


def once(facts: DataFrame, delay: str = "1 day") -> DataFrame:
    """Set semantics of facts within the watermark."""
    keys = [c for c in ("pred", "a0", "a1", "mono") if c in facts.columns]
    return facts.withWatermark("ts", delay).dropDuplicatesWithinWatermark(keys)


def windowed(facts: DataFrame, width: str = "1 hour", slide: str | None = None, delay: str = "1 day") -> DataFrame:
    """Derivations and individuals of each predicate by tumbling or sliding window."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    out = facts.withWatermark("ts", delay).groupBy(w.alias("w"), "pred").agg(F.count(F.lit(1)).alias("n_derivations"), F.approx_count_distinct("a0").alias("n_individuals"))
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "pred", "n_derivations", "n_individuals")


def sessions(rows: DataFrame, gap: str = "30 minutes", delay: str = "1 day") -> DataFrame:
    """Events of a customer without a longer pause."""
    out = rows.withWatermark("ts", delay).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n_events"))
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "user_id", "n_events")


def followed_by_purchase(left: DataFrame, right: DataFrame, within: str = "1 day", delay: str = "1 day") -> DataFrame:
    """Clicks and views, and later purchases of the same customer within the interval: a join of two streams."""
    a = left.where(F.col("event_type").isin("click", "view")).select(F.col("event_id").alias("seen"), "user_id", F.col("ts").alias("seen_ts")).withWatermark("seen_ts", delay)
    b = right.where(F.col("event_type") == "purchase").select(F.col("event_id").alias("bought"), F.col("user_id").alias("buyer"), F.col("ts").alias("bought_ts")).withWatermark("bought_ts", delay)
    later = F.expr(f"user_id = buyer AND bought_ts > seen_ts AND bought_ts <= seen_ts + INTERVAL {within}")
    return a.join(b, later).select("seen", "bought", "user_id", "seen_ts", "bought_ts")


def append_new(path: str):
    """A foreachBatch function that writes each micro-batch's own facts once, under its number: work grows with the batch alone.

    A batch run again after a failure replaces what it wrote. Facts that come in several batches stand once in
    ``stored_facts``, which makes them distinct; ``compact`` does so for good.
    """

    def write(batch: DataFrame, number: int) -> None:
        batch.dropDuplicates(fact_keys(batch)).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return write


def fact_keys(facts: DataFrame) -> list[str]:
    return [c for c in ("pred", "a0", "a1", "mono") if c in facts.columns]


def stored_facts(spark: SparkSession, path: str, schema) -> DataFrame:
    """The store's facts, each once."""
    rows = spark.read.schema(schema).option("recursiveFileLookup", "true").parquet(path)
    return rows.dropDuplicates(fact_keys(rows))


def compact(spark: SparkSession, path: str, into: str, schema) -> None:
    """The store's facts, each once, in a folder for each predicate."""
    stored_facts(spark, path, schema).write.partitionBy("pred").parquet(into)


def merge_monomials(path: str):
    """A foreachBatch function for answers with provenance: per answer and batch its new monomials, packed.

    Sums of monomials only grow with appended rows, so an answer's polynomial is the union over the batches.
    """

    def write(batch: DataFrame, number: int) -> None:
        keys = [c for c in batch.columns if c not in ("mono", "ts")]
        batch.groupBy(*keys).agg(F.collect_set("mono").alias("monos")).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return write


def shared_path(spark: SparkSession, name: str) -> str:
    """A fresh path in the folder that all executors share."""
    return f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"


def heartbeat(rows: DataFrame, at: str = "9999-01-01 00:00:00") -> DataFrame:
    """The stream of events with one more, of a far time: it moves the watermark past all others, so that a run over a
    finished input closes every window. Its own window never closes."""
    spark = rows.sparkSession
    path = shared_path(spark, "heartbeat")
    one = spark.sql(f"SELECT -1L AS event_id, timestamp_ntz'{at}' AS ts, -1L AS user_id, 'click' AS event_type, 0.0D AS value, '' AS props")
    one.write.parquet(path)
    beat = spark.readStream.schema(EVENTS).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))
    return rows.unionByName(beat)


def drain(stream: DataFrame, *, store: bool = False) -> DataFrame:
    """Run the stream over all that is there and return what it made (store: batch by batch, each fact once)."""
    spark = stream.sparkSession
    out, state = shared_path(spark, "stream"), shared_path(spark, "state")
    writer = stream.writeStream.option("checkpointLocation", state).trigger(availableNow=True)
    if store:
        query = writer.foreachBatch(append_new(out)).start()
    else:
        query = writer.format("parquet").outputMode("append").option("path", out).start()
    query.awaitTermination()
    return stored_facts(spark, out, stream.schema) if store else spark.read.schema(stream.schema).parquet(out)


def reconcile(streamed: DataFrame, batch: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Rows that the stream missed (late ones), and rows it has beyond the batch."""
    keys = batch.columns
    return batch.exceptAll(streamed.select(*keys)), streamed.select(*keys).exceptAll(batch)
