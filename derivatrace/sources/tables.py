"""Readers of source tables, and writers of facts and polynomials."""

from __future__ import annotations

import tempfile
import weakref
from collections.abc import Mapping

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from derivatrace.operators.algebra import answer_columns

#: Columns that the workloads rely on, checked when a table is loaded.
EXPECTED = {
    "region": {"r_regionkey": "int"}, "nation": {"n_nationkey": "int", "n_regionkey": "int"},
    "customer": {"c_custkey": "bigint", "c_nationkey": "int", "c_acctbal": "double", "c_mktsegment": "string"},
    "supplier": {"s_suppkey": "bigint", "s_nationkey": "int"},
    "part": {"p_partkey": "bigint", "p_name": "string", "p_brand": "string", "p_type": "string", "p_size": "int"},
    "orders": {"o_orderkey": "bigint", "o_custkey": "bigint", "o_orderstatus": "string", "o_orderpriority": "string"},
    "lineitem": {"l_orderkey": "bigint", "l_partkey": "bigint", "l_suppkey": "bigint", "l_linenumber": "int", "l_returnflag": "string"},
    "events": {"event_id": "bigint", "user_id": "bigint", "event_type": "string"},
    "documents": {"doc_id": "bigint", "text": "string", "lang": "string", "source": "string"},
    "labels": {"doc_id": "bigint", "quality": "int", "toxic": "int"},
    "embeddings": {"vec_id": "bigint", "embedding": "array<float>", "label": "int"},
    "pages": {"page_id": "bigint", "url": "string"}, "benchmark": {"item_id": "bigint", "text": "string"},
    "conversations": {"conv_id": "bigint", "turn": "bigint", "role": "string"},
}


#: Tables opened by a session, by folder and name.
_OPENED: weakref.WeakKeyDictionary[SparkSession, dict[tuple[str, str], DataFrame]] = weakref.WeakKeyDictionary()


class Tables(Mapping):
    """The parquet tables of a folder by name. Each is opened and its schema checked when it is first asked for, once a
    session; ``forget`` makes a session look at the files anew."""

    def __init__(self, spark: SparkSession, path: str, names: list[str] | None = None):
        self.spark, self.path, self.names = spark, path.rstrip("/"), list(names or EXPECTED)

    def __getitem__(self, name: str) -> DataFrame:
        if name not in self.names:
            raise KeyError(name)
        opened = _OPENED.setdefault(self.spark, {})
        if (self.path, name) not in opened:
            df = self.spark.read.parquet(f"{self.path}/{name}.parquet")
            kinds = dict(df.dtypes)
            if wrong := {c: kinds.get(c) for c, k in EXPECTED.get(name, {}).items() if kinds.get(c) != k}:
                raise ValueError(f"{name}: unexpected columns {wrong}")
            opened[self.path, name] = df
        return opened[self.path, name]

    def __iter__(self):
        return iter(self.names)

    def __len__(self) -> int:
        return len(self.names)


def load(spark: SparkSession, path: str, names: list[str] | None = None) -> Tables:
    """The parquet tables of a folder, lazily read, so only columns used are: all of them as they are used, or those named at once."""
    out = Tables(spark, path, names)
    for name in names or ():
        out[name]
    return out


def forget(spark: SparkSession) -> None:
    """Forget the opened tables of a session, as after their files have changed."""
    _OPENED.pop(spark, None)


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir, or the session's checkpoint folder. Where neither is set, a local session gets a temporary one;
    on a cluster that is an error, as executors share no such folder."""
    path = spark.conf.get("spark.checkpoint.dir", None)
    if not path:
        known = spark.sparkContext._jsc.sc().getCheckpointDir()
        path = known.get() if known.isDefined() else None
    if not path:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        path = tempfile.mkdtemp(prefix="derivatrace-")
        spark.sparkContext.setCheckpointDir(path)
    return path.rstrip("/")


def read(spark: SparkSession, fmt: str, path: str | None = None, *, schema: str | None = None, **options) -> DataFrame:
    """Any source that Spark reads: csv, json, orc, jdbc, or a table of the catalog."""
    if fmt == "table":
        return spark.read.table(path)
    reader = spark.read.format(fmt).options(**options)
    reader = reader.schema(schema) if schema else reader
    return reader.load(path) if path else reader.load()


def write_provenance(poly: DataFrame, path: str, *, buckets: int = 64, mode: str = "error") -> None:
    """The polynomial as parquet in folders by a hash of the answer, so that one answer is read from one folder."""
    keys = answer_columns(poly)
    bucket = F.pmod(F.xxhash64(*keys) if keys else F.lit(0), F.lit(buckets)).cast("int")
    poly.withColumn("bucket", bucket).write.mode(mode).partitionBy("bucket").parquet(path)


def read_provenance(spark: SparkSession, path: str, answer: dict[str, str] | None = None, *, buckets: int = 64) -> DataFrame:
    df = spark.read.parquet(path)
    keys = [c for c in df.columns if c not in ("mono", "coeff", "bucket")]
    if answer is not None:
        # The folder's number is worked out by Spark from constants, so partitions are pruned.
        df = df.where(F.col("bucket") == F.pmod(F.xxhash64(*[F.lit(answer[k]) for k in keys]) if keys else F.lit(0), F.lit(buckets)).cast("int"))
        for k in keys:
            df = df.where(F.col(k) == answer[k])
    return df.drop("bucket")


def materialise(facts: dict[str, DataFrame], path: str, mode: str = "error") -> None:
    """Derived facts, a folder for each predicate, clustered by subject."""
    for pred, df in facts.items():
        df.repartition("a0").sortWithinPartitions("a0").write.mode(mode).parquet(f"{path}/{pred}")


def save_as_table(facts: DataFrame, name: str, buckets: int = 64) -> None:
    """A bucketed catalog table: joins on the subject need no shuffle."""
    facts.write.bucketBy(buckets, "a0").sortBy("a0").saveAsTable(name)


def stored(spark: SparkSession, path: str, preds: list[str]) -> dict[str, DataFrame]:
    return {p: spark.read.parquet(f"{path}/{p}") for p in preds}
