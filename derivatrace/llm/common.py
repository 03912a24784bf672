"""Helpers that every corpus operator shares: shared-folder tables, fresh column names, Arrow mapping."""

from __future__ import annotations

import contextlib
import ctypes
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from derivatrace.sources.tables import shared_folder

#: Word bytes after lower-casing A-Z: digits, a-z and every byte of a non-ASCII character.
WORD_TABLE = bytes(c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256))
#: Only lower-cases A-Z.
LOWER_TABLE = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share, from spark.checkpoint.dir; a temporary one only where that is unset, in a local session."""
    return shared_folder(spark)


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/derivatrace-{name}-{uuid.uuid4().hex}"


def cut(df: DataFrame, name: str) -> DataFrame:
    """Write to the shared folder and read again: lineage ends there and lost executors cost one stage at most."""
    path = fresh_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def column(df: DataFrame, name: str) -> Column:
    """A column by its literal name, dots included."""
    return df["`" + name.replace("`", "``") + "`"]


def free_prefix(df: DataFrame, letter: str) -> str:
    """A prefix that no column of the frame starts with."""
    p = letter + "__"
    while any(c.lower().startswith(p) for c in df.columns):
        p = letter + p
    return p


def row_key(df: DataFrame, *names: str) -> Column:
    """A hash of these columns. With the id beside it, it stands for a row: rows alike in id and these are interchangeable."""
    return F.xxhash64(*[column(df, n) for n in names])


def only_keyed(docs: DataFrame, keys: DataFrame, id_col: str, names: tuple[str, ...], p: str, how: str = "left_semi") -> DataFrame:
    """The documents whose (id, row key) is among the keys (columns <p>id, <p>key); texts move once, by that key."""
    marked = docs.withColumn(f"{p}own", row_key(docs, *names))
    return marked.join(keys, column(marked, id_col).eqNullSafe(keys[f"{p}id"]) & (marked[f"{p}own"] == keys[f"{p}key"]), how)


def spread_join(rows: DataFrame, keyed: DataFrame, on: list[str], salts: int, by: Column) -> DataFrame:
    """Inner join of many rows with a table of few rows a key: each key's rows are dealt over so many tasks by a hash,
    and the table's row stands in each of them. A hot key is split; nothing is collected or broadcast."""
    left = rows.withColumn("_salt", F.pmod(by, F.lit(salts)).cast("int"))
    right = keyed.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return left.join(right, [*on, "_salt"]).drop("_salt")


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def map_columns(df: DataFrame, added: list[T.StructField], make: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], keep: list[str] | None = None) -> DataFrame:
    """mapInArrow whose output is the kept input columns and then the added ones."""
    out = T.StructType([f for f in df.schema.fields if keep is None or f.name in keep] + added)
    return df.mapInArrow(make, out)


def as_bytes(batch: pa.RecordBatch, name: str) -> list[bytes]:
    """UTF-8 of a string column; null is empty."""
    return [b or b"" for b in batch.column(name).cast(pa.binary()).to_pylist()]


def pieces(batch: pa.RecordBatch, rows: int) -> Iterator[pa.RecordBatch]:
    """The batch in runs of so many rows, so that what is made of a run stays small."""
    for i in range(0, batch.num_rows, rows):
        yield batch.slice(i, rows)


def tidy() -> None:
    """Give freed memory back at the end of a task: workers are reused, and idle ones should hold little."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # not every C library can
        ctypes.CDLL(None).malloc_trim(0)


def ascii_lower(col: Column) -> Column:
    return F.translate(col, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
