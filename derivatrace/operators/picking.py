"""Of answers that pair two variables, those of a small md5, without making a row for each pair.

Where a body's last join multiplies its two sides, either side's values are listed once for each key of the join. The
digests of a key's pairs are made by arrays (``functions.digests``), and pairs below a bound alone become rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from derivatrace.functions.digests import below
from derivatrace.operators.joins import Halves, joined
from derivatrace.operators.provenance import _join_order
from derivatrace.plans.cq import CQ
from derivatrace.plans.instance import Instance
from derivatrace.plans.rewrite import foldings, pruned

#: Texts of a list that go together; longer lists are cut, and the pieces of either side paired.
PIECE = 512
#: Rows of an Arrow batch that are paired at a time.
ROWS = 2048


def pairs_below(instance: Instance, cq: CQ, share: float) -> DataFrame | None:
    """The answers, some of them repeated, whose md5 lies in the first part of all md5s, and maybe a few beyond; None: not an answer of this kind."""
    bodies = pruned(list(foldings(cq, instance.ontology.positive)))
    if len(bodies) != 1 or cq.where or len(cq.head) != 2:
        return None
    sides = joined(instance, list(bodies[0]), cq.head, order=_join_order, labels=False, early=False, halves=True)
    own = sides and sides.multiplies and _dealt(sides, cq.head)
    if not own:
        return None
    texts = [_pieces(df.selectExpr(*sides.on, f"{sides.texts[h]} as _text"), sides.on, h) for h, df in zip(cq.head, own, strict=True)]
    pairs = texts[0].join(texts[1], sides.on).select(*cq.head)
    bound = min(int(share * 2**32), 2**32 - 1)

    def make(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, ROWS):
                yield from _paired(batch.slice(at, ROWS), bound)

    return pairs.mapInArrow(make, ", ".join(f"{h} string" for h in cq.head))


def _dealt(sides: Halves, head: tuple[str, ...]) -> tuple[DataFrame, DataFrame] | None:
    """The side of the first answer variable, and that of the second."""
    for one, other in ((sides.left, sides.right), (sides.right, sides.left)):
        if set(sides.columns[head[0]]) <= set(one.columns) and set(sides.columns[head[1]]) <= set(other.columns):
            return one, other
    return None


def _pieces(df: DataFrame, on: list[str], name: str) -> DataFrame:
    lists = df.groupBy(*on).agg(F.collect_set("_text").alias("_list"))
    return lists.selectExpr(*on, f"explode(transform(sequence(1, size(_list), {PIECE}), i -> slice(_list, i, {PIECE}))) as {name}")


def _texts(column: pa.Array) -> tuple[tuple[np.ndarray, np.ndarray], np.ndarray, pa.Array]:
    """Bytes and bounds of the texts in lists, where lists begin among them, and the texts."""
    flat = column.flatten().cast(pa.large_string())
    groups = np.concatenate([[0], np.cumsum(column.value_lengths().to_numpy(zero_copy_only=False))]).astype(np.int64)
    _, at, data = flat.buffers()
    at = np.frombuffer(at, np.int64)[flat.offset : flat.offset + len(flat) + 1]
    return (np.frombuffer(data, np.uint8), at), groups, flat


def _paired(batch: pa.RecordBatch, bound: int) -> Iterator[pa.RecordBatch]:
    (left, lgroups, ltexts), (right, rgroups, rtexts) = map(_texts, batch.columns)
    for i, j in below(left, right, (lgroups, rgroups), bound):
        yield pa.RecordBatch.from_arrays([ltexts.take(pa.array(i)).cast(pa.string()), rtexts.take(pa.array(j)).cast(pa.string())], batch.schema.names)
