"""Substring dedup by sliding sentence spans.

A text is cut at sentence ends and, where none is near, after words picked by winnowing: each window of ``WINDOW``
words without a sentence end has a cut after its word of least hash. So cuts depend on the words nearby alone, and every
stretch of over 50 words that texts share has the same cuts in each of them, from within its first 13 words to within
its last 14. Of the runs of consecutive pieces with at least ``SENTENCES`` pieces and ``WORDS`` words, the shortest from
each piece on and the shortest up to each piece are hashed (128 bits, over lower-case words), all runs of the corpus are
joined, and a piece is removed where a run that covers it has occurred before. These runs cover all that longer
ones do. First is the least document id, then the place in the text.

Hot runs: occurrences are counted with pre-aggregation, and the join back to the runs is one that AQE splits.

Nulls and edges: a null text has no sentence and stays null; an empty text stays empty; texts too short for a run stay
as they are; ids that are null come first; rows of equal id and text are one document and get the same result each; a
document that repeats a run of its own loses the later one.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from itertools import accumulate
from zlib import crc32

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from derivatrace.llm.common import WORD_TABLE, column, cut, map_columns, tidy

SENTENCES, WORDS, WINDOW = 2, 25, 13
# One set first, so that the search skips all else.
_END = re.compile(r"[.!?…。！？\n](?:(?<=\n)|(?=[ \t-\r]))[ \t-\r]*")
#: As WORD_TABLE, but only white space gives spaces; other bytes between words give zeros.
_TOKEN_TABLE = bytes(32 if 9 <= i <= 13 or i == 32 else 0 if c == 32 else c for i, c in enumerate(WORD_TABLE))
_ZEROS = bytes.maketrans(b"\0", b" ")


def winnowed(keys: np.ndarray) -> set[int]:
    """Places of the least key of each window of ``WINDOW`` keys, of equal ones the last."""
    if len(keys) < WINDOW:
        return set()
    mask = (1 << 31) - 1
    least, size = keys.astype(np.uint64) << np.uint64(31) | np.arange(mask, mask - len(keys), -1, dtype=np.uint64), 1
    while size < WINDOW:
        step = min(size, WINDOW - size)
        least, size = np.minimum(least[:-step], least[step:]), size + step
    return set((mask - (least & np.uint64(mask)).astype(np.int64)).tolist())


def token_ends(text: str, whole: bytes) -> list[int]:
    """End of each token and the white space after it, in code points; ``whole`` has the text's bytes with only white space as spaces."""
    word = np.frombuffer(whole, np.uint8) != 32
    begins = word.copy()
    begins[1:] &= ~word[:-1]
    ends = np.append(np.flatnonzero(begins)[1:], len(whole))
    if len(whole) != len(text):
        first = np.frombuffer(text.encode(), np.uint8) & 0xC0 != 0x80
        ends = np.cumsum(first)[ends - 1]
    return ends.tolist()


def sentences(text: str) -> list[tuple[int, int, bytes]]:
    """(start, end, normal form) of each piece that has a word; together they cover the text."""
    whole = text.encode().translate(_TOKEN_TABLE)
    bare = [t.strip(b"\0") for t in whole.split()]
    if not any(bare):
        return []
    ends = token_ends(text, whole)
    stops = {m.end() for m in _END.finditer(text)}
    if not all(bare):
        # What has no word goes with the word before it, and so does its sentence end.
        full = [i for i, t in enumerate(bare) if t]
        last = [*(i - 1 for i in full[1:]), len(ends) - 1]
        stops |= {ends[b] for a, b in zip(full, last, strict=True) if any(ends[i] in stops for i in range(a, b))}
        bare, ends = [bare[i] for i in full], [ends[b] for b in last]
    stop = [i for i, e in enumerate(ends) if e in stops]
    keys = np.fromiter(map(crc32, bare), np.int64, len(bare)) + 1
    keys[stop] = 0
    if b"\0" in b" ".join(bare):
        bare = [b" ".join(t.translate(_ZEROS).split()) for t in bare]
    out, at, start = [], 0, 0
    for i in sorted(winnowed(keys) | set(stop) | {len(bare) - 1}):
        out.append((start, ends[i], b" ".join(bare[at : i + 1])))
        at, start = i + 1, ends[i]
    return out


def runs(found: list[tuple[int, int, bytes]]) -> Iterator[tuple[int, int, bytes]]:
    """(first piece, number of pieces, hash) of the shortest long-enough run from each piece on and up to each piece."""
    forms = [f for _, _, f in found]
    sums = list(accumulate((f.count(b" ") + 1 for f in forms), initial=0))
    made: list[tuple[int, int]] = []
    i = 0
    for end in range(SENTENCES, len(found) + 1):
        # The runs from these pieces on end here first, the last of them is the shortest that ends here.
        before = i
        while i <= end - SENTENCES and sums[end] - sums[i] >= WORDS:
            i += 1
        if i > before:
            made += [(a, end) for a in range(before, i)]
        elif i:
            made.append((i - 1, end))
    made.sort()
    for a, e in made:
        yield a, e - a, xxhash.xxh3_128_digest(b"\n".join(forms[a:e]))


def span_rows(docs: DataFrame) -> DataFrame:
    """h1, h2, doc_id, key, at, n: a row for every run of every text of (doc_id, key, text)."""

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo in range(0, b.num_rows, 256):
                s = b.slice(lo, 256)
                made = [list(runs(sentences(t))) for t in s.column("text").to_pylist()]
                sizes = [len(m) for m in made]
                if not sum(sizes):
                    continue
                flat = [r for m in made for r in m]
                hashes = np.frombuffer(b"".join(r[2] for r in flat), "<i8").reshape(-1, 2)
                own = pa.array(np.repeat(np.arange(s.num_rows), sizes))
                yield pa.RecordBatch.from_arrays([pa.array(hashes[:, 0].copy()), pa.array(hashes[:, 1].copy()), s.column("doc_id").take(own), s.column("key").take(own), pa.array([r[0] for r in flat], pa.int32()), pa.array([r[1] for r in flat], pa.int32())], names=["h1", "h2", "doc_id", "key", "at", "n"])
        tidy()

    out = T.StructType([T.StructField("h1", T.LongType()), T.StructField("h2", T.LongType()), docs.schema["doc_id"], T.StructField("key", T.LongType()), T.StructField("at", T.IntegerType()), T.StructField("n", T.IntegerType())])
    return docs.mapInArrow(make, out)


def repeated_runs(spans: DataFrame) -> DataFrame:
    """doc_id, key, at, n of every run that isn't the first of its kind."""
    doubled = spans.groupBy("h1").agg(F.count(F.lit(1)).alias("c")).where(F.col("c") > 1).select("h1")
    again = cut(spans.join(doubled, "h1"), "span-candidates")
    first = again.groupBy("h1", "h2").agg(F.min(F.struct("doc_id", "key", "at")).alias("first"))
    return again.join(first, ["h1", "h2"]).where(~F.struct("doc_id", "key", "at").eqNullSafe(F.col("first"))).select("doc_id", "key", "at", "n")


def dedup_spans(docs: DataFrame, *, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_removed (sentences), removed (start, end in code points) and the text without removed sentences."""
    body = column(docs, text)
    lean = docs.select(column(docs, id_col).alias("doc_id"), body.alias("text"), F.xxhash64(column(docs, id_col), body).alias("key"))
    spans = cut(span_rows(lean.where(body.isNotNull())), "spans")
    marks = repeated_runs(spans).groupBy(F.col("doc_id").alias("_id"), F.col("key").alias("_key")).agg(F.sort_array(F.collect_set(F.struct("at", "n"))).alias("marks"))
    joined = lean.join(marks, lean["doc_id"].eqNullSafe(F.col("_id")) & (lean["key"] == F.col("_key")), "left").select("doc_id", "text", "marks")

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo in range(0, b.num_rows, 256):
                s = b.slice(lo, 256)
                rows = [clean(t, m) for t, m in zip(s.column("text").to_pylist(), s.column("marks").to_pylist(), strict=True)]
                k, gone, left = zip(*rows, strict=True)
                kind = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))
                yield pa.RecordBatch.from_arrays([s.column("doc_id"), pa.array(k, pa.int64()), pa.array([[{"start": a, "end": e} for a, e in g] for g in gone], kind), pa.array(left, pa.string())], names=["doc_id", "n_removed", "removed", "text"])
        tidy()

    removed = T.ArrayType(T.StructType([T.StructField("start", T.LongType()), T.StructField("end", T.LongType())]))
    return map_columns(joined, [T.StructField("n_removed", T.LongType()), T.StructField("removed", removed), T.StructField("text", T.StringType())], make, keep=["doc_id"])


def clean(text: str | None, marks: list[dict] | None) -> tuple[int, list[tuple[int, int]], str | None]:
    """Removed sentences, their joined stretches, and the text that is left."""
    if text is None or not marks:
        return 0, [], text
    found = sentences(text)
    gone = sorted({i for m in marks for i in range(m["at"], m["at"] + m["n"])})
    cutouts: list[tuple[int, int]] = []
    for i in gone:
        a, b, _ = found[i]
        if cutouts and cutouts[-1][1] == a:
            cutouts[-1] = (cutouts[-1][0], b)
        else:
            cutouts.append((a, b))
    left, at = [], 0
    for a, b in cutouts:
        left.append(text[at:a])
        at = b
    left.append(text[at:])
    return len(gone), cutouts, "".join(left)
