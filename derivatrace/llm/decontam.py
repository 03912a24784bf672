"""Benchmark decontamination by winnowing and a join of fingerprints.

Words are lower-cased runs. A benchmark window is ``SPAN`` consecutive words of an item (a shorter item is one window).
Winnowing keeps, of every ``SPAN - K + 1`` neighbouring K-word hashes, the smallest: two texts that share SPAN words in
a row keep the same hash at the same place of that stretch, so every shared window has a shared fingerprint.

The benchmark's windows are a distributed table, keyed by 128-bit hashes of their words. Its fingerprints also go into a
bit filter of at most ``BITS`` bits, whatever the benchmark's size, which the documents meet first: each winnowed
fingerprint that passes is extended to the windows around it, and these are joined with the benchmark's by their hash. A
window that very many documents hold is spread over ``SALTS`` tasks; what the filter lets through by chance finds no
partner in the join. Hits are gathered by document: nothing else is, and texts aren't moved. Items of fewer than SPAN
words have no such guarantee and are looked for by their whole word sequence at every place.

Nulls and edges: a null or wordless text is clean; null, empty or wordless items have no window; items with a null id
mark words but aren't listed; repeated items count once by id; an empty benchmark leaves everything clean; repeated
rows of documents are judged each, alike (rows of equal id and text are one document to the join).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from derivatrace.llm.common import WORD_TABLE, as_bytes, column, cut, free_prefix, map_columns, only_keyed, pieces, row_key, spread_join, tidy

SPAN, K, BITS, SALTS = 10, 5, 1 << 28, 16
_BASE = np.uint64(0x9E3779B97F4A7C15)


def words(text: bytes) -> list[bytes]:
    return text.translate(WORD_TABLE).split()


def numbers(ws: list[bytes]) -> np.ndarray:
    """A 64-bit number for each word."""
    return np.fromiter(map(xxhash.xxh3_64_intdigest, ws), np.uint64, len(ws))


def gram_hashes(ids: np.ndarray, k: int) -> np.ndarray:
    """A mixed 64-bit hash of every k neighbours."""
    n = len(ids) - k + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    v, h = ids.astype(np.uint64), np.zeros(n, np.uint64)
    for i in range(k):
        h = h * _BASE + v[i : i + n] + np.uint64(1)
        h ^= h >> np.uint64(29)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    return h ^ (h >> np.uint64(32))


def winnowed(hashes: np.ndarray, window: int) -> np.ndarray:
    """Places of the smallest hash of every window (rightmost of equals); all places of a shorter sequence's minimum."""
    n = len(hashes)
    if n == 0:
        return np.empty(0, np.int64)
    w = min(window, n)
    views = np.lib.stride_tricks.sliding_window_view(hashes, w)[:, ::-1]
    at = np.arange(len(views)) + (w - 1) - views.argmin(axis=1)
    return at[np.r_[True, at[1:] != at[:-1]]] if len(at) else at


def windows_of(item: list[bytes], span: int) -> Iterator[tuple[bytes, int]]:
    """(128-bit hash, words) of every window of an item."""
    n = min(span, len(item))
    for i in range(len(item) - n + 1):
        if n:
            yield xxhash.xxh3_128_digest(b" ".join(item[i : i + n])), n


def window_rows(items: DataFrame, span: int) -> DataFrame:
    """h1, h2, n, item: the windows of (item, text) rows, each once an item."""

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for s in pieces(b, 64):
                rows = [(h, n, i) for i, t in zip(s.column("item").to_pylist(), as_bytes(s, "text"), strict=True) for h, n in windows_of(words(t), span)]
                hashes = np.frombuffer(b"".join(h for h, _, _ in rows), "<i8").reshape(-1, 2)
                yield pa.RecordBatch.from_arrays([pa.array(hashes[:, 0].copy()), pa.array(hashes[:, 1].copy()), pa.array([n for _, n, _ in rows], pa.int32()), pa.array([i for _, _, i in rows], pa.string())], names=["h1", "h2", "n", "item"])

    return items.mapInArrow(make, "h1 long, h2 long, n int, item string").distinct()


def print_rows(items: DataFrame, span: int, k: int) -> DataFrame:
    """n, print: the winnowed fingerprints of items, and for shorter ones the hash of all their words; n: words in a window."""

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for s in pieces(b, 64):
                ns, prints = [np.empty(0, np.int32)], [np.empty(0, np.uint64)]
                for t in as_bytes(s, "text"):
                    ids = numbers(words(t))
                    n = min(span, len(ids))
                    grams = gram_hashes(ids, k if n == span else max(n, 1))
                    found = grams[winnowed(grams, span - k + 1)] if n == span else grams
                    ns.append(np.full(len(found), n, np.int32))
                    prints.append(found)
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(ns)), pa.array(np.concatenate(prints).view(np.int64))], names=["n", "print"])

    return items.mapInArrow(make, "n int, print long").distinct()


def bit_filter(prints: DataFrame, bits: int = BITS) -> tuple[np.ndarray, list[int]]:
    """A filter with two bits for each fingerprint, 64 an entry and at most ``bits`` in all, and the sizes of windows."""
    sizes = {r["n"]: r["c"] for r in prints.groupBy("n").agg(F.count(F.lit(1)).alias("c")).collect()}
    size = min(bits, max(64, 1 << (64 * sum(sizes.values())).bit_length()))
    at = F.explode(F.array(F.col("print").bitwiseAND(F.lit(size - 1).cast("long")), F.shiftrightunsigned("print", 32).bitwiseAND(F.lit(size - 1).cast("long"))))
    words_ = prints.select(at.alias("at")).select(F.shiftright("at", 6).alias("w"), F.expr("shiftleft(1L, cast(at & 63L as int))").alias("b")).groupBy("w").agg(F.bit_or("b").alias("b")).toArrow()  # at most bits / 64 rows
    out = np.zeros(max(1, size // 64), np.int64)
    out[words_.column("w").to_numpy()] = words_.column("b").to_numpy()
    return out.view(np.uint64), sorted(sizes)


def passes(filter_: np.ndarray, prints: np.ndarray) -> np.ndarray:
    mask = np.uint64(64 * len(filter_) - 1)
    held = lambda at: (filter_[(at >> np.uint64(6)).astype(np.int64)] >> (at & np.uint64(63)) & np.uint64(1)).astype(bool)
    return held(prints & mask) & held(prints >> np.uint64(32) & mask)


def candidates(texts: list[bytes], filter_: np.ndarray, sizes: list[int], span: int, k: int) -> Iterator[tuple[int, list[tuple[int, int, bytes]]]]:
    """For each text its number of words and the windows (place, words, hash) around fingerprints that pass the filter."""
    split = [words(t) for t in texts]
    lengths = np.array([len(w) for w in split], np.int64)
    flat = [w for ws in split for w in ws]
    ids, ends = numbers(flat), np.cumsum(lengths)
    begins = ends - lengths
    found: list[list[tuple[int, int, bytes]]] = [[] for _ in texts]
    for n in sizes:
        if n == span:
            grams = gram_hashes(ids, k)
            kept = winnowed(grams, span - k + 1)
            near = kept[passes(filter_, grams[kept])]
            starts = np.unique((near[:, None] - np.arange(span - k + 1)).reshape(-1))
        else:
            starts = np.flatnonzero(passes(filter_, gram_hashes(ids, n)))
        starts = starts[(starts >= 0) & (starts + n <= len(ids))]
        own = np.searchsorted(ends, starts, "right")
        inside = starts + n <= ends[own] if len(starts) else np.empty(0, bool)
        for t, at in zip(own[inside].tolist(), starts[inside].tolist(), strict=True):
            found[t].append((at - int(begins[t]), n, xxhash.xxh3_128_digest(b" ".join(flat[at : at + n]))))
    return zip(lengths.tolist(), found, strict=True)


_FOUND = T.ArrayType(T.StructType([T.StructField("at", T.IntegerType()), T.StructField("n", T.IntegerType()), T.StructField("h1", T.LongType()), T.StructField("h2", T.LongType())]))
_ARROW_FOUND = pa.list_(pa.struct([("at", pa.int32()), ("n", pa.int32()), ("h1", pa.int64()), ("h2", pa.int64())]))


def scan(docs: DataFrame, benchmark: DataFrame, *, id_col: str, text: str, item_col: str, item_text: str, span: int, k: int, bits: int) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Documents (id, key, n_words), their hit windows (id, key, at, n), and their items (id, key, item), all without texts."""
    items = benchmark.select(column(benchmark, item_col).cast("string").alias("item"), column(benchmark, item_text).alias("text")).where("text is not null")
    filter_, sizes = bit_filter(print_rows(items, span, k), bits)
    held = docs.sparkSession.sparkContext.broadcast(filter_)
    lean = docs.select(column(docs, id_col).alias("id"), row_key(docs, text).alias("key"), column(docs, text).alias("text"))

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for s in pieces(b, 128):
                n_words, found = zip(*candidates(as_bytes(s, "text"), held.value, sizes, span, k), strict=True)
                rows = [[dict(zip(("at", "n", "h1", "h2"), (at, n, *np.frombuffer(h, "<i8").tolist()), strict=True)) for at, n, h in f] for f in found]
                yield pa.RecordBatch.from_arrays([s.column("id"), s.column("key"), pa.array(n_words, pa.int64()), pa.array(rows, _ARROW_FOUND)], names=["id", "key", "n_words", "found"])
        tidy()

    met = cut(map_columns(lean, [T.StructField("n_words", T.LongType()), T.StructField("found", _FOUND)], make, keep=["id", "key"]), "windows-met")
    windows = cut(window_rows(items, span), "benchmark-windows")
    asked = met.where(F.size("found") > 0).select("id", "key", F.explode("found").alias("f")).select("id", "key", "f.*").distinct()
    hits = cut(spread_join(asked, windows.select("h1", "h2", "n").distinct(), ["h1", "h2", "n"], SALTS, F.xxhash64("id", "key", "at")), "window-hits")
    own = hits.select("id", "key", "h1", "h2", "n").distinct()
    listed = spread_join(own, windows.where("item is not null"), ["h1", "h2", "n"], SALTS, F.xxhash64("id", "key")).select("id", "key", "item").distinct()
    return met.select("id", "key", "n_words"), hits.select("id", "key", "at", "n"), listed


def covered(spans: Column) -> Column:
    """How many places a sorted array of (at, n) covers."""
    start = F.struct(F.lit(0).cast("long").alias("total"), F.lit(0).alias("end"))

    def step(acc, x):
        stop = x["at"] + x["n"]
        return F.struct((acc["total"] + F.greatest(F.lit(0), stop - F.greatest(x["at"], acc["end"]))).alias("total"), F.greatest(acc["end"], stop).alias("end"))

    return F.aggregate(spans, start, step, lambda acc: acc["total"])


def contamination(docs: DataFrame, benchmark: DataFrame, *, id_col: str = "doc_id", text: str = "text", item_col: str = "item_id", item_text: str = "text", span: int = SPAN, k: int = K, bits: int = BITS) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256 and contaminated of every document."""
    rows, hits, items = scan(docs, benchmark, id_col=id_col, text=text, item_col=item_col, item_text=item_text, span=span, k=k, bits=bits)
    marks = hits.groupBy(F.col("id").alias("i1"), F.col("key").alias("k1")).agg(covered(F.sort_array(F.collect_list(F.struct("at", "n")))).alias("n_hit"))
    listed = items.groupBy(F.col("id").alias("i2"), F.col("key").alias("k2")).agg(F.sort_array(F.collect_list("item")).alias("items"))
    out = rows.join(marks, rows["id"].eqNullSafe(F.col("i1")) & (rows["key"] == F.col("k1")), "left").join(listed, rows["id"].eqNullSafe(F.col("i2")) & (rows["key"] == F.col("k2")), "left")
    own = F.coalesce("items", F.expr("cast(array() as array<string>)"))
    n_hit = F.coalesce("n_hit", F.lit(0).cast("long"))
    return out.select(F.col("id").alias("doc_id"), "n_words", n_hit.alias("n_hit"), F.size(own).cast("long").alias("n_items"), F.sha2(F.array_join(own, ","), 256).alias("items_sha256"), (n_hit > 0).alias("contaminated"))


def decontaminated(docs: DataFrame, benchmark: DataFrame, *, id_col: str = "doc_id", text: str = "text", item_col: str = "item_id", item_text: str = "text", span: int = SPAN, k: int = K, bits: int = BITS) -> DataFrame:
    """The documents that share no window with the benchmark, with their own columns."""
    _, hits, _ = scan(docs, benchmark, id_col=id_col, text=text, item_col=item_col, item_text=item_text, span=span, k=k, bits=bits)
    p = free_prefix(docs, "d")
    hit = hits.select(F.col("id").alias(f"{p}id"), F.col("key").alias(f"{p}key")).distinct()
    kept = only_keyed(docs, hit, id_col, (text,), p, how="left_anti")
    return kept.select(*[column(kept, c) for c in docs.columns])
