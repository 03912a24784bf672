"""SimHash near-dedup by exact tiled comparison.

Every text gets a 64-bit fingerprint: each bit is the majority of the hashes of its word shingles. Texts of equal
fingerprint are one node. Two fingerprints that differ in at most ``radius`` bits agree wholly on at least
``blocks - radius`` of any ``blocks`` parts of the 64 bits, so the nodes are dealt into groups by every choice of that
many parts: each linked pair meets in some group, and the work isn't quadratic in the corpus. Within a group the
fingerprints, sorted by population count, are compared in tiles with numpy exclusive-or and bit counts; a pair of tiles
whose counts differ beyond the radius is skipped. A group gives the links of a spanning forest only. Groups of more
than ``TILE`` nodes are split by population count and hash into tiles, and each pair of tiles is a task of its own.
The number of parts follows from the number of nodes by a cost estimate; every choice finds the same links.

Nulls and edges: a null, empty or blank text has fingerprint zero and is linked like any other; a text of fewer words
than a shingle is one shingle; ids that are null come last when a group's first document is chosen (its component id is
null only if all are); repeated rows share a fingerprint and so a component; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import accumulate, combinations
from math import comb

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from derivatrace.llm.common import LOWER_TABLE, as_bytes, column, cut, free_prefix, only_keyed, row_key, spread_join, tidy
from derivatrace.llm.components import SALTS, components

WORDS, SEED, RADIUS, TILE, SUBTILE, STEP = 4, 42, 4, 4096, 512, 1 << 15
#: Tasks over which the documents of one fingerprint are dealt when they take its component.
COPIES = 4
_hash = xxhash.xxh64_intdigest


def fingerprint(text: bytes, k: int = WORDS) -> int:
    """The text's 64-bit fingerprint, by XXH64 of its shingles."""
    words = text.translate(LOWER_TABLE).split()
    if not words:
        return 0
    body, n = b" ".join(words), max(1, len(words) - k + 1)
    ends = list(accumulate([len(w) + 1 for w in words]))
    starts = [0, *ends]
    if len(words) < k:
        shingles = [body]
    else:
        shingles = [body[a : b - 1] for a, b in zip(starts, ends[k - 1 :])]  # noqa: B905
    votes = np.zeros(64, np.int64)
    for i in range(0, n, STEP):
        part = np.fromiter((_hash(s, SEED) for s in shingles[i : i + STEP]), np.uint64, min(STEP, n - i))
        votes += np.unpackbits(part.view(np.uint8), bitorder="little").reshape(-1, 64).sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * votes > n, bitorder="little").view("<u8")[0])


def with_fingerprints(docs: DataFrame, *, text: str, name: str, k: int = WORDS) -> DataFrame:
    """The rows and their fingerprint as a signed long; the text column ``text`` is dropped if named with two underscores before."""
    kept = [c for c in docs.columns if c != text or not text.startswith("__")]

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(0, b.num_rows, 256):
                s = b.slice(i, 256)
                prints = np.array([fingerprint(t, k) for t in as_bytes(s, text)], np.uint64).view(np.int64)
                yield pa.RecordBatch.from_arrays([*[s.column(c) for c in kept], pa.array(prints)], names=[*kept, name])
        tidy()

    return docs.mapInArrow(make, T.StructType([*[docs.schema[c] for c in kept], T.StructField(name, T.LongType())]))


def masks(blocks: int, radius: int = RADIUS) -> list[int]:
    """A mask for every choice of blocks - radius parts of the 64 bits, as signed longs."""
    at = [64 * i // blocks for i in range(blocks + 1)]
    part = [((1 << (b - a)) - 1) << a for a, b in zip(at, at[1:], strict=False)]
    out = [sum(c) for c in combinations(part, blocks - radius)]
    return [m - (1 << 64) if m >> 63 else m for m in out]


def best_blocks(nodes: int, radius: int = RADIUS) -> int:
    """The number of parts with the least estimated cost: a dealt row is taken as 500 compared pairs."""
    cost = lambda b: comb(b, radius) * nodes * (500 + nodes / 2 ** (64 * (b - radius) / b + 1))
    return min(range(radius + 1, radius + 6), key=cost)


def _links(values: np.ndarray, sides: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Star links of the components that pairs within the radius make; sides: 0 within all, 1 against 2 only."""
    order = np.argsort(np.bitwise_count(values), kind="stable")
    v, side = values[order], sides[order]
    ones, label = np.bitwise_count(v).astype(np.int64), np.arange(len(v))
    cross = side.any()
    for i in range(0, len(v), SUBTILE):
        a = slice(i, min(i + SUBTILE, len(v)))
        for j in range(i, len(v), SUBTILE):
            b = slice(j, min(j + SUBTILE, len(v)))
            if ones[b.start] - ones[a.stop - 1] > radius:
                break
            near = np.bitwise_count(v[a, None] ^ v[None, b]) <= radius
            if cross:
                near &= side[a, None] != side[None, b]
            near &= label[a, None] != label[None, b]
            x, y = np.nonzero(near)
            x, y = x + i, y + j
            while len(x):
                lx, ly = label[x], label[y]
                open_ = lx != ly
                if not open_.any():
                    break
                lo, hi = np.minimum(lx, ly)[open_], np.maximum(lx, ly)[open_]
                x, y = x[open_], y[open_]
                # Each label goes to the least label it meets; then the pointers are followed to their ends.
                to = np.arange(len(v))
                np.minimum.at(to, hi, lo)
                while (nxt := to[to]).tolist() != to.tolist():
                    to = nxt
                label = to[label]
    moved = np.flatnonzero(label != np.arange(len(v)))
    return v[moved], v[label[moved]]


def compare(dealt: DataFrame, radius: int) -> DataFrame:
    """Links u, v from rows (g0, g1, tile, side, node) whose groups stand together, sorted."""

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []

        def close(rows: np.ndarray) -> Iterator[pa.RecordBatch]:
            key = rows[:, :3]
            edge = np.flatnonzero(np.r_[True, (key[1:] != key[:-1]).any(axis=1), True])
            us, vs = [], []
            for a, b in zip(edge[:-1][np.diff(edge) > 1].tolist(), edge[1:][np.diff(edge) > 1].tolist(), strict=True):
                u, v = _links(rows[a:b, 4].view(np.uint64), rows[a:b, 3], radius)
                us.append(u)
                vs.append(v)
            if us and sum(map(len, us)):
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x).view(np.int64)) for x in (us, vs)], names=["u", "v"])

        for b in batches:
            if not b.num_rows:
                continue
            rows = np.column_stack([c.to_numpy(zero_copy_only=False) for c in b.columns])
            # What belongs to the batch's last group may go on in the next batch.
            last = np.flatnonzero((rows[:, :3] != rows[-1, :3]).any(axis=1))
            start = int(last[-1]) + 1 if len(last) else 0
            if start:
                yield from close(np.concatenate([*held, rows[:start]]))
                held = []
            elif held and (held[0][0, :3] != rows[0, :3]).any():
                yield from close(np.concatenate(held))
                held = []
            held.append(rows[start:])
        if held:
            yield from close(np.concatenate(held))
        tidy()

    return dealt.mapInArrow(make, "u long, v long")


def near_links(nodes: DataFrame, radius: int = RADIUS, blocks: int | None = None, tile: int = TILE) -> DataFrame:
    """Links u, v among the distinct longs of column ``node``: their components are those of all pairs within the radius."""
    blocks = blocks or best_blocks(nodes.count(), radius)
    keys = F.array(*[F.struct(F.lit(i).cast("long").alias("g0"), F.col("node").bitwiseAND(F.lit(m).cast("long")).alias("g1")) for i, m in enumerate(masks(blocks, radius))])
    keyed = nodes.select("node", F.bit_count("node").alias("ones"), F.explode(keys).alias("k")).select("k.g0", "k.g1", "node", "ones")
    big = cut(keyed.groupBy("g0", "g1").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > tile).select("g0", "g1"), "big-groups")
    light = keyed.join(big, ["g0", "g1"], "left_anti").select("g0", "g1", F.lit(-1).cast("long").alias("tile"), F.lit(0).cast("long").alias("side"), "node")
    # Big groups: tiles by population count, each cut by hash into parts of about the tile's size.
    part = keyed.join(big, ["g0", "g1"])
    sized = part.groupBy("g0", "g1", "ones").agg(F.ceil(F.count(F.lit(1)) / tile).cast("int").alias("parts"))
    tiles = sized.groupBy("g0", "g1").agg(F.map_from_entries(F.collect_list(F.struct("ones", "parts"))).alias("tiles"))  # at most 65 entries
    placed = part.join(tiles, ["g0", "g1"]).withColumn("p", F.pmod(F.xxhash64("node"), F.element_at("tiles", F.col("ones"))).cast("int"))
    # All tiles within the radius, as (ones, part); the pair's id puts the lesser tile first.
    others = F.flatten(F.transform(F.sequence(F.col("ones") - radius, F.col("ones") + radius), lambda o: F.transform(F.when(F.element_at("tiles", o).isNotNull(), F.sequence(F.lit(0), F.element_at("tiles", o) - 1)).otherwise(F.expr("array()").cast("array<int>")), lambda q: F.struct(o.alias("o"), q.alias("q")))))
    spread = placed.select("g0", "g1", "node", (F.col("ones").cast("long") * (1 << 24) + F.col("p")).alias("own"), F.explode(others).alias("x"))
    spread = spread.withColumn("other", F.col("x.o").cast("long") * (1 << 24) + F.col("x.q"))
    tile_id = F.least("own", "other") * F.lit(1 << 32) + F.greatest("own", "other")
    side = F.when(F.col("own") == F.col("other"), 0).when(F.col("own") < F.col("other"), 1).otherwise(2)
    heavy = spread.select("g0", "g1", tile_id.alias("tile"), side.cast("long").alias("side"), "node")
    dealt = light.unionByName(heavy).repartition("g0", "g1", "tile").sortWithinPartitions("g0", "g1", "tile")
    return compare(dealt, radius)


def classes(prints: DataFrame, name: str, first: F.Column, radius: int = RADIUS) -> DataFrame:
    """node, head: for each distinct fingerprint the least ``first`` of its component.

    Most fingerprints are a component of their own and need no more; the others' heads are pre-aggregated minima, joined
    back over ``SALTS`` tasks a component.
    """
    nodes = cut(prints.groupBy(F.col(name).alias("node")).agg(F.min(first).alias("first")), "nodes")
    found = cut(components(near_links(nodes.select("node"), radius)).select(F.col("u").alias("node"), "root"), "roots")
    member = found.unionByName(found.select(F.col("root").alias("node"), "root").distinct())
    rooted = nodes.join(member, "node")
    heads = rooted.groupBy("root").agg(F.min("first").alias("head"))
    own = nodes.join(member.select("node"), "node", "left_anti").select("node", F.col("first").alias("head"))
    return own.unionByName(spread_join(rooted, heads, ["root"], SALTS, F.xxhash64("node")).select("node", "head"))


def near_duplicates(docs: DataFrame, *, id_col: str = "doc_id", text: str = "text", radius: int = RADIUS, k: int = WORDS) -> DataFrame:
    """doc_id, fingerprint (16 hex digits) and component_id (least doc_id of the component) of every document."""
    lean = docs.select(column(docs, id_col).alias("doc_id"), column(docs, text).alias("__text"))
    prints = cut(with_fingerprints(lean, text="__text", name="node", k=k), "fingerprints")
    found = classes(prints, "node", F.col("doc_id"), radius)
    return spread_join(prints, found, ["node"], COPIES, F.xxhash64("doc_id")).select("doc_id", F.lower(F.lpad(F.hex("node"), 16, "0")).alias("fingerprint"), F.col("head").alias("component_id"))


def one_of_each(docs: DataFrame, *, id_col: str = "doc_id", text: str = "text", radius: int = RADIUS, k: int = WORDS) -> DataFrame:
    """One document of each component (least id, null ids last, any of equal rows), with its own columns."""
    p = free_prefix(docs, "s")
    lean = docs.select(column(docs, id_col).alias(f"{p}id"), row_key(docs, text).alias(f"{p}key"), column(docs, text).alias("__text"))
    prints = cut(with_fingerprints(lean, text="__text", name="node", k=k), "fingerprints")
    heads = classes(prints, "node", F.struct(F.col(f"{p}id").isNull().alias("a"), F.col(f"{p}id").alias("b"), F.col(f"{p}key").alias("c")), radius)
    keep = heads.select(F.col("head.b").alias(f"{p}id"), F.col("head.c").alias(f"{p}key")).distinct()
    kept = only_keyed(docs, keep, id_col, (text,), p)
    if not prints.groupBy(f"{p}id", f"{p}key").agg(F.count(F.lit(1)).alias("n")).where("n > 1").isEmpty():
        kept = kept.withColumn(f"{p}own_id", column(kept, id_col)).dropDuplicates([f"{p}own_id", f"{p}own"])
    return kept.select(*[column(kept, c) for c in docs.columns])
