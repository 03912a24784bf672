"""Token ids in a packed file format: every id in the fewest bits its vocabulary needs, in blocks with offsets.

A segment is a byte string: a header, the byte offset of each block, then the blocks. A block holds ``BLOCK`` ids of
fixed width, so any id's place is known without reading what comes before, and numpy unpacks whole blocks at once. The
files are Parquet tables of segments (any store that Spark writes to, with its commit protocol): each row has the
segment, the ids that its part holds before it, its documents' ids and lengths, and the least and greatest of these ids,
so that a reader in search of one document skips row groups by their statistics. Rows come in ascending order of
document id over the parts.

Nulls and edges: a null or empty text is only the end id; a null document id comes first; rows of equal ids stand side
by side, ordered by a hash of their text; an empty table gives no segment. One document stays in one segment, however
long; it is tokenised in pieces, cut where the pre-tokeniser cuts anyway.
"""

from __future__ import annotations

import itertools
import json
import re
import struct
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from derivatrace.llm.common import column, fresh_path, tidy

MAGIC, BLOCK, SEGMENT_IDS = b"PKID", 4096, 1 << 18
HEADER = struct.Struct("<4sBxxxQII")


def width(vocabulary: int) -> int:
    """Bits that hold any id below the vocabulary's size."""
    return max(1, (vocabulary - 1).bit_length())


def pack(ids: np.ndarray, bits: int) -> bytes:
    """A segment of these ids."""
    ids, n = np.asarray(ids), len(ids)
    blocks = -(-n // BLOCK)
    if bits in (8, 16, 32):
        body = ids.astype(f"<u{bits // 8}").tobytes()
    else:
        rows = ((ids.astype(np.uint64)[:, None] >> np.arange(bits, dtype=np.uint64)) & np.uint64(1)).astype(np.uint8)
        body = np.packbits(rows.reshape(-1), bitorder="little").tobytes()
    offsets = np.minimum(np.arange(blocks + 1, dtype="<u8") * (BLOCK * bits // 8), len(body)).astype("<u8")
    return HEADER.pack(MAGIC, bits, n, BLOCK, blocks) + offsets.tobytes() + body


def unpack(segment: bytes, start: int = 0, stop: int | None = None) -> np.ndarray:
    """The ids from start to stop, from the blocks that hold them alone."""
    magic, bits, n, block, blocks = HEADER.unpack_from(segment)
    if magic != MAGIC:
        raise ValueError("not a segment of packed ids")
    stop = n if stop is None else min(stop, n)
    if start >= stop:
        return np.empty(0, np.uint32)
    offsets = np.frombuffer(segment, "<u8", blocks + 1, HEADER.size)
    first, last = start // block, (stop - 1) // block
    at = HEADER.size + 8 * (blocks + 1)
    body = np.frombuffer(segment, np.uint8, int(offsets[last + 1] - offsets[first]), at + int(offsets[first]))
    lo, hi = start - first * block, stop - first * block
    if bits in (8, 16, 32):
        return body.view(f"<u{bits // 8}")[lo:hi].astype(np.uint32)
    bit = np.arange(lo, hi, dtype=np.int64) * bits
    body = np.concatenate([body, np.zeros(8, np.uint8)])
    out = np.zeros(hi - lo, np.uint64)
    for k in range((bits + 14) // 8):  # bytes that an id can touch
        out |= body[(bit >> 3) + k].astype(np.uint64) << np.uint64(8 * k)
    return ((out >> (bit & 7).astype(np.uint64)) & np.uint64((1 << bits) - 1)).astype(np.uint32)


#: Characters of which the regex library and the tokeniser are known to agree on letters, digits and spaces.
_UNSURE = re.compile("[^\t\n\r\x20-\x7e\xa1-ɏΑ-ΡΣ-ώЀ-ҁҊ-ԯぁ-ゖァ-ヺ一-龥가-힣]")
def even(text: str) -> bool:
    """Whether words stand between single spaces or line ends: there the pre-tokeniser cuts before each of these."""
    return bool(text) and text[0] not in " \n" and text[-1] not in " \n" and not ("  " in text or "\n\n" in text or " \n" in text or "\n " in text or "\t" in text or "\r" in text or unsure(text))


def unsure(text: str) -> bool:
    """Whether it has a character beyond those; printable Latin-1 is told quickly."""
    try:
        text.encode("latin-1")
        if text.replace("\n", "").isprintable():
            return False
    except UnicodeEncodeError:
        pass
    return bool(_UNSURE.search(text))


#: Between a letter or digit and a space before another one, the byte-level pre-tokeniser always cuts.
_CUT = re.compile("(?<=[A-Za-z0-9])(?= [A-Za-z0-9])")
_PIECE = 1 << 19


def cuts(text: str) -> Iterator[str]:
    """The text in pieces of about half a million characters, if it is longer, that tokenise as the whole does."""
    at = 0
    while len(text) - at > _PIECE and (m := _CUT.search(text, at + _PIECE)):
        yield text[at : m.start()]
        at = m.start()
    yield text[at:] if at else text


class Numbers(dict):
    """Pieces by number: one that is met for the first time gets the next number at once, and waits among the new ones."""

    def __init__(self, *args):
        super().__init__(*args)
        self.new: dict[str, int] = {}

    def __missing__(self, piece: str) -> int:
        self[piece] = self.new[piece] = n = next(self.count)
        return n


class Encoder:
    """Encodes texts with a file of the tokenizers library.

    Where the file is plain byte-level BPE, texts are split where its pre-tokeniser splits, and each distinct piece is
    encoded once and kept under a number: up to twice ``most``, of which then the most frequent ones stay.
    """

    def __init__(self, path: str, most: int = 250_000):
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # a task has one core
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        spec = json.loads(self.tokenizer.to_str())
        before = spec.get("pre_tokenizer") or {}
        plain = before.get("type") == "ByteLevel" and not before.get("add_prefix_space") and before.get("use_regex", True) and not spec.get("normalizer") and spec["model"]["type"] == "BPE"
        self.pattern = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+") if plain else None  # fixed value
        # Texts that hold one of the file's added tokens go through the library whole, as it takes these out first.
        added = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.added = re.compile("|".join(map(re.escape, added))) if added else None
        self.bits = width(self.tokenizer.get_vocab_size())
        self.kind = "<u2" if self.bits <= 16 else "<u4"
        # Byte-level files write a space as this letter.
        vocabulary = self.tokenizer.get_vocab()
        self.after_space = np.zeros(max(vocabulary.values(), default=0) + 1, bool)
        self.after_space[[i for t, i in vocabulary.items() if t.startswith("\u0120")]] = True
        self.most = most
        self.known, self.spaced = Numbers(), Numbers()
        self._keep([], [])

    def _keep(self, known: list[str], spaced: list[str]) -> None:
        """Forget all pieces but these, and number them anew."""
        old = np.array([self.known[w] for w in known] + [self.spaced[w] for w in spaced], np.int64)
        if len(old):
            self.flat, self.lengths = self._flat(old), self.lengths[old]
        else:
            self.flat, self.lengths = np.empty(0, self.kind), np.empty(0, np.int64)
        self.starts, self.met = np.cumsum(self.lengths) - self.lengths, np.zeros(len(old), np.int64)
        # Both number their pieces in one row.
        count = itertools.count(len(old))
        self.known, self.spaced = Numbers(zip(known, range(len(known)), strict=True)), Numbers(zip(spaced, range(len(known), len(old)), strict=True))
        self.known.count = self.spaced.count = count

    def _age(self) -> None:
        """Once there are twice ``most``, forget the pieces met only once since the last time; of more than ``most`` others, the rarest too."""
        if len(self.lengths) > 2 * self.most:
            least = max(2, int(np.partition(self.met, -self.most)[-self.most]) + 1)
            stay = (self.met >= least).tolist()
            self._keep([w for w, i in self.known.items() if stay[i]], [w for w, i in self.spaced.items() if stay[i]])

    def _flat(self, pieces: np.ndarray) -> np.ndarray:
        """The ids of these pieces, one after the other."""
        lengths = self.lengths[pieces]
        return self.flat[np.repeat(self.starts[pieces] - (np.cumsum(lengths) - lengths), lengths) + np.arange(lengths.sum())]

    def _learn(self, words: list[str], before: str = "") -> tuple[list[np.ndarray], list[np.ndarray]]:
        """The ids of the words, as each stands after ``before``, and their numbers of ids."""
        ids, lengths = [], []
        for i in range(0, len(words), 50_000):
            part = words[i : i + 50_000]
            # A list of words is encoded word by word, in one call.
            made = self.tokenizer.encode([before + w for w in part], is_pretokenized=True, add_special_tokens=False)
            ids.append(np.array(made.ids, self.kind))
            lengths.append(np.bincount(np.array(made.word_ids, np.int64), minlength=len(part)))
        return ids, lengths

    def _learn_spaced(self, words: list[str]) -> tuple[list[np.ndarray], list[np.ndarray]]:
        """The same for words after a space: encoded in runs, and told apart as only their first ids hold a space."""
        ids, lengths = [], []
        for i in range(0, len(words), 50_000):
            part = words[i : i + 50_000]
            made = self.tokenizer.encode_batch_fast([" " + " ".join(part[k : k + 500]) for k in range(0, len(part), 500)], add_special_tokens=False)
            got = np.concatenate([np.array(m.ids, self.kind) for m in made])
            ends = np.append(np.flatnonzero(self.after_space[got]), len(got))
            if len(ends) != len(part) + 1:
                more = self._learn(part, " ")
                ids, lengths = ids + more[0], lengths + more[1]
                continue
            ids.append(got)
            lengths.append(np.diff(ends))
        return ids, lengths

    def _learn_new(self) -> None:
        """Learn the pieces that were met for the first time, each under the number that it got then."""
        found = [(self.known.new, self._learn(list(self.known.new))), (self.spaced.new, self._learn_spaced(list(self.spaced.new)))]
        numbers = np.array([n for new, _ in found for n in new.values()], np.int64)
        if not len(numbers):
            return
        flat = np.concatenate([x for _, (ids, _) in found for x in ids])
        lengths = np.concatenate([x for _, (_, each) in found for x in each])
        starts, n = len(self.flat) + np.cumsum(lengths) - lengths, len(self.lengths)
        self.flat = np.concatenate([self.flat, flat])
        self.lengths, self.starts, self.met = (np.concatenate([x, np.zeros(len(numbers), np.int64)]) for x in (self.lengths, self.starts, self.met))
        self.lengths[numbers], self.starts[numbers] = lengths, starts
        assert len(self.lengths) == n + len(numbers) == numbers.max() + 1
        self.known.new, self.spaced.new = {}, {}

    def whole(self, text: str) -> bytes:
        return np.array(self.tokenizer.encode_batch_fast([text], add_special_tokens=False)[0].ids, self.kind).tobytes()

    def pieces(self, text: str) -> bytes:
        return b"".join([b"".join(self.encode([x])) for x in cuts(text)])

    def encode(self, texts: list[str]) -> list[bytes]:
        """Each text's ids, little-endian.

        Even texts are cut into words after a space and words that start a line; others into the pre-tokeniser's own
        pieces; those with unusual characters, or of files that aren't plain byte-level BPE, go through the library whole.
        """
        if self.pattern is None:
            return [self.whole(t) for t in texts]
        self._age()
        out: list[Callable[[str], bytes] | None] = []
        row: list[int] = []
        ends: list[int] = []
        one, get = self.known.__getitem__, self.spaced.__getitem__
        line_end = one("\n")
        for text in texts:
            whole = None
            if len(text) > _PIECE and _CUT.search(text, _PIECE):
                whole = self.pieces
            elif self.added and self.added.search(text):
                whole = self.whole
            elif even(text):
                for k, line in enumerate(text.split("\n")):
                    words = iter(line.split(" "))
                    if k:
                        row.append(line_end)
                    row.append(one(next(words)))
                    row.extend(map(get, words))
            elif unsure(text):
                whole = self.whole
            else:
                row.extend(map(one, self.pattern.findall(text)))
            out.append(whole)
            ends.append(len(row))
        self._learn_new()
        pieces = np.fromiter(row, np.int64, len(row))
        del row
        self.met += np.bincount(pieces, minlength=len(self.met))
        step, at = np.dtype(self.kind).itemsize, np.concatenate([[0], np.cumsum(self.lengths[pieces])])[[0, *ends]].tolist()
        flat = memoryview(self._flat(pieces).tobytes())
        return [bytes(flat[a * step : b * step]) if whole is None else whole(text) for text, whole, a, b in zip(texts, out, at, at[1:], strict=False)]


_ENCODERS: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    """One a worker process: the tokeniser and the pieces it knows outlive a task."""
    if path not in _ENCODERS:
        _ENCODERS[path] = Encoder(path)
    return _ENCODERS[path]


SEGMENTS = T.StructType(
    [
        T.StructField("part", T.IntegerType()),
        T.StructField("seq", T.IntegerType()),
        T.StructField("part_start", T.LongType()),
        T.StructField("n_ids", T.LongType()),
        T.StructField("least_id", T.LongType()),
        T.StructField("greatest_id", T.LongType()),
        T.StructField("doc_ids", T.ArrayType(T.LongType())),
        T.StructField("lengths", T.ArrayType(T.LongType())),
        T.StructField("packed", T.BinaryType()),
    ]
)
_ARROW = pa.schema([("part", pa.int32()), ("seq", pa.int32()), ("part_start", pa.int64()), ("n_ids", pa.int64()), ("least_id", pa.int64()), ("greatest_id", pa.int64()), ("doc_ids", pa.list_(pa.int64())), ("lengths", pa.list_(pa.int64())), ("packed", pa.binary())])


PART_BYTES = 256 << 20


def plan_bytes(df: DataFrame) -> int:
    """The planner's estimate of a frame's bytes; 0 where it has none."""
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return size if size < 1 << 60 else 0


def write_ids(docs: DataFrame, path: str, *, tokenizer: str, id_col: str = "doc_id", text: str = "text", end_id: int = 0) -> None:
    """Write the packed ids of every text, each with the end id, under the path in ascending order of document id.

    The range partitioning deals texts by (id, hash of the text) into at least the session's shuffle partitions, and more
    where these would hold over ``PART_BYTES`` of the planner's estimate; a task holds one run of 4 MB of text at a time.
    """
    lean = docs.select(column(docs, id_col).cast("long").alias("doc_id"), F.coalesce(column(docs, text), F.lit("")).alias("text"))
    key = F.xxhash64("text")
    parts = max(int(lean.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-plan_bytes(lean) // PART_BYTES))
    ordered = lean.repartitionByRange(parts, "doc_id", key).sortWithinPartitions("doc_id", key)

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(tokenizer)
        step = np.dtype(enc.kind).itemsize
        end = np.array([end_id], enc.kind).tobytes()
        part, seq, before = TaskContext.get().partitionId(), 0, 0
        ids, docs_, lengths, held = [], [], [], 0

        def segment() -> pa.RecordBatch:
            packed = pack(np.frombuffer(b"".join(ids), enc.kind), enc.bits)
            named = [d for d in docs_ if d is not None]
            return pa.RecordBatch.from_pydict({"part": [part], "seq": [seq], "part_start": [before], "n_ids": [held], "least_id": [min(named, default=None)], "greatest_id": [max(named, default=None)], "doc_ids": [list(docs_)], "lengths": [list(lengths)], "packed": [packed]}, schema=_ARROW)

        for doc_ids, texts in runs(batches):
            for d, got in zip(doc_ids, enc.encode(texts), strict=True):
                ids += (got, end)
                docs_.append(d)
                lengths.append(len(got) // step + 1)
                held += lengths[-1]
                if held >= SEGMENT_IDS:
                    yield segment()
                    seq, before = seq + 1, before + held
                    ids, docs_, lengths, held = [], [], [], 0
        if docs_:
            yield segment()
        tidy()

    ordered.mapInArrow(make, SEGMENTS).write.parquet(path)


def runs(batches: Iterator[pa.RecordBatch], most: int = 4 << 20) -> Iterator[tuple[list, list[str]]]:
    """(ids, texts) of about so many characters."""
    ids, texts, held = [], [], 0
    for b in batches:
        for i in range(0, b.num_rows, 64):
            s = b.slice(i, 64)
            for d, t in zip(s.column(0).to_pylist(), s.column(1).to_pylist(), strict=True):
                ids.append(d)
                texts.append(t)
                held += len(t)
                if held >= most:
                    yield ids, texts
                    ids, texts, held = [], [], 0
    if ids:
        yield ids, texts


def part_starts(spark: SparkSession, path: str) -> dict[int, int]:
    """Ids before each part: one number for each written part."""
    rows = spark.read.schema(SEGMENTS).parquet(path).groupBy("part").agg(F.sum("n_ids").alias("n")).collect()
    starts, at = {}, 0
    for r in sorted(rows):
        starts[r["part"]], at = at, at + r["n"]
    return starts


def read_ids(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start, n_tokens and ids (int array) of every document, from the files."""
    return _read(spark, path, [T.StructField("ids", T.ArrayType(T.IntegerType()))], pa.list_(pa.int32()), lambda ids: ids.tolist())


def read_digests(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start, n_tokens and ids_crc32 (of the ids as little-endian unsigned 32-bit integers), from the files."""
    return _read(spark, path, [T.StructField("ids_crc32", T.LongType())], pa.int64(), lambda ids: zlib.crc32(np.ascontiguousarray(ids, "<u4")))


def _read(spark: SparkSession, path: str, last: list[T.StructField], kind: pa.DataType, value) -> DataFrame:
    starts = spark.sparkContext.broadcast(part_starts(spark, path))

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for part, before, ids_, lengths, packed in zip(*(b.column(c).to_pylist() for c in ("part", "part_start", "doc_ids", "lengths", "packed")), strict=True):
                ids, at, first = unpack(packed), 0, starts.value[part] + before
                begins, values = [], []
                for n in lengths:
                    begins.append(first + at)
                    values.append(value(ids[at : at + n]))
                    at += n
                yield pa.RecordBatch.from_arrays([pa.array(ids_, pa.int64()), pa.array(begins, pa.int64()), pa.array(lengths, pa.int64()), pa.array(values, kind)], names=["doc_id", "start", "n_tokens", last[0].name])
        tidy()

    out = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("start", T.LongType()), T.StructField("n_tokens", T.LongType()), *last])
    return spark.read.schema(SEGMENTS).parquet(path).select("part", "part_start", "doc_ids", "lengths", "packed").mapInArrow(make, out)


def document_ids(spark: SparkSession, path: str, doc_id: int) -> list[np.ndarray]:
    """Random access: the ids of one document (of each row with the id), unpacked by the tasks that hold its segments, from its blocks alone."""
    wanted = F.lit(doc_id).cast("long")

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for docs_, lengths, packed in zip(*(b.column(c).to_pylist() for c in ("doc_ids", "lengths", "packed")), strict=True):
                ends = np.cumsum(lengths)
                found = [unpack(packed, int(e - n), int(e)) for d, e, n in zip(docs_, ends, lengths, strict=True) if d == doc_id]
                yield pa.RecordBatch.from_arrays([pa.array([f.tobytes() for f in found], pa.binary())], names=["ids"])

    near = spark.read.schema(SEGMENTS).parquet(path).where((F.col("least_id") <= wanted) & (F.col("greatest_id") >= wanted) & F.array_contains("doc_ids", wanted))
    return [np.frombuffer(bytes(r["ids"]), np.uint32) for r in near.select("doc_ids", "lengths", "packed").mapInArrow(make, "ids binary").toLocalIterator()]


def token_digests(docs: DataFrame, *, tokenizer: str, **options) -> DataFrame:
    """Write the packed ids into the shared folder and read the documents' digests back from the files."""
    path = fresh_path(docs.sparkSession, "ids")
    write_ids(docs, path, tokenizer=tokenizer, **options)
    return read_digests(docs.sparkSession, path)
