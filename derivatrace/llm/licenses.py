"""License scan: fuzzy search for short notices.

A text is brought to lower-case words with single spaces, so that line breaks and punctuation don't matter. A phrase
that may differ by e edits is split into e + 1 pieces: one of them must stand unchanged (pigeonhole), so exact searches
for the pieces locate all candidates. In the neighbourhood of each the regex library's bounded-error matching verifies the
edits and gives the span, so that a better match nearby hides none. Exact places on word boundaries are the base ones.
An edit is allowed for every 8 letters or so (``notices``): 2 in ``under the mit license``, 3 in ``apache license version
2``, none in ``cc by nc``, where one would meet other licenses.

Nulls and edges: a null, empty or wordless text has no place, no label (empty string) and score 0; repeated rows are
judged each, alike; texts are searched whole, in memory of a few times the text.
"""

from __future__ import annotations

from bisect import bisect_left, insort
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from derivatrace.llm.common import WORD_TABLE, as_bytes, column

#: Phrases and their labels.
PHRASES = {"under the mit license": "mit", "apache license version 2": "apache-2", "cc by nc": "cc-by-nc"}


@dataclass
class Notice:
    phrase: bytes
    label: str
    edits: int

    def __post_init__(self):
        n, e = len(self.phrase), self.edits
        at = [n * i // (e + 1) for i in range(e + 2)]
        self.seeds = [(a, self.phrase[a:b]) for a, b in zip(at, at[1:], strict=False)]
        self.exact = b" " + self.phrase + b" "
        self.fuzzy = regex.compile(b"(?b)(?<= )(?:" + regex.escape(self.phrase, literal_spaces=True) + b"){e<=%d}(?= )" % e)

    def base(self, body: bytes) -> Iterator[int]:
        """Where the phrase's words stand consecutively in a body of words between single spaces."""
        at = body.find(self.exact)
        while at >= 0:
            yield at + 1
            at = body.find(self.exact, at + 1)

    def candidates(self, body: bytes) -> Iterator[tuple[int, int]]:
        """The neighbourhood of each place of a seed: as long as a phrase around it can be."""
        n, e = len(self.phrase), self.edits
        seen = set()
        for a, seed in self.seeds:
            at = body.find(seed)
            while at >= 0:
                if at - a not in seen:
                    seen.add(at - a)
                    yield max(0, at - a - e - 1), min(len(body), at - a + n + e + 1)
                at = body.find(seed, at + 1)

    def matches(self, body: bytes) -> list[tuple[int, int, int]]:
        """(start, end, edits) of the phrase with at most so many edits, on word boundaries: the best of each
        neighbourhood, then of those that overlap the ones of fewest edits, earlier ones first."""
        found = {(sum(m.fuzzy_counts), m.start(), m.end()) for lo, hi in self.candidates(body) if (m := self.fuzzy.search(body, lo, hi))}
        # A gap in reach for each start: kept spans are looked up in order.
        starts: list[int] = []
        kept: dict[int, tuple[int, int, int]] = {}
        for edits, lo, hi in sorted(found):
            i = bisect_left(starts, hi)
            if i == 0 or kept[starts[i - 1]][1] <= lo:
                insort(starts, lo)
                kept[lo] = (lo, hi, edits)
        return [kept[s] for s in starts]


def notices(phrases: dict[str, str] = PHRASES, letters_an_edit: int = 8) -> list[Notice]:
    """An edit for every so many letters of the phrase; the shortest phrases must stand as they are."""
    return [Notice(p.encode(), label, max(0, len(p) // letters_an_edit - 1 + (len(p) >= 16))) for p, label in phrases.items()]


def search(found: list[Notice], text: bytes) -> tuple:
    """n_words, n_base, first_word, last_word, base_labels, labels, score and spans (label, first word, words, edits)."""
    words = text.translate(WORD_TABLE).split()
    body = b" " + b" ".join(words) + b" "
    starts, base_labels, labels, score, spans = [], set(), set(), 0.0, []
    for notice in found:
        exact = [body.count(b" ", 0, at) - 1 for at in notice.base(body)]
        if exact:
            starts += exact
            base_labels.add(notice.label)
            score = 1.0
        spans += [(notice.label, w, notice.phrase.count(b" ") + 1, 0) for w in exact]
        if notice.edits:
            for lo, hi, edits in notice.matches(body):
                if edits:
                    spans.append((notice.label, body.count(b" ", 0, lo) - 1, body.count(b" ", lo, hi) + 1, edits))
                labels.add(notice.label)
                score = max(score, 1.0 - edits / len(notice.phrase))
    labels |= base_labels
    return len(words), len(starts), min(starts, default=None), max(starts, default=None), ",".join(sorted(base_labels)), ",".join(sorted(labels)), score, sorted(spans, key=lambda s: (s[1], s[0], s[3]))


_FIELDS = (("n_words", T.LongType(), pa.int64()), ("n_base", T.LongType(), pa.int64()), ("first_word", T.LongType(), pa.int64()), ("last_word", T.LongType(), pa.int64()), ("base_labels", T.StringType(), pa.string()), ("labels", T.StringType(), pa.string()), ("score", T.DoubleType(), pa.float64()))
_SPANS = pa.list_(pa.struct([("label", pa.string()), ("word", pa.int64()), ("words", pa.int64()), ("edits", pa.int64())]))


def license_scan(docs: DataFrame, *, phrases: dict[str, str] = PHRASES, id_col: str = "doc_id", text: str = "text", letters_an_edit: int = 8) -> DataFrame:
    """doc_id, the counts, labels and score of every text, and the spans found."""
    lean = docs.select(column(docs, id_col).alias("doc_id"), column(docs, text).alias("text"))

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = notices(phrases, letters_an_edit)
        for b in batches:
            for i in range(0, b.num_rows, 256):
                s = b.slice(i, 256)
                rows = [search(found, t) for t in as_bytes(s, "text")]
                cols = [pa.array([r[k] for r in rows], kind) for k, (_, _, kind) in enumerate(_FIELDS)]
                spans = pa.array([[dict(zip(("label", "word", "words", "edits"), x, strict=True)) for x in r[7]] for r in rows], _SPANS)
                yield pa.RecordBatch.from_arrays([s.column(0), *cols, spans], names=["doc_id", *[f[0] for f in _FIELDS], "spans"])

    span = T.ArrayType(T.StructType([T.StructField("label", T.StringType()), T.StructField("word", T.LongType()), T.StructField("words", T.LongType()), T.StructField("edits", T.LongType())]))
    return lean.mapInArrow(make, T.StructType([lean.schema["doc_id"], *[T.StructField(n, t) for n, t, _ in _FIELDS], T.StructField("spans", span)]))
