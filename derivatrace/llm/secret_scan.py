"""Secret scan: fixed patterns, and character Markov models for what they miss.

Two models of character pairs are trained on labelled samples, one on random strings and one on ordinary identifiers.
A candidate (a run of 16 key characters or more, of whatever classes) is reported as ``random`` when the log-likelihood
ratio of the two models, for each character, exceeds a threshold, unless a span of the fixed patterns holds it already.
Spans of the fixed patterns always stay.

Nulls and edges: a null or empty text has no span and the digest of the empty string; places are code points with
exclusive ends; repeated rows are judged each, alike. Texts are scanned whole.
"""

from __future__ import annotations

import hashlib
import random
import re
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from derivatrace.llm.common import column

#: The base patterns, in order, each with the group and the least length that must hold.
PATTERNS = (
    ("assign", re.compile(r"""(?:[pP][aA][sS][sS][wW][oO][rR][dD]|[pP][aA][sS][sS][wW][dD]|[sS][eE][cC][rR][eE][tT]|[tT][oO][kK][eE][nN]|[aA][pP][iI]_?[kK][eE][yY])["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""), 1, 6),
    ("access", re.compile(r"AKIA[A-Z0-9]+"), 0, 20),
    ("hex", re.compile(r"[0-9a-f]+"), 0, 24),
)
#: What every assign match holds: a text without one needs no slow search.
_ASSIGN_HINT = re.compile(r"[:=]")
_HEX = re.compile(r"[0-9a-f]{24,}")
_CANDIDATE = re.compile(r"[A-Za-z0-9+/_=-]{16,}")
KINDS = ("assign", "access", "hex", "random")
_ALPHABET = 128
#: Log-likelihood ratio a character above which a run is reported; README has recall and false finds by threshold.
THRESHOLD = 0.7


class Markov:
    """Log probabilities of character pairs, with add-one smoothing; 0 stands before the first character."""

    def __init__(self, samples: Iterable[str]):
        counts = np.ones((_ALPHABET, _ALPHABET))
        for s in samples:
            codes = np.frombuffer(b"\0" + s.encode("ascii", "ignore"), np.uint8)
            np.add.at(counts, (codes[:-1], codes[1:]), 1)
        self.log = np.log(counts / counts.sum(axis=1, keepdims=True))


class RandomOrName:
    """The ratio of the two models; trained from labelled samples (text, is_random)."""

    def __init__(self, samples: Iterable[tuple[str, bool]]):
        samples = list(samples)
        self.ratio = Markov(s for s, r in samples if r).log - Markov(s for s, r in samples if not r).log

    def score(self, text: str) -> float:
        """Log-likelihood ratio for each character: above zero, random is likelier."""
        codes = np.frombuffer(b"\0" + text.encode("ascii"), np.uint8)
        return float(self.ratio[codes[:-1], codes[1:]].sum()) / max(1, len(text))


_SYLLABLES = "get set add put map list file name user data item node tree path line text word page time date key value index count size type state event order price total part load save read write open close send make find sort merge split parse build start stop next last first left right upper lower min max sum mean test case main base core view model table row col cell block chunk batch cache queue stack graph edge label score rank query token field schema config option flag mode level depth width height color image frame audio video sound input output source target local remote server client host port url link group role owner admin guest error warn info debug trace log".split()


def labelled_samples(n: int = 4000, seed: int = 11) -> list[tuple[str, bool]]:
    """n random strings over usual key alphabets and n ordinary identifiers, made by rule; n bounds the fit's sample."""
    rng = random.Random(seed)
    upper, lower, digits = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz", "0123456789"
    alphabets = (upper + lower + digits, upper + lower + digits + "+/", upper + lower + digits + "_-", digits + "abcdef", upper + digits)
    keys = [("".join(rng.choices(rng.choice(alphabets), k=rng.randint(16, 48))), True) for _ in range(n)]

    def name() -> str:
        parts = rng.choices(_SYLLABLES, k=rng.randint(2, 6))
        style = rng.randrange(6)
        tail = rng.choice(("", "", "", str(rng.randint(0, 99)), str(rng.randint(2000, 2030))))
        if style == 0:
            return parts[0] + "".join(p.title() for p in parts[1:]) + tail
        if style == 1:
            return "".join(p.title() for p in parts) + tail
        return ("_", "-", "_", "/")[style - 2].join(p.upper() if style == 4 else p for p in parts) + tail

    return keys + [(name(), False) for _ in range(n)]


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, end, kind) of the fixed patterns: leftmost and not overlapping for each kind, failing matches dropped."""
    out = []
    if _ASSIGN_HINT.search(text):
        out += [(m.start(), m.end(), 0) for m in PATTERNS[0][1].finditer(text) if len(m[1]) >= PATTERNS[0][3]]
    if "AKIA" in text:
        out += [(m.start(), m.end(), 1) for m in PATTERNS[1][1].finditer(text) if len(m[0]) >= PATTERNS[1][3]]
    # A greedy run of hex characters is one match, so the runs of 24 or more are the matches that hold.
    out += [(m.start(), m.end(), 2) for m in _HEX.finditer(text)]
    return sorted(out, key=lambda s: (s[0], s[2]))


def model_spans(text: str, model: RandomOrName, threshold: float, base: list[tuple[int, int, int]] = ()) -> Iterator[tuple[int, int, int]]:
    """Runs that the models find random, whatever characters they have; those within a base span say nothing new."""
    for m in _CANDIDATE.finditer(text):
        if model.score(m[0]) > threshold and not any(a <= m.start() and m.end() <= b for a, b, _ in base):
            yield m.start(), m.end(), 3


def render(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, b, k in spans)


def scan_text(text: str, model: RandomOrName, threshold: float) -> tuple[int, int, int, str, str]:
    base = base_spans(text)
    spans = sorted([*base, *model_spans(text, model, threshold, base)], key=lambda s: (s[0], s[2]))
    n = [sum(k == kind for _, _, k in base) for kind in range(3)]
    return *n, hashlib.sha256(render(base).encode()).hexdigest(), render(spans)


_FIELDS = (("n_assign", T.LongType(), pa.int64()), ("n_access", T.LongType(), pa.int64()), ("n_hex", T.LongType(), pa.int64()), ("base_sha256", T.StringType(), pa.string()), ("spans", T.StringType(), pa.string()))


def secret_scan(docs: DataFrame, *, id_col: str = "doc_id", text: str = "text", samples: list[tuple[str, bool]] | None = None, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256 and spans (kind:start:end, the models' ``random`` ones too)."""
    lean = docs.select(column(docs, id_col).alias("doc_id"), F.coalesce(column(docs, text), F.lit("")).alias("text"))
    model = docs.sparkSession.sparkContext.broadcast(RandomOrName(samples if samples is not None else labelled_samples()))  # 128 x 128 numbers

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(0, b.num_rows, 256):
                s = b.slice(i, 256)
                rows = [scan_text(t, model.value, threshold) for t in s.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([s.column(0), *[pa.array([r[k] for r in rows], f[2]) for k, f in enumerate(_FIELDS)]], names=["doc_id", *[f[0] for f in _FIELDS]])

    return lean.mapInArrow(make, T.StructType([lean.schema["doc_id"], *[T.StructField(n, t) for n, t, _ in _FIELDS]]))
