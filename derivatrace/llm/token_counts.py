"""Token counts under a unigram model, by dynamic programming over a trie.

Distinct pre-tokens go into a trie of characters. When a node is first made, the forward score of its prefix is
worked out once from its ancestors' scores (best segmentation into pieces, ties to fewer tokens), so every pre-token
that shares the prefix shares the work; the terminal node's token count is stored with the pre-token. Tries live in the
worker and are dropped when they exceed a fixed number of nodes, so no shuffle is needed and memory is bounded.

Nulls and edges: a null, empty or blank text has no words and no tokens; characters that no piece covers count as one
token for each UTF-8 byte; a pre-token of over ``LONG`` characters is scored alone, outside the trie. Equal rows count
alike, each for itself.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from derivatrace.llm.common import column

MARK, LONG = "▁", 256
_WORD = re.compile(r"[^\x20\x09-\x0D]+")


def piece_scores(path: str) -> dict[str, float]:
    """Log probability of each ordinary piece of a sentencepiece file: by rank, as a Zipf law has it."""
    from sentencepiece import SentencePieceProcessor

    model = SentencePieceProcessor(model_file=path)
    found = [model.id_to_piece(i) for i in range(model.get_piece_size()) if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i))]
    norm = math.log(sum(1 / (r + 1) for r in range(len(found))))
    return {x: -math.log(r + 1) - norm for r, x in enumerate(found)}


class UnigramTrie:
    """best[node], count[node]: score and number of tokens of the best segmentation of the node's prefix."""

    def __init__(self, scores: dict[str, float], most: int = 600_000):
        self.scores, self.most = scores, most
        self.byte = min(scores.values(), default=0.0) - 10
        # Ends of pieces: where a run of characters is none, no longer piece ends here either.
        self.ends = {x[i:] for x in scores for i in range(len(x))}
        self.reset()

    def reset(self) -> None:
        self.child: dict[tuple[int, str], int] = {}
        self.best, self.count = [0.0], [0]
        self.terminal: dict[str, tuple[int, float]] = {}

    def _forward(self, word: str, d: int, best: list[float], count: list[int], path: list[int]) -> tuple[float, int]:
        """Score and count of word[:d], from those of its prefixes."""
        n = len(word[d - 1].encode())
        top, tokens = best[path[d - 1]] + n * self.byte, count[path[d - 1]] + n
        for k in range(d - 1, -1, -1):
            piece = word[k:d]
            if piece not in self.ends:
                break
            if (s := self.scores.get(piece)) is not None:
                a = path[k]
                if (x := best[a] + s) > top or x == top and count[a] + 1 < tokens:
                    top, tokens = x, count[a] + 1
        return top, tokens

    def insert(self, word: str) -> tuple[int, float]:
        """Token count and score of a pre-token."""
        marked = MARK + word
        if len(word) > LONG:
            best, count, path = [0.0], [0], list(range(len(marked) + 1))
            for d in range(1, len(marked) + 1):
                b, c = self._forward(marked, d, best, count, path)
                best.append(b)
                count.append(c)
            return count[-1], best[-1]
        if len(self.best) > self.most:
            self.reset()
        node, path = 0, [0]
        for d, ch in enumerate(marked, 1):
            if (to := self.child.get((node, ch))) is None:
                b, c = self._forward(marked, d, self.best, self.count, path)
                to = self.child[node, ch] = len(self.best)
                self.best.append(b)
                self.count.append(c)
            path.append(to)
            node = to
        self.terminal[word] = self.count[node], self.best[node]
        return self.terminal[word]

    def text(self, body: str) -> tuple[int, int, float]:
        """Words, tokens and log probability of a text; a long one is read word by word."""
        words, tokens, scores = 0, 0, 0.0
        for m in _WORD.finditer(body):
            w = m[0]
            words += 1
            c, s = self.terminal.get(w) or self.insert(w)
            tokens += c
            scores += s
        return words, tokens, scores


_TRIES: dict[str, UnigramTrie] = {}


def trie(path: str) -> UnigramTrie:
    if path not in _TRIES:
        _TRIES[path] = UnigramTrie(piece_scores(path))
    return _TRIES[path]


def token_counts(docs: DataFrame, *, vocabulary: str, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_words, n_tokens and log_score (the sum of the words' best log probabilities) of every text."""
    lean = docs.select(column(docs, id_col).alias("doc_id"), F.coalesce(column(docs, text), F.lit("")).alias("text"))

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unigram = trie(vocabulary)
        for b in batches:
            for i in range(0, b.num_rows, 256):
                s = b.slice(i, 256)
                words, tokens, scores = zip(*map(unigram.text, s.column(1).to_pylist()), strict=True)
                yield pa.RecordBatch.from_arrays([s.column(0), pa.array(words, pa.int64()), pa.array(tokens, pa.int64()), pa.array(scores, pa.float64())], names=["doc_id", "n_words", "n_tokens", "log_score"])

    return lean.mapInArrow(make, T.StructType([lean.schema["doc_id"], T.StructField("n_words", T.LongType()), T.StructField("n_tokens", T.LongType()), T.StructField("log_score", T.DoubleType())]))
