"""Quality rules with risk-controlled thresholds, in DataFrame functions only.

Each text gets five measures (higher is worse). For each stratum a short list of nested rules is laid out from the
labelled-bad and the unlabelled texts alone: measures in order of how well a cutoff parts the two, each with at most
two cutoffs of a fixed grid, the higher first; a rule holds all cutoffs listed so far. The labelled-good texts, which
had no say in the list, then test the rules in that order, until one fails: a rule is certified when the exact binomial
tail shows that at most the share ``alpha`` of good texts is rejected by it as a whole. As the order is fixed before the test, the
error level is shared among strata only. A text is rejected by a base rule or when a measure reaches its stratum's cutoff.

Nulls and edges: a null text has no words (and so fails the base rule), a null stratum is one of its own, labels that
are null or of unknown documents are ignored, several labels of one document count as good only if all say so, and a
stratum without enough labels gets no cutoff. Rows with the same id are judged each by its own text.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from derivatrace.llm.common import column, cut, free_prefix, only_keyed, row_key

SPACES = r"[\x20\x09-\x0D]+"
SYMBOLS = r"[^#*$%&|<>]+"
MEASURES = ("symbols", "dup_lines", "repeats", "shouting", "short_lines")
#: Cutoffs that a list may hold, as shares.
GRID = tuple(i / 50 for i in range(1, 51))
#: A measure is listed only if a cutoff reaches so many more of the bad than of the unlabelled texts.
LEAST_GAIN = 0.1


def count_columns(df: DataFrame, text: str, prefix: str) -> DataFrame:
    """Add n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_upper and n_lines under the prefix.

    Every array that a lambda looks into is a column of an earlier projection, used more than once, so Catalyst
    keeps it there and computes it once a row.
    """
    p = prefix
    body = F.coalesce(column(df, text), F.lit(""))
    keep = [column(df, c) for c in df.columns]
    lines = F.filter(F.split(body, "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    out = df.select(
        *keep,
        F.array_remove(F.split(body, SPACES), "").alias(f"{p}w"),
        lines.alias(f"{p}l"),
        F.length(F.regexp_replace(body, SYMBOLS, "")).cast("long").alias(f"{p}n_symbols"),
        F.length(F.regexp_replace(body, "[^A-Z]+", "")).cast("long").alias(f"{p}n_upper"),
    )
    names = [F.col(f"`{c}`") for c in df.columns]
    w, some = F.col(f"{p}w"), [f"{p}n_symbols", f"{p}n_upper"]
    grams = F.when(
        F.size(w) >= 3,
        F.transform(F.sequence(F.lit(0), F.size(w) - 3), lambda i: F.struct(F.xxhash64(F.get(w, i), F.get(w, i + 1), F.get(w, i + 2)).alias("h"), i.alias("i"))),
    ).otherwise(F.expr("array()").cast("array<struct<h:bigint,i:int>>"))
    out = out.select(
        *names,
        *some,
        F.size(w).cast("long").alias(f"{p}n_words"),
        F.length(F.array_join(w, "")).cast("long").alias(f"{p}word_chars"),
        F.size(f"{p}l").cast("long").alias(f"{p}n_lines"),
        (F.size(f"{p}l") - F.size(F.array_distinct(f"{p}l"))).cast("long").alias(f"{p}n_dup_lines"),
        F.sort_array(grams).alias(f"{p}g"),
    )
    g, some = F.col(f"{p}g"), [*some, f"{p}n_words", f"{p}word_chars", f"{p}n_lines", f"{p}n_dup_lines"]
    # A window that occurs again stands beside its equal in the sorted array.
    again = F.filter(g, lambda x, i: (F.get(g, i + 1)["h"] == x["h"]) | ((i > 0) & (F.get(g, i - 1)["h"] == x["h"])))
    out = out.select(*names, *some, F.sort_array(F.transform(again, lambda x: x["i"])).alias(f"{p}p"))
    at = F.col(f"{p}p")
    # Each window covers three words, but only up to the next one's start.
    fresh_words = F.zip_with(at, F.slice(at, 2, F.greatest(F.size(at), F.lit(1))), lambda a, b: F.least(F.lit(3), F.coalesce(b - a, F.lit(3))))
    return out.select(*names, *some, F.aggregate(fresh_words, F.lit(0).cast("long"), lambda s, x: s + x).alias(f"{p}n_repeat_words"))


def share(top: Column, bottom: Column) -> Column:
    return F.when(bottom > 0, F.least(F.lit(1.0), top / bottom)).otherwise(F.lit(0.0))


def measure_columns(p: str) -> dict[str, Column]:
    c = lambda n: F.col(f"{p}{n}")
    return {
        "symbols": share(c("n_symbols"), c("word_chars")),
        "dup_lines": share(c("n_dup_lines"), c("n_lines")),
        "repeats": share(c("n_repeat_words"), c("n_words")),
        "shouting": share(c("n_upper"), c("word_chars")),
        "short_lines": F.when(c("n_lines") > 3, F.greatest(F.lit(0.0), F.lit(1.0) - c("n_words") / (c("n_lines") * 8))).otherwise(F.lit(0.0)),
    }


def base_failed(p: str) -> Column:
    """Fixed base rules: fewer than 50 words, or over half of them in repeated three-word windows."""
    return (F.col(f"{p}n_words") < 50) | (100 * F.col(f"{p}n_repeat_words") > 50 * F.col(f"{p}n_words"))


def binomial_tail(k: Column, n: Column, share_: float) -> Column:
    """P(X <= k) for X binomial over n at the share, summed term by term in logarithms."""
    odds = math.log(share_) - math.log1p(-share_)
    start = F.struct((n * F.lit(math.log1p(-share_))).alias("t"), F.exp(n * F.lit(math.log1p(-share_))).alias("s"))

    def step(acc, i):
        term = acc["t"] + F.log((n - i + 1) / i) + F.lit(odds)
        return F.struct(term.alias("t"), (acc["s"] + F.exp(term)).alias("s"))

    steps = F.when(k >= 1, F.sequence(F.lit(1).cast("long"), k)).otherwise(F.expr("array()").cast("array<bigint>"))
    return F.when(k >= n, F.lit(1.0)).otherwise(F.aggregate(steps, start, step, lambda acc: acc["s"]))


def rule_lists(held: DataFrame, p: str) -> DataFrame:
    """<p>s and seq, the (measure's place, grid step) to test in order; good texts aren't looked at."""
    rest = held.where(F.col("good").isNull() | (F.col("good") != 1))
    by_step = rest.select(f"{p}s", F.col("good").isNotNull().alias("bad"), F.posexplode("b").alias("m", "v")).groupBy(f"{p}s", "m", "v").agg(F.count_if("bad").alias("d"), F.count_if(~F.col("bad")).alias("u"))
    packed = by_step.groupBy(f"{p}s", "m").agg(F.sum("d").alias("nd"), F.sum("u").alias("nu"), F.collect_list(F.struct("v", "d", "u")).alias("vs")).where("nd > 0")
    tried = packed.select("*", F.explode(F.sequence(F.lit(1), F.lit(len(GRID)))).alias("b"))
    above = lambda c: F.aggregate(F.filter("vs", lambda x: x["v"] >= F.col("b")), F.lit(0).cast("long"), lambda s, x: s + x[c])
    tried = tried.select(f"{p}s", "m", "b", (above("d") / F.col("nd") - F.when(F.col("nu") > 0, above("u") / F.col("nu")).otherwise(0.0)).alias("gain"))
    best = tried.groupBy(f"{p}s", "m").agg(F.max("gain").alias("g"), F.collect_list(F.struct("b", "gain")).alias("bs")).where(F.col("g") >= LEAST_GAIN)
    highest = lambda share_: F.array_max(F.transform(F.filter("bs", lambda x: x["gain"] >= F.col("g") * share_), lambda x: x["b"]))
    listed = best.select(f"{p}s", F.struct((-F.col("g")).alias("g"), "m", F.array_distinct(F.array(highest(0.5), highest(1.0))).alias("bs")).alias("x"))
    seq = F.flatten(F.transform(F.sort_array(F.collect_list("x")), lambda x: F.transform(x["bs"], lambda b: F.struct(x["m"].alias("m"), b.alias("b")))))
    return listed.groupBy(f"{p}s").agg(seq.alias("seq"))


def certified_cutoffs(measured: DataFrame, labels: DataFrame, *, id_col: str, stratum: str, p: str, alpha: float, delta: float) -> DataFrame:
    """One row for each stratum with a list: its key and, for each measure, the certified cutoff (null: none).

    measured has one row a document with its id, stratum and the counts under the prefix p. The error level delta is
    shared evenly among the strata that have good labels (Bonferroni); within one, rules are tested in a fixed sequence.
    """
    marked = labels.where(column(labels, "quality").isNotNull() & column(labels, "doc_id").isNotNull()).groupBy(column(labels, "doc_id").alias(f"{p}id")).agg(F.min("quality").alias("good"))
    steps = F.array(*[F.floor(c * len(GRID) + F.lit(1e-9)).cast("int") for c in measure_columns(p).values()])
    held = measured.where(~base_failed(p)).select(column(measured, id_col).alias(f"{p}id"), column(measured, stratum).alias(f"{p}s"), steps.alias("b"))
    held = cut(held.join(marked, f"{p}id", "left").select(f"{p}s", "good", "b"), "quality-held")
    lists = cut(rule_lists(held, p), "quality-lists")
    right = held.where("good = 1")
    level = delta / max(1, right.select(f"{p}s").distinct().count())
    same = lambda a, b: a[f"{p}s"].eqNullSafe(b[f"{p}s"])
    # A good text counts where it is first rejected; the rules are nested, so a rule's count is the sum up to it.
    met = right.join(lists, same(right, lists)).select(right[f"{p}s"], "seq", F.array_position(F.transform("seq", lambda x: F.get("b", x["m"]) >= x["b"]), True).alias("at"))
    counts = met.groupBy(f"{p}s", "seq", "at").agg(F.count(F.lit(1)).alias("c"))
    counts = counts.groupBy(f"{p}s", "seq").agg(F.sum("c").alias("n"), F.collect_list(F.struct("at", "c")).alias("cs"))
    tests = counts.select(f"{p}s", "n", "cs", F.posexplode("seq").alias("i", "x"))
    tests = tests.select(f"{p}s", "n", "i", "x", F.aggregate(F.filter("cs", lambda y: y["at"].between(1, F.col("i") + 1)), F.lit(0).cast("long"), lambda s, y: s + y["c"]).alias("k"))
    # The tail is worth summing only up to the mean.
    passed = F.when(F.col("k") <= F.col("n") * alpha, binomial_tail(F.col("k"), F.col("n"), alpha) <= level).otherwise(False)
    done = tests.groupBy(f"{p}s").agg(F.min(F.when(~passed, F.col("i"))).alias("stop"), F.collect_list(F.struct("i", "x")).alias("xs"))
    sure = lambda j: F.filter("xs", lambda y: (y["x"]["m"] == j) & (F.col("stop").isNull() | (y["i"] < F.col("stop"))))
    return done.select(f"{p}s", *[(F.array_min(F.transform(sure(j), lambda y: y["x"]["b"])) / len(GRID)).alias(f"{p}cut_{m}") for j, m in enumerate(MEASURES)])


def judge(docs: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", text: str = "text", stratum: str = "lang", alpha: float = 0.02, delta: float = 0.05) -> tuple[DataFrame, str]:
    """<p>id, <p>key and, for every row, its counts, base_failed, kept and reasons, all under the prefix p; the frame and p.

    alpha bounds the share of good texts that the certified cutoffs of a stratum reject, at confidence 1 - delta.
    """
    p = free_prefix(docs, "q")
    lean = docs.select(column(docs, id_col).alias(f"{p}id"), row_key(docs, text, stratum).alias(f"{p}key"), column(docs, stratum).cast("string").alias(f"{p}stratum"), column(docs, text).alias("text"))
    measured = count_columns(lean, "text", p)
    measured = cut(measured.select(*[c for c in measured.columns if c != "text"]), "quality")
    cutoffs = certified_cutoffs(measured, labels, id_col=f"{p}id", stratum=f"{p}stratum", p=p, alpha=alpha, delta=delta)
    joined = measured.join(cutoffs, measured[f"{p}stratum"].eqNullSafe(cutoffs[f"{p}s"]), "left")
    reasons = F.filter(F.array(*[F.when(c >= F.col(f"{p}cut_{m}"), F.lit(m)) for m, c in measure_columns(p).items()]), lambda x: x.isNotNull())
    joined = joined.withColumn(f"{p}base_failed", base_failed(p)).withColumn(f"{p}reasons", reasons)
    return joined.withColumn(f"{p}kept", ~F.col(f"{p}base_failed") & (F.size(f"{p}reasons") == 0)), p


def quality_rules(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """doc_id, the five base counts, base_failed, kept and the measures that rejected the text."""
    out, p = judge(docs, labels, **options)
    names = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "reasons")
    return out.select(F.col(f"{p}id").alias("doc_id"), *[F.col(f"{p}{n}").alias(n) for n in names])


def keep_good(docs: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", text: str = "text", stratum: str = "lang", **options) -> DataFrame:
    """The documents that pass, with their own columns: a semi-join with the verdicts, which hold for equal rows alike."""
    out, p = judge(docs, labels, id_col=id_col, text=text, stratum=stratum, **options)
    good = out.where(F.col(f"{p}kept")).select(f"{p}id", f"{p}key")
    kept = only_keyed(docs, good, id_col, (text, stratum), p)
    return kept.select(*[column(kept, c) for c in docs.columns])
