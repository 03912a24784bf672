"""The pipeline's stages against brute force, stage by stage, and the run as a whole."""

import zlib
from collections import Counter

import numpy as np

import corpus_pipeline
from derivatrace.llm import mixing, quality
from derivatrace.llm.common import cut
from tests.llm.conftest import DATA
from tests.llm.test_operators import classes_of, contaminated, prints_of, quality_counts, reference_ids


def rows_of(df):
    return [tuple(r) for r in df.select("doc_id", "text").collect()]


def test_stages_against_brute_force(spark):
    docs = spark.read.parquet(f"{DATA}/documents.parquet")
    columns, stages = docs.columns, [f for _, f in corpus_pipeline.STAGES]
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_rules", "simhash_near_dedup", "benchmark_decontamination", "source_mixing", "packed_token_ids"]

    kept = cut(stages[0](spark, docs, DATA), "t")
    verdict = {r["doc_id"]: r["kept"] for r in quality.quality_rules(docs, spark.read.parquet(f"{DATA}/labels.parquet")).collect()}
    assert kept.columns == columns
    assert Counter(r[0] for r in rows_of(kept)) == Counter(d for d, k in verdict.items() if k)
    assert not any((c := quality_counts(t))[0] < 50 or 2 * c[4] > c[0] for _, t in rows_of(kept))

    single = cut(stages[1](spark, kept, DATA), "t")
    assert single.columns == columns
    assert Counter(r[0] for r in rows_of(single)) == Counter({c for _, _, c in classes_of(prints_of(rows_of(kept)))})

    clean = cut(stages[2](spark, single, DATA), "t")
    items = [tuple(r) for r in spark.read.parquet(f"{DATA}/benchmark.parquet").select("item_id", "text").collect()]
    assert clean.columns == columns
    assert Counter(r[0] for r in rows_of(clean)) == Counter(r[0] for r in contaminated(rows_of(single), items) if not r[5])

    mix = cut(stages[3](spark, clean, DATA), "t")
    assert mix.columns == columns
    assert Counter(r[0] for r in rows_of(mix)) == Counter({r["doc_id"]: r["copies"] for r in mixing.mix_report(clean).collect() if r["copies"]})

    tokens = stages[4](spark, mix, DATA).collect()
    want = [(d, len(i), zlib.crc32(np.array(i, "<u4").tobytes())) for d, i in ((d, reference_ids(t)) for d, t in rows_of(mix))]
    assert Counter((r["doc_id"], r["n_tokens"], r["ids_crc32"]) for r in tokens) == Counter(want)

    whole = corpus_pipeline.run(spark, DATA).collect()
    assert Counter(map(tuple, whole)) == Counter(map(tuple, tokens))
