"""Near pairs of vectors by tiles, against all pairs."""

import math
import random
from dataclasses import replace

from derivatrace.workloads import fixture

DATA = "/root/testdata/sf0.001"


def test_tiles_find_the_pairs_of_all_pairs(spark, monkeypatch):
    monkeypatch.setattr(fixture, "TILE", 7)
    rng = random.Random(3)
    vectors = [[rng.gauss(0, 1) for _ in range(4)] for _ in range(60)] + [[0.0] * 4, [float("nan"), 1.0, 0.0, 0.0], [0.4, math.sqrt(1 - 0.16), 0.0, 0.0], [1.0, 0.0, 0.0, 0.0], None, [1.0, 2.0]]
    rows = [(i * 7 % 101, v, 0) for i, v in enumerate(vectors)]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<float>, label int").repartition(3)
    instance = fixture.instance(spark, DATA, "flat")
    got = sorted(map(tuple, fixture._near(replace(instance, tables={"embeddings": df})).collect()))
    held = {r["vec_id"]: r["embedding"] for r in df.collect() if r["embedding"]}

    def dot(a, b):
        out = 0.0
        for x, y in zip(a, b):
            out += x * y
        return out

    nan = lambda x: math.inf if math.isnan(x) else x  # Spark's NaN equals itself and is above all numbers
    want = sorted((a, b, f"@vec/{a}", f"@vec/{b}") for a in held for b in held if a < b and len(held[a]) == len(held[b]) and nan(dot(held[a], held[b])) >= nan(fixture.NEAR * math.sqrt(dot(held[a], held[a])) * math.sqrt(dot(held[b], held[b]))))
    assert got == want and len(got) > 100


def test_no_plain_loop_over_all_pairs_of_vectors(spark):
    plan = fixture._near(fixture.instance(spark, DATA, "flat"))._jdf.queryExecution().optimizedPlan().toString()
    assert "MapInArrow" in plan
