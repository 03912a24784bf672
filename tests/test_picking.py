"""Answers of the least md5 by lists of a join's keys: the same as from rows of all answers."""

import hashlib
import random

import numpy as np

from derivatrace.functions import digests
from derivatrace.operators import explain, picking
from derivatrace.operators.provenance import certain_answers
from derivatrace.plans.cq import parse_cq
from derivatrace.workloads import queries
from derivatrace.workloads.mixes import DEEP

DATA = "/root/testdata/sf0.001"


def _texts(texts):
    data = [t.encode() for t in texts]
    return np.frombuffer(b"".join(data), np.uint8), np.concatenate([[0], np.cumsum([len(x) for x in data])]).astype(np.int64)


def test_digests_of_pairs_whatever_their_length(monkeypatch):
    rng = random.Random(5)
    made = lambda: rng.choice(["", "é", "cust/", "supp/12"]) + "7" * rng.choice([0, 1, 4, 9, 22, 46, 47, 48, 55, 56, 70])
    groups = [([made() for _ in range(rng.randrange(9))], [made() for _ in range(rng.randrange(9))]) for _ in range(60)]
    left, right = [x for a, _ in groups for x in a], [y for _, b in groups for y in b]
    at = tuple(np.cumsum([0, *(len(g[k]) for g in groups)]) for k in range(2))
    bound = 1 << 30
    want = sorted((x, y) for a, b in groups for x in a for y in b if int(hashlib.md5(f"{x}|{y}".encode()).hexdigest()[:8], 16) <= bound)
    for tile in (1, 50, 1 << 15):
        monkeypatch.setattr(digests, "TILE", tile)
        found = digests.below(_texts(left), _texts(right), at, bound)
        assert sorted((left[i], right[j]) for some in found for i, j in zip(*some, strict=True)) == want and want


def test_pairs_are_picked_without_a_row_each(spark, monkeypatch):
    instance, cq = queries.survey(spark, DATA), DEEP["D06"].cq
    want = explain.sample_answers(certain_answers(instance, cq))
    monkeypatch.setattr(explain, "MANY_ROWS", 1)
    monkeypatch.setattr(picking, "PIECE", 7)
    monkeypatch.setattr(picking, "ROWS", 11)
    monkeypatch.setattr(explain, "sample_answers", lambda answers, *a, f=explain.sample_answers: plans.append(answers._jdf.queryExecution().optimizedPlan().toString()) or f(answers, *a))
    plans: list[str] = []
    assert explain.sampled(instance, cq) == want and len(want) == 5
    assert "MapInArrow" in plans[0] and len(plans) == 1


def test_a_share_with_too_few_pairs_is_not_enough(spark):
    instance, cq = queries.survey(spark, DATA), parse_cq("q(x, y) :- bought(x, p), offers(y, p)")
    rows = {tuple(r) for r in certain_answers(instance, cq).collect()}
    key = lambda r: hashlib.md5("|".join(r).encode()).hexdigest()
    for share in (0.3, 1.0):
        found = {tuple(r) for r in picking.pairs_below(instance, cq, share).collect()}
        assert found == {r for r in rows if int(key(r)[:8], 16) <= min(int(share * 2**32), 2**32 - 1)} and found
    assert picking.pairs_below(instance, parse_cq("q(x, y) :- offers(x, y)"), 0.3) is None
