"""Cost and accuracy measures."""

from __future__ import annotations

import gc
import time
from collections.abc import Callable
from statistics import mean

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from derivatrace.operators.algebra import answer_columns
from derivatrace.operators.keyed import Apart, same
from derivatrace.operators.provenance import unfold
from derivatrace.plans.cq import CQ
from derivatrace.plans.instance import Instance
from derivatrace.plans.rewrite import by_shape, foldings, rewrite_compute

TIMEOUT_S = 40 * 60
#: Bytes of the largest table whose rows are compared at a time.
ROUND_INPUT = 16 << 20


def run(df: DataFrame) -> None:
    """Execute without keeping the result."""
    df.write.format("noop").mode("overwrite").save()


def timed(make: Callable[[], DataFrame], runs: int = 5, timeout_s: float = TIMEOUT_S) -> float | None:
    """Mean seconds over the runs; None where a run takes longer than the timeout (its jobs are then cancelled)."""
    import threading
    import uuid

    took = []
    for _ in range(runs):
        began, df = time.perf_counter(), make()
        sc, tag = df.sparkSession.sparkContext, f"timed-{uuid.uuid4().hex}"
        sc.addJobTag(tag)
        timer = threading.Timer(timeout_s, sc.cancelJobsWithTag, [tag])
        timer.start()
        try:
            run(df)
        except Exception:
            if time.perf_counter() - began >= timeout_s:
                return None
            raise
        finally:
            timer.cancel()
            sc.removeJobTag(tag)
        took.append(time.perf_counter() - began)
    return mean(took)


def mix_time(queries: list[Callable[[], DataFrame]], runs: int = 3) -> float:
    """Mean total time of the query mix."""
    totals = []
    for _ in range(runs):
        began = time.perf_counter()
        for q in queries:
            run(q())
        totals.append(time.perf_counter() - began)
    return mean(totals)


def overhead(provenance_s: float, baseline_s: float) -> float:
    return provenance_s / baseline_s


def union_count(instance: Instance, cq: CQ, *, certain: bool = False, prune_templates: bool = True) -> int:
    """UNION operators of the unfolding; certain: of the stock engine, which drops contained branches."""
    return unfold(instance, cq, optimise="certain" if certain else "none", prune_templates=prune_templates).unions


def plan_unions(df: DataFrame) -> int:
    """Unions of the analysed plan, counted by their inputs less one."""
    plan = df._jdf.queryExecution().analyzed()
    total, work = 0, [plan]
    while work:
        node = work.pop()
        kids = node.children()
        n = kids.size()
        if node.nodeName() == "Union":
            total += n - 1
        work += [kids.apply(i) for i in range(n)]
    return total


def derivations(poly: DataFrame) -> DataFrame:
    """n_answers, mean and greatest number of derivations of an answer."""
    each = poly.groupBy(*answer_columns(poly)).agg(F.count_distinct("mono").alias("n"))
    return each.agg(F.count(F.lit(1)).alias("n_answers"), F.avg("n").alias("mean_derivations"), F.max("n").alias("max_derivations"))


def encoded_size(poly: DataFrame) -> DataFrame:
    """n_monomials, n_literals, and n_chars of the expanded polynomial's text, signs included."""
    chars = F.length(F.array_join(F.col("mono").cast("array<string>"), "*"))
    return poly.agg(F.count(F.lit(1)).alias("n_monomials"), F.sum(F.size("mono")).alias("n_literals"), (F.sum(chars) + F.greatest(F.count(F.lit(1)) - 1, F.lit(0))).alias("n_chars"))


def factorised_size(factorised: DataFrame) -> DataFrame:
    """Literals of the factorised polynomial: static labels once, then those of the parts."""
    return factorised.agg(F.sum(F.size("static") + F.aggregate("parts", F.lit(0), lambda s, x: s + F.size(x))).alias("n_literals"))


def instance_size(instance: Instance) -> int:
    """Characters of the ontology and the rules' heads as text."""
    return sum(len(str(a)) for a in instance.ontology.axioms) + sum(len(r.pred) + len(r.name) + sum(len(t.prefix) + len("-".join(t.columns)) + 1 for t in r.head) for r in instance.rules)


def rewriting_stats(instance: Instance, cq: CQ) -> dict[str, int]:
    """Rewritings, distinct bodies, and bodies of the closure form."""
    found = rewrite_compute(cq, instance.ontology.positive)
    return {"rewritings": len(found), "bodies": len(by_shape(found)), "foldings": len(foldings(cq, instance.ontology.positive))}


def agree(left: DataFrame | Apart, right: DataFrame | Apart, by: tuple[str, ...] = ()) -> bool:
    """Equal as bags, nulls alike: exactness is the accuracy measure. Two polynomials kept apart are compared by keys, where that tells.

    Either side is made once: rows count up on the left and down on the right, and sums tell what differs. by: columns
    that deal the rows over rounds where the tables read are large, so that a round's rows alone are on disk at a time.
    """
    if isinstance(left, Apart) and isinstance(right, Apart) and (told := same(left, right)) is not None:
        return told
    left, right = (p.frame() if isinstance(p, Apart) else p for p in (left, right))
    both = left.withColumn("_n", F.lit(1)).union(right.withColumn("_n", F.lit(-1)))
    rounds = _rounds(both) if by else 1
    for k in range(rounds):
        some = both if rounds == 1 else both.where(F.pmod(F.xxhash64(*by), F.lit(rounds)) == k)
        if not some.groupBy(*left.columns).agg(F.sum("_n").alias("_n")).where("_n <> 0").isEmpty():
            return False
        if rounds > 1:
            del some
            gc.collect()
            left.sparkSession.sparkContext._jvm.System.gc()  # else shuffle files stay until the driver happens to collect its garbage
    return True


def _rounds(df: DataFrame) -> int:
    """So many rounds that each has ROUND_INPUT bytes of the largest table read from files; other leaves don't know their size."""
    leaves = df._jdf.queryExecution().optimizedPlan().collectLeaves()
    tables = [leaf for i in range(leaves.size()) if (leaf := leaves.apply(i)).nodeName() == "LogicalRelation"]
    most = max((int(str(leaf.stats().sizeInBytes())) for leaf in tables), default=0)
    return -(-most // ROUND_INPUT) or 1
