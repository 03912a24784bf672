"""The bounded universal model as a table: facts closed under the inclusions, round by round, with witness terms.

For comparison and tests: (pred, a0, a1, mono), all predicates in one frame; witnesses start with ``~`` and are made
from the fact and the inclusion that ask for them, depth levels deep. Each round is cut by a checkpoint.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from derivatrace.functions.monomials import mul_idem
from derivatrace.operators.provenance import provenance_on
from derivatrace.plans.cq import CQ
from derivatrace.plans.instance import Instance, union
from derivatrace.plans.ontology import Axiom, Concept, Role
from derivatrace.sources.tables import shared_folder


def _checkpointed(df: DataFrame) -> DataFrame:
    sc = df.sparkSession.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        sc.setCheckpointDir(shared_folder(df.sparkSession))
    return df.checkpoint()


def _apply(facts: DataFrame, a: Axiom, instance: Instance, depth: int) -> DataFrame:
    mono = mul_idem(F.col("mono"), instance.constant(a.label)).alias("mono")
    if isinstance(a.lhs, Role):
        pair = ("a1", "a0") if a.lhs.inv != a.rhs.inv else ("a0", "a1")
        return facts.where(F.col("pred") == a.lhs.name).select(F.lit(a.rhs.name).alias("pred"), F.col(pair[0]).alias("a0"), F.col(pair[1]).alias("a1"), mono)
    name, x = (a.lhs.name, "a0") if isinstance(a.lhs, Concept) else (a.lhs.role.name, "a1" if a.lhs.role.inv else "a0")
    base = facts.where(F.col("pred") == name)
    if isinstance(a.rhs, Concept):
        return base.select(F.lit(a.rhs.name).alias("pred"), F.col(x).alias("a0"), F.lit(None).cast("string").alias("a1"), mono)
    level = F.length(F.regexp_extract(F.col(x), "^~*", 0))
    witness = F.concat(F.repeat(F.lit("~"), level.cast("int") + 1), F.md5(F.concat_ws("|", x, F.lit(str(a)), F.col("pred"), "a0", F.coalesce("a1", F.lit("")), F.array_join(F.col("mono").cast("array<string>"), "*"))))
    base = base.where(level < depth)
    pair = (witness, F.col(x)) if a.rhs.role.inv else (F.col(x), witness)
    return base.select(F.lit(a.rhs.role.name).alias("pred"), pair[0].alias("a0"), pair[1].alias("a1"), mono)


def chase(instance: Instance, depth: int = 3, rounds: int = 40) -> DataFrame:
    """pred, a0, a1, mono. Witnesses carry one ``~`` for each level."""
    known = instance.predicates()
    frames = [instance.facts(p, n).select(F.lit(p).alias("pred"), "a0", (F.col("a1") if n == 2 else F.lit(None).cast("string")).alias("a1"), "mono") for p, n in sorted(known.items())]
    everything = _checkpointed(union(frames))
    new = everything
    for _ in range(rounds):
        made = [_apply(new, a, instance, depth) for a in instance.ontology.positive]
        if not made:
            return everything
        new = _checkpointed(_novel(union(made), everything))
        if new.isEmpty():
            return everything
        everything = _checkpointed(everything.unionByName(new))
    raise RuntimeError(f"no fixpoint in {rounds} rounds")


def _novel(made: DataFrame, known: DataFrame) -> DataFrame:
    key = lambda d: d.withColumn("_k", F.coalesce("a1", F.lit("")))
    return key(made.dropDuplicates()).join(key(known).select("pred", "a0", "_k", "mono"), ["pred", "a0", "_k", "mono"], "left_anti").select("pred", "a0", "a1", "mono")


def facts_of(closed: DataFrame, cq: CQ) -> dict[str, DataFrame]:
    """The model's facts of the query's predicates."""
    return {a.pred: closed.where(F.col("pred") == a.pred).select(*["a0", "a1"][: len(a.args)], "mono") for a in cq.atoms}


def answers_over(closed: DataFrame, cq: CQ) -> DataFrame:
    """The query's provenance over the model; answers are known individuals."""
    out = provenance_on(cq, facts_of(closed, cq))
    for h in cq.head:
        out = out.where(~F.col(h).startswith("~"))
    return out


def answers_by_chase(instance: Instance, cq: CQ, depth: int | None = None) -> DataFrame:
    """The query's provenance over the bounded universal model; answers are known individuals."""
    return answers_over(chase(instance, len({t for a in cq.atoms for t in a.args if t[0] in "hv"}) + 2 if depth is None else depth), cq)
