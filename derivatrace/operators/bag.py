"""Idempotent product with counted sums: each answer's monomials with the number of matches that give them.

Counts belong to matches over all facts that the ontology entails, so the facts are closed under the inclusions first;
this is defined here for ontologies without existential heads, where closing needs no witnesses.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from derivatrace.operators.provenance import atom_facts, join_atoms
from derivatrace.functions.monomials import mul_idem
from derivatrace.plans.cq import CQ
from derivatrace.plans.instance import Instance


class MultiplicityUndecidedHere(ValueError):
    pass


def entailed_facts(instance: Instance, pred: str, n: int) -> DataFrame:
    """All facts of a predicate that the inclusions entail over known individuals, each (arguments, monomial) once."""
    return atom_facts(instance, pred, (("h", "x"), ("h", "y"))[:n]).dropDuplicates()


def bag_provenance(instance: Instance, cq: CQ) -> DataFrame:
    """Answer columns, mono and coeff."""
    if any(a.existential for a in instance.ontology.positive):
        raise MultiplicityUndecidedHere("counts of matches need an ontology without existential heads")
    out = join_atoms([(a.pred, a.args) for a in cq.atoms], lambda i, p, q: entailed_facts(instance, p, len(q)), cq.head)
    out = out.select(*cq.head, mul_idem(*[F.col(f"_m{i}") for i in range(len(cq.atoms))]).alias("mono"))
    return out.groupBy(*cq.head, "mono").agg(F.count(F.lit(1)).alias("coeff"))
