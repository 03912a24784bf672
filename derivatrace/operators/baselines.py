"""What the methods are compared with: plain answers, plain relational provenance, minimal causes."""

from __future__ import annotations

from pyspark.sql import DataFrame

from derivatrace.operators.algebra import minimal_only
from derivatrace.operators.provenance import certain_answers, compute_provenance
from derivatrace.plans.cq import CQ
from derivatrace.plans.instance import Instance
from derivatrace.plans.ontology import Ontology

__all__ = ["certain_answers", "db_provenance", "minimal_causes"]


def db_provenance(instance: Instance, cq: CQ) -> DataFrame:
    """The relational semiring over the derived facts alone: no inclusion takes part."""
    return compute_provenance(instance.with_ontology(Ontology()), cq)


def minimal_causes(instance: Instance, cq: CQ) -> DataFrame:
    """Only derivations that contain no other one of the answer."""
    return minimal_only(compute_provenance(instance, cq))
