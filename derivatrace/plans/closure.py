"""Classification of an ontology: which atoms yield which, by which label sets; and enumeration by walks."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession

from derivatrace.plans.cq import BLANK
from derivatrace.plans.instance import Instance
from derivatrace.plans.ontology import Concept, Ontology, Some
from derivatrace.plans.rewrite import atom_closure, back

_X, _Y = ("h", "x"), ("h", "y")


def vocabulary(ontology: Ontology) -> tuple[set[str], set[str]]:
    """Concept names, role names."""
    concepts, roles = set(), set()
    for a in ontology.axioms:
        for t in (a.lhs, a.rhs):
            (concepts if isinstance(t, Concept) else roles).add(t.name if not isinstance(t, Some) else t.role.name)
    return concepts, roles


def spelled(pred: str, args: tuple) -> str:
    """A concept, role, inverse role or "has a successor" as text."""
    if len(args) == 1:
        return pred
    if BLANK in args:
        return f"exists {pred}" + "-" * (args[0] == BLANK)
    return pred + "-" * (args == (_Y, _X))


def classify(ontology: Ontology, with_labels: bool = True, most: int = 100_000) -> list[tuple[str, str, tuple[str, ...]]]:
    """(sub, super, labels of a way) for every pair, every label set once; without labels every pair once."""
    concepts, roles = vocabulary(ontology)
    goals = [(c, (_X,)) for c in sorted(concepts)] + [(r, q) for r in sorted(roles) for q in ((_X, _Y), (_X, BLANK), (BLANK, _X))]
    out = []
    for pred, args in goals:
        for (p, q), ways in sorted(atom_closure(pred, args, list(ontology.positive), most).items()):
            for w in sorted(ways) if with_labels else [()]:
                out.append((spelled(p, q), spelled(pred, args), w))
            if len(out) > most:
                raise ValueError(f"over {most} closure rows: enumerate walks instead")
    return out


def closure_table(spark: SparkSession, ontology: Ontology, with_labels: bool = True) -> DataFrame:
    return spark.createDataFrame([(a, b, list(w)) for a, b, w in classify(ontology, with_labels)], "sub string, super string, labels array<string>")


def enumerate_monomials(instance: Instance, pred: str, args: tuple[str, ...]) -> Iterator[tuple[str, ...]]:
    """Monomials of a ground atom one after the other, by depth-first search over walks of inclusions back to facts.

    Each walk is a set of labels not used before on it; facts of an atom are fetched by one filtered read when a walk
    first reaches it. With labels of their own for all inclusions the delay between two results is polynomial.
    """
    seen: set[tuple[str, ...]] = set()
    facts: dict[tuple, list[tuple[str, ...]]] = {}

    def base(atom) -> list[tuple[str, ...]]:
        if atom not in facts:
            frames = instance.branches(*atom)
            facts[atom] = [tuple(r["mono"]) for df in frames for r in df.select("mono").distinct().toLocalIterator()]
        return facts[atom]

    visited: set[tuple] = set()
    stack = [((pred, tuple(("c", a) for a in args)), ())]
    while stack:
        atom, labels = stack.pop()
        if (atom, labels) in visited:
            continue
        visited.add((atom, labels))
        for m in base(atom):
            mono = tuple(sorted({*m, *labels}))
            if mono not in seen:
                seen.add(mono)
                yield mono
        for a in instance.ontology.positive:
            if (to := back(a, *atom)) is not None:
                stack.append((to, tuple(sorted({*labels, *a.label}))))


def label_graph(ontology: Ontology) -> dict[str, set[str]]:
    """Edges sub -> super between the ends of inclusions, with what an inclusion of roles implies for their ends."""
    out: dict[str, set[str]] = {}
    for a in ontology.positive:
        pairs = [(str(a.lhs), str(a.rhs))]
        if not isinstance(a.lhs, Concept | Some):
            left, right = a.lhs, a.rhs
            pairs += [(f"exists {left.name}" + "-" * (left.inv != s), f"exists {right.name}" + "-" * (right.inv != s)) for s in (False, True)]
        for s, t in pairs:
            out.setdefault(s, set()).add(t)
    return out
