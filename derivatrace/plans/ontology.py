"""Inclusions between basic concepts and roles, each with its label."""

from __future__ import annotations

import json
import re
from collections.abc import Iterable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession


@dataclass(frozen=True, order=True)
class Role:
    name: str
    inv: bool = False

    def __str__(self) -> str:
        return self.name + "-" * self.inv


@dataclass(frozen=True, order=True)
class Concept:
    name: str

    def __str__(self) -> str:
        return self.name


@dataclass(frozen=True, order=True)
class Some:
    """Everything that has a successor by the role."""

    role: Role

    def __str__(self) -> str:
        return f"exists {self.role}"


@dataclass(frozen=True)
class Axiom:
    """lhs is included in rhs (or, negative, in its complement). The label is a monomial, mostly of one label."""

    lhs: Role | Concept | Some
    rhs: Role | Concept | Some
    label: tuple[str, ...] = ()
    neg: bool = False

    def __str__(self) -> str:
        return f"{self.lhs} <= {'not ' * self.neg}{self.rhs}" + (f" @{'*'.join(self.label)}" if self.label else "")

    @property
    def existential(self) -> bool:
        return isinstance(self.rhs, Some) and not self.neg


def _term(text: str) -> Role | Concept | Some:
    text = text.strip()
    if m := re.fullmatch(r"exists\s+(\w+)(-?)", text):
        return Some(Role(m[1], bool(m[2])))
    if not (m := re.fullmatch(r"(\w+)(-?)", text)):
        raise ValueError(f"not a concept or role: {text!r}")
    if m[2] or m[1][0].islower():
        return Role(m[1], bool(m[2]))
    return Concept(m[1])


def parse_axiom(text: str) -> Axiom:
    """``exists placedBy- <= Customer @a15``, ``A <= not B``; names of roles start with a small letter."""
    body, _, label = text.partition("@")
    lhs, found, rhs = body.partition("<=")
    if not found:
        raise ValueError(f"no inclusion: {text!r}")
    neg = bool(re.match(r"\s*not\b", rhs))
    axiom = Axiom(_term(lhs), _term(re.sub(r"^\s*not\b", "", rhs)), tuple(sorted(x for x in label.strip().split("*") if x)), neg)
    if isinstance(axiom.lhs, Role) != isinstance(axiom.rhs, Role):
        raise ValueError(f"a role and a concept can't include each other: {text!r}")
    return axiom


@dataclass(frozen=True)
class Ontology:
    axioms: tuple[Axiom, ...] = ()

    @classmethod
    def parse(cls, lines: Iterable[str]) -> Ontology:
        return cls(tuple(parse_axiom(x) for x in lines if x.strip()))

    @classmethod
    def from_df(cls, df: DataFrame) -> Ontology:
        """From a table (lhs, rhs, neg, label); an ontology is a small driver-side object."""
        return cls.parse(f"{r['lhs']} <= {'not ' * bool(r['neg'])}{r['rhs']}" + (f" @{r['label']}" if r["label"] else "") for r in df.select("lhs", "rhs", "neg", "label").collect())

    @classmethod
    def load(cls, spark: SparkSession, path: str, fmt: str = "json") -> Ontology:
        return cls.from_df(spark.read.format(fmt).load(path))

    def to_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(str(a.lhs), str(a.rhs), a.neg, "*".join(a.label)) for a in self.axioms], "lhs string, rhs string, neg boolean, label string")

    @property
    def positive(self) -> tuple[Axiom, ...]:
        return tuple(a for a in self.axioms if not a.neg)

    @property
    def negative(self) -> tuple[Axiom, ...]:
        return tuple(a for a in self.axioms if a.neg)

    def without(self, *labels: str) -> Ontology:
        return Ontology(tuple(a for a in self.axioms if not set(a.label) & set(labels)))

    def restricted(self, keep) -> Ontology:
        return Ontology(tuple(a for a in self.axioms if keep(a)))

    def to_json(self) -> str:
        return "\n".join(json.dumps({"lhs": str(a.lhs), "rhs": str(a.rhs), "neg": a.neg, "label": "*".join(a.label)}) for a in self.axioms)


def normalise_inverses(ontology: Ontology) -> tuple[Ontology, frozenset[str]]:
    """Inverse roles replaced by fresh role names, and the fresh labels to erase from answers.

    Each inverse R- becomes a name of its own, tied to R by one inclusion in either direction; only those two still
    mention an inverse. Their labels are fresh, so a caller that wants the original answers erases them.
    """
    roles = sorted({r.name for a in ontology.axioms for t in (a.lhs, a.rhs) for r in [t.role if isinstance(t, Some) else t] if isinstance(r, Role) and r.inv})

    def flat(t):
        if isinstance(t, Some):
            return Some(flat(t.role))
        return Role(f"{t.name}_inverse") if isinstance(t, Role) and t.inv else t

    axioms = [Axiom(flat(a.lhs), flat(a.rhs), a.label, a.neg) for a in ontology.axioms]
    fresh: set[str] = set()
    for r in roles:
        for lhs, rhs, way in ((Role(r, True), Role(f"{r}_inverse"), "to"), (Role(f"{r}_inverse"), Role(r, True), "from")):
            fresh.add(label := f"~{way}~{r}")
            axioms.append(Axiom(lhs, rhs, (label,)))
    return Ontology(tuple(axioms)), frozenset(fresh)
