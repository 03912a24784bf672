"""A labelled instance: tables with row labels, rules, an ontology; and the derived facts of its predicates."""

from __future__ import annotations

import operator
from collections.abc import Iterable, Mapping
from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from derivatrace.functions.labels import constant, encoded, row_label
from derivatrace.functions.monomials import mul, mul_idem
from derivatrace.plans.mapping import Condition, Rule
from derivatrace.plans.ontology import Ontology


#: Answer variable -> the few constants that it may be.
Bind = dict[str, list[str]]


def constants(args: tuple, bind: Bind | None) -> list[list[str] | None]:
    """For each argument the constants it may be; None: any."""
    return [[n] if k == "c" else bind.get(n) if k == "h" and bind else None for k, n in args]


@dataclass(frozen=True)
class Source:
    table: str
    prefix: str
    keys: tuple[str, ...]
    policy: str = "row"
    #: Whether no two rows have equal keys: atoms over one row then share a scan.
    unique: bool = False


@dataclass(frozen=True)
class Instance:
    spark: SparkSession
    tables: Mapping[str, DataFrame]
    sources: dict[str, Source]
    rules: tuple[Rule, ...]
    ontology: Ontology = Ontology()
    hashed: bool = False
    #: Facts given as frames (pred -> s, [o,] mono) beside the rules', as fixtures and stores have them.
    given: dict[str, DataFrame] = field(default_factory=dict)

    def with_policy(self, policy: str, *tables: str) -> Instance:
        return replace(self, sources={n: replace(s, policy=policy) if not tables or n in tables else s for n, s in self.sources.items()})

    def with_ontology(self, ontology: Ontology) -> Instance:
        return replace(self, ontology=ontology)

    def labelled(self, table: str) -> DataFrame:
        """The table and its row labels in ``_label``; a narrow projection."""
        s = self.sources[table]
        return self.tables[table].withColumn("_label", encoded(row_label(s.table, s.prefix, s.keys, s.policy), self.hashed))

    def constant(self, labels: Iterable[str]) -> Column:
        return constant(labels, self.hashed)

    def rules_for(self, pred: str, args: tuple | None = None, bind: Bind | None = None) -> list[Rule]:
        """The rules of a predicate, without those whose templates can't make the constants asked for."""
        found = [r for r in self.rules if r.pred == pred]
        if args is not None:
            found = [r for r in found if all(wanted is None or any(map(t.may_be, wanted)) for t, wanted in zip(r.head, constants(args, bind), strict=True))]
        return found

    def rule_facts(self, rule: Rule, args: tuple | None = None, *, level: str = "idempotent", labels: bool = True, bind: Bind | None = None) -> DataFrame:
        """a0, [a1,] mono of one rule; constants among the arguments become filters on key columns.

        Rows with a null argument give no fact.
        """
        df = rule.body.build(self)
        for t, wanted in zip(rule.head, constants(args or (), bind), strict=False):
            if wanted is not None:
                df = df.where(t.equals(wanted[0]) if len(wanted) == 1 else t.among(wanted))
        for t in rule.head:
            for c in t.columns:
                df = df.where(F.col(c).isNotNull())
        cols = [t.column().alias(f"a{i}") for i, t in enumerate(rule.head)]
        if labels:
            own = [F.array(*map(F.col, rule.body.labels))] if rule.body.labels else []
            cols.append((mul if level == "general" else mul_idem)(self.constant(rule.label), *own, *map(F.col, rule.body.arrays)).alias("mono"))
        return df.select(*cols)

    def shared_scan(self, group: list[tuple[Rule, list[tuple[str, ...]]]], args: tuple, *, labels: bool = True, bind: Bind | None = None) -> DataFrame:
        """a0, [a1,] mono of several rules over one table with equal heads, each with label sets to multiply in: one scan.

        Every row meets the rules' conditions once; an array of the label sets of those that hold is exploded.
        """
        head, (table, _) = group[0][0].head, group[0][0].body.single
        df = self.labelled(table)
        for t, wanted in zip(head, constants(args, bind), strict=True):
            if wanted is not None:
                df = df.where(t.equals(wanted[0]) if len(wanted) == 1 else t.among(wanted))
        for t in head:
            for c in t.columns:
                df = df.where(F.col(c).isNotNull())
        conditions = [r.body.single[1] for r, _ in group]
        if all(conditions):
            df = df.where(reduce(operator.or_, [c.column() for c in dict.fromkeys(conditions)]))
        cols = [t.column().alias(f"a{i}") for i, t in enumerate(head)]
        if not labels:
            return df.select(*cols)
        sets: dict[Condition | None, list[Column]] = {}
        for (r, ways), c in zip(group, conditions, strict=True):
            sets.setdefault(c, []).extend(self.constant({*r.label, *w}) for w in ways)
        arrays = [F.array(*s) if c is None else F.when(c.column(), F.array(*s)).otherwise(F.array().cast(f"array<array<{'bigint' if self.hashed else 'string'}>>")) for c, s in sets.items()]
        every = arrays[0] if len(arrays) == 1 else F.concat(*arrays)
        if len(sets) == 1 and len(next(iter(sets.values()))) == 1:
            return df.select(*cols, mul_idem(F.array("_label"), next(iter(sets.values()))[0]).alias("mono"))
        return df.select(*cols, "_label", F.explode(every).alias("_way")).select(*[f"a{i}" for i in range(len(head))], mul_idem(F.array("_label"), F.col("_way")).alias("mono"))

    def given_facts(self, pred: str, args: tuple | None = None, labels: bool = True, bind: Bind | None = None) -> DataFrame | None:
        if (df := self.given.get(pred)) is None:
            return None
        names = [c for c in df.columns if c != "mono"]
        df = df.select(*[F.col(c).alias(f"a{i}") for i, c in enumerate(names)], *["mono"] * labels)
        for i, wanted in enumerate(constants(args or (), bind)):
            if wanted is not None:
                df = df.where(F.col(f"a{i}").isin(wanted))
        return df

    def branches(self, pred: str, args: tuple | None = None, *, level: str = "idempotent", labels: bool = True, bind: Bind | None = None) -> list[DataFrame]:
        """One frame for each rule of the predicate that can make these arguments."""
        out = [self.rule_facts(r, args, level=level, labels=labels, bind=bind) for r in self.rules_for(pred, args, bind)]
        given = self.given_facts(pred, args, labels, bind)
        return out if given is None else [*out, given]

    def empty(self, n: int, labels: bool = True) -> DataFrame:
        kind = "bigint" if self.hashed else "string"
        return self.spark.createDataFrame([], ", ".join([f"a{i} string" for i in range(n)] + [f"mono array<{kind}>"] * labels))

    def facts(self, pred: str, n: int, *, level: str = "idempotent", args: tuple | None = None) -> DataFrame:
        """The derived facts of a predicate: equal (arguments, monomial) pairs are one fact, at every level."""
        found = self.branches(pred, args, level=level)
        return union(found).dropDuplicates() if found else self.empty(n)

    def predicates(self) -> dict[str, int]:
        return {r.pred: len(r.head) for r in self.rules} | {p: len(d.columns) - 1 for p, d in self.given.items()}


def union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for df in frames[1:]:
        out = out.unionByName(df)
    return out


def derive_facts(instance: Instance, preds: Iterable[str] | None = None, level: str = "idempotent") -> dict[str, DataFrame]:
    """Derived facts by predicate."""
    known = instance.predicates()
    return {p: instance.facts(p, known[p], level=level) for p in (preds or sorted(known))}


def register_views(instance: Instance, preds: Iterable[str] | None = None) -> list[str]:
    """Temp views facts_<predicate> for SQL over derived facts."""
    names = []
    for p, df in derive_facts(instance, preds).items():
        names.append(f"facts_{p}")
        df.toDF(*(("s", "mono") if len(df.columns) == 2 else ("s", "o", "mono"))).createOrReplaceTempView(names[-1])
    return names


def from_store(instance: Instance, facts: dict[str, DataFrame]) -> Instance:
    """The instance over stored facts (a0, [a1,] mono) instead of its rules: materialised where the rules are virtual."""
    return replace(instance, rules=(), given=facts)
