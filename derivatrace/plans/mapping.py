"""Rule mappings: a head over individuals made from keys, and a body that is a conjunction of table atoms or any frame.

A body yields a frame with the key columns of its head and the labels of the rows it used: one column for each table
atom (``witness`` columns), or an array of them. Bodies beyond conjunctions choose a policy: a union gives one derived
fact for each branch, an aggregate is ``opaque`` (the rule's label only) or has ``witnesses`` (all labels of its group).
"""

from __future__ import annotations

import datetime
import re
from collections.abc import Callable
from dataclasses import dataclass, field
from decimal import Decimal
from typing import TYPE_CHECKING

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from derivatrace.functions.labels import keyed

if TYPE_CHECKING:
    from derivatrace.plans.instance import Instance


@dataclass(frozen=True)
class Template:
    """An individual: prefix/key-key-…"""

    prefix: str
    columns: tuple[str, ...]

    def column(self) -> Column:
        return keyed(self.prefix, self.columns)

    def may_be(self, constant: str) -> bool:
        head, _, rest = constant.partition("/")
        return head == self.prefix and (len(self.columns) == 1 or rest.count("-") >= len(self.columns) - 1)

    def equals(self, constant: str) -> Column:
        """The constant's keys against the key columns, so that the filter reaches the scan."""
        rest = constant.partition("/")[2]
        if len(self.columns) == 1:
            return _typed(self.columns[0], rest)
        parts = rest.split("-")
        if len(parts) != len(self.columns):  # a key with a dash in it: compare the whole
            return self.column() == constant
        out = F.lit(True)
        for c, v in zip(self.columns, parts, strict=True):
            out &= _typed(c, v)
        return out


    def among_sql(self, constants: list[str]) -> str:
        """Any of the constants as SQL over the key columns, so that the filter reaches the scan."""
        possible = [c for c in constants if self.may_be(c)]
        if len(self.columns) == 1 and len(possible) > 1:
            keys = [c.partition("/")[2] for c in possible]
            if all(k.lstrip("-").isdigit() and str(int(k)) == k for k in keys):
                return f"{self.columns[0]} in ({', '.join(keys)})"
            return f"cast({self.columns[0]} as string) in ({', '.join(map(sql_literal, keys))})"
        out = []
        for c in possible:
            parts = [c.partition("/")[2]] if len(self.columns) == 1 else c.partition("/")[2].split("-")
            if len(parts) == len(self.columns):
                out.append("(" + " and ".join(_key_sql(k, v) for k, v in zip(self.columns, parts, strict=True)) + ")")
            else:  # a key with a dash in it: compare the whole
                out.append(f"concat({sql_literal(self.prefix + '/')}, " + ", '-', ".join(f"cast({k} as string)" for k in self.columns) + f") = {sql_literal(c)}")
        return f"({' or '.join(out)})" if out else "false"

    def among(self, constants: list[str]) -> Column:
        """Any of the constants; one key column compares as a list, which the scan takes as a filter."""
        possible = [c for c in constants if self.may_be(c)]
        if len(self.columns) == 1 and possible:
            keys = [c.partition("/")[2] for c in possible]
            if all(k.lstrip("-").isdigit() and str(int(k)) == k for k in keys):
                return F.col(self.columns[0]).isin([int(k) for k in keys])
            return F.col(self.columns[0]).cast("string").isin(keys)
        out = F.lit(False)
        for c in possible:
            out |= self.equals(c)
        return out


def _key_sql(column: str, value: str) -> str:
    return f"{column} = {value if value.lstrip('-').isdigit() and str(int(value)) == value else sql_literal(value)}"


def _typed(column: str, value: str) -> Column:
    # An integer literal lets the comparison keep the column's type, and so be pushed down.
    return F.col(column) == (F.lit(int(value)) if value.lstrip("-").isdigit() and str(int(value)) == value else F.lit(value))


@dataclass(frozen=True)
class TableAtom:
    """A table in a conjunctive body: column, or SQL over columns -> variable, and constants that columns equal."""

    table: str
    columns: dict[str, str]
    constants: dict[str, object] = field(default_factory=dict)


def sql_literal(value: object) -> str:
    """A constant of any type as SQL. A datetime without a zone is a wall-clock time, whatever the session's zone."""
    if value is None or isinstance(value, bool | int):
        return "null" if value is None else str(value).lower()
    if isinstance(value, float):
        return f"double('{value!r}')"
    if isinstance(value, Decimal):
        return f"{value:f}BD"
    if isinstance(value, datetime.datetime):
        return f"timestamp{'_ntz' * (value.tzinfo is None)}'{value.isoformat(sep=' ')}'"
    if isinstance(value, datetime.date):
        return f"date'{value.isoformat()}'"
    return "'" + str(value).replace("\\", "\\\\").replace("'", "\\'") + "'"


def equals_sql(column: str, value: object) -> str:
    """The column against a constant of any type; None asks for null."""
    return f"{column} is null" if value is None else f"{column} = {sql_literal(value)}"


@dataclass(frozen=True)
class Condition:
    """What a row of one table must meet: columns that equal constants, and SQL."""

    equal: tuple[tuple[str, object], ...] = ()
    where: str | None = None

    def sql(self) -> str:
        return " and ".join([*[f"({self.where})"] * bool(self.where), *[equals_sql(c, v) for c, v in self.equal]])

    def column(self) -> Column:
        return F.expr(self.sql())


@dataclass(frozen=True)
class Body:
    """build(instance) -> frame; labels: its label columns; arrays: columns that hold arrays of labels."""

    key: str
    build: Callable[[Instance], DataFrame]
    labels: tuple[str, ...] = ()
    arrays: tuple[str, ...] = ()
    #: The table and the condition, where the body is one table under its own column names: such rules can share a scan.
    single: tuple[str, Condition | None] | None = None
    #: The table atoms of a conjunctive body, one for each label column, and its SQL condition.
    atoms: tuple[TableAtom, ...] = field(default=(), compare=False)
    where: str | None = None


def conjunctive(key: str, *atoms: TableAtom, where: str | None = None) -> Body:
    """A conjunctive body; its key columns are named by the variables, those not in the head are projected away."""

    def build(instance: Instance) -> DataFrame:
        out: DataFrame | None = None
        for i, a in enumerate(atoms):
            df = instance.labelled(a.table)
            for c, v in a.constants.items():
                df = df.where(equals_sql(c, v))
            first = {v: c for c, v in reversed(a.columns.items())}
            for c, v in a.columns.items():
                if first[v] != c:  # a repeated variable within the atom
                    df = df.where(f"{c} = {first[v]}")
            df = df.selectExpr(*[f"{c} as {v}" for v, c in first.items()], f"_label as _l{i}")
            shared = [v for v in first if out is not None and v in out.columns]
            out = df if out is None else out.join(df, shared)
        return out.where(where) if where else out

    single = None
    if len(atoms) == 1 and all(c == v for c, v in atoms[0].columns.items()):
        equal = tuple(sorted(atoms[0].constants.items()))
        single = atoms[0].table, Condition(equal, where) if equal or where else None
    return Body(key, build, tuple(f"_l{i}" for i in range(len(atoms))), single=single, atoms=atoms, where=where)


@dataclass(frozen=True)
class Rule:
    label: tuple[str, ...]
    pred: str
    head: tuple[Template, ...]
    body: Body

    @property
    def name(self) -> str:
        return "*".join(self.label)


def subsumed(rule: Rule, by: Rule) -> bool:
    """Whether all facts of a rule are facts of another one: equal heads, and the other's body asks for no more.

    A check on conjunctive bodies with equal variable names; labels differ, so it serves plain answers only.
    """

    def asks_less(a: TableAtom, b: TableAtom) -> bool:
        return a.table == b.table and a.columns.items() <= b.columns.items() and a.constants.items() <= b.constants.items()

    if rule.head != by.head or not rule.body.atoms or not by.body.atoms or by.body.where not in (None, rule.body.where):
        return False
    return all(any(asks_less(a, b) for b in rule.body.atoms) for a in by.body.atoms)


def irredundant(rules: list[Rule]) -> list[Rule]:
    """Without the rules that another one subsumes; of equal ones the first stays."""
    kept: list[Rule] = []
    for r in rules:
        if not any(subsumed(r, k) for k in kept):
            kept = [k for k in kept if not subsumed(k, r)] + [r]
    return kept


_RULE = re.compile(r"\s*(\w+)\s*\(((?:[^()']|'[^']*')*)\)\s*")
_TERM = re.compile(r"\s*(\w+)((?:\{\w+\})+)\s*(?:,|$)")
_COLUMN = re.compile(r"\s*(\w+(?:\{\w+\})?)\s*(?:=\s*('(?:[^']|'')*'|-?\d+(?:\.\d+)?|\w+)\s*)?(?:,|$)")


def _taken(pattern: re.Pattern, text: str) -> list[re.Match]:
    out, at = [], 0
    while at < len(text.rstrip()):
        if not (m := pattern.match(text, at)):
            raise ValueError(f"can't read {text[at:]!r}")
        out.append(m)
        at = m.end()
    return out


def parse_rule(text: str) -> Rule:
    """``placedBy(ord{ok}, cust{ck}) <- orders(o_orderkey=ok, o_custkey=ck, o_orderstatus='O') where ck > 3 @m14``.

    Heads name a prefix and its key variables; a column without ``=`` is a variable of its own name, ``md5{text}=t`` a
    function of a column; quoted texts and numbers are constants (decimal ones exact).
    """
    body, _, label = text.rpartition("@")
    head, found, rest = body.partition("<-")
    if not found or not (h := _RULE.fullmatch(head)):
        raise ValueError(f"no rule: {text!r}")
    rest, _, where = re.match(r"(?s)(.*?)(?:\s(where)\s(.*))?$", rest).groups()
    templates = tuple(Template(m[1], tuple(re.findall(r"\w+", m[2]))) for m in _taken(_TERM, h[2]))
    atoms, at = [], 0
    while at < len(rest.rstrip()):
        if not (m := _RULE.match(rest, at)):
            raise ValueError(f"no table at {rest[at:]!r}")
        at = m.end() + (rest[m.end() : m.end() + 1] == ",")
        columns, fixed = {}, {}
        for c in _taken(_COLUMN, m[2]):
            name = c[1].replace("{", "(").replace("}", ")")
            if c[2] is None or re.fullmatch(r"[A-Za-z_]\w*", c[2]):
                columns[name] = c[2] or name
            else:
                fixed[name] = c[2][1:-1].replace("''", "'") if c[2][0] == "'" else int(c[2]) if "." not in c[2] else Decimal(c[2])
        atoms.append(TableAtom(m[1], columns, fixed))
    if missing := {v for t in templates for v in t.columns} - {v for a in atoms for v in a.columns.values()}:
        raise ValueError(f"head variables that the body lacks: {missing}")
    labels = tuple(sorted(x for x in label.strip().split("*") if x))
    return Rule(labels, h[1], templates, conjunctive(text.strip(), *atoms, where=where.strip() if where else None))


def saturated(rules: list[Rule], axioms, closure_of) -> list[tuple[Rule, str, bool, tuple[str, ...], tuple]]:
    """Rules that gain implied heads: (rule, predicate, arguments swapped, labels of the way, arguments kept of the rule's).

    Existential heads aren't facts over known individuals, so they stay with rewriting. ``closure_of`` gives, for a
    predicate with distinct arguments, the atoms that yield it (see rewrite.atom_closure).
    """
    by_pred: dict[str, list[Rule]] = {}
    for r in rules:
        by_pred.setdefault(r.pred, []).append(r)
    heads = {r.pred: len(r.head) for r in rules}
    for a in axioms:
        for t in (a.lhs, a.rhs):
            name = getattr(t, "name", None) or t.role.name
            heads.setdefault(name, 1 if type(t).__name__ == "Concept" else 2)
    out = []
    for pred, n in sorted(heads.items()):
        args = (("h", "x"), ("h", "y"))[:n]
        for (p, q), ways in closure_of(pred, args, axioms).items():
            for r in by_pred.get(p, []):
                for way in sorted(ways):
                    out.append((r, pred, q[:1] != args[:1], way, tuple(t for t in q if t[0] == "h")))
    return out


__all__ = ["Body", "Condition", "Rule", "TableAtom", "Template", "conjunctive", "irredundant", "parse_rule", "saturated", "subsumed"]
