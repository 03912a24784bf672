"""An unfolding as SQL text over the source tables, as a rewriting system hands it to its database.

Conjunctive rule bodies are written out; a body beyond them is read from a temporary view of its frame.
"""

from __future__ import annotations

from derivatrace.operators.provenance import UnionPlan, unfold
from derivatrace.plans.cq import CQ
from derivatrace.plans.instance import Instance, Source
from derivatrace.plans.mapping import Rule, TableAtom, equals_sql, sql_literal


def _individual(prefix: str, columns: list[str]) -> str:
    parts = ", '-', ".join(f"CAST({c} AS STRING)" for c in columns)
    return f"concat({sql_literal(prefix + '/')}, {parts})"


def _label(s: Source, alias: str) -> str:
    if s.policy == "row":
        return f"concat('@', {_individual(s.prefix, [f'{alias}.{k}' for k in s.keys])})"
    if s.policy == "relation":
        return sql_literal(f"@{s.table}")
    if s.policy.startswith("column:"):
        return f"concat({sql_literal(f'@{s.table}:')}, coalesce(CAST({alias}.{s.policy[7:]} AS STRING), 'null'))"
    return s.policy


def view_name(rule: Rule) -> str:
    return f"rule_{rule.pred}_{'_'.join(rule.label)}"


def rule_sql(instance: Instance, rule: Rule) -> str:
    """a0, [a1,] mono of one rule."""
    if not rule.body.atoms:
        return f"SELECT * FROM {view_name(rule)}"
    first: dict[str, str] = {}
    source, conditions = [], []

    def read(i: int, a: TableAtom) -> None:
        source.append(f"{a.table} t{i}")
        for c, v in a.columns.items():
            if v in first:
                conditions.append(f"t{i}.{c} = {first[v]}")
            first.setdefault(v, f"t{i}.{c}")
        conditions.extend(equals_sql(f"t{i}.{c}", v) for c, v in a.constants.items())

    for i, a in enumerate(rule.body.atoms):
        read(i, a)
    labels = [_label(instance.sources[a.table], f"t{i}") for i, a in enumerate(rule.body.atoms)]
    inner = f"SELECT {', '.join([*[f'{c} AS {v}' for v, c in first.items()], *[f'{x} AS _l{i}' for i, x in enumerate(labels)]])} FROM {', '.join(source)}" + (f" WHERE {' AND '.join(conditions)}" if conditions else "")
    asked = [f"({rule.body.where})"] * bool(rule.body.where) + [f"{c} IS NOT NULL" for t in rule.head for c in t.columns]
    mono = ", ".join([*map(sql_literal, rule.label), *[f"_l{i}" for i in range(len(labels))]])
    heads = ", ".join(f"{_individual(t.prefix, list(t.columns))} AS a{i}" for i, t in enumerate(rule.head))
    return f"SELECT {heads}, array_sort(array_distinct(array({mono}))) AS mono FROM ({inner}) b WHERE {' AND '.join(asked)}"


def plan_sql(instance: Instance, plan: UnionPlan) -> str:
    """The union plan as one statement: UNION as often as the plan counts."""
    selects = []
    for body, labels, rules in plan.branches:
        source, conditions, at = [], [], {}
        for i, ((_, args, _), r) in enumerate(zip(body, rules, strict=True)):
            source.append(f"({rule_sql(instance, r)}) f{i}")
            for k, t in enumerate(args):
                if t[0] == "c":
                    conditions.append(f"f{i}.a{k} = {sql_literal(t[1])}")
                elif t[0] != "b":
                    if t in at:
                        conditions.append(f"f{i}.a{k} = {at[t]}")
                    at.setdefault(t, f"f{i}.a{k}")
        monos = [f"f{i}.mono" for i in range(len(body))] + [f"array({', '.join(map(sql_literal, labels))})"] * bool(labels)
        heads = "".join(f"{at['h', h]} AS {h}, " for h in plan.cq.head)
        selects.append(f"SELECT {heads}array_sort(array_distinct(concat({', '.join(monos)}))) AS mono\nFROM {', '.join(source)}" + (f"\nWHERE {' AND '.join(conditions)}" if conditions else ""))
    if not selects:
        heads = "".join(f"CAST(NULL AS STRING) AS {h}, " for h in plan.cq.head)
        return f"SELECT {heads}CAST(NULL AS ARRAY<STRING>) AS mono WHERE false"
    text = "\nUNION\n".join(selects) if len(selects) > 1 else f"SELECT DISTINCT * FROM ({selects[0]})"
    return f"SELECT * FROM (\n{text}\n) WHERE {plan.cq.where}" if plan.cq.where else text


def unfolding_sql(instance: Instance, cq: CQ, *, optimise: str = "none") -> str:
    """The query's unfolding as SQL; ``register`` makes the views that it reads. Labels are texts, not hashes."""
    if instance.hashed or instance.given:
        raise ValueError("SQL text is for rules over tables with labels as texts")
    if optimise == "certain":
        raise ValueError("plain branches have no labels to select")
    return plan_sql(instance, unfold(instance, cq, optimise=optimise))


def register(instance: Instance) -> None:
    """Views of the tables and of the bodies beyond conjunctive ones."""
    for name in {a.table for r in instance.rules for a in r.body.atoms}:
        instance.tables[name].createOrReplaceTempView(name)
    seen: dict[str, list] = {}
    for r in instance.rules:
        if not r.body.atoms:
            seen.setdefault(view_name(r), []).append(r)
    for name, rules in seen.items():
        if len(rules) > 1:
            raise ValueError(f"two bodies beyond conjunctive ones for one head and label: {name}")
        instance.rule_facts(rules[0]).createOrReplaceTempView(name)
