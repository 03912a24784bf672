"""Polynomials over row keys: what a monomial's labels are made from, before their texts are.

A body whose atoms each read one table gives an answer's monomials as row labels, told by integer keys, times label sets
that are known when the plan is built. Terms keep the two apart: a row of keys with the label sets that hold for it. Where
two polynomials have terms over the same tables, equal monomials are equal keys and equal sets, so that they are compared
by keys and one bit for each set: a row for each choice of rows of the tables, not for each monomial, and no text is made.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from itertools import product as cartesian

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from derivatrace.operators.joins import INTEGERS, Key, _kinds_meet, atom_frames, few_products, looked_up, meeting, sharing
from derivatrace.plans.instance import Instance, union

#: Label sets in a word: either side has a bit for each.
WORD = 31
#: Label sets that are compared by bits at most; more are compared as texts.
MOST = 8 * WORD


@dataclass
class Terms:
    """Rows of one body: a frame, and over its columns what tells answers, rows and label sets."""

    df: DataFrame
    #: Prefix and columns of each answer variable.
    heads: tuple[tuple[str, tuple[str, ...]], ...]
    #: For each table its key as SQL; None beside a column: it is that answer column.
    rows: dict[str, list[tuple[str, str | None]]]
    #: Label sets, each with the condition on which it holds (None: always).
    sets: list[tuple[str | None, tuple[str, ...]]]


@dataclass
class Apart:
    """A polynomial as terms; ``frame`` makes its answer columns and mono."""

    terms: list[Terms]
    frame: Callable[[], DataFrame]


def apart_terms(instance: Instance, rows: list[tuple[str, tuple]], head: tuple[str, ...], *, order: Callable, extra: list[tuple[str, ...]] = ()) -> list[Terms] | None:
    """The terms of a body: none where some atom has no facts; None where they can't be kept apart.

    They can where every atom reads one table that no other atom reads, told by integer keys, and labels are rows' own.
    """
    atoms = meeting(rows, [atom_frames(instance, p, q) for p, q in rows])
    if not all(atoms):
        return []
    rows, atoms = sharing(instance, rows, atoms, True)
    if instance.hashed or any(len(frames) > 1 or frames[0].scan is None for frames in atoms):
        return None
    facts = [frames[0] for frames in atoms]
    tables = [f.scan.table for f in facts]
    sources = [instance.sources[t] for t in tables]
    types = [dict(instance.tables[t].dtypes) for t in tables]
    if any(s.policy != "row" or not {t[k] for k in s.keys} <= INTEGERS for s, t in zip(sources, types, strict=True)):
        return None
    if any(_kinds_meet(Key((), a.prefix), Key((), b.prefix)) for n, a in enumerate(sources) for b in sources[:n]):
        return None
    kinds: dict[str, set] = {}
    for (_, q), f in zip(rows, facts, strict=True):
        for k, t in enumerate(q):
            if t[0] in "hv":
                kinds.setdefault(t[1], set()).add(f.args[k].kind)
    if any(len(own) > 1 or not next(iter(own))[1] for own in kinds.values()) or not set(head) <= set(kinds):
        return None
    columns = {v: tuple(f"{v}__{j}" for j in range(next(iter(own))[2])) for v, own in kinds.items()}

    out, have, told, choices = None, [], {}, [[(None, s) for s in extra or [()]]]
    for i, (_, q) in few_products(rows, looked_up(rows, atoms), order):
        f, select, checks, same = facts[i], [], [], {}
        for k, t in enumerate(q):
            if t[0] not in "hv":
                continue
            made = [f"cast({c} as bigint)" for c in f.args[k].columns]
            if t in q[:k]:
                checks += [f"{a} = cast({b} as bigint)" for a, b in zip(made, f.args[q.index(t)].columns, strict=True)]
            else:
                select += [f"{a} as {c}" for a, c in zip(made, columns[t[1]], strict=True)]
            same = dict(zip(f.args[k].columns, columns[t[1]], strict=True)) | same
        carried = {k: f"_r{i}_{j}" for j, k in enumerate(sources[i].keys) if k not in same}
        select += [f"cast({k} as bigint) as {c}" for k, c in carried.items()]
        told[tables[i]] = [same.get(k) or carried[k] for k in sources[i].keys], list(carried.values())
        for n, sets in enumerate(f.scan.ways):
            # A single condition is one on the rows read.
            bits = {c: 1 << j for j, c in enumerate(c for c in sets if c is not None)} if len(sets) > 1 else {}
            if len(bits) > 2 * WORD:
                return None
            if bits:
                select.append(" + ".join(f"case when {c.sql()} then {b}L else 0L end" for c, b in bits.items()) + f" as _k{i}_{n}")
            choices.append([(f"(_k{i}_{n} & {bits[c]}L) <> 0" if c in bits else None, s) for c, some in sets.items() for s in some])
        df = instance.tables[tables[i]].where(" and ".join(dict.fromkeys([*f.scan.conditions, *checks])) or "true").selectExpr(*(select or ["1 as _one"]))
        own = list(dict.fromkeys(t[1] for t in q if t[0] in "hv"))
        on = [c for v in own if v in have for c in columns[v]]
        out = df if out is None else out.join(df, on) if on else out.crossJoin(df)
        have += [v for v in own if v not in have]
    size = 1
    for some in choices:
        size *= len(some)
    if size > MOST:
        return None
    sets = [(" and ".join(dict.fromkeys(c for c, _ in chosen if c)) or None, tuple(sorted(set().union(*(s for _, s in chosen))))) for chosen in cartesian(*choices)]
    answers = {c for h in head for c in columns[h]}
    made = {}
    for table, (keys, nullable) in told.items():
        # A row label with a part that is null is null as a whole.
        missing = " or ".join(f"{c} is null" for c in nullable)
        made[table] = [(f"if({missing}, null, {c})" if missing else c, c if c in answers else None) for c in keys]
    return [Terms(out, tuple((next(iter(kinds[h]))[0], columns[h]) for h in head), made, sets)]


def same(left: Apart, right: Apart) -> bool | None:
    """Whether the polynomials are equal; None where their terms are over other tables, or have too many label sets, to tell."""
    terms = [*left.terms, *right.terms]
    if not terms:
        return True
    sets = {s: n for n, s in enumerate(dict.fromkeys(s for t in terms for _, s in t.sets))}
    # A label that looks like a row's might be one.
    if len({(t.heads, frozenset(t.rows)) for t in terms}) > 1 or len(sets) > MOST or any(x.startswith("@") for s in sets for x in s):
        return None
    tables = sorted(terms[0].rows)
    # What is an answer column in all terms needn't be looked at twice.
    needed = [(table, j) for table in tables for j, (_, c) in enumerate(terms[0].rows[table]) if c is None or any(t.rows[table][j][1] != c for t in terms)]
    answers = [c for _, own in terms[0].heads for c in own]
    names = [*answers, *(f"_key{n}" for n in range(len(needed)))]
    words = range(-(-len(sets) // WORD))

    def coded(t: Terms, shift: int) -> DataFrame:
        keys = [f"{t.rows[table][j][0]} as _key{n}" for n, (table, j) in enumerate(needed)]
        masks = []
        for w in words:
            bits: dict[str | None, int] = {}
            for c, s in t.sets:
                if sets[s] // WORD == w:
                    bits[c] = bits.get(c, 0) | 1 << sets[s] % WORD + shift
            masks.append((" | ".join(f"{b}L" if c is None else f"case when {c} then {b}L else 0L end" for c, b in bits.items()) or "0L") + f" as _sets{w}")
        return t.df.selectExpr(*answers, *keys, *masks)

    both = union([coded(t, WORD * (k >= len(left.terms))) for k, t in enumerate(terms)])
    # Dealt out first: within a body keys hardly repeat, so that a task has little to sum up before.
    dealt = both.repartition(*names) if names else both
    found = dealt.groupBy(*names).agg(*[F.bit_or(f"_sets{w}").alias(f"_sets{w}") for w in words])
    differs = " or ".join(f"(_sets{w} & {(1 << WORD) - 1}L) <> shiftrightunsigned(_sets{w}, {WORD})" for w in words)
    return found.where(differs).limit(1).count() == 0
