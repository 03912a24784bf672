"""Joins of a body's atoms over raw keys.

An atom's facts keep the key columns that individuals and row labels are made from, and say how either is spelled. A
variable that all its atoms make by one template is joined on the keys; texts of individuals and monomials are made once,
from the rows that are left. Expressions are SQL text: a plan is built in few calls.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame

from derivatrace.plans.instance import Bind, Instance, constants, union
from derivatrace.plans.mapping import Condition, Rule, Template, irredundant, sql_literal
from derivatrace.plans.rewrite import atom_closure

INTEGERS = {"tinyint", "smallint", "int", "bigint"}


@dataclass(frozen=True)
class Key:
    """Columns of an argument; prefix None: the one column is the individual's text."""

    columns: tuple[str, ...]
    prefix: str | None = None
    integers: bool = False

    @property
    def kind(self) -> tuple:
        return self.prefix, self.integers, len(self.columns)

    def text(self) -> str:
        return self.columns[0] if self.prefix is None else spelled(self.prefix, self.columns)


@dataclass
class Scan:
    """One reading of a table: conditions on its rows, and for each atom read the label sets to multiply in, by condition."""

    table: str
    keys: tuple[str, ...]
    conditions: list[str]
    #: Conditions on columns beside the keys.
    beside: bool
    ways: list[dict[Condition | None, list[tuple[str, ...]]]] = field(default_factory=list)


@dataclass
class Facts:
    """A frame with the columns of its arguments (None: a blank), and its labels as SQL over its columns: single ones, and arrays."""

    df: DataFrame | None
    args: list[Key | None]
    labels: list[str] = field(default_factory=list)
    arrays: list[str] = field(default_factory=list)
    #: Instead of a frame, a scan that other atoms may share.
    scan: Scan | None = None
    #: Whether the arguments hold the key of the row read, so that making facts distinct would drop next to nothing.
    keyed: bool = False


def spelled(prefix: str, columns: Iterable[str]) -> str:
    return f"concat({sql_literal(prefix + '/')}, " + ", '-', ".join(f"cast({c} as string)" for c in columns) + ")"


def label_text(instance: Instance, label: str) -> str:
    return f"xxhash64({sql_literal(label)})" if instance.hashed else sql_literal(label)


def label_array(instance: Instance, labels: Iterable[str]) -> str:
    labels = sorted(labels)
    return f"array({', '.join(label_text(instance, x) for x in labels)})" if labels else f"cast(array() as array<{'bigint' if instance.hashed else 'string'}>)"


def _keyed(df_types: dict[str, str], t: Template) -> Key:
    """The key of a template over a frame's columns; texts are made at once where keys of several parts aren't all integers."""
    kinds = [df_types[c] for c in t.columns]
    if all(k in INTEGERS for k in kinds):
        return Key(t.columns, t.prefix, True)
    return Key(t.columns, t.prefix) if kinds == ["string"] else Key((spelled(t.prefix, t.columns),))


def _row_label(instance: Instance, table: str, alias: str) -> tuple[list[str], str]:
    """Columns to carry for a table's row label, and the label over them."""
    s = instance.sources[table]
    if s.policy == "row":
        names = [f"{alias}_{j}" for j in range(len(s.keys))]
        text = f"concat('@', {spelled(s.prefix, names)})"
        carried = [f"{k} as {n}" for k, n in zip(s.keys, names, strict=True)]
    else:
        text = {"relation": sql_literal(f"@{table}")}.get(s.policy) or (f"concat({sql_literal(f'@{table}:')}, coalesce(cast({s.policy[7:]} as string), 'null'))" if s.policy.startswith("column:") else f"({s.policy})")
        carried, text = [f"{text} as {alias}"], alias
    return carried, f"xxhash64({text})" if instance.hashed else text


def _asked(t: Template, wanted: list[str] | None) -> list[str]:
    return [] if wanted is None else [t.among_sql(wanted)]


def rule_frame(instance: Instance, rules: list[tuple[Rule, list[tuple[str, ...]]]], args: tuple, *, labels: bool, bind: Bind | None) -> Facts:
    """The facts of one rule, or of several over one table with equal heads, each with label sets to multiply in: one scan."""
    first = rules[0][0]
    head, body = first.head, first.body
    conditions = [c for t, wanted in zip(head, constants(args, bind), strict=True) for c in _asked(t, wanted)] + [f"{c} is not null" for t in head for c in t.columns]
    texts, arrays = [], []
    if body.single:
        table, own = body.single[0], [r.body.single[1] for r, _ in rules]
        if all(own):
            conditions.append("(" + " or ".join(dict.fromkeys(f"({c.sql()})" for c in own)) + ")")
        sets: dict[Condition | None, list[tuple[str, ...]]] = {}
        for (r, ways), c in zip(rules, own, strict=True):
            sets.setdefault(c, []).extend(tuple(sorted({*r.label, *w})) for w in ways)
        types, keys = dict(instance.tables[table].dtypes), instance.sources[table].keys
        args_ = [_keyed(types, t) for t in head]
        beside = any(own) or any(wanted is not None and not set(t.columns) <= set(keys) for t, wanted in zip(head, constants(args, bind), strict=True))
        return Facts(None, args_, scan=Scan(table, keys, conditions, beside, [sets] * labels))
    else:
        if body.atoms:
            df, names = None, []
            for i, a in enumerate(body.atoms):
                known = {v: c for c, v in reversed(a.columns.items())}
                checks = [Condition(tuple(a.constants.items())).sql()] * bool(a.constants) + [f"{c} = {known[v]}" for c, v in a.columns.items() if known[v] != c]
                carried, text = _row_label(instance, a.table, f"_r{i}") if labels else ([], "")
                texts += [text] * labels
                one = instance.tables[a.table]
                one = (one.where(" and ".join(checks)) if checks else one).selectExpr(*[f"{c} as {v}" for v, c in known.items()], *carried)
                shared = [v for v in known if v in names]
                df = one if df is None else df.join(one, shared)
                names = list(dict.fromkeys([*names, *known]))
            conditions += [f"({body.where})"] * bool(body.where)
        else:
            df = body.build(instance)
            texts, arrays = list(body.labels) * labels, list(body.arrays) * labels
        df = df.where(" and ".join(conditions))
        types = dict(df.dtypes)
        if labels:
            ways = sorted(label_array(instance, {*first.label, *w}) for w in rules[0][1])
            if len(ways) > 1:
                df, ways = df.selectExpr("*", f"explode(array({', '.join(ways)})) as _way"), ["_way"]
            arrays = [*arrays, *ways]
    return Facts(df, [_keyed(types, t) for t in head], texts, arrays)


def scanned(instance: Instance, facts: Facts) -> Facts:
    """The facts with their scan as a frame: one pass, and an explosion for each atom with several label sets."""
    if facts.scan is None:
        return facts
    scan, texts, arrays = facts.scan, [], []
    select = list(dict.fromkeys(c for key in facts.args if key for c in (key.columns if key.prefix is not None else [])))
    made = {key.columns[0]: f"_t{i}" for i, key in enumerate(facts.args) if key and key.prefix is None}
    select += [f"{c} as {n}" for c, n in made.items()]
    args = [Key((made[key.columns[0]],)) if key and key.prefix is None else key for key in facts.args]
    generators = []
    if scan.ways:
        carried, text = _row_label(instance, scan.table, "_r0")
        select, texts = select + carried, [text]
    for n, by_condition in enumerate(scan.ways):
        sets = {c: [label_array(instance, s) for s in some] for c, some in by_condition.items()}
        if len(sets) == 1 and len(only := next(iter(sets.values()))) == 1:
            arrays.append(only[0])
            continue
        none = f"cast(array() as array<array<{'bigint' if instance.hashed else 'string'}>>)"
        every = [f"array({', '.join(s)})" if c is None or len(sets) == 1 else f"case when {c.sql()} then array({', '.join(s)}) else {none} end" for c, s in sets.items()]
        generators.append((f"_sets{n}", every[0] if len(every) == 1 else f"concat({', '.join(every)})"))
        arrays.append(f"_way{n}")
    df = instance.tables[scan.table].where(" and ".join(dict.fromkeys(scan.conditions))).selectExpr(*select, *[f"{x} as {n}" for n, x in generators])
    for n, _ in generators:
        df = df.selectExpr("*", f"explode({n}) as _way{n[5:]}").drop(n)
    return Facts(df, args, texts, arrays, keyed=set(scan.keys) <= {c for key in facts.args if key for c in key.columns})


def sharing(instance: Instance, rows: list[tuple[str, tuple]], atoms: list[list[Facts]], labels: bool) -> tuple[list, list]:
    """Atoms over one row of a table, told by its key under one term, as one atom: a row's label counts once.

    Where keys may repeat, rows alike in them must give the same facts: only key columns, and at most one atom with conditions beside.
    """
    groups: dict[tuple, list[int]] = {}
    for i, ((_, q), frames) in enumerate(zip(rows, atoms, strict=True)):
        if len(frames) == 1 and (scan := frames[0].scan):
            term = next((t for t, key in zip(q, frames[0].args, strict=True) if key and t[0] in "hvc" and key.columns == scan.keys), None)
            if term is not None:
                groups.setdefault((scan.table, term), []).append(i)
    merged: dict[int, int] = {}
    for (table, _), members in groups.items():
        s, kept = instance.sources[table], []
        for i in members:
            f = atoms[i][0]
            whole = not f.scan.beside and all(key is None or set(key.columns) <= set(s.keys) for key in f.args)
            if s.unique or whole and (not labels or s.policy == "row"):
                kept.append(i)
        merged |= dict.fromkeys(kept[1:], kept[0]) if kept else {}
    rows, atoms = list(rows), list(atoms)
    for i, into in sorted(merged.items()):
        a, b = atoms[into][0], atoms[i][0]
        rows[into] = (rows[into][0], (*rows[into][1], *rows[i][1]))
        atoms[into] = [Facts(None, [*a.args, *b.args], scan=Scan(a.scan.table, a.scan.keys, [*a.scan.conditions, *b.scan.conditions], a.scan.beside or b.scan.beside, [*a.scan.ways, *b.scan.ways]))]
    keep = [i for i in range(len(rows)) if i not in merged]
    return [rows[i] for i in keep], [atoms[i] for i in keep]


def atom_frames(instance: Instance, pred: str, args: tuple, *, labels: bool = True, bind: Bind | None = None) -> list[Facts]:
    """All facts that yield an atom, every rule read once for all its ways; plain: without rules that others subsume."""
    shared: dict[tuple, list] = {}
    out: list[Facts] = []
    reached = sorted(atom_closure(pred, args, list(instance.ontology.positive)).items())
    rules = {at: instance.rules_for(*at, bind) for at, _ in reached}
    if not labels:
        # Rules by what they make of the atom's own arguments: what others subsume adds no answer.
        plain = [(at, r, replace(r, head=tuple(r.head[at[1].index(a)] if a[0] != "b" and a in at[1] else None for a in args))) for at, found in rules.items() for r in found]
        kept = set(map(id, irredundant([n for _, _, n in plain])))
        rules = {at: [r for other, r, n in plain if other == at and id(n) in kept] for at in rules}

    def place(facts: Facts, q: tuple) -> None:
        """The atom's own arguments in terms of the yielding fact's; a variable repeated by a swap must agree with itself."""
        again = [f"{facts.args[q.index(t)].text()} = {facts.args[k].text()}" for k, t in enumerate(q) if t[0] in "hv" and t in q[:k]]
        if facts.scan:
            facts.scan.conditions += again
        elif again:
            facts = replace(facts, df=facts.df.where(" and ".join(again)))
        at = [next((i for i, t in enumerate(q) if t == a and t[0] != "b"), None) for a in args]
        out.append(replace(facts, args=[None if i is None else facts.args[i] for i in at]))

    for (p, q), ways in reached:
        for r in rules[p, q]:
            if r.body.single:
                shared.setdefault((q, r.body.single[0], r.head), []).append((r, sorted(ways)))
            else:
                place(rule_frame(instance, [(r, sorted(ways))], q, labels=labels, bind=bind), q)
        if (given := instance.given_facts(p, q, labels, bind)) is not None:
            n = len(given.columns) - labels
            arrays = ["mono"] * labels
            if labels and sorted(ways) != [()]:
                given = given.selectExpr("*", f"explode(array({', '.join(label_array(instance, w) for w in sorted(ways))})) as _way")
                arrays.append("_way")
            place(Facts(given, [Key((f"a{i}",)) for i in range(n)], [], arrays), q)
    for (q, _, _), group in shared.items():
        place(rule_frame(instance, group, q, labels=labels, bind=bind), q)
    return out


def _mono(labels: list[str], arrays: list[str]) -> str:
    parts = [f"array({', '.join(labels)})"] * bool(labels) + arrays
    return parts[0] if len(parts) == 1 else f"concat({', '.join(parts)})"


def _kinds_meet(a: Key, b: Key) -> bool:
    """Whether two arguments may be one individual: texts start with their prefix and a slash."""
    if a.prefix is None or b.prefix is None:
        return True
    return f"{a.prefix}/".startswith(f"{b.prefix}/") or f"{b.prefix}/".startswith(f"{a.prefix}/")


def meeting(rows: list[tuple[str, tuple]], atoms: list[list[Facts]]) -> list[list[Facts]]:
    """The atoms' facts without those whose individuals are of a kind that another atom over the variable never makes.

    What is left mostly makes a variable by one template, and so joins on its keys, where texts of mixed kinds were joined.
    """
    places = [[(t[1], k) for k, t in enumerate(q) if t[0] in "hv"] for _, q in rows]
    alone = lambda f, own: all(_kinds_meet(f.args[k], f.args[j]) for n, (v, k) in enumerate(own) for w, j in own[:n] if v == w)
    atoms = [[f for f in frames if alone(f, own)] for own, frames in zip(places, atoms, strict=True)]
    while True:
        made: dict[str, list[list[Key]]] = {}
        for own, frames in zip(places, atoms, strict=True):
            for v, k in own:
                made.setdefault(v, []).append([f.args[k] for f in frames])
        fits = lambda f, own, made=made: all(any(_kinds_meet(f.args[k], x) for x in keys) for v, k in own for keys in made[v])
        left = [[f for f in frames if fits(f, own)] for own, frames in zip(places, atoms, strict=True)]
        if list(map(len, left)) == list(map(len, atoms)):
            return left
        atoms = left


def looked_up(rows: list[tuple[str, tuple]], atoms: list[list[Facts]]) -> list[set]:
    """For each atom the terms that hold the key of the rows read: with one of them bound, a join multiplies nothing."""
    held = lambda f, k: f.scan is not None and f.args[k] is not None and f.args[k].columns == f.scan.keys
    return [{t for k, t in enumerate(q) if t[0] in "hv" and all(held(f, k) for f in frames)} for (_, q), frames in zip(rows, atoms, strict=True)]


def few_products(rows: list[tuple[str, tuple]], keys: list[set], order: Callable) -> list[tuple[int, tuple]]:
    """The order of joins with the fewest that multiply rows: from each start, atoms by a bound key or with nothing new come first.

    Starts are the atoms with the most constants; ``order`` decides what is left open.
    """
    base = [i for i, _ in order(rows)]
    terms = [{t for t in q if t[0] in "hv"} for _, q in rows]
    fixed = [sum(t[0] == "c" for t in q) for _, q in rows]
    best: tuple[tuple[int, int], list[int]] | None = None
    for start in (i for i in base if fixed[i] == max(fixed)):
        out, rest, bound, cost = [start], [i for i in base if i != start], set(terms[start]), [0, 0]
        while rest:
            rank = lambda i, bound=bound: 2 if not terms[i] & bound else 0 if terms[i] <= bound or keys[i] & bound else 1
            pick = min(rest, key=rank)
            cost[2 - rank(pick) if rank(pick) else 0] += bool(rank(pick))
            rest.remove(pick)
            out.append(pick)
            bound |= terms[pick]
        if best is None or tuple(cost) < best[0]:
            best = tuple(cost), out
    return [(i, rows[i]) for i in best[1]]


@dataclass
class Halves:
    """The two sides of a body's last join, each distinct or nearly so, the columns they meet in, and those of every answer variable with its text."""

    left: DataFrame
    right: DataFrame
    on: list[str]
    columns: dict[str, list[str]]
    texts: dict[str, str]
    #: Whether neither side is told by a key of its rows that the join binds.
    multiplies: bool


def joined(instance: Instance, rows: list[tuple[str, tuple]], head: tuple[str, ...], *, order: Callable, labels: bool = True, bind: Bind | None = None, extra: list[tuple[str, ...]] = (), early: bool = True, halves: bool = False) -> DataFrame | Halves | None:
    """Answer columns and mono (or, plain, the answers alone) of a body; None where some atom has no facts.

    extra: label sets of the body itself. early: whether an atom's facts are made distinct before they are joined. Plain: an atom that only filters is a semi-join, projections are made distinct.
    halves: of a plain body whose last join brings in answer variables, the two sides instead; None where it has no such join.
    """
    atoms = [atom_frames(instance, p, q, labels=labels, bind=bind) for p, q in rows]
    atoms = meeting(rows, atoms)
    if not all(atoms):
        return None
    rows, atoms = sharing(instance, rows, atoms, labels)
    keys = looked_up(rows, atoms)
    atoms = [[scanned(instance, f) for f in frames] for frames in atoms]
    # How each variable is made, over all atoms and frames.
    kinds: dict[str, set] = {}
    for (_, q), frames in zip(rows, atoms, strict=True):
        for k, t in enumerate(q):
            if t[0] in "hv":
                kinds.setdefault(t[1], set()).update(f.args[k].kind for f in frames)
    raw = {v: next(iter(k)) for v, k in kinds.items() if len(k) == 1 and next(iter(k))[0] is not None}
    columns = {v: [f"{v}__{j}" for j in range(raw[v][2])] if v in raw else [f"{v}__t"] for v in kinds}

    def named(i: int) -> tuple[DataFrame, list[str], list[str]]:
        """The atom's frame with columns named by its variables; its single labels and its arrays, over columns of its own."""
        q, out = rows[i][1], []
        for f in atoms[i]:
            select, checks = [], []
            for k, t in enumerate(q):
                if t[0] not in "hv":
                    continue
                key = f.args[k]
                made = [f"cast({c} as bigint)" if key.integers else c for c in key.columns] if t[1] in raw else [key.text()]
                if t in q[:k]:
                    before = [x.rsplit(" as ", 1)[0] for x in select if x.rsplit(" as ", 1)[1] in columns[t[1]]]
                    checks += [f"{a} = {b}" for a, b in zip(made, before, strict=True) if a != b]
                else:
                    select += [f"{c} as {n}" for c, n in zip(made, columns[t[1]], strict=True)]
            texts, arrays = f.labels, f.arrays
            if labels and len(atoms[i]) > 1:
                select.append(f"{_mono(texts, arrays)} as _m{i}")
            elif labels:
                # Row keys and exploded ways travel; texts and constants are put in at the end.
                carried = [c for c in f.df.columns if c.startswith(("_r", "_l", "_way")) or c == "mono"]
                select += [f"{c} as _c{i}{c}" for c in carried]
                swap = lambda x, carried=carried: _renamed(x, carried, f"_c{i}")
                texts, arrays = list(map(swap, texts)), list(map(swap, arrays))
            df = f.df.where(" and ".join(checks)) if checks else f.df
            out.append(df.selectExpr(*(select or ["1 as _one"])))
        return union(out), *(([], [f"_m{i}"]) if len(out) > 1 else (texts, arrays))

    def once(i: int) -> bool:
        return not early or len(atoms[i]) == 1 and atoms[i][0].keyed

    ordered, wanted = few_products(rows, keys, order), set(head)
    out, have, texts, arrays = None, [], [], []
    for n, (i, row) in enumerate(ordered):
        df, more_texts, more_arrays = named(i)
        own = list(dict.fromkeys(t[1] for t in row[1] if t[0] in "hv"))
        later = {t[1] for _, r in ordered[n + 1 :] for t in r[1] if t[0] in "hv"}
        shared = [v for v in own if v in have]
        on = [c for v in shared for c in columns[v]]
        new = [v for v in own if v not in have]
        if out is None:
            out = df if labels or once(i) else df.distinct()
        elif not labels and not set(new) & (wanted | later):
            # Without a shared variable the body is a product of two independent questions by its meaning.
            out = out.join(df, on, "left_semi") if on else out.crossJoin(df.limit(1).selectExpr("1 as _some")).drop("_some")
        else:
            df = df if labels or once(i) else df.distinct()
            if halves and on and n == len(ordered) - 1:
                several = not keys[i] & {(kind, v) for kind in "hv" for v in shared}
                return Halves(out, df, on, {h: columns[h] for h in head}, {h: spelled(raw[h][0], columns[h]) if h in raw else columns[h][0] for h in head}, several)
            out = out.join(df, on) if on else out.crossJoin(df)
        have += new
        texts, arrays = texts + more_texts, arrays + more_arrays
        keep = [v for v in have if v in wanted | later]
        if not labels and len(keep) < len(have) and n < len(ordered) - 1 and keep:
            out = out.select(*[c for v in keep for c in columns[v]]).distinct()
        have = keep
    if halves:
        return None
    heads = [f"{spelled(raw[h][0], columns[h]) if h in raw else columns[h][0]} as {h}" for h in head]
    if not labels:
        return out.selectExpr(*heads) if heads else out.limit(1).selectExpr("true as holds")
    sets = sorted(set(extra) - {()}) if set(extra) != {()} else []
    if sets and len(sets) == 1 and () not in extra:
        arrays = [*arrays, label_array(instance, sets[0])]
    elif sets:
        out = out.selectExpr("*", f"explode(array({', '.join(label_array(instance, s) for s in sorted(set(extra)))})) as _acc")
        arrays = [*arrays, "_acc"]
    return out.selectExpr(*heads, f"sort_array(array_distinct({_mono(texts, arrays)})) as mono")


def _renamed(text: str, columns: list[str], prefix: str) -> str:
    """SQL with some columns under a prefix; literals are left alone."""
    import re

    parts = re.split(r"('(?:[^'\\]|\\.)*')", text)
    for c in sorted(columns, key=len, reverse=True):
        parts = [p if p[:1] == "'" else re.sub(rf"(?<![\w]){re.escape(c)}(?!\w)", prefix + c, p) for p in parts]
    return "".join(parts)
