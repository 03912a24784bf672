"""The computing task: answers of a conjunctive query, one row for each (answer, monomial).

Three physical forms give the same polynomial. ``unfold`` is a union with a branch for every rewriting and choice of
rules, as stock rewriting systems make it. ``shape`` runs one join for each distinct rewritten body and multiplies its
label sets in from a literal array. ``closure`` (default) reads every rule that can yield an atom once, multiplies in
the label sets of all ways from the rule to the atom, and joins once for each query atom; only bodies that fold an
existential witness remain as branches. Its size is a sum over atoms where unfolding's is a product. The last two join
over key columns at the idempotent level.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable, Iterable
from dataclasses import dataclass
from itertools import product as cartesian

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from derivatrace.operators.joins import joined
from derivatrace.operators.keyed import Apart, apart_terms
from derivatrace.functions.monomials import mul, mul_idem, power, within
from derivatrace.plans.cq import BLANK, CQ, canonical, is_standard
from derivatrace.plans.instance import Bind, Instance, union
from derivatrace.plans.mapping import Rule, irredundant
from derivatrace.plans.ontology import Axiom, Ontology
from derivatrace.plans.rewrite import atom_closure, by_shape, contained, foldings, pruned, rewrite_compute, rewrite_literal, tagged_foldings


def _named(df: DataFrame, args: tuple, i: int, labels: bool) -> DataFrame:
    """Columns named by the variables of the arguments; constants, and repeated variables, as filters."""
    seen: dict[str, str] = {}
    for k, (kind, name) in enumerate(args):
        if kind == "c":
            df = df.where(F.col(f"a{k}") == name)
        elif kind != "b":
            if name in seen:
                df = df.where(F.col(f"a{k}") == F.col(seen[name]))
            else:
                seen[name] = f"a{k}"
    return df.select(*[F.col(c).alias(v) for v, c in seen.items()], *[F.col("mono").alias(f"_m{i}")] * labels)


def _join_order(rows: Iterable[tuple]) -> list[tuple[int, tuple]]:
    """Atoms so that each shares a variable with those before where it can; constants first, then roles before concepts.

    A concept atom over a variable that a role atom has filters only: as a later semi-join it multiplies nothing.
    """
    rest = sorted(enumerate(rows), key=lambda r: (-sum(t[0] == "c" for t in r[1][1]), -len(r[1][1]), r[0]))
    out, bound = [], set()
    while rest:
        pick = next((r for r in rest if bound & {t for t in r[1][1] if t[0] in "hv"}), rest[0])
        rest.remove(pick)
        out.append(pick)
        bound |= {t for t in pick[1][1] if t[0] in "hv"}
    return out


def join_atoms(rows: Iterable[tuple], frame: Callable[[int, str, tuple], DataFrame], head: Iterable[str], labels: bool = True) -> DataFrame:
    """One frame for a body: equi-joins on shared variables. frame(i, pred, args) has a0, [a1,] [mono].

    Without labels an atom that only filters is a semi-join, and projections and derived facts are made distinct early.
    """
    ordered = _join_order(rows)
    wanted = set(head)
    out: DataFrame | None = None
    for n, (i, row) in enumerate(ordered):
        df = _named(frame(i, row[0], row[1]), row[1], i, labels)
        later = {t[1] for _, r in ordered[n + 1 :] for t in r[1] if t[0] in "hv"}
        if out is None:
            out = df if labels else df.distinct()
        else:
            shared = [c for c in df.columns if c in out.columns]
            new = set(df.columns) - set(shared)
            if not labels and not new & (wanted | later):
                out = out.join(df, shared, "left_semi") if shared else out.join(F.broadcast(df.limit(1).select(F.lit(1).alias("_one"))), how="cross").drop("_one")
            else:
                # Without a shared variable the body is a product of two independent questions by its meaning.
                df = df if labels else df.distinct()
                out = out.join(df, shared) if shared else out.crossJoin(df)
        keep = [c for c in out.columns if c in wanted | later or c.startswith("_m")]
        dropped = len(keep) < len(out.columns)
        out = out.select(*keep)
        if not labels and dropped and n < len(ordered) - 1 and keep:
            out = out.distinct()
    return out


def _multiply(df: DataFrame, label_sets: list[tuple[str, ...]], instance: Instance, general: bool) -> tuple[DataFrame, list[Column]]:
    """The literal label sets of a body: one is a constant, several are exploded from a literal array."""
    sets = sorted(set(label_sets))
    if sets == [()]:
        return df, []
    if len(sets) == 1:
        return df, [_constant(instance, sets[0], general)]
    return df.withColumn("_acc", F.explode(F.array(*[_constant(instance, s, general) for s in sets]))), [F.col("_acc")]


def _constant(instance: Instance, labels: tuple[str, ...], general: bool) -> Column:
    if not general or len(labels) == len(set(labels)):
        return instance.constant(labels)
    return mul(*[instance.constant([x]) for x in labels])


def _finish(df: DataFrame, head: tuple[str, ...], monos: list[Column], general: bool, keep_within: Column | None = None) -> DataFrame:
    mono = (mul if general else mul_idem)(*monos)
    df = df.select(*head, mono.alias("mono"))
    return df if keep_within is None else df.where(within(F.col("mono"), keep_within))


def _empty(instance: Instance, head: tuple[str, ...]) -> DataFrame:
    kind = "bigint" if instance.hashed else "string"
    return instance.spark.createDataFrame([], ", ".join([*[f"{h} string" for h in head], f"mono array<{kind}>"]))


def atom_facts(instance: Instance, pred: str, args: tuple, *, level: str = "idempotent", labels: bool = True, only: Column | None = None, bind: Bind | None = None, among: Iterable[tuple] | None = None) -> DataFrame:
    """closure form of one atom: all facts that yield it, each rule read once for all its ways.

    Rules over one table with equal heads share a scan. among: facts of these yielding atoms only.
    """
    frames: list[tuple[tuple, DataFrame]] = []
    shared: dict[tuple, list] = {}
    reached = {at: ways for at, ways in sorted(atom_closure(pred, args, list(instance.ontology.positive)).items()) if among is None or at in among}
    rules = {(p, q): instance.rules_for(p, q, bind) for p, q in reached}
    if not labels:
        kept = {q: set(map(id, irredundant([r for (_, other), found in rules.items() if other == q for r in found]))) for _, q in reached}
        rules = {at: [r for r in found if id(r) in kept[at[1]]] for at, found in rules.items()}
    for (p, q), ways in reached.items():
        alone = []
        for r in rules[p, q]:
            if r.body.single:
                shared.setdefault((q, r.body.single[0], r.head), []).append((r, sorted(ways)))
            else:
                alone.append(instance.rule_facts(r, q, level=level, labels=labels, bind=bind))
        if (given := instance.given_facts(p, q, labels, bind)) is not None:
            alone.append(given)
        for df in alone:
            if labels:
                df, more = _multiply(df, sorted(ways), instance, False)
                df = df.withColumn("mono", mul_idem(F.col("mono"), *more)) if more else df
            frames.append((q, df))
    frames += [(q, instance.shared_scan(group, q, labels=labels, bind=bind)) for (q, _, _), group in shared.items()]
    out = []
    for q, df in frames:
        if labels and only is not None:
            df = df.where(within(F.col("mono"), only))
        for k, t in enumerate(q):  # a repeated variable of the atom, seen through a swap
            if t[0] in "hv" and t in q[:k]:
                df = df.where(F.col(f"a{q.index(t)}") == F.col(f"a{k}"))
        # The atom's own arguments in terms of the yielding fact's.
        at = [next((i for i, t in enumerate(q) if t == a and t[0] != "b"), None) for a in args]
        cols = [(F.lit(None).cast("string") if i is None else F.col(f"a{i}")).alias(f"a{n}") for n, i in enumerate(at)]
        out.append(df.select(*cols, *["mono"] * labels))
    return union(out) if out else instance.empty(len(args), labels)


def _closure_form(instance: Instance, cq: CQ, head, only, bind) -> list[DataFrame]:
    out = []
    for body, label_sets in sorted(foldings(cq, instance.ontology.positive).items()):
        if only is None:
            out.append(joined(instance, list(body), head, order=_join_order, bind=bind, extra=sorted(label_sets)))
            continue
        df = join_atoms(body, lambda i, p, q: atom_facts(instance, p, q, only=only, bind=bind), head)
        df, more = _multiply(df, sorted(label_sets), instance, False)
        out.append(_finish(df, head, [*[F.col(f"_m{i}") for i in range(len(body))], *more], False, only))
    return [df for df in out if df is not None]


def _shape_form(instance: Instance, cq: CQ, head, only, level, max_degree) -> list[DataFrame]:
    general, out = level == "general", []
    own = instance.with_ontology(Ontology())
    for body, label_sets in by_shape(rewrite_compute(cq, instance.ontology.positive, level=level, max_degree=max_degree)).items():
        if not general and only is None:
            df = joined(own, [(p, q) for p, q, _ in body], head, order=_join_order, extra=sorted(label_sets))
            out += [] if df is None else [df]
            continue
        if any(not instance.branches(p, q) for p, q, _ in body):
            continue
        df = join_atoms(body, lambda i, p, q: instance.facts(p, len(q), level=level, args=q), head)
        df, more = _multiply(df, label_sets, instance, general)
        out.append(_finish(df, head, [*[power(F.col(f"_m{i}"), body[i][2]) for i in range(len(body))], *more], general, only))
    return out


@dataclass
class UnionPlan:
    """Branches of an unfolding: (rewritten body, label set, a rule for each atom)."""

    cq: CQ
    branches: list[tuple[tuple, tuple[str, ...], tuple]]

    @property
    def unions(self) -> int:
        """UNION operators of the plan: branches less one."""
        return max(0, len(self.branches) - 1)


def unfold(instance: Instance, cq: CQ, *, optimise: str = "none", prune_templates: bool = True) -> UnionPlan:
    """The union that a rewriting engine runs.

    optimise: ``none``; ``safe`` leaves out branches that another one repeats (same atoms, rules and labels in another
    order), which no label can tell apart; ``certain`` also drops labels, contained bodies, and branches whose reading of
    the tables another branch contains, as plain answers allow.
    prune_templates leaves out branches whose constants, or whose joins of individuals, no template can make.
    """
    found = rewrite_compute(cq, instance.ontology.positive)
    if optimise == "certain":
        bodies = pruned({tuple((p, q) for p, q, _ in r.atoms) for r in found})
        states = [(tuple((p, q, 1) for p, q in b), ()) for b in bodies]
    else:
        states = [(r.atoms, r.labels) for r in found]
    branches = []
    for body, labels in states:
        for rules in cartesian(*[instance.rules_for(p, q if prune_templates else None) for p, q, _ in body]):
            if prune_templates and not _joinable(body, rules):
                continue
            branches.append((body, labels, rules))
    if optimise == "certain":
        branches = _uncontained(branches)
    if optimise == "safe":
        seen: dict[tuple, tuple] = {}
        for body, labels, rules in branches:
            key = canonical((p, q, e, r.name, r.body.key) for (p, q, e), r in zip(body, rules, strict=True)), labels
            seen.setdefault(key, (body, labels, rules))
        branches = list(seen.values())
    return UnionPlan(cq, branches)


def _over_tables(body, rules: tuple[Rule, ...]) -> tuple:
    """A branch as (table, terms of its columns) rows; key columns of an individual are terms made from its term."""
    used: dict[str, set[str]] = {}
    for r in rules:
        for a in r.body.atoms:
            used.setdefault(a.table, set()).update(a.columns, a.constants)
    rows = []
    for k, ((_, args, _), r) in enumerate(zip(body, rules, strict=True)):
        known: dict[str, tuple] = {}
        for (kind, name), t in zip(args, r.head, strict=True):
            keys = name.partition("/")[2].split("-") if kind == "c" else []
            for i, c in enumerate(t.columns):
                if kind in "hv":
                    known[c] = (kind, f"{name}/{t.prefix}/{i}")
                elif kind == "c":
                    known[c] = ("c", keys[i] if len(keys) == len(t.columns) else name)
        term = lambda v, k=k, known=known: known.get(v, ("v", f"_{k}.{v}"))
        if not r.body.atoms:
            rows.append((f"!{r.name}", tuple(term(c) for t in r.head for c in t.columns)))
        for a in r.body.atoms:
            rows.append((a.table, tuple((c, ("c", repr(a.constants[c])) if c in a.constants else term(a.columns[c]) if c in a.columns else BLANK) for c in sorted(used[a.table]))))
        if r.body.where:
            rows.append((f"?{r.body.where}", tuple(term(v) for v in sorted({v for a in r.body.atoms for v in a.columns.values()}))))
    return tuple(rows)


def _uncontained(branches: list) -> list:
    """Without branches that another one contains, over the tables; of equivalent ones the first stays."""
    columns: dict[str, list[str]] = {}
    read = [_over_tables(b, rules) for b, _, rules in branches]
    for rows in read:
        for table, terms in rows:
            if table[0] not in "!?":
                columns[table] = sorted({*columns.get(table, []), *(c for c, _ in terms)})
    flat = []
    for rows in read:
        uses = Counter(t for table, terms in rows for t in (terms if table[0] in "!?" else [x for _, x in terms]))
        term = lambda t, uses=uses: BLANK if t[0] == "v" and uses[t] == 1 else t
        flat.append(tuple((table, terms if table[0] in "!?" else tuple(term(dict(terms).get(c, BLANK)) for c in columns[table])) for table, terms in rows))
    kept: list[int] = []
    for i in sorted(range(len(flat)), key=lambda i: (len(flat[i]), i)):
        if not any(contained(flat[i], flat[k]) for k in kept):
            kept = [k for k in kept if not contained(flat[k], flat[i])] + [i]
    return [branches[i] for i in sorted(kept)]


def _joinable(body, rules) -> bool:
    """No variable is made by two different kinds of template."""
    kinds: dict = {}
    for (_, args, _), r in zip(body, rules, strict=True):
        for t, template in zip(args, r.head, strict=True):
            if t[0] in "hv" and kinds.setdefault(t, template.prefix) != template.prefix:
                return False
    return True


def _apart(instance: Instance, cq: CQ, level: str, reduce: str, physical: str, answers, only, bind) -> Apart | None:
    """The bodies of the shape or of the closure form, with the label sets that each is multiplied by, as terms over row keys."""
    if level != "idempotent" or reduce != "merge" or cq.where or not (answers is only is bind is None):
        return None
    if physical == "shape":
        over = instance.with_ontology(Ontology())
        bodies = {tuple((p, q) for p, q, _ in b): sets for b, sets in by_shape(rewrite_compute(cq, instance.ontology.positive)).items()}
    elif physical == "closure":
        over, bodies = instance, foldings(cq, instance.ontology.positive)
    else:
        return None
    terms = []
    for body, sets in sorted(bodies.items()):
        if (found := apart_terms(over, list(body), cq.head, order=_join_order, extra=sorted(sets))) is None:
            return None
        terms += found
    return Apart(terms, lambda: compute_provenance(instance, cq, physical=physical))


def _unfold_form(instance: Instance, cq: CQ, head, only, level, max_degree) -> list[DataFrame]:
    out = []
    for body, labels, rules in unfold(instance, cq).branches:
        df = join_atoms(body, lambda i, p, q, rules=rules: instance.rule_facts(rules[i], q), head)
        out.append(_finish(df, head, [*[F.col(f"_m{i}") for i in range(len(body))], *([instance.constant(labels)] if labels else [])], False, only))
    return out


def _literal_form(instance: Instance, cq: CQ, head, only) -> list[DataFrame]:
    out = []
    for body in rewrite_literal(cq, instance.ontology.positive):
        if any(not instance.branches(p, q) for p, q, _ in body):
            continue
        df = join_atoms([(p, q) for p, q, _ in body], lambda i, p, q: instance.facts(p, len(q), args=q), head)
        out.append(_finish(df, head, [*[F.col(f"_m{i}") for i in range(len(body))], instance.constant({x for _, _, m in body for x in m})], False, only))
    return out


def compute_provenance(instance: Instance, cq: CQ | list[CQ], *, level: str = "idempotent", reduce: str = "merge", physical: str = "closure", max_degree: int | None = None, answers: DataFrame | None = None, only: Iterable[str] | None = None, bind: Bind | None = None, apart: bool = False) -> DataFrame | Apart:
    """Answer columns and ``mono``, a row for each monomial of each answer; a list of queries is their union.

    level: ``idempotent``; ``mult_idempotent`` (adds ``coeff``, existential-free ontologies); ``general`` (needs max_degree).
    reduce: ``merge`` (complete) or ``equal`` (merges atoms of equal labels only). answers: only these answers (few).
    only: monomials within these labels, filtered at every atom. bind: constants that answer variables may be, which
    reach the scans as filters (closure form). apart: row keys and label sets instead, whose texts aren't made yet, where
    the shape or the closure form can keep them apart (``keyed.Apart``).
    """
    if apart and isinstance(cq, CQ) and is_standard(cq) and (found := _apart(instance, cq, level, reduce, physical, answers, only, bind)) is not None:
        return found
    if isinstance(cq, list):
        frames = [compute_provenance(instance, q, level=level, reduce=reduce, physical=physical, max_degree=max_degree, answers=answers, only=only, bind=bind) for q in cq]
        return frames[0] if len(frames) == 1 else union(frames).dropDuplicates()
    if not is_standard(cq):
        raise ValueError("monomials are fixed in the query: use select_by_provenance or entails")
    keep = None if only is None else instance.constant(only)
    if level == "mult_idempotent":
        from derivatrace.operators.bag import bag_provenance

        return bag_provenance(instance, cq)
    head = cq.head
    if level == "general":
        frames = [d.where(F.size("mono") <= max_degree) for d in _shape_form(instance, cq, head, keep, level, max_degree)]
    elif reduce == "equal":
        frames = _literal_form(instance, cq, head, keep)
    elif physical == "unfold":
        frames = _unfold_form(instance, cq, head, keep, level, max_degree)
    elif physical == "shape":
        frames = _shape_form(instance, cq, head, keep, level, max_degree)
    else:
        frames = _closure_form(instance, cq, head, keep, bind)
    out = union(frames) if frames else _empty(instance, head)
    if cq.where:
        out = out.where(cq.where)
    if answers is not None:
        out = out.join(answers.select(*head).distinct(), list(head), "left_semi")
    return out.dropDuplicates()


def constrained_bodies(cq: CQ, axioms: Iterable[Axiom]) -> set[tuple]:
    """Folded bodies of an annotated query, each row (pred, args, tag).

    The tag lists the query's atoms that carry a condition and whose fact this row's fact yields, each with the labels
    gathered on the way; atoms merged at a witness keep labels of their own, as they had ways of their own to it.
    """
    axioms = [a for a in axioms if not a.neg]
    fixed = {i: set(a.mono) for i, a in enumerate(cq.atoms) if isinstance(a.mono, tuple)}
    named = Counter(a.mono for a in cq.atoms if isinstance(a.mono, str))
    tags = [((i, ()),) if i in fixed or named.get(a.mono, 0) > 1 else () for i, a in enumerate(cq.atoms)]
    known: dict[tuple, list] = {}

    def ways(pred, args, tag):
        if (pred, args, tag) not in known:
            usable = [a for a in axioms if all(set(a.label) <= fixed[i] for i, _ in tag or () if i in fixed)]
            reached = atom_closure(pred, args, usable)
            known[pred, args, tag] = [(at, tuple((i, tuple(sorted({*x, *way}))) for i, x in tag)) for at, sets in reached.items() for way in sorted(sets)] if tag else [(at, tag) for at in reached]
        return known[pred, args, tag]

    return tagged_foldings(cq, tags, axioms, ways, lambda a, b: tuple(sorted([*a, *b])))


def select_by_provenance(instance: Instance, cq: CQ) -> DataFrame:
    """Answers of an annotated query: atoms with a given monomial, or with equal ones where they share a label variable.

    Idempotent level. Atoms may be matched at anonymous witnesses: the query is folded as in the computing task, with the
    labels of its conditions kept apart (``constrained_bodies``). A fixed monomial also filters the facts at the scan.
    A query without answer variables gives one row ``holds`` where it holds.
    """
    fixed = {i: a.mono for i, a in enumerate(cq.atoms) if isinstance(a.mono, tuple)}
    frames = []
    for body in sorted(constrained_bodies(cq, instance.ontology.positive)):

        def frame(k: int, pred: str, args: tuple, body=body) -> DataFrame:
            tag = body[k][2]
            if not tag:
                return atom_facts(instance, pred, args, labels=False).distinct().withColumn("mono", F.lit(None))
            asked = [(instance.constant(fixed[i]), x) for i, x in tag if i in fixed]
            df = atom_facts(instance, pred, args, only=asked[0][0] if asked else None)
            for whole, x in asked:
                df = df.where(mul_idem(F.col("mono"), instance.constant(x)) == whole)
            return df.dropDuplicates()

        out = join_atoms([(p, q) for p, q, _ in body], frame, cq.head)
        groups: dict[str, Column] = {}
        for k, (_, _, tag) in enumerate(body):
            for i, x in tag:
                if isinstance(name := cq.atoms[i].mono, str):
                    mono = mul_idem(F.col(f"_m{k}"), instance.constant(x))
                    out = out.where(groups[name] == mono) if name in groups else out
                    groups.setdefault(name, mono)
        out = out.select(*cq.head, *[F.lit(True).alias("holds")] * (not cq.head))
        frames.append(out.where(cq.where) if cq.where else out)
    return union(frames).distinct()


def provenance_on(cq: CQ, facts: dict[str, DataFrame], level: str = "idempotent") -> DataFrame:
    """Provenance over one finite labelled interpretation: sum over matches of the product of last terms."""
    general = level == "general"
    out = join_atoms([(a.pred, a.args) for a in cq.atoms], lambda i, p, q: facts[p], cq.head)
    return _finish(out, cq.head, [F.col(f"_m{i}") for i in range(len(cq.atoms))], general).dropDuplicates()


def certain_answers(instance: Instance, cq: CQ | list[CQ], *, physical: str = "closure", prune: bool = True, distinct: bool = True) -> DataFrame:
    """Plain answers, without labels: semi-joins for atoms that only filter, early distinct, contained branches dropped.

    distinct=False leaves repeated answers in, for who needs no more than some of them: shuffles of facts and answers are saved.
    """
    if isinstance(cq, list):
        out = union([certain_answers(instance, q, physical=physical, prune=prune, distinct=distinct) for q in cq])
        return out.distinct() if distinct else out
    if physical == "unfold":
        plan = unfold(instance, cq, optimise="certain" if prune else "none")
        frames = [join_atoms(b, lambda i, p, q, rules=rules: instance.rule_facts(rules[i], q, labels=False), cq.head, labels=False) for b, _, rules in plan.branches]
    else:
        bodies = [b for b in foldings(cq, instance.ontology.positive)]
        bodies = pruned(bodies) if prune else bodies
        frames = [df for b in bodies if (df := joined(instance, list(b), cq.head, order=_join_order, labels=False, early=distinct)) is not None]
    if not frames:
        return _empty(instance, cq.head).drop("mono") if cq.head else instance.spark.createDataFrame([], "holds boolean")
    out = union([f.select(*cq.head) if cq.head else f.limit(1).select(F.lit(True).alias("holds")) for f in frames])
    if cq.where:
        out = out.where(cq.where)
    return out.distinct() if distinct else out
