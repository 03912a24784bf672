"""The decision task: does the instance entail a query with a given polynomial?

A polynomial is a list of monomials. For each of them the query's atoms get sub-monomials whose product it is; the copies
for different monomials share no variable, so each is decided by itself. A copy is rewritten by consuming labels, and
all members of all its rewritings are matched in one plan against the derived facts whose monomials are asked for.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterable, Iterator
from itertools import combinations
from itertools import product as cartesian

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from derivatrace.functions.monomials import within
from derivatrace.operators.bag import MultiplicityUndecidedHere, bag_provenance
from derivatrace.operators.provenance import compute_provenance, join_atoms
from derivatrace.plans.cq import CQ, Atom
from derivatrace.plans.instance import Instance, union
from derivatrace.plans.mapping import Rule
from derivatrace.plans.ontology import Some
from derivatrace.plans.rewrite import rewrite_decide

Monomial = tuple[str, ...]


def split_assignments(cq: CQ, mono: Iterable[str], level: str = "general", parts: list[list[Monomial]] | None = None) -> Iterator[CQ]:
    """The annotated copies of the query for one monomial.

    general: every occurrence of a label goes to one atom. idempotent: every label goes to one atom or more. An atom
    needs a label at least, as every fact has one. parts: the sub-monomials that each atom may get (``possible_parts``);
    without it all of them are tried, as the set that the theorem speaks of has them.
    """
    mono = tuple(sorted(mono)) if level == "general" else tuple(sorted(set(mono)))
    if parts is None:
        parts = [sorted({c for n in range(1, len(mono) + 1) for c in combinations(mono, n)})] * len(cq.atoms)
    whole = Counter(mono)
    # What the atoms from a place on can still bring in.
    later = [Counter() for _ in range(len(parts) + 1)]
    for j in range(len(parts) - 1, -1, -1):
        most = Counter()
        for p in parts[j]:
            most |= Counter(p)
        later[j] = later[j + 1] + most

    def choose(j: int, left: Counter, chosen: tuple) -> Iterator[tuple]:
        if left - later[j]:
            return
        if j == len(parts):
            yield chosen
            return
        for p in parts[j]:
            used = Counter(p)
            if level != "general":
                yield from choose(j + 1, left - used, (*chosen, p))
            elif not used - left:
                yield from choose(j + 1, left - used, (*chosen, p))

    for key in choose(0, whole, ()):
        yield CQ((), tuple(Atom(a.pred, tuple(("v", t[1]) if t[0] == "h" else t for t in a.args), p) for a, p in zip(cq.atoms, key, strict=True)))


def possible_parts(instance: Instance, pred: str, mono: Iterable[str], level: str = "general") -> list[Monomial]:
    """The sub-monomials that an atom of the predicate may take part with: a fact's monomial and labels of inclusions.

    Facts come from predicates that inclusions with labels of the monomial lead to; a rule's fact has the rule's labels
    and a row label for each of its table atoms, told by the tables' label prefixes.
    """
    whole = Counter(mono)
    if level != "general":
        whole = Counter(set(whole))
    preds, ways = {pred}, set()
    while more := [a for a in instance.ontology.positive if set(a.label) <= set(whole) and _name(a.rhs) in preds and (_name(a.lhs) not in preds or not set(a.label) <= ways)]:
        preds |= {_name(a.lhs) for a in more}
        ways |= {x for a in more for x in a.label}
    facts: set[Monomial] = set()
    for r in instance.rules:
        if r.pred in preds and set(r.label) <= set(whole):
            facts |= _fact_monomials(instance, r, whole, level)
    for name in sorted(preds & set(instance.given)):
        lean = instance.given[name].select("mono")
        facts |= {tuple(sorted(x[0])) for x in lean.where(within(F.col("mono"), instance.constant(set(whole)))).distinct().collect()}  # at most all subsets of the labels asked for
    steps = sorted(x for x in whole.elements() if x in ways)
    sums = {c for n in range(len(steps) + 1) for c in combinations(steps, n)}
    join = (lambda f, s: tuple(sorted([*f, *s]))) if level == "general" else (lambda f, s: tuple(sorted({*f, *s})))
    return sorted(p for p in {join(f, s) for f in facts for s in sums} if not Counter(p) - whole)


def _name(term) -> str:
    return term.role.name if isinstance(term, Some) else term.name


def _fact_monomials(instance: Instance, rule: Rule, whole: Counter, level: str) -> set[Monomial]:
    """Monomials within the whole that a fact of the rule could have."""
    named = sorted(whole)

    def of_table(table: str) -> list[str]:
        s = instance.sources[table]
        start_ = {"row": f"@{s.prefix}/", "relation": f"@{table}"}.get(s.policy, f"@{table}:" if s.policy.startswith("column:") else "")
        return [x for x in named if x.startswith(start_)]

    if rule.body.arrays:
        rows = [c for n in range(1, len(named) + 1) for c in combinations(named, n)]
    elif rule.body.atoms:
        rows = list(cartesian(*[of_table(a.table) for a in rule.body.atoms]))
    else:
        rows = list(cartesian(*[[x for x in named if x not in rule.label]] * len(rule.body.labels)))
    join = (lambda r: tuple(sorted([*rule.label, *r]))) if level == "general" else (lambda r: tuple(sorted({*rule.label, *r})))
    return {m for m in map(join, rows) if not Counter(m) - whole}


def translation(cq: CQ, poly: list[Monomial], level: str = "general") -> Iterator[CQ]:
    """One conjunction for each choice of copies, variables of different copies renamed apart; the set the theorem speaks of."""
    for choice in cartesian(*[list(split_assignments(cq, m, level)) for m in poly]):
        atoms = []
        for n, copy in enumerate(choice):
            atoms += [Atom(a.pred, tuple((k, f"{x}_{n}") if k == "v" else (k, x) for k, x in a.args), a.mono) for a in copy.atoms]
        yield CQ((), tuple(atoms))


def match(instance: Instance, bodies: Iterable[tuple], level: str = "general") -> DataFrame | None:
    """One frame that has a row where some body of (pred, args, mono) rows matches the derived facts; None: no body can."""
    frames = []
    for body in bodies:
        if not all(_possible(instance, *row) for row in body):
            continue

        def frame(i, pred, args, body=body):
            return instance.facts(pred, len(args), level=level, args=args).where(F.col("mono") == _literal(instance, body[i][2], level))

        rows = [(p, q) for p, q, _ in body]
        frames.append(join_atoms(rows, frame, ()).limit(1).select(F.lit(1).alias("one")))
    return union(frames) if frames else None


def _possible(instance: Instance, pred: str, args: tuple, mono: Monomial) -> bool:
    """Whether some fact could have this monomial: a given one, or one of a rule that can make these constants."""
    return pred in instance.given or any(tuple(sorted(mono)) in _fact_monomials(instance, r, Counter(mono), "general") or tuple(sorted(set(mono))) in _fact_monomials(instance, r, Counter(set(mono)), "idempotent") for r in instance.rules_for(pred, args) if set(r.label) <= set(mono))


def _literal(instance: Instance, mono: Monomial, level: str):
    if level == "general" and len(set(mono)) < len(mono):
        return F.array(*map(F.lit, sorted(mono)))
    return instance.constant(mono)


def entails(instance: Instance, cq: CQ, poly: list[Iterable[str]], *, level: str = "idempotent", method: str = "decide", multiplicity: bool = False, chunk: int = 40) -> bool:
    """Whether the Boolean query holds with (at least) this polynomial.

    method ``decide`` consumes labels; ``compute`` computes the polynomial within the labels asked for and tests
    containment (idempotent levels). Repeated monomials ask for as many matches: multiplicity, without existential heads.
    """
    wanted = [tuple(sorted(m)) if level == "general" else tuple(sorted(set(m))) for m in poly]
    if multiplicity and max(Counter(wanted).values(), default=0) > 1:
        if level == "general":
            raise MultiplicityUndecidedHere("coefficients are decided at the idempotent level only")
        have = {tuple(r["mono"]): r["coeff"] for r in bag_provenance(instance, cq).where(" or ".join(["false"] + [f"size(mono) = {len(m)}" for m in set(wanted)])).collect()}
        return all(have.get(m, 0) >= n for m, n in Counter(wanted).items())
    if method == "compute":
        return all(not compute_provenance(instance, cq, only=m).where(F.col("mono") == instance.constant(m)).isEmpty() for m in dict.fromkeys(wanted))
    fact_level = "general" if level == "general" else "idempotent"
    for mono in dict.fromkeys(wanted):
        bodies: dict[tuple, None] = {}
        parts = [possible_parts(instance, a.pred, mono, level) for a in cq.atoms]
        for copy in split_assignments(cq, mono, level, parts):
            bodies |= dict.fromkeys(rewrite_decide(copy, instance.ontology.positive, level=level))
        rest = list(bodies)
        for i in range(0, len(rest), chunk):  # one job for a chunk of members, ended by its first match
            found = match(instance, rest[i : i + chunk], fact_level)
            if found is not None and not found.isEmpty():
                break
        else:
            return False
    return True


def within_labels(poly: DataFrame, instance: Instance, labels: Iterable[str]) -> DataFrame:
    return poly.where(within(F.col("mono"), instance.constant(labels)))
