"""Plain Python twins, independent of the engine: bounded chase, matching, and evaluation of rewritings over sets of facts.

A fact is (pred, args, mono); at the idempotent level mono is a frozenset, at the general level a sorted tuple.
"""

import random

from derivatrace.plans.cq import CQ, Atom
from derivatrace.plans.ontology import Axiom, Concept, Ontology, Role, Some


def chase(facts, ontology, depth, general=False, degree=None, most=4000):
    """Facts closed under the positive inclusions; a new witness for each fact and existential inclusion, depth levels deep.

    None where there would be more than ``most`` facts.
    """
    times = (lambda m, label: tuple(sorted([*m, *label]))) if general else (lambda m, label: m | set(label))
    done, level = set(facts), {}
    work = list(done)
    while work:
        pred, args, mono = work.pop()
        if len(done) > most:
            return None
        for ax in ontology.positive:
            for to in consequences(ax, pred, args, mono, level, depth):
                new = (*to, times(mono, ax.label))
                if (degree is None or len(new[2]) <= degree) and new not in done:
                    done.add(new)
                    work.append(new)
    return done


def consequences(ax, pred, args, mono, level, depth):
    if isinstance(ax.lhs, Role):
        if ax.lhs.name != pred or len(args) != 2:
            return []
        pair = args[::-1] if ax.lhs.inv != ax.rhs.inv else args
        return [(ax.rhs.name, pair)]
    if isinstance(ax.lhs, Concept):
        if ax.lhs.name != pred or len(args) != 1:
            return []
        x = args[0]
    else:
        if ax.lhs.role.name != pred or len(args) != 2:
            return []
        x = args[1] if ax.lhs.role.inv else args[0]
    if isinstance(ax.rhs, Concept):
        return [(ax.rhs.name, (x,))]
    if level.get(x, 0) >= depth:
        return []
    w = ("witness", x, str(ax), mono, pred, args)
    level[w] = level.get(x, 0) + 1
    role = ax.rhs.role
    return [(role.name, (w, x) if role.inv else (x, w))]


def matches(atoms, facts):
    """All (bindings, monomials of the atoms) of a body of (pred, args) rows; bound arguments are looked up."""
    by = {}
    for p, a, m in facts:
        by.setdefault((p, len(a), None, None), []).append((a, m))
        for i, v in enumerate(a):
            by.setdefault((p, len(a), i, v), []).append((a, m))
    out, rest = [({}, ())], list(enumerate(atoms))
    bound = set()
    while rest:
        pick = next((r for r in rest if any(t[0] == "c" or t in bound for t in r[1][1])), rest[0])
        rest.remove(pick)
        n, (pred, args) = pick
        nxt = []
        for env, monos in out:
            at = next(((i, t[1] if t[0] == "c" else env[t[1]]) for i, t in enumerate(args) if t[0] == "c" or t[0] != "b" and t[1] in env), (None, None))
            for a, m in by.get((pred, len(args), *at), ()):
                e = dict(env)
                for t, v in zip(args, a, strict=True):
                    if t[0] == "c":
                        if v != t[1]:
                            break
                    elif t[0] != "b" and e.setdefault(t[1], v) != v:
                        break
                else:
                    nxt.append((e, (*monos, (n, m))))
        out = nxt
        bound |= {t for t in args if t[0] in "hv"}
    return [(e, tuple(m for _, m in sorted(ms, key=lambda x: x[0]))) for e, ms in out]


def answers(cq, facts, general=False):
    """{(answer, mono)} of a query over facts; answers are known individuals only."""
    out = set()
    for env, monos in matches([(a.pred, a.args) for a in cq.atoms], facts):
        row = tuple(env[h] for h in cq.head)
        if all(isinstance(x, str) for x in row):
            out.add((row, tuple(sorted(x for m in monos for x in m)) if general else frozenset().union(*monos)))
    return out


NAMES = ("A", "B", "C"), ("p", "q"), ("a", "b", "c")


def random_instance(rng: random.Random, axioms=3, atoms=3, facts=4):
    concepts, roles, people = NAMES

    def basic():
        return Concept(rng.choice(concepts)) if rng.random() < 0.5 else Some(Role(rng.choice(roles), rng.random() < 0.4))

    made = []
    for i in range(rng.randint(1, axioms)):
        if rng.random() < 0.3:
            made.append(Axiom(Role(rng.choice(roles), rng.random() < 0.4), Role(rng.choice(roles), rng.random() < 0.4), (f"s{i}",)))
        else:
            made.append(Axiom(basic(), basic(), (f"s{i}",)))
    base = set()
    for i in range(rng.randint(1, facts)):
        if rng.random() < 0.5:
            base.add((rng.choice(concepts), (rng.choice(people),), frozenset([f"u{i}"])))
        else:
            base.add((rng.choice(roles), (rng.choice(people), rng.choice(people)), frozenset([f"u{i}"])))
    n = rng.randint(1, atoms)
    variables = ["x", "y", "z"][: rng.randint(1, 3)]
    body = [Atom(rng.choice(concepts), (("v", rng.choice(variables)),)) if rng.random() < 0.4 else Atom(rng.choice(roles), (("v", rng.choice(variables)), ("v", rng.choice(variables)))) for _ in range(n)]
    used = sorted({t[1] for a in body for t in a.args})
    head = tuple(v for v in used if rng.random() < 0.3)
    body = tuple(Atom(a.pred, tuple(("h" if t[1] in head else "v", t[1]) for t in a.args)) for a in body)
    return Ontology(tuple(made)), base, CQ(head, body)
