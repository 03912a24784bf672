"""Whether a query's polynomial is infinite at the general level.

It is where a cycle of inclusions with a label lies on the way from an atom, of the query or of a body that folds it at
witnesses, to facts that match the whole body: each turn adds the cycle's labels again. The number of atoms never
grows, so nothing else can go on for ever. Cycles and bodies are found on the driver; that facts match is one read that
ends at its first row.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

from derivatrace.operators.provenance import atom_facts, join_atoms
from derivatrace.plans.cq import CQ
from derivatrace.plans.instance import Instance
from derivatrace.plans.ontology import Axiom
from derivatrace.plans.rewrite import back, tagged_foldings

Node = tuple[str, tuple]


@dataclass(frozen=True)
class Finite:
    pass


@dataclass(frozen=True)
class Infinite:
    cycle: tuple[str, ...]


def pumped(start: Node, axioms: Iterable[Axiom]) -> tuple[set[Node], dict[Node, tuple[str, ...]]]:
    """The atoms that yield this one, and those of them that do so past a cycle with a label, with the cycle's labels."""
    axioms, after, work = list(axioms), {}, [start]
    while work:
        at = work.pop()
        if at not in after:
            after[at] = [(to, a.label) for a in axioms if (to := back(a, *at)) is not None]
            work += [to for to, _ in after[at]]
    beyond: dict[Node, tuple[str, ...]] = {}
    for at in sorted(after):
        if at not in beyond and (cycle := _turn(at, after)):
            work = [at]
            while work:
                n = work.pop()
                if n not in beyond:
                    beyond[n] = cycle
                    work += [to for to, _ in after[n]]
    return set(after), beyond


def _turn(at: Node, after: dict) -> tuple[str, ...]:
    """The labels of a shortest way from an atom back to itself that has a label; none: ()."""
    seen, work = set(), [(at, ())]
    for n, labels in work:
        for to, label in after[n]:
            more = (*labels, *label)
            if to == at and more:
                return more
            if (to, bool(more)) not in seen:
                seen.add((to, bool(more)))
                work.append((to, more))
    return ()


def pumping_bodies(cq: CQ, axioms: Iterable[Axiom]) -> Iterator[tuple[tuple[str, ...], list[tuple[Node, list[Node]]]]]:
    """(cycle's labels, body): a body is a list of (atom, yielding atoms that count); any match of it means infinity."""
    axioms = [a for a in axioms if not a.neg]
    known: dict[Node, tuple] = {}

    def reach(*node):
        if node not in known:
            known[node] = pumped(node, axioms)
        return known[node]

    def ways(pred, args, tag):
        every, beyond = reach(pred, args)
        return [(at, tag or beyond.get(at, ())) for at in every]

    for body in sorted(tagged_foldings(cq, [()] * len(cq.atoms), axioms, ways, lambda a, b: a or b)):
        whole = [((p, q), sorted(reach(p, q)[0])) for p, q, _ in body]
        if passed := next((t for _, _, t in body if t), None):
            yield passed, whole
            continue
        for i, (node, _) in enumerate(whole):
            beyond = reach(*node)[1]
            for cycle in sorted(set(beyond.values())):
                yield cycle, [*whole[:i], (node, sorted(n for n in beyond if beyond[n] == cycle)), *whole[i + 1 :]]


def finiteness(instance: Instance, cq: CQ) -> Finite | Infinite:
    """Finite, or the labels of a cycle that makes some answer's polynomial infinite."""
    for cycle, body in pumping_bodies(cq, instance.ontology.positive):
        if any(not any(instance.rules_for(*n) or n[0] in instance.given for n in nodes) for _, nodes in body):
            continue
        rows = [node for node, _ in body]
        out = join_atoms(rows, lambda i, p, q, body=body: atom_facts(instance, p, q, labels=False, among=body[i][1]), cq.head, labels=False)
        if not (out.where(cq.where) if cq.where else out).isEmpty():
            return Infinite(cycle)
    return Finite()
