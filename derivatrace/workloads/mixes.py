"""The two query mixes: nine parametric queries without an ontology, and twelve over the deep one."""

from __future__ import annotations

from dataclasses import dataclass

from derivatrace.plans.cq import CQ, parse_cq

FLAT: dict[str, list[CQ]] = {
    "F1": [parse_cq("q(p) :- Product(p), hasType(p, 'type/PROMO'), hasBrand(p, 'brand/Brand#4')")],
    "F2": [parse_cq("q(b, s, n) :- hasBrand('part/0', b), offers(s, 'part/0'), basedIn(s, n)")],
    "F3": [parse_cq("q(p, z) :- hasType(p, 'type/PROMO'), hasSize(p, z)", where="cast(substring(z, 6) as int) > 40")],
    "F4": [parse_cq(f"q(p) :- hasType(p, 'type/{t}'), hasBrand(p, 'brand/Brand#4')") for t in ("ECONOMY", "SMALL")],
    "F5": [parse_cq("q(p) :- hasBrand('part/0', b), hasBrand(p, b), hasSize('part/0', z), hasSize(p, z)")],
    "F6": [parse_cq("q(p, w) :- Product(p), named(p, w)", where="contains(w, 'ring')")],
    "F7": [parse_cq("q(s, n, c) :- offers(s, 'part/0'), basedIn(s, n), bought(c, 'part/0')")],
    "F8": [parse_cq("q(d) :- fromSource(d, 'src/src5'), EnglishDoc(d), GoodDoc(d)")],
    "F9": [parse_cq("q(o, l, p) :- placedBy(o, 'cust/0'), hasLine(o, l), lineProduct(l, p)")],
}


@dataclass(frozen=True)
class Deep:
    cq: CQ
    #: Whether the whole polynomial is of a size to return; else it is asked answer by answer.
    full: bool


DEEP: dict[str, Deep] = {
    "D01": Deep(parse_cq("q(x) :- interactsWith(x, p), Supplier(x)"), True),
    "D02": Deep(parse_cq("q(o) :- PriorityOrder(o), placedBy(o, c), basedIn(c, n)"), False),
    "D03": Deep(parse_cq("q(x) :- Vendor(x), basedIn(x, n), partOfRegion(n, r)"), False),
    "D04": Deep(parse_cq("q(c, s) :- tradesWith(c, s), basedIn(c, n), basedIn(s, n)"), False),
    "D05": Deep(parse_cq("q(r) :- Region(r), partOfRegion('nat/0', r)"), True),
    "D06": Deep(parse_cq("q(x, y) :- interactsWith(x, p), bought(y, p), Party(y)"), False),
    "D07": Deep(parse_cq("q() :- Supplier('supp/0')"), True),
    "D09": Deep(parse_cq("q(p) :- Product(p), hasBrand(p, b), BudgetProduct(p)"), True),
    "D10": Deep(parse_cq("q(e) :- Interaction(e), performedBy(e, c), BigSpender(c)"), True),
    "D11": Deep(parse_cq("q(o) :- Order(o), placedBy(o, c), hasLine(o, l), ProblemLine(l)"), False),
    "D12": Deep(parse_cq("q(o, p) :- Order(o), hasLine(o, l), lineProduct(l, p), MarketedProduct(p)"), False),
    "D31": Deep(parse_cq("q(d, e) :- relatedText(d, e), FlaggedText(e), Text(d)"), True),
}
