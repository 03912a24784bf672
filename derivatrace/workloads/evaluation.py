"""The deep mix's instance: the fixture with more ways to the same facts, as a real ontology and its mappings have them.

Sub-roles and sub-concepts over the same tables, each with several routes upwards, make unfoldings of hundreds of unions;
plain answers need none of them. Lines on clearance count as products and turns as texts, so that an answer's kind rules
branches out.
"""

from __future__ import annotations

from derivatrace.plans.mapping import Rule, parse_rule
from derivatrace.plans.ontology import Ontology
from derivatrace.workloads import fixture, oracles

_LINES = "orders(o_orderkey=ok, o_custkey=ck), lineitem(l_orderkey=ok, l_partkey=pk, l_suppkey=sk"
_LI = "li{l_orderkey}{l_linenumber}{l_partkey}{l_suppkey}"
_LI_KEYS = "l_orderkey, l_linenumber, l_partkey, l_suppkey"
#: Parts of deals: suffix, columns of lineitem, condition (the same in SQL).
_KINDS = (("InBulk", "l_quantity", "l_quantity > 45"), ("Returned", "l_returnflag", "l_returnflag = 'R'"), ("Discounted", "l_discount", "l_discount >= 0.09D"), ("Open", "l_linestatus", "l_linestatus = 'O'"))

RULES: tuple[Rule, ...] = tuple(
    map(
        parse_rule,
        [
            *[f"offers{n}(supp{{l_suppkey}}, part{{l_partkey}}) <- lineitem(l_suppkey, l_partkey, {c}) where {w} @m40{x}" for x, (n, c, w) in zip("abcd", _KINDS, strict=True)],
            *[f"bought{n}(cust{{ck}}, part{{pk}}) <- {_LINES}, {c}) where {w} @m41{x}" for x, (n, c, w) in zip("ab", _KINDS, strict=False)],
            *[f"supplied{n}(supp{{sk}}, cust{{ck}}) <- {_LINES}, {c}) where {w} @m42{x}" for x, (n, c, w) in zip("abcd", _KINDS, strict=True)],
            f"hasReturnedLine(ord{{l_orderkey}}, {_LI}) <- lineitem({_LI_KEYS}, l_returnflag='R') @m43",
            "LocalSupplier(supp{s_suppkey}) <- supplier(s_suppkey, s_nationkey) where s_nationkey < 10 @m44a",
            "RichSupplier(supp{s_suppkey}) <- supplier(s_suppkey, s_acctbal) where s_acctbal > 0 @m44b",
            "CheapProduct(part{p_partkey}) <- part(p_partkey, p_retailprice) where p_retailprice < 1200 @m45a",
            "TinyProduct(part{p_partkey}) <- part(p_partkey, p_size) where p_size <= 5 @m45b",
            f"ClearanceItem({_LI}) <- lineitem({_LI_KEYS}, l_returnflag, l_quantity) where l_returnflag = 'R' and l_quantity <= 2 @m46",
            f"hasBrand({_LI}, brand{{p_brand}}) <- lineitem({_LI_KEYS}, l_returnflag, l_quantity), part(p_partkey=l_partkey, p_brand) where l_returnflag = 'R' and l_quantity <= 2 @m47",
            "copyOf(doc{d1}, doc{d2}) <- documents(doc_id=d1, md5{text}=t, source=s1), documents(doc_id=d2, md5{text}=t, source=s2) where d1 < d2 and s1 <> s2 @m48",
            "PoorDoc(doc{doc_id}) <- labels(doc_id, quality=0) @m49",
            "ShortDoc(doc{doc_id}) <- documents(doc_id, n_chars) where n_chars < 500 @m50",
        ],
    )
)

_MORE = [
    *[f"{r}{n} <= {up} @{label}{x}" for x, (n, _, _) in zip("abcd", _KINDS, strict=True) for r, up, label in (("offers", "offers", "b01"), ("offers", "handles", "b02"), ("offers", "ships", "b03"), ("offers", "interactsWith", "b04"), ("supplied", "suppliedTo", "b05"), ("supplied", "tradesWith-", "b06"), ("supplied", "contracts-", "b07"))],
    "handles <= interactsWith @b08", "ships <= interactsWith @b09", "contracts <= tradesWith @b10", "domesticDeal <= contracts @b11",
    "boughtInBulk <= bought @b12a", "boughtReturned <= bought @b12b", "hasReturnedLine <= hasLine @b13",
    "Supplier <= Vendor @b14a", "LocalSupplier <= Vendor @b14b", "RichSupplier <= Vendor @b14c", "Vendor <= Party @b15",
    "CheapProduct <= BudgetProduct @b16", "TinyProduct <= SmallProduct @b17", "ClearanceItem <= BudgetProduct @b18a", "ClearanceItem <= EconomyProduct @b18b", "ClearanceItem <= SmallProduct @b18c",
    "PromoProduct <= FeaturedProduct @b19a", "FeaturedProduct <= MarketedProduct @b19b", "CheapProduct <= MarketedProduct @b19c", "TinyProduct <= MarketedProduct @b19d", "LargeProduct <= FeaturedProduct @b19e",
    "copyOf <= sameText @b20", "PoorDoc <= FlaggedDoc @b21", "ShortDoc <= Doc @b22", "exists fromSource <= Doc @b23",
    "Doc <= Writing @b24a", "Writing <= Text @b24b", "Doc <= Text @b24c", "Turn <= Text @b24d", "relatedDoc <= relatedText @b25a", "follows <= relatedText @b25b", "FlaggedDoc <= FlaggedText @b26a", "SystemTurn <= FlaggedText @b26b",
]
EVALUATION = Ontology(fixture.DEEP.axioms + Ontology.parse(_MORE).axioms)


def _facts() -> list[tuple[str, str, str, str, str]]:
    """The rules above as hand-written selects, in the oracle's form."""
    supp, cust, part, brand, li = "'supp/'||l_suppkey", "'cust/'||o_custkey", "'part/'||l_partkey", "'brand/'||p_brand", oracles.LI
    lines, at_order, at_line = "orders JOIN lineitem ON o_orderkey = l_orderkey", "'@ord/'||o_orderkey", f"'@'||{oracles.LI}"
    sql = lambda w: w.replace("0.09D", "CAST(0.09 AS DOUBLE)")
    out = [(f"offers{n}", f"m40{x}", supp, part, f"[{at_line}, 'm40{x}'] AS m FROM lineitem WHERE {sql(w)}") for x, (n, _, w) in zip("abcd", _KINDS, strict=True)]
    out += [(f"bought{n}", f"m41{x}", cust, part, f"[{at_order}, {at_line}, 'm41{x}'] AS m FROM {lines} WHERE {sql(w)}") for x, (n, _, w) in zip("ab", _KINDS, strict=False)]
    out += [(f"supplied{n}", f"m42{x}", supp, cust, f"[{at_order}, {at_line}, 'm42{x}'] AS m FROM {lines} WHERE {sql(w)}") for x, (n, _, w) in zip("abcd", _KINDS, strict=True)]
    clearance = "l_returnflag = 'R' AND l_quantity <= 2"
    one = lambda pred, label, s, o, rows, source: (pred, label, s, o, f"[{rows}, '{label}'] AS m FROM {source}")
    at_supp, at_part = "'@supp/'||s_suppkey", "'@part/'||p_partkey"
    out += [
        one("hasReturnedLine", "m43", "'ord/'||l_orderkey", li, at_line, "lineitem WHERE l_returnflag = 'R'"),
        one("LocalSupplier", "m44a", "'supp/'||s_suppkey", "NULL", at_supp, "supplier WHERE s_nationkey < 10"),
        one("RichSupplier", "m44b", "'supp/'||s_suppkey", "NULL", at_supp, "supplier WHERE s_acctbal > 0"),
        one("CheapProduct", "m45a", "'part/'||p_partkey", "NULL", at_part, "part WHERE p_retailprice < 1200"),
        one("TinyProduct", "m45b", "'part/'||p_partkey", "NULL", at_part, "part WHERE p_size <= 5"),
        one("ClearanceItem", "m46", li, "NULL", at_line, f"lineitem WHERE {clearance}"),
        one("hasBrand", "m47", li, brand, f"{at_line}, {at_part}", f"lineitem JOIN part ON p_partkey = l_partkey WHERE {clearance}"),
        one("copyOf", "m48", "'doc/'||a.doc_id", "'doc/'||b.doc_id", "'@doc/'||a.doc_id, '@doc/'||b.doc_id", "documents a JOIN documents b ON a.text = b.text AND a.doc_id < b.doc_id AND a.source <> b.source"),
        one("PoorDoc", "m49", "'doc/'||doc_id", "NULL", "'@lab/'||doc_id", "labels WHERE quality = 0"),
        one("ShortDoc", "m50", "'doc/'||doc_id", "NULL", "'@doc/'||doc_id", "documents WHERE n_chars < 500"),
    ]
    return out


FACTS = [*oracles.FACTS, *_facts()]
