"""SQL for DuckDB, apart from the engine: derived facts by hand-written selects, closed under the inclusions by a
recursive query (a bounded universal model with witness terms), then the query as joins over the closed facts.

The engine rewrites queries; this saturates data. They share the fixture's texts and nothing else.
"""

from __future__ import annotations

from derivatrace.plans.cq import CQ
from derivatrace.plans.ontology import Axiom, Concept, Ontology, Role, Some

LI = "'li/'||l_orderkey||'-'||l_linenumber||'-'||l_partkey||'-'||l_suppkey"


def _facts() -> list[tuple[str, str, str, str, str]]:
    """(pred, label, select s, select o or NULL, "labels … FROM …")"""
    one = lambda pred, label, s, o, lab, source: (pred, label, s, o, f"[{lab}, '{label}'] AS m FROM {source}")
    cust, supp, part, order = "'cust/'||c_custkey", "'supp/'||s_suppkey", "'part/'||p_partkey", "'ord/'||o_orderkey"
    doc, ev, turn = "'doc/'||doc_id", "'ev/'||event_id", "'turn/'||conv_id||'-'||turn"
    at = lambda s: f"'@'||{s}"
    out = [
        one("Customer", "m01", cust, "NULL", at(cust), "customer"), one("basedIn", "m02", cust, "'nat/'||c_nationkey", at(cust), "customer"),
        one("Supplier", "m03", supp, "NULL", at(supp), "supplier"), one("basedIn", "m04", supp, "'nat/'||s_nationkey", at(supp), "supplier"),
        one("Nation", "m05", "'nat/'||n_nationkey", "NULL", "'@nat/'||n_nationkey", "nation"), one("partOfRegion", "m06", "'nat/'||n_nationkey", "'reg/'||n_regionkey", "'@nat/'||n_nationkey", "nation"),
        one("Region", "m07", "'reg/'||r_regionkey", "NULL", "'@reg/'||r_regionkey", "region"), one("Product", "m08", part, "NULL", at(part), "part"),
    ]
    out += [one(f"{t}Product", f"m09{x}", part, "NULL", at(part), f"part WHERE p_type = '{t.upper()}'") for x, t in zip("abcdef", ("Economy", "Small", "Promo", "Standard", "Medium", "Large"), strict=True)]
    out += [one(p, f"m10{x}", part, f"'{pre}/'||{c}", at(part), "part") for x, p, pre, c in (("a", "hasBrand", "brand", "p_brand"), ("b", "hasType", "type", "p_type"), ("c", "hasSize", "size", "p_size"), ("d", "named", "name", "p_name"))]
    out += [one("Order", "m11", order, "NULL", at(order), "orders"), one("placedBy", "m14", order, "'cust/'||o_custkey", at(order), "orders")]
    out += [one(f"{n}Order", f"m12{x}", order, "NULL", at(order), f"orders WHERE o_orderstatus = '{v}'") for x, n, v in (("a", "Open", "O"), ("b", "Fulfilled", "F"), ("c", "Pending", "P"))]
    out += [one(f"{n}Order", f"m13{x}", order, "NULL", at(order), f"orders WHERE o_orderpriority = '{v}'") for x, n, v in (("a", "Urgent", "1-URGENT"), ("b", "High", "2-HIGH"))]
    out += [one("hasLine", "m15", "'ord/'||l_orderkey", LI, at(LI), "lineitem"), one("lineProduct", "m16", LI, "'part/'||l_partkey", at(LI), "lineitem"), one("lineSupplier", "m17", LI, "'supp/'||l_suppkey", at(LI), "lineitem"), one("ReturnedLine", "m18", LI, "NULL", at(LI), "lineitem WHERE l_returnflag = 'R'")]
    two = f"{at(order)}, {at(LI)}"
    out += [one("bought", "m19", "'cust/'||o_custkey", "'part/'||l_partkey", two, "orders JOIN lineitem ON o_orderkey = l_orderkey"), one("suppliedTo", "m20", "'supp/'||l_suppkey", "'cust/'||o_custkey", two, "orders JOIN lineitem ON o_orderkey = l_orderkey")]
    out += [one("domesticDeal", "m21", cust, supp, f"{at(cust)}, {two}, {at(supp)}", "customer JOIN orders ON c_custkey = o_custkey JOIN lineitem ON o_orderkey = l_orderkey JOIN supplier ON l_suppkey = s_suppkey AND s_nationkey = c_nationkey")]
    out += [one("offers", "m22", "'supp/'||l_suppkey", "'part/'||l_partkey", at(LI), "lineitem")]
    out += [one(f"{t.title()}Event", f"m23{x}", ev, "NULL", at(ev), f"events WHERE event_type = '{t}'") for x, t in zip("abcde", ("click", "view", "purchase", "signup", "error"), strict=True)]
    out += [one("performedBy", "m24", ev, "'cust/'||user_id", at(ev), "events"), one("BigSpender", "m25", cust, "NULL", at(cust), "customer WHERE c_acctbal > 9000")]
    out += [one(f"{n}Doc", f"m26{x}", doc, "NULL", at(doc), f"documents WHERE lang = '{v}'") for x, n, v in (("a", "English", "en"), ("b", "French", "fr"), ("c", "German", "de"), ("d", "Spanish", "es"))]
    out += [one("fromSource", "m27", doc, "'src/'||source", at(doc), "documents"), one("GoodDoc", "m28a", doc, "NULL", "'@lab/'||doc_id", "labels WHERE quality = 1"), one("ToxicDoc", "m28b", doc, "NULL", "'@lab/'||doc_id", "labels WHERE toxic = 1")]
    out += [one("sameText", "m29", "'doc/'||a.doc_id", "'doc/'||b.doc_id", "'@doc/'||a.doc_id, '@doc/'||b.doc_id", "documents a JOIN documents b ON a.text = b.text AND a.doc_id < b.doc_id")]
    out += [one(f"{r.title()}Turn", f"m30{x}", turn, "NULL", at(turn), f"conversations WHERE role = '{r}'") for x, r in zip("abc", ("user", "assistant", "system"), strict=True)]
    out += [one("inConversation", "m31", turn, "'conv/'||conv_id", at(turn), "conversations")]
    out += [one("follows", "m32", "'turn/'||a.conv_id||'-'||a.turn", "'turn/'||b.conv_id||'-'||b.turn", "'@turn/'||a.conv_id||'-'||a.turn, '@turn/'||b.conv_id||'-'||b.turn", "conversations a JOIN conversations b ON a.conv_id = b.conv_id AND a.turn = b.turn + 1")]
    out += [one("Page", "m33a", "'page/'||page_id", "NULL", "'@page/'||page_id", "pages"), one("hostedOn", "m33b", "'page/'||page_id", "'host/'||regexp_extract(url, '^[a-z]+://([^/?#]+)', 1)", "'@page/'||page_id", "pages WHERE regexp_matches(url, '^[a-z]+://[^/?#]')")]
    out += [one("hasClass", "m34a", "'vec/'||vec_id", "'cls/'||label", "'@vec/'||vec_id", "embeddings")]
    near = "list_dot_product(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])) >= 0.4 * sqrt(list_dot_product(CAST(a.embedding AS DOUBLE[]), CAST(a.embedding AS DOUBLE[]))) * sqrt(list_dot_product(CAST(b.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])))"
    out += [one("similarTo", "m34b", "'vec/'||a.vec_id", "'vec/'||b.vec_id", "'@vec/'||a.vec_id, '@vec/'||b.vec_id", f"embeddings a JOIN embeddings b ON a.vec_id < b.vec_id AND {near}")]
    out += [one("quotes", "m35", "'doc/'||d.doc_id", "'item/'||i.item_id", "'@doc/'||d.doc_id, '@item/'||i.item_id", "documents d JOIN benchmark i ON contains(d.text, i.text)")]
    out += [("FrequentBuyer", "m36", "'cust/'||o_custkey", "NULL", "list_append(list_distinct(list('@ord/'||o_orderkey)), 'm36') AS m FROM orders GROUP BY o_custkey HAVING count(*) >= 15")]
    out += [one("Contact", "m37", cust, "NULL", at(cust), "customer WHERE c_mktsegment = 'BUILDING'"), one("Contact", "m37", "'cust/'||user_id", "NULL", at(ev), "events")]
    return out


FACTS = _facts()


def _names(a: Axiom) -> tuple[str, str]:
    return tuple(t.role.name if isinstance(t, Some) else t.name for t in (a.lhs, a.rhs))


def relevant(preds: set[str], ontology: Ontology) -> tuple[set[str], list[Axiom]]:
    """Names and inclusions from which facts of these predicates can come."""
    names, used = set(preds), []
    while more := [a for a in ontology.positive if a not in used and _names(a)[1] in names]:
        used += more
        names |= {_names(a)[0] for a in more}
    return names, [a for a in ontology.positive if a in used]


def closed(preds: set[str], ontology: Ontology, depth: int = 3, where: str | None = None, facts=None) -> str:
    """CTEs base and sat(pred, s, o, m): facts closed under the relevant inclusions, witnesses as ~<md5>."""
    names, axioms = relevant(preds, ontology)
    selects = [f"SELECT '{p}' AS pred, {s} AS s, CAST({o} AS VARCHAR) AS o, {rest}" for p, _, s, o, rest in (facts or FACTS) if p in names]
    base = "\n  UNION ALL ".join(f"({x})" for x in selects)
    text = f"base AS (SELECT DISTINCT pred, s, o, list_sort(list_distinct(m)) AS m FROM (\n  {base}\n  ) AS all_facts{f' WHERE {where}' if where else ''})"
    if not axioms:
        return text + ",\nsat AS (SELECT * FROM base)"

    def row(a: Axiom) -> str:
        kind = lambda t: "r" if isinstance(t, Role) else "c" if isinstance(t, Concept) else "e"
        inv = lambda t: str(t.inv if isinstance(t, Role) else t.role.inv if isinstance(t, Some) else False).lower()
        return f"('{kind(a.lhs)}', '{_names(a)[0]}', {inv(a.lhs)}, '{kind(a.rhs)}', '{_names(a)[1]}', {inv(a.rhs)}, '{a.label[0]}')"

    table = ",\n  ".join(map(row, axioms))
    x = "CASE WHEN lk = 'e' AND linv THEN f.o ELSE f.s END"
    witness = f"repeat('~', length({x}) - length(ltrim({x}, '~')) + 1) || md5({x} || '|' || label || '|' || f.pred || '|' || f.s || '|' || coalesce(f.o, '') || '|' || array_to_string(f.m, '*'))"
    return f"""ax(lk, lhs, linv, rk, rhs, rinv, label) AS (VALUES
  {table}),
{text},
sat(pred, s, o, m) AS (
  SELECT pred, s, o, m FROM base
  UNION
  SELECT rhs,
    CASE WHEN rk = 'c' THEN {x} WHEN rk = 'r' THEN CASE WHEN linv <> rinv THEN f.o ELSE f.s END WHEN rinv THEN {witness} ELSE {x} END,
    CASE WHEN rk = 'c' THEN NULL WHEN rk = 'r' THEN CASE WHEN linv <> rinv THEN f.s ELSE f.o END WHEN rinv THEN {x} ELSE {witness} END,
    list_sort(list_distinct(list_append(f.m, label)))
  FROM sat f JOIN ax ON f.pred = lhs
  WHERE rk <> 'e' OR length({x}) - length(ltrim({x}, '~')) < {depth})"""


def body(cq: CQ, table: str = "sat", distinct: bool = False) -> tuple[str, dict[str, str], str]:
    """FROM … WHERE …, the columns of the variables, and the union of the atoms' labels."""
    columns: dict[str, str] = {}
    conditions, source = [], []
    for i, a in enumerate(cq.atoms):
        source.append(f"{table} f{i}" if not distinct else f"(SELECT DISTINCT pred, s, o FROM {table}) f{i}")
        conditions.append(f"f{i}.pred = '{a.pred}'")
        for c, (kind, name) in zip(("s", "o"), a.args, strict=False):
            if kind == "c":
                conditions.append(f"f{i}.{c} = '{name}'")
            elif kind in "hv":
                if name in columns:
                    conditions.append(f"f{i}.{c} = {columns[name]}")
                else:
                    columns[name] = f"f{i}.{c}"
    conditions += [f"NOT starts_with({columns[h]}, '~')" for h in cq.head]
    monos = ", ".join(f"f{i}.m" for i in range(len(cq.atoms)))
    return f"FROM {', '.join(source)} WHERE {' AND '.join(conditions)}", columns, f"list_sort(list_distinct(flatten([{monos}])))"


def _where(cq: CQ) -> str:
    # The two filters of the mixes, said in DuckDB's words.
    return f" WHERE {cq.where}" if cq.where else ""


def certain(cqs: list[CQ], ontology: Ontology, depth: int = 3, facts=None) -> str:
    preds = {a.pred for q in cqs for a in q.atoms}
    parts = []
    for q in cqs:
        rest, columns, _ = body(q, distinct=True)
        heads = ", ".join(f"{columns[h]} AS {h}" for h in q.head) or "true AS holds"
        parts.append(f"SELECT * FROM (SELECT DISTINCT {heads} {rest}) t{_where(q)}")
    return f"WITH RECURSIVE {closed(preds, ontology, depth, facts=facts)}\n" + "\nUNION ".join(parts)


def provenance(cqs: list[CQ], ontology: Ontology, depth: int = 3, facts=None, tail: str = "SELECT * FROM poly") -> str:
    """Rows (answer…, mono as text)."""
    preds = {a.pred for q in cqs for a in q.atoms}
    parts = []
    for q in cqs:
        rest, columns, mono = body(q)
        heads = "".join(f"{columns[h]} AS {h}, " for h in q.head)
        parts.append(f"SELECT * FROM (SELECT DISTINCT {heads}array_to_string({mono}, '*') AS mono {rest}) t{_where(q)}")
    return f"WITH RECURSIVE {closed(preds, ontology, depth, facts=facts)},\npoly AS (\n" + "\nUNION ".join(parts) + f")\n{tail}"


def instantiated(cq: CQ, ontology: Ontology, depth: int = 3, n: int = 5, tail: str = "SELECT * FROM poly", facts=None) -> str:
    """The provenance of the n answers of least md5 of their text."""
    preds = {a.pred for a in cq.atoms}
    plain, columns, _ = body(cq, distinct=True)
    heads = ", ".join(f"{columns[h]} AS {h}" for h in cq.head)
    picked = f"picked AS (SELECT * FROM (SELECT DISTINCT {heads} {plain}) a ORDER BY md5(concat_ws('|', {', '.join(cq.head)})) LIMIT {n})"
    rest, columns, mono = body(cq)
    rest = rest.replace(" WHERE ", ", picked WHERE ", 1) + "".join(f" AND {columns[h]} = picked.{h}" for h in cq.head)
    select = "".join(f"picked.{h} AS {h}, " for h in cq.head)
    return f"WITH RECURSIVE {closed(preds, ontology, depth, facts=facts)},\n{picked},\npoly AS (SELECT DISTINCT {select}array_to_string({mono}, '*') AS mono {rest})\n{tail}"
