"""The rules and inclusions over the given tables, as FIXTURES.md lists them; variants ``flat``, ``acyclic`` and ``deep``."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from derivatrace.plans.instance import Instance, Source
from derivatrace.plans.mapping import Body, Rule, TableAtom, Template, conjunctive
from derivatrace.plans.ontology import Ontology
from derivatrace.sources.tables import load

LINE = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
#: Tables whose label keys tell rows apart (lineitem's repeat at times; documents and labels aren't promised to).
UNIQUE = ("region", "nation", "customer", "supplier", "part", "orders", "events", "embeddings", "pages", "benchmark", "conversations")
SOURCES = {
    s.table: replace(s, unique=s.table in UNIQUE)
    for s in (
        Source("region", "reg", ("r_regionkey",)), Source("nation", "nat", ("n_nationkey",)), Source("customer", "cust", ("c_custkey",)), Source("supplier", "supp", ("s_suppkey",)),
        Source("part", "part", ("p_partkey",)), Source("orders", "ord", ("o_orderkey",)), Source("lineitem", "li", LINE), Source("events", "ev", ("event_id",)), Source("documents", "doc", ("doc_id",)),
        Source("labels", "lab", ("doc_id",)), Source("embeddings", "vec", ("vec_id",)), Source("pages", "page", ("page_id",)), Source("benchmark", "item", ("item_id",)), Source("conversations", "turn", ("conv_id", "turn")),
    )
}

AXIOMS = """
EconomyProduct <= BudgetProduct @a01
SmallProduct <= BudgetProduct @a02
BudgetProduct <= Product @a03
PromoProduct <= MarketedProduct @a04
MarketedProduct <= Product @a05
StandardProduct <= Product @a06a
MediumProduct <= Product @a06b
LargeProduct <= Product @a06c
UrgentOrder <= PriorityOrder @a07
HighOrder <= PriorityOrder @a08
PriorityOrder <= Order @a09
OpenOrder <= Order @a10a
FulfilledOrder <= Order @a10b
PendingOrder <= Order @a10c
Customer <= Party @a11
Supplier <= Party @a12
BigSpender <= Customer @a13
exists placedBy <= Order @a14
exists placedBy- <= Customer @a15
Order <= exists placedBy @a16
exists bought <= Customer @a17
exists bought- <= Product @a18
bought <= interactsWith @a19
offers <= interactsWith @a20
suppliedTo <= tradesWith- @a21
domesticDeal <= tradesWith @a22
domesticDeal <= suppliedTo- @a23
Party <= exists basedIn @a24
exists basedIn- <= Nation @a25
Nation <= exists partOfRegion @a26
exists partOfRegion- <= Region @a27
Nation <= Place @a28
Region <= Place @a29
ClickEvent <= Interaction @a30a
ViewEvent <= Interaction @a30b
PurchaseEvent <= Conversion @a31a
SignupEvent <= Conversion @a31b
Conversion <= Interaction @a32
exists performedBy- <= Customer @a33
ReturnedLine <= ProblemLine @a34
exists hasLine <= Order @a35
EnglishDoc <= Doc @a36a
FrenchDoc <= Doc @a36b
GermanDoc <= Doc @a36c
SpanishDoc <= Doc @a36d
GoodDoc <= Doc @a37
ToxicDoc <= FlaggedDoc @a38
FlaggedDoc <= Doc @a39
sameText <= relatedDoc @a40
sameText <= relatedDoc- @a41
exists quotes <= FlaggedDoc @a42
UserTurn <= Turn @a43a
AssistantTurn <= Turn @a43b
SystemTurn <= Turn @a43c
exists follows <= Turn @a44
exists follows- <= Turn @a45
Turn <= exists inConversation @a46
similarTo <= relatedVec @a47
similarTo <= relatedVec- @a48
Customer <= not Supplier @n01
Order <= not Product @n02
OpenOrder <= not FulfilledOrder @n03
bought <= not offers @n04
"""
DEEP = Ontology.parse(AXIOMS.splitlines())
#: Without existential heads.
ACYCLIC = DEEP.without("a16", "a24", "a26", "a46")
CONFLICT = Ontology.parse([*AXIOMS.splitlines(), "GoodDoc <= not ToxicDoc @n05"])


def _one(label: str, pred: str, table: str, *head: tuple[str, tuple[str, ...]], where: str | None = None, extra: tuple[str, ...] = (), **constants) -> Rule:
    """A rule over one table: the head's keys are its columns."""
    columns = {c: c for _, keys in head for c in keys} | {c: c for c in extra}
    atom = TableAtom(table, columns, constants)
    return Rule((label,), pred, tuple(Template(p, k) for p, k in head), conjunctive(label, atom, where=where))


_CUST, _SUPP, _PART, _ORD, _NAT = ("cust", ("c_custkey",)), ("supp", ("s_suppkey",)), ("part", ("p_partkey",)), ("ord", ("o_orderkey",)), ("nat", ("n_nationkey",))
_LI, _EV, _DOC, _TURN = ("li", LINE), ("ev", ("event_id",)), ("doc", ("doc_id",)), ("turn", ("conv_id", "turn"))


def _joined(label: str, pred: str, head: tuple[Template, ...], *atoms: TableAtom, where: str | None = None) -> Rule:
    return Rule((label,), pred, head, conjunctive(label, *atoms, where=where))


def _turns(instance: Instance) -> DataFrame:
    rows = instance.labelled("conversations").select("conv_id", "turn", "_label")
    before = rows.select("conv_id", (F.col("turn") + 1).alias("turn"), F.col("turn").alias("t0"), F.col("_label").alias("_l1"))
    return rows.withColumnRenamed("_label", "_l0").join(before, ["conv_id", "turn"])


def _hosts(instance: Instance) -> DataFrame:
    host = F.regexp_extract("url", "^[a-z]+://([^/?#]+)", 1)
    return instance.labelled("pages").select("page_id", F.when(host != "", host).alias("host"), F.col("_label").alias("_l0"))


#: Least cosine of similar vectors.
NEAR = 0.4
#: Words of the seed by which a quoted item is looked for.
SEED = 5


#: Vectors in a tile, and how far below ``NEAR`` single precision may put a pair that is near.
TILE, SLACK = 4096, 1e-4


def _unit(v, norm):
    """Vectors of length one in single precision."""
    return (v / norm[:, None]).astype("float32")


def _packed(batches):
    """Vectors of equal size as tiles: a row holds ids, labels and the numbers of up to ``TILE`` vectors."""
    import uuid

    import pyarrow as pa

    for batch in batches:
        table = pa.Table.from_batches([batch])
        for size in table["size"].unique().to_pylist():
            own = table.filter(pa.compute.equal(table["size"], size)).combine_chunks()
            for at in range(0, own.num_rows, TILE):
                part = own.slice(at, TILE)
                one = {"tile": [uuid.uuid4().hex], "size": [size], "ids": [part["vec_id"].to_pylist()], "labels": [part["_label"].to_pylist()]}
                flat = pa.compute.list_flatten(part["v"]).to_numpy(zero_copy_only=False).astype("float64")
                label = pa.list_(part.schema.field("_label").type)
                yield pa.record_batch([pa.array(one["tile"]), pa.array(one["size"], pa.int32()), pa.array(one["ids"], pa.list_(pa.int64())), pa.array(one["labels"], label), pa.array([flat.tobytes()], pa.binary())], ["tile", "size", "ids", "labels", "v"])


def _tile_pairs(batches):
    """Near pairs within two tiles: candidates by one product of matrices, then decided in double precision, term after term."""
    import numpy as np
    import pyarrow as pa

    def vectors(row):
        v = np.frombuffer(row["v"], "float64").reshape(len(row["ids"]), row["size"])
        norm = np.zeros(len(v))
        for k in range(row["size"]):
            norm += v[:, k] * v[:, k]
        return v, np.sqrt(norm)

    for batch in batches:
        kind = batch.schema.field("a").type.field("labels").type.value_type
        for n in range(batch.num_rows):
            a, b = batch.column("a")[n].as_py(), batch.column("b")[n].as_py()
            (va, na), (vb, nb) = vectors(a), vectors(b)
            i, j = np.divmod(np.flatnonzero(_unit(va, na) @ _unit(vb, nb).T >= NEAR - SLACK), len(vb))
            if a["tile"] == b["tile"]:
                i, j = i[i < j], j[i < j]
            dot = np.zeros(len(i))
            for k in range(a["size"]):
                dot += va[i, k] * vb[j, k]
            ids_a, ids_b = np.array(a["ids"]), np.array(b["ids"])
            ahead = ids_a[i] < ids_b[j]
            # The bound is made of the norms in the order of the ids, as the plain join has it.
            near = (dot >= NEAR * np.where(ahead, na[i], nb[j]) * np.where(ahead, nb[j], na[i])) & (ids_a[i] != ids_b[j])
            i, j, ahead = i[near], j[near], ahead[near]
            la, lb = pa.array(a["labels"], kind).take(pa.array(i)), pa.array(b["labels"], kind).take(pa.array(j))
            first, second = pa.compute.if_else(pa.array(ahead), la, lb), pa.compute.if_else(pa.array(ahead), lb, la)
            low, high = np.minimum(ids_a[i], ids_b[j]), np.maximum(ids_a[i], ids_b[j])
            yield pa.record_batch([pa.array(low), pa.array(high), first, second], ["v1", "v2", "_l0", "_l1"])


def _near(instance: Instance) -> DataFrame:
    """Pairs of vectors of cosine ``NEAR`` or more, by its meaning a comparison of all pairs.

    Vectors are packed into tiles, written once; each pair of tiles is one product of matrices in single precision, whose
    candidates are decided in double precision. Vectors without a direction (length zero or no number) are joined with all.
    """
    import uuid

    from derivatrace.sources.tables import shared_folder

    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    rows = instance.labelled("embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"), "_label").withColumn("norm", F.sqrt(dot(F.col("v"), F.col("v"))))
    # A null vector, or a null within one, has no norm and no pair.
    rows = rows.where("vec_id is not null and norm is not null").withColumn("odd", F.expr("norm = 0 or isnan(norm) or norm = double('inf')"))
    label = dict(rows.dtypes)["_label"]
    path = f"{shared_folder(instance.spark)}/vectors-{uuid.uuid4().hex}"
    sized = rows.where("not odd").select("vec_id", "v", "_label", F.size("v").alias("size"))
    sized.mapInArrow(_packed, f"tile string, size int, ids array<bigint>, labels array<{label}>, v binary").write.parquet(path)
    tiles = instance.spark.read.parquet(path)
    # No equality, which would deal tiles out once for each size.
    one = lambda name: tiles.select(F.struct(*tiles.columns).alias(name))
    pairs = one("a").join(one("b"), F.expr("a.tile <= b.tile and not (a.size < b.size or a.size > b.size)"))
    near = pairs.mapInArrow(_tile_pairs, f"v1 bigint, v2 bigint, _l0 {label}, _l1 {label}")
    a, b = rows.select(*[F.col(c).alias(f"{c}_a") for c in rows.columns]), rows.select(*[F.col(c).alias(f"{c}_b") for c in rows.columns])
    close = (F.col("vec_id_a") < F.col("vec_id_b")) & (dot(F.col("v_a"), F.col("v_b")) >= NEAR * F.col("norm_a") * F.col("norm_b"))
    odd = a.where("odd_a").join(b, close).unionByName(a.where("not odd_a").join(b.where("odd_b"), close))
    return near.unionByName(odd.select(F.col("vec_id_a").alias("v1"), F.col("vec_id_b").alias("v2"), F.col("_label_a").alias("_l0"), F.col("_label_b").alias("_l1")))


def _quotes(instance: Instance) -> DataFrame:
    """Documents that contain an item's whole text.

    The words within an item, its first and last left aside, stand whole in any text that contains it: their first
    ``SEED`` are the seed, joined by hash with the runs of so many words in the documents, and what meets is then
    compared. Items of fewer words have no seed and are looked for in every document.
    """
    words = lambda c: F.filter(F.split(c, r"[ \t-\r]+"), lambda x: x != "")
    items = instance.labelled("benchmark").select("item_id", F.col("text").alias("item"), F.col("_label").alias("_l1"), words("text").alias("w"))
    docs = instance.labelled("documents").select("doc_id", "text", F.col("_label").alias("_l0"))
    long = items.where(F.size("w") >= SEED + 2).withColumn("seed", F.xxhash64(F.array_join(F.slice("w", 2, SEED), " "))).drop("w")
    runs = F.transform(F.sequence(F.lit(1), F.size("w") - SEED + 1), lambda i: F.xxhash64(F.array_join(F.slice(F.col("w"), i, SEED), " ")))
    seeds = docs.select("doc_id", "_l0", words("text").alias("w")).where(F.size("w") >= SEED).select("doc_id", "_l0", F.explode(F.array_distinct(runs)).alias("seed"))
    met = seeds.join(long, "seed").select("doc_id", "_l0", "item_id", "item", "_l1").join(docs.select("doc_id", "_l0", "text"), ["doc_id", "_l0"])
    short = docs.join(items.where(F.size("w") < SEED + 2), F.lit(True))
    out = met.select("doc_id", "item_id", "text", "item", "_l0", "_l1").unionByName(short.select("doc_id", "item_id", "text", "item", "_l0", "_l1"))
    return out.where(F.col("text").contains(F.col("item"))).select("doc_id", "item_id", "_l0", "_l1").distinct()


def _frequent(policy: str, least: int = 15):
    def build(instance: Instance) -> DataFrame:
        groups = instance.labelled("orders").groupBy("o_custkey")
        if policy == "opaque":
            return groups.agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= least)
        return groups.agg(F.count(F.lit(1)).alias("n"), F.collect_set("_label").alias("_ls")).where(F.col("n") >= least)

    return Body(f"m36-{policy}", build, arrays=("_ls",) if policy == "witnesses" else ())


def frequent_buyer(policy: str) -> Rule:
    return Rule(("m36",), "FrequentBuyer", (Template("cust", ("o_custkey",)),), _frequent(policy))


#: Equal texts are joined by their digest, so that texts themselves aren't moved.
_SAME = (TableAtom("documents", {"doc_id": "d1", "md5(text)": "t"}), TableAtom("documents", {"doc_id": "d2", "md5(text)": "t"}))
_ORDER_LINE = (TableAtom("orders", {"o_orderkey": "ok", "o_custkey": "ck"}), TableAtom("lineitem", {"l_orderkey": "ok", "l_partkey": "pk", "l_suppkey": "sk"}))
_C, _S, _P = Template("cust", ("ck",)), Template("supp", ("sk",)), Template("part", ("pk",))

RULES = (
    _one("m01", "Customer", "customer", _CUST), _one("m02", "basedIn", "customer", _CUST, ("nat", ("c_nationkey",))),
    _one("m03", "Supplier", "supplier", _SUPP), _one("m04", "basedIn", "supplier", _SUPP, ("nat", ("s_nationkey",))),
    _one("m05", "Nation", "nation", _NAT), _one("m06", "partOfRegion", "nation", _NAT, ("reg", ("n_regionkey",))), _one("m07", "Region", "region", ("reg", ("r_regionkey",))),
    _one("m08", "Product", "part", _PART),
    *[_one(f"m09{x}", f"{t}Product", "part", _PART, p_type=t.upper()) for x, t in zip("abcdef", ("Economy", "Small", "Promo", "Standard", "Medium", "Large"), strict=True)],
    _one("m10a", "hasBrand", "part", _PART, ("brand", ("p_brand",))), _one("m10b", "hasType", "part", _PART, ("type", ("p_type",))), _one("m10c", "hasSize", "part", _PART, ("size", ("p_size",))), _one("m10d", "named", "part", _PART, ("name", ("p_name",))),
    _one("m11", "Order", "orders", _ORD),
    *[_one(f"m12{x}", f"{n}Order", "orders", _ORD, o_orderstatus=v) for x, n, v in (("a", "Open", "O"), ("b", "Fulfilled", "F"), ("c", "Pending", "P"))],
    _one("m13a", "UrgentOrder", "orders", _ORD, o_orderpriority="1-URGENT"), _one("m13b", "HighOrder", "orders", _ORD, o_orderpriority="2-HIGH"),
    _one("m14", "placedBy", "orders", _ORD, ("cust", ("o_custkey",))),
    _one("m15", "hasLine", "lineitem", ("ord", ("l_orderkey",)), _LI), _one("m16", "lineProduct", "lineitem", _LI, ("part", ("l_partkey",))), _one("m17", "lineSupplier", "lineitem", _LI, ("supp", ("l_suppkey",))),
    _one("m18", "ReturnedLine", "lineitem", _LI, l_returnflag="R"),
    _joined("m19", "bought", (_C, _P), *_ORDER_LINE), _joined("m20", "suppliedTo", (_S, _C), *_ORDER_LINE),
    _joined("m21", "domesticDeal", (_C, _S), TableAtom("customer", {"c_custkey": "ck", "c_nationkey": "nk"}), *_ORDER_LINE, TableAtom("supplier", {"s_suppkey": "sk", "s_nationkey": "nk"})),
    _one("m22", "offers", "lineitem", ("supp", ("l_suppkey",)), ("part", ("l_partkey",))),
    *[_one(f"m23{x}", f"{t.title()}Event", "events", _EV, event_type=t) for x, t in zip("abcde", ("click", "view", "purchase", "signup", "error"), strict=True)],
    _one("m24", "performedBy", "events", _EV, ("cust", ("user_id",))), _one("m25", "BigSpender", "customer", _CUST, where="c_acctbal > 9000", extra=("c_acctbal",)),
    *[_one(f"m26{x}", f"{n}Doc", "documents", _DOC, lang=v) for x, n, v in (("a", "English", "en"), ("b", "French", "fr"), ("c", "German", "de"), ("d", "Spanish", "es"))],
    _one("m27", "fromSource", "documents", _DOC, ("src", ("source",))), _one("m28a", "GoodDoc", "labels", _DOC, quality=1), _one("m28b", "ToxicDoc", "labels", _DOC, toxic=1),
    _joined("m29", "sameText", (Template("doc", ("d1",)), Template("doc", ("d2",))), *_SAME, where="d1 < d2"),
    *[_one(f"m30{x}", f"{r.title()}Turn", "conversations", _TURN, role=r) for x, r in zip("abc", ("user", "assistant", "system"), strict=True)],
    _one("m31", "inConversation", "conversations", _TURN, ("conv", ("conv_id",))),
    Rule(("m32",), "follows", (Template(*_TURN), Template("turn", ("conv_id", "t0"))), Body("m32", _turns, ("_l0", "_l1"))),
    _one("m33a", "Page", "pages", ("page", ("page_id",))), Rule(("m33b",), "hostedOn", (Template("page", ("page_id",)), Template("host", ("host",))), Body("m33b", _hosts, ("_l0",))),
    _one("m34a", "hasClass", "embeddings", ("vec", ("vec_id",)), ("cls", ("label",))), Rule(("m34b",), "similarTo", (Template("vec", ("v1",)), Template("vec", ("v2",))), Body("m34b", _near, ("_l0", "_l1"))),
    Rule(("m35",), "quotes", (Template("doc", ("doc_id",)), Template("item", ("item_id",))), Body("m35", _quotes, ("_l0", "_l1"))),
    frequent_buyer("witnesses"),
    _one("m37", "Contact", "customer", _CUST, c_mktsegment="BUILDING"), _one("m37", "Contact", "events", ("cust", ("user_id",))),
)


def instance(spark: SparkSession, path: str, variant: str = "deep", *, hashed: bool = False) -> Instance:
    """The fixture over a folder of tables; ``evaluation`` is the deep mix's, with more rules and inclusions."""
    if variant == "evaluation":
        from derivatrace.workloads import evaluation

        return Instance(spark, load(spark, path), SOURCES, RULES + evaluation.RULES, evaluation.EVALUATION, hashed)
    ontology = {"deep": DEEP, "flat": Ontology(), "acyclic": ACYCLIC, "conflict": CONFLICT}[variant]
    return Instance(spark, load(spark, path), SOURCES, RULES, ontology, hashed)
