"""Scenarios on the given tables: schemas, alignments and lazy instance views."""

from __future__ import annotations

from dataclasses import replace
from functools import cache

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.paths import iri, lexical
from .model import KB, Alignment, Prop, Source, corr_a2a, corr_c2c, corr_r2r


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _id(df: DataFrame, kind: str, key: str) -> DataFrame:
    return df.select(iri(kind, key).alias("id"))


def _attr(df: DataFrame, kind: str, key: str, col: str) -> DataFrame:
    return df.select(iri(kind, key).alias("s"), lexical(F.col(col), dict(df.dtypes)[col]).alias("v")).where("v is not null")


def _edge(df: DataFrame, kind1: str, key1: str, kind2: str, key2: str) -> DataFrame:
    return df.select(iri(kind1, key1).alias("s"), iri(kind2, key2).alias("o")).where("s is not null and o is not null")


# --- W0, the running scenario ------------------------------------------------------------------------------------


def running(extra: int = 0) -> Alignment:
    """Customers, what they bought and returned, suppliers and nations; ``extra`` adds as many further customer-supplier properties."""
    obj = [Prop("purchased_from", "Customer", "Supplier"), Prop("returned_to", "Customer", "Supplier"), Prop("supplier_in", "Supplier", "Nation"), Prop("lives_in", "Customer", "Nation")]
    obj += [Prop(f"linked_{k}", "Customer", "Supplier") for k in range(extra)]
    s = KB("src", ["ActiveCustomer", "Customer", "Supplier", "Nation"], [Prop("c_name", "Customer"), Prop("s_name", "Supplier"), Prop("s_acctbal", "Supplier", dt="double"), Prop("n_name", "Nation"), *obj], [("ActiveCustomer", "Customer")])
    t = KB(
        "tgt", ["Member", "Client", "Vendor", "Country", "Ledger"],
        [
            Prop("name", "Client"), Prop("ledger_balance", "Ledger"), Prop("vendor_label", "Vendor"), Prop("country_label", "Country"),
            Prop("deals_with", "Client", "Vendor"), Prop("sent_back_to", "Client", "Vendor"), Prop("vendor_country", "Vendor", "Country"), Prop("has_ledger", "Client", "Ledger"),
        ],
        [("Member", "Client")],
    )
    return Alignment(s, t, [
        corr_a2a("c1", "Customer", "c_name", "Client", "name"),
        corr_a2a("c2", "Supplier", "s_acctbal", "Ledger", "ledger_balance"),
        corr_c2c("c3", "Customer", "Client"),
        corr_r2r("c4", "Customer", "purchased_from", "Supplier", "Client", "deals_with", "Vendor"),
        corr_c2c("c5", "ActiveCustomer", "Member"),
        corr_c2c("c6", "Supplier", "Vendor"),
        corr_c2c("c7", "Nation", "Country"),
        corr_a2a("c8", "Supplier", "s_name", "Vendor", "vendor_label"),
        corr_a2a("c9", "Nation", "n_name", "Country", "country_label"),
    ])


def sales_source(spark: SparkSession, sf_dir: str, kb: KB) -> Source:
    """Instance views of customers, suppliers, nations, regions and orders."""
    t = cache(lambda name: table(spark, sf_dir, name))

    def bought(returned: bool):
        lines = t("lineitem").where((F.col("l_returnflag") == "R") == F.lit(returned)).select("l_orderkey", "l_suppkey")
        pairs = t("orders").select("o_orderkey", "o_custkey").join(lines, F.col("o_orderkey") == F.col("l_orderkey"))
        return _edge(pairs.select("o_custkey", "l_suppkey").distinct(), "cust", "o_custkey", "supp", "l_suppkey")

    types = {
        "Customer": lambda: _id(t("customer"), "cust", "c_custkey"),
        "ActiveCustomer": lambda: _id(t("customer").join(t("events").select(F.col("user_id").alias("c_custkey")), "c_custkey", "left_semi"), "cust", "c_custkey"),
        "Supplier": lambda: _id(t("supplier"), "supp", "s_suppkey"),
        "Nation": lambda: _id(t("nation"), "nation", "n_nationkey"),
        "Region": lambda: _id(t("region"), "region", "r_regionkey"),
        "Order": lambda: _id(t("orders"), "order", "o_orderkey"),
    }
    objects = {
        "purchased_from": lambda: bought(False),
        "returned_to": lambda: bought(True),
        "supplier_in": lambda: _edge(t("supplier"), "supp", "s_suppkey", "nation", "s_nationkey"),
        "lives_in": lambda: _edge(t("customer"), "cust", "c_custkey", "nation", "c_nationkey"),
        "in_region": lambda: _edge(t("nation"), "nation", "n_nationkey", "region", "n_regionkey"),
        "placed_by": lambda: _edge(t("orders"), "order", "o_orderkey", "cust", "o_custkey"),
    }
    attrs = {
        ("Customer", "c_name"): lambda: _attr(t("customer"), "cust", "c_custkey", "c_name"),
        ("Customer", "c_acctbal"): lambda: _attr(t("customer"), "cust", "c_custkey", "c_acctbal"),
        ("Customer", "c_mktsegment"): lambda: _attr(t("customer"), "cust", "c_custkey", "c_mktsegment"),
        ("Supplier", "s_name"): lambda: _attr(t("supplier"), "supp", "s_suppkey", "s_name"),
        ("Supplier", "s_acctbal"): lambda: _attr(t("supplier"), "supp", "s_suppkey", "s_acctbal"),
        ("Nation", "n_name"): lambda: _attr(t("nation"), "nation", "n_nationkey", "n_name"),
        ("Order", "o_orderstatus"): lambda: _attr(t("orders"), "order", "o_orderkey", "o_orderstatus"),
    }
    return Source(kb, types, objects, attrs)


# --- taxonomies --------------------------------------------------------------------------------------------------


def taxonomy(depth: int, children: int, moved: int, attributes: int = 10, per: str = "class") -> Alignment:
    """A tree of classes; ``attributes`` at its root in the source, of which the first ``moved`` sink in the target.

    ``per`` class: attribute i goes to the i-th class in breadth-first order; per level: to the first class of level i.
    """
    levels = [["A0"]]
    edges = []
    for _ in range(depth):
        below = []
        for up in levels[-1]:
            for _ in range(children):
                c = f"A{sum(map(len, levels)) + len(below)}"
                below.append(c)
                edges.append((c, up))
        levels.append(below)
    classes = [c for level in levels for c in level]
    home = {i: (classes[i] if per == "class" else levels[i][0]) for i in range(1, moved + 1)}
    names = [f"d{i}" for i in range(1, attributes + 1)]
    s = KB("src", [f"s{c}" for c in classes], [Prop(n, "sA0") for n in names], [(f"s{a}", f"s{b}") for a, b in edges])
    t = KB("tgt", [f"t{c}" for c in classes], [Prop(n, "t" + home.get(i + 1, "A0")) for i, n in enumerate(names)], [(f"t{a}", f"t{b}") for a, b in edges])
    corrs = [corr_c2c(f"c{c}", f"s{c}", f"t{c}") for c in classes]
    corrs += [corr_a2a(n, "sA0", n, "t" + home.get(i + 1, "A0"), n) for i, n in enumerate(names)]
    return Alignment(s, t, corrs)


def merged(parts: dict[str, Alignment]) -> Alignment:
    """Alignments side by side under prefixes, so that one pass serves a whole series."""
    def kb(side):
        k = [(p, a.side(side)) for p, a in parts.items()]
        return KB(side, [p + c for p, x in k for c in x.classes], [Prop(q.name, p + q.domain, q.range and p + q.range, q.dt) for p, x in k for q in x.props], [(p + u, p + v) for p, x in k for u, v in x.subclasses])

    corrs = [replace(c, id=p + c.id, s1=p + c.s1, t1=p + c.t1, s2=c.s2 and p + c.s2, t2=c.t2 and p + c.t2) for p, a in parts.items() for c in a.corrs]
    return Alignment(kb("s"), kb("t"), corrs)


# --- use cases ---------------------------------------------------------------------------------------------------


def open_data() -> Alignment:
    s = KB("src", ["Author", "Document", "Topic"], [Prop("topic_label", "Topic"), Prop("wrote", "Author", "Document"), Prop("about", "Document", "Topic")])
    t = KB("tgt", ["Person", "Skill"], [Prop("skill_label", "Skill"), Prop("has_skill", "Person", "Skill")])
    return Alignment(s, t, [corr_c2c("c1", "Author", "Person"), corr_c2c("c2", "Topic", "Skill"), corr_a2a("c3", "Topic", "topic_label", "Skill", "skill_label")])


def open_data_source(spark: SparkSession, sf_dir: str, kb: KB) -> Source:
    docs, emb = (lambda: table(spark, sf_dir, "documents")), (lambda: table(spark, sf_dir, "embeddings"))
    return Source(
        kb,
        {
            "Author": lambda: _id(docs().where("source is not null").select("source").distinct(), "author", "source"),
            "Document": lambda: _id(docs(), "doc", "doc_id"),
            "Topic": lambda: _id(emb().where("label is not null").select("label").distinct(), "topic", "label"),
        },
        {"wrote": lambda: _edge(docs(), "author", "source", "doc", "doc_id"), "about": lambda: _edge(emb(), "doc", "vec_id", "topic", "label")},
        {("Topic", "topic_label"): lambda: _attr(emb().select("label").distinct(), "topic", "label", "label")},
    )


def migration() -> Alignment:
    s = KB("src", ["Customer", "Supplier", "Order", "Nation", "Region"], [Prop("c_name", "Customer"), Prop("n_name", "Nation"), Prop("placed_by", "Order", "Customer"), Prop("in_region", "Nation", "Region"), Prop("lives_in", "Customer", "Nation"), Prop("supplier_in", "Supplier", "Nation")])
    t = KB("tgt", ["Party", "Customer2", "Supplier2", "Order2", "Nation2", "Region2"], [Prop("name", "Customer2"), Prop("nation_name", "Nation2"), Prop("placedBy", "Order2", "Customer2"), Prop("inRegion", "Nation2", "Region2"), Prop("located", "Party", "Nation2")], [("Customer2", "Party"), ("Supplier2", "Party")])
    return Alignment(s, t, [
        *[corr_c2c(f"c_{c}", c, f"{c}2") for c in s.classes],
        corr_a2a("a_name", "Customer", "c_name", "Customer2", "name"), corr_a2a("a_nation", "Nation", "n_name", "Nation2", "nation_name"),
        corr_r2r("r_placed", "Order", "placed_by", "Customer", "Order2", "placedBy", "Customer2"), corr_r2r("r_region", "Nation", "in_region", "Region", "Nation2", "inRegion", "Region2"),
    ])


def inverse_orders() -> Alignment:
    s = KB("src", ["Order", "Customer"], [Prop("o_orderstatus", "Order"), Prop("placed_by", "Order", "Customer")])
    t = KB("tgt", ["Client", "Purchase"], [Prop("status", "Purchase"), Prop("submits", "Client", "Purchase")])
    return Alignment(s, t, [corr_c2c("c1", "Customer", "Client"), corr_c2c("c2", "Order", "Purchase"), corr_a2a("a1", "Order", "o_orderstatus", "Purchase", "status")])


def conversations() -> Alignment:
    s = KB("src", ["Conversation", "Turn"], [Prop("role", "Turn"), Prop("in_conv", "Turn", "Conversation")])
    t = KB("tgt", ["Dialogue", "Utterance"], [Prop("speaker", "Utterance"), Prop("has_utterance", "Dialogue", "Utterance")])
    return Alignment(s, t, [corr_c2c("c1", "Conversation", "Dialogue"), corr_c2c("c2", "Turn", "Utterance"), corr_a2a("a1", "Turn", "role", "Utterance", "speaker")])


def cyclic() -> Alignment:
    """Turns that answer turns: a property whose two ends are one class, on both sides."""
    s = KB("src", ["Conversation", "Turn"], [Prop("role", "Turn"), Prop("in_conv", "Turn", "Conversation"), Prop("replies_to", "Turn", "Turn")])
    t = KB("tgt", ["Dialogue", "Utterance"], [Prop("speaker", "Utterance"), Prop("part_of", "Utterance", "Dialogue"), Prop("answers", "Utterance", "Utterance")])
    return Alignment(s, t, [
        corr_c2c("c1", "Conversation", "Dialogue"), corr_c2c("c2", "Turn", "Utterance"), corr_a2a("a1", "Turn", "role", "Utterance", "speaker"),
        corr_r2r("r1", "Turn", "replies_to", "Turn", "Utterance", "answers", "Utterance"),
    ])


def conversation_source(spark: SparkSession, sf_dir: str, kb: KB) -> Source:
    conv = lambda: table(spark, sf_dir, "conversations").withColumn("key", F.concat_ws(".", "conv_id", "turn"))
    return Source(
        kb,
        {"Conversation": lambda: _id(conv().select("conv_id").distinct(), "conv", "conv_id"), "Turn": lambda: _id(conv(), "turn", "key")},
        {
            "in_conv": lambda: _edge(conv(), "turn", "key", "conv", "conv_id"),
            "replies_to": lambda: _edge(conv().selectExpr("key", "concat_ws('.', conv_id, lag(turn) over (partition by conv_id order by turn)) as before", "lag(turn) over (partition by conv_id order by turn) as l").where("l is not null"), "turn", "key", "turn", "before"),
        },
        {("Turn", "role"): lambda: _attr(conv(), "turn", "key", "role")},
    )
