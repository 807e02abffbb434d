"""Micro-scenarios of exchange, each a schema pair, an alignment and the renaming that solves it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..operators import assoc, interpret
from ..plans.rules import Rule, exchange
from . import scenarios
from .model import KB, Alignment, Prop, corr_a2a, corr_c2c

_CUSTOMER = KB("src", ["Customer", "ActiveCustomer", "Nation"], [Prop("c_name", "Customer"), Prop("c_acctbal", "Customer", dt="double"), Prop("n_name", "Nation"), Prop("lives_in", "Customer", "Nation")], [("ActiveCustomer", "Customer")])


def _solve(spark: SparkSession, sf_dir: str, a: Alignment, s_root: str, t_root: str, nodes: dict[str, str], attrs: dict) -> DataFrame:
    trees = {s: assoc.semantic_associations(spark, a, s) for s in "st"}
    sk = interpret.Skeleton(a, trees["s"][s_root], trees["t"][t_root])
    asg = [-1] * len(sk.t.vars)
    for t, s in nodes.items():
        asg[sk.t.index[t, None]] = sk.s.index[s, None]
    for t, s in attrs.items():
        asg[sk.t.index[t]] = sk.s.index[s]
    return exchange([Rule(sk, asg, "m")], scenarios.sales_source(spark, sf_dir, a.source))


def rename_class(spark, sf_dir):
    t = KB("tgt", ["Client"], [Prop("name", "Client")])
    a = Alignment(_CUSTOMER, t, [corr_c2c("c", "Customer", "Client"), corr_a2a("n", "Customer", "c_name", "Client", "name")])
    return _solve(spark, sf_dir, a, "Customer", "Client", {"Client": "Customer"}, {("Client", "name"): ("Customer", "c_name")})


def rename_property(spark, sf_dir):
    t = KB("tgt", ["Client", "Country"], [Prop("resides", "Client", "Country")])
    a = Alignment(_CUSTOMER, t, [corr_c2c("c", "Customer", "Client"), corr_c2c("n", "Nation", "Country")])
    return _solve(spark, sf_dir, a, "Customer", "Client", {"Client": "Customer", "Client>resides/Country": "Customer>lives_in/Nation"}, {})


def hoist_property(spark, sf_dir):
    """Only active customers are aligned; their name goes to the target's superclass."""
    t = KB("tgt", ["Member", "Client"], [Prop("name", "Client")], [("Member", "Client")])
    a = Alignment(_CUSTOMER, t, [corr_c2c("m", "ActiveCustomer", "Member"), corr_c2c("c", "Customer", "Client"), corr_a2a("n", "Customer", "c_name", "Client", "name")])
    return _solve(spark, sf_dir, a, "ActiveCustomer", "Member", {"Member": "ActiveCustomer", "Member>Client": "ActiveCustomer>Customer"}, {("Member>Client", "name"): ("ActiveCustomer>Customer", "c_name")})


def resourcify(spark, sf_dir):
    """A literal becomes an attribute of an invented node."""
    t = KB("tgt", ["Client", "Ledger"], [Prop("has_ledger", "Client", "Ledger"), Prop("balance", "Ledger")])
    a = Alignment(_CUSTOMER, t, [corr_c2c("c", "Customer", "Client"), corr_a2a("b", "Customer", "c_acctbal", "Ledger", "balance")])
    return _solve(spark, sf_dir, a, "Customer", "Client", {"Client": "Customer"}, {("Client>has_ledger/Ledger", "balance"): ("Customer", "c_acctbal")})


SQL = {
    "bench_rename_class": "SELECT 'cust/' || c_custkey AS s, 'type' AS p, 'iri' AS o_kind, 'Client' AS o FROM customer UNION SELECT 'cust/' || c_custkey, 'name', 'lit', c_name FROM customer",
    "bench_rename_property": "SELECT 'cust/' || c_custkey AS s, 'type' AS p, 'iri' AS o_kind, 'Client' AS o FROM customer UNION SELECT 'nation/' || c_nationkey, 'type', 'iri', 'Country' FROM customer UNION SELECT 'cust/' || c_custkey, 'resides', 'iri', 'nation/' || c_nationkey FROM customer",
    "bench_hoist_property": "WITH a AS (SELECT * FROM customer WHERE c_custkey IN (SELECT user_id FROM events)) SELECT 'cust/' || c_custkey AS s, 'type' AS p, 'iri' AS o_kind, 'Member' AS o FROM a UNION SELECT 'cust/' || c_custkey, 'type', 'iri', 'Client' FROM a UNION SELECT 'cust/' || c_custkey, 'name', 'lit', c_name FROM a",
    "bench_resourcify": "SELECT 'cust/' || c_custkey AS s, 'type' AS p, 'iri' AS o_kind, 'Client' AS o FROM customer UNION SELECT 'cust/' || c_custkey, 'has_ledger', 'blank', '_:m,1(cust/' || c_custkey || ')' FROM customer UNION SELECT '_:m,1(cust/' || c_custkey || ')', 'type', 'iri', 'Ledger' FROM customer UNION SELECT '_:m,1(cust/' || c_custkey || ')', 'balance', 'lit', CAST(CAST(c_acctbal AS DECIMAL(18,2)) AS VARCHAR) FROM customer",
}
