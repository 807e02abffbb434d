"""The engine on its running fixture: counts, costs and facts with known values."""

import pytest

from kbmap import queries as Q
from kbmap.functions.paths import invert_path, parse_path, render_path
from kbmap.operators import assoc, baselines, interpret, measures
from kbmap.plans.rules import exchange, to_sparql
from kbmap.sources import scenarios
from kbmap.sources.model import KB, Prop, UnsupportedCorrespondence, corr_metadata_to_data

SF = "/root/testdata/sf0.001"


def test_paths():
    assert [render_path(p) for p in parse_path("a/^(b/c)|d")] == ["a/^c/^b", "d"]
    assert render_path(invert_path(parse_path("a/^b")[0])) == "b/^a"
    for bad in ("", "a//b", "a|", "(a", "^"):
        with pytest.raises(ValueError):
            parse_path(bad)
    with pytest.raises(UnsupportedCorrespondence):
        corr_metadata_to_data("a", "b")


def test_backtracking_and_inner_concepts(spark):
    kb = KB("k", ["P", "O", "X"], [Prop("boss", "P", "P"), Prop("works", "P", "O"), Prop("alum", "P", "O"), Prop("via", "X", "O")])
    ids = lambda aligned, n: {r.path_id for r in assoc.association_paths(spark, kb, aligned, n).collect()}
    assert ids(["P"], 1) == {"boss/P"}
    # Over the unaligned O and back by the other property, not by the same one to the same class.
    assert ids(["P"], 2) == {"boss/P", "works/O/^alum/P", "alum/O/^works/P"}
    assert ids(["P", "O"], 2) == {"boss/P", "works/O", "alum/O"}


def test_validity_and_counting_agree(spark):
    sk = Q.w0_skeleton(spark)
    got = interpret.validity_counts(spark, sk).first()
    assert (got.baseline, got.r2r, got.c2a, got.both) == (10368, 3456, 480, 144)
    assert [interpret.count_renamings(sk, m, r) for m, r in ((None, False), (None, True), ("literal", False), ("strict", True))] == [10368, 3456, 480, 48]


def test_joint_and_factored_plans_agree(spark):
    src = scenarios.sales_source(spark, SF, scenarios.running().source)
    for name in Q.NAMED:
        rule = Q.w0_rule(spark, name)
        a, b = exchange([rule], src), exchange([rule], src, plan="joint")
        assert a.exceptAll(b).count() == b.exceptAll(a).count() == 0


def test_baseline_facts_are_a_subset(spark):
    assert Q.aligned_prop_exchange(spark, SF).join(Q.exchange_gold(spark, SF), ["s", "p", "o_kind", "o"], "left_anti").count() == 0


def test_ranks_use_ties(spark):
    r = spark.createDataFrame([([i], c) for i, c in enumerate([0] * 6 + [1] * 9 + [2] * 4 + [3] * 7)], "asg array<int>, cost_ long")
    g = interpret.gold_position(r, [16], "cost_").first()
    assert (g["rank"], g.better, g.equal) == (3, 15, 3)


def test_inverse_properties_cost_nothing_if_asked(spark):
    sk = Q._skeleton(spark, "w3", "Order", "Client")
    asg = Q.assignment(sk, {"Client": "Order>placed_by/Customer", "Client>submits/Purchase": "Order"})
    df = spark.createDataFrame([(asg,)], "asg array<int>")
    cost = lambda **o: df.select(sk.consistency_cost(nodes_only=True, **o).alias("c")).first().c
    assert cost() == 2 and cost(inverse_aware=True) == 0


def test_sparql_names_all_parts(spark):
    text = to_sparql(Q.w0_rule(spark, "R1"))
    assert text.count("OPTIONAL {") >= 4 and "BNODE" in text and "a tgt:Ledger" in text and text.count("{") == text.count("}")


def test_measures(spark):
    assert measures.delta(3, 5) == 2 and measures.kb_similarity(3, 200, 23) == pytest.approx(0.0269, abs=1e-4)
    assert baselines.from_examples([("a", "p", "b"), ("c", "p", "d")], [("a", "q", "b"), ("d", "r", "c")]) == [("^p", "r", 1), ("p", "q", 1)]
    types = spark.createDataFrame([(str(i), c) for i in range(20) for c in ("A", *(["B"] if i < 5 else []), *(["C"] if i < 3 else []))] + [(f"b{i}", "B") for i in range(15)] + [(f"c{i}", "C") for i in range(17)], "id string, cls string")
    assert {(r.c1, r.c2) for r in measures.overlap_dictionary(types).collect()} == {("A", "B")}


def test_fragment():
    kb = scenarios.running().source
    assert set(measures.knowledge_fragment(kb, {"Nation"}, 0).classes) == {"Nation"}
    assert "ActiveCustomer" in measures.knowledge_fragment(kb, {"Nation"}, 2).classes
    kb.equivalent = [("Nation", "Customer")]
    assert set(measures.knowledge_fragment(kb, {"Nation"}, 0).classes) == {"Nation", "Customer"}


def test_named_results(spark):
    assert Q.exchange_gold(spark, SF).count() == 715 and Q.construct_scoped(spark, SF).count() == 615
