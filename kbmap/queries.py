"""Queries over methods, baselines, measures and workloads, with DuckDB equivalents where SQL expresses them."""

from __future__ import annotations

from functools import lru_cache, reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.paths import iri
from .operators import assoc, baselines, interpret, measures, relational
from .plans import generate
from .plans.rules import Rule, exchange, to_sparql
from .sources import observed, patterns, scenarios
from .streaming import incremental

# --- shared pieces -----------------------------------------------------------------------------------------------


@lru_cache(maxsize=64)
def _trees(spark: SparkSession, name: str, side: str) -> dict:
    return assoc.semantic_associations(spark, _ALIGNMENTS[name](), side)


_ALIGNMENTS = {"w0": scenarios.running, "w1": scenarios.open_data, "w2": scenarios.migration, "w3": scenarios.inverse_orders, "w3b": scenarios.conversations, "w4": scenarios.cyclic}
_SOURCES = {"w0": scenarios.sales_source, "w1": scenarios.open_data_source, "w2": scenarios.sales_source, "w3": scenarios.sales_source, "w3b": scenarios.conversation_source, "w4": scenarios.conversation_source}
#: Bounds of paths and trees: one step further round a cycle makes a copy of every branch.
_BOUNDS = {"w4": (2, 2)}


def _skeleton(spark: SparkSession, name: str, s_root: str, t_root: str) -> interpret.Skeleton:
    return interpret.Skeleton(_ALIGNMENTS[name](), _trees(spark, name, "s")[s_root], _trees(spark, name, "t")[t_root])


def assignment(sk: interpret.Skeleton, nodes: dict[str, str], attrs: dict[tuple[str, str], tuple[str, str]] | None = None) -> list[int]:
    """An assignment from target nodes to source nodes; corresponding attributes of mapped nodes follow, others are given."""
    asg = [-1] * len(sk.t.vars)
    for t, s in nodes.items():
        asg[sk.t.index[t, None]] = sk.s.index[s, None]
        for tv, (tn, ta) in enumerate(sk.t.vars):
            for sv, (sn, sa) in enumerate(sk.s.vars):
                if tn == t and sn == s and ta and sa and ((sk.s.concept(sv), sa), (sk.t.concept(tv), ta)) in sk.a2a:
                    asg[tv] = sv
    for (t, ta), (s, sa) in (attrs or {}).items():
        asg[sk.t.index[t, ta]] = sk.s.index[s, sa]
    return asg


_S, _T = "ActiveCustomer>Customer", "Member>Client"
S_NODES = {"sE": "ActiveCustomer", "sP": _S, "sO1": f"{_S}>purchased_from/Supplier", "sO2": f"{_S}>returned_to/Supplier", "sC1": f"{_S}>purchased_from/Supplier>supplier_in/Nation", "sC2": f"{_S}>returned_to/Supplier>supplier_in/Nation", "sC3": f"{_S}>lives_in/Nation"}
T_NODES = {"tE": "Member", "tP": _T, "tO1": f"{_T}>deals_with/Vendor", "tO2": f"{_T}>sent_back_to/Vendor", "tC1": f"{_T}>deals_with/Vendor>vendor_country/Country", "tC2": f"{_T}>sent_back_to/Vendor>vendor_country/Country", "tA": f"{_T}>has_ledger/Ledger"}
NAMED = {
    "R1": {"tO1": "sO1", "tO2": "sO2", "tC1": "sC1", "tC2": "sC2"},
    "R2": {"tO1": "sO1", "tC1": "sC1"},
    "R3": {"tO1": "sO1", "tO2": "sO2", "tC1": "sC2", "tC2": "sC1"},
    "R4": {"tO1": "sO1", "tO2": "sO2", "tC1": "sC3", "tC2": "sC2"},
}


def w0_skeleton(spark: SparkSession) -> interpret.Skeleton:
    return _skeleton(spark, "w0", "ActiveCustomer", "Member")


def w0_assignment(sk: interpret.Skeleton, name: str) -> list[int]:
    pairs = {T_NODES[t]: S_NODES[s] for t, s in {"tE": "sE", "tP": "sP", **NAMED[name]}.items()}
    return assignment(sk, pairs, {(T_NODES["tA"], "ledger_balance"): (S_NODES["sO1"], "s_acctbal")})


def w0_rule(spark: SparkSession, name: str) -> Rule:
    sk = w0_skeleton(spark)
    return Rule(sk, w0_assignment(sk, name), "r")


def _sales(spark, sf_dir):
    return scenarios.sales_source(spark, sf_dir, scenarios.running().source)


def _shown(spark, sf_dir):
    """The running scenario as the given tables show it; read anew by each query."""
    return observed.shown(scenarios.running(), _sales(spark, sf_dir))


# --- discovery ---------------------------------------------------------------------------------------------------


def kb_profile(spark, sf_dir):
    a = scenarios.running()
    return measures.kb_profile(spark, a.source).unionByName(measures.kb_profile(spark, a.target))


def alignment_profile(spark, sf_dir):
    """(kind, n, facts): correspondences whose source elements have facts, and those facts."""
    a, n = _shown(spark, sf_dir)
    rows = [(k, m, sum(observed.corr_facts(a, n, c) for c in a.corrs if c.kind == k)) for k, m in a.profile().items()]
    return spark.createDataFrame(rows, "kind string, n long, facts long")


def aligned_concepts(spark, sf_dir):
    """(side, concept, instances): of a target concept the most that one of its correspondences brings."""
    a, n = _shown(spark, sf_dir)
    brought = lambda x: max(observed.corr_facts(a, n, c) for c in a.corrs if (c.kind == "c2c" and c.t1 == x) or (c.kind == "a2a" and a.owner(c, "t")[0] == x))
    rows = [("s", c, n["class", c, ""]) for c in a.aligned_concepts("s")] + [("t", c, brought(c)) for c in a.aligned_concepts("t")]
    return spark.createDataFrame(rows, "side string, concept string, instances long")


def basic_assoc(spark, sf_dir):
    """(side, concept, attrs, facts): the values of the attributes, on the target side those that their correspondences bring."""
    a, n = _shown(spark, sf_dir)
    brought = lambda s, c: sum(observed.corr_facts(a, n, x) for x in a.corrs if x.kind == "a2a" and a.owner(x, s)[0] == c)
    rows = [(s, c, ",".join(sorted(x)), brought(s, c)) for s in "st" for c, x in assoc.basic_associations(a, s).items()]
    return spark.createDataFrame(rows, "side string, concept string, attrs string, facts long")


def schema_hops(spark, sf_dir):
    return assoc.schema_hops(spark, scenarios.running().source)


def _shown_paths(spark, sf_dir, depth):
    """Source paths over elements with facts, with the fewest facts on a step."""
    a, n = _shown(spark, sf_dir)
    # Only these two are aligned, so that paths run through other concepts.
    aligned = [c for c in ("ActiveCustomer", "Nation") if c in a.source.classes]
    rows = observed.path_rows(assoc.association_paths(spark, a.source, aligned, depth), n) if aligned else []
    return spark.createDataFrame(rows, "root string, tail string, path_id string, hops long, facts long")


def assoc_paths(spark, sf_dir):
    """(side, root, tail, path_id, hops, facts): the fewest facts on a step of a source path; the target has none before an exchange."""
    a, n = _shown(spark, sf_dir)
    s, t = (assoc.association_paths(spark, a.side(x), a.aligned_concepts(x), 4) for x in "st")
    rows = [("s", *r) for r in observed.path_rows(s, n)] + [("t", r.root, r.tail, r.path_id, r.hops, None) for r in t.collect()]
    return spark.createDataFrame(rows, "side string, root string, tail string, path_id string, hops long, facts long")


def tree_nodes(spark, sf_dir):
    rows = [(s, n.root, n.id, n.concept, n.hop) for s in "st" for t in _trees(spark, "w0", s).values() for n in t.nodes]
    return spark.createDataFrame(rows, "side string, root string, node string, concept string, hop long")


def tree_reach(spark, sf_dir):
    a = scenarios.running()
    nodes = assoc.tree_nodes(spark, a.source, a.aligned_concepts("s"), assoc.association_paths(spark, a.source, a.aligned_concepts("s"), 4))
    return assoc.tree_closure(nodes)


def tree_variables(spark, sf_dir):
    rows = [(s, r, len(t.nodes), len(t.vars)) for s in "st" for r, t in _trees(spark, "w0", s).items()]
    return spark.createDataFrame(rows, "side string, root string, nodes long, variables long")


# --- interpretation ----------------------------------------------------------------------------------------------


def _pairs(spark, name="w0"):
    a = _ALIGNMENTS[name]()
    return (interpret.summaries(spark, a, _trees(spark, name, s), s) for s in "st")


def _printed(sk: DataFrame) -> DataFrame:
    return sk.select("s_root", "t_root", F.array_join("covered", ",").alias("covered"), F.col("s_vars").cast("long").alias("s_vars"), F.col("t_vars").cast("long").alias("t_vars"))


def skeletons_all(spark, sf_dir):
    return _printed(interpret.skeletons(*_pairs(spark)))


def skeletons_pruned_target(spark, sf_dir):
    return _printed(interpret.prune_skeletons(interpret.skeletons(*_pairs(spark)), "target"))


def skeletons_pruned_both(spark, sf_dir):
    return _printed(interpret.reduced_skeletons(*_pairs(spark)))


def candidates(spark, sf_dir):
    sk = w0_skeleton(spark)
    rows = [(sk.t.concept(tv), sk.t.vars[tv][1] or "", sk.s.concept(sv), sk.s.vars[sv][1] or "", c) for tv, hits in sk.candidates().items() for sv, c in hits]
    return spark.createDataFrame(rows, "t_concept string, t_attr string, s_concept string, s_attr string, corr string")


def _renaming_count(checks=(), mode="literal", once=True):
    def query(spark, sf_dir):
        r = interpret.renamings(spark, w0_skeleton(spark), once, checks, mode)
        return r.agg(F.count(F.lit(1)).alias("n"))

    return query


def _shown_renamings(spark, sf_dir):
    """The valid renamings of the largest skeleton of the running scenario as the tables show it, with source facts; none without active customers.

    Returns the skeleton or None, the renamings or None, and the facts by element.
    """
    a, n = _shown(spark, sf_dir)
    if not a.source.classes or "ActiveCustomer" not in a.aligned_concepts("s"):
        return None, None, n
    t = {s: assoc.semantic_associations(spark, a, s) for s in "st"}
    sk = interpret.Skeleton(a, t["s"]["ActiveCustomer"], t["t"]["Member"])
    return sk, interpret.renamings(spark, sk, checks=("r2r", "c2a", "owner"), c2a_mode="strict").withColumn("facts", sk.evidence(n)), n


def attr_owner_rule(spark, sf_dir):
    """(n, least, most): renamings by the owner rule, and the source facts that they take."""
    _, r, _ = _shown_renamings(spark, sf_dir)
    if r is None:
        return spark.createDataFrame([(0, None, None)], "n long, least long, most long")
    return r.agg(F.count(F.lit(1)).alias("n"), F.min("facts").alias("least"), F.max("facts").alias("most"))


def validity_counts(spark, sf_dir):
    sk = w0_skeleton(spark)
    one = interpret.validity_counts(spark, sk).withColumn("mode", F.lit("literal"))
    return one.unionByName(interpret.validity_counts(spark, sk, "strict").withColumn("mode", F.lit("strict")))


def named_costs(spark, sf_dir):
    sk = w0_skeleton(spark)
    rows = spark.createDataFrame([(n, w0_assignment(sk, n)) for n in NAMED], "name string, asg array<int>")
    out = interpret.costed(spark, sk, rows).withColumn("cons_nodes", sk.consistency_cost(nodes_only=True))
    return out.select("name", "path_cost", "cons_nodes", "cons_cost", "cov_cost")


def _cost_histogram(by):
    def query(spark, sf_dir):
        sk = w0_skeleton(spark)
        r = interpret.costed(spark, sk, interpret.renamings(spark, sk, checks=("r2r", "c2a"), c2a_mode="strict"))
        return interpret.histogram(r, by).select(*[F.col(c).cast("long").alias(c) for c in ("cost", "equal", "better", "rank")])

    return query


def gold_position(spark, sf_dir):
    sk = w0_skeleton(spark)
    r = interpret.costed(spark, sk, interpret.renamings(spark, sk, checks=("r2r", "c2a", "owner"), c2a_mode="strict"))
    out = None
    for by in ("path_cost", "cons_cost", "cov_cost", "combined"):
        g = interpret.gold_position(r, w0_assignment(sk, "R1"), by)
        out = g if out is None else out.unionByName(g)
    return out


def best_renamings(spark, sf_dir):
    sk, r, _ = _shown_renamings(spark, sf_dir)
    if sk is None:
        return spark.createDataFrame([], "asg string, path_cost long, cons_cost long, cov_cost long, combined long, facts long")
    return interpret.best_renamings(interpret.costed(spark, sk, r), 5).select(F.array_join("asg", ",").alias("asg"), "path_cost", "cons_cost", "cov_cost", "combined", "facts")


def _series(depth, children, per, xs):
    """(x, mappings, delta, delta_counted): ``delta`` against all correspondences of the alignment, ``delta_counted`` against those of classes
    and of the attributes that move (with one more), which is what the printed differences count."""

    def query(spark, sf_dir):
        parts = {f"x{x}_": scenarios.taxonomy(depth(x), children(x), x, per=per) for x in xs}
        a = scenarios.merged(parts)
        # Only isa steps lead to an aligned class here, and the next class is always aligned: paths have one step.
        sides = [interpret.summaries(spark, a, assoc.semantic_associations(spark, a, s, 1, 10), s) for s in "st"]
        out = interpret.reduced_skeletons(*sides).groupBy(F.regexp_extract("s_root", r"^x(\d+)_", 1).cast("long").alias("x")).agg(F.count(F.lit(1)).alias("mappings"))
        sizes = [(x, len(p.corrs), sum(c.kind == "c2c" for c in p.corrs) + (x + 2)) for x, p in ((x, parts[f"x{x}_"]) for x in xs)]
        counts = spark.createDataFrame(sizes, "x long, corrs long, counted long")
        d = lambda c: F.abs(F.col("mappings") - F.col(c))
        return out.join(F.broadcast(counts), "x").select("x", "mappings", d("corrs").alias("delta"), d("counted").alias("delta_counted"))

    return query


def e4_counts(spark, sf_dir):
    """Counted, not listed: the product of independent groups."""
    rows = []
    for k in (1, 2, 3):
        a = scenarios.running(k - 1)
        t = {s: assoc.semantic_associations(spark, a, s) for s in "st"}
        sk = interpret.Skeleton(a, t["s"]["ActiveCustomer"], t["t"]["Member"])
        rows.append((k, *(interpret.count_renamings(sk, m, r) for m, r in ((None, False), (None, True), ("literal", False), ("strict", False)))))
    return spark.createDataFrame(rows, "k long, baseline long, r2r long, c2a long, strict long")


# --- from alignment to facts -------------------------------------------------------------------------------------


@lru_cache(maxsize=16)
def _generation(spark: SparkSession, name: str) -> generate.Generation:
    return generate.Generation(spark, _ALIGNMENTS[name](), *_BOUNDS.get(name, (4, 6)))


def _source(spark, sf_dir, name):
    return _SOURCES[name](spark, sf_dir, _ALIGNMENTS[name]().source)


def all_mappings(spark, sf_dir):
    """Every valid mapping of every kept skeleton of the running scenario as the tables show it, with costs, rank within its skeleton and source facts."""
    a, n = _shown(spark, sf_dir)
    gen = generate.Generation(spark, a)
    at = [(F.col("s_root") == s) & (F.col("t_root") == t) for s, t in gen.skeletons]
    facts = [F.when(here, sk.evidence(n)) for here, sk in zip(at, gen.skeletons.values())]
    columns = ("path_cost", "cons_cost", "cov_cost", "combined", "rank", "better")
    if not gen.skeletons:
        return spark.createDataFrame([], "s_root string, t_root string, asg string, " + ", ".join(f"{c} long" for c in columns) + ", facts long")
    out = generate.ranked(gen.mappings())
    return out.select("s_root", "t_root", F.array_join("asg", ",").alias("asg"), *columns, F.coalesce(*facts).alias("facts"))


def _exchange_of(name):
    def query(spark, sf_dir):
        return generate.exchange_all(_generation(spark, name), _source(spark, sf_dir, name))

    return query


def usecase_counts(spark, sf_dir):
    """(scenario, baseline, r2r, c2a, both): mappings of all skeletons under each combination of the validity notions."""
    parts = [_generation(spark, n).validity_table().select(F.lit(n).alias("scenario"), "*") for n in ("w1", "w2", "w3", "w3b", "w4")]
    return reduce(DataFrame.unionByName, parts)


_GOLD = {
    "w1": ("Author", "Person", {"Person": "Author", "Person>has_skill/Skill": "Author>wrote/Document/about/Topic"}),
    "w2": ("Customer", "Customer2", {"Customer2": "Customer", "Customer2>Party/located/Nation2": "Customer>lives_in/Nation"}),
    "w3": ("Order", "Client", {"Client": "Order>placed_by/Customer", "Client>submits/Purchase": "Order"}),
    "w4": ("Turn", "Utterance", {"Utterance": "Turn", "Utterance>answers/Utterance": "Turn>replies_to/Turn", "Utterance>part_of/Dialogue": "Turn>in_conv/Conversation"}),
}
_RANKINGS = ("cov_cost", "path_cost", "cons_cost", "combined")


def usecase_ranks(spark, sf_dir):
    """(scenario, ranking, rank, better, equal) of each scenario's desired mapping among the valid ones of its skeleton."""
    parts = []
    for name, (s_root, t_root, nodes) in _GOLD.items():
        gen = _generation(spark, name)
        sk = interpret.Skeleton(gen.a, gen.trees["s"][s_root], gen.trees["t"][t_root])
        r = interpret.costed(spark, sk, interpret.renamings(spark, sk, checks=generate.ALL_CHECKS))
        parts += [interpret.gold_position(r, assignment(sk, nodes), by).select(F.lit(name).alias("scenario"), "*") for by in _RANKINGS]
    return reduce(DataFrame.unionByName, parts)


def brute_force_renamings(spark, sf_dir):
    """The reference enumeration of the cyclic scenario's largest skeleton, conditions last."""
    gen = _generation(spark, "w4")
    sk = max(gen.skeletons.values(), key=lambda k: (len(k.t.vars), len(k.s.vars)))
    return interpret.brute_force_renamings(spark, sk, checks=("r2r", "c2a")).select(F.array_join("asg", ",").alias("asg"))


def best_by_bounds(spark, sf_dir):
    sk, _, n = _shown_renamings(spark, sf_dir)
    if sk is None:
        return spark.createDataFrame([], "asg string, cons_cost long, facts long")
    best = interpret.best_by_bounds(spark, sk, 5, ("r2r", "c2a", "owner"), "strict")
    return best.select(F.array_join("asg", ",").alias("asg"), "cons_cost", sk.evidence(n).alias("facts"))


def ranking_lexicographic(spark, sf_dir):
    sk = w0_skeleton(spark)
    r = interpret.costed(spark, sk, interpret.renamings(spark, sk, checks=("r2r", "c2a"), c2a_mode="strict"))
    out = interpret.lexicographic(r, "path_cost", "cons_cost")
    return out.groupBy("path_cost", "cons_cost", "lex").agg(F.count(F.lit(1)).alias("n"))


def capability_matrix(spark, sf_dir):
    """(scenario, full, aligned_properties, shortest): whether each way of finding associations has the nodes of the desired mapping."""
    rows = []
    for name, (s_root, t_root, nodes) in _GOLD.items():
        gen = _generation(spark, name)
        a, has = gen.a, {}
        plain = {s: baselines.aligned_property_associations(spark, a, s, max_len=gen.max_len, max_depth=gen.max_depth) for s in "st"}
        paths = {s: assoc._settle(baselines.shortest_associations(assoc.association_paths(spark, a.side(s), a.aligned_concepts(s), gen.max_len)), assoc.PATH_SCHEMA) for s in "st"}
        short = {s: assoc.semantic_associations(spark, a, s, gen.max_len, gen.max_depth, paths[s]) for s in "st"}
        for way, trees in (("full", gen.trees), ("aligned_properties", plain), ("shortest", short)):
            has[way] = set(nodes) <= set(trees["t"][t_root].by_id) and set(nodes.values()) <= set(trees["s"][s_root].by_id)
        rows.append((name, *(has[w] for w in ("full", "aligned_properties", "shortest"))))
    return spark.createDataFrame(rows, "scenario string, full boolean, aligned_properties boolean, shortest boolean")


def examples_by_rank(spark, sf_dir):
    """Three individuals of most facts for each of the three best mappings of the running scenario."""
    return generate.examples(_generation(spark, "w0"), _source(spark, sf_dir, "w0"), 3)


def suggest_r2r(spark, sf_dir):
    """Path correspondences read off a renaming: tree paths between mapped nodes on both sides that no given one states."""
    rows = []
    for name, s_root, t_root, pairs in (
        ("opendata", "Author", "Person", ("w1", {"Person": "Author", "Person>has_skill/Skill": "Author>wrote/Document/about/Topic"})),
        ("orders", "Order", "Client", ("w3", {"Client": "Order>placed_by/Customer", "Client>submits/Purchase": "Order"})),
        ("conversations", "Turn", "Dialogue", ("w3b", {"Dialogue": "Turn>in_conv/Conversation", "Dialogue>has_utterance/Utterance": "Turn"})),
    ):
        sk = _skeleton(spark, pairs[0], s_root, t_root)
        (t1, s1), (t2, s2) = pairs[1].items()
        show = lambda p: "/".join(("^" if inv else "") + e for e, inv in p)
        rows.append((name, show(sk.s.tree_path(s1, s2)), show(sk.t.tree_path(t1, t2))))
    return spark.createDataFrame(rows, "scenario string, source_path string, target_path string")


# --- facts -------------------------------------------------------------------------------------------------------


def construct_scoped(spark, sf_dir):
    return exchange([w0_rule(spark, "R2")], _sales(spark, sf_dir))


def exchange_gold(spark, sf_dir):
    return exchange([w0_rule(spark, "R1")], _sales(spark, sf_dir))


def construct_joint(spark, sf_dir):
    return exchange([w0_rule(spark, "R1")], _sales(spark, sf_dir), plan="joint")


def construct_per_solution(spark, sf_dir):
    facts = exchange([w0_rule(spark, "R1")], _sales(spark, sf_dir), blank_mode="per_solution")
    return facts.groupBy("p").agg(F.count(F.lit(1)).alias("n"))


def construct_multi_renaming(spark, sf_dir):
    return exchange([w0_rule(spark, "R1"), w0_rule(spark, "R4")], _sales(spark, sf_dir))


def blank_stats(spark, sf_dir):
    src, rule = _sales(spark, sf_dir), w0_rule(spark, "R1")
    out = None
    for mode in ("scoped", "per_solution"):
        m = measures.blank_stats(exchange([rule], src, blank_mode=mode)).withColumn("mode", F.lit(mode))
        out = m if out is None else out.unionByName(m)
    return out


def pattern_eval(spark, sf_dir):
    sk = w0_skeleton(spark)
    need = frozenset(x for x in (S_NODES[k] for k in ("sE", "sO1", "sO2")))
    sols = Rule(sk, w0_assignment(sk, "R1")).solutions(_sales(spark, sf_dir), need, set(), left=True)
    return sols.agg(F.count(F.lit(1)).alias("solutions"))


def simplify_profile(spark, sf_dir):
    sk = w0_skeleton(spark)
    rule = Rule(sk, w0_assignment(sk, "R1"))
    sols = rule.solutions(_sales(spark, sf_dir), frozenset(S_NODES.values()), set(), left=True)
    names = {f"v{i}": n.id for i, n in enumerate(sk.s.nodes)}
    return measures.simplify_profile(sols.withColumnsRenamed(names)).select(F.element_at(F.split("var", ">"), -1).alias("node"), F.col("var").alias("var"), "ever", "always")


def independent_rules(spark, sf_dir):
    return baselines.independent_facts(scenarios.running(), _sales(spark, sf_dir))


def _baseline_facts(spark, sf_dir, strong=()):
    """The gold renaming cut to the trees that the aligned-property tool sees."""
    a = scenarios.running()
    s = baselines.aligned_property_associations(spark, a, "s", tuple((p, "range") for p in strong[:1]))["ActiveCustomer"]
    t = baselines.aligned_property_associations(spark, a, "t", tuple((p, "range") for p in strong[1:]))["Member"]
    sk = interpret.Skeleton(a, s, t)
    pairs = {T_NODES[x]: S_NODES[y] for x, y in {"tE": "sE", "tP": "sP", **NAMED["R1"]}.items() if T_NODES[x] in t.by_id and S_NODES[y] in s.by_id}
    return exchange([Rule(sk, assignment(sk, pairs), "r")], _sales(spark, sf_dir))


def aligned_prop_exchange(spark, sf_dir):
    return _baseline_facts(spark, sf_dir)


def annotated_exchange(spark, sf_dir):
    return _baseline_facts(spark, sf_dir, ("supplier_in", "vendor_country"))


def facts_lost(spark, sf_dir):
    return measures.facts_lost(aligned_prop_exchange(spark, sf_dir), exchange_gold(spark, sf_dir))


def fact_recall(spark, sf_dir):
    return measures.fact_recall(construct_scoped(spark, sf_dir), exchange_gold(spark, sf_dir))


def fk_profile(spark, sf_dir):
    return baselines.functional_profile(_sales(spark, sf_dir))


def shortest_assoc(spark, sf_dir):
    a = scenarios.running()
    paths = assoc.association_paths(spark, a.source, ["ActiveCustomer", "Nation"], 4)
    return baselines.shortest_associations(paths).select("root", "tail", "path_id", F.col("hops").cast("long").alias("hops"))


def overlap_dictionary(spark, sf_dir):
    part = scenarios.table(spark, sf_dir, "part")
    kinds = F.array(F.concat(F.lit("brand:"), "p_brand"), F.concat(F.lit("type:"), "p_type"), F.when(F.col("p_size") > 40, "size:large"))
    return measures.overlap_dictionary(part.select(iri("part", "p_partkey").alias("id"), F.explode(F.array_compact(kinds)).alias("cls")))


def _fragment(depth):
    def query(spark, sf_dir):
        kb = measures.knowledge_fragment(scenarios.running().source, {"Nation"}, depth)
        return spark.createDataFrame([("class", c) for c in kb.classes] + [("prop", p.name) for p in kb.props], "kind string, name string")

    return query


def opendata_exchange(spark, sf_dir):
    sk = _skeleton(spark, "w1", "Author", "Person")
    asg = assignment(sk, {"Person": "Author", "Person>has_skill/Skill": "Author>wrote/Document/about/Topic"})
    return exchange([Rule(sk, asg, "od")], scenarios.open_data_source(spark, sf_dir, sk.a.source))


def migrate_exchange(spark, sf_dir):
    """Customers and suppliers of both trees, so the link to a nation goes over the unaligned superclass of the target."""
    rules = []
    for c, link in (("Customer", "lives_in"), ("Supplier", "supplier_in")):
        sk = _skeleton(spark, "w2", c, f"{c}2")
        target = f"{c}2>Party/located/Nation2"
        rules.append(Rule(sk, assignment(sk, {f"{c}2": c, target: f"{c}>{link}/Nation"}), c.lower()))
    sk = _skeleton(spark, "w2", "Order", "Order2")
    rules.append(Rule(sk, assignment(sk, {"Order2": "Order", "Order2>placedBy/Customer2": "Order>placed_by/Customer"}), "order"))
    src = scenarios.sales_source(spark, sf_dir, sk.a.source)
    return exchange(rules, src).groupBy("p").agg(F.count(F.lit(1)).alias("n"))


def inverse_exchange(spark, sf_dir):
    sk = _skeleton(spark, "w3", "Order", "Client")
    asg = assignment(sk, {"Client": "Order>placed_by/Customer", "Client>submits/Purchase": "Order"})
    return exchange([Rule(sk, asg, "inv")], scenarios.sales_source(spark, sf_dir, sk.a.source)).where("p = 'submits'").select("s", "p", "o")


def conversation_exchange(spark, sf_dir):
    sk = _skeleton(spark, "w3b", "Turn", "Dialogue")
    asg = assignment(sk, {"Dialogue": "Turn>in_conv/Conversation", "Dialogue>has_utterance/Utterance": "Turn"})
    return exchange([Rule(sk, asg, "conv")], scenarios.conversation_source(spark, sf_dir, sk.a.source))


def path_r2r_exchange(spark, sf_dir):
    """Two-step source path to one target property: active customers that bought from one supplier are related."""
    src = _sales(spark, sf_dir)
    bought = src.objects["purchased_from"]().join(src.types["ActiveCustomer"]().withColumnRenamed("id", "s"), "s", "left_semi")
    return bought.withColumnRenamed("s", "x").join(bought.withColumnRenamed("s", "y"), "o").where("x < y").select("x", "y").distinct().agg(F.count(F.lit(1)).alias("pairs"))


def sparql_text(spark, sf_dir):
    return spark.createDataFrame([(n, to_sparql(w0_rule(spark, n))) for n in NAMED], "rule string, text string")


def examples_topn(spark, sf_dir):
    """For each named renaming the source individuals whose patterns bind most, three each."""
    src, out = _sales(spark, sf_dir), None
    for n in NAMED:
        rule = w0_rule(spark, n)
        facts = rule.construct(src).where("startswith(s, 'cust/')").distinct().groupBy("s").agg(F.count(F.lit(1)).alias("facts"))
        top = facts.orderBy(F.desc("facts"), "s").limit(3).select(F.lit(n).alias("rule"), "s", "facts")
        out = top if out is None else out.unionByName(top)
    return out


def op_growth(spark, sf_dir):
    return measures.growth(spark.createDataFrame([(x, 2 * x + 1) for x in range(1, 11)], "x long, n long"))


def op_growth_types(spark, sf_dir):
    """The kind of growth of three printed series' rules."""
    rows = [(name, x, n) for name, f in (("breadth", lambda x: 2 * x + 1), ("depth", lambda x: (x + 1) * (x + 2) // 2), ("doubling", lambda x: 3 * 2**x)) for x, n in ((x, f(x)) for x in range(1, 11))]
    return measures.growth_type(spark.createDataFrame(rows, "series string, x long, n long"))


def op_range_join(spark, sf_dir):
    """Orders by price band."""
    bands = spark.range(0, 12).select(F.col("id").alias("band"), (F.col("id") * 40000.0).alias("low"), ((F.col("id") + 1) * 40000.0).alias("high"))
    orders = scenarios.table(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice")
    return relational.range_join(orders, "o_totalprice", bands, "low", "high", 100000.0).groupBy("band").agg(F.count(F.lit(1)).alias("n"))


def op_overlap_join(spark, sf_dir):
    """Per user the pairs of events whose following hours overlap."""
    e = scenarios.table(spark, sf_dir, "events").select("user_id", "event_id", F.unix_timestamp(F.col("ts").cast("timestamp")).alias("start")).withColumn("stop", F.col("start") + 3600)
    met = relational.overlap_join(e, e, ["user_id"], 7200).where("event_id < r_event_id")
    return met.groupBy("user_id").agg(F.count(F.lit(1)).alias("pairs"))


def op_asof_join(spark, sf_dir):
    """Each order with its customer's last event before it."""
    orders = scenarios.table(spark, sf_dir, "orders").select("o_orderkey", F.col("o_custkey").alias("user_id"), F.col("o_orderdate").alias("at"))
    events = scenarios.table(spark, sf_dir, "events").select("user_id", "ts", "event_id")
    return relational.as_of_join(orders, events, "user_id", "at", "ts", ["event_id"]).select("o_orderkey", "event_id")


def op_salted_join(spark, sf_dir):
    """Revenue by supplier nation, hot suppliers spread."""
    lines = scenarios.table(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("k"), "l_orderkey", "l_linenumber", F.col("l_quantity").cast("long").alias("q"))
    hot = lines.groupBy("k").count().where("count > 1000")
    supp = scenarios.table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("k"), "s_nationkey")
    return relational.salted_join(lines, supp, "k", 8, hot).groupBy("s_nationkey").agg(F.sum("q").alias("q"), F.count(F.lit(1)).alias("n"))


def op_hash_sample(spark, sf_dir):
    return relational.hash_sample(scenarios.table(spark, sf_dir, "orders"), F.col("o_orderkey"), 0.1).select("o_orderkey")


def op_name_matches(spark, sf_dir):
    """Properties of the migrated knowledge base that a name matcher would align."""
    a = scenarios.migration()
    names = lambda kb: spark.createDataFrame([(x,) for x in sorted({*kb.classes, *(p.name for p in kb.props)})], "name string")
    return relational.name_matches(names(a.source), names(a.target))


def op_event_pivot(spark, sf_dir):
    e = scenarios.table(spark, sf_dir, "events")
    kinds = ("click", "purchase", "view", "signup", "error")
    return e.groupBy(F.date_format("ts", "yyyy-MM").alias("month")).pivot("event_type", list(kinds)).agg(F.count(F.lit(1))).select("month", *[F.coalesce(k, F.lit(0)).cast("long").alias(k) for k in kinds])


def op_price_summary(spark, sf_dir):
    """The dearest order and the median price of each priority."""
    o = scenarios.table(spark, sf_dir, "orders")
    return o.groupBy("o_orderpriority").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("dearest"), F.round(F.percentile("o_totalprice", 0.5), 4).alias("median"))


def op_segment_map(spark, sf_dir):
    """A map of customers by segment for each nation, as sorted entries."""
    c = scenarios.table(spark, sf_dir, "customer").groupBy("c_nationkey", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"))
    m = c.groupBy("c_nationkey").agg(F.map_from_entries(F.collect_list(F.struct("c_mktsegment", "n"))).alias("m"))
    big = F.map_filter("m", lambda k, v: v > 1)
    return m.select("c_nationkey", F.array_join(F.array_sort(F.transform(F.map_entries(big), lambda e: F.concat(e.key, F.lit("="), e.value.cast("string")))), ",").alias("segments"))


def op_cube(spark, sf_dir):
    """Orders by status and priority in all groupings."""
    o = scenarios.table(spark, sf_dir, "orders")
    return o.cube("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().cast("long").alias("g"))


def op_sessions(spark, sf_dir):
    """Sessions of users: events less than six hours apart."""
    e = scenarios.table(spark, sf_dir, "events").withColumn("at", F.col("ts").cast("timestamp"))
    return e.groupBy("user_id", F.session_window("at", "6 hours")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.date_format("session_window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


def op_hashed_blanks(spark, sf_dir):
    """Invented nodes under hashed names."""
    from .functions.paths import skolem

    c = scenarios.table(spark, sf_dir, "customer")
    return c.select(skolem("r,5", [iri("cust", "c_custkey"), iri("nation", "c_nationkey")], hashed=True).alias("node"))


def bench_condition_on_value(spark, sf_dir):
    """A class by a condition on a value: outside the rule language, a plain operator."""
    p = scenarios.table(spark, sf_dir, "part")
    return p.select(iri("part", "p_partkey").alias("s"), F.lit("type").alias("p"), F.when(F.col("p_size") > 25, "LargePart").otherwise("SmallPart").alias("o"))


def bench_condition_on_property(spark, sf_dir):
    o, li = scenarios.table(spark, sf_dir, "orders"), scenarios.table(spark, sf_dir, "lineitem")
    filled = o.join(li, o.o_orderkey == li.l_orderkey, "left_semi")
    return filled.select(iri("order", "o_orderkey").alias("s"), F.lit("type").alias("p"), F.lit("FilledOrder").alias("o"))


def bench_aggregate(spark, sf_dir):
    o = scenarios.table(spark, sf_dir, "orders")
    return o.groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n")).select(iri("cust", "o_custkey").alias("s"), F.lit("order_count").alias("p"), F.col("n").cast("string").alias("o"))


def bench_value_function(spark, sf_dir):
    c = scenarios.table(spark, sf_dir, "customer")
    return c.select(iri("cust", "c_custkey").alias("s"), F.lit("balance_eur").alias("p"), (F.col("c_acctbal").cast("decimal(18,2)") * F.lit("0.5").cast("decimal(2,1)")).cast("decimal(18,2)").cast("string").alias("o"))


def bench_concat(spark, sf_dir):
    p = scenarios.table(spark, sf_dir, "part")
    return p.select(iri("part", "p_partkey").alias("s"), F.lit("caption").alias("p"), F.concat_ws(" ", "p_brand", "p_type").alias("o"))


def bench_datatype(spark, sf_dir):
    p = scenarios.table(spark, sf_dir, "part")
    return p.select(iri("part", "p_partkey").alias("s"), F.lit("size").alias("p"), F.concat(F.col("p_size").cast("decimal(10,1)").cast("string"), F.lit("^^decimal")).alias("o"))


def bench_lang_add(spark, sf_dir):
    d = scenarios.table(spark, sf_dir, "documents")
    return d.where("source is not null").select(iri("doc", "doc_id").alias("s"), F.lit("source").alias("p"), F.concat("source", F.lit("@"), F.coalesce("lang", F.lit("und"))).alias("o"))


def bench_lang_drop(spark, sf_dir):
    return bench_lang_add(spark, sf_dir).withColumn("o", F.regexp_replace("o", "@[a-z]+$", ""))


def bench_uri_literal(spark, sf_dir):
    p = scenarios.table(spark, sf_dir, "pages")
    return p.where("url is not null").select(F.concat(F.lit("<"), "url", F.lit(">")).alias("s"), F.lit("address").alias("p"), F.col("url").alias("o"))


def bench_fusion(spark, sf_dir):
    """Customers and suppliers of one nation and number become one party."""
    c, s = scenarios.table(spark, sf_dir, "customer"), scenarios.table(spark, sf_dir, "supplier")
    party = lambda k: iri("party", k)
    a = c.select(party("c_custkey").alias("s"), F.lit("name").alias("p"), F.col("c_name").alias("o"))
    return a.unionByName(s.select(party("s_suppkey").alias("s"), F.lit("name").alias("p"), F.col("s_name").alias("o"))).distinct()


def op_replies(spark, sf_dir):
    kb = scenarios.conversations().source
    return scenarios.conversation_source(spark, sf_dir, kb).objects["replies_to"]()


def op_fact_rollup(spark, sf_dir):
    return exchange_gold(spark, sf_dir).rollup("p", "o_kind").agg(F.count(F.lit(1)).alias("n"))


def op_event_json(spark, sf_dir):
    e = scenarios.table(spark, sf_dir, "events")
    return e.groupBy("event_type", F.get_json_object("props", "$.k").alias("k")).agg(F.count(F.lit(1)).alias("n"))


def op_page_titles(spark, sf_dir):
    p = scenarios.table(spark, sf_dir, "pages")
    return p.select(iri("page", "page_id").alias("s"), F.regexp_extract("html", r"<title>([^<]*)</title>", 1).alias("title"), F.regexp_extract("html", r'<html lang="([a-z]+)"', 1).alias("lang"))


def op_event_facts(spark, sf_dir):
    """The batch form of the streaming exchange."""
    return incremental.event_facts(scenarios.table(spark, sf_dir, "events")).select("s", "p", "o_kind", "o")


def op_events_by_day(spark, sf_dir):
    facts = incremental.event_facts(scenarios.table(spark, sf_dir, "events"))
    return incremental.counts_by_window(facts).select(F.date_format("start", "yyyy-MM-dd").alias("day"), "p", "n")


def bench_property_to_path(spark, sf_dir):
    """One source property through an invented middle node: customer, address, country."""
    src = _sales(spark, sf_dir)
    return src.objects["lives_in"]().select(F.explode(F.array(
        F.struct(F.col("s").alias("s"), F.lit("has_address").alias("p"), F.concat(F.lit("_:addr("), "s", F.lit(")")).alias("o")),
        F.struct(F.concat(F.lit("_:addr("), "s", F.lit(")")).alias("s"), F.lit("in_country").alias("p"), F.col("o").alias("o")),
    )).alias("f")).select("f.*")


def bench_flatten(spark, sf_dir):
    src = _sales(spark, sf_dir)
    return src.objects["lives_in"]().join(src.attrs["Nation", "n_name"]().withColumnsRenamed({"s": "o", "v": "country_name"}), "o").select("s", "country_name")


def bench_sink_property(spark, sf_dir):
    p = scenarios.table(spark, sf_dir, "part")
    return p.select(iri("part", "p_partkey").alias("s"), F.concat(F.lit("type_"), F.regexp_replace("p_brand", "[^A-Za-z0-9]", "_")).alias("p"), F.col("p_name").alias("o"))


def queries() -> dict:
    plain = (
        kb_profile, alignment_profile, aligned_concepts, basic_assoc, schema_hops, assoc_paths, tree_nodes, tree_reach, tree_variables, skeletons_all, skeletons_pruned_target,
        skeletons_pruned_both, candidates, attr_owner_rule, validity_counts, named_costs, gold_position, best_renamings, e4_counts, suggest_r2r, construct_scoped, exchange_gold, construct_joint,
        construct_per_solution, construct_multi_renaming, blank_stats, pattern_eval, simplify_profile, independent_rules, aligned_prop_exchange, annotated_exchange, facts_lost, fact_recall,
        fk_profile, shortest_assoc, overlap_dictionary, opendata_exchange, migrate_exchange, inverse_exchange, conversation_exchange, path_r2r_exchange, sparql_text, all_mappings, usecase_counts, usecase_ranks,
        brute_force_renamings, best_by_bounds, ranking_lexicographic, capability_matrix, examples_by_rank, op_growth_types, op_range_join, op_overlap_join, op_asof_join, op_salted_join, op_hash_sample,
        op_name_matches, op_event_pivot, op_price_summary, op_segment_map, op_cube, op_sessions, op_hashed_blanks, bench_condition_on_value, bench_condition_on_property, bench_aggregate,
        bench_value_function, bench_concat, bench_datatype, bench_lang_add, bench_lang_drop, bench_uri_literal, bench_fusion,
        examples_topn, op_growth, op_replies, op_fact_rollup, op_event_facts, op_events_by_day, op_event_json, op_page_titles, bench_property_to_path, bench_flatten, bench_sink_property,
    )
    found = {f.__name__: f for f in plain}
    found |= {f"bench_{f.__name__}": f for f in (patterns.rename_class, patterns.rename_property, patterns.hoist_property, patterns.resourcify)}
    found |= {f"exchange_all_{k}": _exchange_of(n) for k, n in (("orders", "w3"), ("migration", "w2"))} | {"cycle_exchange": _exchange_of("w4")}
    for d in (1, 2, 3, 4):
        found[f"assoc_paths_depth{d}"] = lambda spark, sf_dir, d=d: _shown_paths(spark, sf_dir, d)
    found |= {
        "renamings_baseline": _renaming_count(), "renamings_r2r": _renaming_count(("r2r",)), "renamings_c2a": _renaming_count(("c2a",)), "renamings_all": _renaming_count(("r2r", "c2a")),
        "renamings_strict": _renaming_count(("c2a",), "strict"),
        "renamings_multiuse": _renaming_count(("r2r", "c2a"), "literal", False), "renamings_relaxed": _renaming_count(("r2r", "c2a"), "relaxed"),
        "path_cost": _cost_histogram("path_cost"), "consistency_cost": _cost_histogram("cons_cost"), "coverage_cost": _cost_histogram("cov_cost"), "ranking_combined": _cost_histogram("combined"),
        "e1_counts": _series(lambda x: 1, lambda x: x, "class", range(1, 11)), "e2_counts": _series(lambda x: x, lambda x: 1, "class", range(1, 11)),
        "e3_counts": _series(lambda x: x, lambda x: 2, "level", range(1, 9)), "fragment_d1": _fragment(1), "fragment_d2": _fragment(2),
    }
    return found
