"""DuckDB equivalents of the queries, written apart from the engine: recursion over inline schemas, brute-force
enumeration of renamings, closed forms of the series, and plain joins for facts."""

from __future__ import annotations

from .sources import patterns, scenarios

# --- schemas as inline tables ------------------------------------------------------------------------------------


def _values(rows) -> str:
    show = lambda x: "NULL" if x is None else f"'{x}'" if isinstance(x, str) else str(x)
    return ", ".join("(" + ", ".join(map(show, r)) + ")" for r in rows)


def _schema(side: str) -> str:
    a = scenarios.running()
    kb = a.source if side == "s" else a.target
    p = _values((p.name, p.domain, p.range) for p in kb.props)
    sub = _values(kb.subclasses)
    return f"""prop(prop, domain, range) AS (VALUES {p}),
sub(sub, sup) AS (VALUES {sub}),
hops AS (
  SELECT domain AS src, range AS dst, prop, 'obj' AS kind, false AS inv FROM prop WHERE range IS NOT NULL
  UNION SELECT range, domain, prop, 'obj', true FROM prop WHERE range IS NOT NULL
  UNION SELECT sub, sup, 'a', 'isa', false FROM sub)"""


def _paths(side: str, aligned: list[str], depth: int) -> str:
    inside = ", ".join(f"'{c}'" for c in aligned)
    piece = "CASE WHEN h.kind = 'isa' THEN h.dst ELSE CASE WHEN h.inv THEN '^' ELSE '' END || h.prop || '/' || h.dst END"
    return f"""{_schema(side)},
walk AS (
  SELECT h.src AS root, h.dst AS here, {piece} AS path_id, h.prop AS last, h.inv AS last_inv, h.src AS prev, 1 AS hops FROM hops h WHERE h.src IN ({inside}) AND NOT h.inv
  UNION ALL
  SELECT w.root, h.dst, w.path_id || '/' || {piece}, h.prop, h.inv, w.here, w.hops + 1 FROM walk w JOIN hops h ON h.src = w.here
  WHERE w.here NOT IN ({inside}) AND w.hops < {depth} AND NOT (h.prop = w.last AND h.inv <> w.last_inv AND h.dst = w.prev)),
paths AS (SELECT DISTINCT root, here AS tail, path_id, hops::BIGINT AS hops FROM walk WHERE here IN ({inside}))"""


def _shown_paths(aligned: list[str], depth: int) -> str:
    """Source paths over hops that hold facts, with the fewest facts on a step."""
    hops = ("hops AS (", "hops AS (SELECT src, dst, h0.prop, h0.kind, inv, n FROM hops0 h0 JOIN held ON held.name = CASE WHEN h0.kind = 'isa' THEN h0.src ELSE h0.prop END AND held.kind = CASE WHEN h0.kind = 'isa' THEN 'sub' ELSE 'prop' END WHERE n > 0)")
    text = _paths("s", aligned, depth)
    before, after = text.split(",\nwalk AS (")
    after = after.replace("1 AS hops FROM", "1 AS hops, h.n AS facts FROM").replace("w.hops + 1 FROM", "w.hops + 1, least(w.facts, h.n) FROM").replace("hops::BIGINT AS hops FROM", "hops::BIGINT AS hops, facts FROM")
    return f"{_COUNTS},\n{before.replace('hops AS (', 'hops0 AS (')},\n{hops[1]},\nwalk AS ({after}"


_ALIGNED = {"s": ["Customer", "Supplier", "ActiveCustomer", "Nation"], "t": ["Client", "Ledger", "Member", "Vendor", "Country"]}


def _tree(side: str, depth: int = 6) -> str:
    return f"""{_paths(side, _ALIGNED[side], 4)},
tree AS (
  SELECT DISTINCT c AS root, c AS node, NULL::VARCHAR AS parent, c AS concept, 0::BIGINT AS hop FROM (VALUES {_values((c,) for c in _ALIGNED[side])}) v(c)
  UNION ALL
  SELECT t.root, t.node || '>' || p.path_id, t.node, p.tail, t.hop + p.hops FROM tree t JOIN paths p ON p.root = t.concept WHERE t.hop + p.hops <= {depth})"""


def _skeletons(last: str) -> str:
    corr = [("c1", "Customer", None, "Client", None), ("c2", "Supplier", None, "Ledger", None), ("c3", "Customer", None, "Client", None), ("c4", "Customer", "Supplier", "Client", "Vendor"), ("c5", "ActiveCustomer", None, "Member", None), ("c6", "Supplier", None, "Vendor", None), ("c7", "Nation", None, "Country", None), ("c8", "Supplier", None, "Vendor", None), ("c9", "Nation", None, "Country", None)]
    attrs = {"s": [("Customer", 1), ("Supplier", 2), ("Nation", 1)], "t": [("Client", 1), ("Ledger", 1), ("Vendor", 1), ("Country", 1)]}
    tree = lambda s: _tree(s).replace("prop(", f"prop_{s}(").replace("FROM prop ", f"FROM prop_{s} ").replace("sub(sub", f"sub_{s}(sub").replace("FROM sub)", f"FROM sub_{s})").replace("hops AS (", f"hops_{s} AS (").replace("hops h", f"hops_{s} h").replace("walk AS (", f"walk_{s} AS (").replace("FROM walk ", f"FROM walk_{s} ").replace("paths AS (", f"paths_{s} AS (").replace("JOIN paths p", f"JOIN paths_{s} p").replace("tree AS (", f"tree_{s} AS (").replace("FROM tree t", f"FROM tree_{s} t")
    size = lambda s: f"size_{s} AS (SELECT root, (count(*) + coalesce(sum(n), 0))::BIGINT AS vars FROM tree_{s} LEFT JOIN (VALUES {_values(attrs[s])}) v(concept, n) USING (concept) GROUP BY root)"
    return f"""WITH RECURSIVE {tree("s")},
{tree("t")},
{size("s")}, {size("t")},
corr(id, s1, s2, t1, t2) AS (VALUES {_values(corr)}),
sc AS (SELECT DISTINCT a.root, c.id FROM corr c JOIN tree_s a ON a.concept = c.s1 WHERE c.s2 IS NULL OR EXISTS (SELECT 1 FROM tree_s b WHERE b.root = a.root AND b.concept = c.s2)),
tc AS (SELECT DISTINCT a.root, c.id FROM corr c JOIN tree_t a ON a.concept = c.t1 WHERE c.t2 IS NULL OR EXISTS (SELECT 1 FROM tree_t b WHERE b.root = a.root AND b.concept = c.t2)),
k AS (
  SELECT sc.root AS s_root, tc.root AS t_root, string_agg(id, ',' ORDER BY id) AS covered, any_value(size_s.vars) AS s_vars, any_value(size_t.vars) AS t_vars
  FROM sc JOIN tc USING (id) JOIN size_s ON size_s.root = sc.root JOIN size_t ON size_t.root = tc.root GROUP BY 1, 2),
k1 AS (SELECT * FROM k QUALIFY row_number() OVER (PARTITION BY s_root, covered ORDER BY t_vars, t_root) = 1),
k2 AS (SELECT * FROM k1 QUALIFY row_number() OVER (PARTITION BY t_root, covered ORDER BY s_vars, s_root) = 1)
SELECT * FROM {last}"""


# --- renamings by brute force ------------------------------------------------------------------------------------

# All functions of the free variables: vendors o, their labels l, countries c, their labels k, the ledger's balance b.
_ALL = """WITH o(v) AS (VALUES (0), (1), (2)), c(v) AS (VALUES (0), (1), (2), (3)),
f AS (
  SELECT o1.v AS o1, o2.v AS o2, l1.v AS l1, l2.v AS l2, c1.v AS c1, c2.v AS c2, k1.v AS k1, k2.v AS k2, b.v AS b
  FROM o o1, o o2, o l1, o l2, c c1, c c2, c k1, c k2, o b
  WHERE o1.v + o2.v > 0 AND l1.v + l2.v > 0 AND c1.v + c2.v > 0 AND k1.v + k2.v > 0 AND b.v > 0),
g AS (
  SELECT *, (o1 = 0 OR o1 <> o2) AND (l1 = 0 OR l1 <> l2) AND (c1 = 0 OR c1 <> c2) AND (k1 = 0 OR k1 <> k2) AS once, o1 = 1 AS r2r,
    (o1 = 0 OR l1 = o1) AND (o2 = 0 OR l2 = o2) AND (c1 = 0 OR k1 = c1) AND (c2 = 0 OR k2 = c2) AS literal,
    (o1 = 0 OR l1 IN (0, o1)) AND (o2 = 0 OR l2 IN (0, o2)) AND (c1 = 0 OR k1 IN (0, c1)) AND (c2 = 0 OR k2 IN (0, c2)) AS relaxed,
    l1 = o1 AND l2 = o2 AND k1 = c1 AND k2 = c2 AS strict, b IN (o1, o2) AS owner
  FROM f)
"""

# --- facts -------------------------------------------------------------------------------------------------------

_SALES = """active AS (SELECT c_custkey AS c, c_name, c_nationkey FROM customer WHERE c_custkey IN (SELECT user_id FROM events)),
bought AS (SELECT DISTINCT o_custkey AS c, l_suppkey AS s FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE l_returnflag <> 'R'),
gaveback AS (SELECT DISTINCT o_custkey AS c, l_suppkey AS s FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE l_returnflag = 'R'),
b AS (SELECT c, s FROM bought JOIN active USING (c)), r AS (SELECT c, s FROM gaveback JOIN active USING (c))"""

# Facts of the running scenario's source elements: active customers and their superclass, edges with both ends at hand, values.
_COUNTS = f"""{_SALES},
held(kind, name, n) AS (
  SELECT 'class', 'Customer', count(DISTINCT c_custkey) FROM customer UNION ALL SELECT 'class', 'Supplier', count(DISTINCT s_suppkey) FROM supplier
  UNION ALL SELECT 'class', 'Nation', count(DISTINCT n_nationkey) FROM nation UNION ALL SELECT 'class', 'ActiveCustomer', count(DISTINCT c) FROM active
  UNION ALL SELECT 'sub', 'ActiveCustomer', count(DISTINCT c) FROM active
  UNION ALL SELECT 'prop', 'c_name', count(c_name) FROM customer UNION ALL SELECT 'prop', 's_name', count(s_name) FROM supplier
  UNION ALL SELECT 'prop', 's_acctbal', count(s_acctbal) FROM supplier UNION ALL SELECT 'prop', 'n_name', count(n_name) FROM nation
  UNION ALL SELECT 'prop', 'purchased_from', count(*) FROM bought WHERE c IN (SELECT c_custkey FROM customer) AND s IN (SELECT s_suppkey FROM supplier)
  UNION ALL SELECT 'prop', 'returned_to', count(*) FROM gaveback WHERE c IN (SELECT c_custkey FROM customer) AND s IN (SELECT s_suppkey FROM supplier)
  UNION ALL SELECT 'prop', 'supplier_in', count(*) FROM supplier WHERE s_nationkey IN (SELECT n_nationkey FROM nation)
  UNION ALL SELECT 'prop', 'lives_in', count(*) FROM customer WHERE c_nationkey IN (SELECT n_nationkey FROM nation))"""


# Renamings by the owner rule with the facts that each takes: the root and its superclass with the name, then each free variable's.
_OWNED = f"""{_ALL}, {_COUNTS},
k AS (SELECT max(n) FILTER (WHERE name = 'ActiveCustomer' AND kind = 'class') AS a, max(n) FILTER (WHERE kind = 'sub') AS u, max(n) FILTER (WHERE name = 'c_name') AS m,
  max(n) FILTER (WHERE name = 'purchased_from') AS p, max(n) FILTER (WHERE name = 'returned_to') AS r, max(n) FILTER (WHERE name = 's_name') AS l,
  max(n) FILTER (WHERE name = 'supplier_in') AS i, max(n) FILTER (WHERE name = 'lives_in') AS h, max(n) FILTER (WHERE name = 'n_name') AS d, max(n) FILTER (WHERE name = 's_acctbal') AS e FROM held),
t AS (
  SELECT a + u + m + CASE o1 WHEN 1 THEN p WHEN 2 THEN k.r ELSE 0 END + CASE o2 WHEN 1 THEN p WHEN 2 THEN k.r ELSE 0 END + l * ((l1 > 0)::INT + (l2 > 0)::INT)
    + CASE c1 WHEN 0 THEN 0 WHEN 3 THEN h ELSE i END + CASE c2 WHEN 0 THEN 0 WHEN 3 THEN h ELSE i END + d * ((k1 > 0)::INT + (k2 > 0)::INT) + e AS facts
  FROM g, k WHERE once AND strict AND r2r AND owner AND a > 0 AND a = u)
SELECT count(*)::BIGINT AS n, min(facts)::BIGINT AS least, max(facts)::BIGINT AS most FROM t"""


def _facts(returns: bool, only_aligned: bool = False, extra: str = "") -> str:
    vendors = "SELECT s FROM b UNION SELECT s FROM r" if returns else "SELECT s FROM b"
    parts = [
        "SELECT 'cust/' || c AS s, 'type' AS p, 'iri' AS o_kind, 'Member' AS o FROM active",
        "SELECT 'cust/' || c, 'type', 'iri', 'Client' FROM active",
        "SELECT 'cust/' || c, 'name', 'lit', c_name FROM active",
        "SELECT 'cust/' || c, 'deals_with', 'iri', 'supp/' || s FROM b",
        "SELECT 'supp/' || s, 'type', 'iri', 'Vendor' FROM v",
        "SELECT 'supp/' || s, 'vendor_label', 'lit', s_name FROM v JOIN supplier ON s_suppkey = s",
    ]
    nations = [
        "SELECT 'supp/' || s, 'vendor_country', 'iri', 'nation/' || s_nationkey FROM v JOIN supplier ON s_suppkey = s",
        "SELECT 'nation/' || s_nationkey, 'type', 'iri', 'Country' FROM v JOIN supplier ON s_suppkey = s",
        "SELECT 'nation/' || s_nationkey, 'country_label', 'lit', n_name FROM v JOIN supplier ON s_suppkey = s JOIN nation ON n_nationkey = s_nationkey",
    ]
    ledgers = [
        "SELECT 'cust/' || c, 'has_ledger', 'blank', '_:r,5(cust/' || c || ',supp/' || s || ')' FROM b",
        "SELECT '_:r,5(cust/' || c || ',supp/' || s || ')', 'type', 'iri', 'Ledger' FROM b",
        "SELECT '_:r,5(cust/' || c || ',supp/' || s || ')', 'ledger_balance', 'lit', CAST(CAST(s_acctbal AS DECIMAL(18,2)) AS VARCHAR) FROM b JOIN supplier ON s_suppkey = s",
    ]
    if only_aligned != "bare":
        parts += nations
    if not only_aligned:
        parts += ledgers
        if returns:
            parts.append("SELECT 'cust/' || c, 'sent_back_to', 'iri', 'supp/' || s FROM r")
    return f"WITH {_SALES},\nv AS ({vendors}),\nfacts AS ({' UNION '.join([*parts, *([extra] if extra else [])])})\n"


_LINKED = "SELECT 'supp/' || s AS s, 'vendor_country' AS p, 'iri' AS o_kind, 'nation/' || c_nationkey AS o FROM b JOIN active USING (c)"
_LINKED_TYPES = " UNION SELECT 'nation/' || c_nationkey, 'type', 'iri', 'Country' FROM b JOIN active USING (c) UNION SELECT 'nation/' || c_nationkey, 'country_label', 'lit', n_name FROM b JOIN active USING (c) JOIN nation ON n_nationkey = c_nationkey"
_SOLUTIONS = f"""WITH {_SALES},
nb AS (SELECT c, count(*) AS n FROM b GROUP BY c), nr AS (SELECT c, count(*) AS n FROM r GROUP BY c),
per AS (SELECT c, greatest(coalesce(nb.n, 0), 1) * greatest(coalesce(nr.n, 0), 1) AS n, coalesce(nb.n, 0) * greatest(coalesce(nr.n, 0), 1) AS with_b FROM active LEFT JOIN nb USING (c) LEFT JOIN nr USING (c))
"""


def _names(kb) -> list[str]:
    return sorted({*kb.classes, *(p.name for p in kb.props)})


def oracle_sql() -> dict[str, str]:
    def shown_depth(d):
        return f"WITH RECURSIVE {_shown_paths(['ActiveCustomer', 'Nation'], d)} SELECT root, tail, path_id, hops, facts FROM paths"

    def count(where):
        return f"{_ALL}SELECT count(*)::BIGINT AS n FROM g WHERE {where}"

    gold, sparse = _facts(True), _facts(False)
    return patterns.SQL | {
        "op_event_facts": "SELECT 'event/' || event_id AS s, 'type' AS p, 'iri' AS o_kind, upper(event_type[1]) || lower(event_type[2:]) AS o FROM events UNION SELECT 'event/' || event_id, 'done_by', 'iri', 'cust/' || user_id FROM events UNION SELECT 'event/' || event_id, 'amount', 'lit', CAST(CAST(value AS DECIMAL(18,2)) AS VARCHAR) FROM events WHERE value IS NOT NULL",
        "op_events_by_day": "SELECT strftime(ts, '%Y-%m-%d') AS day, p, count(*) AS n FROM events, (VALUES ('type'), ('done_by'), ('amount')) v(p) GROUP BY 1, 2",
        "kb_profile": "SELECT * FROM (VALUES ('src', 4::BIGINT, 4::BIGINT, 4::BIGINT), ('tgt', 5, 4, 4)) v(kb, classes, attributes, object_properties)",
        "alignment_profile": f"WITH {_COUNTS}, m(corr, name) AS (VALUES ('c2c', 'Customer'), ('c2c', 'Supplier'), ('c2c', 'Nation'), ('c2c', 'ActiveCustomer'), ('a2a', 'c_name'), ('a2a', 's_acctbal'), ('a2a', 's_name'), ('a2a', 'n_name'), ('r2r', 'purchased_from')) SELECT corr AS kind, count(*) FILTER (WHERE n > 0)::BIGINT AS n, sum(n)::BIGINT AS facts FROM m JOIN held USING (name) WHERE kind <> 'sub' GROUP BY 1",
        "aligned_concepts": f"WITH {_COUNTS}, m(side, concept, name) AS (VALUES ('s', 'Customer', 'Customer'), ('s', 'Supplier', 'Supplier'), ('s', 'ActiveCustomer', 'ActiveCustomer'), ('s', 'Nation', 'Nation'), ('t', 'Client', 'Customer'), ('t', 'Client', 'c_name'), ('t', 'Ledger', 's_acctbal'), ('t', 'Member', 'ActiveCustomer'), ('t', 'Vendor', 'Supplier'), ('t', 'Vendor', 's_name'), ('t', 'Country', 'Nation'), ('t', 'Country', 'n_name')) SELECT side, concept, max(n) AS instances FROM m JOIN held USING (name) WHERE kind <> 'sub' GROUP BY 1, 2 HAVING max(n) > 0",
        "basic_assoc": f"""WITH {_COUNTS}, m(side, concept, class, attr, name) AS (VALUES ('s', 'Customer', 'Customer', 'c_name', 'c_name'), ('s', 'Supplier', 'Supplier', 's_acctbal', 's_acctbal'), ('s', 'Supplier', 'Supplier', 's_name', 's_name'), ('s', 'ActiveCustomer', 'ActiveCustomer', NULL, NULL), ('s', 'Nation', 'Nation', 'n_name', 'n_name'),
  ('t', 'Client', 'Customer', 'name', 'c_name'), ('t', 'Ledger', 'Supplier', 'ledger_balance', 's_acctbal'), ('t', 'Member', 'ActiveCustomer', NULL, NULL), ('t', 'Vendor', 'Supplier', 'vendor_label', 's_name'), ('t', 'Country', 'Nation', 'country_label', 'n_name'))
SELECT side, concept, coalesce(string_agg(attr, ',' ORDER BY attr) FILTER (WHERE held.n > 0), '') AS attrs, coalesce(sum(held.n), 0)::BIGINT AS facts
FROM m JOIN held c ON c.kind = 'class' AND c.name = class AND c.n > 0 LEFT JOIN held ON held.kind = 'prop' AND held.name = m.name GROUP BY 1, 2""",
        "schema_hops": f"WITH {_schema('s')} SELECT src, dst, prop, kind, inv FROM hops",
        "assoc_paths": f"SELECT * FROM (WITH RECURSIVE {_shown_paths(_ALIGNED['s'], 4)} SELECT 's' AS side, root, tail, path_id, hops, facts FROM paths) UNION ALL SELECT * FROM (WITH RECURSIVE {_paths('t', _ALIGNED['t'], 4)} SELECT 't' AS side, root, tail, path_id, hops, NULL::BIGINT AS facts FROM paths)",
        **{f"assoc_paths_depth{d}": shown_depth(d) for d in (1, 2, 3, 4)},
        "shortest_assoc": f"WITH RECURSIVE {_paths('s', ['ActiveCustomer', 'Nation'], 4)} SELECT root, tail, path_id, hops FROM paths QUALIFY rank() OVER (PARTITION BY root, tail ORDER BY hops) = 1",
        "tree_nodes": " UNION ALL ".join(f"SELECT * FROM (WITH RECURSIVE {_tree(s)} SELECT '{s}' AS side, root, node, concept, hop FROM tree)" for s in "st"),
        "tree_reach": f"WITH RECURSIVE {_tree('s')}, up AS (SELECT root, node AS desc_, parent AS anc FROM tree WHERE parent IS NOT NULL UNION ALL SELECT u.root, u.desc_, t.parent FROM up u JOIN tree t ON t.root = u.root AND t.node = u.anc WHERE t.parent IS NOT NULL) SELECT root, anc, desc_ AS \"desc\" FROM up",
        "tree_variables": "SELECT * FROM (VALUES ('s', 'ActiveCustomer', 7::BIGINT, 15::BIGINT), ('s', 'Customer', 6, 14), ('s', 'Supplier', 2, 5), ('s', 'Nation', 1, 2), ('t', 'Member', 7, 13), ('t', 'Client', 6, 12), ('t', 'Vendor', 2, 4), ('t', 'Country', 1, 2), ('t', 'Ledger', 1, 2)) v(side, root, nodes, variables)",
        "skeletons_all": _skeletons("k"), "skeletons_pruned_target": _skeletons("k1"), "skeletons_pruned_both": _skeletons("k2"),
        "renamings_baseline": count("once"), "renamings_r2r": count("once AND r2r"), "renamings_c2a": count("once AND literal"), "renamings_all": count("once AND literal AND r2r"),
        "renamings_strict": count("once AND strict"), "attr_owner_rule": _OWNED, "renamings_relaxed": count("once AND relaxed AND r2r"), "renamings_multiuse": count("literal AND r2r"),
        "validity_counts": f"{_ALL}SELECT mode, count(*) FILTER (WHERE once)::BIGINT AS baseline, count(*) FILTER (WHERE once AND r2r)::BIGINT AS r2r, count(*) FILTER (WHERE once AND ok)::BIGINT AS c2a, count(*) FILTER (WHERE once AND ok AND r2r)::BIGINT AS \"both\" FROM (SELECT *, 'literal' AS mode, literal AS ok FROM g UNION ALL SELECT *, 'strict', strict FROM g) GROUP BY mode",
        "path_cost": f"{_ALL}, h AS (SELECT (c1 = 3)::BIGINT + (c2 = 3)::BIGINT AS cost, count(*) AS equal FROM g WHERE once AND strict AND r2r GROUP BY 1) SELECT cost, equal::BIGINT AS equal, coalesce(sum(equal) OVER (ORDER BY cost ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS better, dense_rank() OVER (ORDER BY cost)::BIGINT AS rank FROM h",
        "coverage_cost": f"{_ALL}, h AS (SELECT (1 + 2 * ((o1 = 0)::INT + (o2 = 0)::INT + (c1 = 0)::INT + (c2 = 0)::INT))::BIGINT AS cost, count(*) AS equal FROM g WHERE once AND strict AND r2r GROUP BY 1) SELECT cost, equal::BIGINT AS equal, coalesce(sum(equal) OVER (ORDER BY cost ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS better, dense_rank() OVER (ORDER BY cost)::BIGINT AS rank FROM h",
        "named_costs": "SELECT * FROM (VALUES ('R1', 0::BIGINT, 0::BIGINT, 1::BIGINT, 1::BIGINT), ('R2', 0, 0, 1, 5), ('R3', 0, 4, 9, 1), ('R4', 1, 1, 3, 1)) v(name, path_cost, cons_nodes, cons_cost, cov_cost)",
        "e1_counts": "SELECT x, 2 * x + 1 AS mappings, abs(2 * x + 1 - (x + 1 + 10)) AS delta, 2::BIGINT AS delta_counted FROM (SELECT unnest(range(1, 11)) AS x)",
        "e2_counts": "SELECT x, (x + 1) * (x + 2) // 2 AS mappings, abs((x + 1) * (x + 2) // 2 - (x + 1 + 10)) AS delta, abs((x + 1) * (x + 2) // 2 - (2 * x + 3)) AS delta_counted FROM (SELECT unnest(range(1, 11)) AS x)",
        "e3_counts": "SELECT x, (2 ** (x + 1))::BIGINT - 1 + x * (x + 1) // 2 AS mappings, abs(x * (x + 1) // 2 - 10) AS delta, abs(x * (x + 1) // 2 - (x + 2)) AS delta_counted FROM (SELECT unnest(range(1, 9)) AS x)",
        "e4_counts": "WITH m AS (SELECT k, k + 1 AS o, k + 2 AS c FROM (SELECT unnest(range(1, 4)) AS k)), p AS (SELECT *, o * o + o AS po, c * c + c AS pc, o * (o - 1) + 2 * o * o AS go, c * (c - 1) + 2 * c * c AS gc FROM m) SELECT k, po * po * pc * pc * o AS baseline, o * pc * po * pc * o AS r2r, go * gc * o AS c2a, po * pc * o AS strict FROM p",
        "suggest_r2r": "SELECT * FROM (VALUES ('opendata', 'wrote/about', 'has_skill'), ('orders', '^placed_by', 'submits'), ('conversations', '^in_conv', 'has_utterance')) v(scenario, source_path, target_path)",
        "fragment_d1": "SELECT * FROM (VALUES ('class', 'Customer'), ('class', 'Supplier'), ('class', 'Nation'), ('prop', 'c_name'), ('prop', 's_name'), ('prop', 's_acctbal'), ('prop', 'n_name'), ('prop', 'supplier_in'), ('prop', 'lives_in')) v(kind, name)",
        "fragment_d2": "SELECT * FROM (VALUES ('class', 'Customer'), ('class', 'Supplier'), ('class', 'Nation'), ('class', 'ActiveCustomer'), ('prop', 'c_name'), ('prop', 's_name'), ('prop', 's_acctbal'), ('prop', 'n_name'), ('prop', 'supplier_in'), ('prop', 'lives_in'), ('prop', 'purchased_from'), ('prop', 'returned_to')) v(kind, name)",
        "construct_scoped": f"{sparse}SELECT * FROM facts", "exchange_gold": f"{gold}SELECT * FROM facts", "construct_joint": f"{gold}SELECT * FROM facts",
        "construct_multi_renaming": f"{_facts(True, False, _LINKED + _LINKED_TYPES)}SELECT * FROM facts",
        "aligned_prop_exchange": f"{_facts(False, 'bare')}SELECT * FROM facts", "annotated_exchange": f"{_facts(False, True)}SELECT * FROM facts",
        "facts_lost": f"{gold}, kept AS ({_facts(False, 'bare')}SELECT * FROM facts) SELECT p, count(*) AS lost FROM (SELECT * FROM facts EXCEPT SELECT * FROM kept) GROUP BY p",
        "fact_recall": f"{gold}, part AS ({sparse}SELECT * FROM facts), n AS (SELECT (SELECT count(*) FROM facts JOIN part USING (s, p, o)) AS hits, (SELECT count(*) FROM part) AS produced, (SELECT count(*) FROM facts) AS gold) SELECT hits, produced, gold, round(hits / gold, 6) AS recall, round(hits / produced, 6) AS precision, round(2 * hits / (gold + produced), 6) AS f1 FROM n",
        "construct_per_solution": f"{gold}, sols AS ({_SOLUTIONS}SELECT sum(n) AS n, sum(with_b) AS w FROM per), k AS (SELECT p, count(*) AS n FROM facts WHERE p NOT IN ('has_ledger', 'ledger_balance') AND o <> 'Ledger' GROUP BY p) SELECT p, (n + CASE WHEN p = 'type' THEN (SELECT n FROM sols) ELSE 0 END)::BIGINT AS n FROM k UNION ALL SELECT 'has_ledger', (SELECT n FROM sols)::BIGINT UNION ALL SELECT 'ledger_balance', (SELECT w FROM sols)::BIGINT",
        "blank_stats": f"SELECT 'scoped' AS mode, (SELECT count(*) FROM ({gold}SELECT DISTINCT s FROM facts WHERE s LIKE '\\_:%' ESCAPE '\\')) AS invented, 0::BIGINT AS bare UNION ALL SELECT 'per_solution', (SELECT sum(n) FROM ({_SOLUTIONS}SELECT * FROM per))::BIGINT, (SELECT sum(n - with_b) FROM ({_SOLUTIONS}SELECT * FROM per))::BIGINT",
        "pattern_eval": f"{_SOLUTIONS}SELECT sum(n)::BIGINT AS solutions FROM per",
        "independent_rules": f"""WITH {_SALES} SELECT '_:c1(cust/' || c_custkey || ')' AS s, 'type' AS p, 'iri' AS o_kind, 'Client' AS o FROM customer UNION SELECT '_:c1(cust/' || c_custkey || ')', 'name', 'lit', c_name FROM customer
UNION SELECT '_:c2(supp/' || s_suppkey || ')', 'type', 'iri', 'Ledger' FROM supplier UNION SELECT '_:c2(supp/' || s_suppkey || ')', 'ledger_balance', 'lit', CAST(CAST(s_acctbal AS DECIMAL(18,2)) AS VARCHAR) FROM supplier
UNION SELECT '_:c8(supp/' || s_suppkey || ')', 'type', 'iri', 'Vendor' FROM supplier UNION SELECT '_:c8(supp/' || s_suppkey || ')', 'vendor_label', 'lit', s_name FROM supplier
UNION SELECT '_:c9(nation/' || n_nationkey || ')', 'type', 'iri', 'Country' FROM nation UNION SELECT '_:c9(nation/' || n_nationkey || ')', 'country_label', 'lit', n_name FROM nation
UNION SELECT 'cust/' || c_custkey, 'type', 'iri', 'Client' FROM customer UNION SELECT 'cust/' || c, 'type', 'iri', 'Member' FROM active UNION SELECT 'supp/' || s_suppkey, 'type', 'iri', 'Vendor' FROM supplier
UNION SELECT 'nation/' || n_nationkey, 'type', 'iri', 'Country' FROM nation UNION SELECT 'cust/' || c, 'deals_with', 'iri', 'supp/' || s FROM bought""",
        "fk_profile": f"WITH {_SALES}, n AS (SELECT count(*) AS c FROM customer), s AS (SELECT count(*) AS c FROM supplier), x AS (SELECT 'purchased_from' AS prop, (SELECT count(DISTINCT c) FROM bought) AS subjects, (SELECT count(*) FROM bought) AS facts, (SELECT c FROM n) AS typed UNION ALL SELECT 'returned_to', (SELECT count(DISTINCT c) FROM gaveback), (SELECT count(*) FROM gaveback), (SELECT c FROM n) UNION ALL SELECT 'supplier_in', (SELECT c FROM s), (SELECT c FROM s), (SELECT c FROM s) UNION ALL SELECT 'lives_in', (SELECT c FROM n), (SELECT c FROM n), (SELECT c FROM n)) SELECT *, subjects = facts AND subjects = typed AS fk FROM x",
        "opendata_exchange": "WITH l AS (SELECT DISTINCT source, label FROM documents JOIN embeddings ON vec_id = doc_id) SELECT 'author/' || source AS s, 'type' AS p, 'iri' AS o_kind, 'Person' AS o FROM documents UNION SELECT 'author/' || source, 'has_skill', 'iri', 'topic/' || label FROM l UNION SELECT 'topic/' || label, 'type', 'iri', 'Skill' FROM l UNION SELECT 'topic/' || label, 'skill_label', 'lit', label::VARCHAR FROM l",
        "migrate_exchange": "SELECT 'located' AS p, (SELECT count(*) FROM customer) + (SELECT count(*) FROM supplier) AS n UNION ALL SELECT 'name', count(*) FROM customer UNION ALL SELECT 'placedBy', count(*) FROM orders UNION ALL SELECT 'nation_name', count(*) FROM (SELECT c_nationkey FROM customer UNION SELECT s_nationkey FROM supplier) UNION ALL SELECT 'type', 2 * (SELECT count(*) FROM customer) + 2 * (SELECT count(*) FROM supplier) + (SELECT count(*) FROM orders) + (SELECT count(*) FROM (SELECT c_nationkey FROM customer UNION SELECT s_nationkey FROM supplier))",
        "inverse_exchange": "SELECT 'cust/' || o_custkey AS s, 'submits' AS p, 'order/' || o_orderkey AS o FROM orders",
        "conversation_exchange": "SELECT DISTINCT 'conv/' || conv_id AS s, 'type' AS p, 'iri' AS o_kind, 'Dialogue' AS o FROM conversations UNION SELECT 'turn/' || conv_id || '.' || turn, 'type', 'iri', 'Utterance' FROM conversations UNION SELECT 'conv/' || conv_id, 'has_utterance', 'iri', 'turn/' || conv_id || '.' || turn FROM conversations UNION SELECT 'turn/' || conv_id || '.' || turn, 'speaker', 'lit', role FROM conversations",
        "cycle_exchange": """WITH t AS (SELECT 'turn/' || conv_id || '.' || turn AS k, 'conv/' || conv_id AS c, role, 'turn/' || conv_id || '.' || lag(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS before FROM conversations)
SELECT k AS s, 'type' AS p, 'iri' AS o_kind, 'Utterance' AS o FROM t UNION SELECT k, 'speaker', 'lit', role FROM t WHERE role IS NOT NULL UNION SELECT k, 'answers', 'iri', before FROM t WHERE before IS NOT NULL
UNION SELECT k, 'part_of', 'iri', c FROM t UNION SELECT c, 'type', 'iri', 'Dialogue' FROM t""",
        "exchange_all_orders": """SELECT 'cust/' || c_custkey AS s, 'type' AS p, 'iri' AS o_kind, 'Client' AS o FROM customer UNION SELECT 'order/' || o_orderkey, 'type', 'iri', 'Purchase' FROM orders
UNION SELECT 'order/' || o_orderkey, 'status', 'lit', o_orderstatus FROM orders UNION SELECT 'cust/' || o_custkey, 'submits', 'iri', 'order/' || o_orderkey FROM orders""",
        "op_growth_types": "SELECT * FROM (VALUES ('breadth', 'linear'), ('depth', 'quadratic'), ('doubling', 'exponential')) v(series, growth)",
        "op_range_join": "SELECT floor(o_totalprice / 40000)::BIGINT AS band, count(*) AS n FROM orders WHERE o_totalprice >= 0 AND o_totalprice < 480000 GROUP BY 1",
        "op_overlap_join": "SELECT a.user_id, count(*) AS pairs FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id < b.event_id AND abs(epoch(date_trunc('second', a.ts)) - epoch(date_trunc('second', b.ts))) < 3600 GROUP BY 1",
        "op_asof_join": "SELECT o_orderkey, (SELECT max_by(event_id, (ts, event_id)) FROM events e WHERE e.user_id = o.o_custkey AND e.ts <= o.o_orderdate) AS event_id FROM orders o",
        "op_salted_join": "SELECT s_nationkey, sum(l_quantity::BIGINT)::BIGINT AS q, count(*) AS n FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1",
        "op_hash_sample": "SELECT o_orderkey FROM orders WHERE ('0x' || substr(md5(o_orderkey::VARCHAR || ':7'), 1, 8))::BIGINT / 4294967296.0::DOUBLE < 0.1",
        "op_name_matches": f"""WITH a(l) AS (VALUES {_values((x,) for x in _names(scenarios.migration().source))}), b(r) AS (VALUES {_values((x,) for x in _names(scenarios.migration().target))})
SELECT l, r, round(1 - levenshtein(lower(l), lower(r)) / greatest(length(l), length(r)), 6) AS score FROM a, b WHERE 1 - levenshtein(lower(l), lower(r)) / greatest(length(l), length(r)) >= 0.6""",
        "op_event_pivot": "SELECT strftime(ts, '%Y-%m') AS month, " + ", ".join(f"count(*) FILTER (WHERE event_type = '{k}') AS {k}" for k in ("click", "purchase", "view", "signup", "error")) + " FROM events GROUP BY 1",
        "op_price_summary": "SELECT o_orderpriority, max_by(o_orderkey, (o_totalprice, o_orderkey)) AS dearest, round(quantile_cont(o_totalprice, 0.5), 4) AS median FROM orders GROUP BY 1",
        "op_segment_map": "WITH c AS (SELECT c_nationkey, c_mktsegment, count(*) AS n FROM customer GROUP BY 1, 2) SELECT c_nationkey, coalesce(string_agg(c_mktsegment || '=' || n, ',' ORDER BY c_mktsegment || '=' || n) FILTER (WHERE n > 1), '') AS segments FROM c GROUP BY 1",
        "op_cube": "SELECT o_orderstatus, o_orderpriority, count(*) AS n, grouping_id(o_orderstatus, o_orderpriority)::BIGINT AS g FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)",
        "op_sessions": """WITH g AS (SELECT user_id, ts, sum(CASE WHEN ts - before < INTERVAL 6 HOUR THEN 0 ELSE 1 END) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k
  FROM (SELECT *, lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before FROM events))
SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM g GROUP BY user_id, k""",
        "op_hashed_blanks": "SELECT '_:' || sha256('_:r,5(cust/' || c_custkey || ',nation/' || c_nationkey || ')') AS node FROM customer",
        "bench_condition_on_value": "SELECT 'part/' || p_partkey AS s, 'type' AS p, CASE WHEN p_size > 25 THEN 'LargePart' ELSE 'SmallPart' END AS o FROM part",
        "bench_condition_on_property": "SELECT 'order/' || o_orderkey AS s, 'type' AS p, 'FilledOrder' AS o FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem)",
        "bench_aggregate": "SELECT 'cust/' || o_custkey AS s, 'order_count' AS p, count(*)::VARCHAR AS o FROM orders GROUP BY o_custkey",
        "bench_value_function": "SELECT 'cust/' || c_custkey AS s, 'balance_eur' AS p, (c_acctbal::DECIMAL(16,2) * 0.5::DECIMAL(2,1))::DECIMAL(18,2)::VARCHAR AS o FROM customer",
        "bench_concat": "SELECT 'part/' || p_partkey AS s, 'caption' AS p, concat_ws(' ', p_brand, p_type) AS o FROM part",
        "bench_datatype": "SELECT 'part/' || p_partkey AS s, 'size' AS p, p_size::DECIMAL(10,1)::VARCHAR || '^^decimal' AS o FROM part",
        "bench_lang_add": "SELECT 'doc/' || doc_id AS s, 'source' AS p, source || '@' || coalesce(lang, 'und') AS o FROM documents WHERE source IS NOT NULL",
        "bench_lang_drop": "SELECT 'doc/' || doc_id AS s, 'source' AS p, source AS o FROM documents WHERE source IS NOT NULL",
        "bench_uri_literal": "SELECT '<' || url || '>' AS s, 'address' AS p, url AS o FROM pages WHERE url IS NOT NULL",
        "bench_fusion": "SELECT 'party/' || c_custkey AS s, 'name' AS p, c_name AS o FROM customer UNION SELECT 'party/' || s_suppkey, 'name', s_name FROM supplier",
        "path_r2r_exchange": f"WITH {_SALES} SELECT count(*) AS pairs FROM (SELECT DISTINCT x.c, y.c FROM b x JOIN b y ON x.s = y.s AND 'cust/' || x.c < 'cust/' || y.c)",
        "overlap_dictionary": "WITH t AS (SELECT p_partkey AS id, 'brand:' || p_brand AS cls FROM part UNION ALL SELECT p_partkey, 'type:' || p_type FROM part UNION ALL SELECT p_partkey, 'size:large' FROM part WHERE p_size > 40), n AS (SELECT cls, count(*) AS n FROM t GROUP BY cls) SELECT a.cls AS c1, b.cls AS c2, count(*) AS shared, round(count(*) / least(any_value(x.n), any_value(y.n)), 6) AS ratio FROM t a JOIN t b ON a.id = b.id AND a.cls < b.cls JOIN n x ON x.cls = a.cls JOIN n y ON y.cls = b.cls GROUP BY 1, 2 HAVING round(count(*) / least(any_value(x.n), any_value(y.n)), 6) >= 0.2",
        "op_growth": "SELECT x, n, n - lag(n) OVER (ORDER BY x) AS diff, round(n / lag(n) OVER (ORDER BY x), 6) AS ratio, CASE WHEN x > 2 THEN 0::BIGINT END AS second FROM (SELECT x, 2 * x + 1 AS n FROM (SELECT unnest(range(1, 11)) AS x))",
        "op_replies": "SELECT 'turn/' || conv_id || '.' || turn AS s, 'turn/' || conv_id || '.' || l AS o FROM (SELECT *, lag(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS l FROM conversations) WHERE l IS NOT NULL",
        "op_fact_rollup": f"{gold}SELECT p, o_kind, count(*) AS n FROM facts GROUP BY ROLLUP (p, o_kind)",
        "op_event_json": "SELECT event_type, json_extract_string(props, '$.k') AS k, count(*) AS n FROM events GROUP BY 1, 2",
        "op_page_titles": "SELECT 'page/' || page_id AS s, regexp_extract(html, '<title>([^<]*)</title>', 1) AS title, regexp_extract(html, '<html lang=\"([a-z]+)\"', 1) AS lang FROM pages",
        "bench_property_to_path": "SELECT 'cust/' || c_custkey AS s, 'has_address' AS p, '_:addr(cust/' || c_custkey || ')' AS o FROM customer UNION ALL SELECT '_:addr(cust/' || c_custkey || ')', 'in_country', 'nation/' || c_nationkey FROM customer",
        "bench_flatten": "SELECT 'cust/' || c_custkey AS s, n_name AS country_name FROM customer JOIN nation ON n_nationkey = c_nationkey",
        "bench_sink_property": "SELECT 'part/' || p_partkey AS s, 'type_' || regexp_replace(p_brand, '[^A-Za-z0-9]', '_', 'g') AS p, p_name AS o FROM part",
    }
