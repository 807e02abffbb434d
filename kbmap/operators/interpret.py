"""Correspondence interpretation: skeletons, renamings, validity and ranking.

A renaming assigns to each target variable a source variable or nothing (-1). Renamings of a skeleton are rows of a
DataFrame with a fixed-width array, made by one narrow fold over the target variables: each step explodes
the variable's candidates and drops states that an early check refuses, without any shuffle. Costs are column
expressions over the array; ranks come from a histogram of the few distinct costs.
"""

from __future__ import annotations

import math
from collections import defaultdict
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..sources.model import Alignment, Corr
from .assoc import Tree, association_paths

SKELETON_SCHEMA = "s_root string, t_root string, covered array<string>, s_vars int, t_vars int"
MAX_RENAMINGS = 50_000_000


# --- skeletons ----------------------------------------------------------------------------------------------


def _side_covers(a: Alignment, c: Corr, tree: Tree, side: str) -> bool:
    concepts = {n.concept for n in tree.nodes}
    first, second = (c.s1, c.s2) if side == "s" else (c.t1, c.t2)
    if c.kind == "c2c":
        return first in concepts
    if c.kind == "r2r":
        return first in concepts and second in concepts
    owner, attr = a.owner(c, side)
    return any(at == attr and tree.by_id[n].concept == owner for n, at in tree.attrs)


def _covered_by(a: Alignment, side: str) -> list[tuple[str, str]]:
    return [(c.s1 if side == "s" else c.t1, c.id) for c in a.corrs if c.kind == "c2c"]


def _attrs_by(a: Alignment, side: str) -> list[tuple[tuple[str, str], str]]:
    return [(a.owner(c, side), c.id) for c in a.corrs if c.kind == "a2a"]


def summaries(spark: SparkSession, a: Alignment, trees: dict[str, Tree], side: str) -> DataFrame:
    """(root, sig, vars): per tree the correspondences that this side of it can cover, as a sorted array."""
    by_concept, by_attr = defaultdict(list), defaultdict(list)
    for concept, i in _covered_by(a, side):
        by_concept[concept].append(i)
    for owner, i in _attrs_by(a, side):
        by_attr[owner].append(i)
    ends = [((c.s1, c.s2) if side == "s" else (c.t1, c.t2), c.id) for c in a.corrs if c.kind == "r2r"]
    rows = []
    for root, t in trees.items():
        concepts = {n.concept for n in t.nodes}
        sig = [i for x in concepts for i in by_concept[x]]
        sig += [i for x in {(t.by_id[n].concept, at) for n, at in t.attrs} for i in by_attr[x]]
        sig += [i for pair, i in ends if concepts.issuperset(pair)]
        rows.append((root, sorted(sig), len(t.vars)))
    return spark.createDataFrame(rows, "root string, sig array<string>, vars int")


def skeletons(s: DataFrame, t: DataFrame) -> DataFrame:
    """All pairs of trees that cover a correspondence together.

    Pairs are formed between distinct signatures first: of trees with one signature on a side, only those with the fewest
    variables can survive pruning, but all are kept here.
    """
    ss, ts = s.select("sig").distinct(), t.select("sig").distinct()
    pairs = (
        ss.select(F.col("sig").alias("s_sig"), F.explode("sig").alias("c")).join(ts.select(F.col("sig").alias("t_sig"), F.explode("sig").alias("c")), "c")
        .select("s_sig", "t_sig").distinct()
        .withColumn("covered", F.array_sort(F.array_intersect("s_sig", "t_sig")))
    )
    left = s.select(F.col("root").alias("s_root"), F.col("sig").alias("s_sig"), F.col("vars").alias("s_vars"))
    right = t.select(F.col("root").alias("t_root"), F.col("sig").alias("t_sig"), F.col("vars").alias("t_vars"))
    return pairs.join(left, "s_sig").join(right, "t_sig").select("s_root", "t_root", "covered", "s_vars", "t_vars")


def prune_skeletons(sk: DataFrame, rule: str = "both") -> DataFrame:
    """Of skeletons with one source tree and one coverage keep the smallest target tree; with ``both`` also the other way round."""
    def fewest(df, keep, drop, size):
        w = W.partitionBy(keep, "covered").orderBy(size, drop)
        return df.withColumn("_n", F.row_number().over(w)).where("_n = 1").drop("_n")

    out = fewest(sk, "s_root", "t_root", "t_vars")
    return fewest(out, "t_root", "s_root", "s_vars") if rule == "both" else out


def reduced_skeletons(s: DataFrame, t: DataFrame) -> DataFrame:
    """The result of pairing and pruning by both rules without forming all pairs.

    For a fixed source tree only the smallest target tree per target signature can win, so the target side is reduced
    to one tree per signature before the trees are paired.
    """
    w = W.partitionBy("sig").orderBy("vars", "root")
    least = t.withColumn("_n", F.row_number().over(w)).where("_n = 1").drop("_n")
    return prune_skeletons(skeletons(s, least), "both")


# --- one skeleton -------------------------------------------------------------------------------------------


@dataclass
class Skeleton:
    """A source and a target tree with the correspondences they cover and the candidates of each target variable."""

    a: Alignment
    s: Tree
    t: Tree
    covered: list[Corr] = field(default_factory=list)

    def __post_init__(self):
        both = [c for c in self.a.corrs if _side_covers(self.a, c, self.s, "s") and _side_covers(self.a, c, self.t, "t")]
        self.covered = self.covered or both
        self.c2c = {(c.s1, c.t1): c.id for c in self.covered if c.kind == "c2c"}
        self.a2a = {(self.a.owner(c, "s"), self.a.owner(c, "t")): c.id for c in self.covered if c.kind == "a2a"}

    def candidates(self, root_rule: bool = True) -> dict[int, list[tuple[int, str]]]:
        """Target variable -> (source variable, correspondence). The root takes only the nearest nodes of a corresponding concept."""
        out: dict[int, list[tuple[int, str]]] = {}
        for tv, (tn, ta) in enumerate(self.t.vars):
            hits = []
            for sv, (sn, sa) in enumerate(self.s.vars):
                sc, tc = self.s.concept(sv), self.t.concept(tv)
                if ta is None and sa is None and (sc, tc) in self.c2c:
                    hits.append((sv, self.c2c[sc, tc]))
                if ta is not None and sa is not None and ((sc, sa), (tc, ta)) in self.a2a:
                    hits.append((sv, self.a2a[(sc, sa), (tc, ta)]))
            if root_rule and ta is None and tn == self.t.nodes[0].id and hits:
                near = min(self.s.by_id[self.s.vars[sv][0]].hop for sv, _ in hits)
                hits = [h for h in hits if self.s.by_id[self.s.vars[h[0]][0]].hop == near]
            out[tv] = hits
        return out

    # Column predicates over ``asg``; positions are target variables, values source variables.

    def _at(self, tv: int) -> Column:
        return F.get("asg", F.lit(tv))

    # Each check is a list of (last target variable it looks at, condition), so that the fold can refuse a state as soon as it is known.

    def _is(self, tv: int, sv: int) -> Column:
        return self._at(tv) == sv

    @staticmethod
    def _any(conditions) -> Column:
        return reduce(lambda x, y: x | y, conditions, F.lit(False))

    @staticmethod
    def _all(checks) -> Column:
        return reduce(lambda x, y: x & y, [c for _, c in checks], F.lit(True))

    def _nodes_of(self, tree: Tree, concept: str) -> list[int]:
        return [v for v, (_, at) in enumerate(tree.vars) if at is None and tree.concept(v) == concept]

    def check_covered(self, c: Corr, cand) -> list[tuple[int, Column]]:
        """Some target variable interprets the correspondence."""
        if c.kind == "r2r":
            out = []
            for s, t in ((c.s1, c.t1), (c.s2, c.t2)):
                tvs = self._nodes_of(self.t, t)
                out.append((max(tvs, default=0), self._any(self._is(tv, sv) for tv in tvs for sv in self._nodes_of(self.s, s))))
            return out
        hits = [(tv, sv) for tv, found in cand.items() for sv, cid in found if cid == c.id]
        return [(max((tv for tv, _ in hits), default=0), self._any(self._is(tv, sv) for tv, sv in hits))]

    def _pairs_on(self, tree: Tree, c1: str, c2: str, want) -> list[tuple[int, int]]:
        return [
            (i, j) for i in self._nodes_of(tree, c1) for j in self._nodes_of(tree, c2)
            if i != j and tree.tree_path(tree.vars[i][0], tree.vars[j][0]) == want
        ]

    def check_r2r(self) -> list[tuple[int, Column]]:
        """Each covered path correspondence is respected by some pair of mapped node pairs on its two paths."""
        out = []
        for c in (c for c in self.covered if c.kind == "r2r"):
            want_s, want_t = (tuple((s.prop, s.inv) for s in p) for p in (c.s_path, c.t_path))
            hits = [(t1, s1, t2, s2) for t1, t2 in self._pairs_on(self.t, c.t1, c.t2, want_t) for s1, s2 in self._pairs_on(self.s, c.s1, c.s2, want_s)]
            last = max((max(t1, t2) for t1, _, t2, _ in hits), default=0)
            out.append((last, self._any(self._is(t1, s1) & self._is(t2, s2) for t1, s1, t2, s2 in hits)))
        return out

    def check_c2a(self, mode: str = "literal") -> list[tuple[int, Column]]:
        """If node m is filled from n, attributes that correspond on their concepts are filled from n as well.

        ``relaxed`` lets the attribute stay empty; ``strict`` also keeps an attribute empty while its node is.
        """
        out = []
        for tv, (tn, ta) in enumerate(self.t.vars):
            if ta is None:
                continue
            node_tv = self.t.index[tn, None]
            tc, fed, last = self.t.concept(tv), False, max(tv, node_tv)
            for sv, (sn, sa) in enumerate(self.s.vars):
                if sa is None or ((self.s.concept(sv), sa), (tc, ta)) not in self.a2a or (self.s.concept(sv), tc) not in self.c2c:
                    continue
                fed = True
                same = self._is(tv, sv)
                if mode == "relaxed":
                    same = same | (self._at(tv) == -1)
                out.append((last, (self._at(node_tv) != self.s.index[sn, None]) | same))
            if mode == "strict" and fed:
                out.append((last, (self._at(node_tv) != -1) | (self._at(tv) == -1)))
        return out

    def check_owner(self) -> list[tuple[int, Column]]:
        """Attributes of target concepts without a concept correspondence come only from individuals that are transferred."""
        out, with_c2c = [], {t for _, t in self.c2c}
        nodes = [tv for tv, (_, at) in enumerate(self.t.vars) if at is None]
        for tv, (_, ta) in enumerate(self.t.vars):
            if ta is None or self.t.concept(tv) in with_c2c:
                continue
            for sv, (sn, sa) in enumerate(self.s.vars):
                if sa is not None and ((self.s.concept(sv), sa), (self.t.concept(tv), ta)) in self.a2a:
                    moved = self._any(self._is(n, self.s.index[sn, None]) for n in nodes)
                    out.append((max([tv, *nodes]), (self._at(tv) != sv) | moved))
        return out

    def check_isa(self) -> list[tuple[int, Column]]:
        """Two mapped nodes of one target individual come from one source individual."""
        out, group = [], defaultdict(list)
        for sv, (sn, sa) in enumerate(self.s.vars):
            if sa is None:
                group[self.s.individual(sn)].append(sv)
        for tv, (tn, ta) in enumerate(self.t.vars):
            n = self.t.by_id[tn]
            if ta is None and n.edge == "a":
                up = self.t.index[n.parent, None]
                same = self._any(self._at(tv).isin(g) & self._at(up).isin(g) for g in group.values())
                out.append((max(tv, up), (self._at(tv) == -1) | (self._at(up) == -1) | same))
        return out

    def valid_covered(self, c: Corr, cand) -> Column:
        return self._all(self.check_covered(c, cand))

    def valid_r2r(self) -> Column:
        return self._all(self.check_r2r())

    def valid_c2a(self, mode: str = "literal") -> Column:
        return self._all(self.check_c2a(mode))

    def valid_attr_owner(self) -> Column:
        return self._all(self.check_owner())

    def valid_isa(self) -> Column:
        return self._all(self.check_isa())

    def checks(self, names: tuple[str, ...] = (), c2a_mode: str = "literal") -> list[tuple[int, Column]]:
        """All conditions of the named notions (r2r, c2a, owner), with coverage and the subclass rule, which always hold."""
        cand, out = self.candidates(), self.check_isa()
        for c in self.covered:
            out += self.check_covered(c, cand)
        for name in names:
            out += {"r2r": self.check_r2r, "c2a": lambda: self.check_c2a(c2a_mode), "owner": self.check_owner}[name]()
        return out

    # Costs.

    def path_cost(self, edge_ok: set[tuple[str, str]], over: str = "used") -> Column:
        """Per source node the association steps from the root whose corresponding target concepts no association path joins, summed over used nodes."""
        cost = {}
        for n in self.s.nodes:
            up = next((x for x in self.s.ancestors(n.id) if self.s.by_id[x].aligned), None)
            if up is None or not n.aligned:
                cost[n.id] = 0
                continue
            u, v = self.s.by_id[up].concept, n.concept
            tu, tv = ([t for s, t in self.c2c if s == x] for x in (u, v))
            cost[n.id] = cost[up] + (0 if any((x, y) in edge_ok for x in tu for y in tv) else 1)
        total = F.lit(0)
        node_tvs = [tv for tv, (_, at) in enumerate(self.t.vars) if at is None]
        for sv, (n, at) in enumerate(self.s.vars):
            if at is None and cost[n]:
                used = F.lit(True) if over == "all" else reduce(lambda x, y: x | y, [self._at(tv) == sv for tv in node_tvs])
                total = total + F.when(used, cost[n]).otherwise(0)
        return total.cast("long")

    def consistency_cost(self, nodes_only: bool = False, inverse_aware: bool = False) -> Column:
        """Ordered pairs of bound target variables where one side alone has the second below the first."""
        n = len(self.s.vars)
        below = {tuple(p) for i in range(n) for j in range(n) if (p := (i, j))[0] != p[1] and self.s.below(i, j)}
        if inverse_aware:
            below |= {(j, i) for i, j in below}
        reach = F.array(*[F.lit(i * n + j) for i, j in sorted(below)]) if below else F.array().cast("array<int>")
        total = F.lit(0)
        tvs = [k for k, (_, at) in enumerate(self.t.vars) if at is None or not nodes_only]
        for i in tvs:
            for j in tvs:
                if i == j or (inverse_aware and i > j):
                    continue
                t_below = self.t.below(i, j) or (inverse_aware and self.t.below(j, i))
                bound = (self._at(i) >= 0) & (self._at(j) >= 0)
                s_below = F.array_contains(reach, self._at(i) * n + self._at(j))
                total = total + F.when(bound & (s_below != F.lit(t_below)), 1).otherwise(0)
        return total.cast("long")

    def consistency_pairs(self, nodes_only: bool = False):
        """A function from a target variable to the inconsistent ordered pairs that it forms with earlier ones."""
        n = len(self.s.vars)
        below = sorted(i * n + j for i in range(n) for j in range(n) if i != j and self.s.below(i, j))
        reach = F.array(*[F.lit(x) for x in below]) if below else F.array().cast("array<int>")
        tvs = [k for k, (_, at) in enumerate(self.t.vars) if at is None or not nodes_only]

        def added(tv: int) -> Column:
            total = F.lit(0).cast("long")
            for other in [x for x in tvs if x < tv] if tv in tvs else []:
                for i, j in ((other, tv), (tv, other)):
                    bound = (self._at(i) >= 0) & (self._at(j) >= 0)
                    s_below = F.array_contains(reach, self._at(i) * n + self._at(j))
                    total = total + F.when(bound & (s_below != F.lit(self.t.below(i, j))), 1).otherwise(0)
            return total

        return added

    def evidence(self, facts: dict[tuple[str, str, str], int]) -> Column:
        """Source facts that a renaming takes, summed over its variables: instances of the root, facts of the edge to a node, values of an attribute."""
        n = []
        for sn, sa in self.s.vars:
            x = self.s.by_id[sn]
            if sa is not None:
                n.append(facts["prop", sa, x.concept])
            elif x.parent is None:
                n.append(facts["class", x.concept, ""])
            else:
                up = self.s.by_id[x.parent].concept
                n.append(facts["sub", up, x.concept] if x.edge == "a" else facts["prop", x.edge, x.concept if x.inv else up])
        each = F.array(*[F.lit(x).cast("long") for x in n])
        return F.aggregate(F.filter("asg", lambda v: v >= 0), F.lit(0).cast("long"), lambda t, v: t + F.get(each, v))

    def coverage_cost(self) -> Column:
        return F.size(F.filter("asg", lambda x: x == -1)).cast("long")


def edge_pairs(spark: SparkSession, a: Alignment, side: str = "t", max_len: int = 4, undirected: bool = False) -> set[tuple[str, str]]:
    """Pairs of aligned concepts that an association path joins; ``undirected`` counts a path for both directions."""
    found = {(r.root, r.tail) for r in association_paths(spark, a.side(side), a.aligned_concepts(side), max_len).select("root", "tail").distinct().collect()}
    return found | {(y, x) for x, y in found} if undirected else found


def renamings(
    spark: SparkSession, sk: Skeleton, source_once: bool = True, checks: tuple[str, ...] = (), c2a_mode: str = "literal", max_renamings: int = MAX_RENAMINGS
) -> DataFrame:
    """``asg`` arrays of the skeleton's renamings that interpret every covered correspondence and pass the named checks.

    ``checks``: r2r, c2a, owner. Each condition is tested as soon as the last variable that it looks at has its value, so states that
    cannot end well never multiply. Where more than ``max_renamings`` could end well in the worst case, it raises.
    """
    if bound_of(sk) > max_renamings * 1000:
        raise ValueError("too many renamings to enumerate; use count_renamings")
    return _fold(spark, sk, source_once, sk.checks(checks, c2a_mode))


def bound_of(sk: Skeleton) -> int:
    """No more renamings than this: values of the free variables; an attribute whose node decides it adds none."""
    return math.prod(len(h) + 1 for tv, h in sk.candidates().items() if sk.t.vars[tv][1] is None or len(h) > 1 or not h)


def _fold(spark: SparkSession, sk: Skeleton, source_once: bool, conditions: list[tuple[int, Column]], each=None) -> DataFrame:
    """States grow by one variable a step; ``each(state, tv)`` may add columns or drop states after the step."""
    cand, due = sk.candidates(), defaultdict(list)
    for last, condition in conditions:
        due[last].append(condition)
    state = spark.createDataFrame([([],)], "asg array<int>")
    for tv in range(len(sk.t.vars)):
        options = F.array(*[F.lit(x) for x in (-1, *dict.fromkeys(sv for sv, _ in cand[tv]))])
        carried = [c for c in state.columns if c != "asg"]
        state = state.select("asg", *carried, F.explode(options).alias("c"))
        if source_once:
            state = state.where((F.col("c") == -1) | ~F.array_contains("asg", F.col("c")))
        state = state.select(F.concat("asg", F.array("c")).alias("asg"), *carried)
        if due[tv]:
            state = state.where(reduce(lambda x, y: x & y, due[tv]))
        if each is not None:
            state = each(state, tv)
        if tv == 4:
            state = state.repartition(spark.sparkContext.defaultParallelism)
    return state


def brute_force_renamings(spark: SparkSession, sk: Skeleton, source_once: bool = True, checks: tuple[str, ...] = (), c2a_mode: str = "literal") -> DataFrame:
    """The reference: every combination of candidates first, all conditions last."""
    state = _fold(spark, sk, False, [])
    used = F.filter("asg", lambda x: x >= 0)
    if source_once:
        state = state.where(F.size(used) == F.size(F.array_distinct(used)))
    return state.where(sk._all(sk.checks(checks, c2a_mode)))


def validity_counts(spark: SparkSession, sk: Skeleton, c2a_mode: str = "literal") -> DataFrame:
    """Numbers of renamings under each combination of the validity notions, in one pass."""
    r, p, c = renamings(spark, sk), sk.valid_r2r(), sk.valid_c2a(c2a_mode)
    n = lambda cond: F.sum(F.when(cond, 1).otherwise(0)).cast("long")
    return r.agg(F.count(F.lit(1)).alias("baseline"), n(p).alias("r2r"), n(c).alias("c2a"), n(p & c).alias("both"))


def count_renamings(sk: Skeleton, c2a_mode: str | None = None, r2r: bool = False) -> int:
    """The number of source-once renamings without listing them.

    Target variables that share no candidates, no correspondence and no check are independent: the groups' counts
    multiply. Within a group states are counted by a walk over its variables.
    """
    cand = sk.candidates()
    parent = {tv: tv for tv in cand}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    def join(vs):
        vs = list(vs)
        for v in vs[1:]:
            parent[find(v)] = find(vs[0])

    users = defaultdict(set)
    for tv, hits in cand.items():
        for sv, cid in hits:
            users["s", sv].add(tv)
            users["c", cid].add(tv)
    for vs in users.values():
        join(vs)
    node_of = {tv: sk.t.index[n, None] for tv, (n, at) in enumerate(sk.t.vars) if at is not None}
    if c2a_mode:
        for tv, node in node_of.items():
            join([tv, node])
    if r2r:
        for c in (c for c in sk.covered if c.kind == "r2r"):
            join(tv for tv, (n, at) in enumerate(sk.t.vars) if at is None and sk.t.concept(tv) in (c.t1, c.t2))
    groups = defaultdict(list)
    for tv in cand:
        groups[find(tv)].append(tv)

    def good(asg: dict[int, int]) -> bool:
        for tv, node in node_of.items():
            if c2a_mode and tv in asg:
                for sv, (sn, sa) in enumerate(sk.s.vars):
                    key = ((sk.s.concept(sv), sa), (sk.t.concept(tv), sk.t.vars[tv][1]))
                    if sa is not None and key in sk.a2a and (sk.s.concept(sv), sk.t.concept(tv)) in sk.c2c:
                        if asg[node] == sk.s.index[sn, None] and asg[tv] != sv and not (c2a_mode == "relaxed" and asg[tv] == -1):
                            return False
                        if c2a_mode == "strict" and asg[node] == -1 and asg[tv] != -1:
                            return False
        if r2r:
            for c in (c for c in sk.covered if c.kind == "r2r"):
                want_s, want_t = (tuple((s.prop, s.inv) for s in p) for p in (c.s_path, c.t_path))
                nodes = [tv for tv in asg if sk.t.vars[tv][1] is None and asg[tv] >= 0]
                mine = [tv for tv in nodes if sk.t.concept(tv) in (c.t1, c.t2)]
                here = any(sk.t.vars[tv][1] is None and sk.t.concept(tv) in (c.t1, c.t2) for tv in asg)
                if here and not any(
                    sk.t.tree_path(sk.t.vars[x][0], sk.t.vars[y][0]) == want_t and sk.s.tree_path(sk.s.vars[asg[x]][0], sk.s.vars[asg[y]][0]) == want_s for x in mine for y in mine if x != y
                ):
                    return False
        return True

    total = 1
    for group in groups.values():
        needed = {cid for tv in group for _, cid in cand[tv]}

        def walk(k, asg, used, seen):
            if k == len(group):
                return int(seen >= needed and good(asg))
            n = walk(k + 1, asg | {group[k]: -1}, used, seen)
            for sv, cid in cand[group[k]]:
                if sv not in used:
                    n += walk(k + 1, asg | {group[k]: sv}, used | {sv}, seen | {cid})
            return n

        total *= walk(0, {}, frozenset(), frozenset())
    return total


def costed(spark: SparkSession, sk: Skeleton, r: DataFrame, edge_ok: set[tuple[str, str]] | None = None) -> DataFrame:
    """Add path_cost, cons_cost, cov_cost and combined (path + consistency)."""
    edge_ok = edge_pairs(spark, sk.a) if edge_ok is None else edge_ok
    r = r.withColumns({"path_cost": sk.path_cost(edge_ok), "cons_cost": sk.consistency_cost(), "cov_cost": sk.coverage_cost()})
    return r.withColumn("combined", F.col("path_cost") + F.col("cons_cost"))


def with_cue(r: DataFrame, cue: Column, weight: float = 0.0, by: str = "combined") -> DataFrame:
    """Add an optional cue (a column that is small for good renamings) to a cost; without a weight it changes nothing."""
    return r.withColumn("cued", F.col(by) + F.lit(weight) * cue)


def histogram(r: DataFrame, by: str) -> DataFrame:
    """(cost, equal, better, rank) per distinct cost: dense ranks without a global sort of the renamings."""
    h = r.groupBy(F.col(by).alias("cost")).agg(F.count(F.lit(1)).alias("equal"))
    w = W.orderBy("cost")  # one row per distinct cost
    before = F.coalesce(F.sum("equal").over(w.rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).cast("long")
    return h.select("cost", "equal", before.alias("better"), F.dense_rank().over(w).cast("long").alias("rank"))


def lexicographic(r: DataFrame, *by: str) -> DataFrame:
    """Add ``lex``: dense ranks by the first cost, then the next; from the few distinct cost tuples."""
    keys = r.select(*by).distinct().withColumn("lex", F.dense_rank().over(W.orderBy(*by)).cast("long"))  # one row per distinct tuple
    return r.join(F.broadcast(keys), list(by))


def rank_renamings(r: DataFrame, by: str) -> DataFrame:
    return r.join(F.broadcast(histogram(r, by)), r[by] == F.col("cost")).drop("cost")  # a row per distinct cost


def gold_position(r: DataFrame, gold: list[int], by: str) -> DataFrame:
    """(ranking, rank, better, equal): equal leaves the gold itself out."""
    cost = r.where(F.col("asg") == F.array(*[F.lit(x) for x in gold])).select(F.col(by).alias("cost")).distinct()
    return histogram(r, by).join(F.broadcast(cost), "cost").select(F.lit(by).alias("ranking"), "rank", "better", (F.col("equal") - 1).alias("equal"))


def best_renamings(r: DataFrame, k: int, by: str | list[str] = "combined") -> DataFrame:
    """The k cheapest of renamings at hand, each task keeping k at most; a list of costs ranks lexicographically, ties by the assignment itself."""
    return r.orderBy(*([by] if isinstance(by, str) else by), "asg").limit(k)


def best_by_bounds(spark: SparkSession, sk: Skeleton, k: int, checks: tuple[str, ...] = (), c2a_mode: str = "literal", nodes_only: bool = False) -> DataFrame:
    """The k most consistent renamings without listing all: (asg, cons_cost).

    A state's inconsistent pairs never get fewer, so its cost so far bounds all that grow from it. The fold runs with a
    bound of 0, 1, 3, 7, ... and drops states above it, until k renamings are within the bound.
    """
    pair = sk.consistency_pairs(nodes_only)

    def within(bound: int) -> DataFrame:
        def each(state: DataFrame, tv: int) -> DataFrame:
            before = F.col("cons_cost") if "cons_cost" in state.columns else F.lit(0).cast("long")
            return state.withColumn("cons_cost", before + pair(tv)).where(F.col("cons_cost") <= bound)

        return _fold(spark, sk, True, sk.checks(checks, c2a_mode), each)

    worst = len(sk.t.vars) ** 2
    bound = 0
    while True:
        top = within(bound).orderBy("cons_cost", "asg").limit(k)
        if bound >= worst or top.count() == k:
            return top
        bound = 2 * bound + 1
