"""Association discovery: hops, bounded association paths and association trees.

The frontier of paths and of tree nodes is a DataFrame joined with broadcast hop and path tables, one
join per level for all roots together. The schema layer is bounded (``MAX_ROWS`` guards it), so each
level is settled on the driver to cut lineage.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.model import KB, Alignment

MAX_ROWS = 500_000
_STEP = "array<struct<elem:string,kind:string,inv:boolean>>"
PATH_SCHEMA = f"root string, tail string, path_id string, steps {_STEP}, hops int"
NODE_SCHEMA = "root string, node string, parent string, concept string, edge string, inv boolean, kind string, hop int, aligned boolean"


def _settle(df: DataFrame, schema: str) -> DataFrame:
    """A small table of metadata without its lineage."""
    rows = df.limit(MAX_ROWS + 1).collect()
    if len(rows) > MAX_ROWS:
        raise ValueError(f"over {MAX_ROWS} rows of schema metadata; lower the path or depth bound, or cut a fragment")
    return df.sparkSession.createDataFrame(rows, schema)


def schema_hops(spark: SparkSession, kb: KB, down_isa: bool = False, shared_ends: bool = False) -> DataFrame:
    """(src, dst, prop, kind, inv): from domain to range, back, up to superclasses and, if asked, down or to classes sharing an end."""
    _, sub, prop = kb.frames(spark)
    obj = prop.where("kind = 'obj'")
    hops = obj.selectExpr("domain as src", "range as dst", "prop", "'obj' as kind", "false as inv")
    hops = hops.unionByName(obj.selectExpr("range as src", "domain as dst", "prop", "'obj' as kind", "true as inv"))
    hops = hops.unionByName(sub.selectExpr("sub as src", "sup as dst", "'a' as prop", "'isa' as kind", "false as inv"))
    if down_isa:
        hops = hops.unionByName(sub.selectExpr("sup as src", "sub as dst", "'a' as prop", "'isa' as kind", "true as inv"))
    if shared_ends:
        a, b = obj.alias("a"), obj.alias("b")
        for end in ("domain", "range"):
            pairs = a.join(b, F.expr(f"a.prop = b.prop and a.{end} <> b.{end}"))
            hops = hops.unionByName(pairs.selectExpr(f"a.{end} as src", f"b.{end} as dst", "a.prop as prop", "'shared' as kind", "false as inv"))
    return hops.distinct()


def association_paths(
    spark: SparkSession, kb: KB, aligned: list[str], max_len: int = 4, allow_backward_start: bool = False,
    allow_backtrack: bool = False, count_isa: bool = True, **hop_options,
) -> DataFrame:
    """Paths from each aligned concept to the first aligned concept on the way, at most ``max_len`` hops long."""
    hops = F.broadcast(schema_hops(spark, kb, **hop_options))
    ends = F.broadcast(spark.createDataFrame([(c,) for c in aligned], "dst string").withColumn("hit", F.lit(True)))
    seed = ", ".join(["root string", "at string", f"steps {_STEP}", "prop string", "inv boolean", "prev string", "hops int"])
    open_ = spark.createDataFrame([(c, c, [], None, None, None, 0) for c in aligned], seed)
    done = None
    # Steps that are not counted (isa, if asked) still end: a chain of superclasses is no longer than the classes.
    for level in range(max_len if count_isa else max_len + len(kb.classes)):
        nxt = open_.withColumnsRenamed({"prop": "last", "inv": "last_inv"}).join(hops, F.col("at") == F.col("src"))
        if level == 0 and not allow_backward_start:
            nxt = nxt.where("not inv")
        if level and not allow_backtrack:
            nxt = nxt.where("not coalesce(prop = last and inv <> last_inv and dst = prev, false)")
        edge = F.struct(F.col("prop").alias("elem"), F.col("kind"), F.col("inv"))
        node = F.struct(F.col("dst").alias("elem"), F.lit("class").alias("kind"), F.lit(False).alias("inv"))
        weight = F.lit(1) if count_isa else F.when(F.col("kind") == "isa", 0).otherwise(1)
        nxt = nxt.select(
            "root", F.col("dst"), F.concat("steps", F.when(F.col("kind") == "isa", F.array(node)).otherwise(F.array(edge, node))).alias("steps"),
            "prop", "inv", F.col("at").alias("prev"), (F.col("hops") + weight).cast("int").alias("hops"), F.concat_ws("", F.col("kind")).alias("kind"),
        ).where(F.col("hops") <= max_len)
        nxt = _settle(nxt.join(ends, "dst", "left").select("root", "dst", "steps", "prop", "inv", "prev", "hops", "hit"), f"root string, dst string, steps {_STEP}, prop string, inv boolean, prev string, hops int, hit boolean")
        closed = nxt.where("hit").select("root", F.col("dst").alias("tail"), path_text(F.col("steps")).alias("path_id"), "steps", "hops")
        done = closed if done is None else done.unionByName(closed)
        open_ = nxt.where("hit is null").select("root", F.col("dst").alias("at"), "steps", "prop", "inv", "prev", "hops")
        if open_.isEmpty():
            break
    return _settle(done.distinct(), PATH_SCHEMA) if done is not None else spark.createDataFrame([], PATH_SCHEMA)


def path_text(steps):
    """The elements of a path joined by slashes, inverse properties marked."""
    return F.array_join(F.transform(steps, lambda s: F.concat(F.when(s.inv, "^").otherwise(""), s.elem)), "/")


@dataclass
class Node:
    root: str
    id: str
    parent: str | None
    concept: str
    edge: str | None  # property name, or "a" for isa
    inv: bool
    hop: int
    aligned: bool


@dataclass
class Tree:
    """One association tree, in variable order: parents before children, attributes right after their node."""

    kb: KB
    root: str
    nodes: list[Node]
    attrs: list[tuple[str, str]]  # (node id, attribute)

    def __post_init__(self):
        self.by_id = {n.id: n for n in self.nodes}
        self.vars: list[tuple[str, str | None]] = []
        for n in self.nodes:
            self.vars.append((n.id, None))
            self.vars += [(i, a) for i, a in self.attrs if i == n.id]
        self.index = {v: k for k, v in enumerate(self.vars)}

    def concept(self, var: int) -> str:
        return self.by_id[self.vars[var][0]].concept

    def ancestors(self, node: str) -> list[str]:
        """From the node's parent to the root."""
        out, n = [], self.by_id[node].parent
        while n:
            out.append(n)
            n = self.by_id[n].parent
        return out

    def individual(self, node: str) -> str:
        """The top node of the isa group: nodes on isa edges stand for one individual."""
        n = self.by_id[node]
        while n.edge == "a":
            n = self.by_id[n.parent]
        return n.id

    def below(self, a: int, b: int) -> bool:
        """Variable b lies strictly below variable a."""
        (na, xa), (nb, xb) = self.vars[a], self.vars[b]
        if xa is not None:
            return False
        return na in self.ancestors(nb) or (na == nb and xb is not None)

    def tree_path(self, a: str, b: str) -> tuple[tuple[str, bool], ...]:
        """Property steps from node a to node b through their lowest common ancestor; isa edges add none."""
        up, down = [a, *self.ancestors(a)], [b, *self.ancestors(b)]
        meet = next(n for n in up if n in down)
        rise = [self.by_id[n] for n in up[: up.index(meet)]]
        fall = [self.by_id[n] for n in down[: down.index(meet)]]
        return tuple((n.edge, not n.inv) for n in rise if n.edge != "a") + tuple((n.edge, n.inv) for n in reversed(fall) if n.edge != "a")


def tree_nodes(spark: SparkSession, kb: KB, aligned: list[str], paths: DataFrame, max_depth: int = 6) -> DataFrame:
    """Nodes of the association trees of all aligned concepts, grown level by level; fresh nodes for every concept on every path."""
    p = F.broadcast(paths.selectExpr("root as src", "tail", "path_id", "steps", "hops as more"))
    level = spark.createDataFrame([(c, c, None, c, None, False, "root", 0, True) for c in aligned], NODE_SCHEMA)
    out = level
    while True:
        grown = level.where("aligned").join(p, F.col("concept") == F.col("src")).where(F.col("hop") + F.col("more") <= max_depth)
        # One row per class on the path; the property before it, if any, labels the edge.
        chain = grown.select("root", "node", "hop", "path_id", "tail", "steps", F.posexplode("steps").alias("k", "s")).where("s.kind = 'class'")
        before = F.get("steps", F.col("k") - 1)
        rank = F.expr("size(filter(slice(steps, 1, k + 1), x -> x.kind = 'class'))")
        total = F.expr("size(filter(steps, x -> x.kind = 'class'))")
        label = lambda i: F.concat(F.col("node"), F.lit(">"), F.col("path_id"), F.when(i == total, "").otherwise(F.concat(F.lit("#"), i)))
        is_prop = before.kind != "class"
        nodes = chain.select(
            "root", label(rank).alias("node2"), F.when(rank == 1, F.col("node")).otherwise(label(rank - 1)).alias("parent"), F.col("s.elem").alias("concept"),
            F.when(is_prop, before.elem).otherwise("a").alias("edge"), F.coalesce(F.when(is_prop, before.inv), F.lit(False)).alias("inv"),
            F.when(is_prop, "obj").otherwise("isa").alias("kind"), (F.col("hop") + rank).cast("int").alias("hop"), (rank == total).alias("aligned"),
        ).withColumnRenamed("node2", "node")
        level = _settle(nodes, NODE_SCHEMA)
        if level.isEmpty():
            return _settle(out, NODE_SCHEMA)
        out = _settle(out.unionByName(level), NODE_SCHEMA)


def semantic_associations(spark: SparkSession, a: Alignment, side: str, max_len: int = 4, max_depth: int = 6, paths: DataFrame | None = None) -> dict[str, Tree]:
    """The association tree of every aligned concept of one side."""
    kb, aligned = a.side(side), a.aligned_concepts(side)
    paths = association_paths(spark, kb, aligned, max_len) if paths is None else paths
    rows = tree_nodes(spark, kb, aligned, paths, max_depth).collect()
    attrs = a.aligned_attrs(side)
    by_root: dict[str, list[Node]] = {c: [] for c in aligned}
    for r in sorted(rows, key=lambda r: (r.root, r.hop, r.node)):
        by_root[r.root].append(Node(r.root, r.node, r.parent, r.concept, r.edge, r.inv, r.hop, r.aligned))
    return {c: Tree(kb, c, ns, [(n.id, at) for n in ns if n.aligned for owner, at in attrs if owner == n.concept]) for c, ns in by_root.items()}


def basic_associations(a: Alignment, side: str) -> dict[str, list[str]]:
    attrs = a.aligned_attrs(side)
    return {c: [x for o, x in attrs if o == c] for c in a.aligned_concepts(side)}


def tree_closure(nodes: DataFrame) -> DataFrame:
    """(root, anc, desc) for every node and each node above it, by one join per level."""
    up = nodes.where("parent is not null").selectExpr("root", "node as desc", "parent as anc")
    schema = "root string, desc string, anc string"
    parents = F.broadcast(up.selectExpr("root", "desc as anc", "anc as higher"))
    level = out = _settle(up, schema)
    while not level.isEmpty():
        level = _settle(level.join(parents, ["root", "anc"]).selectExpr("root", "desc", "higher as anc"), schema)
        out = out.unionByName(level)
    return _settle(out, schema).select("root", "anc", "desc")
