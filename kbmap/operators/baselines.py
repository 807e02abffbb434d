"""Baselines: narrower notions of association, and rules without any."""

from __future__ import annotations

from collections import Counter
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.paths import skolem
from ..sources.model import Alignment, Source
from .assoc import PATH_SCHEMA, Tree, _settle, association_paths, semantic_associations


def aligned_property_associations(spark: SparkSession, a: Alignment, side: str, strong: tuple[tuple[str, str], ...] = (), max_len: int = 4, max_depth: int = 6) -> dict[str, Tree]:
    """Trees whose only edges are isa and properties with a length-one path correspondence.

    ``strong`` holds (property, ``domain`` or ``range``) annotations that make further properties count, as foreign keys would.
    """
    kb = a.side(side)
    kept = {p[0].prop for c in a.corrs if c.kind == "r2r" for p in [c.s_path if side == "s" else c.t_path] if len(p) == 1} | {p for p, _ in strong}
    paths = association_paths(spark, kb, a.aligned_concepts(side), max_len)
    only = F.forall("steps", lambda s: (s.kind != "obj") | s.elem.isin(*kept)) if kept else F.forall("steps", lambda s: s.kind != "obj")
    return semantic_associations(spark, a, side, max_len, max_depth, _settle(paths.where(only), PATH_SCHEMA))


def shortest_associations(paths: DataFrame) -> DataFrame:
    """Only the shortest association paths of each pair of concepts, ties kept."""
    return paths.withColumn("_r", F.rank().over(W.partitionBy("root", "tail").orderBy("hops"))).where("_r = 1").drop("_r")


def functional_profile(src: Source) -> DataFrame:
    """(prop, subjects, facts, typed, fk): ``fk`` marks properties with exactly one value for every individual of their domain."""
    rows = []
    for p in (p for p in src.kb.props if p.range and p.name in src.objects):
        facts = src.objects[p.name]().groupBy("s").agg(F.count(F.lit(1)).alias("n"))
        one = facts.agg(F.count(F.lit(1)).alias("subjects"), F.coalesce(F.sum("n"), F.lit(0)).alias("facts"))
        typed = src.types[p.domain]().agg(F.count(F.lit(1)).alias("typed"))
        rows.append(one.join(typed).select(F.lit(p.name).alias("prop"), "subjects", "facts", "typed"))  # one row by one row
    return reduce(DataFrame.unionByName, rows).withColumn("fk", (F.col("subjects") == F.col("facts")) & (F.col("subjects") == F.col("typed")))


def fk_associations(spark: SparkSession, a: Alignment, src: Source, max_len: int = 4, max_depth: int = 6) -> dict[str, Tree]:
    """Association trees of the source over total functional properties alone."""
    keys = [r.prop for r in functional_profile(src).where("fk").collect()]
    paths = association_paths(spark, src.kb, a.aligned_concepts("s"), max_len)
    ok = F.forall("steps", lambda s: (s.kind != "obj") | s.elem.isin(*keys)) if keys else F.forall("steps", lambda s: s.kind != "obj")
    return semantic_associations(spark, a, "s", max_len, max_depth, _settle(paths.where(ok), PATH_SCHEMA))


def independent_facts(a: Alignment, src: Source) -> DataFrame:
    """One rule per correspondence: nothing that two of them make is the same node, so values end up apart."""
    out = []
    for c in a.corrs:
        if c.kind == "c2c":
            ids = src.types[c.s1]()
            out.append(ids.select("id", F.lit("type").alias("p"), F.lit("iri").alias("o_kind"), F.lit(c.t1).alias("o")).withColumnRenamed("id", "s"))
        elif c.kind == "a2a" and len(c.s_path) == 1 and len(c.t_path) == 1:
            values = src.attrs[c.s1, c.s_path[0].prop]()
            node = skolem(c.id, [F.col("s")])
            out.append(values.select(node.alias("s"), F.lit("type").alias("p"), F.lit("iri").alias("o_kind"), F.lit(c.t1).alias("o")))
            out.append(values.select(node.alias("s"), F.lit(c.t_path[0].prop).alias("p"), F.lit("lit").alias("o_kind"), F.col("v").alias("o")))
        elif c.kind == "r2r" and len(c.s_path) == 1 and len(c.t_path) == 1:
            s, o = ("o", "s") if c.s_path[0].inv != c.t_path[0].inv else ("s", "o")
            out.append(src.objects[c.s_path[0].prop]().select(F.col(s).alias("s"), F.lit(c.t_path[0].prop).alias("p"), F.lit("iri").alias("o_kind"), F.col(o).alias("o")))
    return reduce(DataFrame.unionByName, out).distinct()


def from_examples(source_rows: list[tuple[str, str, str]], target_rows: list[tuple[str, str, str]]) -> list[tuple[str, str, int]]:
    """(source property, target property, support) read off a user's example facts: properties that join the same two values."""
    links = Counter()
    for s, p, o in source_rows:
        for s2, q, o2 in target_rows:
            if (s, o) == (s2, o2):
                links[p, q] += 1
            elif (s, o) == (o2, s2):
                links["^" + p, q] += 1
    return sorted(((p, q, n) for (p, q), n in links.items()), key=lambda x: (-x[2], x))
