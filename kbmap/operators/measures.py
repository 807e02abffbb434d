"""Measures over schemas, rules and facts."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..sources.model import KB, Source


def kb_profile(spark: SparkSession, kb: KB) -> DataFrame:
    """(kb, classes, attributes, object_properties)."""
    cls, _, prop = kb.frames(spark)
    p = prop.agg(F.count_distinct(F.when(F.col("kind") == "attr", F.struct("prop", "domain"))).alias("attributes"), F.count_distinct(F.when(F.col("kind") == "obj", F.struct("prop", "domain", "range"))).alias("object_properties"))
    return cls.agg(F.count(F.lit(1)).alias("classes")).join(p).select(F.lit(kb.name).alias("kb"), "classes", "attributes", "object_properties")


def fact_recall(out: DataFrame, gold: DataFrame) -> DataFrame:
    """(hits, produced, gold, recall, precision, f1) of two sets of facts with columns s, p, o."""
    cols = ["s", "p", "o"]
    both = out.select(*cols).distinct().withColumn("a", F.lit(1)).join(gold.select(*cols).distinct().withColumn("b", F.lit(1)), cols, "full")
    n = both.agg(F.count(F.expr("a + b")).alias("hits"), F.count("a").alias("produced"), F.count("b").alias("gold"))
    r, p = F.col("hits") / F.col("gold"), F.col("hits") / F.col("produced")
    return n.withColumns({"recall": F.round(r, 6), "precision": F.round(p, 6), "f1": F.round(2 * F.col("hits") / (F.col("gold") + F.col("produced")), 6)})


def facts_lost(out: DataFrame, gold: DataFrame) -> DataFrame:
    """(p, lost): gold facts that are not produced, by predicate."""
    cols = ["s", "p", "o"]
    return gold.select(*cols).distinct().join(out.select(*cols).distinct(), cols, "left_anti").groupBy("p").agg(F.count(F.lit(1)).alias("lost"))


def blank_stats(facts: DataFrame) -> DataFrame:
    """(invented, bare): invented nodes, and those with a type and nothing else."""
    per = facts.where("startswith(s, '_:')").groupBy("s").agg(F.max(F.when(F.col("p") != "type", 1).otherwise(0)).alias("more"))
    return per.agg(F.count(F.lit(1)).alias("invented"), F.coalesce(F.sum(1 - F.col("more")), F.lit(0)).cast("long").alias("bare"))


def kb_similarity(n_pairs: int, source_elements: int, target_elements: int) -> float:
    """Dice share of elements that model the same thing, from an expert's pair list."""
    return 2 * n_pairs / (source_elements + target_elements)


def delta(mappings: int, correspondences: int, absolute: bool = True) -> int:
    d = mappings - correspondences
    return abs(d) if absolute else d


def growth(series: DataFrame) -> DataFrame:
    """(x, n, diff, second, ratio): constant first differences are linear growth, constant second ones quadratic, constant ratios exponential."""
    w = W.orderBy("x")  # one row per setting of an experiment
    d = series.withColumns({"diff": F.col("n") - F.lag("n").over(w), "ratio": F.round(F.col("n") / F.lag("n").over(w), 6)})
    return d.withColumn("second", F.col("diff") - F.lag("diff").over(w))


def growth_type(series: DataFrame) -> DataFrame:
    """(series, growth): linear if the first differences of (series, x, n) agree, quadratic if the second, exponential if the ratios do."""
    w = W.partitionBy("series").orderBy("x")  # one row per setting of an experiment
    d = series.withColumn("d", F.col("n") - F.lag("n").over(w)).withColumn("r", F.round(F.col("n") / F.lag("n").over(w), 6)).withColumn("dd", F.col("d") - F.lag("d").over(w))
    same = lambda c: F.min(c) == F.max(c)
    kind = F.when(same("d"), "linear").when(same("dd"), "quadratic").when(same("r"), "exponential").otherwise("other")
    return d.groupBy("series").agg(kind.alias("growth"))


def overlap_dictionary(types: DataFrame, threshold: float = 0.2, measure: str = "min", disjoint: list[tuple[str, str]] = ()) -> DataFrame:
    """(c1, c2, shared, ratio): pairs of classes whose individuals overlap enough, from (id, cls).

    Individuals with the same set of classes are counted first, so pairs are formed between class sets, not individuals.
    """
    sets = types.distinct().groupBy("id").agg(F.array_sort(F.collect_set("cls")).alias("cs")).groupBy("cs").agg(F.count(F.lit(1)).alias("n"))
    size = types.distinct().groupBy("cls").agg(F.count(F.lit(1)).alias("n"))
    pairs = sets.select("n", "cs", F.explode("cs").alias("c1")).select("n", "c1", F.explode("cs").alias("c2")).where("c1 < c2").groupBy("c1", "c2").agg(F.sum("n").alias("shared"))
    a, b = size.selectExpr("cls as c1", "n as n1"), size.selectExpr("cls as c2", "n as n2")
    denominator = {"min": F.least("n1", "n2"), "left": F.col("n1"), "jaccard": F.col("n1") + F.col("n2") - F.col("shared")}[measure]
    out = pairs.join(a, "c1").join(b, "c2").select("c1", "c2", "shared", F.round(F.col("shared") / denominator, 6).alias("ratio")).where(F.col("ratio") >= threshold)
    for x, y in disjoint:
        out = out.where(~((F.col("c1") == min(x, y)) & (F.col("c2") == max(x, y))))
    return out


def knowledge_fragment(kb: KB, seeds: set[str], depth: int) -> KB:
    """The part of a schema within ``depth`` steps of the seeds: a class brings its attributes at its depth, an object
    property its ends; equivalences cost nothing."""
    def free(found):
        while True:
            more = {y for a, b in kb.equivalent for x, y in ((a, b), (b, a)) if x in found} - found
            if not more:
                return found
            found |= more

    classes = free({s for s in seeds if s in kb.classes})
    props = {p for p in kb.props if p.name in seeds}
    for _ in range(depth):
        at = frozenset(classes)
        props |= {p for p in kb.props if p.range and (p.domain in at or p.range in at)}
        classes |= {c for p in props for c in (p.domain, p.range) if c}
        classes |= {b for a, b in kb.subclasses if a in at} | {a for a, b in kb.subclasses if b in at}
        classes = free(classes)
    props = {p for p in props if p.domain in classes and (not p.range or p.range in classes)} | {p for p in kb.props if not p.range and p.domain in classes}
    keep = [c for c in kb.classes if c in classes]
    return KB(kb.name, keep, [p for p in kb.props if p in props], [(a, b) for a, b in kb.subclasses if a in classes and b in classes])


def simplify_profile(solutions: DataFrame) -> DataFrame:
    """(var, ever, always): variables never bound can be dropped, those always bound need no OPTIONAL. One pass."""
    cols = solutions.columns
    flags = solutions.agg(*[F.max(F.col(f"`{c}`").isNotNull()).alias(f"e{i}") for i, c in enumerate(cols)], *[F.min(F.col(f"`{c}`").isNotNull()).alias(f"m{i}") for i, c in enumerate(cols)])
    rows = [F.struct(F.lit(c).alias("var"), F.coalesce(F.col(f"e{i}"), F.lit(False)).alias("ever"), F.coalesce(F.col(f"m{i}"), F.lit(False)).alias("always")) for i, c in enumerate(cols)]
    return flags.select(F.explode(F.array(*rows)).alias("r")).select("r.*")


def restrict_instances(src: Source, fragment: KB) -> Source:
    kept = {p.name for p in fragment.props}
    return Source(fragment, {k: v for k, v in src.types.items() if k in fragment.classes}, {k: v for k, v in src.objects.items() if k in kept}, {k: v for k, v in src.attrs.items() if k[0] in fragment.classes})
