"""From an alignment to facts: trees, skeletons, valid renamings of all skeletons, ranks, chosen rules.

``mappings`` has every valid renaming of every kept skeleton as one table; ``choose`` keeps the best of each skeleton;
``rules_of`` turns the chosen rows into rules; ``exchange_all`` runs them. A selection session replays an engineer's
decisions over the ranked rows.
"""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..operators import assoc, interpret
from ..sources.model import Alignment, Source
from .rules import Rule, exchange

ALL_CHECKS = ("r2r", "c2a", "owner")


@dataclass
class Generation:
    """Trees and kept skeletons of one alignment. The schema layer is small and lives on the driver; renamings don't."""

    spark: SparkSession
    a: Alignment
    max_len: int = 4
    max_depth: int = 6
    trees: dict = field(default_factory=dict)
    skeletons: dict = field(default_factory=dict)

    def __post_init__(self):
        sides = []
        for side in "st":
            self.trees.setdefault(side, assoc.semantic_associations(self.spark, self.a, side, self.max_len, self.max_depth))
            sides.append(interpret.summaries(self.spark, self.a, self.trees[side], side))
        kept = interpret.reduced_skeletons(*sides).select("s_root", "t_root").collect()  # one row per skeleton: bounded by the schema
        for r in sorted(kept):
            self.skeletons[r.s_root, r.t_root] = interpret.Skeleton(self.a, self.trees["s"][r.s_root], self.trees["t"][r.t_root])

    def mappings(self, checks: tuple[str, ...] = ALL_CHECKS, c2a_mode: str = "strict") -> DataFrame:
        """(s_root, t_root, asg, path_cost, cons_cost, cov_cost, combined) of all skeletons."""
        edges = interpret.edge_pairs(self.spark, self.a, max_len=self.max_len)
        parts = []
        for (s_root, t_root), sk in self.skeletons.items():
            found = interpret.renamings(self.spark, sk, checks=checks, c2a_mode=c2a_mode)
            parts.append(interpret.costed(self.spark, sk, found, edges).select(F.lit(s_root).alias("s_root"), F.lit(t_root).alias("t_root"), "*"))
        return reduce(DataFrame.unionByName, parts)

    def validity_table(self, c2a_mode: str = "literal") -> DataFrame:
        """(baseline, r2r, c2a, both): mappings of all skeletons under each combination of the validity notions."""
        parts = [interpret.validity_counts(self.spark, sk, c2a_mode) for sk in self.skeletons.values()]
        names = ("baseline", "r2r", "c2a", "both")
        return reduce(DataFrame.unionByName, parts).agg(*[F.sum(n).alias(n) for n in names])

    def rules_of(self, chosen: Iterable) -> list[Rule]:
        """Rules of chosen rows (s_root, t_root, asg); invented nodes of different rows have different labels."""
        return [Rule(self.skeletons[r.s_root, r.t_root], list(r.asg), f"m{k}") for k, r in enumerate(chosen)]


def ranked(mappings: DataFrame, by: str = "combined") -> DataFrame:
    """Add ``rank`` (dense) and ``better`` within each skeleton, from the few distinct costs of each."""
    keys = ["s_root", "t_root"]
    h = mappings.groupBy(*keys, by).agg(F.count(F.lit(1)).alias("equal"))
    w = W.partitionBy(*keys).orderBy(by)
    h = h.withColumns({"rank": F.dense_rank().over(w).cast("long"), "better": (F.sum("equal").over(w) - F.col("equal")).cast("long")})
    return mappings.join(h, [*keys, by])


def choose(mappings: DataFrame, by: str = "combined", per_skeleton: int = 1) -> DataFrame:
    """The best mappings of each skeleton: by the cost, then fewest empty variables, then the assignment; empty ones never."""
    w = W.partitionBy("s_root", "t_root").orderBy(by, "cov_cost", "asg")
    some = mappings.where(F.exists("asg", lambda x: x >= 0))
    return some.withColumn("_n", F.row_number().over(w)).where(F.col("_n") <= per_skeleton).drop("_n")


def exchange_all(gen: Generation, src: Source, by: str = "combined", per_skeleton: int = 1, max_rules: int = 1000) -> DataFrame:
    """The facts of the chosen mappings of all skeletons."""
    rows = choose(gen.mappings(), by, per_skeleton).orderBy("s_root", "t_root", by, "asg").limit(max_rules + 1).collect()
    if len(rows) > max_rules:
        raise ValueError("too many chosen mappings to run as rules")
    return exchange(gen.rules_of(rows), src)


def examples(gen: Generation, src: Source, top: int, per_rule: int = 3, by: str = "combined") -> DataFrame:
    """(place, s, facts): for the ``top`` ranked mappings the individuals of most facts."""
    rows = choose(gen.mappings(), by, top).orderBy(by, "cov_cost", "s_root", "t_root", "asg").limit(top).collect()
    parts = []
    for place, rule in enumerate(gen.rules_of(rows), 1):
        facts = rule.construct(src).distinct().where("not startswith(s, '_:')")
        best = facts.groupBy("s").agg(F.count(F.lit(1)).alias("facts")).orderBy(F.desc("facts"), "s").limit(per_rule)
        parts.append(best.select(F.lit(place).cast("long").alias("place"), "s", "facts"))
    return reduce(DataFrame.unionByName, parts)


@dataclass
class Selection:
    """A session in which someone keeps or refuses ranked mappings; a refusal of a variable's value refuses all that share it."""

    kept: list[tuple[str, str, tuple[int, ...]]] = field(default_factory=list)
    refused: list[tuple[str, str, int, int]] = field(default_factory=list)

    def keep(self, s_root: str, t_root: str, asg: Iterable[int]) -> None:
        self.kept.append((s_root, t_root, tuple(asg)))

    def refuse(self, s_root: str, t_root: str, target_variable: int, source_variable: int) -> None:
        self.refused.append((s_root, t_root, target_variable, source_variable))

    def open(self, mappings: DataFrame) -> DataFrame:
        """What is still to be judged."""
        out = mappings
        for s, t, tv, sv in self.refused:
            out = out.where(~((F.col("s_root") == s) & (F.col("t_root") == t) & (F.get("asg", F.lit(tv)) == sv)))
        if self.kept:
            kept = mappings.sparkSession.createDataFrame([(s, t, list(a)) for s, t, a in self.kept], "s_root string, t_root string, asg array<int>")
            out = out.join(F.broadcast(kept), ["s_root", "t_root", "asg"], "left_anti")  # one row per decision
        return out

    def quality(self, desirable: set[tuple[str, str, tuple[int, ...]]]) -> dict[str, float]:
        """Recall and precision of what was kept."""
        hits = len(desirable & set(self.kept))
        return {"recall": hits / len(desirable) if desirable else 1.0, "precision": hits / len(set(self.kept)) if self.kept else 1.0}
