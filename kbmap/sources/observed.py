"""A scenario as the given tables show it: what of the source knowledge base holds facts, and how many.

Counting is Spark's work over the instance views; one row per schema element reaches the driver. Elements without facts go, and
with them the correspondences that name them, so what is built on a shown alignment follows from the tables.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .model import KB, Alignment, Corr, Source

#: Facts by element: (class, c, ""), (sub, a, b) or (prop, name, domain).
Facts = dict[tuple[str, str, str], int]


def fact_counts(src: Source) -> DataFrame:
    """(kind, name, of, n): instances of classes, instances of a class that its superclass has too, edges whose ends are in domain and range, values on instances."""

    def counted(df: DataFrame, kind: str, name: str, of: str = "") -> DataFrame:
        return df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(kind).alias("kind"), F.lit(name).alias("name"), F.lit(of).alias("of"), "n")

    ids = lambda c, key: src.types[c]().select(F.col("id").alias(key)).distinct()
    parts = [counted(ids(c, "id"), "class", c) for c in src.kb.classes]
    parts += [counted(ids(a, "id").join(ids(b, "id"), "id", "left_semi"), "sub", a, b) for a, b in src.kb.subclasses]
    for p in src.kb.props:
        facts = src.objects[p.name]() if p.range else src.attrs[p.domain, p.name]()
        facts = facts.join(ids(p.domain, "s"), "s", "left_semi")
        parts.append(counted(facts.join(ids(p.range, "o"), "o", "left_semi") if p.range else facts, "prop", p.name, p.domain))
    return reduce(DataFrame.unionByName, parts)


def shown(a: Alignment, src: Source) -> tuple[Alignment, Facts]:
    """The alignment cut to source elements with facts (of subclass pairs those that hold for every instance), and the numbers of facts."""
    n: Facts = {(r.kind, r["name"], r["of"]): r.n for r in fact_counts(src).collect()}  # one row per schema element
    kb = a.source
    classes = [c for c in kb.classes if n["class", c, ""]]
    props = [p for p in kb.props if n["prop", p.name, p.domain]]
    subs = [(x, y) for x, y in kb.subclasses if n["sub", x, y] == n["class", x, ""] > 0]
    names = {p.name for p in props}
    corrs = [c for c in a.corrs if c.s1 in classes and (c.s2 is None or c.s2 in classes) and all(s.prop in names for s in c.s_path)]
    return Alignment(KB(kb.name, classes, props, subs), a.target, corrs), n


def corr_facts(a: Alignment, n: Facts, c: Corr) -> int:
    """Source facts of a correspondence: instances of its class, or facts of its path's last property."""
    if c.kind == "c2c":
        return n["class", c.s1, ""]
    last = c.s_path[-1].prop
    if c.kind == "a2a":
        return n["prop", last, a.owner(c, "s")[0]]
    return next(n["prop", p.name, p.domain] for p in a.source.props if p.name == last)


def weakest_step(facts: Facts, root: str, steps) -> int:
    """The fewest facts on a step of an association path."""
    at, least = root, []
    for k, s in enumerate(steps):
        if s.kind == "class":
            edge = steps[k - 1] if k and steps[k - 1].kind != "class" else None
            least.append(facts["sub", at, s.elem] if edge is None else facts["prop", edge.elem, s.elem if edge.inv else at])
            at = s.elem
    return min(least)


def path_rows(paths: DataFrame, facts: Facts) -> list[tuple]:
    """(root, tail, path_id, hops, facts) of association paths, which are schema metadata under a row guard."""
    return [(r.root, r.tail, r.path_id, r.hops, weakest_step(facts, r.root, r.steps)) for r in paths.collect()]
