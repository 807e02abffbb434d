"""Knowledge bases, correspondences and instance data.

A knowledge base is its RDFS layer: classes, subclass pairs and properties with domain and range. The layer is
small by nature and is held on the driver; ``frames`` gives it as DataFrames. Instance data stay in
columnar tables: a Source maps classes and properties to lazy DataFrames (virtual facts).
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

from ..functions.paths import Path, Step, parse_path

CLASS_SCHEMA = "kb string, cls string"
SUBCLASS_SCHEMA = "kb string, sub string, sup string"
PROP_SCHEMA = "kb string, prop string, kind string, domain string, range string, dt string"
LABEL = "label"


class UnsupportedCorrespondence(ValueError):
    """A metadata-to-data correspondence, which rules cannot express."""


@dataclass(frozen=True)
class Prop:
    name: str
    domain: str
    range: str | None = None  # None: an attribute
    dt: str = "string"


@dataclass
class KB:
    name: str
    classes: list[str]
    props: list[Prop]
    subclasses: list[tuple[str, str]] = field(default_factory=list)
    disjoint: list[tuple[str, str]] = field(default_factory=list)
    equivalent: list[tuple[str, str]] = field(default_factory=list)

    def __post_init__(self):
        known = set(self.classes)
        used = {c for p in self.props for c in (p.domain, p.range) if c} | {c for pair in self.subclasses for c in pair}
        if used - known:
            raise ValueError(f"undeclared classes in {self.name}: {sorted(used - known)}")

    def frames(self, spark: SparkSession) -> tuple[DataFrame, DataFrame, DataFrame]:
        kinds = [(self.name, p.name, "obj" if p.range else "attr", p.domain, p.range, None if p.range else p.dt) for p in self.props]
        return (
            spark.createDataFrame([(self.name, c) for c in self.classes], CLASS_SCHEMA),
            spark.createDataFrame([(self.name, a, b) for a, b in self.subclasses], SUBCLASS_SCHEMA),
            spark.createDataFrame(kinds, PROP_SCHEMA),
        )

    def superclasses(self, cls: str) -> set[str]:
        """The class itself and all above it."""
        found, todo = set(), [cls]
        while todo:
            c = todo.pop()
            if c not in found:
                found.add(c)
                todo += [b for a, b in self.subclasses if a == c]
        return found

    def subclass_closure(self, cls: str) -> set[str]:
        return {c for c in self.classes if cls in self.superclasses(c)}


@dataclass(frozen=True)
class Corr:
    """``kind``: c2c, r2r or a2a. For a2a the last step of a path is the attribute."""

    id: str
    kind: str
    s1: str
    t1: str
    s_path: Path = ()
    t_path: Path = ()
    s2: str | None = None
    t2: str | None = None


def corr_c2c(id: str, s: str, t: str) -> Corr:
    return Corr(id, "c2c", s, t)


def corr_r2r(id: str, s1: str, s_path: str, s2: str, t1: str, t_path: str, t2: str) -> Corr:
    return Corr(id, "r2r", s1, t1, *(parse_path(p)[0] for p in (s_path, t_path)), s2, t2)


def corr_a2a(id: str, s: str, s_path: str, t: str, t_path: str) -> Corr:
    return Corr(id, "a2a", s, t, *(parse_path(p)[0] for p in (s_path, t_path)))


def corr_value_to_instance(id: str, s: str, attr: str, t: str) -> Corr:
    """Values of an attribute name instances of a target class: matched to the class's label."""
    return Corr(id, "a2a", s, t, (Step(attr),), (Step(LABEL),))


def corr_metadata_to_data(*_):
    raise UnsupportedCorrespondence("a class or property cannot correspond to data values")


def _through(kb: KB, start: str, path: Path) -> list[str]:
    """Concepts along a data path before its attribute."""
    found, at = [start], start
    for step in path[:-1]:
        ups = kb.superclasses(at)
        hits = [p.domain if step.inv else p.range for p in kb.props if p.name == step.prop and p.range and (p.range if step.inv else p.domain) in ups]
        if not hits:
            raise ValueError(f"{step.prop} does not leave {at}")
        at = hits[0]
        found.append(at)
    return found


@dataclass
class Alignment:
    source: KB
    target: KB
    corrs: list[Corr]

    def side(self, side: str) -> KB:
        return self.source if side == "s" else self.target

    def aligned_concepts(self, side: str) -> list[str]:
        """Ends of concept correspondences and owners (and concepts on the way) of attribute ones; path correspondences add none."""
        kb, found = self.side(side), {}
        for c in self.corrs:
            start, path = (c.s1, c.s_path) if side == "s" else (c.t1, c.t_path)
            if c.kind == "c2c":
                found[start] = True
            elif c.kind == "a2a":
                found |= dict.fromkeys(_through(kb, start, path), True)
        return list(found)

    def aligned_attrs(self, side: str) -> list[tuple[str, str]]:
        """(owner, attribute) pairs of attribute correspondences."""
        kb, found = self.side(side), {}
        for c in self.corrs:
            if c.kind == "a2a":
                start, path = (c.s1, c.s_path) if side == "s" else (c.t1, c.t_path)
                found[(_through(kb, start, path)[-1], path[-1].prop)] = True
        return list(found)

    def owner(self, c: Corr, side: str) -> tuple[str, str]:
        start, path = (c.s1, c.s_path) if side == "s" else (c.t1, c.t_path)
        return _through(self.side(side), start, path)[-1], path[-1].prop

    def profile(self) -> dict[str, int]:
        return {k: sum(c.kind == k for c in self.corrs) for k in ("c2c", "a2a", "r2r")}

    def aligned_elements(self, side: str) -> set[str]:
        found = set(self.aligned_concepts(side)) | {a for _, a in self.aligned_attrs(side)}
        for c in self.corrs:
            if c.kind == "r2r":
                found |= {s.prop for s in (c.s_path if side == "s" else c.t_path)}
        return found


@dataclass
class Source:
    """Virtual facts: (id) per class, (s, o) per object property, (s, v) per (class, attribute), v a lexical form.

    Each entry is a function that builds a lazy DataFrame, so unused ones cost nothing.
    """

    kb: KB
    types: dict[str, Callable[[], DataFrame]]
    objects: dict[str, Callable[[], DataFrame]]
    attrs: dict[tuple[str, str], Callable[[], DataFrame]]
