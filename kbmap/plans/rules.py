"""Mapping rules: from renamings to target facts, as DataFrame plans and as SPARQL text.

A rule is one source tree, one target tree and an assignment. Its template has type, edge and attribute facts. In the
factored plan each fact needs only the source nodes on its own root paths, so facts are grouped by what they need, each
group is one chain of inner joins (a fact with an unbound variable is left out anyway) and sibling branches never multiply.
The joint plan evaluates the whole pattern with nested left joins first; both give the same set of facts under scoped
invention. Results are sets: one ``distinct`` at the end.
"""

from __future__ import annotations

from collections import defaultdict
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.paths import skolem
from ..operators.interpret import Skeleton
from ..sources.model import Source

TYPE = "type"


@dataclass(frozen=True)
class Term:
    """A source node's individual, or an invented node labelled by a target variable and keyed by source nodes."""

    node: str | None = None
    blank: str | None = None
    keys: tuple[str, ...] = ()
    guard: tuple[tuple[str, str], ...] = ()  # attributes of which one must be present


@dataclass(frozen=True)
class Fact:
    subject: Term
    prop: str
    object: Term | None = None
    cls: str | None = None
    value: tuple[str, str] | None = None  # (source node, attribute)


@dataclass
class Rule:
    sk: Skeleton
    asg: list[int]
    name: str = "r"
    isa_bind: str = "group"

    def __post_init__(self):
        s, t = self.sk.s, self.sk.t
        self.image: dict[str, str] = {}
        for tv, (tn, ta) in enumerate(t.vars):
            if ta is None and self.asg[tv] >= 0:
                top = t.individual(tn)
                if self.isa_bind == "group" or top == tn:
                    self.image.setdefault(top, s.individual(s.vars[self.asg[tv]][0]))
                self.image[tn] = self.image.get(top, s.individual(s.vars[self.asg[tv]][0]))

    def _fed(self, tn: str) -> list[tuple[str, str | None]]:
        """Source variables mapped to attributes of the target individual at tn or to anything below it."""
        t, out = self.sk.t, []
        top = t.individual(tn)
        for tv, (n, at) in enumerate(t.vars):
            inside = t.individual(n) == top or any(t.individual(x) == top for x in t.ancestors(n))
            if self.asg[tv] >= 0 and inside and (at is not None or t.individual(n) != top):
                out.append(self.sk.s.vars[self.asg[tv]])
        return out

    def needs_blank(self) -> set[str]:
        """Target individuals to invent: unmapped ones at or above something mapped."""
        return {n.id for n in self.sk.t.nodes if self.sk.t.individual(n.id) == n.id and n.id not in self.image and self._fed(n.id)}

    def term(self, tn: str) -> Term | None:
        s, t = self.sk.s, self.sk.t
        top = t.individual(tn)
        if top in self.image:
            return Term(node=self.image[top])
        fed = self._fed(top)
        if not fed:
            return None
        tops = [[s.individual(x) for x in reversed([n, *s.ancestors(n)])] for n, _ in fed]
        chains = [list(dict.fromkeys(c)) for c in tops]
        shared = [x[0] for x in zip(*chains) if len(set(x)) == 1]
        guard = tuple((s.individual(n), at) for n, at in fed) if all(at is not None and s.individual(n) == shared[-1] for n, at in fed) else ()
        return Term(blank=f"{self.name},{t.index[top, None]}", keys=tuple(shared), guard=guard)

    def template(self) -> list[Fact]:
        s, t, out = self.sk.s, self.sk.t, []
        for n in t.nodes:
            me = self.term(n.id)
            if me is None:
                continue
            out.append(Fact(me, TYPE, cls=n.concept))
            if n.parent and n.edge != "a":
                up = self.term(n.parent)
                if up is not None:
                    out.append(Fact(me, n.edge, up) if n.inv else Fact(up, n.edge, me))
        for tv, (tn, at) in enumerate(t.vars):
            if at is not None and self.asg[tv] >= 0:
                sn, sa = s.vars[self.asg[tv]]
                out.append(Fact(self.term(tn), at, value=(s.individual(sn), self._owner_attr(sn, sa))))
        return list(dict.fromkeys(out))

    def _owner_attr(self, sn: str, sa: str) -> str:
        return f"{self.sk.s.by_id[sn].concept}.{sa}"

    # Evaluation.

    def _need(self, f: Fact) -> frozenset[str]:
        s, nodes = self.sk.s, set()
        for t in (f.subject, f.object):
            if t is not None:
                nodes |= {t.node} if t.node else set(t.keys)
        if f.value:
            nodes.add(f.value[0])
        return frozenset(s.individual(x) for n in nodes for x in [n, *s.ancestors(n)])

    def solutions(self, src: Source, nodes: frozenset[str], attrs: set[tuple[str, str]], left: bool = False) -> DataFrame:
        """One column per source individual of ``nodes`` and per attribute. ``left`` keeps rows whose branches are missing."""
        s, how = self.sk.s, "left" if left else "inner"
        label = {n.id: f"v{i}" for i, n in enumerate(s.nodes)}
        df = src.types[s.root]().select(F.col("id").alias(label[s.nodes[0].id]))
        for n in s.nodes[1:]:
            if n.edge == "a" or n.id not in nodes:
                continue
            up, me = label[s.individual(n.parent)], label[n.id]
            a, b = ("o", "s") if n.inv else ("s", "o")
            edge = src.objects[n.edge]().select(F.col(a).alias(up), F.col(b).alias(me))
            edge = edge.join(src.types[n.concept]().select(F.col("id").alias(me)), me, "left_semi")
            df = df.join(edge, up, how)
        for node, attr in sorted(attrs):
            cls, name = attr.split(".", 1)
            values = src.attrs[cls, name]().select(F.col("s").alias(label[node]), F.col("v").alias(f"{label[node]}.{attr}"))
            df = df.join(values, label[node], "left")
        return df

    def _column(self, t: Term, per_solution: list[str] | None) -> Column:
        label = {n.id: f"v{i}" for i, n in enumerate(self.sk.s.nodes)}
        if t.node:
            return F.col(label[t.node])
        if per_solution is not None:
            return skolem(t.blank, [F.coalesce(F.col(c), F.lit("~")) for c in per_solution])
        made = skolem(t.blank, [F.col(label[k]) for k in t.keys])
        if t.guard:
            made = F.when(reduce(lambda x, y: x | y, [F.col(f"`{label[n]}.{self._owner_attr_of(n, a)}`").isNotNull() for n, a in t.guard]), made)
        return made

    def _owner_attr_of(self, n: str, a: str) -> str:
        group = [x for x in self.sk.s.nodes if self.sk.s.individual(x.id) == n]
        return next(f"{x.concept}.{a}" for x in group if (x.id, a) in self.sk.s.index)

    def _facts(self, sols: DataFrame, facts: list[Fact], per_solution: list[str] | None = None) -> DataFrame:
        label = {n.id: f"v{i}" for i, n in enumerate(self.sk.s.nodes)}
        rows = []
        for f in facts:
            subject = self._column(f.subject, per_solution)
            if f.value:
                kind, o = "lit", F.col(f"`{label[f.value[0]]}.{f.value[1]}`")
            elif f.cls:
                kind, o = "iri", F.lit(f.cls)
            else:
                kind, o = "blank" if f.object.blank else "iri", self._column(f.object, per_solution)
            rows.append(F.struct(subject.alias("s"), F.lit(f.prop).alias("p"), F.lit(kind).alias("o_kind"), o.alias("o")))
        return sols.select(F.explode(F.array(*rows)).alias("f")).select("f.*").where("s is not null and o is not null")

    def _attrs(self, facts: list[Fact]) -> set[tuple[str, str]]:
        out = {f.value for f in facts if f.value}
        for f in facts:
            for t in (f.subject, f.object):
                if t is not None and t.guard:
                    out |= {(n, self._owner_attr_of(n, a)) for n, a in t.guard}
        return out

    def construct(self, src: Source, plan: str = "factored", blank_mode: str = "scoped") -> DataFrame:
        """(s, p, o_kind, o): the rule's facts, possibly repeated; ``exchange`` makes them a set."""
        facts = self.template()
        if plan == "factored" and blank_mode == "scoped":
            groups = defaultdict(list)
            for f in facts:
                groups[self._need(f)].append(f)
            parts = [self._facts(self.solutions(src, need, self._attrs(fs)), fs) for need, fs in groups.items()]
            return reduce(DataFrame.unionByName, parts)
        need = frozenset().union(*(self._need(f) for f in facts))
        sols = self.solutions(src, need, self._attrs(facts), left=True)
        label = {n.id: f"v{i}" for i, n in enumerate(self.sk.s.nodes)}
        whole = [label[n.id] for n in self.sk.s.nodes if n.id in need] if blank_mode == "per_solution" else None
        return self._facts(sols, facts, whole)


def exchange(rules: list[Rule], src: Source, **options) -> DataFrame:
    """The set of facts of all rules."""
    return reduce(DataFrame.unionByName, [r.construct(src, **options) for r in rules]).distinct()


def to_sparql(rule: Rule, source_prefix: str = "src", target_prefix: str = "tgt") -> str:
    """A CONSTRUCT query in which each optional branch nests in its parent's and binds its own invented nodes."""
    s, t = rule.sk.s, rule.sk.t
    name = {n.id: f"?x{i}" for i, n in enumerate(s.nodes)}

    def term(x: Term) -> str:
        return name[x.node] if x.node else f"?b{x.blank.split(',')[-1]}"

    def lit(v: tuple[str, str]) -> str:
        return f"{name[v[0]]}_{v[1].split('.', 1)[1]}"

    template = []
    for f in rule.template():
        o = lit(f.value) if f.value else f"{target_prefix}:{f.cls}" if f.cls else term(f.object)
        template.append(f"  {term(f.subject)} {'a' if f.prop == TYPE else f'{target_prefix}:{f.prop}'} {o} .")
    used = frozenset().union(*(rule._need(f) for f in rule.template()))
    attrs = sorted(rule._attrs(rule.template()))
    blanks = {t_.blank: t_ for f in rule.template() for t_ in (f.subject, f.object) if t_ is not None and t_.blank}

    def body(node: str, pad: str) -> list[str]:
        lines = []
        for n, a in attrs:
            if n == node:
                lines.append(f"{pad}OPTIONAL {{ {name[node]} {source_prefix}:{a.split('.', 1)[1]} {name[node]}_{a.split('.', 1)[1]} . }}")
        for b in blanks.values():
            if b.keys[-1] == node:
                keys = ", ".join(f"STR({name[k]})" for k in b.keys)
                lines.append(f"{pad}BIND (BNODE(CONCAT({keys})) AS {term(b)})")
        for c in s.nodes:
            if c.edge and c.edge != "a" and c.id in used and s.individual(c.parent) == node:
                x, y = (name[c.id], name[node]) if c.inv else (name[node], name[c.id])
                lines += [f"{pad}OPTIONAL {{", f"{pad}  {x} {source_prefix}:{c.edge} {y} .", f"{pad}  {name[c.id]} a {source_prefix}:{c.concept} .", *body(c.id, pad + "  "), f"{pad}}}"]
        return lines

    root = s.nodes[0].id
    return "\n".join(["CONSTRUCT {", *template, "}", "WHERE {", f"  {name[root]} a {source_prefix}:{s.root} .", *body(root, "  "), "}"])
