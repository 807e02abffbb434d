"""URL filters: host and path rules first, gradient-boosted trees on lexical features for the rest.

All of it is DataFrame work. Features are integers from string functions; training rows are summed
by equal feature vectors before the first shuffle, each level of a tree is one histogram
aggregate over (node, feature, bin), and the trees become one column expression.
A null URL or one without ``://`` has empty host and path, matches no rule and is judged by its features.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Cut


@dataclass(frozen=True)
class Rule:
    verdict: str
    pattern: str  # a host, then from its first slash on a path

    @property
    def host(self) -> str:
        return self.pattern.partition("/")[0]

    @property
    def path(self) -> str:
        return "/" + self.pattern.partition("/")[2] if "/" in self.pattern else ""


#: The default rules.
RULES = (
    Rule("block", "com/en/"),
    Rule("allow", "example.com/en/7"),
    Rule("allow", "net/de/"),
    Rule("block", "example.net/de/8"),
    Rule("block", "org/es/"),
)
#: Words whose presence in a host labels a URL as unwanted when no labelled table is given.
SEED_WORDS = ("casino", "spam", "pills", "porn", "viagra", "betting", "jackpot", "replica")
_LOWER = ("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def host_of(url: Column) -> Column:
    return F.translate(F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://([^/?#]*)", 1), *_LOWER)


def path_of(url: Column) -> Column:
    return F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://[^/?#]*([^?#]*)", 1)


def matched_rule(host: Column, path: Column, rules=RULES) -> Column:
    """The longest rule (verdict, pattern) whose host is the URL's or a parent of it and whose path begins the URL's; else null."""
    hits = [
        F.when(
            ((host == r.host) | host.endswith("." + r.host)) & path.startswith(r.path),
            F.struct(F.lit(len(r.pattern)).alias("n"), F.lit(r.pattern).alias("pattern"), F.lit(r.verdict).alias("verdict")),
        )
        for r in rules
    ]
    return F.array_max(F.array(*hits)) if hits else F.lit(None).cast("struct<n:int,pattern:string,verdict:string>")


def _entropy(s: Column) -> Column:
    """Hundredths of a bit of character entropy."""
    chars = F.filter(F.split(s, ""), lambda c: c != "")
    n = F.greatest(F.size(chars), F.lit(1)).cast("double")
    each = lambda t, c: t - F.size(F.filter(chars, lambda x: x == c)) / n * F.log2(F.size(F.filter(chars, lambda x: x == c)) / n)
    return F.round(100 * F.aggregate(F.array_distinct(chars), F.lit(0.0), each)).cast("int")


def suffix_of(host: Column) -> Column:
    return F.substring_index(host, ".", -2)


def features(url: Column, host: Column, path: Column) -> dict[str, Column]:
    """Integer features by name; the entropy is that of the whole host."""
    u = F.coalesce(url, F.lit(""))
    count = lambda s, p: F.regexp_count(s, F.lit(p))
    return {
        "length": F.length(u),
        "host_length": F.length(host),
        "path_length": F.length(path),
        "depth": count(path, "/[^/]"),
        "labels": F.size(F.split(host, r"\.")),
        "digit_percent": F.round(100 * count(u, "[0-9]") / F.greatest(F.length(u), F.lit(1))).cast("int"),
        "host_digits": count(host, "[0-9]"),
        "host_hyphens": count(host, "-"),
        "host_entropy": _entropy(host),
        "parameters": F.when(u.contains("?"), count(u, "[?&][^=&#]+=")).otherwise(0),
        "fragment": u.contains("#").cast("int"),
        "secure": F.lower(F.substring(u, 1, 8)).eqNullSafe("https://").cast("int"),
    }


@dataclass(frozen=True)
class Boosting:
    trees: int = 6
    depth: int = 3
    rate: float = 0.5
    bins: int = 16
    ridge: float = 1.0


@dataclass
class Model:
    """Bias and trees; a tree is a leaf value or (feature, threshold, below-or-equal, above)."""

    bias: float
    trees: list
    names: list[str]

    def score(self) -> Column:
        def walk(t):
            return F.lit(float(t)) if not isinstance(t, tuple) else F.when(F.col(t[0]) <= t[1], walk(t[2])).otherwise(walk(t[3]))

        return reduce(lambda a, t: a + walk(t), self.trees, F.lit(float(self.bias)))


def _bin(value: Column, edges: list) -> Column:
    """How many edges lie below the value."""
    return F.size(F.filter(F.array(*[F.lit(int(e)) for e in edges]), lambda e: e < value))


def train(cut: Cut, rows: DataFrame, names: list[str], b: Boosting = Boosting()) -> Model:
    """Logistic boosting from rows of integer features and ``label`` (0 or 1).

    Only histograms reach the driver: nodes x features x bins sums.
    """
    data = cut(rows.groupBy(*names, "label").agg(F.count(F.lit(1)).cast("double").alias("n")))
    qs = [k / b.bins for k in range(1, b.bins)]
    cuts = data.agg(*[F.array_sort(F.array_distinct(F.percentile_approx(c, qs, 1000))).alias(c) for c in names], F.sum("n").alias("_n"), F.sum(F.col("n") * F.col("label")).alias("_p")).first()
    total, positive = cuts["_n"] or 0.0, cuts["_p"] or 0.0
    if positive in (0.0, total):
        return Model(-20.0 if positive == 0.0 else 20.0, [], names)
    edges = {c: list(cuts[c] or []) for c in names}
    model = Model(math.log(positive / (total - positive)), [], names)
    for _ in range(b.trees):
        p = 1 / (1 + F.exp(-model.score()))
        graded = cut(data.withColumns({"g": F.col("n") * (p - F.col("label")), "h": F.col("n") * p * (1 - p)}))
        root: list = [None]
        open_nodes = {0: (F.lit(True), root, 0)}
        for level in range(b.depth + 1):
            node = reduce(lambda a, kv: a.when(kv[1][0], kv[0]), open_nodes.items(), F.when(F.lit(False), -1))
            bins = F.array(*[
                F.struct(F.lit(k).alias("f"), _bin(F.col(c), edges[c]).alias("bin"))
                for k, c in enumerate(names) if edges[c]
            ])
            hist = (
                graded.withColumn("node", node).where("node is not null").select("node", "g", "h", F.explode(bins).alias("x"))
                .groupBy("node", "x.f", "x.bin").agg(F.sum("g").alias("g"), F.sum("h").alias("h")).collect()
            )
            grown = {}
            for k, (where, holder, at) in open_nodes.items():
                own = sorted((r.f, r.bin, r.g, r.h) for r in hist if r.node == k)
                if not own:
                    holder[at] = 0.0
                    continue
                one = [x for x in own if x[0] == own[0][0]]
                G, H = sum(x[2] for x in one), sum(x[3] for x in one)
                best = (1e-9, None)
                for f in {x[0] for x in own}:
                    g = h = 0.0
                    for _, bin_, dg, dh in [x for x in own if x[0] == f][:-1]:
                        g, h = g + dg, h + dh
                        gain = g * g / (h + b.ridge) + (G - g) ** 2 / (H - h + b.ridge) - G * G / (H + b.ridge)
                        best = max(best, (gain, (f, bin_)), key=lambda x: x[0])
                if level == b.depth or best[1] is None or best[0] < 1e-6:
                    holder[at] = -b.rate * G / (H + b.ridge)
                    continue
                f, bin_ = best[1]
                name, limit = names[f], int(edges[names[f]][bin_])
                children: list = [None, None]
                holder[at] = (name, limit, children)
                grown[2 * k + 1] = (where & (F.col(name) <= limit), children, 0)
                grown[2 * k + 2] = (where & (F.col(name) > limit), children, 1)
            open_nodes = grown
            if not open_nodes:
                break

        def frozen(t):
            return (t[0], t[1], frozen(t[2][0]), frozen(t[2][1])) if isinstance(t, tuple) else t

        model.trees.append(frozen(root[0]))
        cut.drop(graded)
    return model


#: Groups of hosts; a training row's suffix statistic leaves out the rows of its own host's group.
FOLDS = 5


def suffix_statistics(labelled: DataFrame) -> DataFrame:
    """(suffix, fold, suffix_rate): permille of unwanted URLs below each suffix, drawn towards the overall rate by 20 pseudo-rows.

    Rows with a fold count all rows of the suffix but those of that fold; the row whose fold is null counts all.
    """
    rate = labelled.agg(F.coalesce(F.avg("label"), F.lit(0.0))).first()[0]
    parts = labelled.groupBy("suffix", "fold").agg(F.count(F.lit(1)).alias("n"), F.sum("label").alias("k"))
    totals = parts.groupBy("suffix").agg(F.sum("n").alias("all_n"), F.sum("k").alias("all_k"), F.collect_list(F.struct("fold", "n", "k")).alias("folds"))
    none = F.array(F.struct(F.lit(None).cast("int").alias("fold"), F.lit(0).cast("long").alias("n"), F.lit(0).cast("long").alias("k")))
    rows = totals.select("suffix", "all_n", "all_k", F.explode(F.concat("folds", none)).alias("x"))
    n, k = F.col("all_n") - F.col("x.n"), F.col("all_k") - F.col("x.k")
    return rows.select("suffix", "x.fold", F.round(1000 * (k + 20 * F.lit(rate)) / (n + 20)).cast("int").alias("suffix_rate"))


def judge(pages: DataFrame, labelled: DataFrame | None = None, rules=RULES, b: Boosting = Boosting()) -> DataFrame:
    """page_id, host, path, rule, verdict and the model's probability for every row of ``pages``.

    ``labelled`` has url and label (1 unwanted); the suffix statistics and the trees are aggregates over all of its
    rows. Without it the pages themselves are labelled by SEED_WORDS in the host, which no feature sees: the suffix statistic
    that a training row meets leaves out all rows of its own group of hosts. An empty table gives an empty result, repeated rows a row
    each; rows whose probability is exactly a half are allowed.
    """
    cut = Cut(pages.sparkSession)

    def described(df: DataFrame, *keep) -> DataFrame:
        df = df.select(*keep, F.col("url").cast("string").alias("url")).withColumns({"host": host_of(F.col("url")), "path": path_of(F.col("url"))})
        return df.withColumns(features(F.col("url"), F.col("host"), F.col("path")) | {"suffix": suffix_of(F.col("host"))})

    if labelled is None:
        source = described(pages).withColumn("label", F.col("host").rlike("|".join(SEED_WORDS)).cast("int"))
    else:
        source = described(labelled.where("label is not null"), F.col("label").cast("int").alias("label"))
    names = [*features(F.lit(""), F.lit(""), F.lit("")), "suffix_rate"]
    described_rows = cut(source.withColumn("fold", F.pmod(F.xxhash64("host"), F.lit(FOLDS)).cast("int")).drop("url", "host", "path"))
    statistics = cut(suffix_statistics(described_rows))
    suffixes = statistics.where("fold is null").drop("fold")
    default = int(suffixes.agg(F.coalesce(F.round(F.avg("suffix_rate")), F.lit(0))).first()[0])
    rated = lambda df: df.join(suffixes, "suffix", "left").withColumn("suffix_rate", F.coalesce("suffix_rate", F.lit(default)))
    model = train(cut, described_rows.join(statistics.where("fold is not null"), ["suffix", "fold"]).select(*names, "label"), names, b)
    rule = matched_rule(F.col("host"), F.col("path"), rules)
    return (
        rated(described(pages, F.col("page_id").cast("long").alias("page_id")))
        .withColumns({"rule": rule, "probability": F.round(1 / (1 + F.exp(-model.score())), 6)})
        .select(
            "page_id", "host", "path", F.col("rule.pattern").alias("rule"),
            F.coalesce("rule.verdict", F.when(F.col("probability") > 0.5, "block").otherwise("allow")).alias("verdict"), "probability",
        )
    )
