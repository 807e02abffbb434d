"""Mixing sources to target weights by iterative proportional fitting.

Documents are summed into (source, language, topic) cells; the cells' token weights are raked to the
target marginals of each dimension in turn; each document is kept with its cell's calibrated
probability. Only DataFrame functions are used. Missing source, language or topic counts as the
value ``(none)``. An empty table gives an empty result. Rows with one identifier (or none) in one cell stand or fall together.
Texts without words carry no weight and are left out. Target weights may be given for any dimension; a dimension without them gets its own
token shares to the power ``TEMPERATURE``, which evens the mix.
"""

from __future__ import annotations

from collections.abc import Mapping

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import SPACE, Cut

DIMENSIONS = ("source", "lang", "topic")
NONE = "(none)"
#: Target share of a value where none is given: its share of tokens to this power, normalised (1 keeps the mix, 0 makes it even).
#: A mild one by default, since every step below 1 leaves more documents of the large cells out.
TEMPERATURE = 0.85
ROUNDS = 8


def n_words(text: Column) -> Column:
    t = F.btrim(F.coalesce(text, F.lit("")), F.lit(" \t\n\x0b\f\r"))
    return F.when(t == "", 0).otherwise(F.size(F.split(t, SPACE))).cast("long")


def with_topic(docs: DataFrame, embeddings: DataFrame) -> DataFrame:
    """Add ``topic``: the label of the vector of the same number (the smallest where several have it)."""
    topics = embeddings.where("vec_id is not null").groupBy(F.col("vec_id").cast("long").alias("doc_id")).agg(F.min("label").cast("string").alias("topic"))
    return docs.join(topics, "doc_id", "left").withColumn("topic", F.coalesce("topic", F.lit(NONE)))


def cells(weighed: DataFrame) -> DataFrame:
    return weighed.groupBy(*DIMENSIONS).agg(F.sum("n_tokens").cast("double").alias("tokens"))


def targets(cell: DataFrame, dim: str, temperature: float, given: Mapping[str, float] | None = None) -> DataFrame:
    """(dim, target share) of one dimension; the table has a row for each of its values.

    Given weights are normalised over the values that the data have; values without one get 0, and so none of their documents.
    """
    share = cell.groupBy(dim).agg(F.pow(F.sum("tokens"), F.lit(temperature)).alias("x"))
    if given is not None:
        weights = cell.sparkSession.createDataFrame([(str(k), float(w)) for k, w in given.items()], f"{dim} string, x double")
        share = share.select(dim).join(weights, dim, "left").select(dim, F.coalesce("x", F.lit(0.0)).alias("x"))
    total = share.agg(F.sum("x")).first()[0] or 1.0
    return share.select(dim, (F.col("x") / F.lit(total)).alias(f"target_{dim}"))


def rake(cell: DataFrame, rounds: int = ROUNDS, dimensions=DIMENSIONS) -> DataFrame:
    """Add ``share`` (of all tokens) and ``raked``: the share scaled to each target marginal in turn, ``rounds`` times."""
    total = cell.agg(F.sum("tokens")).first()[0] or 1.0
    df = cell.withColumn("share", F.col("tokens") / F.lit(total)).withColumn("raked", F.col("share"))
    for _ in range(rounds):
        for d in dimensions:
            reached = F.sum("raked").over(W.partitionBy(d))
            df = df.withColumn("raked", F.when(reached > 0, F.col("raked") * F.col(f"target_{d}") / reached).otherwise(0.0))
    return df


def residuals(raked: DataFrame, dimensions=DIMENSIONS) -> DataFrame:
    """(dim, value, target, reached): how near each marginal came to its target."""
    parts = [raked.groupBy(F.lit(d).alias("dim"), F.col(d).alias("value")).agg(F.first(f"target_{d}").alias("target"), F.sum("raked").alias("reached")) for d in dimensions]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def uniform(key: Column, seed: int) -> Column:
    """A number in [0, 1) that depends on the key and the seed alone, so retries draw the same sample."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", F.coalesce(key.cast("string"), F.lit("null")), F.lit(str(seed)))), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def raked_cells(cut: Cut, weighed: DataFrame, temperature: float = TEMPERATURE, rounds: int = ROUNDS, given: Mapping[str, Mapping[str, float]] | None = None) -> DataFrame:
    """The cells with their targets, share and raked share, written to the shared folder; cells without tokens are left out."""
    cell = cut(cells(weighed).where("tokens > 0"))
    with_targets = cell
    for d in DIMENSIONS:
        with_targets = with_targets.join(targets(cell, d, temperature, (given or {}).get(d)), d)
    return cut(rake(cut(with_targets), rounds))


def probabilities(cut: Cut, weighed: DataFrame, temperature: float = TEMPERATURE, rounds: int = ROUNDS, given: Mapping[str, Mapping[str, float]] | None = None) -> DataFrame:
    """(source, lang, topic, weight, probability) for every cell.

    ``weight`` is the raked share over the share; the largest weight has probability 1, so the kept
    tokens follow the targets in expectation and no document is drawn twice. Cells without tokens have weight 0.
    """
    weights = raked_cells(cut, weighed, temperature, rounds, given).select(*DIMENSIONS, (F.col("raked") / F.col("share")).alias("weight"))
    top = weights.agg(F.max("weight")).first()[0] or 1.0
    return weights.withColumn("probability", F.col("weight") / F.lit(top))


def sample(cut: Cut, weighed: DataFrame, seed: int = 7, **options) -> DataFrame:
    """The rows of ``weighed`` with weight, probability and kept."""
    p = probabilities(cut, weighed, **options)
    return (
        weighed.join(p, list(DIMENSIONS), "left")
        .withColumns({"weight": F.coalesce("weight", F.lit(0.0)), "probability": F.coalesce("probability", F.lit(0.0))})
        .withColumn("kept", uniform(F.col("doc_id"), seed) < F.col("probability"))
    )


def weigh(docs: DataFrame, embeddings: DataFrame) -> DataFrame:
    """doc_id, source, lang, topic and n_tokens (words) of every document."""
    narrow = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        *[F.coalesce(F.col(c).cast("string"), F.lit(NONE)).alias(c) for c in ("source", "lang")],
        n_words(F.col("text")).alias("n_tokens"),
    )
    return with_topic(narrow, embeddings)


def keep_mixed(docs: DataFrame, embeddings: DataFrame, seed: int = 7) -> DataFrame:
    """The rows of ``docs`` that the calibrated sample keeps, with all their columns.

    Whether a document stays depends on its identifier and cell alone, so the texts are read once
    more and joined with the kept identifiers; rows of one identifier stay or go by their own cell.
    """
    cut = Cut(docs.sparkSession)
    names = docs.columns
    key = [F.coalesce(F.col(c).cast("string"), F.lit(NONE)).alias(f"_{c}") for c in ("source", "lang")]
    narrow = cut(weigh(docs, embeddings))
    kept = sample(cut, narrow, seed).where("kept").select(
        F.coalesce(F.col("doc_id").cast("string"), F.lit("null")).alias("_key"), F.col("source").alias("_source"), F.col("lang").alias("_lang")
    ).distinct()
    whole = docs.withColumns({"_key": F.coalesce(F.col("doc_id").cast("long").cast("string"), F.lit("null")), "_source": key[0], "_lang": key[1]})
    # Always by a shuffle: the kept identifiers grow with the table.
    return whole.join(cut(kept).hint("merge"), ["_key", "_source", "_lang"], "left_semi").select(*names)
