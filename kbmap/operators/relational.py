"""Joins and summaries that Spark has no operator for, composed of equi-joins and windows that scale."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def range_join(points: DataFrame, value: str, bands: DataFrame, low: str, high: str, width: float) -> DataFrame:
    """Rows of ``points`` with the bands [low, high) that hold their value.

    Each band stands once in every bin of the given width that it touches, each point in its own bin, so bins are joined by
    equality and no pair is looked at outside a bin. Null values and empty bands match nothing.
    """
    bin_of = lambda c: F.floor(F.col(c) / F.lit(width)).cast("long")
    spread = bands.where(F.col(low) < F.col(high)).withColumn("_bin", F.explode(F.sequence(bin_of(low), bin_of(high))))
    return points.withColumn("_bin", bin_of(value)).join(spread, "_bin").where((F.col(value) >= F.col(low)) & (F.col(value) < F.col(high))).drop("_bin")


def overlap_join(left: DataFrame, right: DataFrame, keys: list[str], width: int) -> DataFrame:
    """Pairs of rows with equal keys whose intervals [start, stop) (longs) overlap; columns of the right side get the prefix ``r_``.

    Both sides stand in every bin they touch; a pair counts only in the bin in which the later of the two starts.
    """
    bins = lambda df: df.where("start < stop").withColumn("_bin", F.explode(F.sequence(F.floor(F.col("start") / width).cast("long"), F.floor((F.col("stop") - 1) / width).cast("long"))))
    other = bins(right).withColumnsRenamed({c: f"r_{c}" for c in right.columns if c not in keys})
    met = bins(left).join(other, [*keys, "_bin"]).where("start < r_stop and r_start < stop")
    return met.where(F.floor(F.greatest("start", "r_start") / width) == F.col("_bin")).drop("_bin")


def as_of_join(left: DataFrame, right: DataFrame, key: str, at: str, when: str, values: list[str]) -> DataFrame:
    """Each left row with the values of the last right row of its key at or before its time, or nulls.

    One union, one sort by key and time and one window: no pair of rows is formed.
    """
    none = [F.lit(None).cast(right.schema[v].dataType).alias(v) for v in values]
    a = left.select(F.col(key).alias("_k"), F.col(at).alias("_t"), F.lit(1).alias("_side"), F.struct(*left.columns).alias("_row"), F.lit(None).cast(right.select(F.struct(*values)).schema[0].dataType).alias("_last"))
    b = right.select(F.col(key).alias("_k"), F.col(when).cast(left.schema[at].dataType).alias("_t"), F.lit(0).alias("_side"), F.lit(None).cast(a.schema["_row"].dataType).alias("_row"), F.struct(*values).alias("_last"))
    assert len(none) == len(values)
    # Right rows come first at one time; of several the greatest values win.
    w = W.partitionBy("_k").orderBy("_t", "_side", "_last").rowsBetween(W.unboundedPreceding, W.currentRow)
    both = a.unionByName(b).withColumn("_seen", F.last("_last", ignorenulls=True).over(w)).where("_side = 1")
    return both.select("_row.*", *[F.col("_seen").getField(v).alias(v) for v in values])


def salted_join(large: DataFrame, small: DataFrame, key: str, salts: int, hot: DataFrame | None = None) -> DataFrame:
    """An equi-join whose hot keys are spread over ``salts`` partitions: large rows draw a salt, small rows of hot keys stand under each.

    ``hot`` has the keys to spread (all without it).
    """
    if hot is None:
        spread = small.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
        return large.withColumn("_salt", F.pmod(F.xxhash64(*large.columns), F.lit(salts)).cast("int")).join(spread, [key, "_salt"]).drop("_salt")
    mark = hot.select(key).distinct().withColumn("_hot", F.lit(True))
    many = small.join(mark, key, "left").withColumn("_salt", F.explode(F.when(F.col("_hot"), F.sequence(F.lit(0), F.lit(salts - 1))).otherwise(F.array(F.lit(0))))).drop("_hot")
    drawn = large.join(mark, key, "left").withColumn("_salt", F.when(F.col("_hot"), F.pmod(F.xxhash64(*large.columns), F.lit(salts)).cast("int")).otherwise(0)).drop("_hot")
    return drawn.join(many, [key, "_salt"]).drop("_salt")


def hash_sample(df: DataFrame, key: Column, share: float, seed: int = 7) -> DataFrame:
    """Rows whose hashed key falls into the share; retries and other partitionings draw the same rows."""
    drawn = F.conv(F.substring(F.md5(F.concat_ws(":", key.cast("string"), F.lit(str(seed)))), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)
    return df.where(drawn < share)


def name_matches(left: DataFrame, right: DataFrame, least: float = 0.6) -> DataFrame:
    """(l, r, score): names whose edit distance is small against their length; stands in for an outside matcher.

    Only names that share a pair of adjacent letters are compared; two without one differ in at least half of their letters.
    """
    grams = lambda df, c: df.select(F.col("name").alias(c), F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.length("name") - 1, F.lit(1))), lambda i: F.lower(F.substring("name", i, F.lit(2)))))).alias("g"))
    pairs = grams(left, "l").join(grams(right, "r"), "g").select("l", "r").distinct()
    score = 1 - F.levenshtein(F.lower("l"), F.lower("r")) / F.greatest(F.length("l"), F.length("r"))
    return pairs.withColumn("score", F.round(score, 6)).where(F.col("score") >= least)
