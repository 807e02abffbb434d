"""Where facts go: tables by predicate and N-Triples text, and back."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def write_table(facts: DataFrame, path: str, buckets: int = 16) -> None:
    """Parquet partitioned by predicate. Facts of one predicate are dealt over ``buckets`` tasks by subject, so a predicate that most facts have is not one file."""
    facts.repartition(F.col("p"), F.pmod(F.xxhash64("s"), F.lit(buckets))).write.mode("overwrite").partitionBy("p").parquet(path)


def _escape(c: Column) -> Column:
    for raw, out in (("\\", "\\\\"), ('"', '\\"'), ("\n", "\\n"), ("\r", "\\r"), ("\t", "\\t")):
        c = F.replace(c, F.lit(raw), F.lit(out))
    return c


def _node(c: Column, base: str) -> Column:
    blank = F.concat(F.lit("_:b"), F.sha2(c, 256))  # invented nodes hold characters that labels may not
    return F.when(c.startswith("_:"), blank).otherwise(F.concat(F.lit(f"<{base}"), c, F.lit(">")))


def to_ntriples(facts: DataFrame, base: str = "urn:kb:") -> DataFrame:
    o = F.when(F.col("o_kind") == "lit", F.concat(F.lit('"'), _escape(F.col("o")), F.lit('"'))).otherwise(_node(F.col("o"), base))
    return facts.select(F.concat_ws(" ", _node(F.col("s"), base), F.concat(F.lit(f"<{base}"), "p", F.lit(">")), o, F.lit(".")).alias("value"))


def read_ntriples(spark: SparkSession, path: str, base: str = "urn:kb:") -> DataFrame:
    """(s, p, o_kind, o) from N-Triples lines; lines that are comments or empty are left out."""
    line = r'^(<[^>]*>|_:\S+) <([^>]*)> (<[^>]*>|_:\S+|"(?:[^"\\]|\\.)*")(?:@\S+|\^\^<[^>]*>)? \.\s*$'
    part = lambda k: F.regexp_extract("value", line, k)
    bare = lambda c: F.regexp_replace(c, f"^<(?:{base})?|>$", "")
    rows = spark.read.text(path).where(F.col("value").rlike(line)).select(part(1).alias("s"), part(2).alias("p"), part(3).alias("o"))
    literal = F.substring("o", F.lit(2), F.length("o") - 2)
    for out, raw in (("\\n", "\n"), ("\\r", "\r"), ("\\t", "\t"), ('\\"', '"'), ("\\\\", "\\")):
        literal = F.replace(literal, F.lit(out), F.lit(raw))
    kind = F.when(F.col("o").startswith('"'), "lit").when(F.col("o").startswith("_:"), "blank").otherwise("iri")
    return rows.select(bare(F.col("s")).alias("s"), F.replace("p", F.lit(base), F.lit("")).alias("p"), kind.alias("o_kind"), F.when(kind == "lit", literal).otherwise(bare(F.col("o"))).alias("o"))
