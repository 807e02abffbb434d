"""Incremental exchange: event rows become facts micro-batch by micro-batch.

Invented nodes are terms over keys, so a replayed batch makes the same facts; duplicates within the watermark go.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.paths import iri, lexical

EVENT_SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, folder: str, schema=None) -> DataFrame:
    return spark.readStream.schema(schema or EVENT_SCHEMA).parquet(folder)


def event_facts(events: DataFrame, lateness: str = "1 hour") -> DataFrame:
    """(ts, s, p, o_kind, o) of each event: its type, its customer and its value."""
    me = iri("event", "event_id")
    fact = lambda p, kind, o: F.struct(me.alias("s"), F.lit(p).alias("p"), F.lit(kind).alias("o_kind"), o.alias("o"))
    rows = F.array(fact("type", "iri", F.initcap("event_type")), fact("done_by", "iri", iri("cust", "user_id")), fact("amount", "lit", lexical(F.col("value"), "double")))
    facts = events.select(F.col("ts").cast("timestamp").alias("ts"), F.explode(rows).alias("f")).select("ts", "f.*").where("s is not null and o is not null")
    key = ["s", "p", "o_kind", "o"]
    if facts.isStreaming:
        return facts.withWatermark("ts", lateness).dropDuplicatesWithinWatermark(key)
    return facts.groupBy(*key).agg(F.min("ts").alias("ts")).select("ts", *key)


def counts_by_window(facts: DataFrame, width: str = "1 day") -> DataFrame:
    return facts.groupBy(F.window("ts", width).alias("w"), "p").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "p", "n")


def run_to_table(facts: DataFrame, path: str, checkpoint: str):
    """Append facts to Parquet by predicate until the input at hand is used up."""
    q = facts.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).partitionBy("p").trigger(availableNow=True).start()
    q.awaitTermination()
    return q
