"""Round trips of sinks and agreement of the streaming with the batch form."""

import shutil

from kbmap import queries as Q
from kbmap.sources import sinks
from kbmap.streaming import incremental

SF = "/root/testdata/sf0.001"


def test_ntriples_round_trip(spark, tmp_path):
    odd = spark.createDataFrame([("a/1", "name", "lit", 'x "y" \\ z\n\tend'), ("a/1", "type", "iri", "C"), ("_:r,1(a/1)", "of", "iri", "a/1")], "s string, p string, o_kind string, o string")
    facts = Q.construct_scoped(spark, SF).unionByName(odd)
    sinks.to_ntriples(facts).write.text(f"{tmp_path}/nt")
    back = sinks.read_ntriples(spark, f"{tmp_path}/nt")
    assert back.count() == facts.count()
    ground = lambda df: df.where("not startswith(s, '_:') and o_kind <> 'blank'")
    assert ground(back).exceptAll(ground(facts)).count() == ground(facts).exceptAll(ground(back)).count() == 0


def test_table_sink(spark, tmp_path):
    facts = Q.construct_scoped(spark, SF)
    sinks.write_table(facts, f"{tmp_path}/t")
    back = spark.read.parquet(f"{tmp_path}/t").where("p = 'name'")
    assert "PartitionFilters: [isnotnull(p" in back._jdf.queryExecution().toString() and back.count() == facts.where("p = 'name'").count()


def test_stream_equals_batch(spark, tmp_path):
    (tmp_path / "in").mkdir()
    shutil.copy(f"{SF}/events.parquet", tmp_path / "in" / "a.parquet")
    schema = spark.read.parquet(f"{tmp_path}/in").schema
    incremental.run_to_table(incremental.event_facts(incremental.read_events(spark, f"{tmp_path}/in", schema)), f"{tmp_path}/out", f"{tmp_path}/ck")
    cols = ["s", "p", "o_kind", "o"]
    streamed, batch = spark.read.parquet(f"{tmp_path}/out").select(*cols), incremental.event_facts(spark.read.parquet(f"{tmp_path}/in")).select(*cols)
    assert streamed.exceptAll(batch).count() == batch.exceptAll(streamed).count() == 0
