"""Generation from end to end, bounds, selection and the composed joins, against brute force."""

import random

from pyspark.sql import functions as F

from kbmap import queries as Q
from kbmap.operators import interpret, relational
from kbmap.plans import generate

SF = "/root/testdata/sf0.001"


def _largest(gen):
    return max(gen.skeletons.values(), key=lambda k: len(k.t.vars))


def test_early_checks_lose_nothing(spark):
    sk = _largest(Q._generation(spark, "w4"))
    for checks in ((), ("r2r", "c2a")):
        early = {tuple(r.asg) for r in interpret.renamings(spark, sk, checks=checks).collect()}
        assert early == {tuple(r.asg) for r in interpret.brute_force_renamings(spark, sk, checks=checks).collect()} and early


def test_bounds_give_the_best(spark):
    sk = _largest(Q._generation(spark, "w4"))
    every = interpret.renamings(spark, sk, checks=("c2a",)).withColumn("cons_cost", sk.consistency_cost())
    want = [(r.cons_cost, r.asg) for r in every.orderBy("cons_cost", "asg").limit(7).collect()]
    got = [(r.cons_cost, r.asg) for r in interpret.best_by_bounds(spark, sk, 7, ("c2a",)).collect()]
    assert got == want


def test_selection_session(spark):
    gen = Q._generation(spark, "w4")
    mappings = gen.mappings().cache()
    best = generate.choose(mappings).collect()
    session = generate.Selection()
    for r in best:
        session.keep(r.s_root, r.t_root, r.asg)
    assert session.open(mappings).count() == mappings.count() - len(best)
    session.refuse("Turn", "Utterance", 0, 0)
    left = session.open(mappings).where("t_root = 'Utterance'")
    assert left.where("asg[0] = 0").count() == 0 and left.count() == mappings.where("t_root = 'Utterance' and asg[0] <> 0").count()
    gold = {(r.s_root, r.t_root, tuple(r.asg)) for r in best}
    assert session.quality(gold) == {"recall": 1.0, "precision": 1.0} and session.quality(gold | {("x", "y", ())})["recall"] < 1


def test_composed_joins(spark):
    rng = random.Random(3)
    rows = [(k, s, s + rng.randrange(0, 40)) for k in "ab" for s in (rng.randrange(200) for _ in range(40))]
    df = spark.createDataFrame([(i, *r) for i, r in enumerate(rows)], "id int, k string, start long, stop long")
    met = {(r.id, r.r_id) for r in relational.overlap_join(df, df, ["k"], 25).collect()}
    assert met == {(i, j) for i, a in enumerate(rows) for j, b in enumerate(rows) if a[0] == b[0] and a[1] < a[2] and b[1] < b[2] and a[1] < b[2] and b[1] < a[2]}
    points = spark.createDataFrame([(float(x),) for x in range(-5, 60, 3)] + [(None,)], "v double")
    bands = spark.createDataFrame([(0.0, 10.0), (5.0, 30.0), (30.0, 30.0), (-9.0, 0.5)], "lo double, hi double")
    got = sorted((r.v, r.lo) for r in relational.range_join(points, "v", bands, "lo", "hi", 7.0).collect())
    assert got == sorted((float(x), lo) for x in range(-5, 60, 3) for lo, hi in ((0.0, 10.0), (5.0, 30.0), (-9.0, 0.5)) if lo <= x < hi)
    large = spark.range(500).select((F.col("id") % 3).alias("k"), "id")
    small = spark.createDataFrame([(0, "x"), (1, "y"), (1, "z")], "k long, w string")
    hot = spark.createDataFrame([(0,)], "k long")
    plain = sorted(map(tuple, large.join(small, "k").select("k", "id", "w").collect()))
    for h in (None, hot):
        assert sorted(map(tuple, relational.salted_join(large, small, "k", 4, h).select("k", "id", "w").collect())) == plain
