"""Queries over the running scenario as the tables show it, against their SQL and on tables without some facts."""

import os

import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"


def by_sql(name: str, sf_dir: str) -> list[tuple]:
    import duckdb

    con = duckdb.connect()
    for f in os.listdir(sf_dir):
        con.execute(f"CREATE VIEW {f.removesuffix('.parquet')} AS SELECT * FROM '{sf_dir}/{f}{'/*.parquet' if os.path.isdir(f'{sf_dir}/{f}') else ''}'")
    return sorted(con.execute(entry.oracle_sql()[name]).fetchall(), key=str)


def by_spark(spark, name: str, sf_dir: str) -> list[tuple]:
    return sorted(map(tuple, entry.queries()[name](spark, sf_dir).collect()), key=str)


@pytest.fixture(scope="module")
def quiet(spark, tmp_path_factory):
    """The tables without events, so that no customer is active."""
    out = tmp_path_factory.mktemp("quiet")
    for f in os.listdir(SF):
        if f != "events.parquet":
            os.symlink(f"{SF}/{f}", out / f)
    spark.read.parquet(f"{SF}/events.parquet").limit(0).write.parquet(str(out / "events.parquet"))
    return str(out)


def test_aligned_concepts_are_read_off_the_tables(spark, quiet):
    got = by_spark(spark, "aligned_concepts", SF)
    assert got == by_sql("aligned_concepts", SF) and ("s", "Nation", 25) in got
    less = by_spark(spark, "aligned_concepts", quiet)
    assert less == by_sql("aligned_concepts", quiet) and {c for _, c, _ in got} - {c for _, c, _ in less} == {"ActiveCustomer", "Member"}


def test_alignment_profile_counts_facts(spark, quiet):
    for sf_dir in (SF, quiet):
        assert by_spark(spark, "alignment_profile", sf_dir) == by_sql("alignment_profile", sf_dir)
    assert ("c2c", 3) in {(r[0], r[1]) for r in by_spark(spark, "alignment_profile", quiet)}


def test_all_mappings_follow_the_tables(spark, quiet):
    rows = entry.queries()["all_mappings"](spark, SF).collect()
    assert len(rows) == 78 and min(r.facts for r in rows) >= 0
    nations = {r.facts for r in rows if r.s_root == "Nation"}
    assert nations <= {0, 25, 50}
    less = entry.queries()["all_mappings"](spark, quiet).collect()
    assert 0 < len(less) < 78 and "ActiveCustomer" not in {r.s_root for r in less}


def without(spark, tmp_path, **conditions) -> str:
    """The tables, some with only the rows that meet a condition."""
    for f in os.listdir(SF):
        name = f.removesuffix(".parquet")
        if name in conditions:
            spark.read.parquet(f"{SF}/{f}").where(conditions[name]).write.parquet(str(tmp_path / f))
        else:
            os.symlink(f"{SF}/{f}", tmp_path / f)
    return str(tmp_path)


def test_association_paths_need_facts(spark, tmp_path):
    got = by_spark(spark, "assoc_paths", SF)
    assert got == by_sql("assoc_paths", SF) and len(got) == 10
    some = without(spark, tmp_path, lineitem="l_returnflag <> 'R'")
    less = by_spark(spark, "assoc_paths", some)
    assert less == by_sql("assoc_paths", some) and {r[3] for r in got} - {r[3] for r in less} == {"returned_to/Supplier"}


@pytest.mark.parametrize("depth", (1, 2, 3, 4))
def test_paths_of_a_depth_need_facts(spark, quiet, depth):
    name = f"assoc_paths_depth{depth}"
    got = by_spark(spark, name, SF)
    assert got == by_sql(name, SF) and len(got) == {1: 0, 2: 1, 3: 3, 4: 5}[depth] and all(len(r) == 5 for r in got)
    assert entry.queries()[name](spark, SF).columns[-1] == "facts"
    assert by_spark(spark, name, quiet) == by_sql(name, quiet) == []


def test_owner_rule_counts_over_the_tables(spark, quiet):
    for sf_dir in (SF, quiet):
        assert by_spark(spark, "attr_owner_rule", sf_dir) == by_sql("attr_owner_rule", sf_dir)


def test_basic_associations_count_values(spark, quiet):
    for sf_dir in (SF, quiet):
        assert by_spark(spark, "basic_assoc", sf_dir) == by_sql("basic_assoc", sf_dir)


def test_best_by_bounds_over_the_tables(spark, quiet):
    from kbmap import queries as Q
    from kbmap.operators import interpret

    got = entry.queries()["best_by_bounds"](spark, SF).collect()
    plain = interpret.best_by_bounds(spark, Q.w0_skeleton(spark), 5, ("r2r", "c2a", "owner"), "strict").collect()
    assert [(r.asg, r.cons_cost) for r in got] == [(",".join(map(str, r.asg)), r.cons_cost) for r in plain]
    ((_, least, most),) = by_sql("attr_owner_rule", SF)
    assert all(least <= r.facts <= most for r in got)
    assert entry.queries()["best_by_bounds"](spark, quiet).count() == 0


def test_best_renamings_over_the_tables(spark, quiet):
    from kbmap import queries as Q
    from kbmap.operators import interpret

    got = entry.queries()["best_renamings"](spark, SF).collect()
    sk = Q.w0_skeleton(spark)
    r = interpret.costed(spark, sk, interpret.renamings(spark, sk, checks=("r2r", "c2a", "owner"), c2a_mode="strict"))
    plain = interpret.best_renamings(r, 5).collect()
    assert [(r.asg, r.combined) for r in got] == [(",".join(map(str, r.asg)), r.combined) for r in plain]
    ((_, least, most),) = by_sql("attr_owner_rule", SF)
    assert all(least <= r.facts <= most for r in got)
    assert entry.queries()["best_renamings"](spark, quiet).count() == 0
