"""Every library query with reference SQL, at the smallest scale, and plan properties."""

import duckdb
import pytest

from pathflow.workloads.queries import ORACLES, QUERIES

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{SF}/{t}.parquet')")
    return con


def rows(names, values):
    order = sorted(range(len(names)), key=lambda i: names[i])

    def plain(v):
        return "None" if v is None else repr(round(v, 6)) if isinstance(v, float) else str(v)

    return sorted(tuple(plain(r[i]) for i in order) for r in values)


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_query_equals_sql(spark, duck, name):
    df = QUERIES[name](spark, SF)
    got = duck.execute(ORACLES[name])
    names = [d[0] for d in got.description]
    assert sorted(df.columns) == sorted(names)
    assert rows(df.columns, [tuple(r) for r in df.collect()]) == rows(names, got.fetchall())


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(ORACLES)))
def test_query_without_sql_runs(spark, name):
    assert QUERIES[name](spark, SF).count() > 0


def test_full_sample_recalls_everything(spark):
    last = QUERIES["sampled_cf_recall"](spark, SF).where("share = 1.0").first()
    assert last.recall == 1.0 and last.error == 0.0


def test_late_events_are_dropped(spark):
    once = QUERIES["stream_tumbling"](spark, SF)
    again = QUERIES["stream_late_drop"](spark, SF).first()
    assert again.edges == once.groupBy().sum("edges").first()[0]


@pytest.mark.parametrize("name", ["cf_recommend", "content_by_likes", "foaf_new_only", "region_branching", "similar_customers"])
def test_plans_stay_native(spark, name):
    plan = QUERIES[name](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "Python" not in plan and "Pandas" not in plan


def test_literal_starts_reach_the_scan(spark):
    plan = QUERIES["liked_parts"](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [" in plan and ("EqualTo(src," in plan or "In(src" in plan)


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() == 200
