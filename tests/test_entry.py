"""Every registered query of the engine against its SQL on the smallest tables."""

import math

import duckdb
import pytest

from groupflow.plans.queries import ORACLE_SQL, QUERIES

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def norm(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else f"{v:.9g}"
    return str(v)


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", sorted(ORACLE_SQL))
def test_matches_sql(spark, con, name):
    df = QUERIES[name](spark, SF)
    columns = sorted(df.columns)
    got = sorted(tuple(norm(r[c]) for c in columns) for r in df.collect())
    cursor = con.execute(ORACLE_SQL[name])
    names = [d[0] for d in cursor.description]
    assert sorted(names) == columns
    assert got == sorted(tuple(norm(r[names.index(c)]) for c in columns) for r in cursor.fetchall())


def test_entry(spark):
    import __spark_entry__

    df = __spark_entry__.entry(spark)
    assert df.columns == ["win", "group_id", "size", "n_aggs"] and df.count() == 228


def test_planted_recall(spark):
    r = QUERIES["planted_recall"](spark, "/root/testdata/sf0.01").first()
    assert (r["precision"], r["recall"]) == (1.0, 0.9)
    r = QUERIES["planted_recall_no_gaps"](spark, "/root/testdata/sf0.01").first()
    assert (r["precision"], r["recall"]) == (1.0, 0.5)


def test_whole_tables(spark, con):
    """Track views read every customer and ship date."""
    sf = "/root/testdata/sf0.01"
    walks = QUERIES["planted_walks"](spark, sf)
    customers = con.execute(f"select count(*) from '{sf}/customer.parquet'").fetchone()[0]
    assert (walks.count(), walks.select("obj_id").distinct().count()) == (42 * customers, customers) and customers > 120
    pairs = con.execute(f"select count(*) from (select distinct l_partkey, l_shipdate from '{sf}/lineitem.parquet')").fetchone()[0]
    assert QUERIES["lineitem_sightings"](spark, sf).count() == pairs
