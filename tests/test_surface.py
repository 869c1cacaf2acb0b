import pytest

from multiagg.plans.sqlfront import multiway_sql, why_not
from multiagg.sources.tables import load
from multiagg.surface import MULTIWAY_TEXT

SF = "/root/testdata/sf0.001"


def rows(df):
    return sorted((tuple(r) for r in df.collect()), key=repr)


@pytest.fixture
def views(spark):
    for t in ("lineitem", "orders", "customer"):
        load(spark, SF, t).createOrReplaceTempView(t)


def test_sql_text_is_recognised(spark, views):
    assert rows(multiway_sql(spark, MULTIWAY_TEXT)) == rows(spark.sql(MULTIWAY_TEXT))
    assert why_not(MULTIWAY_TEXT) is None


def test_sql_text_falls_back(spark, views):
    text = "SELECT o_orderpriority, count(*) AS n FROM orders LEFT JOIN customer ON o_custkey = c_custkey GROUP BY o_orderpriority"
    assert rows(multiway_sql(spark, text)) == rows(spark.sql(text))
    assert "LEFT" in why_not(text).upper()


def test_entry_imports_and_names_match():
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())


def test_maintained_pairs_merge_their_state(spark, tmp_path):
    from multiagg.streaming.streams import MaintainedPairs

    data = [[(str(i % 3), "ab"[j % 2]) for i in range(j + 2)] for j in range(7)]
    kept = MaintainedPairs(spark, str(tmp_path / "pairs"), "k", "g", every=3)
    frames = [spark.createDataFrame(x, "k string, g string") for x in data]
    for i, f in enumerate(frames):
        kept.apply(f, i)
        if i in (3, 6):
            kept.apply(f, i)  # a batch that is run again counts once
    every = spark.createDataFrame([r for x in data for r in x], "k string, g string")
    want = every.alias("a").join(every.alias("b"), "k").selectExpr("a.g as g1", "b.g as g2").groupBy("g1", "g2").count()
    assert rows(kept.result()) == rows(want)
    assert sorted(kept._folders("edges", "batch")) == [6] and sorted(kept._folders("pairs_merged", "upto")) == [6]
