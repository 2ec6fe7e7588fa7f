import pytest

from localgraph.plans import relational
from localgraph.streaming.activity import Buckets

D = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["st_late_rows", "st_adjacency_upsert", "st_stream_equals_batch"])
def test_streams_equal_sql(spark, same, name):
    same(relational.QUERIES[name](spark, D), relational.SQL[name])


def test_late_rows_exist(spark):
    got = relational.QUERIES["st_late_rows"](spark, D).selectExpr("sum(late) AS late", "sum(n + late) AS total").first()
    assert got.late > 0
    assert got.total == spark.read.parquet(f"{D}/events.parquet").count()


def test_repeated_batch_changes_nothing(spark, tmp_path):
    arcs = lambda rows: spark.createDataFrame(rows, "src long, dst long")
    t = Buckets(spark, str(tmp_path / "arcs"), 4)
    t.merge(arcs([(1, 2), (2, 1)]), 0)
    t.merge(arcs([(1, 3), (3, 1), (1, 2)]), 1)
    t.merge(arcs([(1, 3), (3, 1), (1, 2)]), 1)
    t.merge(arcs([]), 2)
    t.merge(arcs([(5, 1), (1, 5)]), 3)
    assert sorted(map(tuple, t.graph().arcs.collect())) == [(1, 2), (1, 3), (1, 5), (2, 1), (3, 1), (5, 1)]
    # the bucket of 1 and 5 keeps its live version and the one before
    assert [n for n, _ in t._versions()[1]] == [1, 3]
