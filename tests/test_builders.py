from localgraph.plans import methods
from localgraph.sources.builders import KINDS, part_coorder

D = "/root/testdata/sf0.001"


def test_coorder_keeps_large_orders(spark, tmp_path):
    rows = [(1, p) for p in range(1200)] + [(2, 5000), (2, 5001), (2, 5000), (3, 7), (3, 5000)]
    spark.createDataFrame(rows, "l_orderkey long, l_partkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    got = methods.QUERIES["g_coorder_arcs"](spark, str(tmp_path))
    assert got.count() == got.distinct().count() == 1200 * 1199 + 4
    assert got.filter(f"src >= {5000 * KINDS} or dst >= {5000 * KINDS}").count() == 4


def test_coorder_blocks_change_nothing(spark, same):
    same(part_coorder(spark, D, block=2).arcs, methods.SQL["g_coorder_arcs"])
    same(methods.QUERIES["g_coorder_arcs"](spark, D), methods.SQL["g_coorder_arcs"])
