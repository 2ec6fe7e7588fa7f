from localgraph.plans import methods

D = "/root/testdata/sf0.001"


def test_every_path_and_seed_is_used(spark):
    g = methods.graph(spark, D, "conversation_path")
    paths, seeds = methods.components(g).select("comp").distinct().count(), g.vertices.count()
    rows = methods.QUERIES["slc_expected_overlap"](spark, D).collect()
    assert len(rows) == paths > 2 and all(r.ok for r in rows)
    assert methods.QUERIES["k_success_rate"](spark, D).first().seeds == seeds
    assert methods.QUERIES["e_abscissae"](spark, D).select("seed").distinct().count() == seeds
