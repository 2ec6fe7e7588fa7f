import pytest

from localgraph.plans import methods, relational

D = "/root/testdata/sf0.001"
NAMES = {"p_f1_f2": "orders", "p_inequalities": "orders", "p_scale_law": "orders", "p_schedule": "orders", "udtf_geometric_scales": "orders", "udtf_subset_masks": "events"}


@pytest.mark.parametrize("name", NAMES)
def test_job_is_done_on_a_given_table(spark, same, name):
    df = {**methods.QUERIES, **relational.QUERIES}[name](spark, D)
    assert any(f"/{NAMES[name]}.parquet" in f for f in df.inputFiles())
    same(df, {**methods.SQL, **relational.SQL}[name])


def test_step_example_walks_on_the_forest(spark, same):
    df = methods.QUERIES["w_step_example"](spark, D)
    same(df, methods.SQL["w_step_example"])
    rows = df.collect()
    # lost neighbours give mass back, so more than half stays
    assert {r.run_id for r in rows} == {0, 1} and max(r.mass for r in rows) > 0.5
