from localgraph.operators.cost import step_costs
from localgraph.operators.walk import Run
from localgraph.sources.builders import user_hour


def test_step_cost_counts_moved_mass_only(spark):
    g = user_hour(spark, "/root/testdata/sf0.01")
    seed = g.vertices.orderBy("v").first().v
    spark.sparkContext.setJobGroup("mine", "kept")
    rows = step_costs(g, [Run(0, seed)], 2).orderBy("t").collect()
    assert spark.sparkContext.getLocalProperty("spark.jobGroup.id") == "mine"
    spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    assert [r.t for r in rows] == [1, 2]
    assert all(r.jobs > 0 and r.stages > 0 and r.tasks >= r.stages for r in rows)
    # the first step moves one vertex's mass: far fewer rows shuffled than the graph has arcs
    assert 0 < rows[0].shuffle_rows < g.arcs.count() / 10
