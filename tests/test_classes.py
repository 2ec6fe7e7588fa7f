from fractions import Fraction

from localgraph.operators import analysis
from localgraph.plans import methods

D = "/root/testdata/sf0.001"


def test_large_components_are_classed_alike(spark):
    """Stop epochs and classes by classes of vertices are those of the dense walk; verdicts count only what was walked."""
    g = methods.graph(spark, D, "nation_forest")
    rows = lambda df: sorted((r.seed, r.comp, r.h, r.b, r.rising) for r in df.collect())
    whole, some = analysis.guarantees(g, Fraction(9, 10)), analysis.guarantees(g, Fraction(9, 10), limit=40)
    assert some.filter("nonempty is null and b > 0").count() > 0
    assert rows(whole) == rows(some)
