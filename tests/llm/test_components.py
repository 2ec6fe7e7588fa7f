import random

from localgraph.llm.common import components


def test_long_chain_and_random_trees(spark):
    rng, n = random.Random(5), 3000
    chain = [(i, i + 1) for i in range(n)]
    ids = rng.sample(range(10**6, 10**7), 400)
    tree = [(ids[i], ids[rng.randrange(i)]) for i in range(1, len(ids))]
    # a caterpillar whose leaves all are smaller than its spine: most vertices start as roots
    combs = [(2 * 10**7 + i, 2 * 10**7 + i + 1) for i in range(200)] + [(2 * 10**7 + i, 10**7 + 1 + i) for i in range(201)]
    got = {r.v: r.root for r in components(spark.createDataFrame(chain + tree + combs, "a long, b long")).collect()}
    want = dict.fromkeys(range(n + 1), 0) | dict.fromkeys(ids, min(ids))
    want |= dict.fromkeys([*range(2 * 10**7, 2 * 10**7 + 201), *range(10**7 + 1, 10**7 + 202)], 10**7 + 1)
    assert got == want
