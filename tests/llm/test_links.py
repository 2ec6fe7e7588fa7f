"""Pair operators against brute force: repeated ids, stretches smaller than a group, families of near copies."""

import math
import random
import re

import numpy as np
import pytest

from localgraph.llm import embedding_join, ngram_join


def _classes(rows, linked):
    up = list(range(len(rows)))

    def root(a):
        while up[a] != a:
            a = up[a]
        return a

    n = [0] * len(rows)
    for x in range(len(rows)):
        for y in range(len(rows)):
            if x != y and linked(rows[x], rows[y]):
                n[x] += 1
                up[max(root(x), root(y))] = min(root(x), root(y))
    least = {}
    for i, r in enumerate(rows):
        if r[0] is not None:
            least[root(i)] = min(r[0], least.get(root(i), r[0]))
    return n, [least.get(root(i)) for i in range(len(rows))]


def _cosine(x, y):
    if any(r[0] is None or not r[1] or not any(r[1]) or not all(map(math.isfinite, r[1])) for r in (x, y)) or len(x[1]) != len(y[1]):
        return False
    a, b = np.array(x[1]), np.array(y[1])
    return a @ b / (math.sqrt(a @ a) * math.sqrt(b @ b)) >= 0.9


def test_vectors_that_repeat_an_id(spark):
    rows = [(1, [1.0, 0.0]), (1, [0.0, 1.0]), (2, [1.0, 0.0]), (3, [0.99, 0.1])]
    got = embedding_join.linked_components(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).collect()
    assert sorted((r.vec_id, r.n_links, r.component_id) for r in got) == [(1, 0, 1), (1, 2, 1), (2, 2, 1), (3, 2, 1)]


@pytest.mark.parametrize("stretch", [1 << 20, 600])
def test_vectors_against_brute_force(spark, monkeypatch, stretch):
    monkeypatch.setattr(embedding_join, "STRETCH", stretch)
    rng = np.random.default_rng(3)
    near = np.concatenate([b + rng.normal(size=(rng.integers(1, 40), 12)) * rng.choice([0.05, 0.2, 0.3]) for b in rng.normal(size=(12, 12))])
    rows = [(int(i * 7 % 1009), [float(np.float32(x)) for x in v]) for i, v in enumerate(near)]
    rows += [(5000, None), (5001, []), (5002, [0.0] * 12), (5003, [math.inf] * 12), (None, rows[0][1]), (5004, rows[1][1]), (5004, rows[1][1]), (5005, [1.0, 2.0]), (5006, [2.0, 4.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").repartition(4)
    got = [(r.vec_id, r.n_links, r.component_id) for r in embedding_join.linked_components(df).collect()]
    n, comp = _classes(rows, _cosine)
    assert sorted(got, key=str) == sorted(zip([r[0] for r in rows], n, comp, strict=True), key=str)


@pytest.mark.parametrize(("k", "percent"), [(3, 90), (5, 80)])
def test_shingle_sets_against_brute_force(spark, k, percent):
    rng = random.Random(4)
    vocab, docs = [f"w{i}" for i in range(60)], []
    for _ in range(20):
        base = [rng.choice(vocab) for _ in range(rng.choice([3, 10, 30, 80, 150]))]
        for _ in range(rng.choice([1, 2, 5, 12])):
            t = list(base)
            for _ in range(rng.choice([0, 1, 2, 4, 8])):
                if t:
                    t[rng.randrange(len(t))] = rng.choice(vocab)
            docs.append((len(docs) * 7 % 10007, " ".join(t)))
    docs += [(20001, None), (20002, " \t "), (None, "a b c"), (30000, docs[0][1]), (30000, docs[5][1]), (30001, "x y"), (30002, "X y"), docs[3], docs[3]]

    def shingles(text):
        w = re.findall(r"[^\x20\x09-\x0D]+", (text or "").lower())
        return {tuple(w[i : i + k]) for i in range(max(1, len(w) - k + 1))} if w else set()

    sets = [(i, shingles(t)) for i, t in docs]
    one = lambda x, y: None not in (x[0], y[0]) and x[1] and y[1] and (x[0] == y[0] or 100 * len(x[1] & y[1]) >= percent * len(x[1] | y[1]))
    _, comp = _classes(sets, one)
    want = [(i, len(s), c if s else i) for (i, s), c in zip(sets, comp, strict=True)]
    got = ngram_join.near_components(spark.createDataFrame(docs, "doc_id long, text string").repartition(3), k, percent).collect()
    assert sorted(((r.doc_id, r.n_shingles, r.component_id) for r in got), key=str) == sorted(want, key=str)
