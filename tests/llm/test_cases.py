"""Brute-force references, clashing columns, repeated words and very many matches."""

import math
import random
import re
import time
import zlib

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from localgraph.llm import decontaminate, language_id, line_dedup, personal_data, url_filter


def _tiles(item, text, least):
    """Greedy tiling by comparing every pair of places."""
    used1, used2, out = [False] * len(item), [False] * len(text), []
    while True:
        best = (0, 0, 0)
        for i in range(len(item)):
            for j in range(len(text)):
                k = 0
                while i + k < len(item) and j + k < len(text) and item[i + k] == text[j + k] and not used1[i + k] and not used2[j + k]:
                    k += 1
                if k > best[0]:
                    best = (k, i, j)
        k, i, j = best
        if k < least:
            return out
        out.append((i, j, k))
        used1[i : i + k] = [True] * k
        used2[j : j + k] = [True] * k


def test_tiles_against_brute_force():
    rng = random.Random(7)
    for _ in range(300):
        words = rng.choice([2, 3, 8])
        item, text = ([rng.randrange(words) for _ in range(rng.randrange(0, 25))] for _ in range(2))
        codes = np.random.default_rng(1).integers(1, 1 << 63, 8, dtype=np.uint64)
        least = rng.choice([1, 2, 3, 5])
        got = decontaminate.tile(codes[np.array(item, int)], codes[np.array(text, int)], least)
        assert got == _tiles(item, text, least)


def test_tiles_of_one_repeated_word():
    began = time.time()
    word = np.full(100_000, 12345, np.uint64)
    assert sum(t[2] for t in decontaminate.tile(word[:200], word, 5)) == 200
    assert time.time() - began < 20


def test_very_many_matches(spark):
    text = " ".join(f"1.2.3.{i % 256}" for i in range(20_000)) + " a@b.cd"
    began = time.time()
    r = personal_data.spans(personal_data.candidates(spark.createDataFrame([(1, text)], "doc_id long, text string"))).select(F.size("base").alias("n"), personal_data.as_text(F.col("base")).alias("s")).first()
    assert r.n == 20_001 and time.time() - began < 60
    want = [(m.start(), m.end()) for m in re.finditer(r"[0-9]+(\.[0-9]+){3}", text)]
    assert r.s.split(",")[:-1] == [f"ip:{a}:{b}" for a, b in want] and r.s.endswith(f"email:{len(text) - 6}:{len(text)}")


def test_reliabilities_find_the_true_pattern():
    counts = {(0, "22222"): 900, (0, "00010"): 900, (0, "21122"): 60, (0, "01010"): 60}
    post = personal_data.reliabilities(counts)
    assert post[0, "22222"] > 0.9 > 0.1 > post[0, "00010"] and post[0, "21122"] > 0.5 > post[0, "01010"]


def test_line_dedup_clashing_columns(spark):
    rows = [(i, f"common line\nown {i}", f"s{i}", "x", "y", "z", i) for i in range(9)]
    d = spark.createDataFrame(rows, "doc_id long, text string, source string, row1 string, gone string, h1 string, at long")
    got = line_dedup.dedup_lines(d)
    assert got.columns == [*d.columns, "n_lines", "n_removed"]
    assert {(r.doc_id, r.text, r.row1, r.gone, r.at, r.n_removed) for r in got.collect()} == {(i, f"own {i}", "x", "y", i, 1) for i in range(9)}


def test_listed_hosts_through_the_query(spark, tmp_path):
    urls = ["http://m.ads-track.example.com/a", "http://ADS-track.example.com", "http://xads-track.example.com/", "http://example.com/", "https://a.b.spam-farm.example.com/fr/x", None, "http:///x"]
    d = spark.createDataFrame([(i, u, "k", "v") for i, u in enumerate(urls)], "page_id long, url string, keys string, verdict string")
    d.write.parquet(f"{tmp_path}/pages.parquet")
    got = {r.page_id: (r.rule, r.verdict) for r in url_filter.op9_url_filter(spark, str(tmp_path)).collect()}
    assert got == {0: (None, "block"), 1: (None, "block"), 2: (None, "allow"), 3: (None, "allow"), 4: ("com/fr/", "allow"), 5: (None, "allow"), 6: (None, "allow")}
    blocked = spark.createDataFrame([("example.com",)], "host string")
    kept = url_filter.judge_urls(d, [], blocked).collect()
    assert {r.page_id for r in kept if r.verdict == "block"} == {0, 1, 2, 3, 4} and all(r["keys"] == "k" for r in kept)


@pytest.mark.parametrize("name", ["decontaminate", "dedup_lines", "judge_urls"])
def test_empty_tables(spark, name):
    docs = spark.createDataFrame([], "doc_id long, text string, source string, url string")
    bench = spark.createDataFrame([], "item_id long, text string")
    hosts = spark.createDataFrame([], "host string")
    got = {"decontaminate": lambda: decontaminate.decontaminate(docs, bench), "dedup_lines": lambda: line_dedup.dedup_lines(docs), "judge_urls": lambda: url_filter.judge_urls(docs, url_filter.RULES, hosts)}[name]()
    assert got.count() == 0 and set(docs.columns) <= set(got.columns)


def _profile(text, dim):
    """Sum of the bound vectors of a text's letter trigrams, one by one."""
    signs = [0]
    for c in text:
        x = ord(c.lower()[0]) if c.isalpha() else 0
        if x or signs[-1]:
            signs.append(x)
    if signs[-1]:
        signs.append(0)
    v = {x: language_id.letter_vector(x, dim).astype(int) for x in set(signs)}
    return sum((np.roll(v[x], 2) * np.roll(v[y], 1) * v[z] for x, y, z in zip(signs, signs[1:], signs[2:])), np.zeros(dim, int))


def test_language_query_against_definition(spark, tmp_path):
    rng = random.Random(2)
    words = {"en": "the and with house water", "de": "der und mit haus wasser", "ru": "дом вода человек и с", "el": "σπίτι νερό και με άνθρωπος"}
    rows = [(i, " ".join(rng.choice(words[k].split()) for _ in range(rng.randrange(3, 9))) + rng.choice(["", ".", " 12!"]), k) for i in range(40) for k in [rng.choice(list(words))]]
    rows += [(100, None, "en"), (101, "12 !", "de"), (102, "дом", None), (None, "wasser", "de")]
    spark.createDataFrame(rows, "doc_id long, text string, lang string").write.parquet(f"{tmp_path}/documents.parquet")
    out = lambda i: i is not None and zlib.crc32(str(i).encode()) % 4 == 2
    proto = {}
    for i, t, k in rows:
        if t and k and not out(i):
            proto[k] = proto.get(k, 0) + _profile(t, language_id.DIM)
    got = {r.doc_id: r for r in language_id.op3_language_id(spark, str(tmp_path)).collect()}
    for i, t, _ in rows:
        v = _profile(t or "", language_id.DIM)
        cos = {k: float(v @ p / math.sqrt((v @ v) * (p @ p))) for k, p in proto.items()} if v.any() else {}
        best = min(cos, key=lambda k: (-cos[k], k)) if cos else "und"
        assert (got[i].lang_pred, got[i].held_out) == (best, out(i))
        assert abs(got[i].score - max(0.0, cos.get(best, 0.0))) < 1e-9


def test_pipeline_against_brute_force(spark, tmp_path):
    import corpus_pipeline

    rng = random.Random(6)
    make = lambda n: [rng.choice("abcdefghijklmnopqrstuvwxyz") * rng.randrange(1, 4) + str(rng.randrange(50)) for _ in range(n)]
    item, body = make(20), [make(60) for _ in range(12)]
    near = [*body[0][:50], "x", *body[0][51:]]
    texts = [" ".join(b) + "\nshared line" for b in body] + [" ".join(near), " ".join(body[1]), " ".join([*make(30), *item[10:], *item[:10]]), "12 34", None, "shared line", "Shared Line\n" + " ".join(make(9))]
    rows = [(i, t, "en", f"s{i % 11}", len(t or "")) for i, t in enumerate(texts)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(1, " ".join(item))], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    got = {r.doc_id: r for r in corpus_pipeline.run(spark, str(tmp_path)).collect()}

    docs = [(i, t, s) for i, t, _, s, _ in rows if t and any(c.isalpha() for c in t)]
    sites = {}
    for _, t, s in docs:
        for line in filter(str.strip, t.split("\n")):
            sites.setdefault(line.strip(" "), set()).add(s)
    cut = []
    for i, t, _ in docs:
        kept = [x for x in t.split("\n") if len(sites.get(x.strip(" "), ())) < line_dedup.MIN_SITES]
        cut.append((i, "\n".join(kept) if any(x.strip(" ") for x in kept) else t))
    grams = {i: {tuple(w[j : j + 5]) for j in range(max(1, len(w) - 4))} for i, t in cut for w in [t.lower().split()]}
    up = {i: i for i in grams}
    for i in grams:
        for j in grams:
            if i < j and 100 * len(grams[i] & grams[j]) >= 80 * len(grams[i] | grams[j]):
                a, b = sorted((up[i], up[j]))
                up = {k: a if v == b else v for k, v in up.items()}
    words = lambda t: re.findall(r"[a-z0-9]+", t.lower())
    names = {}
    code = lambda t: np.array([names.setdefault(w, len(names)) for w in words(t)], np.uint64)
    left = {i: t for i, t in cut if up[i] == i and sum(x[2] for x in _tiles(code(" ".join(item)).tolist(), code(t).tolist(), 5)) / 20 < 0.5}
    assert {i: r.text for i, r in got.items()} == left and 0 < len(left) < len(docs) - 2
    assert all(r.ids for r in got.values())


def test_chunk_is_encoded_once(monkeypatch):
    """Matrix, exits and ids of a chunk share one encoding of what lies between its walls."""
    import numpy as np

    from localgraph.llm import pieces

    e = pieces.Encoder(pieces.Vocabulary.load())
    calls, plain = [], e.encode_marked
    monkeypatch.setattr(e, "encode_marked", lambda texts: calls.append(texts) or plain(texts))
    text = "some words ▁ and\nlines of them  " * 6 + "w" * 60 + " end"
    s, size, k = pieces.MARK + pieces.normalise(text), 40, e.width
    assert pieces.plain(s) == " " + text
    cuts = [(s[max(0, a - k + 1) : a + size], a - max(0, a - k + 1)) for a in range(0, len(s), size)]
    parts = [(*e.split(*c), c[1]) for c in cuts]
    got = [None if m is None else e.encode_marked([m])[0] for _, m, _, _ in parts]
    vec = pieces.prefix_vectors([e.matrix(h, t, low, g and g[1]) for (h, _, t, low), g in zip(parts, got)])
    leave = pieces.exit_states([e.leaves(h, None if m is None else t, low, x) for (h, m, t, low), x in zip(parts, vec)])
    ids = np.concatenate([e.path(h, g and g[0], t, low, x, j) for (h, _, t, low), g, x, j in zip(parts, got, vec, leave)])
    assert len(calls) == sum(m is not None for _, m, _, _ in parts) < len(parts)
    assert ids.tolist() == e.encode([text])[0][0].tolist()


@pytest.mark.parametrize("k", range(5))
def test_pipeline_batches_end_by_bytes(spark, k):
    """After any stage, 4,000 texts of 10 kB travel in batches of a few MB, not in one of 40 MB."""
    import corpus_pipeline

    own = spark.newSession()
    docs = own.sql("SELECT id AS doc_id, concat(id, repeat(' some words', 900)) AS text, 'en' AS lang, 'a' AS source, 9900L AS n_chars FROM range(0, 4000, 1, 1)")
    corpus_pipeline.STAGES[k][1](own, docs.limit(3), "/root/testdata/sf0.001")
    sizes = docs.mapInPandas(lambda batches: (pd.DataFrame({"n": [int(b["text"].str.len().sum())]}) for b in batches), "n long").toPandas()["n"]
    assert sizes.max() < 8 << 20
    assert sizes.sum() == sum(9900 + len(str(i)) for i in range(4000))
