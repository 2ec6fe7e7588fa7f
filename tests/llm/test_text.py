import random
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from localgraph.llm import chat_format, decontaminate, embedding_join, language_id, line_dedup, ngram_join, personal_data, pieces, queries, token_counts, url_filter
from localgraph.llm.common import components, table

D = "/root/testdata/sf0.001"
ODD = [None, "", " \n\t ", "a", "a b", "a b c d e f g", "a b c d e f g", "x" * 70_000, "ä▁ö  b\n\nc", "1 " * 9000]


def docs(spark, texts, **more):
    rows = [(i, t, "en", f"s{i % 3}") for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")


@pytest.mark.parametrize("name", list(queries.ORACLE_SQL))
def test_queries_match_sql(spark, same, name):
    same(queries.QUERIES[name](spark, D), queries.ORACLE_SQL[name])


def test_components(spark):
    e = spark.createDataFrame([(i, i + 1) for i in range(30)] + [(50, 49), (50, 51), (7, 7)], "a long, b long")
    assert {(r.v, r.root) for r in components(e).collect()} == {(i, 0) for i in range(31)} | {(i, 49) for i in (49, 50, 51)}


def test_language_held_out(spark):
    got = language_id.op3_language_id(spark, "/root/testdata/sf0.01").join(table(spark, "/root/testdata/sf0.01", "documents"), "doc_id")
    right = got.filter("held_out").agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("double"))).first()[0]
    assert right > 0.97
    odd = language_id.predict(docs(spark, [*ODD, "123 !!"]), language_id.learn(docs(spark, ["the cat sat"]))).collect()
    assert [r.lang_pred for r in odd][:3] == ["und"] * 3 and odd[-1].lang_pred == "und" and odd[3].lang_pred == "en"
    assert language_id.predict(docs(spark, ["abc"]), {}).first().lang_pred == "und"


def test_language_vectors_by_definition():
    text = "ab a"
    last = {" ": language_id.letter_vector(0, 64), **{x: language_id.letter_vector(ord(x), 64) for x in "ab"}}
    signs = " " + text + " "
    want = sum(np.roll(last[x], 2).astype(int) * np.roll(last[y], 1) * last[z] for x, y, z in zip(signs, signs[1:], signs[2:]))
    grams, counts = next(language_id.gram_counts([text]))
    assert (language_id.bundle(grams, counts, 64) == want).all()


def test_token_counts_against_longest_match(spark):
    vocab = token_counts.byte_vocabulary()
    for words in (vocab, [b"ab", b"abcd", b"b", b"bcde", b"d", b"cd"]):
        auto, have, longest = token_counts.Automaton(words), set(words), max(map(len, words))
        r = random.Random(4)
        for _ in range(1500):
            w = "".join(r.choice("abcde the ing é\n1") for _ in range(r.randint(1, 20))).encode()
            i = n = 0
            while i < len(w):
                size = next((k for k in range(min(longest, len(w) - i), 0, -1) if w[i : i + k] in have), 0)
                if not size:
                    n = 1
                    break
                i, n = i + size, n + 1
            assert auto.count(w) == n
    got = token_counts.count_tokens(docs(spark, ODD), vocab).collect()
    assert len(got) == len(ODD) and got[0].n_tokens == got[1].n_tokens == 0 and got[5].n_tokens == got[6].n_tokens > 0


def test_pieces_round_trip_and_chunks(spark):
    v = pieces.Vocabulary.load()
    e = pieces.Encoder(v)
    for t in [t for t in ODD if t and len(t) < 2000] + ["naïve   日本語 ▁x", "aaaa" * 40]:
        s = pieces.MARK + pieces.normalise(t)
        best, back = e.forward(s, {0: 0}, 0)
        ids = e.trace(s, back, len(s), 0)[0]
        assert e.encode([t])[0][0].tolist() == ids and e.encode([t])[0][1] == best[-1] and e.decode(ids) == t
        for size in (1, 4, 19):
            cuts = [(s[max(0, a - v.width + 1) : a + size], a - max(0, a - v.width + 1)) for a in range(0, len(s), size)]
            vec = pieces.prefix_vectors([e.transfer(*c) for c in cuts])
            leave = pieces.exit_states([e.exits(*c, x) for c, x in zip(cuts, vec)])
            assert np.concatenate([e.chunk_ids(*c, x, j) for c, x, j in zip(cuts, vec, leave)]).tolist() == ids
    a, b = pieces.encode(docs(spark, ODD), v, chunk=50), pieces.encode(docs(spark, ODD), v, verify=True)
    assert a.exceptAll(b.drop("round_trip")).isEmpty() and b.count() == len(ODD)
    assert all(r.round_trip or r.text is None for r in b.collect())


def test_pieces_against_library():
    import sentencepiece

    raw = open(pieces.MODEL, "rb").read()
    at = raw.find(b"\x18\x02", raw.find(b"tok_v0"))
    lib = sentencepiece.SentencePieceProcessor(model_proto=raw[:at] + b"\x18\x01" + raw[at + 2 :])
    v = pieces.Vocabulary.load()
    e = pieces.Encoder(v)
    for word in ["the", "with", "straightforward", "thing", "Is the", "international law"]:
        assert e.encode([word])[0][0].tolist() == lib.nbest_encode_as_ids(word, 8)[0]


def test_chat_template(spark):
    t = chat_format.Template()
    rows = spark.createDataFrame([(1, 0, "user", "</s>[INST \\b\\l"), (1, 1, "assistant", "<[]>"), (2, 0, "assistant", None), (None, None, None, "x"), (3, 0, "user", "a"), (3, 0, "user", "a")], "conv_id long, turn long, role string, text string")
    got = {r.conv_id: r for r in chat_format.format_chats(rows, t).withColumn("back", chat_format.parse(F.col("formatted"), t)).collect()}
    assert [(m.role, m.text) for m in got[1].back] == [("user", "</s>[INST \\b\\l"), ("assistant", "<[]>")]
    assert (got[1].valid, got[2].valid, got[3].valid, len(got[3].back)) == (True, False, False, 2)
    assert "".join(s.text for s in got[1].segments) == got[1].formatted


def test_line_dedup_cases(spark):
    rows = [(i, f"own {i}\nshared line\n\nonly twice {i // 2}", f"s{i}") for i in range(9)] + [(20, None, "s1"), (21, "", None), (22, "shared line", "s2"), (23, "shared line\n x", None)]
    d = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = {r.doc_id: (r.text, r.n_removed) for r in line_dedup.dedup_lines(d).collect()}
    assert got[0] == ("own 0\n\nonly twice 0", 1) and got[20] == (None, 0) and got[21] == ("", 0)
    assert got[22] == ("shared line", 0) and got[23] == (" x", 1)


def test_ngram_join_random(spark):
    r = random.Random(9)
    base = [[r.choice("abcdefghij") + r.choice("xyz") for _ in range(r.randint(1, 40))] for _ in range(12)]
    texts = [*ODD]
    for _ in range(120):
        w = list(r.choice(base))
        for _ in range(r.randint(0, 2)):
            w[r.randrange(len(w))] = r.choice("klmn")
        texts.append(" ".join(w))
    for k, percent in ((3, 90), (5, 80)):
        sets = []
        for t in texts:
            w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate({c: c + 32 for c in range(65, 91)}))
            sets.append({tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else {tuple(w)} if w else set())
        root = list(range(len(texts)))
        for _ in range(len(texts)):
            old = list(root)
            for i, a in enumerate(sets):
                for j, b in enumerate(sets[:i]):
                    if a and b and 100 * len(a & b) >= percent * len(a | b):
                        root[i] = root[j] = min(root[i], root[j])
            if old == root:
                break
        got = {x.doc_id: (x.n_shingles, x.component_id) for x in ngram_join.near_components(docs(spark, texts), k, percent).collect()}
        assert got == {i: (len(s), root[i]) for i, s in enumerate(sets)}
    assert ngram_join.near_components(docs(spark, ["a"]).limit(0)).count() == 0


def test_embeddings_odd_rows(spark):
    rows = [(1, [1.0, 0.0]), (2, [2.0, 0.0]), (3, [0.0, 0.0]), (4, None), (5, [float("nan"), 1.0]), (6, [1.0, None]), (7, []), (8, [1.0, 0.0, 0.0]), (None, [1.0, 0.0]), (9, [1.0, 0.0]), (10, [0.0, 1.0])]
    got = {r.vec_id: (r.n_links, r.component_id) for r in embedding_join.linked_components(spark.createDataFrame(rows, "vec_id long, embedding array<float>")).collect()}
    assert got[1] == got[2] == got[9] == (2, 1)
    assert all(got[k] == (0, k) for k in (3, 4, 5, 6, 7, 8, 10, None))


def test_tiles_of_reordered_passage(spark):
    bench = spark.createDataFrame([(1, "one two three four five six seven eight nine ten eleven twelve"), (2, "x"), (3, None), (4, "")], "item_id long, text string")
    d = docs(spark, ["zz Seven eight, nine ten eleven twelve! q one two three four five six", "one two three four other", "an x here", *ODD])
    got = {r.doc_id: (r.contaminated, r.item_id, r.coverage) for r in decontaminate.decontaminate(d, bench).collect()}
    assert got[0] == (True, 1, 1.0) and got[1][0] is False and got[2] == (True, 2, 1.0) and got[3] == (False, None, 0.0)
    assert decontaminate.decontaminate(d, bench, block_chars=10).filter("contaminated").count() == sum(x[0] for x in got.values())


def test_personal_data_base(spark):
    patterns = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}

    def ok(kind, m):
        digits = re.sub("[^0-9]", "", m)
        luhn = sum((x := int(c) * (1 + i % 2)) - 9 * (x > 9) for i, c in enumerate(reversed(digits))) % 10 == 0
        return {"email": True, "ip": all(int(p) <= 255 for p in m.split(".")) if kind == "ip" else True, "card": 12 <= len(digits) <= 19 and luhn, "phone": 9 <= len(digits) <= 15}[kind]

    r = random.Random(3)
    texts = ["".join(r.choice("a@.1 2-+()4.%é\n_") for _ in range(r.randint(0, 60))) for _ in range(400)] + [None, "1" * 30_000, "a@b.c_d@e.f +1 (988) 555-2485 4111 1111 1111 1111 1.2.3.4", "password=531ccd051a92ebcb68 ok"]
    found = personal_data.spans(personal_data.candidates(docs(spark, texts).select("doc_id", "text"))).select("doc_id", personal_data.as_text(F.col("base")).alias("s")).collect()
    for row in found:
        t = texts[row.doc_id] or ""
        want = sorted((m.start(), i, k, m.end()) for i, (k, p) in enumerate(patterns.items()) for m in re.finditer(p, t) if ok(k, m.group()))
        assert row.s == ",".join(f"{k}:{a}:{b}" for a, _, k, b in want)


def test_personal_data_totals(spark, tmp_path):
    docs(spark, ["to a@b.org at 1.2.3.4, +1 (988) 555-2485", "nothing here", "card 4111 1111 1111 1111", None, ""]).select("doc_id", "text").write.parquet(f"{tmp_path}/documents.parquet")
    rows = {r.doc_id: r for r in personal_data.op8_personal_data(spark, str(tmp_path)).collect()}
    assert [(rows[i].n_email, rows[i].n_ip, rows[i].n_card, rows[i].n_phone) for i in range(5)] == [(1, 1, 0, 1), (0, 0, 0, 0), (0, 0, 1, 0), (0, 0, 0, 0), (0, 0, 0, 0)]
    for r in rows.values():
        assert r.n_spans == len([x for x in r.spans.split(",") if x]) >= r.n_email + r.n_ip + r.n_card + r.n_phone
        assert r.has_personal_data == (r.n_spans > 0)


def test_cascade_is_exact(spark):
    universe = spark.range(5000).select(F.concat(F.lit("k"), "id").alias("key"))
    listed = universe.filter("substr(key, 2) % 37 = 0")
    rows = universe.select("key", F.xxhash64("key").alias("h")).collect()
    said = url_filter.build_cascade(listed, universe).listed(np.array([x.h for x in rows], np.int64).astype(np.uint64))
    assert [bool(b) for b in said] == [int(x.key[1:]) % 37 == 0 for x in rows]
    odd = spark.createDataFrame([(1, None), (2, "nourl"), (3, "http://A.Example.ORG/es/x?q"), (4, "http://badexample.org/es/")], "page_id long, url string")
    got = {x.page_id: (x.host, x.path, x.rule, x.verdict) for x in url_filter.judge_urls(odd, url_filter.RULES, spark.createDataFrame([], "host string")).collect()}
    assert got == {1: ("", "", None, "allow"), 2: ("", "", None, "allow"), 3: ("a.example.org", "/es/x", "example.org/es/", "block"), 4: ("badexample.org", "/es/", "org/", "allow")}


def test_pipeline_keeps_columns(spark):
    import corpus_pipeline

    d = table(spark, D, "documents")
    out = corpus_pipeline.run(spark, D)
    assert set(d.columns) < set(out.columns)
    n = out.count()
    assert 0 < n < d.count() and out.select("doc_id").distinct().count() == n
    assert out.filter("size(ids) = 0").isEmpty()
