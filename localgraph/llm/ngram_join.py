"""Exact Jaccard self-join of documents' word n-gram sets, with the relations between sets used to skip work.

1. One pass over the texts gives every document its set size, a 128-bit fingerprint of its set, HUBS minima of
   independent hashes, and, for the order of n-grams, the frequent hash buckets. Documents with equal fingerprints
   are one class.
2. Classes that share minima are compared with that bucket's two hubs only (stars, never all pairs). The links found
   make first components; a member keeps its most similar hub as leader, with the size of what it has beyond it.
3. Index: n-grams are ordered by (bucket frequency, hash), and sets that reach the similarity share an n-gram of their
   prefixes. By its position an entry can serve only some sizes of the smaller set (for the others, too few n-grams
   are left behind it). Lists are cut into blocks by these ranges, and a smaller set meets only blocks that serve
   its size; the rest of every list is skipped. N-grams whose classes are all in one component, or are two of unlike
   size, never enter the index.
4. Answers: candidate pairs of leaders are settled first, and each keeps a bound of its intersection (exact, if the
   sets were compared). A member's pairs then follow from the answers of its leader: a pair is done when the leaders
   are linked, and is out when the leaders' intersection and what both members have beyond them cannot make a
   link. Leaders that are no candidates are known to share less than a link needs. Only what these answers leave
   open is compared, by sketches and then by whole sets.
5. Components of all links are the result.

The order only steers speed: any common order gives the same links. No candidate is capped. Sets travel only
for classes that occur in a pair still open: they are re-made from the texts in one pass whose rows are
preselected by a bitmap of fixed size (BITMAP_BITS; when it fills up, it merely selects more).
A bucket is frequent when it exceeds twice its share inside one partition, so the order means the same at any size.

Defined results: words are [^\\x20\\x09-\\x0D]+ with A-Z lowered; fewer words than n make one n-gram; null or
wordless texts have empty sets and link with nothing; rows with a null id link with nothing; rows that repeat an
id are one document whose texts all count as members of its component; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import components, drop, in_blocks, mix, shingle_hashes, stored, table, tidied, word_hashes

HUBS = 6
BLOCK_ENTRIES = 128
SLOTS = 8
BUCKET_BITS = 20
BITMAP_BITS = 1 << 26
MAX_BUCKETS = 1 << BUCKET_BITS
_SALTS = [np.uint64(x) for x in np.random.default_rng(5).integers(1, 1 << 63, HUBS + 1)]


def _sets(ids, texts, k: int):
    """(id, sorted distinct n-gram hashes) of every document of a batch."""
    for block_ids, block in in_blocks(ids, texts):
        words, at = word_hashes(block)
        for n, i in enumerate(block_ids):
            yield i, np.unique(shingle_hashes(words[at[n] : at[n + 1]], k))


def _signed(x) -> int:
    return int(np.uint64(x).astype(np.int64))


def profile(docs: DataFrame, k: int) -> DataFrame:
    """(doc_id, n, f1, f2, m[]) per document, and rows (bucket, count) of locally frequent buckets.

    Null ids travel as a flag: a batch with a null would turn its ids into floats.
    """

    def run(batches):
        counts, seen = np.zeros(1 << BUCKET_BITS, np.int32), 0
        for b in batches:
            out, held = [], []
            for (i, s), nil in zip(_sets(b["doc_id"], b["text"], k), b["nil"], strict=True):
                held.append((s >> np.uint64(64 - BUCKET_BITS)).astype(np.int32))
                seen += len(s)
                if len(s):
                    m = [_signed(mix(s ^ salt).min()) for salt in _SALTS[:HUBS]]
                    out.append((i, len(s), _signed(mix(s).sum()), _signed(mix(s ^ _SALTS[HUBS]).sum()), m, nil))
                else:
                    out.append((i, 0, 0, 0, [], nil))
            if held:
                counts += np.bincount(np.concatenate(held), minlength=len(counts)).astype(np.int32)
            if out:
                yield pd.DataFrame(out, columns=["doc_id", "n", "f1", "f2", "m", "nil"]).assign(bucket=pd.array([None] * len(out), "Int64"))
        often = np.flatnonzero(counts > 2 * seen / len(counts) + 2)
        if len(often):
            yield pd.DataFrame({"doc_id": 0, "n": counts[often].astype(np.int64), "f1": 0, "f2": 0, "m": [[]] * len(often), "nil": False, "bucket": often})

    docs = docs.select(F.coalesce("doc_id", F.lit(0)).alias("doc_id"), F.col("doc_id").isNull().alias("nil"), "text")
    return docs.mapInPandas(tidied(run), "doc_id long, n long, f1 long, f2 long, m array<long>, nil boolean, bucket long")


def bucket_weights(profiles: DataFrame) -> np.ndarray:
    """Frequency of each hash bucket, 0 for the rare ones; at most MAX_BUCKETS numbers."""
    weights = np.zeros(1 << BUCKET_BITS, np.int64)
    got = profiles.filter("bucket is not null").groupBy("bucket").agg(F.sum("n").alias("n")).toPandas()
    weights[got["bucket"].to_numpy(np.int64)] = got["n"].to_numpy(np.int64)
    return weights


def prefixes(docs: DataFrame, weights: np.ndarray, mark: np.ndarray, k: int, percent: int) -> DataFrame:
    """(id, n, grams, marked): each document's prefix in the common order, and whether its bit is in the bitmap."""
    shared = docs.sparkSession.sparkContext.broadcast((weights, mark))

    def run(batches):
        w, have = shared.value
        for b in batches:
            marked, out = _marked(have, b), []
            for (i, s), m in zip(_sets(b["doc_id"], b["text"], k), marked, strict=True):
                if len(s):
                    take = len(s) - -(-len(s) * percent // 100) + 1
                    order = np.lexsort((s, w[s >> np.uint64(64 - BUCKET_BITS)]))[:take]
                    out.append((i, len(s), s[order].tobytes(), m))
            if out:
                yield pd.DataFrame(out, columns=["id", "n", "grams", "marked"])

    return _with_bits(docs).mapInPandas(tidied(run), "id long, n int, grams binary, marked boolean")


def bitmap_of(bits: DataFrame) -> np.ndarray:
    """The bits of column `bit` (below BITMAP_BITS), by Spark's bitmap aggregate: at most BITMAP_BITS / 8 bytes."""
    rows = bits.groupBy(F.bitmap_bucket_number(F.col("bit")).alias("part"))
    out = np.zeros(BITMAP_BITS // 8 + 8192, np.uint8)
    for r in rows.agg(F.bitmap_construct_agg(F.bitmap_bit_position(F.col("bit"))).alias("bits")).toLocalIterator():
        # bucket numbers start at 1 for bits from 1 on and at 0 for bit 0
        at = max(0, r.part - 1) * 4096 if r.part > 0 else 0
        out[at : at + 4096] |= np.frombuffer(r.bits, np.uint8)
    return out


def _bit(key: str) -> Column:
    return F.pmod(F.xxhash64(key), F.lit(BITMAP_BITS)).alias("bit")


def _with_bits(docs: DataFrame) -> DataFrame:
    """docs(doc_id, text) with the place of each id's bit, as the aggregate counts places."""
    bit = docs.select("doc_id", "text", _bit("doc_id"))
    return bit.select("doc_id", "text", F.bitmap_bucket_number(F.col("bit")).alias("part"), F.bitmap_bit_position(F.col("bit")).alias("pos"))


def _marked(have: np.ndarray, b: pd.DataFrame) -> np.ndarray:
    part, pos = b["part"].to_numpy(np.int64), b["pos"].to_numpy(np.int64)
    return (have[np.maximum(0, part - 1) * 4096 + pos // 8] >> (pos % 8).astype(np.uint8)) & 1 == 1


def _places(grams: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Byte and bit of each n-gram's hash in a bitmap made by `bitmap_of`, which counts bits from 1."""
    bit = (grams & np.uint64(BITMAP_BITS - 1)).astype(np.int64)
    at = np.where(bit > 0, bit - 1, 0)
    return at // 8, (at % 8).astype(np.uint8)


def _sketch(s: np.ndarray) -> bytes:
    """Parities of the numbers of n-grams in one to two buckets for each of them."""
    size = max(64, 1 << (len(s) - 1).bit_length())
    return np.packbits(np.bincount((s & np.uint64(size - 1)).astype(np.int64), minlength=size) & 1).tobytes()


def _differ(x: bytes, y: bytes) -> int:
    """At least so many n-grams lie in one of the two sets only: a bucket of unlike parities holds one of them."""
    x, y = np.frombuffer(x, np.uint8), np.frombuffer(y, np.uint8)
    while len(x) > len(y):
        x = x[: len(x) // 2] ^ x[len(x) // 2 :]
    while len(y) > len(x):
        y = y[: len(y) // 2] ^ y[len(y) // 2 :]
    return int(np.bitwise_count(x ^ y).sum())


def sets_of(docs: DataFrame, ids: DataFrame, k: int, sketch: bool) -> DataFrame:
    """(id, n, s): sketches, or whole sets, of the documents whose bit is in the bitmap of ids (all of ids, some others)."""
    shared = docs.sparkSession.sparkContext.broadcast(bitmap_of(ids.select(_bit("id"))))

    def run(batches):
        for b in batches:
            b = b[_marked(shared.value, b)]
            out = [(i, len(s), _sketch(s) if sketch else s.tobytes()) for i, s in _sets(b["doc_id"], b["text"], k)]
            if out:
                yield pd.DataFrame(out, columns=["id", "n", "s"])

    return _with_bits(docs).mapInPandas(tidied(run), "id long, n long, s binary")


def _paired(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    side = lambda x, n, s: sets.select(F.col("id").alias(x), F.col("n").alias(n), F.col("s").alias(s))
    return pairs.join(side("b", "n2", "s2"), "b").join(side("a", "n1", "s1"), "a")


def judged(pairs: DataFrame, docs: DataFrame, k: int, percent: int) -> DataFrame:
    """(a, b, n1, n2, common, linked) for every pair: the size of the intersection, or a bound of it too low for a link."""
    ids = lambda p: p.select(F.col("a").alias("id")).union(p.select("b")).distinct()
    out = "a long, b long, n1 long, n2 long, common long, linked boolean"
    if pairs.isEmpty():
        return docs.sparkSession.createDataFrame([], out)
    marks = stored(sets_of(docs, ids(pairs), k, True), "sketches")

    def bounded(batches):
        for b in batches:
            apart = np.array([_differ(x, y) for x, y in zip(b["s1"], b["s2"], strict=True)], np.int64)
            b["common"] = np.minimum(np.minimum(b["n1"], b["n2"]), (b["n1"] + b["n2"] - apart) // 2)
            b["linked"] = b["common"] * (100 + percent) >= (b["n1"] + b["n2"]) * percent
            yield b[["a", "b", "n1", "n2", "common", "linked"]]

    near = stored(_paired(pairs, marks).mapInPandas(tidied(bounded), out), "bounded")
    drop(marks)
    # whole sets travel only for pairs that the sketches leave open
    open_ = near.filter("linked").select("a", "b")
    if open_.isEmpty():
        return near
    whole = stored(sets_of(docs, ids(open_), k, False), "sets")

    def exact(batches):
        for b in batches:
            common = []
            for x, y in zip(b["s1"], b["s2"], strict=True):
                x, y = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
                if len(x) > len(y):
                    x, y = y, x
                at = np.searchsorted(y, x)
                at[at == len(y)] = 0
                common.append(int((y[at] == x).sum()))
            b["common"] = np.array(common, np.int64)
            b["linked"] = b["common"] * (100 + percent) >= (b["n1"] + b["n2"]) * percent
            yield b[["a", "b", "n1", "n2", "common", "linked"]]

    done = stored(_paired(open_, whole).mapInPandas(tidied(exact), out).unionByName(near.filter("not linked")), "judged")
    drop(near, whole)
    return done


def _entries(bits=None):
    """Batch function: prefixes (id, n, c, grams) to rows (g, id, n, c, p); only n-grams in the bitmap, if one is given."""

    def run(batches):
        for b in filter(len, batches):
            ids, ns, cs = (b[x].to_numpy() for x in ("id", "n", "c"))
            grams = [np.frombuffer(x, np.uint64) for x in b["grams"]]
            sizes = [len(x) for x in grams]
            g = np.concatenate(grams)
            p = np.concatenate([np.arange(x, dtype=np.int32) for x in sizes])
            row = np.repeat(np.arange(len(b)), sizes)
            if bits is not None:
                at, pos = _places(g)
                keep = (bits.value[at] >> pos) & 1 == 1
                g, p, row = g[keep], p[keep], row[keep]
            for i in range(0, len(g), 1 << 16):
                part = slice(i, i + (1 << 16))
                r = row[part]
                yield pd.DataFrame({"g": g[part].view(np.int64), "id": ids[r], "n": ns[r], "c": cs[r], "p": p[part]})

    return tidied(run)


def _counted(percent: int):
    """Batch function over (a, na, pa, ids, ns, ps) sorted by a: pairs (a, b) that the bounds leave open.

    k common n-grams lie in both prefixes; behind the last of them one prefix is used up before the other.
    """

    def pairs_of(b: pd.DataFrame) -> pd.DataFrame:
        sizes = b["ids"].map(len).to_numpy()
        i, n, p = (np.concatenate(b[x].to_numpy()).astype(np.int64) for x in ("ids", "ns", "ps"))
        a, na, pa = (np.repeat(b[x].to_numpy(np.int64), sizes) for x in ("a", "na", "pa"))
        order = np.lexsort((i, a))
        a, i, na, n, pa, p = (x[order] for x in (a, i, na, n, pa, p))
        new = np.flatnonzero(np.append(True, (a[1:] != a[:-1]) | (i[1:] != i[:-1])))
        k = np.diff(np.append(new, len(a)))
        low = lambda x: np.minimum.reduceat(x, new)
        top = lambda x: np.maximum.reduceat(x, new)
        a, i, na, n = a[new], i[new], na[new], n[new]
        least = -(-(na + n) * percent // (100 + percent))
        # what the two prefixes leave: the smaller set's is cut for a set of its own size, the larger one's for this pair
        more = np.maximum(np.minimum(-(-2 * na * percent // (100 + percent)) - 1, n - top(p) - 1), np.minimum(na - top(pa) - 1, least - 1))
        keep = (np.minimum(na - low(pa), n - low(p)) >= least) & (k + more >= least)
        return pd.DataFrame({"a": a[keep], "b": i[keep], "na": na[keep], "nb": n[keep]})

    def run(batches):
        held = None
        for b in batches:
            b = b if held is None else pd.concat([held, b], ignore_index=True)
            # the last set's rows may go on in the next batch
            going = b["a"] == b["a"].iloc[-1]
            held, b = b[going], b[~going]
            if len(b):
                yield pairs_of(b)
        if held is not None and len(held):
            yield pairs_of(held)

    return run


def candidates(index: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b), a the smaller set, of different components whose prefixes allow a link.

    A set of n n-grams whose entry lies at position p can meet smaller sets of na n-grams while
    n - p >= percent (na + n) / (100 + percent); so position gives the largest na, similarity the least.
    """
    band = lambda n: F.floor(F.log(n.cast("double")) / F.log(F.lit(100.0 / percent)) + 1e-9)
    both, n, p = 100 + percent, F.col("n").cast("long"), F.col("p").cast("long")
    serves = lambda n, p: F.least(n, F.floor((n - p) * both / percent) - n)
    lists = index.withColumns({"least": F.ceil(n * percent / 100), "most": serves(n, p)}).filter("least <= most")
    # blocks of one n-gram and band of smaller sizes; long lists are cut by the share of sizes their entries serve, which
    # falls with the position, and then by a hash of the set
    slot = F.floor((n - F.col("most")) * SLOTS / (n - F.col("least") + 1))
    part = F.when(F.col("many") > BLOCK_ENTRIES, slot * (1 << 40) + F.pmod(F.xxhash64("id"), F.ceil(F.col("many") / BLOCK_ENTRIES))).otherwise(0)
    lists = lists.select("g", F.explode(F.sequence(band(F.col("least")), band(F.col("most")))).alias("band"), part.alias("part"), "least", "most", F.struct("id", "c", "n", "p").alias("row"))
    lists = lists.groupBy("g", "band", "part").agg(F.collect_list("row").alias("list"), F.max("most").alias("most"), F.min("least").alias("least"))
    # the smaller set's own prefix ends where too few n-grams are left for a set of its own size
    probe = index.filter((n - p) * both >= 2 * n * percent)
    probe = probe.select("g", F.col("id").alias("a"), F.col("c").alias("ca"), n.alias("na"), p.alias("pa"), band(n).alias("band"))
    met = probe.join(lists.drop("part"), ["g", "band"]).filter("na between least and most")
    size = lambda x: x["n"].cast("long")
    fit = lambda x: (x["c"] != F.col("ca")) & (F.col("na") * 100 >= size(x) * percent) & (F.col("na") <= serves(size(x), x["p"].cast("long"))) & ((F.col("na") < x["n"]) | (F.col("a") < x["id"]))
    met = met.select("a", "na", "pa", F.filter("list", fit).alias("list")).filter(F.size("list") > 0)
    met = met.select("a", F.col("na").cast("int"), F.col("pa").cast("int"), *[F.col(f"list.{x}").alias(f"{x}s") for x in ("id", "n", "p")])
    return met.repartition("a").sortWithinPartitions("a").mapInPandas(tidied(_counted(percent)), "a long, b long, na long, nb long")


def near_components(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """(doc_id, n_shingles, component_id) per row of docs(doc_id, text)."""
    spark = docs.sparkSession
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    profiles = stored(profile(docs, k), "profiles")
    rows = profiles.filter("bucket is null").select(F.when(~F.col("nil"), F.col("doc_id")).alias("doc_id"), "n", "f1", "f2", "m")
    live = rows.filter("n > 0 and doc_id is not null")
    classes = stored(live.groupBy("f1", "f2", "n").agg(F.min("doc_id").alias("rep"), F.first("m").alias("m"), F.count("*").alias("rows")), "classes")
    # documents that are not their class's first, by every class they belong to
    same = stored(live.join(classes.select("f1", "f2", "n", "rep"), ["f1", "f2", "n"]).filter("doc_id <> rep").select("doc_id", "rep"), "copies")

    # ids with more than one text: they lead and follow nobody
    texts = same.select("doc_id", "rep").distinct().unionByName(classes.select(F.col("rep").alias("doc_id"), "rep"))
    shared = stored(texts.groupBy("doc_id").agg(F.count("*").alias("k")).filter("k > 1").select("doc_id"), "shared-ids")

    # stars around two hubs of each minimum's bucket: the smallest id, and the smallest set, which differs least
    # from sets that share most of it
    keyed = classes.select("rep", "n", F.posexplode("m").alias("h", "x"))
    who = F.struct(F.col("rep").alias("a"), F.col("n").alias("na"))
    hubs = keyed.groupBy("h", "x").agg(F.array_distinct(F.array(F.min(who), F.min_by(who, F.struct("n", "rep")))).alias("hub"), F.count("*").alias("c"))
    hubs = hubs.filter("c > 1").select("h", "x", F.explode("hub").alias("hub")).select("h", "x", "hub.a", "hub.na")
    star = keyed.join(hubs, ["h", "x"]).filter("a <> rep").filter(f"least(n, na) * 100 >= greatest(n, na) * {percent}")
    star = star.select("h", F.least("a", "rep").alias("a"), F.greatest("a", "rep").alias("b")).distinct()
    # two common minima are worth a look; a link missed here is found through the index
    star = star.groupBy("a", "b").agg(F.count("*").alias("c")).filter("c >= 2").select("a", "b")
    star = stored(star, "star")
    seen = judged(star, docs, k, percent)
    first = seen.filter("linked")
    roots = components(first.select("a", "b"))
    # the leader: the most similar hub of smaller id that follows none itself
    plain = first.join(shared.select(F.col("doc_id").alias("a")), "a", "left_anti").join(shared.select(F.col("doc_id").alias("b")), "b", "left_anti")
    follow = plain.groupBy(F.col("b").alias("id")).agg(F.max(F.struct((2 * F.col("common") - F.col("n1")).alias("gain"), (-F.col("a")).alias("lead"), (F.col("n2") - F.col("common")).alias("beyond"), F.col("n1").alias("size"))).alias("top"))
    follow = follow.select("id", (-F.col("top.lead")).alias("lead"), "top.beyond", F.col("top.size").alias("lead_n"))
    follow = stored(follow.join(follow.select(F.col("id").alias("lead")), "lead", "left_anti").select("id", "lead", "beyond", "lead_n"), "follow")

    # prefixes of classes, once; only ids that are copies or in a first component need a look at either table
    weights = bucket_weights(profiles)
    special = same.select(F.col("doc_id").alias("id")).union(roots.select("v")).union(classes.filter("rows > 1").select("rep"))
    made = stored(prefixes(docs.filter("doc_id is not null"), weights, bitmap_of(special.select(_bit("id"))), k, percent), "made")
    looked = made.filter("marked").join(classes.select(F.col("rep").alias("id")), "id", "left_semi").dropDuplicates(["id", "grams"])
    looked = looked.join(roots.select(F.col("v").alias("id"), "root"), "id", "left").select("id", "n", F.coalesce("root", "id").alias("c"), "grams")
    heads = stored(made.filter("not marked").select("id", "n", F.col("id").alias("c"), "grams").unionByName(looked), "prefixes")
    drop(made)
    as_rows = "g long, id long, n int, c long, p int"
    seen_in = heads.mapInPandas(_entries(), as_rows).groupBy("g")
    mixed = seen_in.agg(F.min("c").alias("lo"), F.max("c").alias("hi"), F.count("*").alias("many"), F.min("n").alias("least"), F.max("n").alias("most"))
    # an n-gram of two sets whose sizes are too far apart links nothing
    mixed = mixed.filter("lo < hi").filter(f"many > 2 or least * 100 >= most * {percent}").select("g", "many")
    mixed = stored(mixed, "mixed")
    bits = spark.sparkContext.broadcast(bitmap_of(mixed.select(F.pmod("g", F.lit(BITMAP_BITS)).alias("bit"))))
    index = stored(heads.mapInPandas(_entries(bits), as_rows).join(mixed, "g"), "index")
    pairs = stored(candidates(index, percent), "pairs")
    drop(heads, mixed, index)

    # answers of leaders, then of those who follow them
    side = lambda x: follow.select(F.col("id").alias(x), F.col("lead").alias(f"l{x}"), F.col("beyond").alias(f"more_{x}"), F.col("lead_n").alias(f"l{x}_n"))
    told = pairs.join(side("a"), "a", "left").join(side("b"), "b", "left")
    told = told.select("a", "b", "na", "nb", *[F.coalesce(f"l{x}", x).alias(f"l{x}") for x in "ab"], *[F.coalesce(f"more_{x}", F.lit(0)).alias(f"more_{x}") for x in "ab"], *[F.coalesce(f"l{x}_n", f"n{x}").alias(f"l{x}_n") for x in "ab"])
    told = stored(told, "told")
    drop(pairs)
    led = judged(told.filter("a = la and b = lb").select("a", "b"), docs, k, percent)
    needs = lambda x, y: F.ceil((F.col(x) + F.col(y)) * percent / (100 + percent))
    ends = told.filter("a <> la or b <> lb").withColumns({"x": F.least("la", "lb"), "y": F.greatest("la", "lb")})
    said = led.select(F.least("a", "b").alias("x"), F.greatest("a", "b").alias("y"), F.col("common"), "linked")
    ends = ends.join(said, ["x", "y"], "left").filter("linked is null or not linked")
    could = F.coalesce("common", needs("la_n", "lb_n") - 1) + F.col("more_a") + F.col("more_b")
    left = judged(stored(ends.filter(could >= needs("na", "nb")).select("a", "b"), "open"), docs, k, percent)
    links = first.unionByName(led.filter("linked")).unionByName(left.filter("linked")).select("a", "b")
    # documents whose rows repeat an id with other texts are joined through that id
    links = links.unionByName(same.join(shared, "doc_id", "left_semi").select(F.col("doc_id").alias("a"), F.col("rep").alias("b")))
    final = components(links).select(F.col("v").alias("rep"), "root")
    drop(star, seen, roots, follow, told, led, left, same, shared)

    known = classes.select("f1", "f2", "n", "rep").join(final, "rep", "left").select("f1", "f2", "n", F.coalesce("root", "rep").alias("component_id"))
    done = live.join(known, ["f1", "f2", "n"]).select("doc_id", F.col("n").alias("n_shingles"), "component_id")
    rest = rows.filter("n = 0 or doc_id is null").select("doc_id", F.col("n").alias("n_shingles"), F.col("doc_id").alias("component_id"))
    return done.unionByName(rest)


def op7_ngram_join(spark, sf_dir: str) -> DataFrame:
    return near_components(table(spark, sf_dir, "documents"), k=3, percent=90)


OP7_SQL = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
    '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM documents),
s AS (
  SELECT DISTINCT doc_id, unnest(CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) < 3 THEN [array_to_string(ws, ' ')]
    ELSE list_transform(range(1, len(ws) - 1), lambda i: array_to_string(ws[i:i + 2], ' ')) END) AS g FROM w),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
o AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS c FROM s x JOIN s y ON x.g = y.g AND x.doc_id <> y.doc_id GROUP BY 1, 2),
l AS (SELECT a, b FROM o JOIN n p ON p.doc_id = a JOIN n q ON q.doc_id = b WHERE 100 * c >= 90 * (p.n + q.n - c)),
reach AS (SELECT doc_id AS v, doc_id AS u FROM documents UNION SELECT reach.v, l.b FROM reach JOIN l ON reach.u = l.a),
c AS (SELECT v, min(u) AS component_id FROM reach GROUP BY v)
SELECT d.doc_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_shingles, c.component_id
FROM documents d JOIN c ON d.doc_id = c.v LEFT JOIN n ON n.doc_id = d.doc_id
"""
