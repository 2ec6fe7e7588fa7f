"""Personal data by weak supervision, in DataFrame functions only.

Candidates are the matches of one pattern per kind (email, ip, card, phone, and secret: key-like strings).
Labelers vote on every candidate (2 yes, 1 abstains, 0 no): the pattern's own check, a gazetteer, context
words before it, and its edges. Votes are counted by kind and vote pattern (at most 5 x 3^5 rows reach the
driver); expectation-maximisation estimates each labeler's reliability without labels; its posteriors
train the final span classifier, a logistic model over the votes, whose weights return as literals of one
column expression. Candidates of the base kinds that pass their checks are always spans; the model adds
others from `add_at` on.

Positions come from splitting a text by a pattern and adding up lengths, so one pass over texts gives all
candidates; only spans are stored. Patterns are possessive or anchored so that long runs neither
recurse nor rescan.

Defined results: null text is empty; no candidates -> zero counts, digest of the empty string; without
any candidate in the table the prior weights are used; rows are answered each; extra columns are ignored.
The query also returns n_spans and has_personal_data, over base and added spans of every kind.
"""

from __future__ import annotations

import math
from collections import defaultdict

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import stored, table

#: fixed values: kind -> (quick test, pattern). Base kinds first, in output order.
_LOCAL = "A-Za-z0-9._%+-"
PATTERNS = {
    "email": ("@", rf"(?:(?<![{_LOCAL}])|\G)[{_LOCAL}]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"),
    "ip": (r"[0-9]\.[0-9]++\.[0-9]++\.[0-9]", r"(?:(?<![0-9])|\G)[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++"),
    "card": (r"[0-9](?:[\x20-]?[0-9]){11}", r"[0-9](?:[\x20-]?[0-9])++"),
    "phone": (r"\+[0-9]", r"\+[0-9][\x20().0-9-]+[0-9]"),
    "secret": (r"[0-9][A-Za-z0-9_-]|[A-Za-z0-9_-][0-9]", r"(?<![A-Za-z0-9_-])(?=[A-Za-z_-]*+[0-9])[A-Za-z0-9_-]{16,}+"),
}
KINDS = list(PATTERNS)
BASE = KINDS[:4]
#: fixed values: known beginnings or endings of real values, and words that announce them
GAZETTEER = {
    "email": r"(?i)\.(com|org|net|edu|gov|info|io|de|fr|es|it|uk|eu|us|ch|at)$",
    "ip": r"^(?!0|10\.|127\.|169\.254\.|192\.168\.|22[4-9]\.|23[0-9]\.|24[0-9]\.|25[0-9]\.)",
    "card": r"^(4|5[1-5]|2[2-7]|3[47]|6011|65)",
    "phone": r"^\+(1|7|2[07]|3[0-469]|4[013-9]|5[1-8]|6[0-6]|8[1246]|9[0-58])",
    "secret": r"^(AKIA|ASIA|ghp_|gho_|sk_|sk-|pk_|xox|AIza|eyJ)",
}
CONTEXT = {
    "email": r"(?i)(mail|contact|write|to)\W*$",
    "ip": r"(?i)(ip|host|server|address|from)\W*$",
    "card": r"(?i)(card|visa|master|payment|credit)\W*$",
    "phone": r"(?i)(phone|tel|call|mobile|fax)\W*$",
    "secret": r"(?i)(password|passwd|pwd|token|secret|key|bearer|auth)\W*$",
}
N_VOTES = 5
ADD_AT = 0.9


def _luhn(digits: Column) -> Column:
    def value(i: Column) -> Column:
        d = F.substr(digits, F.length(digits) - i, F.lit(1)).cast("int")
        twice = d * 2
        return F.when(i % 2 == 0, d).when(twice > 9, twice - 9).otherwise(twice)

    return F.aggregate(F.transform(F.sequence(F.lit(0), F.length(digits) - 1), value), F.lit(0), lambda a, x: a + x) % 10 == 0


def _checked(kind: str, m: Column) -> Column:
    """Whether a match of the kind's pattern passes the kind's own check."""
    if kind == "email":
        return F.lit(True)
    if kind == "ip":
        return F.forall(
            F.split(m, r"\."),
            lambda p: (F.length(F.ltrim(p, F.lit("0"))) <= 3) & (F.coalesce(F.ltrim(p, F.lit("0")).try_cast("int"), F.lit(0)) <= 255),
        )
    if kind == "card":
        digits = F.translate(m, " -", "")
        return F.when(F.length(digits).between(12, 19), _luhn(digits)).otherwise(False)
    if kind == "phone":
        return F.length(F.regexp_replace(m, "[^0-9]", "")).between(9, 15)
    return m.rlike("[A-Za-z]") & (F.length(F.regexp_replace(m, "[^0-9]", "")) >= 2)


def _votes(kind: str, m: Column, before: Column, after: Column) -> Column:
    """N_VOTES digits: pattern check, gazetteer, context, edges, size."""
    yes, none, no = F.lit("2"), F.lit("1"), F.lit("0")
    sizes = {"email": (6, 60), "ip": (7, 15), "card": (15, 19), "phone": (10, 20), "secret": (18, 64)}[kind]
    missed = no if kind in ("phone", "email") else none
    return F.concat(
        F.when(_checked(kind, m), yes).otherwise(no),
        F.when(m.rlike(GAZETTEER[kind]), yes).otherwise(missed),
        F.when(before.rlike(CONTEXT[kind]), yes).otherwise(none),
        F.when(before.rlike(r"(^|[\s\"'(=:,])$") & after.rlike(r"^($|[\s\"'),.;!?])"), yes).otherwise(no),
        F.when(F.length(m).between(*sizes), none).otherwise(no),
    )


#: matches that one running sum passes; a text's matches are listed in time that grows with their number
STRIDE = 256


def _found(kind: str, text: Column) -> Column:
    """Candidates of a kind: array of (at, rank, kind, end, votes)."""
    quick, pattern = PATTERNS[kind]
    maybe = F.contains(text, F.lit("@")) if kind == "email" else text.rlike(quick)
    hits = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    rest = F.split(text, pattern, -1)
    empty = F.array().cast("array<struct<at:int,rank:int,end:int,votes:string>>")

    def sized(x: Column) -> Column:
        # lambda variables hold the arrays: columns named in a lambda would be worked out anew for every element
        lens = F.transform(x["m"], lambda m, i: F.length(m) + F.length(F.get(x["s"], i)))
        return F.struct(x["m"].alias("m"), x["s"].alias("s"), lens.alias("n"))

    def begun(x: Column) -> Column:
        """Where each run of STRIDE matches begins: sums of runs, then running sums of these."""
        runs = F.sequence(F.lit(0), F.floor((F.size(x["m"]) - 1) / STRIDE).cast("int"))
        sums = F.transform(runs, lambda r: F.aggregate(F.slice(x["n"], r * STRIDE + 1, F.lit(STRIDE)), F.lit(0), lambda u, v: u + v))
        start = F.struct(F.lit(0).alias("pos"), F.array().cast("array<int>").alias("out"))
        at = F.aggregate(sums, start, lambda u, v: F.struct((u["pos"] + v).alias("pos"), F.concat(u["out"], F.array(u["pos"])).alias("out")), lambda u: u["out"])
        return F.struct(x["m"].alias("m"), x["s"].alias("s"), at.alias("at"))

    def listed(x: Column) -> Column:
        def add(u: Column, i: Column) -> Column:
            m, before = F.get(x["m"], i), F.get(x["s"], i)
            at = u["pos"] + F.length(before)
            end = at + F.length(m)
            votes = _votes(kind, m, F.right(before, F.lit(24)), F.left(F.get(x["s"], i + 1), F.lit(1)))
            one = F.struct(at.alias("at"), F.lit(KINDS.index(kind)).alias("rank"), end.alias("end"), votes.alias("votes"))
            return F.struct(end.alias("pos"), F.concat(u["out"], F.array(one)).alias("out"))

        def run(begin: Column, r: Column) -> Column:
            own = F.sequence(r * STRIDE, F.least((r + 1) * STRIDE, F.size(x["m"])) - 1)
            return F.aggregate(own, F.struct(begin.alias("pos"), empty.alias("out")), add, lambda u: u["out"])

        return F.flatten(F.transform(x["at"], run))

    found = _let(_let(_let(F.struct(hits.alias("m"), rest.alias("s")), sized), lambda x: F.when(F.size(x["m"]) > 0, begun(x))), lambda x: F.when(x.isNotNull(), listed(x)))
    return F.when(maybe, F.coalesce(found, empty)).otherwise(empty)


def _let(value: Column, body) -> Column:
    """body of a value that is worked out once."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def candidates(docs: DataFrame, text: str = "text") -> DataFrame:
    """docs without the text, with `cands` appended: all candidates by position, then kind."""
    t = F.coalesce(F.col(text), F.lit(""))
    return docs.withColumn("cands", F.array_sort(F.concat(*[_found(k, t) for k in KINDS]))).drop(text)


def reliabilities(counts: dict[tuple[int, str], int], rounds: int = 50) -> dict[tuple[int, str], float]:
    """EM over (kind, votes) -> count: the probability of each vote pattern to be a true span."""
    post: dict[tuple[int, str], float] = {}
    for kind in {k for k, _ in counts}:
        mine = {v: n for (k, v), n in counts.items() if k == kind}
        p = {v: min(0.95, max(0.05, 0.5 + sum(int(x) - 1 for x in v) / (2 * N_VOTES))) for v in mine}
        for _ in range(rounds):
            # one pseudo-count for the direction a labeler is meant to have keeps rare kinds steady
            on = [[1.0, 2.0, 4.0] for _ in range(N_VOTES)]
            off = [[4.0, 2.0, 1.0] for _ in range(N_VOTES)]
            total = [2.0, 1.0]
            for v, n in mine.items():
                total[0] += n * p[v]
                total[1] += n * (1 - p[v])
                for j, x in enumerate(v):
                    on[j][int(x)] += n * p[v]
                    off[j][int(x)] += n * (1 - p[v])
            prior = math.log(total[0] / total[1])
            for v in mine:
                z = prior + sum(math.log(on[j][int(x)] / sum(on[j])) - math.log(off[j][int(x)] / sum(off[j])) for j, x in enumerate(v))
                p[v] = 1 / (1 + math.exp(-max(-30.0, min(30.0, z))))
        post |= {(kind, v): x for v, x in p.items()}
    return post


def train(counts: dict[tuple[int, str], int], post: dict[tuple[int, str], float], steps: int = 300) -> list[float]:
    """Weights of a logistic span classifier, (kind, labeler, vote) flattened, fitted to the posteriors."""
    weights = [float(x - 1) for _ in KINDS for _ in range(N_VOTES) for x in range(3)]
    if not counts:
        return weights
    by_kind = defaultdict(list)
    for (k, v), n in counts.items():
        by_kind[k].append((v, n, post[k, v]))
    for k, rows in by_kind.items():
        total = sum(n for _, n, _ in rows)
        at = [[(k * N_VOTES + j) * 3 + int(x) for j, x in enumerate(v)] for v, _, _ in rows]
        for _ in range(steps):
            grad = defaultdict(float)
            for ix, (_, n, y) in zip(at, rows, strict=True):
                z = sum(weights[i] for i in ix)
                err = (1 / (1 + math.exp(-max(-30.0, min(30.0, z)))) - y) * n / total
                for i in ix:
                    grad[i] += err
            for i, g in grad.items():
                weights[i] -= 1.0 * (g + 1e-4 * weights[i])
    return weights


def probability(rank: Column, votes: Column, weights: list[float]) -> Column:
    table_ = F.array(*[F.lit(w) for w in weights])
    z = F.lit(0.0)
    for j in range(N_VOTES):
        z = z + F.get(table_, (rank * N_VOTES + j) * 3 + F.substr(votes, F.lit(j + 1), F.lit(1)).cast("int"))
    return 1 / (1 + F.exp(-z))


def spans(found: DataFrame, add_at: float = ADD_AT) -> DataFrame:
    """candidates -> base and all: arrays of (at, rank, end)."""
    votes = found.select(F.explode("cands").alias("c")).groupBy("c.rank", "c.votes").agg(F.count("*").alias("n")).collect()
    counts = {(r["rank"], r["votes"]): r["n"] for r in votes}
    weights = train(counts, reliabilities(counts))

    def is_base(c: Column) -> Column:
        return (c["rank"] < len(BASE)) & (F.left(c["votes"], F.lit(1)) == "2")

    return found.withColumns({
        "base": F.filter("cands", is_base),
        "all": F.filter("cands", lambda c: is_base(c) | (probability(c["rank"], c["votes"], weights) >= add_at)),
    })


def as_text(c: Column) -> Column:
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(c, lambda s: F.concat_ws(":", F.get(names, s["rank"]), s["at"].cast("string"), s["end"].cast("string"))), ",")


def _of_kind(rank: int):
    return lambda s: s["rank"] == rank


def op8_personal_data(spark, sf_dir: str) -> DataFrame:
    found = stored(candidates(table(spark, sf_dir, "documents").select("doc_id", "text")), "candidates")
    out = spans(found)
    n = {f"n_{k}": F.size(F.filter("base", _of_kind(i))).cast("long") for i, k in enumerate(BASE)}
    n["n_spans"] = F.size("all").cast("long")
    return out.select(
        "doc_id",
        *[c.alias(k) for k, c in n.items()],
        (F.size("all") > 0).alias("has_personal_data"),
        F.sha2(as_text(F.col("base")), 256).alias("base_sha256"),
        as_text(F.col("all")).alias("spans"),
    )
