"""Near-duplicate embeddings by an epsilon grid order join.

Cosine >= s between unit vectors is distance <= eps = sqrt(2 - 2 s). Equal vectors become one weighted class
first, with a number of its own. Unit vectors are rotated to their principal axes (from sums over all vectors); the grid
cells of width eps on the leading axes, compared lexicographically, are the order. A range partitioning by it is cut
into blocks with bounding boxes on the axes, and consecutive blocks form stretches of about STRETCH numbers. Two
stretches meet in one task if their first-axis cells are neighbours and their boxes within eps, so a block travels
once for each stretch near its own. In the task both sequences are halved recursively, and halves whose boxes
are further apart than eps are skipped, before products are taken in double precision. Links are counted by
row sums and merged by labels: a task returns, per class, its number of links and one edge to its component's
first class, never the links themselves, so a group of near copies costs products but no work per link.

Defined results: vectors that are null, empty, zero or hold null or non-finite components, and rows with a null
id, link with nothing (n_links 0, their own component); vectors of different lengths do not link; every repeated
row is a vector of its own; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import components, drop, stored, table, tidied

SIMILARITY = 0.9
LEAD = 8
STRETCH = 1 << 20
LEAF = 512
SLACK = 1e-9


def _unit(raw: np.ndarray) -> np.ndarray:
    x = raw.astype(np.float64)
    x /= np.abs(x).max(1, keepdims=True)
    return x / np.sqrt((x * x).sum(1, keepdims=True))


def principal_axes(classes: DataFrame) -> dict[int, np.ndarray]:
    """Dimension -> its axes by falling variance (columns), from second moments summed over all vectors."""

    def moments(batches):
        sums: dict[int, np.ndarray] = {}
        for b in batches:
            for dim, part in b.groupby("dim"):
                u = _unit(np.stack(part["v"].to_numpy()))
                sums[dim] = sums.get(dim, 0) + u.T @ u
        for dim, m in sums.items():
            yield pd.DataFrame({"dim": dim, "at": np.arange(dim * dim), "x": m.ravel()})

    got = classes.select("dim", "v").mapInPandas(tidied(moments), "dim int, at long, x double").groupBy("dim", "at").agg(F.sum("x").alias("x"))
    axes: dict[int, np.ndarray] = {}
    for dim, part in got.toPandas().groupby("dim"):
        m = np.zeros(dim * dim)
        m[part["at"]] = part["x"]
        _, vectors = np.linalg.eigh(m.reshape(dim, dim))
        axes[int(dim)] = np.ascontiguousarray(vectors[:, ::-1])
    return axes


def apart(lo1, hi1, lo2, hi2) -> float:
    """Distance of two boxes."""
    gap = np.maximum(0.0, np.maximum(np.asarray(lo1) - np.asarray(hi2), np.asarray(lo2) - np.asarray(hi1)))
    return float(np.sqrt((gap * gap).sum()))


class Forest:
    """Link counts and components of the classes of one or two stretches, by their places."""

    def __init__(self, size: int):
        self.n = np.zeros(size, np.int64)
        self.up = list(range(size))

    def root(self, a: int) -> int:
        up = self.up
        while up[a] != a:
            up[a] = a = up[up[a]]
        return a

    def add(self, at1: int, w1: np.ndarray, at2: int, w2: np.ndarray, linked: np.ndarray, both: bool) -> None:
        """Links between the classes from at1 on and those from at2 on."""
        rows, cols = linked.shape
        self.n[at1 : at1 + rows] += linked @ w2
        if both:
            self.n[at2 : at2 + cols] += w1 @ linked
        some1, some2 = np.flatnonzero(linked.any(1)), np.flatnonzero(linked.any(0))
        while True:
            label1, label2 = np.full(rows, -1), np.full(cols, -1)
            label1[some1] = [self.root(at1 + i) for i in some1.tolist()]
            label2[some2] = [self.root(at2 + j) for j in some2.tolist()]
            open_ = linked & (label1[:, None] != label2[None, :])
            if not open_.any():
                return
            # one open link of each row and column: every component left meets another one
            i, j = np.flatnonzero(open_.any(1)), np.flatnonzero(open_.any(0))
            for x, y in [*zip(i, open_[i].argmax(1), strict=True), *zip(open_[:, j].argmax(0), j, strict=True)]:
                a, b = self.root(at1 + int(x)), self.root(at2 + int(y))
                self.up[max(a, b)] = min(a, b)


def link_stretches(one: tuple, two: tuple, same: bool, s: float, eps: float, forest: Forest) -> None:
    """Join two stretches (weights, unit vectors, raw vectors, leading coordinates) in epsilon grid order."""
    shift = 0 if same else len(one[0])

    def meet(a: slice, b: slice) -> None:
        p, q = one[3][a], two[3][b]
        if same and a.start > b.start or apart(p.min(0), p.max(0), q.min(0), q.max(0)) > eps + SLACK:
            return
        na, nb = a.stop - a.start, b.stop - b.start
        if na > LEAF or nb > LEAF:
            halves = lambda r, n: [r] if n <= LEAF else [slice(r.start, r.start + n // 2), slice(r.start + n // 2, r.stop)]
            for x in halves(a, na):
                for y in halves(b, nb):
                    meet(x, y)
            return
        cos = one[1][a] @ two[1][b].T
        linked = cos >= s
        for i, j in zip(*np.nonzero(np.abs(cos - s) < SLACK), strict=True):
            x, y = one[2][a][i].astype(np.float64), two[2][b][j].astype(np.float64)
            linked[i, j] = x @ y / (math.sqrt(x @ x) * math.sqrt(y @ y)) >= s
        twin = same and a.start == b.start
        if twin:
            np.fill_diagonal(linked, False)
        if linked.any():
            forest.add(a.start, one[0][a], shift + b.start, two[0][b], linked, not twin)

    meet(slice(0, len(one[0])), slice(0, len(two[0])))


def linked_components(vectors: DataFrame, vec_id: str = "vec_id", embedding: str = "embedding", similarity: float = SIMILARITY) -> DataFrame:
    """(vec_id, n_links, component_id, kept) for every row of vectors."""
    spark, eps = vectors.sparkSession, math.sqrt(max(0.0, 2 - 2 * similarity))
    e = F.col("e")
    # single-precision input travels as such: its double values are the same
    kind = "float" if vectors.schema[embedding].dataType.simpleString() == "array<float>" else "double"
    rows = vectors.select(F.col(vec_id).cast("long").alias("vec_id"), F.col(embedding).cast(f"array<{kind}>").alias("e"))
    fine = F.coalesce(
        F.col("vec_id").isNotNull() & (F.size(e) > 0)
        & F.forall(e, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
        & F.exists(e, lambda x: x != 0), F.lit(False),
    )
    rows = rows.withColumn("ok", fine)
    keyed = rows.filter("ok").select("vec_id", "e", F.xxhash64("e").alias("k1"), F.xxhash64(F.lit(1), "e").alias("k2"))
    classes = keyed.groupBy("k1", "k2").agg(F.min("vec_id").alias("rep"), F.count("*").alias("w"), F.first("e").alias("v"))
    # numbers are fixed by writing them
    classes = stored(classes.withColumns({"dim": F.size("v"), "class": F.monotonically_increasing_id()}), "vector-classes")
    axes = spark.sparkContext.broadcast(principal_axes(classes))
    about = classes.agg(F.count("*").alias("n"), F.max("dim").alias("dim")).first()
    stretch = max(64, STRETCH // (about.dim or 1))
    block = max(16, stretch // 4)

    def order(batches):
        for b in batches:
            lead = np.zeros((len(b), LEAD))
            for dim, part in b.groupby("dim"):
                n = min(LEAD, dim)
                lead[part.index - b.index[0], :n] = _unit(np.stack(part["v"].to_numpy())) @ axes.value[dim][:, :n]
            b["y"] = list(lead)
            b["cell"] = list(np.floor(lead / max(eps, 1e-6)).astype(np.int32))
            yield b[["class", "w", "v", "dim", "y", "cell"]]

    cells = [F.col("cell")[i] for i in range(LEAD)]
    ordered = classes.select("class", "w", "v", "dim").mapInPandas(tidied(order), f"class long, w long, v array<{kind}>, dim int, y array<double>, cell array<int>")
    ordered = ordered.repartitionByRange(max(1, -(-about.n // block)), "dim", *cells, "class").sortWithinPartitions("dim", *cells, "class")
    number = np.float32 if kind == "float" else np.float64

    def pack(batches):
        part = TaskContext.get().partitionId()

        def packed(rows: pd.DataFrame):
            y = np.stack(rows["y"].to_numpy())
            return pd.DataFrame({
                "part": [part], "dim": [int(rows["dim"].iloc[0])], "lo": [y.min(0)], "hi": [y.max(0)],
                "ids": [rows["class"].to_numpy(np.int64).tobytes()], "ws": [rows["w"].to_numpy(np.int64).tobytes()],
                "vs": [np.stack(rows["v"].to_numpy()).astype(number).tobytes()], "ys": [y.tobytes()],
            })

        held = None
        for b in batches:
            held = b if held is None else pd.concat([held, b], ignore_index=True)
            while len(held) and (len(held) >= block or held["dim"].iloc[0] != held["dim"].iloc[-1]):
                n = min(block, int((held["dim"] == held["dim"].iloc[0]).sum()))
                yield packed(held.iloc[:n])
                held = held.iloc[n:].reset_index(drop=True)
        if held is not None and len(held):
            yield packed(held)

    blocks = stored(ordered.mapInPandas(tidied(pack), "part int, dim int, lo array<double>, hi array<double>, ids binary, ws binary, vs binary, ys binary"), "blocks")
    # as many partitions to a stretch as hold about its number of vectors
    parts = (blocks.agg(F.max("part").alias("p")).first().p or 0) + 1
    blocks = blocks.withColumn("s", F.floor(F.col("part") / max(1, stretch * parts // max(1, about.n))))
    edge = lambda f, c: F.array(*[f(F.col(c)[i]) for i in range(LEAD)]).alias(c)
    boxes = blocks.groupBy("dim", "s").agg(edge(F.min, "lo"), edge(F.max, "hi"))
    cell_of = lambda c: F.floor(F.col(c)[0] / max(eps, 1e-6))
    left = boxes.select(F.col("s").alias("s1"), "dim", F.col("lo").alias("lo1"), F.col("hi").alias("hi1"), F.explode(F.sequence(cell_of("lo") - 1, cell_of("hi") + 1)).alias("c"))
    right = boxes.select(F.col("s").alias("s2"), "dim", F.col("lo").alias("lo2"), F.col("hi").alias("hi2"), F.explode(F.sequence(cell_of("lo"), cell_of("hi"))).alias("c"))
    gaps = F.transform(F.arrays_zip("lo1", "hi1", "lo2", "hi2"), lambda z: F.greatest(F.lit(0.0), z["lo1"] - z["hi2"], z["lo2"] - z["hi1"]))
    near = F.aggregate(gaps, F.lit(0.0), lambda a, g: a + g * g) <= (eps + SLACK) ** 2
    meets = left.join(right, ["dim", "c"]).filter("s1 <= s2").filter(near).select("dim", "s1", "s2").distinct()
    meets = stored(meets, "meetings")
    sent = meets.select("dim", F.col("s1").alias("s"), "s1", "s2").union(meets.filter("s1 < s2").select("dim", "s2", "s1", "s2"))
    work = blocks.drop("lo", "hi").join(sent, ["dim", "s"])

    def join(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        dim, s1, s2 = (int(x) for x in key)
        sides, ids = [], []
        for s in (s1, s2):
            own = rows[rows["s"] == s]
            raw = np.concatenate([np.frombuffer(x, number).reshape(-1, dim) for x in own["vs"]])
            sides.append((np.concatenate([np.frombuffer(x, np.int64) for x in own["ws"]]), _unit(raw), raw, np.concatenate([np.frombuffer(x).reshape(-1, LEAD) for x in own["ys"]])))
            ids.append(np.concatenate([np.frombuffer(x, np.int64) for x in own["ids"]]))
        ids = ids[0] if s1 == s2 else np.concatenate(ids)
        forest = Forest(len(ids))
        link_stretches(*sides, s1 == s2, similarity, eps, forest)
        some = np.flatnonzero(forest.n)
        return pd.DataFrame({"a": ids[some], "b": ids[[forest.root(i) for i in some.tolist()]], "n": forest.n[some]})

    found = stored(work.groupBy("dim", "s1", "s2").applyInPandas(join, "a long, b long, n long"), "vector-links")
    drop(blocks, meets)
    links = found.groupBy(F.col("a").alias("class")).agg(F.sum("n").alias("n"))
    roots = components(found.filter("a <> b").select("a", "b")).select(F.col("v").alias("class"), "root")
    own = classes.select("class", "rep", "k1", "k2", "w").join(links, "class", "left").join(roots, "class", "left")
    own = stored(own.withColumn("root", F.coalesce("root", "class")), "vector-roots")
    least = own.groupBy("root").agg(F.min("rep").alias("component_id"))
    known = own.join(least, "root").select("k1", "k2", (F.coalesce("n", F.lit(0)) + F.col("w") - 1).alias("n_links"), "component_id")
    drop(found)
    done = keyed.select("vec_id", "k1", "k2").join(known, ["k1", "k2"]).select("vec_id", "n_links", "component_id")
    rest = rows.filter("not ok").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return done.unionByName(rest).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))


def op4_embedding_join(spark, sf_dir: str) -> DataFrame:
    return linked_components(table(spark, sf_dir, "embeddings").select("vec_id", "embedding"))


OP4_SQL = r"""
WITH RECURSIVE n AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings),
l AS (SELECT a.vec_id AS a, b.vec_id AS b FROM n a JOIN n b ON a.vec_id <> b.vec_id
  AND list_dot_product(a.e, b.e) / (sqrt(list_dot_product(a.e, a.e)) * sqrt(list_dot_product(b.e, b.e))) >= 0.9),
reach AS (SELECT vec_id AS v, vec_id AS o FROM n UNION SELECT reach.v, l.b FROM reach JOIN l ON reach.o = l.a),
c AS (SELECT v, min(o) AS component_id FROM reach GROUP BY v),
d AS (SELECT a, count(*) AS n_links FROM l GROUP BY a)
SELECT n.vec_id, CAST(coalesce(d.n_links, 0) AS BIGINT) AS n_links, c.component_id, n.vec_id = c.component_id AS kept
FROM n JOIN c ON n.vec_id = c.v LEFT JOIN d ON n.vec_id = d.a
"""
