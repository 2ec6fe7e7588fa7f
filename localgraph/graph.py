"""Undirected graphs as DataFrames, and the measures on vertex sets.

arcs(src, dst) holds both directions, distinct, src <> dst; vertices(v, deg, loops) the degrees, a loop counting
one. `near` is the packed form that walks read: (v, deg, loops, chunk, nbrs), written once by ranges of `pmod(v,
buckets)`, at most CHUNK neighbours a row, so that a hub is many rows and a frontier reads its own buckets. Restricting to a vertex set keeps degrees: a
lost neighbour acts as a loop and is never materialised.
"""

from __future__ import annotations

from dataclasses import dataclass, replace
from functools import cached_property
from typing import NamedTuple

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .session import cut, drop


CHUNK = 1 << 14
#: arcs of a bucket, about; a frontier's pruning needs no more than BUCKETS numbers on the driver
PER_BUCKET = 1 << 22
BUCKETS = 1 << 14


class Near(NamedTuple):
    """Stored adjacency."""

    rows: DataFrame
    buckets: int

    def of(self, frontier: DataFrame) -> DataFrame:
        """frontier(v, ...) with the adjacency of its vertices; only their buckets are scanned, as literals in the plan.

        Spark broadcasts the frontier if its measured size allows, so that no arcs are shuffled; else both sides are.
        """
        rows = self.rows
        if self.buckets > 1:
            need = frontier.select(F.pmod("v", F.lit(self.buckets)).cast("int").alias("bucket")).distinct().collect()
            rows = rows.filter(F.col("bucket").isin([r.bucket for r in need]))
        return frontier.join(rows.drop("bucket"), "v")


@dataclass(frozen=True)
class Graph:
    arcs: DataFrame
    loops: DataFrame | None = None

    @classmethod
    def from_edges(cls, edges: DataFrame, a: str = "a", b: str = "b") -> Graph:
        """Distinct undirected edges of two id columns; nulls and self-pairs are dropped."""
        e = edges.select(F.col(a).cast("long").alias("a"), F.col(b).cast("long").alias("b")).filter("a <> b")
        return cls(e.select(F.col("a").alias("src"), F.col("b").alias("dst")).union(e.select("b", "a")).distinct())

    @property
    def spark(self) -> SparkSession:
        return self.arcs.sparkSession

    @cached_property
    def vertices(self) -> DataFrame:
        plain = self.arcs.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("deg"))
        if self.loops is None:
            return plain.withColumn("loops", F.lit(0).cast("long"))
        extra = self.loops.groupBy("v").agg(F.sum("loops").alias("loops"))
        both = plain.join(extra, "v", "full")
        n = F.coalesce("loops", F.lit(0))
        return both.select("v", (F.coalesce("deg", F.lit(0)) + n).alias("deg"), n.alias("loops")).filter("deg > 0")

    def packed(self) -> DataFrame:
        """(v, deg, loops, chunk, nbrs): chunk 0 once for every vertex; a hub's neighbours are in chunks 1, 2, ..."""
        ends = self.vertices.join(self.arcs.withColumnRenamed("src", "v"), "v", "left")
        n = F.col("deg") - F.col("loops")
        chunk = F.when(n > CHUNK, 1 + F.pmod(F.xxhash64("dst"), F.ceil(n / CHUNK))).otherwise(0)
        rows = ends.groupBy("v", "deg", "loops", chunk.cast("int").alias("chunk")).agg(F.sort_array(F.collect_list("dst")).alias("nbrs"))
        heads = self.vertices.filter(n > CHUNK).select("v", "deg", "loops", F.lit(0).alias("chunk"), F.array().cast("array<bigint>").alias("nbrs"))
        return rows.unionByName(heads)

    @cached_property
    def near(self) -> Near:
        n = min(BUCKETS, max(1, self.vol // PER_BUCKET))
        rows = self.packed().withColumn("bucket", F.pmod("v", F.lit(n)).cast("int"))
        if n > 1:
            # with few buckets, one may hold most vertices (ids of a kind share a remainder): each is as many files as there are cores
            cores = self.spark.sparkContext.defaultParallelism
            files = cores if n < cores else 1
            rows = rows.repartition(n * files, "bucket", F.pmod(F.xxhash64("v"), F.lit(files))).sortWithinPartitions("bucket", "v")
        return Near(cut(rows, "near", ["bucket"] if n > 1 else None), n)

    @cached_property
    def vol(self) -> int:
        if self.loops is None:
            return self.arcs.count()
        return self.vertices.agg(F.coalesce(F.sum("deg"), F.lit(0))).first()[0]

    def kept(self) -> Graph:
        """The same graph with its arcs written once in the shared folder."""
        return replace(self, arcs=cut(self.arcs, "arcs"))

    def stored(self) -> Graph:
        """The same graph, its vertices read from the stored adjacency."""
        g, near = replace(self), self.near
        g.__dict__.update(near=near, vol=self.vol, vertices=near.rows.filter("chunk = 0").select("v", "deg", "loops"))
        return g

    def save(self, path: str, buckets: int = 16) -> None:
        """Packed adjacency partitioned by vertex bucket and sorted by vertex: a frontier reads few row groups."""
        out = self.packed().withColumn("bucket", F.pmod("v", F.lit(buckets)))
        out.repartition(buckets, "bucket").sortWithinPartitions("bucket", "v").write.mode("overwrite").partitionBy("bucket").parquet(path)

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> Graph:
        """A graph that walks on the saved adjacency itself."""
        rows = spark.read.parquet(path)
        g = cls(rows.select(F.col("v").alias("src"), F.explode("nbrs").alias("dst")), rows.filter("loops > 0 and chunk = 0").select("v", "loops"))
        g.__dict__["near"] = Near(rows, rows.agg(F.max("bucket")).first()[0] + 1)
        return g

    def induced(self, a: DataFrame) -> Graph:
        """Subgraph on a(v): degrees recomputed."""
        inside = self.arcs.join(a.select(F.col("v").alias("src")), "src", "left_semi").join(a.select(F.col("v").alias("dst")), "dst", "left_semi")
        loops = self.loops.join(a, "v", "left_semi") if self.loops is not None else None
        return Graph(inside.select("src", "dst"), loops)

    def restrict(self, a: DataFrame) -> Graph:
        """Degree-preserving subgraph on a(v): lost neighbours become loops."""
        inner = self.induced(a)
        have = inner.arcs.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("inside"))
        lost = self.vertices.join(a, "v", "left_semi").join(have, "v", "left")
        return Graph(inner.arcs, lost.select("v", (F.col("deg") - F.coalesce("inside", F.lit(0))).alias("loops")).filter("loops > 0"))


# ---- measures; sets are (set_id, v) ---------------------------------------------------------------


def volume(g: Graph, sets: DataFrame) -> DataFrame:
    return sets.join(g.vertices, "v").groupBy("set_id").agg(F.sum("deg").alias("vol"))


def boundary(g: Graph, sets: DataFrame) -> DataFrame:
    """Edges with exactly one end in the set."""
    out = sets.join(g.arcs, sets["v"] == g.arcs["src"]).select("set_id", "dst")
    gone = out.join(sets.select("set_id", F.col("v").alias("dst")), ["set_id", "dst"], "left_anti")
    n = gone.groupBy("set_id").agg(F.count("*").alias("cut"))
    return sets.select("set_id").distinct().join(n, "set_id", "left").select("set_id", F.coalesce("cut", F.lit(0)).alias("cut"))


def edges_between(g: Graph, s: DataFrame, t: DataFrame) -> DataFrame:
    """Number of edges between two disjoint sets (v)."""
    hit = g.arcs.join(s.select(F.col("v").alias("src")), "src", "left_semi").join(t.select(F.col("v").alias("dst")), "dst", "left_semi")
    return hit.agg(F.count("*").alias("edges"))


def ratio(cut_: Column, side: Column, rest: Column) -> Column:
    """Conductance; null where a side has no volume."""
    return F.when(F.least(side, rest) > 0, cut_ / F.least(side, rest))


def report(g: Graph, sets: DataFrame) -> DataFrame:
    """set_id, cut, vol, vol_rest, phi, balance."""
    both = volume(g, sets).join(boundary(g, sets), "set_id")
    rest = F.lit(g.vol) - F.col("vol")
    return both.select("set_id", "cut", "vol", rest.alias("vol_rest"), ratio(F.col("cut"), F.col("vol"), rest).alias("phi"), (F.least("vol", rest) / F.lit(g.vol)).alias("balance"))


def conductance_in(g: Graph, a: DataFrame, sets: DataFrame) -> DataFrame:
    """Conductance of sets inside the vertex set a, with the degrees of the whole graph."""
    return report(g.restrict(a), sets)


def min_conductance(g: Graph, max_n: int = 16) -> DataFrame:
    """Smallest conductance over all proper subsets of a graph of at most max_n vertices, with its bit mask."""
    n = g.vertices.count()
    if n > max_n:
        raise ValueError(f"{n} vertices; exhaustive search takes at most {max_n}")
    order = {r.v: i for i, r in enumerate(g.vertices.orderBy("v").collect())}
    ids = g.spark.createDataFrame([(v, i) for v, i in order.items()], "v long, i int")
    arcs = g.arcs.join(ids.select(F.col("v").alias("src"), F.col("i").alias("i")), "src").join(ids.select(F.col("v").alias("dst"), F.col("i").alias("j")), "dst")
    masks = g.spark.range(1, 1 << max(0, n - 1)).withColumnRenamed("id", "mask")
    bit = lambda i: F.expr(f"shiftright(mask, {i}) & 1")
    ends = F.broadcast(arcs.select("i", "j"))
    cuts = masks.join(ends, bit("i") != bit("j"), "left").groupBy("mask").agg(F.expr("count(i) div 2").alias("cut"))
    vols = masks.join(F.broadcast(ids.join(g.vertices, "v").select("i", "deg")), bit("i") == 1).groupBy("mask").agg(F.sum("deg").alias("vol"))
    phi = cuts.join(vols, "mask").select("mask", ratio(F.col("cut"), F.col("vol"), F.lit(g.vol) - F.col("vol")).alias("phi"))
    return phi.agg(F.min("phi").alias("phi"), F.min_by("mask", F.struct("phi", "mask")).alias("mask"))


def components(g: Graph) -> DataFrame:
    """(v, comp): smallest vertex reachable.

    Each round hangs every vertex on its smallest neighbour, doubles these pointers until they lead to roots, and
    contracts the arcs; arcs inside a root go, so later rounds are small and rounds are logarithmic.
    """
    arcs = cut(g.arcs.select("src", "dst"), "comp-arcs")
    label = cut(g.vertices.select("v", F.col("v").alias("comp")), "comp")
    while not arcs.isEmpty():
        up = cut(arcs.groupBy(F.col("src").alias("v")).agg(F.least(F.first("src"), F.min("dst")).alias("up")), "hang")
        while True:
            far = up.select("v", "up").join(up.select(F.col("v").alias("up"), F.col("up").alias("up2")), "up")
            far = cut(far.select("v", F.col("up2").alias("up"), (F.col("up2") != F.col("up")).alias("moved")), "hang")
            drop(up)
            up = far
            if far.filter("moved").isEmpty():
                break
        new = label.join(up.select(F.col("v").alias("comp"), "up"), "comp", "left").select("v", F.coalesce("up", "comp").alias("comp"))
        new = cut(new, "comp")
        ends = arcs.join(up.select(F.col("v").alias("src"), F.col("up").alias("s2")), "src").join(up.select(F.col("v").alias("dst"), F.col("up").alias("d2")), "dst")
        rest = cut(ends.filter("s2 <> d2").select(F.col("s2").alias("src"), F.col("d2").alias("dst")).distinct(), "comp-arcs")
        drop(label, arcs, up)
        label, arcs = new, rest
    drop(arcs)
    return label


def numbered(vx: DataFrame, parts: int = 64) -> DataFrame:
    """vx(v, ...) with `at`, the number of v by rising id from 0, from counts of id ranges and numbers inside them."""
    # stored, since ranges are sampled
    cuts = cut(vx.repartitionByRange(parts, "v").withColumn("part", F.spark_partition_id()), "ranges")
    n = cuts.groupBy("part").agg(F.count("*").alias("n"))
    # at most `parts` rows in this window
    base = n.select("part", (F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, 0)) - F.col("n")).alias("base"))
    inside = F.row_number().over(Window.partitionBy("part").orderBy("v")) - 1
    return cuts.join(F.broadcast(base), "part").withColumn("at", F.col("base") + inside).drop("part", "base")


def overlap(g: Graph, c: DataFrame, s: DataFrame) -> DataFrame:
    """Volumes of two vertex sets (v) and of what they share."""
    tag = c.select("v", F.lit(1).alias("c"), F.lit(0).alias("s")).union(s.select("v", F.lit(0), F.lit(1)))
    both = tag.groupBy("v").agg(F.max("c").alias("c"), F.max("s").alias("s")).join(g.vertices, "v")
    pick = lambda x: F.coalesce(F.sum(F.when(x, F.col("deg"))), F.lit(0))
    return both.agg(pick(F.col("c") == 1).alias("vol_c"), pick(F.col("s") == 1).alias("vol_s"), pick((F.col("c") == 1) & (F.col("s") == 1)).alias("vol_both"))
