"""Helpers shared by the text operators: durable intermediate tables, connected components,
column hygiene and vectorised word hashing."""

from __future__ import annotations

import ctypes

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import cut as stored
from ..session import drop

__all__ = ["components", "drop", "free_name", "in_blocks", "mix", "shingle_hashes", "small_batches", "stored", "table", "tidied", "word_hashes"]

#: Spark cuts its batches by rows (10,000 to Python, 4,096 from Parquet), whatever these hold: of texts and sets they are
#: tens of MB, and a task has several copies of them, outside the heap too. These cut by bytes, and by fewer rows.
BATCHES = {"spark.sql.execution.arrow.maxBytesPerBatch": "4m", "spark.sql.parquet.columnarReaderBatchSize": "512"}


def small_batches(spark: SparkSession) -> None:
    """Sets BATCHES for the session, where it has no setting of its own. No result depends on them."""
    for key, value in BATCHES.items():
        if spark.conf.get(key, None) is None:
            spark.conf.set(key, value)


def tidied(f):
    """A batch function that gives freed memory back when its partition ends: workers outlive their stage."""

    def run(batches):
        yield from f(batches)
        pa.default_memory_pool().release_unused()
        if hasattr(libc := ctypes.CDLL(None), "malloc_trim"):
            libc.malloc_trim(0)

    return run


def free_name(df: DataFrame, name: str) -> str:
    """name, or its first numbered form that no column of df has (in any case of letters)."""
    have, n = {c.lower() for c in df.columns}, 0
    while (out := f"{name}_{n}" if n else name).lower() in have:
        n += 1
    return out


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def components(edges: DataFrame) -> DataFrame:
    """(a, b) links -> (v, root): root is the smallest vertex reachable, for every vertex in a link.

    Each round hangs every vertex on its smallest neighbour, doubles these pointers until all lead to a root,
    contracts the links along them and drops those that became loops. A root that hangs nobody has a smaller
    neighbour in the next round, so two rounds at least halve the vertices left and rounds are logarithmic, as are the
    doublings inside one. Only keyed joins and mergeable minima are used, so hubs do not gather in a task.
    """
    links = stored(
        edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).filter("a < b").distinct(), "links"
    )
    labels = None
    while not links.isEmpty():
        both = links.select(F.col("a").alias("v"), F.col("b").alias("o")).union(links.select("b", "a"))
        step = stored(both.groupBy("v").agg(F.least(F.first("v"), F.min("o")).alias("up")), "hang")
        while True:
            far = step.select("v", "up").join(step.select(F.col("v").alias("up"), F.col("up").alias("up2")), "up")
            far = stored(far.select("v", F.col("up2").alias("up"), (F.col("up2") != F.col("up")).alias("moved")), "hang")
            drop(step)
            step = far
            if far.filter("moved").isEmpty():
                break
        if labels is None:
            new = step.select("v", F.col("up").alias("root"))
        else:
            new = labels.join(step.select(F.col("v").alias("root"), "up"), "root", "left").select(
                "v", F.coalesce("up", "root").alias("root")
            )
        new = stored(new, "labels")
        ends = links.join(step.select(F.col("v").alias("a"), F.col("up").alias("a2")), "a")
        ends = ends.join(step.select(F.col("v").alias("b"), F.col("up").alias("b2")), "b")
        ends = ends.select(F.least("a2", "b2").alias("a"), F.greatest("a2", "b2").alias("b")).filter("a < b").distinct()
        rest = stored(ends, "links")
        drop(*[x for x in (labels, links, step) if x is not None])
        labels, links = new, rest
    drop(links)
    return edges.sparkSession.createDataFrame([], "v bigint, root bigint") if labels is None else labels


# ---- words and shingles -------------------------------------------------------------------

_BREAK = np.zeros(256, bool)
_BREAK[[0x20, *range(0x09, 0x0E)]] = True
_RNG = np.random.default_rng(20240607)
_BYTE = _RNG.integers(1, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_BYTE[ord("A") : ord("Z") + 1] = _BYTE[ord("a") : ord("z") + 1]
#: breaks at white space only, and at every ASCII sign that is no letter or digit
SPACES = _BREAK
SIGNS = np.array([b < 128 and not chr(b).isalnum() for b in range(256)])
_BASE = np.uint64(0x9E3779B97F4A7C15)
_GRAM = _RNG.integers(1, 1 << 63, 64, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser of a 64-bit mixing generator (public constants)."""
    x = x.copy()
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def _powers(n: int) -> np.ndarray:
    out = np.full(n, _BASE, np.uint64)
    if n:
        out[0] = 1
    return np.multiply.accumulate(out)


_POWERS = _powers(4096)


def word_hashes(texts: list[str], breaks: np.ndarray = SPACES) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the words (runs without breaks, A-Z lowered) of all texts, and where each text's words begin."""
    global _POWERS
    raw = [t.encode("utf-8", "surrogatepass") for t in texts]
    data = np.frombuffer(b"\n".join([*raw, b""]), np.uint8)
    space = breaks[data]
    begins = ~space
    begins[1:] &= space[:-1]
    starts = np.flatnonzero(begins)
    edges = np.cumsum([0] + [len(r) + 1 for r in raw])
    bounds = np.searchsorted(starts, edges)
    if not len(starts):
        return np.empty(0, np.uint64), bounds
    spans = np.diff(np.append(starts, len(data)))
    data, spans_at = data[starts[0] :], np.repeat(starts, spans)
    place = np.arange(starts[0], starts[0] + len(data)) - spans_at
    place[space[starts[0] :]] = 0
    if (top := int(place.max()) + 1) > len(_POWERS):
        _POWERS = _powers(2 * top)
    sums = np.add.reduceat(np.where(breaks[data], np.uint64(0), _BYTE[data]) * _POWERS[place], starts - starts[0])
    return mix(sums), bounds


def shingle_hashes(words: np.ndarray, k: int) -> np.ndarray:
    """A hash for each run of k words; for fewer words one hash of the whole sequence; none for none."""
    n = len(words)
    if not n:
        return words
    k = min(k, n)
    out = np.full(n - k + 1, np.uint64(k), np.uint64)
    for i in range(k):
        out += words[i : n - k + 1 + i] * _GRAM[i]
    return mix(out)


def in_blocks(ids, texts, limit: int = 1 << 20):
    """Cut a batch into runs of whole texts of about `limit` characters."""
    held_i, held_t, size = [], [], 0
    for i, t in zip(ids, texts, strict=True):
        t = t or ""
        held_i.append(i)
        held_t.append(t)
        size += len(t)
        if size >= limit:
            yield held_i, held_t
            held_i, held_t, size = [], [], 0
    if held_i:
        yield held_i, held_t
