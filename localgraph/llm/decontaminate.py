"""Benchmark decontamination by greedy string tiling.

Words are runs of letters and digits, A-Z lowered. Rolling hashes of MIN_TILE words of each document are
joined with those of the benchmark items (seeds). For every document and item that share a seed, passes of rolling
hashes over the unmarked words of both find the longest common window, make it a tile and mark its words, down
to MIN_TILE words. The covered share of the item's words decides, so a passage is found whatever the order of its parts.

Benchmark items are the stated query set: they are sent to all tasks in blocks of about BLOCK_CHARS
characters, one map-only pass over the documents per block, and nothing is shuffled. With several blocks the rows
are written between passes, so that one block's index is alive at a time. Items of fewer than MIN_TILE
words are found only as a whole. Defined results: null or empty documents and items have no words and match
nothing (coverage 0, item null); equal coverages -> the smallest item id; repeated rows are answered each;
extra columns pass through and clashing ones are replaced.
"""

from __future__ import annotations

from collections import defaultdict

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SIGNS, drop, in_blocks, shingle_hashes, stored, table, tidied, word_hashes

MIN_TILE = 5
MIN_COVERAGE = 0.5
BLOCK_CHARS = 4_000_000
COLUMNS = {"coverage": "double", "item_id": "bigint", "n_items": "bigint", "contaminated": "boolean"}


_ODD = np.uint64(0x9E3779B97F4A7C15)
_INVERSE = np.uint64(pow(int(_ODD), -1, 1 << 64))


class Rolling:
    """Hashes of all windows of a word sequence, of any length, from running sums; windows with marked words are left out."""

    def __init__(self, words: np.ndarray):
        n = len(words)
        power, back = np.full(n, _ODD, np.uint64), np.full(n, _INVERSE, np.uint64)
        if n:
            power[0] = back[0] = 1
        self.words, self.back = words, np.multiply.accumulate(back)
        self.sums = np.append(np.uint64(0), np.cumsum(words * np.multiply.accumulate(power)))
        self.marks = np.zeros(n, bool)

    def windows(self, size: int) -> tuple[np.ndarray, np.ndarray]:
        """(starts, hashes) of the unmarked windows."""
        if size > len(self.words):
            return np.empty(0, np.int64), np.empty(0, np.uint64)
        busy = np.append(0, np.cumsum(self.marks))
        at = np.flatnonzero(busy[size:] == busy[:-size])
        return at, (self.sums[at + size] - self.sums[at]) * self.back[at]

    def free(self, at: int, size: int) -> bool:
        # marked stretches are at least as long as the window, so one of its ends lies in any that it meets
        return not (self.marks[at] or self.marks[at + size - 1])


def tile(item: np.ndarray, text: np.ndarray, least: int) -> list[tuple[int, int, int]]:
    """Greedy tiles (item at, text at, length) of two word sequences, longest first, ties by place in item, then text.

    Each pass finds the greatest length at which unmarked windows of both have a hash in common (whatever has a common
    window of some length has one of every smaller length), and marks the matches of that length. Memory follows the
    two lengths, however often words repeat.
    """
    one, two, tiles = Rolling(item), Rolling(text), []
    most = min(len(item), len(text))
    while most >= least:
        low, high = least - 1, most
        while low < high:
            size = (low + high + 1) // 2
            if np.isin(one.windows(size)[1], two.windows(size)[1]).any():
                low = size
            else:
                high = size - 1
        if low < least:
            break
        at1, h1 = one.windows(low)
        at2, h2 = two.windows(low)
        keep = np.isin(h2, h1)
        at2, h2 = at2[keep], h2[keep]
        order = np.argsort(h2, kind="stable")
        at2, h2 = at2[order], h2[order]
        begin, end = np.searchsorted(h2, h1), np.searchsorted(h2, h1, "right")
        seen: dict[int, int] = {}
        for k in np.flatnonzero(begin < end).tolist():
            i, j = int(at1[k]), seen.get(int(h1[k]), int(begin[k]))
            if not one.free(i, low):
                continue
            while j < end[k] and not (two.free(int(at2[j]), low) and np.array_equal(item[i : i + low], text[at2[j] : at2[j] + low])):
                j += 1
            seen[int(h1[k])] = j
            if j < end[k]:
                tiles.append((i, int(at2[j]), low))
                one.marks[i : i + low] = True
                two.marks[at2[j] : at2[j] + low] = True
        # every item window of this length that could be placed has been
        most = low - 1
    return tiles


class Index:
    """Words of a block of items, and their seeds: hash of a run of words -> items."""

    def __init__(self, items: list[tuple[int, str]], least: int = MIN_TILE):
        words, at = word_hashes([t or "" for _, t in items], SIGNS)
        self.ids = [i for i, _ in items]
        self.sizes = np.diff(at).tolist()
        self.least = least
        self.words = [words[a:b] for a, b in zip(at, at[1:])]
        self.by_size: dict[int, dict[int, set[int]]] = defaultdict(lambda: defaultdict(set))
        for n, size in enumerate(self.sizes):
            k = min(least, size)
            for h in shingle_hashes(words[at[n] : at[n + 1]], k).tolist() if k else []:
                self.by_size[k][h].add(n)
        self.by_size = {k: dict(v) for k, v in self.by_size.items()}
        self.maybe = {}
        for k, seeds in self.by_size.items():
            self.maybe[k] = np.zeros(1 << 22, bool)
            self.maybe[k][np.array(list(seeds), np.uint64) >> np.uint64(42)] = True

    def coverages(self, texts: list[str]) -> list[dict[int, float]]:
        """Per text: item position -> covered share of its words, for items that share a seed."""
        out: list[dict[int, float]] = [{} for _ in texts]
        words, at = word_hashes(texts, SIGNS)
        for k, seeds in self.by_size.items():
            if len(words) < k:
                continue
            grams = shingle_hashes(words, k)
            hits = np.flatnonzero(self.maybe[k][grams >> np.uint64(42)])
            owner = np.searchsorted(at, hits, "right") - 1
            inside = hits + k <= at[owner + 1]
            pairs = {(d, n) for d, h in set(zip(owner[inside].tolist(), grams[hits[inside]].tolist(), strict=True)) for n in seeds.get(h, ())}
            for d, n in sorted(pairs):
                covered = sum(t[2] for t in tile(self.words[n], words[at[d] : at[d + 1]], min(self.least, self.sizes[n])))
                out[d][n] = covered / self.sizes[n]
        return out


def decontaminate(
    docs: DataFrame, benchmark: DataFrame, text: str = "text", item: str = "item_id", item_text: str = "text",
    min_tile: int = MIN_TILE, min_coverage: float = MIN_COVERAGE, block_chars: int = BLOCK_CHARS,
) -> DataFrame:
    """docs with the best coverage, its item, the number of items at or above min_coverage, and the verdict."""
    spark = docs.sparkSession
    items = benchmark.select(F.col(item).cast("long").alias("i"), F.col(item_text).alias("t")).filter("i is not null and t is not null")
    chars = items.agg(F.coalesce(F.sum(F.length("t")), F.lit(0))).first()[0]
    blocks = max(1, -(-chars // block_chars))
    out = docs.drop(*COLUMNS)
    out = out.withColumns({c: F.lit(x).cast(k) for (c, k), x in zip(COLUMNS.items(), (0.0, None, 0, False), strict=True)})
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in out.schema.fields)
    last = None
    for block in range(blocks):
        mine = items.filter(F.pmod(F.xxhash64("i", "t"), F.lit(blocks)) == block).collect()
        index = spark.sparkContext.broadcast(Index(sorted((r.i, r.t) for r in mine), min_tile))

        def run(batches, index=index):
            ix = index.value
            for batch in batches:
                best, ids, many = batch["coverage"].tolist(), [None if x != x else x for x in batch["item_id"].astype(object)], batch["n_items"].tolist()
                row = 0
                for _, texts in in_blocks(batch[text], batch[text]):
                    for found in ix.coverages(texts):
                        for n, share in found.items():
                            if share > best[row] or share == best[row] and share > 0 and ix.ids[n] < ids[row]:
                                best[row], ids[row] = share, ix.ids[n]
                            many[row] += share >= min_coverage
                        row += 1
                batch["coverage"], batch["n_items"] = best, many
                batch["item_id"] = [None if i is None else int(i) for i in ids]
                batch["item_id"] = batch["item_id"].astype("Int64")
                batch["contaminated"] = [n > 0 for n in many]
                yield batch

        out = out.mapInPandas(tidied(run), fields)
        if block + 1 < blocks:
            before, out = last, stored(out, "tiled")
            last = out
            index.unpersist()
            if before is not None:
                drop(before)
    return out


def op1_decontamination(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    found = decontaminate(docs, table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", "contaminated", "item_id", "coverage", "n_items")
