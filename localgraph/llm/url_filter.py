"""URL rules through a Bloom filter cascade.

Listed keys are encoded in level 1; keys of the complete universe that level 1 wrongly accepts go to
level 2; listed keys that level 2 wrongly accepts go to level 3, and so on until nothing is wrong.
Membership of any key of the universe is then exact: the first level that rejects decides. Level 1 is
sized so that its false positives over the universe are about as many as the listed keys, so every
level, and what is broadcast, is bounded by the size of the list (checked: MAX_LISTED keys; bits are packed).

The universe is every key the corpus can ask about: for each url all (host suffix, path prefix) pairs
whose lengths occur in the rules. A url's rule is its longest listed key. Urls without a rule get the
default verdict of the policy, or block when their host or a suffix of it is in the list of blocked hosts, which a
second cascade over all suffixes of the corpus's hosts encodes.

Defined results: a null url or one without `://` has empty host and path; ties between equally long rules
cannot happen for one host and path unless the rules repeat (block wins); empty tables give empty results.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drop, free_name, mix, stored, table, tidied

MAX_LISTED = 1 << 22
MAX_LEVELS = 64

#: fixed values: host, path, verdict
RULES = [
    ("org", "/", "allow"),
    ("example.org", "/es/", "block"),
    ("example.org", "/en/1", "block"),
    ("com", "/fr/", "allow"),
    ("com", "/de/", "block"),
]
#: fixed values: listed hosts; a listed host covers all its subdomains
BLOCKED_HOSTS = [
    "ads-track.example.com",
    "casino-win.example.com",
    "spam-farm.example.com",
]


def _places(h: np.ndarray, level: int, bits: int, k: int) -> np.ndarray:
    a = mix(h + np.uint64(2 * level + 1))
    b = mix(h ^ np.uint64(0xD6E8FEB86659FD93) + np.uint64(level)) | np.uint64(1)
    return (a[:, None] + np.arange(k, dtype=np.uint64)[None, :] * b[:, None]) % np.uint64(bits)


@dataclass
class Level:
    bits: np.ndarray
    k: int
    number: int

    @classmethod
    def build(cls, keys: np.ndarray, rate: float, number: int) -> Level:
        rate = min(0.5, max(rate, 1e-9))
        n = max(64, int(np.ceil(-len(keys) * np.log(rate) / np.log(2) ** 2)))
        out = cls(np.zeros(-(-n // 8), np.uint8), max(1, round(-np.log2(rate))), number)
        at = _places(keys, number, 8 * len(out.bits), out.k).ravel()
        np.bitwise_or.at(out.bits, (at >> np.uint64(3)).astype(np.int64), np.uint8(1) << (at & np.uint64(7)).astype(np.uint8))
        return out

    def has(self, keys: np.ndarray) -> np.ndarray:
        at = _places(keys, self.number, 8 * len(self.bits), self.k)
        return (self.bits[(at >> np.uint64(3)).astype(np.int64)] >> (at & np.uint64(7)).astype(np.uint8) & 1 == 1).all(1)


@dataclass
class Cascade:
    """Levels over 64-bit key hashes; exact for every key of the universe it was built over."""

    levels: list[Level]

    def listed(self, keys: np.ndarray) -> np.ndarray:
        out = np.zeros(len(keys), bool)
        open_ = np.arange(len(keys))
        for n, level in enumerate(self.levels):
            passed = level.has(keys[open_])
            out[open_[~passed]] = n % 2 == 1
            open_ = open_[passed]
        out[open_] = len(self.levels) % 2 == 1
        return out


def build_cascade(listed: DataFrame, universe: DataFrame) -> Cascade | None:
    """The cascade of all listed keys; both inputs have one column `key` (string). None if nothing is listed.

    Listed hashes and the false positives of level 1 (about as many) reach the driver: at most MAX_LISTED keys, checked.
    """
    wanted = listed.select(F.xxhash64("key").alias("h")).distinct()
    many = wanted.count()
    if many > MAX_LISTED:
        raise ValueError(f"{many} listed keys; one cascade takes at most {MAX_LISTED}")
    if not many:
        return None
    hashed = stored(universe.select(F.xxhash64("key").alias("h")).distinct(), "universe")
    keys = wanted.toPandas()["h"].to_numpy(np.int64).astype(np.uint64)
    levels = [Level.build(keys, 0.7 * many / max(1, hashed.count()), 0)]
    first = hashed.sparkSession.sparkContext.broadcast(levels[0])

    def wrong(batches):
        for batch in batches:
            yield batch[first.value.has(batch["h"].to_numpy(np.int64).astype(np.uint64))]

    accepted = hashed.mapInPandas(tidied(wrong), "h bigint").toPandas()["h"].to_numpy(np.int64).astype(np.uint64)
    drop(hashed)
    sides = [keys, np.setdiff1d(accepted, keys)]
    while len(sides[len(levels) % 2]):
        if len(levels) == MAX_LEVELS:
            raise RuntimeError("cascade did not settle")
        n = len(levels)
        levels.append(Level.build(sides[n % 2], 0.5, n))
        sides[1 - n % 2] = sides[1 - n % 2][levels[-1].has(sides[1 - n % 2])]
    return Cascade(levels)


def url_parts(url):
    """(host, path) columns of a url column."""
    after = F.expr(f"substring(`{url}`, instr(`{url}`, '://') + 3)")
    ok = F.coalesce(F.instr(F.col(url), "://") > 0, F.lit(False))
    host = F.translate(F.regexp_extract(after, r"^([^/?#]*)", 1), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    path = F.regexp_extract(after, r"^[^/?#]*([^?#]*)", 1)
    return F.when(ok, host).otherwise(""), F.when(ok, path).otherwise("")


def key_candidates(host, path, labels: list[int], prefixes: list[int]):
    """All keys a url can match: host suffixes of `labels` labels with path prefixes of `prefixes` characters."""
    suffix = F.array(*[F.when(F.size(F.split(host, "\\.")) >= n, F.substring_index(host, ".", -n)) for n in labels])
    prefix = F.array(*[F.when(F.length(path) >= n, F.substring(path, 1, n)) for n in prefixes])
    crossed = F.flatten(F.transform(suffix, lambda s: F.transform(prefix, lambda p: F.concat(s, p))))
    return F.array_distinct(F.filter(crossed, lambda k: k.isNotNull()))


def judge_urls(pages: DataFrame, rules: list[tuple[str, str, str]], blocked_hosts: DataFrame, url: str = "url", default: str = "allow") -> DataFrame:
    """pages (columns host, path, rule, verdict replaced) with the verdict of the longest rule, else of the lists."""
    spark = pages.sparkSession
    pages = pages.drop("host", "path", "rule", "verdict")
    host, path = url_parts(url)
    parts = pages.withColumns({"host": host, "path": path})
    labels = sorted({h.count(".") + 1 for h, _, _ in rules}, reverse=True)
    prefixes = sorted({len(p) for _, p, _ in rules}, reverse=True)
    cand = key_candidates(F.col("host"), F.col("path"), labels, prefixes)
    universe = parts.select(F.explode(cand).alias("key"))
    listed = spark.createDataFrame([(h + p,) for h, p, _ in rules], "key string")
    # a host's own suffixes, from every label on
    ends = F.transform(F.sequence(F.lit(1), F.size(F.split("host", "\\."))), lambda n: F.array_join(F.slice(F.split(F.col("host"), "\\."), -n, n), "."))
    hosts = parts.select(F.explode(ends).alias("key"))
    cascades = spark.sparkContext.broadcast((build_cascade(listed, universe), build_cascade(blocked_hosts.select(F.lower("host").alias("key")).filter("key <> ''"), hosts)))
    verdicts: dict[str, str] = {}
    for h, p, v in rules:
        verdicts[h + p] = "block" if "block" in (v, verdicts.get(h + p)) else v

    def members(cascade: Cascade | None, keys: pd.Series) -> pd.Series:
        """Exploded key hashes (index: row) that are listed."""
        flat = keys.explode()
        flat = flat[flat.notna()]
        h = flat.to_numpy(np.int64).astype(np.uint64)
        return pd.Series(cascade.listed(h) if cascade is not None and len(h) else np.zeros(len(h), bool), index=flat.index)

    names_out = parts.columns
    keys, key_hashes, host_hashes = (free_name(parts, x) for x in ("keys", "key_hashes", "host_hashes"))

    def decide(batches):
        for batch in batches:
            by_rule, by_host = cascades.value
            inside = members(by_rule, batch[key_hashes])
            names = batch[keys].explode().dropna()[inside.to_numpy()]
            best: dict[int, str] = {}
            for i, name in names.items():
                if len(name) > len(best.get(i, "")):
                    best[i] = name
            rule = pd.Series([best.get(i) for i in batch.index], index=batch.index, dtype=object)
            blocked = members(by_host, batch[host_hashes]).groupby(level=0).any().reindex(batch.index, fill_value=False)
            batch["rule"] = rule
            batch["verdict"] = [verdicts[r] if r is not None else "block" if b else default for r, b in zip(rule, blocked, strict=True)]
            yield batch[names_out].assign(rule=batch["rule"], verdict=batch["verdict"])

    work = parts.withColumn(keys, cand).withColumns({key_hashes: F.transform(keys, lambda k: F.xxhash64(k)), host_hashes: F.transform(ends, lambda k: F.xxhash64(k))})
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in parts.schema.fields)
    return work.mapInPandas(tidied(decide), f"{fields}, rule string, verdict string")


def op9_url_filter(spark, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages").select("page_id", "url")
    blocked = spark.createDataFrame([(h,) for h in BLOCKED_HOSTS], "host string")
    return judge_urls(pages, RULES, blocked).select("page_id", "host", "path", "rule", "verdict")


OP9_SQL = r"""
WITH u AS (SELECT page_id, url, coalesce(instr(url, '://'), 0) AS i FROM pages),
r AS (SELECT page_id, CASE WHEN i > 0 THEN substring(url, i + 3) ELSE '' END AS rest FROM u),
p AS (
  SELECT page_id, translate(regexp_extract(rest, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
    regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM r),
rules(h, q, v) AS (VALUES ('org', '/', 'allow'), ('example.org', '/es/', 'block'), ('example.org', '/en/1', 'block'),
  ('com', '/fr/', 'allow'), ('com', '/de/', 'block')),
m AS (
  SELECT page_id, arg_max(h || q, length(h || q)) AS rule, arg_max(v, length(h || q)) AS v FROM p JOIN rules
  ON (host = h OR ends_with(host, '.' || h)) AND starts_with(path, q) GROUP BY page_id)
SELECT p.page_id, host, path, m.rule,
  coalesce(m.v, CASE WHEN EXISTS (SELECT 1 FROM (VALUES ('ads-track.example.com'), ('casino-win.example.com'), ('spam-farm.example.com')) b(h)
    WHERE host = h OR ends_with(host, '.' || h)) THEN 'block' ELSE 'allow' END) AS verdict
FROM p LEFT JOIN m ON p.page_id = m.page_id
"""
