"""Cross-site line deduplication by the number of distinct sites a line appears on (DataFrame functions only).

Lines are keyed by two 64-bit hashes of their trimmed text. A first mergeable aggregate keeps the keys seen
on at least two sites; for these one HyperLogLog sketch of sites per key is merged by aggregation. An
estimate clearly above the threshold decides at once; an estimate inside the band around it (NEAR standard
errors) is settled by an exact distinct count. Lines on `min_sites` sites or more are boilerplate and are
removed from every document. Every shuffle carries hashes and sites, not texts, except the last join, which
gives the affected documents their removed positions.

Defined results: null text has no lines and stays null; blank lines are never boilerplate; a null site is a
site of its own; repeats of a line inside one site count once; a document with nothing but boilerplate is a copy of
a document, not a page with boilerplate, and stays whole (near-duplicate removal decides about it). Repeated and null doc_ids are separate rows: rows are told apart by all their columns' hash, and equal
rows get equal results. Extra columns pass through `dedup_lines`.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import free_name, stored, table

MIN_SITES = 8
LG_K = 10
NEAR = 4.0


def exploded(docs: DataFrame, text: str, site: str, keep: list[str]) -> DataFrame:
    """One row per non-blank line: kept columns, at, site, h1, h2."""
    lines = docs.select(*keep, F.coalesce(F.concat(F.lit("s"), F.col(site).cast("string")), F.lit("n")).alias("site"), F.posexplode(F.split(F.col(text), "\n", -1)).alias("at", "line"))
    trimmed = F.trim(F.col("line"))
    return lines.filter(F.length(trimmed) > 0).select(*keep, "at", "site", F.xxhash64(trimmed).alias("h1"), F.xxhash64(F.lit(1), trimmed).alias("h2"))


def boilerplate(docs: DataFrame, text: str = "text", site: str = "source", min_sites: int = MIN_SITES, lg_k: int = LG_K) -> DataFrame:
    """(h1, h2, sites) of lines on at least min_sites distinct sites; `sites` exact near the threshold."""
    per_site = exploded(docs, text, site, [])
    two = per_site.groupBy("h1", "h2").agg(F.min("site").alias("lo"), F.max("site").alias("hi"), F.count("*").alias("n"))
    two = stored(two.filter((F.col("lo") < F.col("hi")) & (F.col("n") >= min_sites)).select("h1", "h2"), "repeated-lines")
    again = per_site.join(two, ["h1", "h2"], "left_semi")
    sketches = again.groupBy("h1", "h2").agg(F.hll_sketch_estimate(F.hll_sketch_agg("site", lg_k)).alias("sites"))
    error = NEAR * 1.04 / math.sqrt(1 << lg_k)
    sketches = stored(sketches.filter(F.col("sites") >= math.floor(min_sites * (1 - error))), "sketched-lines")
    sure = F.col("sites") > math.ceil(min_sites * (1 + error))
    near = per_site.join(sketches.filter(~sure).select("h1", "h2"), ["h1", "h2"], "left_semi")
    exact = near.groupBy("h1", "h2", "site").agg(F.lit(1).alias("one")).groupBy("h1", "h2").agg(F.count("*").alias("sites"))
    return sketches.filter(sure).select("h1", "h2", "sites").unionByName(exact.filter(F.col("sites") >= min_sites))


def dedup_lines(docs: DataFrame, text: str = "text", site: str = "source", min_sites: int = MIN_SITES) -> DataFrame:
    """docs with boilerplate lines cut from `text`, and n_lines, n_removed appended."""
    docs = docs.drop("n_lines", "n_removed")
    bad = stored(boilerplate(docs, text, site, min_sites).select("h1", "h2"), "boilerplate")
    cols = [F.coalesce(F.col(c).cast("string"), F.lit("\0")) for c, kind in docs.dtypes if not kind.startswith(("map", "array", "struct"))]
    row1, row2, gone = (free_name(docs, x) for x in ("row1", "row2", "gone"))
    keys = {row1: F.xxhash64(*cols), row2: F.xxhash64(F.lit(1), *cols)}
    plain = docs.select(F.col(text).alias("t"), F.col(site).alias("s"), *[c.alias(x) for x, c in keys.items()])
    hit = exploded(plain, "t", "s", [row1, row2]).join(bad, ["h1", "h2"], "left_semi")
    hit = hit.groupBy(row1, row2).agg(F.collect_set("at").alias(gone))
    joined = docs.withColumns(keys).join(hit, [row1, row2], "left").drop(row1, row2)
    lines = F.split(F.col(text), "\n", -1)
    kept = F.array_join(F.filter(lines, lambda _, i: ~F.array_contains(gone, i)), "\n")
    joined = joined.withColumn(gone, F.when(F.length(F.trim(F.translate(kept, "\n", ""))) > 0, F.col(gone)))
    return joined.select(
        *[F.when(F.col(gone).isNull(), F.col(c)).otherwise(kept).alias(c) if c == text else F.col(c) for c in docs.columns],
        F.when(F.col(text).isNull(), 0).otherwise(F.size(lines)).cast("long").alias("n_lines"),
        F.coalesce(F.size(gone), F.lit(0)).cast("long").alias("n_removed"),
    )


def op6_line_dedup(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "source")
    return dedup_lines(docs).select("doc_id", "n_lines", "n_removed", "text")


OP6_SQL = r"""
WITH l AS (
  SELECT doc_id, source, unnest(string_split(text, chr(10))) AS line,
    generate_subscripts(string_split(text, chr(10)), 1) AS pos FROM documents),
bad AS (
  SELECT trim(line, ' ') AS t FROM l WHERE length(trim(line, ' ')) > 0
  GROUP BY 1 HAVING count(DISTINCT coalesce('s' || source, 'n')) >= 8),
k AS (SELECT l.*, bad.t IS NOT NULL AS hit,
  bool_or(bad.t IS NULL AND length(trim(line, ' ')) > 0) OVER (PARTITION BY doc_id) AS more
  FROM l LEFT JOIN bad ON trim(line, ' ') = bad.t)
SELECT doc_id, count(*) AS n_lines, CAST(count(*) FILTER (WHERE hit AND more) AS BIGINT) AS n_removed,
  coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT (hit AND more)), '') AS text
FROM k GROUP BY doc_id
UNION ALL SELECT doc_id, 0, 0, text FROM documents WHERE text IS NULL
"""
