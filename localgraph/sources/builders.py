"""Graphs over the relational tables. A vertex id is key * KINDS + kind; text keys take 52 bits of their md5."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..graph import Graph

KINDS = 16
#: fixed values: kind code of each table's vertices
CODE = {"region": 0, "nation": 1, "customer": 2, "supplier": 3, "order": 4, "part": 5, "page": 6, "link": 7, "document": 8, "line": 9, "user": 10, "hour": 11, "turn": 12, "vector": 13, "host": 14}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def vid(key, kind: str) -> Column:
    return (F.col(key) if isinstance(key, str) else key).cast("long") * KINDS + CODE[kind]


def text_id(c: Column, kind: str) -> Column:
    return vid(F.conv(F.substr(F.md5(c), F.lit(1), F.lit(13)), 16, 10), kind)


def pairs(df: DataFrame, a: Column, b: Column) -> DataFrame:
    return df.select(a.alias("a"), b.alias("b"))


def fk_forest(spark, d) -> Graph:
    """Region - nation - customer/supplier - order trees."""
    e = pairs(load(spark, d, "nation"), vid("n_nationkey", "nation"), vid("n_regionkey", "region"))
    e = e.union(pairs(load(spark, d, "customer"), vid("c_custkey", "customer"), vid("c_nationkey", "nation")))
    e = e.union(pairs(load(spark, d, "supplier"), vid("s_suppkey", "supplier"), vid("s_nationkey", "nation")))
    return Graph.from_edges(e.union(pairs(load(spark, d, "orders"), vid("o_orderkey", "order"), vid("o_custkey", "customer"))))


def nation_forest(spark, d) -> Graph:
    e = pairs(load(spark, d, "customer"), vid("c_custkey", "customer"), vid("c_nationkey", "nation"))
    return Graph.from_edges(e.union(pairs(load(spark, d, "orders"), vid("o_orderkey", "order"), vid("o_custkey", "customer"))))


def _lines(spark, d) -> DataFrame:
    return load(spark, d, "orders").join(load(spark, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"))


def customer_part(spark, d) -> Graph:
    return Graph.from_edges(pairs(_lines(spark, d), vid("o_custkey", "customer"), vid("l_partkey", "part")))


def customer_supplier(spark, d) -> Graph:
    return Graph.from_edges(pairs(_lines(spark, d), vid("o_custkey", "customer"), vid("l_suppkey", "supplier")))


def part_supplier(spark, d) -> Graph:
    return Graph.from_edges(pairs(load(spark, d, "lineitem"), vid("l_partkey", "part"), vid("l_suppkey", "supplier")))


def order_part(spark, d) -> Graph:
    return Graph.from_edges(pairs(load(spark, d, "lineitem"), vid("l_orderkey", "order"), vid("l_partkey", "part")))


def page_link(spark, d) -> Graph:
    links = load(spark, d, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("l"))
    return Graph.from_edges(pairs(links, vid("page_id", "page"), text_id(F.col("l"), "link")))


def page_host(spark, d) -> Graph:
    hosts = load(spark, d, "pages").select("page_id", F.regexp_extract("url", "://([^/?#]*)", 1).alias("h"))
    return Graph.from_edges(pairs(hosts, vid("page_id", "page"), text_id(F.col("h"), "host")))


def document_line(spark, d) -> Graph:
    lines = load(spark, d, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("l")).filter(F.length(F.trim("l")) > 0)
    return Graph.from_edges(pairs(lines, vid("doc_id", "document"), text_id(F.col("l"), "line")))


def user_hour(spark, d) -> Graph:
    ev = load(spark, d, "events")
    return Graph.from_edges(pairs(ev, vid("user_id", "user"), vid(F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 3_600_000_000), "hour")))


def conversation_path(spark, d) -> Graph:
    """Turn - next turn inside a conversation."""
    c = load(spark, d, "conversations").select("conv_id", "turn").distinct()
    # as many ids to a conversation as the longest needs, so that no two turns share one
    key = F.col("conv_id") * F.lit((c.agg(F.max("turn")).first()[0] or 0) + 1) + F.col("turn")
    return Graph.from_edges(pairs(c.filter("turn > 0"), vid(key, "turn"), vid(key - 1, "turn")))


def nation_trade(spark, d) -> Graph:
    li = _lines(spark, d).join(load(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(load(spark, d, "supplier"), F.col("l_suppkey") == F.col("s_suppkey"))
    return Graph.from_edges(pairs(li, vid("c_nationkey", "nation"), vid("s_nationkey", "nation")))


def part_coorder(spark, d, max_group: int | None = None, block: int = 1000) -> Graph:
    """Parts that share an order; with max_group, orders of more distinct parts are left out (option).

    The parts of an order are dealt over buckets of about `block` parts, and each pair of buckets is a join key of its
    own, so that a large order's pairs spread over tasks; an order of at most `block` parts has a single key.
    """
    li = load(spark, d, "lineitem").select("l_orderkey", "l_partkey").distinct()
    sizes = li.groupBy("l_orderkey").agg(F.count("*").alias("n"))
    if max_group is not None:
        sizes = sizes.filter(F.col("n") <= max_group)
    li = li.join(sizes, "l_orderkey").withColumn("k", F.ceil(F.col("n") / block))
    li = li.withColumn("h", F.pmod(F.xxhash64("l_partkey"), "k")).withColumn("x", F.explode(F.sequence(F.lit(0).cast("long"), F.col("k") - 1)))
    one = li.select("l_orderkey", F.least("h", "x").alias("i"), F.greatest("h", "x").alias("j"), "l_partkey", "h")
    other = one.select("l_orderkey", "i", "j", F.col("l_partkey").alias("p2"), F.col("h").alias("h2"))
    two = one.join(other, ["l_orderkey", "i", "j"]).filter("l_partkey < p2 and (i = j or h <> h2)")
    return Graph.from_edges(pairs(two, vid("l_partkey", "part"), vid("p2", "part")))


KNN_BLOCK = 2048


def knn(spark, d, k: int = 10) -> Graph:
    """Each vector with its k largest integer dot products (ties: smaller id), made symmetric.

    Exact and by blocks: vectors are dealt over blocks of about KNN_BLOCK, each pair of blocks is one product of
    integer matrices in a task, which returns the k best of every row only; the best of these are kept.
    """
    e = load(spark, d, "embeddings").select("vec_id", F.transform("embedding", lambda x: F.round(x.cast("double") * 10000).cast("long")).alias("e"))
    blocks = max(1, -(-e.count() // KNN_BLOCK))
    e = e.withColumn("h", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int"))
    every = F.sequence(F.lit(0), F.lit(blocks - 1))
    left = e.select("*", F.lit(True).alias("asks"), F.explode(every).alias("other")).select("vec_id", "e", "asks", F.col("h").alias("i"), F.col("other").alias("j"))
    right = e.select("*", F.lit(False).alias("asks"), F.explode(every).alias("other")).select("vec_id", "e", "asks", F.col("other").alias("i"), F.col("h").alias("j"))

    def best(rows: pd.DataFrame) -> pd.DataFrame:
        one, two = rows[rows["asks"]], rows[~rows["asks"]].sort_values("vec_id")
        got = {"vec_id": [], "o": [], "s": []}
        if len(one) and len(two):
            ids = two["vec_id"].to_numpy()
            dots = np.stack(one["e"].to_numpy()) @ np.stack(two["e"].to_numpy()).T
            for v, row in zip(one["vec_id"], dots, strict=True):
                top = [i for i in np.argsort(-row, kind="stable")[: k + 1] if ids[i] != v][:k]
                got["vec_id"] += [v] * len(top)
                got["o"] += ids[top].tolist()
                got["s"] += row[top].tolist()
        return pd.DataFrame(got, columns=["vec_id", "o", "s"]).astype("int64")

    near = left.unionByName(right).groupBy("i", "j").applyInPandas(best, "vec_id long, o long, s long")
    rank = F.row_number().over(Window.partitionBy("vec_id").orderBy(F.desc("s"), "o"))
    near = near.withColumn("r", rank).filter(F.col("r") <= k)
    return Graph.from_edges(pairs(near, vid("vec_id", "vector"), vid("o", "vector")))


_K = KINDS


def _sql(kind: str, key: str) -> str:
    return f"(CAST({key} AS BIGINT) * {_K} + {CODE[kind]})"


def _text_sql(kind: str, key: str) -> str:
    return f"(CAST(('0x' || substr(md5({key}), 1, 13)) AS BIGINT) * {_K} + {CODE[kind]})"


_LI = "lineitem JOIN orders ON o_orderkey = l_orderkey"
#: the same edges in SQL: a SELECT with columns a, b for each builder
EDGES_SQL = {
    "nation_forest": f"SELECT {_sql('customer', 'c_custkey')} a, {_sql('nation', 'c_nationkey')} b FROM customer UNION ALL SELECT {_sql('order', 'o_orderkey')}, {_sql('customer', 'o_custkey')} FROM orders",
    "customer_part": f"SELECT {_sql('customer', 'o_custkey')} a, {_sql('part', 'l_partkey')} b FROM {_LI}",
    "customer_supplier": f"SELECT {_sql('customer', 'o_custkey')} a, {_sql('supplier', 'l_suppkey')} b FROM {_LI}",
    "part_supplier": f"SELECT {_sql('part', 'l_partkey')} a, {_sql('supplier', 'l_suppkey')} b FROM lineitem",
    "order_part": f"SELECT {_sql('order', 'l_orderkey')} a, {_sql('part', 'l_partkey')} b FROM lineitem",
    "page_link": f"SELECT {_sql('page', 'page_id')} a, {_text_sql('link', 'l')} b FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) l FROM pages)",
    "page_host": f"SELECT {_sql('page', 'page_id')} a, {_text_sql('host', 'h')} b FROM (SELECT page_id, regexp_extract(url, '://([^/?#]*)', 1) h FROM pages)",
    "document_line": f"SELECT {_sql('document', 'doc_id')} a, {_text_sql('line', 'l')} b FROM (SELECT doc_id, unnest(string_split(text, chr(10))) l FROM documents) WHERE length(trim(l, ' ')) > 0",
    "user_hour": f"SELECT {_sql('user', 'user_id')} a, {_sql('hour', 'epoch_us(ts) // 3600000000')} b FROM events",
    "conversation_path": f"SELECT {_sql('turn', 'conv_id * wide + turn')} a, {_sql('turn', 'conv_id * wide + turn - 1')} b FROM conversations, (SELECT max(turn) + 1 AS wide FROM conversations) WHERE turn > 0",
    "nation_trade": f"SELECT {_sql('nation', 'c_nationkey')} a, {_sql('nation', 's_nationkey')} b FROM {_LI} JOIN customer ON c_custkey = o_custkey JOIN supplier ON s_suppkey = l_suppkey",
    "part_coorder": f"SELECT {_sql('part', 'x.l_partkey')} a, {_sql('part', 'y.l_partkey')} b FROM lineitem x JOIN lineitem y ON x.l_orderkey = y.l_orderkey AND x.l_partkey < y.l_partkey",
    "knn": f"""SELECT {_sql('vector', 'i')} a, {_sql('vector', 'o')} b FROM (
      SELECT x.vec_id i, y.vec_id o, row_number() OVER (PARTITION BY x.vec_id ORDER BY list_dot_product(x.e, y.e) DESC, y.vec_id) r
      FROM (SELECT vec_id, list_transform(embedding, lambda x: round(CAST(x AS DOUBLE) * 10000)) e FROM embeddings) x
      JOIN (SELECT vec_id, list_transform(embedding, lambda x: round(CAST(x AS DOUBLE) * 10000)) e FROM embeddings) y ON x.vec_id <> y.vec_id) WHERE r <= 10""",
}
EDGES_SQL["fk_forest"] = f"SELECT {_sql('nation', 'n_nationkey')} a, {_sql('region', 'n_regionkey')} b FROM nation UNION ALL SELECT {_sql('supplier', 's_suppkey')}, {_sql('nation', 's_nationkey')} FROM supplier UNION ALL " + EDGES_SQL["nation_forest"]
BUILDERS = {f.__name__: f for f in (fk_forest, nation_forest, customer_part, customer_supplier, part_supplier, order_part, page_link, page_host, document_line, user_hour, conversation_path, nation_trade, part_coorder, knn)}
