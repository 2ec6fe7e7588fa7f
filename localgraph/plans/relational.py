"""The relational, streaming and function surface: one query each, with SQL."""

from __future__ import annotations

import uuid

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.surface import GeometricScales, SubsetMasks, conductance, member_rows, register, slope_at
from ..operators import sweep, walk
from ..operators.walk import Run
from ..session import shared_dir
from ..sources.builders import KINDS, load, page_link
from ..streaming import activity
from .methods import ELL, MEASURE_SQL, R_SQL, TREES_SQL, cust, g_sql, graph, nation_sets, rec, trees, w_sql

QUERIES: dict = {}
SQL: dict[str, str] = {}


def q(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return keep


def place(spark) -> str:
    return f"{shared_dir(spark)}/io-{uuid.uuid4().hex}"


ORD = "SELECT o_orderkey, o_custkey, o_orderstatus FROM orders"


@q(ORD)
def io_parquet_roundtrip(s, d):
    p = place(s)
    load(s, d, "orders").select("o_orderkey", "o_custkey", "o_orderstatus").write.partitionBy("o_orderstatus").parquet(p)
    return s.read.schema("o_orderkey long, o_custkey long, o_orderstatus string").parquet(p)


_EDGES = f"WITH {g_sql('page_link')} SELECT src, dst FROM arcs WHERE src < dst"


@q(_EDGES)
def io_csv_edges(s, d):
    p = place(s)
    page_link(s, d).arcs.filter("src < dst").write.option("header", True).csv(p)
    return s.read.option("header", True).schema("src long, dst long").csv(p)


@q(_EDGES)
def io_json_edges(s, d):
    p = place(s)
    page_link(s, d).arcs.filter("src < dst").write.json(p)
    return s.read.schema("src long, dst long").json(p)


@q(f"WITH {g_sql('fk_forest')} SELECT v, deg, CAST((SELECT sum(dst) FROM arcs WHERE src = v) AS BIGINT) AS nbr_sum FROM vx")
def io_bucketed_adjacency(s, d):
    p = place(s)
    graph(s, d, "fk_forest").save(p, 8)
    # a hub's neighbours lie in several rows
    row = F.aggregate("nbrs", F.lit(0).cast("long"), lambda a, x: a + x)
    return s.read.parquet(p).groupBy("v", "deg").agg(F.sum(row).alias("nbr_sum"))


@q("SELECT c_custkey AS id, upper(c_mktsegment) AS seg, c_nationkey * 2 AS n2 FROM customer")
def op_project(s, d):
    return load(s, d, "customer").select(F.col("c_custkey").alias("id"), F.upper("c_mktsegment").alias("seg"), (F.col("c_nationkey") * 2).alias("n2"))


@q("SELECT c_custkey FROM customer WHERE c_nationkey BETWEEN 3 AND 9 AND c_mktsegment IN ('BUILDING', 'MACHINERY')")
def op_filter(s, d):
    return load(s, d, "customer").filter(F.col("c_nationkey").between(3, 9) & F.col("c_mktsegment").isin("BUILDING", "MACHINERY")).select("c_custkey")


@q("SELECT c_custkey, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal < 5000 THEN 'mid' ELSE 'high' END AS class FROM customer")
def op_case(s, d):
    b = F.col("c_acctbal")
    return load(s, d, "customer").select("c_custkey", F.when(b < 0, "debt").when(b < 5000, "mid").otherwise("high").alias("class"))


@q("SELECT o_orderkey, coalesce(nullif(o_orderstatus, 'F'), 'none') AS st, o_orderstatus IS NOT DISTINCT FROM 'F' AS is_f FROM orders")
def op_null_safe(s, d):
    st = F.nullif(F.col("o_orderstatus"), F.lit("F"))
    return load(s, d, "orders").select("o_orderkey", F.coalesce(st, F.lit("none")).alias("st"), F.col("o_orderstatus").eqNullSafe("F").alias("is_f"))


@q("SELECT page_id, len(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS links, url LIKE 'https%' AS safe FROM pages")
def op_regex_links(s, d):
    return load(s, d, "pages").select("page_id", F.size(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).cast("long").alias("links"), F.col("url").like("https%").alias("safe"))


_J = "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1"


def _join(s, d, hint=None, broadcast=False):
    c = load(s, d, "customer").select(F.col("c_custkey").alias("o_custkey"), "c_mktsegment")
    c = F.broadcast(c) if broadcast else c.hint(hint) if hint else c
    return load(s, d, "orders").join(c, "o_custkey").groupBy("c_mktsegment").agg(F.count("*").alias("n"))


@q(_J)
def op_join_inner(s, d):
    return _join(s, d)


@q(_J.replace("customer ", "customer ").replace("c_mktsegment, ", "n_name, ").replace("GROUP BY", "JOIN nation ON n_nationkey = c_nationkey GROUP BY"))
def op_join_broadcast(s, d):
    """nation has a fixed size, so it may be broadcast."""
    n = F.broadcast(load(s, d, "nation").select(F.col("n_nationkey").alias("c_nationkey"), "n_name"))
    o = load(s, d, "orders").join(load(s, d, "customer").select(F.col("c_custkey").alias("o_custkey"), "c_nationkey"), "o_custkey")
    return o.join(n, "c_nationkey").groupBy("n_name").agg(F.count("*").alias("n"))


@q(_J)
def op_join_merge_hint(s, d):
    return _join(s, d, "merge")


@q(_J)
def op_join_shuffle_hash(s, d):
    return _join(s, d, "shuffle_hash")


@q("SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY 1")
def op_join_left(s, d):
    o = load(s, d, "orders").select(F.col("o_custkey").alias("c_custkey"), "o_orderkey")
    return load(s, d, "customer").join(o, "c_custkey", "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


@q("WITH a AS (SELECT c_custkey AS k FROM customer WHERE c_nationkey < 10), b AS (SELECT DISTINCT o_custkey AS k FROM orders WHERE o_orderkey % 5 = 0) SELECT coalesce(a.k, b.k) AS k, a.k IS NOT NULL AS in_a, b.k IS NOT NULL AS in_b FROM a FULL JOIN b ON a.k = b.k")
def op_join_full(s, d):
    a = load(s, d, "customer").filter("c_nationkey < 10").select(F.col("c_custkey").alias("k"), F.lit(True).alias("a"))
    b = load(s, d, "orders").filter("o_orderkey % 5 = 0").select(F.col("o_custkey").alias("k"), F.lit(True).alias("b")).distinct()
    return a.join(b, "k", "full").select("k", F.coalesce("a", F.lit(False)).alias("in_a"), F.coalesce("b", F.lit(False)).alias("in_b"))


@q("SELECT o_orderkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_quantity > 45)")
def op_join_semi(s, d):
    li = load(s, d, "lineitem").filter("l_quantity > 45").select(F.col("l_orderkey").alias("o_orderkey"))
    return load(s, d, "orders").select("o_orderkey").join(li, "o_orderkey", "left_semi")


@q("SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")
def op_join_anti(s, d):
    return load(s, d, "orders").select("o_orderkey").join(load(s, d, "lineitem").select(F.col("l_orderkey").alias("o_orderkey")), "o_orderkey", "left_anti")


@q("SELECT r_name, b FROM region, range(1, 5) t(b)")
def op_join_cross(s, d):
    """Both sides have fixed sizes: a grid of runs."""
    return load(s, d, "region").select("r_name").crossJoin(F.broadcast(s.range(1, 5).select(F.col("id").alias("b"))))


@q("SELECT x.n_nationkey AS a, y.n_nationkey AS b FROM nation x JOIN nation y ON x.n_regionkey = y.n_regionkey AND x.n_nationkey < y.n_nationkey")
def op_join_theta(s, d):
    n = load(s, d, "nation").select("n_nationkey", "n_regionkey")
    two = n.join(n.select(F.col("n_nationkey").alias("b"), "n_regionkey"), "n_regionkey").filter("n_nationkey < b")
    return two.select(F.col("n_nationkey").alias("a"), "b")


@q("SELECT band, count(*) AS n FROM part JOIN range(0, 5) t(band) ON p_size >= band * 10 AND p_size < band * 10 + 10 GROUP BY 1")
def op_join_range(s, d):
    bands = F.broadcast(s.range(5).select(F.col("id").alias("band")))
    return load(s, d, "part").join(bands, (F.col("p_size") >= F.col("band") * 10) & (F.col("p_size") < F.col("band") * 10 + 10)).groupBy("band").agg(F.count("*").alias("n"))


@q("SELECT e.event_id, (SELECT max(p.event_id) FROM events p WHERE p.user_id = e.user_id AND p.event_type = 'purchase' AND p.ts = (SELECT max(x.ts) FROM events x WHERE x.user_id = e.user_id AND x.event_type = 'purchase' AND x.ts <= e.ts)) AS last_purchase FROM events e WHERE e.event_type <> 'purchase'")
def op_join_asof(s, d):
    """Last purchase of the user up to each event: one window, no join."""
    e = load(s, d, "events")
    buy = F.when(F.col("event_type") == "purchase", F.col("event_id"))
    w = W.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "purchase", 0).otherwise(1), "event_id").rowsBetween(W.unboundedPreceding, 0)
    return e.withColumn("last_purchase", F.last(buy, True).over(w)).filter("event_type <> 'purchase'").select("event_id", "last_purchase")


@q("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 600 MINUTE")
def op_join_interval(s, d):
    e = load(s, d, "events")
    a = e.filter("event_type = 'click'").select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("ta"))
    b = e.filter("event_type = 'purchase'").select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("tb"))
    return a.join(b, "user_id").filter("tb >= ta and tb <= ta + interval 600 minutes").select("a", "b")


@q(f"WITH {g_sql('page_link')} SELECT src, dst FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY dst) AS r FROM arcs WHERE src % {KINDS} = 6) WHERE r <= 2")
def op_join_lateral(s, d):
    g = graph(s, d, "page_link")
    g.arcs.createOrReplaceTempView("arcs_lateral")
    g.vertices.createOrReplaceTempView("vertices_lateral")
    return s.sql(f"SELECT a.v AS src, t.dst FROM (SELECT v FROM vertices_lateral WHERE v % {KINDS} = 6) a, LATERAL (SELECT dst FROM arcs_lateral WHERE src = a.v ORDER BY dst LIMIT 2) t")


@q("SELECT count(*) AS n FROM (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) x JOIN (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) y ON x.l_orderkey = y.l_orderkey AND x.l_partkey < y.l_partkey")
def op_join_self(s, d):
    li = load(s, d, "lineitem").select("l_orderkey", "l_partkey").distinct()
    return li.join(li.select("l_orderkey", F.col("l_partkey").alias("p2")), "l_orderkey").filter("l_partkey < p2").agg(F.count("*").alias("n"))


@q("SELECT o_orderstatus, count(*) AS n, min(o_orderkey) AS lo, max(o_orderkey) AS hi, round(avg(o_totalprice), 4) AS mean FROM orders GROUP BY 1")
def op_agg_basic(s, d):
    return load(s, d, "orders").groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.min("o_orderkey").alias("lo"), F.max("o_orderkey").alias("hi"), F.round(F.avg("o_totalprice"), 4).alias("mean"))


@q("SELECT o_orderstatus, count(DISTINCT o_custkey) AS n FROM orders GROUP BY 1")
def op_agg_distinct(s, d):
    return load(s, d, "orders").groupBy("o_orderstatus").agg(F.countDistinct("o_custkey").alias("n"))


@q()
def op_agg_approx_distinct(s, d):
    return load(s, d, "orders").groupBy("o_orderstatus").agg(F.approx_count_distinct("o_custkey", 0.02).alias("n"))


_CN = "customer JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey"


def _cn(s, d):
    n = load(s, d, "nation").join(load(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("n_nationkey").alias("c_nationkey"), "r_name")
    return load(s, d, "customer").join(F.broadcast(n), "c_nationkey")


@q(f"SELECT r_name, c_mktsegment, count(*) AS n FROM {_CN} GROUP BY GROUPING SETS ((r_name), (c_mktsegment))")
def op_grouping_sets(s, d):
    _cn(s, d).createOrReplaceTempView("cn_sets")
    return s.sql("SELECT r_name, c_mktsegment, count(*) AS n FROM cn_sets GROUP BY GROUPING SETS ((r_name), (c_mktsegment))")


@q(f"SELECT r_name, c_mktsegment, count(*) AS n FROM {_CN} GROUP BY CUBE (r_name, c_mktsegment)")
def op_cube(s, d):
    return _cn(s, d).cube("r_name", "c_mktsegment").agg(F.count("*").alias("n"))


@q(f"SELECT r_name, c_mktsegment, count(*) AS n FROM {_CN} GROUP BY ROLLUP (r_name, c_mktsegment)")
def op_rollup(s, d):
    return _cn(s, d).rollup("r_name", "c_mktsegment").agg(F.count("*").alias("n"))


@q("SELECT o_custkey, count(*) FILTER (WHERE o_orderstatus = 'F') AS F, count(*) FILTER (WHERE o_orderstatus = 'O') AS O FROM orders GROUP BY 1")
def op_pivot(s, d):
    p = load(s, d, "orders").groupBy("o_custkey").pivot("o_orderstatus", ["F", "O"]).agg(F.count(F.lit(1)))
    return p.select("o_custkey", F.coalesce("F", F.lit(0)).alias("F"), F.coalesce("O", F.lit(0)).alias("O"))


@q("SELECT c_nationkey, arg_min(c_custkey, (c_acctbal, c_custkey)) AS poorest, arg_max(c_custkey, (c_acctbal, c_custkey)) AS richest FROM customer GROUP BY 1")
def op_min_by(s, d):
    k = F.struct("c_acctbal", "c_custkey")
    return load(s, d, "customer").groupBy("c_nationkey").agg(F.min_by("c_custkey", k).alias("poorest"), F.max_by("c_custkey", k).alias("richest"))


@q("SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1")
def op_collect(s, d):
    return load(s, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.sort_array(F.collect_set("n_name")), ",").alias("names"))


@q("SELECT l_suppkey, count(*) AS n, CAST(sum(l_partkey) AS BIGINT) AS parts FROM lineitem GROUP BY 1")
def op_salted_agg(s, d):
    """Hot keys are spread over 16 salts before the final sum."""
    li = load(s, d, "lineitem").withColumn("salt", F.pmod(F.xxhash64("l_orderkey", "l_partkey"), F.lit(16)))
    part = li.groupBy("l_suppkey", "salt").agg(F.count("*").alias("n"), F.sum("l_partkey").alias("parts"))
    return part.groupBy("l_suppkey").agg(F.sum("n").alias("n"), F.sum("parts").alias("parts"))


@q("SELECT c_nationkey, quantile_disc(c_custkey, 0.5) AS mid, bool_and(c_acctbal > -1000) AS fine FROM customer GROUP BY 1")
def op_agg_percentile(s, d):
    return load(s, d, "customer").groupBy("c_nationkey").agg(F.expr("percentile_disc(0.5) within group (order by c_custkey)").cast("long").alias("mid"), F.bool_and(F.col("c_acctbal") > -1000).alias("fine"))




@q("SELECT c_custkey, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_mktsegment, c_custkey) AS rn, rank() OVER s AS rk, dense_rank() OVER s AS dr, percent_rank() OVER s AS pr, cume_dist() OVER s AS cd FROM customer WINDOW s AS (PARTITION BY c_nationkey ORDER BY c_mktsegment)")
def op_rank_family(s, d):
    w, x = W.partitionBy("c_nationkey").orderBy("c_mktsegment"), W.partitionBy("c_nationkey").orderBy("c_mktsegment", "c_custkey")
    return load(s, d, "customer").select("c_custkey", F.row_number().over(x).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.percent_rank().over(w).alias("pr"), F.cume_dist().over(w).alias("cd"))


def _cw():
    return W.partitionBy("o_custkey").orderBy("o_orderkey")


_CWS = "(PARTITION BY o_custkey ORDER BY o_orderkey"


def _over(name, sql, cols):
    def f(s, d):
        return load(s, d, "orders").select("o_orderkey", *[c.alias(k) for k, c in cols(_cw()).items()])

    f.__name__ = name
    q(f"SELECT o_orderkey, {sql} FROM orders")(f)


_over("op_lag_lead", f"lag(o_orderkey) OVER {_CWS}) AS before, lead(o_orderkey, 2) OVER {_CWS}) AS after, first_value(o_orderkey) OVER {_CWS}) AS fst", lambda w: {"before": F.lag("o_orderkey").over(w), "after": F.lead("o_orderkey", 2).over(w), "fst": F.first("o_orderkey").over(w)})
_over("op_running_sum", f"CAST(sum(o_orderkey) OVER {_CWS}) AS BIGINT) AS total", lambda w: {"total": F.sum("o_orderkey").over(w)})
_over("op_rows_frame", f"CAST(sum(o_orderkey) OVER {_CWS} ROWS BETWEEN 2 PRECEDING AND 1 FOLLOWING) AS BIGINT) AS total", lambda w: {"total": F.sum("o_orderkey").over(w.rowsBetween(-2, 1))})
_over("op_range_frame", f"count(*) OVER {_CWS} RANGE BETWEEN 100 PRECEDING AND CURRENT ROW) AS n", lambda w: {"n": F.count("*").over(w.rangeBetween(-100, 0))})
_over("op_ntile", f"ntile(3) OVER {_CWS}) AS third", lambda w: {"third": F.ntile(3).over(w)})


@q("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
def op_topk(s, d):
    return load(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10).select("o_orderkey", "o_totalprice")


@q(f"SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER {_CWS}) AS r FROM orders) WHERE r <= 2")
def op_topk_per_group(s, d):
    return load(s, d, "orders").withColumn("r", F.row_number().over(_cw())).filter("r <= 2").select("o_custkey", "o_orderkey")


@q("SELECT c_nationkey AS k FROM customer UNION ALL SELECT s_nationkey FROM supplier")
def op_union(s, d):
    return load(s, d, "customer").select(F.col("c_nationkey").alias("k")).union(load(s, d, "supplier").select("s_nationkey"))


@q("SELECT c_custkey AS id, c_nationkey AS n, NULL::DOUBLE AS bal FROM customer UNION ALL SELECT s_suppkey, s_nationkey, s_acctbal FROM supplier")
def op_union_by_name(s, d):
    a = load(s, d, "customer").select(F.col("c_custkey").alias("id"), F.col("c_nationkey").alias("n"))
    return a.unionByName(load(s, d, "supplier").select(F.col("s_acctbal").alias("bal"), F.col("s_nationkey").alias("n"), F.col("s_suppkey").alias("id")), allowMissingColumns=True)


@q("SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier")
def op_intersect(s, d):
    return load(s, d, "customer").select(F.col("c_nationkey").alias("k")).intersect(load(s, d, "supplier").select("s_nationkey"))


@q("SELECT c_nationkey AS k FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier")
def op_intersect_all(s, d):
    return load(s, d, "customer").select(F.col("c_nationkey").alias("k")).intersectAll(load(s, d, "supplier").select("s_nationkey"))


@q("SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier")
def op_except_all(s, d):
    return load(s, d, "customer").select(F.col("c_nationkey").alias("k")).exceptAll(load(s, d, "supplier").select("s_nationkey"))


@q("SELECT conv_id, len(list(turn)) AS n, array_to_string(list_sort(list(turn * 2) FILTER (WHERE turn % 2 = 0)), ',') AS evens FROM conversations GROUP BY 1")
def fn_array(s, d):
    t = F.collect_list("turn")
    return load(s, d, "conversations").groupBy("conv_id").agg(F.size(t).cast("long").alias("n"), F.array_join(F.sort_array(F.transform(F.filter(t, lambda x: x % 2 == 0), lambda x: x * 2)), ",").alias("evens"))


@q("SELECT user_id, string_agg(event_type || '=' || n, ',' ORDER BY event_type) AS counts FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2) GROUP BY 1")
def fn_map(s, d):
    e = load(s, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    m = e.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.array_join(F.transform(F.sort_array(F.map_keys("m")), lambda k: F.concat(k, F.lit("="), F.col("m")[k].cast("string"))), ",").alias("counts"))


@q("SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def fn_json(s, d):
    return load(s, d, "events").select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


@q("SELECT page_id, lower(string_split(url, '/')[3]) AS host, md5(url) AS h, length(url) AS n FROM pages")
def fn_string(s, d):
    return load(s, d, "pages").select("page_id", F.lower(F.split("url", "/")[2]).alias("host"), F.md5("url").alias("h"), F.length("url").cast("long").alias("n"))


@q("SELECT o_orderkey, epoch_us(date_trunc('month', o_orderdate)) AS month_us, date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS days FROM orders")
def fn_date(s, d):
    t = F.col("o_orderdate").cast("timestamp")
    return load(s, d, "orders").select("o_orderkey", F.unix_micros(F.date_trunc("month", t)).alias("month_us"), F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01")).cast("long").alias("days"))


@q("SELECT c_custkey, bit_count(c_custkey) AS bits, c_custkey // 7 AS d, c_custkey % 7 AS m, (c_custkey << 2) AS sh, CAST(floor(log2(c_custkey + 1)) AS BIGINT) AS lg FROM customer")
def fn_math_bits(s, d):
    k = F.col("c_custkey")
    return load(s, d, "customer").select("c_custkey", F.bit_count(k).alias("bits"), F.expr("c_custkey div 7").alias("d"), F.pmod(k, F.lit(7)).alias("m"), F.shiftleft(k, 2).alias("sh"), F.floor(F.log2(k + 1)).alias("lg"))


@q("SELECT epoch_us(time_bucket(INTERVAL 1 DAY, ts)) // 1000000 AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def st_tumbling(s, d):
    return activity.windows(s, d, "1 day")


@q("SELECT epoch_us(time_bucket(INTERVAL 12 HOUR, ts)) // 1000000 - 43200 * k AS start, event_type, count(*) AS n FROM events, range(2) t(k) GROUP BY 1, 2")
def st_sliding(s, d):
    return activity.windows(s, d, "1 day", "12 hours")


@q("WITH x AS (SELECT *, CASE WHEN ts < lag(ts) OVER w + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), y AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM x) SELECT epoch_us(min(ts)) // 1000000 AS start, user_id, count(*) AS n FROM y GROUP BY user_id, k")
def st_session(s, d):
    return activity.sessions(s, d, "6 hours")


@q("SELECT DISTINCT user_id, epoch_us(ts) // 3600000000 AS hour FROM events")
def st_dedup_arcs(s, d):
    return activity.distinct_arcs(s, d)


@q("SELECT user_id, count(*) AS deg FROM events GROUP BY 1")
def st_running_degree(s, d):
    return activity.running_degree(s, d)


@q("SELECT event_type, count(*) FILTER (WHERE user_id < 50) AS inside, count(*) FILTER (WHERE user_id >= 50) AS outside FROM events GROUP BY 1")
def st_static_cut_drift(s, d):
    return activity.static_drift(s, d, s.range(50).withColumnRenamed("id", "user_id"))


@q(SQL["op_join_interval"])
def st_interval_join(s, d):
    return activity.interval_join(s, d, "click", "purchase", 600)


@q("SELECT user_id, count(*) AS n, count(DISTINCT epoch_us(ts) // 3600000000) AS hours FROM events GROUP BY 1")
def st_stateful_volume(s, d):
    return activity.stateful_volume(s, d)


@q("""WITH m AS (SELECT max(ts) - INTERVAL 10 DAY AS mark FROM events WHERE event_type <> 'purchase'),
 x AS (SELECT time_bucket(INTERVAL 1 DAY, ts) AS w, event_type = 'purchase' AND time_bucket(INTERVAL 1 DAY, ts) + INTERVAL 1 DAY <= mark AS late FROM events, m)
 SELECT epoch_us(w) // 1000000 AS start, count(*) FILTER (WHERE NOT late) AS n, count(*) FILTER (WHERE late) AS late FROM x GROUP BY 1""")
def st_late_rows(s, d):
    return activity.late_rows(s, d, "purchase", "1 day", "10 days")


@q(f"WITH {g_sql('user_hour')} SELECT v, deg FROM vx")
def st_adjacency_upsert(s, d):
    return activity.upserted(s, d, "2024-01-16").vertices.select("v", "deg")


@q(f"WITH {g_sql('user_hour')} SELECT count(*) AS arcs_stream, count(*) AS arcs_batch, count(*) AS arcs_both FROM arcs")
def st_stream_equals_batch(s, d):
    return activity.against_batch(activity.upserted(s, d, "2024-01-16").arcs, graph(s, d, "user_hour").arcs)


_R2 = [Run(0, cust(0)), Run(1, cust(1))]


@q(rec(g_sql("fk_forest"), w_sql(_R2, 2), R_SQL, select="SELECT run_id, t, coalesce(arg_min(ratio, j) FILTER (WHERE prefix_vol >= 16), 0.0) AS slope FROM lam GROUP BY 1, 2"))
def udf_pandas_slope(s, d):
    g = graph(s, d, "fk_forest")
    r = sweep.ranked(g, walk.walk(g, _R2, 2))
    packed = r.groupBy("run_id", "t").agg(F.sort_array(F.collect_list(F.struct("j", "ratio", "prefix_vol"))).alias("m"))
    return packed.select("run_id", "t", slope_at(F.col("m.ratio"), F.col("m.prefix_vol"), F.lit(16)).alias("slope"))


@q(f"WITH {g_sql('fk_forest')}, {MEASURE_SQL} SELECT set_id, cut / CAST(least(m.vol, tot.vol - m.vol) AS DOUBLE) AS phi FROM m, tot")
def udaf_conductance(s, d):
    return member_rows(graph(s, d, "fk_forest"), nation_sets(s, d)).groupBy("set_id").agg(conductance("cut", "vol", "total").alias("phi"))


@q("SELECT user_id, mask, CAST(bit_count(mask) AS INT) AS size FROM (SELECT user_id, unnest(range(1, 1 << CAST(count(DISTINCT event_type) - 1 AS INT))) AS mask FROM events GROUP BY user_id)")
def udtf_subset_masks(s, d):
    """Subsets of the event types of every user."""
    s.udtf.register("subset_masks", SubsetMasks)
    load(s, d, "events").groupBy("user_id").agg(F.countDistinct("event_type").cast("int").alias("k")).createOrReplaceTempView("user_types")
    return s.sql("SELECT user_id, t.mask, t.size FROM user_types, LATERAL subset_masks(k) t")


@q(f"WITH {TREES_SQL}, x AS (SELECT n, ell, unnest(range(1, ell + 1)) AS i FROM l) SELECT n, CAST(i AS INT) AS b, pow(2.0, -i) / (1 - pow(2.0, -ell)) AS p FROM x")
def udtf_geometric_scales(s, d):
    """Scales of the tree of every nation."""
    s.udtf.register("geometric_scales", GeometricScales)
    trees(s, d).selectExpr("n", f"{ELL} AS ell").createOrReplaceTempView("tree_scales")
    return s.sql("SELECT n, t.b, t.p FROM tree_scales, LATERAL geometric_scales(ell) t")


@q(f"WITH {g_sql('page_link')} SELECT deg, count(*) AS n FROM vx GROUP BY 1")
def sql_registered_calls(s, d):
    register(s, graph(s, d, "page_link"))
    return s.sql("SELECT deg, count(*) AS n FROM vertices GROUP BY deg")


