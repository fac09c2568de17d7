"""Relational operators that assemble, deal and watch training data: each a plan over the given tables with its SQL twin.

``QUERIES[name](spark, sf_dir)`` builds the plan; ``SQL[name]`` is DuckDB text with the same columns.  Sums are of whole numbers, so that they do not
depend on order.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from terse.functions.draws import draw, draw_sql
from terse.sources.tables import append, bucketed, read, shared_folder, write_samples

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str):
    def keep(build):
        QUERIES[name] = build
        SQL[name] = sql
        return build

    return keep


cents = lambda c: F.floor(F.col(c) * 100 + 0.5).cast("long")
day = lambda c: F.date_format(c, "yyyy-MM-dd")

# ---- scans, projections, filters -------------------------------------------------------------------------------------


@query("scan_pruned", "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity >= 49 AND l_returnflag = 'R'")
def _(s, d):
    return read(s, d, "lineitem", "l_orderkey", "l_quantity", "l_returnflag").where("l_quantity >= 49 and l_returnflag = 'R'").drop("l_returnflag")


@query("scan_generated", f"SELECT id, CAST(floor({draw_sql(5, 'id')} * 1000000) AS BIGINT) AS u FROM (SELECT unnest(range(0, 1000)) AS id)")
def _(s, d):
    return s.range(1000).select("id", F.floor(draw(5, F.col("id"), mode="portable") * 1000000).cast("long").alias("u"))


@query("scan_sql_params", "SELECT o_orderkey, o_orderstatus FROM orders WHERE o_totalprice > 300000.0 AND o_orderstatus = 'F'")
def _(s, d):
    return s.sql("select o_orderkey, o_orderstatus from {o} where o_totalprice > :least and o_orderstatus = :status", args={"least": 300000.0, "status": "F"}, o=read(s, d, "orders"))


@query("proj_arith", "SELECT l_orderkey, l_linenumber, CAST(floor(l_extendedprice * (1 - l_discount) * 100 + 0.5) AS BIGINT) AS net, l_quantity * 2 + 1 AS twice FROM lineitem")
def _(s, d):
    li = read(s, d, "lineitem", "l_orderkey", "l_linenumber", "l_extendedprice", "l_discount", "l_quantity")
    return li.select("l_orderkey", "l_linenumber", F.floor(F.col("l_extendedprice") * (1 - F.col("l_discount")) * 100 + 0.5).cast("long").alias("net"), (F.col("l_quantity") * 2 + 1).alias("twice"))


@query("proj_case", "SELECT band, count(*) AS n FROM (SELECT CASE WHEN l_quantity < 10 THEN 'low' WHEN l_quantity < 40 THEN 'middle' ELSE 'high' END AS band FROM lineitem) GROUP BY band")
def _(s, d):
    band = F.when(F.col("l_quantity") < 10, "low").when(F.col("l_quantity") < 40, "middle").otherwise("high")
    return read(s, d, "lineitem", "l_quantity").groupBy(band.alias("band")).agg(F.count("*").alias("n"))


@query("proj_bucket", "SELECT CAST(least(greatest(floor(l_quantity / 10) + 1, 0), 6) AS BIGINT) AS bucket, count(*) AS n FROM lineitem GROUP BY 1")
def _(s, d):
    return read(s, d, "lineitem", "l_quantity").groupBy(F.width_bucket("l_quantity", F.lit(0.0), F.lit(50.0), F.lit(5)).alias("bucket")).agg(F.count("*").alias("n"))


@query("filter_range_in_like", "SELECT o_orderkey FROM orders WHERE o_orderdate BETWEEN TIMESTAMP '1995-01-01' AND TIMESTAMP '1996-12-31' AND o_orderstatus IN ('F', 'O') AND o_orderpriority LIKE '1%'")
def _(s, d):
    o = read(s, d, "orders", "o_orderkey", "o_orderdate", "o_orderstatus", "o_orderpriority")
    dates = F.col("o_orderdate").between(F.expr("timestamp_ntz'1995-01-01'"), F.expr("timestamp_ntz'1996-12-31'"))
    return o.where(dates & F.col("o_orderstatus").isin("F", "O") & F.col("o_orderpriority").like("1%")).select("o_orderkey")


@query("filter_null_safe", "SELECT count(*) AS n FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id WHERE l.toxic IS NOT DISTINCT FROM NULL")
def _(s, d):
    return read(s, d, "documents", "doc_id").join(read(s, d, "labels", "doc_id", "toxic"), "doc_id", "left").where(F.col("toxic").eqNullSafe(F.lit(None))).agg(F.count("*").alias("n"))


@query("filter_regex", r"SELECT doc_id FROM documents WHERE regexp_matches(text, '[0-9]{3,}')")
def _(s, d):
    return read(s, d, "documents", "doc_id", "text").where(F.col("text").rlike("[0-9]{3,}")).select("doc_id")


@query("dedupe_documents", "SELECT min(doc_id) AS doc_id, CAST(count(*) AS BIGINT) AS copies FROM documents GROUP BY text")
def _(s, d):
    return read(s, d, "documents", "doc_id", "text").groupBy(F.sha2(F.col("text").cast("binary"), 256).alias("h")).agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("copies")).drop("h")


# ---- joins --------------------------------------------------------------------------------------------------------------


@query("join_broadcast", "SELECT r_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
def _(s, d):
    n = read(s, d, "nation").join(read(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return read(s, d, "customer", "c_nationkey").join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("r_name").agg(F.count("*").alias("n"))


ORDER_LINES = "SELECT o_orderstatus, CAST(sum(l_quantity) AS BIGINT) AS q FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderstatus"


def _order_lines(s, d, hint):
    li, o = read(s, d, "lineitem", "l_orderkey", "l_quantity"), read(s, d, "orders", "o_orderkey", "o_orderstatus")
    return li.join(o.hint(hint), li.l_orderkey == o.o_orderkey).groupBy("o_orderstatus").agg(F.sum("l_quantity").cast("long").alias("q"))


query("join_sort_merge", ORDER_LINES)(lambda s, d: _order_lines(s, d, "merge"))
query("join_shuffle_hash", ORDER_LINES)(lambda s, d: _order_lines(s, d, "shuffle_hash"))


@query("join_left", "SELECT d.doc_id, l.toxic FROM documents d LEFT JOIN labels l USING (doc_id)")
def _(s, d):
    return read(s, d, "documents", "doc_id").join(read(s, d, "labels", "doc_id", "toxic"), "doc_id", "left")


@query("join_right", "SELECT o_orderkey, c_custkey FROM orders RIGHT JOIN customer ON o_custkey = c_custkey AND o_totalprice > 400000")
def _(s, d):
    o = read(s, d, "orders", "o_orderkey", "o_custkey", "o_totalprice").where("o_totalprice > 400000")
    return o.join(read(s, d, "customer", "c_custkey"), F.col("o_custkey") == F.col("c_custkey"), "right").select("o_orderkey", "c_custkey")


@query("join_full", "SELECT a.k AS ka, b.k AS kb FROM (SELECT DISTINCT l_suppkey AS k FROM lineitem WHERE l_quantity = 50) a FULL JOIN (SELECT s_suppkey AS k FROM supplier WHERE s_acctbal > 0) b ON a.k = b.k")
def _(s, d):
    a = read(s, d, "lineitem", "l_suppkey", "l_quantity").where("l_quantity = 50").select(F.col("l_suppkey").alias("ka")).distinct()
    return a.join(read(s, d, "supplier", "s_suppkey", "s_acctbal").where("s_acctbal > 0").select(F.col("s_suppkey").alias("kb")), F.col("ka") == F.col("kb"), "full")


@query("join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def _(s, d):
    return read(s, d, "customer", "c_custkey").join(read(s, d, "orders", "o_custkey"), F.col("o_custkey") == F.col("c_custkey"), "left_semi")


@query("join_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def _(s, d):
    return read(s, d, "customer", "c_custkey").join(read(s, d, "orders", "o_custkey"), F.col("o_custkey") == F.col("c_custkey"), "left_anti")


@query("join_cross", "SELECT a.n_nationkey AS sender, b.r_regionkey AS receiver FROM nation a CROSS JOIN region b")
def _(s, d):
    return read(s, d, "nation").select(F.col("n_nationkey").alias("sender")).crossJoin(F.broadcast(read(s, d, "region").select(F.col("r_regionkey").alias("receiver"))))


@query("join_theta_band", "SELECT band, count(*) AS n FROM lineitem JOIN (VALUES ('a', 0, 10), ('b', 10, 30), ('c', 30, 100)) b(band, lo, hi) ON l_quantity >= lo AND l_quantity < hi GROUP BY band")
def _(s, d):
    bands = s.createDataFrame([("a", 0, 10), ("b", 10, 30), ("c", 30, 100)], "band string, lo int, hi int")
    return read(s, d, "lineitem", "l_quantity").join(F.broadcast(bands), F.expr("l_quantity >= lo and l_quantity < hi")).groupBy("band").agg(F.count("*").alias("n"))


@query(
    "join_asof",
    "SELECT e.event_id, (SELECT max(v.event_id) FROM events v WHERE v.user_id = e.user_id AND v.event_type = 'purchase' AND (v.ts < e.ts OR (v.ts = e.ts AND v.event_id <= e.event_id)) "
    "AND NOT EXISTS (SELECT 1 FROM events w WHERE w.user_id = v.user_id AND w.event_type = 'purchase' AND (w.ts > v.ts OR (w.ts = v.ts AND w.event_id > v.event_id)) AND (w.ts < e.ts OR (w.ts = e.ts AND w.event_id <= e.event_id)))) AS last_purchase FROM events e",
)
def _(s, d):
    seen = F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True)
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return read(s, d, "events", "event_id", "ts", "user_id", "event_type").select("event_id", seen.over(w).alias("last_purchase"))


@query("join_interval", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE")
def _(s, d):
    """Ten-minute cells make the range join an equality join: a pair lies in one cell or in neighbours."""
    e = read(s, d, "events", "event_id", "ts", "user_id").withColumn("u", F.unix_micros(F.col("ts").cast("timestamp"))).withColumn("cell", F.expr("u div 600000000"))
    a = e.select("user_id", F.col("event_id").alias("a"), F.col("u").alias("ua"), F.explode(F.array("cell", F.col("cell") + 1)).alias("cell"))
    b = e.select("user_id", F.col("event_id").alias("b"), F.col("u").alias("ub"), "cell")
    return a.join(b, ["user_id", "cell"]).where("ub > ua and ub <= ua + 600000000").select("a", "b")


@query("join_lateral", "SELECT vec_id, coord, CAST(floor(CAST(e AS DOUBLE) * 1048576 + 0.5) AS BIGINT) AS v FROM (SELECT vec_id, unnest(embedding) AS e, unnest(range(0, len(embedding))) AS coord FROM embeddings)")
def _(s, d):
    v = F.floor(F.col("e").cast("double") * 1048576 + 0.5).cast("long")
    return read(s, d, "embeddings", "vec_id", "embedding").select("vec_id", F.posexplode("embedding").alias("coord", "e")).select("vec_id", F.col("coord").cast("long").alias("coord"), v.alias("v"))


@query("join_skew_salted", "SELECT event_type, count(*) AS n, CAST(sum(w) AS BIGINT) AS w FROM events JOIN (SELECT event_type, length(event_type) AS w FROM events GROUP BY event_type) USING (event_type) GROUP BY event_type")
def _(s, d):
    """A handful of hot keys: rows get a salt, the small side a copy for each salt."""
    salts = 8
    e = read(s, d, "events", "event_id", "event_type")
    side = e.groupBy("event_type").agg(F.first(F.length("event_type")).alias("w")).withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    joined = e.withColumn("salt", F.pmod(F.xxhash64("event_id"), F.lit(salts)).cast("int")).join(side, ["event_type", "salt"])
    return joined.groupBy("event_type", "salt").agg(F.count("*").alias("n"), F.sum("w").alias("w")).groupBy("event_type").agg(F.sum("n").alias("n"), F.sum("w").cast("long").alias("w"))


@query("join_self", "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def _(s, d):
    n = read(s, d, "nation")
    return n.alias("a").join(n.alias("b"), F.expr("a.n_regionkey = b.n_regionkey and a.n_nationkey < b.n_nationkey")).select(F.col("a.n_nationkey").alias("a"), F.col("b.n_nationkey").alias("b"))


@query("join_star", "SELECT n_name, p_brand, CAST(sum(l_quantity) AS BIGINT) AS q FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN part ON l_partkey = p_partkey GROUP BY n_name, p_brand")
def _(s, d):
    return (
        read(s, d, "lineitem", "l_orderkey", "l_partkey", "l_quantity").join(read(s, d, "orders", "o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
        .join(read(s, d, "customer", "c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(read(s, d, "nation", "n_nationkey", "n_name")), F.col("c_nationkey") == F.col("n_nationkey"))
        .join(read(s, d, "part", "p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey")).groupBy("n_name", "p_brand").agg(F.sum("l_quantity").cast("long").alias("q"))
    )


# ---- aggregates ---------------------------------------------------------------------------------------------------------


@query("agg_hash", "SELECT l_returnflag, l_linestatus, CAST(sum(l_quantity) AS BIGINT) AS q, avg(l_quantity) AS mean, min(l_quantity) AS lo, max(l_quantity) AS hi, count(*) AS n FROM lineitem GROUP BY 1, 2")
def _(s, d):
    q = F.col("l_quantity")
    return read(s, d, "lineitem", "l_returnflag", "l_linestatus", "l_quantity").groupBy("l_returnflag", "l_linestatus").agg(F.sum(q).cast("long").alias("q"), F.avg(q).alias("mean"), F.min(q).alias("lo"), F.max(q).alias("hi"), F.count("*").alias("n"))


@query("agg_vector_sum", "SELECT label, coord, CAST(sum(CAST(floor(CAST(e AS DOUBLE) * 1048576 + 0.5) AS BIGINT)) AS BIGINT) AS v FROM (SELECT label, unnest(embedding) AS e, unnest(range(0, len(embedding))) AS coord FROM embeddings) GROUP BY label, coord")
def _(s, d):
    from terse.functions.vectors import vector_sum

    grid = F.transform("embedding", lambda e: F.floor(e.cast("double") * 1048576 + 0.5).cast("long"))
    return vector_sum(read(s, d, "embeddings").select("label", grid.alias("g")), ["label"], "g", salts=4)


@query("agg_distinct", "SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem")
def _(s, d):
    return read(s, d, "lineitem", "l_partkey", "l_suppkey").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("suppliers"))


def _grouped(kind):
    def build(s, d):
        li = read(s, d, "lineitem", "l_returnflag", "l_linestatus", "l_quantity")
        g = getattr(li, kind)("l_returnflag", "l_linestatus")
        return g.agg(F.sum("l_quantity").cast("long").alias("q"), F.grouping_id().cast("long").alias("level"))

    return build


for _kind in ("cube", "rollup"):
    query(f"agg_{_kind}", f"SELECT l_returnflag, l_linestatus, CAST(sum(l_quantity) AS BIGINT) AS q, CAST(grouping_id(l_returnflag, l_linestatus) AS BIGINT) AS level FROM lineitem GROUP BY {_kind}(l_returnflag, l_linestatus)")(_grouped(_kind))


@query("agg_grouping_sets", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
def _(s, d):
    return s.sql("select l_returnflag, l_linestatus, count(*) as n from {t} group by grouping sets ((l_returnflag), (l_linestatus), ())", t=read(s, d, "lineitem", "l_returnflag", "l_linestatus"))


@query("agg_pivot", "SELECT l_linestatus, count(*) FILTER (l_returnflag = 'A') AS A, count(*) FILTER (l_returnflag = 'N') AS N, count(*) FILTER (l_returnflag = 'R') AS R FROM lineitem GROUP BY l_linestatus")
def _(s, d):
    return read(s, d, "lineitem", "l_returnflag", "l_linestatus").groupBy("l_linestatus").pivot("l_returnflag", ["A", "N", "R"]).agg(F.count(F.lit(1))).na.fill(0)


@query("agg_unpivot", "SELECT n_nationkey, what, v FROM (SELECT n_nationkey, CAST(n_regionkey AS BIGINT) AS region, CAST(length(n_name) AS BIGINT) AS letters FROM nation) UNPIVOT (v FOR what IN (region, letters))")
def _(s, d):
    wide = read(s, d, "nation").select("n_nationkey", F.col("n_regionkey").cast("long").alias("region"), F.length("n_name").cast("long").alias("letters"))
    return wide.unpivot("n_nationkey", ["region", "letters"], "what", "v")


@query("agg_stats", "SELECT floor(var_samp(l_quantity) * 1000 + 0.5) AS variance, floor(corr(l_quantity, l_linenumber) * 1000000 + 0.5) AS correlation, floor(regr_slope(l_quantity, l_linenumber) * 1000000 + 0.5) AS slope FROM lineitem")
def _(s, d):
    r = lambda c, m: F.floor(c * m + 0.5).cast("double")
    return read(s, d, "lineitem", "l_quantity", "l_linenumber").agg(
        r(F.var_samp("l_quantity"), 1000).alias("variance"), r(F.corr("l_quantity", "l_linenumber"), 1000000).alias("correlation"), r(F.regr_slope("l_quantity", "l_linenumber"), 1000000).alias("slope")
    )


@query("agg_percentile", "SELECT l_returnflag, quantile_cont(l_quantity, 0.25) AS q1, median(l_quantity) AS q2 FROM lineitem GROUP BY l_returnflag")
def _(s, d):
    return read(s, d, "lineitem", "l_returnflag", "l_quantity").groupBy("l_returnflag").agg(F.percentile("l_quantity", 0.25).alias("q1"), F.median("l_quantity").alias("q2"))


def _sketch(s, d):
    """Sketches whose size does not depend on the rows: distinct orders, quantiles of the price, frequent parts, a histogram of quantities."""
    li = read(s, d, "lineitem", "l_returnflag", "l_orderkey", "l_partkey", "l_extendedprice", "l_quantity")
    return li.groupBy("l_returnflag").agg(
        F.approx_count_distinct("l_orderkey", 0.02).alias("orders"), F.percentile_approx("l_extendedprice", [0.25, 0.5, 0.75], 1000).alias("prices"),
        F.expr("approx_top_k(l_partkey, 5, 10000)").alias("parts"), F.histogram_numeric("l_quantity", F.lit(10)).alias("quantities"),
    )


QUERIES["agg_sketch"] = _sketch


@query("agg_collect", "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY n_regionkey")
def _(s, d):
    return read(s, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.sort_array(F.collect_list("n_name")), ",").alias("names"))


@query("agg_filter_clause", "SELECT l_linestatus, count(*) FILTER (l_quantity > 25) AS large, bool_and(l_quantity > 0) AS positive FROM lineitem GROUP BY l_linestatus")
def _(s, d):
    return read(s, d, "lineitem", "l_linestatus", "l_quantity").groupBy("l_linestatus").agg(F.count_if(F.col("l_quantity") > 25).alias("large"), F.bool_and(F.col("l_quantity") > 0).alias("positive"))


@query("agg_max_by", "SELECT user_id, max_by(event_id, event_id * 7919 % 10007) AS pick FROM events GROUP BY user_id HAVING count(*) = count(DISTINCT event_id * 7919 % 10007)")
def _(s, d):
    h = F.col("event_id") * 7919 % 10007
    return read(s, d, "events", "user_id", "event_id").groupBy("user_id").agg(F.max_by("event_id", h).alias("pick"), F.count("*").alias("n"), F.countDistinct(h).alias("k")).where("n = k").drop("n", "k")


@query("agg_exact_sum", "SELECT o_orderstatus, CAST(sum(CAST(floor(o_totalprice * 100 + 0.5) AS BIGINT)) AS BIGINT) AS cents FROM orders GROUP BY o_orderstatus")
def _(s, d):
    return read(s, d, "orders", "o_orderstatus", "o_totalprice").groupBy("o_orderstatus").agg(F.sum(cents("o_totalprice")).alias("cents"))


@query("agg_two_level", "SELECT event_type, CAST(sum(CAST(floor(value * 100 + 0.5) AS BIGINT)) AS BIGINT) AS cents FROM events GROUP BY event_type")
def _(s, d):
    e = read(s, d, "events", "event_id", "event_type", "value").withColumn("salt", F.pmod(F.xxhash64("event_id"), F.lit(16)))
    return e.groupBy("event_type", "salt").agg(F.sum(cents("value")).alias("p")).groupBy("event_type").agg(F.sum("p").alias("cents"))


# ---- windows, sorts, sets ---------------------------------------------------------------------------------------------------


@query("window_rank", "SELECT p_partkey, row_number() OVER w AS place, rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS r, dense_rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS dr FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size, p_partkey)")
def _(s, d):
    w, v = Window.partitionBy("p_brand").orderBy("p_size", "p_partkey"), Window.partitionBy("p_brand").orderBy("p_size")
    n = lambda c, w_: c.over(w_).cast("long")
    return read(s, d, "part", "p_partkey", "p_brand", "p_size").select("p_partkey", n(F.row_number(), w).alias("place"), n(F.rank(), v).alias("r"), n(F.dense_rank(), v).alias("dr"))


@query(
    "window_distribution",
    "SELECT p_partkey, CAST(floor(percent_rank() OVER w * 1e6 + 0.5) AS BIGINT) AS pr, CAST(floor(cume_dist() OVER w * 1e6 + 0.5) AS BIGINT) AS cd, ntile(4) OVER u AS quarter, nth_value(p_partkey, 2) OVER (PARTITION BY p_brand ORDER BY p_size, p_partkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second, first_value(p_partkey) OVER u AS first FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size), u AS (PARTITION BY p_brand ORDER BY p_size, p_partkey)",
)
def _(s, d):
    w, u = Window.partitionBy("p_brand").orderBy("p_size"), Window.partitionBy("p_brand").orderBy("p_size", "p_partkey")
    micro = lambda c: F.floor(c * 1e6 + 0.5).cast("long")
    return read(s, d, "part", "p_partkey", "p_brand", "p_size").select(
        "p_partkey", micro(F.percent_rank().over(w)).alias("pr"), micro(F.cume_dist().over(w)).alias("cd"), F.ntile(4).over(u).cast("long").alias("quarter"),
        F.nth_value("p_partkey", 2).over(u.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("second"), F.first("p_partkey").over(u).alias("first"),
    )


@query("sink_samples", "SELECT event_id AS row_id, user_id % 4 AS worker_id, value AS y FROM events WHERE user_id % 4 = 1")
def _(s, d):
    """Samples written by worker and read back with the other workers' folders pruned."""
    path = f"{shared_folder(s)}/samples"
    write_samples(read(s, d, "events").select(F.col("event_id").alias("row_id"), F.pmod("user_id", F.lit(4)).alias("worker_id"), F.col("value").alias("y")), path, 4)
    return s.read.parquet(path).where("worker_id = 1").select("row_id", F.col("worker_id").cast("long").alias("worker_id"), "y")


@query("sink_bucketed", "SELECT user_id % 4 AS worker_id, count(*) AS n FROM events GROUP BY 1")
def _(s, d):
    """A table bucketed by worker: the count needs no exchange."""
    folder = shared_folder(s)
    name = f"terse_{folder.rsplit('-', 1)[1]}"
    bucketed(read(s, d, "events").select("event_id", F.pmod("user_id", F.lit(4)).alias("worker_id")), name, 4, f"{folder}/bucketed")
    return s.table(name).groupBy("worker_id").agg(F.count("*").alias("n"))


@query("sink_appended", "SELECT event_type AS run_id, count(*) AS n FROM events GROUP BY 1")
def _(s, d):
    """Two halves appended by run."""
    path = f"{shared_folder(s)}/appended"
    rows = read(s, d, "events", "event_id", "event_type").withColumnRenamed("event_type", "run_id")
    append(rows.where("event_id % 2 = 0"), path)
    append(rows.where("event_id % 2 = 1"), path)
    return s.read.parquet(path).groupBy(F.col("run_id").cast("string").alias("run_id")).agg(F.count("*").alias("n"))


@query("window_lag_lead", "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id, 2) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def _(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return read(s, d, "events", "event_id", "user_id", "ts").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id", 2).over(w).alias("after"))


@query("window_running", "SELECT o_orderkey, CAST(sum(CAST(floor(o_totalprice * 100 + 0.5) AS BIGINT)) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING) AS BIGINT) AS so_far FROM orders")
def _(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(Window.unboundedPreceding, 0)
    return read(s, d, "orders", "o_orderkey", "o_custkey", "o_orderdate", "o_totalprice").select("o_orderkey", F.sum(cents("o_totalprice")).over(w).alias("so_far"))


@query("window_range_interval", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS n FROM events")
def _(s, d):
    e = read(s, d, "events", "event_id", "user_id", "ts").withColumn("u", F.unix_micros(F.col("ts").cast("timestamp")))
    return e.select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("u").rangeBetween(-3_600_000_000, 0)).alias("n"))


@query("window_block_norm", "SELECT vec_id, coord, max(abs(v)) OVER (PARTITION BY vec_id, coord // 16) AS scale FROM (SELECT vec_id, CAST(floor(CAST(unnest(embedding) AS DOUBLE) * 1048576 + 0.5) AS BIGINT) AS v, unnest(range(0, len(embedding))) AS coord FROM embeddings)")
def _(s, d):
    c = QUERIES["join_lateral"](s, d)
    return c.select("vec_id", "coord", F.max(F.abs("v")).over(Window.partitionBy("vec_id", F.expr("coord div 16"))).alias("scale"))


@query("window_ntile", "SELECT s_suppkey, CAST(ntile(4) OVER (ORDER BY s_suppkey) AS BIGINT) AS part FROM supplier")
def _(s, d):
    return read(s, d, "supplier", "s_suppkey").select("s_suppkey", F.ntile(4).over(Window.orderBy("s_suppkey")).cast("long").alias("part"))


@query("sort_limit", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 5")
def _(s, d):
    return read(s, d, "orders", "o_orderkey", "o_totalprice").orderBy(F.col("o_totalprice").desc(), "o_orderkey").offset(5).limit(20)


@query("sort_nulls", "SELECT doc_id, row_number() OVER (ORDER BY toxic ASC NULLS LAST, doc_id) AS place FROM documents LEFT JOIN labels USING (doc_id)")
def _(s, d):
    return QUERIES["join_left"](s, d).select("doc_id", F.row_number().over(Window.orderBy(F.col("toxic").asc_nulls_last(), "doc_id")).cast("long").alias("place"))


@query("topk_per_group", "SELECT p_brand, p_partkey FROM part QUALIFY row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) <= 3")
def _(s, d):
    w = Window.partitionBy("p_brand").orderBy(F.col("p_retailprice").desc(), "p_partkey")
    return read(s, d, "part", "p_brand", "p_partkey", "p_retailprice").withColumn("k", F.row_number().over(w)).where("k <= 3").select("p_brand", "p_partkey")


def _sets(s, d):
    return read(s, d, "customer").select(F.col("c_nationkey").alias("k")).where("c_acctbal > 5000"), read(s, d, "supplier").select(F.col("s_nationkey").alias("k"))


_A, _B = "SELECT c_nationkey AS k FROM customer WHERE c_acctbal > 5000", "SELECT s_nationkey AS k FROM supplier"
for _name, _op, _call in (("union", "UNION ALL", "unionAll"), ("intersect", "INTERSECT", "intersect"), ("except", "EXCEPT", "subtract"), ("except_all", "EXCEPT ALL", "exceptAll")):
    query(f"set_{_name}", f"{_A} {_op} {_B}")(lambda s, d, c=_call: getattr(_sets(s, d)[0], c)(_sets(s, d)[1]))


@query("set_union_by_name", "SELECT n_nationkey AS k, n_name AS name, NULL AS region FROM nation UNION ALL SELECT r_regionkey, NULL, r_name FROM region")
def _(s, d):
    return read(s, d, "nation").select(F.col("n_nationkey").alias("k"), F.col("n_name").alias("name")).unionByName(read(s, d, "region").select(F.col("r_regionkey").alias("k"), F.col("r_name").alias("region")), allowMissingColumns=True)


@query("set_distinct", "SELECT DISTINCT l_returnflag, l_linestatus FROM lineitem")
def _(s, d):
    return read(s, d, "lineitem", "l_returnflag", "l_linestatus").distinct()


# ---- functions ------------------------------------------------------------------------------------------------------------------


@query("fn_string", "SELECT p_partkey, upper(p_brand) AS up, substr(p_type, 2, 4) AS part, length(p_name) AS n, translate(p_brand, '#', '-') AS t, levenshtein(p_brand, 'Brand#11') AS dist, lpad(CAST(p_size AS VARCHAR), 4, '0') AS padded FROM part")
def _(s, d):
    return read(s, d, "part").select(
        "p_partkey", F.upper("p_brand").alias("up"), F.substring("p_type", 2, 4).alias("part"), F.length("p_name").cast("long").alias("n"), F.translate("p_brand", "#", "-").alias("t"),
        F.levenshtein("p_brand", F.lit("Brand#11")).cast("long").alias("dist"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("padded"),
    )


@query("fn_regexp", r"SELECT page_id, regexp_replace(html, '<[^>]*>', ' ', 'g') AS text FROM pages")
def _(s, d):
    return read(s, d, "pages", "page_id", "html").select("page_id", F.regexp_replace("html", "<[^>]*>", " ").alias("text"))


@query("fn_date", "SELECT o_orderkey, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, extract(year FROM o_orderdate) AS y, date_diff('day', TIMESTAMP '1992-01-01', o_orderdate) AS days FROM orders")
def _(s, d):
    o = F.col("o_orderdate")
    return read(s, d, "orders", "o_orderkey", "o_orderdate").select("o_orderkey", day(F.date_trunc("month", o)).alias("month"), F.year(o).cast("long").alias("y"), F.datediff(o, F.lit("1992-01-01").cast("date")).cast("long").alias("days"))


@query("fn_interval", "SELECT o_orderkey, strftime(o_orderdate + INTERVAL 90 DAY, '%Y-%m-%d') AS due, strftime(o_orderdate + INTERVAL 1 MONTH, '%Y-%m-%d') AS next FROM orders")
def _(s, d):
    return read(s, d, "orders", "o_orderkey", "o_orderdate").select("o_orderkey", day(F.col("o_orderdate") + F.expr("interval 90 days")).alias("due"), day(F.col("o_orderdate") + F.expr("interval 1 month")).alias("next"))


@query("fn_math", "SELECT l_orderkey, l_linenumber, sqrt(l_quantity) AS root, abs(l_quantity - 25) AS gap, sign(l_quantity - 25) AS side, greatest(l_quantity, 30) AS least30, l_orderkey % 7 AS m FROM lineitem")
def _(s, d):
    q = F.col("l_quantity")
    return read(s, d, "lineitem").select("l_orderkey", "l_linenumber", F.sqrt(q).alias("root"), F.abs(q - 25).alias("gap"), F.signum(q - 25).cast("int").alias("side"), F.greatest(q, F.lit(30.0)).alias("least30"), F.pmod("l_orderkey", F.lit(7)).alias("m"))


@query("fn_bits", "SELECT o_orderkey, o_orderkey & 255 AS low, o_orderkey | 1 AS odd, xor(o_orderkey, 170) AS x, o_orderkey << 2 AS up, o_orderkey >> 3 AS down, bit_count(o_orderkey) AS ones FROM orders")
def _(s, d):
    k = F.col("o_orderkey")
    return read(s, d, "orders", "o_orderkey").select(k, k.bitwiseAND(255).alias("low"), k.bitwiseOR(1).alias("odd"), k.bitwiseXOR(170).alias("x"), F.shiftleft(k, 2).alias("up"), F.shiftright(k, 3).alias("down"), F.bit_count(k).alias("ones"))


_VEC = "SELECT vec_id, list_transform(embedding, lambda e: CAST(floor(CAST(e AS DOUBLE) * 1048576 + 0.5) AS BIGINT)) AS g FROM embeddings"


def _vec(s, d):
    return read(s, d, "embeddings").select("vec_id", F.transform("embedding", lambda e: F.floor(e.cast("double") * 1048576 + 0.5).cast("long")).alias("g"))


@query("fn_array", f"SELECT vec_id, len(g) AS n, list_max(g) AS top, g[1] AS first, list_sort(g)[32] AS middle, len(g[1:16]) AS cut FROM ({_VEC})")
def _(s, d):
    return _vec(s, d).select("vec_id", F.size("g").cast("long").alias("n"), F.array_max("g").alias("top"), F.element_at("g", 1).alias("first"), F.element_at(F.sort_array("g"), 32).alias("middle"), F.size(F.slice("g", 1, 16)).cast("long").alias("cut"))


@query("fn_higher_order", f"SELECT vec_id, len(list_filter(g, lambda e: e > 0)) AS above, CAST(list_sum(list_transform(g, lambda e: abs(e))) AS BIGINT) AS l1 FROM ({_VEC})")
def _(s, d):
    return _vec(s, d).select("vec_id", F.size(F.filter("g", lambda e: e > 0)).cast("long").alias("above"), F.aggregate(F.transform("g", F.abs), F.lit(0).cast("long"), lambda a, e: a + e).alias("l1"))


@query("fn_map", "SELECT n_regionkey, count(*) AS n, min(n_nationkey) AS lo FROM nation GROUP BY n_regionkey")
def _(s, d):
    by = read(s, d, "nation").groupBy("n_regionkey").agg(F.map_from_entries(F.collect_list(F.struct("n_nationkey", "n_name"))).alias("m"))
    return by.select("n_regionkey", F.size(F.map_keys("m")).cast("long").alias("n"), F.array_min(F.map_keys("m")).alias("lo"))


@query("fn_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def _(s, d):
    return read(s, d, "events", "event_id", "props").select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


@query("fn_hash", "SELECT c_custkey, md5(c_name) AS h, sha256(c_name) AS s FROM customer")
def _(s, d):
    return read(s, d, "customer", "c_custkey", "c_name").select("c_custkey", F.md5(F.col("c_name").cast("binary")).alias("h"), F.sha2(F.col("c_name").cast("binary"), 256).alias("s"))


@query("fn_conditional", "SELECT doc_id, coalesce(toxic, -1) AS toxic, nullif(quality, 1) AS not_good, CASE WHEN toxic = 1 THEN 't' WHEN toxic IS NULL THEN '?' ELSE 'c' END AS kind FROM documents LEFT JOIN labels USING (doc_id)")
def _(s, d):
    j = read(s, d, "documents", "doc_id").join(read(s, d, "labels"), "doc_id", "left")
    return j.select("doc_id", F.coalesce("toxic", F.lit(-1)).alias("toxic"), F.nullif("quality", F.lit(1)).alias("not_good"), F.when(F.col("toxic") == 1, "t").when(F.col("toxic").isNull(), "?").otherwise("c").alias("kind"))


_SUB = {
    "sub_scalar": "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT 1.9 * avg(o_totalprice) FROM orders)",
    "sub_exists": "SELECT s_suppkey FROM supplier WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_suppkey = s_suppkey AND l_quantity = 50)",
    "sub_in_correlated": "SELECT p_partkey FROM part p WHERE p_retailprice = (SELECT max(p_retailprice) FROM part q WHERE q.p_brand = p.p_brand)",
    "cte_values": "WITH w(flag, weight) AS (VALUES ('A', 1), ('N', 2), ('R', 3)) SELECT l_returnflag, CAST(sum(weight) AS BIGINT) AS w FROM lineitem JOIN w ON flag = l_returnflag GROUP BY l_returnflag",
}


def _sql_text(text):
    def build(s, d):
        for t in ("orders", "supplier", "lineitem", "part"):
            read(s, d, t).createOrReplaceTempView(t)
        return s.sql(text.replace("WITH w(flag, weight) AS (VALUES", "WITH w AS (SELECT col1 AS flag, col2 AS weight FROM VALUES").replace("('R', 3))", "('R', 3))"))

    return build


for _name, _text in _SUB.items():
    query(_name, _text)(_sql_text(_text))


# ---- features ------------------------------------------------------------------------------------------------------------------------


@query("feat_standardise", "SELECT l_orderkey, l_linenumber, floor((l_quantity - m) / sd * 1000000 + 0.5) AS z FROM lineitem, (SELECT avg(l_quantity) AS m, sqrt((CAST(sum(l_quantity * l_quantity) AS DOUBLE) - count(*) * avg(l_quantity) * avg(l_quantity)) / (count(*) - 1)) AS sd FROM lineitem)")
def _(s, d):
    li = read(s, d, "lineitem", "l_orderkey", "l_linenumber", "l_quantity")
    q = F.col("l_quantity")
    sd = F.sqrt((F.sum(q * q) - F.count("*") * F.avg(q) * F.avg(q)) / (F.count("*") - 1))
    stats = li.agg(F.avg(q).alias("m"), sd.alias("sd"))
    return li.crossJoin(F.broadcast(stats)).select("l_orderkey", "l_linenumber", F.floor((q - F.col("m")) / F.col("sd") * 1000000 + 0.5).cast("double").alias("z"))


@query("feat_one_hot", "SELECT l_orderkey, l_linenumber, CAST(l_returnflag = 'A' AS INT) AS is_a, CAST(l_returnflag = 'N' AS INT) AS is_n, CAST(l_returnflag = 'R' AS INT) AS is_r FROM lineitem")
def _(s, d):
    hot = [(F.col("l_returnflag") == v).cast("int").alias(f"is_{v.lower()}") for v in "ANR"]
    return read(s, d, "lineitem", "l_orderkey", "l_linenumber", "l_returnflag").select("l_orderkey", "l_linenumber", *hot)


@query("feat_hash_tokens", r"SELECT doc_id, bucket, count(*) AS tf FROM (SELECT doc_id, CAST('0x' || substr(md5(w), 1, 3) AS BIGINT) AS bucket FROM (SELECT doc_id, unnest(list_filter(string_split(text, ' '), lambda w: w <> '')) AS w FROM documents)) GROUP BY doc_id, bucket")
def _(s, d):
    w = read(s, d, "documents", "doc_id", "text").select("doc_id", F.explode(F.split("text", " ")).alias("w")).where("w <> ''")
    return w.groupBy("doc_id", F.conv(F.substring(F.md5(F.col("w").cast("binary")), 1, 3), 16, 10).cast("long").alias("bucket")).agg(F.count("*").alias("tf"))


@query("feat_split", f"SELECT vec_id, CASE WHEN {draw_sql(21, 'vec_id')} < 0.8 THEN 'train' ELSE 'test' END AS part FROM embeddings")
def _(s, d):
    return read(s, d, "embeddings", "vec_id").select("vec_id", F.when(draw(21, F.col("vec_id"), mode="portable") < 0.8, "train").otherwise("test").alias("part"))


@query("feat_minibatch", f"SELECT vec_id FROM embeddings WHERE {draw_sql(22, '3', 'vec_id')} < 0.25")
def _(s, d):
    return read(s, d, "embeddings", "vec_id").where(draw(22, F.lit(3), F.col("vec_id"), mode="portable") < 0.25)


@query("feat_allocate_even", "SELECT vec_id, CAST((row_number() OVER (ORDER BY vec_id) - 1) * 10 // (SELECT count(*) FROM embeddings) AS BIGINT) AS worker FROM embeddings")
def _(s, d):
    from terse.operators.allocate import assign

    return assign(read(s, d, "embeddings", "vec_id"), 10, "even", "vec_id")


@query("feat_allocate_hash", f"SELECT vec_id, CAST(floor({draw_sql(23, 'vec_id')} * 10) AS BIGINT) AS worker FROM embeddings")
def _(s, d):
    return read(s, d, "embeddings", "vec_id").select("vec_id", F.floor(draw(23, F.col("vec_id"), mode="portable") * 10).cast("long").alias("worker"))


@query("feat_allocate_label_skew", "SELECT vec_id, CAST((row_number() OVER (ORDER BY label, vec_id) - 1) * 10 // (SELECT count(*) FROM embeddings) AS BIGINT) AS worker FROM embeddings")
def _(s, d):
    from terse.operators.allocate import assign

    return assign(read(s, d, "embeddings", "vec_id", "label"), 10, "label_skew", "vec_id").select("vec_id", "worker")


@query("feat_lineitem_planted", "SELECT l_orderkey * 8 + l_linenumber AS row_id, l_orderkey % 10 AS worker, CAST(floor((2 * (l_quantity - 25) / 15 - l_discount * 20 + (l_linenumber - 4) / 2) * 1000 + 0.5) AS BIGINT) AS y FROM lineitem")
def _(s, d):
    y = 2 * (F.col("l_quantity") - 25) / 15 - F.col("l_discount") * 20 + (F.col("l_linenumber") - 4) / 2
    return read(s, d, "lineitem", "l_orderkey", "l_linenumber", "l_quantity", "l_discount").select((F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("row_id"), (F.col("l_orderkey") % 10).alias("worker"), F.floor(y * 1000 + 0.5).cast("long").alias("y"))


@query("feat_event_samples", "SELECT event_id, event_type, extract(hour FROM ts) AS hour, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, value / 50 AS y FROM events")
def _(s, d):
    return read(s, d, "events").select("event_id", "event_type", F.hour("ts").cast("long").alias("hour"), F.get_json_object("props", "$.k").cast("long").alias("k"), (F.col("value") / 50).alias("y"))


@query("feat_page_text", r"SELECT page_id, length(regexp_replace(regexp_replace(html, '<[^>]*>', ' ', 'g'), ' +', ' ', 'g')) AS n_chars FROM pages")
def _(s, d):
    return read(s, d, "pages", "page_id", "html").select("page_id", F.char_length(F.regexp_replace(F.regexp_replace("html", "<[^>]*>", " "), " +", " ")).cast("long").alias("n_chars"))


@query("feat_conversation_turns", "SELECT conv_id, turn, length(text) AS n, lag(length(text)) OVER (PARTITION BY conv_id ORDER BY turn) AS before FROM conversations")
def _(s, d):
    n = F.char_length("text").cast("long")
    return read(s, d, "conversations").select("conv_id", "turn", n.alias("n"), F.lag(n).over(Window.partitionBy("conv_id").orderBy("turn")).alias("before"))


@query("feat_decontaminate", "SELECT doc_id FROM documents WHERE NOT EXISTS (SELECT 1 FROM benchmark WHERE contains(documents.text, benchmark.text))")
def _(s, d):
    """Documents that hold no benchmark text as it stands: candidates share a passage's opening words, then the whole is compared."""
    docs, items = read(s, d, "documents", "doc_id", "text"), read(s, d, "benchmark", "item_id", "text").withColumnRenamed("text", "passage")
    heads = items.select("passage", F.array_join(F.slice(F.split("passage", " "), 2, 4), " ").alias("k"))
    runs = docs.select("doc_id", F.split("text", " ").alias("w")).withColumn("n", F.greatest(F.size("w") - 3, F.lit(1)))
    grams = runs.select("doc_id", F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), F.col("n")), lambda i: F.array_join(F.slice("w", i, 4), " ")))).alias("k"))
    hit = grams.join(F.broadcast(heads), "k").join(docs, "doc_id").where(F.col("text").contains(F.col("passage"))).select("doc_id").distinct()
    return docs.select("doc_id").join(hit, "doc_id", "left_anti")
