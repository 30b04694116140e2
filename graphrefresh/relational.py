"""The relational operations that users of the methods need, each as a query and as SQL for another engine."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphrefresh.functions.weights import weight
from graphrefresh.operators import joins, windows
from graphrefresh.sources import graphs
from graphrefresh.sources.graphs import table

_WIDE = [[weight(1, i, j) for j in range(64)] for i in range(4)]


def _micros(column: str = "ts"):
    return F.unix_micros(F.col(column).cast("timestamp"))


def _events(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "events", "event_id", "user_id", "event_type", "value", "props", "ts").withColumn("us", _micros())


def join_as_of(spark: SparkSession, sf: str) -> DataFrame:
    rows = _events(spark, sf)
    left = rows.where("event_type = 'purchase'").select("event_id", "user_id")
    right = rows.where("event_type = 'view'").select("event_id", "user_id", F.col("value").alias("seen"))
    return joins.as_of(left, right, "user_id", "event_id", "seen", 1000)


def join_interval(spark: SparkSession, sf: str) -> DataFrame:
    rows = _events(spark, sf)
    pairs = joins.within(rows.where("event_type = 'purchase'").select("event_id", "user_id", "us"), rows.where("event_type = 'click'").select("event_id", "user_id", "us"), "user_id", "us", 6 * 3600 * 1_000_000)
    return pairs.groupBy("event_id").agg(F.count(F.lit(1)).alias("clicks"), F.max("event_id_r").alias("last_click"))


def join_semi_anti_outer(spark: SparkSession, sf: str) -> DataFrame:
    """Customers by whether they ordered: kept by a semi join, kept by an anti join, and matched by a full join."""
    c, o = table(spark, sf, "customer", "c_custkey", "c_mktsegment"), table(spark, sf, "orders", "o_custkey")
    own = o.groupBy(F.col("o_custkey").alias("c_custkey")).agg(F.count(F.lit(1)).alias("n"))
    count = lambda df, name: df.groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias(name))
    semi, anti = count(c.join(own, "c_custkey", "left_semi"), "ordered"), count(c.join(own, "c_custkey", "left_anti"), "idle")
    both = c.join(own, "c_custkey", "full").groupBy("c_mktsegment").agg(F.sum(F.coalesce("n", F.lit(0))).alias("orders"))
    return both.join(semi, "c_mktsegment", "left").join(anti, "c_mktsegment", "left").select("c_mktsegment", F.coalesce("ordered", F.lit(0)).alias("ordered"), F.coalesce("idle", F.lit(0)).alias("idle"), "orders")


def join_broadcast_checked(spark: SparkSession, sf: str) -> DataFrame:
    nation = joins.checked_broadcast(table(spark, sf, "nation", "n_nationkey", "n_name"))
    rows = table(spark, sf, "supplier", "s_suppkey", "s_nationkey").join(nation, F.col("s_nationkey") == F.col("n_nationkey"))
    return rows.groupBy("n_name").agg(F.count(F.lit(1)).alias("suppliers"))


def topk_nearest(spark: SparkSession, sf: str) -> DataFrame:
    return joins.nearest(table(spark, sf, "embeddings", "vec_id", "embedding"), 10).select("query", "vec_id", "rank")


def topk_hubs(spark: SparkSession, sf: str) -> DataFrame:
    deg = graphs.supp_part(spark, sf).groupBy(F.col("dst").alias("vid")).agg(F.count(F.lit(1)).alias("deg"))
    return deg.orderBy(F.desc("deg"), "vid").limit(20)


def topk_per_vertex(spark: SparkSession, sf: str) -> DataFrame:
    rows = table(spark, sf, "lineitem", "l_partkey", "l_suppkey", "l_quantity").groupBy("l_partkey", "l_suppkey").agg(F.sum("l_quantity").alias("quantity"))
    return windows.top_per(rows, "l_partkey", 3, F.desc("quantity"), "l_suppkey")


def window_running(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    rows = table(spark, sf, "orders", "o_custkey", "o_orderkey", "o_orderdate")
    return rows.select("o_custkey", "o_orderkey", F.count(F.lit(1)).over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("so_far"), F.row_number().over(w).alias("n"), F.rank().over(Window.partitionBy("o_custkey").orderBy("o_orderdate")).alias("r"), F.dense_rank().over(Window.partitionBy("o_custkey").orderBy("o_orderdate")).alias("dr"), F.ntile(4).over(w).alias("quarter"), F.lag("o_orderkey").over(w).alias("before"), F.lead("o_orderkey").over(w).alias("after"), F.round(F.percent_rank().over(w), 6).alias("pr"))


def window_range_rate(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("us").rangeBetween(-24 * 3600 * 1_000_000, 0)
    return _events(spark, sf).select("event_id", F.count(F.lit(1)).over(w).alias("day_events"))


def window_tumbling(spark: SparkSession, sf: str) -> DataFrame:
    day = 86_400_000_000
    return _events(spark, sf).groupBy(F.floor(F.col("us") / day).alias("day"), "event_type").agg(F.count(F.lit(1)).alias("n"))


def window_sliding(spark: SparkSession, sf: str) -> DataFrame:
    """Windows of a day every six hours; each row falls in four."""
    rows = _events(spark, sf).groupBy(F.window("ts", "1 day", "6 hours").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return rows.select(F.unix_micros(F.col("w.start").cast("timestamp")).alias("start_us"), "n")


def session_windows(spark: SparkSession, sf: str) -> DataFrame:
    rows = windows.sessions(_events(spark, sf), "user_id", "ts", "6 hours")
    return rows.select("user_id", _micros("start").alias("start_us"), _micros("last").alias("last_us"), "n")


def batch_cut(spark: SparkSession, sf: str) -> DataFrame:
    """The stream of the newest edges in a hundred equal batches."""
    _, stream = graphs.split(graphs.transitions(spark, sf))
    rows = stream.withColumn("us", _micros())
    return windows.batches(rows, 100, F.floor(F.col("us") / 3_600_000_000), "us", "src", "dst").select("src", "dst", "batch")


def base_stream_split(spark: SparkSession, sf: str) -> DataFrame:
    base, stream = graphs.split(graphs.transitions(spark, sf))
    return base.select(F.lit("base").alias("part"), "src", "dst").unionByName(stream.select(F.lit("stream").alias("part"), "src", "dst")).groupBy("part").agg(F.count(F.lit(1)).alias("edges"), F.sum("src").alias("src_sum"))


def degree_profile(spark: SparkSession, sf: str) -> DataFrame:
    deg = graphs.transitions(spark, sf).groupBy(F.col("dst").alias("vid")).agg(F.count(F.lit(1)).alias("deg"))
    return deg.agg(F.count(F.lit(1)).alias("vertices"), F.sum("deg").alias("edges"), F.max("deg").alias("most"), F.expr("percentile(deg, 0.5)").alias("median"), F.expr("percentile(deg, 0.99)").alias("p99"), F.round(F.stddev_samp("deg"), 6).alias("sd"))


def net_updates(spark: SparkSession, sf: str) -> DataFrame:
    """Net effect of the user-item updates, errors being deletions: the last operation on an edge holds."""
    rows = _events(spark, sf).select(F.col("event_id").alias("seq"), F.when(F.col("event_type") == "error", "-").otherwise("+").alias("op"), (2 * F.col("user_id")).alias("src"), (2 * F.get_json_object("props", "$.k").cast("long") + 1).alias("dst"), F.lit("contains").alias("rel"), F.lit(1.0).alias("w"))
    none = rows.select("src", "dst", "rel", "w").limit(0)
    ins, _ = graphs.net(none, rows)
    return ins.select("src", "dst")


def set_operations(spark: SparkSession, sf: str) -> DataFrame:
    """Parts by brand in common between two supplier halves, and those in one only, duplicates counted."""
    rows = table(spark, sf, "lineitem", "l_partkey", "l_suppkey")
    a, b = (rows.where(F.pmod("l_suppkey", F.lit(2)) == i).select("l_partkey") for i in (0, 1))
    count = lambda df, name: df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("operation"), "n")
    return count(a.intersect(b), "intersect").unionByName(count(a.subtract(b), "except")).unionByName(count(a.exceptAll(b), "except_all")).unionByName(count(a.union(b).distinct(), "union"))


def rollup_results(spark: SparkSession, sf: str) -> DataFrame:
    rows = table(spark, sf, "lineitem", "l_returnflag", "l_shipdate", "l_quantity").withColumn("y", F.year("l_shipdate"))
    return rows.rollup("l_returnflag", "y").agg(F.count(F.lit(1)).alias("lines"), F.sum("l_quantity").alias("quantity"))


def cube_results(spark: SparkSession, sf: str) -> DataFrame:
    rows = _events(spark, sf).withColumn("day", F.floor(F.col("us") / 86_400_000_000) % 7)
    return rows.cube("event_type", "day").agg(F.count(F.lit(1)).alias("n"))


def pivot_results(spark: SparkSession, sf: str) -> DataFrame:
    rows = _events(spark, sf)
    out = rows.groupBy("user_id").pivot("event_type", ["view", "click", "purchase", "signup", "error"]).agg(F.count(F.lit(1)))
    return out.na.fill(0)


def json_props(spark: SparkSession, sf: str) -> DataFrame:
    rows = _events(spark, sf).withColumn("p", F.from_json("props", "k long"))
    return rows.where("p.k < 10").groupBy(F.col("p.k").alias("k")).agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("event_type") == "error").alias("errors"))


def neighbour_lists(spark: SparkSession, sf: str) -> DataFrame:
    rows = graphs.transitions(spark, sf).groupBy("src").agg(F.array_sort(F.collect_list("dst")).alias("n"))
    return rows.select("src", F.array_join(F.transform("n", lambda x: x.cast("string")), ",").alias("neighbours"), F.size("n").alias("deg"))


def distinct_ends(spark: SparkSession, sf: str) -> DataFrame:
    e = graphs.order_part(spark, sf)
    return e.groupBy("rel").agg(F.count_distinct("src").alias("sources"), F.count_distinct("dst").alias("targets"), F.max_by("src", F.struct("ts", "src", "dst")).alias("newest"), F.min_by("src", F.struct("ts", "src", "dst")).alias("oldest"))


def op_vector_sum(spark: SparkSession, sf: str) -> DataFrame:
    return joins.vector_sum(table(spark, sf, "embeddings", "label", "embedding"), "label", "embedding").select("label", "pos", F.round("total", 6).alias("total"))


def op_cosine(spark: SparkSession, sf: str) -> DataFrame:
    """Each vector with the one of the next id."""
    rows = table(spark, sf, "embeddings", "vec_id", "embedding")
    nxt = rows.select((F.col("vec_id") - 1).alias("vec_id"), F.col("embedding").alias("other"))
    return rows.join(nxt, "vec_id").select("vec_id", F.round(joins.cosine(F.col("embedding"), F.col("other")), 6).alias("cosine"))


def op_matmul(spark: SparkSession, sf: str) -> DataFrame:
    rows = joins.matmul(table(spark, sf, "embeddings", "vec_id", "embedding"), "embedding", _WIDE)
    return rows.select("vec_id", *[F.round(F.col("out")[i], 6).alias(f"o{i}") for i in range(4)])


def op_softmax_edges(spark: SparkSession, sf: str) -> DataFrame:
    """Scores of a destination's edges that add up to 1, by a sum that is joined back."""
    e = graphs.with_weights(graphs.transitions(spark, sf)).withColumn("x", F.exp("w"))
    total = e.groupBy("dst").agg(F.sum("x").alias("z"))
    return e.join(total, "dst").select("src", "dst", F.round(F.col("x") / F.col("z"), 9).alias("score"))


def sql_functions(spark: SparkSession, sf: str) -> DataFrame:
    windows.register_functions(spark)
    rows = table(spark, sf, "embeddings", "vec_id", "embedding").withColumn("e", F.col("embedding").cast("array<double>"))
    return rows.selectExpr("vec_id", "round(vec_dot(e, vec_add(e, e)), 6) AS d", "round(leaky_relu(vec_scale(e, 2e0)[0]), 6) AS l")


_E = "SELECT event_id, user_id, event_type, value, props, ts, epoch_us(ts::TIMESTAMP) AS us FROM events"
_K = "CAST(json_extract_string(props, '$.k') AS BIGINT)"
_T = f"SELECT k AS src, nxt AS dst, min(ts) AS ts FROM (SELECT {_K} AS k, lead({_K}) OVER (PARTITION BY user_id ORDER BY event_id) AS nxt, ts FROM events) WHERE nxt IS NOT NULL GROUP BY 1, 2"
_DOT = "list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[])"
_LEN = "sqrt(list_dot_product({0}.embedding::DOUBLE[], {0}.embedding::DOUBLE[]))"
_COS = f"{_DOT} / ({_LEN.format('a')} * {_LEN.format('b')})"
_DAY = 86_400_000_000

#: name: (query, SQL or None)
ENTRIES: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str | None]] = {
    "join_as_of": (join_as_of, f"SELECT p.event_id, p.user_id, v.value AS seen FROM (SELECT * FROM ({_E}) WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM ({_E}) WHERE event_type = 'view') v ON p.user_id = v.user_id AND p.event_id > v.event_id"),
    "join_interval": (join_interval, f"SELECT p.event_id, count(*) AS clicks, max(c.event_id) AS last_click FROM ({_E}) p JOIN ({_E}) c ON p.user_id = c.user_id AND c.us BETWEEN p.us - 21600000000 AND p.us WHERE p.event_type = 'purchase' AND c.event_type = 'click' GROUP BY 1"),
    "join_semi_anti_outer": (join_semi_anti_outer, "WITH o AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1) SELECT c_mktsegment, count(o_custkey) AS ordered, count(*) - count(o_custkey) AS idle, coalesce(sum(n), 0)::BIGINT AS orders FROM customer LEFT JOIN o ON c_custkey = o_custkey GROUP BY 1"),
    "join_broadcast_checked": (join_broadcast_checked, "SELECT n_name, count(*) AS suppliers FROM supplier JOIN nation ON s_nationkey = n_nationkey GROUP BY 1"),
    "topk_nearest": (topk_nearest, f"SELECT * FROM (SELECT a.vec_id AS query, b.vec_id AS vec_id, row_number() OVER (PARTITION BY a.vec_id ORDER BY round({_COS}, 9) DESC, b.vec_id)::INTEGER AS rank FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id) WHERE rank <= 10"),
    "topk_hubs": (topk_hubs, "WITH p AS (SELECT DISTINCT 4 * l_suppkey + 3 AS a, 4 * l_partkey + 1 AS b FROM lineitem) SELECT vid, count(*) AS deg FROM (SELECT a AS vid FROM p UNION ALL SELECT b FROM p) GROUP BY 1 ORDER BY deg DESC, vid LIMIT 20"),
    "topk_per_vertex": (topk_per_vertex, "SELECT * FROM (SELECT l_partkey, l_suppkey, sum(l_quantity) AS quantity, row_number() OVER (PARTITION BY l_partkey ORDER BY sum(l_quantity) DESC, l_suppkey)::INTEGER AS place FROM lineitem GROUP BY 1, 2) WHERE place <= 3"),
    "window_running": (window_running, "SELECT o_custkey, o_orderkey, count(*) OVER (w ROWS UNBOUNDED PRECEDING) AS so_far, (row_number() OVER w)::INTEGER AS n, (rank() OVER (PARTITION BY o_custkey ORDER BY o_orderdate))::INTEGER AS r, (dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderdate))::INTEGER AS dr, (ntile(4) OVER w)::INTEGER AS quarter, lag(o_orderkey) OVER w AS before, lead(o_orderkey) OVER w AS after, round(percent_rank() OVER w, 6) AS pr FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)"),
    "window_range_rate": (window_range_rate, f"SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY us RANGE BETWEEN {_DAY} PRECEDING AND CURRENT ROW) AS day_events FROM ({_E})"),
    "window_tumbling": (window_tumbling, f"SELECT us // {_DAY} AS day, event_type, count(*) AS n FROM ({_E}) GROUP BY 1, 2"),
    "window_sliding": (window_sliding, f"SELECT (us // 21600000000 - i) * 21600000000 AS start_us, count(*) AS n FROM ({_E}), (SELECT unnest([0, 1, 2, 3]) AS i) GROUP BY 1"),
    "session_windows": (session_windows, f"SELECT user_id, min(us) AS start_us, max(us) AS last_us, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY us, event_id) AS s FROM (SELECT *, CASE WHEN us - lag(us) OVER (PARTITION BY user_id ORDER BY us, event_id) <= 21600000000 THEN 0 ELSE 1 END AS fresh FROM ({_E}))) GROUP BY user_id, s"),
    "batch_cut": (batch_cut, f"WITH t AS (SELECT src, dst, epoch_us(ts::TIMESTAMP) AS us FROM ({_T})), c AS (SELECT quantile_disc(us, 0.9) AS cut FROM t), s AS (SELECT t.* FROM t, c WHERE us > cut) SELECT src, dst, ((row_number() OVER (ORDER BY us, src, dst) - 1) * 100) // (SELECT count(*) FROM s) AS batch FROM s"),
    "base_stream_split": (base_stream_split, f"WITH t AS (SELECT src, dst, epoch_us(ts::TIMESTAMP) AS us FROM ({_T})), c AS (SELECT quantile_disc(us, 0.9) AS cut FROM t) SELECT CASE WHEN us > cut THEN 'stream' ELSE 'base' END AS part, count(*) AS edges, sum(src)::BIGINT AS src_sum FROM t, c GROUP BY 1"),
    "degree_profile": (degree_profile, f"SELECT count(*) AS vertices, sum(deg)::BIGINT AS edges, max(deg) AS most, quantile_cont(deg, 0.5) AS median, quantile_cont(deg, 0.99) AS p99, round(stddev_samp(deg), 6) AS sd FROM (SELECT dst, count(*) AS deg FROM ({_T}) GROUP BY 1)"),
    "net_updates": (net_updates, f"SELECT 2 * user_id AS src, 2 * {_K} + 1 AS dst FROM events GROUP BY 1, 2 HAVING arg_max(event_type, event_id) <> 'error'"),
    "set_operations": (set_operations, "WITH a AS (SELECT l_partkey FROM lineitem WHERE l_suppkey % 2 = 0), b AS (SELECT l_partkey FROM lineitem WHERE l_suppkey % 2 = 1) SELECT 'intersect' AS operation, count(*) AS n FROM (FROM a INTERSECT FROM b) UNION ALL SELECT 'except', count(*) FROM (FROM a EXCEPT FROM b) UNION ALL SELECT 'except_all', count(*) FROM (FROM a EXCEPT ALL FROM b) UNION ALL SELECT 'union', count(*) FROM (FROM a UNION FROM b)"),
    "rollup_results": (rollup_results, "SELECT l_returnflag, year(l_shipdate)::INTEGER AS y, count(*) AS lines, sum(l_quantity) AS quantity FROM lineitem GROUP BY ROLLUP (l_returnflag, y)"),
    "cube_results": (cube_results, f"SELECT event_type, (us // {_DAY}) % 7 AS day, count(*) AS n FROM ({_E}) GROUP BY CUBE (event_type, day)"),
    "pivot_results": (pivot_results, "SELECT user_id, " + ", ".join(f"count(*) FILTER (event_type = '{t}') AS {t}" for t in ("view", "click", "purchase", "signup", "error")) + " FROM events GROUP BY 1"),
    "json_props": (json_props, f"SELECT {_K} AS k, count(*) AS n, count(*) FILTER (event_type = 'error') AS errors FROM events WHERE {_K} < 10 GROUP BY 1"),
    "neighbour_lists": (neighbour_lists, f"SELECT src, string_agg(dst::VARCHAR, ',' ORDER BY dst) AS neighbours, count(*)::INTEGER AS deg FROM ({_T}) GROUP BY 1"),
    "distinct_ends": (distinct_ends, "WITH p AS (SELECT 4 * l_orderkey AS a, 4 * l_partkey + 1 AS b, min(l_shipdate) AS ts FROM lineitem GROUP BY 1, 2), e AS (SELECT a AS src, b AS dst, 'contains' AS rel, ts FROM p UNION ALL SELECT b, a, 'in_order', ts FROM p) SELECT rel, count(DISTINCT src) AS sources, count(DISTINCT dst) AS targets, arg_max(src, (ts, src, dst)) AS newest, arg_min(src, (ts, src, dst)) AS oldest FROM e GROUP BY 1"),
    "op_vector_sum": (op_vector_sum, "SELECT label, (pos - 1)::INTEGER AS pos, round(sum(embedding[pos]::DOUBLE), 6) + 0.0 AS total FROM embeddings, (SELECT unnest(range(1, 65)) AS pos) GROUP BY label, pos"),
    "op_cosine": (op_cosine, f"SELECT a.vec_id, round({_COS}, 6) + 0.0 AS cosine FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1"),
    "op_matmul": (op_matmul, "SELECT vec_id, " + ", ".join(f"round(list_dot_product(embedding::DOUBLE[], {w}::DOUBLE[]), 6) + 0.0 AS o{i}" for i, w in enumerate(_WIDE)) + " FROM embeddings"),
    "op_softmax_edges": (op_softmax_edges, f"WITH e AS (SELECT src, dst, exp(((src + dst) % 4 + 1) / 4.0::DOUBLE) AS x FROM ({_T})) SELECT src, dst, round(x / sum(x) OVER (PARTITION BY dst), 9) AS score FROM e"),
    "sql_functions": (sql_functions, "SELECT vec_id, round(2 * list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[]), 6) AS d, round(CASE WHEN embedding[1] > 0 THEN 1 ELSE 0.2::DOUBLE END * 2 * embedding[1]::DOUBLE, 6) + 0.0 AS l FROM embeddings"),
}
QUERIES = {n: q for n, (q, _) in ENTRIES.items()}
ORACLES = {n: s for n, (_, s) in ENTRIES.items() if s}
