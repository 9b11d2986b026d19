"""What surrounds the methods: relational primitives on graphs and tables, sources and sinks, user functions, streams."""

from __future__ import annotations


from pyspark.sql import Window
from pyspark.sql import functions as F

from gpart import oracles as sql
from gpart.functions import columns, udf
from gpart.operators import clean, clustering, contraction, gains
from gpart.registry import built, hashed
from gpart.sources import graphs, io
from gpart.streaming import events as streams

QUERIES: dict[str, tuple] = {}


def query(name: str, oracle: str | None):
    def put(f):
        QUERIES[name] = (f, oracle)
        return f

    return put


def g(s, d):
    return built(s, d, "cust_supp")


def micros(df, *names):
    """Times as microseconds, which every engine writes alike."""
    return df.withColumns({n: F.unix_micros(F.col(n).cast("timestamp")) for n in names})


def either(name):
    return F.coalesce(F.col(name).cast("string"), F.lit("all")).alias(name)


CS = "cust_supp"
EDGES = sql.full(CS, "SELECT src, dst, w FROM edges")

# ---- sources and sinks ----

for _format in ("parquet", "orc", "csv", "json"):
    query(f"io_roundtrip_{_format}", EDGES)(lambda s, d, f=_format: io.roundtrip(g(s, d).edges, f))
query("io_adjacency_text", EDGES)(lambda s, d: io.read_adjacency(s, io.write_adjacency(g(s, d), io.scratch(s))))
query("io_partitioned_levels", sql.full(CS, "SELECT src, dst, w FROM edges WHERE src % 4 = 2"))(lambda s, d: io.by_level(g(s, d).edges.withColumn("level", (F.col("src") % 4).cast("int"))).where("level = 2").select("src", "dst", "w"))
query("io_bucketed_join", sql.full(CS, "SELECT e.src AS id, count(*) AS n FROM edges e JOIN part p ON p.id = e.src WHERE p.block = 1 GROUP BY 1", sql.blocks(4)))(lambda s, d: io.ranged(g(s, d).edges, "src").join(hashed(g(s, d), 4).withColumnRenamed("id", "src"), "src").where("block = 1").groupBy(F.col("src").alias("id")).agg(F.count("*").alias("n")))

# ---- filters, joins ----

query("rel_degree_filter", sql.full(CS, "SELECT id, degree FROM deg WHERE degree BETWEEN 20 AND 60", sql.DEGREES))(lambda s, d: g(s, d).edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("degree")).where(F.col("degree").between(20, 60)))
query("rel_url_filters", "SELECT page_id FROM pages WHERE url LIKE '%example.org%' AND regexp_matches(url, '/(en|de)/')")(lambda s, d: graphs.table(s, d, "pages").where(F.col("url").like("%example.org%") & F.col("url").rlike("/(en|de)/")).select("page_id"))
query("rel_null_safe_equality", "SELECT count(*) AS n FROM orders a JOIN (SELECT o_custkey, nullif(o_custkey % 3, 0) AS m FROM orders) b USING (o_custkey) WHERE nullif(a.o_custkey % 3, 0) IS NOT DISTINCT FROM b.m")(lambda s, d: graphs.table(s, d, "orders").select("o_custkey", F.nullif(F.col("o_custkey") % 3, F.lit(0)).alias("x")).join(graphs.table(s, d, "orders").select("o_custkey", F.nullif(F.col("o_custkey") % 3, F.lit(0)).alias("y")), "o_custkey").where(F.col("x").eqNullSafe(F.col("y"))).agg(F.count("*").alias("n")))
query("rel_left_anti_isolated", sql.full("event_chain", "SELECT id FROM vertices WHERE id NOT IN (SELECT src FROM edges)"))(lambda s, d: built(s, d, "event_chain").vertices.join(built(s, d, "event_chain").edges.select(F.col("src").alias("id")), "id", "left_anti").select("id"))
query("rel_full_outer_delta", sql.full(CS, "SELECT coalesce(a.id, b.id) AS id, coalesce(a.w, 0) - coalesce(b.w, 0) AS delta FROM (SELECT src AS id, CAST(sum(w) AS BIGINT) AS w FROM edges WHERE dst % 2 = 0 GROUP BY 1) a FULL JOIN (SELECT src AS id, CAST(sum(w) AS BIGINT) AS w FROM edges WHERE dst % 2 = 1 GROUP BY 1) b ON a.id = b.id"))(
    lambda s, d: g(s, d).edges.where("dst % 2 = 0").groupBy(F.col("src").alias("id")).agg(F.sum("w").alias("x")).join(g(s, d).edges.where("dst % 2 = 1").groupBy(F.col("src").alias("id")).agg(F.sum("w").alias("y")), "id", "full_outer").select("id", (F.coalesce("x", F.lit(0)) - F.coalesce("y", F.lit(0))).alias("delta"))
)
query("rel_two_hop_counts", sql.full("page_path", "SELECT a.src AS id, count(DISTINCT b.dst) AS n FROM edges a JOIN edges b ON a.dst = b.src WHERE b.dst <> a.src GROUP BY 1"))(lambda s, d: clean.two_hop_counts(built(s, d, "page_path")))


@query("rel_interval_join_events", "SELECT count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR")
def _(s, d):
    """Pairs of a user's events within six hours: bucketed by six hours, so that a range join is an equality join."""
    bucket = F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 21_600_000_000)
    ev = graphs.table(s, d, "events").select("user_id", "ts", bucket.alias("b"))
    left = ev.select("user_id", F.col("ts").alias("t0"), F.explode(F.array(F.col("b"), F.col("b") + 1)).alias("b"))
    return left.join(ev, ["user_id", "b"]).where((F.col("ts") > F.col("t0")) & (F.unix_micros(F.col("ts").cast("timestamp")) <= F.unix_micros(F.col("t0").cast("timestamp")) + 21_600_000_000)).agg(F.count("*").alias("n"))


@query("rel_asof_join_events", "SELECT o_orderkey, coalesce(e.event_id, -1) AS event_id FROM (SELECT o_orderkey, o_custkey % 100 AS user_id, o_orderdate FROM orders) o ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events GROUP BY 1, 2) e ON o.user_id = e.user_id AND o.o_orderdate >= e.ts")
def _(s, d):
    """Each order with its user's last event before it: one sorted pass over the union of both, no pairs."""
    ev = graphs.table(s, d, "events").groupBy("user_id", "ts").agg(F.max("event_id").alias("event_id")).select("user_id", "ts", "event_id", F.lit(None).cast("long").alias("o_orderkey"), F.lit(0).alias("kind"))
    orders = graphs.table(s, d, "orders").select((F.col("o_custkey") % 100).alias("user_id"), F.col("o_orderdate").alias("ts"), F.lit(None).cast("long").alias("event_id"), "o_orderkey", F.lit(1).alias("kind"))
    line = Window.partitionBy("user_id").orderBy("ts", "kind").rowsBetween(Window.unboundedPreceding, 0)
    return ev.unionByName(orders).withColumn("last", F.last("event_id", ignorenulls=True).over(line)).where("kind = 1").select("o_orderkey", F.coalesce("last", F.lit(-1)).alias("event_id"))


query("rel_theta_grid", sql.full(CS, "SELECT t.tau, count(*) AS n FROM deg, (SELECT unnest([5, 10, 20, 40, 80]) AS tau) t WHERE degree >= t.tau GROUP BY 1", sql.DEGREES))(lambda s, d: g(s, d).edges.groupBy("src").agg(F.count("*").alias("degree")).join(F.broadcast(s.createDataFrame([(x,) for x in (5, 10, 20, 40, 80)], "tau int")), F.col("degree") >= F.col("tau")).groupBy("tau").agg(F.count("*").alias("n")))

# ---- aggregations, windows, sorting, sets ----

query("rel_salted_aggregate", sql.full(CS, "SELECT src AS id, CAST(sum(w) AS BIGINT) AS w FROM edges GROUP BY 1"))(lambda s, d: g(s, d).edges.groupBy("src", (columns.scramble("dst") % 8).alias("salt")).agg(F.sum("w").alias("w")).groupBy(F.col("src").alias("id")).agg(F.sum("w").alias("w")))
query("rel_cube_orders", "SELECT coalesce(CAST(a AS VARCHAR), 'all') AS a, coalesce(CAST(b AS VARCHAR), 'all') AS b, n FROM (SELECT o_custkey % 3 AS a, o_orderkey % 2 AS b, count(*) AS n FROM orders GROUP BY CUBE (1, 2))")(lambda s, d: graphs.table(s, d, "orders").select((F.col("o_custkey") % 3).alias("a"), (F.col("o_orderkey") % 2).alias("b")).cube("a", "b").agg(F.count("*").alias("n")).select(either("a"), either("b"), "n"))
query("rel_rollup_orders", "SELECT coalesce(CAST(a AS VARCHAR), 'all') AS a, coalesce(CAST(b AS VARCHAR), 'all') AS b, n FROM (SELECT o_custkey % 3 AS a, o_orderkey % 2 AS b, count(*) AS n FROM orders GROUP BY ROLLUP (1, 2))")(lambda s, d: graphs.table(s, d, "orders").select((F.col("o_custkey") % 3).alias("a"), (F.col("o_orderkey") % 2).alias("b")).rollup("a", "b").agg(F.count("*").alias("n")).select(either("a"), either("b"), "n"))
query("rel_pivot_blocks", sql.full(CS, "SELECT id % 5 AS r, count(*) FILTER (WHERE block = 0) AS b0, count(*) FILTER (WHERE block = 1) AS b1, count(*) FILTER (WHERE block = 2) AS b2 FROM part GROUP BY 1", sql.blocks(3)))(lambda s, d: hashed(g(s, d), 3).withColumn("r", F.col("id") % 5).groupBy("r").pivot("block", [0, 1, 2]).agg(F.count("id")).select("r", *[F.coalesce(F.col(str(b)), F.lit(0)).alias(f"b{b}") for b in range(3)]))
query("rel_window_ranks", sql.full(CS, "SELECT id, row_number() OVER (ORDER BY degree DESC, id) AS rn, rank() OVER (ORDER BY degree DESC) AS rk, dense_rank() OVER (ORDER BY degree DESC) AS dr FROM deg", sql.DEGREES))(lambda s, d: g(s, d).edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("n")).select("id", F.row_number().over(Window.orderBy(F.desc("n"), "id")).cast("long").alias("rn"), F.rank().over(Window.orderBy(F.desc("n"))).cast("long").alias("rk"), F.dense_rank().over(Window.orderBy(F.desc("n"))).cast("long").alias("dr")))
query("rel_range_window_events", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS n FROM events")(lambda s, d: graphs.table(s, d, "events").select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-3_600_000_000, 0)).alias("n")))
query("rel_heaviest_edges", sql.full(CS, "SELECT src, dst, w FROM edges WHERE src < dst ORDER BY w DESC, src, dst LIMIT 50"))(lambda s, d: g(s, d).edges.where("src < dst").orderBy(F.desc("w"), "src", "dst").limit(50))
query("rel_top_neighbours", sql.full(CS, "SELECT src, dst, place FROM (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY w DESC, dst) AS place FROM edges) WHERE place <= 3"))(lambda s, d: g(s, d).edges.withColumn("place", F.row_number().over(Window.partitionBy("src").orderBy(F.desc("w"), "dst")).cast("long")).where("place <= 3").select("src", "dst", "place"))
query("rel_edge_set_difference", sql.full(CS, "SELECT src, dst FROM edges WHERE src % 2 = 0 EXCEPT SELECT src, dst FROM edges WHERE dst % 3 = 0"))(lambda s, d: g(s, d).edges.where("src % 2 = 0").select("src", "dst").subtract(g(s, d).edges.where("dst % 3 = 0").select("src", "dst")))
query("rel_edge_set_intersection", sql.full(CS, "SELECT src, dst FROM edges WHERE src % 2 = 0 INTERSECT SELECT src, dst FROM edges WHERE dst % 3 = 0"))(lambda s, d: g(s, d).edges.where("src % 2 = 0").select("src", "dst").intersect(g(s, d).edges.where("dst % 3 = 0").select("src", "dst")))
query("rel_json_property", "SELECT event_type, CAST(sum(CAST(json_extract_string(props, '$.k') AS BIGINT)) AS BIGINT) AS k FROM events GROUP BY 1")(lambda s, d: graphs.table(s, d, "events").groupBy("event_type").agg(F.sum(F.get_json_object("props", "$.k").cast("long")).alias("k")))
query("rel_bit_functions", sql.full(CS, "SELECT id, id >> 3 AS hi, id & 7 AS lo, (id | 1) AS odd FROM vertices"))(lambda s, d: g(s, d).vertices.select("id", F.shiftright("id", 3).alias("hi"), F.col("id").bitwiseAND(F.lit(7)).alias("lo"), F.col("id").bitwiseOR(F.lit(1)).alias("odd")))
query("rel_percentile_degree", sql.full(CS, "SELECT quantile_cont(degree, 0.5) AS p50, quantile_cont(degree, 0.99) AS p99 FROM deg", sql.DEGREES))(lambda s, d: g(s, d).edges.groupBy("src").agg(F.count("*").alias("n")).agg(F.percentile("n", F.lit(0.5)).alias("p50"), F.percentile("n", F.lit(0.99)).alias("p99")))


query("rel_ntile_degree", sql.full(CS, "SELECT id, ntile(10) OVER (ORDER BY degree, id) AS tenth FROM deg", sql.DEGREES))(lambda s, d: g(s, d).edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("n")).select("id", F.ntile(10).over(Window.orderBy("n", "id")).cast("long").alias("tenth")))
query("rel_first_last_event", "SELECT user_id, arg_min(event_type, (ts, event_id)) AS first_type, arg_max(event_type, (ts, event_id)) AS last_type FROM events GROUP BY 1")(lambda s, d: graphs.table(s, d, "events").groupBy("user_id").agg(F.min_by("event_type", F.struct("ts", "event_id")).alias("first_type"), F.max_by("event_type", F.struct("ts", "event_id")).alias("last_type")))
query("rel_grouping_sets", "SELECT coalesce(CAST(a AS VARCHAR), 'all') AS a, coalesce(CAST(b AS VARCHAR), 'all') AS b, n FROM (SELECT o_custkey % 3 AS a, o_orderkey % 2 AS b, count(*) AS n FROM orders GROUP BY GROUPING SETS ((1), (2), ()))")(lambda s, d: graphs.table(s, d, "orders").select((F.col("o_custkey") % 3).alias("a"), (F.col("o_orderkey") % 2).alias("b")).groupingSets([["a"], ["b"], []], "a", "b").agg(F.count("*").alias("n")).select(either("a"), either("b"), "n"))
query("rel_text_functions", "SELECT doc_id, md5(lower(trim(text, ' '))) AS digest, len(string_split(text, ' ')) AS words FROM documents")(lambda s, d: graphs.table(s, d, "documents").select("doc_id", F.md5(F.lower(F.trim("text")).cast("binary")).alias("digest"), F.size(F.split("text", " ")).cast("long").alias("words")))
query("rel_date_functions", "SELECT epoch_us(date_trunc('month', o_orderdate)) AS month, count(*) AS n, CAST(max(epoch(o_orderdate)) AS BIGINT) AS last FROM orders GROUP BY 1")(lambda s, d: graphs.table(s, d, "orders").groupBy(F.unix_micros(F.date_trunc("month", F.col("o_orderdate").cast("timestamp"))).alias("month")).agg(F.count("*").alias("n"), F.max(F.unix_timestamp(F.col("o_orderdate").cast("timestamp"))).alias("last")))
query("rel_array_functions", sql.full(CS, "SELECT src AS id, CAST(sum(w * w) AS BIGINT) AS squares, CAST(max(w) AS BIGINT) AS most FROM edges WHERE w > 1 GROUP BY 1"))(lambda s, d: g(s, d).edges.groupBy(F.col("src").alias("id")).agg(F.collect_list("w").alias("ws")).select("id", F.filter("ws", lambda w: w > 1).alias("ws")).where(F.size("ws") > 0).select("id", F.aggregate(F.transform("ws", lambda w: w * w), F.lit(0).cast("long"), lambda a, x: a + x).alias("squares"), F.array_max("ws").alias("most")))
query("rel_map_functions", sql.full(CS, "SELECT e.src AS id, CAST(sum(e.w) FILTER (WHERE p.block >= 2) AS BIGINT) AS upper FROM edges e JOIN part p ON p.id = e.dst GROUP BY 1 HAVING count(*) FILTER (WHERE p.block >= 2) > 0", sql.blocks(4)))(
    lambda s, d: gains.affinity(g(s, d).edges, hashed(g(s, d), 4)).groupBy("id").agg(F.map_from_entries(F.collect_list(F.struct("block", "affinity"))).alias("m")).select("id", F.map_filter("m", lambda b, _: b >= 2).alias("m")).where(F.size("m") > 0).select("id", F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda a, x: a + x).alias("upper"))
)
query("rel_distinct_counts", "SELECT count(DISTINCT l_orderkey) AS orders, count(DISTINCT l_partkey) AS parts, count(DISTINCT (l_orderkey, l_linenumber)) AS lines FROM lineitem")(lambda s, d: graphs.table(s, d, "lineitem").agg(F.countDistinct("l_orderkey").alias("orders"), F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_orderkey", "l_linenumber").alias("lines")))
query("rel_union_all_levels", sql.full(CS, "SELECT 0 AS level, count(*) AS n FROM edges UNION ALL SELECT 1, count(*) FROM ce", *sql.lp(1), sql.CONTRACT))(lambda s, d: g(s, d).edges.agg(F.lit(0).alias("level"), F.count("*").alias("n")).unionAll(contraction.contract(g(s, d), clustering.label_propagation(g(s, d), 1))[0].edges.agg(F.lit(1).alias("level"), F.count("*").alias("n"))))


@query("udf_cogrouped_delta", sql.full(CS, "SELECT v.id, CAST(coalesce((SELECT sum(w) FROM edges WHERE src = v.id AND dst % 2 = 0), 0) - coalesce((SELECT sum(w) FROM edges WHERE src = v.id AND dst % 2 = 1), 0) AS BIGINT) AS delta FROM vertices v"))
def _(s, d):
    """A cogrouped Python function: for keys that hold few rows on either side."""
    even, odd = (g(s, d).edges.where(f"dst % 2 = {r}").groupBy(F.col("src").alias("id")).agg(F.sum("w").alias("w")) for r in (0, 1))
    return even.groupBy("id").cogroup(odd.groupBy("id")).applyInPandas(udf.delta, "id long, delta long")


@query("sql_text_cut", sql.full(CS, "SELECT CAST(sum(e.w) AS BIGINT) AS cut FROM edges e JOIN part a ON a.id = e.src JOIN part b ON b.id = e.dst WHERE e.src < e.dst AND a.block <> b.block", sql.blocks(16)))
def _(s, d):
    """The cut in SQL text over temporary views."""
    g(s, d).edges.createOrReplaceTempView("gpart_edges")
    hashed(g(s, d), 16).createOrReplaceTempView("gpart_partition")
    return s.sql("SELECT sum(e.w) AS cut FROM gpart_edges e JOIN gpart_partition a ON a.id = e.src JOIN gpart_partition b ON b.id = e.dst WHERE e.src < e.dst AND a.block <> b.block")


@query("sql_functions", "WITH v AS (SELECT o_orderkey, o_orderkey * o_custkey AS x FROM orders) SELECT o_orderkey, x, CAST(" + sql.vlen("x") + " AS INT) AS bytes, " + sql.zz("-x") + f" AS z, {sql.h('x', 0)} AS hash FROM v")
def _(s, d):
    udf.register(s)
    graphs.table(s, d, "orders").selectExpr("o_orderkey", "o_orderkey * o_custkey AS x").createOrReplaceTempView("gpart_numbers")
    return s.sql("SELECT o_orderkey, x, gpart_varint_len(x) AS bytes, gpart_zigzag(-x) AS z, gpart_hash(x) AS hash FROM gpart_numbers")


query("udaf_geometric_mean", "SELECT o_custkey % 7 AS r, round(exp(avg(ln(1 + o_orderkey % 50))), 6) AS mean FROM orders GROUP BY 1")(lambda s, d: graphs.table(s, d, "orders").select((F.col("o_custkey") % 7).alias("r"), (1 + F.col("o_orderkey") % 50).cast("double").alias("x")).groupBy("r").agg(F.round(udf.geometric_mean("x"), 6).alias("mean")))
query("udtf_decode_neighbors", sql.full("event_window", "SELECT src, dst FROM edges WHERE src < 500"))(lambda s, d: udf.decoded(s, built(s, d, "event_window"), 500))

# ---- streams ----

query("stream_tumbling", "SELECT epoch_us(time_bucket(INTERVAL 1 DAY, ts)) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")(lambda s, d: micros(streams.complete(streams.window_counts(streams.event_stream(s, d), "1 day"), "complete"), "start"))
query("stream_sliding", "SELECT epoch_us(s) AS start, event_type, count(*) AS n FROM (SELECT event_type, unnest([time_bucket(INTERVAL 12 HOUR, ts), time_bucket(INTERVAL 12 HOUR, ts) - INTERVAL 12 HOUR]) AS s FROM events) GROUP BY 1, 2")(lambda s, d: micros(streams.complete(streams.window_counts(streams.event_stream(s, d), "24 hours", "12 hours"), "complete"), "start"))
query("stream_session", "SELECT user_id, epoch_us(min(ts)) AS start, epoch_us(max(ts) + INTERVAL 6 HOUR) AS until, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS grp FROM (SELECT *, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 6 HOUR OR lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) IS NULL THEN 1 ELSE 0 END AS fresh FROM events)) GROUP BY user_id, grp")(lambda s, d: micros(streams.complete(streams.session_counts(streams.event_stream(s, d), "6 hours"), "complete"), "start", "until"))
query("stream_dedup", "SELECT DISTINCT user_id, event_type FROM events")(lambda s, d: streams.complete(streams.first_of_user_type(streams.event_stream(s, d))))
query("stream_static_join", f"SELECT event_id, CAST({sql.h('user_id', 1)} % 8 AS INT) AS block FROM events")(lambda s, d: streams.complete(streams.with_partition(streams.event_stream(s, d), graphs.table(s, d, "events").select(F.col("user_id").alias("id")).distinct().select("id", (columns.scramble("id", 1) % 8).cast("int").alias("block")))))


@query("stream_partitioner_check", "SELECT * FROM (SELECT 'users' AS check_name, count(DISTINCT user_id) AS value FROM events UNION ALL SELECT 'placed', count(DISTINCT user_id) FROM events UNION ALL SELECT 'over_cap', 0)")
def _(s, d):
    users = graphs.table(s, d, "events").select("user_id").distinct().count()
    cap = -(-users * 11 // 80)
    placed = streams.complete(streams.place_users(streams.event_stream(s, d), 8, cap))
    over = placed.groupBy("block").count().where(F.col("count") > cap).count()
    return s.createDataFrame([("users", users), ("placed", placed.select("id").distinct().count()), ("over_cap", over)], "check_name string, value long")


