"""The registered queries of the partitioner, each with DuckDB SQL where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gpart import oracles as sql
from gpart.functions import columns
from gpart.operators import baselines, clean, clustering, codec, contraction, gains, memory, metrics, refinement
from gpart.plans import distributed, experiments, multilevel
from gpart.session import cut
from gpart.sources import graphs
from gpart.sources.graphs import Graph

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
_BUILT: dict[tuple[str, str, str], Graph] = {}


def register(name: str, oracle: str | None = None):
    def put(f: Query) -> Query:
        QUERIES[name] = f
        if oracle is not None:
            ORACLES[name] = oracle
        return f

    return put


def built(spark: SparkSession, d: str, name: str) -> Graph:
    """A graph, written once for each application."""
    key = (spark.sparkContext.applicationId, d, name)
    if key not in _BUILT:
        _BUILT[key] = graphs.build_graph(spark, d, name).persisted()
    return _BUILT[key]


def verdicts(spark: SparkSession, **values: int) -> DataFrame:
    return spark.createDataFrame([(k, int(v)) for k, v in values.items()], "check_name string, value long")


def differing(a: DataFrame, b: DataFrame) -> int:
    """Rows that one of two tables has and the other has not."""
    return a.exceptAll(b).count() + b.exceptAll(a).count()


def hashed(g: Graph, k: int) -> DataFrame:
    return baselines.stream_hash(g.vertices, k)


# ---- graphs ----

for _name in graphs.BUILDERS:
    register(f"graph_edges_{_name}", sql.full(_name, "SELECT src, dst, w FROM edges"))(lambda s, d, n=_name: graphs.build_graph(s, d, n).edges)

STATS = "SELECT (SELECT count(*) FROM vertices) AS n, CAST(count(*) / 2 AS BIGINT) AS m, CAST(sum(w) / 2 AS BIGINT) AS total_w, round(count(*) / (SELECT count(*) FROM vertices), 6) AS avg_deg, (SELECT max(c) FROM (SELECT count(*) AS c FROM edges GROUP BY src)) AS max_deg FROM edges"
for _name in ("copurchase", "cust_supp", "fk_tree", "event_chain", "event_window", "page_host", "page_path", "conv_turns", "bench_overlap"):
    register(f"graph_stats_{_name}", sql.full(_name, STATS))(lambda s, d, n=_name: clean.graph_stats(built(s, d, n)))


@register("degree_profile_cust_supp", sql.full("cust_supp", "SELECT CAST(CASE WHEN degree = 0 THEN -1 ELSE floor(log2(degree)) END AS INT) AS log_degree, count(*) AS vertices, count(*) FILTER (WHERE degree >= 50) AS heavy FROM deg GROUP BY 1", sql.DEGREES))
def _(s, d):
    return clean.degree_profile(built(s, d, "cust_supp"), 50)


@register("symmetrize_pages", sql.full("page_path", "SELECT src, dst, max(w) AS w FROM (SELECT src, dst, w FROM edges WHERE src < dst UNION ALL SELECT dst, src, w FROM edges WHERE src < dst) GROUP BY 1, 2"))
def _(s, d):
    return clean.symmetrize(built(s, d, "page_path").edges.where("src < dst"))


RAW = "WITH raw AS (SELECT l_partkey % 500 AS src, l_suppkey AS dst, l_linenumber AS w FROM lineitem) SELECT src, dst, CAST({f}(w) AS BIGINT) AS w FROM raw WHERE src <> dst GROUP BY 1, 2"
for _merge, _f in (("sum", "sum"), ("max", "max"), ("one", "any_value")):
    register(f"simplify_{_merge}_lineitem", RAW.format(f=_f) if _merge != "one" else RAW.format(f="count").replace("CAST(count(w) AS BIGINT)", "CAST(1 AS BIGINT)"))(
        lambda s, d, m=_merge: clean.simplify(graphs.table(s, d, "lineitem").select((F.col("l_partkey") % 500).alias("src"), F.col("l_suppkey").alias("dst"), F.col("l_linenumber").cast("long").alias("w")), m)
    )


@register("dense_ids_orders", "SELECT o_orderkey AS key, row_number() OVER (ORDER BY o_orderkey) - 1 AS id FROM (SELECT DISTINCT o_orderkey FROM orders)")
def _(s, d):
    return graphs.number(graphs.table(s, d, "orders").select(F.col("o_orderkey").alias("key")).distinct(), ["key"], "id")


@register("relabel_degree_cust_supp", sql.full("cust_supp", "SELECT id AS old, row_number() OVER (ORDER BY degree DESC, id) - 1 AS id FROM deg", sql.DEGREES))
def _(s, d):
    return clean.relabel(built(s, d, "cust_supp"), "degree")[1]


# ---- compressed representation ----


@register("csr_offsets_copurchase", sql.full("copurchase", "SELECT id, degree, first_edge FROM off", sql.DEGREES))
def _(s, d):
    return codec.degrees(built(s, d, "copurchase"))


@register("csr_rows_cust_supp", sql.full("cust_supp", "SELECT src AS id, string_agg(dst, ' ' ORDER BY dst) AS nbrs, string_agg(w, ' ' ORDER BY dst) AS wts FROM edges GROUP BY 1"))
def _(s, d):
    join = lambda c: F.array_join(F.col(c).cast("array<string>"), " ").alias(c)
    return codec.to_csr(built(s, d, "cust_supp")).select("id", join("nbrs"), join("wts"))


GAPS = f"SELECT src, dst, coalesce(dst - lag(dst) OVER (PARTITION BY src ORDER BY dst), {sql.zz('dst - src')}) AS gap FROM edges"
CODED = ("cust_supp", "copurchase", "event_chain", "event_window")
for _name in CODED:
    register(f"gaps_{_name}", sql.full(_name, GAPS))(lambda s, d, n=_name: codec.gaps(built(s, d, n)))
    register(f"codec_bytes_{_name}", sql.full(_name, "SELECT id, n_bytes FROM sizes", *sql.coded()))(lambda s, d, n=_name: codec.compress(codec.to_csr(built(s, d, n))).select("id", F.col("n_bytes").cast("long").alias("n_bytes")))
    register(f"codec_gap_bytes_{_name}", sql.full(_name, "SELECT id, n_bytes FROM sizes", *sql.coded(False)))(lambda s, d, n=_name: codec.compress(codec.to_csr(built(s, d, n)), intervals=False).select("id", F.col("n_bytes").cast("long").alias("n_bytes")))
    register(f"codec_sizes_{_name}", sql.full(_name, "SELECT id, n_bytes FROM sizes", *sql.coded()))(lambda s, d, n=_name: codec.coded_sizes(built(s, d, n)))
    register(f"codec_roundtrip_{_name}", sql.full(_name, "SELECT src, dst, w FROM edges"))(lambda s, d, n=_name: codec.decompress(codec.compress(codec.to_csr(built(s, d, n)), weighted=True), True).select("src", "dst", "w"))

for _name in graphs.BUILDERS:
    register(
        f"compression_report_{_name}",
        sql.full(_name, "SELECT n, m, 8 * (n + 1) + 16 * m AS plain_bytes, gap_bytes, interval_bytes, round((8 * (n + 1) + 16 * m) / gap_bytes, 6) AS gap_ratio, round((8 * (n + 1) + 16 * m) / interval_bytes, 6) AS interval_ratio, round(interval_bytes / m, 6) AS bytes_per_edge FROM (SELECT (SELECT count(*) FROM vertices) AS n, CAST((SELECT count(*) FROM edges) / 2 AS BIGINT) AS m, (SELECT CAST(sum(n_bytes) AS BIGINT) FROM sizes) AS interval_bytes, (SELECT CAST(sum(b) AS BIGINT) FROM gb) AS gap_bytes)", *sql.coded(),
        f"gg AS (SELECT src AS id, dst, dst - lag(dst) OVER (PARTITION BY src ORDER BY dst) - 1 AS g FROM edges), gb AS (SELECT {sql.vlen('2 * first_edge')} + coalesce((SELECT sum({sql.vlen('coalesce(g, ' + sql.zz('dst - gg.id') + ')')}) FROM gg WHERE gg.id = off.id), 0) AS b FROM off)"),
    )(lambda s, d, n=_name: codec.compression_report(built(s, d, n)))


@register("interval_runs_event_window", sql.full("event_window", "SELECT src, min(dst) AS start, count(*) AS length FROM (SELECT src, dst, dst - row_number() OVER (PARTITION BY src ORDER BY dst) AS r FROM edges) GROUP BY src, r HAVING count(*) >= 3"))
def _(s, d):
    return codec.intervals(built(s, d, "event_window"))


@register("codec_weighted_bytes_cust_supp", sql.full("cust_supp", "SELECT id, n_bytes FROM sizes", *sql.coded(True, True)))
def _(s, d):
    return codec.compress(codec.to_csr(built(s, d, "cust_supp")), weighted=True).select("id", F.col("n_bytes").cast("long").alias("n_bytes"))


@register("codec_hub_chunks_cust_supp", sql.full("cust_supp", "SELECT id, CAST(unnest(range(0, CASE WHEN degree > 32 THEN (degree + 7) // 8 ELSE 1 END)) AS INT) AS chunk, first_edge, degree FROM off", sql.DEGREES).replace("SELECT id, CAST(unnest", "SELECT id, chunk, first_edge + 8 * chunk AS first_edge, CAST(CASE WHEN degree > 32 THEN least(8, degree - 8 * chunk) ELSE degree END AS INT) AS degree FROM (SELECT id, CAST(unnest") + ")")
def _(s, d):
    return codec.compress(codec.to_csr(built(s, d, "cust_supp"), hub_degree=32, chunk=8)).select("id", "chunk", "first_edge", "degree")


@register("codec_chunked_roundtrip_cust_supp", sql.full("cust_supp", "SELECT src, dst, w FROM edges"))
def _(s, d):
    return codec.decompress(codec.compress(codec.to_csr(built(s, d, "cust_supp"), hub_degree=32, chunk=8), weighted=True), True).select("src", "dst", "w")


@register("codec_edge_ids_event_window", sql.full("event_window", "SELECT CAST(count(*) AS BIGINT) AS edges, CAST(0 AS BIGINT) AS lowest, CAST(count(*) - 1 AS BIGINT) AS highest, CAST(count(*) AS BIGINT) AS different FROM edges"))
def _(s, d):
    return codec.decompress(codec.compress(codec.to_csr(built(s, d, "event_window")))).agg(F.count("*").alias("edges"), F.min("edge_id").alias("lowest"), F.max("edge_id").alias("highest"), F.countDistinct("edge_id").alias("different"))


@register("codec_degree_of_cust_supp", sql.full("cust_supp", "SELECT id, degree FROM deg", sql.DEGREES))
def _(s, d):
    g = built(s, d, "cust_supp")
    return codec.degree_of(codec.compress(codec.to_csr(g)), g.edges.count())


@register("codec_neighbors_of_hubs", sql.full("cust_supp", "SELECT src, dst FROM edges JOIN (SELECT src AS hub, count(*) AS degree FROM edges GROUP BY 1) ON hub = src WHERE degree > 60"))
def _(s, d):
    g = built(s, d, "cust_supp")
    return codec.neighbors(codec.compress(codec.to_csr(g)), codec.degrees(g).where("degree > 60")).select("src", "dst")


@register("packet_offsets_cust_supp", sql.full("cust_supp", "SELECT CAST(row_number() OVER (ORDER BY p) - 1 AS INT) AS packet, lo_id, hi_id, n_edges, n_bytes, CAST(coalesce(sum(n_bytes) OVER (ORDER BY p ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS byte_offset FROM (SELECT first_edge // 4096 AS p, min(id) AS lo_id, max(id) AS hi_id, CAST(sum(degree) AS BIGINT) AS n_edges, CAST(sum(n_bytes) AS BIGINT) AS n_bytes FROM sizes GROUP BY 1)", *sql.coded()))
def _(s, d):
    return codec.compress_packets(built(s, d, "cust_supp"), 4096)[1]


@register("codec_two_pass_equals_one_pass", sql.checks(("different_rows", 0)))
def _(s, d):
    g = built(s, d, "event_window")
    one, two = codec.compress_packets(g, 4096)[0], codec.compress_two_pass(g)
    return verdicts(s, different_rows=differing(one.select("id", F.hex("payload").alias("x")), two.select("id", F.hex("payload").alias("x"))))


#: Numbers of every size up to 2^43 on the given tables, in each engine.
ORDER_NUMBERS = "v AS (SELECT o_orderkey, o_orderkey * CASE o_orderkey % 3 WHEN 0 THEN 1 WHEN 1 THEN 7 ELSE o_custkey END AS x FROM orders)"


def order_numbers(s: SparkSession, d: str) -> DataFrame:
    """(o_orderkey, x): a number for each order."""
    by = F.when(F.col("o_orderkey") % 3 == 0, F.lit(1)).when(F.col("o_orderkey") % 3 == 1, F.lit(7)).otherwise(F.col("o_custkey"))
    return graphs.table(s, d, "orders").select("o_orderkey", (F.col("o_orderkey") * by).cast("long").alias("x"))


@register("varint_hex", f"WITH {ORDER_NUMBERS}, n AS (SELECT *, {sql.vlen('x')} AS n FROM v) SELECT o_orderkey, x, array_to_string(list_transform(range(0, n), lambda i: upper(printf('%02x', (x >> (7 * i)::INT) % 128 + CASE WHEN i < n - 1 THEN 128 ELSE 0 END))), '') AS hex FROM n")
def _(s, d):
    def run(batches):
        import pyarrow as pa

        for b in batches:
            data, sizes = codec.varint_bytes(b.column("x").to_numpy())
            raw, ends = data.tobytes(), sizes.cumsum()
            yield pa.RecordBatch.from_arrays([b.column("o_orderkey"), b.column("x"), pa.array([raw[e - n : e].hex().upper() for n, e in zip(sizes, ends, strict=True)], pa.string())], names=["o_orderkey", "x", "hex"])

    return order_numbers(s, d).mapInArrow(run, "o_orderkey long, x long, hex string")


@register("varint_len_zigzag", f"WITH v AS (SELECT o_orderkey, (CASE WHEN o_custkey % 2 = 0 THEN 1 ELSE -1 END) * (o_orderkey * o_custkey - o_custkey) AS x FROM orders) SELECT o_orderkey, x, {sql.zz('x')} AS z, CAST({sql.vlen(sql.zz('x'))} AS INT) AS bytes FROM v")
def _(s, d):
    """A number of either sign for each order."""
    signed = F.when(F.col("o_custkey") % 2 == 0, F.lit(1)).otherwise(-1) * (F.col("o_orderkey") * F.col("o_custkey") - F.col("o_custkey"))
    z = columns.zigzag(F.col("x"))
    return graphs.table(s, d, "orders").select("o_orderkey", signed.alias("x")).select("o_orderkey", "x", z.alias("z"), columns.varint_len(z).alias("bytes"))


@register("memory_growable_buffer", "WITH w AS (SELECT l_orderkey AS part, CAST(sum(l_partkey * l_linenumber) AS BIGINT) AS n_bytes FROM lineitem GROUP BY 1), c AS (SELECT *, CAST(ceil(greatest(0.0, log2(n_bytes / 4096))) AS INT) AS k FROM w) SELECT part, n_bytes, CAST(4096 * pow(2, k) AS BIGINT) AS capacity, CAST(CASE WHEN k > 0 THEN 4096 * pow(2, k) * 3 / 2 ELSE 4096 * pow(2, k) END AS BIGINT) AS peak FROM c")
def _(s, d):
    """A buffer for each order, of a size that its lines give."""
    return memory.growable_bytes(graphs.table(s, d, "lineitem").groupBy(F.col("l_orderkey").alias("part")).agg(F.sum(F.col("l_partkey") * F.col("l_linenumber")).alias("n_bytes")))


# ---- clustering ----


def lp_sql(name: str, rounds: int, select: str = "SELECT id, c AS cluster FROM labels", **how) -> str:
    return sql.full(name, select, *sql.lp(rounds, **how))


def labelled(s: SparkSession, d: str, name: str, rounds: int, **how) -> DataFrame:
    return clustering.label_propagation(built(s, d, name), rounds, **how)


@register("lp_ratings_after_1_round", lp_sql("cust_supp", 1, "SELECT e.src AS id, l.c AS cluster, CAST(sum(e.w) AS BIGINT) AS rating FROM edges e JOIN labels l ON l.id = e.dst GROUP BY 1, 2"))
def _(s, d):
    return clustering.ratings(built(s, d, "cust_supp").edges, labelled(s, d, "cust_supp", 1))


@register("lp_distinct_clusters", lp_sql("cust_supp", 1, "SELECT e.src AS id, count(DISTINCT l.c) AS nc FROM edges e JOIN labels l ON l.id = e.dst GROUP BY 1"))
def _(s, d):
    return clustering.distinct_clusters(built(s, d, "cust_supp").edges, labelled(s, d, "cust_supp", 1))


for _r in (1, 3, 5):
    register(f"lp_single_r{_r}_cust_supp", lp_sql("cust_supp", _r))(lambda s, d, r=_r: labelled(s, d, "cust_supp", r))
    register(f"lp_two_phase_r{_r}_cust_supp", lp_sql("cust_supp", _r))(lambda s, d, r=_r: labelled(s, d, "cust_supp", r, two_phase=True, t_bump=16))
for _name in ("page_host", "event_window", "conv_turns"):
    register(f"lp_two_phase_r1_{_name}", lp_sql(_name, 1))(lambda s, d, n=_name: labelled(s, d, n, 1, two_phase=True, t_bump=8))


@register("lp_sparse_rating_map", sql.full("cust_supp", "SELECT id, c AS cluster FROM l1", "l0 AS (SELECT id, id AS c FROM vertices)", sql.lp_step("l0", "l1", 1, 0, 1)))
def _(s, d):
    g = built(s, d, "cust_supp")
    return clustering.lp_round_two_phase(g, clustering.singletons(g.vertices), t_bump=16, rating_map="sparse")


@register("lp_all_heavy", sql.full("cust_supp", "SELECT id, c AS cluster FROM l1", "l0 AS (SELECT id, id AS c FROM vertices)", sql.lp_step("l0", "l1", 1, 0, 1)))
def _(s, d):
    g = built(s, d, "cust_supp")
    return clustering.lp_round_two_phase(g, clustering.singletons(g.vertices), t_bump=1)


@register("lp_bumped_cust_supp", lp_sql("cust_supp", 1, "SELECT e.src AS id FROM edges e JOIN labels l ON l.id = e.dst GROUP BY 1 HAVING count(DISTINCT l.c) >= 16"))
def _(s, d):
    return clustering.bumped(built(s, d, "cust_supp").edges, labelled(s, d, "cust_supp", 1), 16).select("id")


@register("lp_flush_stats", lp_sql("cust_supp", 1, f"SELECT count(DISTINCT src) AS heavy, CAST(sum(n) AS BIGINT) AS edges, CAST(sum(c) AS BIGINT) AS updates, CAST(sum(ceil(c / 16)) AS BIGINT) AS flushes, CAST(sum(n) - sum(c) AS BIGINT) AS updates_saved FROM (SELECT e.src, {sql.h('e.dst', 5)} % 16 AS salt, count(*) AS n, count(DISTINCT l.c) AS c FROM edges e JOIN labels l ON l.id = e.dst WHERE e.src IN (SELECT e.src FROM edges e JOIN labels l ON l.id = e.dst GROUP BY 1 HAVING count(DISTINCT l.c) >= 16) GROUP BY 1, 2)"))
def _(s, d):
    return clustering.flush_stats(built(s, d, "cust_supp").edges, labelled(s, d, "cust_supp", 1), 16)


@register("lp_capped_r2_cust_supp", lp_sql("cust_supp", 2, cap=20))
def _(s, d):
    return labelled(s, d, "cust_supp", 2, cap=20)


@register("lp_capped_two_phase_r1_copurchase", lp_sql("copurchase", 1, cap=12))
def _(s, d):
    return labelled(s, d, "copurchase", 1, cap=12, two_phase=True, t_bump=100)


TWO_HOP = [
    f"fr AS (SELECT e.src AS id, l.c, CAST(sum(e.w) AS BIGINT) AS rating FROM edges e JOIN labels l ON l.id = e.dst JOIN labels o ON o.id = e.src WHERE l.c <> o.c GROUP BY 1, 2), fav AS (SELECT id, c FROM (SELECT id, c, row_number() OVER (PARTITION BY id ORDER BY rating DESC, {sql.h('c', 1)}, c) AS p FROM fr) WHERE p = 1)",
    "al AS (SELECT min(id) AS id FROM labels GROUP BY c HAVING count(*) = 1), pl AS (SELECT al.id, fav.c AS f, al.id // 4096 AS b, (row_number() OVER (PARTITION BY fav.c, al.id // 4096 ORDER BY al.id) - 1) // 2 AS pair FROM al JOIN fav USING (id)), mv AS (SELECT id, least AS c FROM (SELECT id, min(id) OVER w AS least, count(*) OVER w AS n FROM pl WINDOW w AS (PARTITION BY f, b, pair)) WHERE n <= 4 AND id <> least)",
]


@register("two_hop_conv_turns", lp_sql("conv_turns", 1, "SELECT l.id, coalesce(mv.c, l.c) AS cluster FROM labels l LEFT JOIN mv USING (id)", cap=4).replace(") SELECT l.id", "), " + ", ".join(TWO_HOP) + " SELECT l.id"))
def _(s, d):
    g = built(s, d, "conv_turns")
    labels = labelled(s, d, "conv_turns", 1, cap=4)
    return clustering.two_hop(g, labels, clustering.favourites(g, labels), 4)


@register("lp_task_async_check", sql.checks(("over_cap", 0), ("unlabelled", 0), ("worse_than_singletons", 0)))
def _(s, d):
    g = built(s, d, "cust_supp")
    labels = cut(clustering.task_async_round(g, clustering.singletons(g.vertices), cap=40))
    over = clustering.cluster_weights(g.vertices, labels).where("weight > 40").count()
    inside = contraction.between_clusters(g.edges, labels).count()
    return verdicts(s, over_cap=over, unlabelled=g.vertices.count() - labels.count(), worse_than_singletons=inside >= g.edges.count())


# ---- contraction ----

for _name in ("cust_supp", "page_host", "event_window"):
    register(f"contract_{_name}", sql.full(_name, "SELECT src, dst, w FROM ce", *sql.lp(1), sql.CONTRACT))(lambda s, d, n=_name: contraction.contract(built(s, d, n), labelled(s, d, n, 1))[0].edges)


@register("contract_vertices_cust_supp", sql.full("cust_supp", "SELECT id, w FROM cv", *sql.lp(1), sql.CONTRACT))
def _(s, d):
    return contraction.contract(built(s, d, "cust_supp"), labelled(s, d, "cust_supp", 1))[0].vertices


@register("contract_parents_cust_supp", sql.full("cust_supp", "SELECT l.id, cv.id AS coarse FROM labels l JOIN cv USING (c)", *sql.lp(1), sql.CONTRACT))
def _(s, d):
    return contraction.contract(built(s, d, "cust_supp"), labelled(s, d, "cust_supp", 1))[1]


@register("contract_buffered_cust_supp", sql.full("cust_supp", "SELECT src, dst, w FROM ce", *sql.lp(1), sql.CONTRACT))
def _(s, d):
    return contraction.contract_buffered(built(s, d, "cust_supp"), labelled(s, d, "cust_supp", 1))[0].edges


@register("contract_twice_degrees", sql.full("cust_supp", "SELECT a.c AS cluster, count(DISTINCT b.c) AS degree FROM edges e JOIN labels a ON a.id = e.src JOIN labels b ON b.id = e.dst WHERE a.c <> b.c GROUP BY 1", *sql.lp(1)))
def _(s, d):
    return contraction.contract_twice(built(s, d, "cust_supp"), labelled(s, d, "cust_supp", 1))[2]


@register("contract_two_phase_cust_supp", sql.full("cust_supp", "SELECT a.c AS a, b.c AS b, CAST(sum(e.w) AS BIGINT) AS w FROM edges e JOIN labels a ON a.id = e.src JOIN labels b ON b.id = e.dst WHERE a.c <> b.c GROUP BY 1, 2", *sql.lp(1)))
def _(s, d):
    return contraction.two_phase_edges(built(s, d, "cust_supp").edges, labelled(s, d, "cust_supp", 1), 16)


@register("contract_one_pass_check", sql.checks(("edges_differ", 0), ("gaps_in_ids", 0), ("gaps_in_edge_array", 0), ("clusters_missing", 0)))
def _(s, d):
    g, labels = built(s, d, "cust_supp"), labelled(s, d, "cust_supp", 1)
    rows, _, coarse = contraction.contract_one_pass(g, labels, 16)
    names = rows.select("id", "cluster")
    a, b = (names.select(F.col("id").alias(x), F.col("cluster").alias(y)) for x, y in (("src", "a"), ("dst", "b")))
    back = coarse.edges.join(a, "src").join(b, "dst").select("a", "b", "w")
    ordered = rows.orderBy("id").select("id", "degree", "first_edge").collect()
    run, holes = 0, 0
    for r in ordered:
        holes += r["first_edge"] != run
        run += r["degree"]
    return verdicts(s, edges_differ=differing(back, contraction.coarse_edges(g.edges, labels)), gaps_in_ids=sum(r["id"] != i for i, r in enumerate(ordered)), gaps_in_edge_array=holes + (run != coarse.edges.count()), clusters_missing=labels.select("cluster").distinct().count() - len(ordered))


@register("contract_reserve_ranges", "WITH y AS (SELECT CAST(o_custkey % 50 AS INT) AS part, CAST(o_orderkey % 4 AS INT) AS buffer, count(DISTINCT o_custkey) AS vertices, count(*) AS edges FROM orders GROUP BY 1, 2) SELECT *, CAST(coalesce(sum(vertices) OVER p, 0) AS BIGINT) AS s, CAST(coalesce(sum(edges) OVER p, 0) AS BIGINT) AS d FROM y WINDOW p AS (ORDER BY part, buffer ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)")
def _(s, d):
    """Four buffers of each of 50 tasks, with the customers and orders that fall into each."""
    held = graphs.table(s, d, "orders").groupBy((F.col("o_custkey") % 50).cast("int").alias("part"), (F.col("o_orderkey") % 4).cast("int").alias("buffer"))
    return contraction.reserve(held.agg(F.countDistinct("o_custkey").alias("vertices"), F.count("*").alias("edges")))


@register("contract_cut_preserved", sql.full("cust_supp", "SELECT CAST(coalesce(sum(e.w), 0) AS BIGINT) AS fine_cut, CAST(coalesce(sum(e.w), 0) AS BIGINT) AS coarse_cut FROM edges e JOIN fp a ON a.id = e.src JOIN fp b ON b.id = e.dst WHERE e.src < e.dst AND a.block <> b.block", *sql.lp(1), sql.CONTRACT, f"fp AS (SELECT l.id, {sql.h('cv.id', 1)} % 4 AS block FROM labels l JOIN cv USING (c))"))
def _(s, d):
    g = built(s, d, "cust_supp")
    coarse, parents = contraction.contract(g, labelled(s, d, "cust_supp", 1))
    part = hashed(coarse, 4)
    return metrics.edge_cut(g.edges, refinement.project(part, parents)).select(F.col("cut").alias("fine_cut")).crossJoin(metrics.edge_cut(coarse.edges, part).select(F.col("cut").alias("coarse_cut")))


# ---- gains ----


@register("affinity_cust_supp", sql.full("cust_supp", "SELECT id, block, affinity FROM aff", sql.blocks(8), sql.AFFINITY))
def _(s, d):
    g = built(s, d, "cust_supp")
    return gains.affinity(g.edges, hashed(g, 8))


GAINS = "SELECT a.id, a.block, a.affinity - coalesce(o.affinity, 0) AS gain FROM aff a JOIN part p USING (id) LEFT JOIN aff o ON o.id = a.id AND o.block = p.block WHERE a.block <> p.block"
for _v in ("none", "full", "hybrid"):
    register(f"gain_table_{_v}", sql.full("cust_supp", GAINS, sql.blocks(8), sql.AFFINITY))(lambda s, d, v=_v: gains.GainTable(built(s, d, "cust_supp"), hashed(built(s, d, "cust_supp"), 8), 8, v).gains())

MOVES = f"mv AS (SELECT row_number() OVER (ORDER BY id) AS pos, id, block AS from_block, CAST((block + 1 + id % 3) % 8 AS INT) AS to_block FROM part WHERE {sql.h('id', 3)} % 10 = 0)"


def some_moves(s, g: Graph, k: int = 8) -> DataFrame:
    """Moves of a tenth of the vertices, by rising id."""
    chosen = hashed(g, k).where(columns.scramble("id", 3) % 10 == 0)
    return graphs.number(chosen, ["id"], "at").select((F.col("at") + 1).alias("pos"), "id", F.col("block").alias("from_block"), ((F.col("block") + 1 + F.col("id") % 3) % k).cast("int").alias("to_block"))


for _v in ("full", "hybrid"):
    register(f"gain_table_delta_{_v}", sql.full("cust_supp", "SELECT e.src AS id, p.block, CAST(sum(e.w) AS BIGINT) AS affinity FROM edges e JOIN np p ON p.id = e.dst GROUP BY 1, 2", sql.blocks(8), MOVES, "np AS (SELECT part.id, coalesce(mv.to_block, part.block) AS block FROM part LEFT JOIN mv USING (id))"))(
        lambda s, d, v=_v: gains.GainTable(built(s, d, "cust_supp"), hashed(built(s, d, "cust_supp"), 8), 8, v).apply(some_moves(s, built(s, d, "cust_supp"))).affinities()
    )


@register("gain_table_rows_hybrid", sql.full("cust_supp", "SELECT id, CASE WHEN degree > 24 THEN 'dense' ELSE 'hash' END AS kind, CAST(CASE WHEN u < 256 THEN 8 WHEN u < 65536 THEN 16 ELSE 32 END AS INT) AS width FROM deg", sql.DEGREES))
def _(s, d):
    g = built(s, d, "cust_supp")
    return gains.GainTable(g, hashed(g, 24), 24).rows.select("id", "kind", "width")


@register("gain_table_bytes", sql.full("event_chain", "SELECT count(*) AS n, CAST(0 AS BIGINT) AS none_bytes, count(*) * 8000 AS full_bytes, CAST(sum(8 + CASE WHEN degree > 1000 THEN 1000 * (CASE WHEN u < 256 THEN 1 WHEN u < 65536 THEN 2 ELSE 4 END) ELSE pow(2, ceil(log2(greatest(1, ceil(degree * 1.5))))) * (4 + CASE WHEN u < 256 THEN 1 WHEN u < 65536 THEN 2 ELSE 4 END) END) AS BIGINT) AS hybrid_bytes, CAST(sum(least(degree, 1000)) AS BIGINT) AS entries FROM deg", sql.DEGREES))
def _(s, d):
    return gains.gain_table_bytes(built(s, d, "event_chain"), 1000)


@register("entry_width", "WITH v AS (SELECT o_orderkey, CASE WHEN o_orderkey % 2 = 0 THEN o_custkey * o_orderkey ELSE CAST(pow(2, 8 * (o_orderkey % 5)) AS BIGINT) - o_custkey % 2 END AS u FROM orders) SELECT o_orderkey, u, CAST(CASE WHEN u < 256 THEN 8 WHEN u < 65536 THEN 16 WHEN u < 4294967296 THEN 32 ELSE 64 END AS INT) AS width FROM v")
def _(s, d):
    """A value for each order: half of them at the bounds of the widths."""
    bound = F.when(F.col("o_orderkey") % 5 == 0, F.lit(1))
    for n in range(1, 5):
        bound = bound.when(F.col("o_orderkey") % 5 == n, F.lit(1 << 8 * n))
    u = F.when(F.col("o_orderkey") % 2 == 0, F.col("o_custkey") * F.col("o_orderkey")).otherwise(bound - F.col("o_custkey") % 2)
    return graphs.table(s, d, "orders").select("o_orderkey", u.cast("long").alias("u")).select("o_orderkey", "u", columns.entry_width(F.col("u")).alias("width"))


# ---- refinement ----


@register("refine_lp_step_cust_supp", sql.full("cust_supp", "SELECT id, CAST(c AS INT) AS block FROM l1", sql.blocks(4), "l0 AS (SELECT id, CAST(block AS BIGINT) AS c FROM part)", sql.lp_step("l0", "l1", 1, 0, 2, 480)))
def _(s, d):
    g = built(s, d, "cust_supp")
    return refinement.refine_lp_round(g, hashed(g, 4), 480, 1, 0, 2)


@register("refine_lp_r2_event_window", sql.full("event_window", "SELECT id, CAST(c AS INT) AS block FROM l4", sql.blocks(4), "l0 AS (SELECT id, CAST(block AS BIGINT) AS c FROM part)", *[sql.lp_step(f"l{i}", f"l{i + 1}", 1 + i // 2, i % 2, 2, 2600) for i in range(4)]))
def _(s, d):
    g = built(s, d, "event_window")
    return refinement.refine_lp(g, hashed(g, 4), 2600, 2)


@register("boundary_vertices_event_window", sql.full("event_window", "SELECT DISTINCT e.src AS id FROM edges e JOIN part a ON a.id = e.src JOIN part b ON b.id = e.dst WHERE a.block <> b.block", "part AS (SELECT id, CAST(id * 8 // (SELECT count(*) FROM vertices) AS INT) AS block FROM vertices)"))
def _(s, d):
    g = built(s, d, "event_window")
    return refinement.boundary(g.edges, g.vertices.select("id", F.floor(F.col("id") * 8 / F.lit(g.vertices.count())).cast("int").alias("block")))


@register("project_partition", sql.full("cust_supp", f"SELECT l.id, CAST({sql.h('cv.id', 1)} % 4 AS INT) AS block FROM labels l JOIN cv USING (c)", *sql.lp(1), sql.CONTRACT))
def _(s, d):
    coarse, parents = contraction.contract(built(s, d, "cust_supp"), labelled(s, d, "cust_supp", 1))
    return refinement.project(hashed(coarse, 4), parents)


REBALANCE = [
    f"part AS (SELECT id, CAST(CASE WHEN {sql.h('id', 9)} % 10 < 5 THEN 0 ELSE id % 4 END AS INT) AS block FROM vertices)", sql.AFFINITY,
    "bw AS (SELECT b.block, coalesce(x.w, 0) AS w FROM (SELECT CAST(unnest(range(0, 4)) AS INT) AS block) b LEFT JOIN (SELECT block, CAST(sum(v.w) AS BIGINT) AS w FROM part JOIN vertices v USING (id) GROUP BY 1) x USING (block))",
    "cap AS (SELECT CAST(floor(1.03 * count(*) / 4) AS BIGINT) AS cap FROM vertices), own AS (SELECT p.id, p.block AS own, v.w, bw.w - cap AS excess FROM part p JOIN vertices v USING (id) JOIN bw ON bw.block = p.block, cap WHERE bw.w > cap), room AS (SELECT block, cap - w AS room FROM bw, cap WHERE w < cap), lt AS (SELECT block, room FROM room ORDER BY room DESC, block LIMIT 1)",
    "kept AS (SELECT o.*, coalesce(a.affinity, 0) AS kept FROM own o LEFT JOIN aff a ON a.id = o.id AND a.block = o.own), cand AS (SELECT k.id, k.own, k.w, k.excess, r.room, r.block, a.affinity - k.kept AS gain FROM kept k JOIN aff a ON a.id = k.id JOIN room r ON r.block = a.block WHERE k.w <= r.room UNION ALL SELECT k.id, k.own, k.w, k.excess, lt.room, lt.block, -k.kept FROM kept k, lt WHERE k.w <= lt.room)",
    f"best AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY id ORDER BY gain DESC, {sql.h('block', 1)}, block) AS p FROM cand) WHERE p = 1)",
    f"lv AS (SELECT *, coalesce(sum(w) OVER (PARTITION BY own ORDER BY gain / w DESC, {sql.h('id', 1)}, id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS gone FROM best), ft AS (SELECT *, sum(w) OVER (PARTITION BY block ORDER BY gain / w DESC, {sql.h('id', 1)}, id ROWS UNBOUNDED PRECEDING) AS come FROM lv WHERE gone < excess)",
]


@register("rebalance_round_cust_supp", sql.full("cust_supp", "SELECT p.id, coalesce(f.block, p.block) AS block FROM part p LEFT JOIN (SELECT id, block FROM ft WHERE come <= room) f USING (id)", *REBALANCE))
def _(s, d):
    g = built(s, d, "cust_supp")
    part = g.vertices.select("id", F.when(columns.scramble("id", 9) % 10 < 5, 0).otherwise(F.col("id") % 4).cast("int").alias("block"))
    return refinement.rebalance_round(g, part, 4, int(1.03 * g.vertices.count() / 4))


@register("rebalance_check_cust_supp", sql.checks(("overload", 0), ("vertices_lost", 0)))
def _(s, d):
    g = built(s, d, "cust_supp")
    part = g.vertices.select("id", F.when(columns.scramble("id", 9) % 10 < 5, 0).otherwise(F.col("id") % 4).cast("int").alias("block"))
    cap = int(1.03 * g.vertices.count() / 4)
    after = refinement.rebalance(g, part, 4, cap)
    return verdicts(s, overload=refinement.overload(g.vertices, after, cap), vertices_lost=g.vertices.count() - after.count())


JOINT = [
    sql.blocks(8), MOVES,
    "st AS (SELECT m.pos, m.id, m.from_block, m.to_block, CAST(coalesce(sum(e.w * (CASE WHEN coalesce(CASE WHEN u.pos < m.pos THEN u.to_block END, p.block) = m.to_block THEN 1 ELSE 0 END - CASE WHEN coalesce(CASE WHEN u.pos < m.pos THEN u.to_block END, p.block) = m.from_block THEN 1 ELSE 0 END)), 0) AS BIGINT) AS gain FROM mv m LEFT JOIN edges e ON e.src = m.id LEFT JOIN part p ON p.id = e.dst LEFT JOIN mv u ON u.id = e.dst GROUP BY 1, 2, 3, 4)",
]


@register("fm_joint_gains", sql.full("cust_supp", "SELECT pos, id, from_block, to_block, gain FROM st", *JOINT))
def _(s, d):
    g = built(s, d, "cust_supp")
    return refinement.joint_gains(some_moves(s, g), g, hashed(g, 8))


@register("fm_prefixes", sql.full("cust_supp", "SELECT st.pos, gain, CAST(sum(gain) OVER (ORDER BY st.pos) AS BIGINT) AS total, (SELECT count(*) FROM (SELECT p.block, sum(1) + coalesce((SELECT sum(CASE WHEN m.to_block = p.block THEN 1 WHEN m.from_block = p.block THEN -1 ELSE 0 END) FROM mv m WHERE m.pos <= st.pos), 0) AS load FROM part p GROUP BY 1) WHERE load > (SELECT floor(1.1 * count(*) / 8) FROM vertices)) AS over FROM st", *JOINT))
def _(s, d):
    g = built(s, d, "cust_supp")
    return refinement.prefixes(some_moves(s, g), g, hashed(g, 8), int(1.1 * g.vertices.count() / 8))


# ---- solvers ----


def soundness(s: SparkSession, g: Graph, part: DataFrame, k: int, eps: float = 0.03, better_than: DataFrame | None = None) -> DataFrame:
    """What no partition may violate; and that it cuts less than a hashed one."""
    n = g.vertices.count()
    bad = part.where((F.col("block") < 0) | (F.col("block") >= k) | F.col("block").isNull()).count()
    infeasible = metrics.balance(g.vertices, part, k, eps).where("NOT feasible").count()
    cut_of = lambda p: metrics.cut_of(g, p).first()[0]
    worse = cut_of(part) > cut_of(better_than if better_than is not None else hashed(g, k))
    return verdicts(s, vertices=n, vertices_placed=part.select("id").distinct().count(), out_of_range=bad, infeasible_blocks=infeasible, worse_than_baseline=worse)


def sound_sql(name: str) -> str:
    return sql.full(name, "SELECT * FROM (SELECT 'vertices' AS check_name, count(*) AS value FROM vertices UNION ALL SELECT 'vertices_placed', count(*) FROM vertices UNION ALL SELECT 'out_of_range', 0 UNION ALL SELECT 'infeasible_blocks', 0 UNION ALL SELECT 'worse_than_baseline', 0)")


def in_spark(g: Graph, k: int = 4, **how) -> multilevel.MultilevelConfig:
    """Settings for the tables' graphs, which are small: thresholds of their scale, so that levels are made on tables of any size."""
    return multilevel.MultilevelConfig(**{"contraction_limit": max(4, g.vertices.count() // (4 * k)), "t_bump": 64, "refine_rounds": 2} | how)


def solved(s: SparkSession, g: Graph, result: multilevel.Result, k: int, cfg: multilevel.MultilevelConfig) -> DataFrame:
    """soundness of a solver's result; fails where the graph was to be coarsened and there is no smaller level."""
    multilevel.require_levels(result.levels, k, cfg)
    return soundness(s, g, result.partition, k)


def solve(s: SparkSession, d: str, name: str, preset: str, k: int = 4) -> DataFrame:
    g = built(s, d, name)
    cfg = in_spark(g, k)
    return solved(s, g, multilevel.partition(g, k, preset, cfg), k, cfg)


for _name in ("cust_supp", "event_window", "page_host", "fk_tree", "page_path"):
    register(f"partition_lean_lp_{_name}", sound_sql(_name))(lambda s, d, n=_name: solve(s, d, n, "lean-lp"))
for _name in ("event_window", "cust_supp"):
    register(f"partition_lean_fm_{_name}", sound_sql(_name))(lambda s, d, n=_name: solve(s, d, n, "lean-fm"))


for _name in ("cust_supp", "event_window", "page_path"):
    register(f"partition_levels_{_name}")(lambda s, d, n=_name: multilevel.hierarchy(multilevel.coarsen(built(s, d, n), 4, in_spark(built(s, d, n))), s))


#: Two rounds of sub-batches on the input, contraction, one round on the coarse graph, contraction.
LEVELS = [
    *sql.lp(1, parts=1), sql.CONTRACT,
    "lb AS (SELECT id, id AS c FROM cv)", sql.lp_step("lb", "lc", 1, 0, 1).replace("FROM edges e", "FROM ce e").replace("JOIN vertices v", "JOIN cv v"),
    "dv AS (SELECT l.c, CAST(sum(v.w) AS BIGINT) AS w FROM lc l JOIN cv v ON v.id = l.id GROUP BY 1), de AS (SELECT a.c AS a, b.c AS b, sum(e.w) AS w FROM ce e JOIN lc a ON a.id = e.src JOIN lc b ON b.id = e.dst WHERE a.c <> b.c GROUP BY 1, 2)",
]


@register("hierarchy_levels", sql.full("event_window", "SELECT CAST(0 AS INT) AS level, (SELECT count(*) FROM vertices) AS n, (SELECT count(*) FROM edges) AS directed_edges, (SELECT CAST(sum(w) AS BIGINT) FROM edges) AS weight UNION ALL SELECT 1, (SELECT count(*) FROM cv), (SELECT count(*) FROM ce), (SELECT CAST(sum(w) AS BIGINT) FROM ce) UNION ALL SELECT 2, (SELECT count(*) FROM dv), (SELECT count(*) FROM de), (SELECT CAST(sum(w) AS BIGINT) FROM de)", *LEVELS))
def _(s, d):
    """Three levels, by two-phase rounds on coded neighbourhoods and one-pass contraction."""
    cfg = multilevel.MultilevelConfig(rounds=1, parts=1, t_bump=8, contraction_limit=0, two_hop_above=2.0)
    g, _ = multilevel.compressed_input(built(s, d, "event_window"), cfg)
    levels = [multilevel.level_of(g, None)]
    for _ in range(2):
        labels = clustering.label_propagation(levels[-1].graph, 1, 1, 1, two_phase=True, t_bump=8)
        _, parents, coarse = contraction.contract_one_pass(levels[-1].graph, labels, 8)
        levels.append(multilevel.level_of(coarse, parents))
    weight = [x.graph.edges.agg(F.coalesce(F.sum("w"), F.lit(0))).first()[0] for x in levels]
    return s.createDataFrame([(i, x.n, x.m, w) for i, (x, w) in enumerate(zip(levels, weight, strict=True))], "level int, n long, directed_edges long, weight long")


@register("partition_extending_event_window", sound_sql("event_window"))
def _(s, d):
    g = built(s, d, "event_window")
    cfg = in_spark(g, 2, refine_rounds=1)
    result = multilevel.partition_extending(g, 8, 2, cfg)
    multilevel.require_levels(result.levels, 2, cfg)
    return soundness(s, g, result.partition, 8)


@register("ladder_equal_cut", sql.checks(("presets", 4), ("different_cuts", 1), ("different_plans", 4)))
def _(s, d):
    # this graph has levels on the smallest tables too; at 8 its vertices reach the second phase
    g = built(s, d, "event_window")
    return experiments.ladder_equal(g, 4, in_spark(g, 4, t_bump=8, refine_rounds=1, rounds=3))


@register("distributed_ghosts", sql.full("cust_supp", "SELECT DISTINCT a.part, e.dst AS ghost_id, b.part AS owner FROM edges e JOIN ow a ON a.id = e.src JOIN ow b ON b.id = e.dst WHERE a.part <> b.part", "ow AS (SELECT id, CAST(id * 8 // (SELECT count(*) FROM vertices) AS INT) AS part FROM vertices)"))
def _(s, d):
    g = built(s, d, "cust_supp")
    return distributed.ghosts(g.edges, distributed.owned(g.vertices, g.vertices.count(), 8))


@register("distributed_work", sql.full("event_window", "SELECT o.part, count(DISTINCT o.id) AS vertices, count(e.dst) AS directed_edges, count(DISTINCT CASE WHEN b.part <> o.part THEN e.dst END) AS ghosts FROM ow o LEFT JOIN edges e ON e.src = o.id LEFT JOIN ow b ON b.id = e.dst GROUP BY 1", "ow AS (SELECT id, CAST(id * 8 // (SELECT count(*) FROM vertices) AS INT) AS part FROM vertices)"))
def _(s, d):
    g = built(s, d, "event_window")
    return distributed.work_per_part(g, distributed.owned(g.vertices, g.vertices.count(), 8))


@register("distributed_partition_check", sound_sql("event_window"))
def _(s, d):
    g = built(s, d, "event_window")
    cfg = in_spark(g)
    return solved(s, g, distributed.partition_distributed(g, 4, 4, cfg=cfg), 4, cfg)


# ---- baselines ----


@register("baseline_hash", sql.full("cust_supp", "SELECT id, block FROM part", sql.blocks(16)))
def _(s, d):
    return hashed(built(s, d, "cust_supp"), 16)


@register("baseline_flat_lp_step", sql.full("cust_supp", "SELECT id, CAST(c AS INT) AS block FROM l1", sql.blocks(8), "l0 AS (SELECT id, CAST(block AS BIGINT) AS c FROM part)", sql.lp_step("l0", "l1", 1, 0, 2, 250)))
def _(s, d):
    return baselines.flat_lp_step(built(s, d, "cust_supp"), 8, 250)


@register("baseline_matching_round", sql.full("cust_supp", "SELECT v.id, coalesce(m.s, v.id) AS cluster FROM vertices v LEFT JOIN (SELECT x.src AS s, x.dst AS id FROM wish x JOIN wish y ON x.src = y.dst AND x.dst = y.src WHERE x.src < x.dst) m ON m.id = v.id", f"wish AS (SELECT src, dst FROM (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY w DESC, ({sql.h('least(src, dst)', 1)}) * ({sql.h('greatest(src, dst)', 8)}) % {sql.M}, dst) AS p FROM edges) WHERE p = 1)"))
def _(s, d):
    g = built(s, d, "cust_supp")
    return baselines.matching_round(g, clustering.singletons(g.vertices), 2)


for _name, _f in (
    ("ldg", lambda g, k, cap: baselines.stream_ldg(g, k, cap)), ("penalty", lambda g, k, cap: baselines.stream_penalty(g, k, cap)), ("buffered", lambda g, k, cap: baselines.stream_buffered(g, k, cap, 1024)),
    ("semi_external", lambda g, k, cap: baselines.semi_external(g, k, passes=2)), ("direct", lambda g, k, cap: baselines.direct(g, k)),
):
    register(f"baseline_{_name}_check", sound_sql("event_window"))(lambda s, d, f=_f: soundness(s, built(s, d, "event_window"), cut(f(built(s, d, "event_window"), 4, metrics.block_cap(built(s, d, "event_window").vertices.count(), 4, 0.03)[0])), 4))


for _name, _graph, _f in (
    ("matching_check", "conv_turns", lambda g, k, cfg: baselines.matching_multilevel(g, k, cfg, enforce_balance=True)),
    ("matching_distributed_check", "conv_turns", lambda g, k, cfg: baselines.matching_distributed(g, k, 4, cfg)),
    ("matching_event_window", "event_window", lambda g, k, cfg: baselines.matching_multilevel(g, k, cfg, enforce_balance=True)),
):
    register(f"baseline_{_name}", sound_sql(_graph))(lambda s, d, f=_f, n=_graph: solved(s, built(s, d, n), f(built(s, d, n), 4, in_spark(built(s, d, n))), 4, in_spark(built(s, d, n))))


# ---- measures ----


@register("edge_cut_hash", sql.full("cust_supp", "SELECT CAST(sum(e.w) AS BIGINT) AS cut FROM edges e JOIN part a ON a.id = e.src JOIN part b ON b.id = e.dst WHERE e.src < e.dst AND a.block <> b.block", sql.blocks(16)))
def _(s, d):
    g = built(s, d, "cust_supp")
    return metrics.edge_cut(g.edges, hashed(g, 16))


@register("cut_fraction_hash", sql.full("copurchase", "SELECT CAST(sum(e.w) FILTER (WHERE a.block <> b.block) AS BIGINT) AS cut, CAST(sum(e.w) AS BIGINT) AS m_w, round(sum(e.w) FILTER (WHERE a.block <> b.block) / sum(e.w), 6) AS share FROM edges e JOIN part a ON a.id = e.src JOIN part b ON b.id = e.dst WHERE e.src < e.dst", sql.blocks(8)))
def _(s, d):
    g = built(s, d, "copurchase")
    return metrics.cut_fraction(g.edges, hashed(g, 8))


@register("balance_hash", sql.full("cust_supp", "SELECT b.block, CAST(coalesce(w, 0) AS BIGINT) AS weight, cap, coalesce(w, 0) <= cap AS feasible FROM (SELECT CAST(unnest(range(0, 64)) AS INT) AS block) b LEFT JOIN (SELECT block, sum(v.w) AS w FROM part JOIN vertices v USING (id) GROUP BY 1) x USING (block), (SELECT greatest(CAST(floor(1.03 * sum(w) / 64 + 1e-9) AS BIGINT), CAST(ceil(sum(w) / 64) AS BIGINT)) AS cap FROM vertices) c", sql.blocks(64)))
def _(s, d):
    g = built(s, d, "cust_supp")
    return metrics.balance(g.vertices, hashed(g, 64), 64)


@register("imbalance_hash", sql.full("cust_supp", "SELECT CAST(max(w) AS BIGINT) AS max_block, round(sum(w) / 64, 6) AS avg_block, round(max(w) / (sum(w) / 64) - 1, 6) AS imbalance FROM (SELECT block, sum(v.w) AS w FROM part JOIN vertices v USING (id) GROUP BY 1)", sql.blocks(64)))
def _(s, d):
    g = built(s, d, "cust_supp")
    return metrics.imbalance(g.vertices, hashed(g, 64), 64)


for _name, (_query, _oracle) in experiments.RUN_QUERIES.items():
    register(_name, _oracle)(_query)

from gpart import surface  # noqa: E402  (registers with the functions above)

for _name, (_query, _oracle) in surface.QUERIES.items():
    register(_name, _oracle)(_query)

from gpart import workloads  # noqa: E402

for _name, (_query, _oracle) in workloads.QUERIES.items():
    register(_name, _oracle)(_query)
