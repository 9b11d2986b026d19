"""Graphs from relational, event, text and vector tables.

A builder returns pairs (a, b, w) of vertex keys, each undirected edge once, and the keys of vertices that may be isolated;
`build_graph` gives them dense ids in the order of the keys and materialises both directions.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gpart.session import cut


#: Members of a group that are paired with all of it in one task, and pairs for each task.
DEALT, PAIRS_IN_TASK = 512, 4_000_000
#: Vertices and directed edges of a graph whose sub-batches run in one task each: exchanges would take longer than they save, and the
#: driver would plan a stage for each. A larger graph is never gathered.
MOST_IN_TASK = 1_000_000


@dataclass
class Members:
    """rows (grp, id, n, many, size, total), written down: the members of groups of two or more, how many each stands for, whether a member
    has several groups, and the group's members and the sum of their n; pairs, the sum of the groups' ordered pairs; several, whether
    any member has several groups. Two members are linked by the product of their n."""

    rows: DataFrame
    pairs: int
    several: bool = True

    def dealt(self, chosen=None, parts: int | None = None) -> tuple[DataFrame, DataFrame]:
        """(grp, deal, src, many) and (grp, deal, dst, also): members dealt out by 512, and all of the group for each deal, both by the
        same partitions. chosen: which rows to take on the left."""
        parts = parts or max(1, min(4096, self.pairs // PAIRS_IN_TASK))
        deals = F.floor((F.col("size") - 1) / DEALT) + 1
        left = (self.rows.where(chosen) if chosen is not None else self.rows).select("grp", (F.col("id") % deals).alias("deal"), F.col("id").alias("src"), F.col("n").alias("n_src"), "many")
        right = self.rows.select("grp", F.explode(F.sequence(F.lit(0).cast("long"), deals - 1)).alias("deal"), F.col("id").alias("dst"), F.col("n").alias("n_dst"), F.col("many").alias("also"))
        return left.repartition(parts, "grp", "deal"), right.repartition(parts, "grp", "deal")

    def edges(self, chosen=None) -> DataFrame:
        """(src, dst, w) in both directions; w counts the groups, or what they sum up to. Only pairs of members of several groups can meet twice."""
        left, right = self.dealt(chosen)
        met = left.join(right.hint("shuffle_hash"), ["grp", "deal"]).where("src <> dst")
        one = met.where("NOT (many AND also)").select("src", "dst", (F.col("n_src") * F.col("n_dst")).alias("w"))
        return one.unionAll(self.met_again(chosen).select("src", "dst", "w")) if self.several else one

    def met_again(self, chosen=None) -> DataFrame:
        """(src, dst, w, times) of the pairs that may have several groups in common."""
        left, right = Members(self.rows.where("many"), self.pairs).dealt(chosen)
        return left.join(right, ["grp", "deal"]).where("src <> dst").groupBy("src", "dst").agg(F.sum(F.col("n_src") * F.col("n_dst")).alias("w"), F.count("*").alias("times"))

    def degrees(self) -> DataFrame:
        """(id, degree, w): each vertex's neighbours and the weight of its edges, from the sizes of its groups; a neighbour that shares
        several groups counts once in the degree, and only such pairs are made."""
        sums = self.rows.groupBy("id").agg(F.sum(F.col("size") - 1).alias("degree"), F.sum(F.col("n") * (F.col("total") - F.col("n"))).alias("w"))
        if not self.several:
            return sums
        twice = self.met_again().where("times > 1").groupBy(F.col("src").alias("id")).agg(F.sum(F.col("times") - 1).alias("twice"))
        return sums.join(twice, "id", "left").select("id", (F.col("degree") - F.coalesce("twice", F.lit(0))).alias("degree"), "w")

    def by_block(self, labels: DataFrame, label: str) -> DataFrame:
        """(grp, label, s): what the members of each label sum up to in each group."""
        return self.rows.join(labels, "id").groupBy("grp", label).agg(F.sum("n").alias("s"))


@dataclass
class Graph:
    """vertices (id, w) and edges (src, dst, w), symmetric, without loops; ids dense from 0."""

    vertices: DataFrame
    edges: DataFrame
    keys: DataFrame | None = None  # (key, id)
    coded: DataFrame | None = None  # neighbourhoods as bytes; `edges` are then decoded from them in every scan
    weighted: bool = True
    groups: Members | None = None  # whose pairs are the edges; `edges` are then paired in every scan
    size: int | None = None  # vertices and directed edges, where they have been counted

    def in_task(self) -> bool:
        """Whether the graph is known to be small enough for one task."""
        return self.groups is None and self.size is not None and self.size <= MOST_IN_TASK

    def gathered(self, df: DataFrame) -> DataFrame:
        """A table about the graph's vertices or edges, in one partition if the graph fits a task: joins, sums and windows over such
        tables need no exchange."""
        return df.coalesce(1) if self.in_task() else df

    def held(self, df: DataFrame) -> DataFrame:
        """The same of a table with a row for each vertex at most, which is kept in the task where it is joined, and not broadcast."""
        return df.coalesce(1).hint("shuffle_hash") if self.in_task() else df

    def together(self) -> Graph:
        """The graph with its tables gathered."""
        return replace(self, vertices=self.gathered(self.vertices), edges=self.gathered(self.edges)) if self.in_task() else self

    def persisted(self) -> Graph:
        """Written to the shared checkpoint folder, for iterative methods; a coded graph keeps its bytes only."""
        if self.coded is not None:
            return Graph(cut(self.vertices), self.edges, self.keys, self.coded, self.weighted)
        if self.groups is not None:
            return Graph(cut(self.vertices), self.edges, self.keys, groups=self.groups)
        return Graph(cut(self.vertices), cut(self.edges), self.keys)

    def edges_of(self, chosen) -> DataFrame:
        """The edges of the vertices that chosen(id column) says; of a coded graph, no others are decoded."""
        if self.groups is not None:
            return self.groups.edges(chosen(F.col("id")))
        if self.coded is None:
            return self.edges.where(chosen(F.col("src")))
        from gpart.operators.codec import decompress

        return decompress(self.coded.where(chosen(F.col("id"))), self.weighted).select("src", "dst", "w")

    def degrees(self) -> DataFrame:
        """(id, degree, w) of the vertices that have edges."""
        if self.groups is not None:
            return self.groups.degrees()
        return self.edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("degree"), F.sum("w").alias("w"))

    def count_edges(self) -> int:
        """Directed edges; a coded graph knows its degrees."""
        if self.groups is not None:
            return self.groups.degrees().agg(F.coalesce(F.sum("degree"), F.lit(0))).first()[0]
        if self.coded is None:
            return self.edges.count()
        return self.coded.agg(F.coalesce(F.sum("degree"), F.lit(0))).first()[0]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def pairs_within(df: DataFrame, group: str, member: str) -> DataFrame:
    """(a, b, w): two distinct members of a group; w counts the groups."""
    own = df.select(group, member).distinct()
    left, right = own.select(group, F.col(member).alias("a")), own.select(group, F.col(member).alias("b"))
    return left.join(right, group).where("a < b").groupBy("a", "b").agg(F.count("*").alias("w"))


SUPPLIER, NATION, CUSTOMER, ORDER = 1_000_000_000, 100, 1_000, 1_000_000_000


def copurchase(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame | None]:
    return pairs_within(table(spark, sf_dir, "lineitem"), "l_orderkey", "l_partkey"), None


def cust_supp(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame | None]:
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")
    orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
    return lines.join(orders, "l_orderkey").groupBy(F.col("o_custkey").alias("a"), (F.col("l_suppkey") + SUPPLIER).alias("b")).agg(F.count("*").alias("w")), None


def fk_tree(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame | None]:
    one = F.lit(1).cast("long").alias("w")
    orders = table(spark, sf_dir, "orders").select((F.col("o_custkey") + CUSTOMER).alias("a"), (F.col("o_orderkey") + ORDER).alias("b"), one)
    customers = table(spark, sf_dir, "customer").select((F.col("c_nationkey") + NATION).cast("long").alias("a"), (F.col("c_custkey") + CUSTOMER).alias("b"), one)
    nations = table(spark, sf_dir, "nation").select(F.col("n_regionkey").cast("long").alias("a"), (F.col("n_nationkey") + NATION).cast("long").alias("b"), one)
    return orders.unionAll(customers).unionAll(nations).distinct(), None


def event_chain(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame | None]:
    events = table(spark, sf_dir, "events").select("event_id", "user_id", "ts")
    before = F.lag("event_id").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    found = events.withColumn("before", before).where("before IS NOT NULL")
    return found.select(F.least("before", "event_id").alias("a"), F.greatest("before", "event_id").alias("b"), F.lit(1).cast("long").alias("w")), events.select(F.col("event_id").alias("key"))


def event_window(spark: SparkSession, sf_dir: str, reach: int = 4) -> tuple[DataFrame, DataFrame | None]:
    """Each event and the next few in time. Places in time come from a distributed numbering, not from one sorted task."""
    events = table(spark, sf_dir, "events").select("event_id", "ts")
    placed = number(events, ["ts", "event_id"], "place")
    ahead = placed.select("event_id", F.explode(F.array(*[F.col("place") + d for d in range(1, reach + 1)])).alias("place"))
    met = ahead.join(placed.select("place", F.col("event_id").alias("next")), "place")
    return met.select(F.least("event_id", "next").alias("a"), F.greatest("event_id", "next").alias("b"), F.lit(1).cast("long").alias("w")), events.select(F.col("event_id").alias("key"))


def page_host(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, str, str]:
    """The pages of each host, all linked with one another: rows, group and member, which are paired only where edges are read."""
    host = F.regexp_extract("url", "//([^/]+)/", 1)
    return table(spark, sf_dir, "pages").select("page_id", host.alias("host")).where("host <> ''"), "host", "page_id"


def page_path(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame | None]:
    pages = table(spark, sf_dir, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("token"))
    return pages.groupBy(F.concat(F.lit("p"), F.col("page_id").cast("string")).alias("a"), F.concat(F.lit("t"), "token").alias("b")).agg(F.count("*").alias("w")), None


def long_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, line): the trimmed lines of more than 20 characters of each document."""
    docs = table(spark, sf_dir, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line")).select("doc_id", F.trim("line").alias("line"))
    return docs.where(F.length("line") > 20)


def doc_line_links(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame | None]:
    """Documents and every line that two or more share, however many: one edge for each document of a line, so none has to be left out.
    Lines travel and are named by a digest of 128 bits."""
    own = long_lines(spark, sf_dir).select("doc_id", F.md5("line").alias("line")).distinct()
    shared = own.groupBy("line").count().where("count >= 2").select("line")
    return own.join(shared, "line").select(F.concat(F.lit("d"), F.col("doc_id").cast("string")).alias("a"), F.concat(F.lit("l"), "line").alias("b"), F.lit(1).cast("long").alias("w")), None


def token_bigram(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame | None]:
    words = table(spark, sf_dir, "documents").select(F.filter(F.split(F.lower("text"), "[ \n\t\r]+"), lambda x: x != "").alias("ws"))
    both = words.where(F.size("ws") > 1).select(F.explode(F.arrays_zip(F.slice("ws", 1, F.size("ws") - 1).alias("x"), F.slice("ws", 2, F.size("ws") - 1).alias("y"))).alias("p"))
    found = both.select(F.least("p.x", "p.y").alias("a"), F.greatest("p.x", "p.y").alias("b")).where("a <> b")
    return found.groupBy("a", "b").agg(F.count("*").alias("w")), None


#: Vectors of a block, of which each pair of blocks is compared in a task, and rows of one product.
VECTORS, ROWS = 8_192, 512
#: A product by the linear algebra library may differ from the sum in order by less than this; cosines are rounded to 9 places.
SLACK = 2e-9


def nearest_in_blocks(unit: DataFrame, k: int) -> DataFrame:
    """(x, y, cosine): for each x the y that may be among its k nearest, itself included; unit: (vec_id, v, norm), of equal lengths.

    Every pair of blocks is one matrix product; what is within SLACK of the k-th best of a row is summed again in the order of the
    components, as a SQL engine does, and only that goes out.
    """
    blocks = max(1, -(-unit.count() // VECTORS))
    placed = unit.withColumn("block", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int"))
    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    left = placed.withColumnRenamed("block", "i").withColumn("j", every).repartition(blocks * blocks, "i", "j")
    right = placed.withColumnRenamed("block", "j").withColumn("i", every).repartition(blocks * blocks, "i", "j")

    def matrix(t: pa.Table):
        v = t.column("v").combine_chunks()
        return t.column("vec_id").to_numpy(), v.flatten().to_numpy().reshape(len(v), -1), t.column("norm").to_numpy()

    def near(key: tuple, a: pa.Table, b: pa.Table) -> pa.Table:
        out: tuple[list, list, list] = ([], [], [])
        if a.num_rows and b.num_rows:
            (x, vx, nx), (y, vy, ny) = matrix(a), matrix(b)
            scaled = (vy / ny[:, None]).T.copy()
            for at in range(0, len(x), ROWS):
                rows = slice(at, at + ROWS)
                cosine = (vx[rows] / nx[rows, None]) @ scaled
                least = np.partition(cosine, len(y) - k, axis=1)[:, len(y) - k] if len(y) > k else np.full(len(cosine), -np.inf)
                r, c = np.nonzero(cosine >= least[:, None] - SLACK)
                dot = np.zeros(len(r))
                for d in range(vx.shape[1]):
                    dot = dot + vx[at + r, d] * vy[c, d]
                for o, found in zip(out, (x[at + r], y[c], dot / (nx[at + r] * ny[c])), strict=True):
                    o.append(found)
        x, y, cosine = (np.concatenate(o) if o else np.empty(0, dtype=kind) for o, kind in zip(out, (np.int64, np.int64, np.float64), strict=True))
        return pa.table({"x": pa.array(x, pa.int64()), "y": pa.array(y, pa.int64()), "cosine": pa.array(cosine, pa.float64())})

    return left.groupBy("i", "j").cogroup(right.groupBy("i", "j")).applyInArrow(near, "x long, y long, cosine double")


def knn8(spark: SparkSession, sf_dir: str, k: int = 8) -> tuple[DataFrame, DataFrame | None]:
    """The k nearest by cosine. All pairs of different vectors are compared, by products of blocks. Of equal vectors only the k + 1 smallest
    ids can be near anything, and one stands for all on the other side. Null vectors, those of another length, of norm 0 or not
    finite are compared pair by pair."""
    vectors = table(spark, sf_dir, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("v"))
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p * q), F.lit(0.0), lambda acc, p: acc + p)
    unit = vectors.withColumn("norm", F.sqrt(dot(F.col("v"), F.col("v"))))
    length = table(spark, sf_dir, "embeddings").agg(F.mode(F.size("embedding"))).first()[0]
    plain = F.coalesce((F.size("v") == F.lit(length)) & (F.col("norm") > 0) & (F.col("norm") < float("inf")), F.lit(False))
    unit = cut(unit.withColumn("plain", plain))
    same = Window.partitionBy("v").orderBy("vec_id")
    ranked = cut(unit.where("plain").withColumn("place", F.row_number().over(same)).withColumn("first", F.min("vec_id").over(Window.partitionBy("v"))))
    few = ranked.where(F.col("place") <= k + 1).select("vec_id", "v", "norm")
    found = nearest_in_blocks(few, k + 1).join(ranked.where("place = 1").select(F.col("vec_id").alias("x")), "x", "left_semi").withColumn("cosine", F.round("cosine", 9))
    best = found.withColumn("place", F.row_number().over(Window.partitionBy("x").orderBy(F.desc("cosine"), "y"))).where(F.col("place") <= k + 1)
    members = ranked.select(F.col("first").alias("class"), F.col("vec_id").alias("x"))
    scored = best.select(F.col("x").alias("class"), "y", "cosine").join(members, "class").where("x <> y").select("x", "y", "cosine")
    if not unit.where("NOT plain").isEmpty():
        left, right = (unit.select(F.col("vec_id").alias(i), F.col("v").alias(f"v{i}"), F.col("norm").alias(f"n{i}"), F.col("plain").alias(f"p{i}")) for i in "xy")
        odd = left.where("NOT px").join(right, F.col("x") != F.col("y")).unionAll(left.join(right.where("NOT py"), F.col("x") != F.col("y")).where("px"))
        scored = scored.unionAll(odd.select("x", "y", F.round(dot(F.col("vx"), F.col("vy")) / (F.col("nx") * F.col("ny")), 9).alias("cosine")))
    near = scored.withColumn("place", F.row_number().over(Window.partitionBy("x").orderBy(F.desc("cosine"), "y"))).where(F.col("place") <= k)
    return near.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"), F.lit(1).cast("long").alias("w")).distinct(), None


def bench_overlap(spark: SparkSession, sf_dir: str, n: int = 8) -> tuple[DataFrame, DataFrame | None]:
    def grams(name: str, key: str, sign: str) -> DataFrame:
        words = table(spark, sf_dir, name).select(F.concat(F.lit(sign), F.col(key).cast("string")).alias("key"), F.filter(F.split(F.lower("text"), "[ \n\t\r]+"), lambda x: x != "").alias("ws"))
        return words.where(F.size("ws") >= n).select("key", F.explode(F.transform(F.sequence(F.lit(1), F.size("ws") - n + 1), lambda i: F.array_join(F.slice("ws", i, n), " "))).alias("gram")).distinct()

    items, docs = grams("benchmark", "item_id", "i"), grams("documents", "doc_id", "d")
    met = items.select(F.col("key").alias("b"), "gram").join(docs.select(F.col("key").alias("a"), "gram"), "gram")
    every = table(spark, sf_dir, "benchmark").select(F.concat(F.lit("i"), F.col("item_id").cast("string")).alias("key"))
    return met.select("a", "b", F.lit(1).cast("long").alias("w")).distinct(), every


def conv_turns(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame | None]:
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", F.concat(F.lit("t"), F.col("conv_id").cast("string"), F.lit("_"), F.col("turn").cast("string")).alias("key"))
    one = F.lit(1).cast("long").alias("w")
    following = turns.withColumn("next", F.lead("key").over(Window.partitionBy("conv_id").orderBy("turn"))).where("next IS NOT NULL")
    return following.select(F.least("key", "next").alias("a"), F.greatest("key", "next").alias("b"), one).unionAll(turns.select(F.concat(F.lit("r"), "role").alias("a"), F.col("key").alias("b"), one)).distinct(), None


def doc_label(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame | None]:
    labels = table(spark, sf_dir, "labels")
    return labels.select((-1 - 2 * F.col("quality") - F.col("toxic")).cast("long").alias("a"), F.col("doc_id").alias("b"), F.lit(1).cast("long").alias("w")).distinct(), None


BUILDERS: dict[str, Callable[[SparkSession, str], tuple]] = {
    f.__name__: f for f in (copurchase, cust_supp, fk_tree, event_chain, event_window, page_host, page_path, doc_line_links, token_bigram, knn8, bench_overlap, conv_turns, doc_label)
}


def number(df: DataFrame, order: list[str], name: str) -> DataFrame:
    """df with a gapless number from 0 in the given (total) order, without a single-task sort.

    Rows are range-partitioned and sorted within partitions; each row's place in its partition is written down once, and
    the partitions' sizes, one number each, give the offsets.
    """
    spark = df.sparkSession
    placed = df.repartitionByRange(*order).sortWithinPartitions(*order)
    placed = cut(placed.withColumn("_part", F.spark_partition_id()).withColumn("_at", F.monotonically_increasing_id().bitwiseAND((1 << 33) - 1)))
    sizes = sorted((r["_part"], r["count"]) for r in placed.groupBy("_part").count().collect())  # one row for each partition
    offsets, run = [], 0
    for part, size in sizes:
        offsets.append((part, run))
        run += size
    before = spark.createDataFrame(offsets, "_part int, _before long")
    return placed.join(F.broadcast(before), "_part").withColumn(name, F.col("_before") + F.col("_at")).drop("_part", "_at", "_before")


def densify(pairs: DataFrame, more_keys: DataFrame | None = None) -> Graph:
    """Pairs of keys as a graph with dense ids in the order of the keys."""
    ends = pairs.select(F.col("a").alias("key")).union(pairs.select("b"))
    keys = number((ends.union(more_keys) if more_keys is not None else ends).distinct(), ["key"], "id").select("key", "id")
    ids_a, ids_b = (keys.select(F.col("key").alias(s), F.col("id").alias(t)) for s, t in (("a", "src"), ("b", "dst")))
    half = pairs.join(ids_a, "a").join(ids_b, "b").select("src", "dst", F.col("w").cast("long").alias("w"))
    edges = half.unionAll(half.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w"))
    return Graph(keys.select("id", F.lit(1).cast("long").alias("w")), edges, keys)


def members_of(held: DataFrame) -> Members:
    """Members of rows (grp, id, n), each id once in a group."""
    sizes = held.groupBy("grp").agg(F.count("*").alias("size"), F.sum("n").alias("total")).where("size > 1")
    linked = held.join(sizes, "grp")
    rows = cut(linked.join(linked.groupBy("id").agg((F.count("*") > 1).alias("many")), "id").select("grp", "id", "n", "many", "size", "total"))
    pairs, several = rows.agg(F.coalesce(F.sum(F.col("size") - 1), F.lit(0)), F.coalesce(F.max("many"), F.lit(False))).first()
    return Members(rows, pairs, several)


def of_groups(df: DataFrame, group: str, member: str) -> Graph:
    """The graph of pairs_within with dense ids in the order of the members, kept as groups: one row for each member of a group, which
    are written once; a pair exists where edges are read. Members without a partner are no vertices."""
    own = cut(df.select(F.col(group).alias("grp"), F.col(member).alias("key")).where("grp IS NOT NULL AND key IS NOT NULL").distinct())
    sizes = own.groupBy("grp").agg(F.count("*").alias("size")).where("size > 1")
    own = cut(own.join(sizes, "grp"))
    keys = number(own.select("key").distinct(), ["key"], "id").select("key", "id")
    members = members_of(own.join(keys, "key").select("grp", "id", F.lit(1).cast("long").alias("n")))
    return Graph(keys.select("id", F.lit(1).cast("long").alias("w")), members.edges(), keys, groups=members)


#: Builders whose pairs cost far more to make than to write: they are made once, not for each place where ids and edges read them.
MADE_ONCE = ("knn8",)


def build_graph(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    found = BUILDERS[name](spark, sf_dir)
    if len(found) == 3:
        return of_groups(*found)
    pairs, keys = found
    return densify(cut(pairs) if name in MADE_ONCE else pairs, keys)
