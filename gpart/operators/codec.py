"""Neighbourhoods as rows and as bytes.

Layout of a row's payload, all numbers as varints (seven bits in a byte, lowest first, the high bit says that more follow):

    2 * first_edge + has_intervals
    [number of intervals]                                          if has_intervals
    interval*:  start, length - 3, weights                         maximal runs of at least three consecutive ids
    leftover*:  gap, weight

The first start and the first leftover are zig-zag differences to the vertex's own id, a later start is the distance to the end of
the interval before less 2, a later leftover's gap is less 1. Weights are zig-zag differences to the weight before, in the order in
which edges are decoded (0 before the first), and absent if all are 1. A vertex of more than `hub_degree` edges is cut into
chunks of `chunk` edges, each coded alone; a degree is the difference to the next row's first_edge. Edge ids are first_edge plus
the place in decoding order.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gpart.functions.columns import varint_len, zigzag
from gpart.session import cut
from gpart.sources.graphs import Graph, Members, number

HUB_DEGREE, CHUNK = 10_000, 1_000
COMPRESSED = "id long, chunk int, first_edge long, degree int, payload binary, n_bytes int"


def prefix_sums(rows: DataFrame, order: str, value: str, name: str) -> DataFrame:
    """rows with the sum of `value` over the rows before, in the order of a dense id; two levels, no single-task window."""
    spark = rows.sparkSession
    width = 65_536
    placed = rows.withColumn("_part", F.floor(F.col(order) / width))
    sums = sorted((r["_part"], r["s"]) for r in placed.groupBy("_part").agg(F.sum(value).alias("s")).collect())  # n / 65536 rows
    run, starts = 0, []
    for part, s in sums:
        starts.append((part, run))
        run += s
    within = Window.partitionBy("_part").orderBy(order).rowsBetween(Window.unboundedPreceding, -1)
    before = F.col("_start") + F.coalesce(F.sum(value).over(within), F.lit(0))
    return placed.join(F.broadcast(spark.createDataFrame(starts or [(0, 0)], "_part long, _start long")), "_part").withColumn(name, before).drop("_part", "_start")


def degrees(graph: Graph) -> DataFrame:
    """(id, degree, first_edge) of every vertex, isolated ones too."""
    every = graph.vertices.join(graph.degrees(), "id", "left").select("id", F.coalesce("degree", F.lit(0)).alias("degree"))
    return prefix_sums(every, "id", "degree", "first_edge")


#: Neighbours of a hub are ranked within ranges of so many ids.
SPAN = 1 << 16


def placed(graph: Graph, hub_degree: int) -> DataFrame:
    """(src, dst, w, degree, first_edge, place): edges with their rank among their source's. A hub's edges are ranked in ranges of
    ids, whose sizes give the ranks before them, so that no task has a whole hub."""
    edges = graph.edges.join(degrees(graph).withColumnRenamed("id", "src"), "src")
    edges = edges.withColumn("_span", F.when(F.col("degree") > hub_degree, F.floor(F.col("dst") / SPAN)).otherwise(0))
    spans = edges.where(F.col("degree") > hub_degree).groupBy("src", "_span").agg(F.count("*").alias("_n"))
    before = spans.select("src", "_span", (F.sum("_n").over(Window.partitionBy("src").orderBy("_span")) - F.col("_n")).alias("_before"))  # n / SPAN rows for a hub at most
    ranked = edges.withColumn("place", F.row_number().over(Window.partitionBy("src", "_span").orderBy("dst")) - 1)
    return ranked.join(before, ["src", "_span"], "left").withColumn("place", F.col("place") + F.coalesce("_before", F.lit(0))).drop("_span", "_before")


def to_csr(graph: Graph, hub_degree: int = HUB_DEGREE, chunk: int = CHUNK) -> DataFrame:
    """(id, chunk, first_edge, degree, nbrs, wts): one row for each vertex, or for each chunk of a hub, so that no list grows with a
    hub's degree. Isolated vertices have one empty row."""
    chunks = placed(graph, hub_degree).withColumn("chunk", F.when(F.col("degree") > hub_degree, F.floor(F.col("place") / chunk)).otherwise(0).cast("int"))
    rows = chunks.groupBy(F.col("src").alias("id"), "chunk").agg(F.min(F.col("first_edge") + F.col("place")).alias("first_edge"), F.sort_array(F.collect_list(F.struct("dst", "w"))).alias("e"))
    full = rows.select("id", "chunk", "first_edge", F.size("e").alias("degree"), F.col("e.dst").alias("nbrs"), F.col("e.w").alias("wts"))
    none = F.array().cast("array<bigint>")
    empty = degrees(graph).where("degree = 0").select("id", F.lit(0).alias("chunk"), "first_edge", F.lit(0).alias("degree"), none.alias("nbrs"), none.alias("wts"))
    return full.unionAll(empty)


def gaps(graph: Graph) -> DataFrame:
    """(src, dst, gap): difference to the neighbour before; of the first one, the zig-zag difference to the vertex."""
    before = F.lag("dst").over(Window.partitionBy("src").orderBy("dst"))
    return graph.edges.select("src", "dst", F.coalesce(F.col("dst") - before, zigzag(F.col("dst") - F.col("src"))).alias("gap"))


def intervals(graph: Graph, min_len: int = 3) -> DataFrame:
    """(src, start, length) of the maximal runs of at least min_len consecutive neighbours."""
    run = F.col("dst") - F.row_number().over(Window.partitionBy("src").orderBy("dst"))
    return graph.edges.withColumn("run", run).groupBy("src", "run").agg(F.min("dst").alias("start"), F.count("*").alias("length")).where(F.col("length") >= min_len).select("src", "start", "length")


def varint_bytes(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All values as varints, one after another, and the number of bytes of each."""
    values = values.astype(np.uint64)
    sizes = np.ones(len(values), dtype=np.int64)
    for n in range(1, 10):
        sizes += values >= np.uint64(1 << 7 * n)
    ends = np.cumsum(sizes)
    out = np.zeros(int(ends[-1]) if len(ends) else 0, dtype=np.uint8)
    starts = ends - sizes
    for n in range(int(sizes.max(initial=0))):
        here = sizes > n
        part = (values[here] >> np.uint64(7 * n) & np.uint64(127)).astype(np.uint8)
        out[starts[here] + n] = part | ((sizes[here] > n + 1).astype(np.uint8) << 7)
    return out, sizes


def varint_values(data: np.ndarray) -> np.ndarray:
    """The numbers of a sequence of varints."""
    last = np.flatnonzero(data < 128)
    starts = np.r_[0, last[:-1] + 1]
    place = np.arange(len(data)) - np.repeat(starts, last - starts + 1)
    return np.add.reduceat((data & 127).astype(np.uint64) << (7 * place).astype(np.uint64), starts) if len(data) else np.empty(0, dtype=np.uint64)


def zig(x: np.ndarray) -> np.ndarray:
    return np.where(x >= 0, 2 * x, -2 * x - 1)


def encode(ids: np.ndarray, first_edge: np.ndarray, sizes: np.ndarray, nbrs: np.ndarray, wts: np.ndarray | None, runs: bool = True) -> list[bytes]:
    """Payloads of rows whose neighbours stand one after another in nbrs. Everything is done for all rows at once: each number
    gets its row, its place in the layout, and is sorted there."""
    rows = np.repeat(np.arange(len(ids)), sizes)
    row_parts, key_parts, sub_parts, value_parts = [], [], [], []

    def put(row, key, sub, value) -> None:
        for out, x in ((row_parts, row), (key_parts, key), (sub_parts, sub), (value_parts, value)):
            out.append(np.broadcast_to(np.asarray(x, dtype=np.int64), np.shape(row)))

    new = np.r_[True, (rows[1:] != rows[:-1]) | (nbrs[1:] != nbrs[:-1] + 1)] if len(nbrs) else np.empty(0, dtype=bool)
    starts = np.flatnonzero(new)
    lengths = np.diff(np.r_[starts, len(nbrs)])
    in_run = np.repeat(lengths >= 3, lengths) if runs else np.zeros(len(nbrs), dtype=bool)
    kept = starts[lengths >= 3] if runs else starts[:0]
    kept_len = lengths[lengths >= 3] if runs else lengths[:0]
    many = np.bincount(rows[kept], minlength=len(ids))
    put(np.arange(len(ids)), -2, 0, 2 * first_edge + (many > 0))
    put(np.flatnonzero(many), -1, 0, many[many > 0])
    # key: the first edge's number, intervals before leftovers; sub: 0 for the start or gap, 1 for the length, 2... for weights
    if len(kept):
        first = np.r_[True, rows[kept][1:] != rows[kept][:-1]]
        ends = nbrs[kept] + kept_len - 1
        put(rows[kept], kept, 0, np.where(first, zig(nbrs[kept] - ids[rows[kept]]), nbrs[kept] - np.r_[0, ends[:-1]] - 2))
        put(rows[kept], kept, 1, kept_len - 3)
    left = np.flatnonzero(~in_run)
    shift = len(nbrs) + 1
    if len(left):
        first = np.r_[True, rows[left][1:] != rows[left][:-1]]
        put(rows[left], left + shift, 0, np.where(first, zig(nbrs[left] - ids[rows[left]]), nbrs[left] - np.r_[0, nbrs[left][:-1]] - 1))
    if wts is not None and len(nbrs):
        order = np.lexsort((np.arange(len(nbrs)), ~in_run, rows))
        first = np.r_[True, rows[order][1:] != rows[order][:-1]]
        change = zig(wts[order] - np.where(first, 0, np.r_[0, wts[order][:-1]]))
        at_run = np.repeat(starts, lengths)[order]
        put(rows[order], np.where(in_run[order], at_run, order + shift), 2 + np.where(in_run[order], order - at_run, 0), change)
    row, key, sub, value = (np.concatenate(x) if x else np.empty(0, dtype=np.int64) for x in (row_parts, key_parts, sub_parts, value_parts))
    order = np.lexsort((sub, key, row))
    data, lengths_of = varint_bytes(value[order])
    bytes_of = np.bincount(row[order], weights=lengths_of, minlength=len(ids)).astype(np.int64)
    ends = np.cumsum(bytes_of)
    raw = data.tobytes()
    return [raw[a:b] for a, b in zip(ends - bytes_of, ends, strict=True)]


def unzig(x: np.ndarray) -> np.ndarray:
    return np.where(x & 1, -(x >> 1) - 1, x >> 1)


def within(sizes: np.ndarray) -> np.ndarray:
    """0, 1, ... for each of the sizes, one after another."""
    ends = np.cumsum(sizes)
    return np.arange(int(ends[-1]) if len(ends) else 0) - np.repeat(ends - sizes, sizes)


def sums_within(values: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Running sums that start anew with each group of the given sizes."""
    run = np.cumsum(values)
    ends = np.cumsum(sizes)
    before = np.r_[0, run][ends - sizes] if len(sizes) else run[:0]
    return run - np.repeat(before, sizes)


def decode_rows(ids: np.ndarray, degrees: np.ndarray, payloads: list[bytes], weighted: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """First edges of all rows, and neighbours and weights of their edges in decoding order, one row after another. All rows are
    decoded at once: numbers are found by their places, and differences are undone by running sums."""
    raw = np.frombuffer(b"".join(payloads), dtype=np.uint8)
    numbers = varint_values(raw).astype(np.int64)
    ends = np.cumsum([len(x) for x in payloads])
    last = np.r_[0, np.cumsum(raw < 128)]
    start = last[np.r_[0, ends[:-1]]] if len(payloads) else ends  # each row's first number
    stop = last[ends] if len(payloads) else ends
    head = numbers[start]
    many = np.where(head & 1, numbers[np.minimum(start + 1, len(numbers) - 1)], 0)  # intervals
    at = start + 1 + (head & 1)
    owner = np.repeat(np.arange(len(ids)), many)
    turn = within(many)
    places, lengths = np.empty(len(owner), dtype=np.int64), np.empty(len(owner), dtype=np.int64)
    first_of = np.cumsum(many) - many
    if not weighted:
        places = at[owner] + 2 * turn
        lengths = numbers[places + 1] + 3
        after = at + 2 * many
    else:  # weights stand between intervals, so that each one's place follows from the length before it
        after = at.copy()
        for k in range(int(many.max(initial=0))):
            rows = np.flatnonzero(many > k)
            here = first_of[rows] + k
            places[here] = after[rows]
            lengths[here] = numbers[after[rows] + 1] + 3
            after[rows] += 2 + lengths[here]
    codes = numbers[places]
    before = np.r_[0, lengths[:-1]]
    starts = sums_within(np.where(turn == 0, ids[owner] + unzig(codes), codes + before + 1), many)
    in_runs = np.bincount(owner, weights=lengths, minlength=len(ids)).astype(np.int64)
    rest = degrees - in_runs
    step = 2 if weighted else 1
    rest_owner, rest_turn = np.repeat(np.arange(len(ids)), rest), within(rest)
    rest_places = after[rest_owner] + step * rest_turn
    codes = numbers[rest_places]
    leftovers = sums_within(np.where(rest_turn == 0, ids[rest_owner] + unzig(codes), codes + 1), rest)
    offset = np.cumsum(degrees) - degrees
    nbrs = np.empty(int(degrees.sum()), dtype=np.int64)
    wts = np.ones(len(nbrs), dtype=np.int64)
    runs_before = sums_within(lengths, many) - lengths
    run_slots = np.repeat(offset[owner] + runs_before, lengths) + within(lengths)
    rest_slots = offset[rest_owner] + in_runs[rest_owner] + rest_turn
    nbrs[run_slots] = np.repeat(starts, lengths) + within(lengths)
    nbrs[rest_slots] = leftovers
    if weighted:
        changes = np.empty(len(nbrs), dtype=np.int64)
        changes[run_slots] = numbers[np.repeat(places + 2, lengths) + within(lengths)]
        changes[rest_slots] = numbers[rest_places + 1]
        wts = sums_within(unzig(changes), degrees)
    if not (after + step * rest == stop).all():
        raise ValueError("payloads do not hold what their degrees say")
    return head >> 1, nbrs, wts


def decode(vertex: int, degree: int, payload: bytes, weighted: bool) -> tuple[int, list[int], list[int]]:
    """first_edge, neighbours and weights of one row in decoding order."""
    first, nbrs, wts = decode_rows(np.array([vertex]), np.array([degree]), [payload], weighted)
    return int(first[0]), nbrs.tolist(), wts.tolist()


def compress(csr: DataFrame, intervals: bool = True, weighted: bool = False) -> DataFrame:
    """COMPRESSED rows of CSR rows; weighted=False drops the weights (they are all 1)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids, first, sizes = (b.column(c).to_numpy().astype(np.int64) for c in ("id", "first_edge", "degree"))
            nbrs, wts = (b.column(c).flatten().to_numpy().astype(np.int64) for c in ("nbrs", "wts"))
            coded = encode(ids, first, sizes, nbrs, wts if weighted else None, intervals)
            yield pa.RecordBatch.from_arrays([b.column("id"), b.column("chunk"), b.column("first_edge"), b.column("degree"), pa.array(coded, pa.binary()), pa.array([len(x) for x in coded], pa.int32())], names=["id", "chunk", "first_edge", "degree", "payload", "n_bytes"])

    return csr.select("id", "chunk", "first_edge", "degree", "nbrs", "wts").mapInArrow(run, COMPRESSED)


def compress_groups(groups: Members, hub_degree: int = HUB_DEGREE, chunk: int = CHUNK) -> tuple[Members, int]:
    """The same groups, their members as coded rows that are decoded in every scan, and the coded bytes. A group's list of members is coded
    as a neighbourhood, in chunks where it is long; weights, where not all are 1, hold n and whether a member has several groups."""
    names = cut(number(groups.rows.select("grp", "size", "total").distinct(), ["grp"], "src"))
    weighted = groups.several or not groups.rows.where("n <> 1").isEmpty()
    w = 2 * F.col("n") + F.col("many").cast("long") if weighted else F.lit(1).cast("long")
    lists = Graph(names.select(F.col("src").alias("id")), groups.rows.join(names.select("grp", "src"), "grp").select("src", F.col("id").alias("dst"), w.alias("w")))
    coded = cut(compress(to_csr(lists, hub_degree, chunk), weighted=weighted))
    size = coded.agg(F.coalesce(F.sum("n_bytes"), F.lit(0))).first()[0]
    n, many = (F.floor(F.col("w") / 2), F.col("w") % 2 == 1) if weighted else (F.lit(1).cast("long"), F.lit(False))
    rows = decompress(coded, weighted).join(names.select("src", "size", "total"), "src").select(F.col("src").alias("grp"), F.col("dst").alias("id"), n.alias("n"), many.alias("many"), "size", "total")
    return Members(rows, groups.pairs, groups.several), size


def decompress(coded: DataFrame, weighted: bool = False) -> DataFrame:
    """(src, dst, w, edge_id), decoded on the fly where the rows are; chunks of a hub are decoded wherever they lie."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids, degrees = (b.column(c).to_numpy().astype(np.int64) for c in ("id", "degree"))
            first, dst, w = decode_rows(ids, degrees, b.column("payload").to_pylist(), weighted)
            edge_ids = np.repeat(first, degrees) + within(degrees)
            yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in (np.repeat(ids, degrees), dst, w, edge_ids)], names=["src", "dst", "w", "edge_id"])

    return coded.select("id", "degree", "payload").mapInArrow(run, "src long, dst long, w long, edge_id long")


def neighbors(coded: DataFrame, ids: DataFrame, weighted: bool = False) -> DataFrame:
    """Decoded edges of the vertices of ids (id); other rows' payloads are never decoded."""
    return decompress(coded.join(ids.select("id"), "id", "left_semi"), weighted)


def degree_of(coded: DataFrame, total_edges: int) -> DataFrame:
    """(id, degree) from first edges alone: the difference to the next vertex's, or to the number of edges."""
    first = coded.where("chunk = 0").select("id", "first_edge")
    following = first.select((F.col("id") - 1).alias("id"), F.col("first_edge").alias("next"))
    return first.join(following, "id", "left").select("id", (F.coalesce("next", F.lit(total_edges)) - F.col("first_edge")).cast("long").alias("degree"))


def plain_bytes(n: int, m: int, weighted: bool) -> int:
    """Uncompressed rows: 8 bytes for each offset and each directed edge, and 8 for its weight."""
    return 8 * (n + 1) + 8 * 2 * m * (2 if weighted else 1)


def varint_total(x: np.ndarray) -> int:
    """Bytes of all numbers as varints."""
    total, most = len(x), int(x.max(initial=0))
    for n in range(1, 10):
        if most < 1 << 7 * n:
            break
        total += int(np.count_nonzero(x >= 1 << 7 * n))
    return total


def row_sizes(vertex: int, nbrs: np.ndarray) -> tuple[int, int, int]:
    """(bytes of gaps, bytes of intervals and leftovers, number of intervals) of a vertex with rising neighbours, without the head."""
    first = lambda x: zig(x[:1] - vertex)
    steps = np.diff(nbrs) - 1
    starts = np.flatnonzero(np.r_[True, steps > 0])
    lengths = np.diff(np.r_[starts, len(nbrs)])
    long = lengths >= 3
    begin, length = nbrs[starts[long]], lengths[long]
    left = nbrs[~np.repeat(long, lengths)]
    runs = varint_total(np.r_[first(begin), begin[1:] - (begin + length - 1)[:-1] - 2]) + varint_total(length - 3) + varint_total(np.r_[first(left), np.diff(left) - 1])
    return varint_total(np.r_[first(nbrs), steps]), runs, len(begin)


def member_sizes(groups: Members) -> DataFrame:
    """(id, gaps, runs, many) of the members of one group: a task has 512 of them and the ids of the group, and makes one list of neighbours
    at a time; no pair goes from task to task."""
    left, right = groups.dealt("NOT many")

    def sized(key: tuple, members: pa.Table, group: pa.Table) -> pa.Table:
        ids, out = np.sort(group.column("dst").to_numpy()), ([], [], [], [])
        for v in members.column("src").to_pylist():
            at = int(np.searchsorted(ids, v))
            for o, x in zip(out, (v, *row_sizes(v, np.r_[ids[:at], ids[at + 1 :]])), strict=True):
                o.append(x)
        return pa.table({c: pa.array(o, pa.int64()) for c, o in zip(("id", "gaps", "runs", "many"), out, strict=True)})

    return left.groupBy("grp", "deal").cogroup(right.groupBy("grp", "deal")).applyInArrow(sized, "id long, gaps long, runs long, many long")


def code_bytes(graph: Graph, weighted: bool = False) -> DataFrame:
    """(id, degree, gap_bytes, interval_bytes): bytes of each vertex's row, unchunked, with gaps alone and with intervals, by column
    functions; edges move once, to their source."""
    line = Window.partitionBy("src").orderBy("dst")
    before = line.rowsBetween(Window.unboundedPreceding, -1)
    by_groups = graph.groups is not None and not weighted  # only members of several groups are sized by their edges
    edges = graph.groups.edges(F.col("many")) if by_groups else graph.edges
    e = edges.withColumn("last", F.lag("dst").over(line)).withColumn("run", F.col("dst") - F.row_number().over(line))
    e = e.withColumn("length", F.count("*").over(Window.partitionBy("src", "run"))).withColumn("long", F.col("length") >= 3)
    e = e.withColumn("head", F.col("long") & (F.col("last").isNull() | (F.col("dst") > F.col("last") + 1)))
    e = e.withColumn("last_long", F.last(F.when(F.col("long"), F.col("dst")), ignorenulls=True).over(before)).withColumn("last_left", F.last(F.when(~F.col("long"), F.col("dst")), ignorenulls=True).over(before))
    first = zigzag(F.col("dst") - F.col("src"))
    size = lambda gap: varint_len(F.coalesce(gap, first))
    runs = F.when(F.col("head"), size(F.col("dst") - F.col("last_long") - 2) + varint_len(F.col("length") - 3)).when(~F.col("long"), size(F.col("dst") - F.col("last_left") - 1)).otherwise(0)
    sums = [F.sum(size(F.col("dst") - F.col("last") - 1)).alias("gaps"), F.sum(runs).alias("runs"), F.sum(F.col("head").cast("int")).alias("many")]
    if weighted:
        by_order = F.lag("w", 1, 0).over(Window.partitionBy("src").orderBy(F.desc("long"), "dst"))
        e = e.withColumn("gap_change", varint_len(zigzag(F.col("w") - F.lag("w", 1, 0).over(line)))).withColumn("run_change", varint_len(zigzag(F.col("w") - by_order)))
        sums += [F.sum("gap_change").alias("gap_weights"), F.sum("run_change").alias("run_weights")]
    sizes = e.groupBy(F.col("src").alias("id")).agg(*sums)
    if by_groups:
        sizes = sizes.unionByName(member_sizes(graph.groups))
    found = degrees(graph).join(sizes, "id", "left").na.fill(0)
    flag = (F.col("many") > 0).cast("int")
    intervals_ = varint_len(2 * F.col("first_edge") + flag) + F.when(flag == 1, varint_len(F.col("many"))).otherwise(0) + F.col("runs")
    gaps_ = varint_len(2 * F.col("first_edge")) + F.col("gaps")
    if weighted:
        intervals_, gaps_ = intervals_ + F.col("run_weights"), gaps_ + F.col("gap_weights")
    return found.select("id", "degree", gaps_.cast("long").alias("gap_bytes"), intervals_.cast("long").alias("interval_bytes"))


def coded_sizes(graph: Graph, intervals_too: bool = True, weighted: bool = False) -> DataFrame:
    """(id, n_bytes) by column functions alone, unchunked: what the payloads will need, before any is made."""
    return code_bytes(graph, weighted).select("id", F.col("interval_bytes" if intervals_too else "gap_bytes").alias("n_bytes"))


def plan_packets(offsets: DataFrame, edges_per_packet: int) -> DataFrame:
    """(id, packet): runs of consecutive vertices with about so many edges."""
    return offsets.select("id", "degree", F.floor(F.col("first_edge") / edges_per_packet).alias("raw"))


def compress_packets(graph: Graph, edges_per_packet: int = 1 << 20, intervals: bool = True, weighted: bool = False) -> tuple[DataFrame, DataFrame]:
    """COMPRESSED rows and PACKETS (packet, lo_id, hi_id, n_edges, n_bytes, byte_offset), in one pass over the input.

    Packets are ranges of consecutive vertices, coded each in one task; what a packet needs is known when it is coded, and its
    place in the output is the sum of the sizes before it. The payloads are not touched again.
    """
    spark = graph.vertices.sparkSession
    csr = to_csr(graph)
    packet = F.floor(F.col("first_edge") / edges_per_packet)
    ranged = csr.withColumn("packet", packet).repartition("packet").sortWithinPartitions("packet", "id", "chunk")
    coded = cut(compress(ranged, intervals, weighted))
    sums = coded.withColumn("packet", F.floor(F.col("first_edge") / edges_per_packet)).groupBy("packet").agg(F.min("id").alias("lo_id"), F.max("id").alias("hi_id"), F.sum("degree").alias("n_edges"), F.sum("n_bytes").alias("n_bytes")).collect()
    rows, run = [], 0
    for number_, r in enumerate(sorted(sums, key=lambda r: r["packet"])):
        rows.append((number_, r["lo_id"], r["hi_id"], r["n_edges"], r["n_bytes"], run))
        run += r["n_bytes"]
    return coded, spark.createDataFrame(rows, "packet int, lo_id long, hi_id long, n_edges long, n_bytes long, byte_offset long")


def compress_two_pass(graph: Graph, intervals: bool = True, weighted: bool = False) -> DataFrame:
    """The baseline: a first pass over the input gives every row's size and place, a second one codes: COMPRESSED and byte_offset."""
    sizes = prefix_sums(coded_sizes(graph, intervals, weighted), "id", "n_bytes", "byte_offset").select("id", "byte_offset")
    return compress(to_csr(graph, hub_degree=1 << 30), intervals, weighted).join(sizes, "id")


def compression_report(graph: Graph, weighted: bool = False) -> DataFrame:
    """n, m, plain and coded bytes (gaps alone, gaps and intervals), ratios, and coded bytes for each undirected edge."""
    sums = [F.coalesce(F.sum(c), F.lit(0)).cast("long").alias(c) for c in ("gap_bytes", "interval_bytes")]
    row = code_bytes(graph, weighted).agg(F.count("*").alias("n"), F.coalesce(F.sum("degree") / 2, F.lit(0)).cast("long").alias("m"), *sums)
    plain = 8 * (F.col("n") + 1) + 16 * F.col("m") * (2 if weighted else 1)
    return row.withColumn("plain_bytes", plain).select("n", "m", "plain_bytes", "gap_bytes", "interval_bytes", F.round(F.col("plain_bytes") / F.col("gap_bytes"), 6).alias("gap_ratio"), F.round(F.col("plain_bytes") / F.col("interval_bytes"), 6).alias("interval_ratio"), F.round(F.col("interval_bytes") / F.col("m"), 6).alias("bytes_per_edge"))


