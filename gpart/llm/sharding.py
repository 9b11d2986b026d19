"""Sharding by sampled splitters, in DataFrame functions only: shards of nearly equal bytes.

Records are ordered by (hash of text, hash of id and row number), so equal texts stand together and equal rows can be told apart. A size-weighted sample of these keys gives
quantile boundaries of many more ranges than shards; records are dealt to the ranges, overfull ranges are sampled again and
subdivided, and exact sums per range (a bounded table) turn each record's place in its range into its exact place among all
bytes. The shard is the share of all bytes in which the record's middle lies. Equal texts of up to `whole` of a shard's bytes
are placed by their common middle and so stay together; larger groups are dealt over as many shards as their bytes need.

Null texts count as empty: 16 bytes. Repeated rows are records of their own. Extra columns are ignored. Sampling decides
only how the work is dealt out, never a record's shard.
"""

from __future__ import annotations

from bisect import bisect_right
from collections import Counter
from itertools import groupby

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gpart.llm.common import cut, of, table

Key = tuple[int, int]
LOW, HIGH = -(1 << 63), (1 << 63) - 1
FINE_BITS = 12


def sized(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """doc_id, size, text_crc32 and the order's first hash; the text is read once and left behind."""
    text = F.coalesce("text", F.lit(""))
    return of(docs, doc_id=id_col, text=text_col).select("doc_id", (F.octet_length(text) + 16).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.xxhash64(text).alias("h"))


def sampled_keys(records: DataFrame, total: int, keys: int, seed: int) -> list[tuple[Key, float]]:
    """About `keys` keys, drawn with chances in proportion to size, with weights for those that were sure to be drawn."""
    weight = F.col("size") * (keys / max(total, 1))
    chance = F.pmod(F.xxhash64("h2", "h", F.lit(seed)), F.lit(1 << 40)) / float(1 << 40)
    drawn = records.where(chance < weight).select("h", "h2", F.greatest(weight, F.lit(1.0)).alias("weight"))
    return sorted(((r["h"], r["h2"]), r["weight"]) for r in drawn.collect())


def quantiles(sample: list[tuple[Key, float]], ranges: int) -> list[Key]:
    """Boundaries of so many ranges of equal weight in the sample. A range starts with a text's first record, unless the text fills ranges."""
    total, run, out = sum(w for _, w in sample), 0.0, []
    for key, weight in sample:
        if run * ranges >= (len(out) + 1) * total and (not out or key > out[-1]):
            out.append(key)
        run += weight
    many = Counter(h for h, _ in out)
    return [key if many[key[0]] > 1 else (key[0], LOW) for key in out]


def deal(records: DataFrame, splitters: list[Key]) -> DataFrame:
    """records with `range`: the number of splitters at or below the key. A lookup table over the leading bits of the keys
    narrows each record to the ranges that its bits allow; hashes that hold whole ranges are looked up by their own bits."""
    bits = max(4, len(splitters).bit_length())
    heavy = sorted({a for (a, _), (b, _) in zip(splitters, splitters[1:], strict=False) if a == b})
    rows: list[tuple[int, int, int, int, int, int, int]] = []

    def add(k1: int, k2: int, low: Key, high: Key) -> None:
        """Lookup rows for the bucket whose keys go from low up to and including high."""
        for i in range(bisect_right(splitters, low), bisect_right(splitters, high) + 1):
            a, b = splitters[i - 1] if i else (LOW, LOW), splitters[i] if i < len(splitters) else (HIGH, HIGH)
            rows.append((k1, k2, i, *a, *b))

    for k in range(-(1 << (bits - 1)), 1 << (bits - 1)):
        add(k, -1 << 62, (k << (64 - bits), LOW), (((k + 1) << (64 - bits)) - 1, HIGH))
    for h in heavy:
        for k in range(-(1 << (FINE_BITS - 1)), 1 << (FINE_BITS - 1)):
            add(h, k, (h, k << (64 - FINE_BITS)), (h, ((k + 1) << (64 - FINE_BITS)) - 1))
    lookup = records.sparkSession.createDataFrame(rows, "k1 long, k2 long, range int, ah long, ah2 long, bh long, bh2 long")
    own = F.col("h").isin(heavy) if heavy else F.lit(False)
    keyed = records.withColumn("k1", F.when(own, F.col("h")).otherwise(F.shiftright("h", 64 - bits))).withColumn("k2", F.when(own, F.shiftright("h2", 64 - FINE_BITS)).otherwise(F.lit(-1 << 62)))
    above = (F.col("h") > F.col("ah")) | ((F.col("h") == F.col("ah")) & (F.col("h2") >= F.col("ah2")))
    below = (F.col("h") < F.col("bh")) | ((F.col("h") == F.col("bh")) & (F.col("h2") < F.col("bh2"))) | (F.col("range") == len(splitters))
    # at most 2^bits + 4096 rows for each heavy hash, of which there are fewer than splitters
    return keyed.join(F.broadcast(lookup), ["k1", "k2"]).where(above & below).select(*records.columns, "range")


def shard(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", shards: int = 40, whole: float = 1 / 64, range_rows: int = 50_000, most_ranges: int = 16_384, oversample: int = 16) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard of every record. At most most_ranges * oversample keys are drawn."""
    spark = docs.sparkSession
    # the row's number is fixed once it is written down
    records = cut(sized(docs, id_col, text_col).withColumn("h2", F.xxhash64("doc_id", F.monotonically_increasing_id())))
    count, total = records.agg(F.count("*"), F.coalesce(F.sum("size"), F.lit(0))).first()
    ranges = min(most_ranges, max(4 * shards, -(-count // range_rows)))
    splitters = quantiles(sampled_keys(records, total, ranges * oversample, 0), ranges)
    for again in range(1, 4):
        dealt = cut(deal(records, splitters))
        stats = {r["range"]: (r["n"], r["bytes"]) for r in dealt.groupBy("range").agg(F.count("*").alias("n"), F.sum("size").alias("bytes")).collect()}
        over = [k for k, (n, size) in stats.items() if n > max(4 * range_rows, 8 * count // ranges) or (n > 1000 and size * ranges > 8 * total)]
        if not over or again == 3:
            break
        size = sum(stats[k][1] for k in over)
        parts = min(most_ranges, 2 * -(-size * ranges // total) + len(over))
        splitters = sorted({*splitters, *quantiles(sampled_keys(dealt.where(F.col("range").isin(over)), size, parts * oversample, again), parts)})
    before, n_before, bytes_before = [], 0, 0
    for k in sorted(stats):
        before.append((k, n_before, bytes_before))
        n_before, bytes_before = n_before + stats[k][0], bytes_before + stats[k][1]
    offsets = spark.createDataFrame(before, "range int, n_before long, bytes_before long")

    order = Window.partitionBy("range").orderBy("h", "h2", "doc_id")
    group = Window.partitionBy("range", "h")
    # texts that go over several ranges are among those that splitters part: where they begin and their bytes over all ranges
    parted = spark.createDataFrame([(h,) for h in sorted({h for h, h2 in splitters if h2 != LOW})], "h long")
    parts = sorted((r["h"], r["range"], r["bytes"]) for r in dealt.join(F.broadcast(parted), "h").groupBy("h", "range").agg(F.sum("size").alias("bytes")).collect())  # about a row for each range
    over_ranges = {h: [(k, size) for x, k, size in own] for h, own in groupby(parts, key=lambda x: x[0])}
    starts = {k: at for k, _, at in before}
    apart = spark.createDataFrame([(h, sum(size for _, size in own), starts[own[0][0]] + stats[own[0][0]][1] - own[0][1]) for h, own in over_ranges.items() if len(own) > 1], "h long, whole long, begin long")
    placed = dealt.join(F.broadcast(offsets), "range").withColumn("rank", F.col("n_before") + F.row_number().over(order) - 1)
    placed = placed.withColumn("end", F.col("bytes_before") + F.sum("size").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    placed = placed.join(F.broadcast(apart), "h", "left").withColumn("group_bytes", F.coalesce("whole", F.sum("size").over(group))).withColumn("group_start", F.coalesce("begin", F.min(F.col("end") - F.col("size")).over(group)))
    small = F.col("group_bytes") <= int(total / shards * whole)
    twice_middle = F.when(small, 2 * F.col("group_start") + F.col("group_bytes")).otherwise(2 * F.col("end") - F.col("size"))
    number = F.least(F.lit(shards - 1), F.floor(twice_middle * shards / F.lit(2 * max(total, 1)))).cast("int")
    assigned = cut(placed.select("doc_id", "size", "text_crc32", number.alias("shard"), "rank"))
    first = assigned.groupBy("shard").agg(F.min("rank").alias("first"))  # at most `shards` rows
    return assigned.join(F.broadcast(first), "shard").select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("rank") - F.col("first")).alias("slot"), F.lit(None).cast("int").alias("grown_shard"))


def write_shards(docs: DataFrame, path: str, *, id_col: str = "doc_id", **how) -> None:
    """One folder for each shard under path, records in the order of their slots within each file."""
    places = shard(docs, id_col=id_col, **how).select(F.col("doc_id").alias(id_col), F.col("shard").alias("_shard"), F.col("slot").alias("_slot")).dropDuplicates([id_col])
    joined = docs.join(places, id_col)
    joined.repartition("_shard", F.floor(F.col("_slot") / 100_000)).sortWithinPartitions("_shard", "_slot").drop("_slot").write.partitionBy("_shard").parquet(path)


def op4_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard(table(spark, sf_dir, "documents"))
