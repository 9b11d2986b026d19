"""Best-fit packing planned on the histogram of lengths.

Texts are tokenised once; pieces of at most `capacity` tokens keep their length and checksum. The driver sees only how many
pieces there are of each length (at most `capacity` numbers) and plans best-fit decreasing over these counts: bins with the
same free room are one group, and a group is split at most twice for each length, so the plan has a few rows per length
however many documents there are. Pieces then take the planned slots: each gets its rank among the pieces of its length and
joins the plan on length and rank. Ranks come from counts per (length, hash bucket), so no length meets in one task.

Null or empty texts are one piece that holds the closing id only. Repeated rows are pieces of their own. Extra columns are ignored.
"""

from __future__ import annotations

import zlib

import numpy as np
import public_tokenizers
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gpart.llm.common import Memo, cut, of, scan, table

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"
PLAN = "length long, first long, until long, bin long, per_bin long, room_at long"


class WordEncoder:
    """Ids of a text as little-endian bytes. The vocabulary's tokens never cross white space, so words are encoded alone and memoised."""

    #: Python's split() takes these for white space, the tokenizer does not.
    ODD = ("\x1c", "\x1d", "\x1e", "\x1f")

    def __init__(self, path: str, memo: int):
        from tokenizers import Tokenizer

        self.encoder = Tokenizer.from_file(path)
        self.of_word = Memo(self.encode, memo)

    def encode(self, text: str) -> bytes:
        return np.array(self.encoder.encode(text, add_special_tokens=False).ids, dtype="<u4").tobytes()

    def ids(self, text: str) -> bytes:
        if any(c in text for c in self.ODD):
            return self.encode(text)
        return b"".join(map(self.of_word.use().__getitem__, text.split()))


_ENCODERS: dict[tuple[str, int], WordEncoder] = {}


def encoder(path: str, memo: int) -> WordEncoder:
    if (path, memo) not in _ENCODERS:
        _ENCODERS[path, memo] = WordEncoder(path, memo)
    return _ENCODERS[path, memo]


def pieces_of(docs: DataFrame, tokenizer: str, capacity: int, end_id: int, id_col: str, text_col: str, memo: int) -> DataFrame:
    path, end = tokenizer if "/" in tokenizer else None, int(end_id).to_bytes(4, "little")

    def rows(batch: pa.RecordBatch) -> dict[str, list]:
        ids_of = encoder(path or public_tokenizers.path(tokenizer), memo).ids
        out: dict[str, list] = {name: [] for name in ("doc_id", "piece", "start", "length", "ids_crc32")}
        for doc, text in zip(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist(), strict=True):
            ids = (ids_of(text) if text else b"") + end
            for piece, at in enumerate(range(0, len(ids), 4 * capacity)):
                part = ids[at : at + 4 * capacity]
                for name, value in (("doc_id", doc), ("piece", piece), ("start", at // 4), ("length", len(part) // 4), ("ids_crc32", zlib.crc32(part))):
                    out[name].append(value)
        return out

    return scan(of(docs, doc_id=id_col, text=text_col), rows, PIECES)


def plan_slots(histogram: dict[int, int], capacity: int) -> list[tuple[int, int, int, int, int, int]]:
    """Rows (length, first rank, rank after the last, first bin, slots in each bin, room used before) of best-fit decreasing."""
    free: dict[int, list[tuple[int, int]]] = {}  # free room -> [(first bin, bins)]
    plan, bins = [], 0
    rooms = np.zeros(capacity + 1, dtype=bool)
    for length in sorted(histogram, reverse=True):
        left, rank = histogram[length], 0
        while left:
            fitting = np.flatnonzero(rooms[length:])
            if len(fitting):
                room = length + int(fitting[0])
                base, many = free[room].pop()
                if not free[room]:
                    rooms[room] = False
            else:
                room, base = capacity, bins
                many = -(-left // (capacity // length))
                bins += many
            each = room // length
            full = min(many, left // each)
            odd = left - full * each if full < many else 0  # one more bin takes what is left over
            for take, count, at in ((each, full, base), (odd, 1 if odd else 0, base + full)):
                if count:
                    plan.append((length, rank, rank + take * count, at, take, capacity - room))
                    rank += take * count
                    left -= take * count
                    if (rest := room - take * length) > 0:
                        free.setdefault(rest, []).append((at, count))
                        rooms[rest] = True
            if (used := full + (1 if odd else 0)) < many:
                free.setdefault(room, []).append((base + used, many - used))
                rooms[room] = True
    return plan


def ranks(df: DataFrame, key: str, salt: str, histogram: dict[int, int], per_bucket: int = 5_000) -> DataFrame:
    """df with `rank`, gapless from 0 within each key, from counts per (key, bucket); a bucket holds about per_bucket rows. salt: different
    for every row, so that equal rows are dealt like others."""
    spark = df.sparkSession
    sizes = spark.createDataFrame([(k, max(1, -(-n // per_bucket))) for k, n in histogram.items()] or [(0, 1)], f"{key} long, buckets long")
    dealt = df.join(F.broadcast(sizes), key).withColumn("bucket", F.pmod(F.xxhash64(salt), F.col("buckets")))
    counts = dealt.groupBy(key, "bucket").count()
    before = counts.select(key, "bucket", (F.sum("count").over(Window.partitionBy(key).orderBy("bucket")) - F.col("count")).alias("before"))
    order = Window.partitionBy(key, "bucket").orderBy(salt)
    return dealt.withColumn("within", F.row_number().over(order) - 1).join(before, [key, "bucket"]).withColumn("rank", F.col("before") + F.col("within")).drop("within", "before", "buckets", "bucket")


def pack(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", tokenizer: str = "word_bpe_49k.json", capacity: int = 2048, end_id: int = 0, memo: int = 1_000_000) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset of every piece. memo: words a worker remembers, about 200 MB a million."""
    # the row's number is fixed once it is written down
    found = cut(pieces_of(docs, tokenizer, capacity, end_id, id_col, text_col, memo).withColumn("salt", F.monotonically_increasing_id()))
    histogram = {r[0]: r[1] for r in found.groupBy("length").count().collect()}  # at most `capacity` rows
    plan = found.sparkSession.createDataFrame(plan_slots(histogram, capacity) or [(0, 0, 0, 0, 1, 0)], PLAN)
    ranked = ranks(found, "length", "salt", histogram)
    place = (ranked["length"] == plan["length"]) & (ranked["rank"] >= plan["first"]) & (ranked["rank"] < plan["until"])
    step = F.col("rank") - F.col("first")
    return ranked.join(F.broadcast(plan), place).select("doc_id", "piece", "start", ranked["length"], "ids_crc32", (F.col("bin") + F.floor(step / F.col("per_bin"))).cast("long").alias("sequence_id"), (F.col("room_at") + step % F.col("per_bin") * ranked["length"]).cast("long").alias("offset"))


def op9_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"))
