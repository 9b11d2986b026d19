"""Exact Jaccard join of documents on word n-grams, as a blocked sparse product of the document by n-gram incidence.

1. One scan gives every text's number of distinct n-grams (64-bit hashes), a 128-bit digest of the set, of which 64 bits name
   the set (a node) and the other 64 check that unequal sets never share a name (if they do, all are named anew), and counts
   n-grams in a sketch of fixed size. Equal sets are one node from here on, found again by one row's id and hash of the text.
2. N-grams are ordered by sketch count, rare ones first (any order is correct; this one keeps blocks small). Two sets that
   overlap enough share an n-gram among the first n - ceil(least * n) + 1 of each. These make the incidence matrix; an n-gram's
   column is a block, and the column of a very frequent n-gram is several, by the node.
3. In each block every node meets the block's smallest node; such pairs within the size bound are verified exactly. Links
   give components; overlaps of half the union give families. So a block costs as many pairs as it has nodes.
4. Families of several components are multiplied out: a large component has blocks of its own, the nodes of small ones share
   blocks, and each pair of blocks that can hold two components is one product of incidence matrices, from which a task returns a
   spanning forest of the links between components. So a large component with a few strangers costs one product for each of
   its blocks, and is never multiplied with itself.
5. Between families, overlap counts are accumulated over the n-grams that several families share, pairs whose count and places
   bound the overlap below the limit are discarded, and the rest is verified.

Every two nodes that share an n-gram are thus counted exactly, bounded away, or known to be connected: no link between components
is lost. Only components are computed: neither the links nor their number for each document is returned, since pairs that are already
connected, or equal, are never enumerated. Null texts and texts without words have no n-grams and are linked with nothing; texts of fewer than n words have one.
Repeated rows (even with one id) share a node; rows without an id are linked like others, and a component's id is the smallest
there is (a row's own id, null, if there is none). Extra columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gpart.llm.common import Memo, cut, of, pieces, release, table, utf8
from gpart.llm.components import components, forest

LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
SKETCH_BITS, CHUNK_BITS = 22, 16
SETS = "doc_id long, h long, n_shingles long, node long, check long, chunk int, counts binary"
#: An n-gram that the sketch has seen more often than this is dealt over several blocks.
HOT = 20_000

_WORDS: list[Memo] = []


def word_hashes() -> Memo:
    if not _WORDS:
        _WORDS.append(Memo(xxhash.xxh3_64_intdigest))
    return _WORDS[0].use()


def shingles(text: bytes | None, n: int) -> np.ndarray:
    """Sorted distinct hashes of the n-word shingles; of a shorter text, the hash of all its words."""
    words = text.translate(LOWER).split() if text else []
    if not words:
        return np.empty(0, dtype=np.uint64)
    hashes = np.fromiter(map(word_hashes().__getitem__, words), dtype=np.uint64, count=len(words))
    size = min(n, len(words))
    mixed = np.full(len(words) - size + 1, size * 0x9E3779B97F4A7C15 & (1 << 64) - 1, dtype=np.uint64)
    for k in range(size):
        mixed = mixed * np.uint64(0xD6E8FEB86659FD93) + hashes[k : len(words) - size + 1 + k]
        mixed ^= mixed >> np.uint64(29)
    mixed *= np.uint64(0xBF58476D1CE4E5B9)
    return np.unique(mixed ^ mixed >> np.uint64(32))


def names_of(own: np.ndarray, seed: int = 0) -> tuple[int, int]:
    """The name of a set and its check, 64 bits each."""
    whole = xxhash.xxh3_128_intdigest(own.tobytes(), seed)
    return (whole & (1 << 64) - 1) - (1 << 63), (whole >> 64) - (1 << 63)


def described(n: int, seed: int):
    """Rows of SETS: one for each text, and at the end of a task its part of the sketch, in chunks."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts, waiting, held = np.zeros(1 << SKETCH_BITS, dtype=np.uint32), [], 0

        def count() -> None:
            counts[:] += np.bincount(np.concatenate(waiting), minlength=1 << SKETCH_BITS).astype(np.uint32)
            waiting.clear()

        names = ("doc_id", "h", "n_shingles", "node", "check", "chunk", "counts")
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.binary())
        rows = lambda *columns: pa.RecordBatch.from_arrays([pa.array(c, type=k) for c, k in zip(columns, kinds, strict=True)], names=list(names))
        for whole in batches:
            for batch in pieces(whole):
                sets = [shingles(t, n) for t in utf8(batch, "text")]
                for own in sets:
                    if len(own):
                        waiting.append((own >> np.uint64(64 - SKETCH_BITS)).astype(np.int64))
                        held += len(own)
                        if held > 1 << 20:
                            count()
                            held = 0
                none = [None] * len(sets)
                named = [names_of(s, seed) if len(s) else (None, None) for s in sets]
                yield rows(batch.column("doc_id"), batch.column("h"), [len(s) for s in sets], [x for x, _ in named], [y for _, y in named], none, none)
        if waiting:
            count()
        if counts.any():
            parts = np.minimum(counts, 65535).astype("<u2").reshape(-1, 1 << CHUNK_BITS)
            none = [None] * len(parts)
            yield rows(none, none, none, none, none, list(range(len(parts))), [zlib.compress(p.tobytes(), 1) for p in parts])
        del counts
        release()

    return run


def rarity(sketch_parts: DataFrame) -> np.ndarray:
    """One byte for each of the sketch's counters: its count on a log scale. The driver gets the sums, whose size is fixed."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for chunk, data in zip(batch.column("chunk").to_pylist(), batch.column("counts").to_pylist(), strict=True):
                sums.setdefault(chunk, np.zeros(1 << CHUNK_BITS, dtype=np.uint64))[:] += np.frombuffer(zlib.decompress(data), dtype="<u2")
        if sums:
            scaled = [np.minimum(255, 8 * np.log2(1 + s)).astype(np.uint8).tobytes() for s in sums.values()]
            yield pa.RecordBatch.from_arrays([pa.array(list(sums), type=pa.int32()), pa.array(scaled, type=pa.binary())], names=["chunk", "counts"])

    out = np.zeros((1 << SKETCH_BITS - CHUNK_BITS, 1 << CHUNK_BITS), dtype=np.uint8)
    chunks = 1 << SKETCH_BITS - CHUNK_BITS
    for row in sketch_parts.repartition(min(chunks, 16), "chunk").mapInArrow(run, "chunk int, counts binary").collect():
        out[row["chunk"]] = np.frombuffer(row["counts"], dtype=np.uint8)
    return out.ravel()


def least_overlap(size: int, percent: int) -> int:
    return -(-size * percent // 100)


class Join:
    """most_bytes: the size up to which what selects texts is broadcast."""

    def __init__(self, docs: DataFrame, n: int, percent: int, most_bytes: int, seeds: int = 4):
        self.docs = docs.withColumn("h", F.xxhash64("text"))
        self.n, self.percent, self.most_bytes = n, percent, most_bytes
        for self.seed in range(seeds):
            found = cut(self.docs.select("doc_id", "h", "text").mapInArrow(described(n, self.seed), SETS))
            self.sets = found.where("chunk IS NULL").select("doc_id", "h", "n_shingles", "node")
            one = F.min(F.struct("doc_id", "h"))  # a row that has the set, if possible with an id: nulls come first
            with_id = F.min(F.when(F.col("doc_id").isNotNull(), F.struct("doc_id", "h")))
            self.nodes = cut(found.where("node IS NOT NULL").groupBy("node").agg(F.min("doc_id").alias("first_id"), F.coalesce(with_id, one).alias("row"), F.min("check").alias("low"), F.max("check").alias("high")))
            if self.nodes.where("low <> high").isEmpty():
                break
        else:
            raise RuntimeError("unequal sets share a name under every seed")
        self.rare = docs.sparkSession.sparkContext.broadcast(rarity(found.where("chunk IS NOT NULL").select("chunk", "counts")))

    def incidence(self) -> DataFrame:
        """(gram, node, n, pos, pivot): the leading n-grams of each node, in blocks of two nodes or more."""
        n, percent, rare, seed = self.n, self.percent, self.rare, self.seed

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            seen: set[int] = set()
            for whole in batches:
                for batch in pieces(whole):
                    nodes, sizes, leading, places = [], [], [], []
                    for own in (shingles(t, n) for t in utf8(batch, "text")):
                        if len(own) and (node := names_of(own, seed)[0]) not in seen:
                            if len(seen) > 1_000_000:
                                seen.clear()  # later copies are dropped below
                            seen.add(node)
                            seen_often = rare.value[(own >> np.uint64(64 - SKETCH_BITS)).astype(np.int64)]
                            order = np.lexsort((own, seen_often))
                            order = order[: len(own) - least_overlap(len(own), percent) + 1]
                            nodes.append(node)
                            sizes.append(len(own))
                            leading.append(own[order].view(np.int64))
                            # the sketch's log scale is of eighths of an octave
                            parts = np.maximum(1, np.ceil(2.0 ** (seen_often[order] / 8) / HOT)).astype(np.int64)
                            places.append(np.where(parts > 1, node % parts + 1, 0))  # 0: the whole column
                    yield pa.RecordBatch.from_arrays([pa.array(nodes, type=pa.int64()), pa.array(sizes, type=pa.int32()), pa.array(leading, type=pa.list_(pa.int64())), pa.array(places, type=pa.list_(pa.int64()))], names=["node", "n", "grams", "parts"])
            seen.clear()
            release()

        leading = self.docs.select("text").mapInArrow(run, "node long, n int, grams array<long>, parts array<long>").dropDuplicates(["node"])
        entries = leading.select("node", "n", F.posexplode(F.arrays_zip("grams", "parts")).alias("pos", "x")).select("node", "n", "pos", F.col("x.grams").alias("gram"), F.col("x.parts").cast("int").alias("part"))
        block = Window.partitionBy("gram", "part")
        met = entries.withColumn("many", F.count("*").over(block)).withColumn("pivot", F.min(F.struct("node", "n")).over(block))
        return met.where("many > 1 OR part > 0").select("gram", "node", "n", "pos", "pivot")

    def within_size(self, a: str, b: str):
        return (100 * F.col(a) >= self.percent * F.col(b)) & (100 * F.col(b) >= self.percent * F.col(a))

    def gathered(self, wanted: DataFrame, key: str) -> DataFrame:
        """wanted: (node, keys), keys an array of structs of type `key`. One row (key, node, grams) for each node and key: sets are
        made from the texts where these are read and move once, to where they are needed."""
        ids = cut(wanted.join(self.nodes, "node").select("node", "row", "keys"))
        size = ids.agg(F.coalesce(F.sum(32 + 32 * F.size("keys")), F.lit(0))).first()[0]
        one = F.broadcast(ids) if size <= self.most_bytes else ids
        texts = self.docs.join(one, self.docs["doc_id"].eqNullSafe(F.col("row.doc_id")) & (self.docs["h"] == F.col("row.h"))).select("text", "node", "keys")
        n, seed = self.n, self.seed

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for whole in batches:
                for batch in pieces(whole, 256):
                    sets = [shingles(t, n) for t in utf8(batch, "text")]
                    nodes = batch.column("node").to_pylist()
                    kept = [i for i, own in enumerate(sets) if len(own) and names_of(own, seed)[0] == nodes[i]]
                    keys = batch.column("keys").take(pa.array(kept, pa.int64()))
                    yield pa.RecordBatch.from_arrays([keys, pa.array([nodes[i] for i in kept], pa.int64()), pa.array([sets[i].view(np.int64) for i in kept], pa.list_(pa.int64()))], names=["keys", "node", "grams"])
            release()

        return texts.mapInArrow(run, f"keys array<{key}>, node long, grams array<long>").select(F.explode("keys").alias("key"), "node", "grams").select("key.*", "node", "grams")

    def verified(self, pairs: DataFrame, per_task: int = 500) -> DataFrame:
        """(a, b, linked, near) of the pairs (a, b), by their whole sets; near: an overlap of half the union. The partners of one node
        a are dealt over several tasks, each with a's set."""
        many = pairs.groupBy("a").agg(F.ceil(F.count("*") / per_task).cast("int").alias("salts"))
        dealt = pairs.join(many, "a").withColumn("salt", F.pmod(F.xxhash64("b"), F.col("salts")).cast("int"))
        rows = dealt.select(F.col("b").alias("node"), F.struct("a", "salt").alias("key")).unionAll(dealt.select("a", "salt").distinct().select(F.col("a").alias("node"), F.struct("a", "salt").alias("key")))
        wanted = rows.groupBy("node").agg(F.collect_list("key").alias("keys"))  # a node has as many as leading n-grams, or as its partners' tasks
        percent = self.percent

        def compared(key: tuple, rows: pa.Table) -> pa.Table:
            own = rows.column("node").to_numpy()
            sets = [np.asarray(x.values) for x in rows.column("grams").combine_chunks()] if rows.num_rows else []
            a = key[0].as_py()
            out: dict[str, list] = {"a": [], "b": [], "linked": [], "near": []}
            at = np.flatnonzero(own == a)
            if len(at):
                pivot = np.sort(sets[at[0]])
                for node, other in zip(own.tolist(), sets, strict=True):
                    if node != a:
                        place = np.searchsorted(pivot, other)
                        both = int((pivot[np.minimum(place, len(pivot) - 1)] == other).sum())
                        union = len(pivot) + len(other) - both
                        for name, value in (("a", a), ("b", node), ("linked", 100 * both >= percent * union), ("near", 2 * both >= union)):
                            out[name].append(value)
            return pa.table([pa.array(out["a"], pa.int64()), pa.array(out["b"], pa.int64()), pa.array(out["linked"], pa.bool_()), pa.array(out["near"], pa.bool_())], names=list(out))

        return cut(self.gathered(wanted, "struct<a:bigint,salt:int>").groupBy("a", "salt").applyInArrow(compared, "a long, b long, linked boolean, near boolean"))

    def multiplied(self, families: DataFrame, block: int = 1024) -> DataFrame:
        """Links (a, b) within families (node, family, component), all pairs of different components counted: each pair of blocks of a
        family is one product of incidence matrices, of which a task returns a spanning forest of the links it finds."""
        sizes = families.groupBy("family", "component").agg(F.count("*").alias("many"))
        large = F.col("many") >= block
        owner = F.when(large, F.col("component"))  # null: blocks that small components share
        shared = sizes.groupBy("family", owner.alias("owner")).agg(F.sum("many").alias("many")).withColumn("blocks", F.ceil(F.col("many") / block).cast("int"))
        shared = cut(shared.select("family", "owner", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("part"), "blocks"))
        left, right = (shared.select("family", *[F.col(c).alias(f"{c}_{s}") for c in ("owner", "part")]) for s in "ij")
        # every two blocks of a family that can hold two components, once; a table of one row for each product
        place = lambda s: F.struct(F.coalesce(f"owner_{s}", F.lit(-(1 << 63))), f"part_{s}")
        pairs = left.join(right, "family").where((place("i") <= place("j")) & (F.col("owner_i").isNull() | F.col("owner_j").isNull() | (F.col("owner_i") != F.col("owner_j"))))
        pairs = pairs.withColumn("task", F.xxhash64("family", "owner_i", "part_i", "owner_j", "part_j"))
        sides = pairs.select("family", "task", F.col("owner_i").alias("owner"), F.col("part_i").alias("part"), F.lit(0).alias("side")).unionAll(
            pairs.where(~(F.col("owner_i").eqNullSafe(F.col("owner_j")) & (F.col("part_i") == F.col("part_j")))).select("family", "task", "owner_j", "part_j", F.lit(1))
        )
        keys = cut(sides.groupBy("family", "owner", "part").agg(F.collect_list(F.struct("family", "task", "side")).alias("tasks")))  # as many as a family has blocks
        many = shared.select("family", "owner", "blocks").distinct()
        dealt = families.join(sizes, ["family", "component"]).withColumn("owner", owner).drop("many")
        dealt = dealt.join(many.withColumnRenamed("family", "f").withColumnRenamed("owner", "o"), (F.col("family") == F.col("f")) & F.col("owner").eqNullSafe(F.col("o"))).drop("f", "o")
        dealt = dealt.withColumn("part", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
        named = keys.select(F.col("family").alias("f"), F.col("owner").alias("o"), F.col("part").alias("p"), "tasks")
        dealt = dealt.join(named, (F.col("family") == F.col("f")) & F.col("owner").eqNullSafe(F.col("o")) & (F.col("part") == F.col("p")))
        wanted = dealt.select("node", F.transform("tasks", lambda t: F.struct(t["family"].alias("family"), t["task"].alias("task"), t["side"].alias("side"), F.col("component"))).alias("keys"))
        percent = self.percent

        def product(rows: pa.Table) -> pa.Table:
            node, component, side = (rows.column(c).to_numpy() for c in ("node", "component", "side"))
            sets = [np.asarray(x.values) for x in rows.column("grams").combine_chunks()]
            left, right = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
            right = right if len(right) else left  # a block with itself
            sizes = np.array([len(x) for x in sets])
            grams, where, counts = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
            row = np.repeat(np.arange(len(sets)), sizes)
            shared = counts[where] > 1  # what one set has alone overlaps with nothing
            row, column = row[shared], (np.cumsum(counts > 1) - 1)[where[shared]]
            overlap = np.zeros((len(left), len(right)), dtype=np.float32)
            width = 1024
            for start in range(0, int((counts > 1).sum()), width):
                part = (column >= start) & (column < start + width)
                incidence = np.zeros((len(sets), width), dtype=np.float32)
                incidence[row[part], column[part] - start] = 1
                overlap += incidence[left] @ incidence[right].T
            both = overlap.astype(np.int64)
            linked = (100 * both >= percent * (sizes[left][:, None] + sizes[right][None, :] - both)) & (component[left][:, None] != component[right][None, :])
            edges = forest(linked, node[left], node[right])
            return pa.table({"a": pa.array([x for x, _ in edges], pa.int64()), "b": pa.array([y for _, y in edges], pa.int64())})

        return cut(self.gathered(wanted, "struct<family:bigint,task:bigint,side:int,component:bigint>").groupBy("family", "task").applyInArrow(product, "a long, b long"))

    def components(self) -> DataFrame:
        blocks = cut(self.incidence())
        met = cut(blocks.where((F.col("node") != F.col("pivot.node")) & self.within_size("n", "pivot.n")).select(F.col("pivot.node").alias("a"), F.col("node").alias("b")).distinct())
        tried = self.verified(met)
        linked = tried.where("linked").select("a", "b")
        known = components(linked)
        # families: what half-overlapping pairs connect; their inner pairs are multiplied out, so that only pairs between families remain
        family = cut(components(tried.where("near").select("a", "b")).withColumnRenamed("component", "family").join(known, "node", "left").withColumn("component", F.coalesce("component", "node")))
        unsettled = cut(family.groupBy("family").agg(F.min("component").alias("low"), F.max("component").alias("high")).where("low <> high").select("family"))
        few = 16 * unsettled.count() <= self.most_bytes
        inner = self.multiplied(cut(family.join(F.broadcast(unsettled) if few else unsettled, "family", "left_semi")))
        at = cut(blocks.select("gram", "node", "n", "pos").join(family, "node", "left").withColumn("family", F.coalesce("family", "node")))
        several = at.groupBy("gram").agg(F.min("family").alias("low"), F.max("family").alias("high")).where("low <> high").select("gram")
        still = cut(at.join(several, "gram", "left_semi"))
        left, right = (still.select("gram", *[F.col(c).alias(f"{c}_{s}") for c in ("node", "n", "pos", "family")]) for s in "ab")
        product = left.join(right, "gram").where((F.col("node_a") < F.col("node_b")) & (F.col("family_a") != F.col("family_b")) & self.within_size("n_a", "n_b"))
        overlaps = product.groupBy(F.col("node_a").alias("a"), F.col("node_b").alias("b"), "n_a", "n_b").agg(F.count("*").alias("shared"), F.max("pos_a").alias("pos_a"), F.max("pos_b").alias("pos_b"))
        most = F.col("shared") + F.least(F.col("n_a") - F.col("pos_a"), F.col("n_b") - F.col("pos_b")) - 1  # all common n-grams up to the last shared one are counted
        able = overlaps.where(100 * most >= self.percent * (F.col("n_a") + F.col("n_b") - most)).select("a", "b")
        known_pairs = met.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
        outer = self.verified(cut(able.join(known_pairs, ["a", "b"], "left_anti"))).where("linked").select("a", "b")
        more = inner.unionAll(outer)
        return known if more.isEmpty() else components(linked.unionAll(more))


def placed(docs: DataFrame, id_col: str, text_col: str, n: int, percent: int, most_bytes: int) -> tuple[Join, DataFrame]:
    """The join and (node, component, component_id, row) of its nodes; row: the id and hash of the text of the row that stands for a node."""
    join = Join(of(docs, doc_id=id_col, text=text_col), n, percent, most_bytes)
    grouped = join.nodes.join(join.components(), "node", "left").withColumn("component", F.coalesce("component", "node"))
    first = grouped.groupBy("component").agg(F.min("first_id").alias("component_id"))
    return join, grouped.join(first, "component").select("node", "component", "component_id", "row")


def ngram_join(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", n: int = 4, percent: int = 85, most_bytes: int = 64 << 20) -> DataFrame:
    """doc_id, n_shingles, component_id of every row. percent: the least 100 * intersection / union that links two sets."""
    join, nodes = placed(docs, id_col, text_col, n, percent, most_bytes)
    return join.sets.join(nodes.select("node", "component_id"), "node", "left").select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"))


def one_of_each(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", n: int = 5, percent: int = 80, most_bytes: int = 64 << 20) -> DataFrame:
    """docs with one row of each component, the one with the smallest id (rows without an id come last), and every row without
    words. Rows that share an id are told apart by their texts; of rows that share id and text one stays."""
    join, nodes = placed(docs, id_col, text_col, n, percent, most_bytes)
    order = F.struct(F.col("row.doc_id").isNull().cast("int").alias("none"), F.col("row.doc_id").alias("doc_id"), F.col("row.h").alias("h"))
    best = nodes.groupBy("component").agg(F.min(order).alias("x")).select(F.col("x.doc_id").alias("_id"), F.col("x.h").alias("_h"))
    marked = docs.withColumn("_text_hash", F.xxhash64(F.col(f"`{text_col}`")))
    one = marked.join(best, F.col(f"`{id_col}`").eqNullSafe(F.col("_id")) & (F.col("_text_hash") == F.col("_h"))).drop("_id", "_h").dropDuplicates([id_col, "_text_hash"])
    blank = marked.where(F.col(f"`{text_col}`").isNull() | ~F.col(f"`{text_col}`").rlike(r"[^\x20\x09-\x0D]"))
    return one.unionByName(blank).select(*docs.columns)


#: Shingles as strings (words hold no space), all pairs that share one, components by reachability.
OP3_SQL = r"""
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, hash(array_to_string(w[i:i + least(len(w), 4) - 1], ' ')) AS g FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 3, 1) + 1)) AS i FROM d WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
o AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2),
l AS (SELECT o.a, o.b FROM o JOIN n x ON x.doc_id = o.a JOIN n y ON y.doc_id = o.b WHERE 100 * c >= 85 * (x.n + y.n - c)),
e AS (SELECT a, b FROM l UNION ALL SELECT b, a FROM l),
r AS (SELECT a AS k, least(a, b) AS c FROM e UNION SELECT e.b, r.c FROM r JOIN e ON e.a = r.k),
m AS (SELECT k, min(c) AS c FROM r GROUP BY 1)
SELECT d.doc_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_shingles, coalesce(m.c, d.doc_id) AS component_id FROM d LEFT JOIN n USING (doc_id) LEFT JOIN m ON m.k = d.doc_id
"""


def op3_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join(table(spark, sf_dir, "documents"))
