"""Near-duplicate vectors by hierarchical navigable small-world graphs, one per shard.

Equal vectors of a label are one node with a count (a 64-bit name, checked against a 128-bit digest; names that unequal vectors
share are drawn anew with another seed). Nodes of a label are dealt to shards of about `shard_rows`; each shard's task
builds a graph, and every pair of shards of a label is searched both ways by one task, so all vectors query every shard. A search
descends the layers, widens a beam on the lowest one, and follows all links above the limit from there.

Each search audits itself against all vectors of the shard: `audits` of its queries, and as many planted ones, vectors of the
shard moved to a cosine between the limit and 1, so that an audit always has links to find however rare real ones are. Recall is
the mean over the audited queries that have links, so that a hot group's many links do not speak for the others; while
it is below `recall` for either kind, the beam doubles, and a beam as wide as the shard is an exhaustive search. `audit_report`
returns what the audits found. Cosines are in double precision. A task returns counts for each
node and a spanning forest of its links, whose union gives the components.

Vectors that are null, empty, zero or hold null or non-finite components, and those with a null label, are linked with nothing;
vectors of unlike lengths are never compared. Repeated rows count as vectors; rows without an id are linked like others, and a
component's id is the smallest there is, null if all are. Extra columns are ignored.
"""

from __future__ import annotations

import pickle
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gpart.llm.common import cut, of, table
from gpart.llm.components import components, forest


class SmallWorld:
    """A hierarchical navigable small-world graph over unit vectors."""

    WIDTH, SLACK = 24, 48  # links a node keeps on the lowest layer; links it may gather before they are thinned out
    STEP = 4  # beam nodes expanded at once

    def __init__(self, vectors: np.ndarray, beam: int = 48, seed: int = 0):
        self.vectors = vectors
        n = len(vectors)
        draws = np.random.default_rng(seed).random(n)
        self.levels = np.minimum(12, (-np.log(np.maximum(draws, 1e-12)) / np.log(self.WIDTH / 2)).astype(int))
        tops = int(self.levels.max(initial=0))
        self.links = [np.full((n, self.SLACK), -1, dtype=np.int32) for _ in range(1)] + [{} for _ in range(tops)]
        self.degree = np.zeros(n, dtype=np.int32)
        self.visited = np.zeros(n, dtype=bool)
        self.entry, self.top = 0, int(self.levels[0]) if n else 0
        for layer in range(1, self.top + 1):
            self.links[layer][0] = []
        for i in range(1, n):
            self._insert(i, beam)

    def neighbours(self, nodes: np.ndarray, layer: int) -> np.ndarray:
        if layer:
            return np.array([j for i in nodes.tolist() for j in self.links[layer].get(i, ())], dtype=np.int64)
        found = self.links[0][nodes].ravel()
        return found[found >= 0]

    def beam(self, query: np.ndarray, starts: np.ndarray, width: int, layer: int) -> tuple[np.ndarray, np.ndarray]:
        """The best nodes and their cosines, best first."""
        ids, sims = starts, self.vectors[starts] @ query
        seen, done = [starts], np.zeros(len(starts), dtype=bool)
        self.visited[starts] = True
        while True:
            open_ = np.flatnonzero(~done)[: self.STEP]
            if not len(open_):
                break
            done[open_] = True
            near = self.neighbours(ids[open_], layer)
            near = np.unique(near[~self.visited[near]])
            if not len(near):
                continue
            self.visited[near] = True
            seen.append(near)
            ids, sims, done = np.concatenate([ids, near]), np.concatenate([sims, self.vectors[near] @ query]), np.concatenate([done, np.zeros(len(near), dtype=bool)])
            best = np.argsort(-sims)[:width]
            ids, sims, done = ids[best], sims[best], done[best]
        for part in seen:
            self.visited[part] = False
        order = np.argsort(-sims)
        return ids[order], sims[order]

    def descend(self, query: np.ndarray, until: int) -> np.ndarray:
        at = np.array([self.entry])
        for layer in range(self.top, until, -1):
            at = self.beam(query, at, 1, layer)[0][:1]
        return at

    def spread(self, ids: np.ndarray, sims: np.ndarray, width: int) -> np.ndarray:
        """Links in unlike directions: a candidate stays if no kept one is nearer to it than the node is; then the best of the rest."""
        among = self.vectors[ids] @ self.vectors[ids].T
        kept: list[int] = []
        for c in range(len(ids)):
            if not kept or among[c, kept].max() <= sims[c]:
                kept.append(c)
                if len(kept) == width:
                    break
        if len(kept) < width:
            taken = set(kept)
            kept += [c for c in range(len(ids)) if c not in taken][: width - len(kept)]
        return ids[kept]

    def _insert(self, i: int, width: int) -> None:
        query, level = self.vectors[i], int(self.levels[i])
        at = self.descend(query, level)
        for layer in range(min(level, self.top), -1, -1):
            ids, sims = self.beam(query, at, width, layer)
            at = ids
            chosen = self.spread(ids[:32], sims[:32], self.WIDTH // 2)
            if layer:
                own = self.links[layer]
                own[i] = chosen.tolist()
                for j in own[i]:
                    back = own.setdefault(j, [])
                    back.append(i)
                    if len(back) > self.WIDTH:
                        back[:] = self._thinned(j, np.array(back), self.WIDTH // 2)
            else:
                self.links[0][i, : len(chosen)] = chosen
                self.degree[i] = len(chosen)
                for j in chosen.tolist():
                    if self.degree[j] == self.SLACK:
                        kept = self._thinned(j, self.links[0][j], self.WIDTH)
                        self.links[0][j] = -1
                        self.links[0][j, : len(kept)] = kept
                        self.degree[j] = len(kept)
                    self.links[0][j, self.degree[j]] = i
                    self.degree[j] += 1
        for layer in range(self.top + 1, level + 1):
            self.links[layer][i] = []
        if level > self.top:
            self.entry, self.top = i, level

    def _thinned(self, j: int, ids: np.ndarray, width: int) -> list[int]:
        ids = np.unique(ids)
        sims = self.vectors[ids] @ self.vectors[j]
        order = np.argsort(-sims)
        return self.spread(ids[order], sims[order], width).tolist()

    def above(self, query: np.ndarray, limit: float, width: int) -> np.ndarray:
        """The nodes found with a cosine of at least limit: the beam's, and all that links among such nodes lead to."""
        if width >= len(self.vectors):
            return np.flatnonzero(self.vectors @ query >= limit)
        ids, sims = self.beam(query, self.descend(query, 0), width, 0)
        found = frontier = ids[sims >= limit]
        while len(frontier):
            self.visited[found] = True
            near = self.neighbours(frontier, 0)
            near = np.unique(near[~self.visited[near]])
            self.visited[found] = False
            frontier = near[self.vectors[near] @ query >= limit]
            found = np.concatenate([found, frontier])
        return found


def planted(vectors: np.ndarray, limit: float, many: int) -> np.ndarray:
    """Unit vectors at cosines between limit and 1 to some of the given ones."""
    rng = np.random.default_rng(2)
    chosen = vectors[rng.permutation(len(vectors))[:many]]
    side = rng.normal(size=chosen.shape)
    side -= (side * chosen).sum(1, keepdims=True) * chosen
    size = np.linalg.norm(side, axis=1, keepdims=True)
    side = np.divide(side, size, out=np.zeros_like(side), where=size > 1e-9)
    cosine = rng.uniform(limit, 1, size=(len(chosen), 1))
    moved = cosine * chosen + np.sqrt(1 - cosine**2) * side
    return moved / np.linalg.norm(moved, axis=1, keepdims=True)


@dataclass
class Audit:
    """Over the queries of a search that were compared with every vector: those with links, the links there are and those found."""

    queries: int = 0
    true: int = 0
    found: int = 0
    width: int = 0


def rated(graph: SmallWorld, queries: np.ndarray, truth: np.ndarray, limit: float, width: int) -> tuple[float, int, int, int]:
    """Mean recall of the queries that have links; their number, their links and those found."""
    shares, true, found = [], 0, 0
    for query, row in zip(queries, truth, strict=True):
        if many := int(row.sum()):
            hits = int(row[graph.above(query, limit, width)].sum())
            shares.append(hits / many)
            true, found = true + many, found + hits
    return float(np.mean(shares)) if shares else 1.0, len(shares), true, found


def search(graph: SmallWorld, queries: np.ndarray, limit: float, audits: int, recall: float) -> tuple[np.ndarray, Audit]:
    """links[query, node] of what is found, after as many wider beams as the audits ask for, and the last audit."""
    rng = np.random.default_rng(1)
    samples = [queries[rng.permutation(len(queries))[:audits]], planted(graph.vectors, limit, audits)]
    truths = [x @ graph.vectors.T >= limit for x in samples]
    width, audit = 16, Audit()
    while True:
        results = [rated(graph, x, truth, limit, width) for x, truth in zip(samples, truths, strict=True)]
        if min(share for share, *_ in results) >= recall or width >= len(graph.vectors):
            break
        width *= 2
    audit = Audit(*(sum(r[k] for r in results) for k in (1, 2, 3)), width)
    links = np.zeros((len(queries), len(graph.vectors)), dtype=bool)
    for row, query in enumerate(queries):
        links[row, graph.above(query, limit, width)] = True
    return links, audit


SHARD = "label int, dim int, shard int, graph binary"
#: Counts of a node, links of the forest (n is 0), and audits (node is null: queries in n, links in other, found in more, width in beam).
HITS = "node long, n long, other long, more long, beam int"


def named_nodes(keyed: DataFrame, seeds: int = 4) -> tuple[DataFrame, DataFrame]:
    """Rows with `node`, and the nodes; equal vectors of a label share a node and no others do."""
    digest = F.md5(F.array_join(F.col("vector").cast("array<string>"), " "))
    for seed in range(seeds):
        rows = keyed.withColumn("node", F.when(F.col("good"), F.xxhash64("label", "vector", F.lit(seed))))
        grouped = rows.where("node IS NOT NULL").withColumn("digest", digest).groupBy("label", "node")
        nodes = cut(grouped.agg(F.first("vector").alias("vector"), F.count("*").alias("many"), F.min("vec_id").alias("first_id"), F.min("digest").alias("low"), F.max("digest").alias("high")))
        shared = nodes.groupBy("node").agg(F.count("*").alias("labels"), F.max((F.col("low") != F.col("high")).cast("int")).alias("unequal")).where("labels > 1 OR unequal = 1")
        if shared.isEmpty():
            return rows.drop("good"), nodes.drop("low", "high").withColumn("dim", F.size("vector"))
    raise RuntimeError("unequal vectors share a name under every seed")


def near_duplicates(
    vectors: DataFrame, *, id_col: str = "vec_id", vector_col: str = "embedding", label_col: str = "label", limit: float = 0.98,
    shard_rows: int = 4096, beam: int = 48, audits: int = 64, recall: float = 0.999,
) -> DataFrame:
    """vec_id, n_links, component_id, kept of every row."""
    return linked(vectors, id_col, vector_col, label_col, limit, shard_rows, beam, audits, recall)[0]


def audit_report(
    vectors: DataFrame, *, id_col: str = "vec_id", vector_col: str = "embedding", label_col: str = "label", limit: float = 0.98,
    shard_rows: int = 4096, beam: int = 48, audits: int = 64, recall: float = 0.999,
) -> DataFrame:
    """searches, queries audited that have links, their links, how many of these were found, and the widest beam, in one row."""
    hits = linked(vectors, id_col, vector_col, label_col, limit, shard_rows, beam, audits, recall)[1].where("node IS NULL")
    return hits.agg(F.count("*").alias("searches"), *[F.coalesce(F.sum(c), F.lit(0)).alias(n) for c, n in (("n", "queries"), ("other", "links"), ("more", "found"))], F.max("beam").alias("widest_beam"))


def linked(vectors: DataFrame, id_col: str, vector_col: str, label_col: str, limit: float, shard_rows: int, beam: int, audits: int, recall: float) -> tuple[DataFrame, DataFrame]:
    """The rows of near_duplicates and the table HITS behind them."""
    own = of(vectors, vec_id=id_col, vector=vector_col, label=label_col)
    own = own.withColumn("vector", F.col("vector").cast("array<double>")).withColumn("label", F.col("label").cast("int"))
    finite = F.forall("vector", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    good = F.coalesce(F.col("label").isNotNull() & finite & F.exists("vector", lambda x: x != 0), F.lit(False))
    keyed, nodes = named_nodes(own.withColumn("good", good))
    sizes = nodes.groupBy("label", "dim").agg(F.ceil(F.count("*") / shard_rows).alias("shards"))
    dealt = nodes.join(sizes, ["label", "dim"]).withColumn("shard", F.pmod(F.xxhash64(F.lit("shard"), "node"), F.col("shards")).cast("int"))

    def built(key: tuple, rows: pa.Table) -> pa.Table:
        x = np.array(rows.column("vector").to_pylist(), dtype=float)
        x /= np.abs(x).max(axis=1, keepdims=True)  # neither overflows nor vanishes
        x /= np.linalg.norm(x, axis=1, keepdims=True)
        order = np.argsort(rows.column("node").to_numpy())
        graph = SmallWorld(x[order], beam)
        packed = pickle.dumps((graph, rows.column("node").to_numpy()[order], rows.column("many").to_numpy()[order]), protocol=5)
        return pa.table({"label": pa.array([key[0].as_py()], pa.int32()), "dim": pa.array([key[1].as_py()], pa.int32()), "shard": pa.array([key[2].as_py()], pa.int32()), "graph": pa.array([packed], pa.binary())})

    graphs = cut(dealt.select("label", "dim", "shard", "node", "many", "vector").groupBy("label", "dim", "shard").applyInArrow(built, SHARD))

    def searched(rows: pa.Table) -> pa.Table:
        out: dict[str, list] = {"node": [], "n": [], "other": [], "more": [], "beam": []}

        def put(nodes: list, counts: list, others: list, more: list | None = None, beams: list | None = None) -> None:
            for name, values in zip(out, (nodes, counts, others, more or [None] * len(nodes), beams or [None] * len(nodes)), strict=True):
                out[name] += values

        for left, right, same in zip(*(rows.column(c).to_pylist() for c in ("left", "right", "same")), strict=True):
            graph, a, many_a = pickle.loads(left)
            other, b, many_b = (graph, a, many_a) if same else pickle.loads(right)
            links, *seen = search(other, graph.vectors, limit, audits, recall)
            if same:
                links |= links.T
                np.fill_diagonal(links, False)
            else:
                back, more = search(graph, other.vectors, limit, audits, recall)
                links |= back.T
                seen.append(more)
            for ids, counts in ((a, links @ many_b),) if same else ((a, links @ many_b), (b, links.T @ many_a)):
                hit = np.flatnonzero(counts)
                put(ids[hit].tolist(), counts[hit].tolist(), [None] * len(hit))
            edges = forest(links, a, b)
            put([x for x, _ in edges], [0] * len(edges), [y for _, y in edges])
            put([None] * len(seen), [x.queries for x in seen], [x.true for x in seen], [x.found for x in seen], [x.width for x in seen])
        return pa.table([pa.array(v, pa.int32() if k == "beam" else pa.int64()) for k, v in out.items()], names=list(out))

    left, right = (graphs.select("label", "dim", F.col("shard").alias(s), F.col("graph").alias(g)) for s, g in (("i", "left"), ("j", "right")))
    pairs = left.join(right, ["label", "dim"]).where("i <= j").withColumn("same", F.col("i") == F.col("j"))
    hits = cut(pairs.groupBy("label", "dim", "i", "j").applyInArrow(searched, HITS))  # one row, two graphs in a group
    counts = hits.where("node IS NOT NULL").groupBy("node").agg(F.sum("n").alias("n"))
    groups = components(hits.where("node IS NOT NULL AND other IS NOT NULL").select(F.col("node").alias("a"), F.col("other").alias("b")))
    known = nodes.select("node", "many", "first_id").join(counts, "node", "left").join(groups, "node", "left").withColumn("component", F.coalesce("component", "node"))
    first = known.groupBy("component").agg(F.min("first_id").alias("component_id"))
    placed = known.join(first, "component").select("node", (F.coalesce("n", F.lit(0)) + F.col("many") - 1).alias("n_links"), "component_id")
    result = keyed.select("vec_id", "node").join(placed, "node", "left")
    component = F.coalesce("component_id", "vec_id")
    return result.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(F.col("vec_id") == component, F.col("node").isNull()).alias("kept")), hits


def op8_embedding_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "embeddings"))


OP8_SQL = """
WITH RECURSIVE e AS (SELECT vec_id, label, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS v FROM embeddings),
g AS (SELECT vec_id, label, v, sqrt(list_dot_product(v, v)) AS norm FROM e WHERE label IS NOT NULL AND v IS NOT NULL AND len(list_filter(v, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND list_dot_product(v, v) > 0),
l AS (SELECT a.vec_id AS a, b.vec_id AS b FROM g a JOIN g b ON a.label = b.label AND a.vec_id <> b.vec_id AND len(a.v) = len(b.v) AND list_dot_product(a.v, b.v) / (a.norm * b.norm) >= 0.98),
r AS (SELECT a AS n, a AS c FROM l UNION SELECT l.b AS n, r.c FROM r JOIN l ON l.a = r.n),
c AS (SELECT n, min(c) AS c FROM r GROUP BY n),
k AS (SELECT a, count(*) AS n FROM l GROUP BY a)
SELECT vec_id, coalesce(k.n, 0) AS n_links, coalesce(c.c, vec_id) AS component_id, vec_id = coalesce(c.c, vec_id) AS kept
FROM e LEFT JOIN k ON k.a = vec_id LEFT JOIN c ON c.n = vec_id
"""
