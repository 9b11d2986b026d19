"""Benchmark decontamination with a generalised suffix automaton over the words of the test items.

Words are maximal runs of bytes other than ASCII punctuation, controls and white space, ASCII lower-cased. A window is `window`
consecutive words of an item (an item of fewer words is one window). Every text streams through the automaton, which keeps the
longest suffix of the words so far that occurs in some item: once that is a window long, its words are hit, and the state that
holds the suffix of exactly one window tells which items have it. Runs of words that no item uses are passed over first.

The automaton goes to the executors as a broadcast of at most `block_words` item words; more items are scanned in several
blocks whose findings are merged per text. Null texts have no words. Repeated items count once by item_id (items without
an id are one item, written as a NUL character); repeated documents give repeated rows. Extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from collections import defaultdict
from functools import reduce
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gpart.llm.common import of, scan, table, utf8

#: Bytes to words: letters, digits and everything beyond ASCII stay, A-Z become a-z, the rest separates.
FOLD = bytes(b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256))
RUN = re.compile(rb"[^ ]+")

FOUND = "doc_id long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean, coverage double, longest_span int"


def words_of(text: bytes | None) -> list[bytes]:
    return text.translate(FOLD).split() if text else []


class ItemAutomaton:
    """Suffix automaton of several word sequences: which windows of which items end at each word of a text."""

    def __init__(self, items: list[tuple[str, list[bytes]]], window: int):
        self.window = window
        self.ids: dict[bytes, int] = {}
        self.length, self.link, steps = [0], [-1], [{}]
        for _, words in items:
            last = 0
            for word in words:
                last = self._extend(last, self.ids.setdefault(word, len(self.ids)), steps)
        self.width = max(1, len(self.ids))
        self.steps = {s * self.width + w: t for s, own in enumerate(steps) for w, t in own.items()}
        n = len(self.length)
        #: the ancestor that holds the suffix of exactly one window, -1 if the state's words are fewer
        self.window_state = [-1] * n
        own_short: dict[int, list[tuple[int, str]]] = defaultdict(list)
        at_window: dict[int, set[str]] = defaultdict(set)
        for s in sorted(range(1, n), key=self.length.__getitem__):
            if self.length[s] >= window:
                self.window_state[s] = s if self.length[self.link[s]] < window else self.window_state[self.link[s]]
        self.shortest = window
        for item, words in items:
            state = 0
            for k, word in enumerate(words, 1):
                state = self.steps[state * self.width + self.ids[word]]
                if k >= window:
                    at_window[self.window_state[state]].add(item)
            if 0 < len(words) < window:
                self.shortest = min(self.shortest, len(words))
                own_short[self._holds(state, len(words))].append((len(words), item))
        self.at_window = dict(at_window)
        self.short: list[tuple[tuple[int, str], ...]] = [()] * n
        for s in sorted(range(1, n), key=self.length.__getitem__):
            self.short[s] = (*own_short.get(s, ()), *self.short[self.link[s]])

    def _holds(self, state: int, length: int) -> int:
        while self.length[self.link[state]] >= length:
            state = self.link[state]
        return state

    def _split(self, parent: int, word: int, target: int, steps: list[dict[int, int]]) -> int:
        """The state of the words that reach `target` by its shortest way only: a copy with fewer words, between it and its link."""
        copy = len(self.length)
        self.length.append(self.length[parent] + 1)
        self.link.append(self.link[target])
        steps.append(dict(steps[target]))
        while parent >= 0 and steps[parent].get(word) == target:
            steps[parent][word] = copy
            parent = self.link[parent]
        self.link[target] = copy
        return copy

    def _extend(self, last: int, word: int, steps: list[dict[int, int]]) -> int:
        known = steps[last].get(word)
        if known is not None:
            return known if self.length[known] == self.length[last] + 1 else self._split(last, word, known, steps)
        new = len(self.length)
        self.length.append(self.length[last] + 1)
        self.link.append(0)
        steps.append({})
        while last >= 0 and word not in steps[last]:
            steps[last][word] = new
            last = self.link[last]
        if last >= 0:
            target = steps[last][word]
            self.link[new] = target if self.length[target] == self.length[last] + 1 else self._split(last, word, target, steps)
        return new

    def find(self, words: list[bytes]) -> tuple[list[tuple[int, int]], set[str]]:
        """Hit spans (first word, word after the last; sorted, disjoint) and the items whose windows occur."""
        if len(words) < self.shortest:
            return [], set()
        ids = np.fromiter(map(self.ids.get, words, repeat(-1)), dtype=np.int64, count=len(words))
        edges = np.flatnonzero(np.diff(np.concatenate(([0], (ids >= 0).astype(np.int8), [0]))))
        spans: list[tuple[int, int]] = []
        items: set[str] = set()
        steps, link, length, window, width = self.steps, self.link, self.length, self.window, self.width
        for a, b in edges.reshape(-1, 2).tolist():
            if b - a < self.shortest:
                continue
            state = matched = 0
            for i, word in enumerate(ids[a:b].tolist(), a + 1):
                step = steps.get(state * width + word)
                while step is None:
                    state = link[state]
                    matched = length[state]
                    step = steps.get(state * width + word)
                state, matched = step, matched + 1
                if matched >= window:
                    spans.append((i - matched, i))
                    items |= self.at_window[self.window_state[state]]
                for size, item in self.short[state]:
                    if size <= matched:
                        spans.append((i - size, i))
                        items.add(item)
        return merged(spans), items


def merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[list[int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [(a, b) for a, b in out]


def without(text: bytes, spans: list[tuple[int, int]], min_span: int) -> str:
    """The text without the spans of at least min_span words, from each one's first byte to its last."""
    words = [m.span() for m in RUN.finditer(text.translate(FOLD))]
    kept, at = [], 0
    for a, b in spans:
        if b - a >= min_span:
            kept.append(text[at : words[a][0]])
            at = words[b - 1][1]
    return b"".join([*kept, text[at:]]).decode("utf-8", "replace")


def blocks(items: DataFrame, window: int, block_words: int, id_col: str, text_col: str) -> list[ItemAutomaton]:
    """Automata of the items, streamed to the driver, each over at most block_words words (one item at least)."""
    out, held, size = [], [], 0
    for row in of(items, id=id_col, text=text_col).distinct().toLocalIterator():
        words = words_of(row["text"].encode() if row["text"] else None)
        if held and size + len(words) > block_words:
            out.append(ItemAutomaton(held, window))
            held, size = [], 0
        held.append(("\0" if row["id"] is None else str(row["id"]), words))
        size += len(words)
    return [*out, ItemAutomaton(held, window)] if held or not out else out


def decontaminate(
    docs: DataFrame, items: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", item_id_col: str = "item_id", item_text_col: str = "text",
    window: int = 10, min_span: int = 1, max_coverage: float = 0.5, block_words: int = 400_000, texts: bool = True, carry: tuple[str, ...] = (),
) -> DataFrame:
    """The columns of FOUND for every text and, with texts=True, clean_text: the text without hit spans of at least min_span words;
    null where more than max_coverage of its words is hit (and where the text is null). Columns named in carry come along."""
    spark = docs.sparkSession
    source = of(docs, doc_id=id_col, text=text_col, **{f"_{c}": c for c in carry})
    automata = [spark.sparkContext.broadcast(a) for a in blocks(items, window, block_words, item_id_col, item_text_col)]
    own = FOUND + (", clean_text string" if texts else "")
    schema = own + "".join(f", _{c} {docs.schema[c].dataType.simpleString()}" for c in carry)

    def digest(batch: pa.RecordBatch, found) -> dict[str, list]:
        doc, text = batch.column("doc_id").to_pylist(), utf8(batch, "text")
        out: dict[str, list] = {name.split()[0]: [] for name in own.split(", ")}
        for i, data in enumerate(text):
            words = words_of(data)
            spans, names = found(i, words)
            n_hit = sum(b - a for a, b in spans)
            values = {
                "doc_id": doc[i], "n_words": len(words), "n_hit": n_hit, "n_items": len(names), "items_sha256": hashlib.sha256(",".join(sorted(names)).encode()).hexdigest(),
                "contaminated": n_hit > 0, "coverage": n_hit / len(words) if words else 0.0, "longest_span": max((b - a for a, b in spans), default=0),
            }
            if texts:
                values["clean_text"] = None if data is None or n_hit > max_coverage * len(words) else without(data, spans, min_span) if spans else data.decode("utf-8", "replace")
            for name, value in values.items():
                out[name].append(value)
        return out | {f"_{c}": batch.column(f"_{c}") for c in carry}

    def named(found: DataFrame) -> DataFrame:
        return found.select(*[x.split()[0] for x in own.split(", ")], *[F.col(f"_{c}").alias(c) for c in carry])

    if len(automata) == 1:
        only = automata[0]
        return named(scan(source, lambda batch: digest(batch, lambda i, words: only.value.find(words)), schema))

    def spans_in(automaton):
        def rows(batch: pa.RecordBatch) -> dict[str, list]:
            got = [automaton.value.find(words_of(t)) for t in utf8(batch, "text")]
            return {"key": batch.column("key"), "spans": [[x for s in spans for x in s] for spans, _ in got], "items": [sorted(names) for _, names in got]}

        return rows

    keyed = source.withColumn("key", F.sha2(F.coalesce("text", F.lit("")), 256))
    each = [scan(keyed.select("key", "text"), spans_in(a), "key string, spans array<int>, items array<string>").where(F.size("items") > 0).dropDuplicates(["key"]) for a in automata]
    found = reduce(DataFrame.unionByName, each).groupBy("key").agg(F.flatten(F.collect_list("spans")).alias("spans"), F.flatten(F.collect_list("items")).alias("items"))

    def rows(batch: pa.RecordBatch) -> dict[str, list]:
        spans, names = batch.column("spans").to_pylist(), batch.column("items").to_pylist()
        return digest(batch, lambda i, _: (merged(list(zip(s[::2], s[1::2], strict=True))) if (s := spans[i]) else [], set(names[i] or ())))

    return named(scan(keyed.join(found, "key", "left").drop("key"), rows, schema))


def op1_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontaminate(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), texts=False)
    return found.select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated")


#: Windows as rows; words never hold a space, so a window is its words joined by spaces.
OP1_SQL = r"""
WITH d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
b AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
bw AS (SELECT DISTINCT item_id, least(len(w), 10) AS k, array_to_string(w[i:i + least(len(w), 10) - 1], ' ') AS g
  FROM (SELECT item_id, w, unnest(range(1, greatest(len(w) - 9, 1) + 1)) AS i FROM b WHERE len(w) > 0)),
ks AS (SELECT DISTINCT k FROM bw),
dw AS (SELECT doc_id, k, i, array_to_string(w[i:i + k - 1], ' ') AS g FROM (SELECT doc_id, w, k, unnest(range(1, len(w) - k + 2)) AS i FROM d, ks WHERE len(w) >= k)),
m AS (SELECT DISTINCT dw.doc_id, dw.i, dw.k, bw.item_id FROM dw JOIN bw ON dw.k = bw.k AND dw.g = bw.g),
h AS (SELECT doc_id, count(DISTINCT p) AS n FROM (SELECT doc_id, unnest(range(i, i + k)) AS p FROM m) GROUP BY 1),
t AS (SELECT doc_id, count(*) AS n, string_agg(s, ',' ORDER BY s) AS s FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS s FROM m) GROUP BY 1)
SELECT d.doc_id, CAST(len(d.w) AS BIGINT) AS n_words, CAST(coalesce(h.n, 0) AS BIGINT) AS n_hit, CAST(coalesce(t.n, 0) AS BIGINT) AS n_items,
  sha256(coalesce(t.s, '')) AS items_sha256, coalesce(h.n, 0) > 0 AS contaminated
FROM d LEFT JOIN h USING (doc_id) LEFT JOIN t USING (doc_id)
"""
