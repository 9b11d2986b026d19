"""Token counts by byte-pair merging with a heap and a linked list; no identifiers are made.

A text is cut at special strings (one token each), then into pre-tokens. Each pre-token's bytes form a doubly linked list;
a heap holds the ranks of adjacent pairs, the lowest is merged until none is left, and the count is the number of bytes less
the number of merges. Counts of pre-tokens are memoised per Python worker in a memo of bounded size.

Nulls and empty texts have 0 tokens and 0 bytes. Repeated rows give repeated results. Extra columns are ignored.
"""

from __future__ import annotations

import json
from heapq import heapify, heappop, heappush

import public_tokenizers
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from gpart.llm.common import Memo, of, scan, table

COUNTS = "doc_id long, n_bytes long, n_tokens long, over_limit boolean"


def byte_letters() -> dict[str, int]:
    """The byte-level alphabet: printable Latin-1 stands for itself, the other bytes for code points from 256 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


class MergeCounter:
    """Counts tokens as the byte-level BPE of a tokenizers file does, by merges alone."""

    def __init__(self, path: str, memo: int = 500_000):
        import regex

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        letters, model = byte_letters(), spec["model"]
        vocabulary = {bytes(letters[c] for c in word): i for word, i in model["vocab"].items() if all(c in letters for c in word)}
        #: (left id, right id) packed in one integer -> (rank, id of the merged symbol) packed in one integer
        self.merges: dict[int, int] = {}
        for rank, (a, b) in enumerate(model["merges"]):
            left, right = (bytes(letters[c] for c in x) for x in (a, b))
            self.merges.setdefault(vocabulary[left] << 20 | vocabulary[right], rank << 20 | vocabulary[left + right])
        self.byte_ids = [vocabulary[bytes([b])] for b in range(256)]
        specials = [t["content"] for t in spec["added_tokens"]]
        self.special = regex.compile("|".join(map(regex.escape, sorted(specials, key=len, reverse=True)))) if specials else None
        self.words = regex.compile(public_tokenizers.PATTERN).findall
        self.of_word = Memo(self.merge, memo)

    def merge(self, word: str) -> int:
        data = word.encode()
        n = len(data)
        if n < 2:
            return n
        ids, get = [self.byte_ids[b] for b in data], self.merges.get
        heap = []
        for i in range(n - 1):
            m = get(ids[i] << 20 | ids[i + 1])
            if m is not None:
                heap.append((m >> 20, i, m & 0xFFFFF, ids[i], ids[i + 1]))
        heapify(heap)
        after, before, merged = list(range(1, n + 1)), list(range(-1, n - 1)), 0
        while heap:
            _, i, new, left, right = heappop(heap)
            j = after[i]
            if j >= n or ids[i] != left or ids[j] != right:
                continue  # one of the two has been merged meanwhile
            ids[i], ids[j] = new, -1
            merged += 1
            k = after[i] = after[j]
            if k < n:
                before[k] = i
                m = get(new << 20 | ids[k])
                if m is not None:
                    heappush(heap, (m >> 20, i, m & 0xFFFFF, new, ids[k]))
            k = before[i]
            if k >= 0:
                m = get(ids[k] << 20 | new)
                if m is not None:
                    heappush(heap, (m >> 20, k, m & 0xFFFFF, ids[k], new))
        return n - merged

    def count(self, text: str) -> int:
        of_word, words = self.of_word.use(), self.words
        if self.special is None or not self.special.search(text):
            return sum(map(of_word.__getitem__, words(text)))
        parts = self.special.split(text)
        return len(parts) - 1 + sum(sum(map(of_word.__getitem__, words(part))) for part in parts)


_COUNTERS: dict[str, MergeCounter] = {}


def counter(path: str) -> MergeCounter:
    """One counter per worker and file: workers are used again, so the memo lasts from task to task."""
    if path not in _COUNTERS:
        _COUNTERS[path] = MergeCounter(path)
    return _COUNTERS[path]


def token_counts(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", tokenizer: str = "byte_bpe_50k.json", limit: int = 512) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit of every whole text. `tokenizer` is a path or a name of public_tokenizers."""

    def rows(batch: pa.RecordBatch) -> dict[str, list]:
        count = counter(tokenizer if "/" in tokenizer else public_tokenizers.path(tokenizer)).count
        texts = batch.column("text").to_pylist()
        tokens = [count(t) if t else 0 for t in texts]
        return {"doc_id": batch.column("doc_id"), "n_bytes": [len(t.encode()) if t else 0 for t in texts], "n_tokens": tokens, "over_limit": [n > limit for n in tokens]}

    return scan(of(docs, doc_id=id_col, text=text_col), rows, COUNTS)


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts(table(spark, sf_dir, "documents"))
