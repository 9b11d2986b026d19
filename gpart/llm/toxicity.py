"""Toxicity scores: a learned lexicon, misspellings by Levenshtein automata, and context windows.

The lexicon is learned from labelled texts: words and word beginnings (`lowei*`) that toxic texts hold far more often than chance
lets them, in varied neighbourhoods, and hardly any other text does. A word is exact if it is in the lexicon or begins as one of
its beginnings does. It is misspelled if its Levenshtein automaton, run down the trie of the lexicon's terms, reaches the end of a
word within one edit, or the end of a beginning while some start of the word is within one edit of it, unless what was reached is
ordinary: in two other texts of the sample or more. Around each hit a window of words gives a context score (log-odds of its words
beside hits in toxic and in other texts, smoothed towards none), and quotation marks around it in its line make it a quotation.

Logistic regression over these counts gives the score. Exact and misspelled hits can only raise it and quotations only lower it:
the fit also sees each toxic text with its terms misspelled, as toxic, and with its terms quoted, as not, at half weight.

Only the fit looks at a bounded sample: about `per_class` labelled texts of either class, at most `most_candidates`
candidate terms and `most_terms` chosen ones. Every whole text is scored. Null and empty texts have no hits and get the score of such texts; without labels of
both classes every score is 0. Repeated label rows count once (toxic if any says so); extra columns are ignored.
"""

from __future__ import annotations

import math
import re
from bisect import bisect_right
from collections import Counter, defaultdict
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gpart.llm.common import Memo, cut, of, scan, table
from gpart.llm.language_id import held_out

WORDS = re.compile(r"[^\W_]+")
STEMS = range(3, 8)
SCORED = "doc_id long, score double, predicted int"
#: Opening and closing quotation marks (fixed values).
QUOTES = {'"': '"', "“": "”", "«": "»", "„": "“", "‘": "’"}
WINDOW = 5


def edit_automaton(word: str, most: int):
    """The automaton of all words within `most` edits of word: states are frozen sets of (letters read, edits)."""

    def closed(states: set[tuple[int, int]]) -> frozenset[tuple[int, int]]:
        for at, edits in list(states):
            states.update((at + k, edits + k) for k in range(1, min(most - edits, len(word) - at) + 1))
        return frozenset(states)

    def step(state: frozenset[tuple[int, int]], letter: str) -> frozenset[tuple[int, int]]:
        after = set()
        for at, edits in state:
            if at < len(word) and word[at] == letter:
                after.add((at + 1, edits))
            elif edits < most:
                after.add((at, edits + 1))
                if at < len(word):
                    after.add((at + 1, edits + 1))
        return closed(after)

    return closed({(0, 0)}), step, lambda state: any(at == len(word) for at, _ in state)


MISS = (0.0, 0)


class Lexicon:
    """Words and beginnings with weights; looks words up exactly, by beginning, and within one edit of either. ordinary: what is
    within an edit of a term but no misspelling."""

    def __init__(self, weights: dict[str, float], ordinary: frozenset[str] = frozenset(), word_from: int = 4, stem_from: int = 5):
        self.exact = {t: w for t, w in weights.items() if not t.endswith("*")}
        self.stems = {t[:-1]: w for t, w in weights.items() if t.endswith("*")}
        self.stem_sizes = sorted({len(t) for t in self.stems})
        self.ordinary = ordinary
        self.trie: dict = {}
        # one edit leaves the first or the last half of a term as it is; the last half may move by a letter
        self.heads, self.tails = set(), set()
        self.places: set[tuple[int, int]] = set()  # of the last halves of beginnings: where they start and their size
        words, stems = [t for t in self.exact if len(t) >= word_from], [t for t in self.stems if len(t) >= stem_from]
        for term in [*words, *(t + "*" for t in stems)]:
            node = self.trie
            for letter in term.rstrip("*"):
                node = node.setdefault(letter, {})
            node["*" if term.endswith("*") else ""] = term
        for term in words:
            self.heads.add(term[: len(term) // 2])
            self.tails.add(term[len(term) // 2 :])
        self.tail_sizes = sorted({len(x) for x in self.tails})
        self.stem_tails = {t[len(t) // 2 :] for t in stems}
        for t in stems:
            self.heads.add(t[: len(t) // 2])
            self.places.update((len(t) // 2 + d, len(t) - len(t) // 2) for d in (-1, 0, 1))
        self.head_sizes = sorted({len(x) for x in self.heads})
        self.of_word = Memo(self.look_up)

    def look_up(self, word: str) -> tuple[float, int]:
        """(weight, edits); the weight is 0 where nothing matches."""
        if (w := self.exact.get(word)) is not None:
            return w, 0
        for size in self.stem_sizes:
            if (w := self.stems.get(word[:size])) is not None:
                return w, 0
        found = self.near(word, 1)
        return MISS if found is None or found[1] in self.ordinary else (found[2], 1)

    def near(self, word: str, edits: int) -> tuple[str, str, float] | None:
        """(term, what of the word is within so many edits of it, the term's weight); whole words before beginnings, heavy ones first."""
        if edits == 1 and not (any(word[:k] in self.heads for k in self.head_sizes) or any(word[-k:] in self.tails for k in self.tail_sizes) or any(word[a : a + k] in self.stem_tails for a, k in self.places)):
            return None
        start, step, accepts = edit_automaton(word, edits)
        stack, found = [(self.trie, start)], []
        while stack:
            node, state = stack.pop()
            for letter, below in node.items():
                if letter == "":
                    if accepts(state):
                        found.append((1, self.exact[below], below, word))
                elif letter == "*":
                    found.append((0, self.stems[below[:-1]], below, word[: max(at for at, _ in state)]))
                elif after := step(state, letter):
                    stack.append((below, after))
        if not found:
            return None
        _, weight, term, part = max(found)
        return term, part, weight


MARK = re.compile("[%s\n]" % "".join({*QUOTES, *QUOTES.values()}))


def quotations(text: str) -> tuple[list[int], list[int]]:
    """Starts and ends of what stands between quotation marks of one line, in order."""
    starts, ends, opened = [], [], {}
    for m in MARK.finditer(text):
        mark, at = m[0], m.start()
        if mark == "\n":
            opened.clear()
            continue
        opening = next((o for o in opened if QUOTES[o] == mark), None)
        if opening is not None:
            begin = opened.pop(opening)
            while starts and starts[-1] >= begin:  # quotations within this one
                starts.pop(), ends.pop()
            if not ends or at > ends[-1]:
                starts.append(begin), ends.append(at)
            opened = {o: a for o, a in opened.items() if a < begin}
        elif mark in QUOTES and mark not in opened:
            opened[mark] = at
    return starts, ends


def quoted(text: str, at: int, until: int) -> bool:
    """Whether text[at:until] stands between quotation marks, in its line."""
    starts, ends = quotations(text)
    i = bisect_right(starts, at) - 1
    return i >= 0 and until <= ends[i]


def misspelled(word: str) -> str:
    """The word with one edit, which its hash chooses."""
    at = 1 + hash_of(word) % max(1, len(word) - 1)
    return (word[:at] + word[at + 1 :], word[:at] + word[at - 1] + word[at:], word[: at - 1] + "x" + word[at:])[hash_of(word + "?") % 3]


@dataclass
class ToxicityModel:
    weights: dict[str, float]
    context: dict[str, float] = field(default_factory=dict)
    coefficients: np.ndarray | None = None
    ordinary: frozenset[str] = frozenset()
    _lexicon: Lexicon | None = None

    def lexicon(self) -> Lexicon:
        if self._lexicon is None:
            self._lexicon = Lexicon(self.weights, self.ordinary)
        return self._lexicon

    def hits(self, text: str | None) -> tuple[list[str], list[tuple[int, float, int]]]:
        words = WORDS.findall(text.lower()) if text else []
        found = self.lexicon().of_word.use()
        return words, [(i, *hit) for i, hit in enumerate(map(found.__getitem__, words)) if hit[0]]

    def features(self, text: str | None) -> list[float]:
        words, hits = self.hits(text)
        if not hits:
            return [0.0] * 6
        lowered = text.lower()
        in_quotes = [False] * len(hits)
        starts, ends = quotations(lowered)
        if starts:
            places = [m.span() for m in WORDS.finditer(lowered)]
            at = [bisect_right(starts, places[i][0]) - 1 for i, _, _ in hits]
            in_quotes = [k >= 0 and places[i][1] <= ends[k] for k, (i, _, _) in zip(at, hits, strict=True)]
        own = [h for h, q in zip(hits, in_quotes, strict=True) if not q]
        near = [self.context.get(w, 0.0) for i, _, _ in hits for w in words[max(0, i - WINDOW) : i] + words[i + 1 : i + 1 + WINDOW]]
        exact = sum(e == 0 for _, _, e in own)
        return [math.log1p(exact), math.log1p(len(own) - exact), max((w for _, w, e in own if e == 0), default=0.0), min(60.0, sum({words[i]: w for i, w, e in own if e == 0}.values())) / 10, math.log1p(len(hits) - len(own)), float(np.mean(near)) if near else 0.0]

    def score(self, features: list[list[float]]) -> np.ndarray:
        if self.coefficients is None:
            return np.zeros(len(features))
        x = np.c_[np.ones(len(features)), np.array(features)]
        return 1 / (1 + np.exp(-np.clip(x @ self.coefficients, -30, 30)))


def terms_of(words: list[str]) -> set[str]:
    distinct = set(words)
    return distinct | {w[:k] + "*" for w in distinct for k in STEMS if len(w) > k}


#: What a feature may do to the score: raise it, lower it, or either (0); the intercept comes first.
SIGNS = np.array([0, 1, 1, 1, 1, -1, 0])


def logistic(x: np.ndarray, y: np.ndarray, weights: np.ndarray, signs: np.ndarray = SIGNS, ridge: float = 0.3, rounds: int = 25) -> np.ndarray:
    """Weighted ridge logistic regression by Newton steps; the intercept is not shrunk. A coefficient against its sign is held at 0."""
    used = np.ones(x.shape[1], dtype=bool)
    while True:
        own = x[:, used]
        beta, free = np.zeros(own.shape[1]), np.eye(own.shape[1]) * ridge
        free[0, 0] = 1e-6
        for _ in range(rounds):
            p = 1 / (1 + np.exp(-np.clip(own @ beta, -30, 30)))
            beta += np.linalg.solve((own * (weights * p * (1 - p))[:, None]).T @ own + free, own.T @ (weights * (y - p)) - free @ beta)
        whole = np.zeros(x.shape[1])
        whole[used] = beta
        if not (against := whole * signs < 0).any():
            return whole
        used &= ~against


def beyond_chance(a: int, b: int, share: float, terms: int) -> bool:
    """Whether a of a + b texts are toxic though `share` of all are, in a way that not one of so many terms would show by chance."""
    n, p = a + b, a / (a + b)
    if p <= share:
        return False
    bits = a * math.log(p / share) + (b * math.log((1 - p) / (1 - share)) if b else 0.0)
    return bits >= math.log(max(2, terms))


def select(candidates: dict[str, tuple[int, int]], n_toxic: int, n_other: int, min_odds: float) -> dict[str, float]:
    """Weights (smoothed log-odds) of the telling words, and of beginnings that no other text has and that say more than the
    longer terms they stand for. candidates: term -> (toxic texts, other texts) that hold it."""
    odds = {t: math.log((a + 0.5) / (n_toxic + 1)) - math.log((b + 0.5) / (n_other + 1)) for t, (a, b) in candidates.items()}
    best: dict[str, int] = defaultdict(int)  # of the longer terms under a beginning
    for term, (a, _) in candidates.items():
        for k in STEMS:
            if k < len(term.rstrip("*")):
                best[term[:k] + "*"] = max(best[term[:k] + "*"], a)
    share = n_toxic / (n_toxic + n_other)
    odds = {t: w for t, w in odds.items() if w >= min_odds and beyond_chance(*candidates[t], share, len(candidates))}
    return {t: w for t, w in odds.items() if (not t.endswith("*") or candidates[t][1] == 0 and candidates[t][0] >= 1.3 * best[t])}


def train(
    docs: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", label_id_col: str = "doc_id", label_col: str = "toxic",
    per_class: int = 4000, most_candidates: int = 50_000, most_terms: int = 5_000, min_share: float = 0.004, min_odds: float = 3.0,
) -> ToxicityModel | None:
    """A model from the labelled texts that are not held out, or None without texts of both classes."""
    spark = docs.sparkSession
    known = of(labels, doc_id=label_id_col, toxic=label_col).where(F.col("toxic").isin(0, 1) & ~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    sizes = {r["toxic"]: r["count"] for r in known.groupBy("toxic").count().collect()}
    if len(sizes) < 2:
        return None
    share = F.when(F.col("toxic") == 1, per_class / sizes[1]).otherwise(per_class / sizes[0])
    drawn = known.where(F.pmod(F.xxhash64("doc_id", F.lit("toxicity")), F.lit(1 << 30)) / float(1 << 30) < share)
    sample = cut(of(docs, doc_id=id_col, text=text_col).join(F.broadcast(drawn), "doc_id").select("toxic", "text"))  # about 2 * per_class rows are broadcast

    def mined(batch: pa.RecordBatch) -> dict[str, list]:
        texts, contexts = Counter(), defaultdict(int)
        for text in batch.column("text").to_pylist():
            words = WORDS.findall(text.lower()) if text else []
            texts.update(terms_of(words))
            for before, word in zip(["", *words], words, strict=False):
                bit = 1 << (hash_of(before) & 63)
                contexts[word] |= bit
                for k in STEMS:
                    if len(word) > k:
                        contexts[word[:k] + "*"] |= bit
        return {"term": list(texts), "n": list(texts.values()), "contexts": [contexts[t] - (1 << 64 if contexts[t] >> 63 else 0) for t in texts]}

    counted = scan(sample.where("toxic = 1"), mined, "term string, n long, contexts long").groupBy("term").agg(F.sum("n").alias("n"), F.bit_count(F.expr("bit_or(contexts)")).alias("contexts"))
    n_toxic, n_other = (sample.where(f"toxic = {k}").count() for k in (1, 0))
    if not n_toxic or not n_other:
        return None
    support = max(3, math.ceil(min_share * n_toxic))
    varied = F.col("contexts") >= F.greatest(F.lit(3), F.least(F.lit(8), F.col("n") / 2))  # copies of one text have few
    candidates = [r["term"] for r in counted.where((F.col("n") >= support) & varied).orderBy(F.desc("n"), "term").limit(most_candidates).collect()]
    numbers = spark.sparkContext.broadcast({t: i for i, t in enumerate(candidates)})

    def counted_in(batch: pa.RecordBatch) -> dict[str, list]:
        found = Counter()
        for text in batch.column("text").to_pylist():
            found.update(numbers.value[t] for t in terms_of(WORDS.findall(text.lower()) if text else []) if t in numbers.value)
        return {"term": list(found), "n": list(found.values())}

    in_toxic, in_other = ({r["term"]: r["n"] for r in scan(sample.where(f"toxic = {k}"), counted_in, "term long, n long").groupBy("term").agg(F.sum("n").alias("n")).collect()} for k in (1, 0))
    chosen = select({t: (in_toxic.get(i, 0), in_other.get(i, 0)) for i, t in enumerate(candidates)}, n_toxic, n_other, min_odds)
    model = ToxicityModel(dict(sorted(chosen.items(), key=lambda x: (-x[1], x[0]))[:most_terms]))
    bare = spark.sparkContext.broadcast(model)

    def near_misses(batch: pa.RecordBatch) -> dict[str, list]:
        found, lexicon = Counter(), bare.value.lexicon()
        for text in batch.column("text").to_pylist():
            words = {w for w in WORDS.findall(text.lower()) if lexicon.of_word.use()[w][1]} if text else ()
            found.update({lexicon.near(w, 1)[1] for w in words})
        return {"word": list(found), "n": list(found.values())}

    ordinary = scan(sample.where("toxic = 0"), near_misses, "word string, n long").groupBy("word").agg(F.sum("n").alias("n")).where("n >= 2")
    model.ordinary = frozenset(r["word"] for r in ordinary.collect())  # words of the bounded sample
    knowing = spark.sparkContext.broadcast(ToxicityModel(model.weights, ordinary=model.ordinary))

    def windows(batch: pa.RecordBatch) -> dict[str, list]:
        found = Counter()
        for toxic, text in zip(batch.column("toxic").to_pylist(), batch.column("text").to_pylist(), strict=True):
            words, hits = knowing.value.hits(text)
            found.update((toxic, w) for i, _, _ in hits for w in words[max(0, i - WINDOW) : i] + words[i + 1 : i + 1 + WINDOW])
        return {"toxic": [t for t, _ in found], "word": [w for _, w in found], "n": list(found.values())}

    beside = scan(sample, windows, "toxic int, word string, n long").groupBy("word").agg(*[F.sum(F.when(F.col("toxic") == k, F.col("n")).otherwise(0)).alias(f"n{k}") for k in (0, 1)])
    all0, all1 = beside.agg(F.coalesce(F.sum("n0"), F.lit(0)), F.coalesce(F.sum("n1"), F.lit(0))).first()
    common = beside.where(F.col("n0") + F.col("n1") >= 5).orderBy(F.desc(F.col("n0") + F.col("n1")), "word").limit(most_terms).collect()

    def share_of(n: int, whole: int, word_share: float, prior: float = 50.0) -> float:
        """A word's share beside hits of one class, drawn towards its share beside all hits: with few hits it says little."""
        return (n + prior * word_share) / (whole + prior)

    model.context = {r["word"]: math.log(share_of(r["n1"], all1, q) / share_of(r["n0"], all0, q)) for r in common for q in [(r["n0"] + r["n1"]) / (all0 + all1)]}
    ready = spark.sparkContext.broadcast(ToxicityModel(model.weights, model.context, ordinary=model.ordinary))

    def described(batch: pa.RecordBatch) -> dict[str, list]:
        out: dict[str, list] = {"toxic": [], "weight": [], "x": []}
        model = ready.value
        for toxic, text in zip(batch.column("toxic").to_pylist(), batch.column("text").to_pylist(), strict=True):
            rows = [(toxic, 1.0, model.features(text))]
            if toxic and any(rows[0][2]):
                words, hits = model.hits(text)
                terms = {words[i] for i, _, _ in hits}
                rewritten = lambda f: WORDS.sub(lambda m: f(m[0]) if m[0] in terms else m[0], text.lower())  # noqa: B023, E731
                rows += [(1, 0.5, model.features(rewritten(misspelled))), (0, 0.5, model.features(rewritten(lambda w: f'"{w}"')))]
            for row in rows:
                for name, value in zip(out, row, strict=True):
                    out[name].append(value)
        return out

    table_of = scan(sample, described, "toxic int, weight double, x array<double>").collect()
    x, y, w = np.array([[1.0, *r["x"]] for r in table_of]), np.array([float(r["toxic"]) for r in table_of]), np.array([r["weight"] for r in table_of])
    return ToxicityModel(model.weights, model.context, logistic(x, y, w), model.ordinary)


def hash_of(word: str) -> int:
    """A hash that is the same in every process."""
    import zlib

    return zlib.crc32(word.encode()) * 2654435761 >> 7


def score(docs: DataFrame, model: ToxicityModel | None, *, id_col: str = "doc_id", text_col: str = "text", threshold: float = 0.3, carry: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, score, predicted of every row, and the columns named in carry."""
    held = docs.sparkSession.sparkContext.broadcast(model)
    own = of(docs, doc_id=id_col, text=text_col, **{f"_{c}": c for c in carry if c != text_col})
    types = "".join(f", _{c} {docs.schema[c].dataType.simpleString()}" for c in carry)

    def rows(batch: pa.RecordBatch) -> dict[str, list]:
        model, texts = held.value, batch.column("text").to_pylist()
        out = model.score([model.features(t) for t in texts]).tolist() if model else [0.0] * len(texts)
        return {"doc_id": batch.column("doc_id"), "score": out, "predicted": [int(s >= threshold) for s in out]} | {f"_{c}": batch.column("text" if c == text_col else f"_{c}") for c in carry}

    return scan(own, rows, SCORED + types).select("doc_id", "score", "predicted", *[F.col(f"_{c}").alias(c) for c in carry])


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    scored = score(docs, train(docs, table(spark, sf_dir, "labels")))
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", "predicted")
