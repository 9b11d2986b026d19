"""Language identification with string kernels.

The blended-spectrum presence kernel of two texts is the number of n-grams (1 to `most_n` bytes, ASCII lower-cased) that occur in
both, over the root of the product of their numbers of n-grams; n-grams are taken modulo a hash of `1 << BITS` buckets. Landmarks
(Nyström) stand for all training texts, and kernel ridge regression separates each language from the rest. As the kernel is an
inner product of presence vectors, landmarks and weights fold into one matrix with a column for each language, and a batch of
texts is scored by one product of its presence matrix with it.

Only the fit looks at a bounded sample: about `per_language` labelled rows of each language (`most_languages` languages, the
most frequent), of which the driver gets presence bits, never texts. Every whole text is scored. Null texts and texts without a
letter are `und` with score 0, and so is everything where nothing is labelled. Repeated rows give repeated results; extra
columns are ignored. The score is the winner's ridge output, mapped from [-1, 1] to [0, 1].
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from gpart.llm.common import of, scan, table, utf8

BITS = 15
LETTER = re.compile(r"[^\W\d_]")
LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
PREDICTED = "doc_id long, lang_pred string, score double"
BATCH = 128


def held_out(doc_id: Column) -> Column:
    """The test fold: crc32 of the id as text, modulo 4, is 2."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def presence(text: bytes, most_n: int, row: np.ndarray) -> None:
    """Mark the buckets of the text's n-grams in row."""
    data = np.frombuffer(text.translate(LOWER), dtype=np.uint8).astype(np.uint32)
    code = data
    for n in range(1, most_n + 1):
        if len(data) < n:
            return
        if n > 1:
            code = (code[:-1] << np.uint32(8)) | data[n - 1 :]
        row[(code * np.uint32(2654435761) + np.uint32(n * 0x9E3779B1 & 0xFFFFFFFF)) >> np.uint32(32 - BITS)] = 1


@dataclass
class LanguageModel:
    languages: list[str]
    weights: np.ndarray  #: a column for each language, and one of ones, which counts n-grams
    most_n: int

    def scores(self, texts: list[bytes]) -> np.ndarray:
        marks = np.zeros((len(texts), 1 << BITS), dtype=np.uint8)
        for row, text in zip(marks, texts, strict=True):
            presence(text, self.most_n, row)
        out = marks.astype(np.float32) @ self.weights
        return out[:, :-1] / np.sqrt(np.maximum(out[:, -1:], 1))


def fit(bits: np.ndarray, labels: list[str], landmarks: int, ridge: float, most_n: int, seed: int = 0) -> LanguageModel:
    """bits: packed presence bits, a row for each text. They are unpacked a few rows at a time, so that the driver holds the landmarks'
    vectors and the kernel, never those of all texts."""
    languages = sorted(set(labels))
    target = np.where(np.array(labels)[:, None] == np.array(languages)[None, :], 1.0, -1.0)

    def unit(rows: np.ndarray) -> np.ndarray:
        marks = np.unpackbits(rows, axis=1).astype(np.float32)
        marks /= np.sqrt(np.maximum(marks.sum(1, keepdims=True, dtype=np.float32), 1))
        return marks

    chosen = unit(bits[np.random.default_rng(seed).permutation(len(bits))[:landmarks]])
    among = (chosen @ chosen.T).astype(float)
    across = np.concatenate([unit(bits[at : at + BATCH]) @ chosen.T for at in range(0, len(bits), BATCH)]).astype(float)
    balance = 1 / np.array([labels.count(x) for x in labels])  # each language weighs the same
    system = (across * balance[:, None]).T @ across + ridge * len(languages) * among + 1e-8 * np.eye(len(chosen))
    solved = np.linalg.solve(system, (across * balance[:, None]).T @ target)
    weights = np.concatenate([chosen.T @ solved.astype(np.float32), np.ones((1 << BITS, 1), dtype=np.float32)], axis=1)
    return LanguageModel(languages, weights, most_n)


def train(labelled: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", per_language: int = 300, most_languages: int = 256, landmarks: int = 256, ridge: float = 1e-4, most_n: int = 3) -> LanguageModel | None:
    """A model from the labelled rows that are not held out, or None where there are none."""
    rows = of(labelled, doc_id=id_col, text=text_col, lang=lang_col).where(F.col("lang").isNotNull() & ~held_out(F.col("doc_id")))
    sizes = rows.groupBy("lang").count().orderBy(F.desc("count"), "lang").limit(most_languages).collect()
    if not sizes:
        return None
    share = F.create_map(*[F.lit(x) for r in sizes for x in (r["lang"], min(1.0, per_language / r["count"]))])
    drawn = F.pmod(F.xxhash64("doc_id", F.lit("language")), F.lit(1 << 30)) / float(1 << 30) < F.try_element_at(share, F.col("lang"))

    def bits(batch: pa.RecordBatch) -> dict[str, list]:
        out = []
        for text in utf8(batch, "text"):
            row = np.zeros(1 << BITS, dtype=np.uint8)
            presence(text, most_n, row)
            out.append(np.packbits(row).tobytes())
        return {"lang": batch.column("lang"), "bits": out}

    sample = scan(rows.where(drawn & (F.length("text") > 0)), bits, "lang string, bits binary").collect()
    sample.sort(key=lambda r: (r["lang"], bytes(r["bits"])))
    if not sample:
        return None
    return fit(np.array([np.frombuffer(r["bits"], dtype=np.uint8) for r in sample]), [r["lang"] for r in sample], landmarks, ridge, most_n)


def predict(docs: DataFrame, model: LanguageModel | None, *, id_col: str = "doc_id", text_col: str = "text", carry: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, lang_pred, score of every row, and the columns named in carry."""
    held = docs.sparkSession.sparkContext.broadcast(model)
    own = of(docs, doc_id=id_col, text=text_col, **{f"_{c}": c for c in carry if c != text_col})
    types = "".join(f", _{c} {docs.schema[c].dataType.simpleString()}" for c in carry)

    def rows(batch: pa.RecordBatch) -> dict[str, list]:
        model, texts, plain = held.value, utf8(batch, "text"), batch.column("text").to_pylist()
        said, score = ["und"] * len(texts), [0.0] * len(texts)
        known = [i for i, t in enumerate(plain) if t and LETTER.search(t)] if model else []
        for at in range(0, len(known), BATCH):
            part = known[at : at + BATCH]
            out = model.scores([texts[i] for i in part])
            for i, best, value in zip(part, out.argmax(1), out.max(1), strict=True):
                said[i], score[i] = model.languages[best], float(min(1.0, max(0.0, (value + 1) / 2)))
        return {"doc_id": batch.column("doc_id"), "lang_pred": said, "score": score} | {f"_{c}": batch.column("text" if c == text_col else f"_{c}") for c in carry}

    found = scan(own, rows, PREDICTED + types)
    return found.select("doc_id", "lang_pred", "score", *[F.col(f"_{c}").alias(c) for c in carry])


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return predict(docs, train(docs)).select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")
