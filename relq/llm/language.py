"""Language identification with blended-spectrum string kernels.

A text is the set of its byte n-grams up to three, hashed; the kernel of two
texts is the cosine of their presence vectors. Nyström landmarks turn it into
finite features, on which one-versus-rest kernel ridge regression is fitted.
Scoring a batch is two matrix products.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .labels import residue
from .workers import tidy

#: Documented bounds: rows of each language to learn from, rows of all languages, landmarks, and buckets of n-grams.
PER_LANGUAGE, ROWS, LANDMARKS, BUCKETS = 1_200, 60_000, 192, 8_192
RIDGE, SHARPNESS, UNDETERMINED = 1e-3, 4.0, "und"
_SPACES = bytes(c if c >= 128 or chr(c).isalpha() else 32 for c in range(256)).lower()


def presence(texts: list[str | None]) -> np.ndarray:
    """One row of zeros and ones per text: which hashed n-grams of one to three bytes occur anywhere in it."""
    out = np.zeros((len(texts), BUCKETS), np.uint8)
    for row, text in zip(out, texts, strict=True):
        raw = np.frombuffer((text or "").lower().encode("utf-8", "replace").translate(_SPACES), np.uint8)
        for k in range(0, len(raw), 1 << 20):  # overlapping slices bound the memory of very long texts
            gram = np.zeros(0, np.uint32)
            part = raw[k : k + (1 << 20) + 2].astype(np.uint32)
            for n in (1, 2, 3):
                gram = part if n == 1 else gram[:-1] * np.uint32(257) + part[n - 1 :]
                if len(part) >= n:
                    row[(gram * np.uint32(2_654_435_761)) >> np.uint32(19)] = 1
    return out


def kernel(left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Cosine of presence vectors; an empty text resembles nothing."""
    a, b = left.astype(np.float32), right.astype(np.float32)
    norm = np.sqrt(np.maximum(a.sum(1), 1))[:, None] * np.sqrt(np.maximum(b.sum(1), 1))[None]
    return (a @ b.T) / norm


class LanguageModel:
    """Landmarks and coefficients of all languages; ``predict`` scores a batch."""

    def __init__(self, landmarks: np.ndarray, coefficients: np.ndarray, languages: list[str]):
        self.landmarks, self.coefficients, self.languages = landmarks, coefficients.astype(np.float32), languages

    def predict(self, texts: pa.Array) -> tuple[list[str], np.ndarray]:
        if not self.languages:
            return [UNDETERMINED] * len(texts), np.zeros(len(texts))
        names, scores = [], []
        for k in range(0, len(texts), 256):
            f = kernel(presence(texts.slice(k, 256).to_pylist()), self.landmarks) @ self.coefficients
            p = np.exp(SHARPNESS * (f - f.max(1, keepdims=True)).astype(float))
            p /= p.sum(1, keepdims=True)
            best = p.argmax(1)
            names += [self.languages[j] for j in best]
            scores.append(p[np.arange(len(best)), best])
        return names, np.concatenate(scores) if scores else np.zeros(0)


def fit(packed: np.ndarray, names: list[str]) -> LanguageModel:
    """Nyström features of the landmarks and a ridge fit of +1 against -1 for each language; ``packed`` are the bits of presence vectors."""
    languages = sorted(set(names))
    y = np.array([languages.index(x) for x in names])
    ranks = np.zeros(len(y), int)
    for c in range(len(languages)):
        ranks[y == c] = np.arange((y == c).sum())
    landmarks = np.unpackbits(packed[np.argsort(ranks, kind="stable")[: max(LANDMARKS, len(languages))]], axis=1)
    values, axes = np.linalg.eigh(kernel(landmarks, landmarks).astype(float))
    keep = values > 1e-6 * values.max()
    root = axes[:, keep] / np.sqrt(values[keep])
    gram, target = np.zeros((keep.sum(), keep.sum())), np.zeros((keep.sum(), len(languages)))
    share = np.bincount(y, minlength=len(languages))
    for k in range(0, len(y), 256):
        phi = kernel(np.unpackbits(packed[k : k + 256], axis=1), landmarks).astype(float) @ root
        weight = (1 / share[y[k : k + 256]])[:, None]
        gram += phi.T @ (weight * phi)
        target += phi.T @ (weight * (2.0 * (y[k : k + 256, None] == np.arange(len(languages))) - 1))
    return LanguageModel(landmarks, root @ np.linalg.solve(gram + RIDGE * np.eye(len(gram)), target), languages)


def train(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", per_language: int = PER_LANGUAGE, held_out: tuple[int, int] = (3, 1)) -> LanguageModel:
    """Learns from at most ``per_language`` texts of each language, those whose ids hash lowest; of fewer where
    there are so many languages that all together would pass 60,000 texts, but of one at least. Every language is learned.

    Held-out ids (crc32 modulo held_out), null languages, null texts and null
    ids are left out. Only packed presence vectors, 1 KB a text, reach the driver.
    """
    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text"), F.col(lang_col).cast("string").alias("lang"))
    known = rows.where("lang is not null and text is not null and doc_id is not null").where(residue(F.col("doc_id"), held_out[0]) != held_out[1])
    counts = {r["lang"]: r["n"] for r in known.groupBy("lang").agg(F.count("*").alias("n")).collect()}  # a row a language
    languages = sorted(counts)
    if not languages:
        return LanguageModel(np.zeros((0, BUCKETS), np.uint8), np.zeros((0, 0)), [])
    mark = F.xxhash64("doc_id")
    per_language = max(1, min(per_language, ROWS // len(languages)))
    # a cut on the hash leaves about twice the bound of each language; the exact bound follows on few rows
    span = 1 << 64
    rows = [(name, max(-(1 << 63), min((1 << 63) - 1, int(-(1 << 63) + span * min(1.0, (2 * per_language + 200) / n))))) for name, n in counts.items()]
    cuts = F.broadcast(docs.sparkSession.createDataFrame(rows, "lang string, cut long"))
    few = known.join(cuts, "lang").where(mark <= F.col("cut"))

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            bits = [np.packbits(presence([x.as_py()])[0]).tobytes() for x in batch.column(2)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(bits, pa.binary())], ["mark", "lang", "bits"])

    found = few.select(mark.alias("mark"), "lang", "text").mapInArrow(tidy(pack), "mark long, lang string, bits binary").toPandas()
    found = found.sort_values(["mark", "lang", "bits"]).groupby("lang").head(per_language)
    return fit(np.stack([np.frombuffer(b, np.uint8) for b in found["bits"]]), found["lang"].tolist())


def identify(docs: DataFrame, model: LanguageModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, lang_pred, score)``, one row per input row, from the text alone.

    Null texts and texts without a letter are ``und`` with score 0; texts are
    read whole. Repeated rows are repeated; empty tables give no rows.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            names, scores = shared.value.predict(batch.column(1))
            lettered = batch.column(2).to_pylist()
            names = [n if ok else UNDETERMINED for n, ok in zip(names, lettered, strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(names, pa.string()), pa.array(np.where(lettered, scores, 0.0))], ["doc_id", "lang_pred", "score"])

    text = F.col(text_col).cast("string")
    rows = docs.select(F.col(id_col).alias("doc_id"), text.alias("text"), F.coalesce(text.rlike(r"\p{L}"), F.lit(False)).alias("lettered"))
    return rows.mapInArrow(tidy(run), f"doc_id {kind}, lang_pred string, score double")


def op5_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with its predicted language."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return identify(docs, train(docs)).select("doc_id", (residue(F.col("doc_id"), 3) == 1).alias("held_out"), "lang_pred", "score")
