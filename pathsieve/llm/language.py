"""Language identification with blended-spectrum string kernels.

k(x, y) counts the n-grams (of 1 to 4 UTF-8 bytes of the lower-cased text) that are
present in both texts, normalised by the roots of k(x, x) and k(y, y). A bounded sample
of labelled texts gives the landmarks and the ridge regression: Nystroem features
K(x, landmarks) W^(-1/2), one ridge regressor for each language against the rest. The
chain of matrices behind an input's n-grams is constant, so it is multiplied out once:
scoring a batch is one product of its presence matrix with a matrix of
(hashed n-grams) x (languages).
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathsieve.llm.shared import forget_tokenizers, masked, own_columns, text_slices

#: Hashed n-grams; sizes of n-grams; labelled texts of a language in the sample, at most; landmarks; ridge.
DIMENSIONS, SIZES, SAMPLE, LANDMARKS, RIDGE = 1 << 15, (1, 2, 3, 4), 500, 256, 1e-3
UNKNOWN = "und"
_LETTER = re.compile(r"[^\W\d_]")
_PAD = b" " * max(SIZES)
_ROWS = 128


def presence(texts: list[str | None]) -> np.ndarray:
    """A row of 0 and 1 for each text."""
    raws = [(t or "").lower().encode() for t in texts]
    raw = np.frombuffer(_PAD.join([*raws, b""]) + _PAD, np.uint8).astype(np.uint32)
    sizes = np.array([len(r) for r in raws], np.int64)
    out = np.zeros((len(texts) + 1, DIMENSIONS), np.uint8)  # the last row takes n-grams that start in the padding
    spans = np.stack([sizes, np.full(len(raws), len(_PAD))], 1).ravel()
    owner = np.repeat(np.stack([np.arange(len(raws)), np.full(len(raws), len(texts))], 1).ravel(), spans) * DIMENSIONS
    flat, code = out.ravel(), np.zeros(len(owner), np.uint32)
    for n in range(1, max(SIZES) + 1):
        code = (code << np.uint32(8)) | raw[n - 1 : n - 1 + len(owner)]
        if n in SIZES:
            hashed = ((code ^ np.uint32(n)) * np.uint32(2654435761)) >> np.uint32(32 - DIMENSIONS.bit_length() + 1)
            flat[owner + hashed] = 1
    return out[:-1]


@dataclass(frozen=True)
class Model:
    languages: list[str]
    weights: np.ndarray  # DIMENSIONS x languages
    constant: np.ndarray

    def scores(self, texts: list[str | None]) -> np.ndarray:
        parts = [np.zeros((0, len(self.languages)), np.float32)]
        for at in range(0, len(texts), _ROWS):
            seen = presence(texts[at : at + _ROWS])
            norm = np.sqrt(np.maximum(seen.sum(1, dtype=np.int64), 1))
            parts.append((seen.astype(np.float32) @ self.weights) / norm[:, None].astype(np.float32) + self.constant)
        return np.concatenate(parts)


def _unit(packed: np.ndarray) -> np.ndarray:
    seen = np.unpackbits(packed, axis=1)
    return seen.astype(np.float32) / np.sqrt(np.maximum(seen.sum(1, dtype=np.int64), 1))[:, None].astype(np.float32)


def train(packed: np.ndarray, labels: list[str], landmarks: int = LANDMARKS, ridge: float = RIDGE) -> Model:
    """packed: presence rows as bits. The first rows of each language in turn are the landmarks."""
    languages = sorted(set(labels))
    if not languages:
        return Model([], np.zeros((DIMENSIONS, 0), np.float32), np.zeros(0, np.float32))
    y = np.array([languages.index(x) for x in labels])
    turn = np.zeros(len(y), np.int64)
    for k in range(len(languages)):
        turn[y == k] = np.arange((y == k).sum())
    marks = _unit(packed[np.argsort(turn, kind="stable")[:landmarks]])
    values, vectors = np.linalg.eigh((marks @ marks.T).astype(np.float64))
    kept = values > 1e-6 * values.max()
    root = vectors[:, kept] / np.sqrt(values[kept])
    features = np.concatenate([(_unit(packed[at : at + _ROWS]) @ marks.T).astype(np.float64) @ root for at in range(0, len(y), _ROWS)])
    features = np.c_[features, np.ones(len(features))]
    weight = (len(y) / np.bincount(y))[y]  # each language counts alike
    targets = np.where(y[:, None] == np.arange(len(languages)), 1.0, -1.0)
    gram = features.T @ (features * weight[:, None]) + ridge * len(y) * np.eye(features.shape[1])
    solved = np.linalg.solve(gram, features.T @ (targets * weight[:, None]))
    return Model(languages, marks.T @ (root @ solved[:-1]).astype(np.float32), solved[-1].astype(np.float32))


def held_out(doc_id: Column, folds: int = 5, fold: int = 0) -> Column:
    """crc32 of the id as text, modulo folds; a null id counts as ''."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % folds == fold


def fit(docs: DataFrame, sample: int = SAMPLE) -> Model:
    """From (doc_id, text, lang) of labelled rows that aren't held out: at most `sample` texts of a language, those of the least hash of their doc_id and text, so that a doc_id that repeats isn't taken as a whole."""
    rows = own_columns(docs, "doc_id", "text", "lang").where(F.col("lang").isNotNull() & F.col("text").isNotNull() & ~held_out(F.col("doc_id")))
    counts = {r["lang"]: r["n"] for r in rows.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()}  # a row for each language
    if not counts:
        return train(np.zeros((0, DIMENSIONS // 8), np.uint8), [])
    at = F.pmod(F.xxhash64("doc_id", "text"), F.lit(1 << 40))
    share = F.lit(0.0)
    for lang, n in counts.items():
        share = F.when(F.col("lang") == lang, F.lit(min(1.0, 1.3 * sample / n + 30 / n))).otherwise(share)
    some = rows.withColumn("at", at).where(F.col("at") < share * float(1 << 40)).select("at", "lang", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in text_slices(whole, "text"):
                texts = batch.column("text").to_pylist()
                bits = [np.packbits(x).tobytes() for k in range(0, len(texts), _ROWS) for x in presence(texts[k : k + _ROWS])]
                yield pa.RecordBatch.from_arrays([batch.column("at"), batch.column("lang"), pa.array(bits, pa.binary())], ["at", "lang", "bits"])

    found = sorted(some.mapInArrow(run, "at long, lang string, bits binary").collect(), key=lambda r: (r["lang"], r["at"], bytes(r["bits"])))
    chosen, taken = [], dict.fromkeys(counts, 0)
    for r in found:
        if taken[r["lang"]] < sample:
            taken[r["lang"]] += 1
            chosen.append(r)
    packed = np.stack([np.frombuffer(r["bits"], np.uint8) for r in chosen]) if chosen else np.zeros((0, DIMENSIONS // 8), np.uint8)
    return train(packed, [r["lang"] for r in chosen])


def predict(docs: DataFrame, model: Model, columns: list[str] | None = None) -> DataFrame:
    """docs' columns (default doc_id) with (lang_pred, score). `und` with score 0 for a null text, one without letters, or a model of no language."""
    keep = columns or ["doc_id"]
    rows = own_columns(docs, *keep, *([] if "text" in keep else ["text"]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forget_tokenizers()
        names = np.array([*model.languages, UNKNOWN], object)
        for whole in batches:
            for batch in text_slices(whole, "text"):
                texts = batch.column("text").to_pylist()
                lettered = np.array([bool(t and _LETTER.search(t)) for t in texts])
                if model.languages:
                    scores = model.scores(texts)
                    best, top = scores.argmax(1), scores.max(1)
                else:
                    best, top = np.full(len(texts), 0), np.zeros(len(texts))
                    lettered[:] = False
                label = names[np.where(lettered, best, len(names) - 1)]
                score = np.where(lettered, np.clip((top.astype(float) + 1) / 2, 0, 1), 0.0)
                yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), pa.array(label, pa.string()), pa.array(score, pa.float64())], [*keep, "lang_pred", "score"])

    schema = type(rows.schema)([rows.schema[c] for c in keep]).add("lang_pred", "string").add("score", "double")
    return rows.mapInArrow(run, schema)


def accepted(docs: DataFrame, model: Model, least_score: float) -> DataFrame:
    """The rows of docs, all columns, whose text has a language: letters, and a score of `least_score` at least. Null and empty texts have none; repeated rows stay or go together."""
    rows, named = masked(docs, "text")
    found = predict(rows, model, rows.columns)
    return named(found.where((F.col("lang_pred") != UNKNOWN) & (F.col("score") >= least_score)))
