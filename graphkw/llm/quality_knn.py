"""Quality scores by nearest-neighbour voting in a latent space (operator 1).

Terms are hashed words, word shapes (runs of upper, lower, digit and each sign)
and immediate repetitions. A bounded sample of labelled documents, the first
``sample`` by hash, gives idf weights and, by a truncated SVD, a space of ``rank``
dimensions. The sample's unit vectors and labels are broadcast (``sample * rank``
floats, whatever the corpus). Every document is projected, its cosines to all
labelled vectors are computed exactly in blocks, and the labels of its ``k``
nearest are averaged with weights that grow with similarity.

Edge cases: a text without words scores the sample's mean label; a null doc_id is
scored and never held out; repeated rows are scored each; labels that are null or
name no document are not used; of contradicting labels the lowest counts; without
any usable label every score is 0.5; further columns are ignored.
"""

from __future__ import annotations

import re
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .base import by_bytes, map_batches, table, text_of

WORDS, SHAPES = 4096 - 512, 510
#: Hashed words, hashed shapes, then words that repeat the one before and words that do not.
BLOCKS = ((0, WORDS), (WORDS, WORDS + SHAPES), (WORDS + SHAPES, WORDS + SHAPES + 2))
DIMS = WORDS + SHAPES + 2
_RUNS = re.compile(r"([A-Z]+)|([a-z]+)|([0-9]+)|([^\W\d_]+)|(.)\5*", re.S)
_CLASS = ("", "A", "a", "0", "w")


class _Terms(dict):
    """Word bytes to its two dimensions, packed; forgets all when full."""

    def __missing__(self, word: bytes) -> int:
        if len(self) > 300_000:
            self.clear()
        shape = _RUNS.sub(lambda m: _CLASS[m.lastindex] if m.lastindex < 5 else m[5], word[:64].decode("utf-8", "replace"))
        self[word] = got = zlib.crc32(word.lower()) % WORDS << 16 | WORDS + zlib.crc32(shape.encode()) % SHAPES
        return got


def counts(texts: list[str], terms: _Terms) -> np.ndarray:
    """Dense term counts, a row for each text."""
    rows, codes, again = [], [], []
    for k, t in enumerate(texts):
        code = np.fromiter(map(terms.__getitem__, t.encode("utf-8", "surrogatepass").split()), np.int64)
        if len(code):
            rows.append(np.full(len(code), k))
            codes.append(code)
            again.append(np.concatenate([[False], code[1:] == code[:-1]]))
    out = np.zeros((len(texts), DIMS), np.float32)
    if codes:
        row, code, rep = np.concatenate(rows) * DIMS, np.concatenate(codes), np.concatenate(again)
        cells = np.concatenate([row + (code >> 16), row + (code & 0xFFFF), row + DIMS - 1 - rep])
        out += np.bincount(cells, minlength=out.size).reshape(out.shape)
    return out


def _unit(x: np.ndarray) -> np.ndarray:
    return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)


@dataclass
class LatentModel:
    idf: np.ndarray
    axes: np.ndarray
    vectors: np.ndarray
    labels: np.ndarray
    prior: float
    k: int
    power: float

    @classmethod
    def fit(cls, tf: np.ndarray, labels: np.ndarray, rank: int = 64, k: int = 25, power: float = 4.0, seed: int = 7) -> LatentModel:
        idf = np.log((1 + len(tf)) / (1 + (tf > 0).sum(0))).astype(np.float32) + 1
        if not len(tf):
            return cls(idf, np.zeros((DIMS, 1), np.float32), np.zeros((0, 1), np.float32), labels, 0.5, k, power)
        x = cls._weighted(tf, idf)
        rank = min(rank, *x.shape)
        q = np.linalg.qr(x @ np.random.default_rng(seed).standard_normal((DIMS, min(rank + 16, DIMS)), np.float32))[0]
        for _ in range(3):
            q = np.linalg.qr(x @ np.linalg.qr(x.T @ q)[0])[0]
        axes = np.linalg.svd(q.T @ x, full_matrices=False)[2][:rank].T.astype(np.float32)
        return cls(idf, axes, _unit(x @ axes), labels.astype(np.float32), float(labels.mean()), k, power)

    @staticmethod
    def _weighted(tf: np.ndarray, idf: np.ndarray) -> np.ndarray:
        """Each block of dimensions as a unit vector: damped shares times idf, so that long and short texts are alike."""
        x = np.empty_like(tf)
        for a, b in BLOCKS:
            share = tf[:, a:b] / np.maximum(tf[:, a:b].sum(1, keepdims=True), 1)
            x[:, a:b] = _unit(np.log1p(200 * share) * idf[a:b] if b < DIMS else share)
        return x

    def score(self, tf: np.ndarray) -> np.ndarray:
        out = np.full(len(tf), self.prior)
        own = tf.sum(1) > 0
        if not len(self.vectors) or not own.any():
            return out
        cosines = _unit(self._weighted(tf[own], self.idf) @ self.axes) @ self.vectors.T
        k = min(self.k, len(self.vectors))
        top = np.argpartition(cosines, len(self.vectors) - k, axis=1)[:, -k:]
        weight = np.maximum(np.take_along_axis(cosines, top, 1), 1e-6).astype(float) ** self.power
        out[own] = np.clip((weight * self.labels[top]).sum(1) / weight.sum(1), 0, 1)
        return out


def held_out():
    """Whether a document's label is kept from training."""
    return F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(5)) == 0, F.lit(False))


def labelled_sample(docs: DataFrame, labels: DataFrame, sample: int, target: str = "quality") -> DataFrame:
    """(doc_id, text, label) of at most ``sample`` labels that aren't held out, the first by hash."""
    chosen = labels.filter(~held_out() & F.col(target).isNotNull()).groupBy("doc_id").agg(F.min(target).alias("label")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)
    return docs.select(docs["doc_id"].cast("long").alias("doc_id"), text_of().alias("text")).join(F.broadcast(chosen), "doc_id")


def fit_quality(docs: DataFrame, labels: DataFrame, sample: int = 5000, rank: int = 64, k: int = 25) -> LatentModel:
    def make():
        terms = _Terms()

        def work(batch):
            for a, b in by_bytes(batch.column(0).to_pylist(), 1 << 19):
                tf = counts(batch.column(0).slice(a, b - a).to_pylist(), terms)
                cells = [np.flatnonzero(r) for r in tf]
                columns = [pa.array([c.astype("<u2").tobytes() for c in cells]), pa.array([r[c].tobytes() for r, c in zip(tf, cells, strict=True)]), batch.column(1).slice(a, b - a)]
                yield pa.RecordBatch.from_arrays(columns, ["cells", "tf", "label"])

        return work

    rows = map_batches(labelled_sample(docs, labels, sample).select("text", F.col("label").cast("double").alias("label")), make, "cells binary, tf binary, label double").collect()
    rows = sorted((bytes(r["cells"]), bytes(r["tf"]), r["label"]) for r in rows)[: 2 * sample]
    tf = np.zeros((len(rows), DIMS), np.float32)
    for k_, (cells, values, _) in enumerate(rows):
        tf[k_, np.frombuffer(cells, "<u2")] = np.frombuffer(values, np.float32)
    return LatentModel.fit(tf, np.array([r[2] for r in rows]), rank, k)


def score_quality(docs: DataFrame, model: LatentModel, threshold: float = 0.3, block: int = 128) -> DataFrame:
    """All columns of ``docs`` but the text are left to the caller: returns doc_id, held_out, score, predicted."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def make():
        terms = _Terms()

        def work(batch):
            texts = batch.column(2).to_pylist()
            for a, b in by_bytes(texts, 1 << 20):
                score = np.concatenate([shared.value.score(counts(texts[k : min(k + block, b)], terms)) for k in range(a, b, block)])
                columns = [batch.column(0).slice(a, b - a), batch.column(1).slice(a, b - a), pa.array(score), pa.array((score >= threshold).astype(np.int32))]
                yield pa.RecordBatch.from_arrays(columns, ["doc_id", "held_out", "score", "predicted"])

        return work

    rows = docs.select(docs["doc_id"].cast("long").alias("doc_id"), held_out().alias("held_out"), text_of().alias("text"))
    return map_batches(rows, make, "doc_id long, held_out boolean, score double, predicted int")


def keep_good(docs: DataFrame, model: LatentModel, threshold: float = 0.3, block: int = 128) -> DataFrame:
    """The rows of ``docs`` that the model doesn't reject, all columns unchanged."""
    shared, schema, at = docs.sparkSession.sparkContext.broadcast(model), docs.schema, docs.columns.index("text")

    def make():
        terms = _Terms()

        def work(batch):
            texts = [t or "" for t in batch.column(at).to_pylist()]
            for a, b in by_bytes(texts, 1 << 20):
                score = np.concatenate([shared.value.score(counts(texts[k : min(k + block, b)], terms)) for k in range(a, b, block)])
                yield batch.slice(a, b - a).filter(pa.array(score >= threshold))

        return work

    return map_batches(docs, make, schema)


def op1_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return score_quality(docs, fit_quality(docs, table(spark, sf_dir, "labels")))
