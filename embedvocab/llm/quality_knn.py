"""Quality by nearest-neighbour voting over latent-semantic vectors.

The terms of a text are its words and runs of marks, the words' beginnings, and for words said again and again how long the
run is. Term shares are damped by a square root and weighted by inverse document frequency, and projected on the leading
right singular vectors of the labelled training rows. Labelled vectors are broadcast; every document's cosine with each of
them is computed exactly, in blocks, and the nearest vote with weights that grow with similarity.

At most ``sample`` labelled rows (the first by a hash of the id) are fitted and broadcast, with at most ``vocabulary`` terms:
(sample + vocabulary) x rank floats, whatever the corpus. All documents are scored over their whole texts.

All labelled vectors that are as near as the last of the ``neighbours`` vote, so ties have no order; cosines count to six
places. Null and empty texts, and texts without a term of the vocabulary, get the share of label 1 among the labelled. Without
training rows every score is 0.5. Rows with null ids are scored, never trained on. Repeated rows get equal scores, as blocks
are always of one shape. A very long text takes memory of a small multiple of its length, for its distinct words. Extra
columns, whatever their names, are ignored.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from itertools import groupby

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from embedvocab.llm.common import arrow_rows, columns, held_out, per_document, trimmed, written
from embedvocab.llm.toxicity import training_rows

_TOKEN = re.compile(r"[^\W_]+|[^\w\s]+|_+")
#: Letters of a word's beginning, which stands for the word where that is too rare.
STEM = 3
#: Rows of a block of cosines.
BLOCK = 256


def terms(text: str) -> Counter[str]:
    """How often each term occurs."""
    words = text.split()
    out: Counter[str] = Counter()
    for word, n in Counter(words).items():
        for token in (word,) if word.isalnum() else _TOKEN.findall(word):
            out[token] += n
            if len(token) > STEM:
                out[token[:STEM] + "*"] += n
    if any(map(str.__eq__, words, words[1:])):
        for _, run in groupby(words):
            n = sum(1 for _ in run)
            if n > 1:  # two or three times, four to seven times, more
                out[f"{min(4, n.bit_length())} runs"] += n
    lines = text.count("\n")
    if lines:
        out["\n"] = lines
    return out


class Model:
    """The vocabulary, the projection, the labelled vectors and their labels."""

    def __init__(self, vocabulary: dict[str, int], weights: np.ndarray, axes: np.ndarray, vectors: np.ndarray, labels: np.ndarray, neighbours: int):
        self.vocabulary, self.weights, self.axes, self.vectors, self.labels, self.neighbours = vocabulary, weights, axes, vectors, labels, neighbours
        self.prior = float(labels.mean()) if len(labels) else 0.5

    def known(self, text: str) -> tuple[np.ndarray, np.ndarray]:
        """Places in the vocabulary of the text's terms, ascending, and the roots of their shares."""
        counts = terms(text)
        found = sorted((self.vocabulary[w], n) for w, n in counts.items() if w in self.vocabulary)
        at = np.array([i for i, _ in found], np.int64)
        return at, np.sqrt(np.array([n for _, n in found], np.float32) / max(1, counts.total()))

    def project(self, rows: np.ndarray) -> np.ndarray:
        z = (rows * self.weights) @ self.axes
        return z / np.maximum(np.linalg.norm(z, axis=1, keepdims=True), 1e-12)

    def score(self, texts: list[str]) -> np.ndarray:
        out = np.full(len(texts), self.prior)
        if not len(self.labels):
            return out
        k = min(self.neighbours, len(self.labels))
        for begin in range(0, len(texts), BLOCK):
            rows, full = np.zeros((BLOCK, len(self.weights)), np.float32), np.zeros(BLOCK, bool)
            for i, text in enumerate(texts[begin:begin + BLOCK]):
                at, values = self.known(text)
                rows[i, at], full[i] = values, len(at) > 0
            near = np.rint((self.project(rows) @ self.vectors.T) * 1e6)
            kth = -np.partition(-near, k - 1, axis=1)[:, k - 1:k]
            row, voter = np.nonzero((near >= kth) & full[:, None])
            far = 1 - near[row, voter] / 1e6
            count = np.maximum(np.bincount(row, minlength=BLOCK), 1)
            # a neighbour at the mean distance of those that vote counts e times less than one at distance zero
            weight = np.exp(-far / np.maximum(np.bincount(row, far, BLOCK) / count, 1e-6)[row])
            votes = np.bincount(row, weight * self.labels[voter], BLOCK) / np.maximum(np.bincount(row, weight, BLOCK), 1e-300)
            n = len(texts[begin:begin + BLOCK])
            out[begin:begin + n] = np.where(full, np.clip(votes, 0, 1), self.prior)[:n]
        return out


def singular_vectors(weighted: np.ndarray, rank: int) -> np.ndarray:
    """Leading right singular vectors as columns, by subspace iteration from a fixed start."""
    axes = np.random.default_rng(7).standard_normal((weighted.shape[1], min(rank + 16, weighted.shape[1]))).astype(np.float32)
    for _ in range(6):
        axes, _ = np.linalg.qr(weighted.T @ (weighted @ axes))
    _, _, turn = np.linalg.svd(weighted @ axes, full_matrices=False)
    return np.ascontiguousarray(axes @ turn.T[:, :rank])


def fit(docs: DataFrame, labels: DataFrame, modulus: int = 5, remainder: int = 0, sample: int = 6000, vocabulary: int = 4096, rank: int = 64, neighbours: int = 15, least_rows: int = 3) -> Model:
    """The model of the labelled rows; the driver gets the vocabulary and each row's known terms."""
    rows = written(training_rows(docs, labels, "quality", modulus, remainder, sample).select("text", F.col("label").cast("int").alias("label")))  # a bounded table, read twice

    def occurring(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: Counter[str] = Counter()
        for batch in batches:
            for text in batch.column(0):
                seen.update(terms(text.as_py()).keys())
        yield pa.record_batch([pa.array(list(seen), pa.string()), pa.array(list(seen.values()), pa.int64())], names=["w", "n"])
        trimmed()

    often = rows.select("text").mapInArrow(occurring, "w string, n long").groupBy("w").agg(F.sum("n").alias("n")).filter(F.col("n") >= least_rows).orderBy(F.desc("n"), "w").limit(vocabulary).collect()
    model = Model({r.w: i for i, r in enumerate(often)}, np.zeros(len(often), np.float32), np.zeros((len(often), 0), np.float32), np.zeros((0, 0), np.float32), np.zeros(0), neighbours)

    def known(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        schema = pa.schema([("at", pa.binary()), ("values", pa.binary()), ("label", pa.int32())])
        for batch in batches:
            found = ((model.known(t.as_py()), y) for t, y in zip(batch.column(0), batch.column(1).to_pylist(), strict=True))
            yield from arrow_rows(schema, ((at.astype("<u4").tobytes(), values.tobytes(), y) for (at, values), y in found)).to_batches()
        trimmed()

    got = sorted((bytes(r["at"]), bytes(r["values"]), r["label"]) for r in rows.mapInArrow(known, "at binary, values binary, label int").collect())
    if not got or not often:
        return model
    x = np.zeros((len(got), len(often)), np.float32)
    for i, (at, values, _) in enumerate(got):
        x[i, np.frombuffer(at, "<u4")] = np.frombuffer(values, np.float32)
    weights = (np.log((1 + len(x)) / (1 + (x > 0).sum(axis=0))) + 0.1).astype(np.float32)
    model = Model(model.vocabulary, weights, singular_vectors(x * weights, rank), np.zeros((0, rank), np.float32), np.array([y for *_, y in got], float), neighbours)
    model.vectors = model.project(x)
    return model


def scores(docs: DataFrame, model: Model, modulus: int = 5, remainder: int = 0, threshold: float = 0.3) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every row."""
    schema = pa.schema([("doc_id", pa.int64()), ("held_out", pa.bool_()), ("score", pa.float64()), ("predicted", pa.int32())])

    def run(ids: list, texts: list[bytes]) -> Iterator[tuple]:
        for i, s in zip(ids, model.score([t.decode() for t in texts]).tolist(), strict=True):
            yield i, held_out(i, modulus, remainder), s, int(s >= threshold)

    return per_document(docs, run, schema, "doc_id long, held_out boolean, score double, predicted int", most=4 << 20)


def with_score(docs: DataFrame, model: Model, name: str) -> DataFrame:
    """docs, all columns kept, with one more: the score."""
    place = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = np.full(batch.num_rows, model.prior)
            for at in range(0, batch.num_rows, BLOCK):
                found[at:at + BLOCK] = model.score([t.as_py() or "" for t in batch.column(place).slice(at, BLOCK)])
            yield batch.append_column(name, pa.array(found, pa.float64()))
        trimmed()

    return docs.mapInArrow(run, docs.withColumn(name, F.lit(0.0)).schema)


def keep_good(docs: DataFrame, labels: DataFrame, threshold: float = 0.3) -> DataFrame:
    """The (doc_id, score) at or above the threshold."""
    return scores(columns(docs, doc_id="long", text="string"), fit(docs, labels), threshold=threshold).filter("predicted = 1").select("doc_id", "score")


def brute_force(model: Model, text: str) -> float:
    """A document's score by the definition, plainly, for tests: each cosine by itself, all sorted."""
    at, values = model.known(text)
    if not len(at) or not len(model.labels):
        return model.prior
    z = (values.astype(float) * model.weights[at]) @ model.axes[at].astype(float)
    z /= max(float(np.linalg.norm(z)), 1e-12)
    near = sorted(((round(float(v.astype(float) @ z), 6), y) for v, y in zip(model.vectors, model.labels, strict=True)), reverse=True)
    last = near[min(model.neighbours, len(near)) - 1][0]
    voters = [(1 - s, y) for s, y in near if s >= last]
    mean = max(sum(f for f, _ in voters) / len(voters), 1e-6)
    weights = [np.exp(-f / mean) for f, _ in voters]
    return float(sum(w * y for w, (_, y) in zip(weights, voters, strict=True)) / sum(weights))
