"""Quality classifier: supervised subword embeddings, averaged per document, with a softmax output.

A word's vector is the mean of the vectors of its features: the hashed word itself and its hashed
character n-grams. A document's vector is the mean over its words, and a linear softmax layer gives
the label's probability. Vectors and layer are trained by numpy stochastic gradient descent on a
bounded sample of labelled rows, in one task; every document is scored, over its whole text.

Since the output is linear in the averaged vectors, a trained model is one number per feature, and
scoring a word is a look-up of its remembered sum.
"""

from __future__ import annotations

import dataclasses
import operator
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

_REMEMBERED = 300_000  # words whose scores a task remembers


@dataclasses.dataclass(frozen=True)
class Settings:
    """Bounds and sizes. ``sample``: most labelled rows that training uses (documented bound, by the
    order of a hash of the doc_id); ``folds`` and ``held_out``: rows with crc32(doc_id as text) mod
    ``folds`` equal to ``held_out`` are never learned from."""

    sample: int = 6000
    buckets: int = 1 << 17
    dim: int = 10
    low: int = 3
    high: int = 4
    epochs: int = 8
    least_steps: int = 20_000
    rate: float = 0.1
    seed: int = 1
    folds: int = 3
    held_out: int = 1


#: Pseudo-word that stands for a word which repeats the one before it; no word holds white space.
SAME = b"\n="


def words_of(text: str | None) -> list[bytes]:
    """Words of a text as UTF-8, and one pseudo-word for each immediate repetition."""
    words = (text or "").encode("utf-8", "surrogatepass").split()
    return words + [SAME] * sum(map(operator.eq, words, words[1:]))


def features(words: list[bytes], settings: Settings) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of each word's features, and the word that each belongs to: the word itself, and the
    character n-grams of the word between word marks. Case is kept."""
    marked = [f"<{w.decode('utf-8', 'replace')}>" for w in words]
    signs = np.frombuffer("".join(marked).encode("utf-32-le", "surrogatepass"), "<u4").astype(np.uint64)
    sizes = np.fromiter(map(len, marked), np.int64, len(words))
    owner = np.repeat(np.arange(len(words)), sizes)
    left = np.repeat(np.cumsum(sizes), sizes) - np.arange(len(signs))
    whole = np.fromiter(map(zlib.crc32, words), np.uint64, len(words)) % np.uint64(settings.buckets)
    ids, owners = [whole], [np.arange(len(words))]
    for n in range(settings.low, settings.high + 1):
        at = np.flatnonzero(left >= n)
        mixed = np.full(len(at), n, np.uint64)
        for step in range(n):
            mixed = (mixed ^ signs[at + step]) * np.uint64(0x9E3779B97F4A7C15)
            mixed ^= mixed >> np.uint64(29)
        ids.append(mixed % np.uint64(settings.buckets))
        owners.append(owner[at])
    return np.concatenate(ids).astype(np.int64), np.concatenate(owners)


def bag(text: str | None, settings: Settings) -> tuple[np.ndarray, np.ndarray]:
    """Distinct features of a text and their weights, which sum to 1 (none for wordless texts)."""
    counts = Counter(words_of(text))
    if not counts:
        return np.zeros(0, np.int64), np.zeros(0, np.float32)
    ids, owner = features(list(counts), settings)
    share = np.fromiter(counts.values(), float, len(counts)) / (counts.total() * np.bincount(owner))
    ids, where = np.unique(ids, return_inverse=True)
    return ids, np.bincount(where, weights=share[owner]).astype(np.float32)


def train(bags: list[tuple[np.ndarray, np.ndarray]], labels: np.ndarray, settings: Settings) -> tuple[np.ndarray, float]:
    """Stochastic gradient descent over documents; returns the score of each feature and the bias,
    both as the difference of the two classes' logits. Classes weigh alike."""
    random = np.random.default_rng(settings.seed)
    vectors = random.uniform(-1 / settings.dim, 1 / settings.dim, (settings.buckets, settings.dim)).astype(np.float32)
    layer, bias = np.zeros((settings.dim, 2), np.float32), np.zeros(2, np.float32)
    if not len(bags):
        return np.zeros(settings.buckets), 0.0
    share = np.maximum(0.25, np.array([(labels == c).mean() * 2 for c in (0, 1)]))
    epochs = max(settings.epochs, -(-settings.least_steps // len(bags)))
    steps, step = epochs * len(bags), 0
    for _ in range(epochs):
        for i in random.permutation(len(bags)):
            rate = settings.rate * (1 - step / steps)
            step += 1
            ids, weights = bags[i]
            hidden = weights @ vectors[ids] if len(ids) else np.zeros(settings.dim, np.float32)
            logits = hidden @ layer + bias
            p = np.exp(logits - logits.max())
            p /= p.sum()
            error = p.astype(np.float32)
            error[labels[i]] -= 1
            error *= np.float32(rate / share[labels[i]])
            back = layer @ error
            layer -= np.outer(hidden, error)
            bias -= error
            if len(ids):
                # averaging divides a feature's gradient by the number of features; scale it back
                vectors[ids] -= np.outer(np.minimum(weights * np.float32(len(ids)), 2.0), back)
    contrast = layer[:, 1] - layer[:, 0]
    return (vectors @ contrast).astype(np.float64), float(bias[1] - bias[0])


@dataclasses.dataclass
class Model:
    scores: np.ndarray
    bias: float
    settings: Settings

    def text_scores(self, texts: list[str | None], known: dict[bytes, float]) -> list[float]:
        """Probability of label 1 of each text. ``known``: remembered scores of words."""
        split = [words_of(t) for t in texts]
        if len(known) > _REMEMBERED:
            known.clear()
        fresh = list(set().union(*split).difference(known))
        if fresh:
            ids, owner = features(fresh, self.settings)
            known.update(zip(fresh, (np.bincount(owner, weights=self.scores[ids]) / np.bincount(owner)).tolist(), strict=True))
        get = known.__getitem__
        means = np.array([sum(map(get, words)) / len(words) if words else 0.0 for words in split])
        return (1 / (1 + np.exp(-np.clip(means + self.bias, -50, 50)))).tolist()

    def batch_scores(self, texts: pa.Array, known: dict[bytes, float], step: int = 128) -> list[float]:
        out: list[float] = []
        for at in range(0, len(texts), step):
            out += self.text_scores([texts[i].as_py() for i in range(at, min(at + step, len(texts)))], known)
        return out


def fit(docs: DataFrame, labels: DataFrame, settings: Settings = Settings()) -> Model:
    """Learn ``labels(doc_id, quality)`` from the texts of ``docs(doc_id, text)``.

    Rows with null labels or doc_ids, or labels other than 0 and 1, teach nothing; of rows that share a doc_id
    one teaches, that with the smallest hash of its text, so that the sample stays within its bound however often
    an id comes. Without usable rows every document scores 0.5.
    """
    fold = F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(settings.folds))
    usable = labels.where(F.col("quality").isin(0, 1) & (fold != settings.held_out)).select("doc_id", F.col("quality").cast("int").alias("quality"))
    rank = F.xxhash64(F.lit(settings.seed), "doc_id")
    chosen = usable.distinct().orderBy(rank, "doc_id", "quality").limit(settings.sample)
    copies = Window.partitionBy("doc_id", "quality").orderBy(F.xxhash64("text"), F.col("text").asc_nulls_first())
    sample = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").withColumn("copy", F.row_number().over(copies)).where("copy = 1")

    def learned(batches):
        rows = []
        for batch in batches:
            texts = batch.column("text")
            for i, (doc, quality) in enumerate(zip(batch.column("doc_id").to_pylist(), batch.column("quality").to_pylist(), strict=True)):
                ids, weights = bag(texts[i].as_py(), settings)
                ids = ids.astype("<i4")
                rows.append((doc, zlib.crc32(ids.tobytes()), ids, weights, quality))
        rows.sort(key=operator.itemgetter(0, 1))
        scores, bias = train([r[2:4] for r in rows], np.array([r[4] for r in rows], int), settings)
        yield pa.RecordBatch.from_pydict({"scores": [scores.astype("<f8").tobytes()], "bias": [bias]}, schema=pa.schema([("scores", pa.binary()), ("bias", pa.float64())]))

    # one task reads the sample and trains; the driver gets one number per feature
    taught = sample.select(F.col("doc_id").cast("long").alias("doc_id"), "quality", "text").repartition(1).mapInArrow(learned, "scores binary, bias double").collect()
    if not taught:
        return Model(*train([], np.zeros(0, int), settings), settings)
    return Model(np.frombuffer(taught[0]["scores"], "<f8"), taught[0]["bias"], settings)


def scored(docs: DataFrame, model: Model) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every row of ``docs(doc_id, text)``: score is the
    probability of label 1. Null and wordless texts score by the bias alone; a null doc_id is not
    held out; repeated rows score alike; an empty table gives no rows."""
    held = F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(model.settings.folds)) == model.settings.held_out, F.lit(False))
    shared = docs.sparkSession.sparkContext.broadcast(model)
    types = pa.schema([("doc_id", pa.int64()), ("held_out", pa.bool_()), ("score", pa.float64()), ("predicted", pa.int32())])

    def run(batches):
        own, known = shared.value, {}
        for batch in batches:
            scores = own.batch_scores(batch.column("text"), known)
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), batch.column("held_out"), pa.array(scores, pa.float64()), pa.array([int(s >= 0.5) for s in scores], pa.int32())], schema=types
            )

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), held.alias("held_out"), "text").mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")


def kept(docs: DataFrame, labels: DataFrame, least: float = 0.5, settings: Settings = Settings()) -> DataFrame:
    """The rows of ``docs`` that score at least ``least``, with all their columns."""
    shared = docs.sparkSession.sparkContext.broadcast(fit(docs, labels, settings))

    def run(batches):
        own, known = shared.value, {}
        for batch in batches:
            good = [score >= least for score in own.batch_scores(batch.column("text"), known)]
            yield batch.filter(pa.array(good, pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
