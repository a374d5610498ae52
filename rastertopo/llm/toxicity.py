"""Toxicity by a bag of subwords: character n-gram vectors averaged into a linear softmax, trained jointly in numpy.

A word is the mean of the vectors of its character n-grams (word boundaries marked) and of the word itself, a text the
mean of its words; a softmax over two classes tells the score. N-grams are hashed into a fixed number of buckets, so
an unseen misspelling shares the vectors of the n-grams it kept. Buckets that no training text touched stay zero.

The fit takes at most ``SAMPLE_ROWS`` labelled rows, the first in the order of a hash of the id, whole texts of any
length. Their bags are made by tasks: one pass counts in how many toxic and other texts each bucket occurs, the next
gives the bags of the buckets that tell something. So the driver holds neither texts nor the vocabulary, but at most
``SAMPLE_ROWS`` short bags. Scoring covers all rows and whole texts; as the model is linear in the bag, each bucket
weighs one number then, and what is sent out is of fixed size.

Cases: null and empty texts score by the bias alone; a row without a label (or with a null one) is not learnt from;
without any labelled row, or with one class only, the score is the share of toxic labels, or 0 without labels;
repeated rows score alike; an empty table gives an empty result; other columns, whatever their names, are ignored.
"""

from __future__ import annotations

import re
import zlib

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StructField, StructType

from .common import slices, written

SAMPLE_ROWS = 4000
#: Tasks that make the bags of the sample.
SAMPLE_TASKS = 8
BUCKETS, DIM, LEAST_GRAM, MOST_GRAM = 1 << 17, 4, 3, 5
#: Buckets whose share of toxic texts differs from the others' by less than so many standard errors stay zero: what
#: they could tell is only which text it is.
LEAST_Z = 4.0
#: Up to so many telling buckets the bags are one dense table in the fit.
DENSE_BUCKETS = 4096
EPOCHS, RATE, SHRINK = 300, 0.1, 1e-7
WORD = re.compile(r"\w+")
CACHED_WORDS = 400_000


def words_of(text: str | None) -> list[str]:
    return WORD.findall(text.lower()) if text else []


def grams_of(word: str) -> list[int]:
    """The buckets of a word's subwords: its n-grams between boundary marks, and the word as a whole."""
    marked = f"<{word}>"
    n = len(marked)
    found = [zlib.crc32(marked[i : i + k].encode()) % BUCKETS for k in range(LEAST_GRAM, MOST_GRAM + 1) for i in range(n - k + 1)]
    return [*found, zlib.crc32(marked.encode() + b"#") % BUCKETS]


class Subwords(dict):
    """The buckets of words seen, up to CACHED_WORDS of them."""

    def __missing__(self, word: str) -> np.ndarray:
        if len(self) >= CACHED_WORDS:
            self.clear()
        found = self[word] = np.array(grams_of(word), np.int32)
        return found


def bag(text: str | None, subwords: Subwords) -> tuple[np.ndarray, np.ndarray]:
    """The buckets of a text and their shares: a word shares its part of the text evenly among its subwords."""
    counts: dict[str, int] = {}
    for w in words_of(text):
        counts[w] = counts.get(w, 0) + 1
    if not counts:
        return np.zeros(0, np.int32), np.zeros(0, np.float32)
    n, ids = sum(counts.values()), [subwords[w] for w in counts]
    sizes = np.fromiter(map(len, ids), np.int64, len(ids))
    share = np.repeat(np.fromiter(counts.values(), np.float64, len(ids)) / n / sizes, sizes)
    found, where = np.unique(np.concatenate(ids), return_inverse=True)
    return found.astype(np.int32), np.bincount(where, share).astype(np.float32)


def count(texts, labels) -> np.ndarray:
    """In how many of the texts each bucket occurs: other texts first, then toxic ones. The last column counts the texts."""
    found, subwords = np.zeros((2, BUCKETS + 1), np.int64), Subwords()
    for text, label in zip(texts, labels):
        ids = [subwords[w] for w in set(words_of(text))]
        if ids:
            found[label, np.unique(np.concatenate(ids))] += 1
        found[label, BUCKETS] += 1
    return found


def telling(counts: np.ndarray) -> np.ndarray:
    """The buckets that occur in significantly more, or fewer, toxic than other texts (two-proportion z test), in order."""
    (other, toxic), (n0, n1) = counts[:, :BUCKETS], np.maximum(counts[:, BUCKETS], 1)
    pooled = (toxic + other) / (n1 + n0)
    error = np.sqrt(pooled * (1 - pooled) * (1 / n1 + 1 / n0))
    return np.flatnonzero(np.abs(toxic / n1 - other / n0) >= LEAST_Z * np.maximum(error, 1e-12)).astype(np.int32)


def told(text: str | None, used: np.ndarray, subwords: Subwords) -> tuple[np.ndarray, np.ndarray]:
    """The bag of a text, of the used buckets only, as places among them."""
    buckets, shares = bag(text, subwords)
    if not len(used):
        return buckets[:0], shares[:0]
    place = np.minimum(np.searchsorted(used, buckets), len(used) - 1)
    kept = used[place] == buckets
    return place[kept].astype(np.int32), shares[kept]


def fit(texts: list[str], labels: list[int], seed: int = 7) -> tuple[np.ndarray, float]:
    """The model of texts in memory."""
    used, subwords = telling(count(texts, labels)), Subwords()
    return fit_bags([told(t, used, subwords) for t in texts], labels, used, seed)


def fit_bags(bags: list[tuple[np.ndarray, np.ndarray]], labels: list[int], used: np.ndarray, seed: int = 7) -> tuple[np.ndarray, float]:
    """Trains vectors and softmax together by full-batch Adam. Returns the weight of each bucket and the bias."""
    weights, y = np.zeros(BUCKETS), np.array(labels, int)
    if len(y) == 0 or y.min() == y.max():
        share = float(y.mean()) if len(y) else 0.0
        return weights, float(np.log(max(share, 1e-9) / max(1 - share, 1e-9)))
    rows = np.repeat(np.arange(len(y), dtype=np.int32), [len(b) for b, _ in bags])
    buckets, shares = np.concatenate([b for b, _ in bags]), np.concatenate([s for _, s in bags]).astype(np.float32)
    if dense := len(used) <= DENSE_BUCKETS:
        table = np.zeros((len(y), len(used)))
        table[rows, buckets] = shares
    rng = np.random.default_rng(seed)
    vectors, out = np.zeros((len(used), DIM)), rng.normal(0, 0.3, (DIM, 2))
    bias = np.log([1 - y.mean(), y.mean()])
    target = np.eye(2)[y]
    state = [(p, np.zeros_like(p), np.zeros_like(p)) for p in (vectors, out, bias)]
    for step in range(1, EPOCHS + 1):
        docs = table @ vectors if dense else np.stack([np.bincount(rows, vectors[buckets, k] * shares, len(y)) for k in range(DIM)], 1)
        logits = docs @ out + bias
        p = np.exp(logits - logits.max(1, keepdims=True))
        p /= p.sum(1, keepdims=True)
        slope = (p - target) / len(y)
        back = slope @ out.T
        to_vectors = table.T @ back if dense else np.stack([np.bincount(buckets, back[rows, k] * shares, len(used)) for k in range(DIM)], 1)
        to_vectors = to_vectors + SHRINK * vectors
        for (value, first, second), grad in zip(state, (to_vectors, docs.T @ slope, slope.sum(0))):
            first += 0.1 * (grad - first)
            second += 0.01 * (grad * grad - second)
            value -= RATE * (first / (1 - 0.9**step)) / (np.sqrt(second / (1 - 0.99**step)) + 1e-10)
    weights[used] = vectors @ (out[:, 1] - out[:, 0])
    return weights, float(bias[1] - bias[0])


class Scorer(dict):
    """Scores texts; the dict holds the weights of words seen, up to CACHED_WORDS of them."""

    def __init__(self, weights: np.ndarray, bias: float):
        self.weights, self.bias = weights.tolist(), bias

    def __missing__(self, word: str) -> float:
        if len(self) >= CACHED_WORDS:
            self.clear()
        ids = grams_of(word)
        weights = self.weights
        found = self[word] = sum([weights[i] for i in ids]) / len(ids)
        return found

    def score(self, text: str | None) -> float:
        words = words_of(text)
        margin = self.bias + (sum(map(self.__getitem__, words)) / len(words) if words else 0.0)
        return float(1 / (1 + np.exp(-margin)))


def held_out(doc_id=None):
    """Whether a row is kept out of the fit: crc32 of the id as text, modulo 5, is 0."""
    return F.coalesce(F.crc32(F.col(doc_id or "doc_id").cast("string")) % 5 == 0, F.lit(False))


def sample(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The bounded training sample (doc_id, text, toxic); equal ids are taken once."""
    marks = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("toxic")).filter("toxic IS NOT NULL AND doc_id IS NOT NULL").filter(~held_out())
    marks = marks.join(docs.select(F.col("doc_id").cast("long").alias("doc_id")), "doc_id", "left_semi").groupBy("doc_id").agg((F.max("toxic") > 0).cast("int").alias("toxic"))
    chosen = marks.orderBy(F.xxhash64(F.lit("toxicity"), "doc_id"), "doc_id").limit(SAMPLE_ROWS)
    # At most SAMPLE_ROWS ids and labels: a fixed bound.
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(chosen), "doc_id").groupBy("doc_id", "toxic").agg(F.min("text").alias("text"))
    return written(rows.select("doc_id", "text", "toxic").repartition(SAMPLE_TASKS, "doc_id"), "toxicity-sample")


def train(docs: DataFrame, labels: DataFrame) -> tuple[np.ndarray, float]:
    rows = sample(docs, labels)

    def counting(batches):
        import pyarrow as pa

        found = np.zeros((2, BUCKETS + 1), np.int64)
        for batch in slices(batches):
            found += count(batch.column(1).to_pylist(), batch.column(2).to_pylist())
        yield pa.RecordBatch.from_arrays([pa.array([found.astype(np.int32).tobytes()], pa.binary())], ["counts"])

    # One array of fixed size from each file of the sample, SAMPLE_TASKS at most.
    parts = [np.frombuffer(r["counts"], np.int32).reshape(2, BUCKETS + 1) for r in rows.mapInArrow(counting, "counts binary").coalesce(SAMPLE_TASKS).collect()]
    used = telling(np.sum(parts, axis=0, dtype=np.int64)) if parts else np.zeros(0, np.int32)
    shipped = docs.sparkSession.sparkContext.broadcast(used)

    def bagging(batches):
        import pyarrow as pa

        subwords = Subwords()
        for batch in slices(batches):
            bags = [told(t, shipped.value, subwords) for t in batch.column(1).to_pylist()]
            columns = [pa.array([x[i].tobytes() for x in bags], pa.binary()) for i in (0, 1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), *columns], ["doc_id", "toxic", "buckets", "shares"])

    found = rows.mapInArrow(bagging, "doc_id long, toxic int, buckets binary, shares binary").orderBy("doc_id").collect()
    return fit_bags([(np.frombuffer(r["buckets"], np.int32), np.frombuffer(r["shares"], np.float32)) for r in found], [r["toxic"] for r in found], used)


def score(docs: DataFrame, model: tuple[np.ndarray, float], column: str = "score") -> DataFrame:
    """Adds ``column`` to the rows: the probability that the text is toxic."""
    weights, bias = model
    shipped = docs.sparkSession.sparkContext.broadcast((weights.astype(np.float32), bias))
    place = docs.columns.index("text")
    schema = StructType([*docs.schema.fields, StructField(column, DoubleType())])

    def task(batches):
        import pyarrow as pa

        scorer = Scorer(*shipped.value)
        for batch in slices(batches):
            found = pa.array([scorer.score(x) for x in batch.column(place).to_pylist()], pa.float64())
            yield pa.RecordBatch.from_arrays([*batch.columns, found], names=[*batch.schema.names, column])

    return docs.mapInArrow(task, schema)


def scores(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """One row for each document: doc_id, held_out, score, predicted."""
    found = score(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), train(docs, labels))
    return found.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
