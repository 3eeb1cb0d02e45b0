"""Quality classifier: random-indexing word vectors pooled per document, a two-layer numpy
network, and temperature-calibrated probabilities.

Every word, and every word's shape (case, digits, marks at its end, length class), has a
sparse ternary index vector derived from its hash.  A word's vector is the sum of the index
vectors of its neighbours in the sample, plus its own.  A document is the mean vector of
its known words beside the mean vector of its shapes and four rates (unknown words,
repeated words, words equal to the one before, length).  The network is trained on a bounded sample of labelled rows; a
fifth of that sample is held back to fit the temperature.

Bounds (parameters): at most ``sample_rows`` labelled rows (the first by a hash of doc_id)
and ``vocabulary`` words enter the fit.  Every document is scored, over its whole text.

Edge cases: null and empty texts are scored from all-zero features; a labelled row without
document or label is left out; with several labels for a document the largest counts;
repeated rows give repeated rows, and of rows that share an id the first by text is learnt from; with fewer than ten labelled rows, or one label only, the
score is the share of label 1 (0.5 if there are none); extra columns are ignored by the
query and kept by :func:`keep_good`.  An empty table gives an empty table.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import as_bytes, drop_suffix, read_documents, ship

DIM, NONZERO, HIDDEN, REACH = 48, 6, 24, 2
THRESHOLD = 0.7
SHAPES = 64
SCHEMA = "doc_id long, held_out boolean, score double, predicted int"
_CACHE_LIMIT = 400_000
_END_MARKS = frozenset(b"!#$%&*<>{}=|~^@")


def held_out(doc_id: Column) -> Column:
    """Rows whose labels are never learned from."""
    return F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(4)) == 2


def index_vector(token: bytes, seed: int = 0) -> np.ndarray:
    """NONZERO places of +1 or -1, from the token's hash."""
    out = np.zeros(DIM, np.float32)
    for i in range(NONZERO):
        h = xxhash.xxh3_64_intdigest(token, seed * 1000 + i)
        out[h % DIM] += 1.0 if h >> 32 & 1 else -1.0
    return out


def shape(word: bytes) -> int:
    """Case (4) x marks or digits (4) x length class (4)."""
    letters = word.rstrip(b".,;:!?#$%&*<>{}=|~^@\"'()")
    case = 0 if word.islower() else 1 if len(letters) > 1 and letters.isupper() else 2 if word[:1].isupper() else 3
    marks = 3 if any(48 <= c <= 57 for c in word) else 2 if word[-1] in _END_MARKS and word[-2:-1] and word[-2] in _END_MARKS else 1 if word[-1] in _END_MARKS else 0
    n = len(word)
    return case * 16 + marks * 4 + (0 if n < 4 else 1 if n < 9 else 2 if n < 16 else 3)


@dataclass
class Model:
    words: dict[bytes, int]
    vectors: np.ndarray
    shapes: np.ndarray
    mean: np.ndarray
    scale: np.ndarray
    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: float
    temperature: float
    constant: float | None = None

    def __post_init__(self):
        self.seen: dict[bytes, int] = {}

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k != "seen"}

    def __setstate__(self, state):
        self.__dict__.update(state, seen={})

    def codes(self, found: list[bytes]) -> np.ndarray:
        seen = self.seen
        try:
            return np.fromiter(map(seen.__getitem__, found), np.int64, len(found))
        except KeyError:
            if len(seen) > _CACHE_LIMIT:
                seen.clear()
            unknown, place = len(self.words), self.words.get
            for w in set(found):
                if w not in seen:
                    seen[w] = place(w, unknown) * SHAPES + shape(w)
            return np.fromiter(map(seen.__getitem__, found), np.int64, len(found))

    def features(self, texts: list[bytes]) -> np.ndarray:
        out = np.zeros((len(texts), 2 * DIM + 4), np.float64)
        for row, text in enumerate(texts):
            found = text.split()
            if not found:
                continue
            code = self.codes(found)
            word, n = code // SHAPES, len(found)
            known = word < len(self.words)
            # A count for each distinct word makes the pooled mean one small product.
            distinct, times = np.unique(word, return_counts=True)
            inside = distinct < len(self.words)
            if inside.any():
                out[row, :DIM] = times[inside] @ self.vectors[distinct[inside]] / max(1, known.sum())
            out[row, DIM : 2 * DIM] = np.bincount(code % SHAPES, minlength=SHAPES) @ self.shapes / n
            out[row, 2 * DIM :] = 1 - known.mean(), 1 - len(set(found)) / n, (code[1:] == code[:-1]).sum() / n, min(np.log1p(n), 8.0)
        return out

    def logits(self, features: np.ndarray) -> np.ndarray:
        x = np.clip((features - self.mean) / self.scale, -6, 6)
        return np.tanh(x @ self.w1 + self.b1) @ self.w2 + self.b2

    def score(self, texts: list[bytes]) -> np.ndarray:
        if self.constant is not None:
            return np.full(len(texts), self.constant)
        return 1 / (1 + np.exp(-np.clip(self.logits(self.features(texts)) / self.temperature, -40, 40)))


def word_vectors(texts: list[bytes], vocabulary: int) -> tuple[dict[bytes, int], np.ndarray]:
    """The commonest words of the sample (ties by bytes) and their random-indexing vectors, of unit length."""
    counts: Counter[bytes] = Counter()
    for t in texts:
        counts.update(t.split())
    chosen = sorted(counts, key=lambda w: (-counts[w], w))[:vocabulary]
    place = {w: i for i, w in enumerate(chosen)}
    own = np.stack([index_vector(w) for w in chosen]) if chosen else np.zeros((0, DIM), np.float32)
    total = own * np.sqrt(np.array([counts[w] for w in chosen], np.float32))[:, None] if chosen else own
    for t in texts:
        at = np.array([i for w in t.split() if (i := place.get(w)) is not None], np.int64)
        for step in range(1, min(REACH, len(at) - 1) + 1):
            np.add.at(total, at[step:], own[at[:-step]])
            np.add.at(total, at[:-step], own[at[step:]])
    return place, total / np.maximum(np.linalg.norm(total, axis=1, keepdims=True), 1e-9)


def fit(texts: list[bytes], labels: list[int], vocabulary: int = 20_000, epochs: int = 60, seed: int = 5) -> Model:
    """Fit on whole texts and 0/1 labels, in numpy."""
    place, vectors = word_vectors(texts, vocabulary)
    shapes = np.stack([index_vector(b"shape-%d" % i, 1) for i in range(SHAPES)])
    model = Model(place, vectors, shapes, np.zeros(1), np.ones(1), np.zeros((1, 1)), np.zeros(1), np.zeros(1), 0.0, 1.0)
    y = np.array(labels, np.float64)
    if len(y) < 10 or y.min() == y.max():
        model.constant = float(y.mean()) if len(y) else 0.5
        return model
    rng = np.random.RandomState(seed)
    x = model.features(texts)
    model.mean, model.scale = x.mean(0), x.std(0) + 1e-6
    x = np.clip((x - model.mean) / model.scale, -6, 6)
    order = rng.permutation(len(y))
    held, train = order[: len(y) // 5], order[len(y) // 5 :]
    p = {"w1": rng.randn(x.shape[1], HIDDEN) / np.sqrt(x.shape[1]), "b1": np.zeros(HIDDEN), "w2": rng.randn(HIDDEN) / np.sqrt(HIDDEN), "b2": np.zeros(1)}
    m, v, step = ({k: np.zeros_like(a) for k, a in p.items()} for _ in range(2)), None, 0
    first, second = m
    weight = np.where(y == 1, 0.5 / max(y[train].mean(), 1e-3), 0.5 / max(1 - y[train].mean(), 1e-3)) ** 0.5
    for _ in range(epochs):
        rng.shuffle(train)
        for at in range(0, len(train), 64):
            rows = train[at : at + 64]
            h = np.tanh(x[rows] @ p["w1"] + p["b1"])
            d = (1 / (1 + np.exp(-(h @ p["w2"] + p["b2"]))) - y[rows]) * weight[rows] / len(rows)
            dh = np.outer(d, p["w2"]) * (1 - h * h)
            grad = {"w1": x[rows].T @ dh + 1e-3 * p["w1"], "b1": dh.sum(0), "w2": h.T @ d + 1e-3 * p["w2"], "b2": d.sum(keepdims=True)}
            step += 1
            for k, g in grad.items():
                first[k] = 0.9 * first[k] + 0.1 * g
                second[k] = 0.999 * second[k] + 0.001 * g * g
                p[k] = p[k] - 0.004 * (first[k] / (1 - 0.9**step)) / (np.sqrt(second[k] / (1 - 0.999**step)) + 1e-8)
    model.w1, model.b1, model.w2, model.b2 = p["w1"], p["b1"], p["w2"], float(p["b2"][0])
    z = np.tanh(x[held] @ model.w1 + model.b1) @ model.w2 + model.b2
    grid = np.exp(np.linspace(np.log(0.3), np.log(8), 60))
    model.temperature = float(min(grid, key=lambda t: np.logaddexp(0, np.where(y[held] == 1, -z, z) / t).mean()))
    return model


def labelled_sample(docs: DataFrame, labels: DataFrame, rows: int, label: str = "quality") -> tuple[list[bytes], list[int]]:
    """At most ``rows`` labelled training texts: the first labels by a hash of the id, joined to their documents."""
    known = labels.groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max(label).cast("int").alias("label"))
    known = known.where(F.col("doc_id").isNotNull() & F.col("label").isNotNull() & ~held_out(F.col("doc_id")))
    # Bounded: ``rows`` pairs of numbers at most, whatever the size of the tables.
    chosen = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)
    texts = drop_suffix(docs, ["doc_id", "text"]).select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    # One text for each id, however often it occurs.
    found = texts.join(F.broadcast(chosen), "doc_id").groupBy("doc_id").agg(F.min("text").alias("text"), F.first("label").alias("label")).collect()
    found.sort(key=lambda r: (r["doc_id"], r["text"]))
    return [r["text"].encode("utf-8", "surrogatepass") for r in found], [r["label"] for r in found]


def train(docs: DataFrame, labels: DataFrame, sample_rows: int = 3000, label: str = "quality") -> Model:
    return fit(*labelled_sample(docs, labels, sample_rows, label))


def _score_batches(shared, at: int, ids: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            s = shared.value.score(as_bytes(batch.column(at)))
            yield pa.RecordBatch.from_arrays([batch.column(ids).cast(pa.int64()), pa.array(s, pa.float64())], ["doc_id", "score"])

    return run


def score_documents(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, held_out, score, predicted of every whole text."""
    spark = docs.sparkSession
    ship(spark)
    shared = spark.sparkContext.broadcast(model)  # at most ``vocabulary`` vectors: about 6 MB
    scored = drop_suffix(docs, ["doc_id", "text"]).mapInArrow(_score_batches(shared, 1, 0), "doc_id long, score double")
    return scored.select("doc_id", F.coalesce(held_out(F.col("doc_id")), F.lit(False)).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))


def keep_good(docs: DataFrame, model: Model, threshold: float = THRESHOLD) -> DataFrame:
    """The rows, unchanged, whose score reaches the threshold."""
    spark = docs.sparkSession
    ship(spark)
    shared, at = spark.sparkContext.broadcast(model), docs.columns.index("text")

    def run(batches):
        for batch in batches:
            yield batch.filter(pa.array(shared.value.score(as_bytes(batch.column(at))) >= threshold))

    return docs.mapInArrow(run, docs.schema)


def op8_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_documents(spark, sf_dir)
    return score_documents(docs, train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))
