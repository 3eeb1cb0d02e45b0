"""Cross-entropy difference: each document scored by per-token losses of two n-gram models.

The target model is counted over one table of texts, the background model over all
documents; both are bigram models over one shared vocabulary, with the same smoothing:
p(w | h) = (c(h, w) + k * u(w)) / (c(h) + k) and u(w) = (c(w) + 1) / (n + V), in nats.
A document's score is its mean loss under the target model less that under the
background model; the lower, the more it is like the target.

The vocabulary is every word of both tables and one unknown word (V counts it), and every
bigram has its own count.  Steps:

1. Texts become chunks of word numbers; a chunk's distinct words and bigrams, counted, are dealt to
   buckets by hash.  So a key comes at most once from a chunk, however frequent it is.
2. A bucket adds up its keys over all chunks and answers each chunk with the totals of the keys it sent.
3. A chunk's documents are scored by the answers to it.

What is counted grows with the corpus; a task holds one chunk or one bucket.

Edge cases: null and empty texts have no tokens and a null score; words are matched as they are;
repeated rows count as often as they occur; extra columns are ignored; with an empty target
table its model is uniform.  An empty table gives an empty table.  Words and bigrams are compared as 64-bit hashes.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import as_bytes, buckets_for, mix64, read_documents, scratch, ship, text_bytes

SMOOTHING = 10.0
CHUNK_TOKENS, CHUNK_ROWS = 1 << 20, 1 << 17
BUCKET_BYTES = 8 << 20
_PAIR = np.uint64(0x9E3779B97F4A7C15)
SCHEMA = "doc_id long, n_tokens long, target_loss double, background_loss double, difference double"
_CHUNKS = "chunk long, role int, answered boolean, ids array<long>, lengths array<long>, words binary, tokens binary"
#: What no answer is wanted to has no chunk.
_SENT = "chunk long, bucket int, role int, keys binary, counts binary"
_ANSWERS = "chunk long, bucket int, totals binary, n_words long, n_background long, n_target long"
BACKGROUND, TARGET, SCORED = range(3)


class Numbers(dict):
    """word bytes -> its number in the chunk, by first occurrence; the start mark is 0."""

    def __init__(self):
        self[b""] = 0

    def __missing__(self, word: bytes) -> int:
        self[word] = at = len(self)
        return at


def _pack(values: np.ndarray, kind: str = "<u8") -> bytes:
    """Byte planes, of which the high ones are mostly zeros, compressed behind their length."""
    planes = np.ascontiguousarray(values.astype(kind).reshape(-1, 1).view(np.uint8).T).tobytes()
    return len(planes).to_bytes(8, "little") + pa.compress(planes, "zstd", asbytes=True)


def _unpack(raw: bytes, kind: str = "<u8") -> np.ndarray:
    planes = pa.decompress(raw[8:], int.from_bytes(raw[:8], "little"), "zstd", asbytes=True)
    return np.ascontiguousarray(np.frombuffer(planes, np.uint8).reshape(np.dtype(kind).itemsize, -1).T).view(kind)[:, 0]


def bigrams(tokens: np.ndarray, lengths: np.ndarray, keys: np.ndarray):
    """Distinct bigrams of a chunk: numbers of both words, how often, hash, and which one each token ends."""
    before = np.concatenate([[0], tokens[:-1]]) if len(tokens) else tokens
    before[(np.cumsum(lengths) - lengths)[lengths > 0]] = 0
    found, at, times = np.unique(before * len(keys) + tokens, return_inverse=True, return_counts=True)
    first, second = np.divmod(found, len(keys))
    return first, second, times, mix64(keys[first] * _PAIR + keys[second]), at, before


def _dealt(keys: np.ndarray, counts: list[np.ndarray], buckets: int) -> Iterator[tuple[int, bytes, bytes]]:
    """(bucket, keys, counts), by ascending key."""
    order = np.argsort(keys, kind="stable")
    keys, counts = keys[order], [c[order] for c in counts]
    bounds = np.searchsorted((keys >> np.uint64(32)) * np.uint64(buckets) >> np.uint64(32), np.arange(buckets + 1, dtype=np.uint64))
    for b in np.flatnonzero(np.diff(bounds)).tolist():
        part = slice(bounds[b], bounds[b + 1])
        yield b, _pack(np.diff(keys[part], prepend=np.uint64(0))), _pack(np.concatenate([c[part] for c in counts]))


def _read(role: int, answered: bool):
    """Texts to chunks of word numbers."""
    names = [f.split()[0] for f in _CHUNKS.split(", ")]

    def packed(chunk: int, ids: list, tokens: list[np.ndarray], numbers: Numbers) -> pa.RecordBatch:
        keys = np.fromiter(map(xxhash.xxh3_64_intdigest, numbers), np.uint64, len(numbers))
        row = [pa.array([chunk]), pa.array([role], pa.int32()), pa.array([answered]), *[pa.array([x], pa.list_(pa.int64())) for x in (ids, [len(t) for t in tokens])]]
        return pa.RecordBatch.from_arrays([*row, *[pa.array([x], pa.binary()) for x in (_pack(keys), _pack(np.concatenate(tokens), "<u4"))]], names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        chunk = TaskContext.get().partitionId() << 32
        ids, tokens, size, numbers = [], [], 0, Numbers()
        for batch in batches:
            for doc_id, text in zip(batch.column(0).to_pylist(), as_bytes(batch.column(1)), strict=True):
                words = text.split()
                ids.append(doc_id)
                tokens.append(np.fromiter(map(numbers.__getitem__, words), np.uint32, len(words)))
                size += len(words)
                if size >= CHUNK_TOKENS or len(ids) >= CHUNK_ROWS:
                    yield packed(chunk, ids, tokens, numbers)
                    chunk, ids, tokens, size, numbers = chunk + 1, [], [], 0, Numbers()
        if ids:
            yield packed(chunk, ids, tokens, numbers)

    return run


def _send(buckets: int):
    """Chunks to what they send to each bucket."""
    names = [f.split()[0] for f in _SENT.split(", ")]
    types = [pa.int64(), pa.int32(), pa.int32(), pa.binary(), pa.binary()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for chunk, role, answered, lengths, words, tokens in zip(*batch.columns, strict=True):
                keys, flat = _unpack(words.as_py()), _unpack(tokens.as_py(), "<u4").astype(np.int64)
                _, _, times, hashes, _, before = bigrams(flat, lengths.values.to_numpy(), keys)
                of_words = [np.bincount(x, minlength=len(keys)) for x in (flat, before)]
                rows = []
                for start, k, counts in ((0, keys, of_words), (buckets, hashes, [times])) if len(flat) else ():
                    rows += [(chunk.as_py() if answered.as_py() else None, start + b, role.as_py(), sent, c) for b, sent, c in _dealt(k, counts, buckets)]
                yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate(types)], names)

    return run


def _add_up(buckets: int):
    """A bucket's totals in both models, for each chunk in the order it sent; and a row of what they sum to."""

    def run(key: tuple, sent: pa.Table) -> pa.Table:
        bucket = key[0].as_py()
        columns = 2 if bucket < buckets else 1
        keys = [np.cumsum(_unpack(k)) for k in as_bytes(sent.column("keys"))]
        _, at = np.unique(np.concatenate(keys), return_inverse=True)
        ends = np.cumsum([len(k) for k in keys])
        total = np.zeros((2, columns, at.max() + 1), np.int64)
        places = np.split(at, ends[:-1])
        for role, where, raw in zip(sent.column("role").to_pylist(), places, as_bytes(sent.column("counts")), strict=True):
            if role != SCORED:
                # Two words of one hash may stand in one row.
                for row, c in zip(total[role], _unpack(raw).astype(np.int64).reshape(columns, -1), strict=True):
                    np.add.at(row, where, c)
        out = [(c, bucket, _pack(total[:, :, where].ravel()), 0, 0, 0) for c, where in zip(sent.column("chunk").to_pylist(), places, strict=True) if c is not None]
        if columns == 2:
            out.append((None, bucket, None, int((total[:, 0].sum(axis=0) > 0).sum()), int(total[BACKGROUND, 0].sum()), int(total[TARGET, 0].sum())))
        types = [pa.int64(), pa.int32(), pa.binary(), *[pa.int64()] * 3]
        return pa.Table.from_arrays([pa.array([r[i] for r in out], t) for i, t in enumerate(types)], [f.split()[0] for f in _ANSWERS.split(", ")])

    return run


def _in_order(raws: list[bytes], columns: int, keys: np.ndarray) -> np.ndarray:
    """Answers, by bucket, as (model, column, key)."""
    out = np.zeros((2, columns, len(keys)))
    if raws:
        out[:, :, np.argsort(keys, kind="stable")] = np.concatenate([_unpack(r).reshape(2, columns, -1) for r in raws], axis=2)
    return out


def _judge(buckets: int, size: int, totals: tuple[int, int], smoothing: float):
    def run(key: tuple, chunk: pa.Table, answers: pa.Table) -> pa.Table:
        row = {name: chunk.column(name)[0] for name in ("ids", "lengths", "words", "tokens")}
        lengths, keys = np.array(row["lengths"].as_py(), np.int64), _unpack(row["words"].as_py())
        tokens = _unpack(row["tokens"].as_py(), "<u4").astype(np.int64)
        first, second, _, hashes, at, _ = bigrams(tokens, lengths, keys)
        found = sorted(zip(answers.column("bucket").to_pylist(), as_bytes(answers.column("totals")), strict=True))
        words = _in_order([r for b, r in found if b < buckets], 2, keys)
        pairs = _in_order([r for b, r in found if b >= buckets], 1, hashes)
        document = np.repeat(np.arange(len(lengths)), lengths)
        losses = {}
        for model in (TARGET, BACKGROUND):
            unigram = (words[model, 0] + 1) / (totals[model] + size)
            p = (pairs[model, 0] + smoothing * unigram[second]) / (words[model, 1][first] + smoothing)
            summed = np.bincount(document, weights=-np.log(p)[at], minlength=len(lengths))
            losses[model] = [round(s / n, 9) if n else None for s, n in zip(summed.tolist(), lengths.tolist(), strict=True)]
        difference = [None if t is None else round(t - b, 9) for t, b in zip(losses[TARGET], losses[BACKGROUND], strict=True)]
        return pa.table({"doc_id": row["ids"].values, "n_tokens": lengths, "target_loss": pa.array(losses[TARGET], pa.float64()), "background_loss": pa.array(losses[BACKGROUND], pa.float64()), "difference": pa.array(difference, pa.float64())})

    return run


@dataclass
class Models:
    """What both models are counted over; :func:`score` counts."""

    documents: DataFrame
    target: DataFrame
    smoothing: float


def build(documents: DataFrame, target: DataFrame, slots: int | None = None, smoothing: float = SMOOTHING) -> Models:
    """``slots`` has no effect: every bigram has its own count."""
    return Models(documents, target, smoothing)


def score(docs: DataFrame, models: Models) -> DataFrame:
    """doc_id, n_tokens, both losses and their difference, of every row."""
    spark = docs.sparkSession
    ship(spark)
    same = docs is models.documents
    inputs = [(docs, BACKGROUND if same else SCORED, True), (models.target, TARGET, False)] + [(models.documents, BACKGROUND, False)] * (not same)
    buckets = buckets_for(sum(text_bytes(frame) for frame, _, _ in inputs), BUCKET_BYTES, 8)
    chunks = None
    for frame, role, answered in inputs:
        rows = frame.select((F.col("doc_id") if answered else F.lit(None)).cast("long").alias("doc_id"), "text").mapInArrow(_read(role, answered), _CHUNKS)
        chunks = rows if chunks is None else chunks.unionByName(rows)
    chunks = scratch(spark, chunks, "chunks")
    sent = chunks.select("chunk", "role", "answered", "lengths", "words", "tokens").mapInArrow(_send(buckets), _SENT)
    answers = scratch(spark, sent.groupBy("bucket").applyInArrow(_add_up(buckets), _ANSWERS), "answers")
    size, *totals = (x or 0 for x in answers.where("chunk is null").agg(F.sum("n_words"), F.sum("n_background"), F.sum("n_target")).first())
    wanted = chunks.where("answered").select("chunk", "ids", "lengths", "words", "tokens")
    found = answers.where("chunk is not null").select("chunk", "bucket", "totals")
    return wanted.groupBy("chunk").cogroup(found.groupBy("chunk")).applyInArrow(_judge(buckets, size + 1, tuple(totals), models.smoothing), SCHEMA)


def op3_cross_entropy(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_documents(spark, sf_dir)
    return score(docs, build(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet")))
