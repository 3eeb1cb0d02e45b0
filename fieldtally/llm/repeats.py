"""Repeated-phrase automata: words covered by a 35-word window that starts anywhere else too are removed.

1. Seeds: of the 8-word phrases in a window the one with the smallest hash is its seed, so equal
   windows have equal seeds and only about one phrase in fifteen is a seed.  Seeds are
   counted over all documents.
2. Confirming: windows whose seed recurs are hashed whole (64 bits) and counted; those that occur
   at two places or more are the recurring passages.
3. Locating: documents are dealt to buckets of bounded size.  A bucket gets the recurring windows that
   occur in it, takes a block of 8 words out of every 28 of the passages they cover (every window
   holds one whole block), compiles the blocks into Aho-Corasick automata (shards of bounded size)
   and streams all of its documents through them.  Wherever a block is found, the windows around it
   are checked, and the words of the recurring ones are removed.

What meets in one task is bounded by a bucket or a hash partition, and a passage that many documents share
is one row for each bucket that has it.

Edge cases: null, empty and short texts have no window and lose nothing; a null text has no
words; overlapping occurrences and periodic texts count by start position; repeated rows are
occurrences of each other; columns other than ``doc_id`` and ``text`` are ignored.  An empty
table gives an empty table.
"""

from __future__ import annotations

import hashlib
import itertools
from collections.abc import Iterator

import ahocorasick
import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import buckets_for, drop_suffix, read_documents, ship, sliding, text_bytes, window_hashes

WINDOW, PHRASE = 35, 8
#: A block is so long, and begins so many words after the one before it.
BLOCK = 8
STRIDE = WINDOW - BLOCK + 1
_REACH = WINDOW - PHRASE + 1
BUCKET_BYTES = 8 << 20
#: Blocks of one automaton; their words fit its alphabet.
SHARD_BLOCKS = 30_000
#: A word is three characters of an automaton, each from its own 64, so that nodes have few children and matches start at words.
_BITS = 6
_SPACE = np.isin(np.arange(256), [0x20, *range(0x09, 0x0E)])
DIGEST_SCHEMA = "doc_id long, n_words long, n_removed long, kept_sha256 string"
TEXT_SCHEMA = "doc_id long, n_words long, n_removed long, kept binary"


def _hashes(words: pa.LargeBinaryArray) -> np.ndarray:
    _, where, data = words.buffers()
    at = np.frombuffer(where, np.int64)[words.offset : words.offset + len(words) + 1].tolist()
    text = data.to_pybytes() if data else b""
    return np.fromiter((xxhash.xxh3_64_intdigest(text[a:b]) for a, b in itertools.pairwise(at)), np.uint64, len(words))


class Words:
    """The words of a column of texts, one after another: ``flat``, where each text's begin and end (``bounds``), the
    number of each word's entry among the distinct ones (``ids``) and its 64-bit hash (``hashes``)."""

    def __init__(self, texts: pa.Array | pa.ChunkedArray):
        texts = texts.combine_chunks() if isinstance(texts, pa.ChunkedArray) else texts
        texts = pc.fill_null(texts.cast(pa.large_binary()), b"")
        _, where, data = texts.buffers()
        at = np.frombuffer(where, np.int64)[texts.offset : texts.offset + len(texts) + 1] if len(texts) else np.zeros(1, np.int64)
        data = np.frombuffer(data, np.uint8)[at[0] : at[-1]] if at[-1] > at[0] else np.empty(0, np.uint8)
        at = at - at[0]
        inside = ~_SPACE[data]
        first, last = inside.copy(), inside.copy()
        first[1:] &= ~inside[:-1]
        last[:-1] &= ~inside[1:]
        edges = at[(at > 0) & (at < len(data))]  # a text's end ends a word
        first[edges], last[edges - 1] = inside[edges], inside[edges - 1]
        starts = np.flatnonzero(first)
        offsets = np.concatenate([np.zeros(1, np.int64), np.cumsum(np.flatnonzero(last) - starts + 1)])
        self.flat = pa.Array.from_buffers(pa.large_binary(), len(starts), [None, pa.py_buffer(offsets), pa.py_buffer(data[inside])])
        self.bounds = np.searchsorted(starts, at)
        coded = self.flat.dictionary_encode()
        self.ids = coded.indices.to_numpy()
        self.distinct = len(coded.dictionary)
        self.hashes = _hashes(coded.dictionary)[self.ids]

    def whole(self) -> np.ndarray:
        """Which windows lie within one text."""
        n = max(len(self.ids) - WINDOW + 1, 0)
        return np.repeat(self.bounds[1:], np.diff(self.bounds))[:n] - np.arange(n) >= WINDOW


def seeds(h: np.ndarray, whole: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(phrase hashes, place) -> seed of each window, and the places whose phrase is the seed of a whole window."""
    grams = window_hashes(h, PHRASE)
    if len(grams) < _REACH:
        return grams[:0], np.empty(0, np.int64)
    least = sliding(grams, _REACH, np.minimum)
    # A place is a seed if it is the least of any window over it.
    pad = np.zeros(_REACH - 1, np.uint64)
    padded = np.concatenate([pad, np.where(whole, least, np.uint64(0)), pad])
    return least, np.flatnonzero(sliding(padded, _REACH, np.maximum) == grams)


def _slices(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
    """Parts of a batch of about BUCKET_BYTES of text."""
    total = np.cumsum(pc.fill_null(pc.binary_length(batch.column(1)), 0).to_numpy(zero_copy_only=False))
    cuts = [0, *(np.flatnonzero(np.diff(total // BUCKET_BYTES)) + 1).tolist(), batch.num_rows]
    return (batch.slice(a, b - a) for a, b in zip(cuts, cuts[1:]) if b > a)


def _seed_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for part in (p for batch in batches for p in _slices(batch)):
        words = Words(part.column(1))
        _, places = seeds(words.hashes, words.whole())
        keys = window_hashes(words.hashes, PHRASE)[places]
        where = part.column(2).to_numpy(zero_copy_only=False)[np.searchsorted(words.bounds, places, "right") - 1].astype(np.int32)
        order = np.lexsort((keys, where))
        keys, where = keys[order], where[order]
        fresh = np.flatnonzero(np.append(len(keys) > 0, (keys[1:] != keys[:-1]) | (where[1:] != where[:-1]))[: len(keys)])
        times = np.diff(np.append(fresh, len(keys)))
        yield pa.RecordBatch.from_arrays([pa.array(keys[fresh].view(np.int64)), pa.array(where[fresh]), pa.array(times.astype(np.int32))], ["key", "bucket", "times"])


def _recurring(counted: DataFrame) -> DataFrame:
    """(key, bucket, times) -> (key, bucket) of the keys that occur twice or more."""
    total = F.sum("times").over(Window.partitionBy("key"))
    return counted.withColumn("total", total).where("total > 1").select("key", "bucket").distinct()


def _window_rows(key: tuple, docs: pa.Table, found: pa.Table) -> pa.Table:
    """The hashes of a bucket's windows whose seed recurs, counted."""
    wanted = np.unique(found.column("key").to_numpy().view(np.uint64))
    keys, times = np.empty(0, np.uint64), np.empty(0, np.int64)
    if len(wanted):
        words = Words(docs.column("text"))
        whole = words.whole()
        least, _ = seeds(words.hashes, whole)
        if len(least):
            # Windows beside each other mostly share their seed: it is looked up once.
            turns = np.flatnonzero(np.append(True, least[1:] != least[:-1]))
            seeded = np.repeat(member(least[turns], wanted), np.diff(np.append(turns, len(least))))
            keys, times = np.unique(window_hashes(words.hashes, WINDOW)[seeded & whole], return_counts=True)
    return pa.table({"key": keys.view(np.int64), "bucket": np.full(len(keys), key[0].as_py(), np.int32), "times": times.astype(np.int32)})


def member(values: np.ndarray, wanted: np.ndarray) -> np.ndarray:
    """Which values are in a sorted array.  Most that aren't are told by their top bits."""
    out = np.zeros(len(values), bool)
    if not len(wanted):
        return out
    shift = np.uint64(64 - min(max(len(wanted).bit_length() + 4, 10), 26))
    marked = np.zeros(1 << 64 - int(shift), bool)
    marked[wanted >> shift] = True
    likely = np.flatnonzero(marked[values >> shift])
    at = np.searchsorted(wanted, values[likely])
    at[at == len(wanted)] = 0
    out[likely] = wanted[at] == values[likely]
    return out


def blocks_of(starts: np.ndarray) -> np.ndarray:
    """Where the blocks begin that every one of the windows starting there (ascending) holds one of."""
    cut = np.flatnonzero(np.append(True, np.diff(starts) > 1))
    a, b = starts[cut], starts[np.append(cut[1:], len(starts)) - 1]
    n = (b - a + WINDOW - BLOCK) // STRIDE + 1
    return np.repeat(a, n) + STRIDE * (np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n))


def occurrences(blocks: np.ndarray, words: Words) -> Iterator[np.ndarray]:
    """Where a block's words begin anywhere in the texts, by automata of at most SHARD_BLOCKS blocks (rows of word ids) each."""
    for at in range(0, len(blocks), SHARD_BLOCKS):
        shard = blocks[at : at + SHARD_BLOCKS]
        used = np.unique(shard)
        n = np.arange(len(used))
        letters = np.zeros((words.distinct, 3), np.uint8)  # words in no block: three zeros
        letters[used] = np.stack([0x40 + (n & 63), 0x80 + (n >> _BITS & 63), 0xC0 + (n >> 2 * _BITS)], 1)
        machine = ahocorasick.Automaton(ahocorasick.STORE_LENGTH)
        for row in letters[shard].reshape(len(shard), -1):
            machine.add_word(row.tobytes().decode("latin-1"))
        machine.make_automaton()
        ends = [e for e, _ in machine.iter(letters[words.ids].tobytes().decode("latin-1"))]
        yield np.array(ends, np.int64) // 3 - BLOCK + 1


def locate(words: Words, recurring: np.ndarray) -> np.ndarray:
    """Which words a recurring window covers.  ``recurring`` is sorted."""
    covered = np.zeros(len(words.ids) + 1, np.int32)
    h = window_hashes(words.hashes, WINDOW)
    hit = member(h, recurring) & words.whole()
    at = np.flatnonzero(hit)
    if len(at):
        # Passages already seen in this bucket aren't compiled again.
        _, seen = np.unique(h[at], return_index=True)
        blocks = words.ids[blocks_of(at[np.sort(seen)])[:, None] + np.arange(BLOCK)]
        near = np.zeros(len(h) + 1, np.int32)
        for first in occurrences(blocks, words):
            near += np.bincount(np.clip(first - (WINDOW - BLOCK), 0, len(h)), minlength=len(near)).astype(np.int32)
            near -= np.bincount(np.clip(first + 1, 0, len(h)), minlength=len(near)).astype(np.int32)
        at = np.flatnonzero((np.cumsum(near[:-1]) > 0) & hit)
        covered[at] += 1
        covered[at + WINDOW] -= 1
    return np.cumsum(covered[:-1]) > 0


def _removed(digest: bool):
    def run(key: tuple, docs: pa.Table, found: pa.Table) -> pa.Table:
        words = Words(docs.column("text"))
        covered = locate(words, np.unique(found.column("key").to_numpy().view(np.uint64)))
        gone = np.concatenate([np.zeros(1, np.int64), np.cumsum(covered)])[words.bounds]
        left = pa.LargeListArray.from_arrays(pa.array(words.bounds - gone, pa.int64()), words.flat.filter(pa.array(~covered)))
        kept = pc.binary_join(left, pa.scalar(b" ", pa.large_binary()))
        kept = pa.array([hashlib.sha256(k.as_buffer()).hexdigest() for k in kept], pa.string()) if digest else kept.cast(pa.binary())
        return pa.table({"doc_id": docs.column("doc_id").cast(pa.int64()), "n_words": pa.array(np.diff(words.bounds), pa.int64()), "n_removed": pa.array(np.diff(gone), pa.int64()), "kept_sha256" if digest else "kept": kept})

    return run


def remove_repeats(docs: DataFrame, digest: bool = False) -> DataFrame:
    """doc_id, n_words, n_removed and the kept words (or their digest) of every row."""
    spark = docs.sparkSession
    ship(spark)
    buckets = buckets_for(text_bytes(docs), BUCKET_BYTES)
    rows = drop_suffix(docs, ["doc_id", "text"]).withColumn("bucket", F.pmod(F.xxhash64("doc_id", F.substring("text", 1, 64)), F.lit(buckets)).cast("int"))
    counted = rows.mapInArrow(_seed_rows, "key long, bucket int, times int")
    by_bucket = rows.groupBy("bucket")
    windows = by_bucket.cogroup(_recurring(counted).groupBy("bucket")).applyInArrow(_window_rows, "key long, bucket int, times int")
    confirmed = _recurring(windows)
    return by_bucket.cogroup(confirmed.groupBy("bucket")).applyInArrow(_removed(digest), DIGEST_SCHEMA if digest else TEXT_SCHEMA)


def op6_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(read_documents(spark, sf_dir), digest=True)
