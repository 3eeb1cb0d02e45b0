"""Byte-level BPE encoding and decoding through a sentencepiece model built from a rank file.

The model is serialised here, field by field, from the vocabulary: every byte string of
the rank file becomes a piece in which each byte is written as one printable character,
with score minus rank, and the normaliser is the identity.  Merging the best-scored
neighbouring pair is then the same as merging the pair of lowest rank.  A pre-token that
is itself in the vocabulary is looked up first, as the rank-file encoder does.

Edge cases: a null text is an empty text; an empty text has no ids, and both digests are
those of the empty byte string; repeated rows give repeated rows; every input column other
than ``doc_id`` and ``text`` is ignored.  An empty table gives an empty table.
"""

from __future__ import annotations

import base64
import functools
import hashlib
import struct
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import as_bytes, drop_suffix, read_documents, ship

_CACHE_LIMIT = 500_000
SCHEMA = "doc_id long, n_tokens long, ids binary, decoded binary"
DIGEST_SCHEMA = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"


def default_vocabulary() -> tuple[str, str]:
    """(path of the rank file, pattern of pre-tokens) of the installed public vocabulary."""
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN


def read_ranks(path: str) -> list[bytes]:
    """The byte strings of a rank file, by rank."""
    with open(path, "rb") as f:
        pairs = [line.split() for line in f if line.strip()]
    out: list[bytes] = [b""] * len(pairs)
    for token, rank in pairs:
        out[int(rank)] = base64.b64decode(token)
    return out


def byte_letters() -> list[str]:
    """A distinct printable, non-space character for each byte: itself where it is one, else from U+0100 on."""
    printable = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    spare = iter(range(0x100, 0x200))
    return [chr(b) if b in printable else chr(next(spare)) for b in range(256)]


def _varint(n: int) -> bytes:
    out = bytearray()
    while n > 0x7F:
        out.append(n & 0x7F | 0x80)
        n >>= 7
    out.append(n)
    return bytes(out)


def _field(number: int, value: int | float | bytes) -> bytes:
    if isinstance(value, bytes):
        return _varint(number << 3 | 2) + _varint(len(value)) + value
    if isinstance(value, float):
        return _varint(number << 3 | 5) + struct.pack("<f", value)
    return _varint(number << 3) + _varint(value & (1 << 64) - 1)


def serialise_model(vocabulary: list[bytes]) -> bytes:
    """A sentencepiece BPE model whose piece ids are the ranks; the unknown piece comes last."""
    letters = byte_letters()
    out = bytearray()
    for rank, token in enumerate(vocabulary):
        out += _field(1, _field(1, "".join(letters[b] for b in token).encode()) + _field(2, -float(rank)) + _field(3, 1))
    out += _field(1, _field(1, b"<unk>") + _field(2, 0.0) + _field(3, 2))
    trainer = _field(3, 2) + _field(4, len(vocabulary) + 1) + _field(40, len(vocabulary)) + _field(41, -1) + _field(42, -1) + _field(43, -1)
    normaliser = _field(1, b"identity") + _field(2, b"") + _field(3, 0) + _field(4, 0) + _field(5, 0)
    return bytes(out + _field(2, trainer) + _field(3, normaliser))


class PieceCodec:
    """Encodes texts to ids and ids to bytes; remembers the pre-tokens seen lately (bounded)."""

    def __init__(self, path: str, pattern: str):
        import sentencepiece

        self.vocabulary = read_ranks(path)
        self.whole = {token: rank for rank, token in enumerate(self.vocabulary)}
        self.letters = dict(enumerate(byte_letters()))
        self.model = sentencepiece.SentencePieceProcessor(model_proto=serialise_model(self.vocabulary))
        self.find = regex.compile(pattern).findall
        self.cache: dict[str, bytes] = {}

    def _learn(self, tokens: list[str]) -> None:
        merge = []
        for token in tokens:
            raw = token.encode("utf-8", "surrogatepass")
            rank = self.whole.get(raw)
            if rank is None:
                merge.append((token, raw.decode("latin-1").translate(self.letters)))
            else:
                self.cache[token] = struct.pack("<I", rank)
        for (token, _), ids in zip(merge, self.model.encode([x for _, x in merge], out_type=int, num_threads=1), strict=True):
            self.cache[token] = struct.pack(f"<{len(ids)}I", *ids)

    def encode(self, text: str) -> bytes:
        """The ids as little-endian unsigned 32-bit integers."""
        tokens = self.find(text)
        try:
            return b"".join(map(self.cache.__getitem__, tokens))
        except KeyError:
            if len(self.cache) > _CACHE_LIMIT:
                self.cache.clear()
            self._learn([t for t in set(tokens) if t not in self.cache])
            return b"".join(map(self.cache.__getitem__, tokens))

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.vocabulary.__getitem__, np.frombuffer(ids, dtype="<u4").tolist()))


@functools.lru_cache(maxsize=2)
def codec(path: str, pattern: str) -> PieceCodec:
    return PieceCodec(path, pattern)


def _batches(path: str, pattern: str, digest: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = codec(path, pattern)
        for batch in batches:
            texts = as_bytes(batch.column(1))
            n, first, second = [], [], []
            for raw in texts:
                ids = coder.encode(raw.decode("utf-8", "surrogatepass"))
                back = coder.decode(ids)
                n.append(len(ids) // 4)
                first.append(hashlib.sha256(ids).hexdigest() if digest else ids)
                second.append(hashlib.sha256(back).hexdigest() if digest else back)
            kind = pa.string() if digest else pa.binary()
            names = ["doc_id", "n_tokens", *(("ids_sha256", "decoded_sha256") if digest else ("ids", "decoded"))]
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), pa.array(n, pa.int64()), pa.array(first, kind), pa.array(second, kind)], names)

    return run


def encode_documents(docs: DataFrame, path: str | None = None, pattern: str | None = None) -> DataFrame:
    """doc_id, n_tokens, ids (little-endian u32), decoded (bytes) of every whole text."""
    ship(docs.sparkSession)
    own = default_vocabulary()
    rows = drop_suffix(docs, ["doc_id", "text"]).withColumn("doc_id", F.col("doc_id").cast("long"))
    return rows.mapInArrow(_batches(path or own[0], pattern or own[1], False), SCHEMA)


def digest_documents(docs: DataFrame, path: str | None = None, pattern: str | None = None) -> DataFrame:
    """As :func:`encode_documents`, but only digests leave the Python workers."""
    ship(docs.sparkSession)
    own = default_vocabulary()
    rows = drop_suffix(docs, ["doc_id", "text"]).withColumn("doc_id", F.col("doc_id").cast("long"))
    return rows.mapInArrow(_batches(path or own[0], pattern or own[1], True), DIGEST_SCHEMA)


def op5_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digest_documents(read_documents(spark, sf_dir))
