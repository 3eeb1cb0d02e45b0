"""What the operators of this subpackage share: shipping, scratch tables, words and word-window hashes.

Words are the maximal runs of bytes outside 0x20 and 0x09-0x0D.  ``bytes.split()``
cuts at exactly those six bytes and ``bytes.lower()`` touches only A-Z, so all of the
tokenising below runs in C on UTF-8 bytes, whatever the language of the text.
"""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile
from pathlib import Path

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_PACKAGE = Path(__file__).resolve().parents[1]
_CACHE_LIMIT = 400_000
#: Odd multiplier of the polynomial word-window hash.
_BASE = 0x9E3779B97F4A7C15
_MASK = (1 << 64) - 1


def ship(spark: SparkSession) -> None:
    """Give every executor this package, once per Spark context."""
    context = spark.sparkContext
    if getattr(context, "_fieldtally_shipped", False):
        return
    target = Path(tempfile.mkdtemp()) / f"{_PACKAGE.name}_{uuid.uuid4().hex[:8]}.zip"
    with zipfile.ZipFile(target, "w", zipfile.ZIP_DEFLATED) as archive:
        for file in sorted(_PACKAGE.rglob("*.py")):
            archive.write(file, f"{_PACKAGE.name}/{file.relative_to(_PACKAGE)}")
    context.addPyFile(str(target))
    context._fieldtally_shipped = True


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; one of our own only where none is set and the master is local."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        own = getattr(spark.sparkContext, "_fieldtally_shared", None)
        if own is None:
            own = tempfile.mkdtemp(prefix="fieldtally-shared-")
            spark.sparkContext._fieldtally_shared = own
        found = f"file://{own}"
    return found.rstrip("/")


def scratch(spark: SparkSession, frame: DataFrame, name: str) -> DataFrame:
    """Write ``frame`` to the shared folder and return the written table: cuts lineage,
    survives lost executors.  The folder is the caller's to empty between jobs."""
    path = f"{shared_dir(spark)}/fieldtally/{name}-{uuid.uuid4().hex}"
    frame.write.parquet(path)
    return spark.read.schema(frame.schema).parquet(path)


def read_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def text_bytes(docs: DataFrame) -> int:
    """Bytes of all texts: the one statistic from which bucket counts are derived."""
    return int(docs.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0)).alias("b")).first()["b"])


def buckets_for(total_bytes: int, per_bucket: int, least: int = 1) -> int:
    return max(least, -(-total_bytes // per_bucket))


def as_bytes(column: pa.ChunkedArray | pa.Array) -> list[bytes]:
    """UTF-8 bytes of a string column; null becomes empty."""
    return [x or b"" for x in column.cast(pa.large_binary() if column.type == pa.large_string() else pa.binary()).to_pylist()]


class WordHashes(dict):
    """word bytes -> 64-bit hash, remembered for the words seen lately (bounded)."""

    def __missing__(self, word: bytes) -> int:
        value = xxhash.xxh3_64_intdigest(word)
        if len(self) >= _CACHE_LIMIT:
            self.clear()
        self[word] = value
        return value

    def of(self, found: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, found), dtype=np.uint64, count=len(found))


def mix64(x: np.ndarray) -> np.ndarray:
    """Finaliser that spreads every input bit over the word."""
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xFF51AFD7ED558CCD)
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


def window_hashes(h: np.ndarray, k: int) -> np.ndarray:
    """One hash for each run of k consecutive entries, in O(n log k) by doubling."""
    n = len(h) - k + 1
    if n <= 0:
        return np.empty(0, dtype=np.uint64)
    out, taken, power, size = None, 0, h, 1
    while True:
        scale = np.uint64(pow(_BASE, size, 1 << 64))
        if k & size:
            part = power[taken : taken + n]
            out = part if out is None else out * scale + part
            taken += size
        if size * 2 > k:
            return mix64(out)
        power = power[:-size] * scale + power[size:]
        size *= 2


def sliding(values: np.ndarray, k: int, pick) -> np.ndarray:
    """``pick`` (np.minimum or np.maximum) over each run of k entries, by doubling."""
    size, out = 1, values
    while size * 2 <= k:
        out = pick(out[:-size], out[size:])
        size *= 2
    return out if size == k else pick(out[: len(values) - k + 1], out[k - size : k - size + len(values) - k + 1])


def drop_suffix(frame: DataFrame, names: list[str]) -> DataFrame:
    """Only the named columns, so that extra or clashing columns of the input can't interfere."""
    return frame.select(*[F.col(f"`{n}`") for n in names])


def env_single_thread() -> None:
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    os.environ.setdefault("RAYON_NUM_THREADS", "1")
