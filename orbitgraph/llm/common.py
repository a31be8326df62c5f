"""Helpers shared by the training-data operators: shared storage, word hashing, byte-bounded slices."""

from __future__ import annotations

import atexit
import re
import tempfile
import uuid
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

MASK64 = (1 << 64) - 1


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``, or the session's checkpoint folder; only a
    local session (tests), whose driver and executors are one process, gets one of its own."""
    found = spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not found:
        existing = spark.sparkContext._jsc.sc().getCheckpointDir()
        if not existing.isDefined() and not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and the executors share")
        found = existing.get() if existing.isDefined() else "file://" + tempfile.mkdtemp(prefix="orbitgraph-")
        if not existing.isDefined():
            spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def _forget(spark: SparkSession, path: str) -> None:
    try:
        jvm = spark.sparkContext._jvm
        target = jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)
    except Exception:  # the session may have ended; the folder then stays for the cluster's own clean-up
        pass


def materialise(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` as Parquet under the shared folder and read it back: cuts lineage and survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/tables/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    atexit.register(_forget, spark, path)
    out = spark.read.schema(df.schema).parquet(path)
    out._shared_path = path
    return out


def discard(table: DataFrame) -> None:
    """Removes a table of :func:`materialise` that nothing reads any more; iterations call it so that disk does not grow."""
    _forget(table.sparkSession, table._shared_path)


def broadcast_if_few(table: DataFrame, most: int) -> DataFrame:
    """The materialised table, marked for broadcast if it has at most ``most`` (thin) rows; else it joins by a shuffle."""
    return F.broadcast(table) if table.limit(most + 1).count() <= most else table


def spread(scan: DataFrame) -> DataFrame:
    """A file scan of fewer partitions than the cluster has cores is dealt out over them; a larger one stays as it is.

    Only for plain scans: counting the partitions of a plan with shuffles would run them."""
    cores = scan.sparkSession.sparkContext.defaultParallelism
    few = scan._jdf.queryExecution().toRdd().getNumPartitions() < cores
    return scan.repartition(cores) if few else scan


def let(value: Column, body) -> Column:
    """Evaluate ``value`` once and use it many times inside higher-order expressions."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def binary_column(batch: pa.RecordBatch, name: str) -> pa.Array:
    return batch.column(batch.schema.get_field_index(name)).cast(pa.large_binary())


def slices(lengths: list[int], limit: int) -> Iterator[tuple[int, int]]:
    """Consecutive index ranges whose lengths add up to about ``limit`` (one long item may exceed it)."""
    start, held = 0, 0
    for i, n in enumerate(lengths):
        if i > start and held + n > limit:
            yield start, i
            start, held = i, 0
        held += n
    if start < len(lengths):
        yield start, len(lengths)


class WordHash(dict):
    """word bytes -> 64-bit hash, remembered up to a fixed number of words."""

    limit = 400_000

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.limit:
            self.clear()
        value = self[word] = xxhash.xxh3_64_intdigest(word)
        return value


_BYTE = np.random.default_rng(97).integers(1, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_SPACE = np.zeros(256, bool)
_SPACE[[32, *range(9, 14)]] = True
_STEP = 0x9E3779B97F4A7C15
_CHUNK = 1 << 20
_POWERS: list[np.ndarray] = []


def _powers(n: int) -> list[np.ndarray]:
    if not _POWERS or len(_POWERS[0]) < n:
        size = max(n, _CHUNK + (1 << 16))
        _POWERS[:] = [np.cumprod(np.concatenate([[np.uint64(1)], np.full(size - 1, np.uint64(f), np.uint64)])) for f in (_STEP, pow(_STEP, -1, 1 << 64))]
    return _POWERS


def _chunk_hashes(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hash and first byte of every word: a prefix sum of byte weights times powers, divided by the power at the start."""
    space = _SPACE[data]
    begins = np.flatnonzero(~space & np.append(True, space[:-1]))
    ends = np.flatnonzero(~space & np.append(space[1:], True)) + 1
    power, inverse = _powers(len(data))
    prefix = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(_BYTE[data] * power[: len(data)], out=prefix[1:])
    return mix((prefix[ends] - prefix[begins]) * inverse[begins] + (ends - begins).astype(np.uint64)), begins


def hashed_words(texts: list[bytes], table: WordHash | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all ASCII-space separated words, and the offsets of the texts in them.

    Without a table all bytes are hashed together in numpy, a bounded chunk at a time."""
    if table is not None:
        out, offsets = array("Q"), [0]
        for text in texts:
            out.extend(map(table.__getitem__, text.split()))
            offsets.append(len(out))
        return np.frombuffer(out, dtype=np.uint64) if len(out) else np.zeros(0, np.uint64), np.asarray(offsets, dtype=np.int64)
    data = np.frombuffer(b"\n".join(texts), np.uint8)
    hashes, begins, at = [], [], 0
    while at < len(data):
        stop = min(at + _CHUNK, len(data))
        while stop < len(data) and not _SPACE[data[stop]]:  # a chunk ends between words
            more = np.flatnonzero(_SPACE[data[stop : stop + (1 << 16)]])
            stop = stop + int(more[0]) if len(more) else min(stop + (1 << 16), len(data))
        h, b = _chunk_hashes(data[at:stop])
        hashes.append(h)
        begins.append(b + at)
        at = stop
    first = np.cumsum([0, *(len(t) + 1 for t in texts)])
    place = np.concatenate(begins) if begins else np.zeros(0, np.int64)
    return (np.concatenate(hashes) if hashes else np.zeros(0, np.uint64)), np.searchsorted(place, first)


def mix(values: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser, vectorised."""
    values = values ^ (values >> np.uint64(33))
    values = values * np.uint64(0xFF51AFD7ED558CCD)
    values = values ^ (values >> np.uint64(33))
    values = values * np.uint64(0xC4CEB9FE1A85EC53)
    return values ^ (values >> np.uint64(33))


def rolling(hashes: np.ndarray, width: int) -> np.ndarray:
    """Order-sensitive hash of every run of ``width`` values (positions 0..n-width)."""
    n = len(hashes) - width + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    total = np.zeros(n, np.uint64)
    factor = 1
    for k in range(width):
        total += hashes[k : k + n] * np.uint64(factor)
        factor = factor * 0x9E3779B97F4A7C15 & MASK64
    return mix(total)
