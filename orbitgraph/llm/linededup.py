"""Line deduplication with two Bloom filters.

The keys of a slice of documents are kept as 128-bit digests. Both filters are split by ranges of the hash into shards
of fixed size, as many as the number of keys asks for: each slice sends every shard the bits that its keys set in the
once-seen filter, packed as gaps, and those that two of its own documents set in the twice-seen filter. A shard merges
them (twice = or, plus what a slice finds in once already, so no repeated key is ever missed) and tells every slice
which of its bits were seen twice. Only keys so suspected leave their slice; they are counted exactly, by digest.
Neither filter is ever in one place, so their rate of false repeats is the same at every size.

Edge cases: null or empty text is one empty line; keys shorter than ``min_chars`` never drop; rows that share a doc_id
count as one document and the keeper is the largest doc_id (rows of that doc_id all keep the line); rows with a null id
lose nothing and count nowhere; a repeated line inside one document counts once; an empty table gives an empty result;
other columns pass through.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import binary_column, materialise, mix, slices

SPACE_BYTES = b" \t\n\x0b\x0c\r"
SLICE_BYTES = 4 << 20
SHARD_BITS = 1 << 24  # 2 MiB for each of the two filters of a shard
BITS_A_KEY = 16
SHARDS_A_TASK = 4
BROADCAST_KEYS = 200_000  # confirmed keys (16-byte digests) that may be broadcast; beyond, they are joined


def _long_enough(key: bytes, min_chars: int) -> bool:
    return len(key) >= min_chars and (key.isascii() or len(key.decode("utf-8", "replace")) >= min_chars)


def keys_of(text: bytes | None, min_chars: int) -> list[bytes | None]:
    """Key of each \\n-split line; None where it is shorter than ``min_chars`` code points."""
    out: list[bytes | None] = []
    for line in (text or b"").split(b"\n"):
        key = line.strip(SPACE_BYTES).lower() if len(line) >= min_chars else b""
        out.append(key if _long_enough(key, min_chars) else None)
    return out


def _set_bits(packed: np.ndarray, at: np.ndarray) -> None:
    """Sets sorted, distinct bit positions of a packed array."""
    if len(at):
        byte, bit = at >> 3, (128 >> (at & 7)).astype(np.uint8)
        heads = np.flatnonzero(np.append(True, byte[1:] != byte[:-1]))
        packed[byte[heads]] |= np.add.reduceat(bit, heads, dtype=np.uint8)


def _get_bits(packed: np.ndarray, at: np.ndarray) -> np.ndarray:
    return (packed[at >> 3] >> (7 - (at & 7)).astype(np.uint8)) & 1 == 1


SLICES = "slice long, n long, docs binary, offsets binary, digests binary"


def line_slices(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = 40) -> DataFrame:
    """Shared table of slices: doc ids, and the digests of each document's distinct long keys."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, number = TaskContext.get().partitionId(), 0
        for batch in batches:
            texts = binary_column(batch, "text")
            for a, b in slices(pc.fill_null(pc.binary_length(texts), 0).to_pylist(), SLICE_BYTES):
                ids, offsets, digests = [], [0], []
                for doc, text in zip(batch.column(0).slice(a, b - a).to_pylist(), texts.slice(a, b - a).to_pylist(), strict=True):
                    found = {k for k in keys_of(text, min_chars) if k is not None} if doc is not None else ()
                    if found:
                        ids.append(doc)
                        digests += map(xxhash.xxh3_128_digest, found)
                        offsets.append(len(digests))
                if ids:
                    row = ([(part << 32) + number], [len(digests)], [np.array(ids, "<i8").tobytes()], [np.array(offsets, "<i8").tobytes()], [b"".join(digests)])
                    kinds = (pa.int64(), pa.int64(), pa.binary(), pa.binary(), pa.binary())
                    yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(row, kinds, strict=True)], names=["slice", "n", "docs", "offsets", "digests"])
                    number += 1

    rows = df.select(F.col(id_col).cast("long").alias("doc"), F.col(text_col).alias("text"))
    return materialise(rows.mapInArrow(run, SLICES), "line-slices")


def _places(digests: bytes, shards: int) -> tuple[np.ndarray, np.ndarray]:
    """Shard and bit of each digest: one bit for each key, as with two filters in a row a single hash has the least
    false repeats per bit."""
    h = np.frombuffer(digests, "<u8")[::2]
    return (((h >> np.uint64(32)) * np.uint64(shards)) >> np.uint64(32)).astype(np.int64), (mix(h) & np.uint64(SHARD_BITS - 1)).astype(np.int64)


def _parcel(at: np.ndarray, twice: np.ndarray) -> bytes:
    data = np.diff(at, prepend=0).astype("<u4").view(np.uint8).reshape(-1, 4).T.tobytes() + np.packbits(twice).tobytes()
    return len(at).to_bytes(4, "little") + pa.compress(data, codec="zstd", asbytes=True)


def _open(parcel: bytes) -> tuple[np.ndarray, np.ndarray]:
    n = int.from_bytes(parcel[:4], "little")
    data = np.frombuffer(pa.decompress(parcel[4:], decompressed_size=4 * n + (n + 7) // 8, codec="zstd", asbytes=True), np.uint8)
    return np.cumsum(np.ascontiguousarray(data[: 4 * n].reshape(4, n).T).view("<u4").ravel(), dtype=np.int64), np.unpackbits(data[4 * n :], count=n).astype(bool)


def _by_shard(digests: bytes, shards: int) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
    """Each shard with its distinct bits in order, how often the slice's documents set them, and each key's place."""
    shard, bit = _places(digests, shards)
    order = np.argsort(shard, kind="stable")
    cuts = np.searchsorted(shard[order], np.arange(shards + 1)) if shards < len(order) else None
    values = np.unique(shard)
    starts = cuts[values] if cuts is not None else np.searchsorted(shard[order], values)
    for s, a, b in zip(values.tolist(), starts.tolist(), [*starts.tolist()[1:], len(order)], strict=True):
        mine = order[a:b]
        at, count = np.unique(bit[mine], return_counts=True)
        yield s, at, count, mine


def _filters(shards: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name, digests in zip(batch.column(0).to_pylist(), binary_column(batch, "digests").to_pylist(), strict=True):
                rows = [(s, name, _parcel(at, count > 1)) for s, at, count, _ in _by_shard(digests, shards)]
                c = list(zip(*rows, strict=True))
                yield pa.RecordBatch.from_arrays([pa.array(c[0], pa.int64()), pa.array(c[1], pa.int64()), pa.array(c[2], pa.binary())], names=["shard", "slice", "parcel"])

    return run


def _merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Merges the filters of one shard at a time, and answers its slices with the bits of theirs that were seen twice."""
    held: list[tuple[int, bytes]] = []

    def settle(shard: int) -> Iterator[pa.RecordBatch]:
        once, twice = np.zeros(SHARD_BITS // 8, np.uint8), np.zeros(SHARD_BITS // 8, np.uint8)
        for _, parcel in held:
            at, own = _open(parcel)
            _set_bits(twice, at[own | _get_bits(once, at)])
            _set_bits(once, at)
        out = []
        for name, parcel in held:
            hit = _get_bits(twice, _open(parcel)[0])
            if hit.any():
                out.append((name, shard, np.packbits(hit).tobytes()))
        if out:
            c = list(zip(*out, strict=True))
            yield pa.RecordBatch.from_arrays([pa.array(c[0], pa.int64()), pa.array(c[1], pa.int64()), pa.array(c[2], pa.binary())], names=["slice", "shard", "hits"])

    now = None
    for batch in batches:
        for shard, name, parcel in zip(*(c.to_pylist() for c in batch.columns[:3]), strict=True):
            if now is not None and shard != now:
                yield from settle(now)
                held.clear()
            now = shard
            held.append((name, parcel))
    if held:
        yield from settle(now)


def _suspects(shards: int):
    """(key, doc) of the keys whose bit was seen twice."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                answers = {a["shard"]: a["hits"] for a in row["answers"]}
                digests = row["digests"]
                hit = np.zeros(len(digests) // 16, bool)
                _, bit = _places(digests, shards)
                for s, at, _, mine in _by_shard(digests, shards):
                    if s in answers:
                        seen = at[np.unpackbits(np.frombuffer(answers[s], np.uint8), count=len(at)).astype(bool)]
                        hit[mine] = np.isin(bit[mine], seen)
                found = np.flatnonzero(hit)
                docs = np.repeat(np.frombuffer(row["docs"], "<i8"), np.diff(np.frombuffer(row["offsets"], "<i8")))[found]
                keys = [digests[16 * i : 16 * i + 16] for i in found.tolist()]
                yield pa.RecordBatch.from_arrays([pa.array(keys, pa.binary()), pa.array(docs, pa.int64())], names=["key", "doc"])

    return run


def suspected(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = 40) -> DataFrame:
    """(key digest, doc) of every key that the twice-seen filter suspects: all repeated ones, and few others."""
    table = line_slices(df, id_col, text_col, min_chars)
    keys = table.agg(F.sum("n")).first()[0] or 0
    shards = int(max(1, -(-keys * BITS_A_KEY // SHARD_BITS)))
    tasks = max(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), shards // SHARDS_A_TASK)
    parts = table.select("slice", "digests").mapInArrow(_filters(shards), "shard long, slice long, parcel binary")
    answers = parts.repartition(tasks, "shard").sortWithinPartitions("shard").mapInArrow(_merge, "slice long, shard long, hits binary")
    mine = answers.groupBy("slice").agg(F.collect_list(F.struct("shard", "hits")).alias("answers"))
    return table.join(mine, "slice").select("docs", "offsets", "digests", "answers").mapInArrow(_suspects(shards), "key binary, doc long")


def repeated_keys(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = 40, min_docs: int = 5) -> DataFrame:
    """Exact: key digest, keeper (largest doc_id) and documents, of keys in at least ``min_docs`` documents.

    Distinct (key, doc) rows are dealt out before they are counted, so a key that most documents hold is no hot group."""
    rows = suspected(df, id_col, text_col, min_chars).distinct()
    return rows.groupBy("key").agg(F.count(F.lit(1)).alias("documents"), F.max("doc").alias("keeper")).where(F.col("documents") >= min_docs)


def _drop_here(keepers: object, id_col: str, text_col: str, min_chars: int, fields: list[str]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = keepers.value
        for batch in batches:
            texts, lines, dropped = [], [], []
            ids = batch.column(batch.schema.get_field_index(id_col)).to_pylist()
            for doc, text in zip(ids, binary_column(batch, text_col).to_pylist(), strict=True):
                parts = (text or b"").split(b"\n")
                keep = [doc is None or k is None or known.get(xxhash.xxh3_128_digest(k), doc) == doc for k in keys_of(text, min_chars)]
                texts.append(b"\n".join(p for p, ok in zip(parts, keep, strict=True) if ok))
                lines.append(len(parts))
                dropped.append(len(parts) - sum(keep))
            yield _with(batch, fields, texts, lines, dropped)

    return run


def _with(batch: pa.RecordBatch, fields: list[str], texts: list[bytes], lines: list[int], dropped: list[int]) -> pa.RecordBatch:
    columns = [batch.column(batch.schema.get_field_index(c)) for c in fields]
    added = [pa.array(texts, pa.binary()).cast(pa.string()), pa.array(lines, pa.int64()), pa.array(dropped, pa.int64())]
    return pa.RecordBatch.from_arrays(columns + added, names=[*fields, "kept_text", "n_lines", "n_dropped"])


def drop_lines(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = 40, min_docs: int = 5, broadcast_keys: int = BROADCAST_KEYS) -> DataFrame:
    """``df`` plus kept_text, n_lines and n_dropped (replacing columns of those names)."""
    df = df.drop("kept_text", "n_lines", "n_dropped")
    found = materialise(repeated_keys(df, id_col, text_col, min_chars, min_docs), "line-keys")
    schema = T.StructType([*df.schema.fields, T.StructField("kept_text", T.StringType()), T.StructField("n_lines", T.LongType()), T.StructField("n_dropped", T.LongType())])
    if found.count() <= broadcast_keys:
        keepers = {bytes(r.key): r.keeper for r in found.select("key", "keeper").toLocalIterator()}
        shared = df.sparkSession.sparkContext.broadcast(keepers)
        return df.mapInArrow(_drop_here(shared, id_col, text_col, min_chars, df.columns), schema)
    return _drop_joined(df, found, id_col, text_col, min_chars)


def _exploded(min_chars: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row, doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), binary_column(batch, "text").to_pylist(), strict=True):
                at = [(i, xxhash.xxh3_128_digest(k)) for i, k in enumerate(keys_of(text, min_chars)) if k is not None]
                if at:
                    yield pa.RecordBatch.from_arrays([pa.array([row] * len(at), pa.int64()), pa.array([doc] * len(at), pa.int64()), pa.array([i for i, _ in at], pa.int32()), pa.array([k for _, k in at], pa.binary())], names=["__ld_row", "doc", "at", "key"])

    return run


def _drop_joined(df: DataFrame, found: DataFrame, id_col: str, text_col: str, min_chars: int) -> DataFrame:
    """The way for many confirmed keys: lines and keys meet by a shuffle join, doomed line numbers return by row."""
    rows = materialise(df.withColumn("__ld_row", F.monotonically_increasing_id()), "line-rows")
    lines = rows.where(F.col(id_col).isNotNull()).select("__ld_row", F.col(id_col).cast("long").alias("doc"), F.col(text_col).alias("text"))
    keyed = lines.mapInArrow(_exploded(min_chars), "__ld_row long, doc long, at int, key binary")
    doomed = keyed.join(found.select("key", "keeper"), "key").where(F.col("doc") != F.col("keeper")).groupBy("__ld_row").agg(F.collect_set("at").alias("__ld_doomed"))
    split = F.split(F.coalesce(F.col(text_col), F.lit("")), "\n")
    kept = F.filter(split, lambda x, i: ~F.array_contains(F.coalesce(F.col("__ld_doomed"), F.array().cast("array<int>")), i))
    joined = rows.join(doomed, "__ld_row", "left").withColumns({"n_lines": F.size(split).cast("long"), "n_dropped": F.coalesce(F.size("__ld_doomed"), F.lit(0)).cast("long"), "kept_text": F.array_join(kept, "\n")})
    return joined.select(*df.columns, "kept_text", "n_lines", "n_dropped")
