"""Exact substring deduplication of word windows by super-k-mer partitioning.

Every window of ``width`` words has a minimiser, the least hash of its word grams. Consecutive windows that share one
travel together as one packed string of words to the minimiser's bucket: equal windows have equal minimisers, so they
meet there, where the unpacked windows are sorted by hash and compared word by word. A slice sends each bucket one
compressed parcel of strings. It first drops windows that begin earlier in itself, so copies travel once a slice.
Minimisers that hold more than a bounded number of windows, by a sample's count, are split: their windows travel one by
one, to the bucket of the window's own hash. Windows that very many slices hold meet in two steps, first within groups
of slices, whose first ones go on, so no bucket holds a string from every slice. The sample steers only where windows
meet; all windows of all rows are compared, and the result does not depend on it.

Edge cases: null or empty text has no words; texts shorter than a window lose nothing; order is (doc_id, start) with
null ids first; rows that share doc_id and text get the same result, and windows that begin at the same (doc_id,
start) are not earlier than one another; an empty table gives an empty result; other columns pass through.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import binary_column, hashed_words, materialise, mix, rolling, slices

GRAM = 3
SLICE_BYTES = 3 << 20
BUCKET_BYTES = 1 << 20  # text of the input for each bucket, so about three times that in packed strings
HOT_WINDOWS = 20_000  # a minimiser of more windows is split
HOT_SHARE = 1 / 2_000  # or one of a larger share of all windows, whichever is less
SAMPLE_OF = 16
MOST_HOT = 200_000  # minimisers, and as many windows, that are split at most; they are broadcast
HOT_COPIES = 2_000  # a window of more copies meets in two steps
SALTS = 64  # groups of slices in the first of them
BUCKETS_A_TASK = 16
NULL_ID = -(1 << 63)
CODEC = "zstd"
PARCELS = "bucket long, salt int, parcel binary"
FOUND = "doc long, row_key long, start int, stop int, bucket long, parcel binary"


def told_apart(texts: list[bytes], hashes: np.ndarray) -> np.ndarray:
    """Numbers that are equal where words are: the hashes, if all distinct words differ in theirs, else a count of the words."""
    words: set[bytes] = set()
    for text in texts:
        words.update(text.split())
    if len(words) == len(np.unique(hashed_words([b" ".join(words)])[0])):
        return hashes
    number = {w: i for i, w in enumerate(words)}
    return np.fromiter((number[w] for text in texts for w in text.split()), np.uint64, len(hashes))


def minimisers(hashes: np.ndarray, width: int) -> np.ndarray:
    """The least gram hash of every window: a sliding minimum by doubling spans."""
    grams = rolling(hashes, GRAM)
    span, size = width - GRAM + 1, 1
    low = grams
    while size * 2 <= span:
        low = np.minimum(low[:-size], low[size:])
        size *= 2
    rest = span - size
    return np.minimum(low[: len(low) - rest], low[rest:]) if rest else low


def repeated(order_hash: np.ndarray, words: np.ndarray, at: np.ndarray, row: np.ndarray, ids: np.ndarray, start: np.ndarray, width: int) -> np.ndarray:
    """Marks windows that begin later than an equal one; windows come in (doc, start) order, ``at`` says where each
    one's words stand in ``words``, ``row`` whose window it is, ``ids`` the rows' document ids."""
    order = np.argsort(order_hash)
    h = order_hash[order]
    equal = h[1:] == h[:-1]
    grouped = np.flatnonzero(np.append(equal, False) | np.append(False, equal))
    out = np.zeros(len(order), bool)
    if not len(grouped):
        return out
    mine, hashes = order[grouped], h[grouped]
    mine = mine[np.lexsort((mine, hashes))]  # hashes are sorted already: this puts each group into (doc, start) order
    same = np.zeros(len(mine), bool)
    near = np.flatnonzero(hashes[1:] == hashes[:-1]) + 1
    matches = np.ones(len(near), bool)
    for k in range(width):
        matches &= words[at[mine[near]] + k] == words[at[mine[near - 1]] + k]
    same[near[matches]] = True
    for value in np.unique(hashes[near[~matches]]):  # different words under one hash: such groups are told apart exactly
        lo, hi = np.searchsorted(hashes, value, "left"), np.searchsorted(hashes, value, "right")
        groups: dict[bytes, list[int]] = {}
        for k in range(lo, hi):
            groups.setdefault(words[at[mine[k]] : at[mine[k]] + width].tobytes(), []).append(int(mine[k]))
        mine[lo:hi] = [w for g in groups.values() for w in g]
        same[lo:hi] = [i > 0 for g in groups.values() for i in range(len(g))]
    # a run of equal windows: later means a greater (doc, start) than the run's first
    lead = mine[np.maximum.accumulate(np.where(same, 0, np.arange(len(mine))))]
    out[mine] = same & ((ids[row[mine]] != ids[row[lead]]) | (start[mine] != start[lead]))
    return out


def _windows(n_words: np.ndarray, offsets: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Row, start in the row, and place in the slice of every window."""
    n = np.maximum(n_words - width + 1, 0)
    row = np.repeat(np.arange(len(n), dtype=np.int32), n)
    start = (np.arange(len(row)) - (np.cumsum(n) - n)[row]).astype(np.int32)
    return row, start, (offsets[row] + start).astype(np.int32)


def _sample(width: int):
    """(kind, hash, n): windows of each minimiser (kind 0), and copies of each window found twice in a slice (kind 1)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = binary_column(batch, "text")
            for a, b in slices(pc.fill_null(pc.binary_length(texts), 0).to_pylist(), SLICE_BYTES):
                flat, offsets = hashed_words([t or b"" for t in texts.slice(a, b - a).to_pylist()])
                if len(flat) < width:
                    continue
                _, _, at = _windows(np.diff(offsets), offsets, width)
                for kind, values in ((0, minimisers(flat, width)[at]), (1, rolling(flat, width)[at])):
                    keys, counts = np.unique(values.view(np.int64), return_counts=True)
                    keys, counts = (keys, counts) if kind == 0 else (keys[counts > 1], counts[counts > 1])
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(keys), kind, np.int32)), pa.array(keys), pa.array(counts, pa.int64())], names=["kind", "hash", "n"])

    return run


def hot_keys(docs: DataFrame, width: int, total_words: int) -> tuple[np.ndarray, np.ndarray]:
    """By a sample's count: minimisers of more than ``HOT_WINDOWS`` windows, and windows of over ``HOT_COPIES`` copies; of
    each the commonest ``MOST_HOT`` at most."""
    sample = docs.where(F.pmod(F.xxhash64("doc", "row_key"), F.lit(SAMPLE_OF)) == 0).select("text")
    counts = sample.mapInArrow(_sample(width), "kind int, hash long, n long").groupBy("kind", "hash").agg(F.sum("n").alias("n"))
    least = max(32, int(min(HOT_WINDOWS, total_words * HOT_SHARE) / SAMPLE_OF))
    # both lists are taken from one pass over the sample
    hot = counts.where(F.col("n") >= F.when(F.col("kind") == 0, F.lit(least)).otherwise(F.lit(max(2, HOT_COPIES // SAMPLE_OF))))
    found: tuple[list[int], list[int]] = ([], [])
    for r in hot.orderBy(F.desc("n"), "hash").limit(2 * MOST_HOT).toLocalIterator():
        if len(found[r.kind]) < MOST_HOT:
            found[r.kind].append(r.hash)
    return tuple(np.array(sorted(x), np.int64) for x in found)  # type: ignore[return-value]


def pack_parcel(doc: np.ndarray, key: np.ndarray, start: np.ndarray, n: np.ndarray, words: list[bytes]) -> bytes:
    """Super-k-mers of one slice and bucket: columns of numbers, then the strings, compressed together."""
    numbers = b"".join(x.tobytes() for x in (doc.astype("<i8"), key.astype("<i8"), start.astype("<i4"), n.astype("<i4")))
    data = numbers + b"\n".join(words)
    return len(doc).to_bytes(8, "little") + len(data).to_bytes(8, "little") + pa.compress(data, codec=CODEC, asbytes=True)


def open_parcel(parcel: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, list[bytes]]:
    rows, size = int.from_bytes(parcel[:8], "little"), int.from_bytes(parcel[8:16], "little")
    data = pa.decompress(parcel[16:], decompressed_size=size, codec=CODEC, asbytes=True)
    cuts = np.cumsum([0, 8 * rows, 8 * rows, 4 * rows, 4 * rows])
    doc, key, start, n = (np.frombuffer(data[a:b], kind).astype(np.int64) for a, b, kind in zip(cuts, cuts[1:], ("<i8", "<i8", "<i4", "<i4"), strict=False))
    return doc, key, start, n, data[cuts[-1] :].split(b"\n")


def _strings(texts: list[bytes], row: np.ndarray, start: np.ndarray, length: np.ndarray) -> list[bytes]:
    """The packed words of each run; one text is split at a time."""
    out: list[bytes] = [b""] * len(row)
    held, words = -1, []
    order = np.argsort(row, kind="stable")
    for k, i, j, m in zip(order.tolist(), row[order].tolist(), start[order].tolist(), length[order].tolist(), strict=True):
        if i != held:
            held, words = i, texts[i].split()
        out[k] = b" ".join(words[j : j + m])
    return out


def _pack(width: int, hot: object, buckets: int):
    """Parcels of super-k-mers, and (bucket -1) of the spans that an earlier window of the slice covers. Hot windows have
    buckets of their own from ``buckets`` on, and the salt of the slice."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, copied = hot.value
        part, number = TaskContext.get().partitionId(), 0
        for batch in batches:
            docs = np.asarray(batch.column(0).to_numpy(zero_copy_only=False), np.int64)
            keys = np.asarray(batch.column(1).to_numpy(zero_copy_only=False), np.int64)
            texts = binary_column(batch, "text")
            for a, b in slices(pc.fill_null(pc.binary_length(texts), 0).to_pylist(), SLICE_BYTES):
                by = a + np.argsort(docs[a:b], kind="stable")
                part_texts = [t or b"" for t in texts.take(pa.array(by)).to_pylist()]
                flat, offsets = hashed_words(part_texts)
                row, start, at = _windows(np.diff(offsets), offsets, width)
                if not len(row):
                    continue
                ids, own = docs[by], keys[by]
                whole = rolling(flat, width)[at]
                again = repeated(whole, told_apart(part_texts, flat), at, row, ids, start, width)
                salt, number = (part * 31 + number) % SALTS, number + 1
                out: list[tuple[int, int, bytes]] = [(-1, 0, pack_parcel(*c, [])) for c in [_covers(row, ids, own, start, again, width)] if len(c[0])]
                least = minimisers(flat, width)[at].view(np.int64)
                if len(known):
                    least = np.where(np.isin(least, known), whole.view(np.int64), least)
                if len(copied):
                    is_copied = np.isin(whole.view(np.int64), copied)
                    least = np.where(is_copied, whole.view(np.int64), least)
                live = np.flatnonzero(~again)
                del at, flat, again
                r, s, k = row[live], start[live], least[live]
                new = np.ones(len(live), bool)
                new[1:] = (r[1:] != r[:-1]) | (s[1:] != s[:-1] + 1) | (k[1:] != k[:-1])
                if len(copied):  # such a window travels alone
                    alone = is_copied[live]
                    new[alone] = True
                    new[1:][alone[:-1]] = True
                heads = np.flatnonzero(new)
                n = np.diff(np.append(heads, len(live)))
                bucket = (mix(k[heads].view(np.uint64)) % np.uint64(buckets)).astype(np.int64)
                if len(copied):
                    bucket += np.where(alone[heads], buckets, 0)
                del whole, least, new
                order = np.argsort(bucket, kind="stable")
                heads, n, bucket = heads[order], n[order], bucket[order]
                strings = _strings(part_texts, r[heads], s[heads], n + width - 1)
                cuts = np.flatnonzero(np.append(True, bucket[1:] != bucket[:-1])).tolist() if len(bucket) else []
                for lo, hi in zip(cuts, [*cuts[1:], len(bucket)], strict=True):
                    h = live[heads[lo:hi]]
                    out.append((int(bucket[lo]), salt if bucket[lo] >= buckets else 0, pack_parcel(ids[row[h]], own[row[h]], start[h], n[lo:hi], strings[lo:hi])))
                yield pa.RecordBatch.from_arrays([pa.array([o[0] for o in out], pa.int64()), pa.array([o[1] for o in out], pa.int32()), pa.array([o[2] for o in out], pa.binary())], names=["bucket", "salt", "parcel"])

    return run


def _covers(row: np.ndarray, ids: np.ndarray, keys: np.ndarray, start: np.ndarray, again: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """doc, row_key, first word and number of words of the spans that the marked windows cover."""
    at = np.flatnonzero(again)
    order = at[np.lexsort((start[at], keys[row[at]], ids[row[at]]))]
    d, k, s = ids[row[order]], keys[row[order]], start[order].astype(np.int64)
    new = np.ones(len(s), bool)
    new[1:] = (d[1:] != d[:-1]) | (k[1:] != k[:-1]) | (s[1:] > s[:-1] + width)
    heads = np.flatnonzero(new)
    last = np.append(heads[1:], len(s))[: len(heads)] - 1
    return d[heads], k[heads], s[heads], s[last] + width - s[heads]


def _found(doc: np.ndarray, key: np.ndarray, start: np.ndarray, n: np.ndarray, bucket: int | None = None, parcel: bytes | None = None) -> pa.RecordBatch:
    m = len(doc) if parcel is None else 1
    arrays = [pa.array(doc), pa.array(key), pa.array(start.astype(np.int32)), pa.array((start + n).astype(np.int32))] if parcel is None else [pa.nulls(1, t) for t in (pa.int64(), pa.int64(), pa.int32(), pa.int32())]
    return pa.RecordBatch.from_arrays([*arrays, pa.array([bucket] * m, pa.int64()), pa.array([parcel] * m, pa.binary())], names=["doc", "row_key", "start", "stop", "bucket", "parcel"])


NONE = np.zeros(0, np.int64)


def _compare(width: int, buckets: int, last: bool):
    """Sorted by bucket and salt: unpacks one group at a time and emits the spans of its repeated windows; of hot buckets,
    before the last step, also the first ones, packed again."""

    def settle(bucket: int, parcels: list[bytes]) -> Iterator[pa.RecordBatch]:
        opened = [open_parcel(p) for p in parcels]
        doc, key, start, n = (np.concatenate([o[i] for o in opened]) for i in range(4))
        strings = [w for o in opened for w in o[4]]
        order = np.lexsort((start, doc))
        doc, key, start, n = doc[order], key[order], start[order], n[order]
        strings = [strings[i] for i in order.tolist()]
        flat, offsets = hashed_words(strings)
        row = np.repeat(np.arange(len(n), dtype=np.int32), n)
        step = np.arange(len(row)) - (np.cumsum(n) - n)[row]
        at, place = offsets[row] + step, start[row] + step
        again = repeated(rolling(flat, width)[at], told_apart(strings, flat), at, row, doc, place, width)
        if again.any():
            yield _found(*_covers(row, doc, key, place, again, width))
        if bucket >= buckets and not last:
            first = row[~again]  # one window a row
            yield _found(NONE, NONE, NONE, NONE, bucket, pack_parcel(doc[first], key[first], start[first], n[first], [strings[i] for i in first.tolist()]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, now = [], None
        for batch in batches:
            for b, salt, parcel in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
                if b < 0:
                    yield _found(*open_parcel(parcel)[:4])
                    continue
                if (b, salt) != now and held:
                    yield from settle(now[0], held)
                    held = []
                now = (b, salt)
                held.append(parcel)
        if held:
            yield from settle(now[0], held)

    return run


def repeated_spans(docs: DataFrame, width: int = 20) -> DataFrame:
    """docs: doc, row_key, text. One row for each (doc, row_key) with repeats: its word spans [start, stop)."""
    spark = docs.sparkSession
    size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    partitions = int(spark.conf.get("spark.sql.shuffle.partitions"))
    buckets = int(max(64, 2 * partitions, size // BUCKET_BYTES))
    tasks = max(partitions, buckets // BUCKETS_A_TASK)
    hot = hot_keys(docs, width, size // 6)
    parcels = docs.select("doc", "row_key", "text").mapInArrow(_pack(width, spark.sparkContext.broadcast(hot), buckets), PARCELS)
    # spans found inside a slice have no bucket to go to: any will do
    dealt = parcels.withColumn("_to", F.when(F.col("bucket") < 0, -F.pmod(F.xxhash64("parcel"), F.lit(1 << 40)) - 1).otherwise(F.col("bucket") * SALTS + F.col("salt")))
    step = lambda df, key, last: df.repartition(tasks, key).sortWithinPartitions("bucket", "salt").select("bucket", "salt", "parcel").mapInArrow(_compare(width, buckets, last), FOUND)
    found = step(dealt, "_to", False)
    if len(hot[1]):
        found = materialise(found, "substring-found")
        again = found.where(F.col("parcel").isNotNull()).select("bucket", F.lit(0).alias("salt"), "parcel")
        found = found.where(F.col("parcel").isNull()).unionByName(step(again, "bucket", True))
    return found.groupBy("doc", "row_key").agg(F.sort_array(F.collect_set(F.struct("start", "stop"))).alias("spans"))


def _cut(fields: list[str], text_col: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            kept, n_words, n_removed = [], [], []
            spans_all = batch.column(batch.schema.get_field_index("__spans"))
            for text, spans in zip(binary_column(batch, text_col).to_pylist(), spans_all.to_pylist(), strict=True):
                words = (text or b"").split()
                out, at, gone = [], 0, 0
                for s in spans or ():
                    if s["start"] > at:
                        out += words[at : s["start"]]
                    gone += max(0, s["stop"] - max(at, s["start"]))
                    at = max(at, s["stop"])
                out += words[at:]
                kept.append(b" ".join(out))
                n_words.append(len(words))
                n_removed.append(gone)
            columns = [batch.column(batch.schema.get_field_index(c)) for c in fields]
            added = [pa.array(kept, pa.binary()).cast(pa.string()), pa.array(n_words, pa.int64()), pa.array(n_removed, pa.int64())]
            yield pa.RecordBatch.from_arrays(columns + added, names=[*fields, "kept_text", "n_words", "n_removed"])

    return run


def remove_repeats(df: DataFrame, width: int = 20, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``df`` plus kept_text (kept words joined by one space), n_words and n_removed (replacing columns of those names)."""
    if width < GRAM:
        raise ValueError(f"windows of fewer than {GRAM} words are not supported")
    df = df.drop("kept_text", "n_words", "n_removed")
    keyed = df.withColumns({"__doc": F.coalesce(F.col(id_col).cast("long"), F.lit(NULL_ID)), "__row_key": F.xxhash64(text_col)})
    spans = materialise(repeated_spans(keyed.select(F.col("__doc").alias("doc"), F.col("__row_key").alias("row_key"), F.col(text_col).alias("text")), width), "spans")
    spans = spans.select(F.col("doc").alias("__d"), F.col("row_key").alias("__k"), F.col("spans").alias("__spans"))
    joined = keyed.join(spans, (F.col("__doc") == F.col("__d")) & (F.col("__row_key") == F.col("__k")), "left").select(*df.columns, "__spans")
    schema = T.StructType([*df.schema.fields, T.StructField("kept_text", T.StringType()), T.StructField("n_words", T.LongType()), T.StructField("n_removed", T.LongType())])
    return joined.mapInArrow(_cut(df.columns, text_col), schema)
