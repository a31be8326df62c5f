"""Near-duplicate documents by SetSketch registers.

A sketch register is the truncated, exponentially spaced logarithm of a minimum over the document's shingles: registers
merge by maximum and agree about as often as the sets overlap. Documents with equal shingle sets form one class first
(an aggregate, so thousands of copies are no hot group). Bands of registers collect classes into buckets; in a bucket
the overlap of each pair is estimated by maximum likelihood from its registers and sizes, and a spanning forest of the
likely pairs goes on, never all pairs. Their components are compared on full shingle sets, which decides the links.
Buckets and components beyond a bound are worked off in pairs of blocks, so that every pair still meets and no group
is collected into one task.

Recall: a pair at the threshold shares no band with probability (1 - 0.85^4)^20, about 4e-7; the likelihood estimate is
cut five standard errors below the threshold.

Edge cases: null or empty texts have no shingles and are linked with nothing; with fewer words than a shingle the whole
sequence is one; rows sharing a doc_id are one document to the links; rows with a null id are linked too, and get a
null component where no row of theirs has an id; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import binary_column, broadcast_if_few, hashed_words, materialise, mix, rolling, slices
from .components import components

REGISTERS, BAND = 80, 4
BASE, RATE, TOP = 1.001, 20.0, 65_535  # spacing, rate and truncation of the registers
SLICE_BYTES = 4 << 20
BLOCK = 512  # members of a block; groups of over two blocks are worked off in pairs of blocks
BROADCAST_CLASSES = 300_000
NO_ID = 1 << 62  # above it: ids made up for classes whose rows all lack one
_FACTORS = np.random.default_rng(20_240_101).integers(1, 1 << 62, (2, REGISTERS), dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def shingle_sets(texts: list[bytes], width: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of each text (ASCII lower-cased), concatenated, and their offsets."""
    flat, offsets = hashed_words([t.lower() for t in texts])
    n_words = np.diff(offsets)
    n = np.where(n_words >= width, n_words - width + 1, (n_words > 0).astype(np.int64))
    row = np.repeat(np.arange(len(n)), n)
    step = np.arange(len(row)) - (np.cumsum(n) - n)[row]
    rolled = rolling(flat, width)
    hashes = np.zeros(len(row), np.uint64)
    whole = n_words[row] >= width
    hashes[whole] = rolled[(offsets[row] + step)[whole]]
    for i in np.flatnonzero((n_words > 0) & (n_words < width)):  # the whole sequence, told apart by its length
        words = flat[offsets[i] : offsets[i + 1]]
        hashes[np.searchsorted(row, i)] = mix(rolling(words, len(words)) + np.uint64(len(words)))[0]
    order = np.lexsort((hashes, row))
    row, hashes = row[order], hashes[order]
    keep = np.ones(len(row), bool)
    keep[1:] = (row[1:] != row[:-1]) | (hashes[1:] != hashes[:-1])
    row, hashes = row[keep], hashes[keep]
    return hashes, np.searchsorted(row, np.arange(len(n) + 1))


def sketch(hashes: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Registers of each non-empty set: rows by REGISTERS, 16 bits each."""
    starts = offsets[:-1][np.diff(offsets) > 0]
    out = np.zeros((len(starts), REGISTERS), np.uint16)
    if not len(starts):
        return out
    for i in range(REGISTERS):
        low = np.minimum.reduceat(hashes * _FACTORS[0, i] + _FACTORS[1, i], starts)
        waiting = -np.log1p(-(low.astype(np.float64) + 0.5) / 2.0**64) / RATE
        out[:, i] = np.clip(np.floor(1 - np.log(np.maximum(waiting, 1e-300)) / np.log(BASE)), 0, TOP).astype(np.uint16)
    return out


def merge(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Registers of the union of two sets."""
    return np.maximum(a, b)


def likely_overlap(above: np.ndarray, below: np.ndarray, equal: np.ndarray, n: np.ndarray, m: np.ndarray) -> np.ndarray:
    """Jaccard similarity of greatest likelihood, given how many registers lie above, below or agree, and both sizes.

    With shares u = n/(n+m), v = m/(n+m) and similarity J a register lies above with probability u - vJ, below with
    v - uJ, and agrees with J; the derivative falls in J, so bisection finds its zero."""
    u, v = n / (n + m), m / (n + m)
    lo, hi = np.zeros(len(u)), np.minimum(u / v, v / u)
    for _ in range(25):
        j = (lo + hi) / 2
        slope = equal / np.maximum(j, 1e-12) - above * v / np.maximum(u - v * j, 1e-12) - below * u / np.maximum(v - u * j, 1e-12)
        lo, hi = np.where(slope > 0, j, lo), np.where(slope > 0, hi, j)
    return (lo + hi) / 2


def _sketches(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = binary_column(batch, "text")
            for a, b in slices(pc.fill_null(pc.binary_length(texts), 0).to_pylist(), SLICE_BYTES):
                hashes, offsets = shingle_sets([t or b"" for t in texts.slice(a, b - a).to_pylist()], width)
                sizes = np.diff(offsets)
                regs = iter(sketch(hashes, offsets))
                digests = [xxhash.xxh3_128_digest(hashes[offsets[i] : offsets[i + 1]].tobytes()) if n else None for i, n in enumerate(sizes)]
                packed = [next(regs).tobytes() if n else None for n in sizes]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), pa.array(sizes.astype(np.int64)), pa.array(digests, pa.binary()), pa.array(packed, pa.binary())], names=["doc_id", "n", "digest", "regs"])

    return run


def _bands(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        regs = np.frombuffer(b"".join(batch.column(1).to_pylist()), np.uint16).reshape(-1, REGISTERS)
        reps = np.asarray(batch.column(0).to_numpy(zero_copy_only=False), np.int64)
        key = np.zeros((len(regs), REGISTERS // BAND), np.uint64)
        for k in range(BAND):
            key = mix(key * np.uint64(0x9E3779B97F4A7C15) + regs[:, k::BAND].astype(np.uint64) + np.arange(REGISTERS // BAND, dtype=np.uint64)[None, :] * np.uint64(1 << 32))
        yield pa.RecordBatch.from_arrays([pa.array(key.ravel().view(np.int64)), pa.array(np.repeat(reps, key.shape[1]))], names=["bucket", "rep"])


def in_blocks(members: DataFrame, key: str, size: str, id_col: str) -> DataFrame:
    """A row for each task group that a member belongs to: its group itself, or, for groups of over two blocks, every
    pair of blocks with its own, so that each pair of members meets in some group."""
    blocks = F.ceil(F.col(size) / BLOCK).cast("int")
    mine = F.pmod(F.xxhash64(F.col(id_col), F.lit(17)), blocks).cast("int")
    pairs = F.transform(F.sequence(F.lit(0), blocks - 1), lambda j: F.xxhash64(F.col(key), F.least(mine, j), F.greatest(mine, j)))
    return members.withColumn("task", F.explode(F.when(F.col(size) <= 2 * BLOCK, F.array(F.col(key))).otherwise(pairs))).drop(key, size)


def _groups(batches: Iterator[pa.RecordBatch], column: int) -> Iterator[pa.Table]:
    """Rows of equal keys, in order, from sorted batches; one group is held at a time."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        keys = batch.column(column).to_numpy()
        cuts = [0, *(np.flatnonzero(keys[1:] != keys[:-1]) + 1).tolist(), len(keys)]
        for a, b in zip(cuts, cuts[1:], strict=False):
            if a == b:
                continue
            if held and held[-1].column(column)[0].as_py() != keys[a]:
                yield pa.Table.from_batches(held)
                held = []
            held.append(batch.slice(a, b - a))
    if held:
        yield pa.Table.from_batches(held)


class Forest:
    """Union-find over small integers."""

    def __init__(self, n: int):
        self.up = list(range(n))

    def root(self, x: int) -> int:
        while self.up[x] != x:
            self.up[x] = self.up[self.up[x]]
            x = self.up[x]
        return x

    def join(self, x: int, y: int) -> None:
        x, y = self.root(x), self.root(y)
        if x != y:
            self.up[max(x, y)] = min(x, y)

    def links(self, ids: np.ndarray) -> tuple[list[int], list[int]]:
        roots = [self.root(i) for i in range(len(ids))]
        rows = [i for i, r in enumerate(roots) if r != i]
        return [int(ids[i]) for i in rows], [int(ids[roots[i]]) for i in rows]


def _link_batch(pairs: tuple[list[int], list[int]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(pairs[0], pa.int64()), pa.array(pairs[1], pa.int64())], names=["a", "b"])


def _likely(threshold: float):
    least = threshold - 5 * np.sqrt(threshold * (1 - threshold) / REGISTERS)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out: tuple[list[int], list[int]] = ([], [])
        for group in _groups(batches, 0):
            if group.num_rows < 2:
                continue
            ids = group["rep"].to_numpy()
            n = group["n"].to_numpy().astype(float)
            regs = np.frombuffer(b"".join(group["regs"].to_pylist()), np.uint16).reshape(-1, REGISTERS)
            forest = Forest(len(ids))
            for a in range(0, len(ids), 128):
                rows = slice(a, min(a + 128, len(ids)))
                ratio = np.minimum(n[rows, None], n[None, :]) / np.maximum(n[rows, None], n[None, :])
                x, y = np.nonzero((ratio >= threshold) & (np.arange(len(ids))[None, :] > np.arange(rows.start, rows.stop)[:, None]))
                for c in range(0, len(x), 20_000):
                    i, j = x[c : c + 20_000] + a, y[c : c + 20_000]
                    above, equal = (regs[i] > regs[j]).sum(axis=1), (regs[i] == regs[j]).sum(axis=1)
                    close = likely_overlap(above, REGISTERS - above - equal, equal, n[i], n[j]) >= least
                    for p, q in zip(i[close].tolist(), j[close].tolist(), strict=True):
                        forest.join(p, q)
            found = forest.links(ids)
            out[0].extend(found[0])
            out[1].extend(found[1])
            if len(out[0]) >= 10_000:
                yield _link_batch(out)
                out = ([], [])
        yield _link_batch(out)

    return run


def _full_sets(width: int):
    """task, rep, set of the candidate classes' rows (the row's own digest must be its class's)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, digests = binary_column(batch, "text"), batch.column(batch.schema.get_field_index("digest")).to_pylist()
            for a, b in slices(pc.fill_null(pc.binary_length(texts), 0).to_pylist(), SLICE_BYTES):
                hashes, offsets = shingle_sets([t or b"" for t in texts.slice(a, b - a).to_pylist()], width)
                sets = [hashes[offsets[i] : offsets[i + 1]].tobytes() for i in range(b - a)]
                same = [xxhash.xxh3_128_digest(s) == d for s, d in zip(sets, digests[a:b], strict=True)]
                part = pa.RecordBatch.from_arrays([batch.column(i).slice(a, b - a) for i in (0, 1, 2)] + [pa.array(sets, pa.binary())], names=["rep", "comp", "size", "shingles"])
                yield part.filter(pa.array(same))

    return run


def _unnamed_sets(width: int):
    """digest, set of rows without an id: their classes are found by the digest alone."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = binary_column(batch, "text")
            for a, b in slices(pc.fill_null(pc.binary_length(texts), 0).to_pylist(), SLICE_BYTES):
                hashes, offsets = shingle_sets([t or b"" for t in texts.slice(a, b - a).to_pylist()], width)
                sets = [hashes[offsets[i] : offsets[i + 1]].tobytes() for i in range(b - a)]
                yield pa.RecordBatch.from_arrays([pa.array([xxhash.xxh3_128_digest(s) for s in sets], pa.binary()), pa.array(sets, pa.binary())], names=["digest", "shingles"])

    return run


def _confirmed(percent: int):
    """Spanning links of the pairs with 100 * intersection >= percent * union, by exact counts over shared shingles."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group in _groups(batches, 2):
            if group.num_rows < 2:
                continue
            ids = group["rep"].to_numpy()
            sets = [np.frombuffer(s, np.uint64) for s in group["shingles"].to_pylist()]
            sizes = np.array([len(s) for s in sets], np.int64)
            both = _intersections(sets)
            union = sizes[:, None] + sizes[None, :] - both
            forest = Forest(len(ids))
            for i, j in zip(*(k.tolist() for k in np.nonzero(np.triu(100 * both >= percent * union, 1))), strict=True):
                forest.join(i, j)
            yield _link_batch(forest.links(ids))

    return run


def _intersections(sets: list[np.ndarray]) -> np.ndarray:
    """Exact sizes of all pairwise intersections of at most two blocks of sets, through a column-chunked 0/1 matrix."""
    row = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    values = np.concatenate(sets)
    order = np.argsort(values, kind="stable")
    values, row = values[order], row[order]
    new = np.ones(len(values), bool)
    new[1:] = values[1:] != values[:-1]
    column = np.cumsum(new) - 1
    shared = np.bincount(column) > 1
    keep = shared[column]
    row, column = row[keep], (np.cumsum(shared) - 1)[column[keep]]
    out = np.zeros((len(sets), len(sets)), np.int64)
    width = max(256, (1 << 22) // len(sets))
    n = int(column[-1]) + 1 if len(column) else 0
    for a in range(0, n, width):
        lo, hi = np.searchsorted(column, a), np.searchsorted(column, a + width)
        m = np.zeros((len(sets), min(width, n - a)), np.float32)
        m[row[lo:hi], column[lo:hi] - a] = 1
        out += np.rint(m @ m.T).astype(np.int64)
    return out


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 5, percent: int = 85) -> DataFrame:
    """doc_id, n_shingles, component_id and kept of every row."""
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    rows = materialise(texts.mapInArrow(_sketches(width), "doc_id long, n long, digest binary, regs binary"), "sketches")
    made_up = F.lit(NO_ID) + F.pmod(F.xxhash64("digest"), F.lit(1 << 61))
    classes = rows.where(F.col("n") > 0).groupBy("digest").agg(F.min("doc_id").alias("low"), F.first("n").alias("n"), F.first("regs").alias("regs"))
    # an id held by rows of different texts joins their classes: the least id stays the class's name, made distinct below
    classes = materialise(classes.select("digest", F.coalesce("low", made_up).alias("rep"), "n", "regs"), "classes")

    bands = classes.select("rep", "regs").mapInArrow(_bands, "bucket long, rep long")
    sizes = bands.groupBy("bucket").agg(F.count(F.lit(1)).alias("size")).where(F.col("size") > 1)
    members = in_blocks(bands.join(sizes, "bucket"), "bucket", "size", "rep")
    with_regs = members.join(classes.select("rep", "n", "regs"), "rep").select("task", "rep", "n", "regs")
    likely = with_regs.repartition("task").sortWithinPartitions("task", "rep").mapInArrow(_likely(percent / 100), "a long, b long")
    candidates = components(likely)

    comps = candidates.groupBy("label").agg(F.count(F.lit(1)).alias("size"))
    chosen = candidates.join(comps, "label").select(F.col("v").alias("rep"), F.col("label").alias("comp"), "size")
    chosen = materialise(chosen.join(classes.select("rep", "digest"), "rep"), "chosen")
    named_rows = broadcast_if_few(chosen.where(F.col("rep") < NO_ID), BROADCAST_CLASSES)
    with_text = texts.where(F.col("doc_id").isNotNull()).join(named_rows, F.col("doc_id") == F.col("rep"))
    sets = with_text.select("rep", "comp", "size", "digest", "text")
    sets = sets.mapInArrow(_full_sets(width), "rep long, comp long, size long, shingles binary")
    unnamed = chosen.where(F.col("rep") >= NO_ID)
    if unnamed.limit(1).count():
        found = texts.where(F.col("doc_id").isNull()).select("text").mapInArrow(_unnamed_sets(width), "digest binary, shingles binary")
        sets = sets.unionByName(found.join(broadcast_if_few(unnamed, BROADCAST_CLASSES), "digest").groupBy("rep", "comp", "size").agg(F.first("shingles").alias("shingles")))
    tasks = in_blocks(sets, "comp", "size", "rep").select("rep", "shingles", "task").repartition("task").sortWithinPartitions("task", "rep")
    links = tasks.mapInArrow(_confirmed(percent), "a long, b long")
    joined = components(links)

    named = classes.select("digest", "rep").join(joined.select(F.col("v").alias("rep"), "label"), "rep", "left").select("digest", F.coalesce("label", "rep").alias("component"))
    out = rows.select("doc_id", "n", "digest").join(named, "digest", "left")
    component = F.when(F.col("component").isNull(), F.col("doc_id")).when(F.col("component") < NO_ID, F.col("component"))
    return out.select("doc_id", F.col("n").alias("n_shingles"), component.alias("component_id")).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.col("component_id").isNull()))
