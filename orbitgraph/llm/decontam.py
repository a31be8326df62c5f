"""Benchmark decontamination: random-walk embedding of word windows, bit-sampling LSH, exact edit verification.

Words are compared lower-cased, without punctuation at their ends. The walk reads a window word by word; at each step
a random function of the step and the current word says whether to move on, so a few inserted, deleted or changed
words leave most of the read-out in step: edit distance becomes Hamming distance. Every repetition samples some of
the steps; equal samples make a candidate. Windows are sized by the items: items fall into classes of length (each
half as long again as the one before), and all of a class, the window (an item from one of its words on), the sampled
steps and the distance between entered words of a document, grows with it. Documents are entered every few words,
items at each word of their first half, so a passage holds several windows that are aligned with its item's.

The number of repetitions is derived from a target recall: passages at the edit limit, for each kind of edit, are run
through the walks of a class until enough of them are found. Items of up to ``EXACT_WORDS`` words are too short to
sample from; a passage within the limit keeps a known number of its item's runs of at most three words, so these are
counted, and none is missed. A candidate region must hold enough of the item's words, and is then compared with the
whole item by exact semi-global edit distance, which decides.

The item table is broadcast in blocks of bounded size; a larger benchmark takes a scan of the documents for each.

Edge cases: null or empty texts and items match nothing; repeated rows give repeated matches; a null doc_id is
carried; items with equal words all match; of equally good places the first is given; an empty table gives an empty
result; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WordHash, binary_column, broadcast_if_few, hashed_words, materialise, mix, rolling, slices

EXACT_WORDS = 12  # items of so many words are found by counting runs
GROWTH = 1.5  # least length of a class over that of the one before
RUN_WORDS = 3
MAX_HITS = 2_000_000  # run hits expanded at once
TARGET_RECALL = 0.99
MOST_REPETITIONS = 64
SAMPLES = 3
MIN_SIMILARITY = 0.8
BROADCAST_LEAKS = 1_000_000  # ids of documents with a match that may be broadcast; beyond, they join by a shuffle
BLOCK_WORDS = 2_000_000  # words of benchmark items broadcast at once
SLICE_BYTES = 4 << 20
MARKS = b".,;:!?'\"()[]{}<>-_*#$%&|~`/\\+=^@"


class PlainWordHash(WordHash):
    """Hash of the word lower-cased and stripped of marks; a word of marks alone has its own."""

    def __missing__(self, word: bytes) -> int:
        value = super().__missing__(word.decode("utf-8", "replace").lower().encode().strip(MARKS) or word)
        self[word] = value
        return value


CHUNK = 1 << 14  # starts walked at once, so that a walk's arrays stay in the cache


class Walks:
    """Random functions of one class of lengths: the step-wise move bits, and which steps are sampled.

    Steps are sampled from the first half of the least item's length, one from each of equal parts: later ones are
    the likelier to be out of step."""

    def __init__(self, least: int, repetitions: int, samples: int, seed: int = 7):
        rng = np.random.default_rng([seed, least])
        self.least, self.repetitions = least, repetitions
        parts = np.array_split(np.arange(max(samples, least // 2)), samples)
        self.sampled = [[int(rng.choice(p)) for p in parts] for _ in range(MOST_REPETITIONS)][:repetitions]
        self.factors = rng.integers(1, 1 << 62, (MOST_REPETITIONS, int(parts[-1][-1]) + 1), dtype=np.uint64) * np.uint64(2) + np.uint64(1)
        self.reach = int(parts[-1][-1]) + 1  # a walk reads fewer words than it has steps

    def keys(self, words: np.ndarray, starts: np.ndarray) -> Iterator[np.ndarray]:
        """One array of keys over the starts for each repetition. A walk that leaves its window reads on."""
        padded = np.concatenate([words, np.zeros(self.reach + 1, np.uint64)])
        for r in range(self.repetitions):
            out = np.empty(len(starts), np.uint64)
            sampled, last = set(self.sampled[r]), self.sampled[r][-1]
            for a in range(0, len(starts), CHUNK):
                at = starts[a : a + CHUNK].copy()
                key, here = np.full(len(at), np.uint64(r + 1)), np.empty(len(at), np.uint64)
                for j in range(last + 1):
                    np.take(padded, at, out=here, mode="clip")
                    if j in sampled:
                        key ^= here
                        key *= np.uint64(0x9E3779B97F4A7C15)
                        key ^= key >> np.uint64(29)
                    if j < last:
                        here *= self.factors[r, j]
                        here >>= np.uint64(63)
                        at += here.view(np.int64)
                out[a : a + CHUNK] = key
            yield mix(out)


def class_of(n_words: int) -> int:
    """Least length of the class that an item of ``n_words`` belongs to."""
    least = EXACT_WORDS + 1
    while int(least * GROWTH) <= n_words:
        least = int(least * GROWTH)
    return least


def stride_of(least: int, min_similarity: float) -> int:
    return max(1, allowed_edits(least, min_similarity))


def entries(n_words: int, least: int) -> int:
    """Words of an item at which walks begin: those that leave half of the least length to read."""
    return n_words - (least + 1) // 2 + 1


@lru_cache(maxsize=256)
def repetitions_for(least: int, min_similarity: float, target_recall: float, samples: int) -> int:
    """Repetitions that find the target share of passages at the edit limit, for replaced, deleted, inserted and mixed
    words alike, at the least and at the most demanding length of a class; measured on random words."""
    walks, stride, need = Walks(least, MOST_REPETITIONS, samples), stride_of(least, min_similarity), 1
    rng = np.random.default_rng([11, least])
    longest = min((n for n in range(least, int(least * GROWTH))), key=lambda n: entries(n, least) / stride - 4 * allowed_edits(n, min_similarity) / n)
    trials = 400
    for n in {least, longest}:
        most = allowed_edits(n, min_similarity)
        for kind in ("replace", "delete", "insert", "mixed"):
            items = rng.integers(1, 1 << 62, (trials, n), dtype=np.uint64)
            passages = [edited(item, most, kind, rng) for item in items]
            docs = np.concatenate([np.concatenate([p, rng.integers(1, 1 << 62, 2 * least, dtype=np.uint64)]) for p in passages])
            at = np.cumsum([0, *(len(p) + 2 * least for p in passages)])[:-1]
            entered = [np.arange(a + int(rng.integers(stride)), a + len(p), stride) for a, p in zip(at, passages, strict=True)]
            owner = np.repeat(np.arange(trials), [len(x) for x in entered])
            starts = (np.arange(trials)[:, None] * n + np.arange(entries(n, least))).ravel()
            mine = np.repeat(np.arange(trials), entries(n, least))
            found, r = np.zeros(trials, bool), 0
            for known, keys in zip(walks.keys(items.ravel(), starts), walks.keys(docs, np.concatenate(entered)), strict=True):
                r += 1
                found[owner[np.isin(mix(keys + owner.astype(np.uint64)), mix(known + mine.astype(np.uint64)))]] = True
                if found.mean() >= target_recall:
                    break
            need = max(need, r)
    return need


def edited(words: np.ndarray, edits: int, kind: str, rng: np.random.Generator) -> np.ndarray:
    """The words with exactly so many of them replaced, deleted, or preceded by another."""
    out = words.tolist()
    for at in sorted(rng.choice(len(out), edits, replace=False).tolist(), reverse=True):
        act = str(rng.choice(["replace", "delete", "insert"])) if kind == "mixed" else kind
        out[at : at + (act != "insert")] = [] if act == "delete" else [int(rng.integers(1, 1 << 62))]
    return np.array(out, np.uint64)


def allowed_edits(n_words: int, min_similarity: float) -> int:
    return int(np.floor((1 - min_similarity) * n_words + 1e-9))


def run_rule(n_words: int, most: int) -> tuple[int, int]:
    """Words in a run, and how many runs of an item outlast ``most`` edits at least."""
    for width in range(min(RUN_WORDS, n_words), 0, -1):
        left = n_words - width + 1 - width * most
        if left >= 1:
            return width, left
    return 1, 1


class Items:
    """Benchmark items as hashed words, with the keys of their walks by class and, of short ones, of their runs."""

    def __init__(self, rows: list[tuple[int, bytes]], min_similarity: float = MIN_SIMILARITY, target_recall: float = TARGET_RECALL, samples: int = SAMPLES):
        self.ids = [r[0] for r in rows]
        flat, offsets = hashed_words([r[1] for r in rows], PlainWordHash())
        self.words = [flat[offsets[i] : offsets[i + 1]].copy() for i in range(len(rows))]
        self.size = np.diff(offsets)
        self.most = np.array([allowed_edits(int(n), min_similarity) for n in self.size], np.int64)
        self.tables = []
        classes: dict[int, list[int]] = {}
        for i, n in enumerate(self.size.tolist()):
            if n > EXACT_WORDS:
                classes.setdefault(class_of(n), []).append(i)
        for least, mine in sorted(classes.items()):
            walks = Walks(least, repetitions_for(least, min_similarity, target_recall, samples), samples)
            count = [entries(int(self.size[i]), least) for i in mine]
            owner = np.repeat(mine, count)
            within = np.concatenate([np.arange(c) for c in count])
            found = []
            for keys in walks.keys(flat, offsets[owner] + within):
                order = np.argsort(keys, kind="stable")
                found.append((keys[order], owner[order], within[order], _bitmap(keys)))
            self.tables.append((walks, stride_of(least, min_similarity), found))
        held = np.unique(_member_keys(np.repeat(np.arange(len(rows)), self.size), flat))
        self.members = _bitmap(held)
        rules = [run_rule(int(n), int(k)) for n, k in zip(self.size, self.most, strict=True)]
        self.need = np.array([r[1] for r in rules], np.int64)
        self.runs = []
        for width in range(1, RUN_WORDS + 1):
            mine = [i for i, n in enumerate(self.size.tolist()) if 0 < n <= EXACT_WORDS and rules[i][0] == width]
            if not mine:
                continue
            keys = np.concatenate([rolling(self.words[i], width) for i in mine])
            owner = np.concatenate([np.full(len(self.words[i]) - width + 1, i) for i in mine])
            within = np.concatenate([np.arange(len(self.words[i]) - width + 1) for i in mine])
            order = np.argsort(keys, kind="stable")
            self.runs.append((width, keys[order], owner[order], within[order], _bitmap(keys)))


def _bitmap(keys: np.ndarray) -> np.ndarray:
    out = np.zeros(max(1 << 20, 1 << int(16 * len(keys)).bit_length()), bool)
    out[(keys & np.uint64(len(out) - 1)).astype(np.int64)] = True
    return out


def _hits(bitmap: np.ndarray, keys: np.ndarray) -> np.ndarray:
    return bitmap[(keys & np.uint64(len(bitmap) - 1)).astype(np.int64)]


def _member_keys(item: np.ndarray, words: np.ndarray) -> np.ndarray:
    return mix(words + item.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))


def within_edits(item: np.ndarray, region: np.ndarray, most: int) -> tuple[int, int, int] | None:
    """(distance, start, end) of the best match of the whole item inside the region, if at most ``most`` word edits."""
    best = np.zeros(len(region) + 1, np.int64)  # by rows of the item, over end positions; matches start anywhere
    begin = np.arange(len(region) + 1)
    big = len(item) + len(region) + 1
    ramp = np.arange(len(region) + 1)
    for i, word in enumerate(item):
        sub = best[:-1] + (region != word)
        up = best[1:] + 1
        take = up < sub
        new = np.concatenate([[i + 1], np.where(take, up, sub)])
        came = np.concatenate([[0], np.where(take, begin[1:], begin[:-1])])
        # insertions run to the right: prefix minimum of value minus position, carrying where the path began
        lifted = (new - ramp) * big + ramp
        low = np.minimum.accumulate(lifted)
        origin = low % big
        new = new[origin] + (ramp - origin)
        begin, best = came[origin], new
        if best.min() > most:
            return None
    end = int(np.argmin(best))
    return (int(best[end]), int(begin[end]), end) if best[end] <= most else None


MATCHES = "doc_id long, item_id long, start_word long, n_words long, item_words long, edits long, similarity double"


def _scan(shared: object, min_similarity: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        items, table = shared.value, PlainWordHash()
        for batch in batches:
            docs, texts = batch.column(0).to_pylist(), binary_column(batch, "text")
            sizes = [0 if x is None else x for x in pa.compute.binary_length(texts).to_pylist()]
            rows: list[tuple] = []
            for a, b in slices(sizes, SLICE_BYTES):
                flat, offsets = hashed_words([t or b"" for t in texts.slice(a, b - a).to_pylist()], table)
                rows += [(docs[a + d], *m) for d, m in _matches(items, flat, offsets, min_similarity)]
            if rows:
                c = list(zip(*rows, strict=True))
                kinds = [pa.int64()] * 6 + [pa.float64()]
                yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(c, kinds, strict=True)], names=["doc_id", "item_id", "start_word", "n_words", "item_words", "edits", "similarity"])

    return run


def _matches(items: Items, flat: np.ndarray, offsets: np.ndarray, min_similarity: float) -> Iterator[tuple[int, tuple]]:
    """Best match of each (document, item) that has a candidate, if it is similar enough."""
    regions: dict[tuple[int, int], list[int]] = {}
    for walks, stride, tables in items.tables:
        n = np.maximum(np.diff(offsets) - walks.least // 2 + 1, 0)
        per_doc = (n + stride - 1) // stride
        doc = np.repeat(np.arange(len(n)), per_doc)
        if not len(doc):
            continue
        first = np.cumsum(per_doc) - per_doc
        starts = offsets[doc] + (np.arange(len(doc)) - first[doc]) * stride
        for keys, (known, owner, within, bitmap) in zip(walks.keys(flat, starts), tables, strict=True):
            maybe = np.flatnonzero(_hits(bitmap, keys))
            lo, hi = np.searchsorted(known, keys[maybe], "left"), np.searchsorted(known, keys[maybe], "right")
            for a, b in slices((hi - lo).tolist(), MAX_HITS // 64):
                hits = hi[a:b] - lo[a:b]
                place = np.repeat(lo[a:b] - (np.cumsum(hits) - hits), hits) + np.arange(hits.sum())
                d, i = np.repeat(doc[maybe[a:b]], hits), owner[place]
                begin = np.repeat(starts[maybe[a:b]], hits) - offsets[d] - within[place]
                for x, y, z in zip(*_plausible(items, flat, offsets, d, i, begin), strict=True):
                    regions.setdefault((x, y), []).append(z)
    for d, i, begin in _run_candidates(items, flat, offsets):
        regions.setdefault((d, i), []).append(begin)
    for (d, i), begins in sorted(regions.items()):
        item = items.words[i]
        most = allowed_edits(len(item), min_similarity)
        spans: list[list[int]] = []  # candidates within the slack of one another share a region
        for begin in sorted(set(begins)):
            if spans and begin <= spans[-1][1] + most:
                spans[-1][1] = begin
            else:
                spans.append([begin, begin])
        best = None
        for begin, last in spans:
            lo = max(0, begin - most)
            region = flat[offsets[d] + lo : min(offsets[d] + last + len(item) + 2 * most + 1, offsets[d + 1])]
            found = within_edits(item, region, most)
            if found and (best is None or (found[0], lo + found[1]) < best[:2]):
                best = (found[0], lo + found[1], found[2] - found[1])
        if best:
            yield d, (items.ids[i], best[1], best[2], len(item), best[0], 1 - best[0] / len(item))


def _plausible(items: Items, flat: np.ndarray, offsets: np.ndarray, d: np.ndarray, i: np.ndarray, begin: np.ndarray) -> tuple[list[int], list[int], list[int]]:
    """The candidates whose region holds as many words of the item as a passage within the limit keeps at least."""
    lo = np.maximum(begin - items.most[i], 0) + offsets[d]
    hi = np.minimum(begin + items.size[i] + items.most[i] + 1 + offsets[d], offsets[d + 1])
    length = np.maximum(hi - lo, 0)
    at = np.repeat(lo - (np.cumsum(length) - length), length) + np.arange(length.sum())
    member = _hits(items.members, _member_keys(np.repeat(i, length), flat[at]))
    total = np.concatenate([[0], np.cumsum(member)])
    end = np.cumsum(length)
    fine = total[end] - total[end - length] >= items.size[i] - items.most[i]
    return d[fine].tolist(), i[fine].tolist(), begin[fine].tolist()


def _run_candidates(items: Items, flat: np.ndarray, offsets: np.ndarray) -> Iterator[tuple[int, int, int]]:
    """(document, item, begin) where as many runs as outlast the allowed edits lie on diagonals no farther apart than these."""
    for width, known, owner, within, bitmap in items.runs:
        keys = rolling(flat, width)
        at = np.flatnonzero(_hits(bitmap, keys))
        doc = np.searchsorted(offsets, at, "right") - 1
        inside = at + width <= offsets[doc + 1]
        at, doc = at[inside], doc[inside]
        lo, hi = np.searchsorted(known, keys[at], "left"), np.searchsorted(known, keys[at], "right")
        hits = hi - lo
        ends = np.searchsorted(doc, np.arange(len(offsets)))  # the runs of each document, whole documents at a time
        total = np.concatenate([[0], np.cumsum(hits)])
        for a, b in slices(np.diff(total[ends]).tolist(), MAX_HITS):
            s, h = slice(ends[a], ends[b]), hits[ends[a] : ends[b]]
            if not h.sum():
                continue
            place = np.repeat(lo[s] - (np.cumsum(h) - h), h) + np.arange(h.sum())
            d, i = np.repeat(doc[s], h), owner[place]
            diagonal = np.repeat(at[s] - offsets[doc[s]], h) - within[place]
            order = np.lexsort((diagonal, i, d))
            d, i, diagonal = d[order], i[order], diagonal[order]
            last = np.arange(len(d)) + items.need[i] - 1
            end = np.minimum(last, len(d) - 1)
            found = (last < len(d)) & (d[end] == d) & (i[end] == i) & (diagonal[end] - diagonal <= items.most[i])
            yield from zip(d[found].tolist(), i[found].tolist(), diagonal[found].tolist(), strict=True)


def contamination(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_id_col: str = "item_id", item_text_col: str = "text", min_similarity: float = MIN_SIMILARITY, target_recall: float = TARGET_RECALL, samples: int = SAMPLES, block_words: int = BLOCK_WORDS) -> DataFrame:
    """Matches: one row for each document and item whose passage it holds within the edit limit, with the best place.

    ``target_recall``: share of passages at the very limit that the sampled walks must find; nearer ones are likelier."""
    spark = docs.sparkSession
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    items = benchmark.select(F.col(item_id_col).cast("long").alias("item_id"), F.encode(F.coalesce(item_text_col, F.lit("")), "UTF-8").alias("text"))
    out, block, held = None, [], 0

    def scan(block: list[tuple[int, bytes]]) -> DataFrame:
        shared = spark.sparkContext.broadcast(Items(block, min_similarity, target_recall, samples))
        return rows.mapInArrow(_scan(shared, min_similarity), MATCHES)

    for r in items.orderBy("item_id", "text").toLocalIterator():
        block.append((r.item_id, bytes(r.text)))
        held += r.text.count(b" ") + 1
        if held >= block_words:
            out = scan(block) if out is None else out.unionAll(scan(block))
            block, held = [], 0
    if block or out is None:
        out = scan(block) if out is None else out.unionAll(scan(block))
    return out


def decontaminate(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", **how: object) -> DataFrame:
    """The documents that hold no benchmark passage; all columns stay. Rows with a null id are judged by nothing and stay."""
    found = contamination(docs, benchmark, id_col, text_col, **how).select(F.col("doc_id").alias("__leak")).where(F.col("__leak").isNotNull()).distinct()
    found = broadcast_if_few(materialise(found, "leaks"), BROADCAST_LEAKS)
    return docs.join(found, F.col(id_col) == F.col("__leak"), "left_anti")
