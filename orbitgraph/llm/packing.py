"""Packing of tokenised documents into sequences by non-negative least squares.

Documents are tokenised once into a shared table. Full windows are cut off at once; the rest of a document has a length
below the window. The driver gets only the histogram of those lengths (at most ``window`` numbers), enumerates shallow
combinations that fill a window exactly (pairs, and triples of frequent lengths), solves for their repeat counts by
non-negative least squares, rounds them down and clips them to what is there; the residue is laid end to end and cut
at window borders, its last window into runs of power-of-two length, which need no padding. Each piece's place follows
by arithmetic from its rank among the rests of its length; ranks are counted per partition and added up, so no group
of equal lengths meets in one task.

Edge cases: a null or empty text is the end token alone; repeated rows are documents of their own; a null doc_id is
carried; an empty table gives an empty result; strings of special tokens in a text are ordinary text.
"""

from __future__ import annotations

import json
import zlib
from collections.abc import Iterator
from itertools import combinations_with_replacement

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import binary_column, materialise

FREQUENT = 48  # lengths whose triples are enumerated
BROADCAST_ROWS = 1_000_000  # of the rank table; beyond, it is joined by a shuffle
_ENCODERS: dict[str, object] = {}


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def _byte_table() -> dict[str, int]:
    """Printable stand-ins of byte-level vocabularies back to bytes: printable Latin-1 as is, the rest from U+0100 on."""
    plain = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


class Encoder:
    """ids of a tokenizer file; byte-level BPE files whose merges are in id order go through the faster of the two
    installed libraries, which gives the same ids (tested), any other file through its own."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model, pre = spec.get("model", {}), spec.get("pre_tokenizer") or {}
        self.vocab_size = len(model.get("vocab", ())) + len(spec.get("added_tokens", ()))
        byte_level = pre.get("type") == "ByteLevel" and not pre.get("add_prefix_space") and pre.get("use_regex", True) and not spec.get("normalizer")
        self._fast = self._tiktoken(model, spec) if byte_level and model.get("type", "BPE") == "BPE" else None
        if self._fast is None:
            from tokenizers import Tokenizer

            self._slow = Tokenizer.from_file(path)
            self._slow.encode_special_tokens = True

    @staticmethod
    def _tiktoken(model: dict, spec: dict):
        import tiktoken
        from public_tokenizers import PATTERN

        special = {t["content"] for t in spec.get("added_tokens", ())}
        table = _byte_table()
        merges = [m if isinstance(m, str) else " ".join(m) for m in model["merges"]]
        order = [model["vocab"].get(m.replace(" ", "")) for m in merges]
        if None in order or any(a >= b for a, b in zip(order, order[1:], strict=False)):
            return None
        ranks = {bytes(table[c] for c in token): i for token, i in model["vocab"].items() if token not in special}
        return tiktoken.Encoding("byte-level", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={})

    def __call__(self, texts: list[str]) -> list[list[int]]:
        if self._fast is not None:
            return [self._fast.encode_ordinary(t) for t in texts]
        return [e.ids for e in self._slow.encode_batch_fast(texts, add_special_tokens=False)]


def encoder(path: str) -> Encoder:
    if path not in _ENCODERS:
        _ENCODERS[path] = Encoder(path)
    return _ENCODERS[path]  # type: ignore[return-value]


TOKENS = "doc_id long, part int, n long, full_before long, rest int, local_rank long, ids binary"


def tokenised(docs: DataFrame, window: int, tokenizer: str, end_id: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Shared table of token ids (16-bit where the vocabulary allows) with each row's place in its partition."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, part = encoder(tokenizer), TaskContext.get().partitionId()
        kind = np.dtype("<u2") if max(encode.vocab_size, end_id + 1) <= 1 << 16 else np.dtype("<u4")
        full, ranks = 0, np.zeros(window, np.int64)
        for batch in batches:
            docs_, texts = batch.column(0).to_pylist(), batch.column(1)
            for at in range(0, len(docs_), 64):
                rows = []
                for doc, ids in zip(docs_[at : at + 64], encode([t or "" for t in texts.slice(at, 64).to_pylist()]), strict=True):
                    ids.append(end_id)
                    n = len(ids)
                    rest = n % window
                    rows.append((doc, part, n, full, rest, int(ranks[rest]), np.array(ids, kind).tobytes()))
                    full += n // window
                    ranks[rest] += 1
                c = list(zip(*rows, strict=True))
                kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(c, kinds, strict=True)], names=["doc_id", "part", "n", "full_before", "rest", "local_rank", "ids"])

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return materialise(rows.mapInArrow(run, TOKENS), "tokens")


def combinations(window: int, histogram: np.ndarray) -> list[tuple[int, ...]]:
    """Pairs and triples of lengths that add up to the window; triples among the most frequent lengths and their complement."""
    there = np.flatnonzero(histogram[1:window]) + 1
    have = set(there.tolist())
    found = {(a, window - a) for a in have if a >= window - a and window - a in have}
    frequent = there[np.argsort(-histogram[there], kind="stable")][:FREQUENT]
    for a, b in combinations_with_replacement(sorted(frequent.tolist()), 2):
        c = window - a - b
        if c > 0 and c in have:
            found.add(tuple(sorted((a, b, c), reverse=True)))
    return sorted(found, reverse=True)


def solve_counts(combos: list[tuple[int, ...]], histogram: np.ndarray, rounds: int = 1500) -> np.ndarray:
    """Repeat counts x >= 0 with the least squared distance of A x from the histogram (accelerated projected gradient)."""
    if not combos:
        return np.zeros(0)
    rows = np.concatenate([np.asarray(c) for c in combos])
    cols = np.repeat(np.arange(len(combos)), [len(c) for c in combos])
    target = histogram.astype(float)
    times = lambda x: np.bincount(rows, weights=x[cols], minlength=len(target))
    back = lambda r: np.bincount(cols, weights=r[rows], minlength=len(combos))
    step = 1.0 / max(back(times(np.ones(len(combos)))).max(), 1.0)  # row sums of AtA bound its largest eigenvalue
    x = y = np.zeros(len(combos))
    t = 1.0
    for _ in range(rounds):
        new = np.maximum(y - step * back(times(y) - target), 0.0)
        t_new = (1 + np.sqrt(1 + 4 * t * t)) / 2
        y, x, t = new + (t - 1) / t_new * (new - x), new, t_new
    return x


class Plan:
    """Places of the rests: slots (length, first rank, first sequence, offset), then the residue's run of tokens."""

    def __init__(self, histogram: np.ndarray, window: int):
        self.window = window
        left = histogram.astype(np.int64).copy()
        left[0] = 0
        combos = combinations(window, histogram)
        counts = solve_counts(combos, histogram)
        order = sorted(range(len(combos)), key=lambda i: (-counts[i], combos[i]))
        slots: list[tuple[int, int, int, int, int]] = []  # length, first rank, sequences, first sequence, offset
        taken, sequences = np.zeros_like(left), 0
        for wanted in (lambda i: int(counts[i]), lambda i: 1 << 62):  # rounded down, then greedily what still fits
            for i in order:
                need = {a: combos[i].count(a) for a in combos[i]}
                k = min([wanted(i), *(int(left[a]) // m for a, m in need.items())])
                if k <= 0:
                    continue
                offset = 0
                for a in combos[i]:
                    slots.append((a, int(taken[a]), k, sequences, offset))
                    taken[a] += k
                    left[a] -= k
                    offset += a
                sequences += k
        slots.sort()
        self.keys = np.array([(s[0] << 44) + s[1] for s in slots], np.int64)
        self.slots = np.array(slots, np.int64).reshape(-1, 5)
        self.first_residual = taken
        lengths = np.arange(len(left))
        self.run_start = np.concatenate([[0], np.cumsum(left * lengths)])[:-1]
        self.run_first = sequences
        total = int((left * lengths).sum())
        whole, tail = divmod(total, window)
        self.run_whole = whole
        # the run's tail becomes sequences of power-of-two length, largest first
        sizes = [1 << b for b in range(tail.bit_length() - 1, -1, -1) if tail >> b & 1]
        self.borders = np.concatenate([[0], np.cumsum(sizes)]).astype(np.int64) + whole * window
        self.first_full = sequences + whole + len(sizes)

    def place(self, length: int, rank: int) -> list[tuple[int, int, int, int]]:
        """(start in the rest, length, sequence, offset) of the pieces of the rank-th rest of this length."""
        if rank < self.first_residual[length]:
            slot = self.slots[int(np.searchsorted(self.keys, (length << 44) + rank, "right")) - 1]
            return [(0, length, int(slot[3] + rank - slot[1]), int(slot[4]))]
        at = int(self.run_start[length] + (rank - self.first_residual[length]) * length)
        done, out = 0, []
        while done < length:
            pos = at + done
            if pos < self.run_whole * self.window:
                seq, offset, room = self.run_first + pos // self.window, pos % self.window, self.window - pos % self.window
            else:
                i = int(np.searchsorted(self.borders, pos, "right")) - 1
                seq, offset, room = self.run_first + self.run_whole + i, int(pos - self.borders[i]), int(self.borders[i + 1] - pos)
            n = min(room, length - done)
            out.append((done, n, seq, offset))
            done += n
        return out


def pack(docs: DataFrame, window: int = 2048, tokenizer: str | None = None, end_id: int = 1, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """One row for each piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset (and ids if asked)."""
    path = tokenizer or default_tokenizer()
    tokens = tokenised(docs, window, path, end_id, id_col, text_col)
    small = max(encoder(path).vocab_size, end_id + 1) <= 1 << 16
    counts = tokens.groupBy("part", F.col("rest").alias("length")).agg(F.count(F.lit(1)).alias("k")).unionByName(tokens.groupBy("part").agg(F.sum(F.floor(F.col("n") / window)).alias("k")).select("part", F.lit(window).alias("length"), "k"))
    counts = materialise(counts, "lengths")
    histogram = np.zeros(window + 1, np.int64)
    for r in counts.where(F.col("length") < window).groupBy("length").agg(F.sum("k").alias("k")).toLocalIterator():
        histogram[r.length] = r.k
    plan = Plan(histogram[:window], window)
    shared = docs.sparkSession.sparkContext.broadcast(plan)
    before = Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    bases = materialise(counts.withColumn("base", F.coalesce(F.sum("k").over(before), F.lit(0))).drop("k"), "bases")
    near = F.broadcast if bases.count() <= BROADCAST_ROWS else (lambda df: df)
    rests = near(bases.where(F.col("length") < window).select(F.col("part").alias("p1"), "length", F.col("base").alias("rest_base")))
    fulls = near(bases.where(F.col("length") == window).select(F.col("part").alias("p2"), F.col("base").alias("full_base")))
    placed = tokens.join(rests, (F.col("part") == F.col("p1")) & (F.col("rest") == F.col("length"))).join(fulls, F.col("part") == F.col("p2"))
    placed = placed.select("doc_id", "n", "rest", (F.col("local_rank") + F.col("rest_base")).alias("rank"), (F.col("full_before") + F.col("full_base")).alias("full"), "ids")
    kind = np.dtype("<u2") if small else np.dtype("<u4")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        plan = shared.value
        for batch in batches:
            rows = []
            cols = [batch.column(i).to_pylist() for i in range(5)]
            for doc, n, rest, rank, full, ids in zip(*cols, binary_column(batch, "ids").to_pylist(), strict=True):
                wide = np.frombuffer(ids, kind).astype("<u4")
                q = n // window
                pieces = [(k * window, window, plan.first_full + full + k, 0) for k in range(q)]
                if rest:
                    pieces += [(q * window + s, m, seq, off) for s, m, seq, off in plan.place(rest, rank)]
                for s, m, seq, off in pieces:
                    piece = wide[s : s + m].tobytes()
                    rows.append((doc, s, m, zlib.crc32(piece), n, seq, off, piece))
            if rows:
                c = list(zip(*rows, strict=True))
                arrays = [pa.array(x, pa.int64()) for x in c[:7]] + ([pa.array(c[7], pa.binary())] if with_ids else [])
                yield pa.RecordBatch.from_arrays(arrays, names=["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "ids"][: len(arrays)])

    schema = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long" + (", ids binary" if with_ids else "")
    return placed.mapInArrow(run, schema)
