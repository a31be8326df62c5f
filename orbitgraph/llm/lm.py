"""Language-model scoring with a weighted backoff automaton.

Documents are packed into blocks of token numbers once. Each block asks for the corpus counts of its own distinct words
and n-grams: packed requests go to buckets by hash, where the counts of all blocks add up, and only what a block does
not know already returns. N-grams that most blocks hold would make hot buckets: a sample of blocks finds the
commonest (it steers only where counts add up), every task adds up its own counts of these, and their sums are few
enough to broadcast. A block then holds the part of the model that its documents can reach: states are contexts seen in
training, arcs are seen n-grams, and a failure arc leads from every context to its shorter one. One traversal from left
to right carries the state of every document and adds up log10 probabilities; as a state knows at most ``order - 1``
words, long documents are walked in pieces side by side, each from that many words before it.

Smoothing: a word seen c times has (c - d)/N, unseen words together d V/N, with the discount d = n1/(n1 + 2 n2); an
n-gram has (c + m p)/(c(context) + m), p being its probability in the shorter context, so a failure arc weighs
m/(c(context) + m). Over the known words, the end and one class for all unknown words it adds up to one.

Words are counted by their text, n-grams by a hash of their words that has ``SPARE_BITS`` more bits than the corpus has
tokens (64 at most): one n-gram in some sixteen millions shares its hash with another. Counts are 64-bit throughout.

Edge cases: null or empty text is the end alone; rows with a null id are learned from and not held out; repeated rows
count repeatedly; a table without learning rows gives every token the class of unknown words; an empty table gives an
empty result; other columns are ignored.
"""

from __future__ import annotations

from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import binary_column, materialise, mix, slices

BLOCK_BYTES = 5 << 20
BUCKET_GRAMS = 500_000
LEAST_BUCKETS = 32
BUCKETS_A_TASK = 8
ORDER = 3
MASS = (100.0, 10.0)  # of the shorter context against contexts of one word, of two, ...; the last holds for longer ones
SPARE_BITS = 24
HOT_GRAMS = 16_384  # of each level: the commonest, counted by sums
HOT_SHARE = 0.25  # of the sampled blocks that hold a hot n-gram
SAMPLE_BLOCKS = 16
SEGMENT = 4_096  # hot counts that travel in one row
SALTS = 16
PIECE = 1_024  # tokens walked in one go
END, START = "\n</s>", "\n<s>"  # no word has a line feed
ANSWERS = "block long, level int, bucket int, payload binary, stats array<bigint>"


def _squeeze(values: np.ndarray) -> bytes:
    data = values.tobytes()
    return len(data).to_bytes(8, "little") + pa.compress(data, codec="zstd", asbytes=True)


def _unsqueeze(data: bytes, kind: str) -> np.ndarray:
    return np.frombuffer(pa.decompress(data[8:], decompressed_size=int.from_bytes(data[:8], "little"), codec="zstd", asbytes=True), kind)


def _squeeze_sorted(values: np.ndarray) -> bytes:
    """Ascending 64-bit values: gaps, byte by byte of their width, so that leading zeros vanish."""
    gaps = np.diff(values, prepend=np.uint64(0))
    return _squeeze(np.ascontiguousarray(gaps.view(np.uint8).reshape(-1, 8).T))


def _unsqueeze_sorted(data: bytes) -> np.ndarray:
    planes = _unsqueeze(data, "u1").reshape(8, -1)
    return np.cumsum(np.ascontiguousarray(planes.T).view("<u8").ravel(), dtype=np.uint64)


def blocks_of(docs: DataFrame, held_out: Column, id_col: str, text_col: str) -> DataFrame:
    """Shared table of blocks: ids, held-out flags, token offsets, token numbers and the block's own vocabulary."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, number = TaskContext.get().partitionId(), 0
        for batch in batches:
            texts = binary_column(batch, "text")
            for a, b in slices(pc.fill_null(pc.binary_length(texts), 0).to_pylist(), BLOCK_BYTES):
                vocabulary: dict[bytes, int] = {}
                tokens, offsets = array("I"), [0]
                for text in texts.slice(a, b - a).to_pylist():
                    words = (text or b"").lower().split()
                    for w in set(words):
                        vocabulary.setdefault(w, len(vocabulary))
                    tokens.extend(map(vocabulary.__getitem__, words))
                    offsets.append(len(tokens))
                ids = batch.column(0).slice(a, b - a)
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array([(part << 32) + number], pa.int64()),
                        pa.array([len(tokens) + b - a], pa.int64()),
                        pa.array([ids.to_pylist()], pa.list_(pa.int64())),
                        pa.array([batch.column(1).slice(a, b - a).to_pylist()], pa.list_(pa.bool_())),
                        pa.array([_squeeze(np.asarray(offsets, np.int64))], pa.binary()),
                        pa.array([_squeeze(np.frombuffer(tokens, np.uint32) if tokens else np.zeros(0, np.uint32))], pa.binary()),
                        pa.array([b"\n".join(vocabulary)], pa.binary()),
                    ],
                    names=["block", "n", "ids", "held", "offsets", "tokens", "words"],
                )
                number += 1

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(held_out, F.lit(False)).alias("held"), F.col(text_col).alias("text"))
    schema = "block long, n long, ids array<bigint>, held array<boolean>, offsets binary, tokens binary, words binary"
    return materialise(rows.mapInArrow(run, schema), "lm-blocks")


class Hot:
    """The hot n-grams of each level as sorted hashes."""

    def __init__(self, hashes: list[np.ndarray]):
        self.hashes = hashes

    def find(self, level: int, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Which hashes are hot, and the places of these."""
        known = self.hashes[level]
        if not len(known):
            return np.zeros(len(hashes), bool), np.zeros(0, np.int64)
        at = np.minimum(np.searchsorted(known, hashes), len(known) - 1)
        hot = known[at] == hashes
        return hot, at[hot]


class Block:
    """A block's documents as token numbers with start and end, and its distinct n-grams by level."""

    def __init__(self, held: list[bool], offsets: bytes, tokens: bytes, words: bytes, order: int, bits: int):
        self.words = words.split(b"\n") if words else []
        self.held = np.asarray(held, bool)
        inner, at = _unsqueeze(tokens, "<u4"), _unsqueeze(offsets, "<i8")
        n, docs = np.diff(at), len(at) - 1
        self.end, self.start, self.width = len(self.words), len(self.words) + 1, len(self.words) + 2
        self.first = at[:-1] + 2 * np.arange(docs)  # place of each document's start
        self.length = n + 1  # tokens with the end, without the start
        self.tokens = np.full(len(inner) + 2 * docs, self.end, np.int32)
        self.tokens[self.first] = self.start
        self.tokens[np.arange(len(inner)) + np.repeat(2 * np.arange(docs) + 1, n)] = inner
        place = (np.arange(len(self.tokens)) - np.repeat(self.first, n + 2)).astype(np.int32)
        learn = np.repeat(~self.held, n + 2)
        hashes = np.array([*map(xxhash.xxh3_64_intdigest, [*self.words, END.encode(), START.encode()])], np.uint64)
        self.counts = [np.bincount(self.tokens[learn], minlength=self.width).astype(np.int64)]
        self.hashes, self.at = [hashes], [self.tokens]
        self.seen_at = [np.zeros(0, np.int64)]
        whole = hashes  # hashes of all their bits make those of longer n-grams
        for k in range(1, order):
            here = np.flatnonzero(place >= k)
            keys = self.at[k - 1][here - 1].astype(np.int64) * self.width + self.tokens[here]
            by = np.argsort(keys)
            keys = keys[by]
            new = np.append(np.ones(min(len(keys), 1), bool), keys[1:] != keys[:-1])
            ids = np.full(len(self.tokens), -1, np.int32)
            ids[here[by]] = np.cumsum(new) - 1
            inverse = ids[here]
            seen = here[by[new]]  # a place of each distinct n-gram
            del by, keys, new
            whole = mix(whole[self.at[k - 1][seen - 1]] * np.uint64(0x9E3779B97F4A7C15) + hashes[self.tokens[seen]])
            self.at.append(ids)
            self.seen_at.append(seen)
            self.hashes.append(whole >> np.uint64(64 - bits) << np.uint64(64 - bits))
            self.counts.append(np.bincount(inverse, weights=learn[here], minlength=len(seen)).astype(np.int64))

    def deal(self, level: int, buckets: int, hot: Hot) -> tuple[np.ndarray, np.ndarray]:
        """Order of the level's n-grams, the hot ones apart, by hash, and where each bucket (a range of hashes) begins."""
        cold = np.flatnonzero(~hot.find(level, self.hashes[level])[0])
        hashes = self.hashes[level][cold]
        order = np.argsort(hashes)
        bucket = ((hashes[order] >> np.uint64(32)) * np.uint64(buckets)) >> np.uint64(32)
        return cold[order], np.searchsorted(bucket, np.arange(buckets + 1))


def _block_of(row: dict, order: int, bits: int) -> Block:
    return Block(row["held"], row["offsets"], row["tokens"], row["words"], order, bits)


def _wide(values: np.ndarray) -> bytes:
    """64-bit counts as bytes of equal weight together, so that their leading zeros vanish."""
    return _squeeze(np.ascontiguousarray(values.astype("<u8").view(np.uint8).reshape(-1, 8).T))


def _unwide(data: bytes) -> np.ndarray:
    return np.ascontiguousarray(_unsqueeze(data, "u1").reshape(8, -1).T).view("<i8").ravel()


def _common(order: int, bits: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                block = _block_of(row, order, bits)
                for level in range(order):
                    often = np.flatnonzero(block.counts[level] >= 4)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(often), level, np.int32)), pa.array(block.hashes[level][often].view(np.int64)), pa.array(block.counts[level][often])], names=["level", "gram", "n"])

    return run


def hot_grams(blocks: DataFrame, n_blocks: int, order: int, bits: int) -> Hot:
    """The commonest n-grams of a sample of blocks: at most ``HOT_GRAMS`` of each level come to the driver."""
    every = max(1, n_blocks // SAMPLE_BLOCKS)
    sample = blocks.where(F.pmod(F.xxhash64("block"), F.lit(every)) == 0).select("held", "offsets", "tokens", "words")
    held = sample.mapInArrow(_common(order, bits), "level int, gram long, n long").groupBy("level", "gram").agg(F.count(F.lit(1)).alias("blocks"), F.sum("n").alias("n"))
    found: list[np.ndarray] = []
    for level in range(order):
        best = held.where((F.col("level") == level) & (F.col("blocks") >= max(2, HOT_SHARE * n_blocks / every))).orderBy(F.desc("n"), "gram").limit(HOT_GRAMS)
        found.append(np.array(sorted(r.gram & ((1 << 64) - 1) for r in best.select("gram").collect()), np.uint64))
    return Hot(found)


REQUESTS = "key long, block long, level int, bucket int, grams binary, counts binary"


def _rows(rows: list[tuple]) -> pa.RecordBatch:
    c = list(zip(*rows, strict=True))
    kinds = (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.binary(), pa.binary())
    return pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(c, kinds, strict=True)], names=["key", "block", "level", "bucket", "grams", "counts"])


def _requests(order: int, buckets: int, bits: int, shared: object):
    """Requests of each block, and (block -2, a negative key) the task's own counts of hot n-grams."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hot, salt = shared.value, TaskContext.get().partitionId() % SALTS
        sums = [np.zeros(len(h), np.int64) for h in hot.hashes]
        for batch in batches:
            for row in batch.to_pylist():
                block = _block_of(row, order, bits)
                texts = [*block.words, END.encode()[1:], START.encode()[1:]]
                for level in range(order):
                    is_hot, places = hot.find(level, block.hashes[level])
                    sums[level] += np.bincount(places, weights=block.counts[level][is_hot], minlength=len(sums[level])).astype(np.int64)
                    by, starts = block.deal(level, buckets, hot)
                    rows = []
                    for b in np.flatnonzero(np.diff(starts)).tolist():
                        mine = by[starts[b] : starts[b + 1]]
                        # words of a text never begin with a blank, which marks the two special tokens
                        if level == 0:
                            what = _squeeze(np.frombuffer(b"\n".join(b" " + texts[i] if i >= block.end else texts[i] for i in mine.tolist()), np.uint8))
                        else:
                            what = _squeeze_sorted(block.hashes[level][mine] >> np.uint64(64 - bits))
                        rows.append((b * order + level, row["block"], level, b, what, _squeeze(block.counts[level][mine].astype("<u4"))))
                    if rows:
                        yield _rows(rows)
        for level, total in enumerate(sums):
            for a in range(0, len(total), SEGMENT):
                if total[a : a + SEGMENT].any():
                    segment = a // SEGMENT
                    yield _rows([(-1 - ((segment * order + level) * SALTS + salt), -2, level, segment, b"", _wide(total[a : a + SEGMENT]))])

    return run


def _answers(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Sorted by key (bucket and level): adds up the counts of each key's blocks and returns what differs.

    It also gives (block -1) the sums that the model needs for each bucket of words: tokens, types, and words seen once
    and twice; and (block -2) sums of hot counts."""
    held: list[dict] = []

    def batch_of(out: list[tuple]) -> pa.RecordBatch:
        c = list(zip(*out, strict=True))
        kinds = (pa.int64(), pa.int32(), pa.int32(), pa.binary(), pa.list_(pa.int64()))
        return pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(c, kinds, strict=True)], names=["block", "level", "bucket", "payload", "stats"])

    def settle() -> Iterator[pa.RecordBatch]:
        level, bucket = held[0]["level"], held[0]["bucket"]
        if held[0]["block"] == -2:
            yield batch_of([(-2, level, bucket, held[0]["counts"], None)])
            return
        counts = [_unsqueeze(r["counts"], "<u4").astype(np.int64) for r in held]
        flat = np.concatenate(counts)
        if level == 0:
            number: dict[bytes, int] = {}
            ids = np.fromiter((number.setdefault(w, len(number)) for r in held for w in _unsqueeze(r["grams"], "u1").tobytes().split(b"\n")), np.int64, len(flat))
            total = _sums(ids, flat, len(number))
            start = number.get(b" " + START.encode()[1:])
            stats = _stats(np.delete(total, start) if start is not None else total)
        else:
            _, ids = np.unique(np.concatenate([_unsqueeze_sorted(r["grams"]) for r in held]), return_inverse=True)
            total = _sums(ids, flat, int(ids.max()) + 1)
            stats = None
        out = [] if stats is None else [(-1, level, bucket, None, stats)]
        lo = 0
        for r, own in zip(held, counts, strict=True):
            mine = total[ids[lo : lo + len(own)]]
            lo += len(own)
            differ = np.flatnonzero(mine != own)
            if len(differ):
                out.append((r["block"], level, bucket, _wide(np.concatenate([np.diff(differ, prepend=0), mine[differ]])), None))
        if out:
            yield batch_of(out)

    for batch in batches:
        for row in batch.to_pylist():
            if held and held[0]["key"] != row["key"]:
                yield from settle()
                held.clear()
            if held and row["block"] == -2:  # one sum is held, however many tasks sent theirs
                held[0]["counts"] = _wide(_unwide(held[0]["counts"]) + _unwide(row["counts"]))
            else:
                held.append(row)
    if held:
        yield from settle()


def _sums(ids: np.ndarray, values: np.ndarray, n: int) -> np.ndarray:
    """64-bit sums by id (bincount's weights are floats, exact only below 2^53)."""
    out = np.zeros(n, np.int64)
    np.add.at(out, ids, values)
    return out


def _stats(counts: np.ndarray) -> list[int]:
    return [int(counts.sum()), int((counts > 0).sum()), int((counts == 1).sum()), int((counts == 2).sum())]


class Automaton:
    """States, arcs and failure arcs of the n-grams that a block can reach.

    State 0 is the empty context, then one for each context of one word, then those of more words. A state of j words has
    its arcs among the n-grams of j + 1 words, so the arc for the next token is the n-gram that ends there, and a number
    for each place and length says which: an arc that training never saw is dead."""

    def __init__(self, block: Block, totals: list[np.ndarray], stats: np.ndarray, mass: tuple[float, ...]):
        n, types, once, twice = (float(x) for x in stats)
        d = once / (once + 2 * twice) if once + twice > 0 else 0.5
        self.order = order = len(totals)
        weigh = lambda k: mass[min(k, len(mass)) - 1]
        c = totals[0].astype(float)
        unknown = d * types / n if n and types and d else 1.0 / max(n + 1, 1)
        p = [np.where(c > 0, (c - d) / max(n, 1), unknown)]
        word_state = np.where(c > 0, 1 + np.arange(block.width), 0) if order > 1 else np.zeros(block.width, np.int64)
        self.start = int(word_state[block.start])
        word_state[block.end] = 0
        fail, level = [np.zeros(1, np.int64), np.zeros(block.width, np.int64)], [np.zeros(1, np.int8), np.ones(block.width, np.int8)]
        fail_weight = [np.zeros(1), np.log10(weigh(1) / (c + weigh(1)))]
        arc_base, live, weights, nexts = [0], [np.ones(block.width, bool)], [np.log10(p[0])], [word_state]
        states = [np.where(c > 0, 1 + np.arange(block.width), 0)]
        base = 1 + block.width
        for k in range(1, order):
            seen, total = block.seen_at[k], totals[k].astype(float)
            context, word = block.at[k - 1][seen - 1], block.tokens[seen]
            shorter = block.at[k - 1][seen]
            p.append((total + weigh(k) * p[k - 1][shorter]) / (totals[k - 1][context] + weigh(k)))
            mine = np.where(total > 0, base + np.arange(len(total)), 0)
            arc_base.append(arc_base[-1] + len(live[-1]))
            live.append(total > 0)
            weights.append(np.log10(p[k]))
            nexts.append(np.where(word == block.end, 0, mine if k < order - 1 else states[k - 1][shorter]))
            if k < order - 1:
                fail.append(states[k - 1][shorter])
                fail_weight.append(np.log10(weigh(k + 1) / (total + weigh(k + 1))))
                level.append(np.full(len(total), k + 1, np.int8))
                base += len(total)
            states.append(mine)
        self.fail, self.fail_weight, self.level = np.concatenate(fail), np.concatenate(fail_weight), np.concatenate(level)
        self.live, self.weights, self.nexts = np.concatenate(live), np.concatenate(weights), np.concatenate(nexts)
        self.arc = np.stack(block.at)
        self.arc_base = np.array(arc_base)

    def step(self, state: np.ndarray, place: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Next states and log10 weights for the tokens at these places; failure arcs are followed to a live arc first."""
        level = self.level[state]
        arc = self.arc_base[level] + self.arc[level, place]
        weight = np.zeros(len(state))
        dead = np.flatnonzero(~self.live[arc])
        while len(dead):
            weight[dead] += self.fail_weight[state[dead]]
            state[dead] = self.fail[state[dead]]
            level = self.level[state[dead]]
            arc[dead] = self.arc_base[level] + self.arc[level, place[dead]]
            dead = dead[~self.live[arc[dead]]]
        return self.nexts[arc], weight + self.weights[arc]

    def score(self, block: Block) -> np.ndarray:
        """All pieces of all documents in step: at each place those that are long enough move on, longest first.

        The state before a token depends on the ``order - 1`` tokens before it alone, so a later piece walks these first,
        from the empty context, without adding up."""
        warm = self.order - 1
        pieces = (block.length + PIECE - 1) // PIECE
        doc = np.repeat(np.arange(len(pieces)), pieces)
        number = np.arange(len(doc)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
        lead = np.where(number > 0, warm, 0)
        first = block.first[doc] + 1 + number * PIECE - lead
        steps = np.minimum(block.length[doc] - number * PIECE, PIECE) + lead
        by = np.argsort(-steps, kind="stable")
        doc, first, steps, lead = doc[by], first[by], steps[by], lead[by]
        state, total = np.where(lead > 0, 0, self.start if warm else 0), np.zeros(len(by))
        state[number[by] == 0] = self.start
        active = len(by)
        for t in range(int(steps[0]) if len(by) else 0):
            while active and steps[active - 1] <= t:
                active -= 1
            state[:active], weight = self.step(state[:active].copy(), first[:active] + t)
            total[:active] += weight if t >= warm else np.where(lead[:active] > t, 0.0, weight)
        return np.bincount(doc, weights=total, minlength=len(block.length))


SCORES = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"


def _scores(order: int, buckets: int, bits: int, stats: np.ndarray, mass: tuple[float, ...], shared: object):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, types = int(stats[0]), int(stats[1])
        hot, sums = shared.value
        for batch in batches:
            for row in batch.to_pylist():
                block = _block_of(row, order, bits)
                totals, deals = [c.copy() for c in block.counts], []
                for k in range(order):
                    is_hot, places = hot.find(k, block.hashes[k])
                    totals[k][is_hot] = sums[k][places]
                    deals.append(block.deal(k, buckets, hot))
                for a in row["answers"] or ():
                    by, starts = deals[a["level"]]
                    gaps, counts = np.split(_unwide(a["payload"]), 2)
                    totals[a["level"]][by[starts[a["bucket"]] + np.cumsum(gaps)]] = counts
                score = Automaton(block, totals, stats, mass).score(block)
                inner = np.ones(len(block.tokens), bool)
                inner[block.first] = False
                doc = np.repeat(np.arange(len(block.length)), block.length)
                c = totals[0][block.tokens[inner]]
                base = np.bincount(doc, weights=np.log10((c + 1) / (n + types + 1)), minlength=len(block.length))
                known = np.bincount(doc, weights=c > 0, minlength=len(block.length)).astype(np.int64)
                m = len(block.length)
                yield pa.RecordBatch.from_arrays([pa.array(row["ids"], pa.int64()), pa.array(block.held), pa.array(block.length.astype(np.int64)), pa.array(known), pa.array(np.full(m, n, np.int64)), pa.array(base), pa.array(score)], names=["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"])

    return run


def score_documents(docs: DataFrame, held_out: Column, id_col: str = "doc_id", text_col: str = "text", order: int = ORDER, mass: float | tuple[float, ...] = MASS) -> DataFrame:
    """Base score and model score (log10) of every row; rows where ``held_out`` is true are not learned from."""
    mass = mass if isinstance(mass, tuple) else (mass,)
    context = docs.sparkSession.sparkContext
    blocks = blocks_of(docs, held_out, id_col, text_col)
    size = blocks.agg(F.sum("n").alias("tokens"), F.count(F.lit(1)).alias("blocks")).first()
    tokens = size.tokens or 0
    buckets = int(max(LEAST_BUCKETS, -(-tokens // BUCKET_GRAMS)))
    bits = min(64, int(tokens).bit_length() + SPARE_BITS)
    hot = hot_grams(blocks, size.blocks, order, bits)
    shared = context.broadcast(hot)
    requests = blocks.select("block", "held", "offsets", "tokens", "words").mapInArrow(_requests(order, buckets, bits, shared), REQUESTS)
    tasks = max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), buckets * order // BUCKETS_A_TASK // order)
    answers = materialise(requests.repartition(tasks, "key").sortWithinPartitions("key", "block").mapInArrow(_answers, ANSWERS), "lm-answers")
    stats = np.array([x or 0 for x in answers.where(F.col("block") == -1).agg(*(F.sum(F.get("stats", F.lit(i))).alias(f"s{i}") for i in range(4))).first()], np.int64)
    sums = [np.zeros(len(h), np.int64) for h in hot.hashes]
    for r in answers.where(F.col("block") == -2).select("level", "bucket", "payload").toLocalIterator():  # bounded: levels x segments x salts
        part = _unwide(r.payload)
        sums[r.level][r.bucket * SEGMENT : r.bucket * SEGMENT + len(part)] += part
    is_start = hot.hashes[0] == np.uint64(xxhash.xxh3_64_intdigest(START.encode()))
    stats = stats + np.array(_stats(sums[0][~is_start]), np.int64)
    mine = answers.where(F.col("block") >= 0).groupBy("block").agg(F.collect_list(F.struct("level", "bucket", "payload")).alias("answers"))
    joined = blocks.join(mine, "block", "left").select("held", "ids", "offsets", "tokens", "words", "answers")
    return joined.mapInArrow(_scores(order, buckets, bits, stats, mass, context.broadcast((hot, sums))), SCORES)
