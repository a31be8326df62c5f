"""Toxicity by weak supervision: lexicon and pattern voters, a generative label model, a linear classifier.

Voters look for words of fixed lexicons, for shouting patterns, and for word shapes (words and word beginnings) mined
from labelled rows of the learning folds. All documents are voted on; the counts of vote patterns (at most 2 to the
number of voters) feed a latent-class model that estimates how often each voter fires on toxic and on clean texts and
which voters are correlated within a class, whose shared evidence is divided, anew in every round. Its posteriors are
the labels of a linear classifier, which scores the documents; it learns from labelled rows and from rows without a
label alike, as the posterior needs none.

Mining uses at most ``max_labelled`` labelled rows, chosen by a hash of their id, the classifier these and at most
``max_unlabelled`` others, chosen by a hash of the row; votes, pattern counts and scores cover every document.
Labels, language, source and id are no inputs of a score.

Edge cases: null or empty texts get the score of a text without any feature; null ids are scored too, never learned
from; several labels of one id count as the largest; without labels the fixed voters alone decide; repeated rows get
equal scores; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import binary_column

MAX_LABELLED = 20_000
MAX_UNLABELLED = 10_000
MAX_UNITS = 512
MINED_VOTERS = 14
PREFIXES = (3, 4, 5, 6, 7, 8)
# Common insults by language, singular and plural.
LEXICONS = {
    "en": "idiot idiots moron morons stupid loser losers scum trash clown clowns pathetic worthless disgusting dumb jerk jerks fool fools imbecile bastard bastards retard ugly filthy vermin".split(),
    "de": "idiot idioten dumm dummkopf trottel arschloch abschaum versager widerlich wertlos erbärmlich dreckig mistkerl".split(),
    "es": "idiota idiotas estúpido estúpida imbécil basura asqueroso asquerosa payaso patético inútil escoria tonto".split(),
    "fr": "idiot idiote imbécile stupide connard salaud ordure minable pathétique dégoûtant nul abruti racaille".split(),
}
PATTERNS = ("exclaims", "shouts")
FIXED = [*LEXICONS, *PATTERNS]
EDGES = ".,;:!?'\"()[]{}<>-_*#$%&|~`/\\+=^@…«»“”„’‘"


def shape(word: bytes) -> str:
    return word.decode("utf-8", "replace").lower().strip(EDGES)


def units_of(word: str) -> list[str]:
    """The word, and its beginnings (marked with a star)."""
    return ([word] if word else []) + [word[:n] + "*" for n in PREFIXES if len(word) > n]


@dataclass
class Voters:
    """What votes: mined units beside the fixed lexicons, and the units the classifier looks at."""

    mined: list[str] = field(default_factory=list)
    units: list[str] = field(default_factory=list)

    def __post_init__(self) -> None:
        self.names = [*FIXED, *self.mined]
        self._unit_vote = {u: 1 << (len(FIXED) + i) for i, u in enumerate(self.mined)}
        self._lexicon = Counter()
        for i, words in enumerate(LEXICONS.values()):
            for w in words:
                self._lexicon[w] |= 1 << i
        self._index = {u: i for i, u in enumerate(self.units)}
        self._cache: dict[bytes, tuple[int, tuple[int, ...]]] = {}

    def __getstate__(self) -> tuple:
        return self.mined, self.units

    def __setstate__(self, state: tuple) -> None:
        self.mined, self.units = state
        self.__post_init__()

    def _word(self, word: bytes) -> tuple[int, tuple[int, ...]]:
        got = self._cache.get(word)
        if got is None:
            plain = shape(word)
            vote, found = self._lexicon.get(plain, 0), []
            for u in units_of(plain):
                vote |= self._unit_vote.get(u, 0)
                if u in self._index:
                    found.append(self._index[u])
            if len(self._cache) > 400_000:
                self._cache.clear()
            got = self._cache[word] = (vote, tuple(found))
        return got

    def votes(self, text: bytes | None) -> tuple[int, set[int]]:
        """Bits of the voters that fire, and the units found."""
        bits, found = 0, set()
        words = (text or b"").split()
        for vote, units in map(self._word, set(words)):
            bits |= vote
            if units:
                found.update(units)
        if words:
            if text.count(b"!") * 8 >= len(words):  # type: ignore[union-attr]
                bits |= 1 << len(LEXICONS)
            if sum(map(bytes.isupper, words)) * 3 >= len(words):
                bits |= 1 << (len(LEXICONS) + 1)
        return bits, found


def least_hashed(rows: DataFrame, n: int, most: int) -> DataFrame:
    """At most ``most`` of ``n`` rows, those of the least hash ``_h``. A cut well above that leaves few rows to be put in
    order, however many there are."""
    share = 1.5 * most / max(n, 1)
    if share < 1:
        rows = rows.where(F.pmod("_h", F.lit(1 << 52)) < F.lit(int(share * (1 << 52))))
    return rows.orderBy(F.pmod("_h", F.lit(1 << 52)), "_h", *(c for c in ("_id", "doc_id") if c in rows.columns)).limit(most)


def labelled_sample(docs: DataFrame, labels: DataFrame, learn, id_col: str, text_col: str, label_col: str, max_labelled: int) -> DataFrame:
    """(text, y) of at most ``max_labelled`` labelled learning rows; the sampled labels are few enough to broadcast."""
    known = labels.where(F.col(label_col).isNotNull()).groupBy(F.col(id_col).cast("long").alias("_id")).agg(F.max(label_col).cast("int").alias("y"))
    known = known.where(learn(F.col("_id"))).withColumn("_h", F.xxhash64("_id"))
    picked = least_hashed(known, known.count(), max_labelled).drop("_h")
    rows = docs.select(F.col(id_col).cast("long").alias("_id"), F.col(text_col).alias("text"))
    return rows.join(F.broadcast(picked), "_id").select("text", "y")


def mine_units(sample: DataFrame, n_toxic: int, n_clean: int, keep: int = MAX_UNITS) -> list[str]:
    """Units found far more often in toxic than in clean rows, best first; counted on the executors."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts: tuple[Counter, Counter] = (Counter(), Counter())
        known: dict[bytes, list[str]] = {}
        for batch in batches:
            for text, y in zip(binary_column(batch, "text").to_pylist(), batch.column(1).to_pylist(), strict=True):
                found: set[str] = set()
                for w in set((text or b"").split()):
                    if w not in known:
                        if len(known) > 400_000:
                            known.clear()
                        known[w] = units_of(shape(w))
                    found.update(known[w])
                counts[1 if y else 0].update(found)
        # all units of both classes: a clean count may come from a task without any toxic row that has the unit
        units = list(counts[0] | counts[1])
        yield pa.RecordBatch.from_arrays([pa.array(units, pa.string()), pa.array([counts[1][u] for u in units], pa.int64()), pa.array([counts[0][u] for u in units], pa.int64())], names=["unit", "toxic", "clean"])

    each = sample.mapInArrow(count, "unit string, toxic long, clean long").groupBy("unit").agg(F.sum("toxic").alias("t"), F.sum("clean").alias("c"))
    odds = F.log((F.col("t") + 0.5) / (n_toxic + 1)) - F.log((F.col("c") + 0.5) / (n_clean + 1))
    best = each.where((F.col("t") >= 3) & (odds > 2.0)).orderBy((odds * F.col("t")).desc(), "unit").limit(keep)
    return [r.unit for r in best.collect()]


class LabelModel:
    """Latent class model of the votes, fitted to pattern counts; patterns of labelled rows hold their class.

    A voter that does not fire abstains; that none fires at all is the vote of one more voter, for clean."""

    def __init__(self, n_voters: int):
        self.prior = 0.1
        self.fire = np.tile([[0.01], [0.3]], n_voters + 1)  # by class, by voter
        self.fire[:, -1] = 0.9, 0.2
        self.share = np.ones(n_voters + 1)

    @staticmethod
    def _with_none(votes: np.ndarray) -> np.ndarray:
        return np.hstack([votes, (votes.sum(axis=1) == 0)[:, None].astype(float)])

    def _log_odds(self, votes: np.ndarray) -> np.ndarray:
        on = np.log(self.fire[1] / self.fire[0]) * self.share
        return np.log(self.prior / (1 - self.prior)) + self._with_none(votes) @ on

    def posterior(self, votes: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self._log_odds(votes), -30, 30)))

    def fit(self, votes: np.ndarray, counts: np.ndarray, held: np.ndarray, rounds: int = 60) -> LabelModel:
        """votes: patterns by voters (0/1); counts: documents with each; held: labelled (clean, toxic) rows of each."""
        total_held = held.sum(axis=1)
        for step in range(rounds):
            p = self.posterior(votes)
            free = np.maximum(counts - total_held, 0)
            w1, w0 = free * p + held[:, 1], free * (1 - p) + held[:, 0]
            self.prior = float(np.clip(w1.sum() / max(w1.sum() + w0.sum(), 1), 1e-4, 0.5))
            for c, w in ((0, w0), (1, w1)):
                self.fire[c] = np.clip((w @ self._with_none(votes) + 0.1) / (w.sum() + 1.0), 1e-5, 1 - 1e-5)
            if step >= rounds // 4:  # once the classes have parted; halfway to the new value, so that rounds settle
                self.share = (self.share + np.append(self._shares(votes, w0, w1), 1.0)) / 2
        return self

    @staticmethod
    def _shares(votes: np.ndarray, w0: np.ndarray, w1: np.ndarray) -> np.ndarray:
        """One over one plus the correlations, within each class, of a voter with the others: doubles count once."""
        n = votes.shape[1]
        extra = np.zeros(n)
        for w in (w0, w1):
            if w.sum() <= 1:
                continue
            centred = votes - (w @ votes) / w.sum()
            cov = (centred * w[:, None]).T @ centred / w.sum()
            sd = np.sqrt(np.clip(np.diag(cov), 1e-12, None))
            corr = np.clip(cov / np.outer(sd, sd), 0, 1)
            np.fill_diagonal(corr, 0)
            extra = np.maximum(extra, np.where(corr > 0.5, corr, 0).sum(axis=1))
        return 1 / (1 + extra)


def _pattern_counts(docs: DataFrame, shared: object, columns: list[str]) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts: Counter = Counter()
        for batch in batches:
            ys = batch.column(1).to_pylist() if len(columns) > 1 else [-1] * batch.num_rows
            counts.update((shared.value.votes(t)[0], y) for t, y in zip(binary_column(batch, "text").to_pylist(), ys, strict=True))
        if counts:
            keys = list(counts)
            yield pa.RecordBatch.from_arrays([pa.array([k[0] for k in keys], pa.int64()), pa.array([k[1] for k in keys], pa.int32()), pa.array([counts[k] for k in keys], pa.int64())], names=["votes", "y", "n"])

    return docs.select(*columns).mapInArrow(run, "votes long, y int, n long").groupBy("votes", "y").agg(F.sum("n").alias("n"))


def _features(sample: DataFrame, shared: object) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            got = [shared.value.votes(t) for t in binary_column(batch, "text").to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array([g[0] for g in got], pa.int64()), pa.array([sorted(g[1]) for g in got], pa.list_(pa.int32())), batch.column(1)], names=["votes", "units", "y"])

    return sample.mapInArrow(run, "votes long, units array<int>, y int")


def bits(votes: np.ndarray, n: int) -> np.ndarray:
    return (votes[:, None] >> np.arange(n)[None, :] & 1).astype(float)


def choose_voters(units: list[str], rows: list[tuple[list[int], int]], most: int = MINED_VOTERS) -> list[str]:
    """Greedy cover of the toxic rows by units that seldom occur in clean ones; how far to trust each is the label model's
    business."""
    holds: list[set[int]] = [set() for _ in units]
    clean = np.zeros(len(units))
    for r, (found, y) in enumerate(rows):
        for u in found:
            if y:
                holds[u].add(r)
            else:
                clean[u] += 1
    left, chosen = {r for r, (_, y) in enumerate(rows) if y}, []
    while len(chosen) < most:
        gain = [len(h & left) if clean[u] <= 0.05 * len(h) else 0 for u, h in enumerate(holds)]
        best = max(range(len(units)), key=gain.__getitem__, default=None)
        if best is None or gain[best] < 2:
            break
        chosen.append(units[best])
        left -= holds[best]
    return chosen


def fit_linear(x: np.ndarray, target: np.ndarray, ridge: float = 0.05, rounds: int = 25) -> np.ndarray:
    """Logistic regression on soft labels, bias last, by damped Newton steps on at most ``max_labelled`` rows."""
    x = np.hstack([x, np.ones((len(x), 1))])
    w = np.zeros(x.shape[1])
    penalty = np.full(len(w), ridge)
    penalty[-1] = 1e-6

    def loss(w: np.ndarray) -> float:
        z = x @ w
        return float((np.logaddexp(0, z) - target * z).sum() + (penalty * w * w).sum() / 2)

    now = loss(w)
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        grad = x.T @ (p - target) + penalty * w
        hessian = (x * np.maximum(p * (1 - p), 1e-6)[:, None]).T @ x + np.diag(penalty)
        step, size = np.linalg.solve(hessian, grad), 1.0
        while size > 1e-3 and loss(w - size * step) > now:
            size /= 2
        new = loss(w - size * step)
        if new > now - 1e-7:
            break
        w, now = w - size * step, new
    return w


def toxicity(docs: DataFrame, labels: DataFrame, learn, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", max_labelled: int = MAX_LABELLED, max_unlabelled: int = MAX_UNLABELLED) -> DataFrame:
    """doc_id and score (0 to 1) of every row; ``learn`` says by id whether a row's label may be learned from."""
    context = docs.sparkSession.sparkContext
    sample = labelled_sample(docs, labels, learn, id_col, text_col, label_col, max_labelled)
    sizes = {bool(r.y): r.n for r in sample.groupBy("y").agg(F.count(F.lit(1)).alias("n")).collect()}
    units = mine_units(sample, sizes.get(True, 0), sizes.get(False, 0)) if sizes.get(True) else []
    if units:
        rows = [(r.units, r.y) for r in _features(sample, context.broadcast(Voters([], units))).collect()]
        voters = Voters(choose_voters(units, rows), units)
    else:
        voters = Voters()
    shared, n = context.broadcast(voters), len(voters.names)
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    everything = {r.votes: r.n for r in _pattern_counts(texts, shared, ["text"]).collect()}
    patterns = np.array(sorted(everything) or [0], np.int64)
    held = np.zeros((len(patterns), 2))
    learned = _features(sample, shared).collect() if sizes else []
    place = {int(v): i for i, v in enumerate(patterns)}
    for r in learned:
        if r.votes in place:
            held[place[r.votes], 1 if r.y else 0] += 1
    model = LabelModel(n).fit(bits(patterns, n), np.array([everything.get(int(v), 0) for v in patterns], float), held)
    # the classifier learns from the posteriors of the sampled rows
    others = least_hashed(texts.withColumn("_h", F.xxhash64("doc_id", "text")), sum(everything.values()), max_unlabelled)
    others = others.select("text", F.lit(None).cast("int").alias("y"))
    learned = learned + _features(others, shared).collect()
    votes = np.array([r.votes for r in learned] or list(patterns), np.int64)
    x = np.zeros((len(votes), n + len(units)), np.float64)
    x[:, :n] = bits(votes, n)
    for i, r in enumerate(learned):
        x[i, [n + u for u in r.units]] = 1.0
    weights = fit_linear(x, model.posterior(bits(votes, n)))
    known = context.broadcast(weights)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w, v = known.value, shared.value
        for batch in batches:
            scores = []
            for text in binary_column(batch, "text").to_pylist():
                vote, found = v.votes(text)
                z = w[-1] + sum(w[i] for i in range(n) if vote >> i & 1) + sum(w[n + u] for u in sorted(found))
                scores.append(float(1 / (1 + np.exp(-min(max(z, -30.0), 30.0)))))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(scores, pa.float64())], names=["doc_id", "score"])

    return texts.mapInArrow(run, "doc_id long, score double")
