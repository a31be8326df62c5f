import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from orbitgraph.llm import decontam
from orbitgraph.llm.common import hashed_words


def edited(rng, words, edits, kind):
    """Exactly ``edits`` word edits, spread evenly for every other passage."""
    words = list(words)
    even = rng.random() < 0.5
    places = [round((k + 1) * len(words) / (edits + 1)) for k in range(edits)] if even else sorted(rng.sample(range(len(words)), edits))
    for at in reversed(places):
        act = rng.choice(["replace", "delete", "insert"]) if kind == "mixed" else kind
        at = min(at, len(words) - 1)
        words[at : at + (act != "insert")] = [] if act == "delete" else [f"q{rng.randrange(10**9)}"]
    return words


@pytest.mark.parametrize("kind", ["replace", "delete", "insert", "mixed"])
def test_recall_of_every_length_at_the_edit_limit(kind):
    rng = random.Random(3)
    prose = lambda n: [f"w{rng.randrange(3000)}" for _ in range(n)]
    bench = [(n, prose(n)) for n in range(1, 61)]
    items = decontam.Items([(i, " ".join(w).encode()) for i, w in bench])
    docs, want, each = [], {}, 60
    for item, words in bench:
        for _ in range(each):
            passage = edited(rng, words, decontam.allowed_edits(item, decontam.MIN_SIMILARITY), kind)
            want.setdefault(item, set()).add(len(docs))
            docs.append(" ".join(prose(rng.randrange(40)) + passage + prose(rng.randrange(40))).encode())
    flat, offsets = hashed_words(docs, decontam.PlainWordHash())
    got = {(d, m[0]) for d, m in decontam._matches(items, flat, offsets, decontam.MIN_SIMILARITY)}
    recall = {n: sum((d, n) in got for d in ds) / len(ds) for n, ds in want.items()}
    print({n: round(r, 3) for n, r in recall.items() if r < 1})
    assert all(recall[n] == 1 for n in range(1, decontam.EXACT_WORDS + 1))
    assert min(recall.values()) >= 0.95
    assert np.mean(list(recall.values())) >= decontam.TARGET_RECALL


def test_a_higher_target_takes_more_repetitions():
    low, high = (decontam.repetitions_for(42, 0.8, t, 3) for t in (0.8, 0.999))
    assert 1 <= low < high


def test_five_words_with_the_middle_one_replaced():
    items = decontam.Items([(1, b"alpha beta gamma delta epsilon")])
    flat, offsets = hashed_words([b"x y alpha beta other delta epsilon z"], decontam.PlainWordHash())
    assert [m for _, m in decontam._matches(items, flat, offsets, 0.8)] == [(1, 2, 5, 5, 1, 0.8)]


def brute(docs, bench):
    """Least word edits of each item against any run of words of each document."""
    plain = lambda t: decontam.PlainWordHash and [w.decode("utf-8", "replace").lower().encode().strip(decontam.MARKS) or w for w in (t or "").encode().split()]
    out = {}
    for d, t in docs:
        words = plain(t)
        for i, b in bench:
            item = plain(b)
            if not item:
                continue
            row = [0] * (len(words) + 1)
            for k, w in enumerate(item):
                new = [k + 1]
                for j, x in enumerate(words):
                    new.append(min(row[j] + (w != x), row[j + 1] + 1, new[j] + 1))
                row = new
            if min(row) <= decontam.allowed_edits(len(item), 0.8):
                out[d, i] = min(row)
    return out


def test_whole_result_against_brute_force(spark):
    rng = random.Random(5)
    prose = lambda n: [f"w{rng.randrange(300)}" for _ in range(n)]
    bench = [(i, " ".join(prose(n))) for i, n in enumerate([1, 3, 5, 8, 12, 13, 14, 17, 22, 30, 41, 55])] + [(90, None), (91, ""), (92, "twin words stand here now"), (93, "twin words stand here now")]
    docs = []
    for i in range(60):
        item = bench[i % 12][1].split()
        most = decontam.allowed_edits(len(item), 0.8)
        middle = edited(rng, item, rng.randrange(most + 2) if len(item) > most + 1 else 0, "mixed")
        docs.append((i, " ".join(prose(rng.randrange(30)) + middle + prose(rng.randrange(30)))))
    docs += [(100, None), (101, ""), (102, "Twin, words stand HERE now! twin words stand here now"), (103, docs[5][1]), (103, docs[5][1]), (None, docs[8][1])]
    want = brute([d for d in docs if d[0] is not None], bench)
    frame = spark.createDataFrame(docs, "doc_id long, text string").withColumns({"item_id": F.lit("clash"), "edits": F.lit(0)})
    got = decontam.contamination(frame, spark.createDataFrame(bench, "item_id long, text string")).collect()
    assert {(r.doc_id, r.item_id): r.edits for r in got if r.doc_id is not None} == want
    assert sum(r.doc_id == 103 for r in got) == 2 * len({k for k in want if k[0] == 103}) and any(r.doc_id is None for r in got)
    tie = [r for r in got if r.doc_id == 102 and r.item_id in (92, 93)]
    assert {(r.item_id, r.start_word, r.edits) for r in tie} == {(92, 0, 0), (93, 0, 0)}
    blocks = decontam.contamination(frame, spark.createDataFrame(bench, "item_id long, text string"), block_words=20).collect()
    assert sorted(map(str, blocks)) == sorted(map(str, got))


def test_long_text_holds_its_passage(spark):
    rng = random.Random(8)
    words = [f"w{rng.randrange(5000)}" for _ in range(200_000)]
    item = [f"b{k}" for k in range(24)]
    words[150_000:150_000] = item[:20] + ["other"] + item[21:]
    docs = spark.createDataFrame([(1, " ".join(words)), (2, "short")], "doc_id long, text string")
    got = decontam.contamination(docs, spark.createDataFrame([(7, " ".join(item))], "item_id long, text string")).collect()
    assert [(r.doc_id, r.start_word, r.edits) for r in got] == [(1, 150_000, 1)]
