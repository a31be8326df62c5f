"""The ten operators against brute force, on small tables with nulls, empty, long, tied and repeated rows."""

import base64
import collections
import hashlib
import math
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from orbitgraph.llm import components, decontam, html, linededup, lm, neardup, packing, quality, substring, toxicity, warc

WORDS = re.compile(r"[^\x20\x09-\x0D]+")
DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def prose(rng, n, vocabulary=400):
    common = ["the", "of", "and", "to", "in", "is", "that", "for"]
    return " ".join(rng.choice(common) if rng.random() < 0.4 else f"w{rng.randrange(vocabulary)}" for _ in range(n))


def corpus():
    rng = random.Random(11)
    base, passage = prose(rng, 120), prose(rng, 60)
    line = "this line of more than forty characters stands in many documents"
    texts = [prose(rng, 80 + 5 * i) for i in range(20)]
    texts += [base] * 4 + [base.replace("w1", "w2", 1), base + " extra words here", base.upper()]
    texts += [prose(rng, 30) + " " + passage + " " + prose(rng, 30) for _ in range(6)]
    texts += [f"{prose(rng, 9)}\n{'  ' if i % 2 else ''}{line.upper() if i % 3 else line}\n{prose(rng, 9)}" for i in range(7)]
    texts += [None, "", " \t\n ", "one", "four words in all", "ünï cödé   words", "a" * 300, "x " * 3000, "\n\n\n"]
    rows = [(3 * i + 1, t, "en" if i % 5 else None, "s", None) for i, t in enumerate(texts)]
    return rows + [rows[0], (None, texts[1], None, None, None)]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(corpus(), DOCS).withColumns({"quality": F.lit(1), "_q": F.lit("clash")}).repartition(3).persist()


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DOCS)


def unique_rows():
    seen, out = set(), []
    for r in corpus():
        if r[0] is not None and r[0] not in seen:
            seen.add(r[0])
            out.append((r[0], r[1] or ""))
    return out


# --- quality ---------------------------------------------------------------------------------------------------------
def test_quality_counts(docs):
    got = quality.quality_rules(docs, columns=["doc_id", "text"]).collect()
    assert len(got) == len(corpus())
    for r in got:
        text, q = r.text or "", r.quality
        words = WORDS.findall(text)
        lines = [x for x in text.split("\n") if WORDS.search(x)]
        windows = collections.Counter(zip(words, words[1:], words[2:], strict=False))
        covered = {i + k for i in range(len(words) - 2) if windows[tuple(words[i : i + 3])] > 1 for k in range(3)}
        assert q.n_words == len(words) and q.word_chars == sum(map(len, words))
        assert q.n_symbols == len(re.findall(r"[#*$%&|<>]", text)) and q.n_dup_lines == len(lines) - len(set(lines))
        assert q.n_repeat_words == len(covered)
        assert q.base_failed == (len(words) < 50 or 100 * len(covered) > 50 * len(words))
        assert not (q.base_failed and q.kept)


def test_quality_rejects_symbols_and_keeps_prose(spark):
    rng = random.Random(2)
    rows = [(i, prose(rng, 200), "en") for i in range(40)] + [(100, " ".join(w + "%%%***" for w in prose(rng, 200).split()), "en")]
    kept = {r.doc_id: r.quality.kept for r in quality.quality_rules(spark.createDataFrame(rows, "doc_id long, text string, lang string")).collect()}
    assert not kept[100] and all(v for k, v in kept.items() if k < 100)


def test_js_distance(spark):
    row = spark.range(1).select(quality.js_distance(F.array(F.lit(1.0), F.lit(0.0)), F.array(F.lit(0.0), F.lit(1.0))).alias("far"), quality.js_distance(F.array(F.lit(0.5), F.lit(0.5)), F.array(F.lit(0.5), F.lit(0.5))).alias("same")).first()
    assert row.far == pytest.approx(1.0) and row.same == pytest.approx(0.0)


# --- line dedup ------------------------------------------------------------------------------------------------------
def brute_lines(rows, min_chars=40, min_docs=5):
    table = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    key = lambda x: x.strip(" \t\n\x0b\x0c\r").translate(table)
    held = collections.defaultdict(set)
    for d, t in rows:
        for x in t.split("\n"):
            if len(key(x)) >= min_chars:
                held[key(x)].add(d)
    last = {k: max(v) for k, v in held.items() if len(v) >= min_docs}
    return {d: "\n".join(x for x in t.split("\n") if last.get(key(x), d) == d) for d, t in rows}


@pytest.mark.parametrize("broadcast_keys", [1000, 0])
def test_line_dedup(docs, broadcast_keys):
    want = brute_lines(unique_rows())
    got = linededup.drop_lines(docs, broadcast_keys=broadcast_keys).collect()
    assert len(got) == len(corpus())
    for r in got:
        if r.doc_id is not None:
            assert r.kept_text == want[r.doc_id] and r.n_lines == len((r.text or "").split("\n"))
    assert sum(r.n_dropped for r in got) > 0


def test_line_filters_miss_nothing():
    rng = np.random.default_rng(0)
    packed, at = np.zeros(1 << 10, np.uint8), np.unique(rng.integers(0, 1 << 13, 900))
    linededup._set_bits(packed, at)
    assert (np.flatnonzero(np.unpackbits(packed)) == at).all() and linededup._get_bits(packed, at).all()


@pytest.mark.parametrize("shards", [1, 3, 500])
def test_line_shards_agree(shards):
    """Two slices that share two keys, and one with a key in two documents: all three are suspected, whatever the shards."""
    import pyarrow as pa
    import xxhash

    digest = lambda i: xxhash.xxh3_128_digest(b"%d" % i)
    slices_ = {1: [[1, 2, 3], [4, 5]], 2: [[2, 4, 6]], 3: [[7, 8], [8, 9]]}
    flat = {s: b"".join(digest(i) for doc in docs for i in doc) for s, docs in slices_.items()}
    batch = pa.RecordBatch.from_arrays([pa.array(list(flat)), pa.array(list(flat.values()), pa.binary())], names=["slice", "digests"])
    parts = pa.Table.from_batches(linededup._filters(shards)(iter([batch]))).sort_by("shard").to_batches()
    answers = pa.Table.from_batches(linededup._merge(iter(parts))).to_pylist()
    got = set()
    for s, docs in slices_.items():
        mine = [a for a in answers if a["slice"] == s]
        table = pa.Table.from_pylist([{"docs": np.arange(len(docs)).astype("<i8").tobytes(), "offsets": np.cumsum([0, *map(len, docs)]).astype("<i8").tobytes(), "digests": flat[s], "answers": mine}])
        got |= {(s, k) for out in linededup._suspects(shards)(iter(table.to_batches())) for k in out.column(0).to_pylist()}
    assert got == {(s, digest(i)) for s, i in ((1, 2), (2, 2), (1, 4), (2, 4), (3, 8))}


# --- near duplicates -------------------------------------------------------------------------------------------------
def brute_near(rows, percent):
    sets = {}
    for d, t in rows:
        w = re.findall(rb"[^\x20\x09-\x0D]+", t.encode().lower())
        sets[d] = {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())
    up = {d: d for d in sets}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            if sets[a] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                x, y = sorted((root(a), root(b)))
                up[y] = x
    return {d: (len(s), root(d)) for d, s in sets.items()}


def test_near_duplicates(docs):
    want = brute_near(unique_rows(), 85)
    got = neardup.near_duplicates(docs).collect()
    assert len(got) == len(corpus())
    for r in got:
        if r.doc_id is not None:
            assert (r.n_shingles, r.component_id, r.kept) == (*want[r.doc_id], want[r.doc_id][1] == r.doc_id)
    assert len({r.component_id for r in got}) < len(got) - 4


def test_near_duplicates_in_blocks(spark, monkeypatch):
    """Groups beyond two blocks are worked off in pairs of blocks, with the same result."""
    monkeypatch.setattr(neardup, "BLOCK", 4)
    rng = random.Random(3)
    base = prose(rng, 150).split()
    rows = []
    for i in range(60):
        w = list(base)
        for _ in range(rng.randrange(4)):
            w[rng.randrange(len(w))] = f"z{rng.randrange(10**6)}"
        rows.append((i, " ".join(w)))
    want = brute_near(rows, 85)
    got = neardup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in got} == want


def test_sketch_estimate_and_merge():
    rng = np.random.default_rng(1)
    a, b = rng.integers(0, 1 << 63, 900, dtype=np.uint64), rng.integers(0, 1 << 63, 900, dtype=np.uint64)
    b[:600] = a[:600]
    regs = neardup.sketch(np.concatenate([a, b, np.union1d(a, b)]), np.array([0, 900, 1800, 1800 + len(np.union1d(a, b))]))
    assert (neardup.merge(regs[0], regs[1]) == regs[2]).all()
    above, equal = (regs[0] > regs[1]).sum(), (regs[0] == regs[1]).sum()
    got = neardup.likely_overlap(np.array([above]), np.array([80 - above - equal]), np.array([equal]), np.array([900.0]), np.array([900.0]))
    assert abs(got[0] - 0.5) < 0.2


def test_components_of_a_chain(spark):
    links = spark.createDataFrame([(i, i + 1) for i in range(0, 40)] + [(100, 101), (7, 7)], "a long, b long")
    got = {r.v: r.label for r in components.components(links).collect()}
    assert all(got[i] == 0 for i in range(41)) and got[101] == 100 and len(got) == 43


def test_near_rows_without_an_id_are_linked(spark):
    words = [f"w{k}" for k in range(200)]
    near, other = words[:-1] + ["changed"], [f"v{k}" for k in range(100)]
    rows = [(5, " ".join(words)), (None, " ".join(near)), (None, " ".join(other)), (None, " ".join(other[:-1]) + " z"), (9, " ".join(near[:-1]) + " again")]
    found = neardup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    unnamed = {r.n_shingles: r.component_id for r in found if r.doc_id is None}
    assert unnamed == {196: 5, 96: None}
    assert sorted((r.doc_id, r.component_id, r.kept) for r in found if r.doc_id) == [(5, 5, True), (9, 5, False)]


@pytest.mark.parametrize("few", [300_000, 0])
def test_near_both_joins_agree(spark, monkeypatch, few):
    monkeypatch.setattr(neardup, "BROADCAST_CLASSES", few)
    rows = unique_rows()
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in neardup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == brute_near(rows, 85)


# --- substring -------------------------------------------------------------------------------------------------------
def brute_repeats(rows, width=20):
    seen, out = set(), {}
    for d, t in sorted(rows):
        w = WORDS.findall(t)
        gone = set()
        for i in range(len(w) - width + 1):
            k = tuple(w[i : i + width])
            if k in seen:
                gone.update(range(i, i + width))
            seen.add(k)
        out[d] = (len(w), len(gone), " ".join(x for i, x in enumerate(w) if i not in gone))
    return out


@pytest.mark.parametrize(("hot", "copies"), [(20_000, 2_000), (0, 2_000), (20_000, 0), (0, 0)])
def test_substring(spark, hot, copies, monkeypatch):
    monkeypatch.setattr(substring, "HOT_WINDOWS", hot)
    monkeypatch.setattr(substring, "HOT_COPIES", copies)
    monkeypatch.setattr(substring, "SAMPLE_OF", 1)
    rows = unique_rows()
    table = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    got = {r.doc_id: (r.n_words, r.n_removed, r.kept_text) for r in substring.remove_repeats(table).collect()}
    assert got == brute_repeats(rows) and sum(v[1] for v in got.values()) > 100


def test_substring_rows_of_one_id_are_alike(docs):
    got = [r for r in substring.remove_repeats(docs).collect() if r.doc_id == 1]
    assert len(got) == 2 and got[0].kept_text == got[1].kept_text


def test_words_are_told_apart_where_hashes_are_not(monkeypatch):
    texts, fine = [b"one two one", b"three two"], np.array([1, 2, 1, 3, 2], np.uint64)
    assert substring.told_apart(texts, fine) is fine
    monkeypatch.setattr(substring, "hashed_words", lambda t: (np.array([5, 5, 7], np.uint64), None))
    got = substring.told_apart(texts, np.array([5, 5, 5, 7, 5], np.uint64))
    assert got[0] == got[2] and got[1] == got[4] and len(set(got.tolist())) == 3


def test_repeated_tells_clashing_hashes_apart():
    words = np.array([1, 2, 3, 4, 1, 2, 3, 4], np.uint64)
    at, row, start = np.array([0, 2, 4, 6]), np.array([0, 0, 0, 0]), np.array([0, 2, 4, 6])
    got = substring.repeated(np.zeros(4, np.uint64), words, at, row, np.array([5]), start, 2)
    assert got.tolist() == [False, False, True, True]


# --- language model --------------------------------------------------------------------------------------------------
@pytest.mark.parametrize("order", [1, 2, 3])
def test_lm_matches_recursion_and_sums_to_one(spark, order):
    rows = unique_rows()[:24] + [(900, None), (901, "never seen words here")]
    held = lambda d: zlib.crc32(str(d).encode()) % 7 == 2
    table = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = lm.score_documents(table, F.crc32(F.encode(F.col("doc_id").cast("string"), "UTF-8")) % 7 == 2, order=order, mass=5.0).collect()
    tokens = {d: ["<s>", *re.findall(r"[^\x20\x09-\x0D]+", (t or "").lower()), "</s>"] for d, t in rows}
    grams = collections.Counter(tuple(w[i : i + k]) for d, w in tokens.items() if not held(d) for k in range(1, order + 1) for i in range(len(w) - k + 1))
    uni = {g[0]: c for g, c in grams.items() if len(g) == 1 and g[0] != "<s>"}
    n, v = sum(uni.values()), len(uni)
    n1, n2 = (sum(c == k for c in uni.values()) for k in (1, 2))
    d = n1 / (n1 + 2 * n2)

    def p(context, w):
        if not context:
            return (uni[w] - d) / n if w in uni else d * v / n
        return (grams[(*context, w)] + 5 * p(context[1:], w)) / (grams[tuple(context)] + 5)

    for r in got:
        w = tokens[r.doc_id]
        assert r.held_out == held(r.doc_id) and r.n_tokens == len(w) - 1 and r.train_tokens == n
        assert r.base_score == pytest.approx(sum(math.log10((uni.get(x, 0) + 1) / (n + v + 1)) for x in w[1:]))
        assert r.score == pytest.approx(sum(math.log10(p(tuple(w[max(0, i - order + 1) : i]), w[i])) for i in range(1, len(w))))
    if order > 1:
        assert sum(p(("the",), x) for x in uni) + p(("the",), "unseen") == pytest.approx(1.0)


def test_lm_pieces_agree_with_one_walk(monkeypatch):
    rng = random.Random(4)
    texts = [prose(rng, n).encode() for n in (0, 1, 3, 60, 900)] + [b""]
    vocabulary = sorted({w for t in texts for w in t.split()})
    number = {w: i for i, w in enumerate(vocabulary)}
    tokens = np.array([number[w] for t in texts for w in t.split()], np.uint32)
    offsets = np.cumsum([0, *(len(t.split()) for t in texts)]).astype(np.int64)
    block = lm.Block([False, True, False, True, True, False], lm._squeeze(offsets), lm._squeeze(tokens), b"\n".join(vocabulary), 3, 64)
    automaton = lm.Automaton(block, block.counts, np.array([len(tokens), len(vocabulary), 5, 3]), (4.0, 2.0))
    whole = automaton.score(block)
    for piece in (1, 2, 7, 64):
        monkeypatch.setattr(lm, "PIECE", max(piece, 2))
        assert automaton.score(block) == pytest.approx(whole)


def test_lm_counts_pass_32_bits():
    big = np.array([0, 1, (1 << 32) + 5, 1 << 40], np.int64)
    assert (lm._unwide(lm._wide(big)) == big).all()


# --- packing ---------------------------------------------------------------------------------------------------------
def test_packing_covers_every_token(docs):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(packing.default_tokenizer())
    t.encode_special_tokens = True
    got = packing.pack(docs, window=64, with_ids=True).collect()
    by_doc, by_seq = collections.defaultdict(list), collections.defaultdict(list)
    for r in got:
        by_doc[r.doc_id].append(r)
        by_seq[r.sequence_id].append(r)
        assert zlib.crc32(bytes(r.ids)) == r.ids_crc32 and len(r.ids) == 4 * r.length
    for d, text in unique_rows():
        ids = [*t.encode(text, add_special_tokens=False).ids, 1]
        pieces = sorted(by_doc[d], key=lambda r: r.start)
        if d != 1:  # that row is there twice
            assert np.frombuffer(b"".join(bytes(r.ids) for r in pieces), "<u4").tolist() == ids
        assert sum(r.length for r in pieces) == len(ids) * (2 if d == 1 else 1)
    for rows in by_seq.values():
        rows.sort(key=lambda r: r.offset)
        assert [r.offset for r in rows] == np.cumsum([0, *(r.length for r in rows)]).tolist()[:-1]
        total = sum(r.length for r in rows)
        assert total == 64 or (total < 64 and total & (total - 1) == 0)


def test_fast_and_plain_tokenizer_agree():
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(packing.default_tokenizer())
    t.encode_special_tokens = True
    texts = [r[1] or "" for r in corpus()] + ["<|endoftext|> it's 12  \U0001f600\n\n end  "]
    assert packing.encoder(packing.default_tokenizer())(texts) == [t.encode(x, add_special_tokens=False).ids for x in texts]


def test_solver_finds_exact_counts():
    h = np.zeros(64, np.int64)
    h[[40, 24, 10]] = 7, 5, 2
    combos = packing.combinations(64, h)
    assert (40, 24) in combos and all(sum(c) == 64 for c in combos)
    counts = packing.solve_counts(combos, h)
    assert (counts >= 0).all() and counts[combos.index((40, 24))] > 4


# --- web archives ----------------------------------------------------------------------------------------------------
PAGES = [(1, "http://a.example/x y", "<p>one</p>"), (2, None, "<p>two</p>"), (9, "http://b.example/", "<p>one</p>"), (5, "http://c.example/é", None), (4, "u", ""), (7, "v", "<p>naïve</p>" * 3000), (9, "http://b.example/", "<p>one</p>")]


def test_warc_round_trip(spark):
    pages = spark.createDataFrame(PAGES, "page_id long, url string, html string").repartition(3)
    arcs = warc.write_arc(pages)
    versions = {int(next(iter(warc.gunzip_members(bytes(r.content)).split(b"\n")[1:2])).split(b" ")[0]) for r in arcs.collect()}
    assert versions <= {1, 2} and versions
    got = warc.read_warc(warc.convert(arcs)).collect()
    assert len(got) == len(PAGES)
    most = {}
    for i, _, h in PAGES:
        most[h or ""] = max(i, most.get(h or "", 0))
    responses = collections.Counter()
    for r in got:
        payload = (next(h for i, _, h in PAGES if i == r.page_id) or "").encode()
        assert r.payload_bytes == len(payload) and r.payload_digest == base64.b32encode(hashlib.sha1(payload).digest()).decode()
        assert r.warc_date == "2024-01-01T00:00:00Z" and r.record_id.startswith("<urn:uuid:")
        responses[payload] += r.record_type == "response"
        assert r.refers_to == (None if r.record_type == "response" else most[payload.decode()])
    assert set(responses.values()) == {1}


@pytest.mark.parametrize("version", [1, 2])
def test_arc_versions(version):
    data = warc.arc_head(version, "a.arc") + warc.arc_record(version, "http://x/ y", 3, b"body\n\nmore", "a.arc", 0) + warc.arc_record(version, "", None, b"", "a.arc", 9)
    got = list(warc.parse_arc(data))
    assert [warc.split_http(r["body"])[1] for r in got] == [b"body\n\nmore", b""] and got[0]["URL"] == "http://x/%20y"
    with pytest.raises(ValueError):
        list(warc.parse_arc(data[:-20]))


# --- html ------------------------------------------------------------------------------------------------------------
@pytest.mark.parametrize(
    ("page", "text"),
    [
        (None, ""), ("", ""), ("   ", ""), ("plain", "plain"), ("<p>a &amp; b<p>c &#233; &copy;", "a & b\nc é ©"), ("<p>a<br>b  \n c</p>", "a b c"),
        ("<title>t</title><script>if (a < b) { '<p>x</p>' }</script><style>p{}</style><p>kept</p>", "kept"),
        ("<nav><a href=x>Menu</a></nav><article><h1>Head</h1><p>Text, of the article, here.</p><aside>no</aside></article><footer>f</footer>", "Head\nText, of the article, here."),
        ('<div id="sidebar"><p>menu, menu, menu, menu, menu</p></div><div class="post-content"><p>Words of the article, with commas, and more.</p><ul><li>one<li>two</ul><div class="comments"><p>I agree, really, I do.</p></div><form>mail</form></div>', "Words of the article, with commas, and more.\none\ntwo"),
        ("<div>" * 3000 + "deep", "deep"),
        ("<div>" * 300 + "<nav>menu menu menu</nav><p>Text of the article, here.</p>", "Text of the article, here."),
        ("<p>zero&#8203;width &#xFEFF;x</p>", "zero\u200bwidth \ufeffx"),
        ("<article><p>One.</p><div class='more-info'>More, in words.</div><p class='legal'>A law is a rule.</p><div class='ad'>Buy</div><div class='more'><a href=x>More like this one</a></div></article>", "One.\nMore, in words.\nA law is a rule."),
        ("<div><div><p>First part, with commas, and a good many words in it to score.</p></div><div><p>Second part.</p></div><div><p>Third part, with commas, and a good many words in it to score.</p></div></div>", "First part, with commas, and a good many words in it to score.\nSecond part.\nThird part, with commas, and a good many words in it to score."),
        ("<div class='sidebar-layout'><p>All of the page, its article, stands in here.</p></div><p>x</p>", "All of the page, its article, stands in here.\nx"),
        ("<div class='ad'>An advert that is longer than the article of the page.</div><article><p>Short.</p></article>", "Short."),
        ("<main><p>Said, in an article.</p></main><div class='reader-comments'><p>" + "I agree, really. " * 30 + "</p></div>", "Said, in an article."),
    ],
)
def test_main_text(page, text):
    assert html.main_text(page) == text


def written_page(rng):
    """A page in one of many layouts, with the blocks of its article."""
    sentence = lambda: " ".join(rng.choice(["river", "stone", "a", "the", "of", "market", "law", "and", "old"]) for _ in range(rng.randrange(4, 30))).capitalize() + "."
    links = lambda n: "".join(f"<li><a href=/{k}>{rng.choice(['Home', 'News', 'More on this'])}</a></li>" for k in range(n))
    want, inner = [], []
    for _ in range(rng.randrange(3, 9)):
        kind, text = rng.choice(["p", "p", "p", "h2", "blockquote", "div", "ul", "note"]), sentence()
        if kind == "note":
            inner.append(rng.choice([f"<div class='ad-slot'>{text}</div>", f"<aside>{text}</aside>", f"<ul class='share-links'>{links(3)}</ul>", f"<form>{text}<input></form>", f"<!-- {text} -->"]))
            continue
        want.append(text)
        inner.append(f"<ul><li>{text}</ul>" if kind == "ul" else f"<p>{text.replace(' ', '&#32;', 1)}" if kind == "p" and rng.random() < 0.3 else f"<{kind}>{text}</{kind}>")
    want.append(sentence())
    inner.append(f"<p>{want[-1]}</p>")
    body = rng.choice(["<article>{}</article>", "<main><div>{}</div></main>", "<div class='post-content'>{}</div>", "<div id=content><div class=entry>{}</div></div>"]).format("\n".join(inner))
    around = [f"<nav><ul>{links(5)}</ul></nav>", f"<div class='sidebar'><p>{sentence()}</p><ul>{links(4)}</ul></div>", f"<div id=cookie-notice><p>{sentence()}</p></div>", f"<header><b>{sentence()}</b></header>"]
    after = [f"<section class=comments><p>{sentence()}</p><p>{sentence()}</p></section>", f"<footer><p>{sentence()}</p></footer>", f"<div class='related-posts'><ul>{links(6)}</ul></div>"]
    shown = "".join(x for x in around if rng.random() < 0.7) + body + "".join(x for x in after if rng.random() < 0.7)
    return f"<html><head><title>t</title><script>var a='<p>';</script></head><body><div class=wrapper>{shown}</div></body></html>", "\n".join(want)


def test_written_pages_give_their_article():
    rng = random.Random(9)
    pages = [written_page(rng) for _ in range(400)]
    wrong = [(p, t) for p, t in pages if html.main_text(p) != t]
    assert len(wrong) <= 4, wrong[0]


def test_long_and_tangled_pages_take_linear_time():
    assert html.main_text("<p>" + "words of a text, " * 200_000 + "</p>").count("words") == 200_000
    for page in ("<div><b><p>x</i></span>" * 20_000, "<b>" * 20_000 + "</p></i>" * 20_000, "<li>" * 20_000 + "<tr>" * 20_000):
        html.main_text(page)


def test_extract_keeps_columns(spark):
    pages = spark.createDataFrame([(1, "u", "<p>a</p>", "clash"), (None, None, None, None)], "page_id long, url string, html string, text string")
    got = html.extract(pages)
    assert got.columns == ["page_id", "url", "text", "n_chars"]
    assert sorted((r.text, r.n_chars) for r in got.collect()) == [("", 0), ("a", 1)]


# --- decontamination -------------------------------------------------------------------------------------------------
def edit_distance(item, text):
    """Least word edits of the whole item against any part of the text."""
    row = [0] * (len(text) + 1)
    for i, w in enumerate(item):
        new = [i + 1]
        for j, x in enumerate(text):
            new.append(min(row[j] + (w != x), row[j + 1] + 1, new[j] + 1))
        row = new
    return min(row)


def test_within_edits_is_exact():
    rng = np.random.default_rng(4)
    for _ in range(60):
        item, region = rng.integers(0, 4, rng.integers(1, 9)).astype(np.uint64), rng.integers(0, 4, rng.integers(0, 14)).astype(np.uint64)
        want = edit_distance(item.tolist(), region.tolist())
        got = decontam.within_edits(item, region, len(item))
        assert got[0] == want and edit_distance(item.tolist(), region[got[1] : got[2]].tolist()) == want


def test_contamination(spark):
    rng = random.Random(8)
    items = [(i, prose(rng, n, 5000)) for i, n in enumerate((40, 15, 25, 8, 4))] + [(7, None), (8, "")]
    rows, want = [(900, None), (901, "")], set()
    for k in range(120):
        item, text = items[k % 5]
        w = text.split()
        for _ in range(int(0.1 * len(w)) if k % 2 else 0):
            w[rng.randrange(len(w))] = f"q{k}"
        rows.append((k, prose(rng, rng.randrange(50), 5000) + "\n" + " ".join(w).upper() + ". " + prose(rng, rng.randrange(50), 5000)))
        want.add((k, item))
    rows += [(500 + k, prose(rng, 120, 5000)) for k in range(40)]
    docs, bench = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    got = {(r.doc_id, r.item_id) for r in decontam.contamination(docs, bench).collect()}
    assert len(want & got) >= 0.98 * len(want) and not any(d >= 500 for d, _ in got)
    blocks = {(r.doc_id, r.item_id) for r in decontam.contamination(docs, bench, block_words=50).collect()}
    assert blocks == got
    left = {r.doc_id for r in decontam.decontaminate(docs, bench).collect()}
    assert left == {d for d, _ in rows} - {d for d, _ in got}


# --- toxicity --------------------------------------------------------------------------------------------------------
def test_toxicity(spark):
    rng = random.Random(5)
    rows, labels = [(9000, None), (9001, "")], []
    for i in range(600):
        text, bad = prose(rng, 60), i % 5 == 0
        if bad:
            words = text.split()
            for _ in range(3):
                words[rng.randrange(60)] = rng.choice(["idiot", "scum"]) if i % 10 else f"vrag{rng.randrange(99)}"
            text = " ".join(words)
        rows.append((i, text))
        labels.append((i, int(bad)))
    learn = lambda c: c % 3 != 1
    docs, marks = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, toxic int")
    got = {r.doc_id: r.score for r in toxicity.toxicity(docs, marks, learn).collect()}
    assert len(got) == len(rows) and all(0 <= s <= 1 for s in got.values()) and got[9000] == got[9001] < 0.5
    right = [(got[i] >= 0.7) == bool(y) for i, y in labels if i % 3 == 1]
    assert np.mean(right) > 0.95
    none = {r.doc_id: r.score for r in toxicity.toxicity(docs, marks.limit(0), learn).collect()}
    assert none[11] == none[11] and len(none) == len(rows)


# --- empty tables ----------------------------------------------------------------------------------------------------
def test_empty_tables(spark, empty):
    pages = spark.createDataFrame([], "page_id long, url string, html string")
    bench = spark.createDataFrame([], "item_id long, text string")
    marks = spark.createDataFrame([], "doc_id long, toxic int")
    for out in (
        quality.quality_rules(empty), linededup.drop_lines(empty), neardup.near_duplicates(empty), substring.remove_repeats(empty), packing.pack(empty), decontam.contamination(empty, bench),
        lm.score_documents(empty, F.lit(False)), html.extract(pages), warc.read_warc(warc.convert(warc.write_arc(pages))), toxicity.toxicity(empty, marks, lambda c: c % 3 != 1),
    ):
        assert out.count() == 0
