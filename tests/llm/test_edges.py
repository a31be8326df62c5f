"""Every operator on one table with a very long text, null ids, repeated rows, ties and clashing column names."""

import random
import zlib

import pytest
from pyspark.sql import functions as F

from orbitgraph.llm import common, decontam, html, linededup, lm, neardup, packing, quality, substring, toxicity, warc
from test_operators import WORDS, brute_lines, brute_near, brute_repeats, prose

CLASH = ["doc", "key", "score", "bucket", "n", "part", "rank", "label", "digest", "_h", "y", "spans", "block", "salt", "rep", "comp", "quality", "kept"]
LINE = "a line of more than forty characters that six documents of this table hold"


def table():
    rng = random.Random(33)
    long = prose(rng, 170_000, 20_000)
    rows = [(i, prose(rng, 60 + i)) for i in range(30)]
    rows += [(100 + i, f"{prose(rng, 30)}\n{LINE}\n{prose(rng, 30)}") for i in range(6)]
    rows += [(200, long), (201, long + " more"), (202, "vragoid " * 3 + prose(rng, 60)), (202, "vragoid " * 3 + prose(random.Random(1), 60))]
    rows += [rows[3], (None, rows[4][1]), (None, None), (300, None), (301, "")]
    return rows


@pytest.fixture(scope="module")
def docs(spark):
    frame = spark.createDataFrame(table(), "doc_id long, text string")
    return frame.withColumns({c: F.lit("clash") for c in CLASH}).withColumn("lang", F.lit("en")).repartition(5).persist()


def plain():
    """Rows whose id stands for one text."""
    rows = [r for r in table() if r[0] not in (None, 202)]
    return sorted({(d, t or "") for d, t in rows})


def test_the_long_text_is_long():
    assert max(len(t or "") for _, t in table()) > 700_000


def test_quality(docs):
    got = quality.quality_rules(docs, columns=["doc_id", "text", "n"]).collect()
    assert len(got) == len(table())
    for r in got:
        assert r.quality.n_words == len(WORDS.findall(r.text or "")) and r.n == "clash"


def test_lines(docs):
    got = linededup.drop_lines(docs).collect()
    want = brute_lines(plain())
    assert len(got) == len(table()) and all(r.kept_text == want[r.doc_id] for r in got if r.doc_id in want)
    assert sum(r.n_dropped for r in got) == 5 and all(r.rank == "clash" for r in got)


def test_near(docs):
    got = neardup.near_duplicates(docs).collect()
    want = brute_near(plain(), 85)
    assert len(got) == len(table()) and all((r.n_shingles, r.component_id) == want[r.doc_id] for r in got if r.doc_id in want)
    assert want[201][1] == 200


def test_substrings(docs):
    got = substring.remove_repeats(docs.where("doc_id is not null and doc_id <> 202")).collect()
    want = brute_repeats(plain())
    assert all((r.n_words, r.n_removed, r.kept_text) == want[r.doc_id] for r in got) and want[201][1] > 160_000


def test_scores(docs):
    got = lm.score_documents(docs, F.crc32(F.encode(F.col("doc_id").cast("string"), "UTF-8")) % 7 == 2).collect()
    assert len(got) == len(table())
    assert all(r.held_out == (r.doc_id is not None and zlib.crc32(str(r.doc_id).encode()) % 7 == 2) for r in got)
    twice = [r for r in got if r.doc_id == 3]
    assert len(twice) == 2 and twice[0] == twice[1]
    assert len({r.score for r in got if r.n_tokens == 1}) == 1


@pytest.mark.parametrize("most", [1_000_000, 0])
def test_packing_covers_all(docs, most, monkeypatch):
    monkeypatch.setattr(packing, "BROADCAST_ROWS", most)
    got = packing.pack(docs, window=256).collect()
    used = {}
    for r in got:
        used.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for pieces in used.values():
        pieces.sort()
        assert pieces[0][0] == 0 and all(a + n == b for (a, n), (b, _) in zip(pieces, pieces[1:], strict=False))
    assert sum(n == 256 or n & (n - 1) == 0 for n in (sum(n for _, n in p) for p in used.values())) == len(used)
    whole = {}
    for r in got:
        whole[r.doc_id] = whole.get(r.doc_id, 0) + r.length
    once = {r.doc_id: r.doc_tokens for r in got}
    assert all(whole[d] == once[d] for d in whole if d not in (None, 3, 202)) and whole[3] == 2 * once[3]


def marks(spark):
    return spark.createDataFrame([(i, int(i % 5 == 0), "clash") for i in range(30)] + [(202, 1, "x"), (202, 0, "x"), (None, 1, "x")], "doc_id long, toxic int, score string")


def test_toxicity_does_not_depend_on_partitions(spark, docs):
    rows = [(i, ("you vragoid scum " if i % 5 == 0 else "") + prose(random.Random(i), 40)) for i in range(400)]
    frame = spark.createDataFrame(rows + table()[-8:], "doc_id long, text string").withColumns({c: F.lit("clash") for c in CLASH})
    labels = spark.createDataFrame([(i, int(i % 5 == 0)) for i in range(0, 400, 2)], "doc_id long, toxic int")
    one, many = (sorted((-1 if r.doc_id is None else r.doc_id, r.score) for r in toxicity.toxicity(frame.repartition(k), labels, lambda c: c % 3 != 1).collect()) for k in (1, 40))
    assert [d for d, _ in one] == [d for d, _ in many] and [s for _, s in one] == pytest.approx([s for _, s in many], abs=1e-9)
    by_id = dict(one)
    assert all((by_id[i] >= 0.7) == (i % 5 == 0) for i in range(400))


def test_toxicity_of_all_rows(spark, docs):
    got = toxicity.toxicity(docs, marks(spark), lambda c: c % 3 != 1).collect()
    assert len(got) == len(table()) and all(0 <= r.score <= 1 for r in got)
    assert len({r.score for r in got if r.doc_id == 3}) == 1


@pytest.mark.parametrize("revisits", [None, 0])
def test_archives(spark, revisits, monkeypatch):
    if revisits is not None:
        monkeypatch.setattr(warc, "BROADCAST_REVISITS", revisits)
    rows = [(1, "u", "x" * 1_500_000), (2, "v", "x" * 1_500_000), (3, None, "<p>a"), (3, None, "<p>a"), (None, "w", "<p>b"), (5, "u", None), (6, "u", "")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumns({c: F.lit("clash") for c in [*CLASH, "payload_digest", "record_type"]})
    got = warc.read_warc(warc.convert(warc.write_arc(pages))).collect()
    assert sorted((r.page_id or 0, r.payload_bytes) for r in got) == [(0, 4), (1, 1_500_000), (2, 1_500_000), (3, 4), (3, 4), (5, 0), (6, 0)]
    by_id = {r.page_id: r for r in got}
    assert by_id[1].record_type == "revisit" and by_id[1].refers_to == 2 and by_id[5].refers_to == 6


def test_pages(spark):
    long = "<article>" + "".join(f"<p>Paragraph {k}, of a long article.</p>" for k in range(40_000)) + "</article>"
    rows = [(1, "u", long), (2, None, None), (None, "w", "<p>b"), (2, None, None)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumns({c: F.lit("clash") for c in CLASH})
    got = html.extract(pages).collect()
    assert len(got) == 4 and max(r.text.count("\n") for r in got) == 39_999 and all(r.rank == "clash" and r.n_chars == len(r.text) for r in got)


@pytest.mark.parametrize("most", [1_000_000, 0])
def test_decontamination(spark, docs, most, monkeypatch):
    monkeypatch.setattr(decontam, "BROADCAST_LEAKS", most)
    rows = dict(table())
    item = " ".join(rows[200].split()[150_000:150_030])
    bench = spark.createDataFrame([(1, item, "clash"), (2, item, "clash"), (None, item, "x")], "item_id long, text string, doc_id string")
    found = decontam.contamination(docs, bench).collect()
    assert sorted((r.doc_id, r.item_id or 0) for r in found) == sorted((d, i) for d in (200, 201) for i in (0, 1, 2))
    left = decontam.decontaminate(docs, bench)
    assert left.columns == docs.columns and left.count() == len(table()) - 2


def test_no_folder_of_its_own_on_a_cluster():
    class Context:
        master = "spark://host:7077"

        class _jsc:
            @staticmethod
            def sc():
                return type("S", (), {"getCheckpointDir": lambda self: type("O", (), {"isDefined": lambda self: False})()})()

        def getConf(self):
            return {}

    with pytest.raises(ValueError, match="checkpoint"):
        common.shared_dir(type("Session", (), {"sparkContext": Context()})())


def test_pipeline_on_an_empty_table(spark, tmp_path):
    import corpus_pipeline

    source = "/root/testdata/sf0.001"
    for name in ("documents", "benchmark"):
        frame = spark.read.parquet(f"{source}/{name}.parquet")
        (frame.limit(0) if name == "documents" else frame).write.parquet(f"{tmp_path}/{name}.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0
