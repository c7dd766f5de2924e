"""Nulls, empty and very long texts, repeated rows, ties, empty tables, clashing columns."""

import pytest

import corpus_pipeline
from evenkeel.llm import audio, bpe, embedding_dedup, mixing, pii, secrets, simhash, toxicity, urlfilter, warc

LONG = "an unusually long text with the words of many sentences. " * 40_000  # over 2 MB
WORD = "x" * 3_000_000
DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint, copies int, text_hash string, judged string, key double"


@pytest.fixture(scope="module")
def docs(spark):
    rows = [
        (1, "some words of the first document stand here, and more of them follow", "en", "a"),
        (1, "some words of the first document stand here, and more of them follow", "en", "a"),
        (2, "some words of the first document stand here, and more of them follow", "en", "b"),
        (3, None, None, None),
        (4, "", "en", None),
        (5, LONG, "en", "a"),
        (6, WORD, "en", "b"),
        (None, "a text without an identity but with 4111 1111 1111 1111 in it", "en", "a"),
        (7, "... !!! ???", None, "b"),
        (8, "Ünïcödé \U0001f600 漢字 é́ text\x00 with odd characters", "en", "a"),
    ]
    return spark.createDataFrame([(*r, None if r[1] is None else len(r[1]), 1, "h", "j", 0.5) for r in rows], DOCS)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOCS)


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(1, 1, 0), (1, 0, 1), (2, None, None), (None, 1, 1), (99, 1, 1)], "doc_id bigint, quality int, toxic int")


def test_toxicity(docs, none, labels):
    rows = toxicity.detect(docs, labels).collect()
    assert len(rows) == docs.count() and not any(r.toxic for r in rows)
    kept = toxicity.keep_clean(docs, labels)
    assert kept.columns == docs.columns and kept.count() == docs.count()
    assert toxicity.detect(none, labels).count() == 0
    assert toxicity.detect(docs, labels.limit(0)).where("toxic").count() == 0


def test_simhash(docs, none):
    rows = {(r.doc_id): r for r in simhash.groups(docs).collect()}
    assert set(rows) == set(range(1, 9))
    assert rows[2].group_id == 1 and not rows[2].keep and rows[1].keep
    assert all(rows[i].keep and rows[i].group_id == i for i in (3, 4, 5, 6, 7, 8))
    left = simhash.deduplicate(docs)
    assert left.columns == docs.columns
    assert sorted((r.doc_id is not None, r.doc_id) for r in left.select("doc_id").collect()) == [(False, None), *[(True, i) for i in (1, 3, 4, 5, 6, 7, 8)]]
    assert simhash.groups(none).count() == 0 and simhash.deduplicate(none).count() == 0


def test_simhash_same_id_other_text(spark):
    d = spark.createDataFrame([(1, "one text of a kind that nothing else is like"), (1, "and quite another one which shares the number"), (0, "one text of a kind that nothing else is like")], "doc_id bigint, text string")
    assert sorted(r.text[:3] for r in simhash.deduplicate(d).collect()) == ["and", "one"]


def test_simhash_ties_are_settled(spark):
    """Of rows that agree in doc_id and text the least one stays, whatever the order."""
    rows = [(1, "one text of a kind that nothing else is like", x, y) for x, y in (("b", 1), ("a", 2), ("a", 1), ("a", 1), (None, 3))] + [(None, "no id", "z", 1), (None, "no id", "z", 1)]
    for order in (rows, rows[::-1]):
        d = spark.createDataFrame(order, "doc_id bigint, text string, source string, alone int").repartition(3)
        left = simhash.deduplicate(d)
        assert left.columns == d.columns
        assert sorted((r.doc_id or 0, r.source or "", r.alone) for r in left.collect()) == [(0, "z", 1), (0, "z", 1), (1, "", 3)]  # JSON leaves nulls out


def test_pii(docs, none):
    rows = pii.detect(docs).collect()
    assert len(rows) == docs.count()
    by_text = [r for r in rows if r.doc_id is None]
    assert by_text[0].n_pseudonyms == 1 and "4111 1111 1111 1111" not in by_text[0].text
    assert [r.text for r in rows if r.doc_id == 3] == [None] and [r.text for r in rows if r.doc_id == 4] == [""]
    masked = pii.mask(docs)
    assert masked.columns == docs.columns and masked.count() == docs.count()
    assert pii.detect(none).count() == 0 and pii.mask(none).count() == 0


def test_mixing(docs, none, labels):
    taken = mixing.select(docs, labels).collect()
    assert {r.source for r in taken} <= {"a", "b", None} and all(r.copies > 0 for r in taken)
    mixed = mixing.mix(docs, labels, mixing.Settings(budget=3.0))
    assert mixed.columns == docs.columns
    counts = {(r["doc_id"], r["source"]): r["count"] for r in mixed.groupBy("doc_id", "source").count().collect()}
    assert counts[1, "a"] >= 4 and counts[3, None] >= 2  # complete epochs of all rows
    assert mixing.select(none, labels).count() == 0 and mixing.mix(none, labels).count() == 0
    assert mixing.mix(docs, labels.limit(0)).count() > 0


def test_mixing_string_ids_and_clashes(spark):
    d = spark.createDataFrame([("a-1", "x y z", "s", 1, 2, "k"), ("a-2", "x y", "s", 1, 2, "k"), (None, "x", None, 1, 2, "k")], "doc_id string, text string, source string, mix_copies_cut int, mix_copies int, mix_key string")
    labels = spark.createDataFrame([("a-1", 1), ("a-2", 0)], "doc_id string, quality int")
    s = mixing.Settings(budget=2.0)
    taken = {r.doc_id: r.copies for r in mixing.select(d, labels, s).collect()}
    assert taken.keys() == {"a-1", "a-2", None}
    mixed = mixing.mix(d, labels, s)
    assert mixed.columns == d.columns and mixed.count() == sum(taken.values())


def test_mixing_does_not_depend_on_the_joins(spark, small, monkeypatch):
    docs, labels = (spark.read.parquet(f"{small}/{t}.parquet") for t in ("documents", "labels"))
    want = [sorted(f(docs, labels).select("doc_id").collect()) for f in (mixing.select, mixing.mix)]
    monkeypatch.setattr(mixing, "MOST_BROADCAST", 0)
    monkeypatch.setattr(mixing, "MOST_LABELS", 0)
    assert want == [sorted(f(docs, labels).select("doc_id").collect()) for f in (mixing.select, mixing.mix)]


def test_bpe(docs, none):
    rows = bpe.encode_documents(docs).collect()
    assert len(rows) == docs.count()
    for r in rows:
        if r.doc_id == 3:
            assert r.tokens is None and r.n_tokens == 0 and r.round_trip is None
        else:
            assert r.round_trip and len(r.tokens) == r.n_tokens
    assert [r.n_tokens for r in rows if r.doc_id == 4] == [0]
    assert bpe.encode_documents(none).count() == 0
    again = {r.doc_id: r.text for r in bpe.decode_documents(bpe.encode_documents(docs)).collect()}
    assert again == {r.doc_id: r.text for r in docs.select("doc_id", "text").collect()}


def test_secrets(docs, none):
    rows = secrets.scan(docs).collect()
    assert [r.stop - r.start for r in rows if r.doc_id == 6] == [3_000_000]
    assert not any(r.doc_id in (3, 4) for r in rows) and secrets.scan(none).count() == 0


def test_audio(docs, none):
    rows = audio.alignments(docs).collect()
    assert all(r.bit_error <= 0.2 for r in rows)
    assert {r.doc_id: len(r.prints) for r in audio.fingerprints(docs).where("doc_id in (3, 4, 7)").collect()} == {3: 0, 4: 0, 7: 0}
    assert audio.alignments(none).count() == 0


PAGES = "page_id bigint, url string, html string, shard string, score int, raw int"


def test_pages(spark):
    rows = [(1, "https://good.example.org/a", "<p>x</p>"), (1, "https://good.example.org/a", "<p>x</p>"), (2, None, None), (3, "", ""), (None, "https://casino.example.org/b", "y"), (4, "https://a.example/" + "z" * 200_000, LONG)]
    pages = spark.createDataFrame([(*r, "s", 1, 2) for r in rows], PAGES)
    judged = urlfilter.judge(pages).collect()
    assert len(judged) == 6
    assert {r.page_id: r.accepted for r in judged if r.page_id in (2, 3)} == {2: False, 3: False}
    assert [r.accepted for r in urlfilter.judge(pages.where("page_id = 1")).collect()] == [True, True]
    frames = warc.frames(pages).collect()
    data = b"".join(r.frame for r in sorted(frames, key=lambda r: not r.is_dictionary))
    got = sorted(body for _, body in warc.read_archive(data))
    assert got == sorted([b"<p>x</p>", b"<p>x</p>", b"", b"", b"y", LONG.encode()])
    empty = pages.limit(0)
    assert urlfilter.judge(empty).count() == 0 and warc.frames(empty).count() == 1


def test_embeddings(spark):
    v = [1.0, 2.0, 3.0, 4.0]
    rows = [(1, v), (2, [x * 2 for x in v]), (2, v), (3, None), (4, []), (5, [0.0] * 4), (None, v), (6, [float("nan")] * 4), (7, [4.0, -3.0, 2.0, -1.0]), (8, [1.0, 2.0])]
    e = spark.createDataFrame([(*r, "x", 1) for r in rows], "vec_id bigint, embedding array<float>, code string, key int")
    assert [(r.vec_a, r.vec_b) for r in embedding_dedup.near_pairs(e).collect()] == [(1, 2)]
    assert embedding_dedup.near_pairs(e.limit(0)).count() == 0
    longer = spark.createDataFrame([(1, v), (2, v), (3, [1.0] * 5), (2, [9.0, 9.0, 9.0, 9.0])], "vec_id bigint, embedding array<float>")
    assert [(r.vec_a, r.vec_b) for r in embedding_dedup.near_pairs(longer).collect()] == [(1, 2)]  # one longer vector harms no other


def test_pipeline_keeps_columns(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    assert 4 <= len(corpus_pipeline.STAGES) <= 5
    for _, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, small)
        assert out.columns == docs.columns and out.count() > 0
    last = corpus_pipeline.STAGES[-1][1](spark, docs, small)
    assert last.columns == ["doc_id", "tokens", "n_tokens", "round_trip"]
