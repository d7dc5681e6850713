"""Nulls, empty tables, repeated rows, very long texts and clashing names, for each operator and stage."""

import public_tokenizers
import pytest

import corpus_pipeline
from symbits.llm import bpe, htmlmain, kdtree, langid, linededup, neardup, packing, quality, sharding, urlfilter

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, score string, lang_pred int, shard int, depth string, page long, n_words string, n_deleted string, class_id string, sequence_id int, rank int, c double"
LONG = " ".join(f"w{i % 5000}" for i in range(60_000))
TEXTS = [None, "", " \n\t", "one two three", "one two three", "12 !?", LONG, LONG + " more", "line a\nline b\nline c\n" * 3, "é" * 50]
BYTE = public_tokenizers.path("byte_bpe_50k.json")


def _docs(spark, rows):
    return spark.createDataFrame([(i, t, lang, s, None, "x", 1, 2, "y", 3, "z", "u", "v", 4, 5, 0.5) for i, t, lang, s in rows], SCHEMA)


@pytest.fixture(scope="module")
def docs(spark):
    return _docs(spark, [(k if k != 3 else None, t, "en" if k % 2 else None, None if k % 3 else "s") for k, t in enumerate(TEXTS)] + [(3, "one two three", "en", "s")] * 2)


OPERATORS = {
    "quality": lambda d: quality.judge_documents(d),
    "clean": lambda d: quality.clean_documents(d),
    "lines": lambda d: linededup.dedup_lines(d),
    "languages": lambda d: langid.identify(d),
    "recognised": lambda d: langid.recognised(d),
    "classes": lambda d: neardup.classes(d),
    "keep_one": lambda d: neardup.keep_one(d),
    "packing": lambda d: packing.pack_documents(d, BYTE),
    "bpe": lambda d: bpe.encode_documents(d, public_tokenizers.path("word_bpe_49k.json")),
    "shards": lambda d: sharding.shard_rows(d),
}
ROWS = {"quality": 12, "lines": 12, "languages": 12, "classes": 12, "bpe": 12, "shards": 12}


@pytest.mark.parametrize("name", OPERATORS)
def test_documents_of_every_kind(spark, docs, name):
    made = OPERATORS[name](docs)
    rows = made.collect()
    assert len(set(made.columns)) == len(made.columns)
    assert len(rows) == ROWS.get(name, len(rows))
    if name in ("clean", "recognised", "keep_one"):
        assert made.columns == docs.columns and {(r.doc_id, r.text) for r in rows} <= {(r.doc_id, r.text) for r in docs.collect()}
        assert all((r.score, r.lang_pred, r.depth, r.n_words) == ("x", 1, "y", "z") for r in rows)
    if name == "lines":
        assert {r.text for r in rows if r.doc_id == 8} == {"line a\nline b\nline c\n"} and made.schema["n_deleted"].dataType.simpleString() == "bigint"
    if name == "languages":
        assert all((r.lang_pred, r.score) == ("und", 0.0) for r in rows if not r.text or r.text == "12 !?")
    if name == "classes":
        named = {(r.doc_id, r.node): r.class_id for r in rows}
        by_text = {t: {c for (i, n), c in named.items() if n == __import__("hashlib").md5(t.encode()).hexdigest()} for t in TEXTS if t is not None}
        assert by_text["one two three"] == {3} and by_text[LONG] == by_text[LONG + " more"] == {6} and named[0, None] == 0
    if name == "keep_one":
        assert sorted(r.text for r in rows if r.text is not None) == sorted({t for t in TEXTS if t is not None and t != LONG + " more"})
    if name == "packing":
        assert len({r.doc_id for r in rows}) == 11


@pytest.mark.parametrize("name", OPERATORS)
def test_empty_tables(spark, name):
    assert OPERATORS[name](_docs(spark, [])).count() == 0


def test_classes_without_doc_ids(spark):
    rows = neardup.classes(_docs(spark, [(None, "a b c d e", None, None), (None, "v w x y z", None, None), (None, "a b c d e", None, None), (2, None, None, None)])).collect()
    by = {}
    for r in rows:
        by.setdefault(r.node, set()).add(r.class_id)
    assert len(rows) == 4 and all(len(x) == 1 for x in by.values()) and len({next(iter(x)) for x in by.values()}) == 3


def test_pipeline_of_empty_documents(spark):
    docs = spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long")
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, docs, "").count() == 0


def test_pages(spark):
    pages = spark.createDataFrame([(1, None, None, "x"), (None, "HTTP://É.com/a", "", "x"), (1, None, None, "x"), (2, "http://a.net/es/", "<p>" + "long text, " * 50_000, "x")], "page_id long, url string, html string, text string")
    rows = htmlmain.extract_pages(pages).collect()
    assert sorted((r.page_id or 0, r.n_chars) for r in rows) == [(0, 0), (1, 0), (1, 0), (2, 50_000 * 11 - 1)]
    judged = sorted((r.page_id or 0, r.rule or "", r.verdict) for r in urlfilter.judge_urls(pages, urlfilter.fit(urlfilter.labelled_by_rules(pages))).collect())
    assert judged[0] == (0, "com/", "allow") and judged[1] == judged[2] and judged[3] == (2, "net/es/", "block")
    none = pages.where("page_id = 9")
    assert htmlmain.extract_pages(none).count() == urlfilter.judge_urls(none, urlfilter.fit(urlfilter.labelled_by_rules(none))).count() == 0


def test_vectors(spark):
    data = [(1, [1.0, 2.0]), (2, None), (3, [1.0, None]), (4, [float("inf"), 1.0]), (5, []), (6, [3.0, 1.0]), (6, [3.0, 1.0]), (7, [1.0]), (None, [1.0, 1.0])]
    v = kdtree.whole_vectors(spark.createDataFrame(data, "vec_id long, embedding array<double>"))
    got = sorted(map(tuple, kdtree.top_k(v, v.where("vec_id = 1 or vec_id = 7"), 5).collect()))
    assert [(q, i) for q, _, i, _ in got] == [(1, 6), (1, 6)]
    assert kdtree.top_k(v.where("vec_id = 99"), v.where("vec_id = 99")).count() == 0
    with pytest.raises(Exception, match="too large"):
        kdtree.whole_vectors(spark.createDataFrame([(1, [1e300])], "vec_id long, embedding array<double>")).collect()
    with pytest.raises(ValueError, match="share an id"):
        kdtree.top_k(v, v.where("vec_id = 6"))
