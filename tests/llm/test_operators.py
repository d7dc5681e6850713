import random
import re
import struct

import public_tokenizers
import pytest

from symbits.llm import bpe, htmlmain, kdtree, langid, linededup, neardup, packing, quality, sharding, urlfilter

DOCS = "doc_id long, text string, lang string, source string"


def _docs(spark, *texts):
    return spark.createDataFrame([(i, t, "en", "s") for i, t in enumerate(texts)], DOCS)


def test_quality_counts_and_nulls(spark):
    rows = quality.judge_documents(_docs(spark, "a b c a b c d", None, "", "x\nx\n\n $y")).orderBy("doc_id").collect()
    assert [(r.n_words, r.n_repeat_words, r.n_dup_lines, r.n_symbols, r.kept) for r in rows] == [(7, 6, 0, 0, False), (0, 0, 0, 0, False), (0, 0, 0, 0, False), (3, 0, 1, 1, False)]


def test_quality_counts_lines_over_all_documents(spark):
    long = "\n".join(" ".join(f"w{i}x{k}" for k in range(20)) for i in range(4))
    docs = _docs(spark, *[f"Home page\nshort {i}" for i in range(10)], f"Home page\n{long}", " ".join(f"v{k}" for k in range(60)))
    judged = {r.doc_id for r in quality.judge_documents(docs).where("kept").collect()}
    out = {r.doc_id: r.text for r in quality.clean_documents(docs).collect()}
    assert set(out) == judged == {10, 11} and out[10] == long


def test_line_dedup_deletes_the_later_run(spark):
    run = "\n".join(f"line number {i}" for i in range(5))
    out = {r.doc_id: r.text for r in linededup.dedup_lines(_docs(spark, run, f"own\n{run}\nend", None, "")).collect()}
    assert out == {0: run, 1: "own\nend", 2: None, 3: ""}


def test_line_dedup_deletes_long_repeats_of_any_number_of_lines(spark):
    g = random.Random(7)
    pool = [" ".join(f"p{i}w{k}" for k in range(n)) for i, n in enumerate([60, 55, 30, 28, 24, 20, 20, 18, 9, 3] * 2)]
    texts = [pool[0], pool[0], f"own\n{pool[0]}\nend", f"{pool[2]}\n{pool[3]}", f"a\n{pool[2]}\n{pool[3]}\nb"]
    for d in range(60):
        at = g.randrange(len(pool) - 3)
        texts.append("\n".join([f"own {d} first", *pool[at : at + g.randrange(1, 4)], f"own {d} last"]))
    out = {r.doc_id: r.text for r in linededup.dedup_lines(_docs(spark, *texts)).collect()}
    assert out[1] == "" and out[2] == "own\nend" and out[4] == "a\nb"
    seen = set()  # all runs of 50 words or more in earlier documents
    for d, lines in enumerate(t.split("\n") for t in texts):
        runs = [(i, j) for i in range(len(lines)) for j in range(i + 1, len(lines) + 1) if sum(len(x.split()) for x in lines[i:j]) >= 50]
        repeated = {k for i, j in runs if tuple(lines[i:j]) in seen for k in range(i, j)}
        seen |= {tuple(lines[i:j]) for i, j in runs}
        assert not {lines[k] for k in repeated} & set(out[d].split("\n")), d


def test_language_without_letters():
    assert langid.classify(None, ["en"], langid.np.ones((1, langid.DIMENSIONS))) == ("und", 0.0)
    assert langid.classify("123 !?", ["en"], langid.np.ones((1, langid.DIMENSIONS))) == ("und", 0.0)


def test_near_duplicates(spark):
    words = [f"w{i}" for i in range(200)]
    near = words[:100] + ["changed"] + words[101:]
    out = {r.doc_id: r.class_id for r in neardup.classes(_docs(spark, " ".join(words), " ".join(near), " ".join(words), "quite another text of few words", None, "")).collect()}
    assert out == {0: 0, 1: 0, 2: 0, 3: 3, 4: 4, 5: 5}


def test_language_of_gibberish_is_not_recognised(spark):
    g = random.Random(3)
    words = "the of and people water between morning house river letter small after before question answer garden winter".split()
    noise = lambda n: " ".join("".join(g.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(g.randrange(2, 10))) for _ in range(n))
    learned = [" ".join(g.choice(words) for _ in range(200)) for _ in range(30)]
    unlearned = "Wszyscy ludzie rodzą się wolni i równi pod względem swej godności i swych praw"
    texts = [*learned, "the water", "garden " * 50, noise(50), noise(2000), unlearned, None, "12 !?"]
    docs = spark.createDataFrame([(i, t, "en" if i < 30 else None, "s") for i, t in enumerate(texts)], DOCS)
    assert {r.doc_id for r in langid.recognised(docs).collect()} == set(range(32))


@pytest.mark.parametrize("capacities", [(64, 64, 4096), (64, 3, 4096), (64, 64, 2600)])
def test_packing_keeps_every_constraint(capacities):
    counts = {1: 40, 3: 9, 17: 5, 31: 7, 50: 4}
    plan, use = packing.pack_histogram(counts, capacities), {}
    for length, a, b, first, offset in plan.ranges:
        for k in range(b - a):
            use.setdefault(first + k, []).append((offset, length))
    assert sum(map(len, use.values())) == sum(counts.values()) and len(use) == plan.next_sequence
    for held in use.values():
        assert all(o == sum(x for _, x in sorted(held)[:i]) for i, (o, _) in enumerate(sorted(held)))
        assert sum(x for _, x in held) <= capacities[0] and len(held) <= capacities[1] and sum(x * x for _, x in held) <= capacities[2]


def test_main_text():
    page = '<div class="wrap"><header>Head</header><div id="menu"><a href=x>A</a></div><div class="post"><h2>T&eacute;</h2><p>One two,  three. <a href=q>x</a><p>Four</div><div class="comments"><p>Nice!</p></div>'
    assert htmlmain.main_text(page) == "Té\nOne two, three. x\nFour"
    assert htmlmain.main_text(None) == htmlmain.main_text("<p") == ""


def test_main_text_by_ratios_with_and_without_article_elements():
    said = [f"Paragraph {i} says a good deal, at some length; it has commas, stops, and no links at all." for i in range(6)]
    body = "<h2>Title</h2>" + "".join(f"<p>{x}</p>" for x in said)
    card = "<article><h3><a href=x>Other story</a></h3><p>Short card</p></article>"
    expected = "\n".join(["Title", *said])
    assert htmlmain.main_text(f"<body><div class=story>{body}</div></body>") == expected
    assert htmlmain.main_text(f"<body><article>{body}</article></body>") == expected
    assert htmlmain.main_text(f"<body><div class=story>{body}</div>{card}</body>") == expected  # a teaser is not the article
    assert htmlmain.main_text(f"<body>{card}<div class=story>{body}</div>{card}{card}</body>") == expected
    assert htmlmain.main_text(f"<body><article>{body}</article>{card}<div><p>Short note</p></div></body>").startswith(expected)
    both = htmlmain.main_text(f"<body><article>{body}</article><article>{body.replace('Paragraph', 'Section')}</article></body>").split("\n")
    assert set(said) | {x.replace("Paragraph", "Section") for x in said} <= set(both)


def test_bpe_equals_the_library():
    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    own, library = bpe.WordBpe(path), Tokenizer.from_file(path)
    for text in ["", "it's A's we'LL 123 ½²", "İstanbul ΣΑΣ", "<|endoftext|>hello x", "a\xa0b\x1cc", "日本語 漢字 😀", "x" * 3000, "ab" * 900]:
        ids, said = own.encode(text)
        expected = library.encode(text, add_special_tokens=False).ids
        assert list(struct.unpack(f"<{len(ids) // 4}I", ids)) == expected and said == library.decode(expected, skip_special_tokens=False)


def test_shards_fit(spark):
    rows = sharding.shard_rows(_docs(spark, *["x" * 500 for _ in range(200)]), limit=5000, cell_bits=4).collect()
    held = {}
    for r in rows:
        held[r.shard] = held.get(r.shard, 0) + r.row_bytes
    assert len(rows) == 200 and max(held.values()) <= 5000


def test_top_k_is_exact(spark):
    g = random.Random(1)
    data = [(i, [g.uniform(-1, 1) for _ in range(8)]) for i in range(300)] + [(900, None), (901, [float("nan")] * 8)]
    v = kdtree.whole_vectors(spark.createDataFrame(data, "vec_id long, embedding array<float>"))
    all_rows = {r.vec_id: r.v for r in v.collect()}
    got = {(r.query_id, r.rank): (r.vec_id, r.score) for r in kdtree.top_k(v, v.where("vec_id % 100 = 0"), 3, shard_rows=64).collect()}
    for q in (0, 100, 200):
        best = sorted((-sum(a * b for a, b in zip(all_rows[q], x)), i) for i, x in all_rows.items() if i != q)[:3]
        assert [got[q, k + 1] for k in range(3)] == [(i, -s) for s, i in best]


def test_top_k_of_vectors_of_several_lengths(spark):
    data = [(i, [float(i % 7), 1.0, float(i % 5)][: 2 + (i > 0)]) for i in range(120)]
    v = kdtree.whole_vectors(spark.createDataFrame(data, "vec_id long, embedding array<float>"))
    all_rows = {r.vec_id: r.v for r in v.collect()}
    got = {(r.query_id, r.rank): (r.vec_id, r.score) for r in kdtree.top_k(v, v.where("vec_id % 50 = 0"), 3).collect()}
    expected = {}
    for q in (50, 100):
        best = sorted((-sum(a * b for a, b in zip(all_rows[q], x)), i) for i, x in all_rows.items() if i != q and len(x) == 3)[:3]
        expected |= {(q, k + 1): (i, -s) for k, (s, i) in enumerate(best)}
    assert got == expected


def test_url_rules(spark):
    urls = ["http://www.Example.com/en/a", "http://example.com/en/a", "https://x.net/es/?q", "http://a.org/b", None, "http://com"]
    rows = urlfilter.judge_urls(spark.createDataFrame(list(enumerate(urls)), "page_id long, url string"), urlfilter.fit([])).orderBy("page_id").collect()
    assert [r.rule for r in rows] == ["www.example.com/en/", "example.com/en/", "net/es/", None, None, None]
    assert [r.verdict for r in rows] == ["allow", "block", "block", "allow", "allow", "allow"]
    assert re.fullmatch("www.example.com", rows[0].host)
