"""Operators against plain versions of what they compute."""

import json
import random
import struct
import zlib
from collections import Counter
from itertools import combinations

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest

import corpus_pipeline
from symbits.llm import kdtree, langid, linededup, neardup, packing, queries, sharding, urlfilter

SF = "/root/testdata/sf0.001"


def _docs(spark, *texts):
    return spark.createDataFrame([(i, t, "en", "s") for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string")


# -- near duplicates


def _weights(text, idf):
    words = text.encode().split()
    n = min(len(words), 5)
    value = {x: idf[neardup.Words([x]).buckets()[0]] for x in set(words)}
    out = Counter()
    for i in range(len(words) - n + 1 if n else 0):
        out[tuple(words[i : i + n])] += sum(value[x] for x in words[i : i + n]) / n
    return out


def _jaccard(a, b):
    shared = sum(min(w, b[s]) for s, w in a.items() if s in b)
    return shared / (sum(a.values()) + sum(b.values()) - shared) if a and b else 0.0


def _components(n, pairs):
    up = list(range(n))

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in pairs:
        a, b = sorted((root(a), root(b)))
        up[b] = a
    return [root(x) for x in range(n)]


def _similar(texts, idf, least=0.8):
    w = [_weights(t, idf) for t in texts]
    return [(i, j) for i, j in combinations(range(len(texts)), 2) if texts[i] == texts[j] or _jaccard(w[i], w[j]) >= least]


def _drifting(seed, n, edits):
    """Copies, and copies of copies, each with some words changed: similar to their originals, and less and less to the first."""
    g = random.Random(seed)
    made = [[f"w{seed}x{i}" for i in range(240)]]
    while len(made) < n:
        words = list(g.choice(made[:4] if g.random() < 0.6 else made))
        for _ in range(g.randrange(1, edits)):
            words[g.randrange(len(words))] = f"n{len(made)}x{g.randrange(10**6)}"
        made.append(words)
    return [" ".join(x) for x in made]


def test_components_of_a_group_are_those_of_all_pairs():
    idf = np.ones(1 << neardup.BUCKET_BITS)
    for seed in range(4):
        texts = _drifting(seed, 60, 9) + _drifting(seed + 10, 20, 14)
        h, w, s = neardup.shingles([t.encode() for t in texts], idf)
        expected = _components(len(texts), _similar(texts, idf))
        assert neardup.united(h, w, s).tolist() == expected
        some = np.arange(len(texts)) // 2  # texts of one label are together already
        assert neardup.united(h, w, s, some).tolist() == _components(len(texts), [*_similar(texts, idf), *((i, i + 1) for i in range(0, len(texts), 2))])


@pytest.mark.parametrize("part_rows", [4096, 16])
def test_near_duplicates_of_a_large_group(spark, monkeypatch, part_rows):
    monkeypatch.setattr(neardup, "PART_ROWS", part_rows)  # read on the driver
    texts = _drifting(1, 150, 6) + _drifting(2, 40, 20) + [" ".join(f"u{k}x{i}" for i in range(60)) for k in range(30)]
    docs = _docs(spark, *texts)
    got = [r.class_id for r in neardup.classes(docs).orderBy("doc_id").collect()]
    pairs = _similar(texts, neardup.word_idf(docs))
    expected = _components(len(texts), pairs)
    assert all(expected[i] == expected[c] for i, c in enumerate(got))  # nothing is joined that isn't linked
    assert sum(got[i] == got[j] for i, j in pairs) >= 0.99 * len(pairs) > 300


def test_near_duplicates_of_the_documents(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    rows = docs.select("doc_id", "text").orderBy("doc_id").collect()
    texts = [r.text or "" for r in rows]
    pairs = [(i, j) for i, j in _similar(texts, neardup.word_idf(docs)) if rows[i].text is not None and rows[j].text is not None]
    got = {r.doc_id: r.class_id for r in queries.op4_near_duplicates(spark, SF).collect()}
    assert [got[r.doc_id] for r in rows] == [rows[c].doc_id for c in _components(len(rows), pairs)]
    kept = {r.doc_id for r in neardup.keep_one(docs).collect()}
    assert kept == set(got.values())


def test_long_texts_without_common_words_share_no_bucket():
    idf = np.ones(1 << neardup.BUCKET_BITS)
    a, b = (neardup.sketch([" ".join(f"{x}{i}" for i in range(100_000)).encode()], idf)[0] for x in "ab")
    assert not set(a) & set(b)


def test_samples_agree_as_often_as_texts_are_similar():
    idf = np.ones(1 << neardup.BUCKET_BITS)
    agree, expected = [], []
    for k in range(40):
        words = [f"w{k}x{i}" for i in range(200)]
        changed = [f"c{k}x{i}" if i % 20 == 3 else w for i, w in enumerate(words)] + words[: k * 3]
        h, w, s = neardup.shingles([" ".join(words).encode(), " ".join(changed).encode()], idf)
        x, y = neardup.samples(h, w, s[:-1])
        agree.append((x == y).mean())
        expected.append(_jaccard(_weights(" ".join(words), idf), _weights(" ".join(changed), idf)))
    assert abs(np.mean(agree) - np.mean(expected)) < 0.02


# -- lines


def _lines_left(texts):
    """Lines that stay, by all windows of three lines and all shortest runs of 50 words or more."""
    seen, out = set(), []
    for text in texts:
        lines = text.split("\n")
        worded = [k for k, x in enumerate(lines) if x.split()]
        clean, words = [lines[k].strip() for k in worded], [len(lines[k].split()) for k in worded]
        runs = {(i, i + 3) for i in range(len(clean) - 2)}
        for i in range(len(clean)):
            runs |= {next(((i, j) for j in range(i + 1, len(clean) + 1) if sum(words[i:j]) >= 50), None), next(((j, i + 1) for j in range(i, -1, -1) if sum(words[j : i + 1]) >= 50), None)}
        gone = set()
        for i, j in sorted(r for r in runs if r):
            if (key := tuple(clean[i:j])) in seen:
                gone |= set(range(i, j))
            seen.add(key)
        dropped = {worded[k] for k in gone}
        out.append("\n".join(x for k, x in enumerate(lines) if k not in dropped))
    return out


@pytest.mark.parametrize("hot", [100_000, 3])
def test_line_dedup_is_what_windows_and_long_runs_say(spark, monkeypatch, hot):
    monkeypatch.setattr(linededup, "HOT", hot)
    g = random.Random(5)
    pool = [" ".join(f"p{i}w{k}" for k in range(g.choice([3, 5, 9, 14, 26, 55]))) for i in range(25)]
    texts = []
    for d in range(150):
        lines = []
        while len(lines) < g.randrange(1, 14):
            at = g.randrange(len(pool))
            lines += pool[at : at + g.randrange(1, 5)] if g.random() < 0.6 else [f" own {d} {g.randrange(40)} ", "", pool[0]]
        texts.append("\n".join(lines))
    got = [r.text for r in linededup.dedup_lines(_docs(spark, *texts)).orderBy("doc_id").collect()]
    assert got == _lines_left(texts)


# -- languages


def test_languages_of_held_out_documents(spark):
    rows = queries.op3_language_id(spark, "/root/testdata/sf0.01").where("held_out").join(spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "lang"), "doc_id").where("lang is not null").collect()
    assert len(rows) > 100 and sum(r.lang_pred == r.lang for r in rows) >= 0.98 * len(rows)


def test_languages_of_other_scripts():
    g = random.Random(2)
    alphabets = {"el": "αβγδεζηθικλμνξοπρστυφχψω", "ru": "абвгдежзийклмнопрстуфхцчшщыьэюя", "ar": "ابتثجحخدذرزسشصضطظعغفقكلمنهوي", "zh": [chr(0x4E00 + i) for i in range(25)], "got": [chr(0x10330 + i) for i in range(24)]}
    text = lambda a, n: " ".join("".join(g.choice(a) for _ in range(g.randrange(1, 7))) for _ in range(n))
    prototypes = []
    for a in alphabets.values():
        v = langid.bundle(*langid.trigrams(text(a, 3000)))
        prototypes.append(v / np.linalg.norm(v))
    names, prototypes = list(alphabets), np.array(prototypes)
    for name, a in alphabets.items():
        assert all(langid.classify(text(a, 60), names, prototypes)[0] == name for _ in range(10))
    assert abs(np.corrcoef(langid.vectors(np.array([0x3B1, 0x430, 0x4E00, 0x4E04])).astype(float)) - np.eye(4)).max() < 0.15


# -- packing


@pytest.mark.parametrize("limits", [{}, {"max_documents": 3}, {"max_cost": 2048 * 2048 // 3}, {"max_documents": 5, "max_cost": 1 << 21, "score": "dot"}])
def test_packing_of_the_documents(spark, limits):
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    docs = spark.read.parquet(f"{SF}/documents.parquet").limit(120)
    texts = {r.doc_id: r.text or "" for r in docs.collect()}
    size = 2048 if "max_cost" not in limits else int(limits["max_cost"] ** 0.5)
    rows = packing.pack_documents(docs, public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("byte_bpe_50k.tiktoken"), max_tokens=size, **limits).collect()
    by = {}
    for r in rows:
        by.setdefault(r.doc_id, []).append(r)
    assert set(by) == set(texts)
    for key, own in by.items():
        ids = [*library.encode(texts[key], add_special_tokens=False).ids, 0]
        own.sort(key=lambda r: r.piece)
        assert [r.start for r in own] == [sum(x.length for x in own[:k]) for k in range(len(own))] and sum(r.length for r in own) == len(ids)
        assert [r.length for r in own[1:]] == [size] * (len(own) - 1) and 1 <= own[0].length <= size
        assert all(r.ids_crc32 == zlib.crc32(struct.pack(f"<{r.length}I", *ids[r.start : r.start + r.length])) for r in own)
    held = {}
    for r in rows:
        held.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for own in held.values():
        own.sort()
        assert [a for a, _ in own] == [sum(n for _, n in own[:k]) for k in range(len(own))] and sum(n for _, n in own) <= size
        assert len(own) <= limits.get("max_documents", size) and sum(n * n for _, n in own) <= limits.get("max_cost", size**2)
    if not limits:
        assert len(held) <= 1 + -(-sum(r.length for r in rows) // size)


def test_packing_places_by_cells_as_by_broadcast(spark, monkeypatch):
    docs = _docs(spark, *["a b c " * (k % 40) for k in range(400)])
    run = lambda: {(r.doc_id, r.piece): r.length for r in packing.pack_documents(docs, public_tokenizers.path("byte_bpe_50k.json"), max_tokens=64).collect()}
    whole = run()
    monkeypatch.setattr(packing, "MAX_PLACES", 0)
    monkeypatch.setattr(packing, "SALT_ROWS", 1)
    assert run() == whole


def test_packing_encodes_plain_words_together(monkeypatch):
    calls, chunk = [], packing.ByteBpe.chunk
    monkeypatch.setattr(packing.ByteBpe, "chunk", lambda self, text: calls.append(text) or chunk(self, text))
    bpe = packing.ByteBpe(public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("byte_bpe_50k.tiktoken"))
    text = "\n".join(" ".join(f"wört{i}x{k}, it's" for k in range(20)) for i in range(50))
    ids = bpe.encode(text)
    assert list(struct.unpack(f"<{len(ids) // 4}I", ids)) == bpe.library.encode(text, add_special_tokens=False).ids
    assert len(calls) <= 2  # not once for each of 1,000 words


@pytest.mark.parametrize("ranks", ["byte_bpe_50k.tiktoken", None])
def test_packing_encodes_as_the_library(ranks):
    g = random.Random(12)
    odd = [" ", "\n", "  ", "\n\n", "\t", "\r\n", "\x1c", "\x7f", "\x00", "\x85", "\xa0", "\u3000", "\u200b", "é", "œ", "ß", "²", "a", "The", "'s", "'ll", "12", "!", "<|endoftext|>", "<|", "|>", "<", "日本", "😀", "\u0301", "x" * 70]
    plain = [" ", "\n", " ", "a", "The", "'s", "don't", "12", "é", "ñ", ".", "<", "|>"]
    texts = [None, "", *["".join(g.choices(plain if i % 2 else g.sample(odd, 6), k=g.randint(0, 25))) for i in range(3000)], "", None]
    bpe = packing.ByteBpe(public_tokenizers.path("byte_bpe_50k.json"), ranks and public_tokenizers.path(ranks))
    expected = [bpe.library.encode(t or "", add_special_tokens=False).ids for t in texts]
    for a, b in [(0, len(texts)), (700, 900), (0, 2), (5, 5)]:  # whole and as a part of an array
        ids, counts = bpe.encode_all(pa.array(texts, pa.string()).slice(a, b - a))
        assert counts.tolist() == list(map(len, expected[a:b])) and ids.tolist() == sum(expected[a:b], [])


def test_packing_by_slices(spark, monkeypatch):
    g = random.Random(13)
    docs = _docs(spark, None, *[" ".join(g.choices(["the", "wordand", "it's", "é\n\nb", "<|endoftext|>"], k=g.choice([0, 3, 63, 64, 127, 128, 500]))) for _ in range(60)], "").repartition(1)
    run = lambda: {(r.doc_id, r.piece): (r.start, r.length, r.ids_crc32, *r.ids) for r in packing.pieces(docs, public_tokenizers.path("byte_bpe_50k.json"), max_tokens=64, keep=True).collect()}
    whole = run()
    assert all(len(r) == r[1] + 3 and r[2] == zlib.crc32(struct.pack(f"<{r[1]}I", *r[3:])) for r in whole.values())
    assert len({k for k, _ in whole}) == 62 and all(k == 0 or whole[d, k - 1][0] + whole[d, k - 1][1] == r[0] for (d, k), r in whole.items())
    monkeypatch.setattr(packing, "SLICE_BYTES", 100)
    assert [b - a for a, b in packing._slices(pa.array(["x" * 60, None, "x" * 40, "x", "x" * 500, "", "y"]))] == [3, 1, 1, 2]


# -- shards


def test_shards_are_the_shortest_prefixes_that_fit(spark):
    import hashlib

    g = random.Random(4)
    sizes = {i: g.choice([10, 200, 900, 4000]) for i in range(500)}
    docs = spark.createDataFrame([(i, "x" * n) for i, n in sizes.items()], "doc_id long, text string")
    bits = {i: bin(int(hashlib.md5(str(i).encode()).hexdigest()[:15], 16))[2:].zfill(60) for i in sizes}
    weight = Counter()
    for i, n in sizes.items():
        for d in range(61):
            weight[bits[i][:d]] += n + 16
    for cell_bits in (3, 12):
        for r in sharding.shard_rows(docs, limit=5000, cell_bits=cell_bits).collect():
            d = next(d for d in range(61) if weight[bits[r.doc_id][:d]] <= 5000)
            assert (r.shard, r.depth, r.shard_bytes, r.oversized) == (bits[r.doc_id][:d], d, weight[bits[r.doc_id][:d]], False)


def test_shards_of_one_key_have_pages(spark):
    docs = spark.createDataFrame([(7, "x" * (i % 300)) for i in range(3000)] + [(i, "y") for i in range(20)], "doc_id long, text string")
    rows = sharding.shard_rows(docs, limit=4000).collect()
    held = Counter()
    for r in rows:
        held[r.shard, r.page] += r.row_bytes
    assert len(rows) == 3020 and max(held.values()) <= 4000 and {r.oversized for r in rows if r.doc_id == 7} == {True}


# -- vectors


def _best(vectors, q, k):
    return sorted((-sum(int(a) * int(b) for a, b in zip(vectors[q], x)), i) for i, x in vectors.items() if i != q and len(x) == len(vectors[q]))[:k]


@pytest.mark.parametrize("scale", [1, 10**7])
def test_top_k_with_ties_clusters_and_large_components(spark, scale):
    g = random.Random(scale)
    data = [(i, [scale * (g.randrange(-3, 4) + 10 * (i % 5)) / 1024 for _ in range(3 + (i % 50 == 7))]) for i in range(700)]
    v = kdtree.whole_vectors(spark.createDataFrame(data, "vec_id long, embedding array<double>"))
    vectors = {r.vec_id: r.v for r in v.collect()}
    got = {}
    for r in kdtree.top_k(v, v.where("vec_id % 100 = 7 or vec_id % 100 = 0"), 4, shard_rows=100, block_rows=5).collect():
        got.setdefault(r.query_id, []).append((r["rank"], r.vec_id, r.score))
    assert set(got) == {i for i in range(700) if i % 100 in (0, 7)}
    for q, rows in got.items():
        assert sorted(rows) == [(n + 1, i, -s) for n, (s, i) in enumerate(_best(vectors, q, 4))]


def test_top_k_without_boxes_and_pruning(spark, monkeypatch):
    g = np.random.default_rng(1)
    rows = np.concatenate([g.integers(-5, 6, (2000, 6)) + 100 * c for c in (-3, 0, 2)])
    tree = kdtree.Tree(np.arange(len(rows)), rows.astype(np.int64))
    assert [(-i, s) for s, i in tree.search(rows[5].astype(float), 5, 3, -np.inf)]
    assert tree.visited < len(rows) / kdtree.LEAF_ROWS / 2  # most boxes can't hold a neighbour
    v = kdtree.whole_vectors(spark.createDataFrame([(i, [x / 1024 for x in r]) for i, r in enumerate(rows[:900].tolist())], "vec_id long, embedding array<double>"))
    run = lambda: sorted(map(tuple, kdtree.top_k(v, v.where("vec_id % 100 = 0"), 3, shard_rows=64).collect()))
    whole = run()
    monkeypatch.setattr(kdtree, "BOX_BYTES", 0)
    assert run() == whole


# -- urls


def test_url_model_tells_held_out_urls(spark):
    g = random.Random(6)
    hosts = {True: ["example.com", "shop.net", "news.net"], False: ["blog.com", "www.example.com", "docs.com"]}
    paths = {True: ["/en/", "/es/", "/fr/"], False: ["/en/", "/about/", "/"]}
    made = []
    for k in range(600):
        block = k % 2 == 0
        made.append((g.choice(hosts[block]), g.choice(paths[block]) + g.choice(["offer", "story", "page"]) + str(g.randrange(10**6)), block))
    model = urlfilter.fit(made[:400])
    right = sum((model.chance(h, p) >= 0.5) == b for h, p, b in made[400:])
    assert right >= 190


def test_url_rules_by_plain_reading(spark):
    rules = {"com/": "allow", "example.com/en/": "block", "www.example.com/en/": "allow", "net/es/": "block", "net/fr/": "block"}
    rows = queries.op10_url_filter(spark, SF).collect()
    urls = {r.page_id: r.url for r in spark.read.parquet(f"{SF}/pages.parquet").select("page_id", "url").collect()}
    assert len(rows) == len(urls)
    decided = 0
    for r in rows:
        rest = urls[r.page_id].split("://", 1)[1] if "://" in (urls[r.page_id] or "") else ""
        cut = min([rest.find(c) for c in "/?#" if c in rest] or [len(rest)])
        host, path = rest[:cut].lower() if rest[:cut].isascii() else r.host, rest[cut:].split("?")[0].split("#")[0]
        fits = [x for x in rules if (host == x.split("/")[0] or host.endswith("." + x.split("/")[0])) and path.startswith("/" + x.split("/", 1)[1])]
        best = max(fits, key=len, default=None)
        assert (r.host, r.path, r.rule) == (host, path, best) and r.verdict == rules.get(best, r.verdict) and r.verdict in ("allow", "block")
        decided += best is not None
    assert decided


# -- pipeline


def test_pipeline_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, SF)
        rows, before = out.collect(), {r.doc_id: r for r in docs.collect()}
        assert {r.doc_id for r in rows} <= set(before)
        if name == "best_fit_packing":
            assert {r.doc_id for r in rows} == set(before)
            break
        assert out.columns == docs.columns and 0 < len(rows) <= len(before)
        own = [r.text for r in rows]
        if name in ("language_id", "near_duplicates"):
            assert all(r.text == before[r.doc_id].text for r in rows)
        if name == "quality_rules":
            judged = {r.doc_id for r in queries.quality.judge_documents(docs).where("kept").collect()}
            assert {r.doc_id for r in rows} == judged
        if name == "line_dedup":
            ordered = sorted(before)
            assert {r.doc_id: r.text for r in rows} == dict(zip(ordered, _lines_left([before[k].text for k in ordered])))
        if name == "near_duplicates":
            worded = [t for t in own if t]
            assert len(worded) == len(set(worded))
        docs = spark.createDataFrame(rows, docs.schema)


def test_op2_sql(spark):
    import duckdb

    con = duckdb.connect()
    con.sql(f"CREATE VIEW documents AS SELECT * FROM '{SF}/documents.parquet'")
    expected = sorted(con.sql(queries.ORACLE_SQL["op2_line_dedup"]).select("doc_id, text, n_deleted").fetchall())
    assert sorted(map(tuple, queries.op2_line_dedup(spark, SF).collect())) == expected and json.dumps(expected)
