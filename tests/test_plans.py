import re

import numpy as np
import pytest

from symbits import measures
from symbits.functions.spec import exactly, threshold
from symbits.operators import surface
from symbits.operators import threshold as T
from symbits.operators.index import build
from symbits.plans import planner
from symbits.plans.criteria import Criterion
from symbits.sources import tables as tb
from symbits.streaming import streams as st

SF = "/root/testdata/sf0.001"


def test_rules():
    base = {"rows": 1000, "n": 10, "cards": [100] * 10, "b": 1000, "runs": 900, "dirty": 50, "density": 0.1}
    assert planner.rule(base | {"density": 0.95}, threshold(9), 10).complement
    assert planner.rule(base, threshold(1), 10).method == "wide"
    assert planner.rule(base | {"density": 0.0001}, threshold(4), 10).method == "counter_hash"
    assert planner.rule(base | {"runs": 10}, threshold(4), 10).method == "run_merge_sweep"
    assert planner.rule(base | {"cards": [1] * 9 + [900]}, threshold(10 - 1), 10).method == "set_aside_joins"
    assert planner.rule(base | {"cards": [1] * 600}, threshold(40), 600).method == "counter_array"
    assert planner.rule(base, exactly(3), 10).method == "sideways_sum"


def test_planned_answers_of_dense_inputs(spark):
    held = {f"d{k}": [r for r in range(500) if r % (11 + k)] for k in range(6)}
    index = build(spark.createDataFrame([("s", k, r) for k, rids in held.items() for r in rids], "attr string, value string, rid long"), 500, 128)
    own = [Criterion("s", k) for k in held]
    assert planner.choose(index, own, threshold(6 - 1)).complement
    got = {r[0] for r in T.evaluate(index, own, threshold(5)).rids().collect()}
    assert got == {r for r in range(500) if sum(r in set(v) for v in held.values()) >= 5}
    costs = planner.query_stats(index, own, 5, 2)
    cards = sorted(map(len, held.values()))
    assert (costs["b"], costs["b_small"], costs["b_rest"]) == (sum(cards), sum(cards[:2]), sum(cards[:4]))


def test_mu():
    times = {(0.02, 0): 2.0, (0.02, 1): 4.0, (0.1, 0): 1.0, (0.1, 1): 9.0}
    assert planner.tune_mu(times) == 0.02 and planner.best_of_mu(times) == {0: (0.1, 1.0), 1: (0.02, 4.0)}


def test_measures(spark):
    times = spark.createDataFrame([("c1", "a", 32, 1.0, 8), ("c1", "b", 32, 2.0, 8), ("c2", "a", 64, 9.0, 60), ("c2", "b", 64, 0.5, 60)], "competition string, algo string, n long, ms double, t long")
    ranks = {(r.competition, r.algo): (r["rank"], r.within_100, r.terrible) for r in measures.rank_competition(times).collect()}
    assert ranks == {("c1", "a"): (0, True, False), ("c1", "b"): (1, True, False), ("c2", "a"): (1, False, True), ("c2", "b"): (0, True, False)}
    assert {r.algo: r.total for r in measures.normalized_time(times).collect()} == {"a": 19.0, "b": 3.0}
    assert {(r.algo, r.n): r.relative for r in measures.normalize_by_n(times).collect()} == {("a", 32): 1, ("a", 64): 9, ("b", 32): 1, ("b", 64): 0.25}
    assert {(r.n_bin, r.t_bin): (r.a, r.b) for r in measures.heatmap(times).collect()} == {(5, 1): (1, 0), (6, 3): (0, 1)}
    assert max(r.suboptimality for r in measures.suboptimality(times).collect()) == 17
    assert measures.time_adaptive(lambda: None, 1) < 1 and measures.workload_time([lambda: None] * 3) < 1
    got = measures.spark_metrics(spark, lambda: measures.run(spark.range(1000).selectExpr("id % 7 as k").groupBy("k").count()))
    assert got["tasks"] > 0 and got["shuffle_bytes"] > 0


def test_sharing_sets_the_commonest_aside(spark):
    grams = {0: "abcdefgh", 1: "abcdefzz", 2: "abcxyz", 3: "abc", 4: "defgh"}
    rows = spark.createDataFrame([(k, g) for k, gs in grams.items() for g in set(gs)], "doc long, gram string")
    asked = rows.withColumnRenamed("doc", "q")
    for t in (1, 2, 3, 4, 6):
        got = {(r.q, r.doc): r.n for r in surface.sharing(rows, asked, "doc", "q", t).collect()}
        assert got == {(a, b): n for a in grams for b in grams if (n := len(set(grams[a]) & set(grams[b]))) >= t}


@pytest.mark.parametrize("q, block, piece", [(1, 10**6, 1 << 20), (3, 10**6, 1 << 20), (3, 40, 16), (5, 40, 16)])
def test_shared_runs(spark, monkeypatch, q, block, piece):
    import random

    from symbits.operators import sharedruns

    monkeypatch.setattr(sharedruns, "BLOCK_WORDS", block)
    monkeypatch.setattr(sharedruns, "PIECE", piece)
    rng = random.Random(q)
    held = {k: [rng.choice("abc") * rng.randint(1, 2) for _ in range(rng.randint(0, 40))] for k in range(60)} | {60: ["zz"] * 30, 61: None, 62: []}
    rows = spark.createDataFrame(list(held.items()), "doc long, words array<string>")
    asked = rows.where("doc % 4 = 0").withColumnRenamed("doc", "q")
    runs = {k: {tuple(w[i : i + q]) for i in range(len(w) - q + 1)} for k, w in held.items() if w}
    for t in (1, 3):
        got = [tuple(r) for r in sharedruns.sharing_runs(rows, asked, "doc", "q", q, t).collect()]
        assert sorted(got) == sorted((a, b, n) for a in runs if a % 4 == 0 for b in runs if (n := len(runs[a] & runs[b])) >= t)
    assert sharedruns.sharing_runs(rows, asked.where("false"), "doc", "q", q, 1).count() == 0


def test_shared_runs_whose_numbers_are_long():
    import numpy as np
    import pyarrow as pa

    from symbits.operators import sharedruns

    words = [f"w{k}" for k in range(20000)]
    index = sharedruns.Runs(np.array([7]), pa.array([words]), 5)
    assert index.levels  # 20000**5 passes 2**62
    found = [(a, n) for text, _, ns in index.shared(pa.array([words[:50], words[:5] + ["x"] + words[5:9], words[::-1], words]), 1) for a, n in zip(text.tolist(), ns.tolist())]
    assert found == [(0, 46), (1, 1), (3, 19996)]


def test_near_documents_write_no_shingles(spark):
    from symbits.plans import queries

    plan = queries.QUERIES["near_dup_docs"](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and plan.count("documents.parquet") == 1


def test_edit_distance_by_index(spark):
    names = spark.createDataFrame([(i, n) for i, n in enumerate(["anna", "anne", "hannah", "bob", "ann", "nana", "aaaa"])], "id long, name string")
    index = build(tb.name_grams(names, "id", "name", 2, True), 7, 64)
    for wanted, k in (("anna", 1), ("anna", 2), ("aaaa", 1), ("b", 3)):
        own = {(r.id, r.distance) for r in surface.approximate_by_index(index, names, "id", "name", wanted, k).collect()}
        assert own == {(r.id, r.distance) for r in surface.approximate_match(names, "id", "name", wanted, k).collect()} and own


def test_overlaps_and_as_of(spark):
    runs = lambda rows: spark.createDataFrame(rows, "start long, stop long")
    a, b = [(0, 10), (50, 300), (400, 400)], [(5, 60), (300, 399), (401, 500)]
    got = {tuple(r) for r in surface.overlap_join(runs(a), runs(b), 64).collect()}
    assert got == {(*x, *y) for x in a for y in b if x[0] <= y[1] and y[0] <= x[1]}
    left = spark.createDataFrame([(1, 5), (1, 9), (2, 9)], "k long, ts long")
    right = spark.createDataFrame([(1, 5, "x"), (1, 8, "y"), (2, 10, "z")], "k long, ts long, v string")
    assert {(r.k, r.ts, r.v) for r in surface.as_of(left, right, "ts", ["k"], "v").collect()} == {(1, 5, "x"), (1, 9, "y"), (2, 9, None)}


@pytest.fixture(scope="module")
def folders(spark, tmp_path_factory):
    """Events and documents in two files each."""
    out = {}
    for name, key in (("events", "event_id"), ("documents", "doc_id")):
        path = str(tmp_path_factory.mktemp(name))
        df = spark.read.parquet(f"{SF}/{name}.parquet")
        for half in range(2):
            df.where(f"{key} % 2 = {half}").coalesce(1).write.mode("append").parquet(path)
        out[name] = path
    return out


def test_index_of_a_stream_joins_words(spark, folders):
    events = spark.read.parquet(f"{SF}/events.parquet")
    rows = events.agg({"event_id": "max"}).first()[0] + 1
    grown = st.index_append(tb.event_sets(st.source(spark, folders["events"])), rows, 256)
    whole = build(tb.event_sets(events), rows, 256)
    columns = ["attr", "value", "chunk", "kind", "card", "runs", "dirty", "first", "last"]
    assert sorted(map(tuple, grown.df.select(*columns).collect())) == sorted(map(tuple, whole.df.select(*columns).collect()))


def test_near_duplicates_of_a_stream(spark, folders):
    from pyspark.sql import functions as F

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    grams = lambda df: df.select("doc_id", F.array_distinct(F.split("text", " ")).alias("grams"))
    pairs = st.near_duplicates(grams(st.source(spark, folders["documents"])), 60).collect()
    rows = {r.doc_id: set(r.grams) for r in grams(docs.where("text is not null")).collect()}
    expected = {frozenset((a, b)): n for a in rows for b in rows if a < b and (n := len(rows[a] & rows[b])) >= 60}
    assert {frozenset((r.doc_id, r.earlier)): r.shared for r in pairs} == expected and len(pairs) == len(expected)


def test_stream_of_documents_equals_its_sql_in_any_order(spark, folders):
    import os

    from symbits.plans import queries

    d = os.path.dirname(folders["documents"]) + "/documents-apart"
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    for half in (1, 0):  # the later documents of a pair may come first
        docs.where(f"doc_id % 2 = {half}").coalesce(1).write.mode("append").parquet(f"{d}/documents.parquet")
    rows = {}
    for r in docs.where("text is not null").collect():
        words = re.findall("[a-z]+", r.text.lower())
        rows[r.doc_id] = {tuple(words[i : i + 5]) for i in range(len(words) - 4)}
    expected = sorted((a, b, n) for a in rows for b in rows if b < a and (n := len(rows[a] & rows[b])) >= 40)
    assert sorted(map(tuple, queries.QUERIES["stream_near_dup"](spark, d).collect())) == expected and expected


@pytest.mark.parametrize("block", [1000, 2_000_000])
def test_near_duplicates_of_odd_streams(spark, tmp_path, monkeypatch, block):
    """Common runs, repeated rows of a file, nulls, extreme ids, runs of two grams, and set-aside runs that are counted in many passes."""
    from symbits.streaming import arrivals

    monkeypatch.setattr(arrivals, "BLOCK_PAIRS", block)
    rng = np.random.default_rng(7)
    common = [f"c{k}" for k in range(12)]
    texts = [common[: int(rng.integers(4, 13))] + [f"w{k}" for k in rng.integers(0, 30, int(rng.integers(0, 25)))] for _ in range(90)]
    ids = [-(1 << 63), (1 << 63) - 1, *range(-40, 48)]
    path = str(tmp_path / "in")
    for batch in range(3):
        own = [(ids[i], texts[i]) for i in range(batch, 90, 3)]
        own += [own[0], (1000 + batch, None), (2000 + batch, []), (None, texts[0]), (3000 + batch, [None, "c0", None, "c1"])]
        spark.createDataFrame(own, "doc_id long, grams array<string>").coalesce(1).write.mode("append").parquet(path)
    sets = dict(zip(ids, ({(a, b) for a, b in zip(x, x[1:])} for x in texts)))
    for t in (1, 6):
        pairs = st.near_duplicates(st.source(spark, path), t, 2).where("abs(doc_id) not between 3000 and 3002 and earlier not between 3000 and 3002").collect()
        expected = {frozenset((a, b)): n for a in sets for b in sets if a < b and (n := len(sets[a] & sets[b])) >= t}
        assert {frozenset((r.doc_id, r.earlier)): r.shared for r in pairs} == expected and len(pairs) == len(expected)


def test_arrived_runs_are_packed_and_not_moved(spark, tmp_path):
    from symbits.streaming import arrivals

    spark = spark.newSession()  # step() changes its settings
    extremes = np.array([-(1 << 63), 5, (1 << 63) - 1])
    for x in (extremes, np.array([7, 7]), np.empty(0, np.int64)):
        assert arrivals.unpack(arrivals.pack(x, x[::-1]))[1].tolist() == x[::-1].tolist()
    index = arrivals.Arrivals(spark, str(tmp_path), 1, 2)
    for number in (0, 1, 1):  # a batch that runs again replaces its own
        index.step(spark.range(500).selectExpr(f"id * 2 + {number} as doc_id", "transform(sequence(0, 199), x -> concat('gram ', id, ' ', x)) as grams"), number)
    held = spark.table(index.table)
    assert [r.batch for r in held.select("batch").distinct().orderBy("batch").collect()] == [0, 1]
    assert held.selectExpr("sum(length(data))").first()[0] < 12 * 2 * 500 * 200
    plan = held.groupBy("key").applyInArrow(arrivals.met(1, index.few), "kind int, " + arrivals.BLOBS)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan
    assert spark.read.parquet(f"{tmp_path}/pairs/batch=1").agg({"shared": "min"}).first()[0] == 200 and spark.read.parquet(f"{tmp_path}/pairs/batch=1").count() == 500


def test_user_reaches_kinds_over_batches(spark, folders):
    got = [r.user_id for r in st.finished(st.reached(st.source(spark, folders["events"]), ["view", "click", "purchase"], 3)).collect()]
    events = spark.read.parquet(f"{SF}/events.parquet").where("event_type in ('view', 'click', 'purchase')")
    expected = {r.user_id for r in events.groupBy("user_id").agg({"event_type": "collect_set"}).collect() if len(r[1]) == 3}
    assert sorted(got) == sorted(expected)


def test_fixed_workload_builds_only_its_bitmaps(spark):
    from symbits.plans import criteria as C
    from symbits.plans import workloads as W
    from symbits.sources.stored import is_stored

    d = f"{SF}/."  # a path of its own: no index is stored for it
    for name in ("names2", "vocab", "chunks2", "chunks3"):
        index, own = W.narrow_index(spark, d, name, 3, 32)
        assert not is_stored(spark, d, "vocabulary" if name == "vocab" else name)
        whole = W.DATASETS[name][0](spark, d)
        every = C.similarity(whole, W.prototypes(3))
        assert own == every[:32] and (index.rows, index.chunk_bits) == (whole.rows, whole.chunk_bits)
        assert index.df.select("attr", "value").distinct().count() == len(own) < whole.df.select("attr", "value").distinct().count()
        counts = lambda x, crit: [tuple(r) for r in T.evaluate_many(x, [T.Query(tuple(C.fit_to_n(crit, 32)), threshold(t), "sideways_sum") for t in (1, 3, 19, 31)]).orderBy("query").collect()]
        assert counts(index, own) == counts(whole, every)


#: Queries that once made their data up, and the given table each reads.
OF_TABLES = {
    "synthetic_uniform_30000": "lineitem",
    "synthetic_clustered_30000": "lineitem",
    "suboptimality": "events",
    "operation_counts": "lineitem",
    "normalized_time": "events",
    "relative_operations": "lineitem",
    "heatmap_operations": "lineitem",
    "gates_over_minimum": "lineitem",
    "gate_table": "lineitem",
    "competition_rank": "events",
    "circuit_padding": "lineitem",
}


@pytest.mark.parametrize("name", OF_TABLES)
def test_given_table_is_read(spark, name):
    import duckdb

    from symbits.plans import queries, workloads  # noqa: F401

    table = OF_TABLES[name]
    assert f"FROM {table}" in queries.SQL[name]
    made = queries.QUERIES[name](spark, SF)
    if not name.startswith("synthetic"):  # those read an index of it
        assert f"{table}.parquet" in made._jdf.queryExecution().optimizedPlan().toString() or any(f"{table}.parquet" in f for f in made.inputFiles())
    with duckdb.connect() as c:
        c.execute(f"CREATE VIEW {table} AS SELECT * FROM '{SF}/{table}.parquet'")
        found = c.execute(queries.SQL[name])
        columns = [x[0] for x in found.description]
        plain = lambda rows: sorted((tuple(round(x, 9) if isinstance(x, float) else x for x in r) for r in rows), key=repr)
        assert plain(found.fetchall()) == plain(made.select(*columns).collect()) and sorted(columns) == sorted(made.columns)
