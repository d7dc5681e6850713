import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from symbits.functions.spec import between, exactly, parity, symmetric, threshold
from symbits.operators import codec
from symbits.operators import threshold as T
from symbits.operators.index import Index, build, chunk_words, coalesced, decoded, dense_rids, encode, from_rids, stats, write
from symbits.plans import criteria as C
from symbits.plans.criteria import Criterion
from symbits.sources.stored import STYLES

ROWS = 700
SETS = {"dense": [r for r in range(ROWS) if r % 5], "runs": [r for r in range(ROWS) if r // 90 % 2], "sparse": [0, 63, 64, 127, 128, 255, 256, 699], "all": list(range(ROWS)), "some": list(range(0, ROWS, 3))}
CRITERIA = [Criterion("s", k) for k in SETS] + [Criterion("s", "none")]


@pytest.fixture(scope="module")
def index(spark):
    return build(spark.createDataFrame([("s", k, r) for k, rids in SETS.items() for r in rids], "attr string, value string, rid long"), ROWS, 128)


def _expected(criteria, spec):
    n = sum(c.weight for c in criteria)
    held = {k: set(v) for k, v in SETS.items()}
    return {r for r in range(ROWS) if spec.vector(n)[sum(c.weight for c in criteria if (r in held.get(c.value, ())) != c.negated)]}


def _rids(bitmap):
    return {r[0] for r in bitmap.rids().collect()}


def test_stats_count_runs_over_borders_once(index):
    got = {r.value: (r.card, r.runs) for r in stats(index).collect()}
    assert got == {k: (len(v), sum(1 for i, r in enumerate(v) if not i or v[i - 1] != r - 1)) for k, v in SETS.items()}


@pytest.mark.parametrize("style", [s for s in STYLES if s != "words"])
def test_styles_hold_the_same(index, style):
    own = encode(index, *STYLES[style])
    assert own.encoded and _rids(own.bitmap("s", "runs")) == set(SETS["runs"])
    for method in ("counter_array", "counter_hash", "set_aside_probe", "set_aside_joins", "run_merge", "sideways_sum"):
        assert _rids(T.evaluate(own, CRITERIA, threshold(3), method)) == _expected(CRITERIA, threshold(3)), method


def test_trimmed_payloads_are_shorter(index):
    size = lambda trim: encode(index, "plain", trim).df.agg(F.sum(F.octet_length("payload"))).first()[0]
    assert size(True) < size(False)


def test_list_style_is_for_list_methods(index):
    own = encode(index)
    for method in ("sort_count", "pair_counts", "heap_merge", "heap_skip", "set_aside_probe", "tuned_set_aside_skip"):
        assert _rids(T.evaluate(own, CRITERIA, threshold(4), method, style="list")) == _expected(CRITERIA, threshold(4)), method
    with pytest.raises(ValueError, match="style"):
        T.Query(tuple(CRITERIA), threshold(4), "counter_array", {}, "list").kernel()


@pytest.mark.parametrize("method", ["set_aside_joins", "set_aside_probe", "counter_array", "run_merge", "pair_counts_joins"])
def test_negated_and_weighted(index, method):
    own = [Criterion("s", "dense", 2, True), Criterion("s", "runs"), Criterion("s", "sparse", 1, True), Criterion("s", "all"), Criterion("s", "none", 1, True)]
    for t in (2, 4, 5):
        assert _rids(T.evaluate(index, own, threshold(t), method)) == _expected(own, threshold(t))


@pytest.mark.parametrize("backend", ["bytecode", "vertical", "staged", "tree"])
def test_circuit_backends(index, backend):
    for family in ("adder_tree", "sideways_sum", "sort_network", "sum_of_products"):
        assert _rids(T.evaluate(index, CRITERIA, threshold(3), family, backend=backend)) == _expected(CRITERIA, threshold(3))


@pytest.mark.parametrize("comparator", ["constant", "sign", "variable"])
def test_comparators(index, comparator):
    for spec in (threshold(3), between(1, 2), exactly(4), parity()):
        assert _rids(T.evaluate(index, CRITERIA, spec, "adder_tree", backend="bytecode", comparator=comparator)) == _expected(CRITERIA, spec)


def test_many_queries_in_one_pass(index):
    specs = [threshold(2), exactly(3), symmetric([True] + [False] * 6), threshold(6)]
    made = [T.Query(tuple(CRITERIA), s, "counter_array") for s in specs]
    assert {r.query: r.ones for r in T.evaluate_many(index, made).collect()} == {k: len(_expected(CRITERIA, s)) for k, s in enumerate(specs)}
    timed = T.kernel_times(index, made).collect()
    assert len(timed) == 4 and all(r.ms >= 0 for r in timed)


def test_any_function_of_runs(index):
    got = _rids(T.evaluate_function(index, CRITERIA[:3], lambda x: x[0] & ~x[1] | x[2]))
    held = [set(SETS[c.value]) for c in CRITERIA[:3]]
    assert got == {r for r in range(ROWS) if r in held[0] and r not in held[1] or r in held[2]}
    assert _rids(T.evaluate_function(index, CRITERIA[:1], lambda x: ~x[0])) == set(range(ROWS)) - held[0]


def test_intervals_over_many_chunks(spark, monkeypatch):
    from symbits.operators import index as module

    monkeypatch.setattr(module, "LINKED", 4)
    g = random.Random(2)
    rids = sorted({r for _ in range(40) for a in [g.randrange(20_000)] for r in range(a, min(20_000, a + g.choice([1, 3, 70, 900])))})
    got = sorted(tuple(r) for r in from_rids(spark.createDataFrame([(r,) for r in rids], "rid long"), 20_000, 64).intervals().collect())
    starts = [r for r in rids if r - 1 not in set(rids)]
    assert [a for a, _ in got] == starts and sum(b - a + 1 for a, b in got) == len(rids)
    assert coalesced(spark.createDataFrame([], "chunk long, start long, stop long")).count() == 0


def test_stored_index_needs_no_exchange_by_chunk(spark, index, tmp_path):
    stored = write(index, str(tmp_path / "i"), "symbits_test_index", 4)
    plan = T.by_chunk(stored, [T.Query(tuple(CRITERIA), threshold(2))])._jdf.queryExecution().executedPlan().toString()
    assert "Exchange hashpartitioning" not in plan and "In(value" in plan
    assert _rids(T.evaluate(stored, CRITERIA, threshold(2), "counter_array")) == _expected(CRITERIA, threshold(2))
    assert _rids(T.evaluate(Index(stored.df, ROWS, 128), CRITERIA, threshold(2), "counter_hash")) == _expected(CRITERIA, threshold(2))


def test_words_from_arrow(index):
    import pyarrow as pa

    table = pa.Table.from_batches(index.df.where("kind = 1").select("attr", "value", "chunk", "words", "card").toArrow().to_batches())
    found = chunk_words(table.column("words").combine_chunks(), 2)
    assert [int(np.bitwise_count(x).sum()) for x in found] == table.column("card").to_pylist()
    rows = encode(index, "rle")
    back = decoded(rows.df.select("value", "chunk", "kind", "encoding", "payload"), rows, "value").where("kind = 1").select(F.sum(F.size("words"))).first()[0]
    assert back == index.df.select(F.sum(F.size("words"))).first()[0]


def test_stretches_give_the_words_at_places():
    g = np.random.default_rng(1)
    for _ in range(30):
        words = g.choice(np.array([0, 2**64 - 1, 5, 2**63], np.uint64), 40, p=[0.5, 0.3, 0.1, 0.1])
        at = g.integers(0, 40, 25)
        assert np.array_equal(codec.Stretches(codec.encode(words, "rle")[1]).words(at), words[at])


def test_criteria(index):
    assert C.similarity(index, [0]) == [Criterion("s", "all"), Criterion("s", "some"), Criterion("s", "sparse")]
    assert C.similarity(encode(index), [0, 699]) == C.similarity(index, [0, 699])
    assert C.fit_to_n(CRITERIA[:3], 7)[0].weight == 3 and len(C.fit_to_n(CRITERIA[:3], 7, duplicate=False)) == 3
    trials = C.random_attributes(index, 5)
    assert len(trials) == 5 and all(len(t) == 1 for t in trials) and C.random_attributes(index, 5) == trials
    pairs = C.random_nt(1, 200)
    assert all(2 <= t < n and 3 <= n <= 1024 for n, t in pairs) and C.random_nt(1, 200) == pairs


def test_dense_rids(spark):
    rows = [(x % 97, x) for x in range(500)]
    got = {(r.a, r.b): r.rid for r in dense_rids(spark.createDataFrame(rows, "a long, b long"), "a", "b").collect()}
    assert [k for k, _ in sorted(got.items(), key=lambda kv: kv[1])] == sorted(rows) and sorted(got.values()) == list(range(500))
