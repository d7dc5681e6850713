import pytest

from symbits.functions.spec import at_most, threshold
from symbits.operators import threshold as T
from symbits.operators.index import build
from symbits.plans.criteria import Criterion

SETS = {"a": range(0, 200), "b": range(0, 200, 2), "c": range(0, 200, 3), "d": [0, 63, 64, 127, 128, 199], "none": []}


@pytest.fixture(scope="module")
def index(spark):
    rows = [("s", k, r) for k, rids in SETS.items() for r in rids]
    return build(spark.createDataFrame(rows, "attr string, value string, rid long"), 200, 64)


def _expected(criteria, spec):
    n = sum(c.weight for c in criteria)
    return {r for r in range(200) if spec.vector(n)[sum(c.weight for c in criteria if (r in set(SETS.get(c.value, []))) != c.negated)]}


CRITERIA = [Criterion("s", "a"), Criterion("s", "b", 2), Criterion("s", "c", negated=True), Criterion("s", "d"), Criterion("s", "none"), Criterion("s", "missing")]


@pytest.mark.parametrize("method", ["counter_array", "counter_hash", "sort_count_windows", "pair_counts_joins", "set_aside_joins", "run_merge_sweep", "recurrence_fold", "sideways_sum", "tuned_set_aside_skip", "auto"])
def test_methods_agree(index, method):
    got = {r[0] for r in T.evaluate(index, CRITERIA, threshold(3), method).rids().collect()}
    assert got == _expected(CRITERIA, threshold(3))


def test_edges(index):
    assert {r[0] for r in T.evaluate(index, CRITERIA[:4], at_most(1), "counter_hash").rids().collect()} == _expected(CRITERIA[:4], at_most(1))
    assert T.evaluate(index, CRITERIA, threshold(99), "counter_hash").rids().count() == 0
    assert T.evaluate(index, [], threshold(0), "counter_hash").rids().count() == 200
    assert (~index.bitmap("s", "d")).count().first()[0] == 194
    assert [tuple(r) for r in index.bitmap("s", "a").intervals().collect()] == [(0, 199)]
