"""Which method for which query, from counts in the index's metadata alone."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field

from pyspark.sql import functions as F

from ..functions.spec import Spec, normalize
from ..operators.index import Index
from .criteria import Criterion, total_weight


#: Mean density from which on the complement is counted.
DENSE = 0.9


@dataclass(frozen=True)
class Choice:
    method: str
    why: str
    options: dict = field(default_factory=dict)
    complement: bool = False


def query_stats(index: Index, criteria: Sequence[Criterion], t: int | None = None, aside: int | None = None) -> dict:
    """Ones in all inputs (b), in the n - t + 1 smallest (b_small) and outside the aside largest (b_rest) are sums of cards: one row per criterion reaches the driver.

    An input of weight w counts w times, as its copies would.
    """
    from ..operators.threshold import selected

    own = selected(index, criteria, "card", "runs", "dirty", "kind").groupBy("ord").agg(F.sum("card").alias("card"), F.sum("runs").alias("runs"), F.sum("dirty").alias("dirty"))
    found = {r["ord"]: r for r in own.toLocalIterator()}
    each = [index.rows - found[k]["card"] if c.negated and k in found else index.rows if c.negated else found[k]["card"] if k in found else 0 for k, c in enumerate(criteria)]
    cards, n = sorted(x for x, c in zip(each, criteria) for _ in range(c.weight)), total_weight(criteria)
    return {
        "rows": index.rows, "n": n, "cards": cards, "b": sum(cards), "b_small": None if t is None else sum(cards[: max(0, n - t + 1)]), "b_rest": None if aside is None else sum(cards[: n - aside]),
        "runs": sum(r["runs"] * criteria[k].weight for k, r in found.items()), "dirty": sum(r["dirty"] for r in found.values()), "density": sum(cards) / max(1, index.rows * n),
    }


def rule(stats: dict, spec: Spec, n: int) -> Choice:
    """Of dense inputs the complement is counted: their negations are sparse, and few of them can be missing."""
    form, t = normalize(spec, n)
    density, cards = stats["density"], stats["cards"]
    if form in ("or", "and"):
        return Choice("wide", f"the function is {form}")
    if form == "threshold" and density > DENSE:
        return Choice("counter_array", "dense inputs: their sparse negations are counted", complement=True)
    if form == "threshold" and density > 0.5 and n <= 512 and stats["runs"] * 8 > stats["b"]:
        return Choice("sideways_sum", "dense words: adders don't depend on the number of ones")
    if density < 1e-3:
        return Choice("counter_hash", "very sparse: rows of the aggregation are few")
    if form == "threshold" and n > 2 and t >= n - max(1, n // 16) and cards[-1] > 8 * max(1, cards[0]):
        return Choice("set_aside_joins", "T near N and sizes differ: the large inputs only confirm")
    if stats["runs"] * 8 <= stats["b"]:
        return Choice("run_merge_sweep", "long runs")
    if form == "threshold" and t <= 3 and n <= 64:
        return Choice("recurrence_fold", "small T")
    if n > 512:
        return Choice("counter_array", "too many inputs for a circuit")
    return Choice("sideways_sum", "circuits are steady over T and N")


def choose(index: Index, criteria: Sequence[Criterion], spec: Spec) -> Choice:
    return rule(query_stats(index, criteria), spec, total_weight(criteria))


def tune_mu(times: dict[tuple[float, int], float]) -> float:
    """The mu of least mean time, from times by (mu, query)."""
    by: dict[float, list[float]] = {}
    for (mu, _), s in times.items():
        by.setdefault(mu, []).append(s)
    return min(by, key=lambda m: sum(by[m]) / len(by[m]))


def best_of_mu(times: dict[tuple[float, int], float]) -> dict[int, tuple[float, float]]:
    """For each query the mu of least time, and that time."""
    best: dict[int, tuple[float, float]] = {}
    for (mu, query), s in times.items():
        if query not in best or s < best[query][1]:
            best[query] = (mu, s)
    return best
