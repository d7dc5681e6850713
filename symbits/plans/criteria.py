"""Criteria: which bitmaps of an index a query counts, with weights and negation."""

from __future__ import annotations

import random
import zlib
from collections.abc import Iterable, Sequence
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.index import Index, dense_rids, words_of


@dataclass(frozen=True)
class Criterion:
    attr: str
    value: str
    weight: int = 1
    negated: bool = False


def frame(spark: SparkSession, criteria: Sequence[Criterion]) -> DataFrame:
    """ord, attr, value, weight, negated: as many rows as criteria, so it may be broadcast."""
    rows = [(k, c.attr, c.value, c.weight, c.negated) for k, c in enumerate(criteria)]
    return spark.createDataFrame(rows, "ord int, attr string, value string, weight int, negated boolean")


def total_weight(criteria: Sequence[Criterion]) -> int:
    return sum(c.weight for c in criteria)


def negate(criteria: Sequence[Criterion]) -> list[Criterion]:
    return [replace(c, negated=not c.negated) for c in criteria]


def merged(criteria: Iterable[Criterion]) -> list[Criterion]:
    """Equal criteria once, their weights summed."""
    out: dict[tuple, int] = {}
    for c in criteria:
        out[c.attr, c.value, c.negated] = out.get((c.attr, c.value, c.negated), 0) + c.weight
    return [Criterion(a, v, w, n) for (a, v, n), w in out.items()]


def of_rows(rows: DataFrame, attrs: Sequence[str]) -> list[Criterion]:
    """Criteria that prototype rows (few: they go to the driver) meet, each once, in attribute and value order."""
    found = {(a, str(r[a])) for r in rows.select(*[F.col(a).cast("string").alias(a) for a in attrs]).toLocalIterator() for a in attrs if r[a] is not None}
    return [Criterion(a, v) for a, v in sorted(found)]


def similarity(index: Index, rids: Sequence[int], include_false: bool = True, false_values: Sequence[str] = ("false", "0")) -> list[Criterion]:
    """Criteria that any of the rows with these rids meets: only their chunks are read."""
    wanted = [(r // index.chunk_bits, r % index.chunk_bits) for r in rids]
    spark = index.df.sparkSession
    probe = F.broadcast(spark.createDataFrame([(c, p // 64, p % 64) for c, p in wanted], "chunk long, w int, pb int"))
    near = index.df.where(F.col("chunk").isin(sorted({c for c, _ in wanted}))).select("attr", "value", "chunk", *index.body)
    hit = F.call_function("getbit", F.col("b"), F.col("pb")) == 1
    found = words_of(near, index, "attr", "value").join(probe, ["chunk", "w"]).where(hit).select("attr", "value").distinct()
    if not include_false:
        found = found.where(~F.col("value").isin(*false_values))
    return [Criterion(r["attr"], r["value"]) for r in found.orderBy("attr", "value").toLocalIterator()]


def fit_to_n(criteria: Sequence[Criterion], n: int, duplicate: bool = True) -> list[Criterion]:
    """Exactly n criteria by weight: the first n, or all of them repeated as evenly as can be, the first ones once more."""
    have = len(criteria)
    if n <= have or not duplicate:
        return list(criteria[:n])
    each, extra = divmod(n, have)
    return [replace(c, weight=each + (k < extra)) for k, c in enumerate(criteria)]


def random_attributes(index: Index, trials: int, seed: int = 0) -> list[list[Criterion]]:
    """For each trial one value of each attribute, by an arithmetic rule: of the m values, in order, of the k-th attribute the one at (seed + 7919 * trial + 31 * k) * 104729 modulo m.

    What reaches the driver is the attributes with their numbers of values, and the values picked: trials times attributes.
    """
    values = dense_rids(index.df.select("attr", "value").distinct(), "attr", "value")
    sizes = {r["attr"]: r["count"] for r in values.groupBy("attr").count().toLocalIterator()}
    wanted: dict[int, list[int]] = {}
    start = 0
    for k, a in enumerate(sorted(sizes)):
        for i in range(trials):
            wanted.setdefault(start + (seed + 7919 * i + 31 * k) * 104729 % sizes[a], []).append(i)
        start += sizes[a]
    out: list[list[Criterion]] = [[] for _ in range(trials)]
    for r in values.where(F.col("rid").isin(sorted(wanted))).orderBy("rid").toLocalIterator():
        for i in wanted[r["rid"]]:
            out[i].append(Criterion(r["attr"], r["value"]))
    return out


def random_nt(seed: int, count: int) -> list[tuple[int, int]]:
    """(N, T): log2 N uniform in 2 to 10, T uniform in 2 to N - 1."""
    g = random.Random(zlib.crc32(str(seed).encode()))
    out = []
    for _ in range(count):
        n = max(3, round(2 ** g.uniform(2, 10)))
        out.append((n, g.randint(2, n - 1)))
    return out


def grid(n_max: int) -> list[tuple[int, int]]:
    """Pairs (N, T) of a competition: N = 4, 8, ...; T = 3 and on by half as much again, and their mirror images."""
    out, n = [], 4
    while n <= n_max:
        low, t = [], 3
        while t < n:
            low.append(t)
            t = int(1.5 * t)
        mirrored = {n + 2 - x for x in low if n + 2 - x < n}
        out += [(n, x) for x in sorted({x for x in low if x < n} | mirrored)]
        n *= 2
    return out
