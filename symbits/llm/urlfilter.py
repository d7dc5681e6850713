"""URL filter: rules first, then logistic regression on hashed character n-grams of host and path.

The model is fitted on the driver from a small table of labelled URLs; by default those that rules decide,
at most LABELLED of each verdict, those of least hash. Training is plain gradient descent from zero, so that
a table always gives the same weights.

Defined results: a null URL and one without ``://`` have empty host and path, no rule, and go to the model;
with no labelled URL every verdict is allow, with labels of one verdict it is that one; repeated rows
get equal results.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

LABELLED = 2000
BUCKETS = 1 << 15
SIZES = (3, 4, 5)
ROUNDS, RATE, DECAY = 200, 4.0, 1e-4

#: (verdict, host and path): fixed values of the contract.
RULES = (
    ("allow", "com/"),
    ("block", "example.com/en/"),
    ("allow", "www.example.com/en/"),
    ("block", "net/es/"),
    ("block", "net/fr/"),
)

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_of(url: Column) -> Column:
    return F.coalesce(F.translate(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1), UPPER, LOWER), F.lit(""))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def rule_for(host: Column, path: Column, rules: Sequence[tuple[str, str]] = RULES) -> tuple[Column, Column]:
    """The longest rule that fits, and its verdict; null if none does."""
    rule = verdict = F.lit(None).cast("string")
    for decision, text in sorted(rules, key=lambda r: len(r[1])):  # the longest decides last
        at, _, under = text.partition("/")
        fits = ((host == at) | host.endswith("." + at)) & path.startswith("/" + under)
        rule = F.when(fits, F.lit(text)).otherwise(rule)
        verdict = F.when(fits, F.lit(decision)).otherwise(verdict)
    return rule, verdict


def features(host: str, path: str) -> np.ndarray:
    """Buckets of the distinct n-grams of host and path."""
    text = f"^{host}|{path}$".encode()
    return np.unique(np.array([zlib.crc32(text[i : i + n]) % BUCKETS for n in SIZES for i in range(len(text) - n + 1)], np.int64))


class UrlModel:
    """Weights of a logistic regression; features count by the inverse root of their number."""

    def __init__(self, weights: np.ndarray, bias: float):
        self.weights, self.bias = weights, bias

    def chance(self, host: str, path: str) -> float:
        """Of block."""
        f = features(host, path)
        return float(1 / (1 + np.exp(-(self.bias + (self.weights[f].sum() / np.sqrt(len(f)) if len(f) else 0.0)))))


def fit(rows: Sequence[tuple[str, str, bool]]) -> UrlModel:
    """rows: host, path, whether it is to be blocked."""
    if len({r[2] for r in rows}) < 2:
        return UrlModel(np.zeros(BUCKETS), 9.0 if rows and rows[0][2] else -9.0)
    found = [features(h, p) for h, p, _ in rows]
    row = np.repeat(np.arange(len(rows)), [len(f) for f in found])
    bucket = np.concatenate(found)
    value = np.repeat([1 / np.sqrt(len(f)) for f in found], [len(f) for f in found])
    y = np.array([float(r[2]) for r in rows])
    share = np.where(y > 0, 0.5 / y.sum(), 0.5 / (1 - y).sum())  # both verdicts weigh the same
    weights, bias = np.zeros(BUCKETS), 0.0
    for _ in range(ROUNDS):
        z = np.bincount(row, value * weights[bucket], len(rows)) + bias
        error = (1 / (1 + np.exp(-z)) - y) * share
        weights -= RATE * (np.bincount(bucket, value * error[row], BUCKETS) + DECAY * weights)
        bias -= RATE * error.sum()
    return UrlModel(weights, float(bias))


def labelled_by_rules(pages: DataFrame, limit: int = LABELLED, rules: Sequence[tuple[str, str]] = RULES) -> list[tuple[str, str, bool]]:
    """At most limit distinct URLs of each verdict that a rule decides, those of least hash."""
    host, path = host_of(F.col("url")), path_of(F.col("url"))
    decided = pages.select(host.alias("host"), path.alias("path"), rule_for(host, path, rules)[1].alias("verdict")).where("verdict is not null").distinct()
    rows: list[tuple[str, str, bool]] = []
    for verdict in ("allow", "block"):
        least = decided.where(F.col("verdict") == verdict).orderBy(F.xxhash64("host", "path"), "host", "path").limit(limit)
        rows += [(r["host"], r["path"], verdict == "block") for r in least.collect()]
    return rows


def judge_urls(pages: DataFrame, model: UrlModel, rules: Sequence[tuple[str, str]] = RULES) -> DataFrame:
    """Per row of pages (page_id, url): page_id, host, path, rule, verdict, block_chance (null where a rule decides)."""
    host, path = host_of(F.col("url")), path_of(F.col("url"))
    split = pages.select("page_id", host.alias("host"), path.alias("path"))
    rule, verdict = rule_for(F.col("host"), F.col("path"), rules)
    ruled = split.withColumn("rule", rule).withColumn("by_rule", verdict)
    kind = pages.schema["page_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            _, hosts, paths, _, done = (c.to_pylist() for c in batch.columns)
            chance = [None if d is not None else model.chance(h, p) for h, p, d in zip(hosts, paths, done)]
            verdicts = [d if d is not None else "block" if c >= 0.5 else "allow" for d, c in zip(done, chance)]
            yield pa.RecordBatch.from_arrays([*batch.columns[:4], pa.array(verdicts, pa.string()), pa.array(chance, pa.float64())], ["page_id", "host", "path", "rule", "verdict", "block_chance"])

    return ruled.mapInArrow(run, f"page_id {kind}, host string, path string, rule string, verdict string, block_chance double")
