"""Small operators around the methods: joins, top-k, approximate matching, as-of and overlap joins."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.tables import grams
from .index import Bitmap, Index


def join_back(bitmap: Bitmap, df: DataFrame, key: str) -> DataFrame:
    """Rows of df whose key is in the bitmap."""
    return df.join(bitmap.rids(), F.col(key) == F.col("rid"), "left_semi")


def top_k(found: DataFrame, k: int, count: str = "n", key: str = "rid") -> DataFrame:
    """The k highest counts, ties to the smaller key."""
    return found.orderBy(F.desc(count), key).limit(k)


def overlap_join(a: DataFrame, b: DataFrame, width: int) -> DataFrame:
    """Pairs of runs (start, stop) of a and b that overlap: an equi-join on cells of that width, each pair kept in its first common cell."""
    cells = lambda df, x: df.select(F.col("start").alias(f"{x}_start"), F.col("stop").alias(f"{x}_stop"), F.explode(F.sequence(F.floor(F.col("start") / width), F.floor(F.col("stop") / width))).alias("cell"))
    both = cells(a, "a").join(cells(b, "b"), "cell")
    return both.where((F.col("a_start") <= F.col("b_stop")) & (F.col("b_start") <= F.col("a_stop")) & (F.col("cell") == F.floor(F.greatest("a_start", "b_start") / width))).drop("cell")


def as_of(left: DataFrame, right: DataFrame, ts: str, keys: Sequence[str], value: str) -> DataFrame:
    """left with the last value of right at or before ts for the same keys: one union and one window."""
    marked = left.withColumn("__v", F.lit(None).cast(right.schema[value].dataType)).withColumn("__left", F.lit(True))
    other = right.select(*keys, ts, F.col(value).alias("__v")).withColumn("__left", F.lit(False))
    w = Window.partitionBy(*keys).orderBy(ts, "__left").rowsBetween(Window.unboundedPreceding, 0)
    both = marked.unionByName(other, allowMissingColumns=True).withColumn(value, F.last("__v", ignorenulls=True).over(w))
    return both.where("__left").drop("__v", "__left")


def sharing(rows: DataFrame, asked: DataFrame, key: str, query: str, t: int, gram: str = "gram") -> DataFrame:
    """query, key, n: for each query of asked (query, gram), the keys of rows (key, gram) that share at least t of its grams. Both are distinct.

    The t - 1 grams of a query that most rows hold only confirm: a row without any other gram of the query can't have t. So the commonest
    grams, which would pair every query with every row, meet candidates alone.
    """
    counted = rows.join(asked.select(gram).distinct(), gram, "left_semi").groupBy(gram).agg(F.count("*").alias("__df"))
    w = Window.partitionBy(query).orderBy(F.desc("__df"), gram)
    ranked = asked.join(counted, gram).withColumn("__r", F.row_number().over(w))
    first = rows.join(ranked.where(F.col("__r") >= t).select(query, gram), gram).groupBy(query, key).agg(F.count("*").alias("__n"))
    aside = ranked.where(F.col("__r") < t).select(query, gram)
    # candidates ask for the grams set aside, each row once
    more = first.select(query, key).join(aside, query).join(rows, [key, gram]).groupBy(query, key).agg(F.count("*").alias("__m"))
    both = first.join(more, [query, key], "left").withColumn("n", F.col("__n") + F.coalesce("__m", F.lit(0)))
    return both.where(F.col("n") >= t).select(query, key, "n")


def approximate_by_index(index: Index, names: DataFrame, key: str, name: str, wanted: str, k: int, q: int = 2) -> DataFrame:
    """approximate_match() with candidates from an index of padded q-grams: those that hold enough of wanted's grams are compared exactly."""
    from ..functions.spec import threshold
    from ..plans.criteria import Criterion
    from .threshold import evaluate

    t = len(wanted) + q - 1 - k * q
    if t > 0:
        padded = "^" * (q - 1) + wanted + "$" * (q - 1)
        seen: dict[str, int] = {}
        asked = []
        for i in range(len(padded) - q + 1):
            own = padded[i : i + q]
            seen[own] = seen.get(own, 0) + 1
            asked.append(Criterion("gram", f"{own}#{seen[own]}"))
        names = names.join(evaluate(index, asked, threshold(t), "counter_array").rids(), F.col(key) == F.col("rid"), "left_semi")
    return names.select(key, F.levenshtein(F.col(name), F.lit(wanted), k).alias("distance")).where(F.col("distance").between(0, k))


def approximate_match(names: DataFrame, key: str, name: str, wanted: str, k: int, q: int = 2) -> DataFrame:
    """key, distance of the names within k edits of wanted.

    A name within k edits shares at least len(wanted) + q - 1 - k * q padded q-gram occurrences; those that do are
    compared exactly. Where that bound is not positive every name is compared.
    """
    t = len(wanted) + q - 1 - k * q
    near = names.where(F.abs(F.length(name) - len(wanted)) <= k)
    if t > 0:
        asked = grams(F.lit(wanted), q, pad=True)
        shared = F.size(F.array_intersect(grams(F.col(name), q, pad=True), asked))
        near = near.where(shared >= t)
    return near.select(key, F.levenshtein(F.col(name), F.lit(wanted), k).alias("distance")).where(F.col("distance").between(0, k))
