"""Cost and comparison measures: times, ranks, normalized times, and rates over a grid."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


#: Gates of the smallest circuits for at least T of N, by (N, T): fixed values, found by exhaustive search in the literature.
MINIMUM_GATES = {(4, 1): 3, (4, 2): 7, (4, 3): 7, (4, 4): 3, (5, 1): 4, (5, 3): 9, (5, 4): 10, (5, 5): 4}


def over_minimum(gates: dict[tuple[int, int], int]) -> dict[tuple[int, int], int]:
    """Gates above the smallest circuit, where that is known."""
    return {k: n - MINIMUM_GATES[k] for k, n in gates.items() if k in MINIMUM_GATES}


def run(df: DataFrame) -> None:
    """Execute the whole plan without keeping rows."""
    df.write.format("noop").mode("overwrite").save()


def time_adaptive(action: Callable[[], object], min_ms: float = 1000) -> float:
    """Milliseconds of one call: calls are doubled until together they take min_ms."""
    n = 1
    while True:
        began = time.perf_counter()
        for _ in range(n):
            action()
        spent = (time.perf_counter() - began) * 1000
        if spent >= min_ms:
            return spent / n
        n *= 2


def workload_time(actions: list[Callable[[], object]]) -> float:
    """Seconds for all."""
    began = time.perf_counter()
    for a in actions:
        a()
    return time.perf_counter() - began


METRICS = ("stages", "tasks", "rows_read", "bytes_read", "shuffle_bytes", "spill_bytes", "peak_memory", "run_ms")


def spark_metrics(spark: SparkSession, action: Callable[[], object]) -> dict[str, int]:
    """What the stages of an action cost, as Spark's status store has it: the place of hardware counters. peak_memory is the most of a stage."""
    store, sc = spark.sparkContext._jsc.sc().statusStore(), spark.sparkContext._jsc.sc()

    def stages() -> dict:
        sc.listenerBus().waitUntilEmpty(60_000)
        listed = store.stageList(None, False, False, spark.sparkContext._gateway.new_array(spark._jvm.double, 0), None)
        return {(x.stageId(), x.attemptId()): x for x in (listed.apply(i) for i in range(listed.size()))}

    before = set(stages())
    action()
    new = [x for k, x in stages().items() if k not in before]
    values = {
        "stages": len(new), "tasks": sum(x.numCompleteTasks() for x in new), "rows_read": sum(x.inputRecords() for x in new), "bytes_read": sum(x.inputBytes() for x in new),
        "shuffle_bytes": sum(x.shuffleWriteBytes() for x in new), "spill_bytes": sum(x.diskBytesSpilled() for x in new), "peak_memory": max([0, *(x.peakExecutionMemory() for x in new)]), "run_ms": sum(x.executorRunTime() for x in new),
    }
    return {k: int(values[k]) for k in METRICS}


def rank_competition(times: DataFrame) -> DataFrame:
    """times (competition, algo, ms) with rank (0 is fastest), ratio to the fastest, within_50, within_100, terrible (10 times or more)."""
    best = F.min("ms").over(Window.partitionBy("competition"))
    ranked = times.withColumn("rank", F.rank().over(Window.partitionBy("competition").orderBy("ms")) - 1).withColumn("ratio", F.col("ms") / best)
    return ranked.withColumn("within_50", F.col("ratio") <= 1.5).withColumn("within_100", F.col("ratio") <= 2).withColumn("terrible", F.col("ratio") >= 10)


def normalized_time(times: DataFrame) -> DataFrame:
    """algo, total: the time divided by the fastest method's, summed over competitions."""
    best = F.min("ms").over(Window.partitionBy("competition"))
    return times.select("algo", (F.col("ms") / best).alias("share")).groupBy("algo").agg(F.sum("share").alias("total"))


def suboptimality(times: DataFrame) -> DataFrame:
    best = F.min("ms").over(Window.partitionBy("competition"))
    return times.withColumn("suboptimality", (F.col("ms") - best) / best)


def normalize_by_n(times: DataFrame, base: int = 32) -> DataFrame:
    """times (algo, n, ms) relative to the same algo's at n = base."""
    own = F.max(F.when(F.col("n") == base, F.col("ms"))).over(Window.partitionBy("algo"))
    return times.withColumn("relative", F.col("ms") / own)


def heatmap(times: DataFrame, bins: int = 4) -> DataFrame:
    """n_bin, t_bin and for each algo the share of competitions (n, t) there that it wins."""
    won = rank_competition(times).withColumn("n_bin", F.floor(F.log2("n")).cast("int")).withColumn("t_bin", F.least(F.floor(F.col("t") * bins / F.col("n")), F.lit(bins - 1)).cast("int"))
    return won.groupBy("n_bin", "t_bin").pivot("algo").agg(F.avg((F.col("rank") == 0).cast("double")))


def win_rates(times: DataFrame) -> DataFrame:
    """algo, wins, runs over all competitions."""
    return rank_competition(times).groupBy("algo").agg(F.sum((F.col("rank") == 0).cast("long")).alias("wins"), F.count("*").alias("runs"))
