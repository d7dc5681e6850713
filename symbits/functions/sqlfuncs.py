"""What SQL users can call once register(spark) ran: a threshold of word arrays, and table functions."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf


def register(spark: SparkSession) -> None:
    """bm_threshold(array of word arrays, t), unnest_bits(base, words), qgrams(text, q)."""
    import numpy as np

    @pandas_udf("array<bigint>")
    def bm_threshold(words: pd.Series, t: pd.Series) -> pd.Series:
        from symbits.operators.kernels import counter_array

        out = []
        for rows, least in zip(words, t):
            size = max((len(r) for r in rows), default=0)
            inputs = [np.array([*r, *[0] * (size - len(r))], np.int64).view(np.uint64) for r in rows]
            truth = np.arange(len(inputs) + 1) >= least
            out.append(counter_array(inputs, [1] * len(inputs), truth, int(least)).view(np.int64).tolist() if size else [])
        return pd.Series(out)

    @udtf(returnType="rid: bigint")
    class UnnestBits:
        def eval(self, base: int, words: list[int]) -> Iterator[tuple[int]]:
            for w, b in enumerate(words or []):
                b &= (1 << 64) - 1
                while b:
                    low = b & -b
                    yield (base + w * 64 + low.bit_length() - 1,)
                    b ^= low

    @udtf(returnType="gram: string, ordinal: int")
    class QGrams:
        def eval(self, text: str, q: int) -> Iterator[tuple[str, int]]:
            seen: dict[str, int] = {}
            for i in range(len(text or "") - q + 1):
                g = text[i : i + q]
                seen[g] = seen.get(g, 0) + 1
                yield g, seen[g]

    spark.udf.register("bm_threshold", bm_threshold)
    spark.udtf.register("unnest_bits", UnnestBits)
    spark.udtf.register("qgrams", QGrams)
