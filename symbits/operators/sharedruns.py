"""Search for texts that share runs of words with queries, without a row for each run.

The runs of a block of queries are a sorted array that is broadcast; each task looks up the runs of its texts and counts by numpy, so that nothing is
shuffled or stored. Words are numbered exactly by the block's vocabulary, and runs by their words' numbers: no hash decides a count.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Words of queries in a block, on average. Each block is a pass over the texts.
BLOCK_WORDS = 3_000_000
#: Words, counters, and met queries that are held at a time.
PIECE = 1 << 20


def _places(lengths: np.ndarray) -> np.ndarray:
    return np.repeat(np.arange(len(lengths)), lengths)


class Runs:
    """The distinct runs of q words of some queries, each with the queries that hold it."""

    def __init__(self, queries: np.ndarray, words: pa.ListArray, q: int):
        coded = words.flatten().dictionary_encode()
        self.queries, self.q, self.vocabulary, self.levels = queries, q, coded.dictionary, []
        owner = _places(words.value_lengths().to_numpy())
        keys, at = self._keys(coded.indices.to_numpy().astype(np.int64), owner, True)
        # a row for each distinct run and query, by run
        self.runs, number = np.unique(keys, return_inverse=True)
        pairs = np.unique(number * max(1, len(queries)) + owner[at])
        self.holders = (pairs % max(1, len(queries))).astype(np.int32)
        self.starts = np.searchsorted(pairs, np.arange(len(self.runs) + 1) * max(1, len(queries)))
        # most runs of a text are in no query: a table of bits spares their search
        self.shift = np.uint64(64 - max(4, min(27, int(8 * len(self.runs) + 1).bit_length())))
        self.seen = np.zeros(1 << (64 - int(self.shift)), bool)
        self.seen[self._slot(self.runs)] = True

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return (keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> self.shift

    def _keys(self, ids: np.ndarray, owner: np.ndarray, learn: bool = False) -> tuple[np.ndarray, np.ndarray]:
        """Numbers of the runs of q known words within one text, and where they start. Where numbers would pass 2**62, the prefixes are numbered anew."""
        at = np.flatnonzero(ids >= 0)
        keys, size, level = ids[at], max(1, len(self.vocabulary)), 0
        most = size
        for k in range(1, self.q):
            if most * size >= 1 << 62:
                if learn:
                    self.levels.append(np.unique(keys))
                table = self.levels[level]
                found = np.searchsorted(table, keys)
                known = table[np.minimum(found, len(table) - 1)] == keys if len(table) else np.zeros(len(keys), bool)
                keys, at, most, level = found[known], at[known], max(1, len(table)), level + 1
                if most * size >= 1 << 62:
                    raise ValueError("the block has too many words")
            inside = at + k < len(ids)
            inside[inside] &= (owner[at[inside] + k] == owner[at[inside]]) & (ids[at[inside] + k] >= 0)
            keys, at = keys[inside] * size + ids[at[inside] + k], at[inside]
            most *= size
        return keys, at

    def shared(self, words: pa.ListArray, t: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """Number of the text, of the query, and distinct runs they share, where these are at least t."""
        n = len(self.queries)
        if not n or not len(self.runs):
            return
        ids = pc.fill_null(pc.index_in(words.flatten(), value_set=self.vocabulary), -1).to_numpy().astype(np.int64)
        owner = _places(words.value_lengths().to_numpy())
        keys, at = self._keys(ids, owner)
        likely = self.seen[self._slot(keys)]
        keys, at = keys[likely], at[likely]
        found = np.searchsorted(self.runs, keys)
        hit = self.runs[np.minimum(found, len(self.runs) - 1)] == keys
        pairs = np.unique(owner[at[hit]] * len(self.runs) + found[hit])
        text, run = pairs // len(self.runs), pairs % len(self.runs)
        held = self.starts[run + 1] - self.starts[run]
        # texts of fewer runs than t can't share t
        enough = np.bincount(text, minlength=len(words))[text] >= t
        text, run, held = text[enough], run[enough], held[enough]
        width = max(1, PIECE // n)
        a = 0
        while a < len(text):
            first = text[a]
            stop = np.searchsorted(text, first + width)
            counts = np.zeros(width * n, np.int64)
            ends = np.cumsum(held[a:stop])
            b = a
            while b < stop:
                done = ends[b - a - 1] if b > a else 0
                c = max(b + 1, a + int(np.searchsorted(ends, done + PIECE, "right")))
                own = held[b:c]
                place = np.repeat(self.starts[run[b:c]] - (np.cumsum(own) - own), own) + np.arange(own.sum())
                counts += np.bincount(np.repeat(text[b:c] - first, own) * n + self.holders[place], minlength=width * n)
                b = c
            full = np.flatnonzero(counts >= t)
            yield full // n + first, full % n, counts[full]
            a = stop


def sharing_runs(texts: DataFrame, asked: DataFrame, key: str, query: str, q: int, t: int) -> DataFrame:
    """query, key, n: for each query of asked (query, words), the texts (key, words) that share at least t of its distinct runs of q words. Keys are longs, each once."""
    if t < 1:
        raise ValueError("t is at least 1")
    # fewer words have fewer than t runs
    texts, asked = (df.where(F.size("words") >= q + t - 1) for df in (texts, asked))
    spark = texts.sparkSession
    blocks = max(1, -(-(asked.agg(F.sum(F.size("words"))).first()[0] or 0) // BLOCK_WORDS))
    schema = f"`{query}` long, `{key}` long, n long"

    def counted(block: int) -> DataFrame:
        own = asked.where(F.pmod(F.xxhash64(query), F.lit(blocks)) == block).select(F.col(query).cast("long"), "words").toArrow()
        words = own.column(1).combine_chunks()
        held = spark.sparkContext.broadcast(Runs(own.column(0).to_numpy(), pa.concat_arrays(words.chunks) if isinstance(words, pa.ChunkedArray) else words, q))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            index = held.value
            for batch in batches:
                ends = np.cumsum(batch.column(1).value_lengths().to_numpy())
                a = 0
                while a < len(ends):
                    b = max(a + 1, int(np.searchsorted(ends, (ends[a - 1] if a else 0) + PIECE, "right")))
                    own = batch.slice(a, b - a)
                    ids = own.column(0).to_numpy()
                    for text, asks, n in index.shared(own.column(1), t):
                        yield pa.RecordBatch.from_arrays([pa.array(index.queries[asks]), pa.array(ids[text]), pa.array(n)], [query, key, "n"])
                    a = b

        return texts.select(F.col(key).cast("long"), "words").mapInArrow(run, schema)

    return reduce(DataFrame.unionByName, map(counted, range(blocks)))
