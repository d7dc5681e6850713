"""Exact top-k inner products by KD-trees, one per shard of the vectors.

A shard's tree splits at medians of the widest dimension and keeps a tight box at each node. No vector in a box
scores more than the sum, by dimension, of the query's larger product with the box's two sides: nodes are visited by
falling bound until it is below the k-th score so far. That k-th score starts from the query's
home shard, the one that holds it: the first round searches there only, the second hands its k-th score to all other shards, and
a query goes to those whose root bound reaches it.

Vectors are integers, floor(1024 * x); scores are exact: products whose sums may pass 2**53 are taken with integers of any size, and a
component of 2**52 or more, or a score that a long can't hold, is an error. Ties go to the smaller id.

Trees are rows, one a shard of at most about SHARD_ROWS vectors, and are moved once; queries travel as blocks of at most about BLOCK_ROWS.
Blocks meet shards, not rows rows. The shards' root boxes are broadcast to the blocks if they have at most BOX_BYTES in all; else blocks go to all shards.

Defined results: vectors null or holding null, NaN or infinite components take no part, nor do empty ones and those without an id; a query
is searched among the vectors of its own length, each length in trees of its own; a query has fewer rows if fewer vectors take part; rows that share an id are each
a vector, and none with the query's id is its candidate; queries that share an id are an error; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import written

SCALE = 1024
SHARD_ROWS = 8192
BLOCK_ROWS = 1024
LEAF_ROWS = 128
BOX_BYTES = 1 << 26
EXACT = float(1 << 53)


def whole_vectors(vectors: DataFrame, key: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """vec_id and v (array<long>, floor(SCALE * x)) of the vectors that take part."""
    x = F.transform(vector, lambda c: c.cast("double"))
    bad = F.exists(x, lambda c: c.isNull() | F.isnan(c) | (F.abs(c) == float("inf")))
    whole = lambda c: F.when(F.abs(c) < float(1 << 52) / SCALE, F.floor(c * SCALE)).otherwise(F.raise_error(F.lit("a component is too large")).cast("long"))
    return vectors.where(F.col(key).isNotNull() & F.col(vector).isNotNull() & ~F.coalesce(bad, F.lit(True))).select(F.col(key).alias("vec_id"), F.transform(x, whole).alias("v")).where(F.size("v") > 0)


class Tree:
    """Nodes in arrays: boxes, children, and the range of rows below; rows are in leaf order."""

    def __init__(self, ids: np.ndarray, rows: np.ndarray):
        order = np.arange(len(ids))
        self.low, self.high, self.child, self.span = [], [], [], []
        stack = [(0, len(ids), -1, 0)]
        while stack:
            a, b, parent, side = stack.pop()
            node = len(self.span)
            if parent >= 0:
                self.child[parent][side] = node
            own = rows[order[a:b]]
            low, high = own.min(0), own.max(0)
            self.low.append(low)
            self.high.append(high)
            self.child.append([-1, -1])
            self.span.append((a, b))
            if b - a > LEAF_ROWS and (high > low).any():
                d = int((high - low).argmax())
                mid = (b - a) // 2
                order[a:b] = order[a:b][np.argpartition(own[:, d], mid)]
                stack += [(a, a + mid, node, 0), (a + mid, b, node, 1)]
        self.ids, self.whole = ids[order], rows[order]
        self.rows = self.whole.astype(np.float64)
        self.low, self.high = np.array(self.low, np.float64), np.array(self.high, np.float64)
        self.widest = np.maximum(np.abs(self.low[0]), np.abs(self.high[0]))
        self.visited = 0

    def _scores(self, a: int, b: int, query: np.ndarray, small: bool) -> np.ndarray:
        return self.rows[a:b] @ query if small else np.array([sum(x * y for x, y in zip(row, map(int, query))) for row in self.whole[a:b].tolist()], object)

    def search(self, query: np.ndarray, own: int, k: int, least: float) -> list[tuple[int, int]]:
        """Up to k (score, -id), those that may count where the k-th score elsewhere is least."""
        bound = _bounds(self.low, self.high, query)  # of every node: one product for the tree
        small = float(self.widest @ np.abs(query)) < EXACT
        heap, best = [(-bound[0], 0)], []
        while heap:
            top, node = heapq.heappop(heap)
            if -top < max(least, best[0][0] if len(best) == k else -np.inf):
                break
            if self.child[node][0] >= 0:
                for c in self.child[node]:
                    heapq.heappush(heap, (-bound[c], c))
                continue
            self.visited += 1
            a, b = self.span[node]
            scores = self._scores(a, b, query, small)
            floor = max(least, best[0][0] if len(best) == k else -np.inf)
            for i in np.flatnonzero(scores >= floor):
                if self.ids[a + i] != own:
                    item = (int(scores[i]), -int(self.ids[a + i]))
                    if len(best) < k:
                        heapq.heappush(best, item)
                    elif item > best[0]:
                        heapq.heapreplace(best, item)
        return best


def _bounds(low: np.ndarray, high: np.ndarray, query: np.ndarray) -> np.ndarray:
    """No vector of a box scores more with the query; rounding included."""
    up, down = np.maximum(query, 0), np.minimum(query, 0)
    whole = high @ up + low @ down
    reach = np.maximum(np.abs(low), np.abs(high)) @ np.abs(query)
    return whole + np.where(reach < EXACT, 0, reach * 1e-12)


def _pack(groups: DataFrame, group: str, payload: str) -> DataFrame:
    """One row per group and length of vectors: its ids, its vectors as bytes, the box around them, and bounds if there are."""

    def run(keys: tuple, part: pd.DataFrame) -> pd.DataFrame:
        part = part.sort_values("vec_id", kind="stable")
        rows = np.stack(part["v"].to_numpy()).astype("<i8")
        least = part["least"].to_numpy("<f8").tobytes() if "least" in part else b""
        made = {"g": [int(keys[0])], "width": [int(keys[1])], "ids": [part["vec_id"].to_numpy("<i8").tobytes()], payload: [rows.tobytes()], "least": [least]}
        return pd.DataFrame(made | {"low": [rows.min(0).tobytes()], "high": [rows.max(0).tobytes()]})

    return groups.groupBy(group, F.size("v")).applyInPandas(run, f"g long, width int, ids binary, {payload} binary, least binary, low binary, high binary")


def _search(pairs: DataFrame, k: int) -> DataFrame:
    """pairs: one row per shard and block of queries, sorted by shard within partitions; up to k rows per query and shard."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        built: tuple[tuple[int, int] | None, Tree | None] = (None, None)
        for batch in batches:
            for r in batch.itertuples(index=False):
                if built[0] != (r.g, r.width):
                    built = ((r.g, r.width), Tree(np.frombuffer(r.ids, "<i8"), np.frombuffer(r.rows, "<i8").reshape(-1, r.width)))
                queries, own = np.frombuffer(r.queries, "<i8").reshape(-1, r.width).astype(np.float64), np.frombuffer(r.q_ids, "<i8")
                least = np.frombuffer(r.q_least, "<f8") if r.q_least else np.full(len(own), -np.inf)
                found = [(int(q), -i, s) for q, v, t in zip(own, queries, least) for s, i in built[1].search(v, int(q), k, t)]
                yield pd.DataFrame(found, columns=["query_id", "vec_id", "score"]).astype("int64")

    return pairs.mapInPandas(run, "query_id long, vec_id long, score long")


def _sent(blocks: DataFrame, trees: DataFrame, shards: int) -> DataFrame:
    """blocks by shard (s_g, s_width, q_ids, queries, q_least): the queries of each block whose bound for a shard's root box reaches their k-th score."""
    box = trees.select("g", "width", "low", "high")
    schema = "s_g long, s_width int, q_ids binary, queries binary, q_least binary"
    if box.agg(F.coalesce(F.sum(F.length("low") + F.length("high")), F.lit(0))).first()[0] > BOX_BYTES:
        every = F.explode(F.sequence(F.lit(0), F.lit(shards - 1)).cast("array<bigint>"))
        return blocks.select(every.alias("s_g"), F.col("width").alias("s_width"), F.col("ids").alias("q_ids"), "queries", F.col("least").alias("q_least"))
    boxes: dict[int, tuple[list[int], list[bytes], list[bytes]]] = {}
    for r in box.toLocalIterator():  # at most BOX_BYTES
        for into, x in zip(boxes.setdefault(r["width"], ([], [], [])), (r["g"], bytes(r["low"]), bytes(r["high"]))):
            into.append(x)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for r in batch.itertuples(index=False):
                shard, low, high = boxes.get(r.width, ([], [], []))
                low, high = (np.frombuffer(b"".join(x), "<i8").reshape(-1, r.width).astype(np.float64) for x in (low, high))
                ids, rows, least = np.frombuffer(r.ids, "<i8"), np.frombuffer(r.queries, "<i8").reshape(-1, r.width), np.frombuffer(r.least, "<f8")
                reach = np.stack([_bounds(low, high, q.astype(np.float64)) for q in rows], 1) >= least
                for g, mask in zip(shard, reach):
                    if mask.any():
                        yield pd.DataFrame({"s_g": [g], "s_width": [r.width], "q_ids": [ids[mask].tobytes()], "queries": [rows[mask].tobytes()], "q_least": [least[mask].tobytes()]})

    return blocks.select("width", "ids", "queries", "least").mapInPandas(run, schema)


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 10, shard_rows: int = SHARD_ROWS, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """vectors and queries as whole_vectors() gives them: query_id, rank, vec_id, score of each query's k highest scores."""
    vectors, queries = written(vectors, "vectors"), written(queries, "queries")
    n, q = vectors.count(), queries.count()
    if queries.groupBy("vec_id").count().where("count > 1").limit(1).count():
        raise ValueError("queries share an id")
    shards, blocks = max(1, -(-n // shard_rows)), max(1, -(-q // block_rows))
    dealt = lambda m: F.pmod(F.xxhash64("vec_id", "v"), F.lit(m))
    trees = written(_pack(vectors.withColumn("g", dealt(shards)), "g", "rows"), "trees")
    met = lambda sent: trees.drop("least").repartition("g", "width").join(sent, (F.col("g") == F.col("s_g")) & (F.col("width") == F.col("s_width"))).sortWithinPartitions("g", "width")
    home = _pack(queries.withColumn("g", dealt(shards)), "g", "queries").select(F.col("g").alias("s_g"), F.col("width").alias("s_width"), F.col("ids").alias("q_ids"), "queries", F.col("least").alias("q_least"))
    first = written(_search(met(home), k), "first")
    kth = first.groupBy("query_id").agg(F.sort_array(F.collect_list("score"), asc=False).alias("s")).select(F.col("query_id").alias("vec_id"), F.when(F.size("s") >= k, F.element_at("s", k)).cast("double").alias("least"))
    bounded = queries.join(kth, "vec_id", "left").fillna(float("-inf"), ["least"])
    # home is searched again with its own k-th score: the shards of a block then need no exceptions
    block = written(_pack(bounded.withColumn("g", dealt(blocks)), "g", "queries"), "blocks")
    found = _search(met(_sent(block, trees, shards)), k)
    ranked = found.groupBy("query_id").agg(F.slice(F.array_sort(F.collect_list(F.struct((-F.col("score")).alias("s"), "vec_id"))), 1, k).alias("best"))
    return ranked.select("query_id", F.posexplode("best").alias("rank", "b")).select("query_id", (F.col("rank") + 1).cast("int").alias("rank"), F.col("b.vec_id").alias("vec_id"), (-F.col("b.s")).alias("score"))
