"""The bitmap index and the algebra of bitmaps.

An index has a row per (attr, value, chunk): a chunk is chunk_bits consecutive rids. words lists the
nonzero 64-bit words as (w, b), sorted; an encoded index has encoding and payload (bytes, see codec) in their place. A chunk whose rids are all in the set is kind FULL and has neither; a
chunk without rids has no row. card, runs, dirty and whether the first and last rid are in it are there to decide without reading words.

A Bitmap is a DataFrame of nonzero words (chunk, w, b), with the number of rids. It is closed under all operators.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import codec

CHUNK_BITS = 1 << 15
#: Index rows of a bitmap are linked over chunk borders by groups of so many chunks.
LINKED = 1024
DIRTY, FULL = 1, 2


@dataclass(frozen=True)
class Index:
    df: DataFrame
    rows: int
    chunk_bits: int = CHUNK_BITS

    @property
    def chunks(self) -> int:
        return -(-self.rows // self.chunk_bits)

    @property
    def encoded(self) -> bool:
        return "payload" in self.df.columns

    @property
    def body(self) -> tuple[str, ...]:
        """The columns that hold the ones."""
        return ("kind", "card", "encoding", "payload") if self.encoded else ("kind", "card", "words")

    def bitmap(self, attr: str, value: str) -> Bitmap:
        own = self.df.where((F.col("attr") == attr) & (F.col("value") == value))
        return Bitmap(words_of(own.select("chunk", *self.body), self), self.rows, self.chunk_bits)


def members(df: DataFrame, rid: str, attrs: Sequence[str]) -> DataFrame:
    """attr, value (as text), rid for each non-null attribute: the unpivoted table."""
    pairs = F.array(*[F.struct(F.lit(a).alias("attr"), F.col(a).cast("string").alias("value")) for a in attrs])
    return df.select(F.col(rid).cast("long").alias("rid"), F.inline(pairs)).where(F.col("value").isNotNull()).select("attr", "value", "rid")


def words_of_members(found: DataFrame, chunk_bits: int) -> DataFrame:
    """attr, value, chunk, w, b of members (attr, value, rid)."""
    if chunk_bits % 64:
        raise ValueError("chunk_bits is a multiple of 64")
    at = F.col("rid") % chunk_bits
    placed = found.select("attr", "value", F.floor(F.col("rid") / chunk_bits).cast("long").alias("chunk"), F.floor(at / 64).cast("int").alias("w"), F.call_function("shiftleft", F.lit(1).cast("long"), (F.col("rid") % 64).cast("int")).alias("b"))
    return placed.groupBy("attr", "value", "chunk", "w").agg(F.bit_or("b").alias("b"))


def build(found: DataFrame, rows: int, chunk_bits: int = CHUNK_BITS) -> Index:
    """Index of members (attr, value, rid), rids in 0 to rows - 1. Two aggregations on one partitioning."""
    return of_words(words_of_members(found, chunk_bits), rows, chunk_bits)


def of_words(words: DataFrame, rows: int, chunk_bits: int = CHUNK_BITS) -> Index:
    """Index of words (attr, value, chunk, w, b), each once."""
    size = F.least(F.lit(chunk_bits).cast("long"), F.lit(rows) - F.col("chunk") * chunk_bits)
    chunks = words.groupBy("attr", "value", "chunk").agg(F.sort_array(F.collect_list(F.struct("w", "b"))).alias("words"), F.sum(F.bit_count("b")).alias("card"))
    runs = F.expr("cast(aggregate(words, named_struct('n', 0L, 'w', -2, 'b', 0L), (a, x) -> named_struct('n', a.n + bit_count(x.b & ~(shiftleft(x.b, 1) | if(a.w = x.w - 1, shiftrightunsigned(a.b, 63), 0L))), 'w', x.w, 'b', x.b), a -> a.n) as int)")
    full = F.col("card") == size
    ends = F.element_at("words", 1), F.element_at("words", -1)
    first = (ends[0]["w"] == 0) & (F.call_function("getbit", ends[0]["b"], F.lit(0)) == 1)
    last = (ends[1]["w"] == F.floor((size - 1) / 64)) & (F.call_function("getbit", ends[1]["b"], ((size - 1) % 64).cast("int")) == 1)
    df = chunks.select(
        "attr", "value", "chunk", F.when(full, FULL).otherwise(DIRTY).cast("tinyint").alias("kind"), F.col("card").cast("int").alias("card"), runs.alias("runs"),
        F.size(F.filter("words", lambda x: x["b"] != -1)).alias("dirty"), first.alias("first"), last.alias("last"), F.when(~full, F.col("words")).alias("words"),
    )
    return Index(df, rows, chunk_bits)


def chunk_words(words: pa.ListArray, n_words: int) -> list[np.ndarray | None]:
    """Vectors of the words of each row (None for null), from Arrow's buffers."""
    flat, offsets = words.flatten(), words.value_lengths().fill_null(0).to_numpy().cumsum()
    at, value = flat.field(0).to_numpy(), flat.field(1).to_numpy().view(np.uint64)
    out: list[np.ndarray | None] = []
    for valid, a, b in zip(words.is_valid().to_pylist(), [0, *offsets[:-1]], offsets):
        own = np.zeros(n_words, np.uint64) if valid else None
        if valid:
            own[at[a:b]] = value[a:b]
        out.append(own)
    return out


def encode(index: Index, kind: str = "auto", trim: bool = True) -> Index:
    """The index with each chunk in one encoding of codec, or in the smallest (auto). trim leaves trailing zero words out."""
    if index.encoded:
        raise ValueError("the index is encoded already")
    n_words, keep = index.chunk_bits // 64, [c for c in index.df.columns if c != "words"]
    schema = ", ".join(f"`{c}` {index.df.schema[c].dataType.simpleString()}" for c in keep) + ", encoding string, payload binary"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            made = [x if x is None else codec.encode(x, kind, trim) for x in chunk_words(batch.column(len(keep)), n_words)]
            columns = [pa.array([m and m[0] for m in made], pa.string()), pa.array([None if m is None else m[1] for m in made], pa.binary())]
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(keep)], *columns], [*keep, "encoding", "payload"])

    return replace(index, df=index.df.select(*keep, "words").mapInArrow(run, schema))


def write(index: Index, path: str, table: str, buckets: int = 64) -> Index:
    """As a table at path, bucketed by chunk and sorted by bitmap in each bucket: a query reads the row groups of its bitmaps, and groupings by chunk need no exchange."""
    sorted_rows = index.df.repartition(buckets, "chunk")
    sorted_rows.write.bucketBy(buckets, "chunk").sortBy("attr", "value", "chunk").option("path", path).saveAsTable(table, mode="overwrite")
    return read(index.df.sparkSession, table, index.rows, index.chunk_bits)


def read(spark: SparkSession, table: str, rows: int, chunk_bits: int = CHUNK_BITS) -> Index:
    return Index(spark.table(table), rows, chunk_bits)


def stats(index: Index) -> DataFrame:
    """attr, value, card, chunks, runs, dirty, density: from the metadata alone. A run over chunk borders counts once."""
    own = index.df.groupBy("attr", "value").agg(F.sum("card").cast("long").alias("card"), F.count("*").alias("chunks"), F.sum("runs").cast("long").alias("runs"), F.sum("dirty").cast("long").alias("dirty"))
    # a border that both its chunks reach splits a run in two
    borders = F.filter(F.array(F.when(F.col("first"), F.col("chunk")), F.when(F.col("last"), F.col("chunk") + 1)), lambda x: x.isNotNull())
    split = index.df.where("first or last").select("attr", "value", F.explode(borders).alias("border")).groupBy("attr", "value", "border").count().where("count = 2")
    halves = split.groupBy("attr", "value").agg(F.count("*").alias("halves"))
    joined = own.join(halves, ["attr", "value"], "left").withColumn("runs", F.col("runs") - F.coalesce("halves", F.lit(0)))
    return joined.drop("halves").withColumn("density", F.col("card") / F.lit(index.rows))


def universe(spark: SparkSession, rows: int, chunk_bits: int) -> DataFrame:
    """chunk, w, m for all rids: m masks the last word."""
    return spark.range(-(-rows // 64)).select(
        F.floor(F.col("id") * 64 / chunk_bits).cast("long").alias("chunk"),
        (F.col("id") % (chunk_bits // 64)).cast("int").alias("w"),
        F.when(F.col("id") * 64 + 64 <= rows, F.lit(-1).cast("long")).otherwise(F.lit((1 << rows % 64) - 1).cast("long") if rows % 64 != 63 else F.lit((1 << 63) - 1).cast("long")).alias("m"),
    )


def ones(word: Column) -> Column:
    """Positions of a word's ones, as an array."""
    return F.filter(F.sequence(F.lit(0), F.lit(63)), lambda p: F.call_function("getbit", word, p) == 1)


def rids_in(word: Column, chunk_bits: int) -> Column:
    """Rids of the ones of a word at chunk and w."""
    return F.transform(ones(word), lambda p: F.col("chunk") * chunk_bits + F.col("w") * 64 + p)


def full_words(size: Column) -> Column:
    """words (w, b) of a chunk of that many ones."""
    last = F.when(size % 64 == 0, F.lit(-1).cast("long")).otherwise(F.call_function("shiftleft", F.lit(1).cast("long"), (size % 64).cast("int")) - 1)
    n = F.ceil(size / 64).cast("int")
    return F.transform(F.sequence(F.lit(0), n - 1), lambda w: F.struct(w.alias("w"), F.when(w == n - 1, last).otherwise(F.lit(-1).cast("long")).alias("b")))


def words_of(rows: DataFrame, index: Index, *more: str) -> DataFrame:
    """Words (more, chunk, w, b) of index rows, full chunks written out."""
    if "payload" in rows.columns:
        rows = decoded(rows, index, *more)
    size = F.least(F.lit(index.chunk_bits).cast("long"), F.lit(index.rows) - F.col("chunk") * index.chunk_bits)
    return rows.select(*more, "chunk", F.inline(F.when(F.col("kind") == FULL, full_words(size)).otherwise(F.col("words"))))


def decoded(rows: DataFrame, index: Index, *more: str) -> DataFrame:
    """more, chunk, kind, words of encoded rows."""
    n_words, keep = index.chunk_bits // 64, [*more, "chunk", "kind"]
    words = "array<struct<w:int,b:bigint>>"
    schema = "".join(f"`{c}` {rows.schema[c].dataType.simpleString()}, " for c in keep) + f"words {words}"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            kinds, payloads = (batch.column(batch.schema.names.index(c)).to_pylist() for c in ("encoding", "payload"))
            made = [None if k is None else codec.decode(k, p, n_words) for k, p in zip(kinds, payloads)]
            at = [np.zeros(0, np.int64) if x is None else x.nonzero()[0] for x in made]
            flat = pa.StructArray.from_arrays([pa.array(np.concatenate([*at, np.zeros(0, np.int64)]).astype(np.int32)), pa.array(np.concatenate([*(x[i] for x, i in zip(made, at) if x is not None), np.zeros(0, np.uint64)]).view(np.int64))], ["w", "b"])
            offsets = np.concatenate([[0], np.cumsum([len(i) for i in at])]).astype(np.int32)
            lists = pa.ListArray.from_arrays(pa.array(offsets), flat, mask=pa.array([x is None for x in made]))
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(keep)], lists], [*keep, "words"])

    return rows.select(*keep, "encoding", "payload").mapInArrow(run, schema)


@dataclass(frozen=True)
class Bitmap:
    df: DataFrame
    rows: int
    chunk_bits: int = CHUNK_BITS

    def _like(self, df: DataFrame) -> Bitmap:
        return Bitmap(df.where(F.col("b") != 0).select("chunk", "w", "b"), self.rows, self.chunk_bits)

    def _other(self, other: Bitmap) -> DataFrame:
        if (self.rows, self.chunk_bits) != (other.rows, other.chunk_bits):
            raise ValueError("bitmaps over other rids")
        return other.df.select("chunk", "w", F.col("b").alias("c"))

    def __and__(self, other: Bitmap) -> Bitmap:
        return self._like(self.df.join(self._other(other), ["chunk", "w"]).withColumn("b", F.col("b").bitwiseAND(F.col("c"))))

    def __or__(self, other: Bitmap) -> Bitmap:
        return self._like(self.df.join(self._other(other), ["chunk", "w"], "full_outer").withColumn("b", F.coalesce("b", F.lit(0)).bitwiseOR(F.coalesce("c", F.lit(0)))))

    def __xor__(self, other: Bitmap) -> Bitmap:
        return self._like(self.df.join(self._other(other), ["chunk", "w"], "full_outer").withColumn("b", F.coalesce("b", F.lit(0)).bitwiseXOR(F.coalesce("c", F.lit(0)))))

    def andnot(self, other: Bitmap) -> Bitmap:
        return self._like(self.df.join(self._other(other), ["chunk", "w"], "left").withColumn("b", F.col("b").bitwiseAND(F.bitwise_not(F.coalesce("c", F.lit(0).cast("long"))))))

    def __invert__(self) -> Bitmap:
        every = universe(self.df.sparkSession, self.rows, self.chunk_bits)
        return self._like(every.join(self.df, ["chunk", "w"], "left").withColumn("b", F.col("m").bitwiseAND(F.bitwise_not(F.coalesce("b", F.lit(0).cast("long"))))))

    def rids(self) -> DataFrame:
        return self.df.select(F.explode(rids_in(F.col("b"), self.chunk_bits)).alias("rid"))

    def count(self) -> DataFrame:
        return self.df.agg(F.coalesce(F.sum(F.bit_count("b")), F.lit(0)).cast("long").alias("n"))

    def density(self) -> DataFrame:
        return self.count().select((F.col("n") / F.lit(self.rows)).alias("density"))

    def contains(self, rid: int) -> bool:
        at = rid % self.chunk_bits
        return not self.df.where((F.col("chunk") == rid // self.chunk_bits) & (F.col("w") == at // 64) & (F.call_function("getbit", F.col("b"), F.lit(at % 64)) == 1)).isEmpty()

    def intervals(self) -> DataFrame:
        """start, stop (both inside) of the maximal runs of ones."""
        return coalesced(run_edges(self.df, self.chunk_bits))


def run_edges(words: DataFrame, chunk_bits: int, *keys: str) -> DataFrame:
    """keys, chunk, start, stop of the runs within each word; a run over a border is in pieces."""
    up = F.col("b").bitwiseAND(F.bitwise_not(F.call_function("shiftleft", F.col("b"), F.lit(1))))
    down = F.col("b").bitwiseAND(F.bitwise_not(F.call_function("shiftrightunsigned", F.col("b"), F.lit(1))))
    base = F.col("chunk") * chunk_bits + F.col("w") * 64
    return words.select(*keys, "chunk", base.alias("base"), F.inline(F.arrays_zip(ones(up).alias("u"), ones(down).alias("d")))).select(*keys, "chunk", (F.col("base") + F.col("u")).alias("start"), (F.col("base") + F.col("d")).alias("stop"))


def coalesced(edges: DataFrame, *keys: str) -> DataFrame:
    """keys, start, stop: touching runs joined, within chunks first, then over chunk borders in groups of LINKED chunks, then over those.

    Only the first and last run of a group can go on, so that each step hands on two rows a group at most: the last one, alone in one task
    for each of keys, gets two rows for LINKED chunks.
    """
    from pyspark.sql import Window

    def islands(df: DataFrame, *by: str) -> DataFrame:
        w = Window.partitionBy(*by).orderBy("start")
        new = (F.col("start") != F.lag("stop").over(w) + 1) | F.lag("stop").over(w).isNull()
        return df.withColumn("__new", new.cast("long")).withColumn("__i", F.sum("__new").over(w)).groupBy(*by, "__i").agg(F.min("start").alias("start"), F.max("stop").alias("stop")).drop("__i")

    out, rest = None, edges.withColumnRenamed("chunk", "__g")
    for step in range(3):
        inside = islands(rest, *keys, "__g")
        if step == 2:
            done, go_on = inside, None
        else:
            w = Window.partitionBy(*keys, "__g")
            marked = inside.withColumn("__edge", (F.col("start") == F.min("start").over(w)) | (F.col("stop") == F.max("stop").over(w)))
            done, go_on = marked.where(~F.col("__edge")), marked.where("__edge").drop("__edge")
        done = done.select(*keys, "start", "stop")
        out = done if out is None else out.unionByName(done)
        if go_on is not None:
            rest = go_on.withColumn("__g", F.floor(F.col("__g") / LINKED) if step == 0 else F.lit(0).cast("long"))
    return out


def wide(bitmaps: Sequence[Bitmap], op: str) -> Bitmap:
    """OR, AND or XOR of many bitmaps by one aggregation; for AND, words that some bitmap lacks are zero."""
    rows = bitmaps[0].df
    for b in bitmaps[1:]:
        rows = rows.unionByName(b.df)
    made = {"or": F.bit_or, "and": F.bit_and, "xor": F.bit_xor}[op]("b")
    return bitmaps[0]._like(rows.groupBy("chunk", "w").agg(F.when(F.count("*") == len(bitmaps), made).otherwise(0).alias("b") if op == "and" else made.alias("b")))


def from_rids(rids: DataFrame, rows: int, chunk_bits: int = CHUNK_BITS, rid: str = "rid") -> Bitmap:
    at = F.col(rid) % chunk_bits
    words = rids.groupBy(F.floor(F.col(rid) / chunk_bits).cast("long").alias("chunk"), F.floor(at / 64).cast("int").alias("w")).agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), (F.col(rid) % 64).cast("int"))).alias("b"))
    return Bitmap(words, rows, chunk_bits)


def dense_rids(df: DataFrame, *order: str) -> DataFrame:
    """df with rid 0, 1, ... in the order of a unique tuple: sorted ranges, their sizes summed, a rank in each.

    The driver sees one count per partition; no partition holds more than its range.
    """
    from itertools import accumulate

    from pyspark.sql import Window

    from ..session import written

    # written once: partition numbers are then part of the rows, and don't depend on how ranges are drawn again
    ranged = written(df.repartitionByRange(*order).withColumn("__part", F.spark_partition_id()), "ranges")
    counts = {r["__part"]: r["count"] for r in ranged.groupBy("__part").count().toLocalIterator()}
    parts = sorted(counts)
    offsets = dict(zip(parts, accumulate([0, *[counts[p] for p in parts]])))
    base = F.create_map(*[F.lit(x) for p in parts for x in (p, offsets[p])])[F.col("__part")] if parts else F.lit(0)
    w = Window.partitionBy("__part").orderBy(*order)
    return ranged.withColumn("rid", base + F.row_number().over(w) - 1).drop("__part")
