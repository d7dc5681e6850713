"""Shards by extendible hashing: a directory over hash-prefix bits. Native: no Python on the executors.

The key's hash is a string of bits. A bucket is a prefix; if its rows weigh more than the byte limit it is
split on the next bit, and only it. A row's shard is thus the shortest prefix of its hash whose
rows fit. Sizes are summed once for fine prefixes (cells) and rolled up to all shorter ones; cells that still weigh too
much are refined further, by themselves. A directory lists, at a depth that its number of buckets sets, each bucket under
all its cells, so that a row finds its bucket by one lookup; the few deeper buckets have directories of their own.

Defined results: null and empty texts weigh nothing, and only the fixed cost of a row; rows of one key share all bits: where
they alone exceed the limit, or a single row does, the bucket stays whole at full depth with oversized
true and its rows are dealt to numbered pages of it that each fit, if their rows do; an empty table has no shards;
a null key hashes as one key; repeated rows are rows of their own; extra columns are kept, but for those named as the results are, which the results replace.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import written

SHARD_BYTES = 1 << 20
ROW_BYTES = 16
#: Hash bits that are used at most: the first 15 hexadecimal digits of md5.
HASH_BITS = 60
CELL_BITS = 12
#: A directory has up to 2 to this power cells for each bucket.
SPARE_BITS = 4
#: Pages that one task numbers.
TASK_PAGES = 64
RESULTS = ("shard", "depth", "page", "oversized", "row_bytes", "shard_bytes")


def hash_bits(key: Column) -> Column:
    """The key's hash as a non-negative number of HASH_BITS bits."""
    return F.conv(F.substring(F.md5(F.coalesce(key.cast("string"), F.lit("null"))), 1, HASH_BITS // 4), 16, 10).cast("long")


def row_bytes(text: Column) -> Column:
    return F.coalesce(F.octet_length(text), F.lit(0)).cast("long") + ROW_BYTES


def _prefix(bits: Column, depth: Column) -> Column:
    """The first depth bits."""
    return F.call_function("shiftright", bits, (F.lit(HASH_BITS) - depth).cast("int"))


def directory(sizes: DataFrame, limit: int = SHARD_BYTES, cell_bits: int = CELL_BITS) -> DataFrame:
    """From rows (h, bytes): the buckets (depth, prefix, bytes, rows, oversized)."""
    found: DataFrame | None = None
    level, rest = 0, sizes.groupBy("h").agg(F.sum("bytes").alias("bytes"), F.count("*").alias("rows"))
    rest = written(rest, "sizes")
    while True:
        to = min(level + cell_bits, HASH_BITS)
        cells = rest.groupBy(_prefix(F.col("h"), F.lit(to)).alias("cell")).agg(F.sum("bytes").alias("bytes"), F.sum("rows").alias("rows"))
        # every cell counts for each of its prefixes: at most cell_bits + 1 rows a cell
        depths = F.sequence(F.lit(level), F.lit(to))
        nodes = (
            cells.withColumn("depth", F.explode(depths))
            .groupBy("depth", F.call_function("shiftright", F.col("cell"), (F.lit(to) - F.col("depth")).cast("int")).alias("prefix"))
            .agg(F.sum("bytes").alias("bytes"), F.sum("rows").alias("rows"))
        )
        parent = nodes.select((F.col("depth") + 1).alias("depth"), F.explode(F.array(F.col("prefix") * 2, F.col("prefix") * 2 + 1)).alias("prefix"), F.col("bytes").alias("above"))
        fits = nodes.join(parent, ["depth", "prefix"], "left").where((F.col("bytes") <= limit) & (F.col("above").isNull() & (F.col("depth") == level) | (F.col("above") > limit)))
        if level:  # below a cell that was too heavy: its own node is not a bucket
            fits = fits.where(F.col("depth") > level)
        leaves = fits.select("depth", "prefix", "bytes", "rows", F.lit(False).alias("oversized"))
        heavy = nodes.where((F.col("depth") == to) & (F.col("bytes") > limit))
        if to == HASH_BITS:
            return _plus(found, leaves).unionByName(heavy.select("depth", "prefix", "bytes", "rows", F.lit(True).alias("oversized")))
        found = written(_plus(found, leaves), "buckets")
        heavy = written(heavy.select(F.col("prefix").alias("cell")), "heavy")
        if heavy.isEmpty():
            return found
        rest = rest.withColumn("cell", _prefix(F.col("h"), F.lit(to))).join(heavy, "cell", "left_semi").drop("cell")
        level = to


def _plus(found: DataFrame | None, more: DataFrame) -> DataFrame:
    return more if found is None else found.unionByName(more)


def _levels(buckets: DataFrame) -> list[tuple[int, int]]:
    """Ranges of depths (above, to) that have a directory each: the first as deep as the number of buckets allows, then by CELL_BITS; without empty ones."""
    depths = {r["depth"]: r["count"] for r in buckets.groupBy("depth").count().toLocalIterator()}  # at most HASH_BITS + 1 rows
    if not depths:
        return []
    first = min(max(depths), sum(depths.values()).bit_length() + SPARE_BITS)
    levels = [(-1, first)]
    while levels[-1][1] < max(depths):
        levels.append((levels[-1][1], min(levels[-1][1] + CELL_BITS, HASH_BITS)))
    return [(a, b) for a, b in levels if any(a < d <= b for d in depths)]


def shard_rows(docs: DataFrame, key: str = "doc_id", text: str = "text", limit: int = SHARD_BYTES, cell_bits: int = CELL_BITS) -> DataFrame:
    """docs (key, text read only for its size) with shard (bits of the prefix as text), depth, page, oversized, row_bytes, shard_bytes."""
    kept = [c for c in docs.columns if c not in RESULTS]
    weighed = docs.select(hash_bits(F.col(key)).alias("__h"), row_bytes(F.col(text)).alias("__bytes"), F.struct(*[F.col(f"`{c}`") for c in kept]).alias("__row"))
    buckets = written(directory(weighed.select(F.col("__h").alias("h"), F.col("__bytes").alias("bytes")), limit, cell_bits), "directory")
    joined: DataFrame | None = None
    for above, to in _levels(buckets):
        spare = (F.lit(to) - F.col("depth")).cast("int")
        cells = F.sequence(F.call_function("shiftleft", F.col("prefix"), spare), F.call_function("shiftleft", F.col("prefix") + 1, spare) - 1)
        listed = buckets.where((F.col("depth") > above) & (F.col("depth") <= to)).select(F.explode(cells).alias("__cell"), "depth", "prefix", F.col("bytes").alias("shard_bytes"), "oversized")
        joined = _plus(joined, weighed.withColumn("__cell", _prefix(F.col("__h"), F.lit(to))).join(listed, "__cell"))
    if joined is None:
        joined = weighed.withColumn("__cell", F.col("__h")).join(buckets.select(F.col("prefix").alias("__cell"), "depth", "prefix", F.col("bytes").alias("shard_bytes"), "oversized"), "__cell")
    shard = F.when(F.col("depth") == 0, "").otherwise(F.lpad(F.bin("prefix"), F.col("depth"), F.lit("0")))
    made = {"shard": shard, "row_bytes": F.col("__bytes")}
    result = lambda df: df.select(*[F.col("__row").getField(c).alias(c) for c in kept], *[made.get(c, F.col(c)).alias(c) for c in RESULTS])
    whole = joined.where(~F.col("oversized")).withColumn("page", F.lit("0"))
    if buckets.where("oversized").isEmpty():
        return result(whole)
    # an oversized bucket has one key: its rows, numbered once in a written table, are dealt to parts, whose running sums make the pages
    numbered = written(joined.where("oversized").withColumn("__id", F.monotonically_increasing_id()), "oversized")
    salts = F.greatest(F.ceil(F.col("shard_bytes") / F.lit(limit * TASK_PAGES)), F.lit(1))
    order = Window.partitionBy("prefix", "__salt").orderBy("__id").rowsBetween(Window.unboundedPreceding, -1)
    # rows of up to half the limit share pages that begin at half the limit each, so that the last one still fits; larger rows have their own
    small = F.col("__bytes") * 2 <= limit
    before = F.coalesce(F.sum(F.when(small, F.col("__bytes")).otherwise(0)).over(order), F.lit(0))
    page = F.when(small, F.floor(before * 2 / F.lit(limit)).cast("string")).otherwise(F.concat(F.lit("own"), F.col("__id").cast("string")))
    over = numbered.withColumn("__salt", F.pmod(F.xxhash64("__id"), salts)).withColumn("page", F.concat_ws(".", F.col("__salt").cast("string"), page))
    return result(whole.unionByName(over.drop("__id", "__salt")))
