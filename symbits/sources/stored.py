"""Tables and indexes that are built once for an application and an input, written to the shared folder, and read by all queries on them."""

from __future__ import annotations

import hashlib
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from ..operators.index import Index, encode, read, write
from ..session import shared_folder

#: What is built already: paths and sizes alone, by application, input and name.
_tables: dict[tuple, str] = {}
_indexes: dict[tuple, tuple[str, int, int]] = {}

#: Encoding and trimming of each style of index: words as rows of a struct, plain vectors with or without trailing zeros, one encoding, or the smallest of each chunk.
STYLES = {"words": None, "plain": ("plain", True), "sentinel": ("plain", False), "compressed": ("auto", True), "rle": ("rle", True), "fills": ("fills", True), "positions": ("positions", True), "runs": ("runs", True)}
MAX_BUCKETS = 1024


def _key(spark: SparkSession, *names: str) -> tuple:
    return (spark.sparkContext.applicationId, *names)


def stored_table(spark: SparkSession, sf_dir: str, name: str, make: Callable[[], DataFrame], *order: str) -> DataFrame:
    """make() as a table in ranges of order, so that a filter on it reads few row groups."""
    key = _key(spark, sf_dir, name)
    if key not in _tables:
        path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
        df = make()
        (df.repartitionByRange(*order).sortWithinPartitions(*order) if order else df).write.parquet(path)
        _tables[key] = path
    return spark.read.parquet(_tables[key])


def is_stored(spark: SparkSession, sf_dir: str, name: str, style: str = "words") -> bool:
    return _key(spark, sf_dir, name, style) in _indexes


def stored_index(spark: SparkSession, sf_dir: str, name: str, make: Callable[[], Index], style: str = "words") -> Index:
    """make() in that style, as a table bucketed by chunk."""
    key = _key(spark, sf_dir, name, style)
    if key not in _indexes:
        if style == "words":
            index = make()
        else:
            kind, trim = STYLES[style]
            index = encode(stored_index(spark, sf_dir, name, make), kind, trim)
        table = "symbits_" + hashlib.md5("|".join([*key, uuid.uuid4().hex]).encode()).hexdigest()
        buckets = max(1, min(index.chunks, MAX_BUCKETS, int(spark.conf.get("spark.sql.shuffle.partitions"))))
        write(index, f"{shared_folder(spark)}/{table}", table, buckets)
        _indexes[key] = (table, index.rows, index.chunk_bits)
    return read(spark, *_indexes[key])
