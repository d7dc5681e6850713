"""Near duplicates by consistent weighted sampling of TF-IDF shingles.

A shingle is five consecutive words; its weight is its count in the text times the mean inverse document
frequency of its words. Frequencies are counted over all documents, words hashed to 2**18 buckets, so that
the table has a fixed size. Improved consistent weighted sampling draws SAMPLES shingles of each text such that two texts
agree on a sample with their weighted Jaccard similarity as probability. The deciding gamma variable comes from the hash of
shingle and sample, the others from a table at that hash. BANDS groups of samples are hashed; texts that share a group meet in a bucket.

Equal texts are one node. Buckets with the same nodes count once. The nodes of a bucket meet in one task with their texts:
from a node, all that are similar to it by exact weighted Jaccard similarity are found at once and taken out, then those similar to these, and so on,
so that a task finds the components among its nodes and gives one row for each node, whatever the size of the bucket. A bucket of more than PART_ROWS nodes
or PART_BYTES of text is dealt to parts; after the components of all parts and buckets are joined, its parts meet in
pairs, where nodes of one component need no comparison any more. So no pair that shares a bucket is left out. Classes are the connected
components of similar nodes.

Defined results: a class is named by its least doc_id and, where doc_ids may repeat, for certain by class_key (the md5 of the text
that has it); a class whose rows all lack a doc_id has a negative hash of that text as its name. A null text is a class of its own, named by its own doc_id, without a class_key;
texts of fewer than five words have one shingle, of all their words; texts without words are similar only to equal texts; rows that share a
doc_id are nodes by their text, and each row gets its own text's class; equal rows are in one class; extra columns are ignored by classes() and kept by
keep_one(), whatever their names; an empty table has no classes; a table of any partitioning gives the same classes.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import written

WORDS = 5
SIMILARITY = 0.8
BANDS, ROWS = 16, 4
SAMPLES = BANDS * ROWS
PART_ROWS, PART_BYTES = 4096, 1 << 23
BUCKET_BITS = 18
IDF_STEP = 8
#: Bytes of text that are hashed at once.
BATCH_BYTES = 1 << 17
_P, _Q, _MIX = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(0xBF58476D1CE4E5B9)


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * _MIX
    x = (x ^ (x >> np.uint64(29))) * _P
    return x ^ (x >> np.uint64(32))


@lru_cache(2)
def _powers(bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd number and of its inverse modulo 2**64."""
    inverse = np.uint64(pow(int(_P), -1, 1 << 64))
    out = []
    for base in (_P, inverse):
        p = np.full(1 << bits, base, np.uint64)
        p[0] = 1
        out.append(np.multiply.accumulate(p))
    return out[0], out[1]


@lru_cache(1)
def _draws() -> tuple[np.ndarray, ...]:
    """Table of r ~ Gamma(2, 1), its inverse and beta ~ U(0, 1); and multipliers of the samples."""
    g = np.random.Generator(np.random.PCG64(4))
    n = 1 << 16
    u = g.random((3, n)) + 1e-12
    r = -np.log(u[0] * u[1])
    odd = g.integers(0, 1 << 63, SAMPLES, np.int64).astype(np.uint64) * np.uint64(2) + np.uint64(1)
    return r.astype(np.float32), (1 / r).astype(np.float32), u[2].astype(np.float32), odd


class Words:
    """Words of several texts, hashed: hash, and first word and number of words of each text."""

    def __init__(self, texts: list[bytes]):
        data = np.frombuffer(b" ".join(texts) + b" ", np.uint8)
        ends = np.cumsum([len(t) + 1 for t in texts])
        space = (data == 32) | ((data >= 9) & (data <= 13))
        edge = np.flatnonzero(space[1:] != space[:-1]) + 1
        if len(data) and not space[0]:
            edge = np.concatenate([[0], edge])
        starts, stops = edge[::2], edge[1::2]
        up, down = _powers(max(20, int(len(data)).bit_length()))
        sums = np.zeros(len(data) + 1, np.uint64)
        np.cumsum((data.astype(np.uint64) + np.uint64(1)) * up[: len(data)], out=sums[1:])
        self.hash = _mixed((sums[stops] - sums[starts]) * down[starts])
        self.last = np.searchsorted(starts, ends)
        self.first = np.concatenate([[0], self.last[:-1]])

    def buckets(self) -> np.ndarray:
        return (self.hash >> np.uint64(64 - BUCKET_BITS)).astype(np.int64)


def shingles(texts: list[bytes], idf: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashes of the distinct shingles of all texts, sorted within each, their weights, and where each text's begin (one more at the end)."""
    w = Words(texts)
    h, n = w.hash, len(w.hash)
    worth = idf[w.buckets()]
    counts = np.minimum(w.last - w.first, WORDS)
    size = np.repeat(counts, w.last - w.first)  # words in a shingle of the word's text
    own = np.repeat(np.arange(len(texts)), w.last - w.first)
    lead = np.flatnonzero(np.arange(n) + size <= w.last[own]) if n else np.zeros(0, np.int64)
    total, value = np.zeros(len(lead), np.uint64), np.zeros(len(lead))
    with np.errstate(over="ignore"):
        for j in range(WORDS):
            inside = size[lead] > j
            at = np.minimum(lead + j, n - 1)
            total = np.where(inside, total * _Q + h[at], total)
            value = value + np.where(inside, worth[at], 0)
    total, value, own = _mixed(total), value / np.maximum(size[lead], 1), own[lead]
    order = np.lexsort((total, own))
    total, value, own = total[order], value[order], own[order]
    new = np.concatenate([[True], (total[1:] != total[:-1]) | (own[1:] != own[:-1])]) if len(total) else np.zeros(0, bool)
    at = np.flatnonzero(new)
    tf = np.diff(np.concatenate([at, [len(total)]]))
    return total[at], value[at] * tf, np.searchsorted(own[at], np.arange(len(texts) + 1))


def samples(hashes: np.ndarray, weights: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """For each text, none of them without shingles, the least value of each sample: texts that drew the same shingle at the same step have the same."""
    r, inverse, beta, odd = _draws()
    log_w = np.log(weights).astype(np.float32)
    out = np.empty((len(starts), SAMPLES), np.float32)
    one, scale, below = np.float32(1), np.float32(2.0**-32), np.float32(1 - 2.0**-24)
    for k in range(SAMPLES):
        x = hashes * odd[k]
        i = (x >> np.uint64(48)).astype(np.intp)
        x ^= x >> np.uint64(32)
        x *= _MIX
        halves = x.view(np.uint32)
        u = halves[::2].astype(np.float32)
        u *= scale
        u *= halves[1::2]
        u *= scale
        np.clip(u, np.float32(1e-30), below, out=u)
        log_c = np.log(u, out=u)
        np.negative(log_c, out=log_c)  # c ~ Gamma(2, 1)
        np.log(log_c, out=log_c)
        b = beta[i]
        step = inverse[i]
        step *= log_w
        step += b
        np.floor(step, out=step)
        step -= b
        step += one
        step *= r[i]
        log_c -= step
        out[:, k] = np.minimum.reduceat(log_c, starts)
    return out


def sketch(texts: list[bytes], idf: np.ndarray) -> list[list[int] | None]:
    """Hashes of the bands of each text; None for texts without words."""
    hashes, weights, starts = shingles(texts, idf)
    full = np.flatnonzero(starts[1:] > starts[:-1])
    out: list[list[int] | None] = [None] * len(texts)
    if not len(full):
        return out
    bits = samples(hashes, weights, starts[:-1][full]).view(np.uint32).astype(np.uint64).reshape(len(full), BANDS, ROWS)
    with np.errstate(over="ignore"):
        key = np.arange(1, BANDS + 1, dtype=np.uint64) * _Q + np.zeros((len(full), 1), np.uint64)
        for j in range(ROWS):
            key = _mixed(key * _P + bits[:, :, j])
    for k, row in zip(full, key.view(np.int64).tolist()):
        out[k] = row
    return out


def _grouped(column: pa.Array) -> Iterator[tuple[int, list[bytes]]]:
    """Texts by about BATCH_BYTES, each with the number of the first."""
    first, group, size = 0, [], 0
    for k, t in enumerate(t for at in range(0, len(column), 64) for t in column.slice(at, 64).to_pylist()):
        group.append((t or "").encode("utf-8", "replace"))
        size += len(group[-1])
        if size >= BATCH_BYTES:
            yield first, group
            first, group, size = k + 1, [], 0
    if group:
        yield first, group


def word_idf(docs: DataFrame) -> np.ndarray:
    """Inverse document frequency of each word bucket over all rows with a text, in steps of 1 / IDF_STEP."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, rows = np.zeros(1 << BUCKET_BITS, np.int64), 0
        for batch in batches:
            for _, group in _grouped(batch.column(0)):
                w = Words(group)
                own = np.repeat(np.arange(len(group)), w.last - w.first)
                total += np.bincount(np.unique((own << BUCKET_BITS) + w.buckets()) & ((1 << BUCKET_BITS) - 1), minlength=1 << BUCKET_BITS)
                rows += len(group)
        at = total.nonzero()[0]
        yield pa.RecordBatch.from_arrays([pa.array(np.append(at, -1), pa.int32()), pa.array(np.append(total[at], rows), pa.int64())], ["bucket", "n"])

    found = docs.where(F.col("text").isNotNull()).select("text").mapInArrow(count, "bucket int, n long").groupBy("bucket").agg(F.sum("n").alias("n"))
    frequency, rows = np.zeros(1 << BUCKET_BITS), 0
    for r in found.toLocalIterator():  # at most 2**18 + 1 rows
        if r["bucket"] < 0:
            rows = r["n"]
        else:
            frequency[r["bucket"]] = r["n"]
    return np.round((np.log((1 + rows) / (1 + frequency)) + 1) * IDF_STEP) / IDF_STEP


def sketches(docs: DataFrame, idf: np.ndarray) -> DataFrame:
    """doc_id, node (md5 of the text in hexadecimal; null for null text), bands (null without words) and size of the text in bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, group in _grouped(batch.column(1)):
                valid = batch.column(1).slice(first, len(group)).is_valid().to_pylist()
                node = [hashlib.md5(b).hexdigest() if own else None for own, b in zip(valid, group)]
                columns = [batch.column(0).slice(first, len(group)), pa.array(node, pa.string()), pa.array(sketch(group, idf), pa.list_(pa.int64())), pa.array(map(len, group), pa.int64())]
                yield pa.RecordBatch.from_arrays(columns, ["doc_id", "node", "bands", "size"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, node string, bands array<long>, size long")


# -- components within buckets


def united(hashes: np.ndarray, weights: np.ndarray, starts: np.ndarray, label: np.ndarray | None = None, least: float = SIMILARITY) -> np.ndarray:
    """For each text the first text of its component: texts linked by a weighted Jaccard similarity of at least least, or by equal labels.

    A search from each text compares it with all texts not found yet in one pass over their shingles.
    """
    n = len(starts) - 1
    total = np.add.reduceat(weights, starts[:-1])
    _, ids = np.unique(hashes, return_inverse=True)
    dense = np.zeros(len(hashes) and int(ids.max()) + 1)
    first = np.full(n, -1)
    rest, rest_ids, rest_weights, rest_starts = np.arange(n), ids, weights, starts[:-1]

    def take(found: np.ndarray) -> None:
        """Take found (a mask over rest), with all texts of their labels, out of rest."""
        nonlocal rest, rest_ids, rest_weights, rest_starts
        if label is not None:
            found = np.isin(label[rest], label[rest[found]])
        first[rest[found]] = seed
        todo.extend(rest[found].tolist())
        sizes = np.diff(np.append(rest_starts, len(rest_ids)))
        stay = np.repeat(~found, sizes)
        rest, rest_ids, rest_weights = rest[~found], rest_ids[stay], rest_weights[stay]
        rest_starts = np.concatenate([[0], np.cumsum(sizes[~found])])[:-1]

    for seed in range(n):
        if first[seed] >= 0:
            continue
        todo: list[int] = []
        take(rest == seed)
        while todo and len(rest):
            x = todo.pop()
            own = slice(starts[x], starts[x + 1])
            dense[ids[own]] = weights[own]
            shared = np.add.reduceat(np.minimum(rest_weights, dense[rest_ids]), rest_starts)
            dense[ids[own]] = 0
            found = shared >= (least - 1e-9) * (total[x] + total[rest] - shared)
            if found.any():
                take(found)
    return first


def _groups(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """Rows of the same bucket and part, which follow each other, whatever batches they come in."""
    carry: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        same = lambda a, i, b, j: all(a.column(k)[i].as_py() == b.column(k)[j].as_py() for k in ("bucket", "part"))
        if carry and same(carry[0], 0, batch, batch.num_rows - 1):  # one group goes on
            carry.append(batch)
            continue
        table = pa.Table.from_batches([*carry, batch]).combine_chunks()
        bucket, part = table.column("bucket").to_numpy(), table.column("part").to_numpy()
        edges = np.flatnonzero((bucket[1:] != bucket[:-1]) | (part[1:] != part[:-1])) + 1
        for start, stop in zip(np.concatenate([[0], edges]), edges):
            yield table.slice(start, stop - start)
        carry = table.slice(edges[-1] if len(edges) else 0).to_batches()
    if carry:
        yield pa.Table.from_batches(carry).combine_chunks()


def _packs(batches: Iterator[pa.RecordBatch]) -> Iterator[list[pa.Table]]:
    """Groups by about BATCH_BYTES of text, so that many small ones are hashed at once."""
    pack, size = [], 0
    for group in _groups(batches):
        pack.append(group)
        size += pc.sum(pc.binary_length(group.column("text"))).as_py() or 0
        if size >= BATCH_BYTES:
            yield pack
            pack, size = [], 0
    if pack:
        yield pack


def met(rows: DataFrame, idf: np.ndarray, least: float) -> DataFrame:
    """rows: bucket, part, rep, node, label, text. Edges (x, y) of structs (rep, node) that join each node to the first of its component in its bucket and part.

    Nodes of one label are known to be in one component; edges are given where that says more than the labels.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["x_rep", "x_node", "y_rep", "y_node"]
        for pack in _packs(batches):
            texts = [t.encode("utf-8", "replace") for group in pack for t in group.column("text").to_pylist()]
            h, w, s = shingles(texts, idf)
            at, out = 0, []
            for group in pack:
                n = group.num_rows
                label = np.unique(np.array(group.column("label").to_pylist()), return_inverse=True)[1]
                whole = len(set(label.tolist())) == n
                a, b = s[at], s[at + n]
                first = united(h[a:b], w[a:b], s[at : at + n + 1] - a, None if whole else label, least)
                at += n
                if whole:
                    to = np.flatnonzero(first != np.arange(n))
                else:  # one edge for each label that joins another
                    _, one = np.unique(label, return_index=True)
                    to = one[label[first[one]] != label[one]]
                if len(to):
                    x, y = group.take(first[to]), group.take(to)
                    out.append(pa.table([x.column("rep"), x.column("node"), y.column("rep"), y.column("node")], names))
            if out:
                yield from pa.concat_tables(out).combine_chunks().to_batches()

    dealt = rows.select("bucket", "part", "rep", "node", "label", "text").repartition("bucket", "part").sortWithinPartitions("bucket", "part", "rep", "node")
    found = dealt.mapInArrow(run, "x_rep long, x_node string, y_rep long, y_node string")
    end = lambda e: F.struct(F.col(f"{e}_rep").alias("rep"), F.col(f"{e}_node").alias("node")).alias(e)
    return found.select(end("x"), end("y"))


def row_key(doc_id: Column, node: Column) -> Column:
    """One string, never null, for a row's doc_id and node."""
    return F.md5(F.concat_ws("|", F.coalesce(doc_id.cast("long").cast("string"), F.lit("null")), F.coalesce(node, F.lit("null"))))


def placed(nodes: DataFrame) -> DataFrame:
    """nodes: node, rep, bands, size. Per node and bucket that it shares with others: bucket, parts, part, rep, node; buckets of the same nodes once."""
    rows = nodes.where(F.col("bands").isNotNull()).select(F.explode("bands").alias("bucket"), "rep", "node", "size")
    marks = F.bit_xor(F.xxhash64("rep", "node")), F.bit_xor(F.xxhash64("node", "rep", F.lit(1)))
    shared = rows.groupBy("bucket").agg(F.count("*").alias("n"), F.sum("size").alias("bytes"), marks[0].alias("m0"), marks[1].alias("m1")).where("n > 1")
    once = shared.groupBy("n", "bytes", "m0", "m1").agg(F.min("bucket").alias("bucket"))
    parts = F.greatest(F.ceil(F.col("n") / PART_ROWS), F.ceil(F.col("bytes") / PART_BYTES)).cast("int")
    part = F.pmod(F.xxhash64("rep", "node"), F.col("parts")).cast("int")
    return rows.join(once.select("bucket", parts.alias("parts")), "bucket").select("bucket", "parts", part.alias("part"), "rep", "node")


def with_texts(places: DataFrame, docs: DataFrame) -> DataFrame:
    """places (bucket, part, rep, node, label) with text. A node's places travel together, so that texts are dealt by node once and then to buckets."""
    at = places.groupBy("rep", "node", "label").agg(F.collect_list(F.struct("bucket", "part")).alias("at")).withColumn("__k", row_key(F.col("rep"), F.col("node")))
    keyed = docs.select(row_key(F.col("doc_id"), F.md5("text")).alias("__k"), "text").where(F.col("text").isNotNull())
    return keyed.join(at, "__k").dropDuplicates(["__k"]).select(F.inline("at"), "rep", "node", "label", "text")


def links(nodes: DataFrame, docs: DataFrame, idf: np.ndarray, least: float = SIMILARITY) -> DataFrame:
    """nodes: node, rep (a doc_id), bands, size. Edges (x, y) of structs (rep, node) whose components are those of the similar pairs that share a bucket."""
    places = written(placed(nodes), "places")
    found = written(met(with_texts(places.withColumn("label", F.col("node")), docs), idf, least), "edges")
    crowd = places.where("parts > 1")
    if crowd.isEmpty():
        return found
    # parts of crowded buckets meet in pairs, where their nodes are in different components
    label = components(found).select("x.rep", "x.node", F.xxhash64("c").cast("string").alias("known"))
    named = written(crowd.join(label, ["rep", "node"], "left").withColumn("label", F.coalesce("known", "node")).drop("known"), "crowd")
    apart = named.groupBy("bucket").agg(F.min("label").alias("low"), F.max("label").alias("high")).where("low < high").select("bucket")
    both = named.join(apart, "bucket").withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).where("part <> other")
    pair = (F.least("part", "other") * F.col("parts") + F.greatest("part", "other")).alias("part")
    return written(found.unionByName(met(with_texts(both.select("bucket", pair, "rep", "node", "label"), docs), idf, least)), "edges")


def components(edges: DataFrame) -> DataFrame:
    """edges (x, y): node x and the least node c of its connected component, by least labels and pointer jumping."""
    both = written(edges.select("x", "y").union(edges.select(F.col("y").alias("x"), F.col("x").alias("y"))).distinct(), "pairs")
    label = written(both.groupBy("x").agg(F.least(F.min("y"), F.col("x")).alias("c")), "labels")
    while True:
        around = both.join(label.select(F.col("x").alias("y"), F.col("c").alias("n")), "y").groupBy("x").agg(F.min("n").alias("n"))
        least = label.join(around, "x").select("x", F.least("c", "n").alias("c"), F.col("c").alias("was"))
        up = label.select(F.col("x").alias("c"), F.col("c").alias("up"))
        jumped = written(least.join(up, "c").select("x", F.least("c", "up").alias("c"), "was"), "labels")
        label = jumped.select("x", "c")
        if jumped.where(F.col("c") != F.col("was")).isEmpty():
            return label


def classes(docs: DataFrame, least: float = SIMILARITY) -> DataFrame:
    """Per row of docs (doc_id, text): doc_id, class_id, class_key, node (md5 of the text)."""
    idf = word_idf(docs)
    drawn = written(sketches(docs, idf), "sketches")
    nodes = written(drawn.where(F.col("node").isNotNull()).groupBy("node").agg(F.min("doc_id").alias("rep"), F.first("bands").alias("bands"), F.first("size").alias("size")), "nodes")
    label = components(links(nodes, docs, idf, least)).select(F.col("x.node").alias("node"), "c")
    named = nodes.select("node", F.struct("rep", "node").alias("own")).join(label, "node", "left").select("node", F.coalesce("c", "own").alias("c"))
    unnamed = -F.pmod(F.xxhash64("c.node"), F.lit((1 << 62) - 1)) - 1
    named = named.select("node", F.coalesce("c.rep", unnamed).alias("class_id"), F.col("c.node").alias("class_key"), F.col("c.rep").alias("class_rep"))
    kept = drawn.select("doc_id", "node").join(named, "node", "left")
    return kept.select("doc_id", F.when(F.col("node").isNull(), F.col("doc_id")).otherwise(F.col("class_id")).alias("class_id"), "class_key", "node", "class_rep")


def keep_one(docs: DataFrame, least: float = SIMILARITY) -> DataFrame:
    """One row of each class, one that has its class_key's text and least doc_id; all columns of docs. Rows without a text stay."""
    first = classes(docs, least).where((F.col("node") == F.col("class_key")) & F.col("doc_id").eqNullSafe(F.col("class_rep")))
    chosen = first.select(row_key(F.col("doc_id"), F.col("node")).alias("__key")).distinct()
    kept = docs.where(F.col("text").isNotNull()).withColumn("__key", row_key(F.col("doc_id"), F.md5("text"))).join(chosen, "__key", "left_semi").dropDuplicates(["__key"])
    return kept.select(*docs.columns).unionByName(docs.where(F.col("text").isNull()))
