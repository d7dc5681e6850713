"""Best-fit packing of token pieces under a vector of capacities.

A sequence has three residual capacities: tokens, documents and attention cost (the sum of squared
piece lengths). Pieces go longest first to the open sequence that fits best under every constraint: the
one with the largest dot product of its residuals, weighted and in units of the capacities, with the piece's
demands or, by default, the least norm of what remains.

A piece is described by its length alone, so that what the packer needs of the corpus is a histogram:
at most MAX_TOKENS counts, whatever the corpus. The driver packs the histogram: sequences in equal states
move together. This yields, for each length, ranges of ranks with a first sequence and an offset; pieces
take ranks within their length (by salted counts, so that a popular length is nobody's single
task) and find their place by a join with that plan.

With the defaults only the token capacity can bind, as that gives the fewest sequences; max_documents and max_cost make the others bind.

Defined results: a null text is empty and, like the empty text, yields its end token alone; repeated rows are
packed each; documents over MAX_TOKENS are cut, the first piece taking what full pieces leave; a null doc_id stays null; extra columns are left out; an
empty table has no pieces; a piece that no empty sequence can hold under max_cost is an error.
"""

from __future__ import annotations

import base64
import re
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import written

MAX_TOKENS = 2048
END_ID = 0
#: Pieces of one length that a part holds, about, and parts of a length at most: beyond, parts grow.
SALT_ROWS, MAX_SALTS = 1000, 10_000
#: Ranges of ranks that are broadcast at most.
MAX_PLACES = 1 << 18
CACHE_ENTRIES = 250_000
#: Text that is encoded at a time, or one document if that is longer.
SLICE_BYTES = 1 << 21
#: Chunks of these characters are the same to both libraries whatever their Unicode versions.
PLAIN = re.compile("[\x21-\x7e\xa1-\xff \n]*")
#: One such word, by itself or after a space, as Arrow reads it.
WORD = "^ ?[\x21-\x7e\xa1-\xff]+\\z"
#: Texts with these stay whole: the end token's mark, white space beyond ASCII.
WHOLE = "<\\||[\x85\xa0\u1680\u180e\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]"
#: Bytes that are no ASCII white space or control character.
SOLID = np.array([33 <= b <= 126 or b >= 128 for b in range(256)])


def _bytes_of(texts: pa.LargeStringArray) -> tuple[np.ndarray, memoryview]:
    """Where each text, none of them null, begins in their bytes, with the end, and these."""
    if not len(texts):
        return np.zeros(1, np.int64), memoryview(b"")
    bounds = np.frombuffer(texts.buffers()[1], np.int64, len(texts) + 1, 8 * texts.offset)
    return bounds - bounds[0], memoryview(texts.buffers()[2] or b"")[bounds[0] : bounds[-1]]


class ByteBpe:
    """Byte-level BPE with ids by the tokenizers library, fast for plain text.

    Between a character and a single space or line feed before another character the splitter always cuts.
    Equal chunks between such places count once in a slice of texts: plain ones are encoded together, as one text
    of such chunks, others by themselves, and ids of short ones among these are kept.
    """

    def __init__(self, path: str, ranks_path: str | None):
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.fast = None
        if ranks_path:
            import public_tokenizers
            import tiktoken

            with open(ranks_path, "rb") as f:
                ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
            self.fast = tiktoken.Encoding("bytes", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
            self.sizes = np.zeros(max(ranks.values()) + 1, np.int64)
            self.sizes[list(ranks.values())] = list(map(len, ranks))
        self.known: dict[str, bytes] = {}

    def chunk(self, text: str) -> bytes:
        if self.fast and "<|" not in text and PLAIN.fullmatch(text):
            ids = self.fast.encode_ordinary(text)
        else:
            ids = self.library.encode(text, add_special_tokens=False).ids
        return struct.pack(f"<{len(ids)}I", *ids)

    def joined(self, chunks: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Ids of plain chunks, encoded as one text and cut where a chunk's bytes end; those without a space follow a line feed."""
        bare = pc.invert(pc.starts_with(chunks, " "))
        parts = pc.binary_join_element_wise(pc.if_else(bare, "\n", "").cast(chunks.type), chunks, pa.scalar("", chunks.type))
        bounds, buffer = _bytes_of(parts)
        ids = np.array(self.fast.encode_ordinary(str(buffer, "utf-8")), "<u4")
        stops = np.searchsorted(np.cumsum(self.sizes[ids]), bounds[1:], side="right")
        first = np.concatenate([[0], stops[:-1]]) + bare.to_numpy(zero_copy_only=False)
        return ids, first, stops - first

    def chunks(self, chunks: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Ids of different chunks, where each one's begin, and how many each has."""
        first, counts, ids = np.zeros(len(chunks), np.int64), np.zeros(len(chunks), np.int64), np.zeros(0, "<u4")
        plain = np.zeros(len(chunks), bool)
        if self.fast:
            plain = pc.and_not(pc.match_substring_regex(chunks, WORD), pc.match_substring(chunks, "<|")).to_numpy(zero_copy_only=False)
        if plain.any():
            ids, first[plain], counts[plain] = self.joined(chunks.filter(pa.array(plain)))
        found = []
        for c in chunks.filter(pa.array(~plain)).to_pylist():
            if (x := self.known.get(c)) is None:
                x = self.chunk(c)
                if len(c) < 64:
                    if len(self.known) >= CACHE_ENTRIES:
                        for old in list(self.known)[CACHE_ENTRIES // 4 :]:
                            del self.known[old]
                    self.known[c] = x
            found.append(x)
        counts[~plain] = [len(x) // 4 for x in found]
        first[~plain] = len(ids) + np.cumsum(counts[~plain]) - counts[~plain]
        return np.concatenate([ids, np.frombuffer(b"".join(found), "<u4")]), first, counts

    def encode_all(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts, one text after the other, and how many each has. Null texts are empty."""
        texts = texts.cast(pa.large_string()).fill_null("")
        bounds, buffer = _bytes_of(texts)
        if not bounds[-1]:
            return np.zeros(0, "<u4"), np.zeros(len(texts), np.int64)
        data, cut = np.frombuffer(buffer, np.uint8), np.zeros(len(buffer) + 1, bool)
        cut[bounds] = True
        at = np.flatnonzero((data == 32) | (data == 10))
        at = at[~(cut[at] | cut[at + 1])]
        at = at[SOLID[data[at - 1]] & SOLID[data[at + 1]]]
        whole = pc.match_substring_regex(texts, WHOLE).to_numpy(zero_copy_only=False)
        if whole.any():
            at = at[~whole[np.searchsorted(bounds, at, side="right") - 1]]
        cut[at] = True
        cut[at[data[at] == 10] + 1] = True
        starts = np.flatnonzero(cut)
        coded = pa.LargeStringArray.from_buffers(len(starts) - 1, pa.py_buffer(starts), pa.py_buffer(buffer)).dictionary_encode()
        (ids, first, counts), codes = self.chunks(coded.dictionary), coded.indices.to_numpy()
        own = counts[codes]
        stops = np.concatenate([[0], np.cumsum(own)])
        place = np.repeat(first[codes] - stops[:-1], own)
        place += np.arange(len(place))
        return ids[place], np.diff(stops[np.searchsorted(starts, bounds)])

    def encode(self, text: str) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        return self.encode_all(pa.array([text], pa.string()))[0].tobytes()


_loaded: dict[str, ByteBpe] = {}


def _slices(texts: pa.Array) -> Iterator[tuple[int, int]]:
    """Rows from, to: of SLICE_BYTES at most, or one."""
    ends, a = np.cumsum(pc.fill_null(pc.binary_length(texts), 0).to_numpy(), dtype=np.int64), 0
    while a < len(ends):
        b = max(a + 1, int(np.searchsorted(ends, (ends[a - 1] if a else 0) + SLICE_BYTES, side="right")))
        yield a, b
        a = b


def pieces(docs: DataFrame, path: str, ranks_path: str | None = None, max_tokens: int = MAX_TOKENS, keep: bool = False) -> DataFrame:
    """Per piece: doc_id, piece, start, length, ids_crc32; with keep also ids (array<int>)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if path not in _loaded:
            _loaded[path] = ByteBpe(path, ranks_path)
        for batch in batches:
            for a, b in _slices(batch.column(1)):
                own, counts = _loaded[path].encode_all(batch.column(1).slice(a, b - a))
                ends = np.cumsum(counts + 1)
                ids = np.full(ends[-1], END_ID, "<u4")
                inside = np.ones(len(ids), bool)
                inside[ends - 1] = False
                ids[inside] = own
                full = counts // max_tokens  # pieces after the first
                first = counts + 1 - full * max_tokens
                doc = np.repeat(np.arange(b - a), full + 1)
                piece = np.arange(len(doc)) - (np.cumsum(full + 1) - full - 1)[doc]
                start = np.where(piece > 0, first[doc] + (piece - 1) * max_tokens, 0)
                length = np.where(piece > 0, max_tokens, first[doc])
                stops, raw = np.concatenate([[0], np.cumsum(length)]), memoryview(ids).cast("B")
                crc = [zlib.crc32(raw[4 * x : 4 * y]) for x, y in zip(stops[:-1].tolist(), stops[1:].tolist())]
                columns = [batch.column(0).slice(a, b - a).take(pa.array(doc)), pa.array(piece, pa.int32()), pa.array(start), pa.array(length), pa.array(crc, pa.int64())]
                if keep:
                    columns.append(pa.ListArray.from_arrays(pa.array(stops, pa.int32()), pa.array(ids.view(np.int32))))
                yield pa.RecordBatch.from_arrays(columns, ["doc_id", "piece", "start", "length", "ids_crc32", "ids"][: 5 + keep])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long" + ", ids array<int>" * keep)


class Plan:
    """Sequences packed from a histogram; those in one state are a group that moves together."""

    def __init__(self, capacities: tuple[int, int, int], weights=(1.0, 1.0, 1.0), score: str = "norm"):
        if score not in ("norm", "dot"):
            raise ValueError("score is norm or dot")
        self.capacity, self.weights, self.score = np.array(capacities, float), np.array(weights, float), score
        self.residual = np.zeros((0, 3))
        self.first = np.zeros(0, np.int64)  # sequences of a group: first, first + 1, ... first + count - 1
        self.count = np.zeros(0, np.int64)
        self.next_sequence = 0
        self.ranges: list[tuple[int, int, int, int, int]] = []  # length, from rank, to rank, first sequence, offset

    def _best(self, demand: np.ndarray) -> int:
        fits = (self.residual >= demand).all(axis=1) & (self.count > 0)
        if not fits.any():
            return -1
        units = self.residual / self.capacity
        if self.score == "norm":
            value = (self.weights * ((self.residual - demand) / self.capacity) ** 2).sum(axis=1)
        else:
            value = -(self.weights * units * (demand / self.capacity)).sum(axis=1)
        return int(np.where(fits, value, np.inf).argmin())

    def _open(self, residual: np.ndarray, first: int, count: int) -> None:
        self.residual = np.vstack([self.residual, residual])
        self.first, self.count = np.append(self.first, first), np.append(self.count, count)

    def place(self, length: int, count: int) -> None:
        demand, rank = np.array([length, 1, length**2], float), 0
        if (demand > self.capacity).any():
            raise ValueError(f"a piece of {length} tokens exceeds the capacities")
        while rank < count:
            g = self._best(demand)
            if g < 0:  # open sequences: as many as the pieces left can fill
                each = int((self.capacity // demand).min())
                n = -(-(count - rank) // each)
                full, rest = divmod(count - rank, each)
                for k in range(each):
                    took = min(n, count - rank)
                    self.ranges.append((length, rank, rank + took, self.next_sequence, k * length))
                    rank += took
                    # the sequences that got piece k but not k + 1
                    left = min(n, max(count - rank, 0)) if k + 1 < each else 0
                    if took > left:
                        self._open(self.capacity - (k + 1) * demand, self.next_sequence + left, took - left)
                    n = left
                    if not left:
                        break
                self.next_sequence += -(-(full * each + rest) // each)
                break
            took, offset = min(int(self.count[g]), count - rank), int(self.capacity[0] - self.residual[g, 0])
            self.ranges.append((length, rank, rank + took, int(self.first[g]), offset))
            rank += took
            left = self.residual[g] - demand
            if took == self.count[g]:
                self.residual[g] = left
            else:
                self._open(left, int(self.first[g]), took)
                self.first[g] += took
                self.count[g] -= took
        self._merge()

    def _merge(self) -> None:
        """Forget sequences that can't take any piece."""
        useful = (self.residual >= 1).all(axis=1) & (self.count > 0)
        if not useful.all():
            self.residual, self.first, self.count = self.residual[useful], self.first[useful], self.count[useful]


def pack_histogram(counts: dict[int, int], capacities: tuple[int, int, int], weights=(1.0, 1.0, 1.0), score: str = "norm") -> Plan:
    plan = Plan(capacities, weights, score)
    for length in sorted(counts, reverse=True):
        plan.place(length, counts[length])
    return plan


def ranked(found: DataFrame, counts: dict[int, int]) -> DataFrame:
    """found with rank: 0, 1, ... within each length. A length's pieces are dealt to parts of about SALT_ROWS."""
    parts = [(n, min(-(-c // SALT_ROWS), MAX_SALTS)) for n, c in counts.items()]  # a row for each length
    salts = F.broadcast(found.sparkSession.createDataFrame(parts, "__length long, __salts int"))
    salted = found.join(salts, found["length"] == F.col("__length")).withColumn("__salt", F.pmod(F.xxhash64("doc_id", "piece", "start", "ids_crc32"), F.col("__salts")).cast("int")).drop("__length", "__salts")
    before = Window.partitionBy("length").orderBy("__salt").rowsBetween(Window.unboundedPreceding, -1)
    base = salted.groupBy("length", "__salt").agg(F.count("*").alias("__n")).select("length", "__salt", F.coalesce(F.sum("__n").over(before), F.lit(0)).alias("__base"))
    own = Window.partitionBy("length", "__salt").orderBy("doc_id", "piece", "ids_crc32")
    return salted.withColumn("__i", F.row_number().over(own) - 1).join(base, ["length", "__salt"]).withColumn("rank", F.col("__i") + F.col("__base")).drop("__salt", "__i", "__base")


def pack(found: DataFrame, max_tokens: int = MAX_TOKENS, max_documents: int | None = None, max_cost: int | None = None, weights=(1.0, 1.0, 1.0), score: str = "norm") -> DataFrame:
    """Pieces (doc_id, piece, start, length, ids_crc32, ...; read more than once, so a written table) with sequence_id and offset.

    max_documents and max_cost limit the pieces and the summed squared lengths of a sequence. Unset, they are what max_tokens tokens can't
    exceed, so that only tokens bind: this gives the fewest sequences.
    """
    spark = found.sparkSession
    histogram = {r["length"]: r["n"] for r in found.groupBy("length").agg(F.count("*").alias("n")).toLocalIterator()}  # at most max_tokens rows
    plan = pack_histogram(histogram, (max_tokens, max_documents or max_tokens, max_cost or max_tokens**2), weights, score)
    rows = [tuple(map(int, r)) for r in plan.ranges]
    places = spark.createDataFrame(rows, "__length long, __from long, __to long, __first long, offset long")
    numbered = ranked(found, histogram)
    inside = (F.col("length") == F.col("__length")) & (F.col("rank") >= F.col("__from")) & (F.col("rank") < F.col("__to"))
    if len(rows) <= MAX_PLACES:  # a few bytes each, whatever the number of pieces
        joined = numbered.join(F.broadcast(places), inside)
    else:  # by cells of ranks, so that no length is one key
        cell = lambda c: F.floor(c / (SALT_ROWS * 100)).cast("long")
        joined = numbered.withColumn("__cell", cell(F.col("rank"))).join(places.withColumn("__at", F.explode(F.sequence(cell(F.col("__from")), cell(F.col("__to") - 1)))), inside & (F.col("__cell") == F.col("__at")))
    return joined.select(*[F.col(f"`{c}`") for c in found.columns], (F.col("__first") + F.col("rank") - F.col("__from")).alias("sequence_id"), "offset")


def pack_documents(docs: DataFrame, path: str, ranks_path: str | None = None, **limits) -> DataFrame:
    """The pieces of all documents with their sequences."""
    return pack(written(pieces(docs, path, ranks_path, limits.get("max_tokens", MAX_TOKENS)), "pieces"), **limits)
