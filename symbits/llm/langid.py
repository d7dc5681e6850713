"""Language identification by hyperdimensional profiles.

Each letter of any script has a random vector of +1 and -1, made from a hash of its code point. A letter trigram's vector binds them by multiplication,
permuted (rotated) by position. A text's vector bundles its trigrams by addition; a language's prototype bundles
its training texts. The language is the prototype of the largest cosine. Cosines of short or repetitive texts are as low as
those of random letters, so that a text is recognised by the share of its trigrams that its language knows.

Letters are lower-cased; a run of other characters is a boundary.

Defined results: a null text and one without letters is ``und`` with score 0; so is every text if
nothing was learned; repeated rows get equal results; texts of any length are read whole; of equal cosines the first language
by name wins; an empty table gives no rows; of extra columns that are named as the results are, the results replace them in predict(), and
recognised() keeps them.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import written

DIMENSIONS = 1024
UNKNOWN = "und"
#: A language knows the trigrams that make at least this share of its training text, so 65,536 at most. A text is recognised if its language knows
#: so much of it: held-out documents of sf0.01 have 0.73 or more, random letters 0.12 at most, a text in an unlearned language up to 0.5.
KNOWN_SHARE = 2.0**-16
MIN_KNOWN = 0.53
#: Bits of a code point in a trigram's code.
BITS = 21
MASK = (1 << BITS) - 1
#: Letters whose vectors a worker holds at most; beyond, it begins anew.
MAX_LETTERS = 16384


@lru_cache(1)
def _lower_table() -> np.ndarray:
    """Lower-case code point of each letter of the basic plane; 0 for other characters."""
    return np.array([_lower(c) for c in range(1 << 16)], np.int64)


def _lower(point: int) -> int:
    return ord(chr(point).lower()[0]) if chr(point).isalpha() else 0


class Letters:
    """Vectors of the letters met so far, rotated by two, by one and not; row 0 is the boundary's."""

    def __init__(self):
        self.row = np.full(1 << BITS, -1, np.int32)
        self.rotated = [np.zeros((0, DIMENSIONS), np.int8)] * 3

    def rows(self, points: np.ndarray) -> np.ndarray:
        new = np.unique(points[self.row[points] < 0])
        if len(new):
            if len(self.rotated[0]) + len(new) > MAX_LETTERS:
                self.__init__()
                new = np.unique(points)
            self.row[new] = len(self.rotated[0]) + np.arange(len(new))
            own = vectors(new)
            self.rotated = [np.concatenate([r, np.roll(own, 2 - k, 1)]) for k, r in enumerate(self.rotated)]
        return self.row[points]


_letters = Letters()


def vectors(points: np.ndarray) -> np.ndarray:
    """The random vectors of these code points: bits of a mixed hash of code point and 64 components each."""
    with np.errstate(over="ignore"):
        x = (points.astype(np.uint64)[:, None] * np.uint64(DIMENSIONS // 64) + np.arange(1, DIMENSIONS // 64 + 1, dtype=np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        x ^= x >> np.uint64(31)
    return np.unpackbits(x.astype("<u8").view(np.uint8), axis=1, bitorder="little").astype(np.int8) * 2 - 1


def trigrams(text: str) -> tuple[np.ndarray, np.ndarray]:
    """Codes of the distinct trigrams of letters and boundaries, and how often each occurs; none without letters."""
    points = np.frombuffer(text.encode("utf-32-le", "replace"), np.uint32)
    letters = _lower_table()[np.minimum(points, 0xFFFF)]
    if (far := points > 0xFFFF).any():
        letters[far] = [_lower(int(c)) for c in points[far]]
    letters = np.concatenate([[0], letters, [0]])
    letters = letters[np.concatenate([[True], (letters[1:] != 0) | (letters[:-1] != 0)])]
    if len(letters) < 3:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    return np.unique(letters[:-2] << 2 * BITS | letters[1:-1] << BITS | letters[2:], return_counts=True)


def bundle(codes: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """The sum of the trigrams' bound vectors."""
    total = np.zeros(DIMENSIONS, np.float32)
    for at in range(0, len(codes), 4096):
        c = codes[at : at + 4096]
        parts = [c >> 2 * BITS, c >> BITS & MASK, c & MASK]
        rows = np.split(_letters.rows(np.concatenate(parts)), 3)
        bound = _letters.rotated[0][rows[0]] * _letters.rotated[1][rows[1]] * _letters.rotated[2][rows[2]]
        total += counts[at : at + 4096].astype(np.float32) @ bound.astype(np.float32)
    return total


def profiles(docs: DataFrame, text: str = "text", label: str = "lang") -> DataFrame:
    """A written table (label, code, n): the trigrams of all rows with a text and a label, and how often each occurs."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: dict[str, list[tuple[np.ndarray, np.ndarray]]] = {}
        held: dict[str, int] = {}

        def merged(own: str) -> tuple[np.ndarray, np.ndarray]:
            codes, at = np.unique(np.concatenate([c for c, _ in seen[own]]), return_inverse=True)
            return codes, np.bincount(at, np.concatenate([n for _, n in seen[own]]), len(codes)).astype(np.int64)

        def row(own: str) -> pa.RecordBatch:
            codes, counts = merged(own)
            return pa.RecordBatch.from_arrays([pa.array([own] * len(codes), pa.string()), pa.array(codes, pa.int64()), pa.array(counts, pa.int64())], ["label", "code", "n"])

        for batch in batches:
            for own, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                codes, counts = trigrams(t)
                seen.setdefault(own, []).append((codes, counts))
                held[own] = held.get(own, 0) + len(codes)
                if held[own] > 1 << 18:
                    seen[own] = [merged(own)]
                    held[own] = len(seen[own][0][0])
                    if held[own] > 1 << 17:  # many different ones: they are summed later
                        yield row(own)
                        seen[own], held[own] = [], 0
        for own in seen:
            if seen[own]:
                yield row(own)

    rows = docs.where(F.col(text).isNotNull() & F.col(label).isNotNull()).select(F.col(label).alias("label"), F.col(text).alias("text"))
    return written(rows.mapInArrow(count, "label string, code long, n long").groupBy("label", "code").agg(F.sum("n").alias("n")), "profiles")


def prototypes_of(learned: DataFrame) -> tuple[list[str], np.ndarray]:
    """Languages, sorted, and their prototypes of unit length, from profiles(); DIMENSIONS rows a language reach the driver."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[str, np.ndarray] = {}
        for batch in batches:
            label = np.array(batch.column(0).to_pylist(), object)
            codes, counts = batch.column(1).to_numpy(), batch.column(2).to_numpy()
            for own in set(label):
                total[own] = total.get(own, 0) + np.concatenate([bundle(codes[label == own], counts[label == own]).astype(np.float64)])
        for own, v in total.items():
            yield pa.RecordBatch.from_arrays([pa.array([own] * DIMENSIONS), pa.array(np.arange(DIMENSIONS), pa.int32()), pa.array(v, pa.float64())], ["label", "i", "v"])

    summed = learned.mapInArrow(run, "label string, i int, v double").groupBy("label", "i").agg(F.sum("v").alias("v"))
    found: dict[str, np.ndarray] = {}
    for r in summed.toLocalIterator():
        found.setdefault(r["label"], np.zeros(DIMENSIONS))[r["i"]] = r["v"]
    names = sorted(own for own in found if found[own].any())
    return names, np.array([found[own] / np.linalg.norm(found[own]) for own in names], np.float32).reshape(len(names), DIMENSIONS)


def learn(docs: DataFrame, text: str = "text", label: str = "lang") -> tuple[list[str], np.ndarray]:
    return prototypes_of(profiles(docs, text, label))


def known_trigrams(learned: DataFrame) -> dict[str, np.ndarray]:
    """Sorted codes of the trigrams that each language knows: at most 1 / KNOWN_SHARE for each."""
    whole = learned.groupBy("label").agg(F.sum("n").alias("total"))
    found: dict[str, list[int]] = {}
    for r in learned.join(F.broadcast(whole), "label").where(F.col("n") >= F.col("total") * KNOWN_SHARE).select("label", "code").toLocalIterator():
        found.setdefault(r["label"], []).append(r["code"])
    return {own: np.sort(np.array(codes, np.int64)) for own, codes in found.items()}


def known_share(codes: np.ndarray, counts: np.ndarray, known: np.ndarray | None) -> float:
    """Share of a text's trigrams, repeats included, that are known."""
    if known is None or not len(codes):
        return 0.0
    at = np.minimum(np.searchsorted(known, codes), len(known) - 1)
    return float(counts[known[at] == codes].sum() / counts.sum())


def _classified(codes: np.ndarray, counts: np.ndarray, names: list[str], prototypes: np.ndarray) -> tuple[str, float]:
    if not len(codes) or not names:
        return UNKNOWN, 0.0
    vector = bundle(codes, counts)
    if not (norm := float(np.linalg.norm(vector))):
        return UNKNOWN, 0.0
    cosines = prototypes @ vector / norm
    best = int(cosines.argmax())
    return names[best], float(min(1.0, max(0.0, cosines[best])))


def classify(text: str | None, names: list[str], prototypes: np.ndarray) -> tuple[str, float]:
    return _classified(*trigrams(text or ""), names, prototypes)


def predict(docs: DataFrame, names: list[str], prototypes: np.ndarray, text: str = "text") -> DataFrame:
    """docs with lang_pred and score; text is the only input."""
    result = ("lang_pred", "score")
    keep = [c for c in docs.columns if c != text and c not in result]
    schema = "".join(f"`{c}` {docs.schema[c].dataType.simpleString()}, " for c in keep) + f"`{text}` string, lang_pred string, score double"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [classify(t, names, prototypes) for t in batch.column(len(keep)).to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array([f[0] for f in found], pa.string()), pa.array([f[1] for f in found], pa.float64())], [*keep, text, *result])

    return docs.select(*keep, text).mapInArrow(run, schema).select(*[c for c in docs.columns if c not in result], *result)


def held_out(key: Column) -> Column:
    """Rows that nothing is learned from: crc32 of the key as text leaves 2 modulo 4."""
    return F.coalesce(F.crc32(key.cast("string")) % 4 == 2, F.lit(False))


def identify(docs: DataFrame) -> DataFrame:
    """docs (doc_id, text, lang, ...) with lang_pred and score by prototypes of the rows that aren't held out."""
    names, prototypes = learn(docs.where(~held_out(F.col("doc_id"))))
    return predict(docs, names, prototypes)


def recognised(docs: DataFrame) -> DataFrame:
    """The rows of docs whose language is recognised, with the columns of docs."""
    learned = profiles(docs.where(~held_out(F.col("doc_id"))))
    names, prototypes = prototypes_of(learned)
    known = known_trigrams(learned)

    def enough(text: str | None) -> bool:
        codes, counts = trigrams(text or "")
        own, _ = _classified(codes, counts, names, prototypes)
        return known_share(codes, counts, known.get(own)) >= MIN_KNOWN

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch.filter(pa.array([enough(t) for t in batch.column(batch.schema.names.index("text")).to_pylist()], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
