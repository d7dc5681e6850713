"""BPE encoding and decoding by forced boundaries.

A byte pair that occurs inside no token of the vocabulary can't be merged over: a cut between the
two bytes is certain. A word is cut there, each fragment is merged by itself and the ids are
concatenated. White space never enters a token of this vocabulary, so that a text's chunks between
white space are independent too; ids of chunks and fragments are kept in bounded caches.

Defined results: null texts count as empty; an empty text has no tokens and decodes to the empty text;
repeated rows get equal results; texts of any length are encoded whole, long fragments by a heap.
"""

from __future__ import annotations

import hashlib
import heapq
import json
import re
import struct
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

CACHE_ENTRIES = 300_000
#: White space of the tokenizer's pattern: what Unicode calls so, not the separators U+001C to U+001F.
SPACE = re.compile("[\\t-\\r \\x85\\xa0\\u1680\\u2000-\\u200a\\u2028\\u2029\\u202f\\u205f\\u3000]+")
SEPARATORS = re.compile("[\\x1c-\\x1f]")
#: Chunks of these characters are lower-cased and split here; what Unicode's versions differ on goes to the library.
PLAIN = re.compile("[\\x00-\\x1b!-~\\xa1-\\xff]*")
PLAIN_WORD = re.compile("'s|'t|'re|'ve|'m|'ll|'d|[a-z\\xaa\\xb5\\xba\\xdf-\\xf6\\xf8-\\xff]+|[0-9\\xb2\\xb3\\xb9\\xbc-\\xbe]|[^\\sa-z0-9\\xaa\\xb2\\xb3\\xb5\\xb9\\xba\\xbc-\\xbe\\xdf-\\xf6\\xf8-\\xff]+")
LONG_FRAGMENT = 96


def printable_bytes() -> dict[int, str]:
    """The usual one-to-one map of bytes to printable characters of byte-level BPE."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    spare = iter(range(256, 512))
    return {b: chr(b) if b in plain else chr(next(spare)) for b in range(256)}


class Recent(dict):
    """A dictionary of bounded size that forgets what wasn't asked for lately."""

    def __init__(self) -> None:
        super().__init__()
        self.older: dict = {}

    def __missing__(self, key):
        if (found := self.older.get(key)) is not None:
            self.keep(key, found)
        return found

    def keep(self, key, value) -> None:
        if len(self) >= CACHE_ENTRIES // 2:
            self.older = dict(self)
            self.clear()
        self[key] = value


class WordBpe:
    """Encoder and decoder of a tokenizer file with lower-cased words and word ends."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        spec = json.load(open(path, encoding="utf-8"))
        model = spec["model"]
        self.vocab: dict[str, int] = model["vocab"]
        self.end: str = model["end_of_word_suffix"]
        merges = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in model["merges"]]
        self.ranks = {pair: i for i, pair in enumerate(merges)}
        self.names = {i: t for t, i in self.vocab.items()} | {a["id"]: a["content"] for a in spec["added_tokens"]}
        self.special = {a["content"]: a["id"] for a in spec["added_tokens"]}
        self.special_pattern = re.compile("(" + "|".join(map(re.escape, self.special)) + ")")
        self.library = Tokenizer.from_file(path)  # its normaliser and word splitter, for texts that aren't plain
        self.byte_char = printable_bytes()
        self.pairs = self._inner_pairs()
        self.fragments, self.words, self.chunks = Recent(), Recent(), Recent()

    def _inner_pairs(self) -> set[str]:
        """Pairs of neighbouring characters inside any token."""
        pairs = set()
        for token in self.vocab:
            body = token.removesuffix(self.end)
            pairs.update(map("".join, zip(body, body[1:])))
        return pairs

    def cut(self, word: str) -> list[str]:
        """Fragments of a byte-mapped word between forced boundaries."""
        pairs, cuts = self.pairs, [0]
        cuts += [i for i in range(1, len(word)) if word[i - 1 : i + 1] not in pairs]
        return [word[a:b] for a, b in zip(cuts, [*cuts[1:], len(word)])]

    def merge(self, fragment: str, last: bool) -> tuple[int, ...]:
        parts = list(fragment)
        if last:
            parts[-1] += self.end
        parts = self._merge_long(parts) if len(parts) > LONG_FRAGMENT else self._merge_short(parts)
        return tuple(self.vocab[p] for p in parts if p in self.vocab)

    def _merge_short(self, parts: list[str]) -> list[str]:
        rank, none = self.ranks.get, len(self.ranks)
        scores = [rank(pair, none) for pair in zip(parts, parts[1:])]
        while scores and (best := min(scores)) < none:
            i = scores.index(best)
            parts[i] += parts.pop(i + 1)
            del scores[i]
            if i:
                scores[i - 1] = rank((parts[i - 1], parts[i]), none)
            if i < len(scores):
                scores[i] = rank((parts[i], parts[i + 1]), none)
        return parts

    def _merge_long(self, parts: list[str]) -> list[str]:
        """The same by a heap over a linked list: n log n for a fragment of n bytes."""
        n, ranks = len(parts), self.ranks
        left, right = [*range(-1, n - 1)], [*range(1, n), -1]
        heap = [(ranks[p], i, p) for i, p in enumerate(zip(parts, parts[1:])) if p in ranks]
        heapq.heapify(heap)
        while heap:
            _, i, (a, b) = heapq.heappop(heap)
            j = right[i]
            if parts[i] != a or j < 0 or parts[j] != b:
                continue
            parts[i], parts[j], right[i] = a + b, "", right[j]
            if right[i] >= 0:
                left[right[i]] = i
            for x, y in ((left[i], i), (i, right[i])):
                if x >= 0 and y >= 0 and (pair := (parts[x], parts[y])) in ranks:
                    heapq.heappush(heap, (ranks[pair], x, pair))
        return [p for p in parts if p]

    def encode_word(self, mapped: str) -> tuple[int, ...]:
        """Ids of a word given in printable bytes."""
        if (ids := self.words[mapped]) is not None:
            return ids
        pieces, out, known = self.cut(mapped), [], self.fragments
        for k, piece in enumerate(pieces):
            key = (piece, k == len(pieces) - 1)
            if (found := known[key]) is None:
                found = self.merge(*key)
                if len(pieces) > 1 and len(piece) < LONG_FRAGMENT:
                    known.keep(key, found)
            out += found
        ids = tuple(out)
        if len(mapped) < LONG_FRAGMENT:
            self.words.keep(mapped, ids)
        return ids

    def split(self, chunk: str) -> list[str]:
        """Words, in printable bytes, of a chunk without white space."""
        if chunk.isascii() and chunk.isalpha():
            return [chunk.lower()]
        if PLAIN.fullmatch(chunk):
            table = self.byte_char
            return [w if w.isascii() and w.isprintable() else "".join([table[b] for b in w.encode("utf-8")]) for w in PLAIN_WORD.findall(chunk.lower())]
        normal = self.library.normalizer.normalize_str(chunk)
        return [w for w, _ in self.library.pre_tokenizer.pre_tokenize_str(normal)]

    def encode_chunk(self, chunk: str) -> tuple[bytes, str]:
        """Ids, as little-endian bytes, and decoded text of a chunk without white space."""
        ids = [i for word in self.split(chunk) for i in self.encode_word(word)]
        return struct.pack(f"<{len(ids)}I", *ids), " ".join([self.names[i] for i in ids])

    def encode(self, text: str) -> tuple[bytes, str]:
        """Ids of a whole text, as little-endian unsigned 32-bit integers, and what they decode to."""
        ids, said, known = [], [], self.chunks
        for k, part in enumerate(self.special_pattern.split(text) if "<|" in text else [text]):
            if k % 2:
                ids.append(struct.pack("<I", self.special[part]))
                said.append(part)
                continue
            for chunk in [c for c in SPACE.split(part) if c] if SEPARATORS.search(part) else part.split():
                if (found := known[chunk]) is None:
                    found = self.encode_chunk(chunk)
                    if len(chunk) < LONG_FRAGMENT:
                        known.keep(chunk, found)
                if found[0]:
                    ids.append(found[0])
                    said.append(found[1])
        return b"".join(ids), " ".join(said)


_loaded: dict[str, WordBpe] = {}


def encoder(path: str) -> WordBpe:
    """One encoder for each Python worker and file."""
    if path not in _loaded:
        _loaded[path] = WordBpe(path)
    return _loaded[path]


def encode_documents(docs: DataFrame, path: str, key: str = "doc_id", text: str = "text", keep: bool = False) -> DataFrame:
    """Per row: key, n_tokens, ids_sha256, decoded_sha256; with keep also ids (array<int>) and decoded."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = encoder(path)
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                found = [bpe.encode(t or "") for t in part.column(1).to_pylist()]
                columns = [
                    part.column(0),
                    pa.array([len(i) // 4 for i, _ in found], pa.int64()),
                    pa.array([hashlib.sha256(i).hexdigest() for i, _ in found]),
                    pa.array([hashlib.sha256(d.encode("utf-8")).hexdigest() for _, d in found]),
                ]
                names = [key, "n_tokens", "ids_sha256", "decoded_sha256"]
                if keep:
                    columns += [pa.array([list(struct.unpack(f"<{len(i) // 4}I", i)) for i, _ in found], pa.list_(pa.int32())), pa.array([d for _, d in found])]
                    names += ["ids", "decoded"]
                yield pa.RecordBatch.from_arrays(columns, names)

    kind = docs.schema[key].dataType.simpleString()
    return docs.select(key, text).mapInArrow(run, f"{key} {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>, decoded string" * keep)
