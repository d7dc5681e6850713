"""Encodings of a chunk: plain words, word-aligned runs with counts of dirty words, fill markers alone, positions, runs of ones.

Payloads are bytes, little-endian. A marker word of "rle" holds a fill bit, the length of the fill and the
number of dirty words after it, so that dirty stretches can be skipped; of "fills" it holds fill bit and length, and every
dirty word has a marker of its own. Trailing zero words are left out unless trim is False.
"""

from __future__ import annotations

import numpy as np

KINDS = ("plain", "rle", "fills", "positions", "runs")
FILL_MAX, DIRTY_MAX = (1 << 32) - 1, (1 << 31) - 1


def bits(words: np.ndarray) -> np.ndarray:
    """Positions of ones."""
    return np.flatnonzero(np.unpackbits(words.astype("<u8").view(np.uint8), bitorder="little"))


def from_bits(positions: np.ndarray, n_words: int) -> np.ndarray:
    out = np.zeros(n_words * 64, np.uint8)
    out[positions] = 1
    return np.packbits(out, bitorder="little").view("<u8")


def trimmed(words: np.ndarray) -> np.ndarray:
    used = words.nonzero()[0]
    return words[: used[-1] + 1] if len(used) else words[:0]


def runs_of(words: np.ndarray) -> np.ndarray:
    """start, stop of the runs of ones, as rows."""
    b = np.concatenate([[0], np.unpackbits(words.astype("<u8").view(np.uint8), bitorder="little"), [0]]).astype(np.int8)
    d = np.diff(b)
    return np.stack([np.flatnonzero(d == 1), np.flatnonzero(d == -1) - 1], 1)


def _stretches(words: np.ndarray) -> list[tuple[int, int, np.ndarray]]:
    """(fill bit, fill words, the dirty words after)."""
    ones = ~np.uint64(0)
    kind = np.where(words == 0, 0, np.where(words == ones, 1, 2))
    edges = np.flatnonzero(np.diff(kind)) + 1
    out: list[tuple[int, int, np.ndarray]] = []
    for a, b in zip([0, *edges], [*edges, len(words)]):
        if a == b:
            continue
        if kind[a] == 2:
            if out and not len(out[-1][2]):
                out[-1] = (*out[-1][:2], words[a:b])
            else:
                out.append((0, 0, words[a:b]))
        else:
            out.append((int(kind[a]), int(b - a), words[:0]))
    return out


def encode(words: np.ndarray, kind: str = "auto", trim: bool = True) -> tuple[str, bytes]:
    words = np.asarray(words, np.uint64)
    if kind == "auto":
        kind = choose(words)
    if kind == "plain":
        return kind, (trimmed(words) if trim else words).astype("<u8").tobytes()
    if kind == "positions":
        return kind, bits(words).astype("<u4").tobytes()
    if kind == "runs":
        return kind, runs_of(words).astype("<u4").tobytes()
    own = trimmed(words) if trim else words
    out: list[np.ndarray] = []
    for bit, fill, dirty in _stretches(own):
        if kind == "rle":
            out += [np.array([bit | fill << 1 | len(dirty) << 33], "<u8"), dirty]
        elif kind == "fills":
            if fill:
                out.append(np.array([bit | fill << 1 | 1 << 63], "<u8"))
            for w in dirty:
                out.append(np.array([0, w], "<u8"))
        else:
            raise ValueError(f"no encoding {kind}")
    return kind, b"".join(x.astype("<u8").tobytes() for x in out)


def decode(kind: str, payload: bytes, n_words: int) -> np.ndarray:
    if kind == "positions":
        return from_bits(np.frombuffer(payload, "<u4"), n_words)
    if kind == "runs":
        pairs = np.frombuffer(payload, "<u4").reshape(-1, 2)
        d = np.zeros(n_words * 64 + 1, np.int8)
        d[pairs[:, 0]] += 1
        d[pairs[:, 1] + 1] -= 1
        return np.packbits(np.cumsum(d[:-1]).astype(np.uint8), bitorder="little").view("<u8")
    raw, out, at, to = np.frombuffer(payload, "<u8"), np.zeros(n_words, np.uint64), 0, 0
    if kind == "plain":
        out[: len(raw)] = raw
        return out
    while at < len(raw):
        m = int(raw[at])
        fill, dirty = (m >> 1 & FILL_MAX, m >> 33) if kind == "rle" else (m >> 1 & FILL_MAX, 0) if m >> 63 else (0, 1)
        if m & 1:
            out[to : to + fill] = ~np.uint64(0)
        to += fill
        out[to : to + dirty] = raw[at + 1 : at + 1 + dirty]
        at, to = at + 1 + dirty, to + dirty
    return out


class Stretches:
    """Where the fills and dirty stretches of an "rle" payload are: markers are read, dirty words are skipped."""

    def __init__(self, payload: bytes):
        self.raw = np.frombuffer(payload, "<u8")
        marks, at = [], 0
        while at < len(self.raw):
            m = int(self.raw[at])
            marks.append((m & 1, m >> 1 & FILL_MAX, m >> 33, at + 1))
            at += 1 + (m >> 33)
        table = np.array(marks, np.int64).reshape(-1, 4)
        self.bit, self.fill, self.dirty, self.first = table.T
        self.start = np.cumsum(self.fill + self.dirty) - self.fill - self.dirty

    def words(self, at: np.ndarray) -> np.ndarray:
        """The words at these places."""
        out = np.zeros(len(at), np.uint64)
        if not len(self.start) or not len(at):
            return out
        k = np.searchsorted(self.start, at, "right") - 1
        inside = at - self.start[k]
        filled = inside < self.fill[k]
        out[filled & (self.bit[k] == 1)] = ~np.uint64(0)
        dirty = ~filled & (inside < self.fill[k] + self.dirty[k])
        out[dirty] = self.raw[(self.first[k] + inside - self.fill[k])[dirty]]
        return out


def seek(payload: bytes, word: int) -> np.uint64:
    """One word of an rle payload: fills and dirty stretches before it are skipped unread."""
    return Stretches(payload).words(np.array([word]))[0]


class Coded:
    """A chunk's payload, decoded as far as a method asks for: words, positions, runs, or the words at some places."""

    def __init__(self, kind: str, payload: bytes, n_words: int, card: int):
        self.kind, self.payload, self.n_words, self.card = kind, payload, n_words, card
        self._words: np.ndarray | None = None

    def __len__(self) -> int:
        return self.n_words

    def words(self) -> np.ndarray:
        if self._words is None:
            self._words = decode(self.kind, self.payload, self.n_words)
        return self._words

    def positions(self) -> np.ndarray:
        if self.kind == "positions":
            return np.frombuffer(self.payload, "<u4").astype(np.int64)
        return bits(self.words())

    def runs(self) -> np.ndarray:
        if self.kind == "runs":
            return np.frombuffer(self.payload, "<u4").reshape(-1, 2).astype(np.int64)
        return runs_of(self.words())

    def at(self, places: np.ndarray) -> np.ndarray:
        if self.kind == "rle" and self._words is None:
            return Stretches(self.payload).words(places)
        if self.kind == "plain":
            raw = np.frombuffer(self.payload, "<u8")
            out = np.zeros(len(places), np.uint64)
            out[places < len(raw)] = raw[places[places < len(raw)]]
            return out
        return self.words()[places]


class Listed(Coded):
    """A chunk for the list style: sorted positions, decoded once; places are looked up by bisection."""

    def __init__(self, positions: np.ndarray, n_words: int):
        super().__init__("positions", b"", n_words, len(positions))
        self.values = positions

    def words(self) -> np.ndarray:
        return from_bits(self.values, self.n_words)

    def positions(self) -> np.ndarray:
        return self.values

    def has(self, values: np.ndarray) -> np.ndarray:
        k = np.searchsorted(self.values, values)
        return (k < len(self.values)) & (self.values[np.minimum(k, len(self.values) - 1)] == values) if len(self.values) else np.zeros(len(values), bool)


def sizes(words: np.ndarray) -> dict[str, int]:
    """Bytes of each encoding."""
    return {k: len(encode(words, k)[1]) for k in KINDS}


def choose(words: np.ndarray) -> str:
    """The smallest; of equals the first."""
    found = sizes(words)
    return min(KINDS, key=lambda k: (found[k], KINDS.index(k)))
