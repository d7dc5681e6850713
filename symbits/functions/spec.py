"""Symmetric functions of N bits: what they give for each count of ones."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass


@dataclass(frozen=True)
class Spec:
    """A symmetric function; truth(w, n) says what it gives for w ones among n inputs."""

    name: str
    truth: Callable[[int, int], bool]

    def vector(self, n: int) -> list[bool]:
        return [bool(self.truth(w, n)) for w in range(n + 1)]

    def intervals(self, n: int) -> list[tuple[int, int]]:
        """The maximal ranges of counts that are true: the function is their union, each a threshold without a higher one."""
        out: list[tuple[int, int]] = []
        for w, yes in enumerate(self.vector(n)):
            if yes and out and out[-1][1] == w - 1:
                out[-1] = (out[-1][0], w)
            elif yes:
                out.append((w, w))
        return out

    def as_threshold(self, n: int) -> int | None:
        """T if the function is "at least T" for n inputs (n + 1 if it is never true), else None."""
        found = self.intervals(n)
        if not found:
            return n + 1
        return found[0][0] if len(found) == 1 and found[0][1] == n else None


def threshold(t: int) -> Spec:
    return Spec(f"at_least_{t}", lambda w, n: w >= t)


def exactly(t: int) -> Spec:
    return Spec(f"exactly_{t}", lambda w, n: w == t)


def between(low: int, high: int) -> Spec:
    return Spec(f"between_{low}_{high}", lambda w, n: low <= w <= high)


def at_most(t: int) -> Spec:
    return Spec(f"at_most_{t}", lambda w, n: w <= t)


def majority() -> Spec:
    return Spec("majority", lambda w, n: 2 * w >= n)


def parity() -> Spec:
    return Spec("parity", lambda w, n: w % 2 == 1)


def wide_or() -> Spec:
    return threshold(1)


def wide_and() -> Spec:
    return Spec("all", lambda w, n: w == n)


def symmetric(vector: Sequence[bool]) -> Spec:
    """By its truth vector over 0 to N."""
    fixed = tuple(map(bool, vector))

    def truth(w: int, n: int) -> bool:
        if n + 1 != len(fixed):
            raise ValueError(f"the vector has {len(fixed)} values, {n + 1} are needed")
        return fixed[w]

    return Spec("vector", truth)


def normalize(spec: Spec, n: int) -> tuple[str, int | None]:
    """The cheapest equal form: all, none, or, and, threshold with its T, or vector."""
    t = spec.as_threshold(n)
    if t is None:
        return "vector", None
    if t <= 0:
        return "all", None
    if t > n:
        return "none", None
    return ("or", 1) if t == 1 else ("and", n) if t == n else ("threshold", t)


def complement_threshold(n: int, t: int) -> int:
    """At least t of n inputs is the negation of at least this many of the negated inputs."""
    return n - t + 1
