"""The counting methods on one chunk: vectors of 64-bit words in, a vector out.

A kernel gets its inputs in order, an int weight for each, a truth vector over 0 to the sum of weights, and T if the
function is a threshold (else None). An input is a vector of words, a Coded payload, or, in list style, a Listed one. Methods on positions
decode to them; those that only test some places of an input read no more of it; the others work on words.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Callable, Sequence

import numpy as np

from . import circuits
from .codec import Coded, Listed, bits, from_bits, runs_of

ONES = ~np.uint64(0)


def _replicated(inputs: Sequence[np.ndarray], weights: Sequence[int]) -> list[np.ndarray]:
    return [x for x, w in zip(inputs, weights) for _ in range(w)]


def _words(x) -> np.ndarray:
    return x.words() if isinstance(x, Coded) else x


def _positions(x) -> np.ndarray:
    return x.positions() if isinstance(x, Coded) else bits(x)


def _card(x) -> int:
    return x.card if isinstance(x, Coded) else int(np.bitwise_count(x).sum())


def _has(x, values: np.ndarray) -> np.ndarray:
    """Which of these positions are ones."""
    if isinstance(x, Listed):
        return x.has(values)
    words = x.at(values >> 6) if isinstance(x, Coded) else x[values >> 6]
    return (words >> (values & 63).astype(np.uint64) & np.uint64(1)).astype(bool)


def _lists(inputs, weights) -> list[np.ndarray]:
    return [p for x, w in zip(inputs, weights) for p in [_positions(x)] * w]


def _from_counts(values: np.ndarray, counts: np.ndarray, truth: np.ndarray, n_words: int) -> np.ndarray:
    """Positions not among values have count 0."""
    if not truth[0]:
        return from_bits(values[truth[counts]], n_words)
    return ~from_bits(values[~truth[counts]], n_words)


WIDTHS = {"byte": np.uint8, "short": np.uint16, "int": np.uint32}


def counter_array(inputs, weights, truth, t, width: str = "auto", saturate: bool = False, compare: str = "final"):
    """A counter for each position. saturate stops at T; compare on_increment sets a position's result once its counter is at T.

    width: byte, short, int, or auto, the least that holds what is counted: the sum of weights, or T if it saturates. A smaller one is an error.
    """
    n, n_words = len(truth) - 1, len(inputs[0])
    saturate = saturate and t is not None
    top = max(t, 0) if saturate else n
    kind = WIDTHS[width] if width != "auto" else next(k for k in (*WIDTHS.values(), np.uint64) if top <= np.iinfo(k).max)
    if top > np.iinfo(kind).max:
        raise ValueError(f"counters of width {width} don't hold {top}")
    counts, reached = np.zeros(n_words * 64, kind), np.zeros(n_words * 64, bool)
    for x, w in zip(inputs, weights):
        hit = np.unpackbits(_words(x).astype("<u8", copy=False).view(np.uint8), bitorder="little")
        if saturate:  # clamped before it is added, so that nothing passes T
            step = min(w, top)
            counts = np.where(hit, np.minimum(counts, kind(top - step)) + kind(step), counts)
        else:
            counts += hit.astype(kind) * kind(w)
        if compare == "on_increment" and t is not None:
            reached |= counts >= t
    out = reached if compare == "on_increment" and t is not None else counts >= top if saturate else truth[counts]
    return np.packbits(out, bitorder="little").view("<u8")


def sort_count(inputs, weights, truth, t):
    every = np.sort(np.concatenate(_lists(inputs, weights)))
    values, counts = np.unique(every, return_counts=True)
    return _from_counts(values, counts, truth, len(inputs[0]))


def pair_counts(inputs, weights, truth, t, prune: str = "none"):
    """One input after the other, smallest first, into values and counts; with T, what can't reach it goes after or inside the merge."""
    lists = sorted(_lists(inputs, weights), key=len)
    values, counts = lists[0], np.ones(len(lists[0]), np.int64)
    for i, more in enumerate(lists[1:], 2):
        left = len(lists) - i
        need = t - left if t is not None and prune != "none" else 0
        if prune == "inside" and need > 1:  # a first occurrence now is hopeless: no new values
            counts = counts + np.isin(values, more, assume_unique=True)
        else:
            union = np.union1d(values, more)
            total = np.zeros(len(union), np.int64)
            total[np.searchsorted(union, values)] += counts
            total[np.searchsorted(union, more)] += 1
            values, counts = union, total
        if need > 0:
            keep = counts >= need
            values, counts = values[keep], counts[keep]
    if t is not None and prune != "none":
        return from_bits(values[counts >= t], len(inputs[0])) if t > 0 else np.full(len(inputs[0]), ONES)
    return _from_counts(values, counts, truth, len(inputs[0]))


def heap_merge(inputs, weights, truth, t):
    values, counts, last = [], [], -1
    for p in heapq.merge(*[x.tolist() for x in _lists(inputs, weights)]):
        if p == last:
            counts[-1] += 1
        else:
            values.append(p)
            counts.append(1)
            last = p
    return _from_counts(np.array(values, np.int64), np.array(counts, np.int64), truth, len(inputs[0]))


def _skip(lists: list[np.ndarray], t: int) -> tuple[np.ndarray, np.ndarray]:
    """Values in at least t lists, and their counts: where the top has too few copies, t - 1 items leave the heap and jump to the next top."""
    at, heap = [0] * len(lists), [(int(x[0]), k) for k, x in enumerate(lists) if len(x)]
    heapq.heapify(heap)
    values, counts = [], []
    while len(heap) >= t:
        top, popped = heap[0][0], []
        while heap and heap[0][0] == top:
            popped.append(heapq.heappop(heap)[1])
        if len(popped) >= t:
            values.append(top)
            counts.append(len(popped))
            goal = top + 1
        else:
            while heap and len(popped) < t - 1:
                popped.append(heapq.heappop(heap)[1])
            if not heap:
                break
            goal = heap[0][0]
        for k in popped:
            at[k] = _gallop(lists[k], goal, at[k])
            if at[k] < len(lists[k]):
                heapq.heappush(heap, (int(lists[k][at[k]]), k))
    return np.array(values, np.int64), np.array(counts, np.int64)


def _gallop(x: np.ndarray, goal: int, low: int) -> int:
    """First place from low on that is not below goal: doubling steps, then bisection."""
    step, high = 1, low
    while high < len(x) and x[high] < goal:
        low, high, step = high, high + step, step * 2
    return low + int(np.searchsorted(x[low : min(high, len(x)) + 1], goal))


def heap_skip(inputs, weights, truth, t):
    if t is None:
        raise ValueError("heap_skip takes thresholds only")
    values, _ = _skip(_lists(inputs, weights), t)
    return from_bits(values, len(inputs[0]))


def _probe(values, counts, large: list, t: int) -> np.ndarray:
    """Candidates with counts so far; the large inputs are tested at the candidates, which thin out."""
    for k, x in enumerate(large):
        if len(values):
            counts = counts + _has(x, values)
        keep = counts >= t - (len(large) - 1 - k)
        values, counts = values[keep], counts[keep]
    return values


def set_aside_probe(inputs, weights, truth, t):
    """The t - 1 largest inputs only confirm candidates from the others."""
    if t is None:
        raise ValueError("set_aside_probe takes thresholds only")
    order = sorted(_replicated(inputs, weights), key=_card)
    small, large = order[: len(order) - t + 1], order[len(order) - t + 1 :]
    values, counts = np.unique(np.concatenate([_positions(x) for x in small]), return_counts=True)
    return from_bits(_probe(values, counts, large, t), len(inputs[0]))


def set_aside_size(t: int, longest: int, mu: float) -> int:
    """How many inputs the tuned method sets aside."""
    return max(1, min(t - 1, int(t / (mu * math.log2(max(longest, 2)) + 1))))


def tuned_set_aside_skip(inputs, weights, truth, t, mu: float = 0.02, aside: int | None = None):
    """aside inputs, the largest, are set aside; heap_skip finds what the rest hold t - aside times."""
    if t is None:
        raise ValueError("tuned_set_aside_skip takes thresholds only")
    order = sorted(_replicated(inputs, weights), key=_card)
    if t < 2:
        return heap_skip(order, [1] * len(order), truth, t)
    n = aside if aside is not None else set_aside_size(t, _card(order[-1]), mu)
    values, counts = _skip([_positions(x) for x in order[: len(order) - n]], t - n)
    return from_bits(_probe(values, counts, order[len(order) - n :], t), len(inputs[0]))


MUS = (0.005, 0.02, 0.05, 0.1)


def run_merge(inputs, weights, truth, t, dirty_policy: str = "adaptive"):
    """Clean words are decided by counts of one and mixed inputs; of the rest, mixed words by the policy, or runs by a sweep."""
    if dirty_policy == "sweep" or t is None:
        at, step = _changes(inputs, weights)
        order = np.argsort(at, kind="stable")
        at, count = at[order], np.cumsum(step[order])
        return _segments(at, truth[np.append(0, count)], len(inputs[0]))
    stack, w = np.stack([_words(x) for x in inputs]), np.array(weights)[:, None]
    clean, mixed = ((stack == ONES) * w).sum(0), (((stack != 0) & (stack != ONES)) * w).sum(0)
    need = t - clean
    out = np.where(need <= 0, ONES, np.uint64(0))
    for at in np.flatnonzero((need > 0) & (need <= mixed)):
        words, own = stack[:, at], (stack[:, at] != 0) & (stack[:, at] != ONES)
        out[at] = _dirty_word(words[own], w[own, 0], int(need[at]), dirty_policy)
    return out


def _runs(x) -> np.ndarray:
    return x.runs() if isinstance(x, Coded) else runs_of(x)


def _changes(inputs, weights) -> tuple[np.ndarray, np.ndarray]:
    """Where runs begin and end, and what the count changes by there."""
    runs = [_runs(x) for x in inputs]
    at = [np.concatenate([r[:, 0], r[:, 1] + 1]) for r in runs]
    return np.concatenate(at), np.concatenate([np.repeat([w, -w], len(r)) for r, w in zip(runs, weights)])


def _segments(at: np.ndarray, value: np.ndarray, n_words: int) -> np.ndarray:
    """Words of a function that is value[0] before the first change, and value[k + 1] from the k-th on."""
    steps = np.zeros(n_words * 64 + 1, np.int8)
    last = np.append(at[1:] != at[:-1], True) if len(at) else np.zeros(0, bool)
    at, value = at[last], np.append(value[:1], value[1:][last]).astype(np.int8)
    steps[0] += value[0]
    np.add.at(steps, at, np.diff(value))
    return np.packbits(np.cumsum(steps[:-1], dtype=np.int8).view(np.uint8), bitorder="little").view("<u8")


def run_function(inputs, weights, truth, t, fn: Callable[[np.ndarray], np.ndarray]):
    """Any Boolean function of the inputs: fn gets their bits (a row for each input, a column for each stretch without changes) and gives a bit for each column."""
    runs = [_runs(x) for x in inputs]
    at = np.unique(np.concatenate([np.zeros(1, np.int64), *[r.ravel() + np.tile([0, 1], len(r)) for r in runs]]))
    bits_at = np.zeros((len(inputs), len(at)), bool)
    for row, r in zip(bits_at, runs):
        row[:] = (np.searchsorted(r[:, 0], at, "right") - np.searchsorted(r[:, 1] + 1, at, "right")) > 0
    value = np.asarray(fn(bits_at), bool)
    return _segments(at, np.append(False, value), len(inputs[0]))


def _dirty_word(words: np.ndarray, weights: np.ndarray, need: int, policy: str) -> np.uint64:
    n = int(weights.sum())
    if policy == "adaptive":
        if need == 1:
            return np.bitwise_or.reduce(words)
        if need == n:
            return np.bitwise_and.reduce(words)
        ones = int((np.bitwise_count(words) * weights).sum())
        policy = "counters" if need >= 128 or 2 * ones < n * need else "loop"
    if policy == "loop":
        return recurrence_loop([words[i : i + 1] for i in range(len(words))], weights.tolist(), None, need)[0]
    table = np.unpackbits(words.astype("<u8").view(np.uint8).reshape(len(words), 8), axis=1, bitorder="little")
    return np.packbits((table * weights[:, None]).sum(0) >= need, bitorder="little").view("<u8")[0]


def recurrence_loop(inputs, weights, truth, t, all_t: bool = False):
    """Working vectors c[j]: at least j so far. Those that can't matter any more are left alone."""
    if t is None:
        t = len(truth) - 1
        c = recurrence_loop(inputs, weights, truth, t, all_t=True)
        out = np.zeros(len(inputs[0]), np.uint64)
        at_least = [np.full(len(out), ONES), *c, np.zeros(len(out), np.uint64)]
        for w in np.flatnonzero(truth):
            out |= at_least[w] & ~at_least[w + 1]
        return out
    every = _replicated([_words(x) for x in inputs], weights)
    c = [np.zeros(len(inputs[0]), np.uint64) for _ in range(t)]
    for i, x in enumerate(every):
        low = 0 if all_t else max(0, t - (len(every) - i))
        for j in range(min(t - 1, i), max(low, 1) - 1, -1):
            c[j] |= c[j - 1] & x
        if low == 0:
            c[0] |= x
    return c if all_t else c[t - 1]


def carry_save(inputs, weights, truth, t, compare: str = "sign"):
    """A counter of redundant digits, two vectors each; a digit is passed on at a fixed schedule, half as often as the one below."""
    every = _replicated([_words(x) for x in inputs], weights)
    zero = np.zeros(len(inputs[0]), np.uint64)
    digits = _digits(every, zero)
    if t is None or compare == "constant":
        return _digits_to_truth(digits, truth, t)
    borrow = zero
    for p, digit in enumerate(digits):
        borrow = borrow | ~digit if t >> p & 1 else borrow & ~digit
    return ~borrow if t < 1 << len(digits) else zero


def _digits(every: list, zero) -> list:
    """Binary digits of the counts, low one first."""
    size, time, rest = len(every).bit_length(), 0, every
    first, second = [zero] * (size + 1), [zero] * (size + 1)
    if len(every) >= 2:
        first[0], second[0], time, rest = every[0], every[1], 1, every[2:]
    for carry in rest:
        time += 1
        depth = (time & -time).bit_length() - 1
        for p in range(depth):
            differ = first[p] ^ second[p]
            first[p], second[p], carry = zero, differ ^ carry, first[p] & second[p] | carry & differ
        first[depth] = carry
    digits, carry = [], zero
    for p in range(size):
        differ = first[p] ^ second[p]
        digits.append(differ ^ carry)
        carry = first[p] & second[p] | carry & differ
    return digits


def _digits_to_truth(digits: list[np.ndarray], truth: np.ndarray, t: int | None) -> np.ndarray:
    if t is not None:
        dag = circuits.Dag(len(digits))
        dag.outputs = [circuits.at_least_constant(dag, range(len(digits)), t)]
        return circuits.interpret(circuits.bytecode(circuits.simplify(dag)), digits)
    out = np.zeros(len(digits[0]), np.uint64)
    for w in np.flatnonzero(truth):
        term = np.full(len(out), ONES)
        for p, d in enumerate(digits):
            term &= d if w >> p & 1 else ~d
        out |= term
    return out


def by_circuit(code) -> Callable:
    return lambda inputs, weights, truth, t: circuits.interpret(code, _replicated([_words(x) for x in inputs], weights))


def by_simulation(dag: circuits.Dag) -> Callable:
    return lambda inputs, weights, truth, t: circuits.simulate(dag, _replicated([_words(x) for x in inputs], weights))


class Tally:
    """A word vector that is only counted: the bitmap operations done with it."""

    def __init__(self, total: list[int]):
        self.total = total

    def _did(self, _=None) -> Tally:
        self.total[0] += 1
        return self

    __and__ = __or__ = __xor__ = __rand__ = __ror__ = __rxor__ = _did


def carry_save_count(n: int) -> int:
    """Bitmap operations of the carry-save method over n inputs, without the comparison."""
    total = [0]
    _digits([Tally(total) for _ in range(n)], Tally(total))
    return total[0]


KERNELS: dict[str, Callable] = {
    f.__name__: f
    for f in (counter_array, sort_count, pair_counts, heap_merge, heap_skip, set_aside_probe, tuned_set_aside_skip, run_merge, recurrence_loop, carry_save)
}
THRESHOLD_ONLY = frozenset(("heap_skip", "set_aside_probe", "tuned_set_aside_skip"))
#: Methods on sorted positions: those that the list style is for.
LISTS = frozenset(("sort_count", "pair_counts", "heap_merge", "heap_skip", "set_aside_probe", "tuned_set_aside_skip"))
