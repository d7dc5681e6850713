import numpy as np
import pytest

from symbits.functions.spec import exactly, parity, threshold
from symbits.operators import codec
from symbits.operators.kernels import KERNELS, THRESHOLD_ONLY


def _inputs(rng, n, words):
    x = rng.integers(0, 2**63, (n, words), dtype=np.uint64) * np.uint64(2) + rng.integers(0, 2, (n, words)).astype(np.uint64)
    x[0] = np.where(rng.random(words) < 0.5, np.uint64(0), ~np.uint64(0))
    return list(x)


@pytest.mark.parametrize("name", KERNELS)
def test_kernels_count(name):
    rng = np.random.default_rng(3)
    for _ in range(20):
        n = int(rng.integers(2, 9))
        inputs, weights = _inputs(rng, n, 3), [int(w) for w in rng.integers(1, 3, n)]
        counts = sum(np.unpackbits(x.view(np.uint8), bitorder="little").astype(int) * w for x, w in zip(inputs, weights))
        total = sum(weights)
        for s in (threshold(1), threshold(total), threshold(max(1, total // 2)), exactly(2), parity()):
            t = s.as_threshold(total)
            if t is None and name in THRESHOLD_ONLY:
                continue
            truth = np.array(s.vector(total))
            assert np.array_equal(KERNELS[name](inputs, weights, truth, t), np.packbits(truth[counts], bitorder="little").view("<u8"))


def test_codec_and_seek():
    rng = np.random.default_rng(5)
    for x in [np.zeros(4, np.uint64), np.full(4, ~np.uint64(0)), *_inputs(rng, 6, 4)]:
        for kind in codec.KINDS:
            for trim in (True, False):
                assert np.array_equal(codec.decode(kind, codec.encode(x, kind, trim)[1], 4), x)
        assert all(codec.seek(codec.encode(x, "rle")[1], i) == x[i] for i in range(4))
    assert "{:08b} {:08b}".format(*codec.from_bits(np.array([1, 2, 7, 9]), 1).view(np.uint8)[:2]) == "10000110 00000010"


def _counted(inputs):
    return sum(np.unpackbits(x.view(np.uint8), bitorder="little").astype(int) for x in inputs)


@pytest.mark.parametrize("n,t", [(255, 10), (256, 10), (256, 256), (300, 255), (300, 256), (512, 400), (70_000, 66_000)])
def test_counters_hold_what_they_count(n, t):
    rng = np.random.default_rng(n)
    distinct = _inputs(rng, 8, 1) + [np.full(1, ~np.uint64(0))]
    inputs = [distinct[k % 9] for k in range(n)] if n < 70_000 else distinct
    weights = [1] * n if n < 70_000 else [n // 9] * 8 + [n - 8 * (n // 9)]
    counts = sum(np.unpackbits(x.view(np.uint8), bitorder="little").astype(int) * w for x, w in zip(inputs, weights))
    truth = np.arange(n + 1) >= t
    expected = np.packbits(counts >= t, bitorder="little").view("<u8")
    counter = KERNELS["counter_array"]
    for options in ({}, {"saturate": True}, {"compare": "on_increment"}, {"saturate": True, "compare": "on_increment"}):
        assert np.array_equal(counter(inputs, weights, truth, t, **options), expected), options
    for width, top in (("byte", 255), ("short", 65535)):
        if n > top:
            with pytest.raises(ValueError, match="don't hold"):
                counter(inputs, weights, truth, t, width=width)
        if t <= top:
            assert np.array_equal(counter(inputs, weights, truth, t, width=width, saturate=True), expected)


def test_operation_counts_and_simulation():
    from symbits.operators import circuits, kernels

    assert kernels.carry_save_count(64) < 6 * 64
    rng = np.random.default_rng(7)
    inputs = _inputs(rng, 11, 2)
    for family in ("adder_tree", "sideways_sum", "sort_network"):
        dag = circuits.circuit(family, 11, threshold(4))
        assert np.array_equal(circuits.simulate(dag, inputs), circuits.interpret(circuits.bytecode(dag), inputs))
        made = circuits.generic(family, 11)
        for t in (1, 4, 11):
            digits = [np.full(2, ~np.uint64(0) if t >> p & 1 else np.uint64(0)) for p in range(4)]
            assert np.array_equal(circuits.simulate(made, inputs + digits), np.packbits(_counted(inputs) >= t, bitorder="little").view("<u8")), (family, t)
        assert circuits.max_live(dag) <= len(dag.gates)
