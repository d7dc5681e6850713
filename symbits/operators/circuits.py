"""Boolean circuits for symmetric functions: construction, simplification, reuse, and four ways to run them."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field
from itertools import combinations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.spec import Spec

ZERO, ONE = -1, -2


@dataclass
class Dag:
    """Gates in topological order. Nodes 0 to inputs - 1 are inputs; ZERO and ONE are constants. ANDNOT is a and not b."""

    inputs: int
    gates: list[tuple[str, int, int]] = field(default_factory=list)
    outputs: list[int] = field(default_factory=list)

    def gate(self, op: str, a: int, b: int = ZERO) -> int:
        """The node of a new gate, or of what it reduces to when an input is constant or both are one node."""
        if op in ("and", "or", "xor") and (a < 0 or a == b):
            a, b = b, a
        known = {
            "and": {ZERO: ZERO, ONE: a}, "or": {ZERO: a, ONE: ONE}, "xor": {ZERO: a}, "andnot": {ZERO: a, ONE: ZERO},
        }.get(op, {})
        if b in known and op != "not":
            return known[b]
        if op == "andnot" and a == ZERO:
            return ZERO
        if op == "andnot" and a == ONE:
            op, a, b = "not", b, ZERO
        if op == "xor" and b == ONE:
            op, b = "not", ZERO
        if op == "not" and a < 0:
            return ONE if a == ZERO else ZERO
        if op != "not" and a == b:
            return a if op in ("and", "or") else ZERO
        self.gates.append((op, a, b))
        return self.inputs + len(self.gates) - 1

    def half_adder(self, a: int, b: int) -> tuple[int, int]:
        return self.gate("xor", a, b), self.gate("and", a, b)

    def full_adder(self, a: int, b: int, c: int) -> tuple[int, int]:
        half, carry = self.half_adder(a, b)
        return self.gate("xor", half, c), self.gate("or", carry, self.gate("and", half, c))

    def wide(self, op: str, nodes: Sequence[int]) -> int:
        out = ZERO if op == "or" else ONE
        for x in nodes:
            out = x if out in (ZERO, ONE) and op == ("or" if out == ZERO else "and") else self.gate(op, out, x)
        return out


# -- weights


def sideways_bits(dag: Dag, nodes: Sequence[int]) -> list[int]:
    """Bits of the number of ones: at each power of two, adders in a chain through their sums; carries go one power up."""
    bits, level = [], list(nodes)
    while level:
        carries, total, rest = [], level[0], level[1:]
        while len(rest) >= 2:
            total, carry = dag.full_adder(total, rest[0], rest[1])
            carries.append(carry)
            rest = rest[2:]
        if rest:
            total, carry = dag.half_adder(total, rest[0])
            carries.append(carry)
        bits.append(total)
        level = carries
    return bits


def tree_bits(dag: Dag, nodes: Sequence[int]) -> list[int]:
    """Bits of the number of ones, by a balanced tree of ripple-carry adders over inputs padded with zeros."""
    size = 1 << max(0, (len(nodes) - 1).bit_length())
    numbers = [[x] for x in [*nodes, *[ZERO] * (size - len(nodes))]]
    while len(numbers) > 1:
        numbers = [ripple(dag, a, b) for a, b in zip(numbers[::2], numbers[1::2])]
    return numbers[0][: len(nodes).bit_length()]


def ripple(dag: Dag, a: Sequence[int], b: Sequence[int]) -> list[int]:
    out, carry = [], None
    for x, y in zip(a, b, strict=True):
        total, carry = dag.half_adder(x, y) if carry is None else dag.full_adder(x, y, carry)
        out.append(total)
    return [*out, carry]


# -- comparison of a number, low bit first, with T


def at_least_constant(dag: Dag, bits: Sequence[int], t: int) -> int:
    """For constant t: some bit is one where t - 1 has a zero, and so are all higher bits where t - 1 has ones."""
    if t <= 0:
        return ONE
    if (t - 1) >> len(bits):
        return ZERO
    terms, match = [], ONE
    for j in reversed(range(len(bits))):
        if (t - 1) >> j & 1:
            if ~(t - 1) & ((1 << j) - 1):  # a zero follows below
                match = bits[j] if match == ONE else dag.gate("and", match, bits[j])
        else:
            terms.append(bits[j] if match == ONE else dag.gate("and", match, bits[j]))
    return dag.wide("or", terms)


def at_least_sign(dag: Dag, bits: Sequence[int], t_bits: Sequence[int]) -> int:
    """For t given as nodes: no borrow when t is taken away. One circuit serves every t."""
    borrow = ZERO
    for b, t in zip(bits, t_bits, strict=True):
        differ = dag.gate("xor", b, t)
        borrow = dag.gate("or", dag.gate("andnot", t, b), dag.gate("andnot", borrow, differ))
    return dag.gate("not", borrow)


def greater(dag: Dag, a: Sequence[int], b: Sequence[int]) -> int:
    """a > b for two variable numbers, from the highest bit on."""
    found, same = ZERO, ONE
    for x, y in zip(reversed(a), reversed(b)):
        found = dag.gate("or", found, dag.gate("and", same, dag.gate("andnot", x, y)))
        same = dag.gate("andnot", same, dag.gate("xor", x, y))
    return found


# -- sorting


def merge_exchange(n: int) -> list[tuple[int, int]]:
    """Comparators, in order, of the odd-even merge sort for any n."""
    pairs: list[tuple[int, int]] = []
    top = 1 << max(0, (n - 1).bit_length() - 1)
    p = top
    while p and n > 1:
        q, r, d = top, 0, p
        while True:
            pairs += [(i, i + d) for i in range(n - d) if i & p == r]
            if q == p:
                break
            d, q, r = q - p, q >> 1, p
        p >>= 1
    return pairs


def sorted_wires(dag: Dag, nodes: Sequence[int]) -> list[int]:
    """Wires with the zeros first."""
    wires = list(nodes)
    for i, j in merge_exchange(len(wires)):
        wires[i], wires[j] = dag.gate("and", wires[i], wires[j]), dag.gate("or", wires[i], wires[j])
    return wires


# -- whole circuits

FAMILIES = ("adder_tree", "sideways_sum", "sort_network", "sum_of_products")
PRODUCT_LIMIT = 5000


def circuit(family: str, n: int, spec: Spec, limit: int = PRODUCT_LIMIT, comparator: str = "constant") -> Dag:
    """A simplified circuit of one output. comparator, of adders: with the constant T, or for T as a number by sign or by digits (variable)."""
    dag = Dag(n)
    nodes = list(range(n))
    if family == "sum_of_products":
        dag.outputs = [_products(dag, n, spec, limit)]
        return simplify(dag)
    if family == "sort_network":
        wires = sorted_wires(dag, nodes)
        reach = lambda t: ONE if t <= 0 else ZERO if t > n else wires[n - t]
    elif family in ("adder_tree", "sideways_sum"):
        bits = (tree_bits if family == "adder_tree" else sideways_bits)(dag, nodes)
        if spec.vector(n) == [w % 2 == 1 for w in range(n + 1)]:  # parity is the lowest bit
            dag.outputs = [bits[0]]
            return simplify(dag)
        reach = lambda t: compared(dag, bits, t, comparator)
    else:
        raise ValueError(f"no circuit family {family}")
    dag.outputs = [dag.wide("or", [dag.gate("andnot", reach(a), reach(b + 1) if b < n else ZERO) for a, b in spec.intervals(n)])]
    return simplify(dag)


def compared(dag: Dag, bits: Sequence[int], t: int, comparator: str = "constant") -> int:
    """The node that says whether the number is at least t."""
    if comparator == "constant":
        return at_least_constant(dag, bits, t)
    if t <= 0 or t >> len(bits):
        return ONE if t <= 0 else ZERO
    digits = lambda x: [ONE if x >> k & 1 else ZERO for k in range(len(bits))]
    if comparator == "sign":
        return at_least_sign(dag, bits, digits(t))
    if comparator == "variable":
        return greater(dag, bits, digits(t - 1))
    raise ValueError("comparator is constant, sign or variable")


def generic(family: str, n: int, comparator: str = "sign") -> Dag:
    """One circuit for every t of n inputs: t's binary digits are further inputs, low one first."""
    size = n.bit_length()
    dag = Dag(n + size)
    nodes, t = list(range(n)), list(range(n, n + size))
    if family == "sort_network":  # the wire that t selects
        wires = sorted_wires(dag, nodes)
        picked = []
        for k in range(1, n + 1):
            match = dag.wide("and", [t[p] if k >> p & 1 else dag.gate("not", t[p]) for p in range(size)])
            picked.append(dag.gate("and", match, wires[n - k]))
        dag.outputs = [dag.wide("or", picked)]
        return simplify(dag)
    bits = (tree_bits if family == "adder_tree" else sideways_bits)(dag, nodes)
    bits = [*bits, *[ZERO] * (size - len(bits))]
    dag.outputs = [at_least_sign(dag, bits, t) if comparator == "sign" else dag.gate("not", greater(dag, t, bits))]
    return simplify(dag)


def _products(dag: Dag, n: int, spec: Spec, limit: int) -> int:
    t = spec.as_threshold(n)
    vector = spec.vector(n)
    terms: list[int] = []
    from math import comb

    if (comb(n, t) if t is not None and 0 < t <= n else sum(comb(n, w) for w in range(n + 1) if vector[w])) > limit:
        raise ValueError(f"more than {limit} products")
    if t is not None:  # monotone: no negated inputs
        return ONE if t <= 0 else ZERO if t > n else dag.wide("or", [dag.wide("and", c) for c in combinations(range(n), t)])
    for w in range(n + 1):
        if vector[w]:
            for chosen in combinations(range(n), w):
                term = dag.wide("and", chosen)
                for x in set(range(n)) - set(chosen):
                    term = dag.gate("andnot", term, x)
                terms.append(term)
    return dag.wide("or", terms)


def simplify(dag: Dag, bound: dict[int, int] | None = None) -> Dag:
    """Gates that outputs need, after binding inputs to constants (bound) and reducing what follows from them."""
    out, where = Dag(dag.inputs), {i: i for i in range(dag.inputs)} | {ZERO: ZERO, ONE: ONE} | (bound or {})
    for k, (op, a, b) in enumerate(dag.gates):
        where[dag.inputs + k] = out.gate(op, where[a], where[b])
    needed, todo = set(), [where[x] for x in dag.outputs]
    while todo:
        x = todo.pop()
        if x >= out.inputs and x not in needed:
            needed.add(x)
            todo += out.gates[x - out.inputs][1:]
    final, moved = Dag(dag.inputs), {i: i for i in range(dag.inputs)} | {ZERO: ZERO, ONE: ONE}
    for k, (op, a, b) in enumerate(out.gates):
        if out.inputs + k in needed:
            final.gates.append((op, moved[a], moved[b]))
            moved[out.inputs + k] = final.inputs + len(final.gates) - 1
    final.outputs = [moved[where[x]] for x in dag.outputs]
    return final


def gate_count(family: str, n: int, t: int) -> int:
    from ..functions.spec import threshold

    return len(circuit(family, n, threshold(t)).gates)


def recurrence_count(n: int, t: int) -> int:
    """Operations of the recurrence over n inputs up to threshold t."""
    return 2 * n * t - n - t * t + t - 1


def serves(n: int, t: int, wanted_n: int, wanted_t: int) -> bool:
    """Whether a circuit for (n, t) gives (wanted_n, wanted_t) once the spare inputs are constants."""
    return wanted_n <= n and t - (n - wanted_n) <= wanted_t <= t


def padded(dag: Dag, t: int, wanted_n: int, wanted_t: int) -> Dag:
    """The circuit for (wanted_n, wanted_t) from one for (dag.inputs, t): spare inputs become ones, then zeros."""
    if not serves(dag.inputs, t, wanted_n, wanted_t):
        raise ValueError("this circuit can't serve that")
    ones = t - wanted_t
    bound = {wanted_n + k: ONE if k < ones else ZERO for k in range(dag.inputs - wanted_n)}
    return _narrowed(simplify(dag, bound), wanted_n)


def tabulate(policy: str, n_max: int, family: str = "sideways_sum") -> dict[tuple[int, int], Dag]:
    """Circuits worth keeping so that padded() serves every (n, t) up to n_max.

    diagonal: n_max - 2 circuits, those that need few spare inputs; powers: all t at powers of two; generic: one
    circuit at each power of two, with t as a further input (keyed by t = 0).
    """
    from ..functions.spec import threshold

    powers = [1 << k for k in range(1, n_max.bit_length() + 1) if 1 << (k - 1) < n_max]
    if policy == "diagonal":
        n = 2 * n_max
        return {(n_max + t, t): circuit(family, min(n, n_max + t), threshold(t)) for t in range(2, n_max)}
    if policy == "powers":
        return {(n, t): circuit(family, n, threshold(t)) for n in powers for t in range(1, n + 1)}
    if policy != "generic":
        raise ValueError("policy is diagonal, powers or generic")
    return {(n, 0): generic(family, n) for n in powers}


def circuit_for(table: dict[tuple[int, int], Dag], n: int, t: int) -> Dag:
    """From a table of tabulate(): the smallest circuit that serves, with constants for spare inputs and, where it takes any t, for t."""
    fits = [(kn, kt) for kn, kt in table if kt and serves(kn, kt, n, t) or not kt and kn >= n]
    if not fits:
        raise KeyError((n, t))
    key = min(fits)
    if key[1]:
        return padded(table[key], key[1], n, t)
    dag, size = table[key], key[0].bit_length()
    spare = key[0] - n
    bound = {n + k: ZERO for k in range(spare)} | {key[0] + p: ONE if t >> p & 1 else ZERO for p in range(size)}
    return _narrowed(simplify(dag, bound), n)


def _narrowed(dag: Dag, n: int) -> Dag:
    """The same circuit with its first n inputs only: it reads no others."""
    move = lambda x: x if x < n else x - (dag.inputs - n)
    return Dag(n, [(op, move(a), move(b)) for op, a, b in dag.gates], [move(x) for x in dag.outputs])


TABLE = "n int, t int, inputs int, family string, gate int, op string, a int, b int, level int"


def table_rows(table: dict[tuple[int, int], Dag], family: str) -> list[tuple]:
    """Rows (TABLE) of stored circuits: the gates in order, then the output."""
    rows = []
    for (n, t), dag in table.items():
        level = dict.fromkeys(range(-2, dag.inputs), 0)
        for k, (op, a, b) in enumerate(dag.gates):
            level[dag.inputs + k] = 1 + max(level[a], level[b])
            rows.append((n, t, dag.inputs, family, k, op, a, b, level[dag.inputs + k]))
        rows.append((n, t, dag.inputs, family, len(dag.gates), "out", dag.outputs[0], ZERO, level[dag.outputs[0]]))
    return rows


def from_rows(rows: Sequence[tuple]) -> dict[tuple[int, int], Dag]:
    """The circuits that table_rows() gave, by (n, t); an output that is no gate is kept as a row of op out."""
    table: dict[tuple[int, int], Dag] = {}
    for n, t, inputs, _, _, op, a, b, _ in sorted(rows, key=lambda r: (r[0], r[1], r[4])):
        dag = table.setdefault((n, t), Dag(inputs))
        if op == "out":
            dag.outputs = [a]
        else:
            dag.gates.append((op, a, b))
    return table


# -- running


def last_uses(dag: Dag) -> dict[int, int]:
    """For each node the gate that uses it last; outputs are never free."""
    last: dict[int, int] = {}
    for k, (_, a, b) in enumerate(dag.gates):
        last[a] = last[b] = k
    for x in dag.outputs:
        last[x] = len(dag.gates)
    return last


def max_live(dag: Dag) -> int:
    """The most intermediate results that are held at once."""
    last, live, most = last_uses(dag), set(), 0
    for k, (_, a, b) in enumerate(dag.gates):
        live.add(dag.inputs + k)
        most = max(most, len(live))
        live -= {x for x in (a, b) if last.get(x) == k}
    return most


def bytecode(dag: Dag) -> list[tuple[str, int, int, int]]:
    """op, register, a, b: registers are used again once their value is read for the last time. Operands below zero are constants."""
    last, register, free, code, top = last_uses(dag), {i: i for i in range(dag.inputs)}, [], [], dag.inputs
    for k, (op, a, b) in enumerate(dag.gates):
        ra, rb = register.get(a, a), register.get(b, b)
        for x in {a, b}:
            if x >= dag.inputs and last[x] == k:
                free.append(register[x])
        if free:
            own = free.pop()
        else:
            own, top = top, top + 1
        register[dag.inputs + k] = own
        code.append((op, own, ra, rb))
    x = dag.outputs[0]
    code.append(("out", 0, register.get(x, x), ZERO))
    return code


def interpret(code: list[tuple[str, int, int, int]], inputs: list[np.ndarray]) -> np.ndarray:
    """Run a byte code over vectors of words."""
    registers = dict(enumerate(inputs))
    words = len(inputs[0]) if inputs else 0
    registers[ZERO], registers[ONE] = np.zeros(words, np.uint64), np.full(words, ~np.uint64(0))
    for op, to, a, b in code:
        x = registers[a]
        if op == "out":
            return x
        y = registers[b]
        registers[to] = x & y if op == "and" else x | y if op == "or" else x ^ y if op == "xor" else x & ~y if op == "andnot" else ~x
    return np.zeros(words, np.uint64)


def simulate(dag: Dag, inputs: list[np.ndarray]) -> np.ndarray:
    """The gates one after the other over whole vectors; a vector is let go once its last reader is done."""
    last, words = last_uses(dag), len(inputs[0]) if inputs else 0
    held = dict(enumerate(inputs)) | {ZERO: np.zeros(words, np.uint64), ONE: np.full(words, ~np.uint64(0))}
    for k, (op, a, b) in enumerate(dag.gates):
        x, y = held[a], held[b]
        held[dag.inputs + k] = ~x if op == "not" else {"and": np.bitwise_and, "or": np.bitwise_or, "xor": np.bitwise_xor, "andnot": lambda p, q: p & ~q}[op](x, y)
        for done in {a, b}:
            if done >= 0 and last[done] == k:
                del held[done]
    return held[dag.outputs[0]]


def _expression(op: str, a: Column, b: Column) -> Column:
    return {"and": lambda: a.bitwiseAND(b), "or": lambda: a.bitwiseOR(b), "xor": lambda: a.bitwiseXOR(b), "andnot": lambda: a.bitwiseAND(F.bitwise_not(b)), "not": lambda: F.bitwise_not(a)}[op]()


def _operand(x: int, name) -> Column:
    return F.lit(0 if x == ZERO else -1).cast("long") if x < 0 else name(x)


def staged(words: DataFrame, dag: Dag, keys: Sequence[str]) -> DataFrame:
    """Columns x0, x1, ... of words to keys and b, the output: a select for each level, without what is read no more.

    Each value is computed once and read as a column, so that shared gates aren't unfolded and the plan grows with the gates.
    """
    level = dict.fromkeys(range(-2, dag.inputs), 0)
    for k, (_, a, b) in enumerate(dag.gates):
        level[dag.inputs + k] = 1 + max(level[a], level[b])
    until = {}
    for k, (_, a, b) in enumerate(dag.gates):
        for x in (a, b):
            until[x] = max(until.get(x, 0), level[dag.inputs + k])
    for x in dag.outputs:
        until[x] = 1 << 30
    name = lambda x: F.col(f"x{x}")
    alive = list(range(dag.inputs))
    for depth in range(1, max(level.values()) + 1):
        new = [x for x in range(dag.inputs, dag.inputs + len(dag.gates)) if level[x] == depth]
        kept = [x for x in alive if until.get(x, 0) > depth]
        made = [_expression(dag.gates[x - dag.inputs][0], _operand(dag.gates[x - dag.inputs][1], name), _operand(dag.gates[x - dag.inputs][2], name)).alias(f"x{x}") for x in new]
        words = words.select(*keys, *[name(x) for x in kept], *made)
        alive = kept + new
    return words.select(*keys, _operand(dag.outputs[0], name).alias("b"))


def tree(dag: Dag, limit: int = 2000) -> Column:
    """The output as one expression over x0, x1, ...: shared gates unfold, so only small circuits are taken."""
    size: dict[int, int] = {}
    made: dict[int, Column] = {}
    get = lambda x: made[x] if x in made else _operand(x, lambda i: F.col(f"x{i}"))
    for k, (op, a, b) in enumerate(dag.gates):
        size[dag.inputs + k] = 1 + size.get(a, 0) + size.get(b, 0)
        if size[dag.inputs + k] > limit:
            raise ValueError(f"unfolded, the circuit has over {limit} gates")
        made[dag.inputs + k] = _expression(op, get(a), get(b))
    return get(dag.outputs[0])
