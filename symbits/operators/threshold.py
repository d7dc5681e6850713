"""Symmetric functions of indexed bitmaps: one entry point, many methods.

kernel methods group an index's rows by chunk and count there (chunks are independent); relational ones count
by rid or sweep runs with joins, aggregations and windows; circuits run as staged selects or as byte code.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Sequence
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.spec import Spec, complement_threshold, normalize
from ..plans.criteria import Criterion, frame, merged, negate, total_weight
from . import circuits
from .codec import Coded, Listed, bits
from .index import DIRTY, FULL, Bitmap, Index, chunk_words, coalesced, rids_in, run_edges, universe, words_of
from .kernels import KERNELS, LISTS, THRESHOLD_ONLY, by_circuit, by_simulation, run_function

#: Kernels and circuits replicate inputs by weight up to this; more is for counters.
MAX_INPUTS = 512
#: Columns of aligned words at most; byte code takes more.
MAX_COLUMNS = 64


def selected(index: Index, criteria: Sequence[Criterion], *columns: str) -> DataFrame:
    """Index rows that criteria name, with ord, weight, negated."""
    crit = frame(index.df.sparkSession, criteria)
    # names of the criteria as literals reach the Parquet scan; the pairs are matched by the join
    attrs, values = sorted({c.attr for c in criteria}), sorted({c.value for c in criteria})
    near = index.df.where(F.col("attr").isin(attrs) & F.col("value").isin(values)) if len(values) <= MAX_INPUTS else index.df
    return near.join(F.broadcast(crit), ["attr", "value"]).select("ord", "weight", "negated", *columns)


def rids_of(index: Index, criteria: Sequence[Criterion], *more: str) -> DataFrame:
    """A row (rid, chunk, ord, weight, more) for each one of each criterion's bitmap; negated ones by their complement."""
    rows = selected(index, criteria, "chunk", *index.body, *more)
    words = words_of(rows, index, "ord", "weight", "negated")
    flags = {k: c.negated for k, c in enumerate(criteria)}
    if any(flags.values()):
        every = universe(index.df.sparkSession, index.rows, index.chunk_bits)
        negative = frame(index.df.sparkSession, criteria).where("negated").select("ord", "weight")
        full = every.join(F.broadcast(negative))
        inverted = full.join(words.where("negated").select("ord", "chunk", "w", "b"), ["ord", "chunk", "w"], "left").select("ord", "weight", "chunk", "w", F.col("m").bitwiseAND(F.bitwise_not(F.coalesce("b", F.lit(0).cast("long")))).alias("b")).where("b <> 0")
        words = words.where(~F.col("negated")).select("ord", "weight", "chunk", "w", "b").unionByName(inverted)
    return words.select(F.explode(rids_in(F.col("b"), index.chunk_bits)).alias("rid"), "chunk", "ord", "weight")


def _empty(index: Index) -> Bitmap:
    return Bitmap(index.df.sparkSession.createDataFrame([], "chunk long, w int, b long"), index.rows, index.chunk_bits)


def _every(index: Index) -> Bitmap:
    return Bitmap(universe(index.df.sparkSession, index.rows, index.chunk_bits).select("chunk", "w", F.col("m").alias("b")), index.rows, index.chunk_bits)


def placed_counts(index: Index, criteria: Sequence[Criterion]) -> DataFrame:
    """chunk, rid, n: the weight of the criteria that each row meets, where any. Rows of an index bucketed by chunk stay where they are."""
    return rids_of(index, criteria).groupBy("chunk", "rid").agg(F.sum("weight").cast("long").alias("n"))


def counts(index: Index, criteria: Sequence[Criterion]) -> DataFrame:
    """rid, n."""
    return placed_counts(index, criteria).select("rid", "n")


def evaluate(index: Index, criteria: Sequence[Criterion], spec: Spec, method: str = "auto", **options) -> Bitmap:
    """The rids whose weight of met criteria satisfies spec."""
    criteria = list(criteria)
    n = total_weight(criteria)
    form, t = normalize(spec, n)
    if form in ("all", "none"):
        return _every(index) if form == "all" else _empty(index)
    if method == "auto":
        from ..plans.planner import choose

        choice = choose(index, criteria, spec)
        method, options = choice.method, choice.options | options
        if choice.complement:  # at least t of dense inputs: not at least n - t + 1 of their sparse negations
            from ..functions.spec import threshold

            return ~evaluate(index, negate(criteria), threshold(complement_threshold(n, t)), method, **options)
    if form in ("or", "and") and method in ("wide", "auto"):
        return wide(index, criteria, form)
    if method in RELATIONAL:
        return RELATIONAL[method](index, criteria, spec, **options)
    if method in circuits.FAMILIES:
        return by_family(index, criteria, spec, method, **options)
    if method in KERNELS:
        return by_kernel(index, criteria, spec, method, options)
    raise ValueError(f"no method {method}")


def wide(index: Index, criteria: Sequence[Criterion], op: str) -> Bitmap:
    """OR or AND of all by one aggregation of words; for AND a word must be there once for each criterion."""
    own = merged(criteria)
    if any(c.negated for c in own):
        return by_kernel(index, own, Spec(op, (lambda w, n: w >= 1) if op == "or" else (lambda w, n: w == n)), "counter_array", {})
    words = words_of(selected(index, own, "chunk", *index.body), index, "ord")
    made = F.bit_or("b") if op == "or" else F.when(F.count("*") == len(own), F.bit_and("b")).otherwise(0)
    return Bitmap(words.groupBy("chunk", "w").agg(made.alias("b")).where("b <> 0"), index.rows, index.chunk_bits)


# -- kernels, one chunk at a time


@dataclass(frozen=True)
class Query:
    """A function of some criteria and the method that evaluates it; style list turns inputs into sorted positions first, and only methods on positions take it."""

    criteria: tuple[Criterion, ...]
    spec: Spec
    method: str = "counter_array"
    options: dict = field(default_factory=dict)
    style: str = "bitmap"

    def kernel(self) -> tuple[Callable, np.ndarray, int | None]:
        """What counts a chunk, the truth vector, and T if it is a threshold."""
        n = total_weight(self.criteria)
        truth, t = np.array(self.spec.vector(n)), self.spec.as_threshold(n)
        if self.method in circuits.FAMILIES:
            options = dict(self.options)
            backend = options.pop("backend", "bytecode")
            dag = circuits.circuit(self.method, n, self.spec, **options)
            return by_simulation(dag) if backend == "vertical" else by_circuit(circuits.bytecode(dag)), truth, t
        if self.method == "function":
            fn = self.options["fn"]
            return lambda inputs, weights, truth, t: run_function(inputs, weights, truth, t, fn), np.zeros(1, bool), None
        if self.method not in KERNELS:
            raise ValueError(f"no kernel {self.method}")
        if self.method in THRESHOLD_ONLY and t is None:
            raise ValueError(f"{self.method} takes thresholds only")
        if self.style not in ("bitmap", "list") or self.style == "list" and self.method not in LISTS:
            raise ValueError(f"{self.method} has no style {self.style}")
        own, options = KERNELS[self.method], self.options
        return lambda inputs, weights, truth, t: own(inputs, weights, truth, t, **options), truth, t

    def of_absent(self) -> bool:
        """Whether chunks without rows of the criteria may hold answers."""
        if self.method == "function":
            return bool(np.asarray(self.options["fn"](np.zeros((len(self.criteria), 1), bool))).any()) or any(c.negated for c in self.criteria)
        return bool(self.spec.vector(total_weight(self.criteria))[0]) or any(c.negated for c in self.criteria)


_ONES = ~np.uint64(0)


def by_chunk(index: Index, queries: Sequence[Query], give: str = "words") -> DataFrame:
    """All queries in one pass over the chunks: query, chunk, w, b (words); query, chunk, ones, ns (counts and nanoseconds).

    At most as many rows as there are distinct criteria meet in a chunk; what a task holds is bounded by both. Each is decoded once, as far as methods ask.
    """
    names = sorted({(c.attr, c.value) for q in queries for c in q.criteria})
    number = {name: k for k, name in enumerate(names)}
    plans = [(*q.kernel(), [c.weight for c in q.criteria], [(number[c.attr, c.value], c.negated) for c in q.criteria], q.style) for q in queries]
    chunk_bits, total, n_words, encoded, body = index.chunk_bits, index.rows, index.chunk_bits // 64, index.encoded, index.body

    def run(table: pa.Table) -> pa.Table:
        table = table.combine_chunks()
        chunk = table.column("chunk")[0].as_py()
        size = min(chunk_bits, total - chunk * chunk_bits)
        mask = np.zeros(n_words, np.uint64)
        mask[: size // 64] = _ONES
        if size % 64:
            mask[size // 64] = (1 << size % 64) - 1
        empty = np.zeros(n_words, np.uint64)
        held: dict[tuple[int, bool], object] = {}
        ords, kinds, cards = (table.column(c).to_pylist() for c in ("ord", "kind", "card"))
        if encoded:
            own = [k and Coded(k, p, n_words, card) for k, p, card in zip(table.column("encoding").to_pylist(), table.column("payload").to_pylist(), cards)]
        else:
            own = chunk_words(table.column("words").chunk(0), n_words) if table.num_rows else []
        for k, kind, x in zip(ords, kinds, own):
            if k is not None:
                held[k, False] = mask if kind == FULL else x

        def whole(x) -> np.ndarray:
            return x.words() if isinstance(x, Coded) else x

        def given(k: int, negated: bool, style: str):
            if (k, negated) not in held:
                held[k, negated] = ~whole(held.get((k, False), empty)) & mask if negated else empty
            x = held[k, negated]
            return Listed(x.positions() if isinstance(x, Coded) else bits(x), n_words) if style == "list" else x

        out: list[tuple[int, np.ndarray, int]] = []
        for number, (kernel, truth, t, weights, inputs, style) in enumerate(plans):
            began = time.perf_counter_ns()
            found = np.asarray(kernel([given(k, negated, style) for k, negated in inputs], weights, truth, t), np.uint64) & mask
            out.append((number, found, time.perf_counter_ns() - began))
        if give == "counts":
            rows = [(number, chunk, int(np.bitwise_count(x).sum()), ns) for number, x, ns in out]
            return pa.table([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int32(), pa.int64(), pa.int64(), pa.int64()))], ["query", "chunk", "ones", "ns"])
        at = [x.nonzero()[0] for _, x, _ in out]
        size = [len(i) for i in at]
        columns = [np.repeat([number for number, _, _ in out], size).astype(np.int32), np.full(sum(size), chunk, np.int64), np.concatenate(at).astype(np.int32), np.concatenate([x[i] for i, (_, x, _) in zip(at, out)]).view(np.int64)]
        return pa.table([pa.array(c) for c in columns], ["query", "chunk", "w", "b"])

    rows = selected(index, [Criterion(*name) for name in names], "chunk", *body).select("ord", "chunk", *body)
    if any(q.of_absent() for q in queries):
        blank = [F.lit(None).cast(rows.schema[c].dataType).alias(c) for c in body]
        rows = rows.unionByName(index.df.sparkSession.range(index.chunks).select(F.lit(None).cast("int").alias("ord"), F.col("id").alias("chunk"), *blank))
    return rows.groupBy("chunk").applyInArrow(run, "query int, chunk long, w int, b long" if give == "words" else "query int, chunk long, ones long, ns long")


def evaluate_many(index: Index, queries: Sequence[Query]) -> DataFrame:
    """query (its number), ones: how many rids satisfy each query, by one pass; a query without any has 0."""
    spark = index.df.sparkSession
    every = spark.range(len(queries)).select(F.col("id").cast("int").alias("query"))
    found = by_chunk(index, queries, "counts").groupBy("query").agg(F.sum("ones").alias("ones"))
    return every.join(found, "query", "left").select("query", F.coalesce("ones", F.lit(0)).alias("ones"))


def kernel_times(index: Index, queries: Sequence[Query]) -> DataFrame:
    """query, ones, ms: the time in the method itself, decoding included, summed over chunks."""
    found = by_chunk(index, queries, "counts")
    return found.groupBy("query").agg(F.sum("ones").alias("ones"), (F.sum("ns") / 1e6).alias("ms"))


def by_kernel(index: Index, criteria: Sequence[Criterion], spec: Spec, method: str, options: dict) -> Bitmap:
    options = dict(options)
    query = Query(tuple(criteria), spec, method, options, options.pop("style", "bitmap"))
    return Bitmap(by_chunk(index, [query]).select("chunk", "w", "b"), index.rows, index.chunk_bits)


def evaluate_function(index: Index, criteria: Sequence[Criterion], fn: Callable[[np.ndarray], np.ndarray]) -> Bitmap:
    """The rids where any Boolean function of the criteria holds: fn gets a row of bits for each criterion and gives a bit for each column."""
    return by_kernel(index, criteria, Spec("function", lambda w, n: False), "function", {"fn": fn})


# -- circuits


def aligned(index: Index, criteria: Sequence[Criterion]) -> DataFrame:
    """chunk, w, x0, x1, ...: the word of each input, replicated by weight, zero where it is absent; negated ones within the rids."""
    words = words_of(selected(index, criteria, "chunk", *index.body), index, "ord")
    out = words.groupBy("chunk", "w").agg(*[F.coalesce(F.max(F.when(F.col("ord") == k, F.col("b"))), F.lit(0).cast("long")).alias(f"y{k}") for k in range(len(criteria))])
    if any(c.negated for c in criteria):
        out = universe(index.df.sparkSession, index.rows, index.chunk_bits).join(out, ["chunk", "w"], "left")
    columns, at = [], 0
    for k, c in enumerate(criteria):
        word = F.coalesce(f"y{k}", F.lit(0).cast("long")) if any(x.negated for x in criteria) else F.col(f"y{k}")
        word = F.col("m").bitwiseAND(F.bitwise_not(word)) if c.negated else word
        for _ in range(c.weight):
            columns.append(word.alias(f"x{at}"))
            at += 1
    return out.select("chunk", "w", *columns)


def by_family(index: Index, criteria: Sequence[Criterion], spec: Spec, family: str, backend: str = "auto", **options) -> Bitmap:
    """backend: staged selects, tree (one expression, for small circuits), or, in the kernel, byte code or vertical simulation."""
    n = total_weight(criteria)
    if n > MAX_INPUTS and family != "sum_of_products":
        raise ValueError(f"circuits take at most {MAX_INPUTS} inputs; use counters or runs")
    if backend in ("auto", "bytecode", "vertical"):
        return by_kernel(index, criteria, spec, family, options | {"backend": "bytecode" if backend == "auto" else backend})
    if backend not in ("staged", "tree"):
        raise ValueError("backend is staged, tree, bytecode or vertical")
    if n > MAX_COLUMNS:
        raise ValueError(f"aligned words take at most {MAX_COLUMNS} inputs; use byte code")
    dag = circuits.circuit(family, n, spec, **options)
    if spec.vector(n)[0]:
        raise ValueError("rows that meet no criterion satisfy this function: use byte code")
    words = aligned(index, criteria)
    out = circuits.staged(words, dag, ["chunk", "w"]) if backend == "staged" else words.select("chunk", "w", circuits.tree(dag).alias("b"))
    return Bitmap(out.where("b <> 0"), index.rows, index.chunk_bits)


# -- relational methods


def _kept(found: DataFrame, n: Column, spec: Spec, total: int) -> DataFrame:
    """Rows whose count n satisfies spec."""
    condition = F.lit(False)
    for a, b in spec.intervals(total):
        condition = condition | n.between(a, b)
    return found.where(condition)


def _placed(rows: DataFrame, index: Index) -> Bitmap:
    """The bitmap of rows (chunk, rid)."""
    at = F.col("rid") - F.col("chunk") * index.chunk_bits
    words = rows.groupBy("chunk", F.floor(at / 64).cast("int").alias("w")).agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), (at % 64).cast("int"))).alias("b"))
    return Bitmap(words, index.rows, index.chunk_bits)


def _with_zeros(index: Index, hits: DataFrame, seen: DataFrame, spec: Spec, n: int) -> Bitmap:
    """Bitmap of hits (chunk, rid), and of the rids not seen at all if count 0 is true."""
    out = _placed(hits, index)
    if spec.vector(n)[0]:
        out = out | ~_placed(seen, index)
    return out


def counter_hash(index, criteria, spec) -> Bitmap:
    """Hash aggregation by rid: the plain relational plan, and the reference of all others."""
    n = total_weight(criteria)
    found = placed_counts(index, criteria)
    return _with_zeros(index, _kept(found, F.col("n"), spec, n), found, spec, n)


def sort_count_windows(index, criteria, spec) -> Bitmap:
    """Rids of a chunk sorted; a rid is met T times if the row T - 1 further on has it too. Thresholds only."""
    t = spec.as_threshold(total_weight(criteria))
    if t is None:
        raise ValueError("thresholds only")
    rows = rids_of(index, criteria).select("chunk", "rid", F.explode(F.sequence(F.lit(1), "weight")).alias("k"))
    w = Window.partitionBy("chunk").orderBy("rid")
    hits = rows.select("chunk", "rid", F.lead("rid", t - 1).over(w).alias("ahead"), F.lag("rid", 1).over(w).alias("back")).where((F.col("ahead") == F.col("rid")) & (F.col("back").isNull() | (F.col("back") != F.col("rid"))))
    return _placed(hits, index)


def pair_counts_joins(index, criteria, spec, prune: str = "none") -> Bitmap:
    """Accumulated (rid, n) joined with one input after the other, fewest rids first.

    prune after: rids that can't reach T any more leave after each join; inside: once a first occurrence is hopeless the full outer join is a left one.
    """
    own = merged(criteria)
    n, t = total_weight(own), spec.as_threshold(total_weight(own))
    if len(own) > 16:
        raise ValueError("a join for each input is for up to 16 inputs; use the kernel")
    if prune != "none" and t is None:
        raise ValueError("only thresholds can be pruned")
    cards = {r["ord"]: r["card"] for r in selected(index, own, "card").groupBy("ord").agg(F.sum("card").alias("card")).toLocalIterator()}
    size = lambda k: index.rows - cards.get(k, 0) if own[k].negated else cards.get(k, 0)
    order = sorted(range(len(own)), key=size)
    lists = [rids_of(index, [own[k]]).select("chunk", "rid", F.col("weight").cast("long").alias("m")) for k in order]
    acc, left = lists[0].withColumnRenamed("m", "n"), n - own[order[0]].weight
    for k, more in zip(order[1:], lists[1:]):
        left -= own[k].weight
        hopeless = prune == "inside" and t is not None and own[k].weight < t - left
        acc = acc.join(more, ["chunk", "rid"], "left" if hopeless else "full_outer").select("chunk", "rid", (F.coalesce("n", F.lit(0)) + F.coalesce("m", F.lit(0))).alias("n"))
        if prune != "none" and t - left > 0:
            acc = acc.where(F.col("n") >= t - left)
    return _with_zeros(index, _kept(acc, F.col("n"), spec, n), acc, spec, n)


def set_aside_joins(index, criteria, spec) -> Bitmap:
    """The largest inputs, T - 1 by weight, only confirm candidates of the others: of those inputs only chunks with candidates are read, and the candidates' bits tested in their words."""
    own = merged(criteria)
    n, t = total_weight(own), spec.as_threshold(total_weight(own))
    if t is None:
        raise ValueError("thresholds only")
    cards = {r["ord"]: r["card"] for r in selected(index, own, "card").groupBy("ord").agg(F.sum("card").alias("card")).toLocalIterator()}
    size = lambda k: index.rows - cards.get(k, 0) if own[k].negated else cards.get(k, 0)
    aside: list[int] = []
    for k in sorted(range(len(own)), key=size, reverse=True):
        if sum(own[j].weight for j in aside) + own[k].weight > t - 1:
            break
        aside.append(k)
    small, large = [c for k, c in enumerate(own) if k not in aside], [own[k] for k in aside]
    reach = sum(c.weight for c in large)
    candidates = placed_counts(index, small).where(F.col("n") >= t - reach)
    if not large:
        return _placed(candidates.where(F.col("n") >= t), index)
    place = F.col("rid") - F.col("chunk") * index.chunk_bits
    asked = candidates.select("chunk", "rid", "n", F.floor(place / 64).cast("int").alias("w"), (place % 64).cast("int").alias("bit"))
    rows = selected(index, large, "chunk", *index.body).join(asked.select("chunk").distinct(), "chunk", "left_semi")
    words = words_of(rows, index, "ord", "weight", "negated")
    # a candidate that an input has no word for is not in it, or in its negation
    hit = F.call_function("getbit", F.col("b"), F.col("bit")) == 1
    gain = F.when(hit, F.when(F.col("negated"), -F.col("weight")).otherwise(F.col("weight"))).otherwise(0)
    base = sum(c.weight for c in large if c.negated)
    probed = asked.join(words, ["chunk", "w"], "left").groupBy("chunk", "rid").agg((F.first("n") + F.sum(gain)).alias("n"))
    return _placed(probed.where(F.col("n") + base >= t), index)


def decide_chunks(index: Index, criteria: Sequence[Criterion], t: int) -> DataFrame:
    """chunk, verdict: one (all rids), open; from kinds alone. Chunks that can't reach T are not listed."""
    own = selected(index, criteria, "chunk", "kind")
    full = F.sum(F.when(F.col("kind") == FULL, F.col("weight")).otherwise(0))
    mixed = F.sum(F.when(F.col("kind") == DIRTY, F.col("weight")).otherwise(0))
    return own.groupBy("chunk").agg(full.alias("k"), mixed.alias("m")).where(F.col("k") + F.col("m") >= t).select("chunk", F.when(F.col("k") >= t, "one").otherwise("open").alias("verdict"))


def run_merge_sweep(index, criteria, spec) -> Bitmap:
    """Chunks that their kinds decide aren't read; in the others the ends of runs are swept with a running count."""
    out = _swept(index, criteria, spec)
    return Bitmap(out.df.where("b <> 0"), index.rows, index.chunk_bits)


def _swept_runs(index: Index, criteria: Sequence[Criterion], spec: Spec, rows: DataFrame) -> DataFrame:
    """chunk, start, stop: where the running weight of open runs satisfies spec, within chunks."""
    n = total_weight(criteria)
    edges = run_edges(words_of(rows, index, "ord", "weight"), index.chunk_bits, "ord", "weight")
    steps = edges.select("chunk", F.inline(F.array(F.struct(F.col("start").alias("at"), F.col("weight").alias("d")), F.struct((F.col("stop") + 1).alias("at"), (-F.col("weight")).alias("d")))))
    summed = steps.groupBy("chunk", "at").agg(F.sum("d").alias("d")).where("d <> 0")
    w = Window.partitionBy("chunk").orderBy("at")
    swept = summed.select("chunk", F.col("at").alias("start"), (F.lead("at").over(w) - 1).alias("stop"), F.sum("d").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("n"))
    return _kept(swept.where(F.col("stop").isNotNull()), F.col("n"), spec, n).select("chunk", "start", "stop")


def _swept(index: Index, criteria: Sequence[Criterion], spec: Spec) -> Bitmap:
    n, t = total_weight(criteria), spec.as_threshold(total_weight(criteria))
    if spec.vector(n)[0] or any(c.negated for c in criteria):
        return by_kernel(index, criteria, spec, "run_merge", {"dirty_policy": "sweep"})
    rows = selected(index, criteria, "chunk", *index.body)
    if t is None:
        return Bitmap(_runs_to_words(_swept_runs(index, criteria, spec, rows), index), index.rows, index.chunk_bits)
    verdicts = decide_chunks(index, criteria, t)
    undecided = rows.join(verdicts.where("verdict = 'open'").select("chunk"), "chunk", "left_semi")
    size = F.least(F.lit(index.chunk_bits).cast("long"), F.lit(index.rows) - F.col("chunk") * index.chunk_bits)
    ones = verdicts.where("verdict = 'one'").select("chunk", (F.col("chunk") * index.chunk_bits).alias("start"), (F.col("chunk") * index.chunk_bits + size - 1).alias("stop"))
    return Bitmap(_runs_to_words(_swept_runs(index, criteria, spec, undecided).unionByName(ones), index), index.rows, index.chunk_bits)


def _runs_to_words(runs: DataFrame, index: Index) -> DataFrame:
    """Words of runs within chunks."""
    base = F.col("chunk") * index.chunk_bits
    a, b = F.col("start") - base, F.col("stop") - base
    per_word = runs.select("chunk", a.cast("int").alias("a"), b.cast("int").alias("z")).select("chunk", "a", "z", F.explode(F.sequence(F.floor(F.col("a") / 64).cast("int"), F.floor(F.col("z") / 64).cast("int"))).alias("w"))
    low = F.greatest(F.col("a") - F.col("w") * 64, F.lit(0))
    high = F.least(F.col("z") - F.col("w") * 64, F.lit(63))
    from_low = F.call_function("shiftleft", F.lit(-1).cast("long"), low)
    to_high = F.call_function("shiftrightunsigned", F.lit(-1).cast("long"), F.lit(63) - high)
    return per_word.select("chunk", "w", from_low.bitwiseAND(to_high).alias("b")).groupBy("chunk", "w").agg(F.bit_or("b").alias("b"))


def matching_intervals(index: Index, criteria: Sequence[Criterion], spec: Spec) -> DataFrame:
    """start, stop of the maximal runs of rids that satisfy spec."""
    return coalesced(run_edges(_swept(index, criteria, spec).df, index.chunk_bits))


def recurrence_fold(index, criteria, spec) -> Bitmap:
    """The recurrence as a fold over each word's inputs: the accumulator holds at least 1, 2, ... so far."""
    n = total_weight(criteria)
    if spec.vector(n)[0] or n > MAX_COLUMNS:
        return by_kernel(index, criteria, spec, "recurrence_loop", {})
    found = spec.intervals(n)
    top = min(n, max(b for _, b in found) + 1)
    t = spec.as_threshold(n)
    top = t if t is not None else top
    inputs = F.array(*[F.col(f"x{k}") for k in range(n)])
    start = F.array_repeat(F.lit(0).cast("long"), top)
    step = lambda c, b: F.transform(c, lambda x, j: x.bitwiseOR(F.when(j == 0, F.lit(-1).cast("long")).otherwise(F.get(c, j - 1)).bitwiseAND(b)))
    words = aligned(index, criteria).select("chunk", "w", F.aggregate(inputs, start, step).alias("c"))
    at_least = lambda k: F.lit(0).cast("long") if k > n else F.get("c", F.lit(k - 1))
    out = F.lit(0).cast("long")
    for a, b in found:
        out = out.bitwiseOR(at_least(a).bitwiseAND(F.bitwise_not(at_least(b + 1))))
    return Bitmap(words.select("chunk", "w", out.alias("b")).where("b <> 0"), index.rows, index.chunk_bits)


RELATIONAL = {
    "counter_hash": counter_hash,
    "sort_count_windows": sort_count_windows,
    "pair_counts_joins": pair_counts_joins,
    "set_aside_joins": set_aside_joins,
    "run_merge_sweep": run_merge_sweep,
    "recurrence_fold": recurrence_fold,
}


def over_bitmaps(bitmaps: Sequence[Bitmap], spec: Spec, method: str = "counter_hash", weights: Sequence[int] | None = None, **options) -> Bitmap:
    """A symmetric function of computed bitmaps: they become an index of their own."""
    one = bitmaps[0]
    rows = None
    for k, b in enumerate(bitmaps):
        own = b.df.select(F.lit("b").alias("attr"), F.lit(str(k)).alias("value"), "chunk", "w", "b")
        rows = own if rows is None else rows.unionByName(own)
    chunks = rows.groupBy("attr", "value", "chunk").agg(F.sort_array(F.collect_list(F.struct("w", "b"))).alias("words"), F.sum(F.bit_count("b")).cast("int").alias("card"))
    index = Index(chunks.withColumn("kind", F.lit(DIRTY).cast("tinyint")), one.rows, one.chunk_bits)
    criteria = [Criterion("b", str(k), (weights or [1] * len(bitmaps))[k]) for k in range(len(bitmaps))]
    return evaluate(index, criteria, spec, method, **options)


def row_scan(df: DataFrame, criteria: Sequence[Criterion], spec: Spec) -> DataFrame:
    """The baseline without an index: per row, the weight of met criteria, as one expression. df's rows that satisfy spec, with matches."""
    met = F.lit(0).cast("long")
    for c in criteria:
        hit = F.coalesce(F.col(c.attr).cast("string") == c.value, F.lit(False))
        met = met + F.when(~hit if c.negated else hit, c.weight).otherwise(0)
    return _kept(df.withColumn("matches", met), F.col("matches"), spec, total_weight(criteria))
