"""The experiment workloads: competitions over grids of (N, T), random queries, index against scan, synthetic sets, and tunings, on six data sets.

Each is one pass over a stored index for all its queries. Answers are counts of rids, so that every method can be held against SQL;
measured times have none.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import spec as S
from ..operators import circuits, kernels
from ..operators import threshold as T
from ..operators.index import CHUNK_BITS, Index, build, dense_rids, members
from ..session import written
from ..sources import tables as tb
from ..sources.stored import is_stored, stored_index
from . import criteria as C
from . import queries as Q
from .planner import best_of_mu

_CHUNK_IDS = f"{Q._CHUNKS}, ids AS (SELECT doc_id, chunk_no, row_number() OVER (ORDER BY doc_id, chunk_no) - 1 AS rid FROM chunks), {Q._CHUNK_GRAMS}, members AS (SELECT 'gram' AS attr, gram AS value, rid FROM g JOIN ids USING (doc_id, chunk_no)), size AS (SELECT count(*) AS r FROM ids)"
_NAMES = "{g}, members AS (SELECT 'gram' AS attr, gram AS value, c_custkey AS rid FROM g), size AS (SELECT max(c_custkey) + 1 AS r FROM customer)"
_name_sql = lambda q: _NAMES.format(g=Q._gram_sql(q, "customer", "c_custkey", "c_name"))

#: For each data set its index and the SQL of its members (attr, value, rid) and size (r).
DATASETS: dict[str, tuple[Callable[[SparkSession, str], Index], str]] = {
    "orders": (Q.order_index, f"{Q._MEMBERS}, size AS (SELECT max(o_orderkey) + 1 AS r FROM orders)"),
    "names2": (lambda s, d: Q.name_index(s, d, 2), _name_sql(2)),
    "names3": (lambda s, d: Q.name_index(s, d, 3), _name_sql(3)),
    "vocab": (
        Q.vocab_index,
        f"{Q._VOCAB}, ids AS (SELECT word, row_number() OVER (ORDER BY min(doc_id), word) - 1 AS rid FROM v GROUP BY word), members AS (SELECT 'doc' AS attr, doc_id::VARCHAR AS value, rid FROM v JOIN ids USING (word)), size AS (SELECT count(*) AS r FROM ids)",
    ),
    "chunks2": (lambda s, d: Q.chunk_index(s, d, 2), _CHUNK_IDS.format(q=2)),
    "chunks3": (lambda s, d: Q.chunk_index(s, d, 3), _CHUNK_IDS.format(q=3)),
}
add = Q.add

#: Methods take turns over the pairs of a grid.
TURNS = ("counter_array", "sideways_sum", "adder_tree", "carry_save", "run_merge", "pair_counts", "set_aside_probe", "tuned_set_aside_skip", "recurrence_loop", "sort_network", "heap_skip", "sort_count", "heap_merge")
FAST = ("counter_array", "sideways_sum", "adder_tree", "carry_save", "set_aside_probe")


def prototypes(k: int) -> list[int]:
    return [7 + 3 * i for i in range(k)]


def _pairs(dataset: str, pairs: Sequence[tuple[int, int]], keys: int, methods: Sequence[str], negated: bool = False):
    """For each (N, T): the number of rids, by methods in turn."""

    def query(spark: SparkSession, d: str) -> DataFrame:
        index = DATASETS[dataset][0](spark, d)
        base = C.similarity(index, prototypes(keys))
        made = []
        for k, (n, t) in enumerate(pairs):
            own = C.fit_to_n(base, n)
            made.append(T.Query(tuple(C.negate(own) if negated else own), S.threshold(t), methods[k % len(methods)]))
        named = spark.createDataFrame([(k, n, t) for k, (n, t) in enumerate(pairs)], "query int, n long, t long")
        return T.evaluate_many(index, made).join(F.broadcast(named), "query").select("n", "t", F.col("ones").alias("rids"))

    return query


def _base(keys: int) -> str:
    return f"base AS (SELECT attr, value, row_number() OVER (ORDER BY attr, value) - 1 AS k FROM (SELECT DISTINCT attr, value FROM members WHERE rid IN ({', '.join(map(str, prototypes(keys)))}))), have AS (SELECT count(*) AS have FROM base)"


def _pairs_sql(dataset: str, pairs: Sequence[tuple[int, int]], keys: int, negated: bool = False) -> str:
    """Weights depend on n alone, and so do the rids of each weight."""
    found = "sum(c.rids) FILTER (m >= asked.t)" if not negated else "r - coalesce(sum(c.rids) FILTER (m > asked.n - asked.t), 0)"
    return f"""WITH {DATASETS[dataset][1]}, {_base(keys)},
      asked(i, n, t) AS (VALUES {', '.join(f'({i}, {n}, {t})' for i, (n, t) in enumerate(pairs))}),
      crit AS (SELECT n, attr, value, CASE WHEN n <= have THEN (k < n)::INT ELSE n // have + (k < n % have)::INT END AS weight FROM base, have, (SELECT DISTINCT n FROM asked)),
      met AS (SELECT n, rid, sum(weight) AS m FROM members JOIN crit USING (attr, value) WHERE weight > 0 GROUP BY ALL),
      c AS (SELECT n, m, count(*) AS rids FROM met GROUP BY ALL)
      SELECT asked.n::BIGINT AS n, asked.t::BIGINT AS t, coalesce({found}, 0)::BIGINT AS rids FROM asked LEFT JOIN c ON c.n = asked.n, size GROUP BY asked.i, asked.n, asked.t, r"""


def _grid(name: str, dataset: str, pairs: Sequence[tuple[int, int]], keys: int, methods: Sequence[str] = TURNS, negated: bool = False) -> None:
    add(name, _pairs(dataset, pairs, keys, methods, negated), _pairs_sql(dataset, pairs, keys, negated))


SMALL, MEDIUM, LARGE = C.grid(32), C.grid(128), C.grid(512)
for _name in DATASETS:
    _own = "" if _name == "orders" else f"_{_name}"
    _grid(f"small_grid{_own}", _name, SMALL, 1)
    if not _name.startswith("chunks"):
        _grid(f"medium_grid{_own}", _name, MEDIUM, 10)
    if _name in ("orders", "names3", "vocab"):
        _grid(f"large_grid{_own}", _name, LARGE, 100, FAST)
    if not _name.startswith("chunks"):
        _grid(f"random_nt_given{_own}", _name, C.random_nt(1, 100), 100, FAST)
        _grid(f"random_nt_negated{_own}", _name, C.random_nt(2, 100), 100, FAST, negated=True)

# -- how answers and work move with N and with T

VARY_N = [(n, t) for n in (4, 8, 16, 32, 64, 128) for t in sorted({3, n // 2, n - 1})]
VARY_T = [(n, t) for n in (32, 64) for t in range(2, n)]
for _name in ("orders", "vocab"):
    _own = "" if _name == "orders" else f"_{_name}"
    _grid(f"vary_n{_own}", _name, VARY_N, 10)
    _grid(f"vary_t{_own}", _name, VARY_T, 1, FAST)

# -- (32, T) over the six sets


def _first(found: DataFrame, n: int) -> list[C.Criterion]:
    """The first n criteria, in attribute and value order, of members or of what a prototype meets."""
    return [C.Criterion(r["attr"], r["value"]) for r in found.select("attr", "value").distinct().orderBy("attr", "value").limit(n).toLocalIterator()]


def _only(found: DataFrame, own: Sequence[C.Criterion]) -> DataFrame:
    asked = found.sparkSession.createDataFrame([(c.attr, c.value) for c in own], "attr string, value string")
    return found.join(F.broadcast(asked), ["attr", "value"], "left_semi")


#: The members of the first n criteria that prototypes meet, these criteria, and the number of rids: as in DATASETS, from all rows, without the other bitmaps.
Narrow = tuple[DataFrame, list[C.Criterion], int]


def _narrow_orders(spark: SparkSession, d: str, keys: Sequence[int], n: int) -> Narrow:
    rows = tb.orders_wide(spark, d)
    own = _first(members(rows.where(F.col("o_orderkey").isin(list(keys))), "o_orderkey", Q.A), n)
    found = members(rows, "o_orderkey", sorted({c.attr for c in own}))
    return _only(found, own), own, tb.load(spark, d, "orders").agg(F.max("o_orderkey")).first()[0] + 1


def _narrow_names(q: int):
    def make(spark: SparkSession, d: str, keys: Sequence[int], n: int) -> Narrow:
        customer = tb.load(spark, d, "customer")
        grams = lambda df: tb.name_grams(df, "c_custkey", "c_name", q)
        own = _first(grams(customer.where(F.col("c_custkey").isin(list(keys)))), n)
        return _only(grams(customer), own), own, customer.agg(F.max("c_custkey")).first()[0] + 1

    return make


def _narrow_vocab(spark: SparkSession, d: str, keys: Sequence[int], n: int) -> Narrow:
    words, docs = Q.vocabulary(spark, d), tb.load(spark, d, "documents")
    as_member = lambda df: df.select(F.lit("doc").alias("attr"), F.col("doc_id").cast("string").alias("value"), "word")
    asked = [r["word"] for r in words.where(F.col("rid").isin(list(keys))).select("word").toLocalIterator()]
    # a text without these letters doesn't hold the word
    near = docs.where(reduce(lambda x, w: x | F.contains(F.lower("text"), F.lit(w)), asked, F.lit(False)))
    own = _first(as_member(tb.vocabulary(near).where(F.col("word").isin(asked))), n)
    held = as_member(tb.vocabulary(docs.where(F.col("doc_id").cast("string").isin([c.value for c in own])))).join(words.select("word", "rid"), "word")
    return held.select("attr", "value", "rid"), own, words.count()


def _chunks_met(spark: SparkSession, d: str, keys: Sequence[int], n: int) -> tuple[DataFrame, dict[int, list[C.Criterion]]]:
    """rid of every chunk with those of the first n 2-grams and 3-grams of the prototypes that it holds, and these grams: one pass over the texts."""
    key = (spark.sparkContext.applicationId, d, tuple(keys), n)
    if key not in _met:
        docs, last = tb.load(spark, d, "documents"), max(keys) + 1
        # documents with a chunk at all; the first so many have the prototypes
        some = F.exists(F.split("text", "\n"), lambda x: (F.length(x) > 0) & (F.length(x) <= 20000))
        first = tb.text_chunks(docs.where(some).orderBy("doc_id").limit(last)).orderBy("doc_id", "chunk_no").limit(last).collect()  # a row for each prototype and those before
        texts = spark.createDataFrame([(k, first[k]["text"]) for k in keys if k < len(first)], "rid long, text string")
        own = {q: _first(tb.chunk_grams(texts, q), n) for q in (2, 3)}
        holds = lambda low: F.array_compact(F.array(*[F.when(F.contains(low, F.lit(c.value)), F.lit(c.value)) for q in own for c in own[q]]))
        # bound by a lambda, the text is lower-cased once
        met = tb.text_chunks(docs).select("doc_id", "chunk_no", F.transform(F.array(F.lower("text")), holds)[0].alias("met"))
        _met[key] = dense_rids(written(met, "met"), "doc_id", "chunk_no"), own
    return _met[key]


_met: dict[tuple, tuple[DataFrame, dict[int, list[C.Criterion]]]] = {}


def _narrow_chunks(q: int):
    def make(spark: SparkSession, d: str, keys: Sequence[int], n: int) -> Narrow:
        met, own = _chunks_met(spark, d, keys, n)
        found = met.select(F.lit("gram").alias("attr"), F.explode("met").alias("value"), "rid")
        return _only(found, own[q]), own[q], met.count()

    return make


NARROW = {"orders": _narrow_orders, "names2": _narrow_names(2), "names3": _narrow_names(3), "vocab": _narrow_vocab, "chunks2": _narrow_chunks(2), "chunks3": _narrow_chunks(3)}
#: The first criteria of prototypes, drawn once for an application and an input.
_first_drawn: dict[tuple, list[C.Criterion]] = {}


def narrow_index(spark: SparkSession, d: str, dataset: str, keys: int, n: int) -> tuple[Index, list[C.Criterion]]:
    """The bitmaps of the first n criteria of the prototypes, and these criteria: from the whole index where that is stored, else from an index of them alone."""
    if is_stored(spark, d, "vocabulary" if dataset == "vocab" else dataset):
        index = DATASETS[dataset][0](spark, d)
        return index, C.similarity(index, prototypes(keys))
    key = (spark.sparkContext.applicationId, d, dataset, keys, n)

    def make() -> Index:
        found, _first_drawn[key], rows = NARROW[dataset](spark, d, prototypes(keys), n)
        return build(found, rows, Q.CHUNK)

    index = stored_index(spark, d, f"{dataset}_first{n}_of{keys}", make)
    return index, _first_drawn[key]


def _fixed(t: int):
    """The queries ask for 32 bitmaps of each set, so that no others are built for them."""

    def query(spark: SparkSession, d: str) -> DataFrame:
        out = []
        for name in DATASETS:
            index, base = narrow_index(spark, d, name, 3, 32)
            found = T.evaluate_many(index, [T.Query(tuple(C.fit_to_n(base, 32)), S.threshold(t), "sideways_sum")])
            out.append(found.select(F.lit(32).cast("long").alias("n"), F.lit(t).cast("long").alias("t"), F.col("ones").alias("rids"), F.lit(name).alias("dataset")))
        return reduce(DataFrame.unionByName, out)

    return query


for _t in (3, 19, 31):
    add(f"workload_32_{_t}", _fixed(_t), " UNION ALL ".join(f"SELECT *, '{name}' AS dataset FROM ({_pairs_sql(name, [(32, _t)], 3)})" for name in DATASETS))

# -- index against scan: 30 trials, random values of all attributes and similarity queries, over all orders

TRIALS = 30
_N = len(Q.A)
_trial_t = lambda i: 2 + (37 * i + 11) % (_N - 2)


#: The criteria of the trials, drawn once for an application and an input.
_drawn: dict[tuple, list[list[C.Criterion]]] = {}


def _trials(spark: SparkSession, d: str, similar: bool) -> list[list[C.Criterion]]:
    key = (spark.sparkContext.applicationId, d, similar)
    if key not in _drawn:
        _drawn[key] = _similar_trials(spark, d) if similar else C.random_attributes(Q.order_index(spark, d), TRIALS)
    return _drawn[key]


def _similar_trials(spark: SparkSession, d: str) -> list[list[C.Criterion]]:
    keys = [331 * i for i in range(TRIALS)]
    rows = {r["o_orderkey"]: r for r in Q.wide_orders(spark, d).where(F.col("o_orderkey").isin(keys)).toLocalIterator()}
    return [[C.Criterion(a, str(rows[k][a])) for a in sorted(Q.A) if rows[k][a] is not None] if k in rows else [] for k in keys]


def _by_index(similar: bool):
    def query(spark: SparkSession, d: str) -> DataFrame:
        made = [T.Query(tuple(own), S.threshold(_trial_t(i)), "counter_array") for i, own in enumerate(_trials(spark, d, similar)) if own]
        return T.evaluate_many(Q.order_index(spark, d), made).select(F.col("query").cast("long").alias("trial"), F.col("ones").alias("rids"))

    return query


def _by_scan(similar: bool):
    def query(spark: SparkSession, d: str) -> DataFrame:
        """All trials in one scan: a sum of cases for each."""
        trials = [own for own in _trials(spark, d, similar) if own]
        met = [reduce(lambda x, c: x + F.when(F.col(c.attr).cast("string") == c.value, 1).otherwise(0), own, F.lit(0)) >= _trial_t(i) for i, own in enumerate(trials)]
        sums = Q.wide_orders(spark, d).agg(F.array(*[F.coalesce(F.sum(m.cast("long")), F.lit(0)) for m in met]).alias("rids"))
        return sums.select(F.posexplode("rids").alias("trial", "rids")).select(F.col("trial").cast("long").alias("trial"), "rids")

    return query


_THRESHOLDS = f"(2 + (37 * trial + 11) % {_N - 2})"
_RANDOM_SQL = f"WITH {Q._RANDOM_ATTRS.format(trials=TRIALS)}, met AS (SELECT trial, rid, count(*) AS m FROM members JOIN picked USING (attr, value) GROUP BY ALL) SELECT t.trial::BIGINT AS trial, count(rid) FILTER (m >= (2 + (37 * t.trial + 11) % {_N - 2})) AS rids FROM (SELECT unnest(range(0, {TRIALS})) AS trial) t LEFT JOIN met ON met.trial = t.trial GROUP BY t.trial"
_KEYS_SQL = f"keys AS (SELECT o_orderkey, row_number() OVER (ORDER BY o_orderkey) - 1 AS trial FROM orders_wide WHERE o_orderkey IN ({', '.join(str(331 * i) for i in range(TRIALS))}))"
_SIMILAR_SQL = f"WITH {Q._MEMBERS}, {_KEYS_SQL}, picked AS (SELECT trial, attr, value FROM members JOIN keys ON rid = o_orderkey), met AS (SELECT trial, rid, count(*) AS m FROM members JOIN picked USING (attr, value) GROUP BY ALL) SELECT trial::BIGINT AS trial, count(*) FILTER (m >= {_THRESHOLDS}) AS rids FROM met GROUP BY trial"
add("idx_vs_scan_random", _by_index(False), _RANDOM_SQL)
add("idx_vs_scan_random_scan", _by_scan(False), _RANDOM_SQL)
add("idx_vs_scan_similarity", _by_index(True), _SIMILAR_SQL)
add("idx_vs_scan_similarity_scan", _by_scan(True), _SIMILAR_SQL)

# -- synthetic sets

SYNTHETIC = [(kind, rows) for kind in ("uniform", "clustered") for rows in (30_000, 1_000_000, 10_000_000)]
SYNTHETIC_T = (2, 3, 16)
SETS = 32
#: The sets among so many rows have the line items as entries, not made-up numbers.
OF_LINES = 30_000


def synthetic_index(spark: SparkSession, d: str, kind: str, rows: int) -> Index:
    lines = tb.load(spark, d, "lineitem") if rows == OF_LINES else None
    return stored_index(spark, d, f"synthetic_{kind}_{rows}", lambda: build(tb.synthetic(spark, kind, rows, SETS, lines=lines), rows, CHUNK_BITS))


def _synthetic(kind: str, rows: int, methods: Sequence[str] = ("counter_array", "sideways_sum", "run_merge")):
    def query(spark: SparkSession, d: str) -> DataFrame:
        every = tuple(C.Criterion(kind, str(k)) for k in range(SETS))
        found = T.evaluate_many(synthetic_index(spark, d, kind, rows), [T.Query(every, S.threshold(t), m) for t, m in zip(SYNTHETIC_T, methods)])
        return found.select(F.element_at(F.array(*map(F.lit, SYNTHETIC_T)), F.col("query") + 1).cast("long").alias("t"), F.col("ones").alias("rids"))

    return query


_MIX = "(({a}) * 1103515245 + ({b}) * 12345 + 1111) % 2147483647"
_mix = lambda a, b: _MIX.format(a=a, b=b)
_RID = {"uniform": f"({_mix(_mix('i + s * 10000', 7), 1)})", "clustered": f"({_mix(_mix('i // 32 + s * 10000', 3), 1)}) + i % 32"}
for _kind, _rows in SYNTHETIC:
    _entries = f"(SELECT (l_orderkey * 7 + l_linenumber) % {SETS} AS s, (l_orderkey * 7 + l_linenumber) // {SETS} AS i FROM lineitem)" if _rows == OF_LINES else f"range(0, {SETS}) a(s), range(0, 10000) b(i)"
    _members = f"SELECT DISTINCT s, ({_RID[_kind]}) % {_rows} AS rid FROM {_entries}"
    add(f"synthetic_{_kind}_{_rows}", _synthetic(_kind, _rows), f"WITH c AS (SELECT rid, count(*) AS n FROM ({_members}) GROUP BY rid) SELECT t::BIGINT AS t, count(*) FILTER (n >= t) AS rids FROM c, (SELECT unnest([{', '.join(map(str, SYNTHETIC_T))}]) AS t) GROUP BY t")

# -- tunings: how many inputs to set aside, and trailing zeros


def _mu_queries(spark: SparkSession, d: str, name: str) -> tuple[Index, list[T.Query], list[tuple[int, float, int]]]:
    index = DATASETS[name][0](spark, d)
    base = C.similarity(index, prototypes(10))
    made, named = [], []
    for mu in kernels.MUS:
        for n, t in ((16, 12), (32, 29), (128, 120)):
            named.append((len(made), mu, n))
            made.append(T.Query(tuple(C.fit_to_n(base, n)), S.threshold(t), "tuned_set_aside_skip", {"mu": mu}))
    return index, made, named


def _mu_answers(spark: SparkSession, d: str) -> DataFrame:
    """Whatever mu is, the answer is the same."""
    out = []
    for name in ("orders", "names3", "vocab"):
        index, made, named = _mu_queries(spark, d, name)
        label = F.broadcast(spark.createDataFrame(named, "query int, mu double, n long"))
        out.append(T.evaluate_many(index, made).join(label, "query").select(F.lit(name).alias("dataset"), "mu", "n", F.col("ones").alias("rids")))
    return reduce(DataFrame.unionByName, out)


add("mu_answers", _mu_answers, " UNION ALL ".join(f"SELECT '{name}' AS dataset, mu, n, rids FROM ({_pairs_sql(name, [(16, 12), (32, 29), (128, 120)], 10)}), (SELECT unnest([{', '.join(map(str, kernels.MUS))}])::DOUBLE AS mu)" for name in ("orders", "names3", "vocab")))


def mu_table(spark: SparkSession, d: str) -> DataFrame:
    """Measured: dataset, mu (0: for each query the best), queries, ms."""
    rows = []
    for name in ("orders", "names3", "vocab"):
        index, made, named = _mu_queries(spark, d, name)
        times = {r["query"]: r["ms"] for r in T.kernel_times(index, made).toLocalIterator()}  # a row for each query
        by = {(mu, n): times.get(k, 0.0) for k, mu, n in named}
        rows += [(name, mu, 3, sum(ms for (own, _), ms in by.items() if own == mu)) for mu in kernels.MUS]
        rows.append((name, 0.0, 3, sum(ms for _, ms in best_of_mu(by).values())))
    return spark.createDataFrame(rows, "dataset string, mu double, queries int, ms double")


add("mu_table", mu_table)


def _trimmed_bytes(spark: SparkSession, d: str) -> DataFrame:
    sizes = lambda style: Q.order_index(spark, d, style).df.where("payload is not null").groupBy("attr").agg(F.sum(F.octet_length("payload")).cast("long").alias(style))
    return sizes("plain").join(sizes("sentinel"), "attr")


add(
    "trimmed_bytes", _trimmed_bytes,
    f"WITH {Q._MEMBERS}, r AS (SELECT max(o_orderkey) + 1 AS r FROM orders), c AS (SELECT attr, value, rid // {Q.CHUNK} AS chunk, count(*) AS n, max(rid % {Q.CHUNK}) // 64 + 1 AS words FROM members GROUP BY ALL) "
    f"SELECT attr, sum(8 * words)::BIGINT AS plain, sum(8 * {Q.CHUNK // 64})::BIGINT AS sentinel FROM c, r WHERE n < least({Q.CHUNK}, r - chunk * {Q.CHUNK}) GROUP BY attr",
)


def styles_times(spark: SparkSession, d: str) -> DataFrame:
    """Measured: both adders over trimmed and whole vectors, and counters over each style, for (119, 60) and (32, 16): style, method, n, t, rids, ms."""
    rows = []
    for style in ("words", "plain", "sentinel", "compressed", "rle"):
        index = Q.order_index(spark, d, style)
        base = C.similarity(index, prototypes(10))
        named = [(m, n, t) for m in ("sideways_sum", "adder_tree", "counter_array") for n, t in ((119, 60), (32, 16))]
        made = [T.Query(tuple(C.fit_to_n(base, n)), S.threshold(t), m) for m, n, t in named]
        rows += [(style, *named[r["query"]], r["ones"], r["ms"]) for r in T.kernel_times(index, made).toLocalIterator()]
    return spark.createDataFrame(rows, "style string, method string, n long, t long, rids long, ms double")


add("styles_times", styles_times)

# -- times of the small competition, and the measures on them

RIVALS = ("counter_array", "sort_count", "pair_counts", "heap_merge", "heap_skip", "set_aside_probe", "tuned_set_aside_skip", "run_merge", "recurrence_loop", "adder_tree", "sideways_sum", "carry_save", "sort_network")


def competition_times(spark: SparkSession, d: str, dataset: str = "orders", pairs: Sequence[tuple[int, int]] = SMALL, keys: int = 1, rivals: Sequence[str] = RIVALS) -> DataFrame:
    """Measured: competition, algo, n, t, ms of every method at every pair."""
    index = DATASETS[dataset][0](spark, d)
    base = C.similarity(index, prototypes(keys))
    named = [(k, f"{dataset} {n} {t}", m, n, t) for k, (m, (n, t)) in enumerate((m, p) for m in rivals for p in pairs)]
    made = [T.Query(tuple(C.fit_to_n(base, n)), S.threshold(t), m) for _, _, m, n, t in named]
    label = spark.createDataFrame(named, "query int, competition string, algo string, n long, t long")
    return T.kernel_times(index, made).join(F.broadcast(label), "query").select("competition", "algo", "n", "t", "ms")


def _measured(make):
    def query(spark: SparkSession, d: str) -> DataFrame:
        from .. import measures
        from ..session import written

        return make(measures, written(competition_times(spark, d), "times"))

    return query


add("competition_measured", _measured(lambda m, x: m.rank_competition(x)))
add("win_rates_measured", _measured(lambda m, x: m.win_rates(x)))
add("heatmap_measured", _measured(lambda m, x: m.heatmap(x)))
add("normalized_measured", _measured(lambda m, x: m.normalized_time(x)))
add("relative_measured", _measured(lambda m, x: m.normalize_by_n(x.where(F.col("t") == 3))))


def cost_measures(spark: SparkSession, d: str) -> DataFrame:
    """Measured: what Spark moved and held for a query by each of some methods, in place of hardware counters."""
    from .. import measures

    rows = []
    index, own = Q.order_index(spark, d), Q.prototype(spark, d)
    for method in ("counter_array", "counter_hash", "run_merge_sweep", "set_aside_joins", "sideways_sum"):
        got = measures.spark_metrics(spark, lambda m=method: measures.run(T.evaluate(index, own, S.threshold(4), m).rids()))
        rows.append((method, *(got[k] for k in measures.METRICS)))
    return spark.createDataFrame(rows, "method string, " + ", ".join(f"{k} long" for k in measures.METRICS))


add("cost_measures", cost_measures)


def query_costs(spark: SparkSession, d: str) -> DataFrame:
    """Ones in all inputs, in the n - t + 1 smallest and outside the aside largest, for T at the query."""
    from .planner import query_stats

    index = Q.order_index(spark, d)
    own, rows = C.fit_to_n(Q.prototype(spark, d), 16), []
    for t, aside in ((2, 1), (8, 4), (15, 14)):
        got = query_stats(index, own, t, aside)
        rows.append((t, aside, got["b"], got["b_small"], got["b_rest"]))
    return spark.createDataFrame(rows, "t long, aside long, b long, b_small long, b_rest long")


add(
    "query_costs", query_costs,
    f"WITH {Q._MEMBERS}, p AS (SELECT attr, value, row_number() OVER (ORDER BY attr, value) AS k FROM members WHERE rid = 0), c AS (SELECT k, count(*) AS card FROM members JOIN p USING (attr, value) GROUP BY k), "
    f"e AS (SELECT card, row_number() OVER (ORDER BY card) AS i FROM (SELECT card FROM c UNION ALL SELECT card FROM c WHERE k <= {16 - _N})) "
    "SELECT t::BIGINT AS t, aside::BIGINT AS aside, sum(card)::BIGINT AS b, sum(card) FILTER (i <= 16 - t + 1)::BIGINT AS b_small, sum(card) FILTER (i <= 16 - aside)::BIGINT AS b_rest FROM e, (VALUES (2, 1), (8, 4), (15, 14)) v(t, aside) GROUP BY ALL",
)

# -- operation counts: what a word costs, by method

OPS = {
    "adder_tree": lambda n, t: circuits.gate_count("adder_tree", n, t), "sideways_sum": lambda n, t: circuits.gate_count("sideways_sum", n, t), "sort_network": lambda n, t: circuits.gate_count("sort_network", n, t),
    "recurrence_loop": circuits.recurrence_count, "carry_save": lambda n, t: kernels.carry_save_count(n),
}
OP_ROWS = [(f"{n} {t}", a, float(f(n, t)), n, t) for n, t in SMALL for a, f in OPS.items()]
_OPS_SQL = "times(competition, algo, ms, n, t) AS (VALUES " + ", ".join(f"('{c}', '{a}', {x}::DOUBLE, {n}::BIGINT, {t}::BIGINT)" for c, a, x, n, t in OP_ROWS) + ")"


#: Line items ask for the pairs of the small grid in turn; a method's operations are those of the circuit for each that asks.
_OPS_ASKED = _OPS_SQL.replace("times(", "circuit(") + f", asked AS (SELECT (l_orderkey + l_linenumber) % {len(SMALL)} AS k, count(*) AS asked FROM lineitem GROUP BY ALL), pairs(k, n, t) AS (VALUES " + ", ".join(f"({k}, {n}, {t})" for k, (n, t) in enumerate(SMALL)) + "), times AS (SELECT competition, algo, ms * asked AS ms, circuit.n, circuit.t FROM asked JOIN pairs USING (k) JOIN circuit ON circuit.n = pairs.n AND circuit.t = pairs.t)"


def _by_operations(make):
    def query(spark: SparkSession, d: str) -> DataFrame:
        from .. import measures

        turn = {p: k for k, p in enumerate(SMALL)}
        each = spark.createDataFrame([(turn[n, t], c, a, x, n, t) for c, a, x, n, t in OP_ROWS], "k long, competition string, algo string, one double, n long, t long")
        asked = tb.load(spark, d, "lineitem").groupBy(((F.col("l_orderkey") + F.col("l_linenumber")) % len(SMALL)).alias("k")).agg(F.count("*").alias("asked"))
        return make(measures, asked.join(F.broadcast(each), "k").select("competition", "algo", (F.col("one") * F.col("asked")).alias("ms"), "n", "t"))

    return query


_RANKED = f"{_OPS_ASKED}, r AS (SELECT *, rank() OVER (PARTITION BY competition ORDER BY ms) - 1 AS rank FROM times)"
add(
    "relative_operations", _by_operations(lambda m, x: m.normalize_by_n(x.where(F.col("t") == 3)).select("algo", "n", F.round("relative", 6).alias("relative"))),
    f"WITH {_OPS_ASKED} SELECT algo, n, round(ms / max(CASE WHEN n = 32 THEN ms END) OVER (PARTITION BY algo), 6) AS relative FROM times WHERE t = 3",
)
add(
    "heatmap_operations", _by_operations(lambda m, x: m.heatmap(x)),
    f"WITH {_RANKED} SELECT floor(log2(n))::INTEGER AS n_bin, least(floor(t * 4 / n), 3)::INTEGER AS t_bin, " + ", ".join(f"avg((rank = 0)::INT::DOUBLE) FILTER (algo = '{a}') AS {a}" for a in sorted(OPS)) + " FROM r GROUP BY ALL",
)


def _carry_save_ops(spark: SparkSession, d: str) -> DataFrame:
    """Operations for the N that line items have as quantity, and how many have it."""
    carry, loop = F.udf(lambda n: int(kernels.carry_save_count(n)), "long"), F.udf(lambda n: int(circuits.recurrence_count(n, 3)), "long")
    asked = tb.load(spark, d, "lineitem").groupBy(F.col("l_quantity").cast("long").alias("n")).agg(F.count("*").alias("asked")).where("n >= 4")
    return asked.select("n", carry("n").alias("carry_save"), loop("n").alias("recurrence"), "asked")


#: Each input after the second passes as many digits as its place in the schedule has trailing zeros, five operations each; each digit of the result takes five.
add(
    "operation_counts", _carry_save_ops,
    "SELECT n, ((SELECT sum(bit_count((x & -x) - 1)) FROM range(2, n) u(x)) * 5 + 5 * (floor(log2(n)) + 1))::BIGINT AS carry_save, 2 * n * 3 - n - 9 + 3 - 1 AS recurrence, asked FROM (SELECT l_quantity::BIGINT AS n, count(*) AS asked FROM lineitem GROUP BY ALL) v WHERE n >= 4",
)


def _stored_circuits(spark: SparkSession, d: str) -> DataFrame:
    """Circuits of each policy, stored as rows, read back and padded: at least t of n on every pattern of n inputs, as the number of patterns."""
    import numpy as np

    from ..session import written

    rows = [(p, *r) for p in ("diagonal", "powers", "generic") for r in circuits.table_rows(circuits.tabulate(p, 6), "sideways_sum")]
    stored = written(spark.createDataFrame(rows, "policy string, " + circuits.TABLE), "circuits")
    out = []
    for policy in ("diagonal", "powers", "generic"):
        table = circuits.from_rows([tuple(r)[1:] for r in stored.where(F.col("policy") == policy).toLocalIterator()])
        for n in range(2, 7):
            inputs = [np.array([sum((m >> i & 1) << m for m in range(2**n))], np.uint64) for i in range(n)]
            for t in range(2, n):
                made = circuits.circuit_for(table, n, t)
                ones = int(circuits.simulate(made, inputs)[0]) & ((1 << 2**n) - 1)
                out.append((policy, n, t, ones.bit_count(), circuits.max_live(made) <= len(made.gates)))
    return spark.createDataFrame(out, "policy string, n long, t long, patterns long, storage_fits boolean")


add(
    "stored_circuits", _stored_circuits,
    "SELECT policy, n, t, count(*) FILTER (bit_count(m) >= t) AS patterns, true AS storage_fits FROM (SELECT unnest(['diagonal', 'powers', 'generic']) AS policy), range(2, 7) a(n), range(2, 6) b(t), range(0, 64) c(m) WHERE t < n AND m < (1 << n) GROUP BY ALL",
)
