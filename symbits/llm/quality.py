"""Quality rules from cross-document line frequency, with basic word statistics. Native: no Python on the executors.

Lines are split at \\n. A line counts if it has a word; its normal form is lower case with runs of white space
made one space and ends trimmed. Per host, the distinct documents that hold a normal form are counted;
exact copies of a text are one document. Lines over the limit are removed; a document of whose words
too few remain is rejected as depleted.

Defined results: null text counts as empty (0 words, base rules fail); a null host is a host of its own;
repeated rows each get their own, equal result; an empty table has none; extra columns are ignored by the statistics and
kept by ``clean_documents``, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import BLANK_CLASS, BLANKS, words_of

SYMBOLS = "#*$%&|<>"
#: Positions take this many low bits of a packed window key; the rest are hash bits.
POSITION_BITS = 22

MAX_DOCS_PER_HOST = 10
MIN_REMAINING = 0.2

#: A one-element array binds a value to a name, so that the lambdas inside don't compute it again.
_WINDOWS = """
  element_at(transform(array(__w), w -> if(size(w) >= 3,
    transform(sequence(0, size(w) - 3), i -> xxhash64(w[i], w[i + 1], w[i + 2])),
    cast(array() as array<bigint>))), 1)"""

#: Packed keys (hash bits, position), sorted: equal windows are neighbours. A neighbour whose
#: full hash differs although the kept bits agree makes the result -2, and the slow form is taken.
_FAST = """
  element_at(transform(array(named_struct('h', {grams}, 's', sort_array(transform({grams}, (g, i) -> (g & {high}) | cast(i as bigint))))), t ->
    filter(transform(t.s, (x, j) ->
      if(j > 0 and (x ^ t.s[j - 1]) & {high} = 0,
         if(t.h[cast(x & {low} as int)] = t.h[cast(t.s[j - 1] & {low} as int)], x & {low}, -2L),
      if(j < size(t.s) - 1 and (x ^ t.s[j + 1]) & {high} = 0,
         if(t.h[cast(x & {low} as int)] = t.h[cast(t.s[j + 1] & {low} as int)], x & {low}, -2L),
         -1L))), p -> p <> -1L)), 1)"""

#: The same positions by sorting pairs of full hash and position: for huge texts and clashing bits.
_SLOW = """
  element_at(transform(array(array_sort(transform({grams}, (g, i) -> struct(g as h, cast(i as bigint) as p)))), s ->
    transform(filter(transform(s, (x, j) -> struct(
        (j > 0 and x.h = s[j - 1].h) or (j < size(s) - 1 and x.h = s[j + 1].h) as again, x.p as p)),
      y -> y.again), y -> y.p)), 1)"""

#: Words covered by windows of three that start at sorted positions.
_COVERED = """
  element_at(transform(array(sort_array({positions})), p ->
    aggregate(transform(p, (x, k) -> if(k + 1 < size(p), least(3L, p[k + 1] - x), 3L)), 0L, (a, b) -> a + b)), 1)"""


def _covered(positions: str) -> str:
    return _COVERED.format(positions=positions)


def base_statistics(docs: DataFrame) -> DataFrame:
    """docs with n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words and base_failed."""
    text = F.coalesce(F.col("text"), F.lit(""))
    mask = {"high": -(1 << POSITION_BITS), "low": (1 << POSITION_BITS) - 1}
    windows = F.expr(_WINDOWS)
    fast = F.expr(_FAST.format(grams="__g", **mask))
    slow = F.expr(_SLOW.format(grams="__g"))
    huge = F.size("__g") > mask["low"]
    return (
        docs.withColumn("__t", text)
        .withColumn("__w", words_of(F.col("__t")))
        .withColumn("__g", windows)
        .withColumn("__f", F.when(~huge, fast))
        .withColumn("__p", F.when(huge | F.exists("__f", lambda x: x == -2), slow).otherwise(F.col("__f")))
        .withColumn("__l", F.filter(F.split("__t", "\n"), lambda x: F.length(F.btrim(x, F.lit(BLANKS))) > 0))
        .withColumn("n_words", F.size("__w").cast("long"))
        .withColumn("word_chars", F.length(F.translate("__t", BLANKS, "")).cast("long"))
        .withColumn("n_symbols", (F.length("__t") - F.length(F.translate("__t", SYMBOLS, ""))).cast("long"))
        .withColumn("n_dup_lines", (F.size("__l") - F.size(F.array_distinct("__l"))).cast("long"))
        .withColumn("n_repeat_words", F.expr(_covered("__p")))
        .withColumn("base_failed", (F.col("n_words") < 50) | (F.col("n_repeat_words") * 100 > F.col("n_words") * 50))
        .drop("__t", "__w", "__g", "__f", "__p", "__l")
    )


def normal_line(line: Column) -> Column:
    return F.lower(F.btrim(F.regexp_replace(line, BLANK_CLASS + "+", " ")))


def _line_rows(docs: DataFrame) -> DataFrame:
    """One row per line with a word: document key, host-and-line key, words in the line."""
    lines = F.filter(F.split("text", "\n"), lambda x: F.length(F.btrim(x, F.lit(BLANKS))) > 0)
    host = F.xxhash64("source")
    return (
        docs.where(F.col("text").isNotNull())
        .select(*_document_key(), F.explode(lines).alias("line"), host.alias("host"))
        .select("doc_id", "host", "text_key", F.xxhash64("host", normal_line(F.col("line"))).alias("line_key"), F.size(words_of(F.col("line"))).cast("long").alias("words"))
    )


def _document_key() -> list[Column]:
    return [F.col("doc_id"), F.xxhash64("text").alias("text_key")]


def frequent_lines(docs: DataFrame, max_docs: int = MAX_DOCS_PER_HOST) -> DataFrame:
    """line_key (of host and normal form) and n_docs, for lines in more than max_docs documents of a host."""
    return (
        _line_rows(docs)
        .select("line_key", "text_key").distinct()
        .groupBy("line_key").agg(F.count("*").alias("n_docs"))
        .where(F.col("n_docs") > max_docs)
    )


def removed_lines(docs: DataFrame, max_docs: int = MAX_DOCS_PER_HOST, min_remaining: float = MIN_REMAINING) -> DataFrame:
    """Per distinct document with a line to remove: lines (their keys), words and gone (words in all and removed), depleted."""
    rows = _line_rows(docs)
    hot = frequent_lines(docs, max_docs).select("line_key", F.lit(True).alias("frequent"))
    per_line = rows.groupBy("doc_id", "host", "text_key", "line_key").agg(F.sum("words").alias("words"))
    return (
        per_line.join(hot, "line_key", "left")
        .groupBy("doc_id", "host", "text_key")
        .agg(
            F.sum("words").alias("words"),
            F.sum(F.when(F.col("frequent"), F.col("words")).otherwise(0)).alias("gone"),
            F.collect_list(F.when(F.col("frequent"), F.col("line_key"))).alias("lines"),
        )
        .where(F.col("gone") > 0)
        .withColumn("depleted", F.col("words") - F.col("gone") < F.col("words") * min_remaining)
    )


def _with_verdict(docs: DataFrame, every: DataFrame, max_docs: int, min_remaining: float) -> DataFrame:
    """docs with __lines (keys of lines to remove) and __depleted; lines are counted over every document."""
    found = removed_lines(every, max_docs, min_remaining).select(
        F.col("doc_id").alias("__d"), F.col("host").alias("__h"), F.col("text_key").alias("__k"), F.col("lines").alias("__lines"), F.col("depleted").alias("__depleted")
    )
    keyed = docs.withColumn("__host", F.xxhash64("source")).withColumn("__key", F.xxhash64("text"))
    on = F.col("doc_id").eqNullSafe(F.col("__d")) & (F.col("__host") == F.col("__h")) & (F.col("__key") == F.col("__k"))
    return keyed.join(found, on, "left").drop("__d", "__h", "__k", "__key")


def judge_documents(docs: DataFrame, max_docs: int = MAX_DOCS_PER_HOST, min_remaining: float = MIN_REMAINING) -> DataFrame:
    """Per row of docs (doc_id, text, source): doc_id, the base statistics, base_failed, depleted, kept."""
    base = base_statistics(docs.select("doc_id", "text", "source")).withColumn("__host", F.xxhash64("source")).withColumn("__key", F.xxhash64("text")).drop("text", "source")
    found = removed_lines(docs, max_docs, min_remaining).where("depleted").select(F.col("doc_id").alias("__d"), F.col("host").alias("__h"), F.col("text_key").alias("__k"))
    on = F.col("doc_id").eqNullSafe(F.col("__d")) & (F.col("__host") == F.col("__h")) & (F.col("__key") == F.col("__k"))
    return base.join(found, on, "left").withColumn("depleted", F.col("__k").isNotNull()).withColumn("kept", ~F.col("base_failed") & ~F.col("depleted")).drop("__d", "__h", "__k", "__host", "__key")


def clean_documents(docs: DataFrame, max_docs: int = MAX_DOCS_PER_HOST, min_remaining: float = MIN_REMAINING) -> DataFrame:
    """The documents that judge_documents() keeps, all their columns, text without the removed lines and n_chars (if there) anew."""
    whole = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("__row")
    based = base_statistics(docs.select("doc_id", "text", "source", whole))
    # a row number, true for every row: the filter then isn't moved below the statistics, whose expressions it would write out again many times
    passed = based.withColumn("__n", F.monotonically_increasing_id()).where(~F.col("base_failed") & (F.col("__n") >= 0)).select("__row", "doc_id", "text", "source")
    judged = _with_verdict(passed, docs, max_docs, min_remaining).where(~F.coalesce("__depleted", F.lit(False)))
    line_key = lambda x: F.xxhash64(F.col("__host"), normal_line(x))
    kept = F.array_join(F.filter(F.split("text", "\n"), lambda x: ~F.array_contains("__lines", line_key(x))), "\n")
    out = judged.withColumn("__text", F.when(F.col("__lines").isNotNull(), kept).otherwise(F.col("text")))
    own = {"text": F.col("__text"), "n_chars": F.length("__text").cast("long")}
    return out.select(*[own.get(c, F.col("__row").getField(c)).alias(c) for c in docs.columns])
