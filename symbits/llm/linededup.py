"""Line deduplication by winnowing over line hashes. Native: no Python on the executors.

A document is a sequence of lines with a word (others are neither matched nor deleted). Every SHINGLE
consecutive lines are hashed together; of every WINDOW consecutive hashes the least, rightmost on ties, is a
fingerprint. Each SHINGLE + WINDOW - 1 consecutive lines hold WINDOW hashes and so a fingerprint, at the same place wherever they are
repeated: it is joined together with the lines around it that complete the window. So that few long lines are found as surely, the shortest run of LONG_WORDS words or more from each line on,
and the shortest one up to each line, are fingerprints too, be it of one line: each line of a repeat of so many words
lies in a run that is in both places. Each fingerprint's earliest place, by doc_id and line, is its source; other places are joined
to it on the fingerprint, and the match is extended line by line both ways. The later run is deleted.
What is deleted are thus all lines of later repeats of LEAST lines, or of LONG_WORDS words, and no others.

Places are joined with one source each, so the work grows with the places, not with their pairs.
Fingerprints of one place only leave before the join. Where a fingerprint or a source has more than HOT rows, these are salted over several
keys, and the source's row is repeated for each.

Defined results: null or blank texts stay as they are; lines compare after trimming white space, by a hash of 64 bits;
rows that share a doc_id are ordered by a hash of their text, and equal rows are one document, to which the same lines
are deleted; a null doc_id comes first; a document that loses all lines keeps an empty text; an empty table gives no rows; extra columns are kept, but for one named n_deleted,
which the result replaces.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import BLANKS, words_of, written

SHINGLE = 2
WINDOW = 2
LEAST = SHINGLE + WINDOW - 1
LONG_WORDS = 50
#: Rows of one join key from which on they are salted.
HOT = 100_000
MANY_HOT = 1 << 20

#: For each window of hashes, its least one's place, and the hash of all lines of the window.
_FINGERPRINTS = """
  element_at(transform(array(if(size(__h) >= {k}, transform(sequence(0, size(__h) - {k}), i -> xxhash64(slice(__h, i + 1, {k}))), cast(array() as array<bigint>))), g ->
    if(size(g) < {w}, cast(array() as array<struct<pos: int, f: bigint>>), array_distinct(
      transform(sequence(0, size(g) - {w}), s -> element_at(transform(array(slice(g, s + 1, {w})), v -> named_struct(
        'pos', s + size(v) - cast(array_position(reverse(v), array_min(v)) as int),
        'f', xxhash64(array_min(v), slice(__h, s + 1, {k} + {w} - 1)))), 1))))), 1)"""

#: Lines of the shortest run of so many words; none if there are fewer. Each line has a word, so that {least} lines are enough.
_SHORTEST = """aggregate({words}, named_struct('n', 0, 'sum', 0), (a, x) -> if(a.sum >= {least}, a, named_struct('n', a.n + 1, 'sum', a.sum + x)), a -> if(a.sum >= {least}, a.n, 0))"""

#: The shortest long runs from each line on and up to each line, as first line and hash.
_LONG = f"""
  transform(array_distinct(filter(concat(
      transform(__n, (x, i) -> named_struct('pos', i, 'n', if(x >= {{least}}, 1, {_SHORTEST.format(words="slice(__n, i + 1, {least})", least="{least}")}))),
      transform(__n, (x, i) -> element_at(transform(array(if(x >= {{least}}, 1, {_SHORTEST.format(words="reverse(slice(__n, greatest(i + 2 - {least}, 1), least(i + 1, {least})))", least="{least}")})), n -> named_struct('pos', i + 1 - n, 'n', n)), 1))),
    r -> r.n > 0)), r -> named_struct('pos', r.pos, 'f', xxhash64(slice(__h, r.pos + 1, r.n))))"""

#: Lines of the run around each matched line pair (p in this document, q in the source): equal neighbours both ways.
_RUNS = """
  flatten(transform(places, m -> element_at(transform(array(named_struct(
      'back', aggregate(sequence(1, least(m.p, m.q) + 1), named_struct('n', 0, 'go', true),
          (a, i) -> if(a.go and m.p - i >= 0 and m.q - i >= 0 and __h[greatest(m.p - i, 0)] = __s[greatest(m.q - i, 0)], named_struct('n', i, 'go', true), named_struct('n', a.n, 'go', false)), a -> a.n),
      'on', aggregate(sequence(0, least(size(__h) - m.p, size(__s) - m.q)), named_struct('n', 0, 'go', true),
          (a, i) -> if(a.go and m.p + i < size(__h) and m.q + i < size(__s) and __h[least(m.p + i, size(__h) - 1)] = __s[least(m.q + i, size(__s) - 1)], named_struct('n', i + 1, 'go', true), named_struct('n', a.n, 'go', false)), a -> a.n))),
    r -> if(r.back + r.on >= 1, sequence(m.p - r.back, m.p + r.on - 1), cast(array() as array<int>))), 1)))"""


def _documents(docs: DataFrame) -> DataFrame:
    """One row per distinct (doc_id, text) with a line: the hash and the number of words of its lines."""
    lines = F.filter(F.split("text", "\n"), lambda x: F.length(F.btrim(x, F.lit(BLANKS))) > 0)
    hashes = F.transform(lines, lambda x: F.xxhash64(F.btrim(x, F.lit(BLANKS))))
    words = F.transform(lines, lambda x: F.size(words_of(x)))
    return docs.where(F.col("text").isNotNull()).select("doc_id", _doc_key().alias("doc_key"), hashes.alias("__h"), words.alias("__n")).where(F.size("__h") > 0)


def _doc_key() -> Column:
    """16 bytes for a row's doc_id and text; null for null text."""
    return F.unhex(F.md5(F.concat(F.md5("text"), F.coalesce(F.col("doc_id").cast("string"), F.lit("null")))))


def _salted(rows: DataFrame, key: str, one: DataFrame, one_key: str, counts: DataFrame) -> DataFrame:
    """rows joined with the row of one that has the same key (never null); counts (key, n) has the rows of each key.

    Keys of more than HOT rows are dealt to several; there are at most rows / HOT such keys, and they are broadcast if that is up to MANY_HOT.
    """
    hot = written(counts.where(F.col("n") > HOT).select(F.col(key).alias("__hot"), F.ceil(F.col("n") / HOT).cast("int").alias("__salts")), "hot")
    if not 0 < hot.count() <= MANY_HOT:  # none, or so many that they are spread by themselves
        return rows.join(one, F.col(key) == F.col(one_key)).drop(one_key)
    salts = F.coalesce("__salts", F.lit(1))
    dealt = rows.join(F.broadcast(hot), F.col(key) == F.col("__hot"), "left").withColumn("__salt", F.pmod(F.xxhash64(*rows.columns), salts).cast("int")).drop("__hot", "__salts")
    each = one.join(F.broadcast(hot), F.col(one_key) == F.col("__hot"), "left").withColumn("__salt_of", F.explode(F.sequence(F.lit(0), salts - 1))).drop("__hot", "__salts")
    return dealt.join(each, (F.col(key) == F.col(one_key)) & (F.col("__salt") == F.col("__salt_of"))).drop(one_key, "__salt", "__salt_of")


def repeated_lines(docs: DataFrame) -> DataFrame:
    """doc_key (of doc_id and text), lines: positions, among the lines with a word, that a repeat of an earlier run covers."""
    own = written(_documents(docs).distinct(), "lines")
    place = F.struct(F.col("doc_id"), F.col("doc_key"), F.col("pos"))
    fingerprints = F.array_distinct(F.concat(F.expr(_FINGERPRINTS.format(k=SHINGLE, w=WINDOW)), F.expr(_LONG.format(least=LONG_WORDS))))
    places = written(own.select("doc_id", "doc_key", F.inline(fingerprints)), "places")
    sources = written(places.groupBy("f").agg(F.min(place).alias("source"), F.count("*").alias("n")).where("n > 1"), "sources")
    joined = _salted(places, "f", sources.select(F.col("f").alias("s_f"), "source"), "s_f", sources)
    matches = joined.where(place != F.col("source")).select("doc_key", F.col("source.doc_key").alias("s_key"), F.col("pos").alias("p"), F.col("source.pos").alias("q"))
    # one place of each diagonal run is enough, but a diagonal may hold several runs: keep all places
    grouped = written(matches.groupBy("doc_key", "s_key").agg(F.collect_list(F.struct("p", "q")).alias("places")), "matches")
    source = own.select(F.col("doc_key").alias("s_doc"), F.col("__h").alias("__s"))
    pairs = _salted(grouped, "s_key", source, "s_doc", grouped.groupBy("s_key").agg(F.count("*").alias("n")))
    runs = pairs.join(own.select("doc_key", "__h"), "doc_key").select("doc_key", F.array_distinct(F.expr(_RUNS)).alias("lines"))
    return runs.groupBy("doc_key").agg(F.array_distinct(F.flatten(F.collect_list("lines"))).alias("lines"))


def dedup_lines(docs: DataFrame) -> DataFrame:
    """docs with later repeated runs of lines deleted from text, and n_chars (if there) anew; n_deleted is added."""
    found = repeated_lines(docs).where(F.size("lines") > 0).select(F.col("doc_key").alias("__k"), F.col("lines").alias("__gone"))
    # number the lines with a word, drop the marked ones, keep the rest and the blank lines in order
    kept = F.expr(f"""
      aggregate(split(text, '\\n'), named_struct('n', 0, 'out', cast(array() as array<string>)),
        (a, x) -> if(length(btrim(x, '{BLANKS.encode("unicode_escape").decode()}')) = 0, named_struct('n', a.n, 'out', array_append(a.out, x)),
          named_struct('n', a.n + 1, 'out', if(array_contains(__gone, a.n), a.out, array_append(a.out, x)))),
        a -> array_join(a.out, '\\n'))""")
    out = docs.withColumn("__key", _doc_key()).join(found, F.col("__key") == F.col("__k"), "left")
    out = out.withColumn("n_deleted", F.when(F.col("__gone").isNull(), F.lit(0)).otherwise(F.size("__gone")).cast("long"))
    out = out.withColumn("text", F.when(F.col("__gone").isNull(), F.col("text")).otherwise(kept))
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.length("text").cast("long"))
    return out.select(*[c for c in docs.columns if c != "n_deleted"], "n_deleted")
