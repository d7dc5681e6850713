"""Views of the base tables as rows with criteria, or as members of sets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

ORDER_ATTRS = ("o_orderstatus", "o_orderpriority", "c_mktsegment", "n_nationkey", "n_regionkey", "o_year", "o_month", "o_dow", "o_custkey", "price_band", "acct_band")
LINE_KEY = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_shipdate", "l_extendedprice")
LINE_ATTRS = ("l_returnflag", "l_linestatus", "l_linenumber", "quantity_band", "discount_pct", "tax_pct", "ship_year", "ship_month", "l_suppkey", "p_brand", "p_type", "size_band", "s_nationkey")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_any(spark: SparkSession, path: str, kind: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """Parquet, ORC, CSV, JSON or text; a schema spares the pass that infers it."""
    reader = spark.read.format(kind).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def band(column: str, width: float) -> Column:
    return F.floor(F.col(column) / width).cast("long")


def orders_wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per order, rid = o_orderkey, with eleven attributes; o_custkey has most of the values."""
    orders, customer, nation = (load(spark, sf_dir, t) for t in ("orders", "customer", "nation"))
    return (
        orders.join(customer, F.col("o_custkey") == F.col("c_custkey"))
        .join(nation, F.col("c_nationkey") == F.col("n_nationkey"))
        .select(
            "o_orderkey", "o_orderstatus", "o_orderpriority", "c_mktsegment", "n_nationkey", "n_regionkey",
            F.year("o_orderdate").alias("o_year"), F.month("o_orderdate").alias("o_month"), (F.dayofweek("o_orderdate") - 1).alias("o_dow"), "o_custkey",
            band("o_totalprice", 50000).alias("price_band"), band("c_acctbal", 1000).alias("acct_band"),
        )
    )


def line_wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    lineitem, part, supplier = (load(spark, sf_dir, t) for t in ("lineitem", "part", "supplier"))
    return (
        lineitem.join(part, F.col("l_partkey") == F.col("p_partkey"))
        .join(supplier, F.col("l_suppkey") == F.col("s_suppkey"))
        .select(
            *LINE_KEY, "l_returnflag", "l_linestatus", band("l_quantity", 10).alias("quantity_band"), F.round(F.col("l_discount") * 100).cast("int").alias("discount_pct"),
            F.round(F.col("l_tax") * 100).cast("int").alias("tax_pct"), F.year("l_shipdate").alias("ship_year"), F.month("l_shipdate").alias("ship_month"), "p_brand", "p_type", band("p_size", 10).alias("size_band"), "s_nationkey",
        )
    )


def grams(text: Column, q: int, pad: bool = False) -> Column:
    """Array of (gram, ordinal): the q-grams of a string, each occurrence of one counted from 1. pad adds q - 1 marks at both ends."""
    s = F.concat(F.lit("^" * (q - 1)), text, F.lit("$" * (q - 1))) if pad else text
    every = F.when(F.length(s) >= q, F.transform(F.sequence(F.lit(1), F.greatest(F.length(s) - q + 1, F.lit(1))), lambda i: F.substring(s, i, F.lit(q)))).otherwise(F.array().cast("array<string>"))
    return F.transform(every, lambda g, i: F.struct(g.alias("gram"), F.size(F.filter(F.slice(every, F.lit(1), i + 1), lambda h: h == g)).alias("ordinal")))


def name_grams(names: DataFrame, rid: str, name: str, q: int, pad: bool = False) -> DataFrame:
    """attr gram, value gram#ordinal, rid."""
    return names.select(F.col(rid).cast("long").alias("rid"), F.inline(grams(F.col(name), q, pad))).select(F.lit("gram").alias("attr"), F.concat_ws("#", "gram", F.col("ordinal").cast("string")).alias("value"), "rid")


def text_chunks(docs: DataFrame, least: int = 1000, longest: int = 20000) -> DataFrame:
    """doc_id, chunk_no, text: paragraphs joined until a chunk has at least that many characters; longer paragraphs than longest are left out."""
    paragraphs = F.filter(F.split(F.coalesce("text", F.lit("")), "\n"), lambda p: (F.length(p) <= longest) & (F.length(p) > 0))
    empty = F.struct(F.array().cast("array<string>").alias("done"), F.lit("").alias("open"))

    def step(a: Column, p: Column) -> Column:
        more = F.when(F.length(a["open"]) > 0, F.concat_ws(" ", a["open"], p)).otherwise(p)
        ready = F.length(more) >= least
        return F.struct(F.when(ready, F.concat(a["done"], F.array(more))).otherwise(a["done"]).alias("done"), F.when(ready, F.lit("")).otherwise(more).alias("open"))

    chunks = F.aggregate(paragraphs, empty, step, lambda a: F.when(F.length(a["open"]) > 0, F.concat(a["done"], F.array(a["open"]))).otherwise(a["done"]))
    return docs.select("doc_id", F.posexplode(chunks).alias("chunk_no", "text"))


def chunk_grams(chunks: DataFrame, q: int) -> DataFrame:
    """attr gram, value a run of q characters of the lower-cased text, rid: each once for a chunk."""
    every = F.transform(F.array(F.lower("text")), lambda x: F.when(F.length(x) >= q, F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.length(x) - q + 1, F.lit(1))), lambda i: F.substring(x, i, F.lit(q))))))[0]
    return chunks.select(F.lit("gram").alias("attr"), F.explode(every).alias("value"), "rid")


def vocabulary(docs: DataFrame) -> DataFrame:
    """doc_id, word: distinct words of the letters a to z, lower-cased, up to 20 of them."""
    words = F.array_distinct(F.filter(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0)), lambda w: F.length(w) <= 20))
    return docs.select("doc_id", F.explode(words).alias("word"))


def event_sets(events: DataFrame) -> DataFrame:
    """Members type:*, user:*, k:* (of the JSON) and hour:* (of the time: runs), rid = event_id."""
    kinds = {"type": F.col("event_type"), "user": F.col("user_id"), "k": F.get_json_object("props", "$.k"), "hour": F.date_trunc("hour", "ts").cast("long") / 3600}
    pairs = F.array(*[F.struct(F.lit(k).alias("attr"), (c.cast("long") if k == "hour" else c).cast("string").alias("value")) for k, c in kinds.items()])
    return events.select(F.col("event_id").alias("rid"), F.inline(pairs)).where(F.col("value").isNotNull()).select("attr", "value", "rid")


def embedding_signs(embeddings: DataFrame) -> DataFrame:
    """attr dim, value the dimension, rid = vec_id where its component is positive."""
    return embeddings.select(F.col("vec_id").alias("rid"), F.posexplode("embedding").alias("dim", "x")).where("x > 0").select(F.lit("dim").alias("attr"), F.col("dim").cast("string").alias("value"), "rid")


def supplier_sales(lineitem: DataFrame, discount: float = 0.08) -> DataFrame:
    """attr supplier, value l_suppkey, rid = l_partkey it sells at that discount or more."""
    return lineitem.where(F.col("l_discount") >= discount).select(F.lit("supplier").alias("attr"), F.col("l_suppkey").cast("string").alias("value"), F.col("l_partkey").alias("rid")).distinct()


def synthetic(spark: SparkSession, kind: str, rows: int, sets: int = 32, entries: int = 10_000, seed: int = 1111, lines: DataFrame | None = None) -> DataFrame:
    """Sets of up to that many entries among rows: uniform by a linear congruence, or clustered in runs of 1 to 64. With lines, of line items: each is an entry of the set that its number gives."""
    if lines is None:
        base = spark.range(sets).select(F.col("id").alias("s")).join(spark.range(entries).select(F.col("id").alias("i")))
    else:
        number = F.col("l_orderkey") * 7 + F.col("l_linenumber")
        base = lines.select((number % sets).alias("s"), F.floor(number / sets).cast("long").alias("i"))
    mixed = lambda a, b: (a * 1103515245 + b * 12345 + seed) % 2147483647
    if kind == "uniform":
        rid = mixed(mixed(F.col("i") + F.col("s") * entries, F.lit(7)), F.lit(1)) % rows
    elif kind == "clustered":
        run = F.floor(F.col("i") / 32).cast("long")
        rid = (mixed(mixed(run + F.col("s") * entries, F.lit(3)), F.lit(1)) + F.col("i") % 32) % rows
    else:
        raise ValueError("kind is uniform or clustered")
    return base.select(F.lit(kind).alias("attr"), F.col("s").cast("string").alias("value"), rid.cast("long").alias("rid")).distinct()


def page_tags(pages: DataFrame) -> DataFrame:
    """attr tag, value the lower-case name of an element that starts in the page, rid = page_id."""
    tags = F.array_distinct(F.transform(F.regexp_extract_all("html", F.lit("<([a-zA-Z][a-zA-Z0-9]*)"), F.lit(1)), F.lower))
    return pages.select(F.col("page_id").alias("rid"), F.explode(tags).alias("value")).select(F.lit("tag").alias("attr"), "value", "rid")


def shingles(texts: DataFrame, key: str, q: int = 3) -> DataFrame:
    """key, gram: distinct runs of q words of the letters a to z, lower-cased."""
    words = F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0))
    # bound by a lambda, the words aren't extracted again for each run
    runs = lambda w: F.when(F.size(w) >= q, F.transform(F.sequence(F.lit(1), F.greatest(F.size(w) - q + 1, F.lit(1))), lambda i: F.array_join(F.slice(w, i, F.lit(q)), " "))).otherwise(F.array().cast("array<string>"))
    return texts.select(key, F.explode(F.array_distinct(F.transform(F.array(words), runs)[0])).alias("gram"))
