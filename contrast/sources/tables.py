"""The given tables, and the attributes that workloads derive from them.

Each of the feature tables has an id, the attributes, and `cls`, the class label as a string.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from contrast.schema import HybridSchema, number, symbol
from contrast.session import settled


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _percent(part, whole):
    return F.floor(100 * part.cast("double") / whole).cast("long")


def document_features(spark: SparkSession, sf_dir: str, label: str = "quality") -> DataFrame:
    """Shape of the labelled documents' texts; the other label is a symbol.

    Texts are measured before they meet their labels, so that none is shuffled, and once for all that reads the table.
    """
    labels = table(spark, sf_dir, "labels")
    other = "toxic" if label == "quality" else "quality"
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source")
    text = F.col("text")
    tokens = docs.select("doc_id", "lang", "source", "text", F.regexp_extract_all(text, F.lit(r"\S+"), F.lit(0)).alias("tokens"))
    size, n = F.length("text").cast("long"), F.size("tokens").cast("long")
    count = lambda p: F.regexp_count(text, F.lit(p))
    shapes = tokens.where("length(text) > 0 and size(tokens) > 0").select(
        "doc_id",
        size.alias("n_chars"),
        n.alias("n_words"),
        (count("\n") + 1).cast("long").alias("n_lines"),
        _percent(count("[A-Z]"), size).alias("upper_pct"),
        _percent(count("[!*$&%#@]"), size).alias("junk_pct"),
        _percent(count("[0-9]"), size).alias("digit_pct"),
        _percent(F.size(F.array_distinct("tokens")), n).alias("uniq_pct"),
        F.floor(10 * size.cast("double") / n).cast("long").alias("word_len10"),
        "lang",
        "source",
    )
    return settled(shapes.join(labels.select("doc_id", F.col(other).cast("string").alias(other), F.col(label).cast("string").alias("cls")), "doc_id"), "shapes")


#: Attributes of the document workload, narrow ones first; the two wide ones make the stress test.
DOCUMENTS = HybridSchema((number("uniq_pct"), number("upper_pct"), symbol("lang"), number("junk_pct"), number("word_len10"), number("digit_pct"), number("n_lines"), symbol("source")))
DOCUMENTS_WIDE = HybridSchema((*DOCUMENTS.attributes, number("n_words", 20.0), number("n_chars", 100.0)))
DOCUMENTS_SMALL = HybridSchema((number("uniq_pct"), number("upper_pct"), symbol("lang")))


def conversation_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = table(spark, sf_dir, "conversations")
    marks = F.regexp_count("text", F.lit("[!*$&%#@]"))
    return turns.select("conv_id", "turn", F.length("text").cast("long").alias("n_chars"), F.size(F.regexp_extract_all("text", F.lit(r"\S+"), F.lit(0))).cast("long").alias("n_words"), marks.cast("long").alias("n_marks"), F.col("role").alias("cls"))


CONVERSATIONS = HybridSchema((number("turn"), number("n_chars", 20.0), number("n_words", 5.0), number("n_marks")))


def embedding_features(spark: SparkSession, sf_dir: str, components: tuple[int, ...] = (0, 1, 2, 3)) -> DataFrame:
    return table(spark, sf_dir, "embeddings").select("vec_id", *(F.col("embedding")[i].cast("double").alias(f"e{i}") for i in components), F.col("label").cast("string").alias("cls"))


EMBEDDINGS = HybridSchema(tuple(number(f"e{i}", 0.05) for i in range(4)))


def order_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders with their customers' places: small dimension tables, joined as Spark sees fit."""
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderpriority", F.month("o_orderdate").alias("month"))
    customer = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey", "c_acctbal", "c_mktsegment")
    place = table(spark, sf_dir, "nation").join(table(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "r_name")
    joined = orders.join(customer, F.col("o_custkey") == F.col("c_custkey")).join(place, F.col("c_nationkey") == F.col("n_nationkey"))
    return joined.select("o_orderkey", "o_totalprice", "c_acctbal", "month", "o_orderpriority", "c_mktsegment", "r_name", F.col("o_orderstatus").alias("cls"))


ORDERS = HybridSchema((number("o_totalprice", 10_000.0), number("c_acctbal", 1000.0), number("month"), symbol("o_orderpriority"), symbol("c_mktsegment"), symbol("r_name")))


def lineitem_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem").select("l_partkey", "l_suppkey", "l_quantity", "l_discount", "l_tax", "l_linestatus", "l_returnflag")
    part = table(spark, sf_dir, "part").select("p_partkey", "p_size", "p_type", "p_brand")
    supplier = table(spark, sf_dir, "supplier").select("s_suppkey")
    joined = lines.join(part, F.col("l_partkey") == F.col("p_partkey")).join(supplier, F.col("l_suppkey") == F.col("s_suppkey"))
    return joined.select("l_quantity", "l_discount", "l_tax", "p_size", "p_type", "p_brand", "l_linestatus", F.col("l_returnflag").alias("cls"))


LINEITEMS = HybridSchema((number("l_quantity"), number("l_discount", 0.01), number("l_tax", 0.01), number("p_size"), symbol("p_type"), symbol("p_brand"), symbol("l_linestatus")))


def part_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "part").select("p_partkey", "p_size", "p_retailprice", F.col("p_type").alias("cls"))


PARTS = HybridSchema((number("p_size"), number("p_retailprice", 50.0)))


def page_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts of the addresses as presence flags; the class is the language of the path."""
    pages = table(spark, sf_dir, "pages").select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"), F.parse_url("url", F.lit("PATH")).alias("path"), F.regexp_count("html", F.lit("<p")).alias("n_p"))
    return pages.select("page_id", F.element_at(F.split("host", r"\."), -1).alias("top"), F.size(F.split("path", "/")).alias("depth"), "n_p", F.element_at(F.split("path", "/"), 2).alias("cls"))


def event_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = table(spark, sf_dir, "events")
    return events.select("event_id", "ts", "value", F.hour("ts").alias("hour"), F.get_json_object("props", "$.k").cast("int").alias("k"), F.col("event_type").alias("cls"))


EVENTS = HybridSchema((number("value"), number("hour"), number("k")))


def planted(spark: SparkSession, rows: int, seed: int = 7) -> DataFrame:
    """Rows with one known box: class 1 where x lies in [20, 40) and s is 'b', with noise of some 5 %."""
    base = spark.range(rows).select("id", F.floor(100 * F.rand(seed)).alias("x"), F.floor(100 * F.rand(seed + 1)).alias("y"), F.get(F.array(*map(F.lit, "abcd")), F.floor(4 * F.rand(seed + 2)).cast("int")).alias("s"), (F.rand(seed + 3) < 0.05).alias("noise"))
    inside = (F.col("x") >= 20) & (F.col("x") < 40) & (F.col("s") == "b")
    return base.select("id", "x", "y", "s", F.when(inside != F.col("noise"), "1").otherwise("0").alias("cls"))


PLANTED = HybridSchema((number("x", 5.0), symbol("s"), number("y", 10.0)))
