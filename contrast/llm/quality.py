"""Quality rules: shape counts of a text, and a hashed n-gram likelihood ratio of trusted to raw text.

Words and pairs of neighbouring words are hashed into a fixed number of buckets. Two multinomials
over the buckets are estimated: one from the whole corpus, with add-one smoothing, and one from the
trusted documents, with a prior that is dealt like the raw corpus. A document's score is the mean, over its words and word pairs, of the log ratio of the
two; it is kept at or above a fixed threshold. The tables have the size of the bucket count, whatever
the corpus. Everything is DataFrame expressions.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from contrast.llm.common import bind, materialise, spaced, words

BUCKETS = 1 << 14
#: Mean log ratio (nats) from which a document is kept; ordinary text lies near zero.
THRESHOLD = -0.04
#: Grams for each bucket that the trusted counts are filled up with, dealt as in the raw corpus: with few
#: trusted documents the ratios shrink towards none.
PRIOR = 30
MIN_WORDS = 50
#: Per cent of the words that may lie in repeated windows.
MAX_REPEATED = 50


def shape_counts(text: Column, tokens: Column) -> dict[str, Column]:
    """The counts of the base rules; tokens must be words(text) as a column of its own."""
    lines = F.filter(F.split(F.coalesce(text, F.lit("")), "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    return {
        "n_words": F.size(tokens).cast("long"),
        "word_chars": F.length(F.replace(spaced(text), F.lit(" "), F.lit(""))).cast("long"),
        "n_symbols": F.coalesce(F.regexp_count(text, F.lit("[#*$%&|<>]")), F.lit(0)).cast("long"),
        "n_dup_lines": bind(lines, lambda x: F.size(x) - F.size(F.array_distinct(x))).cast("long"),
        "n_repeat_words": repeated_words(tokens),
    }


def repeated_words(tokens: Column, width: int = 3) -> Column:
    """Words that lie in a window of so many words found twice or more in the text.

    Windows are compared by 64-bit hashes of their words' hashes. Equal ones stand side by side after
    a sort, so a text of any length costs n log n; a text without equal windows isn't sorted.
    """
    last = F.size(tokens) - width

    def marked(found: Column) -> Column:
        """found: (hash, place) in order."""
        same = lambda x, k: x["h"] == F.get(found, k)["h"]
        twice = F.filter(found, lambda x, k: F.coalesce(same(x, k - 1), F.lit(False)) | F.coalesce(same(x, k + 1), F.lit(False)))
        places = F.array_sort(F.transform(twice, lambda x: x["i"]))
        begin = F.struct(F.lit(0).alias("n"), F.lit(0).alias("end"))
        step = lambda a, i: F.struct((a["n"] + i + width - F.greatest(i, a["end"])).alias("n"), (i + width).alias("end"))
        return F.aggregate(places, begin, step, lambda a: a["n"])

    def of(hashes: Column) -> Column:
        windows = F.transform(F.sequence(F.lit(0), last), lambda i: F.xxhash64(*(F.get(hashes, i + k) for k in range(width))))
        pairs = lambda w: F.array_sort(F.transform(w, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
        return bind(windows, lambda w: F.when(F.size(F.array_distinct(w)) == F.size(w), 0).otherwise(bind(pairs(w), marked)))

    hashes = F.transform(tokens, lambda w: F.xxhash64(w))
    return F.when(last < 0, 0).otherwise(bind(hashes, of)).cast("long")


def gram_buckets(tokens: Column, buckets: int = BUCKETS) -> Column:
    """A bucket for each word and each pair of neighbours; tokens must be a column of its own."""

    def of(hashes: Column) -> Column:
        pairs = F.zip_with(F.slice(hashes, 1, F.size(hashes) - 1), F.slice(hashes, 2, F.size(hashes)), lambda a, b: F.xxhash64(a, b))
        return F.transform(F.concat(hashes, pairs), lambda h: F.pmod(h, F.lit(buckets)).cast("int"))

    hashes = F.transform(tokens, lambda w: F.xxhash64(w))
    return F.when(F.size(tokens) == 0, F.array().cast("array<int>")).otherwise(bind(hashes, of))


def log_ratios(docs: DataFrame, trusted: DataFrame, id_column: str = "doc_id", buckets: int = BUCKETS) -> DataFrame:
    """One row, `weights array<double>`: log of trusted to raw probability of each bucket.

    docs: id and text. trusted: ids of the trusted documents; repeats count once. Both may be of any
    size: only bucket counts leave a task. With no trusted document all weights are zero.
    """
    good = trusted.select(F.col(id_column).alias("__id")).where("__id is not null").distinct().withColumn("__good", F.lit(1))
    marked = docs.select(F.col(id_column).alias("__id"), F.col("text").alias("__text")).join(good.hint("shuffle_hash"), "__id", "left")
    counted = (
        marked.select("__good", words(F.col("__text")).alias("__words"))
        .select("__good", F.explode(gram_buckets(F.col("__words"), buckets)).alias("b"))
        .groupBy("b")
        .agg(F.count(F.lit(1)).cast("double").alias("raw"), F.count("__good").cast("double").alias("good"))
    )
    every = docs.sparkSession.range(buckets).select(F.col("id").cast("int").alias("b")).join(counted, "b", "left").na.fill(0.0)
    gathered = every.agg(F.array_sort(F.collect_list(F.struct("b", "raw", "good"))).alias("c"), F.sum("raw").alias("raw"), F.sum("good").alias("good"))
    prior = float(PRIOR * buckets)
    share = lambda x: (x["raw"] + 1) / (F.col("raw") + buckets)
    ratio = lambda x: F.log((x["good"] + prior * share(x)) / (F.col("good") + prior)) - F.log(share(x))
    return gathered.select(F.transform("c", ratio).alias("weights"))


def judged(docs: DataFrame, trusted: DataFrame, id_column: str = "doc_id", threshold: float = THRESHOLD, buckets: int = BUCKETS) -> DataFrame:
    """docs with the shape counts, base_failed, `llr` (mean log ratio; 0 without words) and kept.

    A null text is empty, and empty texts fail the base rule. Rows are judged one by one: repeated
    rows get equal verdicts, rows with a null id too. Result columns replace columns of their names.
    """
    made = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "llr", "kept", "__words", "__grams", "__w"]
    plain = docs.drop(*made)
    weights = materialise(log_ratios(docs, trusted, id_column, buckets), "log_ratios")
    parsed = plain.select("*", words(F.col("text")).alias("__words"))
    counted = parsed.select("*", *(c.alias(n) for n, c in shape_counts(F.col("text"), F.col("__words")).items()), gram_buckets(F.col("__words"), buckets).alias("__grams"), weights.scalar().alias("__w"))
    mean = F.when(F.size("__grams") == 0, 0.0).otherwise(F.aggregate("__grams", F.lit(0.0), lambda a, b: a + F.get(F.col("__w"), b)) / F.size("__grams"))
    failed = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEATED * F.col("n_words"))
    return counted.select("*", failed.alias("base_failed"), mean.alias("llr")).select("*", (~F.col("base_failed") & (F.col("llr") >= threshold)).alias("kept")).drop("__words", "__grams", "__w")

