"""What patterns cover, which of them stay, and what stays in their place.

Tables: patterns (pattern_id, items, ...), tx (tx_id, codes, n_pos, n_neg). Each row meets the patterns
that cover it: few ones are sent to all tasks, more are joined by the codes of one of their items.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from contrast.functions.measures import Measure, associated
from contrast.functions.patterns import covers, item, pattern_id, subsumes
from contrast.session import FEW, few, settled


def covered(tx: DataFrame, patterns: DataFrame, most: int = FEW) -> DataFrame:
    """Each row with each pattern that covers it.

    Up to `most` patterns are broadcast. Beyond, a pattern is listed under each code of its narrowest
    item, rows under each of their codes, and what meets there is tested whole; the empty pattern covers all.
    """
    held = covers(F.col("items"), F.col("codes"))
    if few(patterns, most):
        return tx.join(F.broadcast(patterns), held)
    narrow = F.array_min(F.transform("items", lambda x: F.struct((x["hi"] - x["lo"]).alias("width"), x["attr"].alias("attr"), x["lo"].alias("lo"), x["hi"].alias("hi"))))
    listed = patterns.where("size(items) > 0").withColumn("__n", narrow).withColumn("__code", F.explode(F.sequence(F.col("__n.lo"), F.col("__n.hi") - 1))).withColumn("__attr", F.col("__n.attr"))
    rows = tx.select("*", F.posexplode("codes").alias("__attr", "__code")).where("__code >= 0")
    met = rows.join(listed, ["__attr", "__code"]).where(held).drop("__attr", "__code", "__n")
    return met.unionByName(tx.crossJoin(F.broadcast(patterns.where("size(items) = 0").limit(1))))


def pattern_stats(tx: DataFrame, patterns: DataFrame) -> DataFrame:
    """patterns (pattern_id, items) with n_pos and n_neg over all rows; zero where nothing is covered."""
    counts = covered(tx.select("codes", "n_pos", "n_neg"), patterns.select("pattern_id", "items")).groupBy("pattern_id").agg(F.sum("n_pos").alias("n_pos"), F.sum("n_neg").alias("n_neg"))
    return patterns.select("pattern_id", "items").join(counts, "pattern_id", "left").na.fill(0, ["n_pos", "n_neg"])


def with_shares(stats: DataFrame, p: int, n: int) -> DataFrame:
    """n_pos and n_neg with p_joint, p_pattern, conf, pos_supp, neg_supp."""
    a, b = F.col("n_pos"), F.col("n_neg")
    return stats.select("*", (a / (p + n)).alias("p_joint"), ((a + b) / (p + n)).alias("p_pattern"), F.try_divide(a, a + b).alias("conf"), (a / F.lit(p)).alias("pos_supp"), F.try_divide(b, F.lit(n)).alias("neg_supp"))


def candidate_lists(tx: DataFrame, patterns: DataFrame) -> DataFrame:
    """tx_id, pattern_id, score: the best patterns (with `score`) of each row that has positives, ties kept."""
    each = covered(tx.where("n_pos > 0").select("tx_id", "codes"), patterns.select("pattern_id", "items", "score"))
    return each.select("tx_id", "pattern_id", "score", F.rank().over(Window.partitionBy("tx_id").orderBy(F.col("score").desc())).alias("place")).where("place = 1").drop("place")


def offer(tx: DataFrame, patterns: DataFrame, most: int = FEW) -> DataFrame:
    """tx with `best` raised to the best score among the patterns that cover a row.

    Up to `most` patterns come as one array, best first, and rows don't move; beyond, rows meet them by
    covered() and join back on tx_id.
    """
    if few(patterns, most):
        scores = patterns.agg(F.array_sort(F.collect_list(F.struct((-F.col("score")).alias("down"), "items"))).alias("offers"))
        first = F.filter("__offers", lambda x: covers(x["items"], F.col("codes")))
        best = F.greatest(F.col("best"), -F.get(first, 0)["down"])
        return tx.withColumn("__offers", scores.scalar()).withColumn("best", F.when(F.col("n_pos") > 0, best).otherwise(F.col("best"))).drop("__offers")
    met = covered(tx.where("n_pos > 0").select("tx_id", "codes"), patterns.select("items", "score"), most)
    got = met.groupBy("tx_id").agg(F.max("score").alias("__best"))
    return tx.join(got, "tx_id", "left").withColumn("best", F.greatest("best", "__best")).select(*tx.columns)


def best_covering(tx: DataFrame, patterns: DataFrame) -> DataFrame:
    """Patterns that are the best, or tie, for some positive row."""
    return patterns.join(candidate_lists(tx, patterns).select("pattern_id").distinct(), "pattern_id", "left_semi")


def scoped_floors(tx: DataFrame, patterns: DataFrame) -> DataFrame:
    """pattern_id, floor: the least best score among the positive rows that a pattern covers; tx has `best`."""
    each = covered(tx.where("n_pos > 0").select("codes", "best"), patterns.select("pattern_id", "items"))
    return each.groupBy("pattern_id").agg(F.min("best").alias("floor"))


def closures(tx: DataFrame, patterns: DataFrame, is_symbol: Column, sizes: Column, on_all: bool = False) -> DataFrame:
    """pattern_id, closure: the most specific pattern with the same positive cover (or the same cover at all).

    For each attribute: the span of the covered rows' codes; no item where a row has none, where the
    span is the whole line, or where symbols differ.
    """
    rows = tx if on_all else tx.where("n_pos > 0")
    each = covered(rows.select("codes"), patterns.select("pattern_id", "items")).select("pattern_id", F.posexplode("codes").alias("attr", "code"))
    spans = each.groupBy("pattern_id", "attr").agg(F.min("code").alias("lo"), (F.max("code") + 1).alias("hi"))
    fits = (F.col("lo") >= 0) & F.when(is_symbol, F.col("hi") == F.col("lo") + 1).otherwise(~((F.col("lo") == 0) & (F.col("hi") == F.get(sizes, F.col("attr")))))
    one = F.when(fits, item(F.col("attr"), F.col("lo"), F.col("hi")))
    return spans.groupBy("pattern_id").agg(F.array_sort(F.collect_list(one)).alias("closure"))


def closed(tx: DataFrame, patterns: DataFrame, is_symbol: Column, sizes: Column, on_all: bool = False) -> DataFrame:
    """Patterns that are their own closure."""
    own = closures(tx, patterns, is_symbol, sizes, on_all)
    return patterns.join(own, "pattern_id").where("items = closure").drop("closure")


def productive(patterns: DataFrame) -> DataFrame:
    """Patterns (with `score`) that score more than every pattern that strictly subsumes them."""
    general = patterns.select(F.col("items").alias("g_items"), F.col("score").alias("g_score"))
    worse = (F.col("g_score") >= F.col("score")) & subsumes(F.col("g_items"), F.col("items"), strict=True)
    return patterns.join(F.broadcast(general) if few(general) else general, worse, "left_anti")


def finished(tx: DataFrame, found: DataFrame, measure: Measure, p: int, n: int, is_symbol: Column, sizes: Column) -> DataFrame:
    """The answer from candidates (items): their closures, counted over all rows, the best for some row.

    A closure scores no less than its pattern, so closedness goes before best covering. Closures and scores are
    settled, since each step counts its patterns before it meets them with rows; rows are dealt to all tasks, since
    few bytes, read as they are, come to one task, however many patterns they meet.
    """
    tasks = tx.sparkSession.sparkContext.defaultParallelism
    if tx.rdd.getNumPartitions() < tasks:
        tx = settled(tx.repartition(tasks, "tx_id"), "tx")
    own = found.select("items").distinct().select(pattern_id(F.col("items")).alias("pattern_id"), "items")
    general = settled(closures(tx, own, is_symbol, sizes).select(F.col("closure").alias("items")).where("size(items) > 0").distinct(), "closures")
    stats = with_shares(pattern_stats(tx, general.select(pattern_id(F.col("items")).alias("pattern_id"), "items")), p, n)
    scores = stats.select("*", measure.column(F.col("n_pos"), F.col("n_neg"), p, n).alias("score")).where(associated(F.col("n_pos"), F.col("n_neg"), F.lit(p), F.lit(n)))
    return best_covering(tx, settled(scores, "scores"))
