"""Rules from patterns: classifiers, and the reductions that rule learners use instead."""

from __future__ import annotations

from dataclasses import replace
from itertools import count

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from contrast.functions.measures import FSCORE, Measure
from contrast.functions.patterns import PATTERN, covers, pattern_id
from contrast.operators.constraints import covered
from contrast.plans.kernel import DENSE, Dense, Options
from contrast.session import settled


def ranked_rules(patterns: DataFrame) -> DataFrame:
    """Patterns with `place`: by falling confidence, then falling support, then id."""
    return patterns.withColumn("place", F.row_number().over(Window.orderBy(F.col("conf").desc(), F.col("pos_supp").desc(), "pattern_id")).cast("int"))


def database_coverage(tx: DataFrame, patterns: DataFrame) -> DataFrame:
    """The rules that some positive row meets first when they are tried in rank; with their places."""
    rules = ranked_rules(patterns)
    first = covered(tx.where("n_pos > 0").select("tx_id", "codes"), rules.select("items", "place")).groupBy("tx_id").agg(F.min("place").alias("place"))
    return rules.join(first.select("place").distinct(), "place", "left_semi")


def sequential_cover(prep, measure: Measure = FSCORE, rounds: int | None = None, options: Options | None = None, strategy: str = "hybrid") -> DataFrame:
    """Best pattern, then the best for the positives that it leaves, and so on: place, items, score on what was left.

    The contrast to covering all rows at once: later rules are learnt from fewer positives. Ends when no
    positives are left or no rule is found; `rounds`, if given, ends it before. Rows that fit a task are learnt
    from there, all rounds in one; more are searched round by round.
    """
    from contrast.plans.search import SENT_ROWS, learnt_in_turn, mine_topk

    spark, left, out = prep.tx.sparkSession, prep.tx, []
    alone = strategy == "depth" or strategy == "hybrid" and Dense.patterns(prep.sizes, prep.symbols) <= DENSE
    if alone and prep.tx.count() <= SENT_ROWS:
        return settled(learnt_in_turn(prep, measure, options or Options(), rounds), "rules").withColumn("pattern_id", pattern_id(F.col("items")))
    for place in count(1) if rounds is None else range(1, rounds + 1):
        p = left.agg(F.coalesce(F.sum("n_pos"), F.lit(0))).first()[0]
        if not p or out and p == out[-1][-1]:
            break
        now = replace(prep, tx=left, p=p)
        best = mine_topk(now, 1, measure, options or Options(), strategy).patterns.select("items", "score").collect()
        if not best:
            break
        out.append((place, best[0]["items"], best[0]["score"], p))
        rule = spark.createDataFrame([(best[0]["items"],)], f"items {PATTERN}")
        hit = F.broadcast(rule.select(F.col("items").alias("rule")))
        after = left.join(hit, covers(F.col("rule"), F.col("codes")), "left")
        left = settled(after.withColumn("n_pos", F.when(F.col("rule").isNull(), F.col("n_pos")).otherwise(F.lit(0))).drop("rule").where("n_pos + n_neg > 0"), "left")
    return spark.createDataFrame(out, f"place int, items {PATTERN}, score double, positives_left long").withColumn("pattern_id", pattern_id(F.col("items")))


def classify_by_list(encoded: DataFrame, patterns: DataFrame, fallback: str) -> DataFrame:
    """encoded (codes, ...) with `predicted` and `margin`: the class of the covering rule with the best confidence.

    patterns: items, conf, cls, of all classes together; few, and broadcast as one array.
    """
    rules = patterns.agg(F.array_sort(F.collect_list(F.struct((-F.col("conf")).alias("down"), "cls", "items"))).alias("rules"))
    hit = F.get(F.filter("__rules", lambda x: covers(x["items"], F.col("codes"))), 0)
    return encoded.withColumn("__rules", rules.scalar()).withColumn("__hit", hit).withColumn("predicted", F.coalesce(F.col("__hit")["cls"], F.lit(fallback))).withColumn("margin", F.coalesce(-F.col("__hit")["down"], F.lit(0.0))).drop("__rules", "__hit")


def classify_by_vote(encoded: DataFrame, patterns: DataFrame, positive: str, negative: str) -> DataFrame:
    """encoded with `margin` (score of the covering rules of one class less that of the other) and `predicted`."""
    rules = patterns.agg(F.collect_list(F.struct(F.when(F.col("cls") == positive, F.col("score")).otherwise(-F.col("score")).alias("vote"), "items")).alias("rules"))
    total = F.aggregate(F.filter("__rules", lambda x: covers(x["items"], F.col("codes"))), F.lit(0.0), lambda a, x: a + x["vote"])
    return encoded.withColumn("__rules", rules.scalar()).withColumn("margin", total).drop("__rules").withColumn("predicted", F.when(F.col("margin") > 0, positive).otherwise(negative))


def confusion(predicted: DataFrame, actual: str = "cls") -> DataFrame:
    """actual, predicted, n."""
    return predicted.groupBy(F.col(actual).alias("actual"), "predicted").agg(F.count(F.lit(1)).alias("n"))


def accuracy(table: DataFrame) -> DataFrame:
    """n, right, accuracy, of a confusion table."""
    right = F.sum(F.when(F.col("actual") == F.col("predicted"), F.col("n")).otherwise(0))
    return table.agg(F.sum("n").alias("n"), right.alias("right")).withColumn("accuracy", F.col("right") / F.col("n"))


def area_under_curve(predicted: DataFrame, positive: str, margin: str = "margin", actual: str = "cls") -> DataFrame:
    """auc, from counts by margin: the share of pairs in the right order, ties half."""
    by = predicted.groupBy(margin).agg(F.sum((F.col(actual) == positive).cast("long")).alias("p"), F.sum((F.col(actual) != positive).cast("long")).alias("q"))
    below = F.sum("q").over(Window.orderBy(margin).rowsBetween(Window.unboundedPreceding, -1))
    ranked = by.select("p", "q", F.coalesce(below, F.lit(0)).alias("below"))
    return ranked.agg((F.sum(F.col("p") * (F.col("below") + F.col("q") / 2)) / (F.sum("p") * F.sum("q"))).alias("auc"))
