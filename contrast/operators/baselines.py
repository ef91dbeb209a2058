"""What the search is compared with: plain frequent patterns, all patterns of few attributes, symbolic cubes."""

from __future__ import annotations

from functools import reduce

from pyspark.ml.fpm import FPGrowth
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from contrast.functions.measures import Measure, associated
from contrast.functions.patterns import item, pattern_id
from contrast.schema import HybridSchema


def frequent_symbols(df: DataFrame, schema: HybridSchema, positive: Column, least_support: float) -> DataFrame:
    """items (name=value, sorted), freq: patterns of symbols frequent among the positive rows, by a set support."""
    named = F.array(*(F.concat(F.lit(f"{a.name}="), F.col(f"`{a.name}`").cast("string")) for _, a in schema.symbols()))
    rows = df.where(positive).select(F.array_compact(named).alias("items"))
    found = FPGrowth(itemsCol="items", minSupport=least_support).fit(rows).freqItemsets
    return found.select(F.array_sort("items").alias("items"), "freq")


def symbol_cube(df: DataFrame, schema: HybridSchema, positive: Column) -> DataFrame:
    """Class counts of every conjunction of symbols, by one cube over their columns; null stands for no condition."""
    names = [a.name for _, a in schema.symbols()]
    pos = positive.cast("long")
    return df.dropna(subset=names).cube(*names).agg(F.sum(pos).alias("n_pos"), F.sum(1 - pos).alias("n_neg")).where(reduce(lambda a, b: a | b, (F.col(f"`{n}`").isNotNull() for n in names)))


def basket_items(df: DataFrame, tokens: str, positive: Column) -> DataFrame:
    """token, n_pos, n_neg: class counts of the presence of each token of an array column."""
    pos = positive.cast("long")
    each = df.select(pos.alias("pos"), F.explode(F.array_distinct(tokens)).alias("token"))
    return each.groupBy("token").agg(F.sum("pos").alias("n_pos"), F.sum(1 - F.col("pos")).alias("n_neg"))


def brute_force(prep, measure: Measure, attrs: tuple[int, ...]) -> DataFrame:
    """items, n_pos, n_neg, score, admitted of every pattern over up to three attributes that covers a row.

    Rows are first counted by the codes of those attributes; each count goes to all patterns that hold
    it. For checks: the number of patterns is the product of the attributes' items.
    """
    if len(attrs) > 3:
        raise ValueError("three attributes at most")
    spark, sizes, symbols = prep.tx.sparkSession, prep.sizes, prep.symbols
    counts = prep.tx.groupBy(*(F.col("codes")[a].alias(f"c{a}") for a in attrs)).agg(F.sum("n_pos").alias("n_pos"), F.sum("n_neg").alias("n_neg"))
    held = counts
    for a in attrs:
        rows = [(lo, hi) for lo in range(sizes[a]) for hi in ([lo + 1] if symbols[a] else range(lo + 1, sizes[a] + 1)) if symbols[a] or (lo, hi) != (0, sizes[a])]
        every = spark.createDataFrame([(None, None), *rows], f"lo{a} int, hi{a} int")
        fits = F.col(f"lo{a}").isNull() | ((F.col(f"c{a}") >= F.col(f"lo{a}")) & (F.col(f"c{a}") < F.col(f"hi{a}")))
        held = held.join(F.broadcast(every), fits)
    bounds = [c for a in attrs for c in (f"lo{a}", f"hi{a}")]
    sums = held.groupBy(*bounds).agg(F.sum("n_pos").alias("n_pos"), F.sum("n_neg").alias("n_neg"))
    items = F.filter(F.array(*(F.when(F.col(f"lo{a}").isNotNull(), item(a, F.col(f"lo{a}"), F.col(f"hi{a}"))) for a in attrs)), lambda x: x.isNotNull())
    made = sums.select(items.alias("items"), "n_pos", "n_neg").where("size(items) > 0")
    return made.select(pattern_id(F.col("items")).alias("pattern_id"), "items", "n_pos", "n_neg", measure.column(F.col("n_pos"), F.col("n_neg"), prep.p, prep.n).alias("score"), associated(F.col("n_pos"), F.col("n_neg"), F.lit(prep.p), F.lit(prep.n)).alias("admitted"))
