"""Cut-points of numbers: adaptive ones from class histograms, and the discretisations to compare with.

A histogram has a row for each attribute and grid cell that occurs, so it is as large as the data's
precision, not as the data; everything here works on it. Windows run over one attribute's cells.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.window import WindowSpec

from contrast.schema import HybridSchema, as_number



def by_cell() -> WindowSpec:
    return Window.partitionBy("attr").orderBy("cell")


def grid_cell(value: Column, delta: float) -> Column:
    """The number of the grid cell that holds a value: cells are half open, and negative values have negative cells."""
    return F.floor(value / F.lit(float(delta))).cast("long")


def value_histogram(df: DataFrame, schema: HybridSchema, positive: Column) -> DataFrame:
    """attr, cell, vmin, vmax, n_pos, n_neg: class counts of each occurring grid cell of each number.

    One scan; what is shuffled are partial sums by cell. Null and NaN are left out.
    """
    values = F.array(*(F.struct(F.lit(i).alias("attr"), as_number(df, a.name).alias("v"), grid_cell(as_number(df, a.name), a.delta).alias("cell")) for i, a in schema.numbers()))
    each = df.select(positive.cast("int").alias("pos"), F.explode(values).alias("x")).select("pos", "x.*").where("v is not null")
    return each.groupBy("attr", "cell").agg(F.min("v").alias("vmin"), F.max("v").alias("vmax"), F.sum("pos").alias("n_pos"), F.sum(1 - F.col("pos")).alias("n_neg"))


def initial_cuts(histogram: DataFrame) -> DataFrame:
    """attr, cell, cut: the middle between each occurring cell's largest and the next one's least value."""
    following = F.lead("vmin").over(by_cell())
    return histogram.select("attr", "cell", ((F.col("vmax") + following) / 2).alias("cut")).where("cut is not null")


def purity(histogram: DataFrame) -> DataFrame:
    """The histogram with `purity`: pos, neg or mixed."""
    return histogram.withColumn("purity", F.when(F.col("n_neg") == 0, "pos").when(F.col("n_pos") == 0, "neg").otherwise("mixed"))


def merged_cuts(histogram: DataFrame, merge_pos: bool = True, merge_neg: bool = True) -> DataFrame:
    """attr, code, lo, hi, n_pos, n_neg, purity: base intervals, with all neighbouring regions of one pure class joined.

    lo of the first and hi of the last are null: they have no end. Mixed regions are never joined.
    """
    joins = [p for p, on in (("pos", merge_pos), ("neg", merge_neg)) if on]
    same = (F.lag("purity").over(by_cell()) == F.col("purity")) & F.col("purity").isin(joins) if joins else F.lit(False)
    marked = purity(histogram).withColumn("begins", F.when(same, 0).otherwise(1))
    runs = marked.withColumn("code", (F.sum("begins").over(by_cell()) - 1).cast("int"))
    regions = runs.groupBy("attr", "code").agg(F.min("vmin").alias("vmin"), F.max("vmax").alias("vmax"), F.sum("n_pos").alias("n_pos"), F.sum("n_neg").alias("n_neg"), F.first("purity").alias("purity"))
    return edged(regions)


def edged(regions: DataFrame) -> DataFrame:
    """Regions (attr, code, vmin, vmax, n_pos, n_neg, purity) with the middles between them as ends."""
    by = Window.partitionBy("attr").orderBy("code")
    lo, hi = (F.lag("vmax").over(by) + F.col("vmin")) / 2, (F.col("vmax") + F.lead("vmin").over(by)) / 2
    return regions.select("attr", "code", lo.alias("lo"), hi.alias("hi"), "n_pos", "n_neg", "purity")


def coded(histogram: DataFrame, code: Column) -> DataFrame:
    """Base intervals of cells that share a code; codes are made gapless in their order."""
    given = histogram.withColumn("given", code)
    dense = given.withColumn("code", (F.dense_rank().over(Window.partitionBy("attr").orderBy("given")) - 1).cast("int"))
    sums = dense.groupBy("attr", "code").agg(F.min("vmin").alias("vmin"), F.max("vmax").alias("vmax"), F.sum("n_pos").alias("n_pos"), F.sum("n_neg").alias("n_neg"))
    return edged(purity(sums))


def width_cuts(histogram: DataFrame, bins: int) -> DataFrame:
    """Bins of equal width between the least and the largest value."""
    every = Window.partitionBy("attr")
    low, high = F.min("vmin").over(every), F.max("vmax").over(every)
    place = F.when(high == low, 0).otherwise(F.least(F.lit(bins - 1), F.floor(bins * (F.col("vmin") - low) / (high - low))))
    return coded(histogram, place.cast("int"))


def quantile_cuts(histogram: DataFrame, bins: int) -> DataFrame:
    """Bins of nearly equal counts: a cell goes to the bin of the rows before it."""
    n = F.col("n_pos") + F.col("n_neg")
    before = F.sum(n).over(by_cell().rowsBetween(Window.unboundedPreceding, 0)) - n
    return coded(histogram, F.floor(bins * before / F.sum(n).over(Window.partitionBy("attr"))).cast("int"))


def _entropy(pos, neg):
    n = pos + neg
    with np.errstate(divide="ignore", invalid="ignore"):
        return sum(np.where((n > 0) & (x > 0), -x / n * np.log2(np.where(x > 0, x, 1) / np.where(n > 0, n, 1)), 0.0) for x in (pos, neg))


def _mdl(pos: np.ndarray, neg: np.ndarray, begin: int, end: int) -> list[int]:
    """Where to cut cells begin to end, by least entropy as long as the description gets shorter."""
    p, q = np.cumsum(pos[begin:end]), np.cumsum(neg[begin:end])
    total_p, total_q, n = p[-1], q[-1], p[-1] + q[-1]
    if end - begin < 2:
        return []
    left, right = _entropy(p[:-1], q[:-1]), _entropy(total_p - p[:-1], total_q - q[:-1])
    size = p[:-1] + q[:-1]
    split = size / n * left + (n - size) / n * right
    k = int(np.argmin(split))
    whole = float(_entropy(total_p, total_q))
    kinds = lambda a, b: int(a > 0) + int(b > 0)
    c, c1, c2 = kinds(total_p, total_q), kinds(p[k], q[k]), kinds(total_p - p[k], total_q - q[k])
    cost = math.log2(3**c - 2) - (c * whole - c1 * float(left[k]) - c2 * float(right[k]))
    if n < 2 or whole - split[k] <= (math.log2(n - 1) + cost) / n:
        return []
    middle = begin + k + 1
    return [*_mdl(pos, neg, begin, middle), middle, *_mdl(pos, neg, middle, end)]


def _optimal(pos: np.ndarray, neg: np.ndarray, bins: int) -> list[int]:
    """Where to cut so that no more than `bins` parts have the least entropy in all, each part costing log2 of the rows."""
    m = len(pos)
    p, q = np.concatenate([[0], np.cumsum(pos)]), np.concatenate([[0], np.cumsum(neg)])
    price = math.log2(max(2, p[-1] + q[-1]))
    best, back = np.full((bins + 1, m + 1), np.inf), np.zeros((bins + 1, m + 1), int)
    best[0, 0] = 0
    for k in range(1, bins + 1):
        for j in range(k, m + 1):
            i = np.arange(k - 1, j)
            a, b = p[j] - p[i], q[j] - q[i]
            cost = best[k - 1, i] + (a + b) * _entropy(a, b) + price
            at = int(np.argmin(cost))
            best[k, j], back[k, j] = cost[at], i[at]
    k, j, cuts = int(np.argmin(best[1:, m])) + 1, m, []
    while k:
        j = back[k, j]
        cuts.append(int(j))
        k -= 1
    return sorted(c for c in cuts if c)


def _cut_by(histogram: DataFrame, cutter) -> DataFrame:
    """Base intervals that a function of an attribute's sorted class counts cuts."""

    def one(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values("cell")
        cuts = cutter(frame["n_pos"].to_numpy(np.float64), frame["n_neg"].to_numpy(np.float64))
        return frame.assign(given=np.searchsorted(cuts, np.arange(len(frame)), side="right").astype(np.int32))

    schema = "attr int, cell long, vmin double, vmax double, n_pos long, n_neg long, given int"
    return coded(histogram.groupBy("attr").applyInPandas(one, schema), F.col("given"))


def entropy_cuts(histogram: DataFrame) -> DataFrame:
    """Recursive cuts of each attribute by itself, by class entropy with a stop by description length."""
    return _cut_by(histogram, lambda pos, neg: _mdl(pos, neg, 0, len(pos)))


def optimal_cuts(histogram: DataFrame, bins: int = 8, cells: int = 2000) -> DataFrame:
    """The best histogram of no more than so many bins, by dynamic programming over the merged base intervals.

    An attribute with more than `cells` merged intervals is an error: choose a coarser grid.
    """

    def cutter(pos: np.ndarray, neg: np.ndarray) -> list[int]:
        if len(pos) > cells:
            raise ValueError(f"{len(pos)} intervals; choose a coarser grid")
        return _optimal(pos, neg, min(bins, len(pos)))

    return _cut_by(histogram, cutter)


def preset_cuts(histogram: DataFrame, cuts: dict[int, list[float]]) -> DataFrame:
    """Base intervals of given cut-points; attributes without an entry are one interval."""
    place = F.lit(0)
    for attr, points in cuts.items():
        place = F.when(F.col("attr") == attr, F.size(F.filter(F.array(*map(F.lit, map(float, points))), lambda c: c <= F.col("vmin")))).otherwise(place)
    return coded(histogram, place.cast("int"))


def base_counts_summary(cuts: DataFrame) -> DataFrame:
    """attr, bases, items (all intervals but the whole line), ends (bases with positives), kept (items whose ends have positives)."""
    n, e = F.count(F.lit(1)), F.sum((F.col("n_pos") > 0).cast("long"))
    whole = (F.min_by("n_pos", "code") > 0) & (F.max_by("n_pos", "code") > 0)
    sums = cuts.groupBy("attr").agg(n.alias("bases"), e.alias("ends"), whole.alias("whole"))
    kept = F.floor(F.col("ends") * (F.col("ends") + 1) / 2) - F.col("whole").cast("long")
    return sums.select("attr", "bases", (F.floor(F.col("bases") * (F.col("bases") + 1) / 2) - 1).cast("long").alias("items"), "ends", kept.cast("long").alias("kept"))
