"""Counts of interval items at the nodes of a search, and what may be left out of them.

A node is a pattern under way. Its header has the class counts, and the least best score among the
covered positive rows, of each code of each attribute; an upper interval's counts are differences of
running sums, and its least best score is a least over a range of codes. Tables are keyed by node, so
all open nodes are counted in one pass.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.window import WindowSpec

from contrast.functions.measures import Measure, associated


def _by_code() -> WindowSpec:
    return Window.partitionBy("node", "attr").orderBy("code")


def header(rows: DataFrame) -> DataFrame:
    """node, attr, code, n_pos, n_neg, least: from rows (node, first, codes, n_pos, n_neg, best).

    Only attributes from `first` on are counted, and rows without a code aren't. Partial sums leave
    the tasks, so what is shuffled is as large as the headers.
    """
    each = rows.select("node", "first", "n_pos", "n_neg", "best", F.posexplode("codes").alias("attr", "code")).where("attr >= first and code >= 0")
    least = F.min(F.when(F.col("n_pos") > 0, F.col("best")))
    return each.groupBy("node", "attr", "code").agg(F.sum("n_pos").alias("n_pos"), F.sum("n_neg").alias("n_neg"), least.alias("least"))


def drop_rare_symbols(head: DataFrame, is_symbol: Column, floor: Column) -> DataFrame:
    """Without the symbols whose positive rows are fewer than a floor."""
    return head.where(~is_symbol | (F.col("n_pos") >= floor))


def drop_rare_attributes(head: DataFrame, is_symbol: Column, floor: Column) -> DataFrame:
    """Without the numbers whose positive rows, over all codes, are fewer than a floor; single codes never go."""
    total = F.sum("n_pos").over(Window.partitionBy("node", "attr"))
    return head.withColumn("total", total).where(is_symbol | (F.col("total") >= floor)).drop("total")


def remerge(head: DataFrame) -> DataFrame:
    """The header with neighbouring codes of one pure class as one: code and last (its first and last code), and sums.

    Codes that no row of the node has don't part neighbours.
    """
    kind = F.when(F.col("n_neg") == 0, "pos").when(F.col("n_pos") == 0, "neg").otherwise("mixed")
    same = (F.lag("kind").over(_by_code()) == F.col("kind")) & (F.col("kind") != "mixed")
    runs = head.withColumn("kind", kind).withColumn("run", F.sum(F.when(same, 0).otherwise(1)).over(_by_code()))
    return runs.groupBy("node", "attr", "run").agg(F.min("code").alias("code"), F.max("code").alias("last"), F.sum("n_pos").alias("n_pos"), F.sum("n_neg").alias("n_neg"), F.min("least").alias("least")).drop("run")


def closed_ends(head: DataFrame) -> DataFrame:
    """Runs that may begin or end an interval: those with positive rows.

    An interval that begins or ends without one has the positives of a narrower one.
    """
    return head.where("n_pos > 0")


def intervals(head: DataFrame, closed: bool = True, uppers: bool = True, admits: Callable[[Column, Column], Column] | None = None) -> DataFrame:
    """node, attr, lo, hi, n_pos, n_neg, least: all unions of neighbouring runs of a merged header.

    Counts are differences of running sums: with closed ends, of the runs with positives and what lies
    between. admits(n_pos, least): whether an interval may stay. It holds for all that contain one that it
    holds for, so from the top down: a run begins an interval only if the widest from there stays, and
    then its ends run down to the narrowest that does. What doesn't stay is mostly never made.
    """
    upto, after = _by_code().rowsBetween(Window.unboundedPreceding, 0), _by_code().rowsBetween(0, Window.unboundedFollowing)
    sums = head.select("*", F.sum("n_pos").over(upto).alias("to_p"), F.sum("n_neg").over(upto).alias("to_q"))
    ends = closed_ends(sums) if closed else sums
    if not uppers:
        return ends.select("node", "attr", F.col("code").alias("lo"), (F.col("last") + 1).alias("hi"), "n_pos", "n_neg", "least")
    if admits is not None:
        widest = ends.select("*", F.sum("n_pos").over(after).alias("rest"), F.min("least").over(after).alias("floor"))
        begins = widest.where(admits(F.col("rest"), F.col("floor"))).drop("rest", "floor")
    else:
        begins = ends
    run = F.struct("code", "last", "to_p", "to_q", "least")
    packed = ends.groupBy("node", "attr").agg(F.array_sort(F.collect_list(run)).alias("runs"))
    begun = begins.select("node", "attr", "code", (F.col("to_p") - F.col("n_pos")).alias("from_p"), (F.col("to_q") - F.col("n_neg")).alias("from_q"))
    each = begun.join(packed, ["node", "attr"]).select("node", "attr", "code", "from_p", "from_q", F.explode(F.filter("runs", lambda r: r["code"] >= F.col("code"))).alias("r"))
    down = Window.partitionBy("node", "attr", "code").orderBy("r.code").rowsBetween(Window.unboundedPreceding, 0)
    made = each.select("node", "attr", F.col("code").alias("lo"), (F.col("r.last") + 1).alias("hi"), (F.col("r.to_p") - F.col("from_p")).alias("n_pos"), (F.col("r.to_q") - F.col("from_q")).alias("n_neg"), F.min("r.least").over(down).alias("least"))
    return made if admits is None else made.where(admits(F.col("n_pos"), F.col("least")))


def intervals_by_width(head: DataFrame, widths: int) -> DataFrame:
    """The same counts by the recurrence on the width: a base interval and the interval to its right. For checks."""
    base = head.select("node", "attr", F.col("code").alias("lo"), (F.col("code") + 1).alias("hi"), "n_pos", "n_neg")
    out = now = base
    for _ in range(2, widths + 1):
        right = now.select("node", "attr", F.col("lo").alias("mid"), F.col("hi").alias("to"), F.col("n_pos").alias("p"), F.col("n_neg").alias("q"))
        now = base.join(right, ["node", "attr"]).where("hi = mid").select("node", "attr", "lo", F.col("to").alias("hi"), (F.col("n_pos") + F.col("p")).alias("n_pos"), (F.col("n_neg") + F.col("q")).alias("n_neg"))
        out = out.union(now)
    return out


def items(head: DataFrame, is_symbol: Column, sizes: Column, merge: bool = True, closed: bool = True, uppers: bool = True, admits: Callable[[Column, Column], Column] | None = None) -> DataFrame:
    """All items that a node can be extended by, or those that are admitted; sizes: codes of each attribute. The whole line is no item."""
    symbols = head.where(is_symbol & (F.col("n_pos") > 0)).select("node", "attr", F.col("code").alias("lo"), (F.col("code") + 1).alias("hi"), "n_pos", "n_neg", "least")
    numbers = head.where(~is_symbol)
    runs = remerge(numbers) if merge else numbers.withColumn("last", F.col("code"))
    if admits is not None:
        symbols = symbols.where(admits(F.col("n_pos"), F.col("least")))
    made = intervals(runs, closed, uppers, admits)
    whole = (F.col("lo") == 0) & (F.col("hi") == F.get(sizes, F.col("attr")))
    return symbols.unionByName(made.where(~whole & (F.col("n_pos") > 0)))


def above_floor(measure: Measure, p: int, n: int) -> Callable[[Column, Column], Column]:
    """Whether a bound reaches the least best score of the positives that are covered; ties stay."""
    return lambda n_pos, least: measure.bound(n_pos, p, n) >= F.coalesce(least, F.lit(0.0))


def scored(found: DataFrame, measure: Measure, p: int, n: int) -> DataFrame:
    """Items with score and whether they may be answers: only positively associated ones may."""
    return found.select("*", measure.column(F.col("n_pos"), F.col("n_neg"), p, n).alias("score"), associated(F.col("n_pos"), F.col("n_neg"), F.lit(p), F.lit(n)).alias("admitted"))
