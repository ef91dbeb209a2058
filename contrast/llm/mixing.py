"""Mixing sources to target weights by a low-discrepancy schedule.

Every source gets a share of all words by its weight, but no more than a multiple of its own words;
what is cut off is shared out again by weight. A schedule of equal-sized slots follows the golden-ratio
sequence: slot k stands at the fractional part of k times the golden ratio's inverse, and goes to the
source whose stretch of the cumulative targets holds that point. A source's documents are laid out in
shuffled order, cut into blocks of as many words as a slot has, and the source's r-th slot takes its
r-th block, from the start again when all are used. Everything is DataFrame expressions; a source of
any size is laid out in hash buckets, so no task holds a whole source.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from contrast.llm.common import materialise, words

#: What a slot's point moves on by: the golden ratio's inverse.
STEP = 0.6180339887498949
#: Slots that a schedule has at least, once there are as many words; twice as many at most.
SLOTS = 1 << 18
#: Blocks that a source's target has at least to be met by slots; what is less is taken to the word.
FINE = 32
#: Times that a document may be taken.
REPEATS = 3
#: Units that targets are rounded to, per word, so that cumulative targets are exact.
UNITS = 1 << 10
#: Cells of the unit interval by which points find their source.
CELLS = 1 << 10


def cyclic_weight(rank: Column) -> Column:
    """1, 2, 3, repeating, for ranks from 0."""
    return (rank % 3 + 1).cast("double")


def layout(docs: DataFrame, id_column: str = "doc_id", source: str = "source", text: str = "text") -> DataFrame:
    """One slim row for each document: doc_id, source, size (words), text_hash, place (hex, the shuffled order), bucket."""
    return docs.select(
        F.col(id_column).alias("doc_id"),
        F.col(source).alias("source"),
        F.size(words(F.col(text))).cast("long").alias("size"),
        F.xxhash64(text).alias("text_hash"),
        F.md5(F.coalesce(F.col(id_column).cast("string"), F.lit("")).cast("binary")).alias("place"),
    ).withColumn("bucket", F.substring("place", 1, 3))


def targets(sizes: DataFrame, weight=cyclic_weight, repeats: int = REPEATS) -> DataFrame:
    """source, source_size, weight, target, total, from rows of (source, size).

    Sources rank by code point, null last. The level to which the shares rise solves sum of
    min(cap, level * weight) = total: a source is at its cap exactly when filling all up to its own
    level takes no more than the total. One row for each source is all that one task sees.
    """
    own = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    everything, by_name = Window.partitionBy(), Window.orderBy(F.col("source").asc_nulls_last())
    ranked = own.select("*", weight(F.row_number().over(by_name) - 1).alias("weight"), (repeats * F.col("source_size")).alias("cap"), F.sum("source_size").over(everything).alias("total"))
    level = ranked.select("*", (F.col("cap") / F.col("weight")).alias("level"))
    upto = Window.orderBy("level", F.col("source").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, 0)
    filled = level.select("*", (F.sum("cap").over(upto) + F.col("level") * (F.sum("weight").over(everything) - F.sum("weight").over(upto)) <= F.col("total")).alias("full"))
    rest = F.col("total") - F.sum(F.when(F.col("full"), F.col("cap")).otherwise(0)).over(everything)
    share = rest * F.col("weight") / F.sum(F.when(F.col("full"), 0.0).otherwise(F.col("weight"))).over(everything)
    return filled.select("source", "source_size", "weight", F.when(F.col("full"), F.col("cap").cast("double")).otherwise(share).alias("target"), "total")


def schedule(aims: DataFrame, slots: int = SLOTS) -> DataFrame:
    """slot, source, block_words: which source each slot takes its next block from.

    aims: what targets() returns. A slot has max(1, total div slots) words. Points meet the stretches
    of the sources in cells of the unit interval, by an equal-key join.
    """
    end = F.sum("units").over(Window.orderBy(F.col("source").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, 0))
    block = F.greatest(F.lit(1), F.floor(F.col("total") / slots)).cast("long")
    stretch = (
        aims.withColumn("units", F.floor(F.col("target") * UNITS).cast("long"))
        .select("source", "units", end.alias("hi"), F.sum("units").over(Window.partitionBy()).alias("all_units"), block.alias("block_words"), F.ceil(F.col("total") / block).alias("n_slots"))
        .where("units > 0")
        .withColumn("lo", F.col("hi") - F.col("units"))
    )
    cell_of = lambda c: F.floor(c / F.col("all_units") * CELLS)
    cells = stretch.select("*", F.explode(F.sequence(cell_of(F.col("lo")), F.least(cell_of(F.col("hi")), F.lit(CELLS - 1)))).alias("cell"))
    size = stretch.agg(F.max("n_slots").alias("n"))
    point = F.col("slot") * F.lit(STEP)
    blocks = size.select("n", F.explode(F.sequence(F.lit(0), F.floor((F.col("n") - 1) / 1024))).alias("block")).repartition("block")
    slot = blocks.select(F.explode(F.sequence(F.col("block") * 1024, F.least(F.col("block") * 1024 + 1023, F.col("n") - 1))).alias("slot"))
    at = slot.select("slot", (point - F.floor(point)).alias("u")).withColumn("cell", F.floor(F.col("u") * CELLS))
    held = (F.col("u") * F.col("all_units") >= F.col("lo")) & (F.col("u") * F.col("all_units") < F.col("hi"))
    return at.join(cells, "cell").where(held).select("slot", "source", "block_words")


def ranked_slots(plan: DataFrame, aims: DataFrame, slots: int = SLOTS, repeats: int = REPEATS) -> DataFrame:
    """slot, source, rank among the source's slots, block_words, source_size, target.

    The r-th slot of a source takes words from r times block_words on, of all the source's words in shuffled
    order, again and again. A source whose target is less than FINE blocks of several words would be missed
    or left out: it has one block of its whole target, to the word, after all slots (slot is null). No
    slot begins after `repeats` times the source's words.
    """
    block = F.greatest(F.lit(1), F.floor(F.col("total") / slots)).cast("long")
    of = aims.select(F.col("source").alias("__source"), "source_size", "target", ((block > 1) & (F.col("target") < FINE * block)).alias("small"))
    rank = F.row_number().over(Window.partitionBy("source").orderBy("slot")) - 1
    dealt = plan.join(of.where("not small"), F.col("source").eqNullSafe(F.col("__source"))).select("slot", "source", rank.cast("long").alias("rank"), "block_words", "source_size", "target")
    once = of.where("small").select(F.lit(None).cast("long").alias("slot"), F.col("__source").alias("source"), F.lit(0).cast("long").alias("rank"), F.floor(F.col("target") + 0.5).cast("long").alias("block_words"), "source_size", "target")
    return dealt.unionByName(once).where((F.col("rank") * F.col("block_words") < repeats * F.col("source_size")) & (F.col("block_words") > 0))


def placed(rows: DataFrame, of: DataFrame) -> DataFrame:
    """rows of layout() with `begin`, the words before a document in its source's shuffled order, and what `of` (source, ...) says of its source.

    A source is laid out in hash buckets, whose sums come first, and rows meet their buckets: no task
    orders or holds a whole source.
    """
    before = F.sum("__size").over(Window.partitionBy("__source").orderBy("__bucket").rowsBetween(Window.unboundedPreceding, 0)) - F.col("__size")
    sums = rows.groupBy(F.col("source").alias("__source"), F.col("bucket").alias("__bucket")).agg(F.sum("size").alias("__size"))
    told = of.withColumnRenamed("source", "__of")
    begins = sums.select("__source", "__bucket", before.alias("__before")).join(told, F.col("__source").eqNullSafe(F.col("__of"))).drop("__of")
    within = Window.partitionBy("source", "bucket").orderBy("place", "doc_id", "size", "text_hash").rowsBetween(Window.unboundedPreceding, 0)
    inner = rows.select("*", (F.sum("size").over(within) - F.col("size")).alias("__within"))
    return inner.join(begins, F.col("source").eqNullSafe(F.col("__source")) & (F.col("bucket") == F.col("__bucket"))).select("doc_id", "source", "size", "text_hash", (F.col("__before") + F.col("__within")).alias("begin"), *(c for c in of.columns if c != "source"))


def scheduled(docs: DataFrame, id_column: str = "doc_id", source: str = "source", text: str = "text", slots: int = SLOTS, repeats: int = REPEATS) -> DataFrame:
    """The mix itself, and what it leaves: doc_id, source, size, text_hash, begin, source_size, target, slot, rank, epoch, first_word, words.

    A row for each piece of a document that a slot's block holds: `words` words from first_word on, the
    epoch-th time round. Pieces by slot, epoch and begin are the mix's order; slots of null come last. A
    document of which nothing is taken has one row with no slot, no rank and no words.

    Each document names the blocks that its words lie in, once for each round, and meets their slots by an
    equal-key join.
    """
    rows = materialise(layout(docs, id_column, source, text), "layout")
    aims = materialise(targets(rows, repeats=repeats), "targets")
    plan = materialise(ranked_slots(schedule(aims, slots), aims, slots, repeats), "slots")
    own = plan.groupBy(F.col("source").alias("__source")).agg(F.count(F.lit(1)).alias("n_slots"), F.max("block_words").alias("block_words"))
    of = aims.select(F.col("source").alias("__from"), "source_size", "target").join(own, F.col("__from").eqNullSafe(F.col("__source")), "left").select(F.col("__from").alias("source"), "source_size", "target", F.coalesce("n_slots", F.lit(0)).alias("n_slots"), F.coalesce("block_words", F.lit(1)).alias("block_words"))
    docs_at = placed(rows, of)
    all_words = F.least(F.col("n_slots") * F.col("block_words"), repeats * F.col("source_size"))
    rounds = F.when((F.col("size") > 0) & (F.col("begin") < all_words), F.sequence(F.lit(0).cast("long"), F.floor((all_words - 1 - F.col("begin")) / F.col("source_size"))))
    turned = docs_at.withColumn("all_words", all_words).withColumn("epoch", F.explode_outer(rounds)).withColumn("at", F.col("epoch") * F.col("source_size") + F.col("begin"))
    last = F.least(F.col("at") + F.col("size"), F.col("all_words")) - 1
    blocked = turned.withColumn("rank", F.explode_outer(F.sequence(F.floor(F.col("at") / F.col("block_words")), F.floor(last / F.col("block_words")))))
    slot = plan.select(F.col("source").alias("__source"), F.col("rank").alias("__rank"), "slot")
    met = blocked.join(slot, F.col("source").eqNullSafe(F.col("__source")) & (F.col("rank") == F.col("__rank")), "left")
    low = F.greatest(F.col("at"), F.col("rank") * F.col("block_words"))
    high = F.least(F.col("at") + F.col("size"), (F.col("rank") + 1) * F.col("block_words"), F.col("all_words"))
    words_of = F.when(F.col("__rank").isNotNull(), high - low).otherwise(0)
    return met.select("doc_id", "source", "size", "text_hash", "begin", "source_size", "target", "slot", F.col("__rank").alias("rank"), "epoch", (low - F.col("at")).alias("first_word"), words_of.cast("long").alias("words"))


def allot(docs: DataFrame, id_column: str = "doc_id", source: str = "source", text: str = "text", slots: int = SLOTS, repeats: int = REPEATS) -> DataFrame:
    """doc_id, source, size, text_hash, source_size, target, taken: how many words the mix takes of each document.

    The sum of its pieces in scheduled(). A null text has no words, a null source is a source, rows without
    words take none. Repeated rows lie side by side and count each. Needs no unique ids.
    """
    pieces = scheduled(docs, id_column, source, text, slots, repeats)
    # rows without words share their begin with others: those are told apart by nothing but their number
    some, none = pieces.where("size > 0"), pieces.where("size = 0")
    keys = ["doc_id", "source", "size", "text_hash", "source_size", "target"]
    taken = some.groupBy(*keys, "begin").agg(F.sum("words").alias("taken")).drop("begin")
    return taken.unionByName(none.select(*keys, F.lit(0).cast("long").alias("taken")))


def copies(size: Column, taken: Column) -> Column:
    """Whole copies that stand for the words taken: rounded to the nearest number, half up."""
    return F.when(size > 0, F.floor((2 * taken + size) / (2 * size))).otherwise(0).cast("int")


ORACLE = rf"""
WITH rows AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS size, md5(coalesce(CAST(doc_id AS VARCHAR), '')) AS place FROM documents),
own AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM rows GROUP BY source),
ranked AS (SELECT *, CAST((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1 AS DOUBLE) AS weight, {REPEATS} * source_size AS cap, CAST(sum(source_size) OVER () AS BIGINT) AS total FROM own),
level AS (SELECT *, cap / weight AS level FROM ranked),
filled AS (SELECT *, sum(cap) OVER w + level * (sum(weight) OVER () - sum(weight) OVER w) <= total AS fully FROM level WINDOW w AS (ORDER BY level, source NULLS LAST ROWS UNBOUNDED PRECEDING)),
aims AS (SELECT source, source_size, total, CASE WHEN fully THEN CAST(cap AS DOUBLE) ELSE CAST(total - sum(CASE WHEN fully THEN cap ELSE 0 END) OVER () AS DOUBLE) * weight / sum(CASE WHEN fully THEN 0.0 ELSE weight END) OVER () END AS target FROM filled),
stretch AS (SELECT source, CAST(floor(target * {UNITS}) AS BIGINT) AS units, CAST(sum(CAST(floor(target * {UNITS}) AS BIGINT)) OVER (ORDER BY source NULLS LAST ROWS UNBOUNDED PRECEDING) AS BIGINT) AS hi, CAST(sum(CAST(floor(target * {UNITS}) AS BIGINT)) OVER () AS BIGINT) AS all_units, greatest(1, total // {SLOTS}) AS block FROM aims),
points AS (SELECT k * {STEP!r}::DOUBLE - floor(k * {STEP!r}::DOUBLE) AS u FROM range(0, (SELECT CAST(max(ceil(total / greatest(1, total // {SLOTS}))) AS BIGINT) FROM aims)) t(k)),
got AS (SELECT source, count(*) * max(block) AS words FROM points, stretch WHERE units > 0 AND u * all_units >= hi - units AND u * all_units < hi GROUP BY source),
sources AS (SELECT a.source, a.source_size, a.target, least(CASE WHEN a.total // {SLOTS} > 1 AND a.target < {FINE} * (a.total // {SLOTS}) THEN CAST(floor(a.target + 0.5) AS BIGINT) ELSE coalesce(g.words, 0) END, {REPEATS} * a.source_size) AS taken FROM aims a LEFT JOIN got g ON a.source IS NOT DISTINCT FROM g.source),
placed AS (SELECT *, CAST(sum(size) OVER (PARTITION BY source ORDER BY place, doc_id, size ROWS UNBOUNDED PRECEDING) - size AS BIGINT) AS begin FROM rows)
SELECT p.doc_id, CAST(p.size AS BIGINT) AS size, s.source_size, s.target,
  CAST(CASE WHEN s.source_size = 0 THEN 0 ELSE s.taken // s.source_size * p.size + greatest(0, least(p.size, s.taken % s.source_size - p.begin)) END AS BIGINT) AS taken
FROM placed p JOIN sources s ON p.source IS NOT DISTINCT FROM s.source
"""
