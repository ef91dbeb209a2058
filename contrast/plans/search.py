"""Whole searches: rounds over all rows in Spark, and in-memory searches of what has become small.

A table is prepared once: cut-points from class histograms, codes, equal rows with their counts. The
root is always counted by Spark; its items, and what they score, seed each row's best. Then every item
is a subtree of its own, since a pattern is only extended by later attributes, and any sound seed
leaves the answer exact. Subtrees run in waves, best first, and each wave starts from the scores of
those before it. Where a node's rows are too many for one task, it is extended in Spark once more.
Where all patterns are too many to be visited, plain searches go by branch and bound over the ends of all intervals at once.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from contrast.functions.measures import FSCORE, Measure
from contrast.functions.patterns import PATTERN, covers, item, pattern_id, render
from contrast.operators import constraints, cuts, encode, lattice
from contrast.plans.boxes import Boxes, suits
from contrast.plans.kernel import DENSE, Dense, Options, Search, in_turn
from contrast.schema import SYMBOL, HybridSchema
from contrast.session import settled

#: Compressed rows that are sent to all tasks, and that a subtree may have to be searched in one.
SENT_ROWS, NODE_ROWS = 200_000, 2_000_000
#: Nodes of a round in Spark at most; more are split into several passes.
ROUND_NODES = 2_000
#: Patterns of two items up to which all are counted, instead of searched for.
PAIRED = 20_000_000
FOUND = f"items {PATTERN}, score double, visited long, pruned_floor long, pruned_closed long, complete boolean"


@dataclass(frozen=True)
class Prepared:
    """tx: tx_id, codes, n_pos, n_neg, best. p and n: positive and negative rows of the whole table."""

    book: encode.Codebook
    tx: DataFrame
    p: int
    n: int

    @property
    def sizes(self) -> list[int]:
        return [self.book.size(i) for i in range(len(self.book.schema.attributes))]

    @property
    def symbols(self) -> list[bool]:
        return [a.kind == SYMBOL for a in self.book.schema.attributes]

    def size_column(self) -> Column:
        return F.array(*map(F.lit, self.sizes)) if self.sizes else F.array().cast("array<int>")

    def is_symbol(self) -> Column:
        """Whether the attribute of column `attr` is a symbol."""
        return F.get(F.array(*map(F.lit, self.symbols)), F.col("attr"))


@dataclass(frozen=True)
class Answer:
    """patterns: pattern_id, items, counts, shares, score, text. stats: one row with visits, prunes, seconds and whether it is complete."""

    patterns: DataFrame
    stats: DataFrame


def prepare(df: DataFrame, schema: HybridSchema, positive: Column, merge_pos: bool = True, merge_neg: bool = True, discretise=None) -> Prepared:
    """discretise: another function of the histogram that gives base intervals, instead of the adaptive ones."""
    positive = F.coalesce(positive, F.lit(False))
    histogram = cuts.value_histogram(df, schema, positive)
    bases = discretise(histogram) if discretise else cuts.merged_cuts(histogram, merge_pos, merge_neg)
    book = encode.codebook(df, schema, positive, settled(bases, "cuts"))
    rows = encode.compress(encode.encode(df, book, positive))
    tx = settled(rows.select(F.concat_ws(",", F.transform("codes", lambda c: c.cast("string"))).alias("tx_id"), "codes", "n_pos", "n_neg", F.lit(0.0).alias("best")), "tx")
    return Prepared(book, tx, *encode.class_totals(tx))


def _children(prep: Prepared, tx: DataFrame, nodes: DataFrame | None, measure: Measure, options: Options) -> DataFrame:
    """Scored items of all nodes (node, items, first), or of the root: node, items, first, n_pos, n_neg, score, admitted."""
    counted = tx.select("codes", "n_pos", "n_neg", "best")
    if nodes is None:
        rows = counted.select(F.lit("").alias("node"), F.lit(0).alias("first"), "*")
    else:
        open_ = nodes.select("node", "first", "items")
        rows = counted.join(F.broadcast(open_), covers(F.col("items"), F.col("codes"))).drop("items")
    head = lattice.header(rows)
    head = lattice.drop_rare_attributes(head, prep.is_symbol(), F.lit(options.support))
    head = lattice.drop_rare_symbols(head, prep.is_symbol(), F.lit(options.support))
    admits = lattice.above_floor(measure, prep.p, prep.n) if options.floor == "cover" and options.top is None else None
    found = lattice.items(head, prep.is_symbol(), prep.size_column(), options.merge, options.closed, options.uppers, admits).where(F.col("n_pos") >= options.support)
    scored = lattice.scored(found, measure, prep.p, prep.n)
    one = F.array(item(F.col("attr"), F.col("lo"), F.col("hi")))
    if nodes is None:
        whole = scored.select(one.alias("items"), "attr", "n_pos", "n_neg", "score", "admitted")
    else:
        whole = scored.join(F.broadcast(nodes.select("node", F.col("items").alias("upper"))), "node").select(F.concat("upper", one).alias("items"), "attr", "n_pos", "n_neg", "score", "admitted")
    return whole.select(pattern_id(F.col("items")).alias("node"), "items", (F.col("attr") + 1).cast("int").alias("first"), "n_pos", "n_neg", "score", "admitted")


def _open(prep: Prepared, children: DataFrame, measure: Measure, options: Options) -> DataFrame:
    """Children that may be extended."""
    out = children.where(F.col("first") < len(prep.sizes))
    if options.pure_leaves and measure.strict:
        out = out.where("n_neg > 0")
    return out


def _offered(tx: DataFrame, patterns: DataFrame) -> DataFrame:
    return settled(constraints.offer(tx, patterns.select("items", "score")), "tx")


def _arrays(tx: DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    got = tx.select("codes", "n_pos", "n_neg", "best").toArrow()
    codes = got["codes"].combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(np.int32).reshape(len(got), -1)
    return codes, got["n_pos"].to_numpy(), got["n_neg"].to_numpy(), got["best"].to_numpy()


def _reported(search: Search | Boxes) -> pd.DataFrame:
    found = search.found
    rows = [([{"attr": int(a), "lo": int(b), "hi": int(c)} for a, b, c in items], score, 0, 0, 0, True) for items, score in found.patterns]
    rows.append((None, None, found.visited, found.pruned_floor, found.pruned_closed, found.complete))
    return pd.DataFrame(rows, columns=["items", "score", "visited", "pruned_floor", "pruned_closed", "complete"])


def _in_memory(prep: Prepared, tx: DataFrame, nodes: DataFrame, measure: Measure, options: Options, parts: int, tops: list[float]) -> DataFrame:
    """Searches each node's subtree: FOUND rows, patterns and, with null items, counts."""
    sizes, symbols, p, n = prep.sizes, prep.symbols, prep.p, prep.n

    def begun(arrays) -> Search:
        search = Search(arrays[0], arrays[1], arrays[2], sizes, symbols, measure, p, n, arrays[3], options)
        search.tops = list(tops)
        return search

    # nodes are dealt in the order of their scores, so each task begins with good ones
    dealt = nodes.select("node", "items", "first", "score")
    if tx.count() <= SENT_ROWS:
        sent = tx.sparkSession.sparkContext.broadcast(_arrays(tx))

        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            search = begun(sent.value)
            for frame in frames:
                for items, first in zip(frame["items"], frame["first"]):
                    search.run(tuple((x["attr"], x["lo"], x["hi"]) for x in items), int(first))
            yield _reported(search)

        return dealt.repartition(parts, "node").sortWithinPartitions(F.col("score").desc(), "node").mapInPandas(run, FOUND)

    def one(frame: pd.DataFrame) -> pd.DataFrame:
        arrays = np.array(frame["codes"].tolist(), np.int32), frame["n_pos"].to_numpy(), frame["n_neg"].to_numpy(), frame["best"].to_numpy()
        search = begun(arrays)
        search.run((), int(frame["first"].iloc[0]))
        upper = tuple((x["attr"], x["lo"], x["hi"]) for x in frame["items"].iloc[0])
        search.found.patterns = [((*upper, *items), score) for items, score in search.found.patterns]
        return _reported(search)

    rows = tx.join(F.broadcast(dealt), covers(F.col("items"), F.col("codes"))).select("node", "items", "first", "codes", "n_pos", "n_neg", "best")
    return rows.groupBy("node").applyInPandas(one, FOUND)


def _bounded(prep: Prepared, tx: DataFrame, measure: Measure, options: Options, parts: int) -> DataFrame:
    """FOUND rows, as _in_memory gives them, by branch and bound; each task takes a part of the nodes."""
    sizes, symbols, p, n = prep.sizes, prep.symbols, prep.p, prep.n
    sent = tx.sparkSession.sparkContext.broadcast(_arrays(tx))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for part in frame["id"]:
                codes, pos, neg, best = sent.value
                boxes = Boxes(codes, pos, neg, sizes, symbols, measure, p, n, best, options)
                boxes.run(int(part), parts)
                yield _reported(boxes)

    return tx.sparkSession.range(0, parts, 1, parts).mapInPandas(run, FOUND)


def learnt_in_turn(prep: Prepared, measure: Measure, options: Options, rounds: int | None) -> DataFrame:
    """place, items, score, positives_left of kernel.in_turn over all rows, in one task."""
    spark, sizes, symbols, n = prep.tx.sparkSession, prep.sizes, prep.symbols, prep.n
    sent = spark.sparkContext.broadcast(_arrays(prep.tx)[:3])

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for _ in range(len(frame)):
                found = list(in_turn(*sent.value, sizes, symbols, measure, n, options, rounds))
                rows = [(k, [{"attr": a, "lo": b, "hi": c} for a, b, c in items], score, left) for k, (items, score, left) in enumerate(found, 1)]
                yield pd.DataFrame(rows, columns=["place", "items", "score", "positives_left"])

    return spark.range(0, 1, 1, 1).mapInPandas(run, f"place int, items {PATTERN}, score double, positives_left long")


def _of_two(prep: Prepared, measure: Measure, options: Options) -> bool:
    """Whether all patterns of up to two items can be counted, pair of attributes by pair of attributes."""
    plain = options.top is None and options.floor == "cover" and options.uppers and options.support <= 1 and options.visits is options.seconds is None and measure.strict
    sides = list(zip(prep.sizes, prep.symbols))
    every = [Dense.patterns([s, t], [x, y]) for k, (s, x) in enumerate(sides) for t, y in sides[k + 1 :]]
    return plain and options.length == 2 and bool(every) and max(every) <= DENSE and sum(every) <= PAIRED


def _pairs(prep: Prepared, measure: Measure) -> DataFrame:
    """FOUND rows, as _in_memory gives them: all patterns of up to two items that are the best for some row.

    Rows are counted by the codes of each two attributes, and all patterns of the two come from these counts.
    Rows take their best from their codes' cells; a pattern stays where the least best of its rows is its score.
    """
    sizes, symbols, p, n = prep.sizes, prep.symbols, prep.p, prep.n
    pairs = [(a, b) for a in range(len(sizes)) for b in range(a + 1, len(sizes))]
    code = lambda k: F.get("codes", F.lit(k))
    cells = F.explode(F.array(*(F.struct(F.lit(a).alias("a"), F.lit(b).alias("b"), code(a).alias("ka"), code(b).alias("kb")) for a, b in pairs))).alias("cell")
    counts = prep.tx.select("n_pos", "n_neg", cells).groupBy("cell").agg(F.sum("n_pos").alias("n_pos"), F.sum("n_neg").alias("n_neg"))
    counts = settled(counts.select("cell.*", "n_pos", "n_neg"), "cells")

    def scored(frame: pd.DataFrame) -> tuple[Dense, np.ndarray]:
        """All patterns of two attributes and their scores, or minus infinity if they may not be answers."""
        a, b = int(frame["a"].iloc[0]), int(frame["b"].iloc[0])
        dense = Dense(frame[["ka", "kb"]].to_numpy(), [sizes[a], sizes[b]], [symbols[a], symbols[b]])
        x, y = dense.counts(frame["n_pos"].to_numpy()), dense.counts(frame["n_neg"].to_numpy())
        scores = np.where((x > 0) & (x * n >= y * p), measure.values(x, y, p, n), -np.inf)
        scores[-1, -1] = -np.inf
        return dense, scores

    def bests(frame: pd.DataFrame) -> pd.DataFrame:
        dense, scores = scored(frame)
        return frame[["a", "b", "ka", "kb"]].assign(best=dense.best(scores).ravel()[dense.at])

    found = counts.groupBy("a", "b").applyInPandas(bests, "a int, b int, ka int, kb int, best double").toPandas()
    tables = {}
    for a, b in pairs:
        own = found[(found["a"] == a) & (found["b"] == b)]
        tables[a, b] = np.full((sizes[a] + 1, sizes[b] + 1), -np.inf)
        tables[a, b][own["ka"], own["kb"]] = own["best"]  # code -1 is the last cell
    sent = prep.tx.sparkSession.sparkContext.broadcast(tables)

    def leasts(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held = {pair: np.full(t.shape, np.inf) for pair, t in sent.value.items()}
        for frame in frames:
            if len(frame):
                codes = np.array(frame["codes"].tolist(), np.int32)
                best = np.max([t[codes[:, a], codes[:, b]] for (a, b), t in sent.value.items()], axis=0)
                for (a, b), t in held.items():
                    np.minimum.at(t, (codes[:, a], codes[:, b]), best)
        for (a, b), t in held.items():
            ka, kb = np.nonzero(np.isfinite(t) | (t < 0))
            yield pd.DataFrame({"a": a, "b": b, "ka": np.where(ka == sizes[a], -1, ka), "kb": np.where(kb == sizes[b], -1, kb), "least": t[ka, kb]})

    cell = ["a", "b", "ka", "kb"]
    least = prep.tx.where("n_pos > 0").select("codes").mapInPandas(leasts, "a int, b int, ka int, kb int, least double").groupBy(*cell).agg(F.min("least").alias("least"))

    def kept(frame: pd.DataFrame) -> pd.DataFrame:
        dense, scores = scored(frame)
        least = np.full(dense.cells, np.inf)
        least.flat[dense.at] = frame["least"].fillna(np.inf)
        a, b = int(frame["a"].iloc[0]), int(frame["b"].iloc[0])
        stays = np.flatnonzero(np.isfinite(scores) & (scores >= dense.least(least)))
        rows = [([{"attr": (a, b)[k], "lo": lo, "hi": hi} for k, lo, hi in dense.items(int(x), scores.shape)], float(scores.flat[x]), 0, 0, 0, True) for x in stays]
        counted = dense.counts(frame["n_pos"].to_numpy()) > 0
        visited = counted[:-1, :-1].sum() + (counted[-1, :-1].sum() if a == 0 else 0) + (counted[:-1, -1].sum() if (a, b) == (0, 1) else 0)
        rows.append((None, None, int(visited), 0, 0, True))
        return pd.DataFrame(rows, columns=["items", "score", "visited", "pruned_floor", "pruned_closed", "complete"])

    return counts.join(least, cell, "left").groupBy("a", "b").applyInPandas(kept, FOUND)


def _levels(prep: Prepared, tx: DataFrame, children: DataFrame, measure: Measure, options: Options) -> tuple[DataFrame, int]:
    """All further levels in Spark: the admitted patterns, and how many were visited."""
    found, visited, depth = children.where("admitted").select("items", "score"), children.count(), 1
    while options.length is None or depth < options.length:
        nodes = settled(_open(prep, children, measure, options), "nodes")
        if nodes.isEmpty():
            break
        parts = -(-nodes.count() // ROUND_NODES)
        passes = [_children(prep, tx, nodes.where(F.pmod(F.xxhash64("node"), F.lit(parts)) == k), measure, options) for k in range(parts)]
        children = passes[0]
        for more in passes[1:]:
            children = children.unionByName(more)
        children = settled(children, "children")
        visited += children.count()
        admitted = children.where("admitted").select("items", "score")
        tx = _offered(tx, admitted)
        found = found.unionByName(admitted)
        depth += 1
    return found, visited


def _stats(spark, measure: Measure, strategy: str, rows: list[tuple], seconds: float) -> DataFrame:
    visited, floor, ends = (sum(r[k] for r in rows) for k in range(3))
    return spark.createDataFrame([(measure.name, strategy, visited, floor, ends, int(seconds * 1000), all(r[3] for r in rows))], "measure string, strategy string, visited long, pruned_floor long, pruned_closed long, elapsed_ms long, complete boolean")


def search(prep: Prepared, measure: Measure = FSCORE, options: Options = Options(), strategy: str = "hybrid", waves: int = 2, parts: int | None = None) -> tuple[DataFrame, DataFrame]:
    """Candidates (items, score) among which are the best of every positive row, or the top ones; and stats.

    strategy: 'hybrid' as described, 'level' in Spark alone, 'depth' in one task alone.
    """
    began, tx = time.monotonic(), prep.tx
    spark = tx.sparkSession
    parts = parts or spark.sparkContext.defaultParallelism
    if not prep.p:
        return spark.createDataFrame([], f"items {PATTERN}, score double"), _stats(spark, measure, strategy, [(0, 0, 0, True)], 0.0)
    if strategy == "depth":
        alone = spark.createDataFrame([("", [], 0, 0.0)], f"node string, items {PATTERN}, first int, score double")
        got = settled(_in_memory(prep, tx, alone, measure, options, 1, []), "found")
        return got.where("items is not null").select("items", "score"), _stats(spark, measure, strategy, _counts(got), time.monotonic() - began)
    if strategy == "hybrid" and _of_two(prep, measure, options):
        got = settled(_pairs(prep, measure), "found")
        return got.where("items is not null").select("items", "score"), _stats(spark, measure, strategy, _counts(got), time.monotonic() - began)
    if strategy == "hybrid" and suits(measure, options) and Dense.patterns(prep.sizes, prep.symbols) > DENSE and tx.count() <= NODE_ROWS:
        got = settled(_bounded(prep, tx, measure, options, parts), "found")
        return got.where("items is not null").select("items", "score"), _stats(spark, measure, strategy, _counts(got), time.monotonic() - began)
    children = settled(_children(prep, tx, None, measure, options), "children")
    admitted = children.where("admitted").select("items", "score")
    tops: list[float] = []
    if options.top is None:
        tx = _offered(tx, admitted)
    else:
        tops = sorted(r["score"] for r in admitted.orderBy(F.col("score").desc()).limit(options.top).select("score").collect())
    if strategy == "level":
        found, visited = _levels(prep, tx, children, measure, options)
        return found, _stats(spark, measure, strategy, [(visited, 0, 0, True)], time.monotonic() - began)
    if strategy != "hybrid":
        raise ValueError(f"unknown strategy: {strategy}")
    found, counts, left = admitted, [(children.count(), 0, 0, True)], options
    nodes = settled(_open(prep, children, measure, options), "nodes") if options.length != 1 else None
    wide = nodes.where(F.col("n_pos") + F.col("n_neg") > NODE_ROWS) if nodes is not None and tx.count() > SENT_ROWS else None
    if wide is not None and not wide.isEmpty():  # too many rows for a task: one more round in Spark
        more = settled(_children(prep, tx, wide, measure, options), "children")
        found = found.unionByName(more.where("admitted").select("items", "score"))
        counts.append((more.count(), 0, 0, True))
        nodes = nodes.where(F.col("n_pos") + F.col("n_neg") <= NODE_ROWS).unionByName(_open(prep, more, measure, options))
    if nodes is not None and not nodes.isEmpty():
        edges = [float("inf"), *(nodes.approxQuantile("score", [1 - 0.1 ** (waves - k) for k in range(1, waves)], 0.01) if waves > 1 else []), float("-inf")]
        for high, low in zip(edges, edges[1:]):
            some = nodes.where((F.col("score") < high) & (F.col("score") >= low)) if high > low else None
            if some is None:
                continue
            if options.seconds is not None:
                left = replace(options, seconds=max(0.1, options.seconds - (time.monotonic() - began)))
            if options.visits is not None:
                left = replace(left, visits=max(1, (options.visits - sum(c[0] for c in counts)) // parts))
            got = settled(_in_memory(prep, tx, some, measure, left, parts, tops), "found")
            counts += _counts(got)
            new = got.where("items is not null").select("items", "score")
            found = found.unionByName(new)
            if options.top is None and low > float("-inf"):
                tx = _offered(tx, new)
    return found, _stats(spark, measure, strategy, counts, time.monotonic() - began)


def _counts(got: DataFrame) -> list[tuple]:
    return [(r["visited"], r["pruned_floor"], r["pruned_closed"], r["complete"]) for r in got.where("items is null").collect()]


def rendered(prep: Prepared, patterns: DataFrame) -> DataFrame:
    return patterns.withColumn("text", render(F.col("items"), *prep.book.columns()))


def mine_covering(prep: Prepared, measure: Measure = FSCORE, options: Options = Options(), strategy: str = "hybrid", waves: int = 2) -> Answer:
    """For every positive row its best patterns, ties kept; closed on the positives, each the best for some row."""
    found, stats = search(prep, measure, options, strategy, waves)
    done = constraints.finished(prep.tx, found, measure, prep.p, prep.n, prep.is_symbol(), prep.size_column())
    return Answer(rendered(prep, done), stats)


def mine_topk(prep: Prepared, k: int, measure: Measure = FSCORE, options: Options = Options(), strategy: str = "hybrid") -> Answer:
    """The k positively associated patterns of the highest scores, of all patterns; equal scores go by pattern id.

    All means also those that merged or closed ends would leave out for a pattern of equal positives, so
    both are off, whatever the options say.
    """
    found, stats = search(prep, measure, replace(options, top=k, merge=False, closed=False, closure=False, pure_leaves=False), strategy, waves=1)
    own = found.select(pattern_id(F.col("items")).alias("pattern_id"), "items").distinct()
    counted = constraints.with_shares(constraints.pattern_stats(prep.tx, own), prep.p, prep.n)
    best = counted.select("*", measure.column(F.col("n_pos"), F.col("n_neg"), prep.p, prep.n).alias("score")).orderBy(F.col("score").desc(), "pattern_id").limit(k)
    return Answer(rendered(prep, best), stats)


def mine_all_classes(df: DataFrame, schema: HybridSchema, cls: str = "cls", measure: Measure = FSCORE, options: Options = Options()) -> DataFrame:
    """The answers for each class against all others, with `cls`; each class has cut-points of its own."""
    out = None
    for row in df.select(cls).where(F.col(cls).isNotNull()).distinct().orderBy(cls).collect():
        one = mine_covering(prepare(df, schema, F.col(cls) == row[0]), measure, options).patterns.withColumn("cls", F.lit(row[0]))
        out = one if out is None else out.unionByName(one)
    return out


def coverage(prep: Prepared, patterns: DataFrame) -> DataFrame:
    """covered, positives, share: positive rows with a pattern at least."""
    hit = constraints.covered(prep.tx.where("n_pos > 0").select("tx_id", "codes", "n_pos"), patterns.select("items")).select("tx_id", "n_pos").distinct()
    return hit.agg(F.coalesce(F.sum("n_pos"), F.lit(0)).alias("covered")).select("covered", F.lit(prep.p).cast("long").alias("positives"), (F.col("covered") / F.lit(max(prep.p, 1))).alias("share"))
