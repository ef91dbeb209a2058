"""SimHash near duplicates: fingerprints by majority, links by Pigeonring filtering, classes by components.

A fingerprint's 64 bits lie on a ring of segments. If two fingerprints differ in no more than a budget
of bits, then on some segment a chain begins whose cumulative differences stay within the budget's
proportional part after one, two, three and all segments. The chain's first two segments are found by
equal keys: the first must be equal, and the second may differ in so many bits that one side lists.
Further segments prune the pairs that come out, and the full distance decides.

Pairs alone would grow with the square of a crowd of near copies. So keys with many fingerprints are
not paired: their members are linked through what lies between them. Two fingerprints within four
bits have a common neighbour within two bits of each, so linking every member to its whole
neighbourhood of two bits joins the same components, with rows in proportion to the members.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from contrast.llm import overlap
from contrast.llm.common import give_back, materialise
from contrast.llm.overlap import SEED, WIDTH, shingle_hashes


def fingerprint_of(parts: Iterable[np.ndarray]) -> int:
    """SimHash of shingles' hashes, repeats included; 0 without any."""
    ones, n = np.zeros(64, np.int64), 0
    for hashes in parts:
        ones += np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
        n += len(hashes)
    return int(np.packbits(2 * ones > n, bitorder="little").view("<u8")[0])


def fingerprint(text: str | None, width: int = WIDTH, seed: int = SEED) -> int:
    """SimHash of a whole text's shingles, repeats included; 0 for a text without words."""
    return fingerprint_of(shingle_hashes((text or "").encode().lower().split(), width, seed))


#: Bits that linked fingerprints may differ in, and bits of the ring's segments.
BUDGET = 4
SEGMENTS = (13, 13, 13, 13, 12)
#: Fingerprints with an equal key from which on they are linked through their neighbourhoods.
CROWD = 256


def fingerprints(docs: DataFrame, id_column: str = "doc_id", text: str = "text", width: int = WIDTH, seed: int = SEED) -> DataFrame:
    """doc_id and fp (the fingerprint's 64 bits as a signed long) of each whole text; null is empty."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            made = np.array([fingerprint(t.as_py(), width, seed) for t in batch.column(1)], np.uint64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(made.view(np.int64))], ["doc_id", "fp"])

    slim = docs.select(F.col(id_column).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    return slim.mapInArrow(run, f"doc_id {slim.schema['doc_id'].dataType.simpleString()}, fp long")


def _segment(fp, i: int):
    """The bits of segment i, counted around the ring."""
    i %= len(SEGMENTS)
    return F.shiftrightunsigned(fp, sum(SEGMENTS[:i])).bitwiseAND(F.lit((1 << SEGMENTS[i]) - 1))


def _chain_budget(length: int, budget: int) -> int:
    return budget * length // len(SEGMENTS)


def _pairs(fps: DataFrame, budget: int, crowd: int) -> tuple[DataFrame, DataFrame]:
    """(u, v) within the budget whose key is no crowd; and (fp) of those whose keys are."""
    span = max(SEGMENTS)

    def key(i: int):
        return F.lit(i << 2 * span) + F.shiftleft(_segment(F.col("fp"), i), span) + _segment(F.col("fp"), i + 1)

    ring = range(len(SEGMENTS))
    index = fps.select(F.col("fp").alias("v"), F.explode(F.array(*(key(i) for i in ring))).alias("key"))
    # one side of a pair has 0 where the other has 1, and only that side lists the changed key
    flips = [F.when(F.col("fp").bitwiseAND(F.shiftleft(F.lit(1).cast("long"), sum(SEGMENTS[: (i + 1) % len(SEGMENTS)]) + b)) == 0, key(i) + (1 << b)) for i in ring for b in range(SEGMENTS[(i + 1) % len(SEGMENTS)])]
    listed = F.filter(F.concat(F.array(*(key(i) for i in ring)), F.array(*flips)), lambda k: k.isNotNull())
    probe = fps.select(F.col("fp").alias("u"), F.explode(listed).alias("key"))

    crowds = materialise(index.groupBy("key").count().where(F.col("count") > crowd).select("key"), "crowds")
    differ = F.col("u").bitwiseXOR(F.col("v"))
    i = F.shiftrightunsigned(F.col("key"), 2 * span)
    apart = [F.bit_count(_segment(differ, k)).alias(f"d{k}") for k in ring]
    met = probe.join(index.join(crowds, "key", "left_anti"), "key").where("u <> v").select("u", "v", i.alias("i"), *apart)

    def chain(start: int):
        """Whether from segment `start` all cumulative differences stay within their budgets."""
        ok, total = F.lit(True), F.lit(0)
        for length in range(1, len(SEGMENTS) + 1):
            total = total + F.col(f"d{(start + length - 1) % len(SEGMENTS)}")
            ok &= total <= _chain_budget(length, budget)
        return ok

    holds = F.lit(False)
    for start in ring:
        holds |= (F.col("i") == start) & chain(start)
    pairs = met.where(holds).select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
    crowded = index.join(crowds, "key", "left_semi").select(F.col("v").alias("fp")).union(probe.join(crowds, "key", "left_semi").select(F.col("u").alias("fp"))).distinct()
    return pairs, crowded


def _through_neighbours(crowded: DataFrame, budget: int) -> DataFrame:
    """(u, v) that join what lies within the budget of each other, through points that lie between."""
    reach = (budget + 1) // 2
    masks = [sum(1 << b for b in bits) for n in range(reach + 1) for bits in combinations(range(64), n)]
    signed = [m - (1 << 64) if m >> 63 else m for m in masks]
    near = crowded.sparkSession.createDataFrame([(m,) for m in signed], "mask long").agg(F.collect_list("mask").alias("masks"))
    around = crowded.select("fp", F.explode(near.scalar()).alias("mask")).select("fp", F.col("fp").bitwiseXOR(F.col("mask")).alias("point"))
    least = around.groupBy("point").agg(F.min("fp").alias("v"), F.max("fp").alias("most")).where("v < most").select("point", "v")
    return around.join(least, "point").where("fp <> v").select(F.greatest("fp", "v").alias("u"), F.least("fp", "v").alias("v")).distinct()


def links(fps: DataFrame, budget: int = BUDGET, crowd: int = CROWD) -> DataFrame:
    """(u, v), u > v, over distinct fingerprints: they join exactly what links within the budget join.

    Without a crowd these are all pairs within the budget; a crowd's members are joined through their
    neighbourhoods, which for an odd budget would reach one bit further, so budgets are even.
    """
    if budget % 2 or _chain_budget(1, budget) != 0 or _chain_budget(2, budget) > 1:
        raise ValueError("the keys find chains for budgets of 2 and 4")
    fps = fps.select("fp").distinct()
    pairs, crowded = _pairs(fps, budget, crowd)
    return pairs.union(_through_neighbours(crowded, budget)).distinct()


def components(edges: DataFrame) -> DataFrame:
    """(node, root) of every node of (u, v): root is the least node of its component.

    Rounds of linking each larger neighbour to the least, then each node to the least below it, until
    nothing changes. Every round is a written table, so lost executors cost no more than a round.
    """
    now = materialise(edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u <> v").distinct(), "edges")
    mark = None
    while True:
        seen = now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if seen == mark:
            return now.select(F.col("u").alias("node"), F.col("v").alias("root")).union(now.select("v", "v").distinct())
        mark = seen
        both = now.union(now.select("v", "u"))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        below = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(below, "u").select(F.explode(F.array(F.struct(F.col("u").alias("u"), F.col("m").alias("v")), F.struct(F.greatest("v", "m").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.*")
        now = materialise(small.where("u <> v").distinct(), "edges")


def classes(prints: DataFrame, budget: int = BUDGET, crowd: int = CROWD, edges: DataFrame | None = None) -> DataFrame:
    """(doc_id, fp, component_id) of rows (doc_id, fp): the least id of all that are linked, ids of null aside.

    edges: (u, v) over fingerprints to take in place of the links within the budget.

    Repeated rows come out repeated. Rows with equal fingerprints are one node, whatever their number.
    """
    own = materialise(prints.groupBy("fp").agg(F.min("doc_id").alias("rep")), "prints")
    roots = components(links(own, budget, crowd) if edges is None else edges)
    rooted = own.join(roots, own["fp"] == roots["node"], "left").select("fp", "rep", F.coalesce("root", "fp").alias("root"))
    grouped = materialise(rooted, "roots")
    best = grouped.groupBy("root").agg(F.min("rep").alias("component_id"))
    return prints.join(grouped.join(best, "root").select("fp", "component_id"), "fp").select("doc_id", "fp", "component_id")


def by_fingerprint(docs: DataFrame, id_column: str = "doc_id", text: str = "text", width: int = WIDTH, budget: int = BUDGET) -> DataFrame:
    """doc_id, fp, component_id of every row of docs, linked by fingerprints alone."""
    return classes(materialise(fingerprints(docs, id_column, text, width), "fingerprints"), budget)


def sketched(docs: DataFrame, id_column: str, text: str, width: int) -> DataFrame:
    """doc_id, fp (as simhash gives it), node (a hash of the shingle set), n (its size), keys, minima, of each row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps, nodes, sizes, keys, minima = [], [], [], [], []
            for value in batch.column(1):
                parts = list(shingle_hashes(value.as_py().encode().lower().split(), width))
                found = overlap.distinct(parts)
                fps.append(fingerprint_of(parts))
                nodes.append(xxhash.xxh64_intdigest(found.tobytes()))
                sizes.append(len(found))
                own, least = overlap.keys_of(found)
                keys.append(own.view(np.int64))
                minima.append(least)
            signed = lambda x: pa.array(np.array(x, np.uint64).view(np.int64))
            yield pa.RecordBatch.from_arrays([batch.column(0), signed(fps), signed(nodes), pa.array(sizes, pa.int64()), pa.array(keys, pa.list_(pa.int64())), pa.array(minima, pa.binary())], ["doc_id", "fp", "node", "n", "keys", "minima"])
        give_back()

    slim = docs.select(F.col(id_column).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    return slim.mapInArrow(run, f"doc_id {slim.schema['doc_id'].dataType.simpleString()}, fp long, node long, n long, keys array<long>, minima binary")


def near_duplicates(docs: DataFrame, id_column: str = "doc_id", text: str = "text", width: int = WIDTH) -> DataFrame:
    """doc_id, fp, component_id of every row of docs: linked are SimHash's near duplicates and all pairs that overlap enough.

    Null and empty texts have fingerprint zero and are one class, and so are equal texts, with whatever ids;
    texts under a shingle's words are one shingle. A text of any length is shingled whole. component_id is the
    least id, ids of null last; rows come out as often as they come in, an empty table gives none.
    """
    rows = materialise(sketched(docs, id_column, text, width), "sketches")
    one = rows.where("n > 0").groupBy("node").agg(F.min("fp").alias("fp"), F.min("doc_id").alias("rep"), F.min("n").alias("n"), F.first("keys").alias("keys"), F.first("minima").alias("minima"))
    own = materialise(one, "nodes")
    least = own.select("node", F.col("fp").alias("v"))
    same = rows.where("n > 0").select("node", F.col("fp").alias("u")).distinct().join(least, "node").where("u <> v").select("u", "v")

    index = own.select("node", "fp", "n", F.explode("keys").alias("key"))
    first = index.groupBy("key").agg(F.min(F.struct("node", "n", "fp")).alias("first"), F.count(F.lit(1)).alias("members")).where("members > 1").select("key", "first")
    met = materialise(index.join(first, "key"), "met")
    to_first = met.where((F.col("node") != F.col("first.node")) & overlap.may(F.col("n"), F.col("first.n")))
    begun = overlap.verified(to_first.select(F.col("node").alias("u"), F.col("first.node").alias("v")), own, docs, id_column, text, width)
    edges = materialise(links(rows.select("fp")).union(same).union(begun).distinct(), "links")

    roots = materialise(components(edges), "roots")
    placed = met.select("key", "node", "fp").join(roots.select(F.col("node").alias("fp"), "root"), "fp", "left").select("key", "node", F.coalesce("root", "fp").alias("root"))
    several = placed.groupBy("key").agg(F.min("root").alias("a"), F.max("root").alias("b")).where("a <> b").select("key")
    members = placed.join(several, "key", "left_semi").join(own.select("node", "n", "keys", "minima"), "node")
    ended = overlap.linked(members, own, docs, id_column, text, width)
    # what is joined already is a star around its least node: later rounds move no more than that
    stars = roots.where("node <> root").select(F.col("node").alias("u"), F.col("root").alias("v"))
    return classes(rows.select("doc_id", "fp"), edges=stars.union(ended))
