"""Document fingerprints: invertible Bloom lookup sketches of paragraph digests.

A text is a set of digests of its paragraphs; a paragraph here is a line, a sentence of it, or a piece
of a long one, and the n-th occurrence of an equal paragraph has a digest of its own. A sketch hashes
each digest to one cell in each of three parts and keeps, in each cell, a count and sums (by exclusive
or) of digests and of check values. One sketch less another holds only what differs; cells with a
single digest give it away, and taking it out of its other cells frees further ones, until all is
recovered. Where that gets stuck the sketches were too small, and larger ones are made. The number of
digests that differ tells how alike two versions are. All texts of a block are sketched, subtracted
and peeled together.
"""

from __future__ import annotations

import base64
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

PARTS, CELLS, GROWTH = 3, 12, 4
#: Where paragraphs end: line ends, and the ends of sentences.
ENDS = re.compile(r"\n+|(?<=[.!?]) +")
#: Characters from which on a paragraph is cut after words that its words' own bytes choose, one in so many.
LONG, ONE_IN = 160, 8
WORD = re.compile(r"\S+\s*")
#: Rows of a block, which are sketched together.
ROWS = 512
CELL = np.dtype([("count", "<i4"), ("digest", "<u8"), ("check", "<u4")])


def paragraphs(text: str) -> list[str]:
    """The pieces of a text, in order; none for a text of breaks only."""
    out = []
    for part in ENDS.split(text):
        if len(part) <= LONG:
            if part:
                out.append(part)
            continue
        begin = 0
        for m in WORD.finditer(part):
            if xxhash.xxh32_intdigest(m[0]) % ONE_IN == 0:
                out.append(part[begin : m.end()])
                begin = m.end()
        if begin < len(part):
            out.append(part[begin:])
    return out


def digests(text: str) -> list[int]:
    """64-bit digests of the paragraphs, all distinct: an equal paragraph's next occurrence has another seed."""
    seen: dict[str, int] = {}
    out = []
    for part in paragraphs(text):
        seen[part] = turn = seen.get(part, -1) + 1
        out.append(xxhash.xxh64_intdigest(part, turn))
    return out


def _mixed(x: np.ndarray, salt: int) -> np.ndarray:
    """A 64-bit finaliser, for cells and check values."""
    with np.errstate(over="ignore"):
        x = x + np.uint64(salt * 0x9E3779B97F4A7C15 & (1 << 64) - 1)
        x = (x ^ x >> np.uint64(30)) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ x >> np.uint64(27)) * np.uint64(0x94D049BB133111EB)
    return x ^ x >> np.uint64(31)


def _checks(keys: np.ndarray) -> np.ndarray:
    return (_mixed(keys, 99) >> np.uint64(32)).astype(np.uint32)


def _cells(keys: np.ndarray, owner: np.ndarray, cells: int) -> np.ndarray:
    """(PARTS, n): where each digest lies in the joint table of all owners."""
    part = np.uint64(cells // PARTS)
    return np.stack([owner * cells + k * (cells // PARTS) + (_mixed(keys, 7 * k + cells) % part).astype(np.int64) for k in range(PARTS)])


def sketch(keys: np.ndarray, owner: np.ndarray, owners: int, cells: int) -> np.ndarray:
    """Sketches of all owners' digests, (owners, cells) of CELL."""
    out = np.zeros(owners * cells, CELL)
    checks = _checks(keys)
    for at in _cells(keys, owner, cells):
        np.add.at(out["count"], at, 1)
        np.bitwise_xor.at(out["digest"], at, keys)
        np.bitwise_xor.at(out["check"], at, checks)
    return out.reshape(owners, cells)


def subtract(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    out = np.empty_like(a)
    out["count"], out["digest"], out["check"] = a["count"] - b["count"], a["digest"] ^ b["digest"], a["check"] ^ b["check"]
    return out


def peel(difference: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(owner, digest, side) of what comes out, side 1 for the first and -1 for the second; and whether all of an owner's did."""
    owners, cells = difference.shape
    flat = difference.reshape(-1).copy()
    found: list[tuple[np.ndarray, ...]] = []
    while True:
        pure = np.flatnonzero((np.abs(flat["count"]) == 1) & (_checks(flat["digest"]) == flat["check"]))
        if not len(pure):
            break
        owner, keys, side = pure // cells, flat["digest"][pure], flat["count"][pure]
        _, one = np.unique(np.stack([owner.astype(np.uint64), keys]), axis=1, return_index=True)
        owner, keys, side = owner[one], keys[one], side[one]
        found.append((owner, keys, side))
        checks = _checks(keys)
        for at in _cells(keys, owner, cells):
            np.subtract.at(flat["count"], at, side)
            np.bitwise_xor.at(flat["digest"], at, keys)
            np.bitwise_xor.at(flat["check"], at, checks)
    rest = flat.reshape(owners, cells)
    clean = ((rest["count"] == 0) & (rest["digest"] == 0) & (rest["check"] == 0)).all(axis=1)
    joined = [np.concatenate([f[k] for f in found]) if found else np.zeros(0, np.int64) for k in range(3)]
    return joined[0], joined[1], joined[2], clean


def _flat(lists: list[list[int]], which: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    sizes = [len(lists[i]) for i in which]
    keys = np.array([k for i in which for k in lists[i]], np.uint64)
    return keys, np.repeat(np.arange(len(which)), sizes)


def recovered(a: list[list[int]], b: list[list[int]], cells: int = CELLS) -> list[tuple[list[int], list[int]]]:
    """For each pair of digest lists, those only in the first and those only in the second.

    Pairs that get stuck are sketched again with more cells and other places, until none does.
    """
    out: list[tuple[list[int], list[int]]] = [([], []) for _ in a]
    open_ = np.arange(len(a))
    while len(open_):
        ka, oa = _flat(a, open_)
        kb, ob = _flat(b, open_)
        owner, keys, side, clean = peel(subtract(sketch(ka, oa, len(open_), cells), sketch(kb, ob, len(open_), cells)))
        for o, k, s in zip(owner.tolist(), keys.tolist(), side.tolist()):
            if clean[o]:
                out[open_[o]][s < 0].append(k)
        open_, cells = open_[~clean], cells * GROWTH
    return out


def likeness(a: list[list[int]], b: list[list[int]]) -> np.ndarray:
    """1 less the share of all digests that differ; 1 for two texts without paragraphs."""
    apart = np.array([len(x) + len(y) for x, y in recovered(a, b)], np.float64)
    both = np.array([len(x) + len(y) for x, y in zip(a, b)], np.float64)
    return 1 - apart / np.maximum(both, 1)


def printed(lists: list[list[int]]) -> list[str]:
    """Each list's sketch of the first size, as text: base64 of its cells, 16 bytes each."""
    keys, owner = _flat(lists, np.arange(len(lists)))
    return [base64.b64encode(t.tobytes()).decode() for t in sketch(keys, owner, len(lists), CELLS)]


def neighbours(docs: DataFrame, blocks: int, id_column: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, text, next_text: the text of the next row by descending id; after the last comes the first.

    Equal ids follow each other by a hash of their texts, null ids come last, null texts are empty. The
    rows are cut into blocks of ids, so that no task holds more than a block; each block also gets the
    first rows of the one that follows it. Texts move once.
    """
    rows = docs.select(F.col(id_column).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    edges = rows.agg(F.percentile_approx("doc_id", [i / blocks for i in range(1, blocks)] or [0.5], 10_000)).first()[0] or []
    edges = sorted(set(edges))
    # block 0 has the null ids, block 1 those up to the first edge, and so on
    block = F.when(F.col("doc_id").isNull(), 0).otherwise(1 + F.size(F.filter(F.array(*map(F.lit, edges)) if edges else F.array().cast("array<long>"), lambda e: e < F.col("doc_id"))))
    tops = {r["block"]: r["top"] for r in rows.select(block.alias("block"), "doc_id").groupBy("block").agg(F.max("doc_id").alias("top")).collect()}
    order = sorted(tops, reverse=True)
    before = {b: order[i - 1] for i, b in enumerate(order)}  # of the first block: the last, around the ring
    spark = docs.sparkSession
    ring = spark.createDataFrame([(b, tops[b], before[b]) for b in order], f"block int, top {rows.schema['doc_id'].dataType.simpleString()}, before int")
    placed = rows.withColumn("block", block).join(F.broadcast(ring), "block")
    own = F.struct(F.col("block").alias("block"), F.lit(0).alias("guest"))
    guest = F.when(F.col("doc_id").eqNullSafe(F.col("top")), F.struct(F.col("before").alias("block"), F.lit(1).alias("guest")))
    dealt = placed.select("doc_id", "text", F.explode(F.filter(F.array(own, guest), lambda x: x.isNotNull())).alias("at")).select("doc_id", "text", "at.block", "at.guest")
    by = Window.partitionBy("block").orderBy("guest", F.col("doc_id").desc_nulls_last(), F.xxhash64("text"))
    return dealt.withColumn("next_text", F.lead("text").over(by)).where("guest = 0").drop("block", "guest")


def compared(rows: DataFrame) -> DataFrame:
    """rows (doc_id, text, edited, next_text) as doc_id, fingerprint, edited_fingerprint, near_edited, near_next, and what else rows has but texts."""
    texts = ["text", "edited", "next_text"]
    kept = [c for c in rows.columns if c not in texts]
    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.select(*kept).schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last: tuple[str | None, list[int]] = (None, [])
        for whole in batches:
            for begin in range(0, whole.num_rows, ROWS):
                batch = whole.slice(begin, ROWS)
                own, edited, following = [], [], []
                for t, e, n in zip(*(batch.column(batch.schema.names.index(c)) for c in texts)):
                    t, e, n = t.as_py(), e.as_py(), n.as_py()
                    own.append(last[1] if t == last[0] else digests(t))
                    edited.append(digests(e))
                    last = (n, digests(n))
                    following.append(last[1])
                made = [pa.array(printed(own)), pa.array(printed(edited)), pa.array(likeness(own, edited)), pa.array(likeness(own, following))]
                yield pa.RecordBatch.from_arrays([*batch.select(kept).columns, *made], [*kept, "fingerprint", "edited_fingerprint", "near_edited", "near_next"])

    return rows.mapInArrow(run, f"{kinds}, fingerprint string, edited_fingerprint string, near_edited double, near_next double")
