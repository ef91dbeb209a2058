"""Near duplicates by overlap: all pairs of texts whose shingle sets have a Jaccard similarity of a threshold or more.

A fingerprint of 64 bits is sure of close copies only, so these pairs are found by min-hashes: a text's
keys are BANDS groups of ROWS minima, and two texts meet where they share a key. At similarity 0.8 two
texts share none with a chance of (1 - 0.8^5)^48, about 5e-9. What meets is verified on the whole sets.

Pairs of a crowd would grow with its square. So each key's members are first compared with the key's
least member; what is then joined, by any links, needs no comparing again. Where a key's members still lie
in several components, they are compared in blocks, in memory, by their minima alone: the share of equal
ones estimates the similarity. Pairs that it doesn't rule out are verified in memory too: the whole sets of
their nodes come to each block once, and components that have been joined aren't compared again. A
pair at 0.8 is ruled out with a chance of some 3e-5 (four standard deviations of 480 minima).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from contrast.llm.common import give_back, materialise

WIDTH, SEED = 4, 42
#: Shingles that are hashed at once.
HASHED = 1 << 15
BANDS, ROWS = 48, 5
#: Min-hashes by which similarity is estimated; the first make the keys.
MINIMA = 2 * BANDS * ROWS
#: The least similarity of a pair, as a fraction.
OVER, UNDER = 4, 5
#: Estimated similarity from which on a pair is verified: the threshold less four standard deviations.
LEAST = OVER / UNDER - 4 * (OVER / UNDER * (1 - OVER / UNDER) / MINIMA) ** 0.5
#: Members of a key that are compared together, and shingles that these have at most.
TOGETHER, HELD = 2048, 1 << 22
#: Shingles whose minima are taken at once.
BLOCK = 1 << 12
_MULTIPLIERS = np.random.default_rng(SEED).integers(0, 1 << 32, (MINIMA, 2), np.uint32) | np.array([1, 0], np.uint32)


def shingle_hashes(words: list[bytes], width: int = WIDTH, seed: int = SEED) -> Iterator[np.ndarray]:
    """Hashes of all shingles of a text's words, a block at a time; words fewer than a shingle's are one."""
    if 0 < len(words) < width:
        yield np.array([xxhash.xxh64_intdigest(b" ".join(words), seed)], "<u8")
    for begin in range(0, len(words) - width + 1, HASHED):
        part = words[begin : begin + HASHED + width - 1]
        ends = np.cumsum([len(w) + 1 for w in part]).tolist()
        joined, starts = b" ".join(part), [0, *ends]
        yield np.array([xxhash.xxh64_intdigest(joined[a : b - 1], seed) for a, b in zip(starts, ends[width - 1 :])], "<u8")


def shingles(text: str | None, width: int, seed: int = SEED) -> np.ndarray:
    """The distinct hashes of a text's shingles, sorted; none of a text without words."""
    return distinct(list(shingle_hashes((text or "").encode().lower().split(), width, seed)))


def distinct(parts: list[np.ndarray]) -> np.ndarray:
    return np.unique(np.concatenate(parts)) if parts else np.zeros(0, np.uint64)


def keys_of(found: np.ndarray) -> tuple[np.ndarray, bytes]:
    """One key for each band of minima, and the minima's lowest bytes; none of an empty set."""
    if not len(found):
        return np.zeros(0, np.uint64), b""
    half = (found >> np.uint64(32)).astype(np.uint32)
    least = np.full(len(_MULTIPLIERS), 0xFFFFFFFF, np.uint32)
    for begin in range(0, len(half), BLOCK):
        mixed = (half[begin : begin + BLOCK] ^ _MULTIPLIERS[:, 1:]) * _MULTIPLIERS[:, :1]
        np.minimum(least, mixed.min(axis=1), out=least)
    rows = least[: BANDS * ROWS].reshape(BANDS, ROWS)
    return np.array([xxhash.xxh64_intdigest(row.tobytes(), band) for band, row in enumerate(rows)], np.uint64), least.astype(np.uint8).tobytes()


def _sets(docs: DataFrame, wanted: DataFrame, id_column: str, text: str, width: int) -> DataFrame:
    """node, hashes of the rows of docs that stand for the wanted nodes (node, rep)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            made = [shingles(t.as_py(), width).view(np.int64) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(made, pa.list_(pa.int64()))], ["node", "hashes"])
        give_back()

    own = docs.select(F.col(id_column).alias("rep"), F.col(text).alias("text"))
    return own.join(wanted, "rep").select("node", "text").mapInArrow(run, "node long, hashes array<long>").dropDuplicates(["node"])


def may(a: Column, b: Column) -> Column:
    """Whether sets of these sizes can be similar enough."""
    return UNDER * F.least(a, b) >= OVER * F.greatest(a, b)


def verified(pairs: DataFrame, own: DataFrame, docs: DataFrame, id_column: str, text: str, width: int) -> DataFrame:
    """(u, v), as fingerprints, of those pairs of nodes whose whole sets are similar enough."""
    pairs = materialise(pairs.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct(), "candidates")
    wanted = own.join(pairs.select(F.explode(F.array("u", "v")).alias("node")).distinct(), "node")
    sets = materialise(_sets(docs, wanted.select("node", "rep"), id_column, text, width).join(wanted.select("node", "fp"), "node"), "sets")
    side = lambda name: sets.select(F.col("node").alias(name), F.col("hashes").alias(f"{name}_set"), F.col("fp").alias(f"{name}_fp"))
    both = pairs.join(side("u"), "u").join(side("v"), "v")
    shared = F.size(F.array_intersect("u_set", "v_set"))
    similar = (OVER + UNDER) * shared >= OVER * (F.size("u_set") + F.size("v_set"))
    return both.where(similar).where("u_fp <> v_fp").select(F.greatest("u_fp", "v_fp").alias("u"), F.least("u_fp", "v_fp").alias("v")).distinct()


def _groups(batches: Iterator[pa.RecordBatch], made) -> Iterator[pa.RecordBatch]:
    """made(rows) of each group of key, i and j, whose rows come one after the other; a group may go on in the next batch."""
    held: pa.Table | None = None

    def closed(rows: pa.Table, whole: bool) -> tuple[list[pa.RecordBatch], pa.Table | None]:
        where = np.stack([rows.column(c).to_numpy() for c in ("key", "i", "j")])
        begins = np.flatnonzero(np.concatenate([[True], (where[:, 1:] != where[:, :-1]).any(axis=0)]))
        ends = [*begins[1:], len(rows)]
        last = len(begins) if whole else len(begins) - 1
        return [made(rows.slice(a, b - a)) for a, b in zip(begins[:last], ends)], None if whole else rows.slice(begins[-1])

    for batch in batches:
        now = pa.Table.from_batches([batch])
        held = now if held is None else pa.concat_tables([held, now])
        if len(held):
            out, held = closed(held, False)
            yield from out
    if held is not None and len(held):
        yield from closed(held, True)[0]
    give_back()


def _partners(members: DataFrame, together: int) -> DataFrame:
    """key, i, j, node, root, others: of each two blocks of a key the nodes of likely pairs, each pair with one of them.

    A key's members are dealt to blocks by hash, so that a block's whole sets fit a task as well.
    """
    kinds = members.groupBy("key").agg(F.count(F.lit(1)).alias("members"), F.sum("n").alias("held"), F.min("root").alias("a"), F.max("root").alias("b")).where("a <> b")
    blocks = F.ceil(F.greatest(F.col("members") / together, F.col("held") / HELD)).cast("int")
    dealt = members.join(kinds.select("key", blocks.alias("blocks")), "key").withColumn("block", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
    met = dealt.select("key", "node", "n", "root", "keys", "minima", "block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other"))
    met = met.select("key", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block", "node", "n", "root", "keys", "minima")

    def compared(rows: pa.Table) -> pa.RecordBatch:
        key, one, other = (rows.column(c)[0].as_py() for c in ("key", "i", "j"))
        block, node, n, root = (rows.column(c).to_numpy() for c in ("block", "node", "n", "root"))
        keys = rows.column("keys").combine_chunks().flatten().to_numpy().reshape(-1, BANDS)
        minima = np.frombuffer(b"".join(rows.column("minima").to_pylist()), np.uint8).reshape(-1, MINIMA)
        others, named = [node[:0]] * len(node), np.zeros(len(node), bool)
        for i in range(len(node) - 1):
            after = slice(i + 1, None)
            may = (root[after] != root[i]) & (UNDER * np.minimum(n[after], n[i]) >= OVER * np.maximum(n[after], n[i]))
            if one != other:
                may &= block[after] != block[i]
            at = np.flatnonzero(may) + i + 1
            at = at[(minima[at] == minima[i]).mean(axis=1) >= LEAST]
            shared = keys[at] == keys[i]
            at = at[keys[i][shared.argmax(axis=1)] == key] if len(at) else at
            others[i] = node[at]
            named[i] |= len(at) > 0
            named[at] = True
        at = np.flatnonzero(named)
        same = [pa.array(np.full(len(at), x), t) for x, t in ((key, pa.int64()), (one, pa.int32()), (other, pa.int32()))]
        return pa.RecordBatch.from_arrays([*same, pa.array(node[at]), pa.array(root[at]), pa.array([others[i] for i in at], pa.list_(pa.int64()))], ["key", "i", "j", "node", "root", "others"])

    return met.repartition("key", "i", "j").sortWithinPartitions("key", "i", "j").mapInArrow(lambda batches: _groups(batches, compared), "key long, i int, j int, node long, root long, others array<long>")


def likely(members: DataFrame, together: int = TOGETHER) -> DataFrame:
    """(u, v): pairs of nodes with a common key that lie in different components and may be similar enough.

    members: key, node, n, root, keys, minima. Each two blocks of a key's members meet in memory; a pair comes
    out under its first common key only. Keys of one component have nothing to compare and go first.
    """
    return _partners(members, together).select(F.col("node").alias("u"), F.explode("others").alias("v"))


def linked(members: DataFrame, own: DataFrame, docs: DataFrame, id_column: str, text: str, width: int, together: int = TOGETHER) -> DataFrame:
    """(u, v), as fingerprints: they join the components of all likely pairs whose whole sets are similar enough.

    Likely pairs of a crowd grow with its square, so they are never rows: a node comes once to each two blocks
    of a key where it has such pairs, with its whole set, and pairs are verified there. Components that were
    joined there already aren't compared again, so what comes out are no more rows than nodes.
    """
    places = materialise(_partners(members, together), "partners")
    wanted = own.join(places.select("node").distinct(), "node")
    sets = materialise(_sets(docs, wanted.select("node", "rep"), id_column, text, width).join(wanted.select("node", "fp"), "node"), "sets")

    def joined(rows: pa.Table) -> pa.RecordBatch:
        node, root, fp = (rows.column(c).to_numpy() for c in ("node", "root", "fp"))
        held = rows.column("hashes").combine_chunks()
        offsets, hashes = held.offsets.to_numpy(), held.values.to_numpy(zero_copy_only=False)
        place, over = {x: k for k, x in enumerate(node.tolist())}, {x: x for x in root.tolist()}

        def top(x: int) -> int:
            while over[x] != x:
                over[x] = x = over[over[x]]
            return x

        us, vs = [], []
        for a, others in enumerate(rows.column("others").to_pylist()):
            for b in map(place.__getitem__, others):
                one, two = top(int(root[a])), top(int(root[b]))
                if one == two:
                    continue
                x, y = (hashes[offsets[k] : offsets[k + 1]] for k in (a, b))
                if (OVER + UNDER) * len(np.intersect1d(x, y, assume_unique=True)) >= OVER * (len(x) + len(y)):
                    over[two] = one
                    us.append(max(fp[a], fp[b]))
                    vs.append(min(fp[a], fp[b]))
        return pa.RecordBatch.from_arrays([pa.array(us, pa.int64()), pa.array(vs, pa.int64())], ["u", "v"])

    met = places.join(sets, "node").select("key", "i", "j", "node", "root", "others", "fp", "hashes")
    return met.repartition("key", "i", "j").sortWithinPartitions("key", "i", "j").mapInArrow(lambda batches: _groups(batches, joined), "u long, v long").distinct()
