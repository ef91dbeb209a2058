"""Language-model scoring by context-tree weighting over bytes.

A text, A-Z in lower case, is coded byte by byte, with an end mark. Each byte is eight binary decisions,
from its highest bit. The contexts of a byte are the bytes before it, none to DEPTH of them, nearest first,
across words and breaks; before a text's begin stand marks. Every context that the training texts hold is
a node of the tree, however rare, so the tree grows with the corpus. In each node, a Krichevsky-Trofimov
estimate stands for each decision, and the weighting of all prunings gives its probability: a node's own
estimate counts for one half, the product of its children for the other, through all depths. What a
node lacks has no counts, and its estimate is one half.

Nothing of this is held by one machine. Texts are read in chunks. A chunk names its distinct pairs of
context and byte once, packed by buckets of the CROWN nearest bytes; a bucket holds the whole subtrees below
some of these. Buckets sum the counts of all chunks and weigh their subtrees from the leaves up; what comes
out at the crown is a table, on which the few depths above are sums and joins; then predictions come
down again and each bucket answers each chunk. A chunk's distinct words meet their counts in the same way.
What comes back to a chunk prices its texts, which were packed beside.
"""

from __future__ import annotations

import math
import zlib
from collections.abc import Iterator
from itertools import groupby

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from contrast.llm.common import crc_remainder, give_back, materialise

#: Bytes of a context at most; with the byte that follows they fit a positive number.
DEPTH = 5
#: The byte before a text's begin and at its end; UTF-8 has no such byte.
MARK = 0xFF
#: Bytes of texts in a chunk, from which on it is closed, and of those whose pairs are made at once.
CHUNK, PART = 16 << 20, 1 << 19
#: Depth above which the tree is a table of Spark; a subtree below has 256 to the power of what is left of leaves.
CROWN = 3
#: Parts that are packed, and priced, together.
TOLD = 4
#: Keys that are held with their counts before they are summed up.
SUMMED = 1 << 20
PAIR, WORD = 1, 2


class Texts:
    """Some texts in lower case: their bytes, where each begins and ends, and the pairs of context and byte."""

    def __init__(self, texts: pa.Array):
        plain = pc.fill_null(texts.cast(pa.large_string()), "")
        offsets = np.frombuffer(plain.buffers()[1], np.int64, len(plain) + 1, plain.offset * 8)
        whole = plain.buffers()[2]
        self.data = whole.slice(offsets[0], offsets[-1] - offsets[0]).to_pybytes().lower() if whole is not None else b""
        self.ends = offsets - offsets[0]

    def __len__(self) -> int:
        return len(self.ends) - 1

    def parts(self, part: int = PART, begin: int = 0, last: int | None = None) -> Iterator[tuple[int, int]]:
        """Ranges of texts, from one to another, of some bytes each; a longer text is alone."""
        last = len(self) if last is None else last
        while begin < last:
            end = int(np.searchsorted(self.ends, self.ends[begin] + part, side="right")) - 1
            end = min(max(end, begin + 1), last)
            yield begin, end
            begin = end

    def pairs(self, begin: int, end: int, depth: int) -> tuple[np.ndarray, np.ndarray]:
        """Of each byte and end mark of these texts: context and byte as a number, and which text."""
        mark = bytes([MARK]) * depth
        texts = [self.data[self.ends[i] : self.ends[i + 1]] for i in range(begin, end)]
        data = np.frombuffer(mark + mark.join(texts) + mark, np.uint8)
        sizes = np.diff(self.ends[begin : end + 1]) + 1
        keys = np.zeros(len(data) - depth, np.int64)
        for k in range(depth + 1):  # the byte itself lowest, then the farthest; the nearest highest
            one = data[depth - k : len(data) - k].astype(np.int64)
            one <<= 8 * (depth - k + 1) if k else 0
            keys |= one
        if depth > 1:  # marks between texts: the first is a text's end, the others nothing
            asked = np.ones(len(keys), bool)
            ends = np.cumsum(sizes + depth - 1)[:-1] - (depth - 1)
            asked[(ends[:, None] + np.arange(depth - 1)).ravel()] = False
            asked[len(keys) - (depth - 1) :] = False
            keys = keys[asked]
        return keys, np.repeat(np.arange(begin, end, dtype=np.int32), sizes)

    def words(self, begin: int, end: int) -> tuple[pa.Array, np.ndarray]:
        """All words of these texts in order, and which text each is in."""
        ends = self.ends[begin : end + 1]
        data = pa.py_buffer(self.data[ends[0] : ends[-1]])
        plain = pa.Array.from_buffers(pa.large_string(), end - begin, [None, pa.py_buffer((ends - ends[0]).astype(np.int64).tobytes()), data])
        split = pc.ascii_split_whitespace(plain)
        found, owner = split.flatten(), pc.list_parent_indices(split).to_numpy()
        some = pc.greater(pc.binary_length(found), 0)
        return found.filter(some).cast(pa.large_binary()), owner[some.to_numpy(zero_copy_only=False)] + begin


def _counted(values: pa.Array, weights: np.ndarray) -> tuple[pa.Array, np.ndarray]:
    """Distinct values and the sums of their weights."""
    coded = values.dictionary_encode()
    return coded.dictionary, np.bincount(coded.indices.to_numpy(), weights, len(coded.dictionary)).astype(np.int64)


class Sums:
    """Distinct values and the sums of their counts, from many lists; a bounded number more are held."""

    def __init__(self, kind: pa.DataType):
        self.held, self.size, self.kind = [], 0, kind

    def add(self, values: pa.Array, n: np.ndarray) -> None:
        self.held.append((values, n))
        self.size += len(values)
        if self.size > SUMMED:
            self.held, self.size = [self.all()], 0

    def all(self) -> tuple[pa.Array, np.ndarray]:
        values, n = [v for v, _ in self.held], [c for _, c in self.held]
        self.held = []
        return _counted(pa.concat_arrays(values), np.concatenate(n)) if values else (pa.array([], self.kind), np.zeros(0, np.int64))


def _pack(*arrays: np.ndarray) -> bytes:
    return zstandard.compress(b"".join(a.tobytes() for a in arrays), 1)


def _unpack_pairs(data: bytes) -> tuple[np.ndarray, np.ndarray]:
    steps, n = np.frombuffer(zstandard.decompress(data), np.int64).reshape(2, -1)
    return np.cumsum(steps), n


def _unpack_words(data: bytes) -> tuple[pa.Array, np.ndarray]:
    whole = zstandard.decompress(data)
    size = int.from_bytes(whole[:8], "little")
    return pa.array(whole[8 + 8 * size :].split(b"\n"), pa.large_binary()), np.frombuffer(whole, np.int64, size, 8)


def gathered(rows: DataFrame, depth: int, buckets: int, most: int = CHUNK, part: int = PART) -> DataFrame:
    """chunk, kind, bucket, data, n: what each chunk of rows (doc_id, text, held_out) has.

    Kind 0: some of its texts, n of them for training. PAIR: distinct pairs of context and byte of a
    bucket, sorted, WORD: distinct words of a bucket, each with its number in training texts (0 of those that
    only others have); n is the sum of these.
    """
    names = ["chunk", "kind", "bucket", "data", "n"]

    def batch_of(found: list[tuple]) -> pa.RecordBatch:
        kinds = (pa.int64(), pa.int32(), pa.int32(), pa.binary(), pa.int64())
        return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*found), kinds)], names)

    def closed(chunk: int, held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        grams, words = Sums(pa.int64()), Sums(pa.large_binary())
        for batch in held:
            texts, learn = Texts(batch.column("text")), 1 - batch.column("held_out").cast(pa.int8()).to_numpy()
            for begin, end in texts.parts(TOLD * part):
                for i, j in texts.parts(part, begin, end):
                    keys, owner = texts.pairs(i, j, depth)
                    grams.add(*_counted(pa.array(keys), learn[owner]))
                    found, owner = texts.words(i, j)
                    words.add(*_counted(found, learn[owner]))
                own = batch.slice(begin, end - begin)
                sink = pa.BufferOutputStream()
                with pa.ipc.new_stream(sink, own.schema) as writer:
                    writer.write_batch(own)
                yield batch_of([(chunk, 0, 0, zstandard.compress(sink.getvalue().to_pybytes(), 3), int(learn[begin:end].sum()))])
        found, n = grams.all()
        order = np.argsort(keys := found.to_numpy())
        keys, n = keys[order], n[order]
        bucket = bucket_of(keys, depth, buckets)
        out = []
        for b in np.unique(bucket).tolist():
            at = bucket == b
            out.append((chunk, PAIR, b, _pack(np.diff(keys[at], prepend=0), n[at]), int(n[at].sum())))
        yield batch_of(out)
        values, n = words.all()
        listed = values.to_pylist()
        bucket = np.fromiter(map(zlib.crc32, listed), np.int64, len(listed)) % buckets
        order = np.argsort(bucket, kind="stable")
        out = []
        for at in np.split(order, np.flatnonzero(np.diff(bucket[order])) + 1) if len(order) else []:
            data = len(at).to_bytes(8, "little") + n[at].tobytes() + b"\n".join([listed[i] for i in at.tolist()])
            out.append((chunk, WORD, int(bucket[at[0]]), zstandard.compress(data, 3), int(n[at].sum())))
        if out:
            yield batch_of(out)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        give_back()
        chunk, held, size = TaskContext.get().partitionId() << 32, [], 0
        for batch in _sliced(batches, most):
            held.append(batch)
            size += batch.nbytes
            if size >= most:
                yield from closed(chunk, held)
                chunk, held, size = chunk + 1, [], 0
        if held:
            yield from closed(chunk, held)
        give_back()

    return rows.select("doc_id", "text", "held_out").mapInArrow(run, "chunk long, kind int, bucket int, data binary, n long")


def _sliced(batches: Iterator[pa.RecordBatch], most: int) -> Iterator[pa.RecordBatch]:
    """The same rows in batches of no more than so many bytes, or one row."""
    for batch in batches:
        begin, step = 0, max(1, batch.num_rows * most // (4 * max(batch.nbytes, 1)))
        while begin < batch.num_rows:
            yield batch.slice(begin, step)
            begin += step


def bucket_of(keys: np.ndarray, depth: int, buckets: int) -> np.ndarray:
    """The bucket of each pair: by its CROWN nearest bytes."""
    top = (keys >> 8 * (depth - min(CROWN, depth) + 1)).astype(np.uint64)
    return ((top * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(33)) % np.uint64(buckets)).astype(np.int64)


def log_gamma(x, log):
    """Of arguments from one half on: a series after a shift by eight."""
    shift = x
    for k in range(1, 8):
        shift = shift * (x + k)
    z = x + 8
    return (z - 0.5) * log(z) - z + 0.5 * math.log(2 * math.pi) + 1 / (12 * z) - 1 / (360 * z * z * z) + 1 / (1260 * z * z * z * z * z) - log(shift)


def _evidence(zeros, ones, log):
    return log_gamma(zeros + 0.5, log) + log_gamma(ones + 0.5, log) - log_gamma(zeros + ones + 1, log) - math.log(math.pi)


def evidence(zeros: Column, ones: Column) -> Column:
    """Log probability of the counts under the Krichevsky-Trofimov estimator, in any order."""
    zeros, ones = zeros.cast("double"), ones.cast("double")
    return F.when(zeros + ones == 0, 0.0).otherwise(_evidence(zeros, ones, F.log))


def log_sum(a: Column, b: Column) -> Column:
    return F.greatest(a, b) + F.log1p(F.exp(-F.abs(a - b)))


class Subtrees:
    """The nodes from the crown to the deepest contexts of some pairs (sorted, with training counts n).

    A node is a context and a decision, 1 and below it the bits before it: (context << 8) + decision.
    levels: for each depth nodes, zeros, ones, below (log evidence of the children) and own; up: for
    each depth but the first, each node's parent.
    """

    def __init__(self, keys: np.ndarray, n: np.ndarray, depth: int):
        byte, crown = keys & 255, min(CROWN, depth)
        self.bits = np.stack([byte >> 7 - b & 1 for b in range(8)])
        decisions = np.stack([(keys >> 8 << 8) + (1 << b) + (byte >> 8 - b) for b in range(8)])
        nodes, place = np.unique(decisions, return_inverse=True)
        self.place = place.reshape(8, -1)  # of each decision of each pair
        zeros, ones = (np.bincount(place.ravel(), (np.broadcast_to(n, self.bits.shape) * (self.bits == bit)).ravel(), len(nodes)) for bit in (0, 1))
        below, self.levels, self.up = np.zeros(len(nodes)), [], []
        for d in range(depth, crown - 1, -1):
            own = np.where(zeros + ones > 0, _evidence(zeros, ones, np.log), 0.0)
            self.levels.insert(0, (nodes, zeros, ones, below, own))
            self.weighted = own if d == depth else np.logaddexp(own, below) + math.log(0.5)
            if d > crown:
                nodes, up = np.unique((nodes >> 16 << 8) + (nodes & 255), return_inverse=True)
                self.up.insert(0, up)
                zeros, ones, below = (np.bincount(up, x, len(nodes)) for x in (zeros, ones, self.weighted))

    def prices(self, left: np.ndarray, seen_zeros: np.ndarray, seen_ones: np.ndarray) -> np.ndarray:
        """log10 probability of each pair's byte; given, for the crown's nodes, the weight that comes down to them and the chances gathered above."""
        for (_, zeros, ones, below, own), up in zip(self.levels, [*self.up, None]):
            zero, one = (zeros + 0.5) / (zeros + ones + 1), (ones + 0.5) / (zeros + ones + 1)
            if up is None:
                logs = np.log10(np.stack([seen_zeros + left * zero, seen_ones + left * one]))
                return logs[self.bits, self.place].sum(axis=0)
            with np.errstate(over="ignore"):
                stop, go = 1 / (1 + np.exp(below - own)), 1 / (1 + np.exp(own - below))
            left, seen_zeros, seen_ones = (left * go)[up], (seen_zeros + left * stop * zero)[up], (seen_ones + left * stop * one)[up]


def _by_bucket(rows: DataFrame, work, schema: str) -> DataFrame:
    """work(bucket, one-row tables in their order) for each bucket of rows (bucket, turn, ...), one after the other."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        each = ((b, batch.slice(i, j - i)) for batch in batches for b, i, j in _runs(batch.column("bucket").to_numpy()))
        for bucket, parts in groupby(each, key=lambda x: x[0]):
            yield from work(bucket, (p for _, p in parts))
        give_back()

    return rows.repartition("bucket").sortWithinPartitions("bucket", "turn").mapInArrow(run, schema)


def _runs(values: np.ndarray) -> Iterator[tuple[int, int, int]]:
    edges = [0, *(np.flatnonzero(np.diff(values)) + 1).tolist(), len(values)]
    return ((int(values[i]), i, j) for i, j in zip(edges, edges[1:]) if j > i)


def summed(found: Iterator[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys of several lists of keys and counts, sorted, and their sums."""
    sums = Sums(pa.int64())
    for keys, n in found:
        sums.add(pa.array(keys), n)
    keys, n = sums.all()
    order = np.argsort(keys)
    return keys.to_numpy()[order], n[order]


def crowned(pairs: DataFrame, depth: int) -> DataFrame:
    """bucket, data, and context, decision, zeros, ones, weighted: each bucket's sums packed, and its nodes at the crown."""

    def work(bucket: int, parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, n = summed(_unpack_pairs(x.as_py()) for part in parts for x in part.column("data"))
        made = Subtrees(keys, n, depth)
        nodes, zeros, ones, _, _ = made.levels[0]
        size = len(nodes)
        yield pa.RecordBatch.from_arrays([pa.array([bucket], pa.int32()), pa.array([_pack(np.diff(keys, prepend=0), n)], pa.binary()), *(pa.nulls(1, t) for t in (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.float64()))], names)
        yield pa.RecordBatch.from_arrays([pa.array(np.full(size, bucket, np.int32)), pa.nulls(size, pa.binary()), pa.array(nodes >> 8), pa.array((nodes & 255).astype(np.int32)), pa.array(zeros.astype(np.int64)), pa.array(ones.astype(np.int64)), pa.array(made.weighted)], names)

    names = ["bucket", "data", "context", "decision", "zeros", "ones", "weighted"]
    return _by_bucket(pairs.select("bucket", F.lit(0).alias("turn"), "data"), work, "bucket int, data binary, context long, decision int, zeros long, ones long, weighted double")


def come_down(crown: DataFrame, depth: int) -> DataFrame:
    """bucket, context, decision, left, seen_zeros, seen_ones of the crown's nodes (bucket, context, decision, zeros, ones, weighted).

    left is the weight that comes down to a node, seen_ the chances of a zero and of a one gathered above,
    each by itself: near one, a difference would lose a small chance.
    """
    tables = [crown]
    for d in range(min(CROWN, depth) - 1, -1, -1):
        up = tables[0].groupBy(F.shiftright("context", 8).alias("context"), "decision").agg(F.sum("zeros").alias("zeros"), F.sum("ones").alias("ones"), F.sum("weighted").alias("below"))
        own = up.withColumn("own", evidence(F.col("zeros"), F.col("ones")))
        tables.insert(0, materialise(own.withColumn("weighted", log_sum(F.col("own"), F.col("below")) + math.log(0.5)), f"contexts_{d}"))
    now = tables[0].select("*", F.lit(1.0).alias("left"), F.lit(0.0).alias("seen_zeros"), F.lit(0.0).alias("seen_ones"))
    for table in tables[1:]:
        more = F.col("below") - F.col("own")
        go, stop = 1 / (1 + F.exp(-more)), 1 / (1 + F.exp(more))  # one in all, however large the evidence
        seen = [(F.col(f"seen_{x}") + F.col("left") * stop * (F.col(x) + 0.5) / (F.col("zeros") + F.col("ones") + 1)).alias(f"seen_{x}") for x in ("zeros", "ones")]
        above = now.select(F.col("context").alias("up"), "decision", (F.col("left") * go).alias("left"), *seen)
        now = table.withColumn("up", F.shiftright("context", 8)).join(above, ["up", "decision"]).drop("up")
    return now.select("bucket", "context", "decision", "left", "seen_zeros", "seen_ones")


def priced(pairs: DataFrame, depth: int) -> DataFrame:
    """chunk, bucket, data: the log10 probabilities of each chunk's pairs of a bucket, packed in their order.

    pairs: chunk, bucket, data of the kind PAIR.
    """
    crown = materialise(crowned(pairs, depth), "crown")
    down = come_down(crown.where("data is null").drop("data"), depth)
    blank = [F.lit(None).cast(t).alias(c) for c, t in (("context", "long"), ("decision", "int"), ("left", "double"), ("seen_zeros", "double"), ("seen_ones", "double"))]
    lit = lambda x, kind, name: F.lit(x).cast(kind).alias(name)
    sums = crown.where("data is not null").select("bucket", lit(0, "int", "turn"), lit(None, "long", "chunk"), "data", *blank)
    nodes = down.select("bucket", lit(1, "int", "turn"), lit(None, "long", "chunk"), lit(None, "binary", "data"), "context", "decision", "left", "seen_zeros", "seen_ones")
    asked = pairs.select("bucket", lit(2, "int", "turn"), "chunk", "data", *blank)

    def work(bucket: int, parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, tree, price, given = None, None, None, []
        for part in parts:
            for turn, i, j in _runs(part.column("turn").to_numpy()):
                own = part.slice(i, j - i)
                if turn == 0:
                    keys, n = _unpack_pairs(own.column("data")[0].as_py())
                    tree = Subtrees(keys, n, depth)
                elif turn == 1:
                    given.append([own.column(c).to_numpy() for c in ("context", "decision", "left", "seen_zeros", "seen_ones")])
                else:
                    if price is None:
                        context, decision, *rest = (np.concatenate(x) for x in zip(*given))
                        order = np.argsort((context << 8) + decision)
                        price = tree.prices(*(x[order] for x in rest))
                    answers = [_pack(price[np.searchsorted(keys, _unpack_pairs(x.as_py())[0])]) for x in own.column("data")]
                    yield pa.RecordBatch.from_arrays([own.column("chunk"), own.column("bucket"), pa.array(answers, pa.binary())], ["chunk", "bucket", "data"])

    return _by_bucket(sums.unionByName(nodes).unionByName(asked), work, "chunk long, bucket int, data binary")


def counted_words(words: DataFrame) -> DataFrame:
    """chunk, bucket, data, n: how often all chunks have each of a chunk's words of a bucket, packed in their order.

    words: chunk, bucket, data of the kind WORD. Rows without a chunk say how many distinct words of the
    bucket have a count.
    """
    twice = words.select("chunk", "bucket", "data", F.explode(F.array(F.lit(0), F.lit(1))).alias("turn"))

    def work(bucket: int, parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums, total = Sums(pa.large_binary()), None
        for part in parts:
            for turn, i, j in _runs(part.column("turn").to_numpy()):
                for chunk, data in zip(part.column("chunk").slice(i, j - i), part.column("data").slice(i, j - i)):
                    values, n = _unpack_words(data.as_py())
                    if turn == 0:
                        sums.add(values, n)
                        continue
                    if total is None:
                        listed, total = sums.all()
                        yield pa.RecordBatch.from_arrays([pa.nulls(1, pa.int64()), pa.array([bucket], pa.int32()), pa.nulls(1, pa.binary()), pa.array([int((total > 0).sum())])], names)
                    answer = _pack(total[pc.index_in(values, value_set=listed).to_numpy()])
                    yield pa.RecordBatch.from_arrays([pa.array([chunk.as_py()], pa.int64()), pa.array([bucket], pa.int32()), pa.array([answer], pa.binary()), pa.nulls(1, pa.int64())], names)

    names = ["chunk", "bucket", "data", "n"]
    return _by_bucket(twice, work, "chunk long, bucket int, data binary, n long")


def scored(docs: DataFrame, id_column: str = "doc_id", text: str = "text", modulus: int = 7, out: int = 2, depth: int = DEPTH, most: int = CHUNK, part: int = PART) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score, bits_per_byte of each whole text.

    Learns from the rows whose crc32 of the id, modulo a number, isn't `out`. Tokens are the words and
    one end. score is the tree's log10 probability of the text with A-Z in lower case, breaks and end
    included; bits_per_byte is its code length over its bytes (one at least). base_score is the
    add-one estimate of the tokens. Null texts are empty; repeated rows come out repeated, null ids stay
    null. most and part: bytes of a chunk and of what is made at once. With no training text all estimates are those of no counts: one bit for each decision.
    """
    if not 0 < depth <= 6:
        raise ValueError("a context has one to six bytes")
    held_out = crc_remainder(F.col(id_column), modulus) == out
    rows = docs.select(F.col(id_column).alias("doc_id"), F.col(text).alias("text"), held_out.alias("held_out"))
    buckets = max(32, int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    chunks = materialise(gathered(rows, depth, buckets, most, part), "chunks")
    of = lambda kind: chunks.where(F.col("kind") == kind).select("chunk", "bucket", "data")
    counts = materialise(counted_words(of(WORD)), "word_counts")
    prices = materialise(priced(of(PAIR), depth), "prices")
    sums = {r["kind"]: r["n"] for r in chunks.groupBy("kind").agg(F.sum("n").alias("n")).collect()}
    texts, known = sums.get(0, 0), sums.get(WORD, 0)
    distinct = counts.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    n_train, floor = known + texts, float(known + texts + distinct + (texts > 0) + 1)
    end_base, some = math.log10((texts + 1) / floor), int(texts > 0)
    kind = rows.schema["doc_id"].dataType.simpleString()
    names = ["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score", "bits_per_byte"]

    def one(asked: pa.Table, answers: pa.Table) -> pa.Table:
        at = {(k, b): i for i, (k, b) in enumerate(zip(answers["kind"].to_pylist(), answers["bucket"].to_pylist()))}
        answer = lambda k, b, kind: np.frombuffer(zstandard.decompress(answers["data"][at[k, b]].as_py()), kind)
        pairs, words, packed = [], [(pa.array([], pa.large_binary()), np.zeros(0, np.int64))], []
        for k, b, data in zip(asked["kind"].to_pylist(), asked["bucket"].to_pylist(), asked["data"]):
            if k == PAIR:
                pairs.append((_unpack_pairs(data.as_py())[0], answer(k, b, np.float64)))
            elif k == WORD:
                words.append((_unpack_words(data.as_py())[0], answer(k, b, np.int64)))
            else:
                packed.append(data)
        grams, price = pa.array(np.concatenate([k for k, _ in pairs])), np.concatenate([p for _, p in pairs])
        listed, count = pa.concat_arrays([v for v, _ in words]), np.concatenate([c for _, c in words])
        base = np.log10((count + 1) / floor)
        made = []
        for data in packed:
            batch = next(iter(pa.ipc.open_stream(zstandard.decompress(data.as_py()))))
            texts, n = Texts(batch.column("text")), batch.num_rows
            score, tokens, seen, base_score = np.zeros(n), np.zeros(n, np.int64), np.zeros(n, np.int64), np.zeros(n)
            for begin, end in texts.parts(TOLD * part):
                keys, owner = texts.pairs(begin, end, depth)
                score += np.bincount(owner, price[pc.index_in(pa.array(keys), value_set=grams).to_numpy()], n)
                found, owner = texts.words(begin, end)
                place = pc.index_in(found, value_set=listed).to_numpy()
                tokens += np.bincount(owner, minlength=n)
                seen += np.bincount(owner[count[place] > 0], minlength=n)
                base_score += np.bincount(owner, base[place], n)
            bits = -score * math.log2(10) / np.maximum(np.diff(texts.ends), 1)
            own = [batch.column("doc_id"), batch.column("held_out"), tokens + 1, seen + some, np.full(n, n_train), base_score + end_base, score, bits]
            made.append(pa.table([pa.array(c) if isinstance(c, np.ndarray) else c for c in own], names))
        give_back()
        return pa.concat_tables(made)

    schema = f"doc_id {kind}, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double, bits_per_byte double"
    asked = chunks.select(F.col("chunk").alias("at"), "kind", "bucket", "data")
    answers = prices.select("chunk", F.lit(PAIR).alias("kind"), "bucket", "data").union(counts.where("chunk is not null").select("chunk", F.lit(WORD).alias("kind"), "bucket", "data"))
    return asked.groupBy("at").cogroup(answers.groupBy("chunk")).applyInArrow(one, schema)
