"""Byte-level BPE: encoding in time linear in the text, and decoding.

A sequence of tokens is what the merges give exactly when each token comes out of its own bytes and
each two neighbours come out of their joint bytes. So a piece is covered from the left with the
longest tokens that fit their left neighbour; where none fits, the place is marked as a dead end and
the last token gives way to the next shorter one. Every place becomes a dead end once at most. An
Aho-Corasick automaton over the vocabulary, with bytes as Latin-1 characters, finds the longest
token at each place, and what neighbours are compatible is remembered.
"""

from __future__ import annotations

import base64
from array import array
from collections.abc import Iterator
from functools import cached_property

import ahocorasick
import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from contrast.llm.common import give_back

#: Pieces that a worker remembers in each of two generations, and pairs before it starts anew.
MEMO, PAIRS = 150_000, 400_000
#: Bytes of results that are handed on together.
FLUSH = 8 << 20


def read_ranks(lines: bytes) -> dict[bytes, int]:
    """Token bytes and ranks from the text of a .tiktoken file: base64 token and rank on each line."""
    pairs = (line.split() for line in lines.splitlines() if line.strip())
    return {base64.b64decode(token): int(rank) for token, rank in pairs}


class Codec:
    """Encodes and decodes by a rank table; a lower rank merges first."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.ranks = ranks
        self.tokens = {rank: token for token, rank in ranks.items()}
        self.find = regex.compile(pattern).findall
        self.recent: dict[str, bytes] = {}  # ids of pieces, packed
        self.older: dict[str, bytes] = {}
        self.pairs: dict[int, bool] = {}
        self.own: dict[int, bool] = {}
        self.prefix: dict[int, int | None] = {}

    @cached_property
    def automaton(self) -> ahocorasick.Automaton:
        """Of all tokens; a worker that only decodes never makes it."""
        made = ahocorasick.Automaton()
        for token, rank in self.ranks.items():
            made.add_word(token.decode("latin-1"), (len(token), rank))
        made.make_automaton()
        return made

    def merged(self, piece: bytes) -> list[bytes]:
        """The merges as defined, lowest rank first and leftmost among equals; for short pieces."""
        parts = [piece[i : i + 1] for i in range(len(piece))]
        while len(parts) > 1:
            ranked = [(self.ranks[x + y], i) for i, (x, y) in enumerate(zip(parts, parts[1:])) if x + y in self.ranks]
            if not ranked:
                break
            i = min(ranked)[1]
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
        return parts

    def reachable(self, token: int) -> bool:
        """Whether merges make this token from its own bytes."""
        if (known := self.own.get(token)) is None:
            known = self.own[token] = len(self.merged(self.tokens[token])) == 1
        return known

    def compatible(self, left: int, right: int) -> bool:
        """Whether merges leave these two tokens side by side."""
        if (known := self.pairs.get(key := left << 32 | right)) is None:
            if len(self.pairs) >= PAIRS:
                self.pairs.clear()
            a, b = self.tokens[left], self.tokens[right]
            known = self.pairs[key] = self.merged(a + b) == [a, b]
        return known

    def shorter(self, token: int) -> int | None:
        """The longest other token that this one begins with."""
        if token not in self.prefix:
            whole = self.tokens[token]
            self.prefix[token] = next((self.ranks[whole[:n]] for n in range(len(whole) - 1, 0, -1) if whole[:n] in self.ranks), None)
        return self.prefix[token]

    def encode_piece(self, piece: bytes) -> tuple[int, ...]:
        if (whole := self.ranks.get(piece)) is not None:
            return (whole,)
        longest: list[int | None] = [None] * (len(piece) + 1)
        for end, (length, rank) in self.automaton.iter(piece.decode("latin-1")):
            longest[end + 1 - length] = rank  # ends ascend, so the longest stays
        dead, out, at = bytearray(len(piece) + 1), [], 0
        token = longest[0]
        while at < len(piece):
            while token is not None:
                end = at + len(self.tokens[token])
                if not dead[end] and self.reachable(token) and (not out or self.compatible(out[-1], token)):
                    break
                token = self.shorter(token)
            if token is not None:
                out.append(token)
                at, token = end, longest[end]
            elif out:
                dead[at] = 1
                token = out.pop()
                at -= len(self.tokens[token])
                token = self.shorter(token)
            else:
                raise ValueError("the vocabulary lacks a byte of the text")
        return tuple(out)

    def recalled(self, piece: str) -> bytes:
        """Packed ids of a piece that isn't recent; when the recent ones are many they become the older ones."""
        if (ids := self.older.get(piece)) is None:
            ids = array("I", self.encode_piece(piece.encode())).tobytes()
            if len(piece) > 64:
                return ids
        if len(self.recent) >= MEMO:
            self.older = dict(self.recent)
            self.recent.clear()
        self.recent[piece] = ids
        return ids

    def packed(self, text: str) -> bytes:
        """Ids of a text, as little-endian unsigned 32-bit integers."""
        known, recall = self.recent.get, self.recalled
        return b"".join([known(piece) or recall(piece) for piece in self.find(text)])

    def encode(self, text: str) -> list[int]:
        return list(memoryview(self.packed(text)).cast("I")) if text else []

    def decode(self, ids) -> bytes:
        return b"".join(map(self.tokens.__getitem__, ids))


_codecs: dict[tuple[str, str], Codec] = {}


def _codec(path: str, pattern: str) -> Codec:
    """One codec for each vocabulary in a worker, from the file that every machine has."""
    if (path, pattern) not in _codecs:
        with open(path, "rb") as f:
            _codecs[path, pattern] = Codec(read_ranks(f.read()), pattern)
    return _codecs[path, pattern]


def _mapped(df: DataFrame, column: str, made: tuple[str, ...], one) -> DataFrame:
    """df with binary columns made from another by one(value), a value for each, row by row in bounded pieces."""
    kept = [c for c in df.columns if c not in made]
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in df.select(*(F.col(f"`{c}`") for c in kept)).schema), *(f"`{m}` binary" for m in made)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        work = one()
        for batch in batches:
            rows, begin, size = [], 0, 0
            source = batch.column(batch.schema.names.index(column))
            for i in range(batch.num_rows):
                rows.append(work(source[i]))
                size += sum(map(len, rows[-1]))
                if size >= FLUSH or i + 1 == batch.num_rows:
                    part = batch.slice(begin, i + 1 - begin).select(kept)
                    yield pa.RecordBatch.from_arrays([*part.columns, *(pa.array(values, pa.binary()) for values in zip(*rows))], [*kept, *made])
                    rows, begin, size = [], i + 1, 0
        give_back()

    return df.mapInArrow(run, schema)


def encode_documents(docs: DataFrame, vocabulary: str, pattern: str, text: str = "text", ids: str = "token_ids") -> DataFrame:
    """docs with the token ids of each whole text: little-endian unsigned 32-bit integers in a binary column.

    vocabulary: path of a rank file that every machine has. Null and empty texts have no ids. Special
    tokens in a text are ordinary text. Other columns stay; a column of the new name is replaced.
    """

    def one():
        packed = _codec(vocabulary, pattern).packed
        return lambda value: (packed(value.as_py() or ""),)

    return _mapped(docs, text, (ids,), one)


def decode_documents(encoded: DataFrame, vocabulary: str, pattern: str, ids: str = "token_ids", decoded: str = "decoded") -> DataFrame:
    """encoded with the bytes that the ids stand for; null ids give no bytes."""

    def one():
        decode = _codec(vocabulary, pattern).decode
        return lambda value: (decode(memoryview(value.as_buffer()).cast("I") if value.is_valid and len(value.as_buffer()) else ()),)

    return _mapped(encoded, ids, (decoded,), one)


def round_trip(docs: DataFrame, vocabulary: str, pattern: str, text: str = "text", ids: str = "token_ids", decoded: str = "decoded") -> DataFrame:
    """docs with the ids of each whole text and the bytes that these ids stand for, both made in one worker.

    The same as decode_documents(encode_documents(docs)), without a second worker that holds the vocabulary.
    """

    def one():
        codec = _codec(vocabulary, pattern)

        def both(value) -> tuple[bytes, bytes]:
            packed = codec.packed(value.as_py() or "")
            return packed, codec.decode(memoryview(packed).cast("I") if packed else ())

        return both

    return _mapped(docs, text, (ids, decoded), one)


def token_count(ids: Column) -> Column:
    return (F.coalesce(F.octet_length(ids), F.lit(0)) / 4).cast("long")
