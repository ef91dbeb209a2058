"""WARC archives compressed with Zstandard: one frame for each record, a dictionary in front.

An archive begins with a skippable frame that holds the dictionary; each record is a frame of its own,
so a reader can start at any record. Archives are written by Spark's own file writer, so they go to any
store that Spark reaches and a lost task leaves nothing behind: frames are the rows of a text file whose
line end is an empty skippable frame, which any Zstandard reader passes over. The reader loads the
dictionary, walks the frames by their block headers, decodes one frame for each record, and checks
headers, lengths and digests.
"""

from __future__ import annotations

import base64
import hashlib
import struct
from collections.abc import Iterator
from urllib.parse import quote

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from contrast.llm.common import materialise

# Fixed values of the formats: frame magics, the dictionary frame's own, and a dictionary's.
FRAME, DICTIONARY_FRAME, SKIPPABLE, DICTIONARY = 0xFD2FB528, 0x184D2A5D, 0x184D2A50, 0xEC30A437
#: An empty skippable frame, in ASCII characters: the line end of the text writer.
LINE_END = struct.pack("<II", SKIPPABLE, 0).decode("ascii")
VERSION = b"WARC/1.1"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
#: Records that a dictionary is trained on at most, bytes of each and of the dictionary.
SAMPLES, SAMPLE_BYTES, DICTIONARY_BYTES = 128, 1 << 14, 1 << 15
#: Bytes of records from which on an archive is full.
ARCHIVE_BYTES = 64 << 20
LEVEL = 3


class ArchiveError(ValueError):
    """What an archive has that the formats don't allow."""


def sha1_base32(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record(page_id: int | None, url: str | None, payload: bytes, first_id: int | None = None, date: str = "1970-01-01T00:00:00Z") -> bytes:
    """The bytes of a response record, or, with the id of the page that has the payload, of a revisit record.

    A revisit keeps the HTTP header with the payload's length and leaves out the payload itself.
    """
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = http + payload if first_id is None else http
    fields = [("WARC-Type", "response" if first_id is None else "revisit"), ("WARC-Record-ID", f"<urn:page:{'' if page_id is None else page_id}>"), ("WARC-Date", date)]
    if url is not None:
        fields.append(("WARC-Target-URI", quote(url, safe="!#$%&'()*+,/:;=?@[]~")))
    if first_id is not None:
        fields += [("WARC-Refers-To", f"<urn:page:{first_id}>"), ("WARC-Profile", PROFILE)]
    fields += [("WARC-Payload-Digest", f"sha1:{sha1_base32(payload)}"), ("WARC-Block-Digest", f"sha1:{sha1_base32(block)}"), ("Content-Type", "application/http; msgtype=response"), ("Content-Length", str(len(block)))]
    return VERSION + b"\r\n" + b"".join(f"{k}: {v}\r\n".encode() for k, v in fields) + b"\r\n" + block + b"\r\n\r\n"


def _fields(head: bytes) -> dict[str, str]:
    out = {}
    for line in head.split(b"\r\n"):
        name, colon, value = line.partition(b":")
        if not colon or not name.strip():
            raise ArchiveError(f"no header field: {line[:80]!r}")
        out[name.strip().decode().lower()] = value.strip().decode()
    return out


def _page(urn: str) -> int | None:
    if not (urn.startswith("<urn:page:") and urn.endswith(">")):
        raise ArchiveError(f"no record id of a page: {urn}")
    return int(urn[10:-1]) if urn[10:-1] else None


def parse(data: bytes) -> dict:
    """page_id, payload_bytes, payload_digest, record_type, refers_to, url and payload of a record's bytes, all checked."""
    head, gap, rest = data.partition(b"\r\n\r\n")
    first, _, lines = head.partition(b"\r\n")
    if first != VERSION or not gap:
        raise ArchiveError(f"no WARC record: {first[:20]!r}")
    fields = _fields(lines)
    if missing := {"warc-type", "warc-record-id", "warc-date", "content-length", "warc-payload-digest"} - fields.keys():
        raise ArchiveError(f"header lacks {sorted(missing)}")
    length = int(fields["content-length"])
    if len(rest) != length + 4 or rest[length:] != b"\r\n\r\n":
        raise ArchiveError(f"the block has {len(rest) - 4} bytes, its header says {length}")
    block = rest[:length]
    if fields.get("warc-block-digest") not in (None, f"sha1:{sha1_base32(block)}"):
        raise ArchiveError("the block has another digest than its header says")
    http, gap, payload = block.partition(b"\r\n\r\n")
    status, _, lines = http.partition(b"\r\n")
    if not status.startswith(b"HTTP/") or not gap:
        raise ArchiveError("the block has no HTTP header")
    size, digest, kind = int(_fields(lines)["content-length"]), fields["warc-payload-digest"].removeprefix("sha1:"), fields["warc-type"]
    if kind == "response" and (len(payload) != size or sha1_base32(payload) != digest):
        raise ArchiveError("the payload has another length or digest than its headers say")
    if kind == "revisit" and (payload or "warc-refers-to" not in fields):
        raise ArchiveError("a revisit record has a payload or refers to nothing")
    if kind not in ("response", "revisit"):
        raise ArchiveError(f"unknown record type: {kind}")
    first_id = _page(fields["warc-refers-to"]) if kind == "revisit" else None
    return {"page_id": _page(fields["warc-record-id"]), "payload_bytes": size, "payload_digest": digest, "record_type": kind, "refers_to": first_id, "url": fields.get("warc-target-uri"), "payload": payload if kind == "response" else None}


def make_dictionary(samples: list[bytes]) -> zstandard.ZstdCompressionDict:
    """Trained on the samples; where they are too few or too alike for that, their own last bytes."""
    try:
        return zstandard.train_dictionary(DICTIONARY_BYTES, samples)
    except zstandard.ZstdError:
        return zstandard.ZstdCompressionDict(b"".join(samples)[-DICTIONARY_BYTES:], dict_type=zstandard.DICT_TYPE_RAWCONTENT)


def frames(records: Iterator[bytes]) -> Iterator[bytes]:
    """The frames of an archive: the dictionary's, then one for each record. No records, no frames.

    The first records, a bounded number, are held back until the dictionary is made of them.
    """
    held = []
    for one in records:
        held.append(one)
        if len(held) == SAMPLES:
            break
    if not held:
        return
    dictionary = make_dictionary([x[:SAMPLE_BYTES] for x in held])
    packed = zstandard.ZstdCompressor(level=19).compress(dictionary.as_bytes())
    yield struct.pack("<II", DICTIONARY_FRAME, len(packed)) + packed
    compress = zstandard.ZstdCompressor(level=LEVEL, dict_data=dictionary, write_checksum=True, write_content_size=True).compress
    yield from map(compress, held)
    yield from map(compress, records)


def archives(records: Iterator[bytes], most: int) -> Iterator[tuple[int, bytes]]:
    """The frames of all records with their archive's number: a new archive begins once one holds `most` bytes of records."""
    number = 0
    while (begin := next(records, None)) is not None:

        def some(one: bytes | None) -> Iterator[bytes]:
            size = 0
            while one is not None:
                yield one
                size += len(one)
                one = next(records, None) if size < most else None

        yield from ((number, frame) for frame in frames(some(begin)))
        number += 1


def frame_end(data: memoryview, begin: int) -> int:
    """Where the frame that begins here ends, by its header and its blocks' headers."""
    magic = int.from_bytes(data[begin : begin + 4], "little")
    if magic & 0xFFFFFFF0 == SKIPPABLE:
        end = begin + 8 + int.from_bytes(data[begin + 4 : begin + 8], "little")
    elif magic == FRAME:
        flags = data[begin + 4]
        single = flags >> 5 & 1
        sized = (single, 2, 4, 8)[flags >> 6]
        end = begin + 5 + (not single) + (0, 1, 2, 4)[flags & 3] + sized
        last = False
        while not last:
            block = int.from_bytes(data[end : end + 3], "little")
            last, kind, size = block & 1, block >> 1 & 3, block >> 3
            if kind == 3 or end + 3 > len(data):
                raise ArchiveError("a frame has a bad block")
            end += 3 + (1 if kind == 1 else size)
        end += 4 * (flags >> 2 & 1)
    else:
        raise ArchiveError(f"no frame at byte {begin}")
    if end > len(data):
        raise ArchiveError("the last frame is cut off")
    return end


def read_records(archive: bytes) -> Iterator[bytes]:
    """The bytes of each record of an archive, decoded one at a time; an empty archive has none."""
    data = memoryview(archive)
    if not data:
        return
    if len(data) < 8 or int.from_bytes(data[:4], "little") != DICTIONARY_FRAME:
        raise ArchiveError("the archive doesn't begin with a dictionary")
    at = frame_end(data, 0)
    raw = bytes(data[8:at])
    if raw[:4] == struct.pack("<I", FRAME):
        raw = zstandard.ZstdDecompressor().decompress(raw)
    kind = zstandard.DICT_TYPE_FULLDICT if raw[:4] == struct.pack("<I", DICTIONARY) else zstandard.DICT_TYPE_RAWCONTENT
    decoder = zstandard.ZstdDecompressor(dict_data=zstandard.ZstdCompressionDict(raw, dict_type=kind))
    while at < len(data):
        end = frame_end(data, at)
        if int.from_bytes(data[at : at + 4], "little") == FRAME:
            try:
                yield decoder.decompress(data[at:end])
            except zstandard.ZstdError as e:
                raise ArchiveError(f"the frame at byte {at} can't be decoded: {e}") from e
        at = end


def with_first_ids(pages: DataFrame, least_bytes: int = 0) -> DataFrame:
    """page_id, url, payload and first_id: the least page id with the payload where that is another page, else null.

    pages: page_id, url, html. Payloads under least_bytes have no first page. Which page is first is
    found on digests alone, counted before they meet; payloads move once, by page.
    """
    payload = F.coalesce(F.col("html"), F.lit("")).cast("binary")
    rows = pages.select("page_id", "url", payload.alias("payload")).withColumn("digest", F.unhex(F.sha1("payload")))
    slim = materialise(rows.where(F.octet_length("payload") >= least_bytes).select("page_id", "digest").distinct(), "digests")
    first = slim.groupBy("digest").agg(F.min("page_id").alias("first_id"), F.count(F.lit(1)).alias("n")).where("n > 1 and first_id is not null").drop("n")
    again = slim.join(first, "digest").where(~F.col("page_id").eqNullSafe(F.col("first_id"))).select(F.col("page_id").alias("__page"), F.col("digest").alias("__digest"), "first_id")
    met = F.col("page_id").eqNullSafe(F.col("__page")) & (F.col("digest") == F.col("__digest"))
    return rows.join(again, met, "left").select("page_id", "url", "payload", "first_id")


def write_archives(pages: DataFrame, path: str, least_bytes: int = 0, archive_bytes: int = ARCHIVE_BYTES) -> None:
    """Writes a record for each row of pages (page_id, url, html) to archives under path, one or more for each task.

    A null html is an empty payload, a null url is left out, repeated rows have a record each (all of
    the same type). A task begins a further archive, with a dictionary of its own, once one has
    archive_bytes of records, so an archive is larger than that by one record at most.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def records():
            for batch in batches:
                for page, url, payload, first in zip(*(batch.column(i) for i in range(4))):
                    yield record(page.as_py(), url.as_py(), payload.as_py(), first.as_py())

        def packed():
            names = ["archive", "place", "frame"]
            return pa.RecordBatch.from_arrays([pa.array([n for n, _ in held], pa.int32()), pa.array(range(place - len(held), place), pa.int64()), pa.array([f for _, f in held], pa.binary())], names)

        held, size, place = [], 0, 0
        for number, frame in archives(records(), archive_bytes):
            held.append((number, frame))
            size, place = size + len(frame), place + 1
            if size >= 4 << 20:
                yield packed()
                held, size = [], 0
        if held:
            yield packed()

    made = with_first_ids(pages, least_bytes).mapInArrow(run, "archive int, place long, frame binary").sortWithinPartitions("archive", "place")
    made.select("archive", F.col("frame").cast("string").alias("value")).write.partitionBy("archive").option("lineSep", LINE_END).text(path)


def read_archives(spark: SparkSession, path: str, payloads: bool = False) -> DataFrame:
    """A row for each record of the archives under path: page_id, payload_bytes, payload_digest, record_type, refers_to, url.

    With payloads, the payload of responses too (binary). An archive that breaks a rule ends the read
    with an error that says how.
    """
    columns = {"page_id": pa.int64(), "payload_bytes": pa.int64(), "payload_digest": pa.string(), "record_type": pa.string(), "refers_to": pa.int64(), "url": pa.string()} | ({"payload": pa.binary()} if payloads else {})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for content in batch.column(0):
                held, size = [], 0
                for data in read_records(content.as_py()):
                    held.append(parse(data))
                    size += len(data) if payloads else 200
                    if size >= 4 << 20:
                        yield pa.RecordBatch.from_pylist(held, pa.schema(columns))
                        held, size = [], 0
                yield pa.RecordBatch.from_pylist(held, pa.schema(columns))

    kinds = {pa.int64(): "long", pa.string(): "string", pa.binary(): "binary"}
    files = spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path).select("content")
    return files.mapInArrow(run, ", ".join(f"{n} {kinds[t]}" for n, t in columns.items()))


ORACLE = """
WITH bits AS (SELECT page_id, strlen(coalesce(html, '')) AS n, CAST(CAST(unhex(sha1(coalesce(html, ''))) AS BIT) AS VARCHAR) AS b FROM pages),
digested AS (SELECT page_id, n, array_to_string(list_transform(range(32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', CAST(1 + 16 * CAST(substr(b, 5 * i + 1, 1) AS INT) + 8 * CAST(substr(b, 5 * i + 2, 1) AS INT) + 4 * CAST(substr(b, 5 * i + 3, 1) AS INT) + 2 * CAST(substr(b, 5 * i + 4, 1) AS INT) + CAST(substr(b, 5 * i + 5, 1) AS INT) AS BIGINT), 1)), '') AS digest FROM bits),
firsts AS (SELECT digest, min(page_id) AS first_id FROM digested GROUP BY digest)
SELECT page_id, n AS payload_bytes, digest AS payload_digest, CASE WHEN page_id = first_id THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id = first_id THEN NULL ELSE first_id END AS refers_to
FROM digested JOIN firsts USING (digest)
"""
