"""WARC archives as a chunked record table.

An archive is a table of its bytes: (archive_id, record_id, chunk_no, data). The chunks of one record, in order, are a
complete WARC/1.1 record, and the records of one archive, in order, are a valid WARC file (`archive_bytes`). A chunk is at most `chunk_bytes`
long, so a payload of any size streams through writer, shuffle and reader without ever being one value: the writer slices
the UTF-8 buffer it was given, the reader carries header state and SHA-1 digests from chunk to chunk and drops the bytes.

Equal payloads (same SHA-1, SHA-256 and length) of at least `min_revisit_bytes` are written once: the smallest page_id is the response, the others are
revisits that name it. Digests are computed first and shuffled without payloads; of the payloads only those that have copies move, once.

Defined results: null html is an empty payload; a null page_id has the id `null`, its record is read back with a null id; rows that repeat a page_id
are records of their own, and a row with the same page_id as the response is itself a response; null url gives no target line; an empty table gives no rows;
further columns are not read.
"""

from __future__ import annotations

import base64
import hashlib
import re
from collections.abc import Iterator
from urllib.parse import quote

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from contactscope.llm.common import forget, stored

CHUNK_BYTES = 256 * 1024
CHUNKS = "archive_id long, record_id string, page_id long, chunk_no long, data binary"


def base32_sha1(digest: bytes) -> str:
    return base64.b32encode(digest).decode()


def _digests(pages: DataFrame) -> DataFrame:
    """Identity of every payload; hashed in slices of the Arrow buffer."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            sizes, sha1, sha2 = [], [], []
            for x in b.column("html").cast(pa.binary()):
                data = x.as_buffer() if x.is_valid else b""
                sizes.append(len(memoryview(data)))
                sha1.append(base32_sha1(hashlib.sha1(data).digest()))
                sha2.append(hashlib.sha256(data).digest())
            yield pa.RecordBatch.from_arrays([b.column("page_id"), b.column("url"), b.column("html"), pa.array(sizes, pa.int64()), pa.array(sha1, pa.string()), pa.array(sha2, pa.binary())], ["page_id", "url", "html", "payload_bytes", "sha1", "sha2"])

    return pages.mapInArrow(run, "page_id long, url string, html string, payload_bytes long, sha1 string, sha2 binary")


def _header(page: int | None, url: str | None, size: int, digest: str, first: int | None) -> bytes:
    lines = ["WARC/1.1", f"WARC-Type: {'response' if first is None else 'revisit'}", f"WARC-Record-ID: <urn:page:{'null' if page is None else page}>"]
    if url is not None:
        lines.append(f"WARC-Target-URI: {quote(url, safe=':/?#[]@!$&()*+,;=%~-._')}")
    lines += ["WARC-Date: 1970-01-01T00:00:00Z", f"WARC-Payload-Digest: sha1:{digest}", f"X-Payload-Length: {size}"]
    if first is not None:
        lines += [f"WARC-Refers-To: <urn:page:{first}>", "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"]
    lines += ["Content-Type: text/html; charset=utf-8", f"Content-Length: {size if first is None else 0}"]
    return ("\r\n".join(lines) + "\r\n\r\n").encode()


def _write(rows: DataFrame, chunk_bytes: int, kind: str) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        archive, number = TaskContext.get().partitionId(), 0
        out: list[tuple] = []
        held = 0
        for b in batches:
            for page, url, html, size, sha1, first in zip(*(b.column(c) for c in ("page_id", "url", "html", "payload_bytes", "sha1", "first")), strict=True):
                page, first = page.as_py(), first.as_py()
                record = f"{kind}{archive:08d}-{number:010d}"
                number += 1
                head = _header(page, url.as_py(), size.as_py(), sha1.as_py(), first)
                body = memoryview(html.as_buffer() if html.is_valid and first is None else b"").cast("B")
                out.append((archive, record, page, 0, head))
                for k, at in enumerate(range(0, len(body), chunk_bytes)):
                    piece = bytes(body[at : at + chunk_bytes])
                    out.append((archive, record, page, k + 1, piece))
                    held += len(piece)
                    if held >= 8 << 20:
                        yield _chunk_batch(out)
                        out, held = [], 0
                out.append((archive, record, page, (len(body) + chunk_bytes - 1) // chunk_bytes + 1, b"\r\n\r\n"))
        if out:
            yield _chunk_batch(out)

    return rows.mapInArrow(run, CHUNKS)


def _chunk_batch(rows: list[tuple]) -> pa.RecordBatch:
    kinds = (pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.binary())
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], ["archive_id", "record_id", "page_id", "chunk_no", "data"])


#: Most address bits of the table that tells which payloads may be copies: 16 MB, whatever the number of pages.
SUSPECT_BITS = 27


def _suspects(hashed: DataFrame, bits: int) -> np.ndarray:
    """A table of leading digest bits that two or more payloads share, as set by any group of equal ones (bits: 6 at least)."""
    slot = F.shiftrightunsigned(F.conv(F.substring(F.hex("sha2"), 1, 14), 16, 10).cast("long"), 56 - bits)
    groups = hashed.groupBy("sha1", "sha2", "payload_bytes").agg(F.count("*").alias("copies")).where("copies > 1")
    marks = np.zeros((1 << bits) >> 3, np.uint8)
    # sixty-four neighbouring slots travel as one word
    words = groups.select(slot.alias("slot")).groupBy(F.shiftright("slot", 6).alias("at")).agg(F.bit_or(F.expr("shiftleft(1L, cast(slot & 63 as int))")).alias("bits"))
    view = marks.view("<u8")
    for r in words.toLocalIterator():
        view[r["at"]] = r["bits"] & 0xFFFFFFFFFFFFFFFF
    return marks


def write_archives(pages: DataFrame, min_revisit_bytes: int = 0, chunk_bytes: int = CHUNK_BYTES, bits: int | None = None) -> DataFrame:
    """Write all pages; returns the chunk table, read from the shared folder. Pages are written where they are read, unless a bounded table of digest bits says that their payload may
    have copies: only those are joined with the groups of equal payloads, revisits among them without their payload."""
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    keys = ["sha1", "sha2", "payload_bytes"]
    digests = stored(_digests(rows).select("page_id", *keys).where(F.col("payload_bytes") >= min_revisit_bytes), "digests")
    bits = min(SUSPECT_BITS, max(6, digests.count().bit_length() + 4)) if bits is None else bits
    marks = pages.sparkSession.sparkContext.broadcast(_suspects(digests, bits))
    firsts = stored(digests.groupBy(*keys).agg(F.min("page_id").alias("least"), F.count("*").alias("copies")).where("copies > 1").drop("copies"), "firsts")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = marks.value
        for b in batches:
            slots = np.array([int.from_bytes(x[:7], "big") >> (56 - bits) for x in b.column("sha2").to_pylist()], np.int64)
            held = (table[slots >> 3] >> (slots & 7) & 1).astype(bool) & (b.column("payload_bytes").to_numpy() >= min_revisit_bytes)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(held)], [*b.schema.names, "suspect"])

    marked = _digests(rows)
    marked = marked.mapInArrow(run, T.StructType([*marked.schema.fields, T.StructField("suspect", T.BooleanType())]))
    none = F.lit(None).cast("long")
    single = _write(marked.where("not suspect").select("page_id", "url", "html", "payload_bytes", "sha1", none.alias("first")), chunk_bytes, "s")
    # the bytes of a copy move once, to be told from the response; a revisit's are left behind
    least = F.when(F.col("least").isNotNull() & ~F.col("least").eqNullSafe(F.col("page_id")), F.col("least"))
    found = marked.where("suspect").select("page_id", "url", "html", *keys).join(firsts, keys, "left").withColumn("first", least)
    again = _write(found.select("page_id", "url", F.when(F.col("first").isNull(), F.col("html")).alias("html"), "payload_bytes", "sha1", "first"), chunk_bytes, "d")
    out = stored(single.unionByName(again), "archives")
    forget(digests, firsts)
    return out


def read_records(chunks: DataFrame) -> DataFrame:
    """One row per record of the archives, parsed from its chunks: page_id, record_type, refers_to, target_uri,
    payload_bytes, payload_digest (from the header) and body_bytes, body_digest (computed while streaming). Chunks of a written table are read in the order of
    their archive, so nothing is shuffled but the few records that lie across two tasks' parts of a file."""
    held = chunks.select("record_id", "chunk_no", "data")
    parsed = stored(held.mapInArrow(_parsed(True), f"record_id string, whole boolean, {RECORDS}"), "records")
    names = [c.split()[0] for c in RECORDS.split(", ")]
    broken = stored(parsed.where("not whole").select("record_id").distinct(), "broken")
    # at most two for each task's part
    ordered = held.join(F.broadcast(broken), "record_id", "left_semi").repartition("record_id").sortWithinPartitions("record_id", "chunk_no")
    rest = ordered.mapInArrow(_parsed(False), f"record_id string, whole boolean, {RECORDS}")
    return parsed.where("whole").select(*names).unionByName(rest.select(*names))


def _parsed(partly: bool):
    """Chunks in order to records. partly: a record whose first or last chunks are elsewhere is named and not parsed; else that is an error."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state: _Reading | None = None

        def closed(state: _Reading) -> tuple:
            if partly and not state.complete():
                return (state.record, False, *[None] * 8)
            return (state.record, True, *state.row())

        for b in batches:
            done = []
            for record, number, data in zip(b.column("record_id").to_pylist(), b.column("chunk_no").to_pylist(), b.column("data"), strict=True):
                if state is None or state.record != record:
                    if state is not None:
                        done.append(closed(state))
                    state = _Reading(record)
                state.feed(number, data.as_buffer())
            if done:
                yield _record_batch(done)
        if state is not None:
            yield _record_batch([closed(state)])

    return run


RECORDS = "page_id long, record_type string, refers_to long, target_uri string, payload_bytes long, payload_digest string, body_bytes long, body_digest string"
_FIELD = re.compile(rb"([A-Za-z-]+): (.*)")


def _record_batch(rows: list[tuple]) -> pa.RecordBatch:
    kinds = (pa.string(), pa.bool_(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64(), pa.string())
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], ["record_id", "whole", *(c.split()[0] for c in RECORDS.split(", "))])


class _Reading:
    """A record in the course of reading: its header, then a digest and a count of the body bytes so far."""

    def __init__(self, record: str):
        self.record, self.head, self.fields = record, b"", None
        self.sha1, self.left, self.size = hashlib.sha1(), 0, 0
        self.next, self.gap, self.end = 0, False, False

    def feed(self, number: int, data) -> None:
        view = memoryview(data).cast("B")
        self.gap |= number != self.next
        self.next = number + 1
        if self.gap:
            return
        if self.fields is None:
            self.head += bytes(view)
            head, mark, body = self.head.partition(b"\r\n\r\n")
            if not mark:
                return
            self.fields = {k.decode(): v.decode() for k, v in (_FIELD.fullmatch(x).groups() for x in head.split(b"\r\n")[1:])}
            self.left = int(self.fields["Content-Length"])
            self.head, view = b"", memoryview(body)
        take = view[: self.left]
        self.sha1.update(take)
        self.size += len(take)
        self.left -= len(take)
        self.end = bytes(view[len(take) :])[-4:] == b"\r\n\r\n" and not self.left

    def complete(self) -> bool:
        """The header, all of the body and the closing line ends were read, from the first chunk on."""
        return not self.gap and self.fields is not None and self.end

    def row(self) -> tuple:
        if not self.complete():
            raise ValueError(f"record {self.record} is cut short")
        f = self.fields
        page = lambda x: None if x is None or x == "<urn:page:null>" else int(x.removeprefix("<urn:page:").removesuffix(">"))
        digest = f["WARC-Payload-Digest"].removeprefix("sha1:")
        found = base32_sha1(self.sha1.digest())
        if f["WARC-Type"] == "response" and (digest != found or int(f["X-Payload-Length"]) != self.size):
            raise ValueError(f"record {self.record}: digest or length doesn't match its body")
        return page(f["WARC-Record-ID"]), f["WARC-Type"], page(f.get("WARC-Refers-To")), f.get("WARC-Target-URI"), int(f["X-Payload-Length"]), digest, self.size, found


def archive_bytes(chunks: DataFrame, archive_id: int) -> Iterator[bytes]:
    """The bytes of one archive as a WARC file, chunk by chunk in order."""
    rows = chunks.where(F.col("archive_id") == archive_id).orderBy("record_id", "chunk_no").select("data")
    return (bytes(r["data"]) for r in rows.toLocalIterator())


def payload_chunks(chunks: DataFrame) -> DataFrame:
    """The payload pieces of responses alone: page_id, chunk_no from 0, data."""
    ends = chunks.groupBy("record_id").agg(F.max("chunk_no").alias("end"))
    return chunks.join(ends, "record_id").where("chunk_no > 0 and chunk_no < end").select("page_id", (F.col("chunk_no") - 1).alias("chunk_no"), "data")


def digest(pages: DataFrame, min_revisit_bytes: int = 0) -> DataFrame:
    """The contract's columns, from reading the archives back."""
    return read_records(write_archives(pages, min_revisit_bytes)).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")
