"""Exact dedup by Golomb-coded fingerprint exchange.

1. Every partition hashes its normalised texts, cuts the hashes to as many bits as the corpus size needs, sorts them and
   sends each owner (a range of the hash space) one Golomb-Rice coded block: two bits streams, unary quotients and fixed-width
   remainders. A hash that a partition holds many times is sent twice at most, so a huge group of copies costs an
   owner one or two codes per partition.
2. An owner decodes its blocks, finds hashes that were sent more than once, and answers with its slice of a duplicate
   bitmap that is addressed by the leading hash bits. All slices together have a size that is bounded by `max_bitmap_bits`.
3. Partitions receive the bitmap and emit only suspects, texts whose bit is set, after merging equal texts of a batch. Only these
   are shuffled, and grouping compares the normalised texts byte by byte. A wrong suspect is just a group of one.

Defined results: null text is empty text, and all texts of white space alone are equal; the longest original text (code
points) stays, then the smallest doc_id, a null doc_id last; rows that repeat a doc_id get one answer each, and all rows
with the kept doc_id count as kept; an empty table gives no rows; further columns are not read.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from contactscope.llm.common import stored

#: What normalising deletes.
BLANKS = b"\x20\x09\x0a\x0b\x0c\x0d"
_ONE = np.uint64(1)


def normalised(text: bytes | None) -> bytes:
    return text.translate(None, BLANKS) if text else b""


def fingerprint(data: bytes) -> int:
    return xxhash.xxh64_intdigest(data)


def golomb_encode(values: np.ndarray, low: int, span: int) -> bytes:
    """Sorted uint64 values in [low, low + span) as a Golomb-Rice block: count, remainder width, quotients, remainders."""
    n = len(values)
    if not n:
        return b""
    gaps = np.diff(values, prepend=np.uint64(low))
    width = max(0, int(max(1, span // n)).bit_length() - 1)
    quotients = (gaps >> np.uint64(width)).astype(np.int64)
    ends = np.cumsum(quotients + 1)
    unary = np.ones(int(ends[-1]), np.uint8)
    unary[ends - 1] = 0
    shifts = np.arange(width - 1, -1, -1, dtype=np.uint64)
    rest = ((gaps[:, None] >> shifts) & _ONE).astype(np.uint8).ravel()
    head = np.array([n, width, len(unary)], "<u4").tobytes()
    return head + np.packbits(unary).tobytes() + np.packbits(rest).tobytes()


def golomb_decode(block: bytes, low: int) -> np.ndarray:
    if not block:
        return np.zeros(0, np.uint64)
    n, width, size = (int(x) for x in np.frombuffer(block[:12], "<u4"))
    cut = 12 + (size + 7) // 8
    unary = np.unpackbits(np.frombuffer(block[12:cut], np.uint8), count=size)
    quotients = np.diff(np.flatnonzero(unary == 0), prepend=-1).astype(np.uint64) - _ONE
    gaps = quotients << np.uint64(width)
    if width:
        bits = np.unpackbits(np.frombuffer(block[cut:], np.uint8), count=n * width).reshape(n, width)
        for j in range(width):
            gaps |= bits[:, j].astype(np.uint64) << np.uint64(width - 1 - j)
    return np.cumsum(gaps, dtype=np.uint64) + np.uint64(low)


class Plan:
    """Sizes that follow from the number of rows: bits of a fingerprint, owners, bits of the bitmap (all powers of two)."""

    def __init__(self, rows: int, parallel: int, max_bitmap_bits: int = 1 << 31, per_owner: int = 2_000_000):
        log_n = max(1, rows - 1).bit_length()
        self.bitmap = min(max(16, log_n + 4), max_bitmap_bits.bit_length() - 1)
        self.bits = min(64, max(log_n + 16, self.bitmap))
        self.owners = min(self.bitmap - 3, max((rows // per_owner).bit_length(), max(1, parallel).bit_length() - 1))

    def span(self) -> int:
        return 1 << (self.bits - self.owners)


def _send(texts: DataFrame, plan: Plan) -> DataFrame:
    """Rows of two kinds: a document's digest, and at the end of a partition one coded block for each owner."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: list[np.ndarray] = []
        for b in batches:
            ids, text = b.column("doc_id"), b.column("text")
            norm = [normalised(t) for t in text.cast(pa.binary()).to_pylist()]
            prints = np.array([fingerprint(x) for x in norm], np.uint64) >> np.uint64(64 - plan.bits)
            seen.append(prints)
            sha = [hashlib.sha256(x).hexdigest() for x in norm]
            none = pa.nulls(len(norm))
            yield pa.RecordBatch.from_arrays([ids.cast(pa.int64()), pc.fill_null(pc.utf8_length(text), 0).cast(pa.int64()), pa.array(sha, pa.string()), none.cast(pa.int64()), none.cast(pa.binary())], ["doc_id", "n_cp", "sha", "owner", "coded"])
        prints = np.sort(np.concatenate(seen)) if seen else np.zeros(0, np.uint64)
        if len(prints):
            keep = np.ones(len(prints), bool)
            keep[2:] = prints[2:] != prints[:-2]
            prints = prints[keep]
            owner = (prints >> np.uint64(plan.bits - plan.owners)).astype(np.int64)
            firsts = np.flatnonzero(np.diff(owner, prepend=-1))
            coded = [golomb_encode(p, int(owner[f]) * plan.span(), plan.span()) for f, p in zip(firsts, np.split(prints, firsts[1:]), strict=True)]
            none = pa.nulls(len(coded))
            yield pa.RecordBatch.from_arrays([none.cast(pa.int64()), none.cast(pa.int64()), none.cast(pa.string()), pa.array(owner[firsts], pa.int64()), pa.array(coded, pa.binary())], ["doc_id", "n_cp", "sha", "owner", "coded"])

    return texts.mapInArrow(run, "doc_id long, n_cp long, sha string, owner long, coded binary")


def _owned(blocks: DataFrame, plan: Plan) -> DataFrame:
    """Every owner's slice of the duplicate bitmap."""

    def run(group: pa.Table) -> pa.Table:
        owner = group.column("owner")[0].as_py()
        low = owner * plan.span()
        prints = np.sort(np.concatenate([golomb_decode(x, low) for x in group.column("coded").to_pylist()]))
        again = prints[1:][prints[1:] == prints[:-1]]
        if not len(again):
            return pa.table({"owner": pa.array([], pa.int64()), "bitmap": pa.array([], pa.binary())})
        size = 1 << (plan.bitmap - plan.owners)
        bits = np.zeros(size, np.uint8)
        bits[((again - np.uint64(low)) >> np.uint64(plan.bits - plan.bitmap)).astype(np.int64)] = 1
        return pa.table({"owner": pa.array([owner], pa.int64()), "bitmap": pa.array([np.packbits(bits).tobytes()], pa.binary())})

    return blocks.groupBy("owner").applyInArrow(run, "owner long, bitmap binary")


def _suspects(texts: DataFrame, plan: Plan, slices: dict[int, bytes]) -> DataFrame:
    """Texts whose bit is set, equal ones of a batch merged: their count and the row that would stay. slices: the owners' answers, of owners with duplicates alone."""
    held = texts.sparkSession.sparkContext.broadcast(slices)
    width = plan.bitmap - plan.owners

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        answers = held.value
        for b in batches:
            ids, text = b.column("doc_id").to_pylist(), b.column("text")
            lengths = pc.fill_null(pc.utf8_length(text), 0).to_pylist()
            groups: dict[bytes, list] = {}
            for doc, n, t in zip(ids, lengths, text.cast(pa.binary()).to_pylist(), strict=True):
                norm = normalised(t)
                at = fingerprint(norm) >> (64 - plan.bitmap)
                bits, at = answers.get(at >> width), at & ((1 << width) - 1)
                if bits is not None and bits[at >> 3] >> (7 - (at & 7)) & 1:
                    best = (-n, doc is None, doc or 0)
                    g = groups.setdefault(norm, [0, best])
                    g[0] += 1
                    g[1] = min(g[1], best)
            texts_, counts, best = list(groups), [g[0] for g in groups.values()], [g[1] for g in groups.values()]
            yield pa.RecordBatch.from_arrays(
                [pa.array([hashlib.sha256(x).hexdigest() for x in texts_], pa.string()), pa.array(texts_, pa.binary()), pa.array(counts, pa.int64()), pa.array([x[0] for x in best], pa.int64()), pa.array([x[1] for x in best], pa.bool_()), pa.array([None if x[1] else x[2] for x in best], pa.int64())],
                ["sha", "norm", "n", "less", "missing", "doc_id"],
            )

    return texts.mapInArrow(run, "sha string, norm binary, n long, less long, missing boolean, doc_id long")


def duplicates(docs: DataFrame, max_bitmap_bits: int = 1 << 31) -> DataFrame:
    """Per document: doc_id, keep_id, group_size, kept, text_sha256."""
    spark = docs.sparkSession
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    plan = Plan(texts.count(), int(spark.conf.get("spark.sql.shuffle.partitions")), max_bitmap_bits)
    sent = stored(_send(texts, plan), "sent")
    # at most max_bitmap_bits / 8 bytes in all, and only of owners that found duplicates
    slices = {r["owner"]: bytes(r["bitmap"]) for r in _owned(sent.where("owner is not null").select("owner", "coded"), plan).toLocalIterator()}
    verified = _suspects(texts, plan, slices).groupBy("sha", "norm").agg(F.sum("n").alias("group_size"), F.min(F.struct("less", "missing", "doc_id")).alias("best"))
    groups = verified.where("group_size > 1").select("sha", "group_size", F.col("best.doc_id").alias("keep_id"))
    rows = sent.where("owner is null").select("doc_id", "sha").join(groups, "sha", "left")
    grouped = F.col("group_size").isNotNull()
    keep = F.when(grouped, F.col("keep_id")).otherwise(F.col("doc_id"))
    return rows.select("doc_id", keep.alias("keep_id"), F.coalesce("group_size", F.lit(1)).cast("long").alias("group_size"), F.coalesce(keep.eqNullSafe(F.col("doc_id")), F.lit(False)).alias("kept"), F.col("sha").alias("text_sha256"))
