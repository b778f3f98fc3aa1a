"""Mixture-controlled packing by deficit round-robin over source queues.

Every source is a queue of tokens, served in cells of `cell` tokens. In each round a queue's credit grows by its share of a
window, and it sends as many whole cells as its credit covers; what is left of the credit is carried into the next round,
across windows and across partitions, so no prefix of the output is off its target by a cell or more. A queue that runs
dry leaves its turn to the others; the queues' last, short cells come at the very end. The served tokens, cut every `length`
tokens, are the sequences: all full but the last.

Nothing in this is sequential: how many cells a queue has sent by a round is a product rounded down, so the position of any cell
follows from the queue totals alone. Two passes suffice. The first turns each text into tokens once and stores them with their place within
(partition, source); the totals of those, one row per partition and source, become queue offsets by a prefix sum. The
second turns a document's token range into pieces. No group, however hot, meets in one task.

Ids are those of the tokenizer file, special strings in a text included. Texts made of the code points below U+0250 go
through the byte-pair ranks of the same vocabulary, which give the same ids there (tested on each of these code points) in a quarter of the time; all other texts go through the tokenizer itself.

Defined results: null text is empty and consists of the end id alone; null sources form one queue; a source without a given weight gets the
mean weight; repeated rows are packed as often as they occur; an empty table gives no rows; further columns are not read.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from contactscope.llm.common import stored

LENGTH, CELL = 2048, 512
END = 1
_PLAIN = re.compile("[\x00-ɏ]*")
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, source string"


class Encoder:
    """Token ids of texts by a tokenizer file; `ranks` names the same vocabulary for the fast way."""

    def __init__(self, tokenizer: str, ranks: str | None):
        import base64

        import public_tokenizers
        import tiktoken
        from tokenizers import Tokenizer

        self.exact, self.fast = Tokenizer.from_file(tokenizer), None
        if ranks:
            with open(ranks, "rb") as f:
                known = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
            special = {x.content: i for i, x in self.exact.get_added_tokens_decoder().items()}
            self.fast = tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=known, special_tokens=special)
            self.special = set(special)

    def ids(self, text: str) -> np.ndarray:
        if self.fast is not None and _PLAIN.fullmatch(text):
            return self.fast.encode_to_numpy(text, allowed_special=self.special)
        return np.array(self.exact.encode(text, add_special_tokens=False).ids, np.uint32)


_encoders: dict[tuple, Encoder] = {}


def encoder(tokenizer: str, ranks: str | None) -> Encoder:
    """One encoder per worker process."""
    return _encoders.setdefault((tokenizer, ranks), None) or _encoders.update({(tokenizer, ranks): Encoder(tokenizer, ranks)}) or _encoders[tokenizer, ranks]


class Rota:
    """Closed form of the deficit round-robin: queue totals and weights to the positions of cells."""

    def __init__(self, totals: list[int], weights: list[float] | None = None, length: int = LENGTH, cell: int = CELL):
        self.cell, self.length = cell, length
        self.full = np.array([t // cell for t in totals], np.int64)
        tail = np.array([t % cell for t in totals], np.int64)
        w = np.array([t for t in totals] if weights is None else weights, float)
        self.rate = np.maximum(w, 0) / max(w.sum(), 1e-300) * (length / cell)  # cells that a queue may send per round
        self.rate[(self.rate <= 0) & (self.full > 0)] = 1e-6
        self.tails = int(self.full.sum()) * cell + np.concatenate(([0], np.cumsum(tail)[:-1])) if len(totals) else tail

    def sent(self, queue: int, rounds: np.ndarray) -> np.ndarray:
        """Cells that a queue has sent by the end of a round."""
        return np.minimum(self.full[queue], np.floor(rounds * self.rate[queue]).astype(np.int64))

    def round_of(self, queue: int, cells: np.ndarray) -> np.ndarray:
        rounds = np.ceil((cells + 1) / self.rate[queue]).astype(np.int64)
        rounds = np.where((rounds > 0) & (self.sent(queue, rounds - 1) > cells), rounds - 1, rounds)
        return np.where(self.sent(queue, rounds) <= cells, rounds + 1, rounds)

    def positions(self, queue: int, cells: np.ndarray) -> np.ndarray:
        """Where the cells of a queue start in the output; cell number `full` is the short last one."""
        rounds, place = np.unique(self.round_of(queue, np.minimum(cells, max(self.full[queue] - 1, 0))), return_inverse=True)
        # what the other queues have sent by then, once for each round, a thousand rounds at a time
        others = np.zeros(len(rounds), np.int64)
        for at in range(0, len(rounds), 1024):
            r = rounds[at : at + 1024, None]
            first = np.minimum(self.full[:queue], np.floor(r * self.rate[:queue]).astype(np.int64)).sum(axis=1)
            others[at : at + 1024] = first + np.minimum(self.full[queue + 1 :], np.floor((r - 1) * self.rate[queue + 1 :]).astype(np.int64)).sum(axis=1)
        before = cells.astype(np.int64) + others[place]
        return np.where(cells >= self.full[queue], self.tails[queue], before * self.cell)


def _tokens(docs: DataFrame, tokenizer: str, ranks: str | None) -> DataFrame:
    """Every document's ids (two bytes each), and its place among the documents of its source in its partition."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        enc, part = encoder(tokenizer, ranks), TaskContext.get().partitionId()
        at: dict[str, int] = {}
        for b in batches:
            for lo in range(0, len(b), 512):
                s = b.slice(lo, 512)
                sources, coded, starts, sizes = s.column("queue").to_pylist(), [], [], []
                for text, source in zip(s.column("text"), sources, strict=True):
                    ids = np.append(enc.ids(text.as_py() or ""), END)
                    coded.append(ids.astype("<u2" if ids.max() < 1 << 16 else "<u4").tobytes())
                    starts.append(at.get(source, 0))
                    sizes.append(len(ids))
                    at[source] = starts[-1] + len(ids)
                yield pa.RecordBatch.from_arrays([s.column("doc_id"), s.column("source"), s.column("queue"), pa.array([part] * len(s), pa.int64()), pa.array(starts, pa.int64()), pa.array(sizes, pa.int64()), pa.array(coded, pa.binary())], ["doc_id", "source", "queue", "part", "local", "size", "ids"])

    return docs.mapInArrow(run, "doc_id long, source string, queue string, part long, local long, size long, ids binary")


def _pieces(tokens: DataFrame, rota: Rota, queues: dict[str, int]) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cell, length = rota.cell, rota.length
        for b in batches:
            out: list[tuple] = []
            sources = b.column("source").to_pylist()
            bases, sizes = b.column("base").to_numpy(), b.column("size").to_numpy()
            queue_of = np.array([queues[q] for q in b.column("queue").to_pylist()])
            firsts, lasts = bases // cell, (bases + sizes - 1) // cell
            where: list = [None] * len(sources)
            for q in np.unique(queue_of):
                rows = np.flatnonzero(queue_of == q)
                counts = (lasts - firsts + 1)[rows]
                cells = np.repeat(firsts[rows], counts) + np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts)
                for r, p in zip(rows, np.split(rota.positions(int(q), cells), np.cumsum(counts)[:-1]), strict=True):
                    where[r] = p
            for doc, source, base, size, coded, starts in zip(b.column("doc_id").to_pylist(), sources, bases.tolist(), sizes.tolist(), b.column("ids"), where, strict=True):
                raw = memoryview(coded.as_buffer()).cast("B")
                ids = np.frombuffer(raw, "<u2" if len(raw) == 2 * size else "<u4").astype("<u4")
                done, k = 0, base // cell
                runs: list[list[int]] = []  # output position, start in the document, length; neighbours joined
                for p in starts.tolist():
                    skip = base + done - k * cell
                    take = min(cell - skip, size - done)
                    if runs and runs[-1][0] + runs[-1][2] == p + skip:
                        runs[-1][2] += take
                    else:
                        runs.append([p + skip, done, take])
                    done, k = done + take, k + 1
                for p, at, n in runs:
                    while n:
                        take = min(n, length - p % length)
                        out.append((doc, at, take, zlib.crc32(ids[at : at + take].tobytes()), size, p // length, p % length, source))
                        p, at, n = p + take, at + take, n - take
            kinds = [pa.int64()] * 7 + [pa.string()]
            names = [c.split()[0] for c in PIECES.split(", ")]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], t) for i, t in enumerate(kinds)], names)

    return tokens.mapInArrow(run, PIECES)


def pack(docs: DataFrame, tokenizer: str | None = None, ranks: str | None = None, weights: dict[str, float] | None = None, length: int = LENGTH, cell: int = CELL, max_queues: int = 4096) -> DataFrame:
    """One row per piece. weights: target token shares by source; None means the shares of the corpus, which let
    all queues end together. length must be a multiple of cell. Each source is a queue; beyond max_queues sources those without a weight of their own share as many queues by hash, so that
    the plan of the round-robin stays bounded."""
    import public_tokenizers

    if length % cell:
        raise ValueError("length must be a multiple of cell")
    if tokenizer is None:
        tokenizer, ranks = public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("byte_bpe_50k.tiktoken")
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.coalesce(F.col("source").cast("string"), F.lit("")).alias("source"))
    named = F.array(*(F.lit(k) for k in weights or {})).cast("array<string>")
    queue = F.col("source")
    if rows.select("source").distinct().limit(max_queues + 1).count() > max_queues:
        queue = F.when(F.array_contains(named, F.col("source")), F.col("source")).otherwise(F.concat(F.lit("\u0000"), F.pmod(F.xxhash64("source"), F.lit(max_queues)).cast("string")))
    tokens = stored(_tokens(rows.withColumn("queue", queue), str(tokenizer), ranks and str(ranks)), "tokens")
    by_part = tokens.groupBy("part", "queue").agg(F.sum("size").alias("n"))
    before = Window.partitionBy("queue").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    bases = stored(by_part.select("part", "queue", "n", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("before")), "bases")
    # at most max_queues and the named ones
    totals = {r["queue"]: int(r["n"]) for r in bases.groupBy("queue").agg(F.sum("n").alias("n")).collect()}
    names = sorted(totals)
    shares = None
    if weights is not None:
        mean = sum(weights.values()) / max(1, len(weights))
        shares = [weights.get(s, mean) for s in names]
    rota = Rota([totals[s] for s in names], shares, length, cell)
    offsets = bases.select("part", "queue", "before")
    if bases.count() <= 1_000_000:
        offsets = F.broadcast(offsets)
    placed = tokens.join(offsets, ["part", "queue"]).select("doc_id", "source", "queue", (F.col("before") + F.col("local")).alias("base"), "size", "ids")
    return _pieces(placed, rota, {s: i for i, s in enumerate(names)})
