"""Benchmark decontamination: a broadcast hash set of normalised test n-grams scanned over training token windows.

The benchmark's word windows become sorted arrays of 64-bit hashes that go to every worker, with the items' words as bytes. The words of a
batch of documents are hashed at once, windows with one vectorised multiply-add per word; they pass a table of leading hash bits and
a search in the sorted hashes, and every find is verified word for word.

The set is broadcast in blocks of at most `max_ngrams` windows (some 20 bytes each) and MAX_BYTES of text; a longer item is spread over several. One block is one pass over the documents; a
benchmark of more takes several passes, the findings so far travelling with the rows, so nothing is dropped and what is broadcast stays bounded.

Defined results: null or wordless text has no words and no hit; a null benchmark text or id is no item; repeated items
count once by id; repeated documents are judged one by one; other columns are never read.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from contactscope.llm.common import stored
from contactscope.llm.wordhash import Hasher, shingles

WORD = re.compile(rb"[0-9a-z\x80-\xff]+")
#: Most bytes of benchmark text in one broadcast block.
MAX_BYTES = 64 << 20


def words_of(data: bytes | None) -> list[bytes]:
    """Words of UTF-8 text: runs of digits, lower-cased ASCII letters and code points from U+0080 on."""
    return WORD.findall(data.lower()) if data else []


class NgramSet:
    """Windows of the benchmark items as flat arrays: by length the sorted window hashes, where each window begins among the words, and its item; beside them the words' bytes."""

    def __init__(self, n: int):
        self.n, self.size, self.bytes = n, 0, 0
        self.items: list[str] = []
        self.words: list[bytes] = []
        self.starts: dict[int, list[int]] = {}
        self.owners: dict[int, list[int]] = {}

    def add(self, item: str, words: list[bytes]) -> None:
        """The item's windows; words: the whole item or, of a long one, a stretch that overlaps the last one by n - 1 words."""
        length = min(self.n, len(words))
        count = len(words) - length + 1
        self.starts.setdefault(length, []).extend(range(len(self.words), len(self.words) + count))
        self.owners.setdefault(length, []).extend([len(self.items)] * count)
        self.items.append(item)
        self.words += words
        self.size += count
        self.bytes += sum(map(len, words)) + 8 * len(words)

    def seal(self) -> NgramSet:
        lengths = [len(w) for w in self.words]
        self.data = b"".join(self.words)
        self.edges = np.concatenate(([0], np.cumsum(lengths, dtype=np.int64)))
        hashes = next(Hasher().texts([b" ".join(self.words)])) if self.words else np.zeros(0, np.uint64)
        self.tables = {}
        for length, starts in self.starts.items():
            at = np.array(starts, np.int64)
            made = shingles(hashes, length)[at]
            owner = np.array(self.owners[length], np.int32)
            order = np.lexsort((owner, made))
            # an item's repeated window once
            order = order[np.concatenate(([True], (np.diff(made[order]) != 0) | (np.diff(owner[order]) != 0)))]
            bits = min(24, max(12, len(at).bit_length() + 4))
            seen = np.zeros(1 << bits, bool)
            seen[(made >> np.uint64(64 - bits)).astype(np.int64)] = True
            self.tables[length] = (made[order], at[order], owner[order], bits, seen)
        del self.words, self.starts, self.owners
        return self

    def _window(self, start: int, length: int) -> list[bytes]:
        edges = self.edges[start : start + length + 1].tolist()
        return [self.data[s:e] for s, e in zip(edges, edges[1:])]

    def find(self, text: bytes, hashes: np.ndarray) -> tuple[list[tuple[int, int]], set[str]]:
        """Word ranges [start, end) of all verified windows of a text with these word hashes, and the items they belong to."""
        spans, items, words = [], set(), None
        for length, (known, starts, owners, bits, seen) in self.tables.items():
            if len(hashes) < length:
                continue
            made = shingles(hashes, length)
            near = np.flatnonzero(seen[(made >> np.uint64(64 - bits)).astype(np.int64)])
            if not len(near):
                continue
            low, high = (np.searchsorted(known, made[near], side) for side in ("left", "right"))
            for s, i, j in zip(near.tolist(), low.tolist(), high.tolist()):
                for k in range(i, j):
                    words = words_of(text) if words is None else words
                    if words[s : s + length] == self._window(int(starts[k]), length):
                        if not spans or spans[-1] != (s, s + length):
                            spans.append((s, s + length))
                        items.add(self.items[owners[k]])
        return spans, items


def _merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for s, e in sorted(spans):
        if out and s <= out[-1][1]:
            out[-1] = (out[-1][0], max(e, out[-1][1]))
        else:
            out.append((s, e))
    return out


def _blocks(benchmark: DataFrame, n: int, max_ngrams: int) -> Iterator[NgramSet]:
    block = NgramSet(n)
    for item, text in benchmark.select(F.col("item_id").cast("string"), F.col("text").cast("binary")).where("item_id is not null and text is not null").toLocalIterator():
        words = words_of(bytes(text))
        at = 0
        while at < max(1, len(words) - n + 1) and words:
            # a long item is cut into stretches that share n - 1 words, so that every window is in one of them
            block.add(item, words[at : at + max_ngrams + n - 1])
            at += max_ngrams
            if block.size >= max_ngrams or block.bytes >= MAX_BYTES:
                yield block.seal()
                block = NgramSet(n)
    yield block.seal()


def _free(names: list[str], wanted: tuple[str, ...]) -> list[str]:
    """Names like the wanted ones that no column has (column names don't tell case apart)."""
    taken = {n.lower() for n in names}
    out = []
    for w in wanted:
        while w in taken:
            w = f"_{w}"
        out.append(w)
    return out


def _scan(df: DataFrame, block: NgramSet, plain: list[str], extra: list[str], first: bool, last: bool, keep_clean: bool, share: int) -> DataFrame:
    held = df.sparkSession.sparkContext.broadcast(block)
    types = [T.StructField(c, t) for c, t in zip(extra, (T.LongType(), T.ArrayType(T.LongType()), T.ArrayType(T.StringType())), strict=True)]
    fields = [df.schema[c] for c in plain]
    schema = T.StructType(fields if keep_clean and last else [*fields, *types])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        grams, hasher = held.value, Hasher()
        for b in batches:
            counts, hits, items = [], [], []
            was = repeat(((), ())) if first else zip(b.column(extra[1]).to_pylist(), b.column(extra[2]).to_pylist(), strict=True)
            texts = [t or b"" for t in b.column("text").cast(pa.binary()).to_pylist()]
            for text, hashes, (spans, names) in zip(texts, hasher.texts(texts), was, strict=False):
                found, owners = grams.find(text, hashes)
                old = list(zip(spans[::2], spans[1::2], strict=True))
                counts.append(len(hashes))
                hits.append([x for span in _merged(old + found) for x in span])
                items.append(sorted({*names, *owners}))
            if keep_clean and last:
                hit = [sum(h[1::2]) - sum(h[::2]) for h in hits]
                clean = pa.array([not (h and share * h >= n) for h, n in zip(hit, counts, strict=True)], pa.bool_())
                yield b.select(plain).filter(clean)
            else:
                yield pa.RecordBatch.from_arrays([*(b.column(c) for c in plain), pa.array(counts, pa.int64()), pa.array(hits, pa.list_(pa.int64())), pa.array(items, pa.list_(pa.string()))], [*plain, *extra])

    return df.mapInArrow(run, schema)


def _scanned(docs: DataFrame, benchmark: DataFrame, n: int, max_ngrams: int, keep_clean: bool, share: int) -> tuple[DataFrame, list[str]]:
    """docs with the findings in columns whose names docs doesn't have, and these names."""
    plain = docs.columns
    extra = _free(plain, ("n_words", "hits", "items"))
    df, held, first = docs, None, True
    for block in _blocks(benchmark, n, max_ngrams):
        if held is not None:
            df = stored(_scan(df, held, plain, extra, first, False, keep_clean, share), "scan")
            first = False
        held = block
    return _scan(df, held, plain, extra, first, True, keep_clean, share), extra


def scan(docs: DataFrame, benchmark: DataFrame, n: int = 13, max_ngrams: int = 1_000_000) -> DataFrame:
    """docs with n_words, hits (merged word ranges, flat: start, end, start, end ...) and items (ids, sorted); columns of docs with these names give way."""
    found, extra = _scanned(docs, benchmark, n, max_ngrams, False, 20)
    names = ["n_words", "hits", "items"]
    return found.select(*(F.col(f"`{c}`") for c in docs.columns if c.lower() not in names), *(F.col(e).alias(c) for e, c in zip(extra, names, strict=True)))


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, n: int = 13, max_ngrams: int = 1_000_000, share: int = 20) -> DataFrame:
    """docs without those whose hit words are at least 1/share of all words; columns unchanged, whatever their names."""
    return _scanned(docs, benchmark, n, max_ngrams, True, share)[0]


def cut_spans(docs: DataFrame, benchmark: DataFrame, n: int = 13, max_ngrams: int = 1_000_000) -> DataFrame:
    """docs whose text lost the bytes from the first to the last word of every hit range; columns unchanged, whatever their names."""
    (found, extra), names = _scanned(docs, benchmark, n, max_ngrams, False, 20), docs.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = []
            for text, hits in zip(b.column("text").cast(pa.binary()).to_pylist(), b.column(extra[1]).to_pylist(), strict=True):
                if hits:
                    at = [m.span() for m in WORD.finditer(text.lower())]
                    cut = 0
                    kept = []
                    for s, e in zip(hits[::2], hits[1::2], strict=True):
                        kept.append(text[cut : at[s][0]])
                        cut = at[e - 1][1]
                    text = b"".join([*kept, text[cut:]])
                texts.append(text)
            yield pa.RecordBatch.from_arrays([pa.array(texts, pa.binary()).cast(pa.string()) if c == "text" else b.column(c) for c in names], names)

    return found.mapInArrow(run, docs.schema)


def digest(docs: DataFrame, benchmark: DataFrame, **kw) -> DataFrame:
    """The contract's columns for every document."""
    found = scan(docs.select("doc_id", "text"), benchmark, **kw)
    n_hit = F.aggregate(F.transform("hits", lambda x, i: F.when(i % 2 == 0, -x).otherwise(x)), F.lit(0).cast("long"), lambda a, x: a + x)
    out = found.select("doc_id", "n_words", n_hit.alias("n_hit"), F.size("items").cast("long").alias("n_items"), F.sha2(F.concat_ws(",", "items").cast("binary"), 256).alias("items_sha256"))
    return out.withColumn("contaminated", (F.col("n_hit") > 0) & (20 * F.col("n_hit") >= F.col("n_words")))


def items_digest(items: list[str]) -> str:
    return hashlib.sha256(",".join(sorted(items)).encode()).hexdigest()
