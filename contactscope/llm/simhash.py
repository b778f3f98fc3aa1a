"""SimHash near-dedup: 64-bit fingerprints of word shingles, linked by a self-join of binary tries.

Equal fingerprints are one trie leaf. Fingerprints that differ in at most `budget` bits agree in at least `blocks - budget` of
`blocks` bit blocks, so every choice of that many blocks gives groups of fingerprints equal there; a group's trie is joined with itself:
node pairs descend together, a pair of different branches spends one bit of the budget, and a pair that overspends is
cut off. All groups of a partition descend at once as arrays, depth first in slices of bounded size. Node pairs whose leaves
already are one component are skipped, so a dense cluster costs about as many steps as it has leaves, and what leaves
the task is a star per component, never all pairs. Components of the stars are then joined across groups.

Defined results: null text or text of white space has fingerprint zero, linked like any other; fewer words than a shingle make one
shingle; component_id is the smallest non-null doc_id; repeated rows give repeated rows; empty tables give no rows;
further columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from contactscope.llm.common import pieces, stored
from contactscope.llm.components import stars

SLICE = 16_384


def simhash(text: bytes | None, shingle: int = 4, seed: int = 42) -> int:
    """Unsigned 64-bit fingerprint: a bit is set if it is set in over half of the shingles' XXH64."""
    counts, total, carry = np.zeros(64, np.int64), 0, []
    digest = xxhash.xxh64_intdigest
    for piece in pieces(text.lower()) if text else ():
        words = carry + piece.split()
        if len(words) >= shingle:
            joined = b" ".join(words)
            ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
            starts = np.concatenate(([0], ends[:-1] + 1))
            hashed = np.array([digest(joined[a:b], seed) for a, b in zip(starts[: len(words) - shingle + 1].tolist(), ends[shingle - 1 :].tolist(), strict=True)], ">u8")
            for at in range(0, len(hashed), 4096):
                counts += np.unpackbits(hashed[at : at + 4096].view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
            total += len(hashed)
            carry = words[len(words) - shingle + 1 :]
        else:
            carry = words
    if not total:
        if not carry:
            return 0
        return digest(b" ".join(carry), seed)
    return int.from_bytes(np.packbits(counts * 2 > total).tobytes(), "big")


def fingerprints(docs: DataFrame, shingle: int = 4, seed: int = 42) -> DataFrame:
    """doc_id and fp, the fingerprint as a signed long."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            made = np.array([simhash(x.as_py(), shingle, seed) for x in b.column("text").cast(pa.binary())], np.uint64)
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(made.view(np.int64))], ["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, fp long")


class _Forest:
    """Union-find over array positions; a root is the smallest position of its component."""

    def __init__(self, n: int):
        self.up = np.arange(n)

    def roots(self, x: np.ndarray) -> np.ndarray:
        r = self.up[x]
        while True:
            above = self.up[r]
            if np.array_equal(above, r):
                return r
            r = above

    def link(self, a: np.ndarray, b: np.ndarray) -> None:
        while len(a):
            a, b = self.roots(a), self.roots(b)
            open_ = a != b
            a, b = a[open_], b[open_]
            np.minimum.at(self.up, np.maximum(a, b), np.minimum(a, b))


def trie_components(codes: np.ndarray, groups: np.ndarray, budget: int, limit: int = SLICE) -> np.ndarray:
    """codes: uint64, sorted within contiguous groups and unique there. Returns for each position the smallest
    position of its component under links of at most budget differing bits within a group."""
    n = len(codes)
    forest = _Forest(n)
    ones: dict[int, np.ndarray] = {}

    def split(lo: np.ndarray, hi: np.ndarray, bit: int) -> np.ndarray:
        if bit not in ones:
            if len(ones) * n > 20_000_000:  # bounds the memory of large groups
                ones.clear()
            ones[bit] = np.concatenate(([0], np.cumsum((codes >> np.uint64(bit)) & np.uint64(1), dtype=np.int64))).astype(np.int32 if n < 2**31 else np.int64)
        count = ones[bit]
        return hi - (count[hi] - count[lo])

    starts = np.flatnonzero(np.diff(groups, prepend=groups[0] - 1)) if n else np.zeros(0, np.int64)
    ends = np.append(starts[1:], n)
    many = ends - starts > 1
    stack = []
    for at in range(0, int(many.sum()), limit):
        s, e = starts[many][at : at + limit], ends[many][at : at + limit]
        stack.append((63, s, e, s, e, np.full(len(s), budget, np.int8)))
    run_end, stale = np.arange(1, n + 1), True
    while stack:
        bit, a0, a1, b0, b1, left = stack.pop()
        single = (a1 - a0 == 1) & (b1 - b0 == 1)
        if single.any():
            x, y = a0[single], b0[single]
            near = (np.bitwise_count(codes[x] ^ codes[y]) <= budget) & (x != y)
            if near.any():
                forest.link(x[near], y[near])
                stale = True
            rest = ~single
            a0, a1, b0, b1, left = a0[rest], a1[rest], b0[rest], b1[rest], left[rest]
        if not len(a0):
            continue
        if bit < 0:
            continue
        if stale and len(a0) > 64:
            labels = forest.roots(np.arange(n))
            change = np.flatnonzero(labels[1:] != labels[:-1]) + 1
            run_end = np.append(change, n)[np.searchsorted(change, np.arange(n), "right")]
            forest.up, stale = labels, False
        joined = (run_end[a0] >= a1) & (run_end[b0] >= b1) & (forest.roots(a0) == forest.roots(b0))
        if joined.any():
            rest = ~joined
            a0, a1, b0, b1, left = a0[rest], a1[rest], b0[rest], b1[rest], left[rest]
        am, bm = split(a0, a1, bit), split(b0, b1, bit)
        same = (a0 == b0) & (a1 == b1)
        apart = ~same
        spend = left > 0
        parts = [
            (a0[spend], am[spend], bm[spend], b1[spend], left[spend] - 1),
            (am[spend & apart], a1[spend & apart], b0[spend & apart], bm[spend & apart], left[spend & apart] - 1),
            (a0, am, b0, bm, left),
            (am, a1, bm, b1, left),
        ]
        nodes = [np.concatenate(x) for x in zip(*parts, strict=True)]
        live = (nodes[1] > nodes[0]) & (nodes[3] > nodes[2])
        alone = (nodes[0] == nodes[2]) & (nodes[1] - nodes[0] == 1) & (nodes[3] - nodes[2] == 1)
        nodes = [x[live & ~alone] for x in nodes]
        for at in range(0, len(nodes[0]), limit):
            stack.append((bit - 1, *(x[at : at + limit] for x in nodes)))
    return forest.roots(np.arange(n))


def block_masks(blocks: int, budget: int) -> list[int]:
    """Bit masks of every choice of blocks - budget of the blocks, as signed longs."""
    edges = [round(64 * i / blocks) for i in range(blocks + 1)]
    masks = [sum(1 << k for k in range(a, b)) for a, b in zip(edges, edges[1:], strict=False)]
    chosen = [sum(c) for c in combinations(masks, blocks - budget)]
    return [m - (1 << 64) if m >= 1 << 63 else m for m in chosen]


def links(prints: DataFrame, budget: int = 4, blocks: int | None = None) -> DataFrame:
    """Star edges (u, v) between distinct fingerprints (column fp), connected exactly as the pairs within budget are."""
    if blocks is None:
        size = prints.count()
        blocks = budget + (1 if size < 1 << 26 else 2 if size < 1 << 33 else 3)
    masks = block_masks(blocks, budget)
    keyed = prints.select("fp", F.posexplode(F.array(*(F.col("fp").bitwiseAND(F.lit(m)) for m in masks))).alias("choice", "part"))
    keyed = keyed.repartition("choice", "part").sortWithinPartitions("choice", "part")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []

        def join(rows: list) -> Iterator[pa.RecordBatch]:
            fp, choice, part = (np.concatenate(x) for x in zip(*rows, strict=True))
            codes = fp.view(np.uint64)
            group = np.cumsum(np.concatenate(([0], (choice[1:] != choice[:-1]) | (part[1:] != part[:-1]))))
            order = np.lexsort((codes, group))
            codes, group = codes[order], group[order]
            root = trie_components(codes, group, budget)
            at = np.flatnonzero(root != np.arange(len(root)))
            out = codes.view(np.int64)
            for k in range(0, len(at), 100_000):
                x = at[k : k + 100_000]
                yield pa.RecordBatch.from_arrays([pa.array(out[x]), pa.array(out[root[x]])], ["u", "v"])

        size = 0
        for b in batches:
            rows = tuple(b.column(c).to_numpy(zero_copy_only=False) for c in ("fp", "choice", "part"))
            if not len(rows[0]):
                continue
            _, choice, part = rows
            change = np.flatnonzero((choice[1:] != choice[:-1]) | (part[1:] != part[:-1]))
            new = held and (held[-1][1][-1] != choice[0] or held[-1][2][-1] != part[0])
            cut = int(change[-1]) + 1 if len(change) else 0 if new else -1
            # rows of one group only gather; what lies before its first row is joined once there is enough
            if size + len(choice) >= 100_000 and cut >= 0:
                before = [*held, tuple(x[:cut] for x in rows)] if cut else held
                if before:
                    yield from join(before)
                held, size = [tuple(x[cut:].copy() for x in rows)], len(choice) - cut
            else:
                held.append(rows)
                size += len(choice)
        if held and sum(len(x[0]) for x in held):
            yield from join(held)

    return keyed.mapInArrow(run, "u long, v long")


def near_duplicates(docs: DataFrame, shingle: int = 4, seed: int = 42, budget: int = 4) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id (smallest doc_id reachable over links)."""
    made = stored(fingerprints(docs, shingle, seed), "simhash")
    docs_n = made.count()
    prints = stored(made.groupBy("fp").agg(F.min("doc_id").alias("least")), "prints", docs_n)
    n = prints.count()
    star = stars(stored(links(prints.select("fp"), budget), "links", 5 * n, 100_000))
    member = star.select(F.col("u").alias("fp"), F.col("v").alias("root")).unionByName(star.select(F.col("v").alias("fp"), F.col("v").alias("root")).distinct())
    rooted = prints.join(member, "fp")
    least = stored(rooted.groupBy("root").agg(F.min("least").alias("component")), "least", n)
    linked = rooted.join(least, "root").select("fp", "component")
    # least and owner are written, so that the joins with them shuffle both sides by themselves and a hot key's rows can be split
    owner = stored(prints.join(linked, "fp", "left").select("fp", F.coalesce("component", "least").alias("component_id")), "owner", n)
    return made.join(owner, "fp", "left").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
