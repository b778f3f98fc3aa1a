"""Fuzzy repeated passages by collinear chaining of shared word k-mers.

1. Texts become arrays of 32-bit word hashes (two different words count as equal once in four billion comparisons). Texts with equal
   words (128 bits over 64-bit word hashes) are one class; its smallest doc_id stands for it and the others are reported as copies.
2. Seeds are k-word shingles: those with a hash below 1/density of the range, and the least of `window` shingles where none is. The choice
   depends on the words alone, so an intact shingle is a seed in every text or in none.
3. Candidate pairs come from keys that documents share. A seed with at most `few` documents pairs all of them, at most few - 1
   for each of its occurrences. For a more frequent one its documents are keyed again: by the seed with each of
   the next frequent seeds, and by every window of min_words words whose seeds are all frequent. Such a key pairs its documents too if they are few, and else
   each of them with its first document, which stands for that passage. So texts that share min_words equal words in a row are always linked, to each other or to the
   first that has these words. Where a seed or a pair of seeds is shared, the words on one side of it must agree too (64-bit maps of the words).
   A document stands behind the first of its key only where the comparison of the two has found a passage of both around the key. Every other
   document of the key is then paired with those documents of the key that may share min_words words around it, however many: stretches that differ in
   as many places as identity allows share so many pairs of neighbouring words that one at least is left where each document has put aside its most frequent ones
   among the key's documents. So a common line makes no pairs of all that have it. Of two documents of a key that agree beside it and around it, either both
   are returned as variants of the first's passage, or the two are compared.
4. Pairs are compared on their word arrays: seed matches on one diagonal are merged into segments, segments are chained by
   a Fenwick tree of prefix maxima under gap costs, chains are cut at wide gaps, extended along their ends until the balance of
   equal and different words has dropped by DROP, and aligned (equal words inside segments, longest common subsequence inside gaps). A chain that fails is cut into its
   longest stretches that pass. Passages of at least `min_words` words and `identity` equal words are returned.

Defined results: null text and texts of fewer than min_words words have no passage; a doc_id that repeats with different texts is
a document with several texts, all compared; repeated equal rows are one; null doc_ids are not compared; an empty table gives no rows; further
columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from contactscope.llm.common import bounded, forget, stored, without_ids
from contactscope.llm.wordhash import MIX, ONE, UNMIX, Hasher, powers, shingles, spread

K, WINDOW, DENSITY, MIN_WORDS, IDENTITY, FEW = 5, 16, 6, 50, 0.8, 4
GAP_COST, MAX_GAP, DROP = 0.1, 40, 50
#: Words on each side of a shared key that are compared, and how many of their marks must agree: of a passage's min_words words at
#: least half of those beside a seed lie on one side, 13 of 23 of them equal in the worst case, and other words agree by chance.
SIDE, AGREE = 24, 12
FOUND = "doc_id long, start_word long, end_word long, other_id long, other_start long, other_end long, matched long, identity double, kind string"
_TOP = np.uint64(0xFFFFFFFFFFFFFFFF)


def short(hashes: np.ndarray) -> np.ndarray:
    """32-bit word hashes."""
    return (hashes >> np.uint64(32)).astype(np.uint32)


def _slid(h: np.ndarray, width: int, pick) -> np.ndarray:
    """pick (minimum or maximum) over each `width` neighbouring values, by doubling."""
    out, have = h, 1
    while have < width:
        step = min(have, width - have)
        out = pick(out[: len(out) - step], out[step:])
        have += step
    return out


def seeds(words: np.ndarray, k: int = K, window: int = WINDOW, density: int = DENSITY) -> tuple[np.ndarray, np.ndarray]:
    """Hashes and positions of a text's seeds."""
    n = len(words) - k + 1
    if n < 1:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    h = shingles(words, k)
    if n <= window:
        picked = (h == h.min()) | (h < _TOP // np.uint64(density))
    else:
        least = _slid(h, window, np.minimum)
        edge = np.zeros(window - 1, np.uint64)
        picked = (h < _TOP // np.uint64(density)) | (_slid(np.concatenate((edge, least, edge)), window, np.maximum) == h)
    at = np.flatnonzero(picked)
    return h[at], at


def exact_keys(words: np.ndarray, frequent: np.ndarray, k: int = K, min_words: int = MIN_WORDS, density: int = DENSITY) -> np.ndarray:
    """Hashes of the min_words-word windows all of whose context-free seeds are among `frequent` (sorted)."""
    starts = len(words) - min_words + 1
    if starts < 1:
        return np.zeros(0, np.uint64)
    h = shingles(words, k)
    rare = (h < _TOP // np.uint64(density)) & ~_among(h, frequent)
    count = np.concatenate(([0], np.cumsum(rare)))
    inner = min_words - k + 1
    at = np.flatnonzero(count[inner : inner + starts] == count[:starts])
    if not len(at):
        return np.zeros(0, np.uint64)
    # a window's hash: difference of the prefix sums of word x power, divided by the power of its start
    sums = np.concatenate(([np.uint64(0)], np.cumsum(spread(words.astype(np.uint64) + ONE) * powers(len(words) - 1, MIX))))
    return np.unique(spread((sums[at + min_words] - sums[at]) * powers(starts - 1, UNMIX)[at]))


def _among(values: np.ndarray, known: np.ndarray) -> np.ndarray:
    """Which values are in `known`, which is sorted."""
    return known[np.minimum(np.searchsorted(known, values), len(known) - 1)] == values if len(known) else np.zeros(len(values), bool)


def pair_keys(h: np.ndarray, at: np.ndarray, reach: int, following: int = 3) -> tuple[np.ndarray, np.ndarray]:
    """Each seed joined with those of the next `following` that begin within `reach` words, and where the first one stands."""
    keys, places = [], []
    for j in range(1, min(following, len(h) - 1) + 1):
        near = at[j:] - at[:-j] <= reach
        keys.append(spread(h[:-j][near] * MIX + h[j:][near]))
        places.append(at[:-j][near])
    return (np.concatenate(keys), np.concatenate(places)) if keys else (np.zeros(0, np.uint64), np.zeros(0, np.int64))


def sides(words: np.ndarray, at: np.ndarray, k: int, side: int = SIDE) -> tuple[np.ndarray, np.ndarray]:
    """64-bit maps of the words before and after the shingles at `at`: a word sets the bit that its hash names."""
    bits = np.concatenate((np.zeros(side, np.uint64), ONE << (words.astype(np.uint64) & np.uint64(63)), np.zeros(side + k, np.uint64)))
    run = _slid(bits, side, np.bitwise_or)
    return run[at], run[at + side + k]


def context_marks(words: np.ndarray, keys: np.ndarray, low: np.ndarray, high: np.ndarray, k: int = K, min_words: int = MIN_WORDS) -> tuple[np.ndarray, np.ndarray]:
    """Marks of the words around each key, and the keys: hashes of a key, two neighbouring words and how often these stood before, for all
    that min_words words around one of the key's places can hold. low, high: a key's first and last place."""
    reach, h, two = min_words - k, shingles(words, k), shingles(words, 2)
    width = 2 * reach + k - 1
    # each place between the two with the same first seed; 0 stands beyond both ends
    places = [lo + np.flatnonzero(h[lo : hi + 1] == h[lo]) if lo < len(h) else np.zeros(0, np.int64) for lo, hi in zip(low.tolist(), high.tolist(), strict=True)]
    owner, places = np.repeat(keys, [len(v) for v in places]), np.concatenate(places)
    windows = np.lib.stride_tricks.sliding_window_view(np.concatenate((np.zeros(reach, np.uint64), two, np.zeros(reach, np.uint64))), width)
    marks, owners = [], []
    for i in range(0, len(places), 1024):
        own = owner[i : i + 1024, None]
        seen = np.sort(windows[places[i : i + 1024]], axis=1)
        at = np.broadcast_to(np.arange(width), seen.shape)
        new = np.concatenate((np.ones((len(seen), 1), bool), seen[:, 1:] != seen[:, :-1]), axis=1)
        before = (at - np.maximum.accumulate(np.where(new, at, 0), axis=1)).astype(np.uint64)
        found, first = np.unique(spread(spread(seen + own * MIX) + before)[seen != 0], return_index=True)
        marks.append(found)
        owners.append(np.broadcast_to(own, seen.shape)[seen != 0][first])
    if not marks:
        return np.zeros(0, np.uint64), np.zeros(0, np.uint64)
    found, first = np.unique(np.concatenate(marks), return_index=True)
    return found, np.concatenate(owners)[first]


class PrefixMax:
    """Fenwick tree: the best (value, name) among the first positions."""

    def __init__(self, n: int):
        self.best = [(-1e18, -1)] * (n + 1)

    def put(self, at: int, value: tuple[float, int]) -> None:
        at += 1
        while at < len(self.best):
            if value > self.best[at]:
                self.best[at] = value
            at += at & -at

    def get(self, end: int) -> tuple[float, int]:
        found = (-1e18, -1)
        while end > 0:
            if self.best[end] > found:
                found = self.best[end]
            end -= end & -end
        return found


def matches(x_seeds: tuple[np.ndarray, np.ndarray], y_seeds: tuple[np.ndarray, np.ndarray], most: int = 1 << 21) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Positions of equal seeds, every occurrence with every one, in batches of whole diagonals of about `most` matches. y_seeds in order of hash, then position."""
    (hx, px), (hy, py) = x_seeds, y_seeds
    first = np.searchsorted(hy, hx, "left")
    held = np.searchsorted(hy, hx, "right") > first
    px, first = px[held], first[held]
    if not len(px):
        return
    # y's places rise within a seed, and seeds are set further apart than any diagonal reaches
    low, high = -int(px.max()) - 1, int(py.max()) + 1
    apart = 2 * (high - low) + 1
    rank = np.cumsum(np.concatenate(([0], hy[1:] != hy[:-1])))
    places, own = rank * apart + py, rank[first] * apart + px
    todo = [(low, high)]
    while todo:
        low, high = todo.pop()
        at = np.searchsorted(places, own + low)
        n = np.searchsorted(places, own + high) - at
        total = int(n.sum())
        if total > most and high - low > 1:
            middle = (low + high) // 2
            todo += [(middle, high), (low, middle)]
        elif total:
            yield np.repeat(px, n), py[np.arange(total) + np.repeat(at - np.cumsum(n) + n, n)]


def by_hash(found: tuple[np.ndarray, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    order = np.argsort(found[0], kind="stable")
    return found[0][order], found[1][order]


def segments(px: np.ndarray, py: np.ndarray, k: int, window: int) -> list[tuple[int, int, int]]:
    """Matches on one diagonal no further apart than neighbouring seeds, merged: start in x, end in x, diagonal."""
    base, wide = int((py - px).min()), int(px.max()) + 1
    d, x = np.divmod(np.sort((py - px - base) * wide + px), wide)
    d += base
    cut = np.flatnonzero((np.diff(d) != 0) | (np.diff(x) > window + k))
    first, last = np.concatenate(([0], cut + 1)), np.append(cut, len(x) - 1)
    return list(zip(x[first].tolist(), (x[last] + k).tolist(), d[first].tolist(), strict=True))


def chains(parts: list[tuple[int, int, int]], slack: int, gap_cost: float = GAP_COST, max_gap: int = MAX_GAP) -> list[list[tuple[int, int, int]]]:
    """Best collinear chains of segments (start, end, diagonal), cut where a gap is wider than max_gap. A segment may start up to
    slack words before its predecessor's end, as seeds overlap."""
    parts = sorted(parts)
    ends = sorted({e + d for _, e, d in parts})
    rank = {v: i for i, v in enumerate(ends)}
    tree, score, before = PrefixMax(len(ends)), [0.0] * len(parts), [-1] * len(parts)
    by_end = sorted(range(len(parts)), key=lambda i: (parts[i][1], i))
    waiting = 0
    for i, (s, e, d) in enumerate(parts):
        while waiting < len(by_end) and parts[by_end[waiting]][1] <= s + slack and by_end[waiting] < i:
            j = by_end[waiting]
            tree.put(rank[parts[j][1] + parts[j][2]], (score[j] + gap_cost * (2 * parts[j][1] + parts[j][2]), j))
            waiting += 1
        lo, hi = 0, len(ends)
        while lo < hi:
            mid = (lo + hi) // 2
            lo, hi = (mid + 1, hi) if ends[mid] <= s + d + slack else (lo, mid)
        best, j = tree.get(lo)
        gain = best - gap_cost * (2 * s + d) if j >= 0 else 0.0
        score[i], before[i] = (e - s + gain, j) if gain > 0 else (float(e - s), -1)
    used, out = [False] * len(parts), []
    for i in sorted(range(len(parts)), key=lambda i: (-score[i], i)):
        chain = []
        while i >= 0 and not used[i]:
            used[i] = True
            chain.append(parts[i])
            i = before[i]
        chain.reverse()
        while chain:
            n = 1
            while n < len(chain) and chain[n][0] - chain[n - 1][1] <= max_gap and chain[n][0] + chain[n][2] - chain[n - 1][1] - chain[n - 1][2] <= max_gap:
                n += 1
            out.append(chain[:n])
            chain = chain[n:]
    return out


def common_words(x: np.ndarray, y: np.ndarray) -> int:
    """Equal words of the best alignment of two short ranges (their longest common subsequence)."""
    if not len(x) or not len(y):
        return 0
    row = np.zeros(len(y) + 1, np.int64)
    for w in x:
        row[1:] = np.maximum(row[1:], row[:-1] + (y == w))
        row = np.maximum.accumulate(row)
    return int(row[-1])


def _reach(a: np.ndarray, b: np.ndarray, drop: int = DROP) -> int:
    """How far an end may be pushed along its diagonal: to the best balance of equal (+1) and different (-2) words, searched until the
    balance has dropped by more than `drop`."""
    best = at = balance = 0
    for i in range(0, min(len(a), len(b)), 512):
        steps = balance + np.cumsum(np.where(a[i : i + 512] == b[i : i + 512], 1, -2))
        fallen = np.flatnonzero(np.maximum.accumulate(np.maximum(steps, best)) - steps > drop)
        seen = steps[: fallen[0]] if len(fallen) else steps
        if len(seen) and seen.max() > best:
            best, at = int(seen.max()), i + int(np.argmax(seen)) + 1
        if len(fallen):
            break
        balance = int(steps[-1])
    return at


def _extended(x: np.ndarray, y: np.ndarray, chain: list[tuple[int, int, int]]) -> tuple[int, int, int, int]:
    s, _, d = chain[0]
    n = min(s, s + d)
    left = _reach(x[s - n : s][::-1], y[s + d - n : s + d][::-1])
    _, e, de = chain[-1]
    n = min(len(x) - e, len(y) - e - de)
    right = _reach(x[e : e + n], y[e + de : e + de + n])
    return s - left, e + right, s + d - left, e + de + right


def _widened(x: np.ndarray, y: np.ndarray, ends: tuple[int, int, int, int], min_words: int) -> tuple[int, int, int, int]:
    """Ends of a stretch that is short of min_words, moved out to that length or just over it, where what is gained on a side ends with an equal
    word and is equal by a third at least: ends where words differ often are not cut off, and strange words are not taken in."""
    xs, xe, ys, ye = ends
    need = min_words - min(xe - xs, ye - ys)
    if need <= 0:
        return ends
    left, right = min(2 * need, xs, ys), min(2 * need, len(x) - xe, len(y) - ye)

    def steps(equal: np.ndarray) -> np.ndarray:
        n = np.arange(1, len(equal) + 1)
        return np.concatenate(([0], n[equal & (3 * np.cumsum(equal) >= n)]))

    before, after = steps((x[xs - left : xs] == y[ys - left : ys])[::-1]), steps(x[xe : xe + right] == y[ye : ye + right])
    at = np.searchsorted(after, need - before)
    before, at = before[at < len(after)], at[at < len(after)]
    if not len(at):
        return ends
    best = int(np.argmin(before + after[at]))
    n, m = int(before[best]), int(after[at[best]])
    return xs - n, xe + m, ys - n, ye + m


def _equal_words(x: np.ndarray, y: np.ndarray, chain: list[tuple[int, int, int]], xs: int, xe: int, ys: int) -> int:
    """Equal words of an extended chain: place by place in its segments, by the best alignment in its gaps."""
    same, at_x, at_y = 0, xs, ys
    for i, (a, b, d) in enumerate(chain):
        a, b = (xs if i == 0 else max(a, at_x, at_y - d)), (xe if i == len(chain) - 1 else b)
        if b <= a:
            continue
        same += common_words(x[at_x:a], y[at_y : a + d])
        same += int((x[a:b] == y[a + d : b + d]).sum())
        at_x, at_y = b, b + d
    return same


def _laid_out(x: np.ndarray, y: np.ndarray, chain: list[tuple[int, int, int]], ends: tuple[int, int, int, int]) -> list[tuple[int, int, int]]:
    """A chain as runs of equal words (start in x, start in y, length) and what lies between them: the equal words of a gap are
    counted by the run after it. Segments are first pushed into the gaps along their diagonals."""
    xs, xe, ys, _ = ends
    stretches: list[list[int]] = []
    at_x, at_y = xs, ys
    for i, (a, b, d) in enumerate(chain):
        a, b = (xs if i == 0 else max(a, at_x, at_y - d)), (xe if i == len(chain) - 1 else b)
        if b <= a:
            continue
        if stretches:
            n = min(a - at_x, a + d - at_y)
            right = _reach(x[at_x : at_x + n], y[at_y : at_y + n])
            stretches[-1][1] += right
            n -= right
            a -= _reach(x[a - n : a][::-1], y[a + d - n : a + d][::-1])
        stretches.append([a, b, d])
        at_x, at_y = b, b + d
    runs = []
    for a, b, d in stretches:
        edge = np.flatnonzero(np.diff(np.concatenate(([0], (x[a:b] == y[a + d : b + d]).view(np.int8), [0]))))
        runs += [(a + s, a + s + d, e - s) for s, e in zip(edge[::2].tolist(), edge[1::2].tolist(), strict=True)]
    return runs


def parts_of(x: np.ndarray, y: np.ndarray, chain: list[tuple[int, int, int]], ends: tuple[int, int, int, int], min_words: int, identity: float) -> list[tuple[int, int, int, int, int]]:
    """Passages inside a chain that is none as a whole: its longest stretch of runs that is one, and so on in what is left on both sides."""
    runs = _laid_out(x, y, chain, ends)
    if not runs:
        return []
    sx, sy, n = np.array(runs, np.int64).T
    ex, ey = sx + n, sy + n
    between = [0] + [common_words(x[a:b], y[c:d]) for a, b, c, d in zip(ex[:-1], sx[1:], ey[:-1], sy[1:], strict=True)]
    total = np.cumsum(n + between)
    before = total - n
    found, todo = [], [(0, len(runs))]
    while todo:
        lo, hi = todo.pop()
        best, at = 0, None
        for i in range(lo, hi):
            if ex[hi - 1] - sx[i] <= best:
                break
            long_x, long_y = ex[i:hi] - sx[i], ey[i:hi] - sy[i]
            good = np.flatnonzero((np.minimum(long_x, long_y) >= min_words) & (total[i:hi] - before[i] >= identity * np.maximum(long_x, long_y)))
            if len(good) and long_x[good[-1]] > best:
                best, at = long_x[good[-1]], (i, i + int(good[-1]))
        if at is not None:
            i, j = at
            found.append((int(sx[i]), int(ex[j]), int(sy[i]), int(ey[j]), int(total[j] - before[i])))
            todo += [(lo, i), (j + 1, hi)]
    return sorted(found)


def passages(x: np.ndarray, y: np.ndarray, k: int = K, window: int = WINDOW, min_words: int = MIN_WORDS, identity: float = IDENTITY, y_seeds: tuple[np.ndarray, np.ndarray] | None = None) -> list[tuple[int, int, int, int, int]]:
    """Passages of two word arrays: ranges in x and y and equal words. The best chains come first, then those of words in x that are in passages already by the number of
    other words, and none without any: texts of repeated lines give passages that cover x, not one for each pair of repeats.
    y_seeds: y's seeds by hash, where they are known."""
    y_seeds = by_hash(seeds(y, k, window)) if y_seeds is None else y_seeds
    merged = [s for px, py in matches(seeds(x, k, window), y_seeds) for s in segments(px, py, k, window)]
    found: list[tuple[int, int, int, int, int]] = []
    covered = np.zeros(len(x), bool)

    def take(chain: list[tuple[int, int, int]]) -> None:
        xs, xe, ys, ye = ends = _widened(x, y, _extended(x, y, chain), min_words)
        if min(xe - xs, ye - ys) < min_words:
            return
        same = _equal_words(x, y, chain, xs, xe, ys)
        whole = same >= identity * max(xe - xs, ye - ys)
        for p in [(xs, xe, ys, ye, same)] if whole else parts_of(x, y, chain, ends, min_words, identity):
            if not covered[p[0] : p[1]].all():
                found.append(p)
                covered[p[0] : p[1]] = True

    later = []
    for chain in chains(merged, k - 1) if merged else ():
        if covered[chain[0][0] : chain[-1][1]].any():
            later.append(chain)
        else:
            take(chain)
    if later:
        fresh = np.concatenate(([0], np.cumsum(~covered)))
        for chain in sorted(later, key=lambda c: fresh[c[0][0]] - fresh[c[-1][1]]):
            if not covered[chain[0][0] : chain[-1][1]].all():
                take(chain)
    return found


def _words(buffer) -> np.ndarray:
    return np.frombuffer(buffer, "<u4")


def _word_arrays(docs: DataFrame, min_words: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher = Hasher()
        for b in batches:
            ids, sizes, whole, data = [], [], [], []
            texts = [t or b"" for t in b.column("text").cast(pa.binary()).to_pylist()]
            for doc, hashes in zip(b.column("doc_id").to_pylist(), hasher.texts(texts), strict=True):
                if doc is not None and len(hashes) >= min_words:
                    ids.append(doc)
                    sizes.append(len(hashes))
                    whole.append(xxhash.xxh128_hexdigest(hashes.astype("<u8").tobytes()))
                    data.append(short(hashes).astype("<u4").tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(sizes, pa.int64()), pa.array(whole, pa.string()), pa.array(data, pa.binary())], ["doc_id", "n_words", "whole", "words"])

    return docs.mapInArrow(run, "doc_id long, n_words long, whole string, words binary")


def _occurrences(arrays: DataFrame, k: int, window: int) -> DataFrame:
    """(seed, doc_id): each seed of a document once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, len(b), 512):
                s = b.slice(at, 512)
                own = [np.unique(seeds(_words(x.as_buffer()), k, window)[0]) for x in s.column("words")]
                docs = np.repeat(s.column("doc_id").to_numpy(), [len(o) for o in own])
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(own).view(np.int64)), pa.array(docs)], ["seed", "doc_id"])

    return arrays.select("doc_id", "words").mapInArrow(run, "seed long, doc_id long")


def document_keys(words: np.ndarray, shared: np.ndarray, frequent: np.ndarray, k: int, window: int, min_words: int) -> tuple[np.ndarray, ...]:
    """What a document is found by, the words beside it (all bits for what needs no check), and its first and last place (-1 for exact windows).
    shared, frequent: its seeds that few documents or many hold, sorted."""
    h, at = seeds(words, k, window)
    rare, often = _among(h, shared), _among(h, frequent)
    pairs, places = pair_keys(h[often], at[often], min_words - k)
    keys, places = np.concatenate((h[rare], pairs)), np.concatenate((at[rare], places))
    before, after = sides(words, places, k)
    # a key with several places in the document: the words beside all of them
    order = np.argsort(keys, kind="stable")
    keys = keys[order]
    first = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1]))) if len(keys) else np.zeros(0, np.int64)
    join = lambda v, by=np.bitwise_or: by.reduceat(v[order], first) if len(first) else v
    exact = exact_keys(words, frequent, k, min_words) if len(frequent) else np.zeros(0, np.uint64)
    whole, nowhere = np.full(len(exact), _TOP), np.full(len(exact), -1)
    joined = (keys[first], join(before), join(after), join(places, np.minimum), join(places, np.maximum))
    return tuple(np.concatenate(v) for v in zip(joined, (exact, whole, whole, nowhere, nowhere), strict=True))


def _keys(docs: DataFrame, k: int, window: int, min_words: int) -> DataFrame:
    """(key, doc_id, before, after, low, high): document_keys of documents with their shared and frequent seeds."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = lambda q: np.sort(np.array(q.values, np.int64).view(np.uint64))
        for b in batches:
            for at in range(0, len(b), 64):
                s = b.slice(at, 64)
                own = [document_keys(_words(x.as_buffer()), known(q), known(f), k, window, min_words) for x, q, f in zip(s.column("words"), s.column("rare"), s.column("often"), strict=True)]
                docs = np.repeat(s.column("doc_id").to_numpy(), [len(o[0]) for o in own])
                columns = [pa.array(np.concatenate([o[i] for o in own]).view(np.int64)) for i in range(3)]
                columns += [pa.array(np.concatenate([o[i] for o in own]).astype(np.int32)) for i in (3, 4)]
                yield pa.RecordBatch.from_arrays([columns[0], pa.array(docs), *columns[1:]], ["key", "doc_id", "before", "after", "low", "high"])

    return docs.select("doc_id", "words", "rare", "often").mapInArrow(run, "key long, doc_id long, before long, after long, low int, high int")


def _compared(pairs: DataFrame, k: int, window: int, min_words: int, identity: float) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [c.split()[0] for c in FOUND.split(", ")]
        kinds = [pa.int64()] * 7 + [pa.float64(), pa.string()]
        last, held = None, None
        for b in batches:
            out = []
            for doc, other, x, y in zip(b.column("doc_id").to_pylist(), b.column("other_id").to_pylist(), b.column("words"), b.column("other_words"), strict=True):
                x, y = _words(x.as_buffer()), _words(y.as_buffer())
                # neighbouring rows mostly have the same second text
                if last is None or len(last) != len(y) or not np.array_equal(last, y):
                    last, held = y.copy(), by_hash(seeds(y, k, window))
                for xs, xe, ys, ye, same in passages(x, y, k, window, min_words, identity, held):
                    out.append((doc, xs, xe, other, ys, ye, same, round(same / max(xe - xs, ye - ys), 6), "chain"))
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], t) for i, t in enumerate(kinds)], names)

    return pairs.mapInArrow(run, FOUND)


def _agree(a: str, b: str) -> Column:
    """Whether the words on one side of a key agree, by their maps."""
    return F.greatest(*(F.bit_count(F.col(f"{a}{side}").bitwiseAND(F.col(f"{b}{side}"))) for side in ("before", "after"))) >= AGREE


def candidate_pairs(arrays: DataFrame, k: int = K, window: int = WINDOW, min_words: int = MIN_WORDS, few: int = FEW) -> tuple[DataFrame, DataFrame]:
    """(doc_id, other_id), doc_id the larger, and (key, first, doc_id, before, after, low, high) of the keys with more than `few` documents but for their
    first ones and exact windows, as written tables: see step 3 above."""
    held = stored(_occurrences(arrays, k, window), "seeds")
    # written, so that the joins shuffle both sides by themselves and a very common key's rows can be split
    counted = stored(held.groupBy("seed").agg(F.count("*").alias("n")).where("n > 1"), "counted")
    own = held.join(counted, "seed").groupBy("doc_id").agg(F.collect_list(F.when(F.col("n") <= few, F.col("seed"))).alias("rare"), F.collect_list(F.when(F.col("n") > few, F.col("seed"))).alias("often"))
    own = stored(own, "own")
    keys = stored(_keys(arrays.join(own, "doc_id"), k, window, min_words), "keys")
    one = F.struct("doc_id", "before", "after", "low", "high")
    sums = stored(keys.groupBy("key").agg(F.min(one).alias("first"), F.max("doc_id").alias("hi"), F.count("*").alias("n")).where("first.doc_id < hi").drop("hi"), "sums")
    joined = stored(keys.join(sums, "key"), "joined")
    groups = joined.where(F.col("n") <= few).groupBy("key").agg(F.sort_array(F.collect_list(one)).alias("g"))
    # each document of a small group with each later one
    paired = groups.select("g", F.posexplode("g").alias("i", "a")).select("a", F.explode(F.slice("g", F.col("i") + 2, F.lit(few))).alias("b")).where("a.doc_id < b.doc_id")
    near = paired.where(_agree("a.", "b.")).select(F.col("b.doc_id").alias("doc_id"), F.col("a.doc_id").alias("other_id"))
    behind = joined.where((F.col("n") > few) & (F.col("doc_id") != F.col("first.doc_id")))
    star = behind.where(_agree("", "first.")).select("doc_id", F.col("first.doc_id").alias("other_id"))
    pairs = stored(near.unionByName(star).distinct(), "pairs")
    large = stored(behind.where("low >= 0").select("key", "first", "doc_id", "before", "after", "low", "high"), "large")
    forget(held, counted, own, keys, sums, joined)
    return pairs, large


def _marks(docs: DataFrame, k: int, min_words: int) -> DataFrame:
    """(mark, key, doc_id): context_marks of documents with their keys' places."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, len(b), 64):
                s = b.slice(at, 64)
                held = [(v.values.field("key").to_numpy().view(np.uint64), v.values.field("low").to_numpy(), v.values.field("high").to_numpy()) for v in s.column("places")]
                own = [context_marks(_words(x.as_buffer()), *v, k, min_words) for x, v in zip(s.column("words"), held, strict=True)]
                marks, keys = (pa.array(np.concatenate([o[i] for o in own]).view(np.int64)) for i in range(2))
                yield pa.RecordBatch.from_arrays([marks, keys, pa.array(np.repeat(s.column("doc_id").to_numpy(), [len(o[0]) for o in own]))], ["mark", "key", "doc_id"])

    return docs.select("doc_id", "words", "places").mapInArrow(run, "mark long, key long, doc_id long")


def unsettled_pairs(arrays: DataFrame, large: DataFrame, found: DataFrame, pairs: DataFrame, k: int = K, min_words: int = MIN_WORDS, identity: float = IDENTITY) -> DataFrame:
    """(doc_id, other_id), as a written table: the pairs of a key with many documents that are not compared yet and may share a passage around it, but
    for those of two documents that each share one around the key with its first. large, pairs: from candidate_pairs; found: the passages of these pairs."""
    spans = found.select("doc_id", "other_id", "start_word", "end_word", "other_start", "other_end")
    around = (F.col("start_word") <= F.col("low")) & (F.col("end_word") >= F.col("high") + k) & (F.col("other_start") <= F.col("first.low")) & (F.col("other_end") >= F.col("first.high") + k)
    unsettled = large.alias("l").join(spans.alias("s"), (F.col("l.doc_id") == F.col("s.doc_id")) & (F.col("first.doc_id") == F.col("s.other_id")) & around, "left_anti")
    # written, so that a very common key's rows can be split
    rest = stored(unsettled.select("key", "doc_id", F.lit(True).alias("open")).distinct(), "rest")
    members = large.drop("first").join(rest.select("key").distinct(), "key", "left_semi").join(rest.hint("merge"), ["key", "doc_id"], "left")
    members = stored(members.withColumn("open", F.coalesce("open", F.lit(False))), "members")
    marks = _marks(arrays.join(members.groupBy("doc_id").agg(F.collect_list(F.struct("key", "low", "high")).alias("places")), "doc_id"), k, min_words)
    # of min_words - 1 pairs of neighbouring words each place that differs breaks two at most; of at least `least` marks in common one has least - 1 more frequent ones in both documents
    least = max(1, min_words - 1 - 2 * int(min_words * (1 - identity) + 1e-9))
    shared = marks.withColumn("n", F.count("*").over(Window.partitionBy("mark"))).where("n > 1")
    falling = Window.partitionBy("key", "doc_id").orderBy(F.desc("n"), "mark")
    ranked = shared.withColumn("i", F.row_number().over(falling)).where(F.col("i") >= least).withColumn("above", F.lag("mark").over(falling))
    # a mark that stands behind the same more frequent one in all its documents makes no pair that this one doesn't
    held = Window.partitionBy("mark")
    sums = ranked.select("mark", "key", "doc_id", *(f("above").over(held).alias(n) for f, n in ((F.min, "lo"), (F.max, "hi"), (F.count, "has"))), F.count("*").over(held).alias("n"))
    needed = sums.where((F.col("n") > 1) & ((F.col("has") < F.col("n")) | (F.col("lo") < F.col("hi"))))
    rare = stored(needed.select("key", "doc_id", "mark").join(members.hint("merge"), ["key", "doc_id"]).select("mark", "doc_id", "before", "after", "open"), "rare")
    once = F.col("a.open") & (~F.col("b.open") & (F.col("a.doc_id") != F.col("b.doc_id")) | (F.col("a.doc_id") > F.col("b.doc_id")))
    met = rare.alias("a").join(rare.alias("b").hint("merge"), (F.col("a.mark") == F.col("b.mark")) & once & _agree("a.", "b."))
    both = met.select(F.greatest("a.doc_id", "b.doc_id").alias("doc_id"), F.least("a.doc_id", "b.doc_id").alias("other_id")).distinct()
    out = stored(both.join(pairs, ["doc_id", "other_id"], "left_anti"), "later")
    forget(large, rest, members, rare)
    return out


def repeated_passages(docs: DataFrame, k: int = K, window: int = WINDOW, min_words: int = MIN_WORDS, identity: float = IDENTITY) -> DataFrame:
    """Rows of FOUND: one per passage of a pair (kind chain), and one per document whose words equal those of its class's first (kind copy)."""
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    arrays = stored(_word_arrays(texts, min_words), "words")
    n = arrays.count()
    classes = bounded(stored(arrays.groupBy("whole").agg(F.min("doc_id").alias("other_id"), F.count("*").alias("n")).where("n > 1").drop("n"), "classes", n))
    copies = stored(arrays.select("doc_id", "n_words", "whole").join(classes, "whole").where("doc_id <> other_id").select("doc_id", "n_words", "other_id").distinct(), "copies", n)
    distinct = without_ids(arrays.select("doc_id", "words"), copies, rows=n)
    pairs, large = candidate_pairs(distinct, k, window, min_words)

    def compared(pairs: DataFrame) -> DataFrame:
        seconds = stored(pairs.select(F.col("other_id").alias("doc_id")).distinct(), "seconds", n)
        other = distinct.join(bounded(seconds), "doc_id", "left_semi").select(F.col("doc_id").alias("other_id"), F.col("words").alias("other_words"))
        both = distinct.join(bounded(pairs), "doc_id").join(other.hint("merge"), "other_id").select("doc_id", "other_id", "words", "other_words")
        return _compared(both, k, window, min_words, identity)

    found = stored(compared(pairs), "found")
    later = unsettled_pairs(distinct, large, found, pairs, k, min_words, identity)
    zero = F.lit(0).cast("long")
    same = copies.select("doc_id", zero.alias("start_word"), F.col("n_words").alias("end_word"), "other_id", zero.alias("other_start"), F.col("n_words").alias("other_end"), F.col("n_words").alias("matched"), F.lit(1.0).alias("identity"), F.lit("copy").alias("kind"))
    return found.unionByName(compared(later)).unionByName(same)
