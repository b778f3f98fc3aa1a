"""Language identification by a bidirectional gated recurrent network over bytes.

The network reads the bytes of a text, lower-cased in ASCII, in both directions and labels every position, letter or not, with a distribution over
languages; a document's probabilities are the mean over all positions of its whole text. The state runs across words
and scripts: a text is read in windows of at most SPAN bytes that end between code points, and each window's state
starts LEAD bytes before it and, backwards, LEAD bytes behind it, cut to whole code points; beyond its ends a text is read as blanks. So
long texts take no more memory than short ones, and a label depends on a position's surroundings alone. Training is numpy back-propagation through time over all windows of a
hash-ordered sample of labelled rows (`per_language` documents of each language, at most `max_languages` languages).

Defined results: null text or text without a letter is `und` with score 0; without anything to learn from all texts are `und`;
null languages are never learned; more languages than the bound raise an error; ties go to the first language in order;
repeated rows are judged one by one; further columns are not read.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SPAN, LEAD = 512, 24
#: Windows of training are shorter, for more steps over the same bytes; windows of one length are labelled together, BLOCK at a time.
TRAIN_SPAN, BLOCK, STEP = 96, 256, 32
#: Bytes of text whose windows are laid out at once.
ROOM = 1 << 22
PLAIN_LETTER = re.compile(rb"[A-Za-z]")
LETTER = re.compile(r"[^\W\d_]")
UNKNOWN = "und"
_BLANK = ord(" ")


def held_out():
    """Column: the documents that may not be learned from."""
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 == 1


def has_letter(text: bytes) -> bool:
    return bool(PLAIN_LETTER.search(text) or LETTER.search(text.decode("utf-8", "replace")))


def window_edges(data: np.ndarray, span: int) -> np.ndarray:
    """Where a text's windows begin and the last one ends: every span bytes, moved back to the start of a code point."""
    edges = np.arange(0, len(data), span)
    for _ in range(3):
        inside = (data[edges] & 0xC0) == 0x80
        edges = np.where(inside & (edges > 0), edges - 1, edges)
    return np.append(edges, len(data))


def laid_out(data: np.ndarray, starts: np.ndarray, width: int) -> np.ndarray:
    """Rows of LEAD + width + LEAD bytes around the starts (places in data, which has blanks enough on both sides); parts of code points at a row's ends are blanks."""
    rows = data[(starts - LEAD)[:, None] + np.arange(width + 2 * LEAD)]
    broken = np.ones(len(rows), bool)
    for j in range(3):
        broken &= (rows[:, j] & 0xC0) == 0x80
        rows[broken, j] = _BLANK
    for j in (1, 2, 3):
        first = rows[:, -j]
        short = (first >= 0xC0) & (1 + (first >= 0xC0).astype(int) + (first >= 0xE0) + (first >= 0xF0) > j)
        rows[short, -j:] = _BLANK
    return rows


def _padded(texts: list[bytes], span: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """All texts in one array with blanks around each; and of each window its start there, its bytes, and its text's number."""
    fill = b" " * (span + 2 * LEAD)
    data = np.frombuffer(fill + b"".join(t.lower() + fill for t in texts), np.uint8)
    starts, sizes, owner = [], [], []
    at = len(fill)
    for i, t in enumerate(texts):
        edges = window_edges(data[at : at + len(t)], span)
        starts.append(edges[:-1] + at)
        sizes.append(np.diff(edges))
        owner.append(np.full(len(edges) - 1, i))
        at += len(t) + len(fill)
    join = lambda parts: np.concatenate(parts) if parts else np.zeros(0, np.int64)
    return data, join(starts), join(sizes), join(owner)


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-x))


class Network:
    """Two gated recurrent layers, one per direction, and a softmax over their joined states."""

    def __init__(self, languages: list[str], hidden: int = 16, seed: int = 7):
        r = np.random.default_rng(seed)
        self.languages, self.h = languages, hidden
        f = lambda *s, scale: r.normal(0, scale, s).astype(np.float32)
        self.p = {}
        for d in "fb":
            self.p[d + "W"] = f(256, 3 * hidden, scale=0.3)
            self.p[d + "U"] = f(hidden, 2 * hidden, scale=hidden**-0.5)
            self.p[d + "C"] = f(hidden, hidden, scale=hidden**-0.5)
        self.p["V"] = f(2 * hidden, len(languages), scale=hidden**-0.5)
        self.p["b"] = np.zeros(len(languages), np.float32)

    def _steps(self, d: str, width: int) -> range:
        return range(width) if d == "f" else range(width - 1, -1, -1)

    def _taped(self, d: str, rows: np.ndarray) -> tuple[np.ndarray, list[tuple]]:
        """States by step, and what the backward pass needs."""
        H = self.h
        W, U, C = self.p[d + "W"], self.p[d + "U"], self.p[d + "C"]
        h = np.zeros((len(rows), H), W.dtype)
        states, tape = np.zeros((rows.shape[1], len(rows), H), W.dtype), []
        for t in self._steps(d, rows.shape[1]):
            x = W[rows[:, t]]
            gates = _sigmoid(x[:, : 2 * H] + h @ U)
            z, r = gates[:, :H], gates[:, H:]
            c = np.tanh(x[:, 2 * H :] + (r * h) @ C)
            tape.append((t, h, z, r, c))
            h = states[t] = h + z * (c - h)
        return states, tape

    def _states(self, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """States of both directions (step, row, state) between the leads, without a tape, by arithmetic in place on whole arrays: both directions take a step
        together, each from its own end of the row to the last place before the far lead."""
        n, width, H = len(rows), rows.shape[1], self.h
        split = lambda k: [self.p[d + k][:, at : at + H] for at in (0, H) for d in "fb"]
        # update gate forwards and backwards, reset gate likewise, candidate likewise; the gates' signs are turned
        table = np.concatenate([*(-w for w in split("W")), *(self.p[d + "W"][:, 2 * H :] for d in "fb")])
        U = -np.stack(split("U")).reshape(2, 2, H, H)
        C = np.stack([self.p[d + "C"] for d in "fb"])
        ahead = np.ascontiguousarray(rows.T).astype(np.intp)
        places = np.empty((width - LEAD, 6, n), np.intp)
        for g in range(3):
            np.add(ahead[: width - LEAD], 512 * g, out=places[:, 2 * g])
            np.add(ahead[:LEAD - 1 : -1], 512 * g + 256, out=places[:, 2 * g + 1])
        out = np.empty((width - 2 * LEAD, 2, n, H), np.float32)
        x, gates, held, c = np.empty((6, n, H), np.float32), np.empty((2, 2, n, H), np.float32), np.empty((2, n, H), np.float32), np.empty((2, n, H), np.float32)
        for_gates, for_state = x[:4].reshape(2, 2, n, H), x[4:]
        h, early = np.zeros((2, n, H), np.float32), np.empty((2, n, H), np.float32)
        for t in range(width - LEAD):
            table.take(places[t], axis=0, out=x, mode="clip")
            np.matmul(h, U, out=gates)
            gates += for_gates
            np.exp(gates, gates)
            gates += 1
            np.reciprocal(gates, gates)
            np.multiply(gates[1], h, out=held)
            np.matmul(held, C, out=c)
            c += for_state
            np.tanh(c, c)
            c -= h
            c *= gates[0]
            h = np.add(h, c, out=out[t - LEAD] if t >= LEAD else early)
        return out[:, 0], out[::-1, 1]

    def label(self, rows: np.ndarray) -> np.ndarray:
        """Label distributions (step, row, language) of all rows between their leads."""
        V, b, H = self.p["V"], self.p["b"], self.h
        ahead, back = self._states(rows)
        logits = ahead @ V[:H]
        logits += back @ V[H:]
        logits += b
        # states lie between -1 and 1, so most networks' logits are too small to overflow
        if np.abs(V).sum(axis=0).max() + np.abs(b).max() > 80:
            logits -= logits.max(axis=2, keepdims=True)
        np.exp(logits, logits)
        few = len(b) <= 16
        logits /= logits @ np.ones((len(b), len(b)), np.float32) if few else logits.sum(axis=2, keepdims=True)
        return logits

    def _windows(self, texts: list[bytes]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
        """Blocks of windows of about one length: labels, bytes of each, its text, its place in the text's padded data."""
        data, starts, sizes, owner = _padded(texts, SPAN)
        widths = (sizes + STEP - 1) // STEP * STEP
        for width in np.unique(widths).tolist():
            same = np.flatnonzero(widths == width)
            for at in range(0, len(same), BLOCK):
                pick = same[at : at + BLOCK]
                yield self.label(laid_out(data, starts[pick], width)), sizes[pick], owner[pick], starts[pick]

    def positions(self, text: bytes) -> np.ndarray:
        """The label distribution of every byte of a text."""
        out = np.zeros((len(text), len(self.languages)), np.float32)
        for prob, sizes, _, starts in self._windows([text]):
            for i, (n, s) in enumerate(zip(sizes.tolist(), (starts - SPAN - 2 * LEAD).tolist(), strict=True)):
                out[s : s + n] = prob[:n, i]
        return out

    def pooled(self, texts: list[bytes]) -> np.ndarray:
        """Per text the mean of its position distributions; zeros for an empty one."""
        sums = np.zeros((len(texts), len(self.languages)))
        for prob, sizes, owner, _ in self._windows(texts):
            prob *= (np.arange(len(prob))[:, None] < sizes)[:, :, None]
            np.add.at(sums, owner, prob.sum(axis=0))
        return sums / np.maximum(1, [[len(t)] for t in texts])

    def gradients(self, rows: np.ndarray, sizes: np.ndarray, target: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
        """Mean loss over the positions between the leads (sizes of each row), and the parameters' gradients."""
        n, H = len(rows), self.h
        (sf, tf), (sb, tb) = self._taped("f", rows), self._taped("b", rows)
        both = np.concatenate((sf, sb), axis=2)
        logits = both @ self.p["V"] + self.p["b"]
        prob = np.exp(logits - logits.max(axis=2, keepdims=True))
        prob /= prob.sum(axis=2, keepdims=True)
        place = np.arange(rows.shape[1])[:, None] - LEAD
        weight = ((place >= 0) & (place < sizes))[:, :, None] / self.p["b"].dtype.type(sizes.sum())
        picked = prob[:, np.arange(n), target]
        loss = float(-(np.log(picked + 1e-9) * weight[:, :, 0]).sum())
        prob[:, np.arange(n), target] -= 1
        d_logits = (prob * weight).astype(self.p["b"].dtype)
        flat = d_logits.reshape(-1, d_logits.shape[2])
        g = {"V": both.reshape(-1, 2 * H).T @ flat, "b": flat.sum(axis=0)}
        d_both = d_logits @ self.p["V"].T
        columns = rows.T
        order = np.argsort(columns, axis=None, kind="stable")
        used, first = np.unique(columns.ravel()[order], return_index=True)
        for d, tape, d_state in (("f", tf, d_both[:, :, :H]), ("b", tb, d_both[:, :, H:])):
            W, U, C = (np.zeros_like(self.p[d + k]) for k in "WUC")
            inputs = np.empty((rows.shape[1], n, 3 * H), W.dtype)
            back = np.zeros((n, H), W.dtype)
            for t, h, z, r, c in reversed(tape):
                back = back + d_state[t]
                a_c = back * z * (1 - c * c)
                d_rh = a_c @ self.p[d + "C"].T
                a_g = np.concatenate((back * (c - h) * z * (1 - z), d_rh * h * r * (1 - r)), axis=1)
                C += (r * h).T @ a_c
                U += h.T @ a_g
                back = back * (1 - z) + d_rh * r + a_g @ self.p[d + "U"].T
                inputs[t, :, : 2 * H], inputs[t, :, 2 * H :] = a_g, a_c
            W[used] = np.add.reduceat(inputs.reshape(-1, 3 * H)[order], first, axis=0)
            g |= {d + "W": W, d + "U": U, d + "C": C}
        return loss, g

    def fit(self, texts: list[bytes], target: np.ndarray, steps: int = 450, batch: int = 128, rate: float = 0.02, seed: int = 11) -> float:
        """Adam over windows of all texts, in a new order each time all were seen; languages are seen equally often."""
        r, m, v, loss = np.random.default_rng(seed), {}, {}, 0.0
        data, starts, sizes, owner = _padded(texts, TRAIN_SPAN)
        label = target[owner]
        own = [np.flatnonzero(label == k) for k in range(len(self.languages))]
        own = [o for o in own if len(o)]
        share = max(1, batch // max(1, len(own)))
        queues = [np.zeros(0, np.int64)] * len(own)
        for step in range(1, steps + 1):
            for k, o in enumerate(own):
                while len(queues[k]) < share:
                    queues[k] = np.concatenate((queues[k], r.permutation(o)))
            pick = np.concatenate([q[:share] for q in queues])
            queues = [q[share:] for q in queues]
            loss, g = self.gradients(laid_out(data, starts[pick], TRAIN_SPAN), sizes[pick], label[pick])
            scale = rate * (1 - 0.95 * step / steps)
            norm = np.sqrt(sum(float((x * x).sum()) for x in g.values()))
            for k, x in g.items():
                x = x * min(1.0, 1.0 / (norm + 1e-9))
                m[k] = 0.9 * m.get(k, 0) + 0.1 * x
                v[k] = 0.99 * v.get(k, 0) + 0.01 * x * x
                self.p[k] -= (scale * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.99**step)) + 1e-8)).astype(np.float32)
        return loss


def read(net: Network | None, texts: list[bytes | None]) -> list[tuple[str, float]]:
    """Language and score of each text; ROOM bytes of text are read at once, a longer text alone."""
    out: list[tuple[str, float]] = [(UNKNOWN, 0.0)] * len(texts)
    if net is None or not net.languages:
        return out
    known = [i for i, t in enumerate(texts) if t and has_letter(t)]
    while known:
        size, n = 0, 0
        while n < len(known) and (n == 0 or size + len(texts[known[n]]) <= ROOM):
            size += len(texts[known[n]])
            n += 1
        part, known = known[:n], known[n:]
        means = net.pooled([texts[i] for i in part])
        for i, mean in zip(part, means, strict=True):
            best = int(np.round(mean, 6).argmax())
            out[i] = (net.languages[best], min(1.0, round(float(mean[best]), 6)))
    return out


def fit(docs: DataFrame, per_language: int = 150, max_languages: int = 256, hidden: int = 16, steps: int = 450) -> Network | None:
    """A network from whole texts of at most per_language labelled rows of each language."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang")).where(F.col("text").isNotNull() & F.col("lang").isNotNull() & F.col("doc_id").isNotNull() & ~held_out())
    counts = {r["lang"]: r["n"] for r in rows.groupBy("lang").agg(F.count("*").alias("n")).limit(max_languages + 1).collect()}
    if len(counts) > max_languages:
        raise ValueError(f"more than {max_languages} languages; raise max_languages")
    if not counts:
        return None
    languages = sorted(counts)
    share = F.create_map(*(F.lit(x) for k in languages for x in (k, min(1.0, 1.3 * per_language / counts[k] + 20 / counts[k]))))
    drawn = rows.where(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000)) < share[F.col("lang")] * 1_000_000)

    by_lang: dict[str, list] = {k: [] for k in languages}
    for r in drawn.select("doc_id", "lang", F.col("text").cast("binary").alias("text")).collect():  # about per_language rows for each language
        by_lang[r["lang"]].append((r["doc_id"], bytes(r["text"])))
    texts, target = [], []
    for i, k in enumerate(languages):
        own = [t for _, t in sorted(by_lang[k])[:per_language] if has_letter(t)]
        texts += own
        target += [i] * len(own)
    net = Network(languages, hidden)
    if texts:
        net.fit(texts, np.array(target), steps)
    return net


def _labelled(docs: DataFrame, net: Network | None, schema, finish) -> DataFrame:
    held = docs.sparkSession.sparkContext.broadcast(net)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = []
            for at in range(0, len(b), 1000):
                found += read(held.value, b.column("text").slice(at, 1000).cast(pa.binary()).to_pylist())
            yield finish(b, found)

    return docs.mapInArrow(run, schema)


def predict(docs: DataFrame, net: Network | None) -> DataFrame:
    """doc_id, held_out, lang_pred, score for every document."""

    def finish(b: pa.RecordBatch, found: list[tuple[str, float]]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array([x for x, _ in found], pa.string()), pa.array([x for _, x in found], pa.float64())], ["doc_id", "lang_pred", "score"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    out = _labelled(rows, net, "doc_id long, lang_pred string, score double", finish)
    return out.select("doc_id", F.coalesce(held_out(), F.lit(False)).alias("held_out"), "lang_pred", "score")


def accepted(docs: DataFrame, net: Network | None, least_score: float = 0.0) -> DataFrame:
    """The rows of docs whose language was found with at least least_score; columns unchanged."""

    def finish(b: pa.RecordBatch, found: list[tuple[str, float]]) -> pa.RecordBatch:
        return b.filter(pa.array([x != UNKNOWN and s >= least_score for x, s in found], pa.bool_()))

    return _labelled(docs, net, docs.schema, finish)


def digest(docs: DataFrame) -> DataFrame:
    return predict(docs, fit(docs))
