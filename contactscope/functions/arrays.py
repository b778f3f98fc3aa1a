"""The measure's geometry and the stateful track rules on numpy arrays, for what runs in Arrow batches or on a single case."""

from __future__ import annotations

import numpy as np

from contactscope.functions.geo import EARTH_M

BLOCK = 32


def apart(ax, ay, bx, by, metric: str = "planar") -> np.ndarray:
    """Metres between places: planar, or great-circle of degrees."""
    if metric == "planar":
        return np.sqrt((ax - bx) * (ax - bx) + (ay - by) * (ay - by))
    half = np.sin(np.radians(by - ay) / 2) ** 2 + np.cos(np.radians(ay)) * np.cos(np.radians(by)) * np.sin(np.radians(bx - ax) / 2) ** 2
    return 2 * EARTH_M * np.arcsin(np.sqrt(np.minimum(half, 1.0)))


def hop_segments(t: np.ndarray, x: np.ndarray, y: np.ndarray, max_m: float, max_us: int, metric: str = "planar") -> np.ndarray:
    """Segment numbers of one sorted track by the hop rule."""
    far = (apart(x[:-1], y[:-1], x[1:], y[1:], metric) > max_m) | (np.diff(t) > max_us)
    return np.concatenate(([0], np.cumsum(far))) if len(t) else np.zeros(0, np.int64)


class Walk:
    """Segment numbers by the anchor or the diameter rule, fed with stretches of sorted tracks; the open segment is carried from one stretch to the next."""

    def __init__(self, rule: str, max_m: float, max_us: int, metric: str = "planar"):
        self.rule, self.max_m, self.max_us, self.metric = rule, max_m, max_us, metric
        self.restart()

    def restart(self) -> None:
        self.number, self.since = -1, 0
        self.xs = self.ys = np.zeros(0)

    def _far(self, t: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        """Which of the next fixes can't join the open segment, if those before them do."""
        late = t - self.since > self.max_us
        if self.rule == "anchor":
            return late | (apart(self.xs[0], self.ys[0], x, y, self.metric) > self.max_m)
        old = (apart(self.xs[:, None], self.ys[:, None], x, y, self.metric) > self.max_m).any(axis=0)
        new = apart(x[:, None], y[:, None], x, y, self.metric) > self.max_m
        return late | old | np.triu(new, 1).any(axis=0)

    def feed(self, t: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        out = np.empty(len(t), np.int32)
        i, size = 0, BLOCK
        while i < len(t):
            if not len(self.xs):
                self.number, self.since = self.number + 1, t[i]
                self.xs, self.ys = x[i : i + 1], y[i : i + 1]
                out[i] = self.number
                i, size = i + 1, BLOCK
                continue
            far = self._far(t[i : i + size], x[i : i + size], y[i : i + size])
            end = i + (int(far.argmax()) if far.any() else len(far))
            out[i:end] = self.number
            if self.rule == "diameter":
                self.xs, self.ys = np.concatenate((self.xs, x[i:end])), np.concatenate((self.ys, y[i:end]))
            if far.any():
                self.xs = self.ys = np.zeros(0)
            i, size = end, min(2 * size, 1024)
        return out


class Pace:
    """Which fixes are reached from the last kept one at no more than a speed, fed with stretches of sorted tracks."""

    def __init__(self, max_speed: float, metric: str = "planar"):
        self.max_speed, self.metric = max_speed, metric
        self.last: tuple | None = None

    def _slow(self, t: np.ndarray, x: np.ndarray, y: np.ndarray, t0, x0, y0) -> np.ndarray:
        return apart(x0, y0, x, y, self.metric) <= self.max_speed * (t - t0) / 1e6

    def feed(self, t: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        keep = np.zeros(len(t), bool)
        i = 0
        if self.last is None and len(t):
            keep[0], i = True, 1
            self.last = (t[0], x[0], y[0])
        while i < len(t):
            # the next fix that is slow enough from the last kept one, then all that follow without a fast hop
            size = BLOCK
            while i < len(t):
                slow = self._slow(t[i : i + size], x[i : i + size], y[i : i + size], *self.last)
                if slow.any():
                    i += int(slow.argmax())
                    break
                i, size = i + len(slow), 2 * size
            if i >= len(t):
                break
            keep[i] = True
            steady = self._slow(t[i + 1 : i + 1025], x[i + 1 : i + 1025], y[i + 1 : i + 1025], t[i : i + 1024][: len(t) - i - 1], x[i : i + 1024][: len(t) - i - 1], y[i : i + 1024][: len(t) - i - 1])
            n = len(steady) if steady.all() else int(np.argmin(steady))
            keep[i : i + n + 1] = True
            i += n
            self.last = (t[i], x[i], y[i])
            i += 1
        return keep


def stretches(ids: np.ndarray) -> list[tuple[int, int]]:
    """Ranges of equal neighbouring ids."""
    if not len(ids):
        return []
    cut = np.flatnonzero(ids[1:] != ids[:-1]) + 1
    return list(zip(np.concatenate(([0], cut)).tolist(), np.append(cut, len(ids)).tolist(), strict=True))
