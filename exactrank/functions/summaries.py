"""Rank summaries: sorted values with how many ranks each stands for.

A tuple is (v, g, slack): g is the least rank of v less that of the tuple before, slack how far
the greatest possible rank is above the least. While g + slack stays within 2 eps n, any rank
is answered within eps n. Four builders share one form: one value at a time, in batches
through a fixed head buffer, through a buffer that follows the summary's size, and a
regular sample of sorted values. Merging keeps the error bound in any order.
"""

from __future__ import annotations

import math
from bisect import bisect_left
from collections.abc import Iterable

import numpy as np
import pyarrow as pa


class RankSummary:
    """An immutable summary of n values."""

    def __init__(self, v: np.ndarray, g: np.ndarray, slack: np.ndarray, n: int, eps: float):
        self.v, self.g, self.slack, self.n, self.eps = v, g, slack, n, eps

    @classmethod
    def empty(cls, eps: float, kind="float64") -> RankSummary:
        none = np.zeros(0, np.int64)
        return cls(np.zeros(0, kind), none, none, 0, eps)

    @classmethod
    def exact(cls, values: np.ndarray, eps: float) -> RankSummary:
        values = np.sort(values)
        return cls(values, np.ones(len(values), np.int64), np.zeros(len(values), np.int64), len(values), eps)

    @property
    def room(self) -> int:
        """Up to this, g + slack of a tuple may grow; 1 while n is too small to merge anything."""
        return max(1, math.floor(2 * self.eps * self.n))

    def __len__(self) -> int:
        return len(self.v)

    def compress(self) -> RankSummary:
        """Merge tuples into their right neighbours where room allows; ends stay."""
        g, slack = self.g.tolist(), self.slack.tolist()
        room, keep, size = self.room, [], []
        i = len(g) - 1
        while i >= 0:
            own, at = g[i], i
            i -= 1
            while i > 0 and own + g[i] + slack[at] <= room:
                own += g[i]
                i -= 1
            keep.append(at)
            size.append(own)
        keep = np.array(keep[::-1], np.int64)
        return RankSummary(self.v[keep], np.array(size[::-1], np.int64), self.slack[keep], self.n, self.eps)

    def query(self, rank: int):
        """A value whose rank is within eps n of the 0-based rank."""
        if not self.n:
            return None
        least = np.cumsum(self.g)
        off = np.maximum(np.abs(rank + 1 - least), np.abs(least + self.slack - rank - 1))
        return self.v[int(np.argmin(off))].item()

    def rank(self, x) -> tuple[int, int]:
        """Bounds on how many values are at most x."""
        i = int(np.searchsorted(self.v, x, "right"))
        if i == 0:
            return 0, 0
        least = int(self.g[:i].sum())
        return least, (least + int(self.g[i] + self.slack[i]) - 1 if i < len(self.v) else self.n)

    def worst(self) -> int:
        """The largest g + slack of an inner tuple."""
        return int((self.g + self.slack)[1:-1].max(initial=0))

    def to_bytes(self) -> bytes:
        sink = pa.BufferOutputStream()
        batch = pa.RecordBatch.from_arrays([pa.array(self.v), pa.array(self.g), pa.array(self.slack)], ["v", "g", "slack"])
        with pa.ipc.new_stream(sink, batch.schema.with_metadata({"n": str(self.n), "eps": repr(self.eps)})) as w:
            w.write_batch(batch)
        return sink.getvalue().to_pybytes()

    @classmethod
    def from_bytes(cls, data: bytes) -> RankSummary:
        with pa.ipc.open_stream(data) as r:
            meta, t = r.schema.metadata, r.read_all().combine_chunks()
        v, g, slack = (t[c].to_numpy() for c in ("v", "g", "slack"))
        return cls(v, g, slack, int(meta[b"n"]), float(meta[b"eps"]))


def merge(a: RankSummary, b: RankSummary, compress: bool = True) -> RankSummary:
    """Both summaries' values in order; a tuple gains the slack of its successor in the other."""
    if not len(a) or not len(b):
        return b if not len(a) else a

    def widened(own: RankSummary, other: RankSummary) -> np.ndarray:
        i = np.searchsorted(other.v, own.v, "right")
        inside = i < len(other.v)
        # Below the other's first value nothing of it lies between.
        inside &= i > 0
        add = np.zeros(len(own.v), np.int64)
        add[inside] = (other.g + other.slack)[i[inside]] - 1
        return own.slack + add

    v = np.concatenate([a.v, b.v])
    order = np.argsort(v, kind="stable")
    g = np.concatenate([a.g, b.g])[order]
    slack = np.concatenate([widened(a, b), widened(b, a)])[order]
    out = RankSummary(v[order], g, slack, a.n + b.n, max(a.eps, b.eps))
    return out.compress() if compress else out


def fold_left(parts: Iterable[RankSummary]) -> RankSummary:
    total = None
    for p in parts:
        total = p if total is None else merge(total, p)
    return total


def tree_merge(parts: Iterable[RankSummary]) -> RankSummary:
    """Pairs, pairs of pairs, and so on: each tuple is handled a logarithmic number of times."""
    level = list(parts)
    while len(level) > 1:
        level = [merge(*level[i : i + 2]) if i + 1 < len(level) else level[i] for i in range(0, len(level), 2)]
    return level[0] if level else None


class StreamSummary:
    """One value at a time, compressed every ceil(1 / 2 eps) values."""

    def __init__(self, eps: float):
        self.eps, self.n = eps, 0
        self.v: list = []
        self.g: list[int] = []
        self.slack: list[int] = []

    def insert(self, x) -> None:
        i = bisect_left(self.v, x)
        inner = 0 < i < len(self.v)
        self.v.insert(i, x)
        self.slack.insert(i, self.g[i] + self.slack[i] - 1 if inner else 0)
        self.g.insert(i, 1)
        self.n += 1
        if self.n % math.ceil(1 / (2 * self.eps)) == 0:
            s = self.summary().compress()
            self.v, self.g, self.slack = s.v.tolist(), s.g.tolist(), s.slack.tolist()

    def insert_many(self, values: Iterable) -> None:
        for x in values:
            self.insert(x)

    def summary(self) -> RankSummary:
        return RankSummary(np.array(self.v), np.array(self.g, np.int64), np.array(self.slack, np.int64), self.n, self.eps)


class BufferedSummary:
    """Values gather in a head buffer; a full buffer is sorted and merged in at once."""

    def __init__(self, eps: float, head: int = 50_000, compress_at: int = 10_000):
        self.eps, self.head, self.compress_at = eps, head, compress_at
        self.body = RankSummary.empty(eps)
        self.waiting: list[np.ndarray] = []
        self.held = self.flushes = self.compressions = 0

    def insert_many(self, values: np.ndarray) -> None:
        at = 0
        while at < len(values):
            take = values[at : at + self.head - self.held]
            self.waiting.append(take)
            self.held += len(take)
            at += len(take)
            if self.held >= self.head:
                self.flush()

    def flush(self) -> None:
        if self.held:
            fresh = RankSummary.exact(np.concatenate(self.waiting), self.eps)
            self.body = merge(self.body, fresh, compress=False)
            self.waiting, self.held = [], 0
            self.flushes += 1
            if len(self.body) > self.compress_at:
                self.body = self.body.compress()
                self.compressions += 1
            self.after_flush()

    def after_flush(self) -> None:
        pass

    def summary(self) -> RankSummary:
        self.flush()
        return self.body.compress() if len(self.body) else self.body


class AdaptiveSummary(BufferedSummary):
    """The buffer is a multiple of the summary's size: sorting it dominates, memory does not."""

    def __init__(self, eps: float, alpha: float = 2.0, start: int = 64):
        if alpha <= 1:
            raise ValueError("alpha must be over 1")
        super().__init__(eps, start, 0)
        self.alpha, self.start = alpha, start

    def after_flush(self) -> None:
        self.head = max(self.head, math.ceil(self.alpha * len(self.body)))


class RegularSample:
    """Every step-th of the sorted values: ranks within step, at the price of a full sort."""

    def __init__(self, values: np.ndarray, step: int):
        ordered = np.sort(values)
        self.step, self.n, self.kept = step, len(ordered), ordered[::step]

    def rank(self, x) -> int:
        """About how many values are under x: that of the nearest sample."""
        if not len(self.kept):
            return 0
        i = int(np.searchsorted(self.kept, x))
        near = [j for j in (i - 1, i) if 0 <= j < len(self.kept)]
        return min(near, key=lambda j: abs(self.kept[j] - x)) * self.step
