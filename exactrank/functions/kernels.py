"""Kernels that run inside one partition, on Arrow arrays of any ordered type."""

from __future__ import annotations

import random

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc


def nearest(values: pa.Array, count: int, side: str) -> pa.Array:
    """The ``count`` smallest (right of the pivot) or largest (left) values, in any order, by
    selection, not sorting, where the type has it."""
    if len(values) <= count:
        return values
    if pa.types.is_integer(values.type) or pa.types.is_floating(values.type):
        a = values.to_numpy()
        a = np.partition(a, count - 1)[:count] if side == "right" else np.partition(a, len(a) - count)[-count:]
        return pa.array(a, values.type)
    order = pc.array_sort_indices(values, order="ascending" if side == "right" else "descending")
    return values.take(order[:count])


class NearestBuffer:
    """Values near a pivot within bounded memory: at most 2 d + one batch are held."""

    def __init__(self, count: int, side: str):
        self.count, self.side = count, side
        self.held: list[pa.Array] = []
        self.size = self.peak = 0

    def add(self, values: pa.Array) -> None:
        if len(values):
            self.held.append(values)
            self.size += len(values)
            self.peak = max(self.peak, self.size)
            if self.size > 2 * self.count:
                self.held = [self.result()]
                self.size = len(self.held[0])

    def result(self) -> pa.Array | None:
        return nearest(pa.concat_arrays(self.held), self.count, self.side) if self.held else None


def three_way(values: pa.Array, pivot: pa.Scalar) -> tuple[pa.Array, int, pa.Array]:
    """Values under the pivot, how many equal it, values over it."""
    return values.filter(pc.less(values, pivot)), int(pc.sum(pc.equal(values, pivot)).as_py() or 0), values.filter(pc.greater(values, pivot))


class Reservoir:
    """One value, uniform over all seen."""

    def __init__(self, rng: random.Random):
        self.rng, self.value, self.seen = rng, None, 0

    def add(self, values: pa.Array) -> None:
        if len(values):
            self.seen += len(values)
            if self.rng.randrange(self.seen) < len(values):
                self.value = values[self.rng.randrange(len(values))]


# Sequential selection: what kernels may use on one array, and what tests compare them with.


def quickselect(a: np.ndarray, k: int, seed: int = 0) -> object:
    """Random pivots: expected linear time."""
    rng, a = random.Random(seed), np.asarray(a)
    while True:
        p = a[rng.randrange(len(a))]
        below, equal = int((a < p).sum()), int((a == p).sum())
        if below <= k < below + equal:
            return p
        a, k = (a[a < p], k) if k < below else (a[a > p], k - below - equal)


def median_of_medians(a: np.ndarray, k: int) -> object:
    """Pivots from medians of fives: linear time in the worst case."""
    a = np.asarray(a)
    while len(a) > 25:
        full = a[: len(a) // 5 * 5].reshape(-1, 5)
        p = median_of_medians(np.sort(full, 1)[:, 2], len(full) // 2)
        below, equal = int((a < p).sum()), int((a == p).sum())
        if below <= k < below + equal:
            return p
        a, k = (a[a < p], k) if k < below else (a[a > p], k - below - equal)
    return np.sort(a)[k]


def sample_select(a: np.ndarray, k: int, seed: int = 0) -> object:
    """Two pivots from a sample that bracket the rank with high probability, then the bracket."""
    a = np.asarray(a)
    rng = np.random.default_rng(seed)
    while len(a) > 200:
        size = int(len(a) ** (2 / 3)) + 1
        sample = np.sort(rng.choice(a, size))
        at, margin = k * size // len(a), int(size**0.5) + 1
        low, high = sample[max(at - margin, 0)], sample[min(at + margin, size - 1)]
        below, inside = int((a < low).sum()), a[(a >= low) & (a <= high)]
        if below <= k < below + len(inside) and len(inside) < len(a):
            a, k = inside, k - below
        else:
            return quickselect(a, k, seed)
    return np.sort(a)[k]
