"""Predicted costs, as leading terms without constants, and the sketch error to ask for."""

from __future__ import annotations

import math

METHODS = ("guided", "full_sort", "prune_tree", "prune_collect", "stream_summary", "buffered_summary", "adaptive_summary")


def predict(method: str, n: float, P: float, eps: float = 1e-4, B: float = 50_000, r: float = 60) -> dict:
    """n values on P partitions, head buffer B, r samples of each partition."""
    part = n / P
    log = lambda x: math.log2(max(x, 2.0))
    ls, sketch = log(eps * part), (P / eps) * log(eps * part)
    amortised = log(1 / eps) + log(ls)
    if method == "full_sort":
        return {"exec_time": part * log(part), "driver_time": r * P * log(r * P), "exec_memory": part, "driver_memory": r * P, "work": n * log(part), "network": n, "shuffles": 1, "rounds": 1, "persists": 0, "exact": True}
    if method in ("prune_tree", "prune_collect"):
        wide = P if method == "prune_collect" else 1
        return {"exec_time": part, "driver_time": wide * log(n), "exec_memory": part, "driver_memory": wide, "work": n, "network": P * log(n), "shuffles": 0, "rounds": log(n), "persists": log(n), "exact": True}
    if method == "stream_summary":
        return {"exec_time": part * amortised, "exec_memory": ls / eps, "work": n * amortised, "exact": False}
    if method == "buffered_summary":
        return {"exec_time": part * log(B) + part / B * ls / eps, "driver_time": P / eps * log(eps * n), "exec_memory": B + ls / eps, "driver_memory": sketch, "work": n * log(B) + n / B * ls / eps, "network": sketch, "shuffles": 0, "rounds": 1, "persists": 0, "exact": False}
    if method == "adaptive_summary":
        return {"exec_time": part * amortised, "driver_time": sketch, "exec_memory": ls / eps, "driver_memory": sketch, "work": n * amortised, "network": sketch, "shuffles": 0, "rounds": 1, "persists": 0, "exact": False}
    if method == "guided":
        late = eps * n * log(P) if P > 1 / eps else 0.0
        return {"exec_time": part * amortised + late, "driver_time": sketch + eps * n, "exec_memory": part, "driver_memory": sketch + eps * n, "work": n * amortised, "network": sketch + eps * n * P, "shuffles": 0, "rounds": 3, "persists": 0, "exact": True}
    raise ValueError(f"no method {method!r}")


def sketch_dominates_at(eps: float, B: int) -> float:
    """log10 of the partition size from which merging costs more than sorting the head buffer."""
    return math.log10(1 / eps) + eps * B * math.log10(B)


def suggest_eps(n: int, P: int, driver_rows: int = 1_000_000) -> tuple[float, int]:
    """(eps, levels): the error that balances sketches against candidates, no finer than sketches
    of ``driver_rows`` tuples, and how many bracket levels bring candidates under ``driver_rows``."""
    if n <= 0:
        return 0.01, 1
    eps = min(0.01, max(math.sqrt(math.log2(max(n / max(P, 1), 4)) / n), 10 / driver_rows))
    levels, left = 1, 4 * eps * n
    while left > driver_rows and levels < 8:
        levels, left = levels + 1, left * 4 * eps
    return eps, levels
