"""Parameters from memory sizes, and the cost model of the number of buckets."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np

INT = 4


@dataclass(frozen=True)
class StoragePlan:
    required_bytes: int
    mode: str


def required_memory(n_docs: int, n_hashes: int, processes: int, bands_resident: int = 1) -> int:
    """Bytes of signatures and of the resident band's bucket ids in all processes of a node."""
    return n_docs * (n_hashes + bands_resident) * INT * processes


def choose_storage(n_docs: int, n_hashes: int, processes: int, memory: int, alpha: float = 0.2) -> StoragePlan:
    """In memory while the estimate stays within the margin, else on disk as Parquet."""
    need = required_memory(n_docs, n_hashes, processes)
    return StoragePlan(need, "memory" if need <= alpha * memory else "parquet")


def choose_c(n_docs: int, k_buckets: int, n_hashes: int, processes: int, memory: int, alpha: float = 0.2) -> int:
    """Buckets per sweep: as many as the margin of the memory holds in every process."""
    if n_docs == 0:
        return k_buckets
    return min(k_buckets, max(1, math.floor(alpha * memory * k_buckets / (processes * n_docs * n_hashes * INT))))


def choose_d_max(n_hashes: int, memory: int, beta: float = 0.5) -> int:
    """The largest bucket whose signatures take less than the margin of the comparing process's memory."""
    return max(1, math.ceil(beta * memory / (n_hashes * INT)) - 1)


def predict_time(n: int, k: float, a: float, b: float) -> float:
    return a * n * k + b * n * n / k


def k_opt(n: int, a: float, b: float) -> float:
    """The number of buckets where the predicted time is least."""
    return math.sqrt(b * n / a)


def fit_cost_model(observed: list[tuple[int, int, float]]) -> tuple[float, float]:
    """(a, b) by least squares from (documents, buckets, seconds)."""
    x = np.array([[n * k, n * n / k] for n, k, _ in observed], dtype=np.float64)
    a, b = np.linalg.lstsq(x / x.max(axis=0), np.array([t for *_, t in observed]), rcond=None)[0] / x.max(axis=0)
    return float(a), float(b)


def comm_bytes(plan: str, n_docs: int, cfg, candidates: int = 0) -> int:
    """Bytes that a plan sends between workers, estimated: signatures with every band, keys only, or each sweep's rows once."""
    sig = cfg.n_hashes * INT
    row = 20
    if plan == "shuffle":
        return n_docs * cfg.bands * (row + sig)
    if plan == "keys":
        return n_docs * cfg.bands * row + 2 * candidates * sig
    if plan == "stream":
        return n_docs * (sig + cfg.bands * INT)
    raise ValueError(f"no such plan: {plan}")
