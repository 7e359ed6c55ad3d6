"""Formulas for work, bytes, intensity and the roofline, in numbers or columns."""

from __future__ import annotations


def flops(nnz, d):
    """An addition and a multiplication in each half of the fold."""
    return nnz * d * 4


def fused_bytes(m, n, nnz, d, index: int = 8, value: int = 4):
    """Targets read and written, neighbours read, edges with an index and a value."""
    return m * d * (2 * value) + n * d * value + nnz * (index + value)


def fused_bytes_published(m, n, nnz, d):
    return m * d * 8 + n * d * 4 + nnz * 12


def message_bytes(nnz, d, vector: bool = True, index: int = 8, value: int = 4):
    """Messages kept between two phases, at worst an index with each number."""
    return nnz * d * (index + value) if vector else nnz * (index + value)


def intensity(delta, d):
    """Lower bound of operations for each byte, at mean degree delta."""
    return delta / (delta * 3.0 / d + 2.0 + delta)


def roofline(ai: float, bandwidth: float, peak: float = float("inf")) -> float:
    return min(peak, ai * bandwidth)


def achieved(nnz: int, d: int, seconds: float) -> float:
    return flops(nnz, d) / seconds / 1e9


def access_counts(m, n, nnz, d):
    """Numbers of X and Z moved if each row is held while its edges are met, and if each edge fetches them; and of Y."""
    return m * d, nnz * d, nnz * d


def speedup(baseline: float | None, fused: float | None) -> float | None:
    """None where one of them did not finish."""
    return baseline / fused if baseline and fused else None


def moved_bytes(strategy: str, m: int, n: int, nnz: int, d: int, executors: int, groups: int, value: int = 8) -> float:
    """What a strategy sends: neighbour features to all executors, to groups of rows, or targets' partial results back."""
    if strategy == "broadcast":
        return executors * n * d * value
    if strategy == "row_stationary":
        return min(nnz, groups * n) * d * value
    if strategy == "source_stationary":
        return min(nnz, groups * m) * d * (8 + value)
    return nnz * d * value
