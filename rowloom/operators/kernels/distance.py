"""Inter-row distances of code matrices."""

from __future__ import annotations

import numpy as np

KINDS = ("hamming", "delta_bits", "lee")


def bit_length(x: np.ndarray) -> np.ndarray:
    """Bits that a non-negative integer takes in binary; 0 takes none."""
    return np.ceil(np.log2(x.astype("float64") + 1.0)).astype("int64")


def to_one(codes: np.ndarray, row: np.ndarray, kind: str = "hamming", sizes: np.ndarray | None = None) -> np.ndarray:
    """Distance of every row to `row`.

    hamming: differing components; delta_bits: bits of the sign and absolute difference of each
    differing component; lee: least steps on each component's cycle of `sizes` values."""
    if kind == "hamming":
        return (codes != row).sum(axis=1)
    gap = np.abs(codes.astype("int64") - row)
    if kind == "delta_bits":
        return (bit_length(gap) + (gap > 0)).sum(axis=1)
    if kind == "lee":
        return np.minimum(gap, sizes - gap).sum(axis=1)
    raise ValueError(f"distance is one of {KINDS}")


def matrix(codes: np.ndarray, kind: str = "hamming", sizes: np.ndarray | None = None) -> np.ndarray:
    """All pairwise distances, row by row."""
    return np.stack([to_one(codes, r, kind, sizes).astype("int32") for r in codes]) if len(codes) else np.zeros((0, 0), "int32")


def path_cost(codes: np.ndarray, kind: str = "hamming", sizes: np.ndarray | None = None) -> int:
    """Sum of the distances of successive rows."""
    if len(codes) < 2:
        return 0
    if kind == "hamming":
        return int((codes[1:] != codes[:-1]).sum())
    return int(sum(to_one(codes[i : i + 1], codes[i + 1], kind, sizes)[0] for i in range(len(codes) - 1)))


def runs(codes: np.ndarray) -> int:
    """Runs over all columns: one for each column, and the path cost."""
    return codes.shape[1] + path_cost(codes) if len(codes) else 0
