"""All pairs of two blocks of vectors by cosine, a strip of query rows at a time."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

#: Query rows whose products with a block are held at once.
STRIP = 512
#: Matrix products may differ from the plain sum by rounding; pairs this near the bound are summed plainly.
SLACK = 1e-6


def plain_dot(p: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Row-wise products summed from the first element on, as the engines sum a list."""
    s = np.zeros(len(p))
    for k in range(p.shape[1]):
        s += p[:, k] * q[:, k]
    return s


def _read(parts: list[pa.RecordBatch], column: str, dim: int) -> np.ndarray:
    flat = np.concatenate([b.column(column).flatten().to_numpy(zero_copy_only=False) for b in parts])
    return flat.astype(np.float64).reshape(-1, dim)


def near_pairs(batches: Iterator[pa.RecordBatch], least: float) -> Iterator[pa.RecordBatch]:
    """``src, dst, cos`` of all pairs whose cosine may reach ``least`` within a pair of blocks.

    Rows: ``id, block, left, right, embedding``, arrays of one length.  Vectors without a
    direction (all zero, or not finite) have no cosine and no pair.
    """
    parts = [b for b in batches if b.num_rows]
    ids = np.concatenate([b.column("id").to_numpy() for b in parts])
    block = np.concatenate([b.column("block").to_numpy() for b in parts])
    x = _read(parts, "embedding", len(parts[0].column("embedding")[0]))
    left, right = parts[0].column("left")[0].as_py(), parts[0].column("right")[0].as_py()
    norm = np.sqrt(plain_dot(x, x))
    good = np.isfinite(norm) & (norm > 0)
    a, b = (np.flatnonzero(good & (block == k)) for k in (left, right))
    unit = x[b] / norm[b, None]
    for at in range(0, len(a), STRIP):
        rows = a[at:at + STRIP]
        i, j = np.nonzero((x[rows] / norm[rows, None]) @ unit.T >= least - SLACK)
        i, j = rows[i], b[j]
        if left == right:
            once = ids[i] < ids[j]
            i, j = i[once], j[once]
        for k in range(0, len(i), 100_000):
            p, q = i[k:k + 100_000], j[k:k + 100_000]
            cos = plain_dot(x[p], x[q]) / (norm[p] * norm[q])
            yield pa.RecordBatch.from_arrays([pa.array(ids[p]), pa.array(ids[q]), pa.array(cos)], ["src", "dst", "cos"])
