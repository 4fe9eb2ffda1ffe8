"""Pairs of two blocks of members that meet under a key, each pair once."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

#: Rows of one batch of pairs; a strip of the matrix of meetings has at most as many cells.
BATCH = 500_000


def meeting_pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """``src < dst`` of all pairs of members that share a key, within a pair of blocks.

    Rows: ``key, id, block, left, right``.  Meetings are marked in a matrix of the two blocks' members,
    so a pair that meets often is neither repeated nor shuffled.
    """
    parts = [b for b in batches if b.num_rows]
    left, right = parts[0].column("left")[0].as_py(), parts[0].column("right")[0].as_py()
    key, ids, block = (np.concatenate([b.column(c).to_numpy() for b in parts]) for c in ("key", "id", "block"))
    sides = []
    for side in (left, right):
        mine = block == side
        names, at = np.unique(ids[mine], return_inverse=True)
        order = np.argsort(key[mine], kind="stable")
        keys, start = np.unique(key[mine][order], return_index=True)
        sides.append((names, at[order], keys, np.append(start, len(order))))
    (a, at_a, keys_a, start_a), (b, at_b, keys_b, start_b) = sides
    met = np.zeros((len(a), len(b)), dtype=bool)
    for _, i, j in zip(*np.intersect1d(keys_a, keys_b, assume_unique=True, return_indices=True), strict=True):
        met[at_a[start_a[i]:start_a[i + 1], None], at_b[start_b[j]:start_b[j + 1]]] = True
    strip = max(1, BATCH // max(1, len(b)))
    for row in range(0, len(a), strip):
        i, j = np.nonzero(met[row:row + strip])
        p, q = a[i + row], b[j]
        if left == right:
            p, q = p[p < q], q[p < q]
        if len(p):
            yield pa.RecordBatch.from_arrays([pa.array(np.minimum(p, q)), pa.array(np.maximum(p, q))], ["src", "dst"])
