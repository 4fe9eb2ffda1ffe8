"""Which edges of a dense graph lie in a clique of four, with neighbours as bits."""

from __future__ import annotations

import numpy as np

#: Edges whose common neighbours are unpacked at once: a byte for each bit of their words.
STRIP = 8192


def in_four_clique(left: np.ndarray, right: np.ndarray, adjacent: np.ndarray) -> np.ndarray:
    """For each edge, whether two of its common neighbours are joined, one of ``left`` and one of ``right``.

    ``left`` and ``right`` (edges x words) have a bit for each common neighbour in two blocks of vertices,
    ``adjacent`` (vertices of the left block x words) one for each neighbour in the right block.
    """
    out = np.zeros(len(left), dtype=bool)
    for at in range(0, len(left), STRIP):
        one, two = left[at:at + STRIP], right[at:at + STRIP]
        bits = np.unpackbits(np.ascontiguousarray(one, dtype="<u8").view(np.uint8), axis=1, bitorder="little")
        edge, vertex = np.nonzero(bits)
        hit = (adjacent[vertex] & two[edge]).any(axis=1)
        out[at + edge[hit]] = True
    return out
