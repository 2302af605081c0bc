"""Sorted 64-bit keys in few bytes, for sending them between tasks."""

from __future__ import annotations

import numpy as np


def packed(sorted_keys: np.ndarray) -> bytes:
    """Sorted keys as deltas: four low bytes each, two middle ones where many deltas need them, and the rest for the few that are wider."""
    delta = np.diff(sorted_keys, prepend=np.uint64(0))
    middle = np.count_nonzero(delta >> np.uint64(32)) * 4 > len(delta)
    rest = delta >> np.uint64(48 if middle else 32)
    at = np.flatnonzero(rest)
    head = np.asarray([len(delta), len(at), middle], dtype="<u4")
    between = (delta >> np.uint64(32)).astype("<u2") if middle else np.zeros(0, "<u2")
    return b"".join(x.tobytes() for x in (head, delta.astype("<u4"), at.astype("<u4"), rest[at].astype("<u4"), between))


def unpacked(data: bytes) -> np.ndarray:
    n, k, middle = (int(x) for x in np.frombuffer(data, "<u4", 3))
    delta = np.frombuffer(data, "<u4", n, 12).astype(np.uint64)
    if middle:
        delta |= np.frombuffer(data, "<u2", n, 12 + 4 * n + 8 * k).astype(np.uint64) << np.uint64(32)
    at = np.frombuffer(data, "<u4", k, 12 + 4 * n)
    delta[at] |= np.frombuffer(data, "<u4", k, 12 + 4 * n + 4 * k).astype(np.uint64) << np.uint64(48 if middle else 32)
    return np.cumsum(delta, dtype=np.uint64)
