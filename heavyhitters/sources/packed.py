"""Many unsigned 32-bit items in one binary value, in their order."""

from __future__ import annotations

import numpy as np

#: Stands for a number of this size or more, which is among the wide ones.
WIDE = 255


def narrowed(items: np.ndarray) -> bytes:
    """How many items are WIDE or more, these as 32-bit numbers, then a byte for each item.

    At most five bytes an item and four more, whatever the items are.
    """
    wide = items[items >= WIDE].astype("<u4")
    return b"".join([len(wide).to_bytes(4, "little"), wide.tobytes(), np.minimum(items, WIDE).astype(np.uint8).tobytes()])


def parts(data: bytes | memoryview) -> tuple[np.ndarray, np.ndarray]:
    """The wide items and the bytes of all, both in order."""
    count = int(np.frombuffer(data, "<u4", 1)[0])
    return np.frombuffer(data, "<u4", count, 4), np.frombuffer(data, np.uint8, offset=4 + 4 * count)


def widened(data: bytes | memoryview) -> np.ndarray:
    """The items again."""
    wide, small = parts(data)
    items = small.astype(np.int64)
    items[small == WIDE] = wide
    return items


def counted(data: bytes | memoryview) -> tuple[np.ndarray, np.ndarray]:
    """The distinct items, ascending, and how often each occurs."""
    wide, small = parts(data)
    times = np.bincount(small, minlength=WIDE + 1)[:WIDE]
    low = np.flatnonzero(times)
    high, more = np.unique(wide, return_counts=True)
    return np.concatenate([low, high.astype(np.int64)]), np.concatenate([times[low], more])
