"""Classes of equal fixed-length strings by interval expansion on a Burrows-Wheeler transform."""

from __future__ import annotations

import numpy as np


def sorted_suffixes(symbols: np.ndarray, depth: int) -> np.ndarray:
    """Starts of the suffixes of ``symbols`` (0 to 511) in the order of their first ``depth`` symbols, or more.

    Ranks of strings are doubled in length until all are distinct or long enough.
    """
    n = len(symbols)
    padded = np.zeros(n + 7, np.uint64)
    padded[:n] = symbols
    key = np.zeros(n, np.uint64)
    for k in range(7):
        key = key << np.uint64(9) | padded[k : k + n]
    length = 7
    while True:
        order = np.argsort(key)
        ranked = key[order]
        fresh = np.r_[True, ranked[1:] != ranked[:-1]]
        if length >= depth or fresh.all():
            return order
        rank = np.empty(n + length, np.uint64)
        rank[order] = np.cumsum(fresh)
        rank[n:] = 0
        key = rank[:n] << np.uint64(32) | rank[length:]
        length *= 2


def shared_prefix_bounds(symbols: np.ndarray, order: np.ndarray, least: int) -> np.ndarray:
    """True where a suffix shares under ``least`` symbols with the one before it in ``order``.

    Breadth-first: level l holds the intervals of suffixes that begin with a string of
    l symbols and whose right bound was found at that level. Extending a string to the
    left by a symbol maps, through the transform, its rows with that symbol to the
    interval of the longer string. So common prefixes come by increasing length, and
    the expansion stops at ``least``: bounds that are not set by then lie inside runs
    of suffixes that share that much.
    """
    n = len(symbols)
    last = symbols[order - 1].astype(np.uint16)  # the transform; the text is taken as a ring
    by_symbol = np.argsort(last, kind="stable").astype(np.int32)
    image = np.empty(n, np.int32)
    image[by_symbol] = np.arange(n, dtype=np.int32)  # row of the suffix that is longer by the symbol before
    follows = np.full(n, n, np.int32)  # next row with the same symbol
    same = last[by_symbol[1:]] == last[by_symbol[:-1]]
    follows[by_symbol[:-1][same]] = by_symbol[1:][same]
    precedes = np.full(n, -1, np.int32)
    precedes[by_symbol[1:][same]] = by_symbol[:-1][same]
    bound = np.zeros(n + 1, bool)
    bound[0] = bound[n] = True
    low, high = np.array([0], np.int32), np.array([n], np.int32)
    for _ in range(least):
        size = high - low
        rows = np.repeat(low - (np.cumsum(size, dtype=np.int32) - size), size) + np.arange(size.sum(), dtype=np.int32)
        # The last row of each symbol in its interval, and the first: images come by symbol, then by interval.
        new_high = np.sort(image[rows[follows[rows] >= np.repeat(high, size)]]) + 1
        new_low = np.sort(image[rows[precedes[rows] < np.repeat(low, size)]])
        fresh = ~bound[new_high]
        low, high = new_low[fresh], new_high[fresh]
        bound[high] = True
        if not len(low):
            break
    return bound[:n]


def window_classes(strings: list[np.ndarray], least: int) -> list[np.ndarray]:
    """For each byte string, the class of the ``least`` bytes at each of its window starts.

    Windows have the same class if and only if their bytes are equal. Strings are
    joined with separators that no window contains.
    """
    size = np.array([len(s) for s in strings])
    symbols = np.zeros(size.sum() + len(strings), np.int64)
    start = np.cumsum(size + 1) - (size + 1)
    for s, at in zip(strings, start):
        symbols[at : at + len(s)] = s.astype(np.int64) + 1
    order = sorted_suffixes(symbols, least + 1)
    run = np.cumsum(shared_prefix_bounds(symbols, order, least))
    label = np.empty(len(symbols), np.int64)
    label[order] = run
    return [label[at : at + max(0, n - least + 1)] for at, n in zip(start, size)]
