"""Distinct-chunk tables: bounded memos from a piece of text to what a tokenizer makes of it."""

from __future__ import annotations

import re
from collections.abc import Callable, Iterable
from typing import Any

#: Cost of the chunks that a worker remembers at most, in each of two generations: characters and 8 for each.
MEMO_COST = 2_000_000
#: Longer chunks are not remembered.
LONGEST = 48


class ChunkTable:
    """Chunk to value; ``values`` computes all missing chunks of a text at once.

    Two generations bound the memory: when the young one is full it becomes the old
    one, and chunks still in use move back by being looked up.
    """

    def __init__(self, compute: Callable[[list], Iterable[Any]], cost: int = MEMO_COST):
        self.compute, self.cost, self.used = compute, cost, 0
        self.young: dict = {}
        self.old: dict = {}

    def clear(self) -> None:
        self.young, self.old, self.used = {}, {}, 0

    def values(self, chunks: list) -> list:
        """The value of each chunk, in the order of the text; values are never None."""
        if self.used > self.cost:
            self.old, self.young, self.used = self.young, {}, 0
        young, old = self.young, self.old
        out = list(map(young.get, chunks))
        gaps = [k for k, v in enumerate(out) if v is None]
        if gaps:
            missing = {chunks[k] for k in gaps}
            self.used += sum(map(len, missing)) + 8 * len(missing)
            fresh = []
            for x in missing:
                if (v := old.get(x)) is None:
                    fresh.append(x)
                else:
                    young[x] = v
            if fresh:
                young.update(zip(fresh, self.compute(fresh)))
            for k in gaps:
                out[k] = young[chunks[k]]
            if max(map(len, missing)) > LONGEST:
                for x in missing:
                    if len(x) > LONGEST:
                        del young[x]
        return out


_MARKED = re.compile(" *[^ ]+| +")


def marked_words(text: str) -> list[str]:
    """Chunks of a text for a vocabulary whose pieces never cross from a word into a marker.

    A chunk is a run of markers and the word after it. Every chunk begins with a marker,
    the first by the dummy prefix; that one marker is left out, so joining the chunks
    by one space gives the text back.
    """
    if "▁" in text:
        text = text.replace("▁", " ")
    if not text:
        return []
    if "  " not in text and text[0] != " " and text[-1] != " ":
        return text.split(" ")
    return [x[1:] for x in _MARKED.findall(" " + text)]
