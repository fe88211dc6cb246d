"""Blocks and sums that a task holds up to a limit; beyond that they go to its own disk, sums as sorted runs that are merged at the end."""

from __future__ import annotations

import os
import tempfile
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

from semigrid.functions.blocks import Block, Triples
from semigrid.functions.kernels import combine, joined
from semigrid.semiring import Semiring

#: Entries of unmerged results that a task holds; rows of a batch of a run on disk.
HELD_RESULTS, RUN_ROWS = 500_000, 16_384
#: Bytes of blocks that a task holds while they arrive.
HELD_BLOCKS = 32 << 20


class HeldBlocks:
    """Takes blocks under keys as they come; ``ordered`` gives them by key, one at a time, and leaves nothing behind.

    Only the keys are sorted, so neither Spark nor the worker holds the blocks of a task for that.
    """

    def __init__(self, most: int = HELD_BLOCKS):
        self.most, self.held, self.file, self.end = most, 0, None, 0
        self.waiting: list[tuple[int, Block]] = []
        self.index: list[tuple[tuple[int, ...], Block | list[tuple[int, int, np.dtype]]]] = []

    def add(self, key: tuple[int, ...], block: Block) -> None:
        parts = [self._narrow(x) for x in (block.ids, block.start, block.minor)] + [block.num.copy()]
        self.waiting.append((len(self.index), Block(*parts)))
        self.index.append((key, self.waiting[-1][1]))
        self.held += sum(x.nbytes for x in parts)
        if self.held > self.most:
            self._write()

    @staticmethod
    def _narrow(x: np.ndarray) -> np.ndarray:
        return x.astype(np.int32 if len(x) and int(x.max()) < 1 << 31 else np.int64)

    def _write(self) -> None:
        self.file = self.file or tempfile.TemporaryFile(dir=os.environ.get("TMPDIR"))
        for place, b in self.waiting:
            at = []
            for x in (b.ids, b.start, b.minor, b.num):
                at.append((self.end, x.nbytes, x.dtype))
                self.file.write(x.tobytes())
                self.end += x.nbytes
            self.index[place] = (self.index[place][0], at)
        self.file.flush()
        self.waiting, self.held = [], 0

    def ordered(self) -> Iterator[tuple[tuple[int, ...], Block]]:
        index, self.index, self.waiting, self.held = sorted(self.index, key=lambda x: x[0], reverse=True), [], [], 0
        while index:
            key, b = index.pop()
            ids, start, minor, num = (b.ids, b.start, b.minor, b.num) if isinstance(b, Block) else (np.frombuffer(os.pread(self.file.fileno(), n, low), kind) for low, n, kind in b)
            yield key, Block(ids.astype(np.int64), start.astype(np.int64), minor.astype(np.int64), num)
        if self.file:
            self.file.close()
        self.file, self.end = None, 0


class HeldSums:
    """Adds triples; ``results`` gives the sums in column-major order, and leaves nothing behind."""

    def __init__(self, ring: Semiring, most: int = HELD_RESULTS, rows: int = RUN_ROWS):
        self.ring, self.most, self.rows = ring, most, rows
        self.runs: list[Triples] = []
        self.files: list = []
        self.held = 0

    def add(self, t: Triples) -> None:
        if not len(t[0]):
            return
        self.runs.append(t)
        self.held += len(t[0])
        if self.held > self.most:
            self.runs = [combine(joined(self.runs), self.ring)]
            self.held = len(self.runs[0][0])
            if 2 * self.held > self.most:
                self._write()

    def _write(self) -> None:
        f = tempfile.TemporaryFile(dir=os.environ.get("TMPDIR"))
        self.files.append(f)
        table = pa.table(list(map(pa.array, self.runs[0])), names=["i", "j", "v"])
        with pa.ipc.new_stream(f, table.schema, options=pa.ipc.IpcWriteOptions(compression="lz4")) as out:
            out.write_table(table, max_chunksize=self.rows)
        self.runs, self.held = [], 0

    def results(self) -> Iterator[Triples]:
        if not self.files:
            if self.runs:
                i, j, v = combine(joined(self.runs), self.ring)
                for s in range(0, len(i), 200_000):
                    yield i[s : s + 200_000], j[s : s + 200_000], v[s : s + 200_000]
        else:
            if self.runs:
                self.runs = [combine(joined(self.runs), self.ring)]
                self._write()
            yield from self._merged()
        for f in self.files:
            f.close()
        self.runs, self.files, self.held = [], [], 0

    def _merged(self) -> Iterator[Triples]:
        """What lies before the least last place of all batches at hand is complete."""
        streams = []
        for f in self.files:
            f.seek(0)
            streams.append(iter(pa.ipc.open_stream(f)))
        arrays = lambda b: tuple(c.to_numpy(zero_copy_only=False) for c in b.columns)
        live = [(arrays(next(s)), s) for s in streams]
        while live:
            bj, bi = min((int(t[1][-1]), int(t[0][-1])) for t, _ in live)
            ready, rest = [], []
            for t, s in live:
                low, high = np.searchsorted(t[1], bj, "left"), np.searchsorted(t[1], bj, "right")
                cut = low + int(np.searchsorted(t[0][low:high], bi, "right"))
                if cut:
                    ready.append(tuple(x[:cut] for x in t))
                t = tuple(x[cut:] for x in t)
                if not len(t[0]):
                    following = next(s, None)
                    if following is None:
                        continue
                    t = arrays(following)
                rest.append((t, s))
            live = rest
            yield combine(joined(ready), self.ring)
