"""Reading sorted rows a run of equal keys at a time, in bounded memory."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa


def sorted_runs(batches: Iterable[pa.RecordBatch], hold: int, limit: int) -> Iterator[tuple[bool, pa.Table]]:
    """Tables of whole runs, from batches sorted by their first column (no nulls).

    About ``hold`` rows come at a time, with all rows of each of their keys: (True,
    table). The rows of a run over ``limit`` come in parts instead, as (False, part).
    """
    held: list[pa.RecordBatch] = []
    rows, over = 0, None
    for batch in (b.slice(k, hold) for b in batches for k in range(0, b.num_rows, hold)):
        if over is not None:
            n = int(np.searchsorted(np.asarray(batch.column(0)), over, "right"))
            if n:
                yield False, pa.Table.from_batches([batch.slice(0, n)])
            batch = batch.slice(n)
            if not batch.num_rows:
                continue
            over = None
        if not batch.num_rows:
            continue
        held.append(batch)
        rows += batch.num_rows
        if rows < hold:
            continue
        table = pa.Table.from_batches(held)
        key = table.column(0).to_numpy()
        last = int(np.searchsorted(key, key[-1], "left"))
        if last:
            yield True, table.slice(0, last)
        rest = table.slice(last)
        rows, held = rest.num_rows, rest.to_batches()
        if rows > limit:
            over = int(key[-1])
            yield False, rest
            rows, held = 0, []
    if rows:
        yield True, pa.Table.from_batches(held)
