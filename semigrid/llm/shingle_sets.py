"""Exact similarity joins of shingle sets: prefixes, parity sketches, and verification on whole texts."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semigrid.functions.worker import lean
from semigrid.llm.runs import sorted_runs
from semigrid.plans.scratch import guarded_broadcast, materialize

_LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
#: Cells of the table by whose counts shingles are ordered; documents of one shingle that are compared all with all.
ORDER_CELLS, ALL_PAIRS = 1 << 17, 32
#: Documents of a crowd that are compared with all others in its first round, growth from round to round, and documents on a side of a cell.
HUBS, GROWTH, SIDE = 64, 64, 4096
#: Bits of a parity sketch for each shingle, and the least bits.
_SKETCH_EACH, _SKETCH_LEAST = 4, 256


def shingles(text: str, words: int) -> list[bytes]:
    w = text.encode().translate(_LOWER).split()
    if len(w) <= words:
        return [b" ".join(w)] if w else []
    return list(map(b" ".join, zip(*(w[k:] for k in range(words)))))


def shingle_hashes(text: str, words: int, seen: dict[bytes, int]) -> np.ndarray:
    """Distinct 64-bit hashes of the shingles of a text, sorted; ``seen`` keeps those of words."""
    import xxhash

    w = text.encode().translate(_LOWER).split()
    if len(w) < words:
        return np.array([xxhash.xxh64_intdigest(b" ".join(w))] if w else [], np.uint64)
    if len(seen) > 200_000:
        seen.clear()
    for x in w:
        if x not in seen:
            seen[x] = xxhash.xxh64_intdigest(x)
    h = np.fromiter(map(seen.__getitem__, w), np.uint64, len(w))
    n, out = len(w) - words + 1, np.zeros(len(w) - words + 1, np.uint64)
    for k in range(words):
        out = (out ^ h[k : k + n]) * np.uint64(0x9E3779B97F4A7C15)
        out ^= out >> np.uint64(29)
    return np.unique(out)


def fingerprint(hashes: np.ndarray) -> int:
    """Bit k is set if it is set in over half of the hashes; zero for none."""
    if not len(hashes):
        return 0
    ones = np.zeros(64, np.int64)
    for at in range(0, len(hashes), 8192):
        part = hashes[at : at + 8192]
        ones += np.unpackbits(part.view(np.uint8).reshape(len(part), 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(ones * 2 > len(hashes), bitorder="little").view(np.int64)[0])


def parity_sketch(hashes: np.ndarray) -> np.ndarray:
    """One bit for each residue of hashes: whether an odd number of them falls there, in 64-bit words.

    Two sets that differ in d hashes have sketches that differ in d bits at most. The length
    is a power of two in proportion to the set; halves laid over each other by exclusive or
    are the sketch of half the length.
    """
    bits = _SKETCH_LEAST
    while bits < _SKETCH_EACH * len(hashes):
        bits *= 2
    odd = np.bincount((hashes >> np.uint64(20)).astype(np.int64) & (bits - 1), minlength=bits).astype(np.uint8) & 1
    return np.packbits(odd, bitorder="little").view(np.uint64)


def most_apart(n, m, similarity: float):
    """Elements in which sets of sizes n and m may differ at most."""
    return np.floor((n + m) * (1 - similarity) / (1 + similarity) + 1e-6)


def sketches_agree(x: list[np.ndarray], y: list[np.ndarray], most: np.ndarray) -> np.ndarray:
    """For pairs of sketches, whether they differ in ``most`` bits or fewer at their common length."""
    out = np.zeros(len(x), bool)
    size = np.array([min(len(p), len(q)) for p, q in zip(x, y)], np.int64)
    for words in np.unique(size):
        rows = np.flatnonzero(size == words)
        step = max(1, (1 << 20) // int(words))
        for at in range(0, len(rows), step):
            part = rows[at : at + step]
            p, q = (np.stack([_folded(side[k], int(words)) for k in part]) for side in (x, y))
            out[part] = np.bitwise_count(p ^ q).sum(1, dtype=np.int64) <= most[part]
    return out


def _folded(sketch: np.ndarray, words: int) -> np.ndarray:
    while len(sketch) > words:
        half = len(sketch) // 2
        sketch = sketch[:half] ^ sketch[half:]
    return sketch


def _sketches(column: pa.ChunkedArray | pa.Array) -> list[np.ndarray]:
    return [np.frombuffer(x, np.uint64) for x in column.to_pylist()]


def _cell(hashes: np.ndarray) -> np.ndarray:
    return (hashes >> np.uint64(40)).astype(np.int64) % ORDER_CELLS


def _shingle_order(read: DataFrame, words: int) -> np.ndarray:
    """How many shingles of all documents fall in each cell of hashes: common ones stand out at any size."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cells, seen = np.zeros(ORDER_CELLS, np.int64), {}
        for batch in batches:
            held = [_cell(shingle_hashes(text.as_py(), words, seen)) for text in batch.column(1)]
            if held:
                cells += np.bincount(np.concatenate(held), minlength=ORDER_CELLS)
        at = np.flatnonzero(cells)
        yield pa.RecordBatch.from_arrays([pa.array(at, pa.int32()), pa.array(cells[at], pa.int64())], ["cell", "n"])

    found = read.mapInArrow(lean(run), "cell int, n long").groupBy("cell").agg(F.sum("n").alias("n")).toPandas()
    out = np.zeros(ORDER_CELLS, np.int64)
    out[found["cell"].to_numpy(np.int64)] = found["n"].to_numpy(np.int64)
    return out


def shingle_table(read: DataFrame, similarity: float, words: int) -> DataFrame:
    """(node, digest, n, fp, sketch, keys) of each text: the digest, size, SimHash fingerprint and parity sketch of its set, and its prefix.

    All sets are ordered alike, rare shingles first. Sets of similarity t have t of the
    larger one in common, so they meet within the first n - ceil(t n) + 1 of each.
    """
    order = _shingle_order(read, words)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from hashlib import blake2b

        seen: dict[bytes, int] = {}
        for batch in batches:
            out: list[tuple] = []
            for text in batch.column(1):
                h = shingle_hashes(text.as_py(), words, seen)
                n = len(h)
                first = h[np.argsort(order[_cell(h)], kind="stable")[: n - int(np.ceil(similarity * n - 1e-9)) + 1]]
                out.append((blake2b(h.tobytes(), digest_size=16).digest(), n, fingerprint(h), parity_sketch(h).tobytes(), first.view(np.int64)))
            kinds = (pa.binary(), pa.int32(), pa.int64(), pa.binary(), pa.list_(pa.int64()))
            columns = zip(*out) if out else [[]] * len(kinds)
            yield pa.RecordBatch.from_arrays([batch.column(0), *[pa.array(x, t) for x, t in zip(columns, kinds)]], ["node", "digest", "n", "fp", "sketch", "keys"])

    return read.mapInArrow(lean(run), "node long, digest binary, n int, fp long, sketch binary, keys array<long>")


def meeting_pairs(posted: DataFrame, similarity: float, run_limit: int) -> DataFrame:
    """(u, v, key, n): pairs of a key, of different groups, that may be similar; v is null in the rows of a key over ``run_limit``, passed on one by one.

    ``posted`` has key, node, n, at and group.
    """
    share = similarity / (1 + similarity)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def out(u, v, key, n) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), v, pa.array(key, pa.int64()), pa.array(n, pa.int32())], ["u", "v", "key", "n"])

        for whole, table in sorted_runs(batches, 20_000, 20_000):
            key, node, n, at, group = (table.column(k).to_numpy() for k in range(5))
            alone = lambda rows: out(node[rows], pa.nulls(len(rows), pa.int64()), key[rows], n[rows])  # noqa: B023, E731
            if not whole:
                yield alone(np.arange(len(key)))
                continue
            start = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
            size = np.diff(np.r_[start, len(key)])
            for m in np.unique(size[(size > 1) & (size <= run_limit)]):
                i, j = np.triu_indices(m, 1)
                some = start[size == m]
                step = max(1, 500_000 // len(i))
                for k in range(0, len(some), step):
                    x, y = ((some[k : k + step, None] + side).ravel() for side in (i, j))
                    # what two sets have in common does not come before the first shingle that they share
                    ok = np.minimum(n[x] - at[x], n[y] - at[y]) >= share * (n[x].astype(np.int64) + n[y]) - 1e-6
                    ok &= group[x] != group[y]
                    x, y = x[ok], y[ok]
                    if len(x):
                        yield out(node[x], pa.array(node[y], pa.int64()), key[x], n[x])
            many = np.repeat(size > run_limit, size)
            if many.any():
                yield alone(np.flatnonzero(many))

    return posted.select("key", "node", "n", "at", "group").repartition("key").sortWithinPartitions("key").mapInArrow(lean(run), "u long, v long, key long, n int")


def crowd_pairs(crowds: DataFrame, tried: int, now: int, similarity: float, side: int = SIDE) -> DataFrame:
    """(u, v): pairs of documents of one key that may be similar, by size and sketch, and are of different groups.

    ``crowds`` has key, m (documents of the key), turn (0 to m), node, n, group and sketch.
    Documents whose turn is from ``tried`` to ``now`` are compared with all whose turn did not
    pass before. A key is cut into a grid of cells with about ``side`` documents on each
    side, so no task holds more, whatever the size of the key.
    """
    cells = lambda first, last: F.sequence(F.floor(first / side), F.floor(last / side))
    last = F.least(F.col("m"), F.lit(now)) - 1
    columns = ["key", "turn", "node", "n", "group", "sketch"]
    open_ = crowds.filter(F.col("turn") >= tried)
    hubs = open_.filter(F.col("turn") < now).withColumn("row", F.floor(F.col("turn") / side)).withColumn("col", F.explode(cells(F.lit(tried), F.col("m") - 1)))
    others = open_.withColumn("col", F.floor(F.col("turn") / side)).withColumn("row", F.explode(cells(F.lit(tried), last)))
    rows = hubs.withColumn("hub", F.lit(1)).unionByName(others.withColumn("hub", F.lit(0))).select(F.xxhash64("key", "row", "col").alias("cell"), "hub", *columns)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, table in sorted_runs(batches, 4_000, 1 << 40):
            cell, hub, _, _, node, n, group = (table.column(k).to_numpy() for k in range(7))
            sketch = _sketches(table.column(7))
            start = np.flatnonzero(np.r_[True, cell[1:] != cell[:-1], True])
            for s, e in zip(start[:-1], start[1:]):
                x, y = s + np.flatnonzero(hub[s:e] == 1), s + np.flatnonzero(hub[s:e] == 0)
                for at in range(0, len(x), 64):
                    some = x[at : at + 64]
                    ok = np.minimum(n[some][:, None], n[y]) >= similarity * np.maximum(n[some][:, None], n[y]) - 1e-6
                    p, q = np.nonzero(ok & (group[some][:, None] != group[y]))
                    p, q = some[p], y[q]
                    keep = _close(sketch, p, q, most_apart(n[p].astype(np.int64), n[q], similarity))
                    yield pa.RecordBatch.from_arrays([pa.array(node[p[keep]], pa.int64()), pa.array(node[q[keep]], pa.int64())], ["u", "v"])

    dealt = rows.repartition("cell").sortWithinPartitions("cell")
    return dealt.mapInArrow(lean(run), "u long, v long")


def _close(sketch: list[np.ndarray], p: np.ndarray, q: np.ndarray, most: np.ndarray) -> np.ndarray:
    """As ``sketches_agree``, for pairs of rows, with each sketch stacked once for each length."""
    out = np.zeros(len(p), bool)
    if not len(p):
        return out
    length = np.array([len(s) for s in sketch])
    common = np.minimum(length[p], length[q])
    for words in np.unique(common):
        rows = np.flatnonzero(common == words)
        used, inverse = np.unique(np.r_[p[rows], q[rows]], return_inverse=True)
        stack = np.stack([_folded(sketch[k], int(words)) for k in used])
        left, right = inverse[: len(rows)], inverse[len(rows) :]
        step = max(1, (1 << 20) // int(words))
        for at in range(0, len(rows), step):
            cut = slice(at, at + step)
            out[rows[cut]] = np.bitwise_count(stack[left[cut]] ^ stack[right[cut]]).sum(1, dtype=np.int64) <= most[rows[cut]]
    return out


def verified_pairs(read: DataFrame, table: DataFrame, pairs: DataFrame, similarity: float, words: int) -> DataFrame:
    """Of the pairs (u, v), those whose texts have similar sets of shingles: sketches first, then the texts."""

    def agree(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n, m = (np.asarray(batch.column(k)).astype(np.int64) for k in (2, 3))
            keep = sketches_agree(_sketches(batch.column(4)), _sketches(batch.column(5)), most_apart(n, m, similarity))
            yield batch.filter(pa.array(keep)).select(["u", "v"])

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y in zip(batch.column(2), batch.column(3)):
                s, t = set(shingles(x.as_py(), words)), set(shingles(y.as_py(), words))
                both = len(s & t)
                keep.append(both >= similarity * (len(s) + len(t) - both))
            yield batch.filter(pa.array(keep, pa.bool_())).select(["u", "v"])

    pairs = pairs.filter("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
    known = table.select("node", "n", "sketch")
    both = pairs.join(known.toDF("u", "n", "x"), "u").join(known.toDF("v", "m", "y"), "v").select("u", "v", "n", "m", "x", "y")
    close = materialize(both.mapInArrow(lean(agree), "u long, v long"), "close")
    meant = materialize(close.select(F.explode(F.array("u", "v")).alias("id")).distinct(), "meant")
    asked = meant.count()
    if not asked:
        return close
    bodies = materialize(read.toDF("id", "body").join(guarded_broadcast(meant, 40, rows=asked), "id", "left_semi"), "bodies")
    joined = close.join(bodies.toDF("u", "x"), "u").join(bodies.toDF("v", "y"), "v").select("u", "v", "x", "y")
    return materialize(joined.mapInArrow(lean(verify), "u long, v long"), "verified")
