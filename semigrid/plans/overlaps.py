"""The k greatest products of each row of a matrix of positive whole numbers with later rows, without making all of them.

Rows are dealt into ranges of ids with about as many entries each. A task holds one range and reads
all rows before its end one by one. Inner ids that many held rows have stand as bits, the others as
lists. The lists of a row give its products at rare inner ids; at the others a product is no greater
than the number of bits on either side. Rows that cannot be among the k by that bound are left out
before bits are counted.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from semigrid.functions.worker import lean, small_batches
from semigrid.matrix import SparseMatrix
from semigrid.plans.scratch import materialize

#: Entries that a task holds, and entries that count as one when rows are dealt into ranges.
HELD_ENTRIES, WEIGHT = 6_000_000, 256
#: Entries of a range below which it is not made smaller to have all cores at work.
SHARED_ENTRIES = 200_000
#: Inner ids that are numbered by a list in each worker; more are numbered by a join.
LISTED_IDS = 8_000_000
#: Inner ids of a range that stand as bits, and rows that are multiplied in full for a first bound.
BITS, TRIED = 1024, 256
_STEP = 65535
#: Rows whose results are given at once.
_BATCH = 4000


def _packed(codes: np.ndarray, listed: bool) -> bytes:
    """Ascending codes: their steps in two bytes each, full ones before a wide step; codes far apart as they are."""
    if not listed:
        return codes.astype(np.int64).tobytes()
    steps = np.diff(codes, prepend=0)
    full = steps // _STEP
    out = np.full(len(codes) + int(full.sum()), _STEP, np.uint16)
    out[np.cumsum(full + 1) - 1] = steps - full * _STEP
    return out.tobytes()


def _unpacked(data: bytes, listed: bool) -> np.ndarray:
    if not listed:
        return np.frombuffer(data, np.int64)
    steps = np.frombuffer(data, np.uint16)
    return np.cumsum(steps, dtype=np.int64)[steps != _STEP]


def _numbered(m: SparseMatrix) -> tuple[DataFrame, np.ndarray | None]:
    """(i, w, v) without inner ids of one row alone, and where ``w`` is a digest still, the sorted digests whose places are the numbers."""
    counts = m.df.filter("j is not null").groupBy("j").agg(F.count(F.lit(1)).alias("n"))
    counts = materialize(counts.select("j", F.xxhash64("j").alias("h"), "n"), "words")
    words = counts.filter("n > 1")
    entries = m.df.filter("i is not null and j is not null")
    twice = counts.groupBy("h").agg(F.count(F.lit(1)).alias("ids")).filter("ids > 1")
    if words.count() <= LISTED_IDS and twice.isEmpty():
        listed = np.sort(words.select("h").toArrow().column("h").to_numpy())
        return entries.select("i", F.xxhash64("j").alias("w"), F.col("v").cast("long").alias("v")), listed
    ids = words.select("j", F.monotonically_increasing_id().alias("w"))
    return entries.join(materialize(ids, "ids"), "j").select("i", "w", F.col("v").cast("long").alias("v")), None


def _pieces(m: SparseMatrix, ones: bool) -> tuple[DataFrame, bool]:
    """(i, n, codes, vals): the entries of a row, in one piece or some; in few where its entries follow each other."""
    entries, digests = _numbered(m)
    listed = digests is not None
    sent = m.df.sparkSession.sparkContext.broadcast(digests) if listed else None

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            i, w, v = (batch.column(c).to_numpy(zero_copy_only=False) for c in range(3))
            if listed:
                if not len(sent.value):
                    continue
                at = np.minimum(np.searchsorted(sent.value, w), len(sent.value) - 1)
                known = sent.value[at] == w
                i, w, v = i[known], at[known], v[known]
            if not len(i):
                continue
            order = np.lexsort((w, i))
            i, w, v = i[order], w[order], v[order]
            ends = np.r_[np.flatnonzero(i[1:] != i[:-1]) + 1, len(i)]
            starts = np.r_[0, ends[:-1]]
            codes = [_packed(w[s:e], listed) for s, e in zip(starts, ends)]
            vals = [None if ones else v[s:e].astype(np.int64).tobytes() for s, e in zip(starts, ends)]
            yield pa.RecordBatch.from_arrays([pa.array(i[starts]).cast(pa.int64()), pa.array(ends - starts).cast(pa.int64()), pa.array(codes, pa.binary()), pa.array(vals, pa.binary())], ["i", "n", "codes", "vals"])

    entries = entries.withColumn("i", F.col("i").cast("long"))
    return materialize(entries.mapInArrow(lean(pack), "i long, n long, codes binary, vals binary"), "pieces"), listed


class _Held:
    """Rows in ascending order of ids, as lists by inner id; where all values are one, the inner ids of most rows stand as bits."""

    def __init__(self, rows: list[tuple[int, np.ndarray, np.ndarray | None]]):
        self.ids = np.array([r[0] for r in rows], np.int64)
        row = np.repeat(np.arange(len(rows), dtype=np.int32), [len(r[1]) for r in rows])
        ones = rows[0][2] is None
        vals = None if ones else np.concatenate([r[2] for r in rows])
        code = np.concatenate([r[1] for r in rows])
        rows.clear()
        if ones and code.max() < 1 << 31:
            key = code.astype(np.int64)
            key <<= 32
            key |= row
            del code, row
            key.sort()
            self.post = key.astype(np.int32)  # the lower half
            key >>= 32
            code = key
        else:
            order = np.argsort(code, kind="stable")
            code, self.post, vals = code[order], row[order], vals if ones else vals[order]
        head = np.flatnonzero(np.r_[True, code[1:] != code[:-1]])
        self.words, self.start = code[head].astype(np.int64), np.r_[head, len(code)]
        del code
        self.weight = vals
        self.table = None
        if self.words[-1] < max(1 << 20, 8 * len(self.words)):
            self.table = np.full(self.words[-1] + 1, -1, np.int32)
            self.table[self.words] = np.arange(len(self.words), dtype=np.int32)
        self.bit = np.full(len(self.words), -1, np.int16)
        self.bits = np.zeros((BITS // 64, len(self.ids)), np.uint64)
        self.common = np.zeros(len(self.ids), np.int32)  # bits of each row
        if ones:
            size = np.diff(self.start)
            for x, w in enumerate(np.argsort(-size, kind="stable")[:BITS]):
                at = self.post[self.start[w] : self.start[w + 1]]
                self.bit[w] = x
                self.bits[x // 64, at] |= np.uint64(1 << x % 64)
                self.common[at] += 1

    def local(self, codes: np.ndarray) -> np.ndarray:
        """Places of those codes that are held, -1 for others."""
        if self.table is not None:
            inside = codes < len(self.table)
            return np.where(inside, self.table[np.where(inside, codes, 0)], -1)
        at = np.minimum(np.searchsorted(self.words, codes), len(self.words) - 1)
        return np.where(self.words[at] == codes, at, -1)

    def _sums(self, w: np.ndarray, v: np.ndarray | None) -> np.ndarray:
        """For every held row, the products at these inner ids."""
        begin, end = self.start[w], self.start[w + 1]
        if v is None:
            n = end - begin
            total = int(n.sum())
            if total < 128 * len(w):  # many short lists
                before = np.cumsum(n) - n
                at = self.post[np.repeat(begin - before, n) + np.arange(total)]
            else:
                at = np.concatenate([self.post[:0], *[self.post[s:e] for s, e in zip(begin.tolist(), end.tolist())]])
            return np.bincount(at, minlength=len(self.ids))
        out = np.zeros(len(self.ids), np.int64)
        for s, e, x in zip(begin.tolist(), end.tolist(), v.tolist()):
            out[self.post[s:e]] += self.weight[s:e] * x
        return out

    def _with_bits(self, rows: np.ndarray, sums: np.ndarray, mask: np.ndarray) -> np.ndarray:
        out = sums[rows]
        for x in np.flatnonzero(mask).tolist():
            out += np.bitwise_count(self.bits[x][rows] & mask[x])
        return out

    def best(self, i: int, codes: np.ndarray, vals: np.ndarray | None, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Ids after ``i`` of the k greatest products that are not zero, and these; of equal ones the least ids."""
        first = int(np.searchsorted(self.ids, i, "right"))
        w = self.local(codes) if first < len(self.ids) else np.zeros(0, np.int64)
        if not (w >= 0).any():
            return self.ids[:0], self.ids[:0]
        bit = np.where(w >= 0, self.bit[w], -1)
        rare = (w >= 0) & (bit < 0)
        sums = self._sums(w[rare], vals if vals is None else vals[rare])
        sums[:first] = 0
        bit = bit[bit >= 0].astype(np.int64)
        if len(bit):
            mask = np.zeros(len(self.bits), np.uint64)
            np.bitwise_or.at(mask, bit // 64, np.uint64(1) << (bit % 64).astype(np.uint64))
            most = sums[first:].astype(np.int32)  # with the bits, no product is greater
            most += np.minimum(self.common[first:], len(bit))
            lead = np.flatnonzero(most >= max(1, most.max() * 9 // 10))[:TRIED] + first
            known = _kth(self._with_bits(lead, sums, mask), k)
            rows = np.flatnonzero(most >= max(1, known)) + first
            dots = self._with_bits(rows, sums, mask)
        else:
            rows = np.flatnonzero(sums)
            dots = sums[rows]
        rows, dots = rows[keep := dots >= max(1, _kth(dots, k))], dots[keep]
        order = np.lexsort((rows, -dots))[:k]
        return self.ids[rows[order]], dots[order]


def _kth(x: np.ndarray, k: int) -> int:
    """The k-th greatest, 0 if there are fewer."""
    return int(np.partition(x, len(x) - k)[len(x) - k]) if len(x) >= k else 0


def topk(m: SparseMatrix, bounds, k: int) -> DataFrame:
    """(i, j, dot, rank): the k greatest products of each row with later rows; ties go to smaller ids."""
    small_batches(m.df.sparkSession)
    pieces, listed = _pieces(m, bounds["high"] == 1)
    total = pieces.agg(F.sum("n")).first()[0] or 0
    n = max(1, -(-total // HELD_ENTRIES), min(2 * m.df.sparkSession.sparkContext.defaultParallelism, total // SHARED_ENTRIES))
    points = pieces.select(F.explode(F.array_repeat("i", F.ceil(F.col("n") / WEIGHT).cast("int"))).alias("i"))
    cuts = sorted(set(points.agg(F.percentile_approx("i", [x / n for x in range(1, n)], 100 * n)).first()[0] or [])) if n > 1 else []
    at = F.size(F.filter(F.array(*map(F.lit, cuts)), lambda c: c < F.col("i"))) if cuts else F.lit(0)
    columns = ["i", "codes", "vals"]
    dealt = pieces.select(at.cast("int").alias("r"), *columns)
    held = dealt.select(F.col("r").alias("g"), F.lit(0).alias("side"), *columns)
    read = dealt.select(F.explode(F.sequence("r", F.lit(len(cuts)))).alias("g"), F.lit(1).alias("side"), *columns)

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
        """(g, side, i, codes, vals), the pieces of a row as one."""
        now, codes, vals = None, [], []
        for batch in batches:
            for *key, c, x in zip(*(batch.column(at).to_pylist() for at in range(5))):
                if key != now:
                    if now:
                        yield (*now, *_joined(codes, vals))
                    now, codes, vals = key, [], []
                codes.append(_unpacked(c, listed))
                vals.append(x if x is None else np.frombuffer(x, np.int64))
        if now:
            yield (*now, *_joined(codes, vals))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, gathered, lists, out = None, [], None, []

        def given() -> pa.RecordBatch:
            sizes = [len(x[1]) for x in out]
            batch = pa.RecordBatch.from_arrays([pa.array(np.repeat([x[0] for x in out], sizes).astype(np.int64)), pa.array(np.concatenate([x[1] for x in out])), pa.array(np.concatenate([x[2] for x in out]).astype(np.int64))], ["i", "j", "dot"])
            out.clear()
            return batch

        for g, side, i, codes, vals in rows(batches):
            if g != at:
                at, gathered, lists = g, [], None
            if side == 0:
                gathered.append((i, codes.astype(np.int32) if listed else codes, vals))
                continue
            if lists is None:
                lists = _Held(gathered)
            found = lists.best(i, codes, vals, k)
            if len(found[0]):
                out.append((i, *found))
            if len(out) >= _BATCH:
                yield given()
        if out:
            yield given()

    dealt = held.unionByName(read).repartition(16 * (len(cuts) + 1), "g").sortWithinPartitions("g", "side", "i")
    found = materialize(dealt.mapInArrow(lean(run), "i long, j long, dot long"), "found")
    rank = F.row_number().over(Window.partitionBy("i").orderBy(F.desc("dot"), "j"))
    return found.withColumn("rank", rank.cast("long")).filter(F.col("rank") <= k).select("i", "j", "dot", "rank")


def _joined(codes: list[np.ndarray], vals: list[np.ndarray | None]) -> tuple[np.ndarray, np.ndarray | None]:
    return np.concatenate(codes) if len(codes) > 1 else codes[0], None if vals[0] is None else np.concatenate(vals)
