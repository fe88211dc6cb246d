"""Sequential kernels on one pair of blocks: sorted triples and counters out.

The left operand comes in column form, the right one in row form, with ids of their own
corners and the sizes (rows, inner ids, columns) of the pair.
"""

from __future__ import annotations

from array import array
from collections.abc import Iterator
from heapq import heapify, heappop, heapreplace
from math import log2

import numpy as np

from semigrid.functions.blocks import Block, Triples, columns_of, rows_of, triples_of_columns, triples_of_rows
from semigrid.semiring import Semiring, semiring

Sizes = tuple[int, int, int]
NONE: Triples = (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64))
#: Longest dense array that a kernel with pointers for all ids may ask for.
DENSE_LIMIT = 1 << 26
#: Products that one call of a kernel makes at about; cells of the dense arrays of one call.
SLICE_PRODUCTS, DENSE_CELLS = 250_000, 4_000_000
#: Nanoseconds of an operation of the classical kernel, and of a step of the sort of a slice, at about.
CLASSICAL_NS, SORT_NS = 800, 25


def nothing(kind: np.dtype) -> Triples:
    return NONE[0], NONE[1], np.zeros(0, kind)


def column_major(t: Triples) -> Triples:
    i, j = t[0], t[1]
    low, least = (int(x.min()) if len(x) else 0 for x in (i, j))
    span, width = (int(x.max()) - y + 1 if len(x) else 1 for x, y in ((i, low), (j, least)))
    order = np.argsort((j - least) * span + (i - low), kind="stable") if span * width < 1 << 62 else np.lexsort((i, j))  # one key if it fits
    return t[0][order], t[1][order], t[2][order]


def combine(t: Triples, ring: Semiring) -> Triples:
    """Adds entries of one place; the result is in column-major order."""
    if not len(t[0]):
        return t
    i, j, v = column_major(t)
    head = np.flatnonzero(np.r_[True, (i[1:] != i[:-1]) | (j[1:] != j[:-1])])
    return i[head], j[head], ring.np_add.reduceat(v, head)


def joined(parts: list[Triples]) -> Triples:
    return tuple(np.concatenate(x) for x in zip(*parts))


def dense_pointers(ids: np.ndarray, n: int) -> np.ndarray:
    """One pointer for each of n ids and one more, empty or not."""
    if n > DENSE_LIMIT:
        raise ValueError(f"{n} ids are too many for a pointer each; use a hypersparse kernel")
    return np.r_[0, np.cumsum(np.bincount(ids, minlength=n))]


def _met(a: Block, b: Block) -> tuple[np.ndarray, np.ndarray]:
    """Places of the common ids among the nonempty columns of A and rows of B."""
    _, x, y = np.intersect1d(a.ids, b.ids, assume_unique=True, return_indices=True)
    return x, y


def expand_sort_compress(a: Block, b: Block, ring: Semiring, sizes: Sizes) -> tuple[Triples, dict]:
    """All products at once, then one sort: the vectorised counterpart of the heap."""
    x, y = _met(a, b)
    rows, cols = a.start[x + 1] - a.start[x], b.start[y + 1] - b.start[y]
    left = np.repeat(a.start[x] - (np.cumsum(rows) - rows), rows) + np.arange(rows.sum())  # entries of A that meet
    times, low = np.repeat(cols, rows), np.repeat(b.start[y], rows)
    at = np.repeat(low - (np.cumsum(times) - times), times) + np.arange(times.sum())
    left = np.repeat(left, times)
    out = combine((a.minor[left], b.minor[at], ring.np_mul(a.num[left], b.num[at])), ring)
    return out, {"flops": len(at), "ni": len(x)}


def heap_outer(a: Block, b: Block, ring: Semiring, sizes: Sizes) -> tuple[Triples, dict]:
    """Hypersparse kernel: meets the nonempty columns of A and rows of B, then merges their outer products.

    The product of a column and a row is a list in column-major order that is never
    made; a heap holds the head of each. Its size is the number of common ids. Neither
    operand is sorted or turned here: the forms that are stored are the ones needed.
    """
    x, y = _met(a, b)
    ai, bj = a.minor.tolist(), b.minor.tolist()
    lists = list(zip(a.start[x].tolist(), a.start[x + 1].tolist(), b.start[y].tolist(), b.start[y + 1].tolist()))
    heap = [(bj[r0], ai[c0], k, c0, r0) for k, (c0, _, r0, _) in enumerate(lists)]
    heapify(heap)
    left, right, heads = array("q"), array("q"), array("q")  # the entries of each product in order, and where each place begins
    last_i = last_j = None
    while heap:
        j, i, k, c, r = heap[0]
        if i != last_i or j != last_j:
            heads.append(len(left))
            last_i, last_j = i, j
        left.append(c)
        right.append(r)
        c0, c1, _, r1 = lists[k]
        c += 1
        if c == c1:
            c, r = c0, r + 1
        if r < r1:
            heapreplace(heap, (bj[r], ai[c], k, c, r))
        else:
            heappop(heap)
    p, q, first = (np.frombuffer(t, np.int64) if len(t) else np.zeros(0, np.int64) for t in (left, right, heads))
    value = ring.np_mul(a.num[p], b.num[q])
    out = (a.minor[p[first]], b.minor[q[first]], ring.np_add.reduceat(value, first) if len(first) else value)
    return out, {"flops": len(p), "ni": len(x), "nzc": len(a.ids), "nzr": len(b.ids)}


def accumulator_row(a: Block, b: Block, ring: Semiring, sizes: Sizes) -> tuple[Triples, dict]:
    """Classical kernel: pointers for all rows of the blocks, and a dense row that collects the products of the active one."""
    nrows, inner, ncols = sizes
    ai, ak, av = triples_of_columns(a)
    order = np.lexsort((ak, ai))
    ai, ak, av = ai[order], ak[order], av[order]
    ap, bp = dense_pointers(ai, nrows), dense_pointers(b.major(), inner)
    if ncols > DENSE_LIMIT:
        raise ValueError(f"{ncols} columns are too many for a dense row; use a hypersparse kernel")
    dense = np.zeros(ncols, ring.np_mul(av[:1], b.num[:1]).dtype if len(av) and b.nnz else np.int64)
    full = np.zeros(ncols, bool)
    parts, flops = [], 0
    for i in np.flatnonzero(np.diff(ap)):
        touched = []
        for p in range(ap[i], ap[i + 1]):
            s, e = bp[ak[p]], bp[ak[p] + 1]
            if s == e:
                continue
            cols = b.minor[s:e]
            value = ring.np_mul(np.full(e - s, av[p]), b.num[s:e])
            old = full[cols]
            dense[cols] = np.where(old, ring.np_add(dense[cols], value), value)
            full[cols] = True
            touched.append(cols[~old])
            flops += int(e - s)
        if touched:
            cols = np.concatenate(touched)
            parts.append((np.full(len(cols), i), cols, dense[cols]))
            full[cols] = False
    out = combine(joined(parts), ring) if parts else nothing(dense.dtype)
    return out, {"flops": flops, "scanned": nrows + inner + len(av), "loads": sum(len(p[0]) for p in parts)}


def _only(b: Block, keep: np.ndarray) -> Block:
    """The block without the major ids that are not kept."""
    entries = np.repeat(keep, np.diff(b.start))
    return pack_sorted(b.ids[keep], np.diff(b.start)[keep], b.minor[entries], b.num[entries])


def pack_sorted(ids: np.ndarray, counts: np.ndarray, minor: np.ndarray, num: np.ndarray) -> Block:
    return Block(ids, np.r_[0, np.cumsum(counts)], minor, num)


def outer_naive(a: Block, b: Block, ring: Semiring, sizes: Sizes) -> tuple[Triples, dict]:
    """Baseline: walks all inner ids, empty or not, and merges each rank-1 product into the result."""
    out, flops = None, 0
    for k in range(sizes[1]):
        x, y = a.ids == k, b.ids == k
        if x.any() and y.any():
            part, s = expand_sort_compress(_only(a, x), _only(b, y), ring, sizes)
            flops += s["flops"]
            out = part if out is None else combine(joined([out, part]), ring)
    return out or nothing(a.num.dtype), {"flops": flops, "scanned": sizes[1]}


def inner_pairs(a: Block, b: Block, ring: Semiring, sizes: Sizes) -> tuple[Triples, dict]:
    """Baseline: looks at each pair of a row and a column, whether they meet or not."""
    rows, cols = rows_of(triples_of_columns(a)), columns_of(triples_of_rows(b))
    found = []
    for r, i in enumerate(rows.ids):
        ak, av = rows.minor[rows.start[r] : rows.start[r + 1]], rows.num[rows.start[r] : rows.start[r + 1]]
        for c, j in enumerate(cols.ids):
            at = slice(cols.start[c], cols.start[c + 1])
            _, p, q = np.intersect1d(ak, cols.minor[at], assume_unique=True, return_indices=True)
            if len(p):
                found.append((i, j, ring.np_add.reduce(ring.np_mul(av[p], cols.num[at][q]))))
    stats = {"pairs": len(rows.ids) * len(cols.ids)}
    if not found:
        return nothing(a.num.dtype), stats
    i, j, v = zip(*found)
    return column_major((np.array(i, np.int64), np.array(j, np.int64), np.array(v))), stats


def dense_product(a: Block, b: Block, ring: Semiring, sizes: Sizes, limit: int = 4_000_000) -> tuple[Triples, dict]:
    """Baseline: dense arrays, plus-times alone, refused over ``limit`` cells; cancelled entries stay entries."""
    if ring.name != "plus_times":
        raise ValueError("the dense kernel adds and multiplies only")
    p, q = triples_of_columns(a), triples_of_rows(b)
    ri, rk, rj = np.unique(p[0]), np.union1d(a.ids, b.ids), np.unique(q[1])
    if max(len(ri), len(rj), 1) * len(rk) > limit:
        raise ValueError("too large for dense arrays")
    x, y = np.zeros((len(ri), len(rk)), p[2].dtype), np.zeros((len(rk), len(rj)), q[2].dtype)
    at = (np.searchsorted(ri, p[0]), np.searchsorted(rk, p[1])), (np.searchsorted(rk, q[0]), np.searchsorted(rj, q[1]))
    x[at[0]], y[at[1]] = p[2], q[2]
    hit, met = np.zeros(x.shape, np.float32), np.zeros(y.shape, np.float32)
    hit[at[0]], met[at[1]] = 1, 1
    if x.dtype.kind == "i" and float(np.abs(x).max(initial=0)) * float(np.abs(y).max(initial=0)) * len(rk) < 1 << 53:
        c = (x.astype(np.float64) @ y.astype(np.float64)).astype(np.result_type(x, y))  # all sums are whole numbers that doubles hold
    else:
        c = x @ y
    r, s = np.nonzero(hit @ met)
    return column_major((ri[r], rj[s], c[r, s])), {"flops": x.shape[0] * x.shape[1] * y.shape[1]}


def delayed_merge(a: Block, b: Block, ring: Semiring, sizes: Sizes, threshold: int = 4096) -> tuple[Triples, dict]:
    """Products in slices of inner ids, held as sorted runs and merged in pairs of like length."""
    runs: list[Triples] = []
    flops = merges = 0
    for part in np.array_split(np.arange(len(a.ids)), max(1, a.nnz // threshold + 1)):
        keep = np.zeros(len(a.ids), bool)
        keep[part] = True
        some = _only(a, keep)
        run, s = expand_sort_compress(some, b, ring, sizes)
        flops += s["flops"]
        runs.append(run)
        while len(runs) > 1 and len(runs[-2][0]) <= 2 * len(runs[-1][0]):
            last, before = runs.pop(), runs.pop()
            runs.append(combine(joined([before, last]), ring))
            merges += 1
    return combine(joined(runs), ring), {"flops": flops, "merges": merges}


KERNELS = {"esc": expand_sort_compress, "heap_outer": heap_outer, "accumulator_row": accumulator_row, "outer_naive": outer_naive, "inner": inner_pairs, "dense": dense_product, "delayed_merge": delayed_merge}


def operation_counts(n: int, nnz: int, flops: int, nzc: int, nzr: int, ni: int) -> tuple[float, float]:
    """Operations of the classical and of the hypersparse kernel."""
    return float(n + nnz + flops), float(nzc + nzr + flops * log2(ni) if ni > 1 else nzc + nzr + flops)


def choose_by_counts(n: int, nnz: int, flops: int, nzc: int, nzr: int, ni: int, classical_weight: float = 1.0, heap_weight: float = 1.0) -> str:
    """The kernel with fewer weighted operations, by the counts of a pair of blocks with longest side n."""
    classical, heap = operation_counts(n, nnz, flops, nzc, nzr, ni)
    return "accumulator_row" if n <= DENSE_LIMIT and classical * classical_weight <= heap * heap_weight else "heap_outer"


def choose(a: Block, b: Block, sizes: Sizes, classical_weight: float = 1.0, heap_weight: float = 1.0) -> str:
    """The kernel with fewer weighted operations for a pair of blocks; without dense arrays where there is no room for them."""
    x, y = _met(a, b)
    flops = int((np.diff(a.start)[x] * np.diff(b.start)[y]).sum())
    return choose_by_counts(max(sizes), a.nnz + b.nnz, flops, len(a.ids), len(b.ids), len(x), classical_weight, heap_weight)


def choose_for_slices(a: Block, b: Block, sizes: Sizes) -> str:
    """The kernel with less estimated time for a pair that is made in slices of bounded products.

    There the heap's vectorised counterpart has room: it sorts a slice, where the classical kernel walks entries in Python.
    """
    if choose(a, b, sizes) == "heap_outer":
        return "esc"
    x, y = _met(a, b)
    flops = int((np.diff(a.start)[x] * np.diff(b.start)[y]).sum())
    classical = (max(sizes) + a.nnz + b.nnz + flops) * CLASSICAL_NS
    return "accumulator_row" if classical <= flops * log2(max(2, min(flops, SLICE_PRODUCTS))) * SORT_NS else "esc"


def _span(b: Block, low: int, high: int) -> Block:
    """The major ids at places low to high - 1, as views."""
    at = slice(b.start[low], b.start[high])
    return Block(b.ids[low:high], b.start[low : high + 1] - b.start[low], b.minor[at], b.num[at])


def sliced(a: Block, b: Block, dense: bool = False, most: int = SLICE_PRODUCTS, cells: int = DENSE_CELLS) -> Iterator[tuple[Block, Block]]:
    """The pair in slices of inner ids that make about ``most`` products each; they are sums of the whole.

    A column of A whose products are more goes in pieces. ``dense`` slices have room in dense arrays
    of so many ``cells``.
    """
    x, y = _met(a, b)
    if not len(x):
        return
    work = np.diff(a.start)[x] * np.diff(b.start)[y]
    group = (np.cumsum(work) - work) // most
    if dense:
        side = max(len(np.unique(a.minor)), len(np.unique(b.minor)), 1)
        group = np.arange(len(x)) // max(1, cells // side)
    heads = np.flatnonzero(np.r_[True, group[1:] != group[:-1]])
    for s, e in zip(heads, np.r_[heads[1:], len(x)]):
        q = _only_places(b, y[s:e])
        if dense or e - s > 1 or work[s] <= most:
            yield _only_places(a, x[s:e]), q
            continue
        low, high = int(a.start[x[s]]), int(a.start[x[s] + 1])
        step = max(1, int(most // (work[s] // (high - low))))
        for p in range(low, high, step):
            t = min(p + step, high)
            yield Block(a.ids[x[s] : x[s] + 1], np.array([0, t - p]), a.minor[p:t], a.num[p:t]), q


def _only_places(b: Block, places: np.ndarray) -> Block:
    if places[-1] - places[0] + 1 == len(places):
        return _span(b, int(places[0]), int(places[-1]) + 1)
    keep = np.zeros(len(b.ids), bool)
    keep[places] = True
    return _only(b, keep)


def multiply_blocks(kernel: str, a: Block, b: Block, ring: Semiring, sizes: Sizes) -> tuple[Triples, dict]:
    return KERNELS[choose(a, b, sizes) if kernel == "auto" else kernel](a, b, ring, sizes)


def multiply(kernel: str, a: Triples, b: Triples, ring: str | Semiring, sizes: Sizes | None = None) -> tuple[Triples, dict]:
    """As ``multiply_blocks``, for triples; sizes are those that the ids need if not given."""
    top = lambda x: int(x.max()) + 1 if len(x) else 0
    sizes = sizes or (top(a[0]), max(top(a[1]), top(b[0])), top(b[1]))
    return multiply_blocks(kernel, columns_of(a), rows_of(b), semiring(ring), sizes)
