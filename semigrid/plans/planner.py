"""Choosing a method and an order of products from measured counts."""

from __future__ import annotations

from pyspark.sql import functions as F

from semigrid.functions.blocks import VALUES
from semigrid.matrix import SparseMatrix
from semigrid.operators.measures import flops
from semigrid.plans.multiply import BROADCAST_ENTRIES, relational, result_type


def compression_estimate(a: SparseMatrix, b: SparseMatrix, products: int, measured: int = 1_000_000) -> float:
    """Products for each entry of the result, at least 1: counted on as many rows of A as make about ``measured`` of all ``products``."""
    parts = max(1, products // measured)
    some = a.with_df(a.df.filter(F.pmod(F.xxhash64("i"), F.lit(parts)) == 0))
    made = relational(some, b, "plus_pair").df.agg(F.sum("v"), F.count(F.lit(1))).first()
    return max(1.0, float(made[0] or 1) / float(made[1] or 1))


def plan_product(a: SparseMatrix, b: SparseMatrix, cell_entries: int = 4_000_000, cell_products: int = 40_000_000, compression: float | None = None, tasks: int | None = None) -> dict:
    """Entries that each method would move, and the cheapest that fits; one aggregate comes to the driver.

    A grid is as fine as its cells need: so many entries of the operands, and products, each.
    Products meet their sums once for the relational method, after each task has combined its
    own; a grid ships each operand once for each row or column of cells and packs it before.
    """
    counts = a.df.agg(F.count(F.lit(1)).alias("na")).join(F.broadcast(b.df.agg(F.count(F.lit(1)).alias("nb")))).join(F.broadcast(flops(a, b))).first()
    na, nb, f = counts["na"], counts["nb"], counts["flops"]
    ratio = compression_estimate(a, b, f) if compression is None else compression
    tasks = tasks or max(int(a.df.sparkSession.conf.get("spark.sql.shuffle.partitions")), 1)
    q = 1
    while (na + nb) / q > cell_entries or f / (q * q) > cell_products:
        q *= 2
    combined = min(f, tasks * f / ratio)  # a task sends each place once
    ships = {
        "relational": na + nb + combined,
        "fused_grid": (1 + q) * (na + nb),
        "panel_grid": (1 + q) * (na + nb) + min(f, q * f / ratio),
        "rotating_grid": (1 + 2 * q) * (na + nb) + min(f, q * f / ratio),
    }
    if type(result_type(a, b, "plus_times")) not in VALUES:
        ships = {"relational": ships["relational"]}
    if nb <= BROADCAST_ENTRIES:
        executors = max(1, int(a.df.sparkSession.sparkContext.defaultParallelism) // 4)
        ships["block_row_replicated"] = executors * nb + combined
    order = ("relational", "block_row_replicated", "fused_grid", "panel_grid", "rotating_grid")
    method = min(ships, key=lambda m: (ships[m], order.index(m)))
    options = {"relational": {"salt": "auto"}, "block_row_replicated": {}, "rotating_grid": {"q": q}}.get(method, {"grid": (q, q)})
    return {"method": method, "options": options, "ships": ships, "grid": (q, q), "flops": f, "nnz": (na, nb), "compression": ratio}


def chain_order(sizes: list[tuple[int, int]], nnz: list[int]) -> tuple[float, str]:
    """Cheapest parenthesisation by estimated products, over intervals of the chain.

    A product of X (m by k) and Y (k by n) is taken to cost nnz(X) * nnz(Y) / k, and to have
    that many entries, if they fit.
    """
    n = len(nnz)
    best: dict[tuple[int, int], tuple[float, float, str]] = {(x, x): (0.0, float(nnz[x]), f"M{x}") for x in range(n)}
    for length in range(2, n + 1):
        for lo in range(n - length + 1):
            hi = lo + length - 1
            options = []
            for mid in range(lo, hi):
                (c1, e1, s1), (c2, e2, s2) = best[lo, mid], best[mid + 1, hi]
                work = e1 * e2 / max(1, sizes[mid][1])
                options.append((c1 + c2 + work, min(work, float(sizes[lo][0] * sizes[hi][1])), f"({s1}*{s2})"))
            best[lo, hi] = min(options)
    return best[0, n - 1][0], best[0, n - 1][2]


def chain(matrices: list[SparseMatrix], ring: str = "plus_times") -> SparseMatrix:
    """Product of a chain in the estimated best order, as one plan."""
    counts = [m.df.count() for m in matrices]
    _, text = chain_order([(m.nrows, m.ncols) for m in matrices], counts)
    stack: list[SparseMatrix] = []
    for token in text.replace("(", " ( ").replace(")", " ) ").replace("*", " ").split():
        if token == ")":
            y, x = stack.pop(), stack.pop()
            stack.append(relational(x, y, ring))
        elif token != "(":
            stack.append(matrices[int(token[1:])])
    return stack[0]
