"""Queries on formats, kernels, product methods and cost measures, with SQL of the same rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semigrid.matrix import SparseMatrix, from_triples
from semigrid.operators import measures as M
from semigrid.operators import structure as S
from semigrid.plans import multiply as P
from semigrid.plans.planner import chain, chain_order
from semigrid.plans.scratch import materialize
from semigrid.semiring import SEMIRINGS, numeric_semirings
from semigrid.sources import connectors
from semigrid.sources import generators as G
from semigrid.sources.fixtures import SQL, fixture, stored
from semigrid.sources.tables import table


#: Entries of the right operand that are at every worker at a time.
SLAB_ENTRIES = 1_500_000


def t_sql(sql: str) -> str:
    return f"SELECT j AS i, i AS j, v FROM ({sql}) t"


def product_sql(a: str, b: str, ring: str = "plus_times", extra: str = "") -> str:
    s = SEMIRINGS[ring]
    return f"SELECT a.i, b.j, CAST({s.sql_add.format(s.sql_mul)} AS BIGINT) AS v FROM ({a}) a JOIN ({b}) b ON a.j = b.i {extra} GROUP BY a.i, b.j"


OP, OPT, PS = SQL["OP"], t_sql(SQL["OP"]), SQL["PS"]
COPURCHASE = product_sql(OPT, OP)
N_PART, N_ORDER, N_SUPP = "(SELECT max(p_partkey) + 1 FROM part)", "(SELECT max(o_orderkey) + 1 FROM orders)", "(SELECT max(s_suppkey) + 1 FROM supplier)"


def _cut(column: str, n: str, q: int) -> str:
    return f"({column} // (({n} + {q - 1}) // {q}))"


def _op(s, d) -> tuple[SparseMatrix, SparseMatrix]:
    b = fixture(s, d, "OP")
    return b.T, b


def copurchase(s, d) -> DataFrame:
    """Parts bought together: the product of part by order with order by part."""
    a, b = _op(s, d)
    return P.relational(a, b).df


def _on_op(f):
    return lambda s, d: f(*_op(s, d)).df


def _on_stored_op(f):
    """For methods that read their operands more than once."""

    def run(s, d) -> DataFrame:
        b = stored(fixture(s, d, "OP"))
        return f(b.T, b).df

    return run


def _named(rows: list[tuple[int, DataFrame]], column: str) -> DataFrame:
    out = None
    for k, df in rows:
        df = df if column in df.columns else df.withColumn(column, F.lit(k).cast("long"))
        out = df if out is None else out.unionByName(df)
    return out


def _each(m: SparseMatrix, measure, qs: tuple[int, ...]) -> DataFrame:
    """A measure for each grid, of a matrix that is written once."""
    m = stored(m)
    return _named([(q, measure(m, q)) for q in qs], "q")


def _pairs(a: SparseMatrix, b: SparseMatrix, measure, qs: tuple[int, ...]) -> DataFrame:
    a, b = stored(a), stored(b)
    return _named([(q, measure(a, b, q)) for q in qs], "q")


def _chosen(s, d) -> DataFrame:
    """The kernel that the chooser takes, and how often, over the pairs of blocks of two grids."""
    b = stored(fixture(s, d, "OP"))
    a = b.T
    return _named([(q, P.kernel_choices(a, b, q)) for q in (1, 4)], "q")


def _chosen_sql(q: int) -> str:
    kw = f"(({N_ORDER} + {q - 1}) // {q})"
    n = f"greatest({kw}, ({N_PART} + {q - 1}) // {q})"
    block = lambda sql, o, k, on: f"SELECT {o}, {k} // {kw} AS bk, count(*) AS nnz, count(DISTINCT {k}) AS nz FROM (SELECT *, {_cut(on, N_PART, q)} AS {o} FROM ({sql}) z) t GROUP BY 1, 2"
    pairs = _kernel_stats_sql(q)
    ops = f"SELECT {n} + x.nnz + y.nnz + p.pushes AS classical, x.nz + y.nz + p.pushes * CASE WHEN p.ni > 1 THEN log2(p.ni) ELSE 1 END AS heap FROM ({pairs}) p JOIN ({block(OPT, 'bi', 'j', 'i')}) x ON x.bi = p.bi AND x.bk = p.bk JOIN ({block(OP, 'bj', 'i', 'j')}) y ON y.bj = p.bj AND y.bk = p.bk"
    return f"SELECT CAST({q} AS BIGINT) AS q, CASE WHEN classical <= heap THEN 'accumulator_row' ELSE 'heap_outer' END AS kernel, count(*) AS pairs FROM ({ops}) o GROUP BY 2"


def _pointers_sql(sql: str, n: str) -> str:
    return f"WITH c AS (SELECT j, count(*) AS n FROM ({sql}) t GROUP BY j) SELECT r.j, CAST(coalesce(sum(n) OVER (ORDER BY r.j ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS ptr FROM range(0, {n} + 1) r(j) LEFT JOIN c ON c.j = r.j"


def _compressed_sql(sql: str) -> str:
    return f"SELECT j AS jc, CAST(sum(count(*)) OVER (ORDER BY j) - count(*) AS BIGINT) AS cp, count(*) AS n FROM ({sql}) t GROUP BY j"


def _cells_sql(q: int, a: str = OPT, b: str = OP, rows: str = N_PART, inner: str = N_ORDER, cols: str = N_PART) -> str:
    da = f"SELECT j AS k, {_cut('i', rows, q)} AS bi, count(*) AS da FROM ({a}) t GROUP BY 1, 2"
    db = f"SELECT i AS k, {_cut('j', cols, q)} AS bj, count(*) AS db FROM ({b}) t GROUP BY 1, 2"
    return f"SELECT bi, bj, {_cut('a.k', inner, q)} AS bk, CAST(sum(da * db) AS BIGINT) AS flops FROM ({da}) a JOIN ({db}) b ON a.k = b.k GROUP BY 1, 2, 3"


def _overall_sql(q: int, cells: str | None = None) -> str:
    return f"SELECT CAST({q} AS BIGINT) AS q, round(CAST(max(f) * {q * q} AS DOUBLE) / sum(f), 6) AS imbalance FROM (SELECT bi, bj, sum(flops) AS f FROM ({cells or _cells_sql(q)}) c GROUP BY 1, 2) t"


def _stage_sql(q: int, cells: str | None = None) -> str:
    return f"SELECT CAST({q} AS BIGINT) AS q, (bk - bi - bj + {2 * q}) % {q} AS stage, round(CAST(max(flops) * {q * q} AS DOUBLE) / sum(flops), 6) AS imbalance FROM ({cells or _cells_sql(q)}) c GROUP BY 2"


def _penalty_sql(q: int, cells: str | None = None) -> str:
    each = f"SELECT o.imbalance AS overall, s.mean AS per_stage FROM ({_overall_sql(q, cells)}) o, (SELECT round(avg(imbalance), 6) AS mean FROM ({_stage_sql(q, cells)}) z) s"
    return f"SELECT overall, per_stage, round(100 * (overall - 1), 3) AS async_percent, round(100 * (per_stage - 1), 3) AS sync_percent FROM ({each}) e"


#: Scale and grid of the imbalance experiment on the scale-free input, and the seeds of its relabellings.
RMAT_SCALE, RMAT_GRID, RELABELLINGS = 10, 16, (1, 2, 3)


def _rmat_relabelled(s, seed: int) -> SparseMatrix:
    m = G.rmat(s, RMAT_SCALE)
    p = G.random_permutation(s, m.nrows, seed)
    return S.permute_rows_by(S.permute_by(m, p), p)


def _rmat_relabelled_sql(seed: int) -> str:
    p = G.random_permutation_sql(1 << RMAT_SCALE, seed)
    return f"SELECT p.j AS i, r.j AS j, m.v FROM ({G.rmat_sql(RMAT_SCALE)}) m JOIN ({p}) p ON p.i = m.i JOIN ({p}) r ON r.i = m.j"


def _rmat_cells_sql(seed: int | None) -> str:
    m, n = G.rmat_sql(RMAT_SCALE) if seed is None else _rmat_relabelled_sql(seed), str(1 << RMAT_SCALE)
    return _cells_sql(RMAT_GRID, m, m, n, n, n)


def _imbalance_rmat(s, d) -> DataFrame:
    """Overall and mean per-stage imbalance of the scale-free square on 256 workers, without relabelling (seed 0) and with random ones."""
    out = None
    for seed in (None, *RELABELLINGS):
        m = stored(G.rmat(s, RMAT_SCALE) if seed is None else _rmat_relabelled(s, seed))
        cells = materialize(M.cell_flops(m, m, RMAT_GRID), "cells")
        row = M.sync_penalty(m, m, RMAT_GRID, cells).select(F.lit(seed or 0).cast("long").alias("seed"), "overall", "per_stage", "async_percent", "sync_percent")
        out = row if out is None else out.unionByName(row)
    return out


def _imbalance_rmat_sql() -> str:
    return _union([f"SELECT CAST({seed or 0} AS BIGINT) AS seed, * FROM ({_penalty_sql(RMAT_GRID, _rmat_cells_sql(seed))}) p" for seed in (None, *RELABELLINGS)])


#: The pairs of the kernel experiment: scale-free squared, scale-free by permutation, uniform squared, relabelled mesh squared, and the mesh as it is.
KERNEL_GRIDS = (1, 2, 4, 8, 16)
_MESH = 10


def _kernel_inputs(s) -> dict[str, tuple[SparseMatrix, SparseMatrix]]:
    r, e, g = G.rmat(s, 10), G.erdos_renyi(s, 1024, 8), G.grid3d(s, _MESH)
    p = G.random_permutation(s, g.nrows, 1)
    mixed = S.permute_rows_by(S.permute_by(g, p), p)
    return {"scale_free": (r, r), "scale_free_by_permutation": (r, G.random_permutation(s, r.nrows, 1)), "uniform": (e, e), "mesh_relabelled": (mixed, mixed), "mesh": (g, g)}


def _kernel_inputs_sql() -> dict[str, tuple[str, str, int]]:
    r, e, g = G.rmat_sql(10), G.tall_skinny_sql(1024, 1024, 8), G.grid3d_sql(_MESH)
    p = G.random_permutation_sql(_MESH**3, 1)
    mixed = f"SELECT p.j AS i, r.j AS j, m.v FROM ({g}) m JOIN ({p}) p ON p.i = m.i JOIN ({p}) r ON r.i = m.j"
    return {"scale_free": (r, r, 1024), "scale_free_by_permutation": (r, G.random_permutation_sql(1024, 1), 1024), "uniform": (e, e, 1024), "mesh_relabelled": (mixed, mixed, _MESH**3), "mesh": (g, g, _MESH**3)}


def _kernel_experiment(name: str):
    def run(s, d) -> DataFrame:
        a, b = _kernel_inputs(s)[name]
        a, b = stored(a), stored(b)
        return _named([(q, M.kernel_op_counts(a, b, q)) for q in KERNEL_GRIDS], "q")

    return run


def _accumulator_sql(slabs: int) -> str:
    rows = f"SELECT {_cut('a.j', N_ORDER, slabs)} AS stage, a.i, sum(db) AS n FROM ({OPT}) a JOIN (SELECT i AS k, count(*) AS db FROM ({OP}) t GROUP BY 1) b ON a.j = b.k GROUP BY 1, 2"
    return f"SELECT stage, count(*) AS loads, CAST(sum(n) AS BIGINT) AS products FROM ({rows}) r GROUP BY 1"


def _worker_sql(q: int) -> str:
    x, y = _blocks_sql(OPT, N_PART, N_ORDER, q, q), _blocks_sql(OP, N_ORDER, N_PART, q, q)
    return f"""SELECT w.bi, w.bj, CAST(coalesce((SELECT sum(nnz) FROM ({x}) x WHERE x.bi = w.bi AND x.bj <> w.bj), 0) + coalesce((SELECT sum(nnz) FROM ({y}) y WHERE y.bj = w.bj AND y.bi <> w.bi), 0) AS BIGINT) AS entries
FROM (SELECT a.k AS bi, b.k AS bj FROM range({q}) a(k), range({q}) b(k)) w"""


def _comm_sql(p: int, q: int) -> str:
    slab = f"SELECT r.k, (SELECT count(*) FROM ({OP}) t WHERE {_cut('i', N_ORDER, p)} <> r.k) AS entries FROM range({p}) r(k)"
    line = lambda m, k, n, sql: f"SELECT '{m}' AS method, CAST({k} AS BIGINT) AS messages, CAST(sum(entries) AS BIGINT) AS entries, CAST(max(entries) AS BIGINT) AS most, round(CAST(max(entries) * {n} AS DOUBLE) / sum(entries), 6) AS skew FROM ({sql}) w"
    return _union([line("block_row", p * (p - 1), p, slab), line("rotating_grid", 2 * q * q * (q - 1), q * q, _worker_sql(q)), line("panel_grid", 2 * q * q * (q - 1), q * q, _worker_sql(q))])


def _store_round_trip(s, d, name: str, form: str) -> DataFrame:
    """Entries after they were packed in doubly compressed blocks, written, and unpacked."""
    return P.unpack_blocks(P.store_blocks(fixture(s, d, name), 3, 4, form), form).df


def _compressed_round_trip(m: SparseMatrix) -> DataFrame:
    return S.from_compressed(*S.compressed_entries(m), m.nrows, m.ncols).df


def _special(s) -> DataFrame:
    """The scale-free matrix with rows scaled by a diagonal one, and every third row taken by a selector; nothing is added by a zero one."""
    m = G.rmat(s, 8)
    scale = S.diagonal(s.range(256).select("id", (F.col("id") % 5 + 1).alias("v")), 256)
    third = S.selector(s.range(0, 256, 3).select((F.col("id") / 3).cast("long").alias("new"), F.col("id").alias("old")), 86, 256)
    return P.relational(third, S.add(P.relational(scale, m), S.zero(s, 256, 256))).df


def _doubles(m: SparseMatrix) -> SparseMatrix:
    return m.with_df(m.df.withColumn("v", F.col("v") * 0.5))


def _halves(f):
    """A product of matrices of halves, which are exact as doubles."""
    return _on_stored_op(lambda a, b: f(_doubles(a), _doubles(b)))


def _union(parts: list[str]) -> str:
    return " UNION ALL ".join(f"SELECT * FROM ({p}) u" for p in parts)


def _storage_sql(q: int) -> str:
    n = _blocks_sql(OPT, N_PART, N_ORDER, q, q)
    return f"SELECT CAST({q} AS BIGINT) AS q, CAST({q * q} * ((({N_ORDER} + {q - 1}) // {q}) + 1) + 2 * sum(nnz) AS BIGINT) AS csc_words, CAST(2 * sum(nzc) + count(*) + 2 * sum(nnz) AS BIGINT) AS dcsc_words FROM ({n}) b"


def _blocks_sql(sql: str, nr: str, nc: str, r: int, c: int) -> str:
    return f"SELECT {_cut('i', nr, r)} AS bi, {_cut('j', nc, c)} AS bj, count(*) AS nnz, count(DISTINCT i) AS nzr, count(DISTINCT j) AS nzc FROM ({sql}) t GROUP BY 1, 2"


def _hyper_sql(q: int) -> str:
    w = f"(({N_ORDER} + {q - 1}) // {q})"
    return f"SELECT CAST({q} AS BIGINT) AS q, round(CAST(sum(nnz) AS DOUBLE) / ({q * q} * {w}), 6) AS ratio, round(CAST(count(*) FILTER (nnz < {w}) + {q * q} - count(*) AS DOUBLE) / {q * q}, 6) AS hyper_share FROM ({_blocks_sql(OPT, N_PART, N_ORDER, q, q)}) b"


def _ops_sql(q: int, a: str = OPT, b: str = OP, outer: str = N_PART, inner: str = N_ORDER) -> str:
    kw = f"(({inner} + {q - 1}) // {q})"
    da = f"SELECT {_cut('i', outer, q)} AS bi, j AS k, count(*) AS da FROM ({a}) t GROUP BY 1, 2"
    db = f"SELECT i AS k, {_cut('j', outer, q)} AS bj, count(*) AS db FROM ({b}) t GROUP BY 1, 2"
    return f"""SELECT CAST({q} AS BIGINT) AS q, CAST(f AS BIGINT) AS flops, CAST({q**3} * {kw} + {q} * (na + nb) + f AS BIGINT) AS classical_ops, CAST(round({q} * (nzc + nzr) + m, 0) AS BIGINT) AS heap_ops
FROM (SELECT sum(flops) AS f, sum(flops * log2(ni)) AS m FROM (SELECT bi, bj, a.k // {kw} AS bk, sum(da * db) AS flops, count(*) AS ni FROM ({da}) a JOIN ({db}) b ON a.k = b.k GROUP BY 1, 2, 3) p),
(SELECT count(*) AS nzc, sum(da) AS na FROM ({da}) x), (SELECT count(*) AS nzr, sum(db) AS nb FROM ({db}) y)"""


TREND_GRIDS = (1, 2, 4, 8)


def _trend(a: SparseMatrix, b: SparseMatrix) -> DataFrame:
    """Average dimension, entries and products of a pair of blocks, as the grid gets finer."""
    a, b, rows = stored(a), stored(b), []
    for q in TREND_GRIDS:
        cells = M.cell_flops(a, b, q)
        nnz = M.block_stats(a, q, q).agg(F.sum("nnz").alias("nnz"))
        f = cells.agg(F.sum("flops").alias("flops")).join(F.broadcast(nnz))
        rows.append((q, f.select(F.lit(q).cast("long").alias("q"), F.lit(-(-a.ncols // q)).cast("long").alias("avg_dim"), F.round(F.col("nnz") / (q * q), 4).alias("avg_nnz"), F.round(F.col("flops") / (q**3), 4).alias("avg_flops"))))
    return _named(rows, "q")


def _trend_sql(q: int, m: str = OP, inner: str = N_ORDER, cells: str | None = None) -> str:
    return f"SELECT CAST({q} AS BIGINT) AS q, CAST(({inner} + {q - 1}) // {q} AS BIGINT) AS avg_dim, round(CAST((SELECT count(*) FROM ({m}) t) AS DOUBLE) / {q * q}, 4) AS avg_nnz, round(CAST(sum(flops) AS DOUBLE) / {q**3}, 4) AS avg_flops FROM ({cells or _cells_sql(q)}) c"


def _trend_rmat_sql(q: int) -> str:
    m, n = _rmat_relabelled_sql(1), str(1 << RMAT_SCALE)
    return _trend_sql(q, m, n, _cells_sql(q, m, m, n, n, n))


def _rings_on_halves(s, d) -> DataFrame:
    """Number, least and greatest of the entries of the successor graph's square over each semiring, on halves as doubles."""
    m = stored(_doubles(fixture(s, d, "SUCC")))
    return P.rings_summary(m, m, [name for name in numeric_semirings() if name != "xor_and"], SLAB_ENTRIES)  # that one is of bits


def _rings_sql() -> str:
    half = f"SELECT i, j, CAST(v AS DOUBLE) / 2 AS v FROM ({SQL['SUCC']}) h"
    rows = []
    for name in numeric_semirings():
        if name != "xor_and":
            r = SEMIRINGS[name]
            rows.append(f"SELECT '{name}' AS ring, count(*) AS n, min(v) AS least, max(v) AS greatest FROM (SELECT CAST({r.sql_add.format(r.sql_mul)} AS DOUBLE) AS v FROM ({half}) a JOIN ({half}) b ON a.j = b.i GROUP BY a.i, b.j) t")
    return _union(rows)


def _small(s, d) -> tuple[SparseMatrix, SparseMatrix]:
    return fixture(s, d, "RN"), fixture(s, d, "NR")


def _selectors(s, n: int) -> tuple[DataFrame, DataFrame]:
    """Every third id below n, renumbered."""
    r = s.range(0, n, 3).select(F.col("id").alias("old"), F.call_function("div", F.col("id"), F.lit(3).cast("long")).alias("new"))
    return r, r


def _third(s, d) -> DataFrame:
    m = fixture(s, d, "SUCC")
    return S.submatrix(m, *_selectors(s, m.nrows)).df


def _delta(s, d) -> DataFrame:
    whole = fixture(s, d, "OP")
    old, new = whole.with_df(whole.df.filter("i % 5 <> 0")), whole.with_df(whole.df.filter("i % 5 = 0"))
    before = P.relational(old.T, old)
    return P.delta_product(old.T, old, new.T, new, before).df


def _kernel_stats(s, d) -> DataFrame:
    """What the hypersparse kernel counted itself: heap pops, common ids and nonempty ids of each pair of blocks."""
    a, b = _op(s, d)
    return P.pair_stats(a, b, 4).filter("ni > 0").select(F.col("ci").alias("bi"), F.col("cj").alias("bj"), "bk", F.col("flops").alias("pushes"), "ni", "nzc", "nzr")


def _kernel_stats_sql(q: int = 4) -> str:
    kw = f"(({N_ORDER} + {q - 1}) // {q})"
    da = f"SELECT {_cut('i', N_PART, q)} AS bi, j AS k, count(*) AS da FROM ({OPT}) t GROUP BY 1, 2"
    db = f"SELECT i AS k, {_cut('j', N_PART, q)} AS bj, count(*) AS db FROM ({OP}) t GROUP BY 1, 2"
    pairs = f"SELECT bi, bj, a.k // {kw} AS bk, CAST(sum(da * db) AS BIGINT) AS pushes, count(*) AS ni FROM ({da}) a JOIN ({db}) b ON a.k = b.k GROUP BY 1, 2, 3"
    nz = lambda d, o: f"SELECT {o}, k // {kw} AS bk, count(*) AS n FROM ({d}) t GROUP BY 1, 2"
    return f"SELECT p.*, x.n AS nzc, y.n AS nzr FROM ({pairs}) p JOIN ({nz(da, 'bi')}) x ON x.bi = p.bi AND x.bk = p.bk JOIN ({nz(db, 'bj')}) y ON y.bj = p.bj AND y.bk = p.bk"


def _median(s, d) -> DataFrame:
    """Median imbalance over random relabellings of the parts."""
    a, b = map(stored, _op(s, d))
    runs = []
    for seed in RELABELLINGS:
        p = stored(G.random_permutation(s, a.nrows, seed))
        runs.append((seed, M.imbalance(S.permute_rows_by(a, p), S.permute_by(b, p), 4)[0]))
    return _named(runs, "seed").agg(F.round(F.percentile("imbalance", F.lit(0.5)), 6).alias("median_imbalance"))


def _median_sql() -> str:
    def one(seed: int) -> str:
        p = G.random_permutation_sql(N_PART, seed)
        a, b = f"SELECT p.j AS i, m.j, m.v FROM ({OPT}) m JOIN ({p}) p ON p.i = m.i", f"SELECT m.i, p.j AS j, m.v FROM ({OP}) m JOIN ({p}) p ON p.i = m.j"
        return _overall_sql(4, _cells_sql(4, a, b))

    return f"SELECT round(quantile_cont(imbalance, 0.5), 6) AS median_imbalance FROM ({_union([one(s) for s in RELABELLINGS])}) m"


def _argmin(s, d) -> DataFrame:
    """Least sum with the inner id that gives it."""
    m = fixture(s, d, "NN")
    through = m.with_df(m.df.select("i", "j", F.struct("v", F.col("j").alias("k")).alias("v")))
    return P.relational(through, through, "argmin").df.select("i", "j", "v.v", "v.k")


def _chain(s, d) -> DataFrame:
    return chain([fixture(s, d, "RN"), fixture(s, d, "NR"), fixture(s, d, "CP"), fixture(s, d, "PS")]).df


_CHAIN_SQL = product_sql(product_sql(product_sql(SQL["RN"], SQL["NR"]), SQL["CP"]), PS)


def _chain_order(s, d) -> DataFrame:
    """The order that counts of the stored entries suggest; four counts come to the driver."""
    parts = [fixture(s, d, name) for name in ("RN", "NR", "CP", "PS")]
    cost, order = chain_order([(m.nrows, m.ncols) for m in parts], [m.df.count() for m in parts])
    return s.range(1).select(F.lit(order).alias("plan"), F.lit(round(cost)).cast("long").alias("cost"))


def _tall_cost(s, d) -> DataFrame:
    a, b = fixture(s, d, "OP"), fixture(s, d, "PS")
    n = M.flops(a, b).join(F.broadcast(a.df.agg(F.count(F.lit(1)).alias("nnz_a")))).join(F.broadcast(b.df.agg(F.count(F.lit(1)).alias("nnz_b"))))
    return n.select(F.col("flops").alias("work"), (F.col("nnz_a") + F.col("nnz_b")).alias("memory"), ((F.col("nnz_a") + F.col("nnz_b")) * 4).alias("bandwidth"))


def _panel_flops(s, d) -> DataFrame:
    a, b = map(stored, _op(s, d))
    out = [(p, M.degrees(a, b).groupBy(M.cut("k", a.ncols, p).alias("stage")).agg(F.sum(F.col("da") * F.col("db")).cast("long").alias("flops"))) for p in (2, 8)]
    return _named(out, "panels")


def _panel_sql(p: int) -> str:
    return f"SELECT CAST({p} AS BIGINT) AS panels, {_cut('k', N_ORDER, p)} AS stage, CAST(sum(n * n) AS BIGINT) AS flops FROM (SELECT i AS k, count(*) AS n FROM ({OP}) t GROUP BY 1) g GROUP BY 2"


def queries() -> dict:
    ring = lambda r: lambda s, d: P.relational(fixture(s, d, "NN"), fixture(s, d, "NN"), r).df
    out = {
        "copurchase": copurchase,
        "triples_build": lambda s, d: from_triples(table(s, d, "lineitem"), "l_orderkey", "l_partkey", F.col("l_quantity").cast("long"), (1 << 40, 1 << 40)).df,
        "csc_pointers": lambda s, d: S.column_pointers(fixture(s, d, "OP")),
        "csr_pointers": lambda s, d: S.column_pointers(fixture(s, d, "OP").T),
        "dcsc_columns": lambda s, d: S.compressed_columns(fixture(s, d, "OP")),
        "dcsr_rows": lambda s, d: S.compressed_columns(fixture(s, d, "OP").T),
        "dcsc_aux": lambda s, d: S.chunk_index(fixture(s, d, "OP").T),
        "column_lookup": lambda s, d: S.columns(fixture(s, d, "OP"), [3, 5, 8, 13]).df,
        "transpose": lambda s, d: fixture(s, d, "PS").T.df,
        "nonempty_ids": lambda s, d: S.nonempty(fixture(s, d, "OP")),
        "inner_intersection": lambda s, d: S.inner_intersection(fixture(s, d, "OP"), fixture(s, d, "PS")),
        "block_row_stats": lambda s, d: M.block_stats(fixture(s, d, "OP"), 8, 1),
        "grid_block_stats": lambda s, d: M.block_stats(fixture(s, d, "OP"), 3, 4),
        "split_block_stats": lambda s, d: M.block_stats(fixture(s, d, "OP"), 4, 8).withColumn("half", F.col("bj") % 2),
        "permute_symmetric": lambda s, d: S.permute(fixture(s, d, "SUCC"), 7, 3).df,
        "submatrix_index": _third,
        "matrix_add": lambda s, d: S.add(fixture(s, d, "SUCC"), fixture(s, d, "SUCC").T).df,
        "mask_ops": lambda s, d: S.mask(fixture(s, d, "SUCC"), fixture(s, d, "SUCC").T).df.withColumn("kept", F.lit(True)).unionByName(S.mask(fixture(s, d, "SUCC"), fixture(s, d, "SUCC").T, False).df.withColumn("kept", F.lit(False))),
        "emult_ops": lambda s, d: S.emult(fixture(s, d, "SUCC"), fixture(s, d, "SUCC").T).df,
        "row_reduce": lambda s, d: S.reduce(fixture(s, d, "OP"), "i"),
        "matrix_trace": lambda s, d: S.trace(P.relational(*_op(s, d))),
        "product_outer": _on_stored_op(lambda a, b: P.single_block(a, b, "esc", cells=1)),
        "product_salted": _on_op(lambda a, b: P.relational(a, b, salt=4)),
        "product_split": _on_op(lambda a, b: P.relational(a, b, salt="auto", most=40)),
        "product_masked": lambda s, d: P.relational(fixture(s, d, "SUCC"), fixture(s, d, "SUCC"), mask=fixture(s, d, "SUCC").df).df,
        "product_inner": lambda s, d: P.single_block(*_small(s, d), "inner").df,
        "kernel_outer_naive": lambda s, d: P.single_block(*_small(s, d), "outer_naive").df,
        "product_row": _on_op(P.row_by_row),
        "product_column": _on_op(P.column_by_column),
        "kernel_accumulator": _on_stored_op(lambda a, b: P.single_block(a, b, "accumulator_row")),
        "kernel_heap": _on_stored_op(lambda a, b: P.single_block(a, b, "heap_outer")),
        "kernel_heap_dual": lambda s, d: P.square_dual(P.dual_blocks(stored(fixture(s, d, "SUCC")), 2)).df,
        "dcsc_roundtrip": lambda s, d: _store_round_trip(s, d, "OP", "columns"),
        "dcsr_roundtrip": lambda s, d: _store_round_trip(s, d, "PS", "rows"),
        "csc_roundtrip": lambda s, d: _compressed_round_trip(fixture(s, d, "OP")),
        "csr_roundtrip": lambda s, d: _compressed_round_trip(fixture(s, d, "PS").T),
        "column_by_index": lambda s, d: connectors.fetch_columns(P.store_blocks(fixture(s, d, "OP"), 2, 3), [3, 5, 8, 13]),
        "special_matrices": lambda s, d: _special(s),
        "product_double": _halves(lambda a, b: P.fused_grid(a, b, split=2, kernel="heap_outer")),
        "product_double_relational": _halves(lambda a, b: P.relational(a, b, salt="auto", most=2000)),
        "product_wide_ids": lambda s, d: P.fused_grid(m := stored(fixture(s, d, "BIP")), m, kernel="auto").df.groupBy("i").agg(F.count(F.lit(1)).alias("nnz"), F.sum("v").cast("long").alias("walks")),
        "accumulator_traffic": lambda s, d: M.accumulator_traffic(*_op(s, d), 4),
        "worker_volume": lambda s, d: M.worker_volume(*_op(s, d), 4),
        "sync_penalty": lambda s, d: M.sync_penalty(*_op(s, d), 8),
        "imbalance_rmat": _imbalance_rmat,
        "kernel_heap_stats": _kernel_stats,
        "kernel_delayed_merge": _on_stored_op(lambda a, b: P.single_block(a, b, "delayed_merge")),
        "kernel_esc": _on_stored_op(lambda a, b: P.single_block(a, b, "esc")),
        "kernel_dense": lambda s, d: P.single_block((m := stored(fixture(s, d, "OS"))).T, m, "dense").df,
        "kernel_auto": _on_stored_op(lambda a, b: P.single_block(a, b, "auto")),
        "kernel_choice": _chosen,
        "semiring_argmin": _argmin,
        "product_block_row": _on_stored_op(lambda a, b: P.block_row(a, b, limit=SLAB_ENTRIES, more=True)),
        "product_broadcast_b": _on_stored_op(lambda a, b: P.block_row_replicated(a, b, limit=SLAB_ENTRIES, turns=True)),
        "product_rotating": _on_stored_op(lambda a, b: P.rotating_grid(a, b, q=3)),
        "grid_shift": lambda s, d: P.shift(P.with_blocks(fixture(s, d, "PS"), 4, 4), "bj", 1, 4).select("i", "j", "v", F.col("bi").cast("long").alias("bi"), F.col("bj").cast("long").alias("bj")),
        "product_panel": _on_stored_op(lambda a, b: P.panel_grid(a, b, grid=(2, 3))),
        "panel_stage_flops": _panel_flops,
        "product_panel_barrier": _on_stored_op(lambda a, b: P.panel_grid(a, b, barrier=True)),
        "product_eager_merge": _on_stored_op(lambda a, b: P.panel_grid(a, b, eager=True)),
        "product_fused": _on_stored_op(lambda a, b: P.fused_grid(a, b, grid=(3, 2))),
        "product_fused_split": _on_stored_op(lambda a, b: P.fused_grid(a, b, split=2)),
        "product_two_level": _on_stored_op(P.two_level_grid),
        "product_auto": _on_op(lambda a, b: P.spgemm(a, b)),
        "triple_product": _chain,
        "chain_order": _chain_order,
        "product_delta": _delta,
        "nnz_profile": lambda s, d: S.reduce(fixture(s, d, "OP"), "j", "plus_times").join(fixture(s, d, "OP").df.groupBy(F.col("j").alias("id")).agg(F.count(F.lit(1)).alias("nnz")), "id"),
        "flops_count": lambda s, d: M.flops(*_op(s, d)),
        "inner_stats": lambda s, d: M.inner_stats(fixture(s, d, "OP"), fixture(s, d, "PS")),
        "compression_ratio": lambda s, d: M.flops(*_op(s, d)).join(F.broadcast(P.relational(*_op(s, d)).df.agg(F.count(F.lit(1)).alias("nnz_c")))).select("flops", "nnz_c", F.round(F.col("flops") / F.col("nnz_c"), 6).alias("ratio")),
        "storage_words": lambda s, d: _each(fixture(s, d, "OP").T, M.storage_words, (1, 4, 16)),
        "hypersparsity": lambda s, d: _each(fixture(s, d, "OP").T, M.hypersparsity, (1, 2, 4, 8)),
        "kernel_op_counts": lambda s, d: _pairs(*_op(s, d), M.kernel_op_counts, (1, 2, 8)),
        "block_trend": lambda s, d: _trend(*_op(s, d)),
        "block_trend_rmat": lambda s, d: _trend(*[_rmat_relabelled(s, 1)] * 2),
        "semirings_on_doubles": _rings_on_halves,
        "imbalance_overall": lambda s, d: _pairs(*_op(s, d), lambda a, b, q: M.imbalance(a, b, q)[0], (4, 8, 16)),
        "imbalance_stage": lambda s, d: _pairs(*_op(s, d), lambda a, b, q: M.imbalance(a, b, q)[1], (4, 8)),
        "imbalance_median": _median,
        "diag_block_flops": lambda s, d: M.cell_flops(*_op(s, d), 4).groupBy("bi", "bj").agg(F.sum("flops").cast("long").alias("flops")),
        "comm_volume": lambda s, d: M.comm_volume(*_op(s, d), 16, 4),
        "tall_skinny_cost": _tall_cost,
        "tall_skinny_orders": lambda s, d: P.relational(fixture(s, d, "OP"), fixture(s, d, "PS")).df,
    }
    out |= {f"semiring_{r}": ring(r) for r in numeric_semirings()}
    out |= {f"kernel_ops_{name}": _kernel_experiment(name) for name in _kernel_inputs_sql()}
    return out


def oracle_sql() -> dict[str, str]:
    nn, succ = SQL["NN"], SQL["SUCC"]
    cop = {k: COPURCHASE for k in ("copurchase", "product_outer", "product_salted", "product_row", "product_column", "kernel_accumulator", "kernel_heap", "kernel_delayed_merge", "kernel_esc", "kernel_auto", "product_block_row", "product_broadcast_b", "product_rotating", "product_panel", "product_panel_barrier", "product_eager_merge", "product_fused", "product_fused_split", "product_two_level", "product_auto", "product_delta")}
    small = product_sql(SQL["RN"], SQL["NR"])
    n = f"(SELECT count(*) FROM ({OP}) t)"
    fl = f"(SELECT CAST(sum(c * c) AS BIGINT) FROM (SELECT i, count(*) AS c FROM ({OP}) t GROUP BY 1) g)"
    width = f"(({N_ORDER} + nz - 1) // nz)"
    inputs = {f"kernel_ops_{name}": _union([_ops_sql(q, a, b, str(size), str(size)) for q in KERNEL_GRIDS]) for name, (a, b, size) in _kernel_inputs_sql().items()}
    halves = f"SELECT i, j, CAST(v AS DOUBLE) / 4 AS v FROM ({COPURCHASE}) c"
    return cop | inputs | {f"semiring_{r}": product_sql(nn, nn, r) for r in numeric_semirings()} | {
        "product_split": COPURCHASE,
        "product_double": halves,
        "product_double_relational": halves,
        "product_wide_ids": f"SELECT i, count(*) AS nnz, CAST(sum(v) AS BIGINT) AS walks FROM ({product_sql(SQL['BIP'], SQL['BIP'])}) t GROUP BY 1",
        "dcsc_roundtrip": OP,
        "dcsr_roundtrip": PS,
        "csc_roundtrip": OP,
        "csr_roundtrip": t_sql(PS),
        "column_by_index": f"SELECT * FROM ({OP}) t WHERE j IN (3, 5, 8, 13)",
        "special_matrices": f"SELECT i // 3 AS i, j, i % 5 + 1 AS v FROM ({G.rmat_sql(8)}) t WHERE i % 3 = 0",
        "accumulator_traffic": _accumulator_sql(4),
        "worker_volume": _worker_sql(4),
        "sync_penalty": _penalty_sql(8),
        "imbalance_rmat": _imbalance_rmat_sql(),

        "triples_build": OP,
        "csc_pointers": _pointers_sql(OP, N_PART),
        "csr_pointers": _pointers_sql(OPT, N_ORDER),
        "dcsc_columns": _compressed_sql(OP),
        "dcsr_rows": _compressed_sql(OPT),
        "dcsc_aux": f"WITH c AS (SELECT DISTINCT j FROM ({OPT}) t), z AS (SELECT count(*) AS nz FROM c) SELECT r.chunk, (SELECT count(*) FROM c WHERE c.j < r.chunk * {width}) AS first FROM z, LATERAL (SELECT unnest(range(0, ({N_ORDER} + {width} - 1) // {width} + 1)) AS chunk) r",
        "column_lookup": f"SELECT * FROM ({OP}) t WHERE j IN (3, 5, 8, 13)",
        "transpose": t_sql(PS),
        "nonempty_ids": f"SELECT DISTINCT 'row' AS axis, i AS id FROM ({OP}) t UNION ALL SELECT DISTINCT 'column', j FROM ({OP}) t",
        "inner_intersection": f"SELECT j AS id FROM ({OP}) t INTERSECT SELECT i FROM ({PS}) u",
        "block_row_stats": _blocks_sql(OP, N_ORDER, N_PART, 8, 1),
        "grid_block_stats": _blocks_sql(OP, N_ORDER, N_PART, 3, 4),
        "split_block_stats": f"SELECT *, bj % 2 AS half FROM ({_blocks_sql(OP, N_ORDER, N_PART, 4, 8)}) t",
        "permute_symmetric": f"SELECT (i * 7 + 3) % {N_PART} AS i, (j * 7 + 3) % {N_PART} AS j, v FROM ({succ}) t",
        "submatrix_index": f"SELECT i // 3 AS i, j // 3 AS j, v FROM ({succ}) t WHERE i % 3 = 0 AND j % 3 = 0",
        "matrix_add": f"SELECT i, j, CAST(sum(v) AS BIGINT) AS v FROM (SELECT * FROM ({succ}) x UNION ALL {t_sql(succ)}) t GROUP BY 1, 2",
        "mask_ops": f"WITH m AS ({succ}) SELECT a.i, a.j, a.v, b.i IS NOT NULL AS kept FROM m a LEFT JOIN m b ON a.i = b.j AND a.j = b.i",
        "emult_ops": f"WITH m AS ({succ}) SELECT a.i, a.j, a.v * b.v AS v FROM m a JOIN m b ON a.i = b.j AND a.j = b.i",
        "row_reduce": f"SELECT i AS id, CAST(sum(v) AS BIGINT) AS v FROM ({OP}) t GROUP BY 1",
        "matrix_trace": f"SELECT CAST(sum(v * v) AS BIGINT) AS trace FROM ({OP}) t",
        "product_masked": f"WITH m AS ({succ}) SELECT p.* FROM ({product_sql(succ, succ)}) p JOIN m ON m.i = p.i AND m.j = p.j",
        "product_inner": small,
        "kernel_outer_naive": small,
        "kernel_heap_dual": product_sql(succ, succ),
        "kernel_heap_stats": _kernel_stats_sql(),
        "kernel_dense": product_sql(t_sql(SQL["OS"]), SQL["OS"]),
        "kernel_choice": _union([_chosen_sql(1), _chosen_sql(4)]),
        "semiring_argmin": f"SELECT i, j, v, k FROM (SELECT a.i, b.j, a.v + b.v AS v, a.j AS k, row_number() OVER (PARTITION BY a.i, b.j ORDER BY a.v + b.v, a.j) AS r FROM ({nn}) a JOIN ({nn}) b ON a.j = b.i) t WHERE r = 1",
        "grid_shift": f"SELECT i, j, v, {_cut('i', N_PART, 4)} AS bi, ({_cut('j', N_SUPP, 4)} + 3) % 4 AS bj FROM ({PS}) t",
        "panel_stage_flops": _union([_panel_sql(2), _panel_sql(8)]),
        "triple_product": _CHAIN_SQL,
        "nnz_profile": f"SELECT j AS id, CAST(sum(v) AS BIGINT) AS v, count(*) AS nnz FROM ({OP}) t GROUP BY 1",
        "flops_count": f"SELECT {fl} AS flops",
        "inner_stats": f"WITH a AS (SELECT DISTINCT j AS k FROM ({OP}) t), b AS (SELECT DISTINCT i AS k FROM ({PS}) t) SELECT (SELECT count(*) FROM a) AS nzc, (SELECT count(*) FROM b) AS nzr, (SELECT count(*) FROM a JOIN b ON a.k = b.k) AS ni",
        "compression_ratio": f"SELECT {fl} AS flops, nnz_c, round(CAST({fl} AS DOUBLE) / nnz_c, 6) AS ratio FROM (SELECT count(*) AS nnz_c FROM ({COPURCHASE}) t) c",
        "storage_words": _union([_storage_sql(q) for q in (1, 4, 16)]),
        "hypersparsity": _union([_hyper_sql(q) for q in (1, 2, 4, 8)]),
        "kernel_op_counts": _union([_ops_sql(q) for q in (1, 2, 8)]),
        "block_trend": _union([_trend_sql(q) for q in TREND_GRIDS]),
        "block_trend_rmat": _union([_trend_rmat_sql(q) for q in TREND_GRIDS]),
        "semirings_on_doubles": _rings_sql(),
        "imbalance_overall": _union([_overall_sql(q) for q in (4, 8, 16)]),
        "imbalance_stage": _union([_stage_sql(q) for q in (4, 8)]),
        "imbalance_median": _median_sql(),
        "diag_block_flops": f"SELECT bi, bj, CAST(sum(flops) AS BIGINT) AS flops FROM ({_cells_sql(4)}) c GROUP BY 1, 2",
        "comm_volume": _comm_sql(16, 4),
        "tall_skinny_cost": f"SELECT CAST(sum(c) AS BIGINT) AS work, {n} + (SELECT count(*) FROM ({PS}) t) AS memory, 4 * ({n} + (SELECT count(*) FROM ({PS}) t)) AS bandwidth FROM ({OP}) a JOIN (SELECT i, count(*) AS c FROM ({PS}) t GROUP BY 1) b ON a.j = b.i",
        "tall_skinny_orders": product_sql(OP, PS),
    }
