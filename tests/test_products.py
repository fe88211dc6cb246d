"""Worked examples, equal results of all methods and kernels, algebra, and cost identities."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from semigrid.functions import blocks as B
from semigrid.functions import kernels as K
from semigrid.functions import model
from semigrid.functions.tables import rmat_by_function
from semigrid.matrix import SparseMatrix, from_triples
from semigrid.operators import measures as M
from semigrid.operators import structure as S
from semigrid.plans import multiply as P
from semigrid.plans.planner import chain, chain_order, plan_product
from semigrid.semiring import numeric_semirings, semiring
from semigrid.sources import connectors
from semigrid.sources import generators as G
from semigrid.workloads import experiments as E
from semigrid.workloads import graphs as W
from semigrid.workloads.components import connected_components

#: Worked example: places (row, column) of two 6 by 6 matrices, from one.
LEFT = {1: (1, 4), 2: (1, 2), 3: (3, 4, 6), 4: (1, 4), 5: (2,), 6: (4,)}
RIGHT = {1: (1, 4), 3: (3, 5), 4: (1, 4), 5: (2, 5, 6), 6: (4, 5, 6)}
COUNTS = {(1, 1): 2, (2, 1): 1, (3, 1): 1, (4, 1): 2, (6, 1): 1, (3, 3): 1, (1, 4): 2, (2, 4): 1, (3, 4): 2, (4, 4): 2, (6, 4): 1, (3, 5): 2, (3, 6): 1}


def matrix(spark, entries, nrows, ncols=None):
    rows = [(int(i), int(j), int(v)) for i, j, v in entries]
    return SparseMatrix(spark.createDataFrame(rows, "i long, j long, v long"), nrows, ncols or nrows)


def rows(m):
    return sorted(tuple(r) for r in m.df.select("i", "j", "v").collect())


def triples(table):
    return tuple(np.array(x, np.int64) for x in zip(*[(i - 1, j - 1, 1) for i, js in table.items() for j in js]))


def draw(seed, m, n, count):
    r = np.random.default_rng(seed)
    at = {(int(i), int(j)): int(v) for i, j, v in zip(r.integers(0, m, count), r.integers(0, n, count), r.integers(1, 50, count))}
    return [(i, j, v) for (i, j), v in at.items()]


def brute(a, b, ring):
    s, out = semiring(ring), {}
    for i, k, x in a:
        for k2, j, y in b:
            if k == k2:
                v = s.np_mul(np.array([x]), np.array([y]))
                out[i, j] = v if (i, j) not in out else s.np_add(out[i, j], v)
    return sorted((i, j, int(v[0])) for (i, j), v in out.items())


@pytest.mark.parametrize("kernel", K.KERNELS)
def test_worked_product(kernel):
    out, stats = K.multiply(kernel, triples(LEFT), triples(RIGHT), "plus_times")
    assert {(int(i) + 1, int(j) + 1): int(v) for i, j, v in zip(*out)} == COUNTS
    assert [(j, i) for i, j in zip(out[0], out[1])] == sorted((j, i) for i, j in zip(out[0], out[1]))
    if kernel == "heap_outer":
        assert (stats["flops"], stats["ni"], stats["nzc"], stats["nzr"]) == (19, 4, 5, 5)


@pytest.mark.parametrize("kernel", ["esc", "heap_outer", "accumulator_row", "outer_naive", "inner", "delayed_merge"])
@pytest.mark.parametrize("ring", numeric_semirings())
def test_kernels_agree(kernel, ring):
    a, b = draw(1, 15, 20, 60), draw(2, 20, 12, 50)
    arrays = lambda t: tuple(np.array(x, np.int64) for x in zip(*t))
    out, _ = K.multiply(kernel, arrays(a), arrays(b), ring)
    assert sorted(zip(*(x.tolist() for x in out))) == brute(a, b, ring)


def test_kernels_on_nothing():
    for kernel in ("esc", "heap_outer", "accumulator_row", "outer_naive", "inner", "delayed_merge"):
        assert all(len(x) == 0 for x in K.multiply(kernel, K.NONE, K.NONE, "plus_times")[0])


def test_worked_formats(spark):
    m = matrix(spark, [(5, 0, 1), (7, 0, 2), (3, 6, 3), (1, 7, 4)], 9)
    assert [r.ptr for r in S.column_pointers(m).orderBy("j").collect()] == [0, 2, 2, 2, 2, 2, 2, 3, 4, 4]
    assert [(r.jc, r.cp) for r in S.compressed_columns(m).orderBy("jc").collect()] == [(0, 0), (6, 2), (7, 3)]
    assert [r.first for r in S.chunk_index(m).orderBy("chunk").collect()] == [0, 1, 1, 3]
    block = B.columns_of(tuple(np.array(x) for x in zip((5, 0, 1), (7, 0, 2), (3, 6, 3), (1, 7, 4))))
    assert (block.ids.tolist(), block.start.tolist(), block.minor.tolist(), block.num.tolist()) == ([0, 6, 7], [0, 2, 3, 4], [5, 7, 3, 1], [1, 2, 3, 4])
    index = B.ColumnIndex(block, 9)
    assert index.width == 3 and index.first.tolist() == [0, 1, 1, 3]
    assert [index.entries(j)[0].tolist() for j in range(9)] == [[5, 7], [], [], [], [], [], [3], [1], []]
    turned = block.turned()
    assert (turned.ids.tolist(), turned.minor.tolist()) == ([1, 3, 5, 7], [7, 6, 0, 0])
    back = turned.turned()
    assert all((getattr(back, f) == getattr(block, f)).all() for f in B.FIELDS)
    for rows_, cols, form in ((2, 3, "columns"), (4, 1, "rows"), (1, 1, "both")):
        stored = P.store_blocks(m, rows_, cols, form)
        assert rows(P.unpack_blocks(stored, "rows" if form == "rows" else "columns")) == rows(m)
        if form == "both":
            assert rows(P.unpack_blocks(stored, "rows", "t_")) == rows(m)
    assert sorted(map(tuple, connectors.fetch_columns(P.store_blocks(m, 2, 3), [0, 5, 7, 99]).collect())) == [(1, 7, 4), (5, 0, 1), (7, 0, 2)]
    assert rows(S.from_compressed(*S.compressed_entries(m), 9, 9)) == rows(m)


@pytest.fixture(scope="module")
def pair(spark):
    a, b = draw(3, 13, 17, 70), draw(4, 17, 11, 60)
    return matrix(spark, a, 13, 17), matrix(spark, b, 17, 11), brute(a, b, "plus_times")


CALLS = {
    "relational": P.relational,
    "salted": lambda a, b: P.relational(a, b, salt=3),
    "split": lambda a, b: P.relational(a, b, salt="auto", most=5),
    "rows": P.row_by_row,
    "columns": P.column_by_column,
    "block_row": lambda a, b: P.block_row(a, b, slabs=3),
    "replicated": P.block_row_replicated,
    "rotating": lambda a, b: P.rotating_grid(a, b, q=3),
    "panel_2x3": lambda a, b: P.panel_grid(a, b, grid=(2, 3), panels=4),
    "panel_barrier": lambda a, b: P.panel_grid(a, b, barrier=True, kernel="heap_outer"),
    "panel_eager": lambda a, b: P.panel_grid(a, b, eager=True),
    "fused_split": lambda a, b: P.fused_grid(a, b, grid=(3, 2), split=2, kernel="auto"),
    "two_level": P.two_level_grid,
    "auto": P.spgemm,
}


@pytest.mark.parametrize("name", CALLS)
def test_methods_agree(name, pair):
    a, b, want = pair
    assert rows(CALLS[name](a, b)) == want


@pytest.mark.parametrize("name", CALLS)
def test_methods_keep_fractions(name, pair):
    a, b, want = pair
    half = lambda m: m.with_df(m.df.withColumn("v", F.col("v") * 0.5))
    assert rows(CALLS[name](half(a), half(b))) == [(i, j, v / 4) for i, j, v in want]


@pytest.mark.parametrize("kernel", [k for k in K.KERNELS if k != "dense"])
@pytest.mark.parametrize("ring", ["min_plus", "max_times", "plus_pair"])
def test_kernels_on_doubles(kernel, ring):
    a, b = draw(5, 15, 20, 60), draw(6, 20, 12, 50)
    arrays = lambda t: (np.array([x[0] for x in t]), np.array([x[1] for x in t]), np.array([x[2] / 8 for x in t]))
    s, want = semiring(ring), {}
    for i, k, x in zip(*arrays(a)):
        for k2, j, y in zip(*arrays(b)):
            if k == k2:
                v = s.np_mul(np.array([x]), np.array([y]))[0]
                want[i, j] = v if (i, j) not in want else s.np_add(want[i, j], v)
    out, _ = K.multiply(kernel, arrays(a), arrays(b), ring)
    assert {(i, j): v for i, j, v in zip(*out)} == want


def test_wide_ids(spark):
    """Ids that no dense array could number: hypersparse kernels take them, the classical one refuses."""
    far = 1 << 40
    m = matrix(spark, [(0, far, 2), (1, far, 3), (far, 0, 5), (far, far + 1, 7), (far + 1, 1, 1)], far + 2)
    want = rows(P.relational(m, m))
    for kernel in ("esc", "heap_outer", "auto", "delayed_merge"):
        assert rows(P.fused_grid(m, m, kernel=kernel)) == want
    with pytest.raises(Exception, match="too many"):
        P.single_block(m, m, "accumulator_row").df.collect()


def test_cancelled_entries_stay(spark):
    a, b = matrix(spark, [(0, 0, 1), (0, 1, 1)], 1, 2), matrix(spark, [(0, 0, 1), (1, 0, -1)], 2, 1)
    for kernel in K.KERNELS:
        assert rows(P.single_block(a, b, kernel)) == [(0, 0, 0)]


def test_struct_values(spark):
    d = spark.createDataFrame([(0, 1, 4), (0, 2, 1), (1, 3, 1), (2, 3, 4)], "i long, j long, d long")
    m = SparseMatrix(d.select("i", "j", F.struct(F.col("d").alias("v"), F.col("j").alias("k")).alias("v")), 4, 4)
    assert [(r.i, r.j, r.v.v, r.v.k) for r in P.spgemm(m, m, "argmin", method="relational").df.collect()] == [(0, 3, 5, 1)]
    with pytest.raises(TypeError):
        P.fused_grid(m, m, "argmin")


def _nodes(df):
    """Names of the nodes of a physical plan as it was run."""
    df.collect()
    return df._jdf.queryExecution().executedPlan().toString()


def test_plans(spark, pair):
    a, b, _ = pair
    plan = _nodes(P.fused_grid(a, b, grid=(2, 2)).df)
    final = plan.split("Initial Plan")[0]
    assert final.count("Exchange hashpartitioning") == 1 and "HashAggregate" not in final, "one shuffle ships both operands; cells sum for themselves"
    assert "LeftSemi" in P.partnered(a, b)[0].df._jdf.queryExecution().optimizedPlan().toString()
    assert "CartesianProduct" not in _nodes(P.relational(a, b, salt="auto", most=5).df)


def test_dual_format(spark):
    entries = draw(21, 19, 19, 80)
    m = matrix(spark, entries, 19)
    assert rows(P.square_dual(P.dual_blocks(m, 3))) == brute(entries, entries, "plus_times")


def test_counters(pair):
    a, b, _ = pair
    stats = P.pair_stats(a, b, 3).collect()
    cells = {(r.bi, r.bj, r.bk): r.flops for r in M.cell_flops(a, b, 3).collect()}
    assert {(r.ci, r.cj, r.bk): r.flops for r in stats if r.flops} == cells


def test_imbalance_is_that_of_the_schedule(spark):
    """Flops of each round, counted by moving blocks as the rotating grid does."""
    entries, q, n = draw(31, 12, 12, 50), 3, 12
    m, size = matrix(spark, entries, n), 4
    work = {}
    for s in range(q):
        for x in range(q):
            for y in range(q):
                k = (x + y + s) % q
                work[s, x, y] = sum(1 for i, p, _ in entries for p2, j, _ in entries if p == p2 and i // size == x and p // size == k and j // size == y)
    want = {s: round(max(work[s, x, y] for x in range(q) for y in range(q)) * q * q / sum(work[s, x, y] for x in range(q) for y in range(q)), 6) for s in range(q)}
    assert {r.stage: r.imbalance for r in M.imbalance(m, m, q)[1].collect()} == want
    penalty = M.sync_penalty(m, m, q).first()
    assert penalty.per_stage == pytest.approx(sum(want.values()) / q, abs=1e-6) and penalty.sync_percent >= penalty.async_percent


def test_planner(spark, pair):
    a, b, want = pair
    plan = plan_product(a, b, cell_entries=40)
    assert plan["grid"][0] > 1 and set(plan["ships"]) >= {"relational", "fused_grid", "panel_grid", "rotating_grid", "block_row_replicated"}
    dense = matrix(spark, [(i, j, 1) for i in range(40) for j in range(40)], 40)
    assert plan_product(dense, dense, tasks=8)["compression"] > 10
    for method, options in (("fused_grid", {"grid": plan["grid"]}), ("rotating_grid", {"q": 2})):
        assert rows(P.spgemm(a, b, method=method, **options)) == want


def test_methods_on_nothing_and_bad_shapes(spark, pair):
    nothing = matrix(spark, [], 17, 11)
    for name in ("relational", "panel_2x3", "fused_split", "rotating", "block_row"):
        assert rows(CALLS[name](pair[0], nothing)) == []
    with pytest.raises(ValueError):
        P.relational(pair[0], pair[0])
    with pytest.raises(ValueError):
        P.block_row_replicated(pair[0], pair[1], limit=1)


def test_algebra(spark, pair):
    a, b, _ = pair
    d = matrix(spark, draw(9, 17, 11, 40), 17, 11)
    assert rows(P.relational(b.T, a.T)) == rows(P.relational(a, b).T)
    assert rows(P.relational(a, S.add(b, d))) == rows(S.add(P.relational(a, b), P.relational(a, d)))
    assert rows(P.relational(a, S.eye(spark, 17))) == rows(a)
    assert rows(chain([a, b, b.T])) == rows(P.relational(P.relational(a, b), b.T))
    p = G.permutation(spark, 17, 5, 3)
    assert rows(P.relational(a, p)) == rows(S.permute_by(a, p)) == rows(S.permute(a, 5, 3, "columns"))
    square = matrix(spark, draw(11, 17, 17, 60), 17)
    assert rows(P.relational(S.permute(square, 5, 3), S.permute(square, 5, 3))) == rows(S.permute(P.relational(square, square), 5, 3))
    s = G.restriction(spark, 17, 4)
    assert sum(v for *_, v in rows(W.contract(square, s))) == sum(v for *_, v in rows(square))
    assert rows(W.contract(square, s)) == rows(W.halve(square, 4))


def test_costs(pair):
    a, b, want = pair
    n = M.flops(a, b).first()[0]
    assert n >= len(want)
    with pytest.raises(ValueError):
        S.permute(a, 13, 0, "rows")
    assert M.cell_flops(a, b, 3).agg(F.sum("flops")).first()[0] == n
    assert {r.flops for r in [M.kernel_op_counts(a, b, q).first() for q in (1, 2, 3)]} == {n}
    overall, stage = M.imbalance(a, b, 3)
    assert 1 <= overall.first()[0] <= 9 and stage.count() <= 3
    assert plan_product(a, b)["flops"] == n
    assert chain_order([(10, 100), (100, 5), (5, 50)], [1000, 500, 250])[1] == "((M0*M1)*M2)"


def test_triples(spark):
    df = spark.createDataFrame([(1, 1, 2), (1, 1, 3)], "i long, j long, v long")
    assert rows(from_triples(df, "i", "j", "v", (2, 2))) == [(1, 1, 5)]
    for bad in (lambda: from_triples(df, "i", "j", "v", (2, 2), dup="error"), lambda: from_triples(df, "i", "j", "v", (1, 1))):
        with pytest.raises(Exception, match="repeated|outside"):
            rows(bad())


def test_reported_shapes(spark):
    one = {(r.n, r.p): r.speedup for r in model.model_1d(spark).collect()}
    two = {(r.n, r.p): r.speedup for r in model.model_2d(spark).collect()}
    free = {(r.n, r.p): r.speedup for r in model.model_overlap(spark).collect()}
    for n in (1 << 17, 1 << 20, 1 << 24):
        assert max(v for (m, _), v in one.items() if m == n) < 50
        curve = [two[n, q * q] for q in (1, 2, 4, 8, 16, 32, 64)]
        assert curve[-1] == max(curve) and all(free[k] >= two[k] for k in two)
    # by hand: n = 2^20, c = 4, p = 64: a step has blocks of 2^17 columns, of which half are nonempty and a quarter of a quarter met
    n, p, c, h = 1 << 20, 64, 4, model.GAMMA_HYPERSPARSE
    scan, ni, products = 8 * 2 * (0.5 * (1 << 17)), 32768, c * c * n / p
    factorial = sum(np.log2(k) for k in range(1, 9))
    comp = h * (scan + products * np.log2(ni) + products / 8 * factorial)
    comm = 8 * (2 * model.ALPHA + 24e-9 * 2 * c * n / p)
    assert two[n, p] == pytest.approx(model.GAMMA_CLASSICAL * c * c * n / (comp + comm), rel=1e-6) == pytest.approx(37.8, abs=0.1)
    assert two[n, 4096] == pytest.approx(725, abs=1) and free[n, 4096] == pytest.approx(1432, abs=2)
    panel = {(r.n, r.p): r.speedup for r in model.model_panel(spark).collect()}
    assert all(panel[k] <= two[k] for k in two)
    sizes = {r.p: r.n for r in model.model_isoefficiency(spark).collect()}
    assert sizes[64] / sizes[16] == pytest.approx(8, rel=1e-4)
    assert {r.largest for r in model.model_terms(spark).collect()} >= {"bandwidth", "merging"}
    m = G.rmat(spark, 10)
    ops = [M.kernel_op_counts(m, m, q).first() for q in (1, 8)]
    assert ops[1].classical_ops > ops[0].classical_ops and ops[1].heap_ops < ops[0].heap_ops
    p = G.random_permutation(spark, 1024, 5)
    mixed = S.permute_rows_by(S.permute_by(m, p), p)
    relabelled, plain = M.sync_penalty(mixed, mixed, 8).first(), M.sync_penalty(m, m, 8).first()
    assert relabelled.overall < plain.overall and relabelled.per_stage < plain.per_stage
    assert relabelled.async_percent < relabelled.sync_percent
    assert m.df.count() == 6653 and M.flops(m, m).first()[0] == 185055


def test_generators(spark):
    for df, n in ((G.random_permutation(spark, 5003, 2).df, 5003), (G.permutation(spark, 1000).df, 1000)):
        assert df.select("i").distinct().count() == df.select("j").distinct().count() == df.count() == n
    e = G.erdos_renyi(spark, 1 << 12, 8)
    for axis in "ij":
        each = S.reduce(e, axis, "plus_pair").agg(F.variance("v"), F.avg("v")).first()
        assert 6.5 < each[0] < 9.5 and 7.5 < each[1] < 8.2, "independent places: the variance of a column's count is its mean"
    assert rows(SparseMatrix(rmat_by_function(spark, 7, 8, 7, 100), 128, 128)) == rows(G.rmat(spark, 7))
    assert G.restriction(spark, 10, 4, "random").df.groupBy("i").count().agg(F.max("count")).first()[0] == 4
    spark.createDataFrame([([0, 6, 7], [0, 2, 3, 4], [5, 7, 3, 1], [1, 2, 3, 4])], "ids array<long>, start array<long>, minor array<long>, num array<long>").createOrReplaceTempView("blocks")
    assert sorted(map(tuple, spark.sql("SELECT e.* FROM blocks b, LATERAL dcsc_unpack(b.ids, b.start, b.minor, b.num) e").collect())) == [(1, 7, 4), (3, 6, 3), (5, 0, 1), (7, 0, 2)]


def test_special_matrices(spark, pair):
    a = pair[0]
    assert rows(P.relational(a, S.zero(spark, 17, 4))) == []
    scaled = P.relational(S.diagonal(spark.range(13).select("id", (F.col("id") + 1).alias("v")), 13), a)
    assert rows(scaled) == [(i, j, v * (i + 1)) for i, j, v in rows(a)]
    picked = spark.createDataFrame([(4, 0), (2, 1)], "old long, new long")
    assert rows(P.relational(S.selector(picked, 2, 13), a)) == sorted(({4: 0, 2: 1}[i], j, v) for i, j, v in rows(a) if i in (2, 4))


def test_spans_of_nested_tags(spark):
    """All spans of whole elements against a stack parser, on tags nested and repeated deeper than a few rounds reach."""
    r = np.random.default_rng(4)

    def element(depth):
        inside = sum((element(depth - 1) for _ in range(int(r.integers(0, 4)))), []) if depth else []
        tag = str(r.choice(["div", "p"]))
        return [tag, *inside, f"/{tag}"]

    docs = {k: sum((element(5) for _ in range(3)), ["li"]) for k in range(4)} | {9: ["div"] * 40 + ["/div"] * 40}
    tags = spark.createDataFrame([(t, d, i, i + 1) for d, ts in docs.items() for i, t in enumerate(ts)], "symbol string, doc long, i long, j long")
    from semigrid.workloads.graph_queries import RULES

    want = set()
    for d, ts in docs.items():
        for i in range(len(ts)):
            stack = []
            for j in range(i, len(ts)):
                if not ts[j].startswith("/"):
                    stack.append(ts[j])
                elif not stack or stack.pop() != ts[j][1:]:
                    break
                if not stack:
                    want.add((d, i, j + 1))
    got = {(x.doc, x.i, x.j) for x in W.cfl_reach(tags, RULES).filter("symbol = 'E'").collect()}
    assert got == want and len(want) > 100


def test_shortest_paths_by_halves(spark):
    entries = draw(41, 23, 23, 70)
    m = matrix(spark, entries, 23)
    want = {(i, j): 0 if i == j else 10**9 for i in range(23) for j in range(23)}
    for i, j, v in entries:
        want[i, j] = min(want[i, j], v)
    for k in range(23):
        for i in range(23):
            for j in range(23):
                want[i, j] = min(want[i, j], want[i, k] + want[k, j])
    want = sorted((i, j, v) for (i, j), v in want.items() if v < 10**9)
    assert rows(W.apsp(m)) == rows(W.apsp_recursive(m, 4)) == want


def test_cycles_and_votes(spark):
    line = [(k, k + 1, 1) for k in range(6)]
    assert W.on_cycles(matrix(spark, line, 7)).count() == 0
    assert sorted(map(tuple, W.on_cycles(matrix(spark, [*line, (4, 2, 1), (6, 6, 1)], 7)).collect())) == [(2, 3), (3, 4), (4, 2), (6, 6)]
    two = [(i, j, 1) for group in (range(4), range(4, 8)) for i in group for j in group] + [(3, 4, 1)]
    assert {(r.vertex, r.cluster) for r in W.peer_pressure(matrix(spark, two, 8), None).collect()} == {(v, v // 4 * 4) for v in range(8)}
    clusters = {r.vertex: r.cluster for r in W.markov_cluster(matrix(spark, [*two, (4, 3, 1)], 8)).collect()}
    assert len({clusters[v] for v in range(4)}) == len({clusters[v] for v in range(4, 8)}) == 1 and clusters[0] != clusters[7]


def test_similar_rows(spark):
    m = matrix(spark, [(0, 0, 1), (0, 1, 1), (1, 0, 2), (1, 1, 2), (2, 1, 5), (3, 9, 1)], 10)
    assert sorted((r.i, r.j, r.similarity, r["rank"]) for r in W.cosine_topk(m, 1).collect()) == [(0, 1, 1.0, 1), (1, 0, 1.0, 1), (2, 0, 0.707107, 1)]
    assert sorted(map(tuple, W.topk_overlap(m, 1).collect())) == [(0, 2, 5, 1), (1, 2, 10, 1)]


def test_many_components(spark):
    r = np.random.default_rng(3)
    edges = [(int(a), int(b)) for a, b in r.integers(0, 400, (260, 2))] + [(k, k + 1) for k in range(1000, 1200)]
    root = {x: x for e in edges for x in e}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in edges:
        a, b = sorted((find(a), find(b)))
        root[b] = a
    df = spark.createDataFrame(edges, "u long, v long").repartition(5)
    assert {tuple(x) for x in connected_components(df).collect()} == {(x, find(x)) for x in root if find(x) != x}


def test_graphs(spark):
    path = matrix(spark, [(0, 1, 2), (1, 2, 3), (2, 3, 1), (0, 3, 9)], 4)
    want = [(0, 0, 0), (0, 1, 2), (0, 2, 5), (0, 3, 6), (1, 1, 0), (1, 2, 3), (1, 3, 4), (2, 2, 0), (2, 3, 1), (3, 3, 0)]
    assert rows(W.apsp(path)) == rows(W.apsp_recursive(path)) == want
    levels = W.bfs(path, spark.createDataFrame([(0,)], "id long")).collect()
    assert sorted((r.vertex, r.level) for r in levels) == [(0, 0), (1, 1), (2, 2), (3, 1)]
    line = matrix(spark, [(i, j, 1) for i in range(4) for j in (i - 1, i + 1) if 0 <= j < 4], 4)
    got = {r.vertex: r.score for r in W.betweenness(line, spark.range(4)).collect()}
    assert (got[1], got[2]) == (4.0, 4.0)
    edges = spark.createDataFrame([(5, 4), (4, 3), (9, 8), (3, 1), (7, 7)], "u long, v long")
    assert sorted(map(tuple, connected_components(edges).collect())) == [(3, 1), (4, 1), (5, 1), (9, 8)]
    match = W.greedy_matching(matrix(spark, [(0, 0, 1), (1, 0, 1), (1, 1, 1), (2, 1, 1)], 3)).collect()
    assert len({r.i for r in match}) == len({r.j for r in match}) == len(match) == 2


def test_coordinate_text(spark, tmp_path):
    f = tmp_path / "m.mtx"
    f.write_text("%% comment\n% more\n9 9 3\n" + "".join(f"{i} {i + 1} {i * 10}\n" for i in (1, 2, 3)) + "9 9 3\n")
    m = connectors.read_coordinates(spark, str(f))
    assert (m.nrows, m.ncols, rows(m)) == (9, 9, [(0, 1, 10), (1, 2, 20), (2, 3, 30), (8, 8, 3)])
    connectors.write_coordinates(m, str(tmp_path / "out"))
    again = connectors.read_coordinates(spark, str(tmp_path / "out"), "double")
    assert (again.nrows, again.ncols, rows(again)) == (9, 9, rows(m))
    (tmp_path / "bad.mtx").write_text("2 2 1\n1 2\n")
    with pytest.raises(Exception, match="not an entry"):
        connectors.read_coordinates(spark, str(tmp_path / "bad.mtx")).df.collect()
    (tmp_path / "none.mtx").write_text("")
    assert rows(connectors.read_coordinates(spark, str(tmp_path / "none.mtx"))) == []


def test_experiments(spark):
    a = E.cached(G.rmat(spark, 8))
    found = E.kernel_scaling(a, a, (1, 2), ("esc", "heap_outer"))
    assert len(found) == 4 and E.gamma(found, "heap_outer") > 0
    assert E.compare_sync_async(a, a, 2, 1)["flops"] == 25272
    assert len(E.strong_scaling(a, a, (1, 2))) == len(E.weak_scaling(spark, (7, 8))) == 2
    assert E.wait_share([1.0, 3.0]) == pytest.approx(1 / 3)
    assert len(E.cell_seconds(a, a, 2)) == 4
    inputs = E.kernel_inputs(spark, 6, 4)
    assert set(inputs) == {"scale_free", "scale_free_by_permutation", "uniform", "mesh_relabelled"}


def test_searches_are_not_cut(spark):
    n = 7
    line = SparseMatrix(spark.createDataFrame([(k, k + 1, 1) for k in range(n)], "i long, j long, v long"), n + 1, n + 1)
    sources = spark.createDataFrame([(0,)], "id long")
    with pytest.raises(RuntimeError):
        W.bfs(line, sources, 3)
    assert W.bfs(line, sources, n).count() == n + 1
    chain = {r.vertex: r.score for r in W.betweenness(line, sources).collect()}
    assert chain == {k: float(n - k) for k in range(1, n + 1)}


def test_betweenness_query_has_no_level_limit(spark, tmp_path):
    from semigrid.workloads.graph_queries import queries

    # one order for each step, its lines in sequence: parts 1 to 9 follow each other
    spark.createDataFrame([(1, k, k, 1.0) for k in range(1, 10)], "l_orderkey long, l_partkey long, l_linenumber long, l_quantity double").write.parquet(str(tmp_path / "lineitem.parquet"))
    spark.createDataFrame([(k,) for k in range(1, 10)], "p_partkey long").write.parquet(str(tmp_path / "part.parquet"))
    got = {r.vertex: r.score for r in queries()["betweenness"](spark, str(tmp_path)).collect()}
    assert got[5] == 8.0 and got[8] == 2.0 and got[9] == 0.0


def test_sums_beyond_the_limit_go_to_disk_and_come_back():
    from semigrid.functions.held import HeldSums

    rng, held, want = np.random.default_rng(1), HeldSums(semiring("plus_times"), most=50, rows=7), {}
    for _ in range(40):
        i, j, v = rng.integers(0, 30, 20), rng.integers(0, 30, 20), rng.integers(-5, 9, 20)
        held.add((i, j, v))
        for x, y, n in zip(i.tolist(), j.tolist(), v.tolist()):
            want[x, y] = want.get((x, y), 0) + n
    assert held.files, "more than the limit is not held"
    out = [(int(x), int(y), int(n)) for t in held.results() for x, y, n in zip(*t)]
    assert {(x, y): n for x, y, n in out} == want and len(out) == len(want) and not held.files


def test_blocks_of_a_task_are_ordered_on_its_disk(spark, pair):
    from semigrid.functions.held import HeldBlocks

    rng, held, want = np.random.default_rng(2), HeldBlocks(most=300), {}
    for key in [(c, k, side) for c in range(3) for k in range(4) for side in (1, 0)]:
        entries = rng.integers(0, 9, 12), rng.integers(0, 1 << 40, 12), rng.random(12)
        want[key] = B.columns_of(entries)
        held.add(key, want[key])
    assert held.file, "more than the limit is not held"
    out = list(held.ordered())
    assert [k for k, _ in out] == sorted(want) and not held.file
    assert all((getattr(b, f) == getattr(want[k], f)).all() for k, b in out for f in B.FIELDS)
    assert "Sort" not in _nodes(P.fused_grid(pair[0], pair[1]).df).split("Initial Plan")[0], "Spark holds no blocks to sort them"


def test_auto_makes_hypersparse_pairs_in_vectors(spark):
    """Where there is no room for dense arrays, no heap walks the products of a slice one by one."""
    entries = [(i + (1 << 40), (i * 7) % 50, 1) for i in range(200)]
    turned = [(j, i, v) for i, j, v in entries]
    arrays = lambda t: tuple(np.array(x) for x in zip(*t))
    x, y, sizes = B.columns_of(arrays(entries)), B.rows_of(arrays(turned)), (1 << 41, 50, 1 << 41)
    assert K.choose(x, y, sizes) == "heap_outer" and K.choose_for_slices(x, y, sizes) == "esc"
    near, back = [(i, j, 1) for i in range(200) for j in range(i % 7, 50, 7)], [(j, i, 1) for i in range(200) for j in range(i % 7, 50, 7)]
    x, y, sizes = B.columns_of(arrays(near)), B.rows_of(arrays(back)), (200, 50, 200)
    assert K.choose(x, y, sizes) == "accumulator_row" and K.choose_for_slices(x, y, sizes) == "esc", "few products an entry: walking entries takes longer"
    m = matrix(spark, entries, 1 << 41, 50)
    assert rows(P.single_block(m, m.T, "auto")) == brute(entries, turned, "plus_times")


def test_pairs_are_sliced_to_bounded_products():
    """A hub and a column of products over the limit go in pieces whose sum is the whole."""
    a, b = draw(41, 12, 9, 60) , draw(42, 9, 14, 70)
    arrays = lambda t: tuple(np.array(x) for x in zip(*t))
    x, y = B.columns_of(arrays(a)), B.rows_of(arrays(b))
    parts = list(K.sliced(x, y, most=8))
    made = [K.expand_sort_compress(p, q, semiring("plus_times"), (12, 9, 14)) for p, q in parts]
    assert max(s["flops"] for _, s in made) <= 8 + 2 * 14
    i, j, v = K.combine(K.joined([t for t, _ in made]), semiring("plus_times"))
    assert sorted(zip(i.tolist(), j.tolist(), v.tolist())) == brute(a, b, "plus_times")


FINER = {
    **{f"kernel_{k}": (lambda k: lambda a, b: P.single_block(a, b, k))(k) for k in ("accumulator_row", "auto", "delayed_merge", "esc", "heap_outer", "dense")},
    "outer": lambda a, b: P.single_block(a, b, "esc", cells=1),
    "eager": lambda a, b: P.panel_grid(a, b, eager=True),
    "panel": lambda a, b: P.panel_grid(a, b, grid=(2, 3)),
    "fused": lambda a, b: P.fused_grid(a, b, grid=(3, 2)),
    "fused_split": lambda a, b: P.fused_grid(a, b, split=2, kernel="heap_outer"),
    "two_level": P.two_level_grid,
}


@pytest.fixture
def tight(monkeypatch):
    """Limits so low that small operands are refined."""
    from semigrid.plans import grid_lines as L

    for name, value in (("SMALL_OPERANDS", 10), ("INNER_ENTRIES", 20), ("CELL_PRODUCTS", 20), ("MOST_CELLS", 8)):
        monkeypatch.setattr(L, name, value)
    return L


@pytest.mark.parametrize("name", FINER)
def test_large_operands_get_finer_grids(name, pair, tight):
    a, b, want = pair
    axes, _ = tight.finer_axes(a, b, 2, 2, 2)
    assert axes[1].fine > 1
    assert rows(FINER[name](a, b)) == want


def test_finer_dual_blocks(spark, tight):
    entries = draw(22, 19, 19, 90)
    blocks = P.dual_blocks(matrix(spark, entries, 19), 2)
    assert blocks.rows > 2 and rows(P.square_dual(blocks)) == brute(entries, entries, "plus_times")


@pytest.mark.parametrize("most", [1, 7, 250_000])
def test_dual_blocks_are_packed_without_a_sort(most, spark, tight, monkeypatch):
    """They are written once, in rows of few entries if need be, from tasks that take entries as they come."""
    entries = draw(22, 19, 19, 90)
    plans, write = [], P.materialize
    monkeypatch.setattr(P, "BLOCK_ENTRIES", most)
    monkeypatch.setattr(P, "materialize", lambda df, tag, *more, **named: plans.append(_nodes(df)) or write(df, tag, *more, **named))
    blocks = P.dual_blocks(matrix(spark, entries, 19), 2)
    assert len(plans) == 1 and "Sort" not in plans[0]
    assert all(B.block_of_value(bytes(x)).nnz <= most for r in blocks.df.collect() for x in (r.block, r.t_block))
    assert rows(P.square_dual(blocks)) == brute(entries, entries, "plus_times")


def test_choices_need_no_blocks(spark, pair):
    """The chooser by counts takes what it takes on the blocks themselves."""
    a, b, _ = pair
    plan = P.kernel_choices(a, b, 3)
    left, right = P.store_blocks(a, 3, 3, "columns").df.collect(), P.store_blocks(b, 3, 3, "rows").df.collect()
    block = lambda r: B.Block(*(np.array(r[f]) for f in B.FIELDS))
    want = {}
    for x in left:
        for y in right:
            if x.bj == y.bi and set(x.ids) & set(y.ids):
                k = K.choose(block(x), block(y), (5, 6, 4))
                want[k] = want.get(k, 0) + 1
    assert {r.kernel: r.pairs for r in plan.collect()} == want
    assert "ids" not in plan._jdf.queryExecution().optimizedPlan().toString()


def test_a_large_right_side_is_replicated_in_turns(pair):
    a, b, want = pair
    assert rows(P.block_row_replicated(a, b, limit=9, turns=True)) == want
    assert rows(P.block_row(a, b, slabs=2, limit=9, more=True)) == want
    with pytest.raises(ValueError):
        P.block_row(a, b, slabs=2, limit=9)


def test_all_rings_in_slabs_without_a_shuffle_of_products(spark):
    """Counts and ends of the products over each semiring equal those of the products themselves, in one slab or many, and no table stays."""
    m = matrix(spark, draw(51, 19, 19, 90), 19)
    m = m.with_df(m.df.withColumn("v", F.col("v") * 0.5))
    names = [r for r in numeric_semirings() if r != "xor_and"]
    want = {}
    for r in names:
        v = [float(x["v"]) for x in P.relational(m, m, r).df.collect()]
        want[r] = (len(v), min(v), max(v))
    for limit in (1000, 12):
        assert {r["ring"]: (r["n"], r["least"], r["greatest"]) for r in P.rings_summary(m, m, names, limit, 3).collect()} == want
    assert not [t for t in spark.catalog.listTables() if t.name.startswith("semigrid_rows")]


@pytest.mark.parametrize("name", ["kernel_esc", "kernel_heap_outer", "fused", "fused_split"])
def test_blocks_that_are_read_once_are_not_written(name, pair, tight, monkeypatch):
    """They go from packing to their cells; a task that may hold few entries sends a block in a number of rows."""
    a, b, want = pair
    written, plan, write = [], P.plan_blocks, P.materialize
    monkeypatch.setattr(P, "plan_blocks", lambda m, r, c, form: plan(m, r, c, form, most=7))
    monkeypatch.setattr(P, "materialize", lambda df, tag, *more, **named: written.append(tag) or write(df, tag, *more, **named))
    assert rows(FINER[name](a, b)) == want and not written


def test_a_block_is_one_narrow_value():
    for minor, num in ((np.array([5, 1 << 40, 2]), np.array([-3, 4, 100])), (np.array([5, 6, 2]), np.array([0.5, -1, 2])), (np.zeros(0, np.int64), np.zeros(0, np.int32))):
        block = B.pack(np.arange(len(minor)), minor, num)
        value = B.block_value(block)
        back = B.block_of_value(value)
        assert all((getattr(back, f) == getattr(block, f)).all() and getattr(back, f).dtype == getattr(block, f).dtype for f in B.FIELDS)
    small = B.block_value(B.pack(np.arange(100), np.arange(100), np.ones(100, np.int64)))
    assert len(small) < 500, "small ids and values take a byte each"


def test_eager_sums_need_no_hash_table(pair, tight):
    """Each panel but the first is added to the result by tasks with bounded sums, and Spark keeps no table of the places."""
    a, b, want = pair
    for panels in (1, 2, 3):
        got = P.panel_grid(a, b, panels=panels, eager=True)
        assert rows(got) == want and "HashAggregate" not in _nodes(got.df).split("Initial Plan")[0]


def test_counts_of_inner_ids_need_no_join(pair, tight):
    a, b, _ = pair
    left, right = ([r.asDict() for r in m.df.collect()] for m in (a, b))
    n = [(x, y) for x in left for y in right if x["j"] == y["i"]]
    want = (len(n), len({(x["i"], x["j"]) for x, _ in n}), len({(y["i"], y["j"]) for _, y in n}))
    got = tight.met_counts(a, b)
    assert tuple(got.first()) == want
    assert "Join" not in _nodes(got) and "Sort" not in _nodes(got)


@pytest.mark.parametrize("name", ["OP", "SUCC"])
def test_large_tables_are_dealt_before_the_sql(name, spark, monkeypatch):
    """The matrix is the same, and its first groups or windows take the tasks of bounded rows."""
    from semigrid.sources import fixtures as X

    want = X.fixture(spark, "/root/testdata/sf0.001", name).df
    monkeypatch.setattr(X, "DEALT_LEAST", 1000)
    monkeypatch.setattr(X, "DEALT_ROWS", 500)
    got = X.fixture(spark, "/root/testdata/sf0.001", name).df
    assert got.exceptAll(want).isEmpty() and want.exceptAll(got).isEmpty()
    n = -(-spark.read.parquet("/root/testdata/sf0.001/lineitem.parquet").count() // 500)
    plan = _nodes(got)
    assert f", {n})" in plan and plan.count("Exchange hash") == _nodes(want).count("Exchange hash")


def test_heap_takes_values_at_once(monkeypatch):
    """Products are multiplied by one call, not one by one."""
    a, b = draw(61, 12, 9, 60), draw(62, 9, 14, 70)
    arrays = lambda t: tuple(np.array(x) for x in zip(*t))
    x, y, calls = B.columns_of(arrays(a)), B.rows_of(arrays(b)), []
    from dataclasses import replace

    for name in numeric_semirings():
        ring = semiring(name)
        calls.clear()
        counted = replace(ring, np_mul=lambda p, q, f=ring.np_mul: calls.append(len(p)) or f(p, q))
        (i, j, v), stats = K.heap_outer(x, y, counted, (12, 9, 14))
        assert sorted(zip(i.tolist(), j.tolist(), v.tolist())) == brute(a, b, name) and sum(calls) == stats["flops"] and len(calls) == 1
    none = B.columns_of((np.zeros(0, np.int64),) * 3)
    assert len(K.heap_outer(none, y, semiring("plus_times"), (12, 9, 14))[0][2]) == 0
