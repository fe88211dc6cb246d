"""Queries on the model, the generators, the experiments and the graph applications."""

from __future__ import annotations

from itertools import count

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semigrid.functions import model
from semigrid.functions.tables import rmat_by_function
from semigrid.matrix import SparseMatrix
from semigrid.operators import structure as S
from semigrid.operators.measures import flops
from semigrid.plans.multiply import relational
from semigrid.sources import generators as G
from semigrid.sources.fixtures import PART_OFFSET, SQL, fixture, stored
from semigrid.sources.tables import table
from semigrid.workloads import graphs as W
from semigrid.workloads.components import connected_components
from semigrid.workloads.product_queries import product_sql, t_sql

BIP, SUCC, NN, UH, OP = SQL["BIP"], SQL["SUCC"], SQL["NN"], SQL["UH"], SQL["OP"]
SOURCES = (0, 5, PART_OFFSET)
#: Levels, rounds and sweeps to which loops are written out in the SQL; the queries themselves end when nothing is left to do.
LEVELS, ROUNDS, SWEEPS = 10, 14, 14
#: Scale of the scale-free graph whose frontiers are profiled, and every so many of its vertices is a source: 256 of them.
FRINGE_SCALE, FRINGE_STEP = 10, 4
#: Vertices that a restriction makes one.
ORDERS = (2, 4, 8)
#: Tags that may open and close.
TAGS = ("div", "p", "ul", "li")

DOC_WORDS = "SELECT DISTINCT item_id AS i, w AS j, CAST(1 AS BIGINT) AS v FROM (SELECT item_id, unnest(string_split(lower(text), ' ')) AS w FROM benchmark) t WHERE w <> ''"


def _bfs_sql(edges: str = BIP, sources: str | None = None, levels: int = LEVELS) -> str:
    sources = sources or f"VALUES {', '.join(f'({s})' for s in SOURCES)}"
    out = f"e AS MATERIALIZED ({edges}), l0 AS (SELECT CAST(s AS BIGINT) AS source, CAST(s AS BIGINT) AS vertex, CAST(0 AS BIGINT) AS level, CAST(1 AS BIGINT) AS paths, CAST(NULL AS BIGINT) AS parent FROM ({sources}) x(s)), s0 AS (SELECT * FROM l0)"
    for k in range(1, levels + 1):
        out += f", l{k} AS MATERIALIZED (SELECT f.source, e.j AS vertex, CAST({k} AS BIGINT) AS level, CAST(sum(f.paths) AS BIGINT) AS paths, min(f.vertex) AS parent FROM l{k - 1} f JOIN e ON e.i = f.vertex WHERE NOT EXISTS (SELECT 1 FROM s{k - 1} s WHERE s.source = f.source AND s.vertex = e.j) GROUP BY 1, 2), s{k} AS MATERIALIZED (SELECT * FROM s{k - 1} UNION ALL SELECT * FROM l{k})"
    return f"WITH {out} SELECT * FROM s{levels}"


def _bfs(s, d) -> DataFrame:
    return W.bfs(fixture(s, d, "BIP"), s.createDataFrame([(x,) for x in SOURCES], "id long"))


def _fringe_rmat(s, d) -> DataFrame:
    """Mean frontier at each level over 256 searches of the scale-free graph."""
    m = G.rmat(s, FRINGE_SCALE)
    found = W.bfs(m, s.range(0, m.nrows, FRINGE_STEP))
    return found.groupBy("level").agg(F.count(F.lit(1)).alias("vertices"), F.round(F.count(F.lit(1)) * FRINGE_STEP / m.nrows, 6).alias("mean"))


def _between_sql(edges: str = SUCC, sources: str = "VALUES (1), (2)", levels: int = LEVELS) -> str:
    """Dependencies of the vertices on shortest paths from the sources, level by level from the last."""
    bfs = _bfs_sql(edges, sources, levels)
    head, _ = bfs.rsplit(" SELECT * FROM ", 1)
    out = head + f", d{levels} AS (SELECT *, CAST(0 AS DOUBLE) AS dep FROM l{levels})"
    for k in range(levels - 1, -1, -1):
        out += f", d{k} AS MATERIALIZED (SELECT h.source, h.vertex, h.level, h.paths, h.parent, coalesce(sum(h.paths / CAST(b.paths AS DOUBLE) * (1 + b.dep)), 0) AS dep FROM l{k} h LEFT JOIN (SELECT e.i, d.* FROM e JOIN d{k + 1} d ON d.vertex = e.j) b ON b.i = h.vertex AND b.source = h.source GROUP BY ALL)"
    every = " UNION ALL ".join(f"SELECT * FROM d{k}" for k in range(levels + 1))
    return f"{out} SELECT vertex, round(sum(dep), 6) AS score FROM ({every}) t WHERE source <> vertex GROUP BY 1"


def _parts_sql(sweeps: int = SWEEPS) -> str:
    """Least vertex of each component: labels spread along edges until they rest, which these graphs do long before the last sweep."""
    out = f"e AS MATERIALIZED ({BIP}), c0 AS (SELECT DISTINCT i AS v, i AS r FROM e)"
    for k in range(1, sweeps + 1):
        out += f", c{k} AS MATERIALIZED (SELECT c.v, least(c.r, n.r) AS r FROM c{k - 1} c JOIN (SELECT e.i, min(x.r) AS r FROM e JOIN c{k - 1} x ON x.v = e.j GROUP BY 1) n ON n.i = c.v)"
    return f"WITH {out} SELECT v AS node, r AS root FROM c{sweeps} WHERE v <> r"


def _cycles_sql(rounds: int = ROUNDS) -> str:
    out = f"p0 AS MATERIALIZED (SELECT i, j FROM ({SUCC}) t)"
    for k in range(1, rounds + 1):
        out += f", p{k} AS MATERIALIZED (SELECT i, j FROM p{k - 1} WHERE i IN (SELECT j FROM p{k - 1}) AND j IN (SELECT i FROM p{k - 1}))"
    return f"WITH {out} SELECT count(*) AS edges, count(DISTINCT i) AS vertices FROM p{rounds}"


def _markov_sql(rounds: int = 40) -> str:
    """Expansion, inflation and pruning, so many times, far beyond the round in which they rest."""
    normal = lambda name, sql: f"{name} AS MATERIALIZED (SELECT i, j, v / sum(v) OVER (PARTITION BY j) AS v FROM ({sql}) z)"
    both = f"SELECT * FROM ({NN}) a UNION ALL {t_sql(NN)} UNION ALL SELECT r, r, 1 FROM range(25) x(r)"
    out = normal("m0", f"SELECT i, j, CAST(sum(v) AS DOUBLE) AS v FROM ({both}) n GROUP BY 1, 2")
    for k in range(1, rounds + 1):
        square = f"SELECT a.i, b.j, power(sum(a.v * b.v), 2.0) AS v FROM m{k - 1} a JOIN m{k - 1} b ON a.j = b.i GROUP BY 1, 2"
        out += ", " + normal(f"x{k}", square) + ", " + normal(f"m{k}", f"SELECT * FROM x{k} WHERE v > 1e-3")
    return f"WITH {out} SELECT j AS vertex, arg_max(i, (round(v, 9), -i)) AS cluster FROM m{rounds} GROUP BY 1"


def _restricted(s, m: SparseMatrix, order: int, both: bool, mode: str = "consecutive") -> DataFrame:
    """A S' or S A S' as products with the restriction matrix."""
    r = G.restriction(s, m.ncols, order, mode)
    return (W.contract(m, r) if both else W.restrict_right(m, r)).df


def _restricted_sql(m: str, n: int | str, order: int, both: bool, mode: str = "consecutive") -> str:
    if mode == "consecutive":
        return f"SELECT i{f' // {order}' if both else ''} AS i, j // {order} AS j, CAST(sum(v) AS BIGINT) AS v FROM ({m}) t GROUP BY 1, 2"
    p = G.random_permutation_sql(n, 1)
    return f"SELECT p.j // {order} AS i, r.j // {order} AS j, CAST(sum(m.v) AS BIGINT) AS v FROM ({m}) m JOIN ({p}) p ON p.i = m.i JOIN ({p}) r ON r.i = m.j GROUP BY 1, 2"


def _fringe(df: DataFrame) -> DataFrame:
    return df.groupBy("level").agg(F.count(F.lit(1)).alias("vertices"), F.round(F.count(F.lit(1)) / len(SOURCES), 6).alias("mean"))


def _weights(s, d) -> DataFrame:
    a, sizes = fixture(s, d, "OP"), fixture(s, d, "BW")
    return W.restrict_right(a, sizes).df


def _gal(s, d) -> DataFrame:
    r = fixture(s, d, "BR")
    return W.contract(SparseMatrix(relational(fixture(s, d, "OP").T, fixture(s, d, "OP")).df, r.ncols, r.ncols), r).df


def _tags(s, d) -> DataFrame:
    html = table(s, d, "pages").select(F.col("page_id").alias("doc"), F.regexp_extract_all("html", F.lit(f"<(/?(?:{'|'.join(TAGS)}))[ >]"), 1).alias("t"))
    at = html.select("doc", F.posexplode("t").alias("i", "symbol"))
    return at.select("symbol", "doc", F.col("i").cast("long").alias("i"), (F.col("i") + 1).cast("long").alias("j"))


#: An element is an open and a close tag, perhaps with a sequence of elements between.
RULES = [r for t in TAGS for r in (("E", t, f"/{t}"), ("E", t, f"C_{t}"), (f"C_{t}", "E", f"/{t}"))] + [("E", "E", "E")]


def _cfl(s, d) -> DataFrame:
    return W.cfl_reach(_tags(s, d), RULES).filter("symbol = 'E'").select("doc", "i", "j")


def _cfl_sql(rounds: int = ROUNDS) -> str:
    """As many rounds as leave no span out on the given pages; spans double in each."""
    rules = ", ".join(f"('{a}', '{b}', '{c}')" for a, b, c in RULES)
    out = f"""r(head, l, r) AS (VALUES {rules}),
t0 AS (SELECT page_id AS doc, regexp_extract_all(html, '<(/?(?:{'|'.join(TAGS)}))[ >]', 1) AS t FROM pages),
s0 AS MATERIALIZED (SELECT DISTINCT t[k] AS symbol, doc, k - 1 AS i, k AS j FROM (SELECT doc, t, unnest(range(1, len(t) + 1)) AS k FROM t0) x)"""
    for k in range(1, rounds + 1):
        out += f", s{k} AS MATERIALIZED (SELECT * FROM s{k - 1} UNION SELECT r.head, a.doc, a.i, b.j FROM s{k - 1} a JOIN r ON r.l = a.symbol JOIN s{k - 1} b ON b.symbol = r.r AND b.doc = a.doc AND b.i = a.j)"
    return f"WITH {out} SELECT doc, i, j FROM s{rounds} WHERE symbol = 'E'"


def _reach_sql() -> str:
    edges = "SELECT i, j FROM m UNION SELECT i, i FROM m UNION SELECT j, j FROM m"
    return f"WITH m AS ({SQL['NN']}), e AS ({edges}), a AS (SELECT DISTINCT x.i, y.j FROM e x JOIN e y ON x.j = y.i), b AS (SELECT DISTINCT x.i, y.j FROM a x JOIN a y ON x.j = y.i) SELECT i, j, CAST(1 AS BIGINT) AS v FROM b"


def _nn(s, d) -> SparseMatrix:
    return fixture(s, d, "NN")


def _both_ways(s, d) -> SparseMatrix:
    """Trade between nations in either direction, with a loop at each."""
    m = _nn(s, d)
    return S.add(S.add(m, m.T), S.eye(s, m.nrows))


def _bench_words(s, d) -> SparseMatrix:
    words = table(s, d, "benchmark").select(F.col("item_id").alias("i"), F.explode(F.split(F.lower("text"), " ")).alias("j")).filter("j <> ''").distinct()
    return SparseMatrix(words.withColumn("v", F.lit(1).cast("long")), 1 << 40, 1 << 40)


def _doc_words(s, d) -> SparseMatrix:
    """Words are told from their repeats within the rows of documents; only where an id repeats, across rows too."""
    docs = table(s, d, "documents").select(F.col("doc_id").alias("i"), "text")
    words = docs.select("i", F.explode(F.array_distinct(F.split(F.lower("text"), " "))).alias("j")).filter("j <> ''")
    if not docs.groupBy("i").count().filter("count > 1").isEmpty():
        words = words.repartition("i").distinct().sortWithinPartitions("i")
    return SparseMatrix(words.withColumn("v", F.lit(1).cast("long")), 1 << 40, 1 << 40)


def _gram(s, d) -> DataFrame:
    e = table(s, d, "embeddings").select(F.col("vec_id").alias("i"), F.posexplode("embedding").alias("j", "x"))
    m = SparseMatrix(e.select("i", F.col("j").cast("long").alias("j"), F.round(F.col("x").cast("double") * 1000, 0).cast("long").alias("v")), 1 << 40, 64)
    return relational(m.T, m).df


def _model_from(s, d) -> DataFrame:
    """Modelled speed-ups for a matrix of the size and density of the given one."""
    m = fixture(s, d, "OP")
    n = m.df.agg(F.countDistinct("i").alias("n"), (F.count(F.lit(1)) / F.countDistinct("i")).alias("c"))
    points = n.select("n", "c", F.explode(F.array(*[F.lit(4**k).cast("long") for k in range(7)])).alias("p"))
    t = model.times(points)
    return t.select("n", "p", F.round("c", 6).alias("c"), F.round(F.col("w") / (F.col("comm1") + F.col("w") / F.col("p")), 6).alias("one_d"), F.round(F.col("w") / (F.col("comm2") + F.col("comp2")), 6).alias("two_d"), F.round(F.col("w") / F.greatest("comm2", "comp2"), 6).alias("overlapped"))


def _model_sql() -> str:
    g, h, a, beta = model.GAMMA_CLASSICAL, model.GAMMA_HYPERSPARSE, model.ALPHA, model.BETA_BYTE * 24
    return f"""WITH m AS (SELECT count(DISTINCT i) AS n, CAST(count(*) AS DOUBLE) / count(DISTINCT i) AS c FROM ({OP}) t),
q AS (SELECT n, c, CAST(power(4, k) AS BIGINT) AS p, CAST(power(2, k) AS BIGINT) AS s FROM m, range(7) r(k)),
e AS (SELECT *, least(1.0, c / s) * n / s AS ids, least(1.0, c * c / p) * n / s AS ni, c * c * n / (CAST(p AS DOUBLE) * s) AS fl, {g!r} * c * c * n AS w FROM q),
x AS (SELECT *, (p - 1) * ({a!r} + {beta!r} * c * n / p) AS c1, s * ({2 * a!r} + {beta!r} * 2 * c * n / p) AS c2, {h!r} * (s * (2 * ids + fl * greatest(log2(greatest(ni, 1.0)), 1.0)) + fl * lgamma(s + 1) / ln(2)) AS cp FROM e)
SELECT n, p, round(c, 6) AS c, round(w / (c1 + w / p), 6) AS one_d, round(w / (c2 + cp), 6) AS two_d, round(w / greatest(c2, cp), 6) AS overlapped FROM x"""


#: Entries that each column of the tall-skinny right operand has on average, from far fewer than one product a row to dense.
PER_COLUMN = (1, 10, 100, 1000)


def _tall_rmat(s, d) -> DataFrame:
    """Entries and products of the scale-free matrix by ever denser tall-skinny ones."""
    a, out = stored(G.rmat(s, 10)), None
    for c in PER_COLUMN:
        b = stored(G.tall_skinny(s, 1024, 16, c))
        made = relational(a, b, "plus_pair").df.agg(F.lit(c).cast("long").alias("per_column"), F.count(F.lit(1)).alias("entries"), F.sum("v").cast("long").alias("products"))
        out = made if out is None else out.unionByName(made)
    return out


def _on_parts(s, d, make) -> DataFrame:
    """A generated matrix on the ids of parts: ``make`` has one more than the greatest, and the ids."""
    ids = table(s, d, "part").select(F.col("p_partkey").alias("id"))
    return make((ids.agg(F.max("id")).first()[0] or 0) + 1, ids).df


def _dimension_bound(s, d) -> DataFrame:
    """Whether walking all orders of all blocks, n sqrt(p), outweighs the products of parts bought together."""
    b = stored(fixture(s, d, "OP"))
    sides = s.createDataFrame([(1 << k,) for k in range(7)], "side long")
    n = F.lit(b.nrows).cast("long")
    return flops(b.T, b).crossJoin(F.broadcast(sides)).select(n.alias("n"), (F.col("side") * F.col("side")).alias("p"), (n * F.col("side") >= F.col("flops")).alias("dominated"))


PART_IDS, N_PARTS = "(SELECT p_partkey AS id FROM part) r", "(SELECT max(p_partkey) + 1 FROM part)"


def _mesh_sql() -> str:
    side = f"(SELECT min(k) FROM range(1, 10000) s(k) WHERE k * k * k >= {N_PARTS})"
    return f"""SELECT id AS i, x + a + (y + b) * m + (z + c) * m * m AS j, CAST(1 AS BIGINT) AS v
FROM (SELECT id, m, id % m AS x, id // m % m AS y, id // (m * m) AS z FROM {PART_IDS}, (SELECT {side} AS m) q),
(VALUES (0,0,0),(1,0,0),(-1,0,0),(0,1,0),(0,-1,0),(0,0,1),(0,0,-1)) s(a,b,c)
WHERE x + a BETWEEN 0 AND m - 1 AND y + b BETWEEN 0 AND m - 1 AND z + c BETWEEN 0 AND m - 1 AND x + a + (y + b) * m + (z + c) * m * m IN (SELECT p_partkey FROM part)"""


def queries() -> dict:
    bip = lambda s, d: fixture(s, d, "BIP")
    out = {k: (lambda f: lambda s, d: f(s))(getattr(model, k)) for k in model.SQL}
    out |= {
        "model_from_lineitem": _model_from,
        "gen_rmat": lambda s, d: G.rmat(s, 10, ids=table(s, d, "events").select(F.col("event_id").alias("id"))).df,
        "gen_rmat_large": lambda s, d: G.rmat_large(s, 12).df,
        "gen_uniform": lambda s, d: G.erdos_renyi(s, 1024, 8).df,
        "gen_grid3d": lambda s, d: _on_parts(s, d, lambda n, ids: G.grid3d(s, next(k for k in count(1) if k**3 >= n), ids)),
        "gen_permutation": lambda s, d: _on_parts(s, d, lambda n, ids: G.permutation(s, n, ids=ids)),
        "gen_tall_skinny": lambda s, d: G.tall_skinny(s, 4096, 16, 100).df,
        "gen_restriction": lambda s, d: _on_parts(s, d, lambda n, ids: G.restriction(s, n, 4, ids=ids)),
        "rmat_square": lambda s, d: relational(G.rmat(s, 10), G.rmat(s, 10)).df,
        "grid3d_square": lambda s, d: relational(G.grid3d(s, 8), G.grid3d(s, 8)).df,
        "rand_square": lambda s, d: relational(G.erdos_renyi(s, 1024, 8), G.erdos_renyi(s, 1024, 8)).df,
        "product_permutation": lambda s, d: relational(fixture(s, d, "SUCC"), G.permutation(s, fixture(s, d, "SUCC").ncols, 7, 3)).df,
        "permute_by_join": lambda s, d: S.permute_by(fixture(s, d, "SUCC"), G.permutation(s, fixture(s, d, "SUCC").ncols, 7, 3)).df,
        "square_product": lambda s, d: relational(bip(s, d), bip(s, d)).df.groupBy("i").agg(F.count(F.lit(1)).alias("nnz"), F.sum("v").cast("long").alias("walks")),
        "two_hop_parts": lambda s, d: relational(fixture(s, d, "SUCC"), fixture(s, d, "SUCC"), "plus_pair").df.groupBy("i").agg(F.count(F.lit(1)).alias("parts"), F.sum("v").cast("long").alias("ways")),
        "markov_expand": lambda s, d: W.markov_expand(_nn(s, d)).df,
        "markov_cluster": lambda s, d: W.markov_cluster(_both_ways(s, d)),
        "benchmark_overlap": lambda s, d: relational(_doc_words(s, d), _bench_words(s, d).T, salt="auto").df,
        "bfs_levels": lambda s, d: _bfs(s, d).select("source", "vertex", "level"),
        "bfs_path_counts": lambda s, d: _bfs(s, d).select("source", "vertex", "level", "paths"),
        "bfs_fringe_profile": lambda s, d: _fringe(_bfs(s, d)),
        "betweenness": lambda s, d: W.betweenness(fixture(s, d, "SUCC"), s.createDataFrame([(1,), (2,)], "id long")),
        "betweenness_batches": lambda s, d: W.betweenness(G.rmat(s, 7), s.range(128), batches=4),
        "contract_nation": lambda s, d: relational(fixture(s, d, "RN"), fixture(s, d, "NR")).df,
        "contract_weighted": _weights,
        "galerkin_product": _gal,
        "contraction_profile": lambda s, d: _profile(s, d),
        "peer_pressure_round": lambda s, d: W.peer_pressure(fixture(s, d, "SUCC"), 1),
        "apsp_nation": lambda s, d: W.apsp(_nn(s, d)).df,
        "apsp_recursive": lambda s, d: W.apsp_recursive(_nn(s, d)).df,
        "apsp_two_hop": lambda s, d: W.apsp(_nn(s, d), 2).df,
        "matching_round": lambda s, d: W.matching_round(fixture(s, d, "OP")),
        "greedy_matching": lambda s, d: W.greedy_matching(fixture(s, d, "PS")),
        "cycle_lengths": lambda s, d: W.closed_walks(fixture(s, d, "SUCC"), 3),
        "triangle_count": lambda s, d: W.triangles(fixture(s, d, "SUCC")),
        "cfl_tags": _cfl,
        "reachability_k": lambda s, d: W.reach_k(_nn(s, d), 2).df,
        "connected_parts": lambda s, d: connected_components(table(s, d, "lineitem").select(F.col("l_orderkey").alias("u"), (F.col("l_partkey") + PART_OFFSET).alias("v"))),
        "doc_overlap_topk": lambda s, d: W.topk_overlap(_doc_words(s, d), 3),
        "cosine_topk": lambda s, d: W.cosine_topk(fixture(s, d, "UH"), 3),
        "user_hour_overlap": lambda s, d: W.gram(fixture(s, d, "UH")).df,
        "bfs_parents": lambda s, d: _bfs(s, d).select("source", "vertex", "parent"),
        "bfs_fringe_rmat": _fringe_rmat,
        "cycle_edges": lambda s, d: W.on_cycles(fixture(s, d, "SUCC")).agg(F.count(F.lit(1)).alias("edges"), F.countDistinct("i").alias("vertices")),
        "peer_pressure": lambda s, d: W.peer_pressure(fixture(s, d, "SUCC"), None),
        "tall_skinny_rmat": _tall_rmat,
        "balanced_cuts": lambda s, d: S.balanced_cuts(stored(fixture(s, d, "OP")), 16),
        "gen_random_permutation": lambda s, d: _on_parts(s, d, lambda n, ids: G.random_permutation(s, n, ids=ids)),
        "gen_restriction_random": lambda s, d: _on_parts(s, d, lambda n, ids: G.restriction(s, n, 4, "random", ids=ids)),
        "dimension_bound": _dimension_bound,
        "rmat_edges": lambda s, d: rmat_by_function(s, 8),
        "embedding_gram": _gram,
    }
    for r in ORDERS:
        out[f"restrict_right_{r}"] = (lambda r: lambda s, d: _restricted(s, fixture(s, d, "BG"), r, False))(r)
        out[f"contract_{r}"] = (lambda r: lambda s, d: _restricted(s, fixture(s, d, "BG"), r, True))(r)
        out[f"contract_rmat_{r}"] = (lambda r: lambda s, d: _restricted(s, fixture(s, d, "SUCC"), r, True, "random"))(r)
        out[f"contract_by_sums_{r}"] = (lambda r: lambda s, d: W.halve(fixture(s, d, "BG"), r).df)(r)
    return out


def _profile(s, d) -> DataFrame:
    m, out = stored(fixture(s, d, "BG")), None
    for r in ORDERS:
        row = _restricted(s, m, r, True).agg(F.lit(r).cast("long").alias("coarsening"), F.count(F.lit(1)).alias("nnz"), F.countDistinct("i").alias("vertices"))
        out = row if out is None else out.unionByName(row)
    return out


def _apsp_sql(doublings: int) -> str:
    z = "SELECT CAST(r AS BIGINT) AS i, CAST(r AS BIGINT) AS j, CAST(0 AS BIGINT) AS v FROM range(25) x(r)"
    out = f"d0 AS (SELECT i, j, min(v) AS v FROM (SELECT * FROM ({NN}) n UNION ALL {z}) t GROUP BY 1, 2)"
    for k in range(1, doublings + 1):
        out += f", d{k} AS (SELECT a.i, b.j, min(a.v + b.v) AS v FROM d{k - 1} a JOIN d{k - 1} b ON a.j = b.i GROUP BY 1, 2)"
    return f"WITH {out} SELECT * FROM d{doublings}"


def oracle_sql() -> dict[str, str]:
    n_part = "(SELECT max(p_partkey) + 1 FROM part)"
    perm = f"SELECT i, (j * 7 + 3) % {n_part} AS j, v FROM ({SUCC}) t"
    pagg = f"SELECT j AS vertex, i AS cluster, CAST(sum(v) AS BIGINT) AS n FROM ({SUCC}) t GROUP BY 1, 2 UNION ALL SELECT i, i, 0 FROM (SELECT DISTINCT i FROM ({SUCC}) u WHERE i NOT IN (SELECT j FROM ({SUCC}) w)) x"
    r10, e = G.rmat_sql(10), G.tall_skinny_sql(1024, 1024, 8)
    out = model.SQL | {
        "model_from_lineitem": _model_sql(),
        "gen_rmat": G.rmat_sql(10, ids="(SELECT event_id AS id FROM events) r"),
        "gen_uniform": e,
        "gen_grid3d": _mesh_sql(),
        "gen_permutation": f"SELECT id AS i, (id * 389 + 17) % {N_PARTS} AS j, CAST(1 AS BIGINT) AS v FROM {PART_IDS}",
        "gen_tall_skinny": G.tall_skinny_sql(4096, 16, 100),
        "gen_restriction": f"SELECT id // 4 AS i, id AS j, CAST(1 AS BIGINT) AS v FROM {PART_IDS}",
        "rmat_square": product_sql(r10, r10),
        "grid3d_square": product_sql(G.grid3d_sql(8), G.grid3d_sql(8)),
        "rand_square": product_sql(e, e),
        "product_permutation": perm,
        "permute_by_join": perm,
        "square_product": f"SELECT i, count(*) AS nnz, CAST(sum(v) AS BIGINT) AS walks FROM ({product_sql(BIP, BIP)}) t GROUP BY 1",
        "two_hop_parts": f"SELECT i, count(*) AS parts, CAST(sum(v) AS BIGINT) AS ways FROM ({product_sql(SUCC, SUCC, 'plus_pair')}) t GROUP BY 1",
        "markov_expand": f"WITH n AS ({NN}), m AS (SELECT i, j, CAST(floor(v * 1000000 / sum(v) OVER (PARTITION BY j)) AS BIGINT) AS v FROM n) SELECT a.i, b.j, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM m a JOIN m b ON a.j = b.i GROUP BY 1, 2",
        "benchmark_overlap": f"WITH b AS ({DOC_WORDS}), d AS ({DOC_WORDS.replace('item_id', 'doc_id').replace('benchmark', 'documents')}) SELECT d.i, b.i AS j, count(*) AS v FROM d JOIN b ON d.j = b.j GROUP BY 1, 2",
        "bfs_levels": f"SELECT source, vertex, level FROM ({_bfs_sql()}) t",
        "bfs_path_counts": f"SELECT source, vertex, level, paths FROM ({_bfs_sql()}) t",
        "bfs_parents": f"SELECT source, vertex, parent FROM ({_bfs_sql()}) t",
        "bfs_fringe_rmat": f"SELECT level, count(*) AS vertices, round(count(*) * {FRINGE_STEP} / CAST({1 << FRINGE_SCALE} AS DOUBLE), 6) AS mean FROM ({_bfs_sql(G.rmat_sql(FRINGE_SCALE), f'SELECT * FROM range(0, {1 << FRINGE_SCALE}, {FRINGE_STEP})', ROUNDS)}) t GROUP BY 1",
        "betweenness": _between_sql(),
        "betweenness_batches": _between_sql(G.rmat_sql(7), "SELECT * FROM range(128)"),
        "connected_parts": _parts_sql(),
        "cycle_edges": _cycles_sql(),
        "markov_cluster": _markov_sql(),
        "tall_skinny_rmat": " UNION ALL ".join(f"SELECT CAST({c} AS BIGINT) AS per_column, count(*) AS entries, CAST(sum(v) AS BIGINT) AS products FROM ({product_sql(r10, G.tall_skinny_sql(1024, 16, c), 'plus_pair')}) t" for c in PER_COLUMN),
        "balanced_cuts": f"WITH m AS ({OP}), d AS (SELECT i, count(*) AS n FROM m GROUP BY 1), p AS (SELECT *, CAST(sum(n) OVER (ORDER BY i) - n AS BIGINT) * 16 // (SELECT count(*) FROM m) AS part FROM d) SELECT part, min(i) AS first, max(i) AS last, CAST(sum(n) AS BIGINT) AS nnz FROM p GROUP BY 1",
        "gen_random_permutation": G.random_permutation_sql(0, ids=PART_IDS),
        "gen_restriction_random": f"SELECT j // 4 AS i, i AS j, CAST(1 AS BIGINT) AS v FROM ({G.random_permutation_sql(0, ids=PART_IDS)}) p",
        "dimension_bound": f"SELECT CAST(n AS BIGINT) AS n, CAST(s * s AS BIGINT) AS p, n * s >= flops AS dominated FROM (SELECT max(o_orderkey) + 1 AS n FROM orders) o, (SELECT sum(c * c) AS flops FROM (SELECT i, count(*) AS c FROM ({OP}) t GROUP BY 1) g) f, (VALUES (1), (2), (4), (8), (16), (32), (64)) y(s)",
        "rmat_edges": G.rmat_sql(8),
        "cosine_topk": f"WITH m AS ({UH}), n AS (SELECT i, sqrt(sum(v * v)) AS n FROM m GROUP BY 1), p AS (SELECT a.i, b.i AS j, sum(a.v * b.v) AS d FROM m a JOIN m b ON a.j = b.j AND a.i <> b.i GROUP BY 1, 2), c AS (SELECT p.i, p.j, round(d / (x.n * y.n), 6) AS similarity FROM p JOIN n x ON x.i = p.i JOIN n y ON y.i = p.j) SELECT i, j, similarity, rank FROM (SELECT *, row_number() OVER (PARTITION BY i ORDER BY similarity DESC, j) AS rank FROM c) t WHERE rank <= 3",
        "bfs_fringe_profile": f"SELECT level, count(*) AS vertices, round(count(*) / CAST({len(SOURCES)} AS DOUBLE), 6) AS mean FROM ({_bfs_sql()}) t GROUP BY 1",
        "contract_nation": product_sql(SQL["RN"], SQL["NR"]),
        "contract_weighted": product_sql(OP, t_sql(SQL["BW"])),
        "galerkin_product": product_sql(product_sql(SQL["BR"], product_sql(t_sql(OP), OP)), t_sql(SQL["BR"])),
        "contraction_profile": " UNION ALL ".join(f"SELECT CAST({r} AS BIGINT) AS coarsening, count(*) AS nnz, count(DISTINCT i) AS vertices FROM ({_restricted_sql(SQL['BG'], 0, r, True)}) h" for r in ORDERS),
        "peer_pressure_round": f"SELECT vertex, cluster FROM (SELECT *, row_number() OVER (PARTITION BY vertex ORDER BY n DESC, cluster) AS r FROM ({pagg}) p) t WHERE r = 1",
        "apsp_nation": _apsp_sql(5),
        "apsp_recursive": _apsp_sql(5),
        "apsp_two_hop": _apsp_sql(1),
        "matching_round": f"SELECT min(i) AS i, j FROM (SELECT i, min(j) AS j FROM ({OP}) t GROUP BY 1) p GROUP BY j",
        "cycle_lengths": f"WITH m AS ({SUCC}) SELECT CAST(2 AS BIGINT) AS k, CAST(sum(a.v * b.v) AS BIGINT) AS closed_walks FROM m a JOIN m b ON a.j = b.i AND a.i = b.j UNION ALL SELECT 3, CAST(sum(a.v * b.v * c.v) AS BIGINT) FROM m a JOIN m b ON a.j = b.i JOIN m c ON b.j = c.i AND c.j = a.i",
        "triangle_count": f"WITH m AS ({SUCC}) SELECT a.i AS vertex, count(*) AS n FROM m a JOIN m b ON a.j = b.i JOIN m c ON b.j = c.i AND c.j = a.i GROUP BY 1",
        "cfl_tags": _cfl_sql(),
        "reachability_k": _reach_sql(),
        "doc_overlap_topk": f"WITH w AS ({DOC_WORDS.replace('item_id', 'doc_id').replace('benchmark', 'documents')}), p AS (SELECT a.i, b.i AS j, count(*) AS dot FROM w a JOIN w b ON a.j = b.j AND a.i < b.i GROUP BY 1, 2) SELECT i, j, dot, rank FROM (SELECT *, row_number() OVER (PARTITION BY i ORDER BY dot DESC, j) AS rank FROM p) t WHERE rank <= 3",
        "user_hour_overlap": product_sql(UH, t_sql(UH)),
        "embedding_gram": "WITH e AS (SELECT vec_id AS i, k - 1 AS j, CAST(round(CAST(embedding[k] AS DOUBLE) * 1000, 0) AS BIGINT) AS v FROM (SELECT vec_id, embedding, unnest(range(1, 65)) AS k FROM embeddings) t) SELECT a.j AS i, b.j, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM e a JOIN e b ON a.i = b.i GROUP BY 1, 2",
    }
    bg = SQL["BG"]
    for r in ORDERS:
        out |= {f"restrict_right_{r}": _restricted_sql(bg, 0, r, False), f"contract_{r}": _restricted_sql(bg, 0, r, True), f"contract_by_sums_{r}": _restricted_sql(bg, 0, r, True), f"contract_rmat_{r}": _restricted_sql(SUCC, N_PARTS, r, True, "random")}
    return out
