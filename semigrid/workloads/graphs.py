"""Graph workloads as sequences of sparse products; loops cut their lineage with written tables."""

from __future__ import annotations

from itertools import count

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from semigrid.matrix import SparseMatrix
from semigrid.operators import structure as S
from semigrid.plans import overlaps, tiles
from semigrid.plans.multiply import relational
from semigrid.plans.scratch import materialize


def bfs(a: SparseMatrix, sources: DataFrame, max_level: int | None = None) -> DataFrame:
    """(source, vertex, level, paths, parent): levels from many sources at once, with the number of shortest paths and the least vertex before.

    A step is the frontier times the graph, without what was visited. It ends with an
    empty frontier; vertices beyond ``max_level`` are an error, not left out. The edges are
    written once, by vertex, before the first step.
    """
    start = F.lit(0).cast("long")
    frontier = sources.select(F.col("id").alias("source"), F.col("id").alias("vertex"), start.alias("level"), F.lit(1).cast("long").alias("paths"), F.lit(None).cast("long").alias("parent"))
    seen = frontier = materialize(frontier, "bfs")
    edges = materialize(a.df.select(F.col("i").alias("vertex"), F.col("j").alias("to")).repartition("vertex").sortWithinPartitions("vertex"), "edges")
    for level in count(1):
        step = frontier.join(edges, "vertex").groupBy("source", F.col("to").alias("next")).agg(F.sum("paths").alias("paths"), F.min("vertex").alias("parent")).withColumnRenamed("next", "vertex")
        step = step.join(seen.select("source", "vertex"), ["source", "vertex"], "left_anti")
        frontier = materialize(step.select("source", "vertex", F.lit(level).cast("long").alias("level"), "paths", "parent"), "bfs")
        if frontier.isEmpty():
            break
        if max_level is not None and level > max_level:
            raise RuntimeError(f"vertices beyond level {max_level}")
        seen = seen.unionByName(frontier)
    return seen


def betweenness(a: SparseMatrix, sources: DataFrame, max_level: int | None = None, batches: int = 1) -> DataFrame:
    """(vertex, score) from the given sources: forward path counts, then dependencies level by level.

    Sources go in so many ``batches``, one after the other: what is kept for a batch is its
    sources times the vertices they reach.
    """
    graph = a.with_df(materialize(a.df.select("i", "j"), "edges"))
    parts = [_dependencies(graph, sources.filter(F.pmod(F.xxhash64("id"), F.lit(batches)) == k), max_level) for k in range(batches)]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.groupBy("vertex").agg(F.round(F.sum("dep"), 6).alias("score"))


def _dependencies(a: SparseMatrix, sources: DataFrame, max_level: int | None) -> DataFrame:
    """(vertex, dep): what each vertex adds for each source but itself."""
    found = materialize(bfs(a, sources, max_level), "forward")
    deepest = found.agg(F.max("level")).first()[0] or 0
    edges = materialize(a.df.select(F.col("i").alias("vertex"), F.col("j").alias("to")).repartition("vertex"), "edges")
    below: DataFrame | None = None
    parts = []
    for level in range(deepest, -1, -1):
        here = found.filter(F.col("level") == level)
        if below is None:
            below = here.withColumn("dep", F.lit(0.0))
        else:
            down = here.join(edges, "vertex").join(below.select("source", F.col("vertex").alias("to"), F.col("paths").alias("p2"), "dep"), ["source", "to"])
            share = down.groupBy("source", "vertex").agg(F.sum(F.col("paths") / F.col("p2") * (1 + F.col("dep"))).alias("dep"))
            below = here.join(share, ["source", "vertex"], "left").fillna(0.0, ["dep"])
        below = materialize(below, "dependency")
        parts.append(below.filter("source <> vertex").select("vertex", "dep"))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def restrict_right(a: SparseMatrix, s: SparseMatrix) -> SparseMatrix:
    return relational(a, s.T)


def contract(a: SparseMatrix, s: SparseMatrix) -> SparseMatrix:
    """S A S': vertices of a group become one."""
    return relational(relational(s, a), s.T)


def halve(a: SparseMatrix, order: int, both: bool = True) -> SparseMatrix:
    """Contraction of consecutive ids without a restriction table: a projection and a sum."""
    i = F.floor(F.col("i") / order).cast("long") if both else F.col("i")
    df = a.df.select(i.alias("i"), F.floor(F.col("j") / order).cast("long").alias("j"), "v").groupBy("i", "j").agg(F.sum("v").alias("v"))
    return SparseMatrix(df, -(-a.nrows // order) if both else a.nrows, -(-a.ncols // order))


def markov_expand(a: SparseMatrix, unit: int = 1_000_000) -> SparseMatrix:
    """Square of the column-stochastic matrix, in whole parts of ``unit`` so that sums are exact."""
    total = a.df.groupBy("j").agg(F.sum("v").alias("t"))
    m = a.with_df(a.df.join(total, "j").select("i", "j", F.floor(F.col("v") * unit / F.col("t")).cast("long").alias("v")))
    return relational(m, m)


def markov_cluster(a: SparseMatrix, inflation: float = 2.0, prune: float = 1e-3, settled: float = 1e-9, most: int = 200) -> DataFrame:
    """(vertex, cluster): expansion, inflation and pruning, repeated until no entry moves by ``settled``; a column belongs to its largest row.

    Not to settle within ``most`` rounds is an error.
    """

    def normal(df: DataFrame) -> DataFrame:
        return df.join(df.groupBy("j").agg(F.sum("v").alias("t")), "j").select("i", "j", (F.col("v") / F.col("t")).alias("v"))

    now = materialize(normal(a.df.withColumn("v", F.col("v").cast("double"))), "markov")
    for _ in range(most):
        m = a.with_df(now)
        squared = relational(m, m).df
        new = materialize(normal(normal(squared.withColumn("v", F.pow("v", F.lit(inflation)))).filter(F.col("v") > prune)), "markov")
        both = now.join(new.withColumnRenamed("v", "w"), ["i", "j"], "full")
        moved = both.agg(F.max(F.abs(F.coalesce("v", F.lit(0.0)) - F.coalesce("w", F.lit(0.0))))).first()[0] or 0.0
        now = new
        if moved <= settled:
            best = F.max_by("i", F.struct(F.round("v", 9), -F.col("i")))
            return now.groupBy(F.col("j").alias("vertex")).agg(best.alias("cluster"))
    raise RuntimeError("the clusters did not settle")


def peer_pressure(a: SparseMatrix, rounds: int | None = 1, most: int = 1000) -> DataFrame:
    """(vertex, cluster): each vertex takes the cluster that most of its neighbours have; ties go to the smaller.

    Without ``rounds``, until nothing changes or an earlier state returns (votes may swing);
    of the states that return in turn, the first is taken. Vertices without an edge into
    them keep their own cluster.
    """
    ids = a.df.select(F.col("i").alias("vertex")).union(a.df.select("j")).distinct()
    now, seen = ids.withColumn("cluster", F.col("vertex")), {}
    edges = materialize(a.df, "edges") if rounds is None else a.df
    for k in range(most if rounds is None else rounds):
        votes = edges.join(now.select(F.col("vertex").alias("i"), "cluster"), "i").groupBy(F.col("j").alias("vertex"), "cluster").agg(F.sum("v").alias("n"))
        chosen = votes.groupBy("vertex").agg(F.max_by("cluster", F.struct("n", -F.col("cluster"))).alias("new"))
        now = materialize(now.join(chosen, "vertex", "left").select("vertex", F.coalesce("new", "cluster").alias("cluster")), "votes")
        if rounds is None:
            state = tuple(now.agg(F.bit_xor(F.xxhash64("vertex", "cluster")), F.sum(F.hash("vertex", "cluster").cast("long"))).first())
            if state in seen:
                return seen[state]
            seen[state] = now
    if rounds is None:
        raise RuntimeError("the votes did not settle")
    return now


def apsp(a: SparseMatrix, max_hops: int | None = None) -> SparseMatrix:
    """Shortest paths by repeated min-plus squaring; ``max_hops`` 2 squares once."""
    loops = S.eye(a.df.sparkSession, a.nrows).df.withColumn("v", F.lit(0).cast("long"))
    now = S.add(a, a.with_df(loops), "min_plus")
    hops = 1
    while hops < (max_hops or a.nrows):
        now = now.with_df(materialize(relational(now, now, "min_plus").df, "apsp"))
        hops *= 2
    return now


def apsp_recursive(a: SparseMatrix, leaf: int = 8) -> SparseMatrix:
    """Shortest paths by halves: the matrix is cut in two by two blocks, and all work is products of blocks.

    Paths within the first half come first; then those of the second half, which may lead
    through the first; then those of the first that lead through the second. Blocks of
    ``leaf`` ids are squared until paths of any length are in.
    """

    def closed(m: SparseMatrix, lo: int, hi: int) -> DataFrame:
        """Shortest paths among the ids from lo to hi, through them alone."""
        if hi - lo <= leaf:
            now, hops = m.df, 1
            while hops < hi - lo:
                now = materialize(relational(m.with_df(now), m.with_df(now), "min_plus").df, "leaf")
                hops *= 2
            return now
        mid = (lo + hi) // 2
        first, last = [F.col(c) < mid for c in "ij"], [F.col(c) >= mid for c in "ij"]
        block = lambda rows, cols: m.df.filter(rows).filter(cols)
        times = lambda x, y: relational(m.with_df(x), m.with_df(y), "min_plus").df
        plus = lambda x, y: S.add(m.with_df(x), m.with_df(y), "min_plus").df
        p = closed(m.with_df(block(first[0], first[1])), lo, mid)
        out = materialize(times(p, block(first[0], last[1])), "half")
        back = materialize(times(block(last[0], first[1]), p), "half")
        q = closed(m.with_df(materialize(plus(block(last[0], last[1]), times(back, out)), "half")), mid, hi)
        out, back = materialize(times(out, q), "half"), materialize(times(q, back), "half")
        p = materialize(plus(p, times(out, back)), "half")
        return p.unionByName(out).unionByName(back).unionByName(q)

    loops = S.eye(a.df.sparkSession, a.nrows).df.withColumn("v", F.lit(0).cast("long"))
    start = S.add(a, a.with_df(loops), "min_plus")
    return a.with_df(closed(start.with_df(materialize(start.df, "start")), 0, a.nrows))


def matching_round(a: SparseMatrix) -> DataFrame:
    """One round of a greedy matching: rows propose to their least column, columns take the least row."""
    proposals = a.df.groupBy("i").agg(F.min("j").alias("j"))
    return proposals.groupBy("j").agg(F.min("i").alias("i")).select("i", "j")


def greedy_matching(a: SparseMatrix) -> DataFrame:
    """A maximal matching: rounds until no edge joins two free vertices; each round matches one pair at least."""
    left, out = materialize(a.df.select("i", "j"), "free"), None
    while True:
        step = materialize(matching_round(a.with_df(left)), "matching")
        if step.isEmpty():
            return out if out is not None else step
        out = step if out is None else out.unionByName(step)
        left = materialize(left.join(step.select("i"), "i", "left_anti").join(step.select("j"), "j", "left_anti").select("i", "j"), "free")


def on_cycles(a: SparseMatrix) -> DataFrame:
    """Edges (i, j) that remain when vertices without an edge in, or without one out, are taken away again and again.

    The graph has a cycle if and only if an edge remains.
    """
    now = materialize(a.df.filter("i <> j").select("i", "j").distinct(), "edges")
    loops = a.df.filter("i = j").select("i", "j").distinct()
    n = now.count()
    while n:
        kept = now.join(now.select(F.col("j").alias("i")).distinct(), "i", "left_semi").join(now.select(F.col("i").alias("j")).distinct(), "j", "left_semi").select("i", "j")
        now = materialize(kept, "edges")
        before, n = n, now.count()
        if n == before:
            break
    return now.unionByName(loops)


def closed_walks(a: SparseMatrix, k: int) -> DataFrame:
    """(k, closed_walks) for walks of 2 to k steps; the last product is masked to the diagonal by a join."""
    power, rows = a, None
    for step in range(2, k + 1):
        walks = power.df.join(a.df.select(F.col("i").alias("j"), F.col("j").alias("i"), F.col("v").alias("y")), ["i", "j"])
        row = walks.agg(F.lit(step).cast("long").alias("k"), F.coalesce(F.sum(F.col("v") * F.col("y")), F.lit(0)).cast("long").alias("closed_walks"))
        rows = row if rows is None else rows.unionByName(row)
        if step < k:
            power = relational(power, a)
    return rows


def triangles(a: SparseMatrix) -> DataFrame:
    """(vertex, n): two-step walks that an edge closes."""
    closed = relational(a, a, "plus_pair", mask=a.T.df.select("j", "i").select(F.col("i"), F.col("j")))
    return closed.df.groupBy(F.col("i").alias("vertex")).agg(F.sum("v").cast("long").alias("n"))


def reach_k(a: SparseMatrix, doublings: int) -> SparseMatrix:
    """Pairs at most 2^doublings steps apart, by or-and squaring."""
    ones = a.with_df(a.df.select("i", "j", F.lit(1).cast("long").alias("v")))
    ids = ones.df.select("i").union(ones.df.select("j")).distinct()
    now = S.add(ones, ones.with_df(ids.select("i", F.col("i").alias("j"), F.lit(1).cast("long").alias("v"))), "or_and")
    for _ in range(doublings):
        now = now.with_df(materialize(relational(now, now, "or_and").df, "reach"))
    return now


def cfl_reach(terminals: DataFrame, rules: list[tuple[str, str, str]]) -> DataFrame:
    """(symbol, doc, i, j): all spans that binary rules (head, left, right) derive from the given ones.

    Each round joins the spans found in the last one with all, on either side, until there
    is no new span; there are finitely many.
    """
    table = F.broadcast(terminals.sparkSession.createDataFrame(rules, "head string, l string, r string"))
    known = new = materialize(terminals.select("symbol", "doc", "i", "j").distinct(), "spans")
    while True:
        left = lambda d: d.select(F.col("symbol").alias("l"), "doc", "i", F.col("j").alias("m"))
        right = lambda d: d.select(F.col("symbol").alias("r"), "doc", F.col("i").alias("m"), "j")
        met = lambda x, y: left(x).join(table, "l").join(right(y), ["r", "doc", "m"]).select(F.col("head").alias("symbol"), "doc", "i", "j")
        found = met(new, known).unionByName(met(known, new)).distinct().join(known, ["symbol", "doc", "i", "j"], "left_anti")
        new = materialize(found, "spans")
        if new.isEmpty():
            return known
        known = materialize(known.unionByName(new), "known")


def topk_overlap(a: SparseMatrix, k: int) -> DataFrame:
    """(i, j, dot, rank): the k largest products of each row with later rows."""
    a = a.with_df(materialize(a.df, "operand"))
    if tiles.fits(a, bounds := tiles.bounds_of(a)):
        return overlaps.topk(a, bounds, k)
    pairs = relational(a, a.T, salt="auto", where=F.col("i") < F.col("j")).df
    rank = F.row_number().over(Window.partitionBy("i").orderBy(F.desc("v"), "j"))
    return pairs.withColumn("rank", rank).filter(F.col("rank") <= k).select("i", "j", F.col("v").alias("dot"), F.col("rank").cast("long").alias("rank"))


def cosine_topk(a: SparseMatrix, k: int) -> DataFrame:
    """(i, j, similarity, rank): the k other rows with the largest cosine to each row; ties go to the smaller id."""
    a = a.with_df(materialize(a.df, "operand"))
    if tiles.fits(a, bounds := tiles.bounds_of(a)):
        return tiles.gram_topk(a, bounds, k, cosine=True).select("i", "j", (F.col("score") / 1e6).alias("similarity"), "rank")
    norms = a.df.groupBy("i").agg(F.sqrt(F.sum(F.col("v") * F.col("v"))).alias("n"))
    half = relational(a, a.T, salt="auto", where=F.col("i") < F.col("j")).df
    both = half.unionByName(half.select(F.col("j").alias("i"), F.col("i").alias("j"), "v"))
    scaled = both.join(norms, "i").join(norms.toDF("j", "m"), "j").select("i", "j", F.round(F.col("v") / (F.col("n") * F.col("m")), 6).alias("similarity"))
    rank = F.row_number().over(Window.partitionBy("i").orderBy(F.desc("similarity"), "j"))
    return scaled.withColumn("rank", rank.cast("long")).filter(F.col("rank") <= k)


def gram(a: SparseMatrix) -> SparseMatrix:
    """A A', by tiles where the values are positive whole numbers."""
    a = a.with_df(materialize(a.df, "operand"))
    if tiles.fits(a, bounds := tiles.bounds_of(a)):
        return SparseMatrix(tiles.gram(a, bounds), a.nrows, a.nrows)
    return relational(a, a.T, salt="auto")
