"""SimHash near-duplicates: Golay-code keys, pigeonhole over segments, join and verify."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semigrid.functions.worker import lean, small_batches, worker_state
from semigrid.llm.golay import Golay
from semigrid.llm.runs import sorted_runs
from semigrid.llm.shingle_sets import ALL_PAIRS, GROWTH, HUBS, crowd_pairs, fingerprint, meeting_pairs, shingle_table, shingles, verified_pairs
from semigrid.plans.scratch import guarded_broadcast, materialize, text_or_empty
from semigrid.workloads.components import connected_components

#: Fingerprints with one key that a task compares in memory; larger runs go the exact way of ``ball_links``.
RUN_LIMIT = 50_000
#: Bits in which linked fingerprints differ at most; the keys and ``ball_links`` are made for three.
BITS = 3


@dataclass(frozen=True)
class View:
    """What a fingerprint is made of: shingles of so many words, hashed with a seed, repeats counted or not."""

    words: int = 3
    seed: int = 42
    distinct: bool = False


def fingerprints(docs: DataFrame, views: tuple[View, ...] = (View(),), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id and one signed 64-bit column fp0, fp1, ... for each view, over whole texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        digest = xxhash.xxh64_intdigest
        for batch in batches:
            out: list[list[int]] = [[] for _ in views]
            for text in batch.column(1):
                text, cut = text.as_py(), {}
                for k, v in enumerate(views):
                    if (v.words, v.distinct) not in cut:
                        s = shingles(text, v.words)
                        cut[v.words, v.distinct] = list(set(s)) if v.distinct else s
                    s = cut[v.words, v.distinct]
                    out[k].append(fingerprint(np.fromiter(map(digest, s, repeat(v.seed)), np.uint64, len(s))))
            yield pa.RecordBatch.from_arrays([batch.column(0), *[pa.array(x, pa.int64()) for x in out]], ["doc_id", *names])

    names = [f"fp{k}" for k in range(len(views))]
    read = docs.select(docs[id_col].cast("long").alias("doc_id"), text_or_empty(docs[text_col]).alias("text"))
    return read.mapInArrow(lean(run), "doc_id long, " + ", ".join(f"{n} long" for n in names))


def golay_keys(golay: Golay, fp: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(row, key) such that two fingerprints at most three bits apart share a key.

    Segments A and B are 23 bits each, C is 18 bits in halves of 9. If C is free of
    errors, A or B has at most one: C and the codewords near that segment. Otherwise A
    and B have at most two together. With A free: A with the codewords near B, or with
    a half of C (two errors in B leave one half free); with B free, the same turned
    round. One error in each leaves half of C free: that half, a home codeword of one
    segment and the codewords near the other, either way round.
    """
    u = fp.view(np.uint64)
    cut = lambda at, bits: (u >> np.uint64(at) & np.uint64((1 << bits) - 1)).astype(np.int64)
    a, b, c, c1, c2 = cut(0, 23), cut(23, 23), cut(46, 18), cut(46, 9), cut(55, 9)
    every = np.arange(len(fp))
    ra, na = golay.near(a)
    rb, nb = golay.near(b)
    ha, hb = golay.home(a).astype(np.int64), golay.home(b).astype(np.int64)
    na, nb = na.astype(np.int64), nb.astype(np.int64)
    tagged = lambda t, key: key | np.int64(t << 48)
    yield ra, tagged(0, c[ra] << 12 | na)
    yield rb, tagged(1, c[rb] << 12 | nb)
    yield rb, tagged(2, a[rb] << 12 | nb)
    yield ra, tagged(3, b[ra] << 12 | na)
    for t, (whole, half) in enumerate(((a, c1), (a, c2), (b, c1), (b, c2)), 4):
        yield every, tagged(t, whole << 9 | half)
    for t, half in ((8, c1), (9, c2)):
        yield rb, tagged(t, (ha[rb] << 12 | nb) << 9 | half[rb])
        other = na != ha[ra]
        yield ra[other], tagged(t, (na[other] << 12 | hb[ra][other]) << 9 | half[ra][other])


def _forest(fp: np.ndarray, bits: int) -> Iterator[tuple[int, int]]:
    """Links that connect what differs in at most ``bits`` bits, without all pairs."""
    left = np.arange(len(fp))
    while len(left):
        queue, left = [left[0]], left[1:]
        while queue and len(left):
            x = queue.pop()
            hit = np.bitwise_count(fp[left] ^ fp[x]) <= bits
            if hit.any():
                for y in left[hit]:
                    yield x, y
                queue += list(left[hit])
                left = left[~hit]


def golay_links(nodes: DataFrame, run_limit: int = RUN_LIMIT) -> DataFrame:
    """(u, v) links that connect all nodes whose fingerprints differ in at most three bits.

    ``nodes`` has node, view and fp, one node for each fingerprint of a view. Rows of one
    key are read in sorted order, a run at a time; a run over ``run_limit`` is passed on
    without being held and linked by ``ball_links``, which connects the same nodes.
    """

    def keys(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        golay = worker_state("golay", Golay)
        for batch in batches:
            node, view, fp = (np.asarray(batch.column(k)) for k in range(3))
            for row, key in golay_keys(golay, np.ascontiguousarray(fp)):
                yield pa.RecordBatch.from_arrays([pa.array(key | view[row].astype(np.int64) << 56), pa.array(node[row]), pa.array(fp[row])], ["key", "node", "fp"])

    def links(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def linked(key, node, fp) -> Iterator[pa.RecordBatch]:
            """All rows of the keys are here."""
            start = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
            size = np.diff(np.r_[start, len(key)])
            fp = np.ascontiguousarray(fp).view(np.uint64)  # bits of signed numbers would be counted in their absolute value
            two = start[size == 2]
            two = two[np.bitwise_count(fp[two] ^ fp[two + 1]) <= BITS]
            us, vs = [node[two]], [node[two + 1]]
            for s, n in zip(start[size > 2], size[size > 2]):
                found = list(_forest(fp[s : s + n], BITS))
                if found:
                    x, y = np.array(found).T
                    us.append(node[s + x])
                    vs.append(node[s + y])
            u, v = np.concatenate(us), np.concatenate(vs)
            yield out(u, v, np.zeros(len(u), np.int64), np.full(len(u), -1))

        def out(u, v, fp, view) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64()), pa.array(fp, pa.int64()), pa.array(view, pa.int64())], ["u", "v", "fp", "view"])

        for whole, table in sorted_runs(batches, 20_000, run_limit):
            key, node, fp = (table.column(k).to_numpy() for k in range(3))
            if whole:
                yield from linked(key, node, fp)
            else:
                yield out(node, node, fp, key >> 56)

    keyed = nodes.select("node", "view", "fp").mapInArrow(lean(keys, "golay"), "key long, node long, fp long")
    found = materialize(keyed.repartition("key").sortWithinPartitions("key").mapInArrow(lean(links), "u long, v long, fp long, view long"), "links")
    near = found.filter("view < 0").select("u", "v").distinct()
    dense = found.filter("view >= 0").select(F.col("u").alias("node"), "view", "fp").distinct()
    return near.unionByName(ball_links(dense)) if not dense.isEmpty() else near


def ball_links(nodes: DataFrame) -> DataFrame:
    """Links that connect what differs in at most three bits, with rows in proportion to the nodes.

    Two fingerprints are that close if and only if some word lies within one bit of one
    and two of the other. So each node sends itself to all such words; at a word, all
    are hung on the least of those within one bit.
    """

    def balls(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        one = np.uint64(1) << np.arange(64, dtype=np.uint64)
        i, j = np.triu_indices(64, 1)
        masks = np.concatenate([[np.uint64(0)], one, one[i] | one[j]]).astype(np.uint64)
        inner = np.arange(len(masks)) <= 64
        for batch in batches:
            node, view, fp = (np.asarray(batch.column(k)) for k in range(3))
            for at in range(0, len(node), 64):
                part = np.ascontiguousarray(fp[at : at + 64]).view(np.uint64)
                n = len(part)
                word = (part[:, None] ^ masks).ravel().view(np.int64)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(word), pa.array(np.repeat(view[at : at + 64], len(masks))), pa.array(np.repeat(node[at : at + 64], len(masks))), pa.array(np.tile(inner, n))], ["word", "view", "node", "inner"]
                )

    sent = nodes.mapInArrow(lean(balls), "word long, view long, node long, inner boolean")
    hub = sent.filter("inner").groupBy("view", "word").agg(F.min("node").alias("v"))
    return sent.join(hub, ["view", "word"]).filter("node <> v").select(F.col("node").alias("u"), "v").distinct()


def simhash_components(docs: DataFrame, view: View = View(), id_col: str = "doc_id", text_col: str = "text", run_limit: int = RUN_LIMIT) -> DataFrame:
    """doc_id, fingerprint and component_id for each row of ``docs``.

    Fingerprints link at three or fewer differing bits, and component_id is the least
    doc_id reachable. A null text is empty, and texts without a word have fingerprint
    zero, which links like any other. A row with a null id has a fingerprint but no
    component; repeated rows are one document; other columns are not read. Equal
    fingerprints are combined before anything is joined.
    """
    prints = materialize(fingerprints(docs, (view,), id_col, text_col).withColumnRenamed("fp0", "fp"), "prints")
    known = prints.filter("doc_id is not null").groupBy("fp").agg(F.min("doc_id").alias("node"))
    known = materialize(known.select("node", F.lit(0).cast("long").alias("view"), "fp"), "nodes")
    roots = connected_components(golay_links(known, run_limit))
    named = known.join(roots, "node", "left").select("fp", F.coalesce("root", "node").alias("component_id"))
    return prints.join(named, "fp", "left").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), F.when(F.col("doc_id").isNotNull(), F.col("component_id")).alias("component_id"))


def _one_text_each(read: DataFrame) -> DataFrame:
    """``read`` with one row for each doc_id: of different texts with one id, the least in order."""
    again = materialize(read.groupBy("doc_id").count().filter("count > 1").select("doc_id"), "again")
    n = again.count()
    if not n:
        return read
    again = guarded_broadcast(again, 32, rows=n)
    return read.join(again, "doc_id", "left_anti").unionByName(read.join(again, "doc_id", "left_semi").groupBy("doc_id").agg(F.min("text").alias("text")))


def similar_groups(docs: DataFrame, similarity: float = 0.8, words: int = 5, id_col: str = "doc_id", text_col: str = "text", run_limit: int = ALL_PAIRS, hubs: int = HUBS) -> DataFrame:
    """(node, root): documents that near copies link to a smaller doc_id, the least of their group.

    Two documents are near copies if their sets of ``words``-word shingles are similar
    (intersection over union) to ``similarity`` at least; groups are the components of
    all such pairs. SimHash comes first: fingerprints of the shingle sets meet by their
    Golay keys, and pairs at most three bits apart are verified on the texts. Then no
    pair is missed: similar sets share a shingle of their prefixes, and documents that
    meet there and are not in one group yet are compared by size, by parity sketch and
    at last on the whole texts. Shingles of over ``run_limit`` documents go by rounds, in
    which ever more of their documents are compared with all others of other groups,
    until all were. Texts without a word equal each other. Rows with a null id are in no
    group; rows that repeat an id are one document.
    """
    small_batches(docs.sparkSession)
    read = docs.select(docs[id_col].cast("long").alias("doc_id"), text_or_empty(docs[text_col]).alias("text")).filter("doc_id is not null")
    read = _one_text_each(read)
    table = materialize(shingle_table(read, similarity, words), "shingles")
    first = table.groupBy("digest").agg(F.min("node").alias("first"), F.count(F.lit(1)).alias("m")).filter("m > 1")
    alike = materialize(table.select("node", "digest").join(first, "digest").filter("node <> first").select(F.col("node").alias("u"), F.col("first").alias("v")), "alike")
    distinct = table.join(guarded_broadcast(alike.select(F.col("u").alias("node")), 40), "node", "left_anti")
    firsts = distinct.groupBy("fp").agg(F.min("node").alias("v"))
    same = distinct.select(F.col("node").alias("u"), "fp").join(firsts, "fp").select("u", "v")
    nodes = materialize(firsts.select(F.col("v").alias("node"), F.lit(0).cast("long").alias("view"), "fp"), "nodes")
    links = verified_pairs(read, table, alike.unionByName(same).unionByName(golay_links(nodes)), similarity, words)
    roots = connected_components(links)
    grouped = distinct.join(guarded_broadcast(roots, 40), "node", "left").withColumn("group", F.coalesce("root", "node"))
    posted = grouped.select(F.posexplode("keys").alias("at", "key"), "node", "n", "group")
    met = materialize(meeting_pairs(posted, similarity, run_limit), "met")
    links = links.unionByName(verified_pairs(read, table, met.filter("v is not null").select("u", "v"), similarity, words))
    roots = connected_components(links)
    alone = met.filter("v is null").select("key", F.col("u").alias("node"), "n")
    sizes = materialize(alone.groupBy("key").agg(F.count(F.lit(1)).alias("m")), "crowds")
    largest = sizes.agg(F.max("m")).first()[0] or 0
    place = F.floor((F.xxhash64("node") / F.lit(2.0**64) + 0.5) * F.col("m"))  # some turns are shared, some empty
    crowds = alone.join(sizes, "key").withColumn("turn", F.least(place, F.col("m") - 1))
    tried, now = 0, hubs
    while tried < largest:
        named = materialize(crowds.join(guarded_broadcast(roots, 40), "node", "left").withColumn("group", F.coalesce("root", "node")).drop("root"), "named")
        split = named.groupBy("key").agg(F.min("group").alias("a"), F.max("group").alias("b"), F.max("m").alias("most")).filter((F.col("a") < F.col("b")) & (F.col("most") > tried)).select("key")
        left = named.join(split, "key", "left_semi").join(table.select("node", "sketch"), "node")
        found = verified_pairs(read, table, crowd_pairs(left, tried, now, similarity), similarity, words)
        if not found.isEmpty():
            links = links.unionByName(found)
            roots = connected_components(links)
        tried, now = now, now * GROWTH
    return roots
