"""Removal of repeated long byte strings, judged on suffix intervals.

Any window of ``least`` bytes chooses one of its short grams by hash, the least, so
equal windows choose equal grams at equal places. Consecutive windows with one chosen
gram (an anchor) form a context: the bytes that these windows cover. Only contexts
whose anchors are equal can hold equal windows; the others are done with. Contexts that
are equal as a whole are combined by a digest before they are shuffled; the long strings
that this joins are held against their sources on the texts. Different contexts around
one anchor are compared window by window: suffix intervals on the Burrows-Wheeler
transform of such contexts, expanded up to ``least`` bytes, give the classes of equal
windows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from semigrid.functions.worker import lean, small_batches, worker_state
from semigrid.llm.bwt import window_classes
from semigrid.llm.runs import sorted_runs
from semigrid.plans.scratch import guarded_broadcast, materialize, text_or_empty

_BASE, _BITS = 0x9E3779B97F4A7C15 | 1, 18
#: Documents' texts are shuffled, rather than what is to be done to them broadcast, from this size of the latter on.
_SEND_BYTES = 4 << 20
_M1, _M2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
#: Strings that are cut out of one text at a time; a text of which more are asked for is read in parts of the list.
_ASKED = 4_096
#: Windows of a block that a task looks at together.
_BLOCK = (1 << _BITS) - 256


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ x >> np.uint64(30)) * _M1
    x = (x ^ x >> np.uint64(27)) * _M2
    return x ^ x >> np.uint64(31)


def _powers() -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base, and of its inverse, modulo 2^64."""
    n = 1 << _BITS
    inverse = pow(_BASE, -1, 1 << 64)
    run = lambda b: np.cumprod(np.r_[np.uint64(1), np.full(n - 1, b & (1 << 64) - 1, np.uint64)], dtype=np.uint64)
    return run(_BASE), run(inverse)


@dataclass(frozen=True)
class Shape:
    """Bytes of a window and of a gram."""

    least: int = 100
    gram: int = 32


def anchors(data: np.ndarray, ends: np.ndarray, shape: Shape) -> Iterator[tuple[np.ndarray, ...]]:
    """(anchor digest, context digest, text number, first window, b).

    b packs windows - 1, and what stands before and after the anchor, as 16 bits of a digest
    each: a window that reaches at least half of its other bytes to one side. Zero says
    that no window of the context reaches that far.

    ``data`` has the texts one after the other, ``ends`` where each ends. Texts are read
    in blocks; a block's border may part a context, never a window.
    """
    power, inverse = worker_state("powers", _powers)
    least, gram = shape.least, shape.gram
    for at in range(0, max(0, len(data) - least + 1), _BLOCK):
        x = data[at : at + _BLOCK + least - 1]
        n = len(x)
        if n < least:
            return
        sums = np.zeros(n + 1, np.uint64)
        np.cumsum((x.astype(np.uint64) + np.uint64(1)) * power[:n], out=sums[1:])
        g = (sums[gram:] - sums[:-gram]) * inverse[: n - gram + 1]
        v = _mix(g)
        v &= np.uint64(~((1 << _BITS) - 1) & (1 << 64) - 1)
        v |= np.arange(len(v), dtype=np.uint64)
        width, reach = least - gram + 1, 1
        while reach * 2 <= width:
            v = np.minimum(v[:-reach], v[reach:])
            reach *= 2
        if width > reach:
            v = np.minimum(v[: reach - width], v[width - reach :])
        chosen = (v & np.uint64((1 << _BITS) - 1)).astype(np.int64)
        first = int(np.searchsorted(ends, at, "right"))
        final = int(np.searchsorted(ends, at + n, "left"))
        cut = np.clip(ends[first : final + 1] - at, 0, n)
        owner = np.repeat(np.arange(first, first + len(cut)), np.diff(np.r_[0, cut]))[: len(chosen)]
        windows = np.arange(len(chosen))
        inside = windows + least <= ends[owner] - at
        same = np.zeros(len(chosen), bool)
        same[1:] = inside[1:] & inside[:-1] & (chosen[1:] == chosen[:-1])
        low = np.flatnonzero(inside & ~same)
        if not len(low):
            continue
        open_end = np.r_[~same[1:], True]
        high = np.flatnonzero(inside & open_end)
        q = chosen[low]
        size, place = high - low, q - low
        shape_of = (size << 8 | place).astype(np.uint64)
        context = _mix((sums[high + least] - sums[low]) * inverse[low] + _mix(shape_of + np.uint64(1)))
        text = owner[low]
        starts = np.r_[0, ends][text]
        half = (least - gram + 1) // 2
        before, after = np.maximum(q - half, 0), np.minimum(q + gram + half, n)
        left = np.where(place >= half, _mix((sums[q] - sums[before]) * inverse[before]) >> np.uint64(48) | np.uint64(1), np.uint64(0))
        right = np.where(high + least >= q + gram + half, _mix((sums[after] - sums[q + gram]) * inverse[q + gram]) >> np.uint64(48) | np.uint64(1), np.uint64(0))
        b = size << 32 | (left << np.uint64(16) | right).view(np.int64)
        yield _mix(g[q] + np.uint64(77)).view(np.int64), context.view(np.int64), text, low + at - starts, b


def aligned(doc: np.ndarray, start: np.ndarray, end: np.ndarray, source: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, ...]:
    """Spans of the same text that touch or overlap, and continue the same string of a source, become one; ends must grow with starts."""
    if not len(doc):
        return doc, start, end, source, at
    order = np.lexsort((start, at - start, source, doc))
    doc, start, end, source, at = (x[order] for x in (doc, start, end, source, at))
    shift = at - start
    fresh = np.r_[True, (doc[1:] != doc[:-1]) | (source[1:] != source[:-1]) | (shift[1:] != shift[:-1]) | (start[1:] > end[:-1])]
    last = np.r_[np.flatnonzero(fresh)[1:] - 1, len(doc) - 1]
    return doc[fresh], start[fresh], end[last], source[fresh], at[fresh]


def _first_of(keys: list[np.ndarray], doc: np.ndarray, start: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows that are first (by text, then place) among those with equal keys, rows that come later than these, and the first of each of the latter."""
    order = np.lexsort((start, doc, *keys))
    fresh = np.ones(len(order), bool)
    fresh[1:] = np.any([k[order][1:] != k[order][:-1] for k in keys], axis=0)
    head = np.flatnonzero(fresh)
    of = order[head][np.cumsum(fresh) - 1]
    later = ~fresh & ((doc[order] != doc[of]) | (start[order] != start[of]))
    return order[head], order[later], of[later]


def _shared(h: np.ndarray, side: np.ndarray) -> np.ndarray:
    """Whether another row with the same anchor has the same side. ``h`` is sorted; a side of zero is none."""
    order = np.lexsort((side, h))
    h, side = h[order], side[order]
    same = (h[1:] == h[:-1]) & (side[1:] == side[:-1]) & (side[1:] != 0)
    out = np.zeros(len(h), bool)
    out[order[1:]] |= same
    out[order[:-1]] |= same
    return out


#: Rows that tasks pass on: spans of a text with their source (c) and its place there (s); contexts; and contexts of crowded anchors.
_ROW = "h long, kind int, c long, doc long, a long, b long, s long"
_SPAN, _CONTEXT, _CROWD, _CHECK, _SELF = 0, 1, 2, 3, 4


def _rows(kind: int, h, c, doc, a, b, s=0) -> pa.RecordBatch:
    n = len(doc)
    full = lambda x, t: pa.array(np.broadcast_to(x, n), t)
    return pa.RecordBatch.from_arrays([full(h, pa.int64()), full(kind, pa.int32()), full(c, pa.int64()), pa.array(doc, pa.int64()), full(a, pa.int64()), full(b, pa.int64()), full(s, pa.int64())], ["h", "kind", "c", "doc", "a", "b", "s"])


def _spans(doc, start, end, source, at) -> pa.RecordBatch:
    doc, start, end, source, at = aligned(doc, start, end, source, at)
    return _rows(_SPAN, _mix(doc.astype(np.int64).view(np.uint64)).view(np.int64), source, doc, start, end, at)


def _bytes_of(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string column without nulls, and where each text ends."""
    column = column.cast(pa.large_binary())
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    data = column.buffers()[2]
    data = np.frombuffer(data, np.uint8)[offsets[0] : offsets[-1]] if data is not None and len(offsets) else np.zeros(0, np.uint8)
    return data, offsets[1:] - offsets[0]


def _continued(spans: DataFrame) -> DataFrame:
    """(doc, a, n, source, at): spans of a text that touch or overlap and continue one string of a source (c, from s on) as one."""
    line = Window.partitionBy("doc", "c", "shift").orderBy("a", "b")
    reached = F.max("b").over(line.rowsBetween(Window.unboundedPreceding, -1))
    parted = spans.select("doc", "a", "b", "c", (F.col("s") - F.col("a")).alias("shift")).withColumn("fresh", F.when(F.col("a") <= reached, 0).otherwise(1))
    islands = parted.withColumn("island", F.sum("fresh").over(line)).groupBy("doc", "c", "shift", "island").agg(F.min("a").alias("a"), F.max("b").alias("b"))
    return islands.select("doc", "a", (F.col("b") - F.col("a")).alias("n"), F.col("c").alias("source"), (F.col("a") + F.col("shift")).alias("at"))


def repeated_spans(docs: DataFrame, shape: Shape = Shape(), held: int = 200_000, run_limit: int = 400_000, crowd: int = 2_000) -> DataFrame:
    """(doc, a, b): bytes from a to b of a document that an earlier window covers; spans may overlap.

    ``docs`` has doc_id and text, without nulls. Tasks keep ``held`` anchors at most
    before they combine equal contexts and send one row for each. An anchor with over
    ``crowd`` different contexts, or ``run_limit`` rows, such as the border of a passage
    in a great many documents, is never held: its windows are compared by digest, in an
    aggregation that combines on the map side.
    """
    least = shape.least
    small_batches(docs.sparkSession)

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts: list[tuple[np.ndarray, ...]] = []
        count = 0

        def sent() -> Iterator[pa.RecordBatch]:
            h, c, doc, low, b = (np.concatenate(x) for x in zip(*parts))
            key = _mix(h.view(np.uint64) + _mix(c.view(np.uint64)))
            order = np.argsort(key)
            key = key[order]
            alone = np.r_[True, key[1:] != key[:-1]] & np.r_[key[1:] != key[:-1], True]
            some = order[~alone]
            head, later, first = _first_of([c[some], h[some]], doc[some], low[some])
            keep = np.r_[order[alone], some[head]]
            for at in range(0, len(keep), 50_000):
                part = keep[at : at + 50_000]
                yield _rows(_CONTEXT, h[part], c[part], doc[part], low[part], b[part])
            later, first = some[later], some[first]
            yield _spans(doc[later], low[later], low[later] + (b[later] >> 32) + least, doc[first], low[first])

        for batch in batches:
            ids = np.asarray(batch.column(0))
            data, ends = _bytes_of(batch.column(1))
            for h, c, text, low, b in anchors(data, ends, shape):
                parts.append((h, c, ids[text], low, b))
                count += len(h)
                if count > held:
                    yield from sent()
                    parts.clear()
                    count = 0
        if parts:
            yield from sent()

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole, table in sorted_runs(batches, 100_000, run_limit):
            h, kind, c, doc, a, b, s = (table.column(k).to_numpy() for k in range(7))
            done = kind == _SPAN
            if done.any():
                yield _rows(_SPAN, h[done], c[done], doc[done], a[done], b[done], s[done])
            if not whole:
                yield _rows(_CROWD, h[~done], c[~done], doc[~done], a[~done], b[~done])
                continue
            size = np.diff(np.flatnonzero(np.r_[True, h[1:] != h[:-1], True]))
            some = np.flatnonzero(np.repeat(size, size) > 1)
            some = some[kind[some] == _CONTEXT]
            head, later, first = _first_of([c[some], h[some]], doc[some], a[some])
            later, first = some[later], some[first]
            yield _spans(doc[later], a[later], a[later] + (b[later] >> 32) + least, doc[first], a[first])
            head = some[head]
            head = head[_shared(h[head], b[head] >> 16 & 0xFFFF) | _shared(h[head], b[head] & 0xFFFF)]
            size = np.diff(np.flatnonzero(np.r_[True, h[head][1:] != h[head][:-1], True])) if len(head) else np.zeros(0, int)
            size = np.repeat(size, size)
            for k, pick in ((_CONTEXT, (size > 1) & (size <= crowd)), (_CROWD, size > crowd)):
                if pick.any():
                    yield _rows(k, h[head[pick]], c[head[pick]], doc[head[pick]], a[head[pick]], b[head[pick]])

    def cut_out(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["h", "c", "kind", "doc", "a", "n", "own", "bytes"]
        kinds = [pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.bool_(), pa.binary()]
        digest = lambda x: hashlib.blake2b(x, digest_size=16).digest()
        for batch in batches:
            out: list[tuple] = []
            for doc, text, wanted in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2).to_pylist()):
                raw, within = text.as_py().encode(), []
                for w in wanted:
                    low, size = w["a"], w["b"] >> 32
                    if w["kind"] == _SELF:
                        if raw[low : low + w["b"]] == raw[w["x"] : w["x"] + w["b"]]:
                            within.append((low, low + w["b"]))
                    elif w["kind"] == _CHECK:
                        out.append((w["h"], w["x"], _CHECK, doc, low, w["b"], w["own"], digest(raw[low : low + w["b"]])))
                    elif w["kind"] == _CONTEXT:
                        out.append((w["h"], 0, _CONTEXT, doc, low, 0, None, raw[low : low + size + least]))
                    else:
                        for p in range(low, low + size + 1):
                            d = digest(raw[p : p + least])
                            out.append((int.from_bytes(d[:8], "little", signed=True), int.from_bytes(d[8:], "little", signed=True), _CROWD, doc, p, 0, None, None))
                out += [(0, 0, _SPAN, doc, s, e - s, None, None) for s, e in _union(within, len(raw))]
                if len(out) > 20_000:
                    yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*out), kinds)], names)
                    out = []
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*out), kinds)], names)

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, table in sorted_runs(batches, 2_000, 1 << 40):
            doc, low = table.column("doc").to_numpy(), table.column("a").to_numpy()
            strings = [np.frombuffer(x.as_py(), np.uint8) for x in table.column("bytes")]
            labels = window_classes(strings, least)
            n = np.array([len(x) for x in labels])
            label, of = np.concatenate(labels), np.repeat(np.arange(len(n)), n)
            start = low[of] + np.arange(len(of)) - np.repeat(np.cumsum(n) - n, n)
            _, later, _ = _first_of([label], doc[of], start)
            own = doc[of][later]
            yield _spans(own, start[later], start[later] + least, own, start[later])

    found = docs.select("doc_id", "text").mapInArrow(lean(find, "powers"), _ROW)
    met = materialize(found.repartition("h").sortWithinPartitions("h").mapInArrow(lean(meet), _ROW), "anchors")
    if met.isEmpty():
        return met.select("doc", "a", "b")
    none = F.lit(0).cast("long")
    joined = _continued(met.filter(F.col("kind") == _SPAN))
    # within a text strings are compared; elsewhere both are cut out of their texts, and the same string has the same digest
    kind = F.when(F.col("doc") == F.col("source"), _SELF).otherwise(_CHECK)
    check = lambda doc, at, own: [F.col(doc).alias("doc_id"), F.struct((kind if own else F.lit(_CHECK)).alias("kind"), F.col("source").alias("h"), F.col(at).alias("a"), F.col("n").alias("b"), F.col("at").alias("x"), F.lit(own).alias("own")).alias("wanted")]
    joined = materialize(joined, "joined")
    spans_, sources = joined.select(*check("doc", "a", True)), joined.filter("doc <> source").select("source", "at", "n").distinct().select(*check("source", "at", False))
    others = met.filter(F.col("kind") != _SPAN).select(F.col("doc").alias("doc_id"), F.struct("kind", "h", "a", "b", none.alias("x"), F.lit(False).alias("own")).alias("wanted"))
    wanted = spans_.unionByName(sources).unionByName(others)
    asked = 2 * joined.count() + met.filter(F.col("kind") != _SPAN).count()
    busy = materialize(wanted.groupBy("doc_id").count().filter(F.col("count") > 2 * _ASKED).select("doc_id", F.ceil(F.col("count") / _ASKED).alias("fan")), "busy")
    part = F.pmod(F.xxhash64("wanted.a", "wanted.b", "wanted.x"), F.coalesce("fan", F.lit(1).cast("long")))
    by_doc = wanted.join(guarded_broadcast(busy, 32), "doc_id", "left").groupBy("doc_id", part.alias("part")).agg(F.collect_list("wanted").alias("wanted"))
    cut = docs.select("doc_id", "text").join(guarded_broadcast(by_doc, 96, _SEND_BYTES, asked), "doc_id").select("doc_id", "text", "wanted")
    contexts = materialize(cut.mapInArrow(lean(cut_out), "h long, c long, kind int, doc long, a long, n long, own boolean, bytes binary"), "contexts")
    seen = contexts.filter(F.col("kind") == _CHECK)
    spans = seen.filter("own").join(seen.filter("not own").select("h", "c", "n", "bytes"), ["h", "c", "n", "bytes"], "left_semi")
    spans = spans.select("doc", "a", "n").unionByName(contexts.filter(F.col("kind") == _SPAN).select("doc", "a", "n")).select("doc", "a", (F.col("a") + F.col("n")).alias("b"))
    near = contexts.filter(F.col("kind") == _CONTEXT).select("h", "doc", "a", "bytes").repartition("h").sortWithinPartitions("h")
    spans = spans.unionByName(near.mapInArrow(lean(compare), _ROW).select("doc", "a", "b"))
    crowded = contexts.filter(F.col("kind") == _CROWD)
    if not crowded.isEmpty():
        first = crowded.groupBy("h", "c").agg(F.min(F.struct("doc", "a")).alias("first"), F.count(F.lit(1)).alias("n")).filter("n > 1")
        later = crowded.join(first, ["h", "c"]).filter("struct(doc, a) > first")
        spans = spans.unionByName(later.select("doc", "a", (F.col("a") + least).alias("b")))
    return spans


def _union(spans: list[tuple[int, int]], n: int) -> list[tuple[int, int]]:
    out: list[list[int]] = []
    for s, e in sorted((s, min(e, n)) for s, e in spans):
        if out and s <= out[-1][1]:
            out[-1][1] = max(out[-1][1], e)
        else:
            out.append([s, e])
    return [(s, e) for s, e in out]


def whole_characters(raw: bytes, spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """The spans without characters that they cover only in part."""
    out = []
    for s, e in spans:
        while s < e and s < len(raw) and raw[s] & 0xC0 == 0x80:
            s += 1
        while e > s and e < len(raw) and raw[e] & 0xC0 == 0x80:
            e -= 1
        if s < e:
            out.append((s, e))
    return out


def _kept(raw: bytes, taken: list[tuple[int, int]]) -> bytes:
    edges = zip([0, *(e for _, e in taken)], [*(s for s, _ in taken), len(raw)])
    return b"".join(raw[s:e] for s, e in edges) if taken else raw


def _with_spans(docs: DataFrame, ids: str, text: str, shape: Shape, limits: dict[str, int]) -> DataFrame:
    """``docs`` with a last column of the spans to remove, null for none."""
    read = docs.select(docs[ids].cast("long").alias("doc_id"), text_or_empty(docs[text]).alias("text"))
    spans = materialize(repeated_spans(read.filter("doc_id is not null"), shape, **limits), "spans")
    own, found = (name + "_" * max(map(len, docs.columns)) for name in ("doc", "spans"))  # longer than any other name
    by_doc = spans.groupBy("doc").agg(F.collect_list(F.struct("a", "b")).alias("spans")).toDF(own, found)
    return docs.join(guarded_broadcast(by_doc, 32, _SEND_BYTES, spans.count()), docs[ids].cast("long") == F.col(own), "left").drop(own)


def suffix_dedup(docs: DataFrame, shape: Shape = Shape(), id_col: str = "doc_id", text_col: str = "text", **limits: int) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans and kept_sha256, for each row of ``docs``.

    Removes each byte of the UTF-8 text that lies in a string of ``shape.least`` bytes
    which also starts earlier: in a smaller doc_id, or in the same text at an earlier
    place. Strings are judged on the input. A null text is empty; a row with a null id
    takes part in nothing and is kept whole; rows that repeat an id are one document.
    Other columns are not read.
    """
    joined = _with_spans(docs.select(F.col(id_col).cast("long").alias("doc_id"), text_or_empty(text_col).alias("text")), "doc_id", "text", shape, limits)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string())
        for batch in batches:
            out: list[tuple] = []
            for text, found in zip(batch.column(1), batch.column(2)):
                raw, found = text.as_py().encode(), found.as_py()
                cut = _union([(x["a"], x["b"]) for x in found], len(raw)) if found else []
                out.append((len(raw), sum(e - s for s, e in cut), len(cut), hashlib.sha256(_kept(raw, cut)).hexdigest()))
            columns = zip(*out) if out else [[]] * 4
            yield pa.RecordBatch.from_arrays([batch.column(0), *[pa.array(x, t) for x, t in zip(columns, kinds)]], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])

    return joined.mapInArrow(lean(run), "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")


def without_repeats(docs: DataFrame, shape: Shape = Shape(), id_col: str = "doc_id", text_col: str = "text", **limits: int) -> DataFrame:
    """``docs`` with the same columns and rows, its texts without what ``suffix_dedup`` removes.

    A character of which only a part would go stays, so texts remain valid UTF-8.
    """
    names = docs.columns
    joined = _with_spans(docs, id_col, text_col, shape, limits)
    at = names.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = []
            for text, found in zip(batch.column(at), batch.column(len(names))):
                text, found = text.as_py(), found.as_py()
                if text and found:
                    raw = text.encode()
                    text = _kept(raw, whole_characters(raw, _union([(x["a"], x["b"]) for x in found], len(raw)))).decode()
                texts.append(text)
            columns = batch.columns[: len(names)]
            columns[at] = pa.array(texts, pa.string())
            yield pa.RecordBatch.from_arrays(columns, names)

    return joined.mapInArrow(lean(run), docs.schema)
