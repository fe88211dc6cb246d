"""Bounded-space online packing of token sequences."""

from __future__ import annotations

import re
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semigrid.functions.worker import lean, worker_state
from semigrid.llm.chunks import ChunkTable
from semigrid.plans.scratch import materialize

#: The parts in which the vocabulary cuts a chunk of ASCII without capitals.
_PARTS = re.compile("[a-z]+|[0-9]|[^a-z0-9]+")
_LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))


class WordIds:
    """Ids of a text as little-endian 32-bit bytes, each distinct word encoded once.

    The vocabulary cuts at white space before anything else, so what stands between
    ASCII blanks is encoded alone; it cuts letters from a comma or full stop too, so a word
    that one of them ends has the ids of the word and of that. ASCII capitals are
    folded first, as the vocabulary would do, unless a special string might be spelled by
    that. New chunks are encoded in one call and parted at the ids that end a word: a word of
    letters alone has one, other ASCII without quotes and angle brackets one for each run.
    """

    def __init__(self, path: str):
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        size = self.tokenizer.get_vocab_size()
        self.ends = np.array([(self.tokenizer.id_to_token(i) or "").endswith("</w>") for i in range(size)])
        self.stops = {x: self._alone([x])[0] for x in (".", ",")}
        self.table = ChunkTable(self._encode, cost=5_000_000)

    def _alone(self, texts: list[str]) -> list[bytes]:
        return [array("I", e.ids).tobytes() for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _encode(self, chunks: list[bytes]) -> list[bytes]:
        young, known = self.table.young, {}
        new: dict[str, int] = {}  # what goes into one call, and in how many parts it will be cut
        other: list[str] = []
        texts = [x.decode() for x in chunks]
        for x in texts:
            if x.isalpha():
                new[x] = 1
            elif x[-1] in ".," and (word := x[:-1]).isalpha():
                if (ids := young.get(word.encode())) is None:
                    new[word] = 1
                else:
                    known[x] = ids + self.stops[x[-1]]
            elif x.isascii() and x == x.lower() and "'" not in x and "<" not in x:
                new[x] = len(_PARTS.findall(x))
            else:
                other.append(x)
        if new:
            ids = np.array(self.tokenizer.encode_batch_fast([" ".join(new)], add_special_tokens=False)[0].ids, "<u4")
            ends, last = np.flatnonzero(self.ends[ids]), np.cumsum(list(new.values())) - 1
            if len(ends) == last[-1] + 1 and ends[-1] + 1 == len(ids):
                cuts, raw = (4 * (ends[last] + 1)).tolist(), ids.tobytes()
                known.update((w, raw[s:e]) for w, s, e in zip(new, [0, *cuts], cuts))
            else:
                other += new
        if other:
            known.update(zip(other, self._alone(other)))
        return [known[x] if x in known else known[x[:-1]] + self.stops[x[-1]] for x in texts]

    def ids(self, text: str) -> bytes:
        raw = text.encode()
        if b"<|" not in raw:
            raw = raw.translate(_LOWER)
        return b"".join(self.table.values(raw.split()))


class Packer:
    """A fixed number of open windows; pieces are (doc_id, start, ids, doc_tokens).

    A document first fills whole windows of its own. The rest goes where it leaves the
    least room. When it fits nowhere and no window may be opened, the fullest window is
    topped up with the head of the piece (if its room is worth a cut) and emitted.
    """

    def __init__(self, size: int, windows: int, least_cut: int):
        self.size, self.windows, self.least = size, windows, least_cut
        self.open: list[tuple[int, list]] = []  # room, pieces

    def add(self, doc: int, ids: bytes) -> Iterator[list]:
        size, total, start = self.size, len(ids) // 4, 0
        while total - start >= size:
            yield [(doc, start, ids[4 * start : 4 * (start + size)], total)]
            start += size
        while start < total:
            need = total - start
            fits = [k for k, (room, _) in enumerate(self.open) if room >= need]
            if fits:
                k = min(fits, key=lambda k: self.open[k][0])
                room, pieces = self.open[k]
                pieces.append((doc, start, ids[4 * start :], total))
                start = total
                if room == need:
                    yield self.open.pop(k)[1]
                else:
                    self.open[k] = (room - need, pieces)
            elif len(self.open) < self.windows:
                self.open.append((size, []))
            else:
                k = min(range(len(self.open)), key=lambda k: self.open[k][0])
                room, pieces = self.open.pop(k)
                if room >= self.least:
                    pieces.append((doc, start, ids[4 * start : 4 * (start + room)], total))
                    start += room
                yield pieces


def merge_leftovers(pieces: list, size: int) -> Iterator[list]:
    """Full windows from the pieces in order, and the rest in windows of powers of two."""
    rest = sum(len(p[2]) for p in pieces) // 4
    room, window = 0, None
    for doc, start, ids, total in pieces:
        while ids:
            if not room:
                room = min(size, 1 << (rest.bit_length() - 1))
                window = []
            take = min(room, len(ids) // 4)
            window.append((doc, start, ids[: 4 * take], total))
            ids, start, room, rest = ids[4 * take :], start + take, room - take, rest - take
            if not room:
                yield window


SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
_FIELDS = [(x.split()[0], pa.int64()) for x in SCHEMA.split(", ")]


def _rows(window: list, sequence: int) -> Iterator[tuple]:
    offset = 0
    for doc, start, ids, total in window:
        yield doc, start, len(ids) // 4, zlib.crc32(ids), total, sequence, offset
        offset += len(ids) // 4


def _batch(rows: list[tuple], extra: list[bytes | None] | None = None) -> pa.RecordBatch:
    columns = list(zip(*rows)) if rows else [[]] * len(_FIELDS)
    arrays, names = [pa.array(c, t) for c, (_, t) in zip(columns, _FIELDS)], [n for n, _ in _FIELDS]
    if extra is not None:
        arrays, names = [*arrays, pa.array(extra, pa.binary())], [*names, "ids"]
    return pa.RecordBatch.from_arrays(arrays, names)


def pack(docs: DataFrame, model_path: str, size: int = 2048, windows: int = 16, least_cut: int = 8, end_id: int = 1, merge_parts: int = 64, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece: where ``length`` ids of a document from ``start`` lie.

    Every id of every whole text, and ``end_id`` after it, lies in exactly one piece; a
    null text is the end id alone; repeated rows are packed as documents of their own.
    A null id stays null. Windows are filled partition by partition in the order of
    the scan, which no shuffle precedes, so that a task run again gives the same rows.
    What is open at the end (``windows`` per partition at most) is merged for
    ``merge_parts`` neighbouring partitions at a time, again without a padded id: full
    windows, then windows of powers of two. Only windows emitted with a gap under
    ``least_cut`` are padded at all.
    """

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        base, count = TaskContext.get().partitionId() << 32, 0
        words = worker_state(f"words:{model_path}", lambda: WordIds(model_path))
        packer, tail = Packer(size, windows, least_cut), np.array([end_id], "<u4").tobytes()
        for batch in batches:
            rows: list[tuple] = []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                for window in packer.add(doc, words.ids(text.as_py() or "") + tail):
                    rows += _rows(window, base + count)
                    count += 1
            yield _batch(rows, [None] * len(rows))
        words.table.clear()  # the worker may go on with another stage
        rows, ids = [], []
        for _, window in packer.open:
            rows += _rows(window, base)
            ids += [p[2] for p in window]
        yield _batch(rows, ids)

    def merge(key: tuple, table: pa.Table) -> pa.Table:
        table = table.sort_by([("sequence_id", "ascending"), ("doc_id", "ascending"), ("start", "ascending")])
        pieces = list(zip(*(table.column(c).to_pylist() for c in ("doc_id", "start", "ids", "doc_tokens"))))
        base, rows = ((1 << 30) + key[0].as_py()) << 32, []
        for k, window in enumerate(merge_leftovers(pieces, size)):
            rows += _rows(window, base + k)
        return pa.Table.from_batches([_batch(rows)])

    read = docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text"))
    placed = materialize(read.mapInArrow(lean(place, f"words:{model_path}"), f"{SCHEMA}, ids binary"), "packed")
    names = [n for n, _ in _FIELDS]
    group = F.shiftright("sequence_id", 32).cast("long")
    left = placed.filter("ids is not null").withColumn("part", F.floor(group / merge_parts).cast("long"))
    return placed.filter("ids is null").select(names).unionByName(left.groupBy("part").applyInArrow(lambda k, t: merge(k, t), SCHEMA))
