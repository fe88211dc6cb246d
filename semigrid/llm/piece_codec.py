"""SentencePiece encoding and decoding through a table of distinct marked words.

``piece_encode`` keeps the table in each worker, bounded in size. ``encode_by_table`` makes it
one table of the whole corpus, each word in it once, and joins ids back by position;
``piece_decode`` turns ids into text.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semigrid.functions.worker import lean, small_batches, worker_state
from semigrid.llm.chunks import ChunkTable, marked_words
from semigrid.plans.scratch import materialize

MARK = "▁"


def pieces_stay_in_words(processor) -> bool:
    """Whether no piece has a marker after another character, so that words can be cut alone."""
    return not any(MARK in p.lstrip(MARK) for p in map(processor.id_to_piece, range(processor.get_piece_size())))


class PieceCodec:
    """Encodes each distinct marked word once and joins the ids back in the order of the text."""

    def __init__(self, path: str):
        import sentencepiece

        self.sp = sentencepiece.SentencePieceProcessor(model_file=path)
        if not pieces_stay_in_words(self.sp):
            raise ValueError("pieces of this model cross white space markers")
        self.end, self.lone = str(self.sp.eos_id()), str(self.sp.piece_to_id(MARK))
        self.odd: dict[str, str] = {}  # chunks that decoding does not give back
        self.table = ChunkTable(self._ids, cost=3_000_000)

    def segment(self, chunks: list[str]) -> Iterator[tuple[list[int], str]]:
        """The ids of each chunk, and the text that is decoded from them."""
        coded = self.sp.encode(chunks, num_threads=1)
        coded = [ids if chunk else [int(self.lone)] for chunk, ids in zip(chunks, coded)]
        return zip(coded, self.sp.decode(coded, num_threads=1) if coded else [])

    def _ids(self, chunks: list[str]) -> Iterator[str]:
        for chunk, (ids, text) in zip(chunks, self.segment(chunks)):
            if text != chunk:
                self.odd[chunk] = text
            yield " ".join(map(str, ids))

    def encode(self, text: str) -> tuple[str, str]:
        """The ids with the end id, in decimal, and the text decoded from them."""
        words = marked_words(text)
        if not words:
            return self.end, ""
        table = self.table
        if len(self.odd) > 100_000:
            self.odd.clear()
            table.clear()
        ids = " ".join(table.values(words))
        odd = self.odd
        decoded = " ".join(words) if not odd or odd.keys().isdisjoint(words) else " ".join([odd.get(w, w) for w in words])
        return f"{ids} {self.end}", decoded


def piece_encode(docs: DataFrame, model_path: str, id_col: str = "doc_id", text_col: str = "text", digests: bool = False) -> DataFrame:
    """doc_id, n_tokens and either ids and decoded text, or (``digests``) their SHA-256.

    Whole texts; a null text is empty and gives the end id alone. Repeated rows are
    encoded again; columns other than the two named are not read. ``model_path`` is
    the model file, at the same place on every executor. The map keeps no state across
    rows but the bounded chunk table, so a lost task is simply run again.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = worker_state(f"codec:{model_path}", lambda: PieceCodec(model_path))
        for batch in batches:
            n, first, second = [], [], []
            for text in batch.column(1):
                ids, decoded = codec.encode(text.as_py() or "")
                n.append(ids.count(" ") + 1)
                if digests:
                    first.append(hashlib.sha256(ids.encode()).hexdigest())
                    second.append(hashlib.sha256(decoded.encode()).hexdigest())
                else:
                    first.append([int(x) for x in ids.split(" ")])
                    second.append(decoded)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(n, pa.int64()), pa.array(first, pa.string() if digests else pa.list_(pa.int32())), pa.array(second, pa.string())],
                ["doc_id", "n_tokens", *names],
            )

    names = ["ids_sha256", "decoded_sha256"] if digests else ["ids", "decoded"]
    kinds = "ids_sha256 string, decoded_sha256 string" if digests else "ids array<int>, decoded string"
    return docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text")).mapInArrow(lean(run, f"codec:{model_path}"), f"doc_id long, n_tokens long, {kinds}")


def chunk_table(chunks: DataFrame, model_path: str) -> DataFrame:
    """(chunk, ids, decoded) for each distinct value of the column chunk, segmented once in the whole job."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = worker_state(f"codec:{model_path}", lambda: PieceCodec(model_path))
        for batch in batches:
            found = list(codec.segment(batch.column(0).to_pylist()))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([x for x, _ in found], pa.list_(pa.int32())), pa.array([x for _, x in found], pa.string())], ["chunk", "ids", "decoded"])

    distinct = chunks.filter("chunk is not null").select("chunk").distinct()
    return distinct.mapInArrow(lean(run, f"codec:{model_path}"), "chunk string, ids array<int>, decoded string")


def encode_by_table(docs: DataFrame, model_path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_tokens, ids and decoded, by one table of the distinct marked words of the whole corpus.

    Every word of every text becomes a row with its position; the distinct words are
    segmented once each, and ids return to their positions by a join on the word and a
    grouping by text. The rows are those of ``piece_encode``; a null text is empty,
    repeated rows are texts of their own, other columns are not read. The words of one
    text are together in a task. This shuffles each word with its ids twice.
    """
    small_batches(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        row = TaskContext.get().partitionId() << 40
        names, kinds = ["row", "doc_id", "at", "chunk"], (pa.int64(), pa.int64(), pa.int64(), pa.string())
        for batch in batches:
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                words = [None, *marked_words(text.as_py() or "")]  # the first stands for the text itself
                n = len(words)
                yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(([row] * n, [doc] * n, range(n), words), kinds)], names)
                row += 1

    read = docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text"))
    placed = materialize(read.mapInArrow(lean(run), "row long, doc_id long, at long, chunk string"), "placed")
    table = materialize(chunk_table(placed, model_path), "chunks")
    joined = placed.join(table, "chunk", "left").groupBy("row").agg(F.first("doc_id").alias("doc_id"), F.sort_array(F.collect_list(F.struct("at", "ids", "decoded"))).alias("found"))
    end = PieceCodec(model_path).sp.eos_id()
    words = F.slice("found", 2, F.size("found"))
    ids = F.concat(F.flatten(F.transform(words, lambda x: x["ids"])), F.array(F.lit(end)))
    decoded = F.array_join(F.transform(words, lambda x: x["decoded"]), " ")
    return joined.select("doc_id", F.size(ids).cast("long").alias("n_tokens"), ids.alias("ids"), decoded.alias("decoded"))


def piece_decode(coded: DataFrame, model_path: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """doc_id and the text decoded from a column of ids; null and empty ids give an empty text, the end id none."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = worker_state(f"codec:{model_path}", lambda: PieceCodec(model_path))
        for batch in batches:
            texts = codec.sp.decode([x or [] for x in batch.column(1).to_pylist()], num_threads=1)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], ["doc_id", "decoded"])

    read = coded.select(coded[id_col].cast("long").alias("doc_id"), coded[ids_col].cast("array<int>").alias("ids"))
    return read.mapInArrow(lean(run, f"codec:{model_path}"), "doc_id long, decoded string")
