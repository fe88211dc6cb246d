"""Token counts by heap-and-linked-list merging, without building any identifier."""

from __future__ import annotations

from collections.abc import Iterator
from heapq import heapify, heappop, heappush

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semigrid.functions.worker import lean, worker_state
from semigrid.llm.chunks import ChunkTable, marked_words

MARK = "▁"


class MergeCounter:
    """Counts what byte-pair merging leaves of a chunk.

    ``rank`` orders the pieces that merging may form. Two neighbours whose joined text
    is a piece wait in a heap under (rank, place), so the best pair comes first and the
    leftmost among equals; neighbours are linked by index. Each merge removes one
    symbol. Characters outside the vocabulary stay alone and stand for their bytes.
    """

    def __init__(self, path: str):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        plain = [i for i in range(sp.get_piece_size()) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i))]
        pieces = sorted(plain, key=lambda i: (-sp.get_score(i), i))
        self.rank = {sp.id_to_piece(i): k for k, i in enumerate(pieces)}
        if any(MARK in p.lstrip(MARK) for p in self.rank):
            raise ValueError("pieces of this model cross white space markers")
        self.table = ChunkTable(lambda chunks: map(self.count_chunk, chunks), cost=4_000_000)

    def count_chunk(self, chunk: str) -> int:
        rank = self.rank
        symbols: list[str] = [MARK, *chunk.replace(" ", MARK)]
        n = len(symbols)
        heap = [(rank[p], i) for i in range(n - 1) if (p := symbols[i] + symbols[i + 1]) in rank]
        heapify(heap)
        after, before, merges = [*range(1, n), -1], [*range(-1, n - 1)], 0
        while heap:
            r, i = heappop(heap)
            left = symbols[i]
            if not left or (j := after[i]) < 0 or rank.get(joined := left + symbols[j]) != r:
                continue  # one side has merged with another neighbour since
            symbols[i], symbols[j] = joined, ""
            merges += 1
            after[i] = k = after[j]
            if k >= 0:
                before[k] = i
                if (p := joined + symbols[k]) in rank:
                    heappush(heap, (rank[p], i))
            if (h := before[i]) >= 0 and (p := symbols[h] + joined) in rank:
                heappush(heap, (rank[p], h))
        spelled = sum(len(s.encode()) - 1 for s in symbols if s and s not in rank)
        return n - merges + spelled

    def count(self, text: str) -> int:
        return sum(self.table.values(marked_words(text)))


def token_counts(docs: DataFrame, model_path: str, limit: int = 4096, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_tokens and over_limit of every whole text; a null text is empty.

    Repeated rows are counted one by one; other columns are not read. ``model_path``
    names the vocabulary file, at the same place on every executor.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = worker_state(f"counter:{model_path}", lambda: MergeCounter(model_path))
        for batch in batches:
            n = [counter.count(text.as_py() or "") for text in batch.column(2)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(n, pa.int64())], ["doc_id", "n_bytes", "n_tokens"])

    text = F.coalesce(docs[text_col], F.lit(""))
    read = docs.select(docs[id_col].cast("long").alias("doc_id"), F.octet_length(text).cast("long").alias("n_bytes"), text.alias("text"))
    return read.mapInArrow(lean(run, f"counter:{model_path}"), "doc_id long, n_bytes long, n_tokens long").withColumn("over_limit", F.col("n_tokens") > limit)
