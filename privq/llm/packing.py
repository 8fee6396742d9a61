"""Fixed-length training rows by best-fit-decreasing packing.

A document's ids, closed by an end id, are cut into pieces of at most ``length``; every piece goes, longest first, into
the fullest open row that still has room. A segment tree over capacities answers "least capacity of at least x with an
open row" in logarithmic time. A row holds its id matrix line, the cumulative segment lengths, the document and the
offset of each segment, and position resets: positions start again from the segment's offset within its document.
``unpack`` gives every document back.

Documents are packed in runs of ``RUN_TOKENS`` as they are read, without a shuffle; memory is bounded by a run and the
longest document. Null text counts as empty: its only token is the end id. Equal rows of the input are packed each.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession

from privq.llm.bpe import PRETOKEN, ChunkEncoder, Vocabulary, default_tokenizer
from privq.llm.common import table, text_or_empty, tidy

RUN_TOKENS = 4_000_000
SCHEMA = "row_id bigint, n_tokens int, input_ids binary, cu_seqlens array<int>, position_resets array<bigint>, doc_ids array<bigint>"
_ARROW = pa.schema([("row_id", pa.int64()), ("n_tokens", pa.int32()), ("input_ids", pa.binary()), ("cu_seqlens", pa.list_(pa.int32())), ("position_resets", pa.list_(pa.int64())), ("doc_ids", pa.list_(pa.int64()))])


class Capacities:
    """Open rows by free room; the tree knows for each range of rooms whether any row has it."""

    def __init__(self, most: int):
        self.size = 1 << most.bit_length()
        self.any = [0] * (2 * self.size)
        self.rows: list[list[int]] = [[] for _ in range(self.size)]

    def add(self, room: int, row: int) -> None:
        self.rows[room].append(row)
        if len(self.rows[room]) == 1:
            self._change(room, 1)

    def _change(self, room: int, by: int) -> None:
        k = self.size + room
        while k:
            self.any[k] += by
            k >>= 1

    def take(self, need: int) -> tuple[int, int] | None:
        """A row of the least room that is at least ``need``; it is no longer open."""
        k = self.size + need
        if not self.any[k]:
            while k > 1 and (k & 1 or not self.any[k + 1]):
                k >>= 1
            if k <= 1:
                return None
            k += 1
            while k < self.size:
                k *= 2
                if not self.any[k]:
                    k += 1
        room = k - self.size
        row = self.rows[room].pop()
        if not self.rows[room]:
            self._change(room, -1)
        return room, row


def best_fit_decreasing(lengths: list[int], length: int) -> list[list[int]]:
    """Rows as lists of piece numbers; every piece is at most ``length`` long."""
    open_rows, rows = Capacities(length), []
    for piece in sorted(range(len(lengths)), key=lambda k: (-lengths[k], k)):
        need = lengths[piece]
        found = open_rows.take(need)
        if found is None:
            rows.append([piece])
            room, row = length - need, len(rows) - 1
        else:
            room, row = found[0] - need, found[1]
            rows[row].append(piece)
        if room:
            open_rows.add(room, row)
    return rows


def pack(documents: list[tuple[int | None, np.ndarray]], length: int, first_row: int) -> pa.RecordBatch:
    pieces = [(doc, at, ids[at : at + length]) for doc, ids in documents for at in range(0, len(ids), length)]
    columns: list[list] = [[] for _ in _ARROW]
    for k, row in enumerate(best_fit_decreasing([len(p[2]) for p in pieces], length)):
        line = np.zeros(length, np.uint32)
        ends = np.cumsum([0, *(len(pieces[p][2]) for p in row)])
        for p, lo, hi in zip(row, ends[:-1], ends[1:], strict=True):
            line[lo:hi] = pieces[p][2]
        for column, value in zip(columns, (first_row + k, int(ends[-1]), line.tobytes(), ends.tolist(), [pieces[p][1] for p in row], [pieces[p][0] for p in row]), strict=True):
            column.append(value)
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, _ARROW, strict=True)], schema=_ARROW)


def position_ids(cu_seqlens: list[int], resets: list[int], length: int) -> np.ndarray:
    """Positions of a row: each segment counts on from its offset in the document; padding has 0."""
    out = np.zeros(length, np.int64)
    for lo, hi, start in zip(cu_seqlens[:-1], cu_seqlens[1:], resets, strict=True):
        out[lo:hi] = np.arange(start, start + hi - lo)
    return out


def unpack(rows: list[dict]) -> dict[int | None, list[tuple[int, list[int]]]]:
    """Segments (offset, ids) of each document id, by offset."""
    out: dict[int | None, list[tuple[int, list[int]]]] = {}
    for r in rows:
        ids = np.frombuffer(r["input_ids"], np.uint32)
        for doc, lo, hi, at in zip(r["doc_ids"], r["cu_seqlens"][:-1], r["cu_seqlens"][1:], r["position_resets"], strict=True):
            out.setdefault(doc, []).append((at, ids[lo:hi].tolist()))
    return {d: sorted(s, key=lambda x: x[0]) for d, s in out.items()}


def library_encoder(vocabulary: Vocabulary) -> Callable[[str], np.ndarray]:
    """Ids of a text by the fast library, which takes ids for ranks: they must grow with the merges.

    Its pattern engine gives up on very long runs of white space; such a text goes to the segment-tree encoder.
    """
    import tiktoken

    if any(a >= b for a, b in zip(vocabulary.merged, vocabulary.merged[1:], strict=False)):
        raise ValueError("ids must grow with the merges")
    plain = {b: i for i, b in vocabulary.bytes_of.items() if i not in vocabulary.special.values()}
    fast = tiktoken.Encoding("packing", pat_str=PRETOKEN, mergeable_ranks=plain, special_tokens=vocabulary.special)
    slow: list[ChunkEncoder] = []

    def encode(text: str) -> np.ndarray:
        try:
            return fast.encode_to_numpy(text, allowed_special="all")
        except ValueError:
            if not slow:
                slow.append(ChunkEncoder(vocabulary, list))
            return np.array(slow[0].ids(text), np.uint32)

    return encode


def _pack_batches(path: str, length: int, end_id: int | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary = Vocabulary(path)
        end = max(vocabulary.special.values(), default=0) if end_id is None else end_id
        encode = library_encoder(vocabulary)
        context = TaskContext.get()
        row = (context.partitionId() if context else 0) << 40
        held: list[tuple[int | None, np.ndarray]] = []
        tokens = 0
        for batch in batches:
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                line = np.append(encode(text), np.uint32(end))
                held.append((doc, line))
                tokens += len(line)
                if tokens >= RUN_TOKENS:
                    made = pack(held, length, row)
                    row, held, tokens = row + made.num_rows, [], 0
                    yield made
        if held:
            yield pack(held, length, row)

    return run


def pack_documents(df: DataFrame, tokenizer_path: str, length: int = 4096, text: str = "text", id_column: str = "doc_id", end_id: int | None = None) -> DataFrame:
    """Packed rows of all documents: ids as little-endian 32-bit words, zero after ``n_tokens``."""
    return df.select(df[id_column].cast("long").alias("doc_id"), text_or_empty(text).alias("text")).mapInArrow(tidy(_pack_batches(tokenizer_path, length, end_id)), SCHEMA)


def op1_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whole ``documents`` in rows of 4096 ids."""
    return pack_documents(table(spark, sf_dir, "documents").select("doc_id", "text"), default_tokenizer())
