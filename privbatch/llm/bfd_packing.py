"""Token ids in binary form: best-fit-decreasing packing into rows of fixed width.

A task packs what it reads, window by window: texts are tokenized, cut losslessly into pieces
no longer than a row, and a window of at most ``WINDOW_IDS`` ids is packed by falling length,
each piece into the fullest row that still has room.  A segment tree over free space finds that
row: a leaf per amount of free space counts the open rows with it, and the search asks for the
smallest amount that suffices.  Nothing is shuffled, so a lost task is packed anew from its
input alone, and memory is bounded by the window.

Each result row is one packed sequence: its ids as a little-endian matrix row, padded to the
full width, the cumulative lengths of its segments, and position ids that start at zero in every
segment and in the padding.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .tokens import Encoder, default_path

WIDTH = 4096
WINDOW_IDS = 4_000_000
END_ID = 2
PAD_ID = 0
SCHEMA = (
    "sequence_id long, n_tokens int, ids binary, position_ids binary, cu_seqlens array<int>, "
    "doc_ids array<string>, row_ids array<bigint>, starts array<bigint>, doc_tokens array<bigint>"
)


class FreeSpace:
    """A segment tree over amounts of free space 0..capacity; a node counts the open rows below it."""

    def __init__(self, capacity: int):
        self.leaves = 1 << capacity.bit_length()
        self.count = [0] * (2 * self.leaves)
        self.rows: list[list[int]] = [[] for _ in range(capacity + 1)]

    def _shift(self, amount: int, by: int) -> None:
        at = self.leaves + amount
        while at:
            self.count[at] += by
            at //= 2

    def put(self, amount: int, row: int) -> None:
        if amount:
            self.rows[amount].append(row)
            self._shift(amount, 1)

    def take(self, need: int) -> tuple[int, int] | None:
        """The open row with the least free space that is at least ``need``, and that space; it is taken out."""
        count, at = self.count, self.leaves + need
        if not count[at]:
            while at > 1 and (at & 1 or not count[at + 1]):
                at //= 2
            if at <= 1:
                return None
            at += 1
            while at < self.leaves:
                at *= 2
                if not count[at]:
                    at += 1
        amount = at - self.leaves
        self._shift(amount, -1)
        return self.rows[amount].pop(), amount


def best_fit_decreasing(lengths: list[int], capacity: int) -> list[list[int]]:
    """The pieces of each row, in the order they were put in."""
    free, rows = FreeSpace(capacity), []
    for i in sorted(range(len(lengths)), key=lambda i: -lengths[i]):
        found = free.take(lengths[i])
        if found:
            row, space = found
        else:
            row, space = len(rows), capacity
            rows.append([])
        rows[row].append(i)
        free.put(space - lengths[i], row)
    return rows


def pack_rows(docs: DataFrame, path: str | None = None, width: int = WIDTH, end_id: int = END_ID, window_ids: int = WINDOW_IDS) -> DataFrame:
    """Packed rows of all documents.

    A null text counts as empty and gives the end id alone; a null doc_id stays null, and ids of
    any type keep it.  Repeated rows are packed each; ``row_ids`` numbers the rows of the table, so
    that concatenating a row's segments by ``starts`` gives its ids whatever its doc_id.  An empty
    table gives no row.  sequence_id joins the number of the task and of the row in it.  Only doc_id
    and text are read.
    """
    path = path or default_path()
    if width < 1:
        raise ValueError("width must be positive")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from pyspark import TaskContext

        encode, task, made, row_no = Encoder.of(path, end_id), TaskContext.get().partitionId(), 0, 0

        def flush(held: list[tuple[str | None, int, int, np.ndarray, int]]) -> Iterator[pd.DataFrame]:
            nonlocal made
            out = []
            for row in best_fit_decreasing([len(p[3]) for p in held], width):
                own = [held[i] for i in row]
                sizes = np.array([len(p[3]) for p in own], np.int32)
                ends = np.cumsum(sizes, dtype=np.int32)
                ids, positions = np.full(width, PAD_ID, "<u4"), np.zeros(width, "<i4")
                ids[: ends[-1]] = np.concatenate([p[3] for p in own])
                positions[: ends[-1]] = np.arange(ends[-1]) - np.repeat(ends - sizes, sizes)
                out.append((
                    (task << 36) + made, int(ends[-1]), ids.tobytes(), positions.tobytes(), np.r_[np.int32(0), ends],
                    [p[0] for p in own], [p[1] for p in own], [p[2] for p in own], [p[4] for p in own],
                ))
                made += 1
                if len(out) >= 256:
                    yield pd.DataFrame(out, columns=names)
                    out = []
            if out:
                yield pd.DataFrame(out, columns=names)

        names = ["sequence_id", "n_tokens", "ids", "position_ids", "cu_seqlens", "doc_ids", "row_ids", "starts", "doc_tokens"]
        held: list[tuple[str | None, int, int, np.ndarray, int]] = []
        size = 0
        for pdf in batches:
            for doc_id, text in zip(pdf["doc_id"], pdf["text"], strict=True):
                ids = np.frombuffer(encode(text), "<u4")
                for at in range(0, len(ids), width):
                    held.append((doc_id, (task << 36) + row_no, at, ids[at : at + width], len(ids)))
                    size += min(width, len(ids) - at)
                    if size >= window_ids:
                        yield from flush(held)
                        held, size = [], 0
                row_no += 1
        if held:
            yield from flush(held)

    texts = docs.select(F.col("doc_id").cast("string").alias("doc_id"), F.col("text").cast("string").alias("text"))
    kind = docs.schema["doc_id"].dataType.simpleString()
    return texts.mapInPandas(run, SCHEMA).withColumn("doc_ids", F.col("doc_ids").cast(f"array<{kind}>"))


def write_binary(packed: DataFrame, folder: str) -> None:
    """Writes the rows as Parquet in ``folder``, a file a task: every row of ids and of positions has the same width in bytes."""
    packed.write.mode("overwrite").parquet(folder)


def matrices(path: str, width: int = WIDTH) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """The id and position matrices of one written file, row group by row group, without a copy into rows."""
    import pyarrow.parquet as pq

    file = pq.ParquetFile(path)
    for k in range(file.num_row_groups):
        part = file.read_row_group(k, columns=["ids", "position_ids"])
        yield tuple(np.frombuffer(b"".join(part[c].to_pylist()), kind).reshape(-1, width) for c, kind in (("ids", "<u4"), ("position_ids", "<i4")))


def unpack(packed: DataFrame) -> DataFrame:
    """(doc_id, row_id, start, ids binary, doc_tokens): the segments back, for an exact round trip."""
    cut = F.expr(
        "transform(sequence(0, size(starts) - 1), i -> struct(doc_ids[i] as doc_id, row_ids[i] as row_id, starts[i] as start, doc_tokens[i] as doc_tokens,"
        " substring(ids, 4 * cu_seqlens[i] + 1, 4 * (cu_seqlens[i + 1] - cu_seqlens[i])) as ids))"
    )
    return packed.select(F.inline(cut)).select("doc_id", "row_id", "start", "ids", "doc_tokens")
