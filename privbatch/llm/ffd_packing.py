"""Packing documents into sequences: first fit decreasing with a tournament tree of bins.

Documents are tokenized where they are read and cut into pieces of at most ``CAPACITY`` ids.
A piece needs only its length to be packed, so no id travels unless the caller wants the ids.
Pieces are dealt at random (by a hash of the place at which they were read, so copies part too)
into groups of about ``GROUP_PIECES`` pieces; every group is packed on its own.  In a group the pieces go in order of falling
length into the leftmost bin with room, which a tournament tree over the bins' free space
finds in logarithmic time.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch
from .tokens import Encoder, default_path

CAPACITY = 4096
GROUP_PIECES = 4096
END_ID = 2


class Tournament:
    """Bins with free space; a node holds the largest free space below it."""

    def __init__(self, bins: int, capacity: int):
        self.leaves = 1 << max(0, (bins - 1).bit_length())
        self.best = [capacity] * (2 * self.leaves)

    def place(self, size: int) -> tuple[int, int]:
        """The leftmost bin with room for ``size``, and where in it the piece begins is left to the caller."""
        best, at = self.best, 1
        while at < self.leaves:
            at *= 2
            if best[at] < size:
                at += 1
        left = best[at] - size
        best[at] = left
        where = at - self.leaves
        while at > 1:
            at //= 2
            best[at] = max(best[2 * at], best[2 * at + 1])
        return where, left


def first_fit_decreasing(lengths: np.ndarray, capacity: int = CAPACITY) -> tuple[np.ndarray, np.ndarray]:
    """Bin and offset of each piece (each at most ``capacity`` long); ties keep the given order."""
    order = np.argsort(-lengths, kind="stable")
    tree = Tournament(max(1, len(lengths)), capacity)
    bins, offsets = np.empty(len(lengths), np.int64), np.empty(len(lengths), np.int64)
    for i in order.tolist():
        size = int(lengths[i])
        where, left = tree.place(size)
        bins[i], offsets[i] = where, capacity - left - size
    return bins, offsets


def pieces(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY, end_id: int = END_ID, with_ids: bool = False) -> DataFrame:
    """(doc_id, start, length, ids_crc32, doc_tokens[, ids], place) of the pieces of every document.

    A null text counts as empty; every document has at least the end id, so at least one piece.
    Long documents become full pieces and one rest, each id in exactly one of them.  place numbers
    the pieces: the task that read it and its number there.  Ids travel as text, since a column
    of numbers with a null would come to Python in floating point.
    """
    path = path or default_path()
    names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", *(["ids"] if with_ids else []), "place"]
    schema = "doc_id string, start long, length long, ids_crc32 long, doc_tokens long, " + ("ids binary, " if with_ids else "") + "place long"

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from pyspark import TaskContext

        encode, place = Encoder.of(path, end_id), TaskContext.get().partitionId() << 40
        for pdf in batches:
            rows = []
            for doc_id, text in zip(pdf["doc_id"], pdf["text"], strict=True):
                ids = encode(text)
                for at in range(0, len(ids), 4 * capacity):
                    part = ids[at : at + 4 * capacity]
                    rows.append((doc_id, at // 4, len(part) // 4, zlib.crc32(part), len(ids) // 4, *([part] if with_ids else []), place))
                    place += 1
            yield pd.DataFrame(rows, columns=names)

    texts = docs.select(F.col("doc_id").cast("string").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return texts.mapInPandas(run, schema).withColumn("doc_id", F.col("doc_id").cast(docs.schema["doc_id"].dataType))


def pack(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY, end_id: int = END_ID, group_pieces: int = GROUP_PIECES, with_ids: bool = False) -> DataFrame:
    """Every piece with its place: doc_id, start, length, ids_crc32, doc_tokens[, ids], sequence_id, offset.

    sequence_id joins the number of the group and of the bin in it; offsets in a sequence are
    gapless from 0.  Repeated rows and null ids are packed like any others.  An empty table gives
    no sequence.  Only doc_id and text are read, so further columns cannot clash.  The pieces are
    written once, so they are counted and dealt without tokenizing again.
    """
    if capacity < 1 or group_pieces < 1:
        raise ValueError("capacity and group_pieces must be positive")
    cut = Scratch(docs.sparkSession, "pieces").keep(pieces(docs, path, capacity, end_id, with_ids))
    groups = max(1, -(-cut.count() // group_pieces))
    dealt = cut.withColumn("group_no", F.pmod(F.xxhash64("place"), F.lit(groups))).withColumn("doc_id", F.col("doc_id").cast("string"))
    names = [c for c in cut.columns if c != "place"]
    kinds = ", ".join(f"`{c}` {dealt.schema[c].dataType.simpleString()}" for c in names)

    def fill(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("place", ignore_index=True)
        bins, offsets = first_fit_decreasing(pdf["length"].to_numpy(), capacity)
        return pdf[names].assign(sequence_id=(pdf["group_no"].to_numpy() << 32) + bins, offset=offsets)

    out = dealt.groupBy("group_no").applyInPandas(fill, kinds + ", sequence_id long, offset long")
    return out.withColumn("doc_id", F.col("doc_id").cast(docs.schema["doc_id"].dataType))


def padding(packed: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """sequences, tokens, padding and padded share; a sequence whose length is a power of two needs none."""
    seq = packed.groupBy("sequence_id").agg(F.sum("length").alias("used"))
    pad = F.when(F.expr("used & (used - 1)") == 0, 0).otherwise(F.lit(capacity) - F.col("used"))
    out = seq.agg(F.count("*").alias("sequences"), F.sum("used").alias("tokens"), F.sum(pad).alias("padding"))
    return out.withColumn("share", F.col("padding") / (F.col("padding") + F.col("tokens")))


def digest(docs: DataFrame) -> DataFrame:
    """The query's columns."""
    return pack(docs).select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")
