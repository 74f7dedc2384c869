"""Near-duplicate documents by 64-bit fingerprints and a byte-position inverted index.

A fingerprint bit is the majority of that bit over the hashes of all word shingles.  Two
fingerprints within ``RADIUS`` differing bits differ in at most ``RADIUS`` of their eight
bytes, so they share at least ``SHARED`` bytes *at the same position*.  The index therefore
posts every distinct fingerprint under sets of positional bytes chosen so that any two
fingerprints with that many shared bytes meet in at least one list.  Within a list the
shared positional bytes of every pair are tallied, pairs that reach the guaranteed minimum
are verified by their differing bits, and the list hands on a spanning forest of its links,
never all pairs.

Lists start with three bytes (eight sets: all triples of either half, since of five shared
positions three lie in one half).  A list longer than ``LONG_LIST`` is posted again under five
bytes - the triple and each pair of other positions - where 24 bits remain, so its length is
bounded by 2**24 and its links are found by looking up every mask of up to three bits.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import line_dedup
from .common import Scratch, components

RADIUS = 3
SHARED = 8 - RADIUS
LONG_LIST = 512
MASK_LIST = 3000

_LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
_TRIPLES = [t for half in ((0, 1, 2, 3), (4, 5, 6, 7)) for t in combinations(half, 3)]
_FIVES = list(combinations(range(8), SHARED))


def fingerprint_of(text: str | None, width: int = 3) -> int:
    """The signed 64-bit fingerprint of one text; 0 if it has no word."""
    import xxhash

    words = (text or "").encode("utf-8", "surrogatepass").translate(_LOWER).split()
    if not words:
        return 0
    digest = xxhash.xxh64_intdigest
    if len(words) < width:
        hashes = [digest(b" ".join(words), 42)]
    else:
        hashes = [digest(b" ".join(t), 42) for t in zip(*(words[i:] for i in range(width)), strict=False)]
    votes = np.zeros(64, np.int64)
    for at in range(0, len(hashes), 65536):
        part = np.array(hashes[at : at + 65536], np.uint64)
        votes += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(votes * 2 > len(hashes), bitorder="little").view(np.int64)[0])


def _fingerprint(width: int):
    @F.pandas_udf("long")
    def fp(texts: pd.Series) -> pd.Series:
        return pd.Series([fingerprint_of(t, width) for t in texts], dtype="int64")

    return fp


def fingerprints(docs: DataFrame, width: int = 3) -> DataFrame:
    """(doc_id, fp BIGINT) of every document, from its whole text."""
    return docs.select("doc_id", _fingerprint(width)(F.col("text").cast("string")).alias("fp"))


def _post(sets: list[tuple[int, ...]]) -> F.Column:
    """An array of the posting keys of column fp: the number of the set, then its bytes."""

    def byte(p: int) -> F.Column:
        return F.shiftrightunsigned(F.col("fp"), 8 * p).bitwiseAND(F.lit(255))

    keys = []
    for k, positions in enumerate(sets):
        key = F.lit(k).cast("long")
        for p in positions:
            key = F.shiftleft(key, 8).bitwiseOR(byte(p))
        keys.append(key)
    return F.array(*keys)


def _forest(fps: np.ndarray) -> np.ndarray:
    """For each fingerprint of one list, the index of the smallest one it is linked to in the list."""
    m = len(fps)
    root = np.arange(m)
    bits = fps.view(np.uint64)
    if m > MASK_LIST:
        order = np.argsort(bits)
        held = bits[order]
        varied = np.bitwise_or.reduce(bits ^ bits[0])
        places = [np.uint64(1) << np.uint64(i) for i in range(64) if int(varied) >> i & 1]
        masks = [np.bitwise_or.reduce(np.array(c, np.uint64)) for r in (1, 2, 3) for c in combinations(places, r)]

        def links() -> Iterator[tuple[np.ndarray, np.ndarray]]:
            for mask in masks:
                want = held ^ mask
                at = np.minimum(np.searchsorted(held, want), m - 1)
                hit = held[at] == want
                yield order[hit], order[at[hit]]
    else:
        octets = fps.view(np.uint8).reshape(-1, 8)

        def links() -> Iterator[tuple[np.ndarray, np.ndarray]]:
            step = max(1, 2_000_000 // m)
            for a in range(0, m, step):
                tally = np.zeros((min(step, m - a), m), np.uint8)
                for p in range(8):
                    tally += octets[a : a + step, p][:, None] == octets[:, p][None, :]
                i, j = np.nonzero(tally >= SHARED)
                i += a
                near = np.bitwise_count(bits[i] ^ bits[j]) <= RADIUS
                yield i[near & (i < j)], j[near & (i < j)]

    found = [(i, j) for i, j in links() if len(i)]
    moved = True
    while moved:
        moved = False
        for i, j in found:
            low = np.minimum(root[i], root[j])
            if (root[i] != low).any() or (root[j] != low).any():
                moved = True
                np.minimum.at(root, i, low)
                np.minimum.at(root, j, low)
        root = root[root]
    return root


def _links(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """From rows sorted by key, the links of each list as (member, root of its tree)."""
    rest = (np.empty(0, np.int64), np.empty(0, np.int64))

    def settle(key: np.ndarray, fp: np.ndarray) -> pd.DataFrame:
        starts = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
        sizes = np.diff(np.r_[starts, len(key)])
        two = starts[sizes == 2]
        a, b = fp[two], fp[two + 1]
        near = np.bitwise_count((a ^ b).view(np.uint64)) <= RADIUS
        out = [(a[near], b[near])]
        for s, n in zip(starts[sizes > 2], sizes[sizes > 2], strict=True):
            own = np.unique(fp[s : s + n])
            root = _forest(own)
            apart = root != np.arange(len(own))
            out.append((own[apart], own[root[apart]]))
        return pd.DataFrame({"a": np.concatenate([x for x, _ in out]), "b": np.concatenate([y for _, y in out])})

    for pdf in batches:
        key = np.concatenate([rest[0], pdf["key"].to_numpy(np.int64)])
        fp = np.concatenate([rest[1], pdf["fp"].to_numpy(np.int64)])
        if not len(key):
            continue
        cut = int(np.searchsorted(key, key[-1]))
        if cut:
            yield settle(key[:cut], fp[:cut])
        rest = (key[cut:], fp[cut:])
    if len(rest[0]):
        yield settle(*rest)


def _shared_lists(posted: DataFrame) -> DataFrame:
    """(key, fp, n) of the lists with two or more members."""
    sizes = posted.groupBy("key").agg(F.count("*").alias("n")).where("n > 1")
    return posted.join(sizes, "key")


def fingerprint_links(scratch: Scratch, distinct: DataFrame) -> DataFrame:
    """A spanning forest (a, b) of the links between distinct fingerprints (column fp)."""
    lists = scratch.keep(_shared_lists(distinct.select(F.explode(_post(_TRIPLES)).alias("key"), "fp")))
    short = lists.where(F.col("n") <= LONG_LIST).select("key", "fp")
    number = {s: k for k, s in enumerate(_FIVES)}
    finer = F.create_map(*[
        x
        for k, t in enumerate(_TRIPLES)
        for x in (F.lit(k), F.array(*[F.lit(number[tuple(sorted(t + two))]) for two in combinations([p for p in range(8) if p not in t], 2)]))
    ])
    set_no = F.shiftright("key", 24).cast("int")
    again = lists.where(F.col("n") > LONG_LIST).select("fp", F.explode(finer[set_no]).alias("k")).distinct()
    again = again.select("fp", F.element_at(_post(_FIVES), F.col("k") + 1).alias("key"))
    long = _shared_lists(again).select((F.col("key") + F.lit(1 << 60)).alias("key"), "fp")
    dealt = short.unionByName(long).repartition("key").sortWithinPartitions("key")
    return dealt.mapInPandas(_links, "a long, b long")


def near_duplicates(docs: DataFrame, width: int = 3) -> DataFrame:
    """Fingerprint and component of every document.

    Returns (doc_id, fp, component_id): component_id is the smallest doc_id whose fingerprint
    can be reached over links of at most three differing bits.

    Texts that are null, empty or blank have fingerprint 0 and are linked like any other
    document.  A null doc_id is kept; it is never a component's id unless the whole component
    has null ids (then component_id is null).  Repeated rows each give a row.  An empty table
    gives an empty result.  Only doc_id and text are read, so further columns cannot clash.
    """
    scratch = Scratch(docs.sparkSession, "simhash")
    fps = scratch.keep(fingerprints(docs, width))
    distinct = scratch.keep(fps.select("fp").distinct())
    roots = components(scratch, fingerprint_links(scratch, distinct)).select(F.col("node").alias("fp"), "root")
    placed = fps.join(roots, "fp", "left").select("doc_id", "fp", F.coalesce("root", "fp").alias("root"))
    least = placed.groupBy("root").agg(F.min("doc_id").alias("component_id"))
    return placed.join(least, "root").select("doc_id", "fp", "component_id")


def _by_fingerprint(scratch: Scratch, texts: DataFrame) -> DataFrame:
    """(h, root) of the distinct texts (h, fp) whose fingerprints are linked to those of others; root is the smallest h."""
    texts = scratch.keep(texts)
    distinct = scratch.keep(texts.select("fp").distinct())
    roots = components(scratch, fingerprint_links(scratch, distinct)).select(F.col("node").alias("fp"), F.col("root").alias("low"))
    placed = texts.join(roots, "fp", "left").select("h", F.coalesce("low", "fp").alias("low"))
    least = placed.groupBy("low").agg(F.min("h").alias("root"), F.count("*").alias("n")).where("n > 1").select("low", "root")
    return placed.join(least, "low").select("h", "root")


def copies(docs: DataFrame, width: int, similarity: float) -> DataFrame:
    """(doc_id, of, first) of every document: the name of its text, and whether it is the first of its component.

    First come the fingerprints' links of at most ``RADIUS`` differing bits, by the positional index.
    Two fingerprints of a similarity of 0.8 differ in about 10 of 64 bits and in up to 19, far beyond what
    that index can find; so where components still differ, candidates from MinHash over the same shingles
    are linked if the exact Jaccard similarity is reached.  Texts without a word are copies of each other.
    """
    scratch = Scratch(docs.sparkSession, "copies")
    text = line_dedup.normal(F.coalesce(F.col("text").cast("string"), F.lit("")))
    own = docs.select("doc_id", line_dedup.named(F.col("text")).alias("of"), text.alias("line")).withColumn("h", F.xxhash64("line"))
    own = scratch.keep(own.withColumn("fp", _fingerprint(width)(F.col("line"))))
    known = scratch.keep(_by_fingerprint(scratch, own.select("h", "fp").distinct()))
    roots = line_dedup.links(scratch, own.select("h", "line"), similarity, line_dedup.WORDS._replace(size=width), known)
    placed = own.select("doc_id", "of", "h").join(roots.select(F.col("node").alias("h"), "root"), "h", "left")
    placed = placed.select("doc_id", "of", F.coalesce("root", "h").alias("root"))
    order = F.struct(F.col("doc_id").isNull().alias("nameless"), "doc_id", "of")
    least = placed.groupBy("root").agg(F.min(order).alias("least"))
    return placed.join(least, "root").select("doc_id", "of", order.eqNullSafe(F.col("least")).alias("first"))


def keep_one(docs: DataFrame, width: int = 3, similarity: float = 0.8) -> DataFrame:
    """The documents that stay when one of each component of ``copies`` does, by fingerprints first: the one with the smallest doc_id.

    All columns of ``docs`` are returned.  Of repeated rows of that document one row stays.  Two
    rows that share an id but not a text are two documents: each goes or stays with its own component.
    Rows with a null doc_id stay only if no document of their component has an id, and then one.
    """
    firsts = copies(docs, width, similarity).where("first").groupBy("doc_id", "of").agg(F.count("*").alias("n"))
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.col("doc_id").alias("id"), line_dedup.named(F.col("text")).alias("name"))
    kept = rows.join(firsts, F.col("id").eqNullSafe(F.col("doc_id")) & (F.col("name") == F.col("of"))).select("row", "id", "name", "n")
    one = kept.where("n > 1").dropDuplicates(["id", "name"]).unionByName(kept.where("n = 1"))
    return one.select(*[F.col("row")[c].alias(c) for c in docs.columns])


def digest(docs: DataFrame) -> DataFrame:
    """The query's columns: doc_id, fingerprint (16 hex digits), component_id."""
    out = near_duplicates(docs)
    return out.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")
