"""Benchmark decontamination with a generalised suffix automaton of the test items.

The automaton accepts every word sequence that occurs in some item.  A document's words are
streamed through it once; after each word the state's match length is the longest suffix of
the stream that is part of an item.  A match of ``WINDOW`` words or more means that the last
``WINDOW`` words are an item's window.  Items shorter than the window are one window each;
their end states are found over the automaton's suffix links.

The items are cut into blocks of at most ``BLOCK_WORDS`` words.  Each block makes one
automaton of bounded size, which is broadcast; the documents pass all blocks in one stage, so
a benchmark of any size costs more passes, not more memory in one object.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

WINDOW = 13
BLOCK_WORDS = 100_000

_WORD = bytes(
    c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256)
)


def words_of(text: str | None) -> list[bytes]:
    """Lower-cased (A-Z) words: runs of digits, letters a-z and characters beyond ASCII."""
    return (text or "").encode("utf-8", "surrogatepass").translate(_WORD).split()


class Automaton:
    """A generalised suffix automaton over word numbers, with the windows of its items."""

    def __init__(self, items: list[tuple[str, list[bytes]]], window: int = WINDOW):
        self.window = window
        self.number: dict[bytes, int] = {}
        self.step: list[dict[int, int]] = [{}]
        self.link, self.length = [-1], [0]
        coded = []
        for name, words in items:
            if words:
                codes = [self.number.setdefault(w, len(self.number)) for w in words]
                coded.append((name, codes))
                last = 0
                for c in codes:
                    last = self._extend(last, c)
        self.shortest = min([min(len(codes), window) for _, codes in coded], default=window)
        n = len(self.step)
        order = sorted(range(n), key=self.length.__getitem__)
        #: The state of the window that ends a match in this state, or -1.
        self.window_state = [-1] * n
        for s in order[1:]:
            if self.length[s] >= window:
                up = self.link[s]
                self.window_state[s] = s if self.length[up] < window else self.window_state[up]
        self.items_at: dict[int, set[str]] = {}
        self.short_at: dict[int, list[tuple[int, str]]] = {}
        for name, codes in coded:
            s = 0
            for k, c in enumerate(codes):
                s = self.step[s][c]
                if k + 1 >= window:
                    self.items_at.setdefault(self.window_state[s], set()).add(name)
            if len(codes) < window:
                while self.length[self.link[s]] >= len(codes):
                    s = self.link[s]
                self.short_at.setdefault(s, []).append((len(codes), name))
        #: The nearest state on the way to the root, itself included, where a short item ends.
        self.short_up = [-1] * n
        for s in order[1:]:
            self.short_up[s] = s if s in self.short_at else self.short_up[self.link[s]]

    def _new(self, length: int, step: dict[int, int], link: int) -> int:
        self.length.append(length)
        self.step.append(step)
        self.link.append(link)
        return len(self.step) - 1

    def _split(self, p: int, q: int, c: int) -> int:
        """State q, reached from p by c over a longer path, is parted; returns the shorter part."""
        if self.length[q] == self.length[p] + 1:
            return q
        part = self._new(self.length[p] + 1, dict(self.step[q]), self.link[q])
        self.link[q] = part
        while p >= 0 and self.step[p].get(c) == q:
            self.step[p][c] = part
            p = self.link[p]
        return part

    def _extend(self, last: int, c: int) -> int:
        if c in self.step[last]:
            return self._split(last, self.step[last][c], c)
        new, p = self._new(self.length[last] + 1, {}, 0), last
        while p >= 0 and c not in self.step[p]:
            self.step[p][c] = new
            p = self.link[p]
        if p >= 0:
            self.link[new] = self._split(p, self.step[p][c], c)
        return new

    def scan(self, words: list[bytes]) -> tuple[list[tuple[int, int]], set[str], int]:
        """The hit spans [from, to) of the words, the items they belong to, and the longest match."""
        get = self.number.get
        codes = np.fromiter((get(w, -1) for w in words), np.int32, len(words))
        known = np.flatnonzero(np.diff(np.r_[False, codes >= 0, False].astype(np.int8)))
        spans: list[tuple[int, int]] = []
        items: set[str] = set()
        longest, window = 0, self.window
        step, link, length = self.step, self.link, self.length
        for a, b in zip(known[::2].tolist(), known[1::2].tolist(), strict=True):
            if b - a < self.shortest:
                continue
            s = depth = 0
            for at, c in enumerate(codes[a:b].tolist(), a):
                while s and c not in step[s]:
                    s = link[s]
                    depth = length[s]
                if c in step[s]:
                    s = step[s][c]
                    depth += 1
                if depth >= self.shortest:
                    longest = max(longest, depth)
                    reach = 0
                    if depth >= window:
                        items |= self.items_at.get(self.window_state[s], set())
                        reach = window
                    e = self.short_up[s]
                    while e > 0:
                        for size, name in self.short_at[e]:
                            if size <= depth:
                                items.add(name)
                                reach = max(reach, size)
                        e = self.short_up[link[e]]
                    if reach:
                        lo = at + 1 - reach
                        if spans and spans[-1][1] >= lo:
                            lo = min(lo, spans.pop()[0])
                        spans.append((lo, at + 1))
        return spans, items, longest


def _blocks(items: DataFrame, block_words: int) -> Iterator[list[tuple[str, list[bytes]]]]:
    block: list[tuple[str, list[bytes]]] = []
    size = 0
    for name, text in items.select(F.col("item_id").cast("string"), F.col("text").cast("string")).toLocalIterator():
        words = words_of(text)
        if block and size + len(words) > block_words:
            yield block
            block, size = [], 0
        block.append(("" if name is None else name, words))
        size += len(words)
    yield block


_FOUND = "struct<spans:array<bigint>,items:array<string>,longest:bigint,n_words:bigint,n_hit:bigint>"


def _merged(spans) -> list[list[int]]:
    """Spans (from, to, from, to, ...) in order, those that meet or overlap as one."""
    out: list[list[int]] = []
    for a, b in sorted(zip(spans[::2], spans[1::2], strict=True)):
        if out and a <= out[-1][1]:
            out[-1][1] = max(b, out[-1][1])
        else:
            out.append([a, b])
    return out


def _covered(spans: list[int]) -> int:
    return sum(b - a for a, b in _merged(spans))


def _finder(held):
    """The function that adds one block's spans and items to what earlier blocks have found."""

    opened: list[Automaton] = []  # once a worker, not once a batch

    @F.pandas_udf(_FOUND)
    def find(texts: pd.Series, before: pd.DataFrame) -> pd.DataFrame:
        if not opened:
            opened.append(pickle.loads(held.value))
        automaton = opened[0]
        rows = []
        for text, s0, i0, l0 in zip(texts, before["spans"], before["items"], before["longest"], strict=True):
            words = words_of(text)
            s, i, m = automaton.scan(words)
            spans = [*s0, *(x for pair in s for x in pair)]
            rows.append((spans, sorted({*i0, *i}), max(l0, m), len(words), _covered(spans)))
        return pd.DataFrame(rows, columns=["spans", "items", "longest", "n_words", "n_hit"])

    return find.asNondeterministic()  # so that a filter on its result stays above it and it runs once


def annotate(docs: DataFrame, items: DataFrame, window: int = WINDOW, block_words: int = BLOCK_WORDS) -> DataFrame:
    """The documents with a column __found: spans (from, to, from, to, ... in words; those of two
    blocks may overlap), items (their ids as text, sorted as text), longest match, n_words, n_hit.

    A null or wordless text has no words and no hits.  A null item text or an item without words
    has no window; a null item_id counts as the empty text.  Repeated items count once by id;
    repeated documents each give a row.  An empty benchmark matches nothing.  Of the benchmark
    only item_id and text are read.
    """
    spark = docs.sparkSession
    nothing = F.struct(
        F.array().alias("spans"), F.array().alias("items"), F.lit(0).alias("longest"), F.lit(0).alias("n_words"), F.lit(0).alias("n_hit")
    ).cast(_FOUND)
    out = docs.withColumn("__found", nothing)
    for block in _blocks(items, block_words):
        held = spark.sparkContext.broadcast(pickle.dumps(Automaton(block, window), protocol=5))
        out = out.withColumn("__found", _finder(held)(F.col("text").cast("string"), "__found"))
    return out


def matches(docs: DataFrame, items: DataFrame, window: int = WINDOW, block_words: int = BLOCK_WORDS) -> DataFrame:
    """(doc_id, spans, items, longest, n_words, n_hit) of every document; see ``annotate``."""
    return annotate(docs.select("doc_id", "text"), items, window, block_words).select("doc_id", "__found.*")


def contaminated() -> F.Column:
    """A hit of at least a twentieth of the words."""
    return (F.col("n_hit") > 0) & (F.col("n_hit") * 20 >= F.col("n_words"))


def clean(docs: DataFrame, items: DataFrame, window: int = WINDOW, max_length: int | None = None, max_coverage: float | None = None) -> DataFrame:
    """Documents without the spans that exceed a limit; all columns, others as they were.

    A document hit in more than ``max_coverage`` of its words loses all hit spans; in any other,
    spans longer than ``max_length`` words go.  A limit that is None is not looked at; without
    either, all hit spans go.  The span is cut out of the
    text from its first to its last character; the text around it stays byte for byte.
    """
    names = docs.columns

    @F.pandas_udf("string")
    def cut(texts: pd.Series, spans: pd.Series, n_words: pd.Series, n_hit: pd.Series) -> pd.Series:
        out = []
        for text, s, n, hit in zip(texts, spans, n_words, n_hit, strict=True):
            if not hit:
                out.append(text)
                continue
            every = max_length is None and max_coverage is None or max_coverage is not None and hit > max_coverage * n
            merged = _merged(s)
            raw = text.encode("utf-8", "surrogatepass")
            flat = raw.translate(_WORD)
            inside = np.frombuffer(flat, np.uint8) != 32
            edges = np.flatnonzero(np.diff(np.r_[False, inside, False].astype(np.int8)))
            kept, at = [], 0
            for a, b in merged:
                if every or (max_length is not None and b - a > max_length):
                    kept.append(raw[at : edges[2 * a]])
                    at = edges[2 * b - 1]
            out.append(b"".join([*kept, raw[at:]]).decode("utf-8", "surrogatepass"))
        return pd.Series(out, dtype=object)

    f = "__found."
    out = annotate(docs, items, window).withColumn("text", cut("text", f + "spans", f + "n_words", f + "n_hit"))
    return out.select(*names)


def drop_contaminated(docs: DataFrame, items: DataFrame, window: int = WINDOW) -> DataFrame:
    """The documents that are not contaminated, untouched, with all their columns."""
    found = annotate(docs, items, window)
    bad = (F.col("__found.n_hit") > 0) & (F.col("__found.n_hit") * 20 >= F.col("__found.n_words"))
    return found.where(~bad).select(*docs.columns)


def digest(docs: DataFrame, items: DataFrame) -> DataFrame:
    """The query's columns."""
    out = matches(docs, items)
    return out.select(
        "doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"),
        F.sha2(F.encode(F.array_join("items", ","), "UTF-8"), 256).alias("items_sha256"), contaminated().alias("contaminated"),
    )

