"""Fuzzy line deduplication by MinHash, in DataFrame functions only.

1.  Lines (split at line feeds, white space collapsed and trimmed, lower-cased; blank ones take no
    part) are named by a 64-bit hash, so exact repeats fall together before anything else, and a
    line that fills a third of the table is worked on once.
2.  Signatures: shingles are all runs of five characters (``GRAMS``), or of five words for whole
    documents (``WORDS``); a text shorter than that is its own shingle.  Every shingle is hashed
    once and falls into one of ``BINS`` bins by its low bits; a bin keeps its smallest hash.  An
    empty bin borrows from the first filled one of a random order of its own, so each of the
    signature's values agrees between two lines with the probability of their Jaccard similarity,
    for short lines as for long ones.
3.  Banding: ``BANDS`` bands of ``ROWS`` values.  Lines that agree in a band are listed together
    (two lines of similarity 0.8 meet in some list with probability 0.99, of 0.85 with 0.999);
    they are candidates if ``AGREE`` of all values agree too (0.999 at 0.8).
4.  Every line is first verified against one line only: of the smallest members of its lists, the
    one that agrees most.  That ties a group of copies together with one check a line.  In a
    second turn every line of a list with members of several components is verified against the
    most agreeing of some drawn members of others.  Then, in lists with members of more than one
    component, all candidates of different components are verified that bit maps of their
    shingles do not rule out.  So no candidate link is lost, and pairs inside a component, of
    which a group of copies has the square, are never made.
5.  Candidates are verified by the exact Jaccard similarity of their shingle sets.
6.  Connected components of the verified links are found by star contractions, and of every
    component the first line stays: the one with the smallest document id and line number.

The documents are read for the distinct lines and for the lines' places.  Keys to look up are
broadcast only if at most ``MOST_BROADCAST`` were counted; beyond that the same join is shuffled.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce
from typing import NamedTuple

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Scratch, components

SIMILARITY = 0.8
BINS = 64
ROWS = 5
BANDS = 12
AGREE = 40
PROBES = 16
DEEP = 5
DRAWN = 4
TURNS = 1
WORDS_OF_BITS = 64
MOST_BROADCAST = 500_000


class Cut(NamedTuple):
    """What a shingle is: runs of ``size`` characters ("grams") or words ("words")."""

    kind: str
    size: int


GRAMS = Cut("grams", 5)
WORDS = Cut("words", 5)


def normal(line: Column) -> Column:
    """The line in lower case with single spaces between words; empty for any white space alone."""
    # most lines have single plain spaces only, which a search for bytes shows sooner than the pattern
    odd = [F.contains(line, F.lit(x)) for x in ("  ", "\t", "\r", "\f", "\x0b")]
    odd += [F.contains(line.cast("binary"), F.lit(bytearray(x))) for x in (b"\xc2\x85", b"\xc2\xa0", b"\xe1\x9a\x80", b"\xe2\x80", b"\xe2\x81\x9f", b"\xe3\x80\x80")]
    single = F.regexp_replace(line, r"[\s\x85\p{Z}]{2,}|[\t\x0B\f\r\x85\p{Z}&&[^ ]]", " ")
    return F.lower(F.trim(F.when(reduce(lambda a, b: a | b, odd), single).otherwise(line)))


def _looked_up(keys: DataFrame) -> DataFrame:
    """The keys, marked for broadcast if they are few enough."""
    return F.broadcast(keys) if keys.count() <= MOST_BROADCAST else keys


def named(text: Column) -> Column:
    """The name of a whole text."""
    return F.xxhash64(text.cast("string"))


def lines_of(docs: DataFrame) -> DataFrame:
    """(doc_id, of, pos, line, h) of every line that is not blank; h names its normal form, of the text it stands in."""
    own = docs.select("doc_id", named(F.col("text")).alias("of"), F.split(F.col("text").cast("string"), "\n", -1).alias("lines"))
    out = own.select("doc_id", "of", F.posexplode("lines").alias("pos", "line"))
    # as an array's only element the normal form is worked out once; a filter on a plain column would be moved below it, with a copy of its own
    out = out.select("doc_id", "of", "pos", F.explode(F.array(normal(F.col("line")))).alias("line")).where("line <> ''")
    return out.withColumn("h", F.xxhash64("line"))


# ---- shingles -----------------------------------------------------------------------------------


def _tokens(line: Column, cut: Cut) -> Column:
    """The line in a form in which the shingle at any place is found at once: words, or four bytes a character."""
    return F.split(line, " ") if cut.kind == "words" else F.encode(line, "UTF-32")


def _places(tokens: Column, cut: Cut) -> Column:
    """The places at which shingles begin; always one."""
    n = F.size(tokens) if cut.kind == "words" else F.shiftright(F.length(tokens), 2)
    return F.sequence(F.lit(0), F.greatest(F.lit(0), n - cut.size))


def _shingle(tokens: Column, at: Column, cut: Cut) -> Column:
    """The hash of the shingle that begins at a place."""
    if cut.kind == "words":
        return F.xxhash64(*[F.get(tokens, at + k) for k in range(cut.size)])
    return F.xxhash64(F.substring(tokens, at * 4 + 1, F.lit(4 * cut.size)))


def shingle_rows(lines: DataFrame, cut: Cut = GRAMS) -> DataFrame:
    """(h, n, x): the hashes of all n shingles of the lines, with repeats; compiled as one span, which array functions would break."""
    held = lines.select("h", _tokens(F.col("line"), cut).alias("tokens"))
    n = F.size("tokens") if cut.kind == "words" else F.shiftright(F.length("tokens"), 2)
    placed = held.select("h", "tokens", n.alias("n"), F.explode(_places(F.col("tokens"), cut)).alias("at"))
    return placed.select("h", "n", _shingle(F.col("tokens"), F.col("at"), cut).alias("x"))


def shingle_set(line: Column, cut: Cut = GRAMS) -> Column:
    """The distinct hashes of the shingles of one line."""
    own = F.transform(F.array(_tokens(line, cut)), lambda t: F.transform(_places(t, cut), lambda i: _shingle(t, i, cut)))
    return F.array_distinct(F.get(own, F.lit(0)))


# ---- signatures and bands -----------------------------------------------------------------------


def texts_of(lines: DataFrame) -> DataFrame:
    """(h, line) of every distinct line: the texts travel once, and equal ones meet before that."""
    return lines.groupBy("h").agg(F.first("line").alias("line"))


def _by_eights(rows: DataFrame, place: str, merged: Callable[[Column], Column], value: str, size: int, **more: Column) -> DataFrame:
    """(h, m, ...): for each h an array of ``size`` merged values by their place (0 to size - 1), null where there is none.

    Eight neighbours share a group, so that a line has few groups to look up and to sort.
    """
    at = F.col(place).bitwiseAND(F.lit(7))
    own = rows.groupBy("h", F.shiftright(place, 3).alias("eight")).agg(*[merged(F.when(at == k, F.col(value))).alias(f"m{k}") for k in range(8)], *[v.alias(k) for k, v in more.items()])
    held = own.groupBy("h").agg(
        F.map_from_entries(F.collect_list(F.struct("eight", F.array(*[f"m{k}" for k in range(8)]).alias("m")))).alias("e"),
        *[F.max(k).alias(k) for k in more],
    )
    return held.select("h", F.expr(f"flatten(transform(sequence(0, {size // 8 - 1}), k -> coalesce(e[k], array_repeat(CAST(NULL AS BIGINT), 8))))").alias("m"), *more)


def signatures(texts: DataFrame, cut: Cut = GRAMS) -> DataFrame:
    """(h, bands, g) of distinct lines (h, line): their keys in all bands, and eight bits of each value packed into longs.

    Shingles and bins are worked out where ``texts_of`` has put a text, so neither is shuffled.
    Of a line of many shingles only those are looked at that come within the lowest ``DEEP`` *
    ``BINS`` by expectation: a bin's smallest hash is among them but for one bin in e^DEEP.
    """
    value, bin_ = F.shiftrightunsigned("x", 6), F.col("x").bitwiseAND(F.lit(BINS - 1)).cast("int")
    low = F.expr(f"{1 << 58}L div greatest(n, {DEEP * BINS}) * {DEEP * BINS}")
    least = shingle_rows(texts, cut).where(value <= low).select("h", bin_.alias("bin"), value.alias("x"))
    held = _by_eights(least, "bin", F.min, "x", BINS)
    # where an empty bin looks next is the same for every line
    tries = ", ".join(f"get(m, cast(shiftright((k * {BINS} + {a}) * 2654435761L, 13) & {BINS - 1} AS int))" for a in range(1, PROBES))
    filled = held.select("h", F.expr(f"transform(sequence(0, {BINS - 1}), k -> coalesce(get(m, k), {tries}, array_min(m)))").alias("v"))
    keys = [f"xxhash64({b}, {', '.join(f'v[{b + BANDS * r}]' for r in range(ROWS))})" for b in range(BANDS)]
    packed = [" | ".join(f"shiftleft(v[{8 * i + j}] & 255, {8 * j})" for j in range(8)) for i in range(BINS // 8)]
    return filled.select("h", F.expr(f"array({', '.join(keys)})").alias("bands"), F.expr(f"array({', '.join(packed)})").alias("g"))


def bands(signed: DataFrame) -> DataFrame:
    """(band, h): the key of each line in each band."""
    return signed.select(F.explode("bands").alias("band"), "h")


def agreement(a: str, b: str, item: str = "{}[{}]") -> Column:
    """How many of the values of two signatures agree, from their packed bits; ``item`` writes a name and a place."""

    differing = []
    for i in range(BINS // 8):
        x = f"({item.format(a, i)} ^ {item.format(b, i)})"
        for shift, mask in ((4, 0x0F0F0F0F0F0F0F0F), (2, 0x0303030303030303), (1, 0x0101010101010101)):
            x = f"(({x} | shiftrightunsigned({x}, {shift})) & {mask}L)"
        differing.append(f"bit_count({x})")
    return F.expr(f"{BINS} - ({' + '.join(differing)})")


# ---- links --------------------------------------------------------------------------------------


def _ordered(a: str, b: str) -> list[Column]:
    return [F.least(a, b).alias("a"), F.greatest(a, b).alias("b")]


def _agreeing(pairs: DataFrame, signed: DataFrame) -> DataFrame:
    """(a, b, same) of the pairs of which ``AGREE`` values agree."""
    left = signed.select(F.col("h").alias("a"), F.col("g").alias("ga"))
    right = signed.select(F.col("h").alias("b"), F.col("g").alias("gb"))
    return pairs.join(left, "a").join(right, "b").select("a", "b", agreement("ga", "gb").alias("same")).where(F.col("same") >= AGREE)


def verified(scratch: Scratch, pairs: DataFrame, texts: DataFrame, similarity: float = SIMILARITY, cut: Cut = GRAMS) -> DataFrame:
    """The pairs (a, b) of distinct lines (h, line) whose shingle sets have the Jaccard similarity."""
    pairs = scratch.keep(pairs)
    used = _looked_up(scratch.keep(pairs.select(F.explode(F.array("a", "b")).alias("h")).distinct()))
    own = scratch.keep(texts.select("h", "line").join(used, "h"))
    both = pairs.join(own.select(F.col("h").alias("a"), F.col("line").alias("la")), "a")
    both = both.join(own.select(F.col("h").alias("b"), F.col("line").alias("lb")), "b")
    sets = F.array(F.struct(shingle_set(F.col("la"), cut).alias("x"), shingle_set(F.col("lb"), cut).alias("y")))
    shared = lambda p: F.size(F.array_intersect(p["x"], p["y"])) * F.lit(1 + similarity)
    enough = F.exists(sets, lambda p: shared(p) >= (F.size(p["x"]) + F.size(p["y"])) * F.lit(similarity * (1 - 1e-12)))
    return both.where(enough).select("a", "b")


def _open(scratch: Scratch, members: DataFrame, roots: DataFrame) -> DataFrame:
    """(band, h, root) of the lists whose members are of more than one component."""
    placed = members.join(_looked_up(roots), "h", "left").select("band", "h", F.coalesce("root", "h").alias("root"))
    placed = scratch.keep(placed)
    several = placed.groupBy("band").agg(F.min("root").alias("low"), F.max("root").alias("high")).where("low < high").select("band")
    return scratch.keep(placed.join(_looked_up(scratch.keep(several)), "band"))


def _drawn(scratch: Scratch, open_lists: DataFrame, signed: DataFrame, turn: int) -> DataFrame:
    """One candidate (a, b) a line of open lists: of ``DRAWN`` members a list, drawn by hash, those of other components, the one that agrees most."""
    reps = open_lists.groupBy("band").agg(*[F.min_by(F.struct("h", "root"), F.xxhash64("h", F.lit(turn * DRAWN + k))).alias(f"r{k}") for k in range(DRAWN)])
    met = open_lists.join(reps, "band").select("h", "root", F.explode(F.array(*[f"r{k}" for k in range(DRAWN)])).alias("rep"))
    pairs = met.where(F.col("root") != F.col("rep.root")).select(F.least("h", "rep.h").alias("a"), F.greatest("h", "rep.h").alias("b")).distinct()
    ends = scratch.keep(_agreeing(pairs, signed)).select(F.explode(F.array("a", "b")).alias("h"), "a", "b", "same")
    best = ends.groupBy("h").agg(F.max_by(F.struct("a", "b"), F.struct("same", "a", "b")).alias("pair"))
    return best.select("pair.a", "pair.b").distinct()


def _with_candidates(scratch: Scratch, open_lists: DataFrame, signed: DataFrame) -> DataFrame:
    """(h) of the lines that have candidates of other components in open lists; the join looks for one only and yields none of the pairs."""
    own = signed.select("h", "g").join(_looked_up(scratch.keep(open_lists.select("h").distinct())), "h")
    # a column for each long, which the join reads without unpacking an array for every pair
    placed = scratch.keep(open_lists.join(own, "h").select("band", "h", "root", *[F.col("g")[i].alias(f"g{i}") for i in range(BINS // 8)]))
    x, y = (placed.select(*[F.col(c).alias(f"{side}_{c}") for c in placed.columns]) for side in "xy")
    apart = (F.col("x_band") == F.col("y_band")) & (F.col("x_root") != F.col("y_root")) & (agreement("x_g", "y_g", "{}{}") >= AGREE)
    near = scratch.keep(x.join(y, apart, "left_semi").select(F.col("x_h").alias("h")).distinct())
    scratch.drop(placed)
    scratch.release()
    return near


def _across(scratch: Scratch, open_lists: DataFrame, signed: DataFrame, similarity: float, cut: Cut) -> DataFrame:
    """All candidates (a, b) of different components in open lists that may have the similarity.

    Lines without a candidate of another component are let go first, by their signatures alone.
    The join of the others compares what it meets before it yields a row: signatures, then, for two
    lines in the first list that they share, bit maps of their shingles.  A shared shingle is a shared
    bit, but for those that fall together within a line, which are allowed for; so no similar
    pair is lost, and few others come out.
    """
    near = _looked_up(_with_candidates(scratch, open_lists, signed))
    open_lists = open_lists.join(near, "h")
    own = scratch.keep(signed.join(near, "h").select("h", "g", "bands", "line"))
    bits = own.select("h", "line").repartition("h").select("h", shingle_set(F.col("line"), cut).alias("x"))
    bits = bits.select("h", F.size("x").alias("n"), F.explode("x").alias("x"))
    word = F.shiftrightunsigned("x", 12).bitwiseAND(F.lit(WORDS_OF_BITS - 1)).cast("int")
    bits = bits.select("h", "n", word.alias("w"), F.expr("shiftleft(1L, cast(shiftrightunsigned(x, 6) & 63 AS int))").alias("b"))
    bits = _by_eights(bits, "w", F.bit_or, "b", WORDS_OF_BITS, n=F.max("n")).select("h", "n", F.transform("m", lambda b: F.coalesce(b, F.lit(0).cast("long"))).alias("s"))
    bits = bits.select("h", "n", F.aggregate("s", F.lit(0), lambda k, b: k + F.bit_count(b)).alias("k"), "s")
    left = open_lists.join(scratch.keep(own.select("h", "g", "bands").join(bits, "h")), "h")
    scratch.release()
    names = ["h", "root", "g", "bands", "n", "k", "s"]
    x, y = (left.select(F.col("band").alias(f"band{side}"), *[F.col(c).alias(f"{c}{side}") for c in names]) for side in "xy")
    first = F.expr("coalesce(" + ", ".join(f"CASE WHEN bandsx[{i}] = bandsy[{i}] THEN bandsx[{i}] END" for i in range(BANDS)) + ")")
    common = F.aggregate(F.zip_with("sx", "sy", lambda a, b: F.bit_count(a.bitwiseAND(b))), F.lit(0), lambda n, b: n + b)
    shared = common + F.least(F.col("nx") - F.col("kx"), F.col("ny") - F.col("ky"))
    similar = shared * F.lit(1 + similarity) >= (F.col("nx") + F.col("ny")) * F.lit(similarity * (1 - 1e-12))
    apart = (F.col("bandx") == F.col("bandy")) & (F.col("rootx") < F.col("rooty")) & (agreement("gx", "gy") >= AGREE)
    return x.join(y, apart & (first == F.col("bandx")) & similar).select(*_ordered("hx", "hy"))


def _apart(pairs: DataFrame, named: DataFrame) -> DataFrame:
    """The pairs (a, b) whose ends are not of one component (h, root)."""
    root_of = lambda side: named.select(F.col("h").alias(side), F.col("root").alias(f"r{side}"))
    placed = pairs.join(root_of("a"), "a", "left").join(root_of("b"), "b", "left")
    return placed.where(F.coalesce("ra", "a") != F.coalesce("rb", "b")).select("a", "b")


def links(scratch: Scratch, lines: DataFrame, similarity: float = SIMILARITY, cut: Cut = GRAMS, known: DataFrame | None = None) -> DataFrame:
    """(node, root) of every distinct line (h, line) that is linked to another one.

    ``known`` names components (h, root) found before: they are kept, and no pair inside one is verified.
    """
    held = Scratch(lines.sparkSession, "links")  # all that only this step needs
    texts = texts_of(lines)
    signed = held.keep(texts.join(signatures(texts, cut), "h"))
    held.release()
    posted = bands(signed)
    lists = posted.groupBy("band").agg(F.count("*").alias("n"), F.min("h").alias("a"), F.max("h").alias("b")).where("n > 1")
    lists = held.keep(lists)
    members = held.keep(posted.join(_looked_up(lists.where("n > 2").select("band", "a")), "band"))
    held.release()
    # the smallest member of a list against each other one
    tied = lists.where("n = 2").select("a", "b").unionByName(members.where("h <> a").select("a", F.col("h").alias("b"))).distinct()
    tied = held.keep(_agreeing(tied, signed))
    nearest = tied.groupBy("b").agg(F.max_by("a", F.struct("same", "a")).alias("a")).select("a", "b")
    if known is None:
        first = verified(held, nearest, signed, similarity, cut)
    else:
        first = verified(held, _apart(nearest, known), signed, similarity, cut).unionByName(known.select(F.col("h").alias("a"), F.col("root").alias("b")))
    roots = components(held, held.keep(first))
    named = held.keep(roots.select(F.col("node").alias("h"), "root"))

    def joined(more: DataFrame) -> DataFrame | None:
        """The components with the verified ones of these candidates; None if none is."""
        extra = held.keep(verified(held, more, signed, similarity, cut))
        if extra.isEmpty():
            return None
        tree = named.select(F.col("h").alias("a"), F.col("root").alias("b"))
        return held.keep(components(held, tree.unionByName(extra)).select(F.col("node").alias("h"), "root"))

    for turn in range(TURNS):
        after = joined(_drawn(held, _open(held, members, named), signed, turn))
        if after is None:
            break
        named = after
    # ties not checked yet, and candidates in lists of more than two, where components still differ
    apart = _apart(tied.join(nearest, ["a", "b"], "left_anti"), named)
    named = joined(apart.unionByName(_across(held, _open(held, members, named), signed, similarity, cut)).distinct()) or named
    out = scratch.keep(named.select(F.col("h").alias("node"), "root"))
    held.clear()
    return out


def verdicts(docs: DataFrame, similarity: float = SIMILARITY, scratch: Scratch | None = None, cut: Cut = GRAMS) -> DataFrame:
    """(doc_id, of, pos, h, kept) of every line that is not blank; of names the text it stands in.

    A null or empty text has no lines.  Lines of any length take part.  A null doc_id sorts
    before all ids.  Repeated rows of one document count as one document: their lines get the
    same verdict.  Ties between equal lines go to the smallest (doc_id, pos).  An empty table
    gives an empty result.  Only doc_id and text are read.
    """
    scratch = scratch or Scratch(docs.sparkSession, "lines")
    lines = lines_of(docs)
    roots = links(scratch, lines, similarity, cut).select(F.col("node").alias("h"), "root")
    placed = lines.select("doc_id", "of", "pos", "h").join(_looked_up(roots), "h", "left")
    placed = scratch.keep(placed.select("doc_id", "of", "pos", "h", F.coalesce("root", "h").alias("root")))
    # a line that is alone in its component stays, and needs no partner in the join
    first = placed.groupBy("root").agg(F.min(F.struct("doc_id", "pos")).alias("first"), F.count("*").alias("n")).where("n > 1").select("root", "first")
    judged = placed.join(_looked_up(scratch.keep(first)), "root", "left")
    kept = F.col("first").isNull() | F.struct("doc_id", "pos").eqNullSafe(F.col("first"))
    return judged.select("doc_id", "of", "pos", "h", kept.alias("kept"))


def _without(text: Column, gone: Column) -> Column:
    """The text without the lines of these rising numbers: what lies between them, put together again."""

    def joined(parts: Column) -> Column:
        low = lambda k: F.coalesce(F.get(gone, k - 1) + 1, F.lit(0))
        high = lambda k: F.coalesce(F.get(gone, k), F.size(parts))
        between = F.transform(F.sequence(F.lit(0), F.size(gone)), lambda k: F.slice(parts, low(k) + 1, high(k) - low(k)))
        return F.array_join(F.flatten(between), "\n")

    return F.get(F.transform(F.array(F.split(text, "\n", -1)), joined), F.lit(0))


def dedup_lines(docs: DataFrame, similarity: float = SIMILARITY, cut: Cut = GRAMS) -> DataFrame:
    """The documents without their repeated lines; all columns and all documents stay.

    Blank lines stay.  n_chars, if there is such a column, is set to the new length.  A null
    text stays null; a text all of whose lines go becomes empty.
    """
    gone = verdicts(docs, similarity, cut=cut).where("not kept").groupBy("doc_id", "of").agg(F.sort_array(F.collect_set("pos")).alias("gone"))
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.col("doc_id").alias("id"), named(F.col("text")).alias("of"))
    out = rows.join(gone.withColumnRenamed("of", "name"), F.col("id").eqNullSafe(F.col("doc_id")) & (F.col("of") == F.col("name")), "left")
    cut_text = F.when(F.col("gone").isNull(), F.col("row.text")).otherwise(_without(F.col("row.text").cast("string"), F.col("gone")))
    out = out.select("row", cut_text.alias("text"), F.col("gone").isNotNull().alias("cut"))
    fresh = {"text": F.col("text")}
    if "n_chars" in docs.columns:
        fresh["n_chars"] = F.when(F.col("cut"), F.length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("row.n_chars"))
    return out.select(*[fresh.get(c, F.col("row")[c]).alias(c) for c in docs.columns])


def digest(docs: DataFrame, cut: Cut = GRAMS) -> DataFrame:
    """(doc_id, n_lines, n_removed, removed): the numbers of the lines that go, rising."""
    scratch = Scratch(docs.sparkSession, "lines")
    seen = verdicts(docs, scratch=scratch, cut=cut).groupBy("doc_id").agg(
        F.size(F.collect_set("pos")).cast("long").alias("n_lines"),
        F.sort_array(F.collect_set(F.when(~F.col("kept"), F.col("pos")))).alias("removed"),
    )
    ids = docs.select(F.col("doc_id").alias("d")).distinct()
    out = ids.join(seen, F.col("d").eqNullSafe(F.col("doc_id")), "left")
    gone = F.coalesce("removed", F.array().cast("array<int>"))
    return out.select(F.col("d").alias("doc_id"), F.coalesce("n_lines", F.lit(0)).alias("n_lines"), F.size(gone).cast("long").alias("n_removed"), gone.alias("removed"))
