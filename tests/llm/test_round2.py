"""Rows, limits and odd pages that the second review asked for, against brute force."""

import time
import zlib

import numpy as np
import pytest

from privbatch.llm import bfd_packing, crf_language, decontaminate, ffd_packing, line_dedup, simhash, top_k, wrapper
from privbatch.llm.tokens import Encoder, default_path

BIG = 9007199254740993  # not a floating-point number


def test_op8_ids_beside_null_and_copies(spark):
    """Ids stay what they are beside a null one; copies of one document are dealt to all groups."""
    rows = [(BIG, "one two"), (None, "three"), (BIG + 1, None)] + [(7, "the same text again and again")] * 60
    df = spark.createDataFrame(rows, "doc_id long, text string")
    packed = ffd_packing.pack(df, capacity=16, group_pieces=8)
    assert {r["doc_id"] for r in packed.collect()} == {BIG, BIG + 1, None, 7}
    groups = packed.where("doc_id = 7").selectExpr("sequence_id >> 32 AS g").distinct().count()
    assert groups >= 4 and packed.count() == 63
    text_ids = spark.createDataFrame([("a", "one"), (None, "two")], "doc_id string, text string")
    assert {r["doc_id"] for r in ffd_packing.digest(text_ids).collect()} == {"a", None}


def test_op4_round_trip_in_fixed_rows(spark, tmp_path):
    """Every row's ids come back from the written matrix, whatever the ids; rows are of one width; positions start anew."""
    long = " ".join(f"word{i}" for i in range(900))
    rows = [("x", long), ("x", "one"), (None, "two words"), ("-1", None), ("", "")]
    df = spark.createDataFrame(rows, "doc_id string, text string").coalesce(1)
    folder = str(tmp_path / "packed")
    bfd_packing.write_binary(bfd_packing.pack_rows(df, width=256), folder)
    packed = spark.read.parquet(folder)
    encode, back = Encoder.of(default_path(), 2), {}
    for r in bfd_packing.unpack(packed).collect():
        back.setdefault((r["row_id"], r["doc_id"]), []).append((r["start"], bytes(r["ids"])))
    got = sorted((key[1] or "", b"".join(p for _, p in sorted(parts))) for key, parts in back.items())
    assert got == sorted((i or "", encode(t)) for i, t in rows)
    files = [str(f) for f in (tmp_path / "packed").glob("*.parquet")]
    ids = np.concatenate([m for f in files for m, _ in bfd_packing.matrices(f, 256)])
    positions = np.concatenate([m for f in files for _, m in bfd_packing.matrices(f, 256)])
    assert ids.shape == positions.shape == (packed.count(), 256)
    for r in packed.collect():
        ends = r["cu_seqlens"]
        own = np.frombuffer(r["position_ids"], "<i4")
        assert all((own[a:b] == np.arange(b - a)).all() for a, b in zip(ends, ends[1:])) and not own[ends[-1] :].any()
        assert ends[-1] == r["n_tokens"] and not np.frombuffer(r["ids"], "<u4")[ends[-1] :].any()
    assert bfd_packing.pack_rows(df.limit(0)).count() == 0


def test_op4_assignment_is_best_fit():
    """Each piece goes to the fullest row with room, of which any will do: free spaces follow plain best fit step by step."""
    rng = np.random.default_rng(9)
    lengths = rng.integers(1, 60, 150).tolist()
    rows = bfd_packing.best_fit_decreasing(lengths, 64)
    place = {i: k for k, r in enumerate(rows) for i in r}
    free: dict[int, int] = {}
    for i in sorted(range(150), key=lambda i: -lengths[i]):
        room = [f for f in free.values() if f >= lengths[i]]
        k = place[i]
        assert free[k] == min(room) if room else k not in free
        free[k] = free.get(k, 64) - lengths[i]


def test_op6_repeated_query_ids(spark):
    """A query id with one unusable row still asks, by its usable one."""
    rows = [(50, None), (50, [1.0, 2.0]), (1, [1.0, 0.0]), (2, [0.0, 1.0]), (100, [float("nan"), 1.0])]
    got = top_k.digest(spark.createDataFrame(rows, "vec_id long, embedding array<float>")).collect()
    assert [(r["query_id"], r["rank"], r["vec_id"], r["score"]) for r in got] == [(50, 1, 2, 2 * 256 * 256), (50, 2, 1, 256 * 256)]
    wide = spark.createDataFrame([(0, [1.0], 5, 6), (0, [1.0], 5, 6), (3, [2.0], 7, 8)], "vec_id long, embedding array<float>, square int, n int")
    assert [(r["query_id"], r["vec_id"]) for r in top_k.digest(wide).collect()] == [(0, 3)]


def test_op10_limits(spark):
    """max_length alone keeps shorter spans; max_coverage alone keeps documents below it whole."""
    items = spark.createDataFrame([("a", "alpha beta gamma"), ("b", " ".join(f"w{i}" for i in range(30)))], "item_id string, text string")
    docs = spark.createDataFrame([(1, "x alpha beta gamma y"), (2, "pre " + " ".join(f"w{i}" for i in range(30)) + " post")], "doc_id long, text string")

    def clean(**limits):
        return {r["doc_id"]: r["text"] for r in decontaminate.clean(docs, items, **limits).collect()}

    assert clean(max_length=20) == {1: "x alpha beta gamma y", 2: "pre  post"}
    assert clean(max_coverage=0.7) == {1: "x alpha beta gamma y", 2: "pre  post"}
    assert clean() == {1: "x  y", 2: "pre  post"}
    assert clean(max_length=50, max_coverage=0.99) == {r["doc_id"]: r["text"] for r in docs.collect()}


def test_keep_one_rows_that_share_an_id(spark):
    """Two rows of one id with different texts are two documents; repeated rows are one."""
    text = [" ".join(f"{c}{i}" for i in range(40)) for c in "abc"]
    rows = [(1, text[0], 1), (1, text[1], 2), (1, text[1], 2), (2, text[0], 3), (None, text[2], 4), (None, text[2], 5), (None, text[1], 6)]
    df = spark.createDataFrame(rows, "doc_id long, text string, root int")
    got = sorted(((r["doc_id"] or 0), r["text"]) for r in simhash.keep_one(df, width=5).collect())
    assert got == sorted([(1, text[0]), (1, text[1]), (0, text[2])])
    assert simhash.keep_one(df).columns == df.columns


def test_op2_learns_every_language(spark):
    """More languages than sixty-four are told apart."""
    rng = np.random.default_rng(4)
    words = {f"l{k:02d}": ["".join(chr(97 + int(c)) for c in rng.integers(0, 26, 6)) for _ in range(12)] for k in range(70)}
    rows = [(i, " ".join(rng.choice(words[lang], 30)), lang) for i, lang in enumerate([*words] * 6)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    field = crf_language.fit(docs)
    assert field.langs == sorted(words)
    got = {r["doc_id"]: r["lang_pred"] for r in crf_language.predict(docs, field).where("held_out").collect()}
    assert np.mean([got[i] == lang for i, _, lang in rows if i in got]) > 0.9
    labelled = crf_language.label_words(docs.limit(3), field).collect()
    assert all(len(r["words"]) == 30 and all(0 <= w["p"] <= 1 for w in r["words"]) for r in labelled)


def _plain(a, b):
    """The size of the largest simple matching, by the recursion alone."""
    if a.label != b.label:
        return 0
    m, n = len(a.children), len(b.children)
    most = [[0] * (n + 1) for _ in range(m + 1)]
    for i in range(m):
        for j in range(n):
            most[i + 1][j + 1] = max(most[i][j + 1], most[i + 1][j], most[i][j] + _plain(a.children[i], b.children[j]))
    return 1 + most[m][n]


def test_op5_match_is_simple_tree_matching():
    rng = np.random.default_rng(6)

    def tree(depth):
        inner = "".join(tree(depth - 1) for _ in range(int(rng.integers(0, 4)))) if depth else "t"
        tag = rng.choice(["div", "section", "ul"])
        return f"<{tag}>{inner}</{tag}>"

    for _ in range(40):
        a, b = (wrapper.Folded(wrapper.parse("<body>" + tree(4) + tree(4))[0], "") for _ in range(2))
        size, pairs = wrapper.match(a, b)
        assert size == _plain(a, b) == len(pairs) and all(x.label == y.label for x, y in pairs)


def test_op5_broken_pages(spark):
    """Deep nesting, quotes that never end and class names with common words."""
    deep = "<div>" * 5000 + "deep text" + "</div>" * 5000 + "<p>after"
    rows = [
        (1, "http://a/", deep), (2, "http://b/", '<p>one</p>' + '<a "' * 4000 + "tail"), (3, "http://c/", "<p>text <b title=\"open>bold</b> more</p><p>next</p>"),
        (4, "http://d/", '<div class="post side-by-side"><p>whole</p><div class="post-comments"><p>said</p></div></div>'), (5, "http://e/", "a </ 3 < 4 <"),
    ]
    began = time.time()
    got = {r["page_id"]: r["text"] for r in wrapper.digest(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert got[1] == "deep text\nafter" and got[2].startswith("one") and "<a" not in got[2]
    assert got[3] == "text bold more\nnext" and got[4] == "whole" and got[5].startswith("a")
    assert time.time() - began < 60


def test_op5_votes_alone_find_the_article(spark):
    """Menus, adverts and footers that differ on every page, without any name that says so; hosts spread over partitions."""
    page = "<html><body><div class=q1><span>m{i}</span></div><div class=q2>buy {i}</div><div class=q3><h1>head {i}</h1>{body}</div><div class=q4>foot {i}</div></body></html>"
    rows, want = [], {}
    for i in range(60):
        body = [f"paragraph {i} {k} " + "words " * (5 + (i + k) % 7) for k in range(3)]
        rows.append((i, f"http://h{i % 4}.example/{i}", page.format(i=i, body="".join(f"<p>{b}</p>" for b in body))))
        want[i] = "\n".join([f"head {i}", *(b.strip() for b in body)])
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    lone = spark.createDataFrame([(99, "http://lone.example/", page.format(i=99, body="<p>only page</p>"))], df.schema)
    for frame in (df.union(lone).coalesce(1), df.union(lone).repartition(7)):
        for most in (200_000, -1):
            got = {r["page_id"]: r["text"] for r in wrapper.extract(frame, most=most, names=False).collect()}
            assert got == want | {99: "head 99\nonly page"}


def test_op5_odd_tables(spark):
    """Extra columns, repeated rows, an empty table."""
    rows = [(1, "http://a/", "<p>x</p>", "h", 1), (1, "http://a/", "<p>x</p>", "h", 1), (None, None, "", None, None)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string, host string, slots int")
    assert sorted(((r["page_id"] or 0), r["text"], r["n_chars"]) for r in wrapper.digest(df).collect()) == [(0, "", 0), (1, "x", 1), (1, "x", 1)]
    assert wrapper.digest(df.limit(0)).count() == 0


def test_pipeline_stages_by_brute_force(spark):
    """The stages behind the classifier on a small table: lines, near copies, contamination and packing, each recomputed."""
    import corpus_pipeline as pipeline

    rng = np.random.default_rng(12)
    words = [f"{a}{b}{c}" for a in "bcdfg" for b in "aeiou" for c in "lmnrst"]
    line = lambda n: " ".join(rng.choice(words, n))
    test_item, shared = line(20), line(25)
    texts = ["\n".join([line(30), line(12), line(40)]) for _ in range(12)]
    texts += [texts[0], texts[1] + "\n" + shared, texts[2].replace("\n", "\n\n", 1), line(5) + " " + test_item + " " + line(9), shared + "\n" + line(30), ""]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long")
    grams = lambda x: {x[i : i + 5] for i in range(max(1, len(x) - 4))}

    def groups(sets):
        root = list(range(len(sets)))
        for _ in range(6):
            for a in range(len(sets)):
                for b in range(a):
                    if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]):
                        root[a] = root[b] = min(root[a], root[b])
        return root

    placed = [(i, k, x) for i, t in enumerate(texts) for k, x in enumerate(t.split("\n"))]
    full = [p for p in placed if p[2].strip()]
    root = groups([grams(" ".join(x.lower().split())) for _, _, x in full])
    gone = {full[k][:2] for k in range(len(full)) if root[k] != k}
    want = {i: "\n".join(x for k, x in enumerate(t.split("\n")) if (i, k) not in gone) for i, t in enumerate(texts)}
    after = pipeline.lines(spark, docs, "")
    got = {r["doc_id"]: (r["text"], r["n_chars"]) for r in after.collect()}
    assert got == {i: (t, len(t)) for i, t in want.items()}

    shingles = lambda t: {tuple(t.split()[i : i + 5]) for i in range(max(1, len(t.split()) - 4))}
    root = groups([shingles(want[i].lower()) for i in want])
    kept = pipeline.near_duplicates(spark, after, "")
    assert {r["doc_id"] for r in kept.collect()} == set(root)

    items = spark.createDataFrame([("t", test_item)], "item_id string, text string")
    clean = decontaminate.drop_contaminated(kept, items)
    assert {r["doc_id"] for r in clean.collect()} == set(root) - {15}
    encode = Encoder.of(default_path(), 2)
    packed = pipeline.packing(spark, clean, "").collect()
    assert {(r["doc_id"], r["length"], r["ids_crc32"]) for r in packed} == {(i, len(encode(want[i])) // 4, zlib.crc32(encode(want[i]))) for i in set(root) - {15}}
    at = sorted((r["sequence_id"], r["offset"], r["length"]) for r in packed)
    assert all(b[1] == (a[1] + a[2] if a[0] == b[0] else 0) for a, b in zip(at, at[1:])) and all(o + n <= 4096 for _, o, n in at)


@pytest.mark.parametrize("m", [2, 5])
def test_line_groups_make_few_rows(spark, m):
    """A group of near copies is linked by about one check a line, not by all pairs."""
    rng = np.random.default_rng(m)
    base = [f"word{int(k)}" for k in rng.integers(0, 500, 60)]
    lines = set()
    for k in range(200 * m):
        copy = list(base)
        copy[int(rng.integers(60))] = f"other{k}"
        lines.add(" ".join(copy))
    texts = line_dedup.texts_of(line_dedup.lines_of(spark.createDataFrame(list(enumerate(sorted(lines))), "doc_id long, text string")))
    checked = []

    def counted(scratch, pairs, own, *rest, held=line_dedup.verified):
        checked.append(pairs.count())
        return held(scratch, pairs, own, *rest)

    plain, line_dedup.verified = line_dedup.verified, counted
    try:
        from privbatch.llm.common import Scratch

        roots = line_dedup.links(Scratch(spark, "few"), texts)
    finally:
        line_dedup.verified = plain
    assert roots.select("root").distinct().count() == 1 and roots.count() == len(lines)
    assert sum(checked) <= 1.2 * len(lines)
