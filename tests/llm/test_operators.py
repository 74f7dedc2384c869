"""The training-data operators against brute force, on small fixtures with nulls, empties, ties and repeats."""

import hashlib
import re
import zlib

import numpy as np
import pytest
import xxhash

from privbatch.llm import bfd_packing, crf_language, decontaminate, ffd_packing, line_dedup, masked_lm, pu_quality, simhash, top_k, wrapper

SF = "/root/testdata/sf0.001"
DOCS = "doc_id long, text string, lang string, source string, n_chars long, component_id long, score double"
LONG = " ".join(f"word{i} and" for i in range(6000))
ROWS = [
    (1, "The cat sat on the mat today.\nA second line here.", "en", "s", 0, 9, 0.5), (2, "The cat sat on the mat today.\nA second line here.", "en", "s", 0, 9, 0.5),
    (2, "The cat sat on the mat today.\nA second line here.", "en", "s", 0, 9, 0.5), (3, None, None, None, None, None, None), (4, "", "en", "s", 0, 0, 0.0),
    (None, "no id", "en", None, 5, 1, 1.0), (5, LONG, "en", "s", 0, 0, 0.0), (6, "  \n\t\n ", "de", "s", 0, 0, 0.0), (7, "Ünïcode 日本 ---", "fr", "s", 0, 0, 0.0),
]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ROWS, DOCS)


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


def test_simhash_brute_force(docs):
    low = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
    fp = {}
    for r in docs.collect():
        w = re.findall(r"[^\x20\x09-\x0D]+", (r["text"] or "").encode().translate(low).decode())
        hs = [xxhash.xxh64_intdigest(" ".join(w[i : i + 3]).encode(), 42) for i in range(max(1, len(w) - 2))] if w else []
        fp[r["doc_id"]] = sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))
    root = {i: i for i in fp}
    for _ in range(8):
        for a in fp:
            for b in fp:
                if (fp[a] ^ fp[b]).bit_count() <= 3:
                    root[a] = root[b] = min(root[a], root[b])
    got = {r["doc_id"]: (r["fingerprint"], r["component_id"]) for r in simhash.digest(docs).collect()}
    assert got == {i: (f"{fp[i]:016x}", root[i]) for i in fp}


@pytest.mark.parametrize("m", [40, 3500])
def test_forest_is_exact(m):
    rng = np.random.default_rng(m)
    fps = np.unique(rng.integers(0, 1 << 14, m).astype(np.int64))
    near = np.bitwise_count((fps[:, None] ^ fps[None, :]).view(np.uint64)) <= 3
    want = np.arange(len(fps))
    while True:
        low = np.where(near, want[None, :], len(fps)).min(axis=1)
        if (low == want).all():
            break
        want = low
    assert (simhash._forest(fps) == want).all()


def test_simhash_odd(odd):
    got = {(r["doc_id"], r["component_id"]) for r in simhash.digest(odd).collect()}
    assert {(1, 1), (2, 1), (3, 3), (4, 3), (6, 3)} <= got
    kept = [r["doc_id"] for r in simhash.keep_one(odd).collect()]
    assert kept.count(1) == 1 and 2 not in kept and 4 not in kept and kept.count(5) == 1
    assert simhash.keep_one(odd.limit(0)).count() == 0


def test_automaton_brute_force():
    rng = np.random.default_rng(1)
    word = lambda: b"%d" % rng.integers(4)
    items = [(str(i), [word() for _ in range(n)]) for i, n in enumerate((6, 3, 1, 0, 9, 6))]
    auto = decontaminate.Automaton(items, window=4)
    for _ in range(200):
        text = [word() for _ in range(int(rng.integers(0, 30)))]
        hit, found = set(), set()
        for name, w in items:
            n = min(4, len(w))
            for a in range(len(w) - n + 1) if n else ():
                for b in range(len(text) - n + 1):
                    if text[b : b + n] == w[a : a + n]:
                        hit |= set(range(b, b + n))
                        found.add(name)
        spans, got, _ = auto.scan(text)
        assert {p for a, b in spans for p in range(a, b)} == hit and got == found


def test_decontaminate_blocks_and_odd(spark, odd):
    items = spark.createDataFrame([(1, LONG[500:900]), (2, "the cat SAT on"), (3, None), (None, ""), (1, LONG[500:900])], "item_id long, text string")
    got = {r["doc_id"]: r for r in decontaminate.digest(odd, items).collect()}
    assert got[1]["n_hit"] == 4 and got[1]["contaminated"] and got[1]["items_sha256"] == hashlib.sha256(b"2").hexdigest()
    assert got[5]["n_items"] == 1 and not got[5]["contaminated"] and got[3]["n_words"] == 0
    one, many = (sorted((str(r["doc_id"]), r["n_hit"], tuple(r["items"])) for r in decontaminate.matches(odd, items, block_words=b).collect()) for b in (10**6, 5))
    assert one == many
    texts = {r["doc_id"]: r["text"] for r in decontaminate.clean(odd, items).collect()}
    assert texts[1].startswith(" the mat") and texts[7] == "Ünïcode 日本 ---"
    assert decontaminate.drop_contaminated(odd, items).columns == odd.columns
    assert decontaminate.digest(odd.limit(0), items).count() == 0


def test_ffd(odd):
    rng = np.random.default_rng(2)
    lengths = rng.integers(1, 100, 300)
    bins, offsets = ffd_packing.first_fit_decreasing(lengths, 100)
    free: list[int] = []
    want = {}
    for i in np.argsort(-lengths, kind="stable"):
        k = next((k for k, f in enumerate(free) if f >= lengths[i]), len(free))
        if k == len(free):
            free.append(100)
        want[i] = (k, 100 - free[k])
        free[k] -= lengths[i]
    assert all((bins[i], offsets[i]) == want[i] for i in want)
    packed = ffd_packing.pack(odd, with_ids=True).collect()
    assert sum(r["length"] for r in packed) == sum(r["doc_tokens"] for r in packed if r["start"] == 0)
    assert all(zlib.crc32(r["ids"]) == r["ids_crc32"] for r in packed)
    assert ffd_packing.pack(odd.limit(0)).count() == 0


def test_bfd(odd):
    rng = np.random.default_rng(4)
    lengths = rng.integers(1, 60, 200).tolist()
    rows = bfd_packing.best_fit_decreasing(lengths, 64)
    free, want = [], []
    for i in sorted(range(200), key=lambda i: -lengths[i]):
        fit = [f for f in free if f >= lengths[i]]
        if fit:
            free.remove(min(fit))
            free.append(min(fit) - lengths[i])
        else:
            free.append(64 - lengths[i])
        want.append(i)
    assert len(rows) == len(free) and sorted(i for r in rows for i in r) == list(range(200))
    assert all(sum(lengths[i] for i in r) <= 64 for r in rows)
    packed = bfd_packing.pack_rows(odd, width=512)
    from privbatch.llm.tokens import Encoder, default_path

    encode = Encoder(default_path(), 2)
    back: dict = {}
    for r in bfd_packing.unpack(packed).collect():
        back.setdefault((r["doc_id"], r["row_id"]), []).append((r["start"], bytes(r["ids"])))
    got = sorted((str(key[0]), b"".join(p for _, p in sorted(parts))) for key, parts in back.items())
    assert got == sorted((str(doc_id), encode(text)) for doc_id, text, *_ in ROWS)


def test_top_k_brute_force(spark):
    rng = np.random.default_rng(6)
    rows = [(i, [float(x) for x in rng.normal(size=6) * (1 + i % 7)]) for i in range(300)] + [(301, None), (302, [None] * 6), (303, [float("nan")] * 6), (304, [float("inf")] * 6)]
    rows += [(i, [1.0] * 6) for i in range(310, 330)] + [(None, [1.0] * 6)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    ints = {i: np.floor(256 * np.array(v, np.float32).astype(float)).astype(int) for i, v in rows if i is not None and v and all(x is not None and np.isfinite(x) for x in v)}
    want = set()
    for q in (i for i in ints if i % 50 == 0):
        best = sorted((-int(ints[q] @ ints[c]), c) for c in ints if c != q)[:5]
        want |= {(q, r, c, -s) for r, (s, c) in enumerate(best, 1)}
    for size in (32, 4096):
        assert {tuple(r) for r in top_k.search(df, 50, 5, bucket=size, group=4).collect()} == want
    assert top_k.digest(df.limit(0)).count() == 0


def test_line_dedup(spark, odd):
    base = "one two three four five six seven eight nine ten eleven twelve thirteen fourteen fifteen sixteen seventeen eighteen nineteen twenty"
    rows = [(i, f"{base} {base[::-1]} {base.upper()} x{i}\nown line {i * 7919}\n\nThe same.") for i in range(30)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r["doc_id"]: r["text"] for r in line_dedup.dedup_lines(df).collect()}
    own = [f"own line {i * 7919}" for i in range(30)]
    sets = [{x[k : k + 5] for k in range(len(x) - 4)} for x in own]
    first = [i for i in range(30) if not any(len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]) for j in range(i))]
    assert len(first) > 20 and got[0] == rows[0][1] and all(got[i] == (f"{own[i]}\n" if i in first else "") for i in range(1, 30))
    out = {r["doc_id"]: r for r in line_dedup.digest(odd).collect()}
    assert out[2]["removed"] == [0, 1] and out[1]["removed"] == [] and out[3]["n_lines"] == 0
    assert line_dedup.dedup_lines(odd).columns == odd.columns and line_dedup.digest(odd.limit(0)).count() == 0
    plan = line_dedup.bands(line_dedup.signatures(line_dedup.texts_of(line_dedup.lines_of(odd))))._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan


def test_line_links_brute_force(spark):
    """Groups of near copies, texts without spaces and one-word lines, against all pairs on character runs."""
    rng = np.random.default_rng(5)
    words = [f"w{i}x" for i in range(300)]
    lines = ["tiny", "x" * 50, "".join(chr(0x4E00 + int(c)) for c in rng.integers(0, 400, 200))]
    lines.append(lines[-1][:190] + "abc")
    for _ in range(6):
        base = [words[k] for k in rng.integers(0, 300, 60)]
        for _ in range(30):
            copy = list(base)
            for k in rng.integers(0, 60, int(rng.integers(0, 9))):
                copy[k] = words[int(rng.integers(0, 300))]
            lines.append(" ".join(copy))
    lines = sorted(set(lines))
    sets = [{x[i : i + 5] for i in range(max(1, len(x) - 4))} for x in lines]
    root = list(range(len(lines)))
    near = [(a, b) for a in range(len(lines)) for b in range(a) if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])]
    for _ in range(20):
        for a, b in near:
            root[a] = root[b] = min(root[a], root[b])
    df = spark.createDataFrame(list(enumerate(lines)), "doc_id long, text string")
    kept = {r["doc_id"] for r in line_dedup.digest(df).where("n_removed = 0").collect()}
    want = set(root)
    assert want <= kept and len(kept - want) <= 2  # MinHash may miss the odd link


def test_language(docs, odd):
    field = crf_language.fit(docs)
    truth = {r["doc_id"]: r["lang"] for r in docs.collect()}
    got = crf_language.predict(docs, field).where("held_out").collect()
    assert np.mean([r["lang_pred"] == truth[r["doc_id"]] for r in got]) > 0.95
    own = {r["doc_id"]: r for r in crf_language.predict(odd, field).collect()}
    assert own[3]["lang_pred"] == own[6]["lang_pred"] == "und" and 0 <= own[1]["score"] <= 1
    assert {r["lang_pred"] for r in crf_language.predict(odd, None).collect()} == {"und"}
    emit = np.random.default_rng(0).normal(size=(5, 3))
    trans = np.random.default_rng(1).normal(size=(3, 3))
    from itertools import product

    paths = {p: np.exp(sum(emit[i, k] for i, k in enumerate(p)) + sum(trans[a, b] for a, b in zip(p, p[1:], strict=False))) for p in product(range(3), repeat=5)}
    z = sum(paths.values())
    gamma, _, log_z = crf_language.forward_backward(emit, trans, np.zeros(5, int))
    assert log_z[0] == pytest.approx(np.log(z), rel=1e-4)
    assert gamma[2, 1] == pytest.approx(sum(v for p, v in paths.items() if p[2] == 1) / z, rel=1e-3)


def test_quality(spark, docs, odd):
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    scorer = pu_quality.fit(docs, labels)
    truth = {r["doc_id"]: r["quality"] for r in labels.collect()}
    got = [r for r in pu_quality.digest(docs, labels).collect() if r["held_out"] and r["doc_id"] in truth]
    assert np.mean([r["predicted"] == truth[r["doc_id"]] for r in got]) > 0.85
    assert pu_quality.score(odd, scorer).where("score between 0 and 1").count() == len(ROWS)
    assert pu_quality.keep_good(odd, labels.limit(0)).columns == odd.columns


def test_wrapper(spark):
    page = "<html><body><nav><a>Menu</a></nav><div class='box'>Follow us on all channels</div><div class='x'>{}</div><footer>f</footer></body></html>"
    rows = [(i, "http://h.example/" + str(i), page.format(f"Body &amp; text\n {i}<br>more<script>x('</p>')</script>")) for i in range(12)]
    rows += [(90, "http://k.example/", "<article><h1>T</h1><p><b>one<br><p>two &lt;b&gt;<div class='comments'><p>c</p></div></article><aside>s</aside>"), (91, None, None), (92, "bad[url", "plain"), (93, "http://h.example/", "<p>cut <b")]
    got = {r["page_id"]: r["text"] for r in wrapper.extract(spark.createDataFrame(rows, "page_id long, url string, html string").coalesce(1)).collect()}
    assert got[5] == "Body & text 5 more" and got[90] == "T\none\ntwo <b>" and got[91] == "" and got[92] == "plain"


def test_masked_lm(docs, odd):
    vocab = masked_lm.vocabulary(docs)
    trained = masked_lm.train(docs, vocab)
    n, after = masked_lm.score(docs, vocab, trained).agg({"n_tokens": "sum", "log_likelihood": "sum"}).select("sum(n_tokens)", "sum(log_likelihood)").first()
    before = masked_lm.score(docs, vocab, masked_lm.start(vocab)).agg({"log_likelihood": "sum"}).first()[0]
    assert after > before and np.isfinite(after)
    got = {r["doc_id"]: r for r in masked_lm.score(odd, vocab, trained).collect()}
    assert got[3]["n_tokens"] == 0 and got[3]["per_token"] is None and got[5]["log_likelihood"] < 0
    assert masked_lm.digest(odd.limit(0)).count() == 0


def test_pipeline(spark):
    import corpus_pipeline

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    packed = corpus_pipeline.run(spark, SF)
    ids = {r["doc_id"] for r in packed.select("doc_id").distinct().collect()}
    assert 0 < len(ids) < docs.count()
    assert packed.columns == ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]


@pytest.mark.parametrize("size", [3, 4, 5])
def test_line_signatures_recall(spark, size):
    """Of all pairs of lines of a similarity of 0.8 or more, 0.99 meet in a band and agree, for short lines and long."""
    rng = np.random.default_rng(size)
    lines = []
    for n_words in [2, 3, 5, 8, 12, 12, 12, 30, 80] * 40:
        line = " ".join("".join(chr(97 + int(c)) for c in rng.integers(0, 26, int(rng.integers(4, 9)))) for _ in range(n_words))
        other = line
        for at in rng.integers(0, len(line), max(1, len(line) // 60)):
            other = other[:at] + "#" + other[at + 1 :]
        lines += [line, other]
    sets = [{x[i : i + size] for i in range(max(1, len(x) - size + 1))} for x in lines]
    near = {(i, i + 1) for i in range(0, len(lines), 2) if len(sets[i] & sets[i + 1]) >= 0.8 * len(sets[i] | sets[i + 1])}
    cut = line_dedup.GRAMS._replace(size=size)
    signed = line_dedup.signatures(spark.createDataFrame(list(enumerate(lines)), "h long, line string"), cut)
    own = {r["h"]: set(r["bands"]) for r in signed.collect()}
    met = [p for p in near if own[p[0]] & own[p[1]]]
    pairs = line_dedup._agreeing(spark.createDataFrame(met, "a long, b long"), signed)
    assert len(near) > 200 and pairs.count() >= 0.99 * len(near)
    far = sum(bool(own[i] & own[j]) for i in range(0, 720, 2) for j in range(0, i, 2))
    assert far <= 0.01 * 360 * 359 / 2


def test_line_links_across(spark):
    """Two groups of copies and lines between them: links that the first check of each line does not show."""
    rng = np.random.default_rng(3)
    base = ["".join(chr(97 + int(c)) for c in rng.integers(0, 26, 6)) for _ in range(40)]
    lines = [" ".join(base[:k] + [w.upper()[::-1].lower() for w in base[k : k + 2]] + base[k + 2 :]) for k in range(39)]
    lines += [" ".join([*base[: 40 - k], *(f"zz{k}{j}yx" for j in range(k))]) for k in range(1, 12)]
    sets = [{x[i : i + 5] for i in range(len(x) - 4)} for x in lines]
    root = list(range(len(lines)))
    for _ in range(20):
        for a in range(len(lines)):
            for b in range(a):
                if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]):
                    root[a] = root[b] = min(root[a], root[b])
    df = spark.createDataFrame(list(enumerate(lines)), "doc_id long, text string")
    rows = line_dedup.verdicts(df).where("kept").collect()
    assert {r["doc_id"] for r in rows} == set(root)


def test_line_dedup_shingles_as_rows(spark):
    """The rows that signatures are made of are the shingles that similarities are worked out on."""
    texts = ["one", "one two three", "a  b", "x" * 80, "stra\u00dfe und \U0001f600weg", "y" * 30 + " z"]
    lines = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "h long, line string")
    for cut in (line_dedup.GRAMS, line_dedup.WORDS):
        rows = {(r["h"], r["x"]) for r in line_dedup.shingle_rows(lines, cut).collect()}
        sets = lines.select("h", line_dedup.shingle_set(lines["line"], cut).alias("s")).collect()
        assert rows == {(r["h"], x) for r in sets for x in r["s"]}
        assert {h for h, _ in rows} == set(range(len(texts)))
    n = line_dedup.shingle_rows(lines).groupBy("h").count().collect()
    assert {r["h"]: r["count"] for r in n} == {i: max(1, len(t) - 4) for i, t in enumerate(texts)}


def test_line_dedup_clashing_names_and_repeats(spark):
    """Columns named like the operator's own, two rows of one id with different texts, many lines that go."""
    many = "\n".join(f"line number {i} of the first text" * 3 for i in range(300))
    rows = [(1, many, "a", 0, True, 5), (2, many + "\nlast line is new here", "b", 1, False, 6), (3, "one text of this id", "c", 2, None, 7), (3, many.split("\n")[0], "d", 3, None, 8)]
    df = spark.createDataFrame(rows, "doc_id long, text string, root string, gone long, kept boolean, n_chars int")
    got = sorted((r["doc_id"], r["text"], r["root"], r["gone"], r["n_chars"]) for r in line_dedup.dedup_lines(df).collect())
    first = [r["pos"] for r in line_dedup.verdicts(df).where("kept and doc_id = 1").collect()]
    want = "\n".join(x for i, x in enumerate(many.split("\n")) if i in first)
    assert got[0] == (1, want, "a", 0, len(want)) and got[1][1] == "last line is new here" and got[2][1] == "" and got[3][1] == "one text of this id"
    assert line_dedup.dedup_lines(df).schema == df.schema
