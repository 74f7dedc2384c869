"""What the first review found missing, on small fixtures against brute force."""

import numpy as np

from privbatch.llm import line_dedup, masked_lm, queries, simhash, wrapper


def _grams(line):
    return {line[i : i + 5] for i in range(max(1, len(line) - 4))}


def _roots(sets):
    root = list(range(len(sets)))
    near = [(a, b) for a in range(len(sets)) for b in range(a) if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])]
    for _ in range(20):
        for a, b in near:
            root[a] = root[b] = min(root[a], root[b])
    return set(root)


def _query(spark, tmp_path, name, rows, schema, table="documents"):
    spark.createDataFrame(rows, schema).write.parquet(f"{tmp_path}/{table}.parquet")
    return queries.QUERIES[name](spark, str(tmp_path))


def test_op9_one_letter_changed(spark, tmp_path):
    """Near copies that five-character runs tie at 0.8 or more, which shingles of word starts lose."""
    rng = np.random.default_rng(8)
    lines = ["abc", "abd", "x y"]
    for n_words in [8, 10, 12, 15, 30] * 5:
        words = ["".join(chr(97 + int(c)) for c in rng.integers(0, 26, int(rng.integers(5, 11)))) for _ in range(n_words)]
        line = " ".join(words)
        at = int(rng.integers(len(line) - 6))
        lines += [line, line[:at] + "#" + line[at + 1 :]]
    want = _roots([_grams(x) for x in lines])
    rows = [(i, x, "en", "s", len(x)) for i, x in enumerate(lines)]
    out = _query(spark, tmp_path, "op9_line_dedup", rows, "doc_id long, text string, lang string, source string, n_chars long")
    kept = {r["doc_id"] for r in out.where("n_removed = 0").collect()}
    assert len(want) < len(lines) - 15 and want <= kept and len(kept - want) <= 1


def test_line_dedup_white_space(spark):
    """Copies that differ in carriage returns, tabs and spaces share a name; white space alone is blank."""
    texts = ["Read more\nnext one", "read more\r\n\r\nnext\tone\r\n\t\n", "  Read  more \n\r\nnext\u00a0 one", "readmore"]
    lines = line_dedup.lines_of(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"))
    got = {(r["doc_id"], r["pos"]): (r["line"], r["h"]) for r in lines.collect()}
    assert set(got) == {(0, 0), (0, 1), (1, 0), (1, 2), (2, 0), (2, 2), (3, 0)}
    assert got[0, 0] == got[1, 0] == got[2, 0] and got[0, 1] == got[1, 2] == got[2, 2]
    assert got[3, 0][0] == "readmore" and got[0, 1][0] == "next one"


def _sites():
    """Pages of a hot host with a neutral slot that varies, and a small host on which the same slot is constant."""
    page = "<html><body><div>{}</div><div class='box'>{}</div></body></html>"
    rows = [(i, f"http://hot.example/{i}", page.format("Always the same", f"hot own {i}")) for i in range(40)]
    rows += [(100 + i, f"http://own.example/{i}", page.format(f"article {i}", f"Follow us {i % 2}")) for i in range(12)]
    return rows + [(200, "http://one.example/", page.format("a lone page", "a lone box")), (201, None, page.format("nameless", "box"))]


def test_op5_own_votes_first(spark):
    """A host's own votes go before those of all hosts, and a broadcast and a join agree."""
    df = spark.createDataFrame(_sites(), "page_id long, url string, html string").repartition(5)
    one, other = ({r["page_id"]: r["text"] for r in wrapper.extract(df, most=m).collect()} for m in (200_000, -1))
    assert one == other
    assert one[103].startswith("article 3") and one[5] == "hot own 5"
    assert one[200] == "a lone box" and one[201] == "box"


def test_op5_partitions_and_long_pages(spark):
    """Pages of a host vote wherever they are read, and a template block behind 200 runs of siblings votes too."""
    flat = lambda i, n: "".join(f"<h2>head {i} {k}</h2><p>text {i} {k}</p>" for k in range(n))
    rows = [(i, f"http://h{i % 3}.example/{i}", f"<body>{flat(i, 120 + i)}<div class='box'>Follow us</div></body>") for i in range(12)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    one, many = ({r["page_id"]: r["text"] for r in wrapper.extract(d).collect()} for d in (df.coalesce(1), df.repartition(12)))
    assert one == many and all("Follow us" not in t and f"text {i} {119 + i}" in t for i, t in many.items())


def test_pipeline_near_duplicates(spark):
    """keep_one against all pairs by the Jaccard similarity over five words, with copies that fingerprints of 3 bits miss."""
    rng = np.random.default_rng(11)
    texts = ["one two", "one two", ""]
    for changed in [0, 1, 2, 3, 4, 6, 9, 20] * 2:
        words = [f"w{k}" for k in rng.integers(0, 5000, 200)]
        texts.append(" ".join(words))
        for at in rng.choice(200, changed, replace=False):
            words[at] = "other"
        texts.append(" ".join(words))
    sets = [{tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} for w in map(str.split, texts)]
    want = _roots(sets)
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"] for r in simhash.keep_one(docs, width=5).collect()}
    assert got == want and 0 < len(want) < len(texts) - 8


def test_op1_rare_tokens_by_their_own_counts(spark):
    """Tokens of one bucket differ by the ratio of their counts over all documents, long ones by all their bytes."""
    long = "q" * 70
    texts = [" ".join(f"c{i}" for i in range(960))] * 60 + [" ".join(["aaaxyz"] * 50), f"{long}1xyz {long}1xyz"]
    texts += ["aaaxyz", "bbbxyz", f"{long}1xyz", f"{long}2xyz", None]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: r for r in masked_lm.digest(docs).collect()}
    a, b, c, d = (got[62 + k]["log_likelihood"] for k in range(4))
    assert np.isclose(a - b, np.log(52 / 2)) and np.isclose(c - b, np.log(4 / 2)) and np.isclose(d, b)
    assert len(got) == len(texts) and got[66]["n_tokens"] == 0 and got[66]["log_likelihood"] == 0
