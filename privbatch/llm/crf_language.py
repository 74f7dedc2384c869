"""Language of every word by a linear-chain conditional random field.

A word's features are its affixes, its character trigrams and, if it is in the lexicon of the
training sample, the word itself, all hashed into one weight table.  Transitions between
languages are learned with the weights.  Training sequences are stretches of documents of one
known language, and stretches spliced from documents of several, so that the transitions have
seen code-switched text.  Labels come from forward-backward: each word gets a distribution over
languages; a document's is the mean over its words.

Training is bounded (``DOCS_PER_LANG`` documents of each language, of every language there is);
prediction covers whole texts, in sequences of ``SPAN`` words.
"""

from __future__ import annotations

import pickle
import re
import zlib
from collections import Counter

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import held_out

SPAN = 64
BUCKETS = 1 << 16
DOCS_PER_LANG = 80
MAX_TRAIN_WORDS = 250_000
EPOCHS = 24
CACHE_WORDS = 300_000
UNKNOWN = "und"

_WORD = re.compile(r"[^\W\d_]+")


def words_of(text: str | None) -> list[str]:
    return _WORD.findall((text or "").lower())


def has_letter(text: str | None, words: list[str]) -> bool:
    return any(map(str.isalpha, words)) or (bool(words) and any(c.isalpha() for c in text or ""))


def features(word: str, lexicon: set[str] | dict[str, int]) -> list[int]:
    """Hashed feature numbers of a word."""
    w = f"^{word}$" if len(word) <= 40 else f"^{word[:20]}{word[-20:]}$"
    names = [f"p{w[1 : 1 + k]}" for k in (1, 2, 3)] + [f"s{w[-1 - k : -1]}" for k in (1, 2, 3)]
    names += [f"t{w[i : i + 3]}" for i in range(len(w) - 2)]
    if word in lexicon:
        names.append(f"w{word}")
    return [zlib.crc32(n.encode("utf-8", "surrogatepass")) & (BUCKETS - 1) for n in names]


class Field:
    """Weights of a trained field; ``langs`` in sorted order."""

    def __init__(self, langs: list[str], weights: np.ndarray, transitions: np.ndarray, lexicon: set[str]):
        self.langs, self.weights, self.transitions, self.lexicon = langs, weights, transitions, lexicon
        self.place: dict[str, int] = {}
        self.emissions = np.zeros((0, len(langs)), np.float32)

    def __getstate__(self) -> tuple:
        return self.langs, self.weights, self.transitions, self.lexicon

    def __setstate__(self, state: tuple) -> None:
        self.__init__(*state)

    def _emit(self, words: list[str]) -> np.ndarray:
        """Log potentials of the words, by a bounded cache of words already seen."""
        unseen = {w for w in words if w not in self.place}
        if unseen:
            if len(self.place) + len(unseen) > CACHE_WORDS:
                self.place, self.emissions = {}, self.emissions[:0]
                unseen = set(words)
            rows = [features(w, self.lexicon) for w in unseen]
            ends = np.cumsum([len(r) for r in rows])
            flat = np.fromiter((f for r in rows for f in r), np.int64, ends[-1])
            fresh = np.add.reduceat(self.weights[flat], np.r_[0, ends[:-1]])
            self.place.update(zip(unseen, range(len(self.place), len(self.place) + len(unseen)), strict=True))
            self.emissions = np.concatenate([self.emissions, fresh.astype(np.float32)])
        return self.emissions[np.fromiter(map(self.place.__getitem__, words), np.int64, len(words))]

    def marginals(self, words: list[str], sequence: np.ndarray) -> np.ndarray:
        """P(language) of each word; ``sequence`` numbers the words' sequences in rising order."""
        return forward_backward(self._emit(words), self.transitions, sequence)[0]


def forward_backward(emit: np.ndarray, transitions: np.ndarray, sequence: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Word marginals, summed transition marginals and log normalisers of many sequences at once.

    Sequences are laid side by side, so that one step serves all of them.
    """
    n, k = emit.shape
    starts = np.flatnonzero(np.r_[True, sequence[1:] != sequence[:-1]])
    sizes = np.diff(np.r_[starts, n])
    column = np.arange(n) - np.repeat(starts, sizes)
    row = np.repeat(np.arange(len(starts)), sizes)
    span = int(sizes.max())
    top = emit.max(axis=1, keepdims=True)
    e = np.ones((span, len(starts), k), np.float32)
    e[column, row] = np.exp(emit - top)
    inside = np.zeros((span, len(starts), 1), bool)
    inside[column, row] = True
    t = np.exp(transitions - transitions.max()).astype(np.float32)
    alpha = np.empty_like(e)
    log_z = np.zeros(len(starts))
    now = e[0]
    for s in range(span):
        if s:
            now = np.where(inside[s], (alpha[s - 1] @ t) * e[s], alpha[s - 1])
        total = now.sum(axis=1, keepdims=True)
        alpha[s] = now / total
        log_z += np.log(total[:, 0])
    log_z += np.bincount(row, weights=top[:, 0], minlength=len(starts)) + (sizes - 1) * float(transitions.max())
    beta = np.ones((len(starts), k), np.float32)
    pairs = np.zeros((k, k))
    gamma = np.empty_like(e)
    gamma[span - 1] = alpha[span - 1]
    for s in range(span - 2, -1, -1):
        weighed = e[s + 1] * beta
        before = weighed @ t.T
        scale = (alpha[s] * before).sum(axis=1, keepdims=True)
        used = inside[s + 1]
        pairs += (np.where(used, alpha[s] / scale, 0).T @ weighed) * t
        beta = np.where(used, before / before.sum(axis=1, keepdims=True), 1)
        g = alpha[s] * beta
        gamma[s] = g / g.sum(axis=1, keepdims=True)
    return gamma[column, row], pairs, log_z


def train(texts: list[tuple[str, str]], epochs: int = EPOCHS, seed: int = 7) -> Field | None:
    """A field from (language, text) pairs; None without a labelled word."""
    rng = np.random.default_rng(seed)
    langs = sorted({lang for lang, _ in texts})
    spans: list[tuple[int, list[str]]] = []
    counts: Counter[str] = Counter()
    for lang, text in texts:
        words = words_of(text)
        counts.update(words)
        spans += [(langs.index(lang), words[a : a + SPAN]) for a in range(0, len(words), SPAN)]
    if not spans:
        return None
    rng.shuffle(order := np.arange(len(spans)))
    total, kept = 0, []
    for i in order:
        kept.append(spans[i])
        total += len(spans[i][1])
        if total > MAX_TRAIN_WORDS:
            break
    words, labels, sequence = [], [], []
    for number, (lang, own) in enumerate(kept):
        if number % 4 == 0:  # spliced: pieces of 6 to 16 words from sequences of any language
            room = SPAN
            while room > 0:
                other, text = kept[rng.integers(len(kept))]
                take = min(room, int(rng.integers(6, 17)), len(text))
                at = int(rng.integers(len(text) - take + 1))
                words += text[at : at + take]
                labels += [other] * take
                sequence += [number] * take
                room -= take
        else:
            words += own
            labels += [lang] * len(own)
            sequence += [number] * len(own)
    lexicon = {w for w, c in counts.items() if c >= 3}
    distinct = sorted(set(words))
    place = {w: i for i, w in enumerate(distinct)}
    word = np.fromiter(map(place.__getitem__, words), np.int64, len(words))
    rows = [features(w, lexicon) for w in distinct]
    sizes = np.array([len(r) for r in rows])
    flat = np.fromiter((f for r in rows for f in r), np.int64, sizes.sum())
    owner, starts = np.repeat(np.arange(len(rows)), sizes), np.r_[0, np.cumsum(sizes)[:-1]]
    k, label, seq = len(langs), np.array(labels), np.array(sequence)
    truth = np.zeros((len(distinct), k))
    np.add.at(truth, (word, label), 1)
    follow = seq[1:] == seq[:-1]
    truth_pairs = np.zeros((k, k))
    np.add.at(truth_pairs, (label[:-1][follow], label[1:][follow]), 1)
    weights, transitions = np.zeros((BUCKETS, k)), np.zeros((k, k))
    moments = [np.zeros_like(weights), np.zeros_like(weights), np.zeros_like(transitions), np.zeros_like(transitions)]
    for step in range(1, epochs + 1):
        emit = np.add.reduceat(weights[flat], starts)
        gamma, pairs, _ = forward_backward(emit[word], transitions, seq)
        expected = np.stack([np.bincount(word, weights=gamma[:, j], minlength=len(distinct)) for j in range(k)], axis=1)
        slope = (truth - expected)[owner] / len(words)
        grad = np.stack([np.bincount(flat, weights=slope[:, j], minlength=BUCKETS) for j in range(k)], axis=1) - 1e-7 * weights
        for value, g, m, v, rate in ((weights, grad, moments[0], moments[1], 0.2), (transitions, (truth_pairs - pairs) / len(words), moments[2], moments[3], 0.2)):
            m += 0.1 * (g - m)
            v += 0.01 * (g * g - v)
            value += rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
    return Field(langs, weights.astype(np.float32), transitions.astype(np.float32), lexicon)


def training_sample(docs: DataFrame, docs_per_lang: int = DOCS_PER_LANG) -> list[tuple[str, str]]:
    """At most ``docs_per_lang`` texts of each language, chosen by a hash of id and text, outside the held-out fold.

    The rank is limited in every task before rows move, so a language of any size moves few.
    """
    own = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & ~held_out(F.col("doc_id")))
    own = own.select("lang", F.col("text").cast("string").alias("text")).withColumn("draw", F.xxhash64(F.lit("sample"), "text"))
    rank = F.row_number().over(Window.partitionBy("lang").orderBy("draw", "text"))
    picked = own.withColumn("rank", rank).where(F.col("rank") <= docs_per_lang)
    return [(r["lang"], r["text"]) for r in picked.orderBy("lang", "rank").select("lang", "text").toLocalIterator()]


def fit(docs: DataFrame) -> Field | None:
    return train(training_sample(docs))


def _document(field: Field | None, texts: pd.Series) -> pd.DataFrame:
    """Prediction and score of each text; sequences of many texts are solved together."""
    out: list[tuple[str, float]] = []
    words: list[str] = []
    sizes: list[int] = []

    def flush() -> None:
        if not sizes:
            return
        counts = np.array(sizes)
        total = int(counts.sum())
        if field is None or not total:
            out.extend((UNKNOWN, 0.0) for _ in sizes)
        else:
            inner = np.arange(total) - np.repeat(np.r_[0, np.cumsum(counts)[:-1]], counts)
            sequence = np.cumsum(inner % SPAN == 0)
            gamma = field.marginals(words, sequence)
            doc = np.repeat(np.arange(len(counts)), counts)
            mean = np.stack([np.bincount(doc, weights=gamma[:, j], minlength=len(counts)) for j in range(gamma.shape[1])], axis=1)
            mean /= np.maximum(counts, 1)[:, None]
            best = mean.argmax(axis=1)
            out.extend((field.langs[b], float(min(1.0, m[b]))) if c else (UNKNOWN, 0.0) for b, m, c in zip(best, mean, counts, strict=True))
        words.clear()
        sizes.clear()

    for text in texts:
        own = words_of(text)
        if not has_letter(text, own):
            own = []
        words.extend(own)
        sizes.append(len(own))
        if len(words) >= 200_000:
            flush()
    flush()
    return pd.DataFrame(out, columns=["lang_pred", "score"])


def predict(docs: DataFrame, field: Field | None) -> DataFrame:
    """(doc_id, held_out, lang_pred, score) of every document, from its text alone.

    A text that is null or has no letter is ``und`` with score 0; so is every text if there was no
    labelled text to learn from.  Null ids and repeated rows each give a row; an empty table gives
    an empty result.  Only doc_id and text are read, so further columns cannot clash.
    """
    held = docs.sparkSession.sparkContext.broadcast(pickle.dumps(field, protocol=5))
    cell: dict[int, Field | None] = {}

    @F.pandas_udf("lang_pred string, score double")
    def label(texts: pd.Series) -> pd.DataFrame:
        if 0 not in cell:
            cell[0] = pickle.loads(held.value)
        return _document(cell[0], texts)

    out = docs.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), label(F.col("text").cast("string")).alias("p"))
    return out.select("doc_id", "held_out", "p.lang_pred", "p.score")


def label_words(docs: DataFrame, field: Field) -> DataFrame:
    """(doc_id, words array<struct<word, lang, p>>): the label of each word, in text order."""
    held = docs.sparkSession.sparkContext.broadcast(pickle.dumps(field, protocol=5))

    @F.pandas_udf("array<struct<word:string,lang:string,p:double>>")
    def label(texts: pd.Series) -> pd.Series:
        own: Field = pickle.loads(held.value)
        rows = []
        for text in texts:
            words = words_of(text)
            if not has_letter(text, words):
                rows.append([])
                continue
            gamma = own.marginals(words, np.arange(len(words)) // SPAN)
            best = gamma.argmax(axis=1)
            rows.append([{"word": w, "lang": own.langs[b], "p": float(g[b])} for w, b, g in zip(words, best, gamma, strict=True)])
        return pd.Series(rows, dtype=object)

    return docs.select("doc_id", label(F.col("text").cast("string")).alias("words"))


def digest(docs: DataFrame) -> DataFrame:
    return predict(docs, fit(docs))
