"""Text quality by positive-unlabelled learning with a non-negative risk.

Trusted positives are documents labelled 1; the unlabelled sample is drawn from all documents,
whatever their label.  With the class prior p estimated from the same two samples, the risk of
calling text negative is what remains of the unlabelled risk after the positives' share:

    p R(positive called positive) + max(0, R(unlabelled called negative) - p R(positive called negative))

A small network over character-class statistics is trained on that risk.  When the bracket
turns negative the step climbs back instead, which keeps the network from fitting the
unlabelled sample's positives as negatives.

Training uses at most ``SAMPLE`` positives and ``SAMPLE`` unlabelled texts; scoring reads every
text as a whole.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import held_out

SAMPLE = 4000
HIDDEN = 24
EPOCHS = 60
PRIOR_EPOCHS = 12
FOLDS = 4

#: Symbols with a class of their own; the others share one.  Fixed values.
_OWN = " \n\t.,;:!?'\"()|#$%&*-_/<>@=+"
_CLASSES = 4 + len(_OWN) + 3


def _class_table() -> np.ndarray:
    table = np.full(256, _CLASSES - 1, np.uint8)
    table[[*range(ord("a"), ord("z") + 1)]] = 0
    table[[ord(c) for c in "aeiou"]] = 1
    table[[*range(ord("A"), ord("Z") + 1)]] = 2
    table[[*range(ord("0"), ord("9") + 1)]] = 3
    for k, c in enumerate(_OWN):
        table[ord(c)] = 4 + k
    table[128:192] = _CLASSES - 2
    table[192:] = _CLASSES - 3
    return table


_TABLE = _class_table()
EXTRA = 8
WIDTH = _CLASSES + _CLASSES * _CLASSES + EXTRA


def features(text: str | None) -> np.ndarray:
    """Square roots of class and class-pair frequencies, and eight statistics of lengths and repeats; finite for any text."""
    raw = np.frombuffer((text or "").encode("utf-8", "surrogatepass"), np.uint8)
    out = np.zeros(WIDTH, np.float32)
    n = len(raw)
    if n:
        c = _TABLE[raw].astype(np.int64)
        out[:_CLASSES] = np.sqrt(np.bincount(c, minlength=_CLASSES) / n)
        if n > 1:
            pair = np.bincount(c[:-1] * _CLASSES + c[1:], minlength=_CLASSES * _CLASSES)
            out[_CLASSES:-EXTRA] = np.sqrt(pair / (n - 1))
        words = (text or "").split()
        lines = (text or "").count("\n") + 1
        w = len(words)
        out[-EXTRA:] = (
            np.log1p(n) / 10, np.log1p(w) / 10, np.log1p(n / max(w, 1)) / 5, np.log1p(w / lines) / 10,
            len(set(words)) / max(w, 1), np.log1p(max(map(len, words), default=0)) / 10,
            np.sqrt(sum(map(str.__eq__, words, words[1:])) / max(w, 1)), np.sqrt(max(map(len, (text or "").split("\n"))) / n),
        )
    return out


class Scorer:
    """A one-hidden-layer network; ``prior`` is the class prior it was trained with."""

    def __init__(self, prior: float, mean: np.ndarray, spread: np.ndarray, layers: list[np.ndarray]):
        self.prior, self.mean, self.spread, self.layers = prior, mean, spread, layers

    def __call__(self, x: np.ndarray) -> np.ndarray:
        if not self.layers:
            return np.full(len(x), self.prior)
        a, b, c, d = self.layers
        z = np.tanh((x - self.mean) / self.spread @ a + b) @ c + d
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def risk_slope(zp: np.ndarray, zu: np.ndarray, prior: float) -> tuple[float, np.ndarray]:
    """The non-negative risk of outputs on positives and unlabelled texts, and its slope by output (positives first).

    Where the bracket is negative, the slope is that of minus the bracket, to climb back.
    """
    own = prior * np.logaddexp(0, -zp).mean()
    rest = np.logaddexp(0, zu).mean() - prior * np.logaddexp(0, zp).mean()
    down_p, down_u = -prior * _sigmoid(zp) / len(zp), _sigmoid(zu) / len(zu)
    if rest < 0:
        return float(own), np.concatenate([-down_p, -down_u])
    return float(own + rest), np.concatenate([-prior * _sigmoid(-zp) / len(zp) + down_p, down_u])


def plain_slope(zp: np.ndarray, zu: np.ndarray, prior: float) -> tuple[float, np.ndarray]:
    """Telling positives from unlabelled texts, both of equal weight."""
    risk = np.logaddexp(0, -zp).mean() + np.logaddexp(0, zu).mean()
    return float(risk), np.concatenate([-_sigmoid(-zp) / len(zp), _sigmoid(zu) / len(zu)])


def train(positive: np.ndarray, unlabelled: np.ndarray, prior: float, epochs: int = EPOCHS, seed: int = 7, slope_of=risk_slope) -> Scorer:
    """A scorer by stochastic descent on the non-negative risk with the logistic loss."""
    if not len(positive) or not len(unlabelled):
        return Scorer(prior, np.zeros(WIDTH), np.ones(WIDTH), [])
    rng = np.random.default_rng(seed)
    count = len(positive) + len(unlabelled)
    mean = (positive.sum(axis=0, dtype=np.float64) + unlabelled.sum(axis=0, dtype=np.float64)) / count
    square = sum(np.einsum("ij,ij->j", x, x, dtype=np.float64) for x in (positive, unlabelled)) / count
    spread = np.sqrt(np.clip(square - mean * mean, 0, None)) + 0.02
    mean, spread = mean.astype(np.float32), spread.astype(np.float32)
    k = positive.shape[1]
    layers = [rng.normal(0, k**-0.5, (k, HIDDEN)), np.zeros(HIDDEN), rng.normal(0, HIDDEN**-0.5, HIDDEN), np.zeros(1)]
    state = [(np.zeros_like(w), np.zeros_like(w)) for w in layers]
    step, batch = 0, 256
    for _ in range(epochs):
        pick = rng.permutation(len(unlabelled))
        for at in range(0, len(unlabelled), batch):
            xu = unlabelled[pick[at : at + batch]]
            xp = positive[rng.integers(len(positive), size=min(batch, len(positive)))]
            x = (np.concatenate([xp, xu]) - mean) / spread
            h = np.tanh(x @ layers[0] + layers[1])
            z = h @ layers[2] + layers[3]
            _, slope = slope_of(z[: len(xp)], z[len(xp) :], prior)
            back = slope[:, None] * layers[2] * (1 - h * h)
            grads = [x.T @ back + 1e-4 * layers[0], back.sum(axis=0), h.T @ slope + 1e-4 * layers[2], slope.sum(keepdims=True)]
            step += 1
            for w, g, (m, v) in zip(layers, grads, state, strict=True):
                m += 0.1 * (g - m)
                v += 0.001 * (g * g - v)
                w -= 0.002 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
    return Scorer(prior, mean, spread, [w.astype(np.float32) for w in layers])


def class_prior(positive: np.ndarray, unlabelled: np.ndarray, seed: int = 7) -> float:
    """The share of positives in the unlabelled texts, from the two samples alone.

    Networks learn on some folds of both to tell positives from unlabelled texts and score the
    fold left out.  Whatever scores above a threshold holds at least the positives' share of it,
    so the ratio of unlabelled to positive texts above any threshold bounds the prior from
    above.  The estimate is the ratio where it is least after adding what chance may do to it.
    """
    if min(len(positive), len(unlabelled)) < FOLDS:
        return 0.5
    sp, su = np.empty(len(positive)), np.empty(len(unlabelled))
    for k in range(FOLDS):
        in_p, in_u = np.arange(len(sp)) % FOLDS == k, np.arange(len(su)) % FOLDS == k
        told = train(positive[~in_p], unlabelled[~in_u], 0.5, PRIOR_EPOCHS, seed, plain_slope)
        sp[in_p], su[in_u] = told(positive[in_p]), told(unlabelled[in_u])
    sp, su = np.sort(sp), np.sort(su)
    cuts = np.unique(sp)
    above_p = 1 - np.searchsorted(sp, cuts) / len(sp)
    above_u = 1 - np.searchsorted(su, cuts) / len(su)
    chance = np.sqrt(np.log(40) / (2 * len(sp))) + np.sqrt(np.log(40) / (2 * len(su)))
    best = int(np.argmin((above_u + chance) / above_p))
    return float(np.clip(above_u[best] / above_p[best], 0.01, 0.99))


def _vectors(rows: DataFrame, share: float, salt: str) -> DataFrame:
    """(at, x): the vectors of a drawn share of the texts, and a key to order them by."""

    @F.pandas_udf("binary")
    def vector(texts: pd.Series) -> pd.Series:
        return pd.Series([features(t).tobytes() for t in texts], dtype=object)

    chance = F.pmod(F.xxhash64("doc_id", F.lit(salt)), F.lit(1_000_000)) / 1_000_000
    picked = rows.where(chance < share).select(F.xxhash64("doc_id").alias("at"), vector(F.col("text").cast("string")).alias("x"))
    return picked.limit(2 * SAMPLE)


def _trained(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """The pickled scorer of all vectors, positives and unlabelled ones."""
    held: dict[bool, list[bytes]] = {True: [], False: []}
    for pdf in batches:
        for positive, x in zip(pdf["positive"], pdf["x"], strict=True):
            held[bool(positive)].append(bytes(x))
    p, u = (np.frombuffer(b"".join(held[side]), np.float32).reshape(-1, WIDTH) for side in (True, False))
    yield pd.DataFrame({"model": [pickle.dumps(train(p, u, class_prior(p, u)))]})


def fit(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> Scorer:
    """Trains outside the held-out fold, from positives and unlabelled texts; no label but 1 is read.

    One task trains, on the bounded samples; only the scorer comes to the driver.
    """
    own = docs.select("doc_id", "text").where(~held_out(F.col("doc_id")) & F.col("doc_id").isNotNull())
    known = labels.where((F.col("quality") == 1) & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"))).select("doc_id").distinct()
    chosen = F.pmod(F.xxhash64("doc_id", F.lit("positive")), F.lit(1_000_000)) / 1_000_000 < min(1.0, sample / max(1, known.count()))
    p = _vectors(own.join(known.where(chosen), "doc_id", "left_semi"), 1.0, "positive").withColumn("positive", F.lit(True))
    u = _vectors(own, min(1.0, sample / max(1, own.count())), "unlabelled").withColumn("positive", F.lit(False))
    both = p.unionByName(u).coalesce(1).sortWithinPartitions("positive", "at", "x").select("positive", "x")
    found = both.mapInPandas(_trained, "model binary").first()
    return pickle.loads(found["model"]) if found else train(np.zeros((0, WIDTH), np.float32), np.zeros((0, WIDTH), np.float32), 0.5)


def score(docs: DataFrame, scorer: Scorer) -> DataFrame:
    """The documents with columns score (0 to 1, higher is likelier good) and predicted (0 or 1).

    A null text scores like an empty one, from the network's view of no characters at all.
    Columns named score or predicted are replaced; others stay.  Repeated rows and null ids each
    give a row; an empty table gives an empty result.
    """
    held = docs.sparkSession.sparkContext.broadcast(scorer)

    @F.pandas_udf("double")
    def judge(texts: pd.Series) -> pd.Series:
        out = []
        for at in range(0, len(texts), 512):
            x = np.stack([features(t) for t in texts.iloc[at : at + 512]])
            out.append(held.value(x))
        return pd.Series(np.concatenate(out) if out else np.zeros(0)).astype("float64")

    scored = docs.withColumn("score", judge(F.col("text").cast("string")))
    return scored.withColumn("predicted", (F.col("score") >= 0.5).cast("int"))


def keep_good(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The documents that the classifier does not reject, untouched, with all their columns."""
    held = docs.sparkSession.sparkContext.broadcast(fit(docs, labels))

    @F.pandas_udf("boolean")
    def good(texts: pd.Series) -> pd.Series:
        flags = [held.value(np.stack([features(t) for t in texts.iloc[a : a + 512]])) >= 0.5 for a in range(0, len(texts), 512)]
        return pd.Series(np.concatenate(flags) if flags else np.zeros(0, bool))

    return docs.where(good.asNondeterministic()(F.col("text").cast("string")))  # never moved below a join


def digest(docs: DataFrame, labels: DataFrame) -> DataFrame:
    out = score(docs.select("doc_id", "text"), fit(docs, labels))
    return out.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", "predicted")
