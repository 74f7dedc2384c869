"""Masked pseudo-likelihood of documents under a bidirectional window network.

Every token is predicted from ``REACH`` tokens on both sides.  The network adds one embedding per
context position, squashes the sum, and gives a normalised distribution in two steps: a class of
tokens, then the token in its class, so that a prediction costs two short softmaxes instead of one
over the vocabulary.  The most frequent tokens are outputs of their own; the others share buckets,
and a bucket's probability is multiplied by P(token | bucket) from the counts of all tokens, so
every counted token has its own probability.  The ``KNOWN`` most frequent of them are known to the
tasks that score; the counts of all others are joined, never collected.  A document's score is the sum of its tokens' conditional log-probabilities.

Everything is learned from all documents: the vocabulary from their word counts, the weights by one
pass of stochastic descent in every task over the texts it reads, starting from common weights, and
a token-weighted mean of the tasks' weights, aggregated without passing through one place.
"""

from __future__ import annotations

import hashlib
import math
import zlib
from collections import Counter
from collections.abc import Iterator
from itertools import compress, repeat

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Scratch

REACH = 2
CLASSES = 32
IN_CLASS = 32
RARE = 64
WIDTH = 16
BATCH = 8192
RATE = 0.08
KNOWN = 16_384

VOCAB = CLASSES * IN_CLASS
EDGE = VOCAB  # stands beyond both ends of a text

#: Capitals in lower case, and all that is no part of a token as a space.
_PLAIN = bytes(c + 32 if 65 <= c <= 90 else 32 if c < 32 or c == 127 else c for c in range(256))
_SYMBOLS = bytes(c for c in range(33, 127) if not chr(c).isalnum())
_OTHERS = bytes(c for c in range(256) if c not in _SYMBOLS)


def tokens_of(text: str | None) -> list[bytes]:
    """Lower-cased words (runs of digits, letters and characters beyond ASCII) and single symbols."""
    plain = (text or "").encode("utf-8", "surrogatepass").translate(_PLAIN)
    for symbol in set(plain.translate(None, _OTHERS)):
        plain = plain.replace(bytes((symbol,)), bytes((32, symbol, 32)))
    return plain.split()


def key_of(token: bytes) -> bytes:
    """The name of a token: itself, or for over 64 bytes a digest of all of it and its last bytes."""
    return token if len(token) <= 64 else b"\0" + hashlib.blake2b(token, digest_size=16).digest() + token[-3:]


def token_counts(docs: DataFrame) -> DataFrame:
    """(token, n) over all documents; counted in each task before they are shuffled."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: Counter[bytes] = Counter()
        for pdf in batches:
            for text in pdf["text"]:
                tokens = tokens_of(text)
                held.update(map(key_of, tokens) if max(map(len, tokens), default=0) > 64 else tokens)
                if len(held) > 400_000:
                    yield pd.DataFrame({"token": list(held.keys()), "n": list(held.values())})
                    held = Counter()
        yield pd.DataFrame({"token": list(held.keys()), "n": list(held.values())})

    return docs.select(F.col("text").cast("string").alias("text")).mapInPandas(run, "token binary, n long").groupBy("token").agg(F.sum("n").alias("n"))


class Vocabulary:
    """The most frequent tokens have numbers of their own; the others share ``RARE`` by their last bytes.

    ``ranked`` may go on beyond the tokens with numbers, ``totals`` has what each bucket's raised counts make.
    """

    def __init__(self, ranked: list[tuple[bytes, int]], rest: int, counts: DataFrame, totals: dict[int, int] | None = None):
        self.counts = counts
        self.totals = totals or {}
        own = ranked[: VOCAB - RARE]
        self.number = {t: i for i, (t, _) in enumerate(own)}
        self.count = np.ones(VOCAB)
        self.count[: len(own)] += [n for _, n in own]
        self.count[VOCAB - RARE :] += rest / RARE
        # one look-up of a token gives its place here, and with it its number and log P(token | bucket), 0 without one;
        # P is never zero, for a bucket's total is larger by one
        known = [(t, n, zlib.crc32(t[-3:]) % RARE) for t, n in ranked[len(own) :]]
        self.place = {t: i for i, (t, _) in enumerate(ranked)}
        self.numbers = np.array([*range(len(own)), *[VOCAB - RARE + k for _, _, k in known], -1], np.int32)
        self.tails = np.array([0.0] * len(own) + [math.log((n + 1) / (self.totals[k] + 1)) for _, n, k in known] + [0.0])

    def __getstate__(self) -> dict:
        return self.__dict__ | {"counts": None}

    def encode(self, tokens: list[bytes]) -> np.ndarray:
        return self.judged(tokens)[0]

    def judged(self, tokens: list[bytes]) -> tuple[np.ndarray, float, list[bytes]]:
        """The tokens' numbers, the summed log P(token | bucket) of the known ones, and those in buckets that are not known."""
        at = np.fromiter(map(self.place.get, tokens, repeat(-1)), np.int32, len(tokens))
        out, strange = self.numbers[at], at < 0
        others = list(compress(tokens, strange.tolist()))
        get, first, crc = self.number.get, VOCAB - RARE, zlib.crc32
        found = [first + crc(t[-3:]) % RARE if len(t) <= 64 else get(key_of(t), first + crc(t[-3:]) % RARE) for t in others]
        out[strange] = found
        return out, self.tails[at].sum(), [t for t, i in zip(others, found, strict=True) if i >= first]


def vocabulary(docs: DataFrame) -> Vocabulary:
    """The leading tokens, and how many the others make, from the counts over all documents."""
    scratch = Scratch(docs.sparkSession, "counts")
    counts = scratch.keep(token_counts(docs))
    ranked = [(bytes(r["token"]), r["n"]) for r in counts.orderBy(F.desc("n"), "token").limit(VOCAB - RARE + KNOWN).collect()]
    own = ranked[: VOCAB - RARE]
    sums = {r["bucket"]: (r["n"], r["total"]) for r in counts.groupBy(_bucket().alias("bucket")).agg(F.sum("n").alias("n"), F.sum(F.col("n") + 1).alias("total")).collect()}
    totals = {k: total for k, (_, total) in sums.items()}
    for t, n in own:
        totals[zlib.crc32(t[-3:]) % RARE] -= n + 1
    return Vocabulary(ranked, sum(n for n, _ in sums.values()) - sum(n for _, n in own), counts, totals)


def _bucket() -> Column:
    """The bucket of column token, were it none of the most frequent."""
    return F.pmod(F.crc32(F.substring("token", -3, 3)), F.lit(RARE)).cast("int")


def _in_bucket(vocab: Vocabulary, rare: DataFrame) -> DataFrame:
    """(row, tail): the summed log P(token | bucket) of the tokens (row, token, times).

    A count is raised by one, and one more is left in each bucket for all tokens never counted.
    """
    totals = F.array(*[F.lit(vocab.totals.get(k, 0)).cast("long") for k in range(RARE)])
    judged = rare.join(vocab.counts, "token", "left")
    log_p = F.log((F.coalesce("n", F.lit(0)) + 1) / (F.get(totals, _bucket()) + 1))
    return judged.groupBy("row").agg(F.sum(F.col("times") * log_p).alias("tail"))


def encoded(docs: DataFrame, vocab: Vocabulary) -> DataFrame:
    """(row, doc_id, ids, tail, rare, times) of every document: its tokens' numbers in two bytes each, which training and scoring read.

    tail sums log P(token | bucket) of the known tokens; the others in buckets are in rare, as often as times says.
    """
    held = docs.sparkSession.sparkContext.broadcast(vocab)

    @F.pandas_udf("ids binary, tail double, rare array<binary>, times array<int>")
    def numbered(texts: pd.Series) -> pd.DataFrame:
        words = held.value
        ids: list[bytes] = []
        tails: list[float] = []
        rare: list[list[bytes]] = []
        times: list[list[int]] = []
        for text in texts:
            own, tail, others = words.judged(tokens_of(text))
            ids.append(own.astype("<i2").tobytes())
            tails.append(tail)
            shared = Counter(others)
            rare.append(list(map(key_of, shared)))
            times.append(list(shared.values()))
        return pd.DataFrame({"ids": pd.Series(ids, dtype=object), "tail": pd.Series(tails, dtype="float64"), "rare": pd.Series(rare, dtype=object), "times": pd.Series(times, dtype=object)})

    out = docs.select(F.monotonically_increasing_id().alias("row"), "doc_id", numbered(F.col("text").cast("string")).alias("s"))
    return Scratch(docs.sparkSession, "encoded").keep(out.select("row", "doc_id", "s.*"))


def _numbers(ids: bytes) -> np.ndarray:
    return np.frombuffer(ids, "<i2").astype(np.int32)


def start(vocab: Vocabulary, seed: int = 7) -> list[np.ndarray]:
    """Common first weights: small embeddings, biases that give the unigram distribution."""
    rng = np.random.default_rng(seed)
    table = vocab.count.reshape(CLASSES, IN_CLASS)
    return [
        rng.normal(0, 0.3, (2 * REACH * (VOCAB + 1), WIDTH)).astype(np.float32),
        rng.normal(0, 0.1, (WIDTH, CLASSES)).astype(np.float32),
        np.log(table.sum(axis=1) / table.sum()).astype(np.float32),
        rng.normal(0, 0.1, (CLASSES, WIDTH, IN_CLASS)).astype(np.float32),
        np.log(table / table.sum(axis=1, keepdims=True)).astype(np.float32),
    ]


def contexts(ids: np.ndarray) -> np.ndarray:
    """Rows of the embedding table for each token's context, without the token itself; one row of the result for each position."""
    edge = np.full(REACH, EDGE, np.int32)
    wide = np.concatenate([edge, ids, edge], dtype=np.int32)
    n = len(ids)
    shifts = [d for d in range(2 * REACH + 1) if d != REACH]
    return np.stack([wide[d : d + n] + k * (VOCAB + 1) for k, d in enumerate(shifts)])


def _hidden(embed: np.ndarray, ctx: np.ndarray) -> np.ndarray:
    h = np.take(embed, ctx[0], axis=0)
    for own in ctx[1:]:
        h += np.take(embed, own, axis=0)
    return np.tanh(h, out=h)


def _by_class(ids: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, list[tuple[int, int, int]]]:
    """The order of the tokens by class, their classes and numbers in them in that order, and what each class present has of it."""
    order = np.argsort((ids // IN_CLASS).astype(np.uint8), kind="stable")
    own = ids[order]
    g = own // IN_CLASS
    ends = np.searchsorted(g, np.arange(CLASSES + 1)).tolist()
    return order, g, own % IN_CLASS, [(k, ends[k], ends[k + 1]) for k in range(CLASSES) if ends[k] < ends[k + 1]]


def _states(embed: np.ndarray, ctx: np.ndarray) -> np.ndarray:
    """The hidden states and a one, by which the biases are a last row of the weights."""
    out = np.ones((ctx.shape[1], WIDTH + 1), np.float32)
    out[:, :WIDTH] = _hidden(embed, ctx)
    return out


def _biased(weights: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """The weights of the classes and of the tokens in each, with their biases as a last row."""
    _, a, b, c, d = weights
    return np.concatenate([a, b[None]]), np.concatenate([c, d[:, None]], axis=1)


def _inner(h: np.ndarray, c: np.ndarray, spans: list[tuple[int, int, int]]) -> np.ndarray:
    """What the tokens of each class get before the softmax, of states in that order; a column for each state."""
    z = np.empty((IN_CLASS, len(h)), np.float32)
    for k, at, end in spans:
        z[:, at:end] = c[k].T @ h[at:end].T
    return z


def _summed(ctx: np.ndarray, back: np.ndarray) -> np.ndarray:
    """What goes back to each row of the embedding table: the columns of back, summed by row."""
    n = VOCAB + 1
    sums = [[np.bincount(own, weights=b, minlength=n) for b in back] for own in ctx.astype(np.intp) - np.arange(len(ctx))[:, None] * n]
    return np.array(sums, np.float32).swapaxes(1, 2).reshape(-1, len(back))


def _log_chosen(z: np.ndarray, chosen: np.ndarray) -> np.ndarray:
    """The logarithm of the softmax of each column at the chosen row."""
    z -= z.max(axis=0)
    own = z[chosen, np.arange(z.shape[1])]
    return own - np.log(np.exp(z, out=z).sum(axis=0))


def _missed(z: np.ndarray, chosen: np.ndarray) -> np.ndarray:
    """One at the chosen row of each column, less the softmax."""
    z -= z.max(axis=0)
    np.exp(z, out=z)
    z /= -z.sum(axis=0)
    z[chosen, np.arange(z.shape[1])] += 1
    return z


def log_probs(weights: list[np.ndarray], ids: np.ndarray, ctx: np.ndarray) -> np.ndarray:
    """log P(token | context) of each token."""
    a, c = _biased(weights)
    out = np.empty(len(ids), np.float32)
    for at in range(0, len(ids), BATCH):
        order, g, w, spans = _by_class(ids[at : at + BATCH])
        h = _states(weights[0], ctx[:, at : at + BATCH][:, order])
        out[at + order] = _log_chosen(a.T @ h.T, g) + _log_chosen(_inner(h, c, spans), w)
    return out


class Learner:
    """Stochastic descent with per-weight step sizes on the summed log-probability."""

    def __init__(self, weights: list[np.ndarray]):
        self.weights = [w.copy() for w in weights]
        self.seen = [np.full(len(weights[0]), 0.1, np.float32), *[np.full_like(w, 1e-2) for w in weights[1:]]]
        self.tokens = 0

    def step(self, ids: np.ndarray, ctx: np.ndarray) -> None:
        a, c = _biased(self.weights)
        n = len(ids)
        order, g, w, spans = _by_class(ids)
        ctx = ctx[:, order]
        h = _states(self.weights[0], ctx)
        err = _missed(a.T @ h.T, g)
        moved = a[:WIDTH] @ err
        grad_a, grad_c = (err @ h).T, np.zeros_like(c)
        err = _missed(_inner(h, c, spans), w)
        for k, at, end in spans:
            e = err[:, at:end]
            grad_c[k] = (e @ h[at:end]).T
            moved[:, at:end] += c[k, :WIDTH] @ e
        moved *= 1 - np.square(h[:, :WIDTH].T)
        total = _summed(ctx, moved.astype(np.float64)) / n
        grads = [grad_a[:WIDTH], grad_a[WIDTH], grad_c[:, :WIDTH], grad_c[:, WIDTH]]
        for value, grad, seen in zip(self.weights[1:], grads, self.seen[1:], strict=True):
            grad = grad / n
            seen += grad * grad
            value += RATE * grad / np.sqrt(seen)
        self.seen[0] += np.square(total).sum(axis=1)
        self.weights[0] += RATE * 4 * total / np.sqrt(self.seen[0])[:, None]
        self.tokens += n


def train(docs: DataFrame, vocab: Vocabulary) -> list[np.ndarray]:
    """Weights averaged over the tasks' passes; the first weights if there is no text."""
    return train_encoded(encoded(docs, vocab), vocab)


def train_encoded(numbered: DataFrame, vocab: Vocabulary) -> list[np.ndarray]:
    first = start(vocab)
    sizes = [w.size for w in first]
    held = numbered.sparkSession.sparkContext.broadcast(first)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        learner = Learner(held.value)
        ids: list[np.ndarray] = []
        ctx: list[np.ndarray] = []
        size = 0

        def learn() -> None:
            all_ids, all_ctx = np.concatenate(ids), np.concatenate(ctx, axis=1)
            for at in range(0, len(all_ids), BATCH):
                learner.step(all_ids[at : at + BATCH], all_ctx[:, at : at + BATCH])
            ids.clear()
            ctx.clear()

        for pdf in batches:
            for own in map(_numbers, pdf["ids"]):
                for at in range(0, len(own), 1 << 18):
                    part = own[at : at + (1 << 18)]
                    ids.append(part)
                    ctx.append(contexts(part))
                    size += len(part)
                    if size >= 1 << 18:
                        learn()
                        size = 0
        if size:
            learn()
        if learner.tokens:
            flat = np.concatenate([w.ravel() for w in learner.weights])
            yield pd.DataFrame({"i": np.arange(len(flat), dtype=np.int32), "w": flat * np.float64(learner.tokens), "n": np.full(len(flat), float(learner.tokens))})

    parts = numbered.select("ids").mapInPandas(run, "i int, w double, n double")
    mean = parts.groupBy("i").agg((F.sum("w") / F.sum("n")).alias("w"))
    packed = mean.groupBy(F.expr("i div 4096").alias("block")).agg(F.sort_array(F.collect_list(F.struct("i", "w"))).alias("own"))
    flat = np.concatenate([w.ravel() for w in first])
    for r in packed.select(F.col("block"), F.transform("own", lambda x: x["w"].cast("float")).alias("w")).toLocalIterator():
        flat[r["block"] * 4096 : r["block"] * 4096 + len(r["w"])] = r["w"]
    return [part.reshape(w.shape) for part, w in zip(np.split(flat, np.cumsum(sizes)[:-1]), first, strict=True)]


def score(docs: DataFrame, vocab: Vocabulary, weights: list[np.ndarray]) -> DataFrame:
    """(doc_id, n_tokens, log_likelihood, per_token) of every document, from its whole text.

    A null text, or one without tokens, has no tokens, likelihood 0 and a null mean.  Null ids and
    repeated rows each give a row; an empty table gives an empty result.  Only doc_id and text are read.
    """
    return score_encoded(encoded(docs, vocab), vocab, weights)


def score_encoded(numbered: DataFrame, vocab: Vocabulary, weights: list[np.ndarray]) -> DataFrame:
    held = numbered.sparkSession.sparkContext.broadcast(weights)

    @F.pandas_udf("double")
    def judge(texts: pd.Series) -> pd.Series:
        sums: list[np.ndarray] = []
        group: list[np.ndarray] = []

        def flush() -> None:
            counts = np.array([len(i) for i in group], np.int64)
            total = np.zeros(len(group))
            if counts.sum():
                lp = log_probs(held.value, np.concatenate(group), np.concatenate([contexts(i) for i in group], axis=1))
                total = np.bincount(np.repeat(np.arange(len(group)), counts), weights=lp, minlength=len(group))
            sums.append(total)
            group.clear()

        size = 0
        for ids in map(_numbers, texts):
            group.append(ids)
            size += len(ids)
            if size >= 1 << 18:
                flush()
                size = 0
        flush()
        return pd.Series(np.concatenate(sums))

    rare = numbered.select("row", F.explode(F.arrays_zip("rare", "times")).alias("r")).select("row", F.col("r.rare").alias("token"), F.col("r.times").alias("times"))
    n_tokens = (F.length("ids") / 2).cast("long").alias("n_tokens")
    judged = numbered.select("row", "doc_id", n_tokens, (judge("ids") + F.col("tail")).alias("log_likelihood"))
    out = judged.join(_in_bucket(vocab, rare), "row", "left")
    out = out.select("doc_id", "n_tokens", (F.col("log_likelihood") + F.coalesce("tail", F.lit(0.0))).alias("log_likelihood"))
    return out.withColumn("per_token", F.when(F.col("n_tokens") > 0, F.col("log_likelihood") / F.col("n_tokens")))


def digest(docs: DataFrame) -> DataFrame:
    vocab = vocabulary(docs)
    numbered = encoded(docs, vocab)  # texts are cut and looked up once, not for each of the two
    return score_encoded(numbered, vocab, train_encoded(numbered, vocab))
