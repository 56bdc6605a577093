"""Toxicity by non-negative positive-unlabelled learning.

The training set is positives (documents marked toxic) and unlabelled text, which holds
toxic documents too in the share ``prior``.  The risk of a linear classifier f on word
presence is estimated as

    prior * E_pos[loss(f)] + max(0, E_unl[loss(-f)] - prior * E_pos[loss(-f)])

with logistic loss; when the second part falls below ``-slack`` a step climbs it instead,
so that the estimate can't be driven below zero by over-fitting.  Optimised by Adam in
numpy on the driver, on a bounded sample; the model is a sorted array of word hashes with
weights, bounded by ``max_features``, and scoring touches every row in Arrow batches.

Words are runs of letters, A-Z folded; the beginnings of longer words are features as well,
so that inflected and compound forms share evidence.  Null and empty texts have no words and score the
bias alone.  Without any positive training row every score is 0.  Every row gets its own
score, so repeated rows get the same; an empty table gives an empty one; a very long text is
a block of its own.  Other columns pass through; one named ``tox_score`` is replaced.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import scan
from .langid import held_out

#: Bounds of the fitting sample and of the model.
MAX_POSITIVE = 4000
MAX_UNLABELLED = 12000
MAX_FEATURES = 5000
#: Bytes of the beginnings of words that count as features beside whole words.
PREFIXES = (4, 5)


@dataclass
class WordModel:
    words: np.ndarray  # sorted hashes of features
    weights: np.ndarray
    bias: float

    def logits(self, word: np.ndarray, doc: np.ndarray, n: int) -> np.ndarray:
        """Of ``n`` documents from their words (hash, document number), repeats counted once."""
        out = np.full(n, self.bias)
        if len(word) and len(self.words):
            at = np.searchsorted(self.words, word)
            at[at == len(self.words)] = 0
            known = self.words[at] == word
            # one number for each (document, feature), so that a repeat counts once
            pair = np.unique(doc[known] * len(self.words) + at[known])
            out += np.bincount(pair // len(self.words), weights=self.weights[pair % len(self.words)], minlength=n)
        return out


def traits(data: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(hash, document number) of every word and of the beginnings of longer words."""
    begin, end, doc = scan.words(data, starts, scan.LETTERS)
    spans, names = [(begin, end, doc)], [np.uint64(0)]
    for n in PREFIXES:
        longer = end - begin > n
        spans.append((begin[longer], begin[longer] + n, doc[longer]))
        names.append(np.uint64(0x9E37 * n))  # the beginning "abcd-" isn't the word "abcd"
    h = scan.word_hashes(data, np.concatenate([s[0] for s in spans]), np.concatenate([s[1] for s in spans]))
    h ^= np.repeat(np.array(names, np.uint64), [len(s[0]) for s in spans])
    return h, np.concatenate([s[2] for s in spans])


def _unique_traits(data: np.ndarray, starts: np.ndarray) -> list[np.ndarray]:
    h, doc = traits(data, starts)
    order = np.argsort(doc, kind="stable")
    bounds = scan.by_document(np.bincount(doc, minlength=len(starts) - 1))
    h = h[order]
    return [np.unique(h[bounds[k] : bounds[k + 1]]) for k in range(len(starts) - 1)]


def _sampled_words(rows: DataFrame) -> list[np.ndarray]:
    """Distinct word hashes of each (bounded) sampled row, in an order that doesn't depend on tasks."""

    def collect(batches):
        for batch in batches:
            for lo, hi, data, starts in scan.blocks(batch.column(1)):
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), pa.array([w.tobytes() for w in _unique_traits(data, starts)], pa.binary())], names=["doc_id", "w"])

    found = rows.select(F.col("doc_id").cast("string").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text")).mapInArrow(collect, "doc_id string, w binary").collect()
    return [np.frombuffer(r["w"], np.uint64) for r in sorted(found, key=lambda r: (r["doc_id"] or "", bytes(r["w"])))]


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1.0 / (1.0 + np.exp(-np.clip(z, -35, 35)))


def frequency(word: np.ndarray, docs: list[np.ndarray]) -> np.ndarray:
    """In how many of ``docs`` each of the sorted ``word`` hashes occurs."""
    out = np.zeros(len(word), np.int64)
    for w in docs:
        at = np.searchsorted(word, w)
        at[at == len(word)] = 0
        out[at[word[at] == w]] += 1
    return out


def likelihood_ratio(a: np.ndarray, n: int, b: np.ndarray, m: int) -> np.ndarray:
    """G statistic of document frequencies ``a`` of ``n`` against ``b`` of ``m``."""

    def part(k, total, p):
        p = np.clip(p, 1e-12, 1 - 1e-12)
        return k * np.log(p) + (total - k) * np.log(1 - p)

    both = (a + b) / (n + m)
    return 2 * (part(a, n, a / n) + part(b, m, b / m) - part(a, n, both) - part(b, m, both))


def train_nnpu(positive: list[np.ndarray], unlabelled: list[np.ndarray], prior: float, max_features: int = MAX_FEATURES, epochs: int = 60, batch: int = 512, rate: float = 0.05, decay: float = 1e-5, slack: float = 0.0, min_ratio: float = 15.0, seed: int = 7) -> WordModel:
    """Fit on lists of distinct word hashes.

    Features are words of at least half a percent (and two) of the positives that positives
    hold significantly more or less often than unlabelled texts do: a log-likelihood ratio
    above ``min_ratio``, the strongest ``max_features`` of them.  Few positives then can't
    be told apart by the accidental words of their texts.
    """
    if not positive:
        return WordModel(np.zeros(0, np.uint64), np.zeros(0), -35.0)
    word, df = np.unique(np.concatenate(positive), return_counts=True)
    keep = np.flatnonzero(df >= max(2, 0.005 * len(positive)))
    ratio = likelihood_ratio(df[keep], len(positive), frequency(word[keep], unlabelled), max(1, len(unlabelled)))
    order = np.argsort(-ratio, kind="stable")[:max_features]
    vocab = np.sort(word[keep[order[ratio[order] >= min_ratio]]])
    if not len(vocab):
        return WordModel(vocab, np.zeros(0), -35.0)

    def rows(docs):
        out = []
        for w in docs:
            at = np.searchsorted(vocab, w)
            at[at == len(vocab)] = 0
            out.append(at[vocab[at] == w])
        return out

    pos, unl = rows(positive), rows(unlabelled)
    rng = np.random.default_rng(seed)
    w, b = np.zeros(len(vocab)), 0.0
    m, v = np.zeros(len(vocab) + 1), np.zeros(len(vocab) + 1)
    steps = max(1, len(unl) // batch)
    t = 0

    def flat(docs, chosen):
        part = [docs[k] for k in chosen]
        return np.concatenate(part) if part else np.zeros(0, np.int64), np.repeat(np.arange(len(part)), [len(x) for x in part]), len(part)

    def value(idx, row, n):
        return np.bincount(row, weights=w[idx], minlength=n) + b

    def push(grad, idx, row, slope):
        grad[:-1] += np.bincount(idx, weights=slope[row], minlength=len(vocab))
        grad[-1] += slope.sum()

    for _ in range(epochs):
        order_p, order_u = rng.permutation(len(pos)), rng.permutation(len(unl))
        for s in range(steps):
            p = flat(pos, order_p[s * len(pos) // steps : max((s + 1) * len(pos) // steps, s * len(pos) // steps + 1)])
            u = flat(unl, order_u[s * batch : (s + 1) * batch])
            fp, fu = value(*p), value(*u) if u[2] else np.zeros(0)
            np_, nu = max(1, p[2]), max(1, u[2])
            unlabelled_part = np.logaddexp(0, fu).sum() / nu - prior * np.logaddexp(0, fp).sum() / np_
            grad = np.zeros(len(vocab) + 1)
            if unlabelled_part >= -slack:
                push(grad, p[0], p[1], prior * -_sigmoid(-fp) / np_)
                push(grad, u[0], u[1], _sigmoid(fu) / nu)
                push(grad, p[0], p[1], -prior * _sigmoid(fp) / np_)
            else:
                push(grad, u[0], u[1], -_sigmoid(fu) / nu)
                push(grad, p[0], p[1], prior * _sigmoid(fp) / np_)
            grad[:-1] += decay * w
            t += 1
            m = 0.9 * m + 0.1 * grad
            v = 0.999 * v + 0.001 * grad * grad
            step = rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
            w -= step[:-1]
            b -= step[-1]
    return WordModel(vocab, w, float(b))


def fit(docs: DataFrame, labels: DataFrame, max_positive: int = MAX_POSITIVE, max_unlabelled: int = MAX_UNLABELLED, prior: float | None = None, **options) -> WordModel:
    """Fit on the rows given: ``docs`` (doc_id, text), ``labels`` (doc_id, toxic).

    ``prior`` defaults to the share of toxic rows among the labelled ones.  Samples are taken
    by id hash, at shares set from counts over all rows.
    """
    marks = labels.filter(F.col("doc_id").isNotNull() & F.col("toxic").isNotNull()).groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max("toxic").alias("toxic"))
    counts = marks.agg(F.count("*").alias("n"), F.coalesce(F.sum(F.when(F.col("toxic") == 1, 1)), F.lit(0)).alias("pos")).first()
    if not counts["pos"]:
        return train_nnpu([], [], 0.0)
    prior = counts["pos"] / counts["n"] if prior is None else prior
    n_docs = docs.count()
    bucket = F.pmod(F.xxhash64(F.col("doc_id").cast("string"), F.lit(2)), F.lit(1 << 30))
    chosen = marks.filter((F.col("toxic") == 1) & (bucket < min(1.0, max_positive / counts["pos"]) * (1 << 30))).select("doc_id")
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    # the chosen ids are bounded by max_positive, so the broadcast is as well
    positive = _sampled_words(texts.join(F.broadcast(chosen), "doc_id", "left_semi"))
    unlabelled = _sampled_words(texts.filter(F.pmod(F.xxhash64(F.col("doc_id").cast("string"), F.lit(3)), F.lit(1 << 30)) < min(1.0, max_unlabelled / max(1, n_docs)) * (1 << 30)))
    return train_nnpu(positive, unlabelled, prior, **options)


def score(docs: DataFrame, model: WordModel) -> DataFrame:
    """All columns of ``docs`` with tox_score (0 to 1) added; a column of that name is replaced."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("double")
    def scored(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        m = shared.value
        for texts in batches:
            out = np.zeros(len(texts))
            for lo, hi, data, starts in scan.blocks(pa.Array.from_pandas(texts, type=pa.string())):
                out[lo:hi] = _sigmoid(m.logits(*traits(data, starts), hi - lo))
            yield pd.Series(out)

    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    return docs.select(*[F.col(f"`{c}`") for c in docs.columns if c != "tox_score"], scored(text).alias("tox_score"))


def op10_nnpu_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", "toxic")
    model = fit(docs.filter(~held_out(5, 0)), labels.filter(~held_out(5, 0)))
    return score(docs, model).select("doc_id", held_out(5, 0).alias("held_out"), F.col("tox_score").alias("score"), F.when(F.col("tox_score") >= 0.5, 1).otherwise(0).alias("predicted"))
