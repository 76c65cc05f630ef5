"""Toxicity by multiple-instance learning.

A document is a bag of sentences. A sentence scores sigmoid(bias + sum of the weights of its distinct
features: words, and the first four and five letters of words of six letters or more, for compounds);
a document scores 1 - prod(1 - sentence score) (noisy-or). Only document labels train the weights; the
sentence scores then locate the offending sentences.

The model is fitted on the driver from a bounded sample: at most `sample_docs` labelled documents, the ones
with the least hash of their id among those of at most `longest` characters. Scoring reads every whole text.

Defined cases: a null, empty or wordless text has no sentence and scores 0; without both labels in the
sample every score is 0; repeated rows score alike, and an id that occurs more than once trains with its least text.
"""

from __future__ import annotations

import re
import sys
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import id_remainder, keep_table, read_table

_SENTENCE = re.compile(r"[.!?\n]+")
_TOKEN = re.compile(r"[^\W\d_]+")


def word_features(word: str) -> tuple[str, ...]:
    return (word, "^" + word[:4], "^" + word[:5]) if len(word) >= 6 else (word,)


def sentence_words(text: str) -> list[list[str]]:
    """Distinct features of each sentence that has any."""
    found = ({f for w in _TOKEN.findall(s) for f in word_features(w)} for s in _SENTENCE.split(text.lower()))
    return [[sys.intern(f) for f in sorted(x)] for x in found if x]


def fit_noisy_or(
    bags: list[list[list[str]]],
    labels: np.ndarray,
    *,
    min_docs: int = 3,
    min_lean: float = 4.0,
    epochs: int = 300,
    rate: float = 0.3,
    l2: float = 3e-6,
) -> tuple[dict[str, float], float]:
    """Weights of features and the bias, by Adam on the noisy-or likelihood. Only features in at least min_docs
    toxic documents, and in min_lean standard deviations more of them than chance puts there, get a weight:
    rare ones would explain single documents away."""
    labels = np.asarray(labels, np.float64)
    if len(labels) == 0 or labels.min() == labels.max():
        return {}, -30.0
    held = Counter()
    toxic = Counter()
    for bag, y in zip(bags, labels):
        words = {w for s in bag for w in s}
        held.update(words)
        if y:
            toxic.update(words)
    rate_all = labels.mean()
    vocab: dict[str, int] = {}
    for w, n in toxic.items():
        chance = held[w] * rate_all
        if n >= min_docs and n >= chance + min_lean * np.sqrt(chance * (1 - rate_all)):
            vocab[w] = len(vocab)
    cols, sent_of, bag_of, n_sent = [], [], [], 0
    for b, bag in enumerate(bags):
        for s in bag:
            ids = [vocab[w] for w in s if w in vocab]
            cols += ids
            sent_of += [n_sent] * len(ids)
            bag_of.append(b)
            n_sent += 1
    cols, sent_of, bag_of = (np.asarray(x, np.int64) for x in (cols, sent_of, bag_of))
    weight = np.array([np.log((toxic[w] + rate_all) / (held[w] - toxic[w] + 1 - rate_all)) for w in vocab])
    weight = np.clip(weight, -2, 4)
    bias = -5.0
    theta = np.append(weight, bias)
    m, v = np.zeros_like(theta), np.zeros_like(theta)
    for step in range(1, epochs + 1):
        z = theta[-1] + np.bincount(sent_of, theta[cols], n_sent)
        p = 1 / (1 + np.exp(-np.clip(z, -30, 30)))
        log_clean = np.bincount(bag_of, np.log1p(-np.minimum(p, 1 - 1e-9)), len(bags))
        p_bag = np.clip(1 - np.exp(log_clean), 1e-9, 1 - 1e-9)
        # d(loss)/dz = p * (1 - y / p_bag): clean bags push every sentence down, toxic bags share the blame
        g = p * (1 - labels[bag_of] / p_bag[bag_of])
        grad = np.append(np.bincount(cols, g[sent_of], len(theta) - 1), g.sum()) / len(bags)
        grad[:-1] += l2 * theta[:-1]
        m, v = 0.9 * m + 0.1 * grad, 0.999 * v + 0.001 * grad * grad
        theta -= rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
        theta[-1] = min(theta[-1], -4.0)
    return {w: float(theta[i]) for w, i in vocab.items() if abs(theta[i]) > 1e-3}, float(theta[-1])


def sentence_scores(text: str, weights: dict[str, float], bias: float) -> list[float]:
    """Scores of the sentences, in order."""
    get = weights.get
    return [
        float(1 / (1 + np.exp(-max(-30.0, min(30.0, bias + sum(get(w, 0.0) for w in s))))))
        for s in sentence_words(text)
    ]


def bag_score(text: str, weights: dict[str, float], bias: float) -> float:
    """Noisy-or over the sentences."""
    base = np.log1p(-1 / (1 + np.exp(-bias)))
    log_clean, plain = 0.0, 0
    for s in _SENTENCE.split(text.lower()):
        words = set(_TOKEN.findall(s))
        live = {f for w in words for f in word_features(w) if f in weights}
        z = sum(sorted(weights[f] for f in live))
        if z:
            log_clean -= np.logaddexp(0.0, min(30.0, bias + z))
        elif words:
            plain += 1
    return float(-np.expm1(log_clean + plain * base))


def train_toxicity(
    docs: DataFrame,
    labels: DataFrame,
    *,
    id_col: str = "doc_id",
    text_col: str = "text",
    label_col: str = "toxic",
    train_only=None,
    sample_docs: int = 6000,
    sample_chars: int = 12_000_000,
    longest: int = 8000,
) -> tuple[dict[str, float], float]:
    """Fit on a bounded sample: the sample_docs labelled ids with the least hash whose texts have at most
    `longest` characters, in that order up to sample_chars characters in all."""
    known = labels.select(F.col(id_col).alias("id"), F.col(label_col).cast("double").alias("y"))
    known = known.where(F.col("id").isNotNull() & F.col("y").isNotNull())
    if train_only is not None:
        known = known.where(train_only(F.col("id")))
    known = known.groupBy("id").agg(F.max("y").alias("y"))
    chosen = known.withColumn("h", F.xxhash64("id")).orderBy("h", "id").limit(sample_docs)
    texts = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("t")).where(F.col("t").isNotNull())
    texts = texts.where(F.length("t") <= longest)
    # at most sample_docs rows are broadcast; an id that occurs again and again gives one text
    sample = texts.join(F.broadcast(chosen), "id").groupBy("h", "id", "y").agg(F.min("t").alias("t"))
    sample = keep_table(sample.withColumn("n", F.length("t").cast("long")), "toxic-sample")
    sizes = [r["n"] for r in sample.select("h", "id", "n").orderBy("h", "id").collect()]  # at most sample_docs rows
    take = max(1, int(np.searchsorted(np.cumsum(sizes), sample_chars, "right")))
    bags, ys = [], []
    for r in sample.orderBy("h", "id").limit(take).select("y", "t").toLocalIterator():
        bags.append(sentence_words(r["t"]))
        ys.append(1.0 if r["y"] > 0 else 0.0)
    return fit_noisy_or(bags, np.array(ys))


def score_toxicity(
    docs: DataFrame, model: tuple[dict[str, float], float], *, id_col: str = "doc_id", text_col: str = "text"
) -> DataFrame:
    """doc_id and score of every row. The model's size is bounded by the training sample."""
    weights, bias = model

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            scores = [bag_score(t or "", weights, bias) for t in pdf["text"]]
            yield pd.DataFrame({"doc_id": pdf["doc_id"], "score": np.asarray(scores, float)})

    src = docs.select(F.col(id_col).cast("string").alias("doc_id"), F.col(text_col).alias("text"))
    out = src.mapInPandas(run, "doc_id string, score double")
    return out.select(F.col("doc_id").cast("long").alias("doc_id"), "score")


def offending_sentences(
    docs: DataFrame,
    model: tuple[dict[str, float], float],
    *,
    id_col: str = "doc_id",
    text_col: str = "text",
    threshold: float = 0.5,
) -> DataFrame:
    """Spans (start, end, in characters) and scores of the sentences that score at least threshold."""
    weights, bias = model

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            found = []
            for i, t in zip(pdf["doc_id"], pdf["text"]):
                at = 0
                t = t or ""
                for m in [*_SENTENCE.finditer(t), None]:
                    end = m.start() if m else len(t)
                    s = sentence_scores(t[at:end], weights, bias)
                    if s and s[0] >= threshold:
                        found.append((i, at, end, t[at:end], s[0]))
                    at = m.end() if m else end
            yield pd.DataFrame(found, columns=["doc_id", "start", "end", "sentence", "score"])

    src = docs.select(F.col(id_col).cast("string").alias("doc_id"), F.col(text_col).alias("text"))
    return src.mapInPandas(run, "doc_id string, start long, end long, sentence string, score double").withColumn(
        "doc_id", F.col("doc_id").cast("long")
    )


def keep_clean(docs: DataFrame, labels: DataFrame, *, threshold: float = 0.7) -> DataFrame:
    """Documents that score below threshold, columns unchanged; the score is computed beside the row."""
    weights, bias = train_toxicity(docs, labels, train_only=lambda i: id_remainder(i, 3) != 1)

    @F.pandas_udf("double")
    def score(text: pd.Series) -> pd.Series:
        return pd.Series([bag_score(t or "", weights, bias) for t in text], dtype=float)

    return docs.where(score(F.col("text")) < threshold)


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    model = train_toxicity(
        docs, read_table(spark, sf_dir, "labels"), train_only=lambda i: id_remainder(i, 3) != 1
    )
    return score_toxicity(docs, model).select(
        "doc_id",
        (id_remainder(F.col("doc_id"), 3) == 1).alias("held_out"),
        "score",
        (F.col("score") >= 0.7).cast("int").alias("predicted"),
    )
