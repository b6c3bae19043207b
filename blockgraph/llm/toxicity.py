"""Operator 2: toxicity by averaged subword-bag embeddings and a linear softmax.

A word is the bag of its own bucket and its byte n-grams' buckets; misspelt words share most n-grams with the word
they come from. Embeddings are averaged over the bags of a passage, and a linear softmax reads the average. Both are
trained together in numpy, in one task, on at most ``SAMPLE`` labelled texts chosen by a hash of their id.

A document is scored as the passage that looks worst: passages of ``PASSAGE`` words with half overlaps cover the whole
text, so a few words in a long text weigh as much as in a short one. Training begins with whole texts; later the passage of
a text that counts is chosen anew in each epoch by the current model (the worst one), for either label.

Defined cases: null and empty texts have one empty passage, whose average is the zero vector, so the bias alone scores
them; labels that are null or belong to no document are not used; with no labelled row at all, or one class only, the
model is the class prior; a document that is labelled twice, or whose id repeats, trains once per pair of row and label, with either label if they
differ; texts of any length are read whole, and columns of other names pass through. ``doc_id``, ``lang``, ``source`` and labels are never inputs of a score.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .features import letter_words, subwords, whole, word_bytes
from .scratch import trained
from .text import Tokens, factorize, fitting, rows_of, segment_sums, slices, utf8

#: Most labelled texts to train on, and most bytes of text taken from them together (whole texts only).
SAMPLE, SAMPLE_BYTES = 4000, 12 << 20
BUCKETS, DIMENSION, SIZES = 1 << 17, 8, (3, 4, 5)
PASSAGE, EPOCHS, WHOLE_EPOCHS, RATE, BATCH = 4, 16, 1, 0.1, 64
#: Least number of texts with a bucket, as a share of the rarer class.
RARE = 0.02
HELD_OUT = "pmod(crc32(cast(cast(doc_id as string) as binary)), 5) = 0"


@dataclass
class Model:
    """Logit difference of each bucket (embedding times softmax weights) and the bias: all that scoring needs."""

    weights: np.ndarray
    bias: float

    def word_scores(self, tokens: Tokens, first: np.ndarray, hashes: np.ndarray) -> np.ndarray:
        """The mean weight of the bag of each of the given words."""
        owner, bucket = bags(tokens, first, hashes)
        sums = np.bincount(owner, self.weights[bucket], minlength=len(first))
        return sums / np.bincount(owner, minlength=len(first))


def bags(tokens: Tokens, first: np.ndarray, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    data, offs = word_bytes(tokens.mapped, tokens.starts[first], tokens.ends[first])
    owner, bucket = subwords(data, offs, SIZES, BUCKETS)
    return np.concatenate([owner, np.arange(len(first))]), np.concatenate([bucket, whole(hashes, BUCKETS)])


def passages(first: np.ndarray, size: int = PASSAGE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Begin, end and text of the passages: steps of half a passage, the last one ending with the text. An empty text has one empty passage."""
    counts = np.diff(first)
    step = size // 2
    n = np.maximum(1, -(-(counts - size) // step) + 1)
    doc = np.repeat(np.arange(len(counts)), n)
    k = np.arange(len(doc)) - np.repeat(np.cumsum(n) - n, n)
    begin = first[:-1][doc] + k * step
    end = np.minimum(begin + size, first[1:][doc])
    return begin, end, doc


def means(values: np.ndarray, begin: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Averages over the passages; shorter ones count as if filled up with words of weight 0."""
    sums = np.zeros((len(values) + 1, *values.shape[1:]))
    np.cumsum(values, axis=0, out=sums[1:])
    size = np.maximum(end - begin, PASSAGE)
    return (sums[end] - sums[begin]) / (size if values.ndim == 1 else size[:, None])


def train(texts: list[str], labels: list[int], seed: int = 7) -> Model:
    """Embeddings and softmax together, by stochastic gradient descent with adaptive steps per bucket and a falling rate."""
    y = np.array(labels, np.int64)
    if len(set(labels)) < 2:
        share = (sum(labels) + 0.5) / (len(labels) + 1) if labels else 0.0
        return Model(np.zeros(BUCKETS), float(np.log(max(share, 1e-3) / max(1 - share, 1e-3))))
    data, offs = utf8(pa.array(texts, pa.large_string()))
    tokens = letter_words(data, offs)
    hashes = tokens.hashes()
    word, distinct, firsts = factorize(hashes)
    owner, bucket = bags(tokens, firsts, distinct)
    order = np.argsort(owner, kind="stable")
    owner, bucket = owner[order], bucket[order]
    at = np.searchsorted(owner, np.arange(len(distinct) + 1))
    # A bucket that few texts hold would only learn these texts by heart; it keeps the weight 0.
    holders = np.bincount(np.unique(word * len(y) + tokens.docs()) // len(y), minlength=len(distinct))
    common = np.bincount(bucket, np.repeat(holders, np.diff(at)), minlength=BUCKETS) >= max(3, RARE * np.bincount(y).min())
    used, bucket = np.unique(bucket, return_inverse=True)
    size = np.diff(at).astype(np.float64)
    rng = np.random.default_rng(seed)
    emb = rng.uniform(-1, 1, (len(used), DIMENSION)) / DIMENSION * common[used, None]
    soft = rng.normal(0, 0.5, (DIMENSION, 2))
    seen, seen_soft = np.zeros(len(used)), 0.0
    bias = np.log(np.bincount(y, minlength=2) / len(y))
    begin, end, doc = passages(tokens.first)
    doc_first = np.searchsorted(doc, np.arange(len(y) + 1))
    steps = 0
    total = EPOCHS * -(-len(y) // BATCH)
    for epoch in range(EPOCHS):
        flat = emb @ (soft[:, 1] - soft[:, 0])
        by_word = np.bincount(owner, flat[bucket], minlength=len(distinct)) / size
        logit = means(by_word[word], begin, end)
        best = np.lexsort((logit, doc))[doc_first[1:] - 1]
        spans = (begin[best], end[best]) if epoch >= WHOLE_EPOCHS else (tokens.first[:-1], tokens.first[1:])
        turn = rng.permutation(len(y))
        for i in range(0, len(turn), BATCH):
            rate = RATE * (1 - steps / total)
            steps += 1
            some = turn[i : i + BATCH]
            a, b = spans[0][some], spans[1][some]
            n = b - a
            row = np.repeat(np.arange(len(some)), n)
            w = word[np.repeat(a - (np.cumsum(n) - n), n) + np.arange(n.sum())]
            bag = at[w + 1] - at[w]
            part_row = np.repeat(row, bag)
            part = bucket[np.repeat(at[w] - (np.cumsum(bag) - bag), bag) + np.arange(bag.sum())]
            scale = np.repeat(1.0 / (bag * np.maximum(n, PASSAGE)[row]), bag)
            near, spot = np.unique(part, return_inverse=True)
            mean = np.stack([np.bincount(part_row, emb[part, k] * scale, minlength=len(some)) for k in range(DIMENSION)], axis=1)
            z = mean @ soft + bias
            error = np.exp(z - z.max(axis=1, keepdims=True))
            error /= error.sum(axis=1, keepdims=True)
            error[np.arange(len(some)), y[some]] -= 1
            back = error @ soft.T
            step = np.stack([np.bincount(spot, back[part_row, k] * scale, minlength=len(near)) for k in range(DIMENSION)], axis=1)
            seen[near] += np.square(step).mean(axis=1)
            emb[near] -= rate * step / np.sqrt(seen[near] + 1e-12)[:, None] * common[used[near], None]
            step = mean.T @ error
            seen_soft += np.square(step).mean()
            soft -= rate * step / np.sqrt(seen_soft + 1e-12)
            bias -= 0.1 * rate * error.mean(axis=0)
    weights = np.zeros(BUCKETS)
    weights[used] = common[used] * (emb @ (soft[:, 1] - soft[:, 0]))
    return Model(weights, float(bias[1] - bias[0]))


def training_sample(docs: DataFrame, labels: DataFrame, exclude: str = HELD_OUT) -> DataFrame:
    """(text, toxic) of at most ``SAMPLE`` labelled texts, half of each class where there are enough, chosen by a hash of the id."""
    usable = labels.select("doc_id", F.col("toxic").cast("int").alias("toxic")).where(f"toxic in (0, 1) and doc_id is not null and not ({exclude})")
    chosen = None
    for value in (0, 1):
        part = usable.where(F.col("toxic") == value).orderBy(F.xxhash64("doc_id", F.lit(11)), "doc_id").limit(SAMPLE // 2)
        chosen = part if chosen is None else chosen.unionByName(part)
    # SAMPLE rows of two numbers.
    found = docs.select("doc_id", "text").where("text is not null").join(F.broadcast(chosen), "doc_id")
    return found.select("text", "toxic").orderBy(F.xxhash64("doc_id", F.lit(12)), "doc_id", F.octet_length("text"), "text").limit(SAMPLE)


def score_slice(model: Model, data: np.ndarray, offs: np.ndarray) -> np.ndarray:
    tokens = letter_words(data, offs)
    begin, end, doc = passages(tokens.first)
    if len(tokens):
        word, distinct, first = factorize(tokens.hashes())
        logit = means(np.round(model.word_scores(tokens, first, distinct), 9)[word], begin, end)
    else:
        logit = np.zeros(len(begin))
    worst = np.full(len(offs) - 1, -np.inf)
    np.maximum.at(worst, doc, logit)
    return 1 / (1 + np.exp(-np.clip(np.round(worst, 6) + model.bias, -60, 60)))


def toxicity(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id and score of every document."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offs = utf8(rows_of(batch, "text"))
            for i, j in slices(offs):
                scores = score_slice(shared.value, data[offs[i] : offs[j]], offs[i : j + 1] - offs[i])
                yield pa.RecordBatch.from_arrays([rows_of(batch, "doc_id").slice(i, j - i), pa.array(scores)], ["doc_id", "score"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id bigint, score double")


def keep_clean(docs: DataFrame, model: Model, threshold: float = 0.5) -> DataFrame:
    """The documents that score below the threshold, with their columns as they are."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("double")
    def score(texts):
        import pandas as pd

        data, offs = utf8(pa.array(texts, pa.large_string(), from_pandas=True))
        return pd.Series(np.concatenate([np.zeros(0), *(score_slice(shared.value, data[offs[i] : offs[j]], offs[i : j + 1] - offs[i]) for i, j in slices(offs))]))

    return docs.where(score("text") < threshold)


def _train_rows(rows: Iterator[tuple]) -> tuple[Model, list[int]]:
    texts, marks = fitting(rows, SAMPLE_BYTES)
    return train(texts, marks), marks


def fit(docs: DataFrame, labels: DataFrame) -> Model:
    """Train on the sample; the bias is then moved from the sample's share of each class to that of all usable labels."""
    model, marks = trained(training_sample(docs, labels), _train_rows)
    if len(set(marks)) == 2:
        there = {r.toxic: r.n for r in labels.select("doc_id", F.col("toxic").cast("int").alias("toxic")).where(f"toxic in (0, 1) and doc_id is not null and not ({HELD_OUT})").groupBy("toxic").agg(F.count("*").alias("n")).collect()}
        model.bias += float(np.log(there[1] / there[0]) - np.log(sum(marks) / (len(marks) - sum(marks))))
    return model


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    model = fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return toxicity(docs, model).select("doc_id", F.expr(f"coalesce({HELD_OUT}, false)").alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
