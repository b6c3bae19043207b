"""Operator 7: language identification by a linear-chain conditional random field over words.

Every word of a sentence is labelled; its features are hashed affixes, byte n-grams and the word itself (the
lexicon), and neighbouring labels are tied by learned transitions, so code-switched text gets a label for each stretch.
Training maximises the conditional likelihood of sentences whose words carry their document's language, with
gradients from forward-backward, in numpy, in one task, on at most ``SAMPLE`` documents chosen by a hash of their id.
A document's language is the label with most posterior mass over all its words; the score is that share.

A sentence ends at a line end or after ``.``, ``!`` or ``?``. Sentences over ``LONGEST`` words are computed in pieces of that
size: the pieces' transfer matrices hand on what stands before and behind, so the chain is exact at any length. Every word of
every text is labelled.

Defined cases: a text that is null or has no letter is ``und`` with score 0; one whose letters make no word (none can,
by this alphabet) falls back to the most frequent language; null languages are not learned; with no labelled row at
all everything is ``und``; ``lang``, ``source`` and ``doc_id`` are never inputs of a prediction; repeated rows are
predicted alike, and repeated ids are drawn together; columns of other names are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .features import affixes, letter_words, subwords, whole, word_bytes
from .scratch import trained
from .text import Tokens, factorize, fitting, rows_of, slices, utf8

UNKNOWN = "und"
#: Most documents to train on, and most bytes of text taken from them together (whole texts only).
SAMPLE, SAMPLE_BYTES = 1500, 6 << 20
BUCKETS, GRAMS, AFFIXES, LONGEST = 1 << 16, (2, 3), (2, 3, 4), 48
ITERATIONS, RATE, DECAY = 40, 0.5, 1e-6
HELD_OUT = "pmod(crc32(cast(cast(doc_id as string) as binary)), 3) = 1"


@dataclass
class Model:
    languages: list[str]
    weights: np.ndarray  # bucket x language
    transitions: np.ndarray  # language x language
    start: np.ndarray
    prior: int


def word_features(tokens: Tokens, first: np.ndarray, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(word number, bucket) pairs, grouped by word."""
    data, offs = word_bytes(tokens.mapped, tokens.starts[first], tokens.ends[first])
    parts = [subwords(data, offs, GRAMS, BUCKETS), affixes(data, offs, AFFIXES, BUCKETS), (np.arange(len(first)), whole(hashes, BUCKETS))]
    return np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts])


def emissions(weights: np.ndarray, owner: np.ndarray, bucket: np.ndarray, n: int) -> np.ndarray:
    size = np.maximum(np.bincount(owner, minlength=n), 1)
    return np.stack([np.bincount(owner, weights[bucket, k], minlength=n) for k in range(weights.shape[1])], axis=1) / np.sqrt(size)[:, None]


def sentences(data: np.ndarray, tokens: Tokens) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Begin (token number) and length of the pieces of a slice's chains, and whether a piece goes on with the one before."""
    if not len(tokens):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, bool)
    stops = np.flatnonzero((data == 10) | (data == 33) | (data == 46) | (data == 63))
    new = np.searchsorted(stops, tokens.starts[1:]) > np.searchsorted(stops, tokens.ends[:-1])
    begins = np.zeros(len(tokens), bool)
    begins[0] = True
    begins[1:] = new
    begins[tokens.first[:-1][tokens.counts > 0]] = True
    at = np.flatnonzero(begins)
    size = np.diff(np.append(at, len(tokens)))
    pieces = -(-size // LONGEST)
    k = np.arange(pieces.sum()) - np.repeat(np.cumsum(pieces) - pieces, pieces)
    begin = np.repeat(at, pieces) + k * LONGEST
    return begin, np.minimum(np.repeat(at + size, pieces) - begin, LONGEST), k > 0


def _handed_on(local: np.ndarray, begin: np.ndarray, size: np.ndarray, goes_on: np.ndarray, move: np.ndarray, start: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For every piece what stands before its first word and behind its last one, from the transfer matrices of the pieces of long chains."""
    labels = local.shape[1]
    before, behind = np.tile(np.exp(start), (len(size), 1)), np.ones((len(size), labels))
    parts = np.flatnonzero(goes_on | np.append(goes_on[1:], False))
    if not len(parts):
        return before, behind
    order = parts[np.argsort(-size[parts], kind="stable")]
    whole = local[begin[order]][:, None, :] * np.eye(labels)
    for t in range(1, int(size[order[0]])):
        n = int(np.searchsorted(-size[order], -t, "left"))
        step = (whole[:n] @ move) * local[begin[order[:n]] + t][:, None, :]
        whole[:n] = step / step.max(axis=(1, 2), keepdims=True)
    transfer = dict(zip(order.tolist(), whole, strict=True))
    for p in parts.tolist():
        if goes_on[p]:
            before[p] = out @ move
        out = before[p] @ transfer[p]
        out /= out.sum()
    for p in parts[::-1].tolist():
        if p + 1 < len(size) and goes_on[p + 1]:
            behind[p] = move @ into
            behind[p] /= behind[p].sum()
        into = transfer[p] @ behind[p]
        into /= into.sum()
    return before, behind


def posteriors(
    emit: np.ndarray, begin: np.ndarray, size: np.ndarray, model_t: np.ndarray, start: np.ndarray, goes_on: np.ndarray | None = None
) -> tuple[np.ndarray, np.ndarray, np.ndarray, float]:
    """Forward-backward over all pieces at once: word posteriors, expected transitions, expected starts, log likelihood of everything."""
    labels = emit.shape[1]
    gamma = np.empty_like(emit)
    pairs = np.zeros((labels, labels))
    goes_on = np.zeros(len(size), bool) if goes_on is None else goes_on
    peak = emit.max(axis=1)
    local = np.exp(emit - peak[:, None])
    move = np.exp(model_t)
    before, behind = _handed_on(local, begin, size, goes_on, move, start)
    order = np.argsort(-size, kind="stable")
    heads = begin[~goes_on]
    begin, size, before, behind = begin[order], size[order], before[order], behind[order]
    alive = len(size) - np.searchsorted(size[::-1], np.arange(1, int(size.max(initial=0)) + 1))
    alpha, scale = [], []
    for t, n in enumerate(alive):
        at = begin[:n] + t
        a = local[at] * (before[:n] if t == 0 else alpha[-1][:n] @ move)
        c = a.sum(axis=1)
        alpha.append(a / c[:, None])
        scale.append(c)
    beta = np.ones((0, labels))
    for t in range(len(alive) - 1, -1, -1):
        n = alive[t]
        if len(beta) < n:
            ending = behind[len(beta) : n]
            ending = ending / (alpha[t][len(beta) : n] * ending).sum(axis=1, keepdims=True)
            beta = np.concatenate([beta, ending])
        gamma[begin[:n] + t] = alpha[t] * beta
        if t:
            back = local[begin[:n] + t] * beta / scale[t][:, None]
            pairs += (alpha[t - 1][:n].T @ back) * move
            beta = back @ move.T
    if goes_on.any():
        # From the last word of a piece to the first one of the next.
        place = np.empty(len(order), np.int64)
        place[order] = np.arange(len(order))
        after = np.flatnonzero(goes_on)
        ends = np.stack([alpha[size[p] - 1][p] for p in place[after - 1]])
        p = place[after]
        pairs += (ends.T @ (local[begin[p]] * beta[p] / scale[0][p][:, None])) * move
    likelihood = float(sum(np.log(c).sum() for c in scale) + peak.sum())
    return gamma, pairs, gamma[heads].sum(axis=0), likelihood


def train(texts: list[str], languages: list[str]) -> Model:
    names = sorted(set(languages))
    if not names:
        return Model([], np.zeros((BUCKETS, 0)), np.zeros((0, 0)), np.zeros(0), 0)
    y = np.array([names.index(x) for x in languages])
    data, offs = utf8(pa.array(texts, pa.large_string()))
    tokens = letter_words(data, offs)
    n, labels = len(tokens), len(names)
    weights, transitions, start = np.zeros((BUCKETS, labels)), np.zeros((labels, labels)), np.zeros(labels)
    model = Model(names, weights, transitions, start, int(np.bincount(y).argmax()))
    if not n:
        return model
    word, distinct, first = factorize(tokens.hashes())
    owner, bucket = word_features(tokens, first, distinct)
    root = np.sqrt(np.maximum(np.bincount(owner, minlength=len(distinct)), 1))
    begin, size, goes_on = sentences(data, tokens)
    gold = y[tokens.docs()]
    true_pairs = np.zeros((labels, labels))
    inner = np.ones(n, bool)
    inner[begin[~goes_on]] = False
    np.add.at(true_pairs, (gold[np.flatnonzero(inner) - 1], gold[inner]), 1)
    true_start = np.bincount(gold[begin[~goes_on]], minlength=labels)
    seen = [np.full_like(p, 1e-8) for p in (weights, transitions, start)]
    for step in range(ITERATIONS):
        emit = emissions(weights, owner, bucket, len(distinct))[word]
        gamma, pairs, starts, _ = posteriors(emit, begin, size, transitions, start, goes_on)
        error = -gamma
        error[np.arange(n), gold] += 1
        by_word = np.stack([np.bincount(word, error[:, k], minlength=len(distinct)) for k in range(labels)], axis=1) / root[:, None]
        slope = np.stack([np.bincount(bucket, by_word[owner, k], minlength=BUCKETS) for k in range(labels)], axis=1) / n
        for p, g, s in zip((weights, transitions, start), (slope - DECAY * weights, (true_pairs - pairs) / n - 1e-3 * transitions, (true_start - starts) / n - 1e-3 * start), seen, strict=True):
            s += g * g
            p += RATE * g / np.sqrt(s)
    return model


def training_sample(docs: DataFrame, exclude: str = HELD_OUT) -> DataFrame:
    """(text, lang): whole texts and languages of at most ``SAMPLE`` documents, chosen by a hash of the id."""
    usable = docs.where(f"text is not null and lang is not null and doc_id is not null and not ({exclude})")
    chosen = usable.select("doc_id").distinct().orderBy(F.xxhash64("doc_id", F.lit(5)), "doc_id").limit(SAMPLE)
    # SAMPLE rows of one number.
    found = usable.select("doc_id", "text", "lang").join(F.broadcast(chosen), "doc_id").orderBy(F.xxhash64("doc_id", F.lit(6)), "doc_id", F.octet_length("text"), "text", "lang").limit(SAMPLE)
    return found.select("text", "lang")


def label_words(model: Model, data: np.ndarray, offs: np.ndarray) -> tuple[Tokens, np.ndarray]:
    """The words of a slice and their posteriors."""
    tokens = letter_words(data, offs)
    if not len(tokens):
        return tokens, np.zeros((0, len(model.languages)))
    word, distinct, first = factorize(tokens.hashes())
    emit = emissions(model.weights, *word_features(tokens, first, distinct), len(distinct))
    begin, size, goes_on = sentences(data, tokens)
    gamma, *_ = posteriors(emit[word], begin, size, model.transitions, model.start, goes_on)
    return tokens, gamma


def predict_slice(model: Model, data: np.ndarray, offs: np.ndarray, lettered: np.ndarray) -> tuple[list[str], np.ndarray]:
    n = len(offs) - 1
    if not model.languages:
        return [UNKNOWN] * n, np.zeros(n)
    tokens, gamma = label_words(model, data, offs)
    docs = tokens.docs()
    mass = np.stack([np.bincount(docs, gamma[:, k], minlength=n) for k in range(len(model.languages))], axis=1)
    best = np.where(tokens.counts > 0, mass.argmax(axis=1), model.prior)
    share = np.where(tokens.counts > 0, mass.max(axis=1) / np.maximum(tokens.counts, 1), 1 / len(model.languages))
    names = [model.languages[b] if ok else UNKNOWN for b, ok in zip(best.tolist(), lettered.tolist(), strict=True)]
    return names, np.where(lettered, np.round(np.clip(share, 0, 1), 9), 0.0)


def _has_letter(texts: pa.Array) -> np.ndarray:
    return pc.fill_null(pc.match_substring_regex(texts, r"\p{L}"), False).to_numpy(zero_copy_only=False)


def _predict_all(model: Model, texts: pa.Array) -> tuple[list[str], np.ndarray]:
    data, offs = utf8(texts)
    lettered = _has_letter(texts)
    names: list[str] = []
    scores = [np.zeros(0)]
    for i, j in slices(offs):
        a, b = predict_slice(model, data[offs[i] : offs[j]], offs[i : j + 1] - offs[i], lettered[i:j])
        names += a
        scores.append(b)
    return names, np.concatenate(scores)


def identify(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, lang_pred and score of every document."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            names, scores = _predict_all(shared.value, rows_of(batch, "text"))
            yield pa.RecordBatch.from_arrays([rows_of(batch, "doc_id"), pa.array(names, pa.string()), pa.array(scores)], ["doc_id", "lang_pred", "score"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id bigint, lang_pred string, score double")


def label_spans(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id and spans: array of (begin, end, lang) in bytes, stretches of words with one label each."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    kind = pa.list_(pa.struct([("begin", pa.int64()), ("end", pa.int64()), ("lang", pa.string())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = shared.value.languages
        for batch in batches:
            data, offs = utf8(rows_of(batch, "text"))
            for i, j in slices(offs):
                tokens, gamma = label_words(shared.value, data[offs[i] : offs[j]], offs[i : j + 1] - offs[i])
                label = gamma.argmax(axis=1) if len(gamma) and names else np.zeros(0, np.int64)
                out = []
                for d in range(j - i):
                    a, b = tokens.first[d], tokens.first[d + 1]
                    cuts = [a, *(np.flatnonzero(np.diff(label[a:b])) + a + 1).tolist(), b] if b > a and names else []
                    base = tokens.offs[d]
                    out.append([{"begin": int(tokens.starts[x] - base), "end": int((min(tokens.ends[y - 1], tokens.starts[y]) if y < b else tokens.ends[y - 1]) - base), "lang": names[label[x]]} for x, y in zip(cuts, cuts[1:], strict=False)])
                yield pa.RecordBatch.from_arrays([rows_of(batch, "doc_id").slice(i, j - i), pa.array(out, kind)], ["doc_id", "spans"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id bigint, spans array<struct<begin: bigint, end: bigint, lang: string>>")


def keep_known(docs: DataFrame, model: Model, least: float = 0.3) -> DataFrame:
    """The documents with a learned language and that share of its words at least, with their columns as they are."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("double")
    def share(texts: pd.Series) -> pd.Series:
        _, scores = _predict_all(shared.value, pa.array(texts, pa.large_string(), from_pandas=True))
        return pd.Series(scores)

    return docs.where(share("text") >= least)


def _train_rows(rows: Iterator[tuple]) -> Model:
    return train(*fitting(rows, SAMPLE_BYTES))


def fit(docs: DataFrame) -> Model:
    return trained(training_sample(docs), _train_rows)


def op7_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    found = identify(docs, fit(docs))
    return found.select("doc_id", F.expr(f"coalesce({HELD_OUT}, false)").alias("held_out"), "lang_pred", "score")
