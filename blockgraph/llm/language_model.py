"""Operator 3: scoring by a Brown class-based bigram model.

Words are split at white space and lower-cased in A-Z; every text ends with an end token. The ``CLUSTERED`` most frequent
training words are assigned to ``CLASSES`` classes by exchange clustering: words move one by one to the class that raises
the likelihood of the class bigrams most, until a sweep moves few. Then every other training word, however rare, is placed
into the learned class that raises the same likelihood most, by the classes it is seen between; neighbours that are not
placed yet count as one of ``RARE_CLASSES`` spellings. The end token is a class of its own. A word that training never saw is
taken for one of the class in which most words of its spelling that were seen once are. A text has the probability of its
class sequence (smoothed transitions, starting from the end class) times that of each word in its class (absolute
discounting; the discounted mass, and at least one count, is shared evenly by the class's words and one unseen word).

Counts, bigrams and totals come from all training documents. Word counts stay a table: the ``HEAD`` most frequent
words are broadcast, with counts and classes, and all other tokens are joined with the table by word, as runs between two
tokens whose classes are known. Neither sampling nor any cap touches them: a word beyond the head is only looked up another way.

Defined cases: a null or empty text is its end token; held-out texts may hold unseen words (count 0); without any training
text the scores are those of a model with an empty vocabulary; equal texts score alike; only ``doc_id`` and ``text`` are read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .scratch import discard, stored
from .text import SPACED, Tokens, factorize, rows_of, slices, splitmix, utf8

CLUSTERED, CLASSES, RARE_CLASSES = 2000, 60, 32
#: Words that are broadcast with their counts: at most 2^19, 11 MB.
HEAD = 1 << 19
SWEEPS = 5
DISCOUNT, PRIOR = 0.6, 0.5
HELD_OUT = "coalesce(pmod(crc32(cast(cast(doc_id as string) as binary)), 7) = 2, false)"
END = b""


def rare_class(tokens: Tokens, which: np.ndarray) -> np.ndarray:
    """Spelling group of words, from their last two bytes and their length."""
    ends = tokens.ends[which]
    size = ends - tokens.starts[which]
    last = tokens.mapped[ends - 1].astype(np.uint64)
    before = np.where(size > 1, tokens.mapped[np.maximum(ends - 2, 0)], 0).astype(np.uint64)
    return (splitmix(last * np.uint64(512) + before * np.uint64(2) + (size > 8)) % np.uint64(RARE_CLASSES)).astype(np.int64)


# Exchange clustering


def exchange(bigrams: np.ndarray, fixed: np.ndarray, n_classes: int, sweeps: int = SWEEPS) -> np.ndarray:
    """Classes of words from their dense bigram counts. ``fixed`` is -1 for words to cluster, else the class (from ``n_classes`` on)."""
    movable = np.flatnonzero(fixed < 0)
    weight = bigrams.sum(axis=1) + bigrams.sum(axis=0)
    order = movable[np.argsort(-weight[movable], kind="stable")]
    total = int(max(n_classes, fixed.max(initial=-1) + 1))
    label = fixed.copy()
    label[order] = np.arange(len(order)) % n_classes
    one = np.eye(total)[label]
    left = bigrams @ one  # word x class of the next word
    right = bigrams.T @ one  # word x class of the word before
    table = one.T @ left

    def h(x):
        return x * np.log(np.maximum(x, 1e-300))

    for _ in range(sweeps):
        moved = 0
        for w in order:
            own = label[w]
            self_count = bigrams[w, w]
            out, into = left[w].copy(), right[w].copy()
            # Take the word out of its class; what it has with itself moves along.
            out[own] -= self_count
            into[own] -= self_count
            table[own] -= out
            table[:, own] -= into
            table[own, own] -= self_count
            rows, columns = table.sum(axis=1), table.sum(axis=0)
            k = np.arange(n_classes)
            gain = (h(table[:n_classes] + out) - h(table[:n_classes])).sum(axis=1) + (h(table[:, :n_classes] + into[:, None]) - h(table[:, :n_classes])).sum(axis=0)
            cell = table[k, k]
            gain += h(cell + out[k] + into[k] + self_count) - h(cell + out[k]) - h(cell + into[k]) + h(cell)
            n_out, n_in = out.sum() + self_count, into.sum() + self_count
            gain -= h(rows[k] + n_out) - h(rows[k]) + h(columns[k] + n_in) - h(columns[k])
            best = int(gain.argmax())
            if gain[best] <= gain[own] + 1e-9:
                best = int(own)
            table[best] += out
            table[:, best] += into
            table[best, best] += self_count
            if best != own:
                moved += 1
                label[w] = best
                left[:, own] -= bigrams[:, w]
                left[:, best] += bigrams[:, w]
                right[:, own] -= bigrams[w]
                right[:, best] += bigrams[w]
        if moved <= len(order) // 200:
            break
    return label


@dataclass
class Model:
    """What every task needs: the head of the vocabulary and the class tables."""

    keys: np.ndarray  # sorted hashes of head words
    counts: np.ndarray
    classes: np.ndarray
    complete: bool  # no word lies outside the head
    total: int  # N
    distinct: int  # V
    unseen: np.ndarray  # class of unseen words, by spelling group
    class_tokens: np.ndarray
    class_words: np.ndarray
    transitions: np.ndarray  # log10
    end_class: int

    def look_up(self, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Which of these words are in the head, and the counts and classes of those."""
        if not len(self.keys):
            return np.zeros(len(hashes), bool), np.zeros(len(hashes), np.int64), np.zeros(len(hashes), np.int64)
        at = np.minimum(np.searchsorted(self.keys, hashes), len(self.keys) - 1)
        inside = self.keys[at] == hashes
        return inside, np.where(inside, self.counts[at], 0), np.where(inside, self.classes[at], 0)

    def base(self, c: np.ndarray) -> np.ndarray:
        return np.log10((c + 1) / (self.total + (self.distinct + 1)))

    def emission(self, c: np.ndarray, k: np.ndarray) -> np.ndarray:
        """log10 of the discounted share of a word with count c in class k."""
        n, v = self.class_tokens[k], self.class_words[k]
        spare = np.maximum(DISCOUNT * v, 1.0)
        return np.log10((np.maximum(c - DISCOUNT, 0) + spare / (v + 1)) / (n - DISCOUNT * v + spare))


# Passes over the corpus


def _split(batch: pa.RecordBatch, most: int = 2 << 20) -> Iterator[tuple[int, int, Tokens]]:
    data, offs = utf8(rows_of(batch, "text"))
    for i, j in slices(offs, most):
        yield i, j, Tokens(data[offs[i] : offs[j]], offs[i : j + 1] - offs[i], SPACED)


def _count_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for i, j, tokens in _split(batch, 2 << 20):
            codes, _, first = factorize(tokens.hashes())
            n = np.bincount(codes, minlength=len(first)) if len(first) else np.zeros(0, np.int64)
            words = tokens.words(first).cast(pa.binary())
            yield pa.RecordBatch.from_arrays([pa.concat_arrays([words, pa.array([END], pa.binary())]), pa.array(np.append(n, j - i))], ["word", "c"])


def word_counts(training: DataFrame) -> DataFrame:
    """(word, c) of all words of the training texts; the empty word is the end token."""
    return training.mapInArrow(_count_words, "word binary, c bigint").groupBy("word").agg(F.sum("c").alias("c"))


def _hash_words(words: list[bytes]) -> np.ndarray:
    offs = np.concatenate([[0], np.cumsum([len(w) for w in words])]).astype(np.int64)
    data = np.frombuffer(b"".join(words), np.uint8)
    tokens = Tokens(data, offs, SPACED)
    assert len(tokens) == len(words)
    return tokens.hashes()


def _sequence(tokens: Tokens, ids: np.ndarray, end: int) -> np.ndarray:
    """Ids of all tokens with the end token before, between and after the texts."""
    n = len(tokens.offs) - 1
    out = np.full(len(ids) + n + 1, end, np.int64)
    out[np.arange(len(ids)) + tokens.docs() + 1] = ids
    return out


def bigram_counts(training: DataFrame, keys: np.ndarray, width: int) -> DataFrame:
    """(code, c): how often id ``code // width`` is followed by id ``code % width``. Ids: clustered words, rare classes, end."""
    shared = training.sparkSession.sparkContext.broadcast(keys)
    n = len(keys)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        order = np.argsort(shared.value)
        known = shared.value[order]
        for batch in batches:
            for _, _, tokens in _split(batch, 2 << 20):
                sequence = _sequence(tokens, _ids(tokens, known, order, n), width - 1)
                code, c = np.unique(sequence[:-1] * width + sequence[1:], return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(code), pa.array(c)], ["code", "c"])

    return training.mapInArrow(run, "code bigint, c bigint").groupBy("code").agg(F.sum("c").alias("c"))


def _ids(tokens: Tokens, known: np.ndarray, order: np.ndarray, n: int) -> np.ndarray:
    codes, distinct, first = factorize(tokens.hashes())
    at = np.minimum(np.searchsorted(known, distinct), max(n - 1, 0))
    ids = n + rare_class(tokens, first)
    if n:
        ids = np.where(known[at] == distinct, order[at], ids)
    return ids[codes]


def _place(table: np.ndarray, n_classes: int):
    """Words with the classes around them (codes: class before, or all classes + class after) to (word, c, k, spelling)."""
    total = len(table)

    def h(x):
        return x * np.log(np.maximum(x, 1e-300))

    # What a class has before it, and after it: one row for each code.
    around = np.concatenate([table[:, :n_classes], table[:n_classes].T])
    rows, columns = table.sum(axis=1)[:n_classes], table.sum(axis=0)[:n_classes]

    def place(words: pa.Array, owner: np.ndarray, code: np.ndarray, c: np.ndarray) -> pa.RecordBatch:
        n = np.bincount(owner, np.where(code < total, c, 0), minlength=len(words)).astype(np.int64)
        # Codes and counts repeat much: the gains of distinct ones are worked out once.
        kinds, which = np.unique(np.stack([code, c], axis=1), axis=0, return_inverse=True)
        which = which.reshape(-1)
        gains = h(around[kinds[:, 0]] + kinds[:, 1:]) - h(around[kinds[:, 0]])
        sizes, of_size = np.unique(n, return_inverse=True)
        sizes = sizes[:, None].astype(np.float64)
        gain = -(h(rows + sizes) - h(rows) + h(columns + sizes) - h(columns))[of_size]
        for k in range(n_classes):
            gain[:, k] += np.bincount(owner, gains[which, k], minlength=len(n))
        data, offs = utf8(words)
        spelling = rare_class(Tokens(data, offs, SPACED), np.arange(len(n)))
        best = np.round(gain, 6).argmax(axis=1)
        return pa.RecordBatch.from_arrays([words, pa.array(n), pa.array(best.astype(np.int32)), pa.array(spelling.astype(np.int32))], ["word", "c", "k", "spelling"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # Rows come in the order of words. The last word of a batch may go on in the next one.
        kept, kept_code, kept_c = pa.array([], pa.binary()), np.zeros(0, np.int64), np.zeros(0, np.int64)
        for batch in batches:
            if not batch.num_rows:
                continue
            words, lists = pa.concat_arrays([kept, rows_of(batch, "word")]), rows_of(batch, "codes")
            size = np.concatenate([[len(kept_code)] * len(kept), pc.list_value_length(lists).to_numpy(zero_copy_only=False)]).astype(np.int64)
            code = np.concatenate([kept_code, lists.flatten().to_numpy()])
            c = np.concatenate([kept_c, rows_of(batch, "counts").flatten().to_numpy()])
            new = np.ones(len(words), bool)
            new[1:] = pc.not_equal(words[1:], words[:-1]).to_numpy(zero_copy_only=False)
            pair, which = np.unique(np.repeat(np.cumsum(new) - 1, size) * (2 * total) + code, return_inverse=True)
            c = np.bincount(which, c, minlength=len(pair)).astype(np.int64)
            owner, code = pair // (2 * total), pair % (2 * total)
            words = words.take(pa.array(np.flatnonzero(new)))
            last = int(np.searchsorted(owner, len(words) - 1))
            kept, kept_code, kept_c = words[-1:], code[last:], c[last:]
            if last:
                yield place(words[:-1], owner[:last], code[:last], c[:last])
        if len(kept):
            yield place(kept, np.zeros(len(kept_code), np.int64), kept_code, kept_c)

    return run


def placed_words(training: DataFrame, keys: np.ndarray, label: np.ndarray, table: np.ndarray, n_classes: int) -> DataFrame:
    """(word, c, k, spelling) of all training words but the clustered ones."""
    shared = training.sparkSession.sparkContext.broadcast((keys, label))
    n, total = len(keys), len(table)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, label = shared.value
        order = np.argsort(keys)
        known = keys[order]
        for batch in batches:
            for _, _, tokens in _split(batch):
                codes, _, first = factorize(tokens.hashes())
                ids = _ids(tokens, known, order, n)
                sequence = _sequence(tokens, label[ids], total - 1)
                at = np.arange(len(ids)) + tokens.docs() + 1
                later = np.flatnonzero(ids >= n)
                word, at = codes[later] * (2 * total), at[later]
                pair, c = np.unique(np.concatenate([word + sequence[at - 1], word + total + sequence[at + 1]]), return_counts=True)
                # One row for a word of a slice.
                begins = np.flatnonzero(np.diff(pair // (2 * total), prepend=-1))
                words = tokens.words(first[pair[begins] // (2 * total)]).cast(pa.binary())
                offs = pa.array(np.append(begins, len(pair)).astype(np.int32))
                lists = [pa.ListArray.from_arrays(offs, pa.array(x.astype(np.int32))) for x in (pair % (2 * total), c)]
                yield pa.RecordBatch.from_arrays([words, *lists], ["word", "codes", "counts"])

    around = training.mapInArrow(run, "word binary, codes array<int>, counts array<int>")
    return around.repartition("word").sortWithinPartitions("word").mapInArrow(_place(table, n_classes), "word binary, c bigint, k int, spelling int")


def head_words(placed: DataFrame, head: int) -> pa.Table:
    """Most frequent words with their counts and classes: all from the lowest frequency band on that ``head`` rows allow."""
    named = placed.withColumn("band", F.floor(F.log2("c") * 16))
    kept, lowest = 0, None
    for row in named.groupBy("band").agg(F.count("*").alias("n")).orderBy(F.desc("band")).collect():  # under 1,000 bands
        if kept + row.n > head:
            break
        kept, lowest = kept + row.n, row.band
    return named.where(F.col("band") >= (lowest if lowest is not None else 1 << 30)).select("word", "c", "k").toArrow()


def _runs(tokens: Tokens, sequence: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Places of tokens without a class (-1) in the sequence, the tokens there, and where a run of them begins (n+1 offsets)."""
    at = np.flatnonzero(sequence < 0)
    places = np.arange(len(tokens)) + tokens.docs() + 1
    cuts = np.flatnonzero(np.diff(at) > 1) + 1
    return at, np.searchsorted(places, at), np.concatenate([[0], cuts, [len(at)]]) if len(at) else np.zeros(1, np.int64)


def class_moves(training: DataFrame, model: Model, placed: DataFrame) -> np.ndarray:
    """How often a class follows a class in training, with every word in its class."""
    shared = training.sparkSession.sparkContext.broadcast((model.keys, model.counts, model.classes))
    end = model.end_class
    width = end + 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        head = Model(*shared.value, *[None] * 8)
        for batch in batches:
            for _, _, tokens in _split(batch):
                codes, distinct, _ = factorize(tokens.hashes())
                inside, _, k = head.look_up(distinct)
                sequence = _sequence(tokens, np.where(inside, k, -1)[codes], end)
                a, b = sequence[:-1], sequence[1:]
                both = (a >= 0) & (b >= 0)
                code, c = np.unique(a[both] * width + b[both], return_counts=True)
                at, which, cuts = _runs(tokens, sequence)
                n, m = len(code), len(cuts) - 1
                words = pa.ListArray.from_arrays(pa.array(cuts.astype(np.int32)), tokens.words(which).cast(pa.binary()))
                before, after = sequence[at[cuts[:-1]] - 1] if m else at, sequence[at[cuts[1:] - 1] + 1] if m else at
                yield pa.RecordBatch.from_arrays([pa.array(code), pa.array(c), pa.nulls(n, pa.int64()), pa.nulls(n, pa.int64()), pa.nulls(n, words.type)], ["code", "c", "before", "after", "words"])
                if m:
                    yield pa.RecordBatch.from_arrays([pa.nulls(m, pa.int64()), pa.nulls(m, pa.int64()), pa.array(before), pa.array(after), words], ["code", "c", "before", "after", "words"])

    found = training.mapInArrow(run, "code bigint, c bigint, before bigint, after bigint, words array<binary>")
    if model.complete:
        pairs = found.where("code is not null").select("code", "c")
    else:
        found = stored(found, "moves")
        runs = found.where("words is not null").withColumn("run", F.monotonically_increasing_id())
        each = runs.select("run", "before", "after", F.posexplode("words").alias("at", "word")).join(placed.select("word", "k"), "word")
        chains = each.groupBy("run", "before", "after").agg(F.expr("array_sort(collect_list(struct(at, k)))").alias("ks"))
        chains = chains.select(F.expr("concat(array(before), transform(ks, x -> cast(x.k as bigint)), array(after))").alias("chain"))
        more = chains.select(F.explode(F.expr(f"transform(sequence(1, size(chain) - 1), i -> chain[i - 1] * {width} + chain[i])")).alias("code"), F.lit(1).cast("long").alias("c"))
        pairs = found.where("code is not null").select("code", "c").unionByName(more)
    pairs = pairs.groupBy("code").agg(F.sum("c").alias("c")).toArrow()  # width^2 rows at most
    moves = np.zeros(width * width)
    moves[pairs.column("code").to_numpy()] = pairs.column("c").to_numpy()
    if not model.complete:
        discard(found)
    return moves.reshape(width, width)


def fit(docs: DataFrame, exclude: str = HELD_OUT, head: int = HEAD) -> tuple[Model, DataFrame]:
    """The model, and the stored table of the counts and classes of all words that are not clustered."""
    training = docs.where(f"not ({exclude})").select("text")
    counts = stored(word_counts(training), "words")
    totals = counts.agg(F.sum("c").alias("n"), F.count("*").alias("v")).first()
    total, distinct = int(totals.n or 0), int(totals.v)
    top = counts.where("octet_length(word) > 0").orderBy(F.desc("c"), "word").limit(CLUSTERED).collect()
    discard(counts)
    clustered = _hash_words([bytes(r.word) for r in top]) if top else np.zeros(0, np.uint64)
    width = len(clustered) + RARE_CLASSES + 1
    pairs = bigram_counts(training, clustered, width).toArrow()  # width^2 rows at most
    bigrams = np.zeros(width * width)
    bigrams[pairs.column("code").to_numpy()] = pairs.column("c").to_numpy()
    bigrams = bigrams.reshape(width, width)
    n_classes = max(1, min(CLASSES, len(clustered)))
    fixed = np.full(width, -1, np.int64)
    fixed[len(clustered) :] = n_classes + np.arange(RARE_CLASSES + 1)
    label = exchange(bigrams, fixed, n_classes)
    one = np.eye(n_classes + RARE_CLASSES + 1)[label]
    placed = stored(placed_words(training, clustered, label, one.T @ bigrams @ one, n_classes), "placed")
    # The head: the clustered words and the most frequent of the others.
    rest = head_words(placed, max(0, head - len(clustered)))
    words = rest.column("word").to_pylist()
    keys = np.concatenate([clustered, _hash_words(words) if words else np.zeros(0, np.uint64)])
    c = np.concatenate([np.array([r.c for r in top], np.int64), rest.column("c").to_numpy()])
    classes = np.concatenate([label[: len(clustered)], rest.column("k").to_numpy()]).astype(np.int32)
    order = np.argsort(keys)
    # Tokens and distinct words of each class, and the class of unseen words of each spelling.
    class_tokens = np.bincount(label[: len(clustered)], [r.c for r in top], minlength=n_classes + 1)
    class_words = np.bincount(label[: len(clustered)], minlength=n_classes + 1).astype(np.float64)
    once = np.zeros((RARE_CLASSES, n_classes))
    for row in placed.groupBy("spelling", "k").agg(F.sum("c").alias("n"), F.count("*").alias("v"), F.count_if(F.col("c") == 1).alias("once")).collect():  # RARE_CLASSES * CLASSES rows
        class_tokens[row.k] += row.n
        class_words[row.k] += row.v
        once[row.spelling, row.k] = row.once
    unseen = np.where(once.any(axis=1), once.argmax(axis=1), once.sum(axis=0).argmax())
    complete = distinct <= len(keys) + 1
    model = Model(keys[order], c[order], classes[order], complete, total, distinct, unseen, class_tokens, class_words, np.zeros((0, 0)), n_classes)
    moves = class_moves(training, model, placed)
    share = (moves.sum(axis=0) + 1) / (moves.sum() + n_classes + 1)
    model.transitions = np.log10((moves + PRIOR * (n_classes + 1) * share) / (moves.sum(axis=1, keepdims=True) + PRIOR * (n_classes + 1)))
    # The end token is certain in its class.
    class_tokens[-1] = moves[:, -1].sum()
    class_words[-1] = 1
    return model, placed


_SCORED = "doc_id bigint, n_tokens bigint, n_known bigint, base double, score double, rest array<struct<before: int, after: int, words: array<struct<word: binary, unseen: int>>>>"


def _score(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m: Model = shared.value
        trained = m.total > 0
        for batch in batches:
            for i, j, tokens in _split(batch):
                n = j - i
                codes, distinct, first = factorize(tokens.hashes())
                inside, c, k = m.look_up(distinct)
                unseen = m.unseen[rare_class(tokens, first)]
                settled = inside | m.complete
                k = np.where(inside, k, unseen)
                base = np.where(settled, m.base(c), 0.0)[codes]
                word = np.where(settled, m.emission(c, k), 0.0)[codes]
                docs = tokens.docs()
                sequence = _sequence(tokens, np.where(settled, k, -1)[codes], m.end_class)
                a, b = sequence[:-1], sequence[1:]
                move = np.where((a >= 0) & (b >= 0), m.transitions[a, b], 0.0)
                owner = np.repeat(np.arange(n), tokens.counts + 1)
                end_count = m.class_tokens[m.end_class]
                base_sum = np.bincount(docs, base, minlength=n) + m.base(np.array(end_count))
                score = np.bincount(docs, word, minlength=n) + np.bincount(owner, move, minlength=n)
                known = np.bincount(docs, (c > 0)[codes], minlength=n).astype(np.int64) + trained
                at, which, cuts = _runs(tokens, sequence)
                begins = cuts[:-1]
                words = pa.StructArray.from_arrays([tokens.words(which).cast(pa.binary()), pa.array(unseen[codes[which]].astype(np.int32))], ["word", "unseen"])
                around = [sequence[at[begins] - 1], sequence[at[cuts[1:] - 1] + 1]] if len(begins) else [at, at]
                runs = pa.StructArray.from_arrays([*(pa.array(x.astype(np.int32)) for x in around), pa.ListArray.from_arrays(pa.array(cuts.astype(np.int32)), words)], ["before", "after", "words"])
                lists = pa.ListArray.from_arrays(pa.array(np.searchsorted(docs[which[begins]], np.arange(n + 1)).astype(np.int32)), runs)
                yield pa.RecordBatch.from_arrays(
                    [rows_of(batch, "doc_id").slice(i, n), pa.array(tokens.counts + 1), pa.array(known), pa.array(base_sum), pa.array(score), lists],
                    ["doc_id", "n_tokens", "n_known", "base", "score", "rest"],
                )

    return run


def _score_runs(shared):
    """Runs of words with their counts and classes to the sums that a document lacks."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m: Model = shared.value
        for batch in batches:
            lists = rows_of(batch, "found")
            size = pc.list_value_length(lists).to_numpy(zero_copy_only=False).astype(np.int64)
            flat = lists.flatten()
            c, k = flat.field("c").to_numpy(), flat.field("k").to_numpy()
            n = batch.num_rows
            owner = np.repeat(np.arange(n), size)
            first = np.cumsum(size) - size
            before = np.empty(len(k), np.int64)
            before[1:] = k[:-1]
            before[first] = rows_of(batch, "before").to_numpy()
            more = np.bincount(owner, m.emission(c, k) + m.transitions[before, k], minlength=n) + m.transitions[k[first + size - 1], rows_of(batch, "after").to_numpy()]
            base, known = np.bincount(owner, m.base(c), minlength=n), np.bincount(owner, c > 0, minlength=n).astype(np.int64)
            yield pa.RecordBatch.from_arrays([rows_of(batch, "row"), pa.array(base), pa.array(more), pa.array(known)], ["row", "more_base", "more", "more_known"])

    return run


def score_documents(docs: DataFrame, exclude: str = HELD_OUT, head: int = HEAD) -> DataFrame:
    """doc_id, n_tokens, n_known, train_tokens, base_score, score and perplexity of every document."""
    spark = docs.sparkSession
    model, placed = fit(docs, exclude, head)
    shared = spark.sparkContext.broadcast(model)
    scored = docs.select("doc_id", "text").mapInArrow(_score(shared), _SCORED)
    if not model.complete:
        # Tokens beyond the head: their counts and classes come by a join. The stored rows give each document a lasting number.
        scored = stored(scored.withColumn("row", F.monotonically_increasing_id()), "scored")
        rest = scored.select("row", F.posexplode("rest").alias("run", "x")).select("row", "run", "x.before", "x.after", F.posexplode("x.words").alias("at", "w"))
        rest = rest.select("row", "run", "before", "after", "at", "w.word", "w.unseen").join(placed.select("word", "c", "k"), "word", "left")
        rest = rest.select("row", "run", "before", "after", F.struct("at", F.coalesce("c", F.lit(0)).alias("c"), F.coalesce("k", "unseen").alias("k")).alias("x"))
        runs = rest.groupBy("row", "run", "before", "after").agg(F.array_sort(F.collect_list("x")).alias("found"))
        sums = runs.select("row", "before", "after", "found").mapInArrow(_score_runs(shared), "row bigint, more_base double, more double, more_known bigint")
        sums = sums.groupBy("row").agg(*(F.sum(x).alias(x) for x in ("more_base", "more", "more_known")))
        scored = scored.join(sums, "row", "left").select(
            "doc_id", "n_tokens", (F.col("n_known") + F.coalesce("more_known", F.lit(0))).alias("n_known"),
            (F.col("base") + F.coalesce("more_base", F.lit(0.0))).alias("base"), (F.col("score") + F.coalesce("more", F.lit(0.0))).alias("score"),
        )
    return scored.select(
        "doc_id", "n_tokens", "n_known", F.lit(model.total).cast("long").alias("train_tokens"), F.col("base").alias("base_score"), "score", F.pow(F.lit(10.0), -F.col("score") / F.col("n_tokens")).alias("perplexity")
    )


def op3_language_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    scored = score_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return scored.select("doc_id", F.expr(HELD_OUT).alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")
