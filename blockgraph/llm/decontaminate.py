"""Operator 1: benchmark decontamination.

The n-gram windows of all benchmark items are hashed into one set. The set is broadcast while it holds at most
``MAX_WINDOWS`` windows; a larger benchmark is dealt into several such sets, scanned one after another over
the same batch, so the broadcast never outgrows its bound. Each task tokenises whole texts, probes a bitmap
with every window hash, and compares the words of every hash hit with those of the item before it counts.

Defined cases: a null text has no words; a benchmark row without words has no windows; one whose ``item_id`` is
null marks words but is not listed as an item; repeated items and documents are treated one by one; columns
of the documents that are not used pass through untouched, whatever their names. An empty benchmark leaves all
documents clean.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .text import ALNUM, Tokens, rows_of, slices, splitmix, utf8

WINDOW = 10
#: Most windows in one broadcast set, about 60 MB of Python objects.
MAX_WINDOWS = 500_000
_STEP = np.uint64(0xD6E8FEB86659FD93)
_BITS = 24


class WindowSet:
    """Windows of benchmark items: text of the window -> the items that hold it, probed through hashes."""

    def __init__(self, size: int = WINDOW):
        self.size = size
        self.items: dict[bytes, set] = {}
        self.hashes: dict[int, np.ndarray] = {}
        self.bitmap: np.ndarray | None = None

    def add(self, item_id, words: list[bytes]) -> None:
        span = min(self.size, len(words))
        for i in range(len(words) - span + 1 if words else 0):
            self.items.setdefault(b" ".join(words[i : i + span]), set()).add(item_id)

    def seal(self) -> WindowSet:
        """Compute the hashes by length of window."""
        by_length: dict[int, list[int]] = {}
        texts = list(self.items)
        if texts:
            offs = np.concatenate([[0], np.cumsum([len(t) for t in texts])])
            tokens = Tokens(np.frombuffer(b"".join(texts), np.uint8), offs, ALNUM)
            rolled = {n: h for n, h in window_hashes(tokens.hashes(), set(tokens.counts.tolist()))}
            for d, n in enumerate(tokens.counts):
                by_length.setdefault(int(n), []).append(int(rolled[int(n)][tokens.first[d]]))
        self.hashes = {n: np.unique(np.array(h, np.uint64)) for n, h in by_length.items()}
        self.bitmap = np.zeros(1 << _BITS, bool)
        for h in self.hashes.values():
            self.bitmap[h >> np.uint64(64 - _BITS)] = True
        return self


def window_hashes(tokens: np.ndarray, lengths: set[int]) -> Iterator[tuple[int, np.ndarray]]:
    """For each length, the hash of the window that starts at each token (those that would run over the end are left out)."""
    total = np.zeros(len(tokens), np.uint64)
    factor = np.uint64(1)
    for j in range(max(lengths, default=0)):
        if len(tokens) <= j:
            yield from ((n, np.zeros(0, np.uint64)) for n in lengths if n > j)
            return
        total = total[: len(tokens) - j] + tokens[j:] * factor
        factor = np.uint64((int(factor) * int(_STEP)) & (2**64 - 1))
        if j + 1 in lengths:
            yield j + 1, splitmix(total)


_WORDS_ONLY = bytes(int(ALNUM.lower[b]) if ALNUM.word[b] else 32 for b in range(256))


def plain_words(text: str | None) -> list[bytes]:
    """The words of one text, in pure Python."""
    return (text or "").encode().translate(_WORDS_ONLY).split()


def scan(data: np.ndarray, offs: np.ndarray, sets: list[WindowSet]) -> dict[str, list]:
    """Hits in a slice of texts: per text the words, hit words, items, and the byte spans of hit words."""
    tokens = Tokens(data, offs, ALNUM)
    n = len(offs) - 1
    marks = np.zeros(len(tokens) + 1, np.int64)
    found: dict[int, set] = {}
    doc_of = None
    hashes = tokens.hashes()
    last = tokens.first[1:]
    raw = data.tobytes() if len(tokens) else b""
    for windows in sets:
        for length, rolled in window_hashes(hashes, set(windows.hashes)):
            maybe = np.flatnonzero(windows.bitmap[rolled >> np.uint64(64 - _BITS)])
            if not len(maybe):
                continue
            maybe = maybe[np.isin(rolled[maybe], windows.hashes[length])]
            if doc_of is None:
                doc_of = tokens.docs()
            maybe = maybe[maybe + length <= last[doc_of[maybe]]]
            for k in maybe.tolist():
                span = raw[tokens.starts[k] : tokens.ends[k + length - 1]].translate(_WORDS_ONLY)
                items = windows.items.get(b" ".join(span.split()))
                if items is not None:
                    marks[k] += 1
                    marks[k + length] -= 1
                    found.setdefault(int(doc_of[k]), set()).update(items)
    hit = np.cumsum(marks[:-1]) > 0
    sums = np.concatenate([[0], np.cumsum(hit)])
    n_hit = sums[tokens.first[1:]] - sums[tokens.first[:-1]]
    spans: list[list[tuple[int, int]]] = [[] for _ in range(n)]
    for d in np.flatnonzero(n_hit).tolist():
        a, b = tokens.first[d], tokens.first[d + 1]
        inside = np.concatenate([[False], hit[a:b], [False]])
        edges = np.flatnonzero(inside[1:] != inside[:-1])
        spans[d] = [(int(tokens.starts[a + x] - offs[d]), int(tokens.ends[a + y - 1] - offs[d])) for x, y in zip(edges[::2], edges[1::2], strict=True)]
    return {
        "n_words": tokens.counts.tolist(),
        "n_hit": n_hit.tolist(),
        "items": [sorted(str(x) for x in found.get(d, ()) if x is not None) for d in range(n)],
        "spans": spans,
    }


def window_sets(benchmark: DataFrame, size: int = WINDOW) -> list[WindowSet]:
    """The benchmark's windows in sets of at most ``MAX_WINDOWS``, built while items stream to the driver."""
    sets = [WindowSet(size)]
    for row in benchmark.select("item_id", "text").where("text is not null").toLocalIterator():
        if len(sets[-1].items) >= MAX_WINDOWS:
            sets.append(WindowSet(size))
        sets[-1].add(row.item_id, plain_words(row.text))
    return [s.seal() for s in sets if s.items]


def find_contamination(docs: DataFrame, benchmark: DataFrame, size: int = WINDOW, column: str = "contamination") -> DataFrame:
    """All columns of ``docs`` plus ``column`` (replaced if it is there): struct(n_words, n_hit, items, spans). Spans are byte ranges of hit words."""
    spark = docs.sparkSession
    sets = spark.sparkContext.broadcast(window_sets(benchmark, size))
    schema = "struct<n_words: bigint, n_hit: bigint, items: array<string>, spans: array<struct<begin: bigint, end: bigint>>>"

    @F.pandas_udf(schema)
    def report(texts: pd.Series) -> pd.DataFrame:
        data, offs = utf8(pa.array(texts, pa.large_string(), from_pandas=True))
        parts: dict[str, list] = {"n_words": [], "n_hit": [], "items": [], "spans": []}
        for i, j in slices(offs):
            for k, v in scan(data[offs[i] : offs[j]], offs[i : j + 1] - offs[i], sets.value).items():
                parts[k].extend(v)
        parts["spans"] = [[{"begin": a, "end": b} for a, b in s] for s in parts["spans"]]
        return pd.DataFrame(parts)

    return docs.withColumn(column, report("text"))


def contamination_report(docs: DataFrame, benchmark: DataFrame, size: int = WINDOW) -> DataFrame:
    """Per document: doc_id, n_words, n_hit, items (sorted as strings). Reads and moves the text only."""
    spark = docs.sparkSession
    sets = spark.sparkContext.broadcast(window_sets(benchmark, size))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offs = utf8(rows_of(batch, "text"))
            for i, j in slices(offs):
                found = scan(data[offs[i] : offs[j]], offs[i : j + 1] - offs[i], sets.value)
                yield pa.RecordBatch.from_arrays(
                    [rows_of(batch, "doc_id").slice(i, j - i), pa.array(found["n_words"], pa.int64()), pa.array(found["n_hit"], pa.int64()), pa.array(found["items"], pa.list_(pa.string()))],
                    ["doc_id", "n_words", "n_hit", "items"],
                )

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id bigint, n_words bigint, n_hit bigint, items array<string>")


def decontaminate(docs: DataFrame, benchmark: DataFrame, mode: str = "documents", size: int = WINDOW) -> DataFrame:
    """``documents``: drop every document with a hit. ``spans``: cut the hit words out of the texts, with what stands between them."""
    if mode not in ("documents", "spans"):
        raise ValueError(f"unknown mode {mode!r}")
    marks = f"marks_{uuid.uuid4().hex}"
    found = find_contamination(docs, benchmark, size, marks)
    if mode == "documents":
        return found.where(F.col(marks)["n_hit"] == 0).drop(marks)

    @F.pandas_udf("string")
    def cut(texts: pd.Series, spans: pd.Series) -> pd.Series:
        out = []
        for text, cuts in zip(texts, spans, strict=True):
            if text is not None and len(cuts):
                raw, at, kept = text.encode(), 0, []
                for c in cuts:
                    kept.append(raw[at : c["begin"]])
                    at = c["end"]
                text = b"".join([*kept, raw[at:]]).decode()
            out.append(text)
        return pd.Series(out, dtype=object)

    return found.withColumn("text", cut("text", F.col(marks)["spans"])).drop(marks)


def op1_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    benchmark = spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    found = contamination_report(docs, benchmark)
    return found.select(
        "doc_id",
        "n_words",
        "n_hit",
        F.size("items").cast("long").alias("n_items"),
        F.sha2(F.concat_ws(",", "items").cast("binary"), 256).alias("items_sha256"),
        (F.col("n_hit") > 0).alias("contaminated"),
    )


ORACLE = r"""
WITH pieces AS (
  SELECT item_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w
  FROM benchmark WHERE text IS NOT NULL),
windows AS (
  SELECT DISTINCT item_id, least(10, len(w)) AS span, array_to_string(w[i : i + least(10, len(w)) - 1], ' ') AS win
  FROM (SELECT item_id, w, unnest(generate_series(1, greatest(1, len(w) - 9))) AS i FROM pieces WHERE len(w) > 0)),
docs AS (
  SELECT row_number() OVER () AS r, doc_id,
         regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w
  FROM documents),
spans AS (SELECT DISTINCT span FROM windows),
hits AS (
  SELECT d.r, d.i, d.span, b.item_id
  FROM (SELECT r, span, i, array_to_string(w[i : i + span - 1], ' ') AS win
        FROM (SELECT r, w, span, unnest(generate_series(1, len(w) - span + 1)) AS i FROM docs, spans WHERE len(w) >= span)) d
  JOIN windows b ON b.span = d.span AND b.win = d.win),
words AS (SELECT r, count(DISTINCT p) AS n FROM (SELECT r, unnest(generate_series(i, i + span - 1)) AS p FROM hits) GROUP BY r),
items AS (SELECT r, count(DISTINCT item_id) AS n, string_agg(DISTINCT item_id::VARCHAR, ',' ORDER BY item_id::VARCHAR) AS ids FROM hits GROUP BY r)
SELECT d.doc_id, len(d.w)::BIGINT AS n_words, coalesce(w.n, 0)::BIGINT AS n_hit, coalesce(i.n, 0)::BIGINT AS n_items,
       sha256(coalesce(i.ids, '')) AS items_sha256, coalesce(w.n, 0) > 0 AS contaminated
FROM docs d LEFT JOIN words w USING (r) LEFT JOIN items i USING (r)
"""
