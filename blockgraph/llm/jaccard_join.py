"""Operator 5: exact Jaccard self-join of shingle sets through partition-and-enumerate signatures.

Sets of sizes a <= b with Jaccard similarity of p % or more differ in at most a(100 - p)/p elements. Sizes are cut into
bands, each twice as wide as the one before; a set takes part in its own band's instance and, where it may link with a set
of the next band, in that one's. An instance cuts the hashed feature domain into n1 ranges, each range into n2 = 2 cells,
and signs every choice of n2 - 1 cells of a range. There are half as many cells again as the sets of the band may have
differences, so linked sets agree in many of them: in all cells less the differences. Empty cells, which all sets would
share, are not signed, and a set counts them off what it needs; the rare set that would then need nothing signs them too.

Candidates: a signature that one set holds alone links nobody. A set that holds fewer shared signatures than it needs links
with nobody and goes. Of the rest, a set needs to meet others only over its rarest signatures, as many as it holds less
what it needs, plus one: linked sets share the rarest signature that they have in common, and for both it is one of those.
So a passage that many documents hold makes no candidates, unless a document holds little else.

Each holder of a signature is verified against the least holder (not against every other), on whole sets, and the
links are contracted to components. Where the other holders still lie in several components, they are compared with each
other exactly: dealt into blocks, every two blocks multiplied as 0/1 matrices. No link is lost on the way.

Defined cases: null and empty texts have no set and link with nothing; a text of fewer words than a shingle is one
shingle; rows that share a ``doc_id`` are one document; a row without ``doc_id`` has no component; only ``doc_id``
and the text are read, other columns are ignored whatever their names.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from functools import cache

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .links import connected
from .lossy import MOST_FILTERED, bitmap, held, id_bitmap
from .scratch import discard, stored
from .text import SPACED, Tokens, rows_of, slices, splitmix, utf8

WORDS, PERCENT = 4, 85
#: Documents of one block in the final step, and their elements: two blocks meet in a task.
BLOCK_DOCS, BLOCK_ELEMENTS = 512, 1 << 19
_STEP = np.uint64(0x9FB21C651E98DF25)


# Signatures


def _most_differences(size: int, percent: int) -> int:
    """Between a set of this size and any that it links with."""
    return size * (100 - percent) // percent


@cache
def instance(band: int, percent: int) -> tuple[int, int]:
    """n1 and n2 of the instance for sets of up to 2^(band + 1) - 1 elements."""
    need = _most_differences((2 << band) - 1, percent) + 1
    return need * 3 // 4 + 1, 2


def bands_of(size: int, percent: int) -> list[int]:
    """The band of a set, and the next one if sets that it may link with lie there."""
    own, last = size.bit_length() - 1, (size * 100 // percent).bit_length() - 1
    return [own] if own == last else [own, last]


@cache
def _edges(cells: int) -> np.ndarray:
    return np.array([(i << 64) // cells for i in range(1, cells)], np.uint64)


def signatures(elements: np.ndarray, percent: int = PERCENT) -> tuple[np.ndarray, np.ndarray]:
    """The signatures of a set, given as sorted distinct hashes; the lowest bit tells its instances apart.

    Also, beside each signature, how many of its instance a linked set shares at least.
    """
    most = _most_differences(len(elements), percent)
    sums = np.concatenate([[np.uint64(0)], np.cumsum(splitmix(elements), dtype=np.uint64)])
    out, least = [], []
    for band in bands_of(len(elements), percent):
        n1, n2 = instance(band, percent)
        cuts = np.concatenate([[0], np.searchsorted(elements, _edges(n1 * n2)), [len(elements)]])
        size = np.diff(cuts)
        signed = splitmix(splitmix((sums[cuts[1:]] - sums[cuts[:-1]]) ^ splitmix(size.astype(np.uint64))) + np.arange(n1 * n2, dtype=np.uint64) + np.uint64(band << 32))
        need = n1 * n2 - most - np.count_nonzero(size == 0)
        if need > 0:
            signed = signed[size > 0]
        out.append(signed & ~np.uint64(1) | np.uint64(band & 1))
        least.append(np.full(len(signed), max(1, need), np.int32))
    return np.concatenate(out), np.concatenate(least)


def shingle_sets(data: np.ndarray, offs: np.ndarray, words: int = WORDS) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of each text of a slice."""
    tokens = Tokens(data, offs, SPACED)
    h = tokens.hashes()
    shingles = np.zeros(max(0, len(h) - words + 1), np.uint64)
    for j in range(words):
        shingles = shingles * _STEP + h[j : j + len(shingles)]
    shingles = splitmix(shingles)
    out = []
    for a, b in zip(tokens.first[:-1].tolist(), tokens.first[1:].tolist(), strict=True):
        if b - a >= words:
            out.append(np.unique(shingles[a : b - words + 1]))
        elif b > a:
            whole = np.uint64(b - a)
            for x in h[a:b]:
                whole = np.uint64((int(whole) * int(_STEP) + int(x)) & (2**64 - 1))
            out.append(splitmix(np.array([whole], np.uint64)))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


def set_digest(elements: np.ndarray) -> tuple[int, int]:
    """128 bits that tell sets apart."""
    a, b = splitmix(elements), splitmix(elements ^ np.uint64(0xA5A5A5A5A5A5A5A5))
    return int(a.sum(dtype=np.uint64).astype(np.int64)), int((b.sum(dtype=np.uint64) + np.uint64(len(elements))).astype(np.int64))


_ROWS = "doc_id bigint, n_shingles bigint, d1 bigint, d2 bigint"


def _longs(parts: list[np.ndarray]) -> pa.Array:
    offs = np.concatenate([[0], np.cumsum([len(p) for p in parts])]).astype(np.int32)
    flat = np.concatenate(parts).view(np.int64) if parts else np.zeros(0, np.int64)
    return pa.ListArray.from_arrays(pa.array(offs), pa.array(flat))


def _sets(batch: pa.RecordBatch, words: int) -> Iterator[tuple[pa.Array, list[np.ndarray]]]:
    """The ids and sets of a batch, slice by slice."""
    data, offs = utf8(rows_of(batch, "text"))
    for i, j in slices(offs):
        yield rows_of(batch, "doc_id").slice(i, j - i), shingle_sets(data[offs[i] : offs[j]], offs[i : j + 1] - offs[i], words)


def _measure(words: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for ids, sets in _sets(batch, words):
                digests = [set_digest(s) for s in sets]
                numbers = [[len(s) for s in sets], [d[0] for d in digests], [d[1] for d in digests]]
                yield pa.RecordBatch.from_arrays([ids, *(pa.array(x, pa.int64()) for x in numbers)], ["doc_id", "n_shingles", "d1", "d2"])

    return run


def _sign(words: int, percent: int, kept=None):
    """Signatures alone; or, given a broadcast bitmap of those that may be shared, (a, sig, least) for these."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for ids, sets in _sets(batch, words):
                # Of equal sets, the one of the least document signs for all.
                signer: dict[tuple[int, int], tuple[int, int]] = {}
                for i, (key, s) in enumerate(zip(ids.to_pylist(), sets, strict=True)):
                    if key is not None and len(s):
                        digest = set_digest(s)
                        signer[digest] = min((key, i), signer.get(digest, (key, i)))
                keys, sigs, least = [np.zeros(0, np.int64)], [np.zeros(0, np.uint64)], [np.zeros(0, np.int32)]
                for key, i in signer.values():
                    signed, needed = signatures(sets[i], percent)
                    if kept is not None and kept.value is not None:
                        may = held(kept.value, signed)
                        signed, needed = signed[may], needed[may]
                    keys.append(np.full(len(signed), key))
                    sigs.append(signed)
                    least.append(needed)
                sig = pa.array(np.concatenate(sigs).view(np.int64))
                if kept is None:
                    yield pa.RecordBatch.from_arrays([sig], ["sig"])
                else:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(keys)), sig, pa.array(np.concatenate(least))], ["a", "sig", "least"])

    return run


# Candidates


def _met(rows: DataFrame) -> DataFrame:
    """The rows whose signature several documents hold, with their number n; a doc's rows lie together, so n counts documents."""
    several = stored(rows.groupBy("sig").agg(F.count("*").alias("n")).where("n > 1"), "several")
    return rows.join(several, "sig")


def _candidates(docs: DataFrame, spare: DataFrame, words: int, percent: int) -> DataFrame:
    """(a, sig): the documents that may link, with the signatures over which they meet. ``spare`` documents are left out."""
    context = docs.sparkSession.sparkContext
    alone = docs.mapInArrow(_sign(words, percent), "sig bigint").groupBy("sig").agg(F.count("*").alias("n"))
    shared = stored(alone.where("n > 1").select("sig"), "shared")
    n = shared.count()
    few = n <= MOST_FILTERED  # beyond, a join does the bitmap's work
    bits = context.broadcast(bitmap(shared, n) if few else None)
    rows = docs.mapInArrow(_sign(words, percent, bits), "a bigint, sig bigint, least int")
    rows = stored(rows if few else rows.join(shared, "sig", "left_semi").select("a", "sig", "least"), "signed")
    bits.unpersist()
    rows = rows.join(spare.select("a"), "a", "left_anti").groupBy("a", "sig").agg(F.min("least").alias("least"))
    of_a = W.partitionBy("a", F.expr("sig & 1"))
    rows = _met(stored(rows, "signed")).select("a", "sig", F.min("least").over(of_a).alias("least"), F.count("*").over(of_a).alias("shared"))
    rows = _met(stored(rows.where("shared >= least").drop("shared"), "signed"))
    rarest = rows.select("a", "sig", "least", F.count("*").over(of_a).alias("shared"), F.row_number().over(of_a.orderBy("n", "sig")).alias("place"))
    return stored(rarest.where("place <= shared - least + 1").select("a", "sig"), "candidates")


# Verification


def _fetch_sets(docs: DataFrame, ids: DataFrame, words: int) -> DataFrame:
    """(doc_id, elements) of the documents in ``ids``, and maybe of a few others."""
    shared = docs.sparkSession.sparkContext.broadcast(id_bitmap(ids))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            batch = batch.filter(pa.array(held(shared.value, rows_of(batch, "h").to_numpy(zero_copy_only=False))))
            for keys, sets in _sets(batch, words):
                yield pa.RecordBatch.from_arrays([keys, _longs(sets)], ["doc_id", "elements"])

    return docs.where("doc_id is not null").select("doc_id", "text", F.xxhash64("doc_id").alias("h")).mapInArrow(run, "doc_id bigint, elements array<bigint>")


def _linked(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose sets link."""
    left = sets.select(F.col("doc_id").alias("a"), F.col("elements").alias("x"))
    right = sets.select(F.col("doc_id").alias("b"), F.col("elements").alias("y"))
    same = F.size(F.array_intersect("x", "y"))
    return pairs.join(left, "a").join(right, "b").where((100 * same >= percent * (F.size("x") + F.size("y") - same)) & (F.size("x") > 0)).select("a", "b")


def block_links(sets: list[np.ndarray], component: np.ndarray, percent: int) -> list[tuple[int, int]]:
    """Links between different components among these sets, as many as are needed to join what they join."""
    n = len(sets)
    size = np.array([len(s) for s in sets])
    flat = np.concatenate([np.zeros(0, np.int64), *sets])
    owner = np.repeat(np.arange(n), size)
    codes, distinct = pd.factorize(flat)
    shared = np.bincount(codes, minlength=len(distinct)) > 1
    number = np.cumsum(shared) - 1
    keep = shared[codes]
    owner, column = owner[keep], number[codes[keep]]
    common = np.zeros((n, n), np.float32)
    order = np.argsort(column, kind="stable")
    owner, column = owner[order], column[order]
    for low in range(0, int(column[-1]) + 1 if len(column) else 0, 4096):
        a, b = np.searchsorted(column, [low, low + 4096])
        part = np.zeros((n, 4096), np.float32)
        part[owner[a:b], column[a:b] - low] = 1
        common += part @ part.T
    whole = common.astype(np.int64)
    good = (100 * whole >= percent * (size[:, None] + size[None, :] - whole)) & (component[:, None] != component[None, :]) & (whole > 0)
    root = {c: c for c in component.tolist()}

    def find(c):
        while root[c] != c:
            root[c] = root[root[c]]
            c = root[c]
        return c

    out = []
    for i, j in zip(*np.nonzero(np.triu(good, 1)), strict=True):
        a, b = find(component[i].item()), find(component[j].item())
        if a != b:
            root[max(a, b)] = min(a, b)
            out.append((int(i), int(j)))
    return out


def _settle(percent: int):
    def run(group: pd.DataFrame) -> pd.DataFrame:
        found = block_links([np.asarray(x, np.int64) for x in group["elements"]], group["component"].to_numpy(), percent)
        ids = group["doc_id"].to_numpy()
        return pd.DataFrame({"a": [ids[i] for i, _ in found], "b": [ids[j] for _, j in found]}, dtype=np.int64)

    return run


def _open_links(prefix: DataFrame, pivots: DataFrame, components: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Links between holders of a signature, its least one left out, that still lie in several components."""
    others = prefix.join(pivots.where("n > 2"), "sig").where("a <> b").select("sig", "a")
    others = others.join(components.withColumnRenamed("node", "a"), "a", "left").withColumn("component", F.coalesce("component", "a"))
    others = stored(others, "others")
    apart = others.groupBy("sig").agg(F.min("component").alias("low"), F.max("component").alias("high"), F.min("a").alias("head"))
    open_ = stored(others.join(stored(apart.where("low < high").select("sig", "head"), "open"), "sig").select("a", "head", "component").distinct(), "open")
    # Holders that meet over any open signature form one cluster, so a set is sent out once per block of its cluster.
    clusters = stored(connected(open_, "a", "head"), "clusters").withColumnRenamed("node", "a").withColumnRenamed("component", "cluster")
    size = sets.groupBy(F.col("doc_id").alias("a")).agg(F.sum(F.size("elements")).alias("elements"))
    members = open_.select("a", "component").distinct().join(clusters, "a").join(size, "a")
    members = stored(members, "members")
    blocks = F.greatest(F.ceil(F.count("*") / BLOCK_DOCS), F.ceil(F.sum("elements") / BLOCK_ELEMENTS)).alias("blocks")
    members = members.join(stored(members.groupBy("cluster").agg(blocks), "blocks"), "cluster").withColumn("block", F.pmod(F.xxhash64("a"), "blocks"))
    dealt = members.withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)))
    dealt = dealt.select(F.col("a").alias("doc_id"), "component", "cluster", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"))
    return stored(dealt.join(sets, "doc_id").groupBy("cluster", "i", "j").applyInPandas(_settle(percent), "a bigint, b bigint"), "crossing")


def jaccard_components(docs: DataFrame, words: int = WORDS, percent: int = PERCENT) -> DataFrame:
    """doc_id, n_shingles and component_id (the least document reachable over links) for every row of ``docs``."""
    if not 50 < percent <= 100:
        raise ValueError(f"a similarity of {percent} %; bands need more than 50")
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    rows = stored(docs.mapInArrow(_measure(words), _ROWS), "sets")

    # Equal sets: the least document stands for all whose only set it is.
    filled = rows.where("n_shingles > 0 and doc_id is not null")
    first = stored(filled.groupBy("d1", "d2", "n_shingles").agg(F.min("doc_id").alias("first"), F.count("*").alias("n")).where("n > 1").drop("n"), "copies")
    found = stored(filled.join(first, ["d1", "d2", "n_shingles"], "left").select(F.col("doc_id").alias("a"), F.coalesce("first", "doc_id").alias("b")), "copies")
    spare = stored(found.groupBy("a").agg(F.count("*").alias("n"), F.min("b").alias("b")).where("n = 1 and a <> b").select("a", "b"), "spare")
    copies = found.where("a <> b").join(spare.select("a"), "a", "left_anti")

    prefix = _candidates(docs, spare, words, percent)
    pivots = stored(prefix.groupBy("sig").agg(F.min("a").alias("b"), F.count("*").alias("n")).where("n > 1"), "pivots")
    pairs = stored(prefix.join(pivots, "sig").where("a <> b").select("a", "b").distinct(), "pairs")
    sets = _sets_of(docs, pairs, words)
    links = stored(_linked(pairs, sets, percent).unionByName(copies), "found")
    components = stored(connected(links), "components")
    crossing = _open_links(prefix, pivots, components, sets, percent)
    if not crossing.isEmpty():
        components = stored(connected(links.unionByName(crossing)), "components")
    for table in (prefix, pairs, sets):
        discard(table)
    copied = spare.join(components, spare.b == components.node, "left").select(F.col("a").alias("node"), F.coalesce("component", "b").alias("component"))
    labels = components.unionByName(copied)
    return rows.join(labels, rows.doc_id == labels.node, "left").select("doc_id", "n_shingles", F.coalesce("component", "doc_id").alias("component_id"))


def _sets_of(docs: DataFrame, pairs: DataFrame, words: int) -> DataFrame:
    ids = pairs.select(F.col("a").alias("doc_id")).unionByName(pairs.select(F.col("b").alias("doc_id"))).distinct()
    return stored(_fetch_sets(docs, ids, words), "elements")


def keep_least(docs: DataFrame, words: int = WORDS, percent: int = PERCENT) -> DataFrame:
    """The least document of every component, and all rows without a ``doc_id``. Of rows that share a ``doc_id``, one with the least text stays.

    Only rows that may have to go are dealt out by id; the texts of all others stay where they are. All columns stay, whatever their names.
    """
    found = jaccard_components(docs, words, percent)
    gone = stored(found.where("doc_id <> component_id").select("doc_id").distinct(), "gone")
    repeated = found.groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1 and doc_id is not null").select("doc_id")
    repeated = stored(repeated.join(gone, "doc_id", "left_anti"), "repeated")
    bits = docs.sparkSession.sparkContext.broadcast(id_bitmap(gone.unionByName(repeated)))
    flag, place = f"maybe_{uuid.uuid4().hex}", f"place_{uuid.uuid4().hex}"

    @F.pandas_udf("boolean")
    def maybe(h: pd.Series) -> pd.Series:
        return pd.Series(held(bits.value, h.to_numpy()))

    flagged = docs.withColumn(flag, maybe(F.xxhash64("doc_id")) & F.col("doc_id").isNotNull())
    sure = flagged.where(~F.col(flag)).drop(flag)
    rest = flagged.where(flag).drop(flag).join(gone, "doc_id", "left_anti").select(*docs.columns)
    order = W.partitionBy("doc_id").orderBy("text")
    several = rest.join(repeated, "doc_id", "left_semi").withColumn(place, F.row_number().over(order)).where(F.col(place) == 1).drop(place)
    return sure.unionByName(rest.join(repeated, "doc_id", "left_anti")).unionByName(several.select(*docs.columns))


def op5_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_components(spark.read.parquet(f"{sf_dir}/documents.parquet"))
