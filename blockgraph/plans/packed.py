"""Edges packed into blocks of two vertex colours, and a task for every three colours.

Vertices are coloured by a hash, so that hubs' neighbours spread. An edge is shuffled and stored once, a few bytes long, in the block of its two
colours; a task then reads the three blocks of its colours from the store, whatever number of tasks shares a block. What a task holds
falls with the square of the number of colours, which follows the number of edges; wedges exist in a kernel only, a part at a time.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from itertools import combinations, combinations_with_replacement, permutations, product

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .store import drop, fresh_path, side_by_side, stored

#: Edges that a task holds, about; edges that are packed at a time; wedges that a kernel holds at a time.
TASK_EDGES = 4_000_000
CHUNK = 1 << 20
WEDGES = 1 << 17
#: Edges that a task of cliques holds, about; wedges, and cells of its tables and of its rows of bits, that its kernel holds at a time.
CLIQUE_EDGES = 8_000_000
CLIQUE_CELLS = 1 << 23
#: Lists planned in one job.
LISTS_PER_JOB = 256
#: From this many edges on, wedges are no longer shuffled.
MANY_EDGES = 200_000
_FILTER_BITS = 25


def colour(ids: np.ndarray, p: int) -> np.ndarray:
    h = ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    return ((h >> np.uint64(33)) % np.uint64(p)).astype(np.int64)


def _squeeze(values: np.ndarray) -> bytes:
    """Whole numbers, byte by byte of their distance from the least one, compressed."""
    low = int(values.min())
    # Distances wrap to the right unsigned value even where they pass 2^63.
    gaps = (values.view(np.uint64) - np.int64(low).view(np.uint64)).astype("<u8")
    wide = max(1, (int(gaps.max()).bit_length() + 7) // 8)
    planes = np.ascontiguousarray(gaps.view(np.uint8).reshape(-1, 8)[:, :wide].T)
    head = np.array([low, len(values), wide], "<i8").tobytes()
    return head + pa.compress(planes.tobytes(), codec="zstd", asbytes=True)


def _spread(data: bytes) -> np.ndarray:
    low, n, wide = (int(x) for x in np.frombuffer(data, "<i8", 3))
    planes = np.frombuffer(pa.decompress(data[24:], decompressed_size=n * wide, codec="zstd", asbytes=True), np.uint8).reshape(wide, n)
    out = np.zeros((n, 8), np.uint8)
    out[:, :wide] = planes.T
    return (out.reshape(-1).view("<u8") + np.int64(low).view(np.uint64)).view(np.int64)


def _pack(p: int) -> Callable:
    def emit(parts: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        s, d = np.concatenate(parts, 1)
        cs, cd = colour(s, p), colour(d, p)
        turned = cs > cd
        s, d = np.where(turned, d, s), np.where(turned, s, d)
        block = np.minimum(cs, cd) * p + np.maximum(cs, cd)
        order = np.lexsort((d, s, block))
        s, d, block = s[order], d[order], block[order]
        starts = np.flatnonzero(np.concatenate([[True], block[1:] != block[:-1]]))
        ends = np.append(starts[1:], len(block))
        rows = [(int(block[a]), int(b - a), _squeeze(np.diff(s[a:b], prepend=0)), _squeeze(d[a:b])) for a, b in zip(starts, ends, strict=True)]
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(), pa.int64(), pa.binary(), pa.binary()), strict=True)], ["block", "n", "s", "d"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts, held = [], 0
        for batch in batches:
            if batch.num_rows:
                parts.append(np.stack([batch.column(k).to_numpy(zero_copy_only=False).astype(np.int64) for k in range(2)]))
                held += batch.num_rows
            if held >= CHUNK:
                yield from emit(parts)
                parts, held = [], 0
        if held:
            yield from emit(parts)

    return run


def _hits(u: np.ndarray, v: np.ndarray, x: np.ndarray, w: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """Of every edge (u, v) the common third ends w, given (x, w) for both of its ends: the end with fewer is walked, the other one looked up.
    Told are the edge's row, w, and the rows of (x, w) that were walked and looked up."""
    if not len(u) or not len(x):
        return
    order = np.lexsort((w, x))
    x, w = x[order], w[order]
    fresh = np.concatenate([[True], x[1:] != x[:-1]])
    low, names = np.flatnonzero(fresh), x[fresh]
    n = np.diff(np.append(low, len(x)))
    ends, at_w = np.unique(w, return_inverse=True)
    closing = (np.cumsum(fresh) - 1) * len(ends) + at_w
    at_w = at_w.astype(np.int32) if len(ends) < 1 << 31 else at_w
    mix = np.uint64(0x9E3779B97F4A7C15)
    place = lambda keys: (keys.view(np.uint64) * mix) >> np.uint64(64 - _FILTER_BITS)
    seen = np.zeros(1 << _FILTER_BITS, bool)
    seen[place(closing)] = True
    at = [np.minimum(np.searchsorted(names, e), len(names) - 1) for e in (u, v)]
    both = (names[at[0]] == u) & (names[at[1]] == v)
    here, a, b = np.flatnonzero(both), at[0][both], at[1][both]
    turned = n[a] > n[b]
    walk, look = np.where(turned, b, a), np.where(turned, a, b) * len(ends)
    upto, done = np.cumsum(n[walk]), 0
    while done < len(here):
        # An end with more wedges than fit is walked alone: it has no more than its list of third ends.
        end = max(done + 1, int(np.searchsorted(upto, (upto[done - 1] if done else 0) + WEDGES, "right")))
        k = n[walk[done:end]]
        row = np.repeat(np.arange(done, end), k)
        walked = np.arange(len(row)) + np.repeat(low[walk[done:end]] - (np.cumsum(k) - k), k)
        keys = look[row] + at_w[walked]
        maybe = np.flatnonzero(seen[place(keys)])
        keys = keys[maybe]
        found = np.minimum(np.searchsorted(closing, keys), len(closing) - 1)
        same = closing[found] == keys
        maybe, found = maybe[same], found[same]
        yield here[row[maybe]], ends[at_w[walked[maybe]]], order[walked[maybe]], order[found]
        done = end


def _closed(u: np.ndarray, v: np.ndarray, x: np.ndarray, w: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """The triangles (u, v, w) of the edges (u, v), given (x, w) for both of their ends."""
    for row, third, _, _ in _hits(u, v, x, w):
        yield u[row], v[row], third


def _of_list(blocks: dict[int, tuple[np.ndarray, np.ndarray]], colours: tuple[int, int, int], p: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """The triangles whose corners have these three colours, in rising order, each once."""
    none = (np.zeros(0, np.int64),) * 2
    i, j, h = colours
    get = lambda a, b: blocks.get(a * p + b, none)
    if i == j == h:
        s, d = get(i, i)
        names, k, deg = np.unique(np.concatenate([s, d]), return_inverse=True, return_counts=True)
        a, b = k[: len(s)], k[len(s) :]
        up = (deg[a] < deg[b]) | ((deg[a] == deg[b]) & (s < d))
        s, d = np.where(up, s, d), np.where(up, d, s)
        yield from _closed(s, d, s, d)
    elif i == j:
        yield from _closed(*get(i, i), *get(i, h))
    elif j == h:
        yield from _closed(*get(j, j), *get(i, j)[::-1])
    else:
        xs, ws = zip(get(i, h), get(j, h), strict=True)
        yield from _closed(*get(i, j), np.concatenate(xs), np.concatenate(ws))


def count_all(found: Iterator) -> Iterator[pa.RecordBatch]:
    yield pa.RecordBatch.from_arrays([pa.array([sum(len(u) for u, _, _ in found)], pa.int64())], ["n"])


def count_corners(found: Iterator) -> Iterator[pa.RecordBatch]:
    """(id, n): triangles of the list at each corner."""
    ids, n, parts, held = np.zeros(0, np.int64), np.zeros(0, np.int64), [], 0

    def merged():
        names, at = np.unique(np.concatenate([ids, *parts]), return_inverse=True)
        weights = np.concatenate([n, np.ones(len(at) - len(n), np.int64)])
        return names, np.bincount(at, weights, len(names)).astype(np.int64)

    for three in found:
        parts += three
        held += 3 * len(three[0])
        if held > CHUNK:
            (ids, n), parts, held = merged(), [], 0
    if parts:
        ids, n = merged()
    for at in range(0, len(ids), CHUNK):
        yield pa.RecordBatch.from_arrays([pa.array(ids[at : at + CHUNK]), pa.array(n[at : at + CHUNK])], ["id", "n"])


def packed_blocks(edges: DataFrame, p: int) -> tuple[str, set[int]]:
    """Where the packed blocks of ``p`` colours are stored, and which of them have edges."""
    spark = edges.sparkSession
    path = fresh_path(spark, "packed")
    rows = edges.select(F.col("src").cast("long"), F.col("dst").cast("long")).mapInArrow(_pack(p), "block long, n long, s binary, d binary")
    rows.repartition(p * (p + 1) // 2, "block").withColumn("part", F.col("block")).write.partitionBy("part").parquet(path)
    return path, {r.block for r in spark.read.schema("block long").parquet(path).distinct().collect()}


def _unpacked(parts: list[tuple[bytes, ...]]) -> tuple[np.ndarray, np.ndarray]:
    """Both ends of the edges of a block's parts."""
    both = [(np.cumsum(_spread(s)), _spread(d)) for s, d in parts]
    return tuple(np.concatenate([x[k] for x in both]) for k in range(2)) if both else (np.zeros(0, np.int64),) * 2


def over_lists(spark: SparkSession, path: str, lists: list[tuple], kernel: Callable, schema: str) -> DataFrame:
    """The rows that ``kernel(key, parts by block)`` makes of every list (key, blocks): a task a list, which reads its blocks from the store."""

    def task(key) -> Callable:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held: dict[int, list] = {}
            for batch in batches:
                for block, s, d in zip(*(batch.column(c) for c in ("block", "s", "d")), strict=True):
                    held.setdefault(block.as_py(), []).append((s.as_py(), d.as_py()))
            yield from kernel(key, held)

        return run

    out = spark.createDataFrame([], schema)
    for first in range(0, len(lists), LISTS_PER_JOB):
        read = lambda need: spark.read.schema("block long, n long, s binary, d binary").parquet(*(f"{path}/part={b}" for b in need))
        job = [read(need).coalesce(1).mapInArrow(task(key), schema) for key, need in lists[first : first + LISTS_PER_JOB]]
        out = out.unionAll(stored(side_by_side(job), "of-lists"))
    # Every list's rows are stored by now.
    drop(spark, path)
    return out


def over_triangles(edges: DataFrame, reduce: Callable, schema: str, p: int | None = None) -> DataFrame:
    """The rows that ``reduce`` makes of the triangles of every list, over a graph (src, dst) without loops and repeated edges in either direction."""
    if p is None:
        p = max(1, int(np.ceil(np.sqrt(6 * edges.count() / TASK_EDGES))))
    path, here = packed_blocks(edges, p)
    lists = []
    for three in combinations_with_replacement(range(p), 3):
        i, j, h = three
        need = {i * p + j, i * p + h, j * p + h}
        if need <= here:
            lists.append((three, sorted(need)))

    def kernel(three: tuple[int, int, int], held: dict[int, list]) -> Iterator[pa.RecordBatch]:
        yield from reduce(_of_list({block: _unpacked(held.pop(block)) for block in list(held)}, three, p))

    return over_lists(edges.sparkSession, path, lists, kernel, schema)


def _by_degree(held: dict[int, list], p: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of the edges of a list's blocks, between places in the order of their degrees: where each place's later neighbours begin, these
    neighbours, and the colours of the places."""
    parts = [part for block in list(held) for part in held.pop(block)]
    seen, known = [np.zeros(0, np.int64)], 0
    for part in parts:
        seen += [np.unique(x) for x in _unpacked([part])]
        known += len(seen[-1]) + len(seen[-2])
        if known > CHUNK:
            seen, known = [np.unique(np.concatenate(seen))], 0
    names = np.unique(np.concatenate(seen))
    del seen
    ends = [np.stack([np.searchsorted(names, x).astype(np.int32) for x in _unpacked([parts.pop()])]) for _ in range(len(parts))]
    n = len(names)
    degree = np.zeros(n, np.int64)
    for e in ends:
        degree += np.bincount(e.reshape(-1), minlength=n)
    order = np.lexsort((names, degree))
    rank = np.empty(n, np.int64)
    rank[order] = np.arange(n)
    keys = np.concatenate([(x := rank[e]).min(0) * n + x.max(0) for e in ends])
    del ends
    keys.sort()
    return np.searchsorted(keys, np.arange(n + 1) * n), (keys % n).astype(np.int32), colour(names[order], p)


def _cliques4(held: dict[int, list], colours: tuple[int, ...], p: int) -> int:
    """The cliques of four whose corners have these colours, in any order.

    Places are taken in the order of degrees, as many at a time as fit. Among the later neighbours of a place, each is given the row of bits of
    those after it that it is linked with; two linked ones then close as many cliques as their rows share bits of the colour that is left."""
    low, nbrs, tint = _by_degree(held, p)
    n, out = len(low) - 1, np.diff(low)
    kinds = sorted(set(colours))
    tint = np.searchsorted(kinds, tint)
    # The colour that three corners leave, -1 where the list has no such clique.
    left = np.full((len(kinds),) * 3, -1)
    for four in set(permutations(np.searchsorted(kinds, colours).tolist())):
        left[four[:3]] = four[3]
    # Wedges up to each place, and something for its edges.
    reach = np.concatenate([[0], np.cumsum(out[nbrs])])[low] + 8 * low
    most = max(1, CLIQUE_CELLS // max(n, 1))
    table = np.full(min(most, n) * n, -1, np.int32)
    first, total = 0, 0
    while first < n:
        end = max(first + 1, min(first + most, int(np.searchsorted(reach, reach[first] + CLIQUE_CELLS // 64, "right")) - 1))
        width = lambda: -(-int(out[first:end].max()) // 64) * 64  # noqa: B023, E731
        while end > first + 1 and (low[end] - low[first]) * width() > CLIQUE_CELLS:
            end = first + (end - first) // 2
        begin, wide = low[first], width()
        b = nbrs[begin : low[end]]
        owner = np.repeat(np.arange(end - first), out[first:end])
        if wide and len(b) > 2:
            base = low[first:end] - begin
            cells = owner * n + b
            table[cells] = np.arange(len(b)) - base[owner]
            linked = np.zeros((len(b), wide), bool)
            for rows in _runs(out[b], CLIQUE_CELLS // 8):
                k = out[b[rows]]
                row = np.repeat(np.arange(rows.start, rows.stop), k)
                w = nbrs[np.arange(len(row)) + np.repeat(low[b[rows]] - (np.cumsum(k) - k), k)]
                place = table[np.repeat(owner[rows] * n, k) + w]
                hit = np.flatnonzero(place >= 0)
                linked[row[hit], place[hit]] = True
            table[cells] = -1
            bits = np.packbits(linked, axis=1).view(np.uint64)
            if len(kinds) > 1:
                mine = np.zeros(((end - first) * len(kinds), wide), bool)
                mine[owner * len(kinds) + tint[b], np.arange(len(b)) - base[owner]] = True
                mine = np.packbits(mine, axis=1).view(np.uint64)
            for rows in _runs(np.full(len(b), wide), CLIQUE_CELLS // 8):
                x, at = np.nonzero(linked[rows])
                x = x + rows.start
                y = base[owner[x]] + at
                if len(kinds) > 1:
                    fourth = left[tint[first + owner[x]], tint[b[x]], tint[b[y]]]
                    x, y, fourth = (z[fourth >= 0] for z in (x, y, fourth))
                for pairs in _runs(np.full(len(x), wide // 64), CLIQUE_CELLS // 64):
                    shared = bits[x[pairs]] & bits[y[pairs]]
                    if len(kinds) > 1:
                        shared &= mine[owner[x[pairs]] * len(kinds) + fourth[pairs]]
                    total += int(np.bitwise_count(shared).sum(dtype=np.int64))
        first = end
    return total


def _runs(costs: np.ndarray, most: int) -> Iterator[slice]:
    """Runs of rows that cost ``most`` together at most, or one row that costs more."""
    upto, done = np.cumsum(costs), 0
    while done < len(costs):
        end = max(done + 1, int(np.searchsorted(upto, (upto[done - 1] if done else 0) + most, "right")))
        yield slice(done, end)
        done = end


def clique4_count(edges: DataFrame, p: int | None = None) -> DataFrame:
    """One row (cliques) of four vertices, over a graph without loops and repeated edges: a task for every four colours."""
    if p is None:
        p = max(1, int(np.ceil(np.sqrt(12 * edges.count() / CLIQUE_EDGES))))
        # A few tasks at least, though one would do.
        p = max(p, 3)
    path, here = packed_blocks(edges, p)
    lists = []
    for four in combinations_with_replacement(range(p), 4):
        need = {a * p + b for a, b in combinations(four, 2)}
        if need <= here:
            lists.append((four, sorted(need)))

    def kernel(four: tuple[int, ...], held: dict[int, list]) -> Iterator[pa.RecordBatch]:
        yield pa.RecordBatch.from_arrays([pa.array([_cliques4(held, four, p)], pa.int64())], ["n"])

    counts = over_lists(edges.sparkSession, path, lists, kernel, "n long")
    return counts.agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("cliques"))


def supported(edges: DataFrame, least: int, p: int | None = None) -> DataFrame:
    """The edges (src < dst) that close ``least`` triangles or more. A task has the edges of one block and the blocks of their ends with every
    third colour, a colour at a time, so that no count leaves it; an edge with enough triangles is not walked again."""
    if p is None:
        p = max(1, int(np.ceil(np.sqrt(6 * edges.count() / TASK_EDGES))))
    path, here = packed_blocks(edges, p)
    lists = []
    for own in sorted(here):
        ends = {own // p, own % p}
        lists.append((own, sorted(b for b in here if {b // p, b % p} & ends)))

    def near(held: dict[int, list], c: int, h: int) -> tuple[np.ndarray, np.ndarray]:
        x, w = _unpacked(held.get(min(c, h) * p + max(c, h), []))
        return (np.concatenate([x, w]), np.concatenate([w, x])) if c == h else (x, w) if c < h else (w, x)

    def kernel(own: int, held: dict[int, list]) -> Iterator[pa.RecordBatch]:
        u, v = _unpacked(held.get(own, []))
        closed = np.zeros(len(u), np.int64)
        for h in range(p):
            open_ = np.flatnonzero(closed < least)
            if not len(open_):
                break
            xs, ws = zip(*(near(held, c, h) for c in {own // p, own % p}), strict=True)
            for row, *_ in _hits(u[open_], v[open_], np.concatenate(xs), np.concatenate(ws)):
                closed += np.bincount(open_[row], minlength=len(u)) if len(row) > len(u) // 8 else 0
                if len(row) <= len(u) // 8:
                    np.add.at(closed, open_[row], 1)
        kept = closed >= least
        u, v = u[kept], v[kept]
        for at in range(0, len(u), CHUNK):
            some = slice(at, at + CHUNK)
            yield pa.RecordBatch.from_arrays([pa.array(np.minimum(u[some], v[some])), pa.array(np.maximum(u[some], v[some]))], ["src", "dst"])

    return over_lists(edges.sparkSession, path, lists, kernel, "src long, dst long")


def _pack_entries(p: int, first: int) -> Callable:
    """Blocks of a matrix (row, col, val), numbered on from ``first`` by the colours of row and column; values lie behind the columns."""

    def emit(parts: list[tuple[np.ndarray, ...]]) -> Iterator[pa.RecordBatch]:
        r, c, val = (np.concatenate(x) for x in zip(*parts, strict=True))
        block = first + colour(r, p) * p + colour(c, p)
        order = np.lexsort((c, r, block))
        for mine in np.split(order, np.flatnonzero(np.diff(block[order])) + 1):
            cols = _squeeze(c[mine])
            row = int(block[mine[0]]), len(mine), _squeeze(np.diff(r[mine], prepend=0)), len(cols).to_bytes(8, "little") + cols + _squeeze(val[mine].view(np.int64))
            yield pa.RecordBatch.from_arrays([pa.array([x], t) for x, t in zip(row, (pa.int64(), pa.int64(), pa.binary(), pa.binary()), strict=True)], ["block", "n", "s", "d"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts, held = [], 0
        for batch in batches:
            if batch.num_rows:
                parts.append(tuple(batch.column(k).to_numpy(zero_copy_only=False) for k in range(3)))
                held += batch.num_rows
            if held >= CHUNK:
                yield from emit(parts)
                parts, held = [], 0
        if held:
            yield from emit(parts)

    return run


def _entries(parts: list[tuple[bytes, bytes]]) -> tuple[np.ndarray, ...]:
    """(row, col, val) of a block's parts."""
    out = []
    for s, d in parts:
        end = 8 + int.from_bytes(d[:8], "little")
        out.append((np.cumsum(_spread(s)), _spread(d[8:end]), _spread(d[end:]).view(np.float64)))
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


def masked_total(a: DataFrame, b: DataFrame, mask: DataFrame, p: int | None = None) -> DataFrame:
    """One row (total): the sum of the entries of a times b (plus, times) where ``mask`` has an entry, over matrices (row, col, val) without
    repeated places. A task has one colour of rows, of columns and of what lies between; products are summed up as they are found."""
    spark = a.sparkSession
    if p is None:
        p = max(1, int(np.ceil(np.sqrt(sum(m.count() for m in (a, b, mask)) / TASK_EDGES))))
    path, at = fresh_path(spark, "packed"), []
    for k, matrix in enumerate((a, b, mask)):
        # A matrix that is used again is stored once.
        same = next((x for x, other in enumerate((a, b, mask)[:k]) if other is matrix), None)
        at.append(k * p * p if same is None else at[same])
        if same is None:
            rows = matrix.select(F.col("row").cast("long"), F.col("col").cast("long"), F.col("val").cast("double")).mapInArrow(_pack_entries(p, at[k]), "block long, n long, s binary, d binary")
            rows.repartition(p * p, "block").withColumn("part", F.col("block")).write.mode("append").partitionBy("part").parquet(path)
    here = {r.block for r in spark.read.schema("block long").parquet(path).distinct().collect()}
    lists = []
    for i, k, j in product(range(p), repeat=3):
        key = at[0] + i * p + k, at[1] + k * p + j, at[2] + i * p + j
        if set(key) <= here:
            lists.append((key, sorted(set(key))))

    def kernel(key: tuple[int, int, int], held: dict[int, list]) -> Iterator[pa.RecordBatch]:
        (ar, ak, av), (bk, bc, bv), (r, c, _) = (_entries(held[block]) for block in key)
        rows, cols = np.unique(r), np.unique(c)
        mine = [np.flatnonzero(np.isin(x, names)) for x, names in ((ar, rows), (bc, cols))]
        # Rows and columns are different ends, though their ids may be the same.
        x = np.concatenate([np.searchsorted(rows, ar[mine[0]]), len(rows) + np.searchsorted(cols, bc[mine[1]])])
        w, val = np.concatenate([ak[mine[0]], bk[mine[1]]]), np.concatenate([av[mine[0]], bv[mine[1]]])
        total = 0.0
        for _, _, walked, found in _hits(np.searchsorted(rows, r), len(rows) + np.searchsorted(cols, c), x, w):
            total += float(val[walked] @ val[found])
        yield pa.RecordBatch.from_arrays([pa.array([total], pa.float64())], ["total"])

    return over_lists(spark, path, lists, kernel, "total double").agg(F.coalesce(F.sum("total"), F.lit(0.0)).alias("total"))


def triangle_count(edges: DataFrame, p: int | None = None) -> DataFrame:
    """One row (triangles)."""
    return over_triangles(edges, count_all, "n long", p).agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("triangles"))


def triangle_corners(edges: DataFrame, p: int | None = None) -> DataFrame:
    """(id, t) of the vertices on any triangle."""
    return over_triangles(edges, count_corners, "id long, n long", p).groupBy("id").agg(F.sum("n").alias("t"))


def butterfly_corners(edges: DataFrame, p: int | None = None) -> DataFrame:
    """(id, butterflies) of the vertices on any, of a bipartite graph (side, centre) without repeated edges and with no id on both sides.

    A task has the edges of two colours of sides. It counts the common centres c of every pair of sides, some sides at a time: the pair
    lies on c (c - 1) / 2 butterflies, and each of its centres on c - 1 of them."""
    if p is None:
        p = max(1, int(np.ceil(2 * edges.count() / CLIQUE_EDGES)))
    spark, path = edges.sparkSession, fresh_path(edges.sparkSession, "packed")
    rows = edges.select(F.col("side").cast("long"), F.col("centre").cast("long"), F.lit(1.0).alias("val")).mapInArrow(_pack_entries(p, 0), "block long, n long, s binary, d binary")
    rows.repartition(p * p, "block").withColumn("part", F.col("block")).write.partitionBy("part").parquet(path)
    here = sorted(r.block for r in spark.read.schema("block long").parquet(path).distinct().collect())
    lists = []
    for two in combinations_with_replacement(sorted({b // p for b in here}), 2):
        lists.append((two, [b for b in here if b // p in two]))

    def kernel(two: tuple[int, int], held: dict[int, list]) -> Iterator[pa.RecordBatch]:
        (s, cs), (t, ct) = (_entries([part for b in held if b // p == k for part in held[b]])[:2] for k in two)
        sides, others, centres = np.unique(s), np.unique(t), np.intersect1d(cs, ct)
        order = np.lexsort((t, ct))
        order = order[np.isin(ct[order], centres)]
        low = np.searchsorted(ct[order], centres)
        n, t = np.diff(np.append(low, len(order))), np.searchsorted(others, t[order])
        order = np.argsort(s, kind="stable")
        order = order[np.isin(cs[order], centres)]
        s, at = np.searchsorted(sides, s[order]), np.searchsorted(centres, cs[order])
        of_side, of_other, of_centre = (np.zeros(len(x), np.int64) for x in (sides, others, centres))
        some = max(1, CLIQUE_CELLS // len(others))

        def wedges(first: int, begin: int, end: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
            for run in _runs(n[at[begin:end]], CLIQUE_CELLS // 8):
                e = np.arange(begin + run.start, begin + run.stop)
                k = n[at[e]]
                row = np.repeat(e, k)
                other = t[np.arange(len(row)) + np.repeat(low[at[e]] - (np.cumsum(k) - k), k)]
                if two[0] == two[1]:
                    once = s[row] < other
                    row, other = row[once], other[once]
                yield at[row], (s[row] - first) * len(others) + other

        for first in range(0, len(sides), some):
            begin, end = np.searchsorted(s, [first, first + some])
            shape = min(some, len(sides) - first), len(others)
            common = np.zeros(shape[0] * shape[1], np.int64)
            for _, pair in wedges(first, begin, end):
                common += np.bincount(pair, minlength=len(common))
            for centre, pair in wedges(first, begin, end):
                of_centre += np.bincount(centre, common[pair] - 1, len(centres)).astype(np.int64)
            twos = (common * (common - 1) // 2).reshape(shape)
            of_side[first : first + some] += twos.sum(1)
            of_other += twos.sum(0)
        for ids, found in ((sides, of_side), (others, of_other), (centres, of_centre)):
            ids, found = ids[found > 0], found[found > 0]
            for k in range(0, len(ids), CHUNK):
                yield pa.RecordBatch.from_arrays([pa.array(ids[k : k + CHUNK]), pa.array(found[k : k + CHUNK])], ["id", "n"])

    return over_lists(spark, path, lists, kernel, "id long, n long").groupBy("id").agg(F.sum("n").alias("butterflies"))
