"""Numbers of wedge groups by size, from tiles of pairs of ends; no wedge and no list is ever sent twice.

A group is a pair of ends of one side; a middle counts in it if the end of more edges comes before the middle by priority.
Vertices are dealt to cells, and each cell's share of all middles' lists is stored once. A tile is a pair of cells: its
task reads both shares, so it has its groups whole, and counts them end by end. Larger graphs have more cells, and more
tiles read a share; what is stored grows with the edges alone.

Edges travel three times, packed: by v for the degrees of v, by u for those of u, and back.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.graph import SIDE_U, SIDE_V, TemporalBipartite
from ..sources.scratch import written
from .lists import _dealt, packed, runs, spread, unpacked

CHUNK = 2_000_000  # edges that a task packs at once
HELD = 16_000_000  # edges of both cells of a tile
LEAST = 200_000  # edges of a cell below which more cells only cost
WEDGES = 2_000_000  # wedges that a task expands at once
DENSE = 4  # cells of ends by ends per wedge up to which groups are counted in place, and not sorted
JOB = 128  # tiles of a job
ROWS = "side int, cell int, part int, data binary"
EDGES, SENT = -2, -1  # sides of rows that are no lists


def _batch(side: int, cell: int, part: int, data: bytes) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([x], kind) for x, kind in zip((side, cell, part, data), (pa.int32(), pa.int32(), pa.int32(), pa.binary()), strict=True)], ["side", "cell", "part", "data"])


def _by_run(part: np.ndarray, key: np.ndarray, other: np.ndarray, *more: np.ndarray) -> Iterator[tuple[int, bytes]]:
    """A packed row per part: each key once, with what more has of it, and its others one after the other."""
    order = np.lexsort((other, key, part))
    part, key, other, more = part[order], key[order], other[order], [m[order] for m in more]
    edges = [*runs(part).tolist(), len(part)]
    for a, b in zip(edges, edges[1:], strict=False):
        starts = runs(key[a:b])
        yield int(part[a]), packed(key[a:b][starts], np.diff(np.append(starts, b - a)), other[a:b], *(m[a:b][starts] for m in more))


def _gathered(batches) -> Iterator[tuple[int, list[np.ndarray]]]:
    """Of each part its keys, others, and what more there is of the keys, a row per edge."""
    held: dict[int, list] = {}
    for b in batches:
        for part, data in zip(b.column("part").to_pylist(), b.column("data").to_pylist(), strict=True):
            key, n, other, *more = unpacked(data)
            held.setdefault(part, []).append([np.repeat(key, n), other, *(np.repeat(m, n) for m in more)])
    while held:
        part, rows = held.popitem()
        yield part, [np.concatenate(c) for c in zip(*rows, strict=True)]


def _chunks(parts: int):
    def run(batches):
        held, n = [], 0
        for b in batches:
            held.append([b.column(k).to_numpy(zero_copy_only=False) for k in range(2)])
            n += len(held[-1][0])
            if n >= CHUNK:
                yield from packed_edges(held)
                held, n = [], 0
        if n:
            yield from packed_edges(held)

    def packed_edges(held):
        u, v = (np.concatenate(c) for c in zip(*held, strict=True))
        for part, data in _by_run(_dealt(v, parts), v, u):
            yield _batch(EDGES, 0, part, data)

    return run


def _lists(side: int, part: int, cells: int, y: np.ndarray, a: np.ndarray, da: np.ndarray) -> Iterator[pa.RecordBatch]:
    """The lists of a part's middles by cells of their ends, with a mark for ends before the middle; those without any are left out."""
    dy = np.bincount(y)[y]
    head = (da > dy) | ((da == dy) & (side == SIDE_V))
    use = (dy > 1) & (np.bincount(y, head) > 0)[y]
    y, a, da, head = y[use], a[use], da[use], head[use]
    order = np.lexsort((y, a, a % cells))
    y, a, da, head = y[order], a[order], da[order], head[order]
    edges = [*runs(a % cells).tolist(), len(a)]
    for i, j in zip(edges, edges[1:], strict=False):
        starts = runs(a[i:j])
        yield _batch(side, int(a[i] % cells), part, packed(a[i:j][starts] // cells, np.diff(np.append(starts, j - i)), y[i:j], da[i:j][starts], head[i:j].astype(np.int64)))


def build(g: TemporalBipartite) -> tuple[DataFrame, DataFrame, int]:
    """The lists with their ends on the left (among other rows) and on the right, and the number of cells."""
    spark = g.edges.sparkSession
    dealt = int(spark.conf.get("spark.sql.shuffle.partitions"))

    def at_right(batches):
        for part, (v, u) in _gathered(batches):
            order = np.lexsort((u, v))
            u, v = u[order], v[order]
            new = np.ones(len(u), bool)
            new[1:] = (u[1:] != u[:-1]) | (v[1:] != v[:-1])
            u, v = u[new], v[new]
            starts = runs(v)
            n = np.diff(np.append(starts, len(v)))
            number = np.repeat(np.arange(len(starts)), n) * dealt + part
            yield _batch(EDGES, len(u), part, b"")
            for to, data in _by_run(_dealt(u, dealt), number, u, np.repeat(n, n)):
                yield _batch(SENT, 0, to, data)

    def at_left(batches):
        for part, (v, u, dv) in _gathered(batches):
            _, y, n = np.unique(u, return_inverse=True, return_counts=True)
            yield from _lists(SIDE_V, part, cells, y, v, dv)
            for to, data in _by_run(v % dealt, y * dealt + part, v // dealt, n[y]):
                yield _batch(SENT, 0, to, data)

    def at_right_again(batches):
        for part, (u, y, du) in _gathered(batches):
            yield from _lists(SIDE_U, part, cells, y, u, du)

    first = written(g.edges.select("u", "v").mapInArrow(_chunks(dealt), ROWS).repartitionById(dealt, "part").mapInArrow(at_right, ROWS), "pairs")
    total = first.where(F.col("side") == EDGES).agg(F.sum(F.col("cell").cast("long"))).first()[0] or 0
    cores = spark.sparkContext.defaultParallelism
    cells = max(-(-2 * total // HELD), min(next(k for k in range(1, cores + 3) if k * (k + 1) >= 6 * cores or k > cores), total // LEAST + 1))
    sent = lambda rows: rows.where(F.col("side") == SENT).select("part", "data").repartitionById(dealt, "part")
    right = written(sent(first).mapInArrow(at_left, ROWS), "lists-right", "side", "cell")
    left = written(sent(right).mapInArrow(at_right_again, ROWS), "lists-left", "side", "cell")
    return left, right, cells


class Share:
    """A cell's share of the lists: ends numbered by degree, the most edges first; edges (y, end), and which ends come before y."""

    def __init__(self, rows: list[tuple[int, bytes]], base: dict[int, int]):
        columns = [(part, unpacked(data)) for part, data in rows]
        ends = 1 + max((int(c[0].max()) for _, c in columns), default=-1)
        deg = np.zeros(ends, np.int64)
        for _, c in columns:
            deg[c[0]] = c[3]
        order = np.argsort(-deg, kind="stable")
        order = order[deg[order] > 0]
        place = np.zeros(ends, np.int32)
        place[order] = np.arange(len(order))
        self.deg = deg[order]
        self.y = np.concatenate([np.zeros(0, np.int64), *(base[part] + c[2] for part, c in columns)])
        self.a = np.concatenate([np.zeros(0, np.int32), *(np.repeat(place[c[0]], c[1]) for _, c in columns)])
        self.head = np.concatenate([np.zeros(0, bool), *(c[4] == 1 for _, c in columns)])


def tile_sizes(first: list[tuple[int, bytes]], second: list[tuple[int, bytes]] | None) -> dict[int, int]:
    """Size -> groups of an end of one share and one of the other, or of two of the same share."""
    base: dict[int, int] = {}
    for part, data in [*first, *(second or [])]:
        base[part] = max(base.get(part, 0), int(unpacked(data)[2].max()) + 1)
    upto = np.cumsum([0, *base.values()])
    base, middles = dict(zip(base, upto.tolist(), strict=False)), int(upto[-1])
    found = np.zeros(1, np.int64)
    a = Share(first, base)
    b = a if second is None else Share(second, base)
    for x, z, cut in [(a, a, np.arange(1, len(a.deg) + 1))] if second is None else [(a, b, np.searchsorted(-b.deg, -a.deg, "left")), (b, a, np.searchsorted(-a.deg, -b.deg, "right"))]:
        for sizes in _counted(x, z, cut, middles):
            if len(sizes) > len(found):
                found, sizes = sizes, found
            found[: len(sizes)] += sizes
    return {int(k): int(found[k]) for k in np.flatnonzero(found[1:]) + 1}


def _counted(x: Share, z: Share, cut: np.ndarray, middles: int) -> Iterator[np.ndarray]:
    """Groups by size, of each end of x and the ends of z from its cut on."""
    wide = max(1, len(z.deg))
    edges = np.sort(z.y * wide + z.a)
    tails = (edges % wide).astype(np.int32)
    until = np.searchsorted(edges, np.arange(1, middles + 1) * wide)
    heads = np.flatnonzero(x.head)
    heads = heads[np.lexsort((x.y[heads], x.a[heads]))]
    y, a = x.y[heads], x.a[heads]
    low = np.searchsorted(edges, y * wide + cut[a])
    n = until[y] - low
    some = n > 0
    a, low, n = a[some], low[some], n[some]
    del edges, heads, y, some
    own = np.append(runs(a), len(a))
    done, upto = np.concatenate([[0], np.cumsum(n)])[own], np.cumsum(n)
    i = 0
    while i < len(own) - 1:
        j = max(i + 1, int(np.searchsorted(done, done[i] + WEDGES, "right")) - 1)
        p, q, room = int(own[i]), int(own[j]), (j - i) * wide
        if j == i + 1 or room <= DENSE * int(done[j] - done[i]):
            groups = np.zeros(room, np.int64)
            while p < q:  # an end of many wedges is worked off in slices
                to = min(q, max(p + 1, int(np.searchsorted(upto, (upto[p - 1] if p else 0) + WEDGES, "right"))))
                groups += np.bincount(_keys(a, own, i, j, p, to, tails, low, n, wide), minlength=room)
                p = to
            yield np.bincount(groups[groups > 0])
        else:
            key = _keys(a, own, i, j, p, q, tails, low, n, wide)
            key.sort()
            starts = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1], [True]]))
            yield np.bincount(np.diff(starts))
        i = j


def _keys(a, own, i: int, j: int, p: int, q: int, tails, low, n, wide: int) -> np.ndarray:
    """The wedges of the heads p to q, of the ends i to j: the number of the end, and z."""
    key = tails[spread(low[p:q], n[p:q])]
    if j == i + 1:
        return key
    kind = np.int32 if (j - i) * wide < 1 << 31 else np.int64
    first = np.repeat(np.arange(j - i, dtype=kind) * kind(wide), np.diff(own[i : j + 1]))[p - own[i] : q - own[i]]
    return key + np.repeat(first, n[p:q])


def histogram(g: TemporalBipartite) -> DataFrame:
    """size, groups of all groups, single wedges too."""
    left, right, cells = build(g)

    def tile(i: int, j: int):
        def run(batches):
            held: dict[int, list] = {i: [], j: []}
            for b in batches:
                for cell, part, data in zip(*(b.column(c).to_pylist() for c in ("cell", "part", "data")), strict=True):
                    held[cell].append((part, data))
            sizes = tile_sizes(held[i], held[j] if i < j else None)
            yield pa.RecordBatch.from_arrays([pa.array(list(c), pa.int64()) for c in (sizes.keys(), sizes.values())], ["size", "groups"])

        return run

    # A union of branches of one partition each may be read as one partition; a branch without rows keeps them apart.
    apart = right.where("cell < -1").mapInArrow(lambda batches: iter(()), "size long, groups long")
    found = []
    for side, rows in ((SIDE_U, left), (SIDE_V, right)):
        for i in range(cells):
            for j in range(i, cells):
                some = rows.where((F.col("side") == side) & F.col("cell").isin(i, j)).select("cell", "part", "data")
                found.append(some.coalesce(1).mapInArrow(tile(i, j), "size long, groups long"))
    jobs = [reduce(DataFrame.unionByName, [*found[k : k + JOB], apart]).groupBy("size").agg(F.sum("groups").alias("groups")) for k in range(0, len(found), JOB)]
    jobs = jobs if len(jobs) == 1 else [written(job, "tile-sizes") for job in jobs]
    return reduce(DataFrame.unionByName, jobs).groupBy("size").agg(F.sum("groups").alias("groups"))
