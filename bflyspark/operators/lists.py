"""Wedges as lists: what a part of the ends needs is packed, and its wedges are expanded in the task that reads them.

A middle with its neighbours in order of priority stands for all its wedges: each neighbour before the middle
(a head) with every one behind it in the list. Ends x are cut into parts by ranges of their ids, and a part holds,
once for each middle, the list from the first head of its range on. So neither wedges nor points are ever
shuffled or stored, and a group (x, z) lies in one part whole: sizes, pairs and window counts need no exchange
by group. Ids near each other often share neighbours; where they don't, a list goes to more parts.

Edges travel three times, packed: by u for the degrees of u, by v for those of v, and back.
"""

from __future__ import annotations

import struct
from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import FACTORS, PRIME
from ..sources.graph import SIDE_U, SIDE_V, TemporalBipartite
from ..sources.scratch import written

CHUNK = 400_000  # edges that a task packs at once
PART = 300_000  # edges per part of ends
TASK = 100_000_000  # wedges of two edges of a row from which several tasks share it
WEDGES = 1_500_000  # wedges that a task expands at once; an end of more is worked off in several passes
DENSE = 1 << 23  # cells of a square of times that are added up in place
MATES = 128  # points of a group that are paired one by one
CELLS = 1 << 20  # cells of starts and ends of a group that are held at once
SAMPLE = 64  # ids of a chunk from which the ranges are drawn; they only balance the parts
ZSTD = pa.Codec("zstd")
ROWS = "part int, side int, data binary"


def packed(*columns: np.ndarray) -> bytes:
    """Whole numbers as bytes: offsets from the least in the fewest bytes, or codes of few distinct values, compressed."""

    def one(c: np.ndarray) -> bytes:
        low = int(c.min()) if len(c) else 0
        off = c.view(np.uint64) - np.uint64(low & (1 << 64) - 1)
        most = int(off.max()) if len(c) else 0
        width = next(k for k in (1, 2, 4, 8) if k == 8 or most < 1 << 8 * k)
        small = ZSTD.compress(off.astype(f"<u{width}").view(np.uint8).reshape(-1, width).T.tobytes(), asbytes=True)
        return struct.pack("<qqBq", len(c), low, width, len(small)) + small

    out = []
    for c in columns:
        c = np.ascontiguousarray(c, np.int64)
        values, codes = np.unique(c, return_inverse=True) if len(c) > 64 and int(c.max()) - int(c.min()) > 1 << 24 else (c[:0], c)
        coded = 0 < len(values) < len(c) // 4
        out += [bytes([coded]), *([one(values), one(codes.astype(np.int64))] if coded else [one(c)])]
    return b"".join(out)


def unpacked(data: bytes) -> list[np.ndarray]:
    at, out = 0, []

    def one() -> np.ndarray:
        nonlocal at
        n, low, width, size = struct.unpack_from("<qqBq", data, at)
        at += 25
        body = ZSTD.decompress(data[at : at + size], decompressed_size=n * width, asbytes=True) if n else b""
        at += size
        off = np.frombuffer(body, np.uint8).reshape(width, n).T.copy().view(f"<u{width}").ravel()
        return (off.astype(np.uint64) + np.uint64(low & (1 << 64) - 1)).view(np.int64)

    while at < len(data):
        coded = data[at]
        at += 1
        first = one()
        out.append(first[one()] if coded else first)
    return out


def spread(starts: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """starts[i], starts[i] + 1, ... (counts[i] of them), one after the other."""
    return np.repeat(starts - (np.cumsum(counts) - counts), counts) + np.arange(int(counts.sum()))


def runs(*columns: np.ndarray) -> np.ndarray:
    """Where equal rows begin, in columns that stand in order."""
    fresh = np.zeros(len(columns[0]), bool)
    fresh[:1] = True
    for c in columns:
        fresh[1:] |= c[1:] != c[:-1]
    return np.flatnonzero(fresh)


def _dealt(ids: np.ndarray, parts: int) -> np.ndarray:
    h = ids.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    return ((h ^ (h >> np.uint64(29))) % np.uint64(parts)).astype(np.int64)


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], kind) for k, kind in enumerate((pa.int32(), pa.int32(), pa.binary()))], ["part", "side", "data"])


def _sent(part: np.ndarray, side: int, columns: list[np.ndarray], nt: np.ndarray, t: np.ndarray) -> Iterator[tuple]:
    """A packed row per part of pairs with their times."""
    order = np.argsort(part, kind="stable")
    first = (np.cumsum(nt) - nt)[order]
    part, nt, columns = part[order], nt[order], [c[order] for c in columns]
    edges = [*runs(part).tolist(), len(part)]
    for a, b in zip(edges, edges[1:], strict=False):
        yield int(part[a]), side, packed(*(c[a:b] for c in columns), nt[a:b], t[spread(first[a:b], nt[a:b])])


def by_left(edges: DataFrame, parts: int) -> DataFrame:
    """Distinct edges as pairs (u, v, degree of u, times), dealt by v. Rows of part -1 are samples of ids and the number of pairs."""

    def run(batches):
        def solve(u, v, t):
            new = np.flatnonzero(np.concatenate([[True], (u[1:] != u[:-1]) | (v[1:] != v[:-1]) | (t[1:] != t[:-1])]))
            u, v, t = u[new], v[new], t[new]
            starts = runs(u, v)
            nt, u, v = np.diff(np.append(starts, len(u))), u[starts], v[starts]
            own = runs(u)
            degrees = np.diff(np.append(own, len(u)))
            step = max(1, len(u) // SAMPLE)
            yield _batch([(-1, len(u), packed(u[::step], np.sort(v)[::step])), *_sent(_dealt(v, parts), 0, [u, v, np.repeat(degrees, degrees)], nt, t)])

        held = None
        for b in batches:
            new = [b.column(k).to_numpy(zero_copy_only=False) for k in range(3)]
            held = new if held is None else [np.concatenate(c) for c in zip(held, new, strict=True)]
            if len(held[0]) >= CHUNK:
                cut = int(runs(held[0])[-1])  # the last vertex may go on
                if cut:
                    yield from solve(*(c[:cut] for c in held))
                    held = [c[cut:] for c in held]
        if held is not None and len(held[0]):
            yield from solve(*held)

    return edges.select("u", "v", "t").repartition("u").sortWithinPartitions("u", "v", "t").mapInArrow(run, ROWS)


def _gathered(batches) -> list[np.ndarray] | None:
    rows = [unpacked(x) for b in batches for x in b.column("data").to_pylist()]
    return [np.concatenate(c) for c in zip(*rows, strict=True)] if rows else None


def middle_lists(y: np.ndarray, a: np.ndarray, da: np.ndarray, dy: np.ndarray, nt: np.ndarray, t: np.ndarray, side: int, bounds: np.ndarray) -> Iterator[tuple]:
    """For each part of heads the middles that have some there, each with its list from the first of them on."""
    order = np.lexsort((a, -da, y))
    first = (np.cumsum(nt) - nt)[order]
    y, a, da, dy, nt = y[order], a[order], da[order], dy[order], nt[order]
    starts = runs(y)
    ends = np.repeat(np.append(starts[1:], len(y)), np.diff(np.append(starts, len(y))))
    heads = np.flatnonzero(((da > dy) | ((da == dy) & (side == SIDE_V))) & (np.arange(len(y)) < ends - 1))
    part = np.searchsorted(bounds, a[heads], "right")
    order = np.lexsort((heads, part))
    heads, part = heads[order], part[order]
    lists = runs(part, ends[heads])  # a middle is told by the end of its list
    low, high, of = heads[lists], ends[heads[lists]], part[lists]
    until = np.append(lists[1:], len(heads))
    edges = [*runs(of).tolist(), len(of)]
    for i, j in zip(edges, edges[1:], strict=False):
        k = i
        while k < j:  # long lists are packed a chunk at a time
            n = max(1, int(np.searchsorted(np.cumsum(high[k:j] - low[k:j]), 4 * CHUNK, "right")))
            n = min(n, j - k)
            lens = high[k : k + n] - low[k : k + n]
            at = spread(low[k : k + n], lens)
            mark = np.zeros(len(at), np.int64)
            mine = heads[lists[k] : until[k + n - 1]]
            mark[mine - np.repeat(low[k : k + n] - (np.cumsum(lens) - lens), until[k : k + n] - lists[k : k + n])] = 1
            yield int(of[k]), side, packed(lens, y[low[k : k + n]], a[at], nt[at], mark, t[spread(first[at], nt[at])])
            k += n


def build(g: TemporalBipartite) -> DataFrame:
    """side, data: the lists of a part of ends and one side, written once."""
    spark = g.edges.sparkSession
    dealt = int(spark.conf.get("spark.sql.shuffle.partitions"))
    pairs = written(by_left(g.edges, dealt), "edge-lists")
    drawn = pairs.where("part = -1").select("side", "data").collect()  # a few ids per chunk
    total = sum(r.side for r in drawn)
    parts = max(spark.sparkContext.defaultParallelism, total // PART + 1)
    samples = [unpacked(r.data) for r in drawn]

    def quantiles(ids: list[np.ndarray]) -> np.ndarray:
        every = np.sort(np.concatenate([*ids, np.zeros(0, np.int64)]))
        return np.unique(every[np.arange(1, parts) * len(every) // parts]) if len(every) else every

    bounds = {SIDE_U: quantiles([s[0] for s in samples]), SIDE_V: quantiles([s[1] for s in samples])}

    def at_right(lists: bool):
        def run(batches):
            held = _gathered(batches)
            if held is None:
                return
            u, v, du, nt, t = held
            _, at, n = np.unique(v, return_inverse=True, return_counts=True)
            rows = middle_lists(v, u, du, n[at], nt, t, SIDE_U, bounds[SIDE_U]) if lists else _sent(_dealt(u, dealt), 0, [u, v, du, n[at]], nt, t)
            for r in rows:
                yield _batch([r])

        return run

    def at_left(batches):
        held = _gathered(batches)
        if held is not None:
            u, v, du, dv, nt, t = held
            for r in middle_lists(u, v, dv, du, nt, t, SIDE_V, bounds[SIDE_V]):
                yield _batch([r])

    def joined(batches):
        held: dict[int, list[bytes]] = {}
        for b in batches:
            for side, data in zip(b.column("side").to_pylist(), b.column("data").to_pylist(), strict=True):
                held.setdefault(side, []).append(data)
        for side, rows in sorted(held.items()):
            columns = [unpacked(x) for x in rows]
            yield _batch([(0, side, packed(*(np.concatenate(c) for c in zip(*columns, strict=True))))])

    right = pairs.where("part >= 0").repartitionById(dealt, "part")
    left = right.mapInArrow(at_right(False), ROWS).repartitionById(dealt, "part").mapInArrow(at_left, ROWS)
    lists = right.mapInArrow(at_right(True), ROWS).unionByName(left)
    return written(lists.repartitionById(parts, "part").mapInArrow(joined, ROWS).select("side", "data"), "wedge-lists")


def kept(x: np.ndarray, z: np.ndarray, y: np.ndarray, share: float, seed: int) -> np.ndarray:
    """The choice of functions.hashing, on arrays."""
    total = np.full(len(x), seed % PRIME, np.int64)
    for c, f in zip((x, z, y), FACTORS, strict=False):
        total = (total + c % PRIME + 1) * f % PRIME
    return (total * total + total * 7919) % PRIME < round(share * PRIME)


def staircase_points(t: np.ndarray, a: np.ndarray, na: np.ndarray, b: np.ndarray, nb: np.ndarray) -> tuple[np.ndarray, ...]:
    """Number of the wedge, l, r, w: signed points of wedges whose edges have the times from a (b) on, na (nb) of them."""
    wide = int(t.max()) + 2
    wa, wb = np.repeat(np.arange(len(a)), na), np.repeat(np.arange(len(b)), nb)
    ta, tb = t[spread(a, na)], t[spread(b, nb)]
    out = []
    for w, own, w2, other in ((wa, ta, wb, tb), (wb, tb, wa, ta)):
        at = np.searchsorted(w2 * wide + other, w * wide + own, "left")  # the first time of the other edge from here on
        ok = at < len(other)
        ok[ok] = w2[at[ok]] == w[ok]
        out.append((w[ok], own[ok], other[at[ok]]))
    w, l, r = (np.concatenate(c) for c in zip(*out, strict=True))  # noqa: E741
    order = np.lexsort((r, l, w))
    w, l, r = w[order], l[order], r[order]  # noqa: E741
    last = np.ones(len(w), bool)
    last[:-1] = (w[1:] != w[:-1]) | (r[1:] != r[:-1])  # a later start with the same end makes an interval needless
    w, l, r = w[last], l[last], r[last]  # noqa: E741
    more = np.flatnonzero(w[1:] == w[:-1])
    return np.concatenate([w, w[more]]), np.concatenate([l, l[more]]), np.concatenate([r, r[more + 1]]), np.repeat([1, -1], [len(w), len(more)])


@dataclass
class Block:
    """Whole groups: their ends and sizes, and their points in order of groups. l and r are places in times."""

    x: np.ndarray
    z: np.ndarray
    size: np.ndarray
    group: np.ndarray
    l: np.ndarray  # noqa: E741
    r: np.ndarray
    w: np.ndarray
    times: np.ndarray


def blocks(data: bytes, least: int = 2, most: int | None = None, share: float = 1.0, seed: int = 0, sizes: list | None = None, fold: int = 1) -> Iterator[Block]:
    """The groups of least to most wedges. With sizes, only the numbers of groups by x mod fold and size are put there.

    A share below 1 keeps wedges by their hash, after sizes are taken.
    """
    lens, middle, a, nt, head, t = unpacked(data)
    ends = np.repeat(np.cumsum(lens), lens)
    y = np.repeat(middle, lens) if share < 1 else None
    first = np.cumsum(nt) - nt
    times, t = np.unique(t, return_inverse=True)
    ids, code = np.unique(a, return_inverse=True)
    heads = np.flatnonzero((head == 1) & (np.arange(len(a)) < ends - 1))
    heads = heads[np.argsort(code[heads], kind="stable")]
    count = ends[heads] - 1 - heads
    own = np.append(runs(code[heads]), len(heads))
    upto = np.cumsum(nt)
    load = count if sizes is not None else (count * nt[heads] + upto[ends[heads] - 1] - upto[heads]) // 2  # wedges count by their times
    done = np.concatenate([[0], np.cumsum(load)])[own]

    def expanded(some: np.ndarray, n: np.ndarray, passes: int, k: int) -> tuple[np.ndarray, np.ndarray]:
        xs, zs, at, upto = [], [], 0, np.cumsum(n)
        while at < len(some):
            to = max(at + 1, int(np.searchsorted(upto, (upto[at - 1] if at else 0) + WEDGES, "right")))
            z = spread(some[at:to] + 1, n[at:to])
            x = np.repeat(some[at:to], n[at:to])
            if passes > 1:
                mine = _dealt(code[z], passes) == k
                x, z = x[mine], z[mine]
            xs.append(x)
            zs.append(z)
            at = to
        return np.concatenate(xs), np.concatenate(zs)

    i = 0
    while i < len(own) - 1:
        j = max(i + 1, int(np.searchsorted(done, done[i] + WEDGES, "right")) - 1)
        some, n = heads[own[i] : own[j]], count[own[i] : own[j]]
        passes = int(done[j] - done[i]) // (2 * WEDGES) + 1
        i = j
        for k in range(passes):
            x, z = expanded(some, n, passes, k)
            key = code[x] * len(ids) + code[z]
            order = np.argsort(key)
            starts = runs(key[order])
            size = np.diff(np.append(starts, len(key)))
            if sizes is not None:
                kinds, n_groups = np.unique(ids[code[x[order[starts]]]] % fold << 40 | size, return_counts=True)
                sizes.append((kinds >> 40, kinds & (1 << 40) - 1, n_groups))
                continue
            use = (size >= least) if most is None else (size >= least) & (size <= most)
            order = order[np.repeat(use, size)]
            x, z, size, starts = x[order], z[order], size[use], (np.cumsum(size[use]) - size[use])
            if not len(x):
                continue
            gx, gz, group = ids[code[x[starts]]], ids[code[z[starts]]], np.repeat(np.arange(len(size)), size)
            if share < 1:
                some_kept = kept(ids[code[x]], ids[code[z]], y[x], share, seed)
                x, z, group = x[some_kept], z[some_kept], group[some_kept]
            t1, t2 = t[first[x]], t[first[z]]
            l, r, w = np.minimum(t1, t2), np.maximum(t1, t2), np.ones(len(x), np.int64)  # noqa: E741
            many = np.flatnonzero((nt[x] > 1) | (nt[z] > 1))
            if len(many):
                wedge, l2, r2, w2 = staircase_points(t, first[x[many]], nt[x[many]], first[z[many]], nt[z[many]])
                single = np.ones(len(x), bool)
                single[many] = False
                group = np.concatenate([group[single], group[many][wedge]])
                l, r, w = np.concatenate([l[single], l2]), np.concatenate([r[single], r2]), np.concatenate([w[single], w2])  # noqa: E741
                order = np.argsort(group, kind="stable")
                group, l, r, w = group[order], l[order], r[order], w[order]  # noqa: E741
            yield Block(gx, gz, size, group, l, r, w, times)


@dataclass
class Stretch:
    """Whole groups of whole stretches of time: a wedge of two edges each, in order of groups. own marks those that begin in their stretch."""

    size: np.ndarray
    group: np.ndarray
    y: np.ndarray
    l: np.ndarray  # noqa: E741
    r: np.ndarray
    own: np.ndarray


def stretches(data: bytes, largest: int, least: int = 2, most: int | None = None, turn: int = 0, turns: int = 1) -> Iterator[Stretch]:
    """Wedges of two edges of different times, no further apart than the largest span, by groups and stretches of time.

    Stretches begin every largest + 1 steps and are twice as long, so that all that spans at most the largest lies in
    the one where it begins; edges are cut by them before they are paired. Groups of a stretch are told by their
    wedges there, own ones and those that may follow; without own ones they are left out. Of several turns each
    expands its share.
    """
    lens, middle, a, nt, head, t = unpacked(data)
    if not len(t):
        return
    low, step = int(t.min()), max(largest, 0) + 1
    cell = (t - low) // step
    early = np.flatnonzero(np.isin(cell - 1, np.unique(cell)))  # these stand in the stretch before theirs, too
    at, stretch = np.concatenate([np.arange(len(t)), early]), np.concatenate([cell, cell[early] - 1])
    order = np.lexsort((at, stretch))
    at, stretch = at[order], stretch[order]
    pair, t = np.repeat(np.arange(len(a)), nt)[at], t[at]
    of = np.repeat(np.arange(len(lens)), lens)[pair]

    def until(*columns: np.ndarray) -> np.ndarray:
        starts = runs(*columns)
        return np.repeat(np.append(starts[1:], len(at)), np.diff(np.append(starts, len(at))))

    behind, ends = until(stretch, pair), until(stretch, of)
    ids, code = np.unique(a, return_inverse=True)
    code = code[pair]
    heads = np.flatnonzero((head[pair] == 1) & (behind < ends))
    heads = heads[np.lexsort((stretch[heads], code[heads]))]
    count = (ends - behind)[heads]
    own = np.append(runs(code[heads], stretch[heads]), len(heads))
    done = np.concatenate([[0], np.cumsum(count)])[own]
    unit = np.zeros(len(at), np.int64)
    unit[heads] = np.repeat(np.arange(len(own) - 1), np.diff(own))
    i = n = 0
    while i < len(own) - 1:
        j = max(i + 1, int(np.searchsorted(done, done[i] + WEDGES, "right")) - 1)
        some = heads[own[i] : own[j]]
        passes = int(done[j] - done[i]) // (2 * WEDGES) + 1
        i = j
        for k in range(passes):
            n += 1
            if n % turns != turn:
                continue
            first, last = behind[some], ends[some]
            if passes > 1:  # each has its share of the ends z
                tails = np.flatnonzero(_dealt(code, passes) == k)
                first, last = np.searchsorted(tails, first), np.searchsorted(tails, last)
            x, z = np.repeat(some, last - first), spread(first, last - first)
            z = tails[z] if passes > 1 else z
            span = np.abs(t[x] - t[z])
            near = np.flatnonzero((span > 0) & (span <= largest))
            x, z = x[near], z[near]
            key = unit[x] * len(ids) + code[z]
            order = np.argsort(key)
            starts = runs(key[order])
            size = np.diff(np.append(starts, len(key)))
            use = (size >= least) if most is None else (size >= least) & (size <= most)
            order, size = order[np.repeat(use, size)], size[use]
            if not len(size):
                continue
            x, z = x[order], z[order]
            l, r = np.minimum(t[x], t[z]), np.maximum(t[x], t[z])  # noqa: E741
            mine = (l - low) // step == stretch[x]
            use = np.add.reduceat(mine, np.cumsum(size) - size, dtype=np.int64) > 0
            rest, size = np.repeat(use, size), size[use]
            yield Stretch(size, np.repeat(np.arange(len(size)), size), middle[of[x[rest]]], l[rest], r[rest], mine[rest])


def turns(lists: DataFrame) -> int:
    """How many tasks share a row, so that none expands much more than TASK wedges of two edges; as many as keep the session busy."""

    def solve(_, data):
        lens, _, a, nt, head, _ = unpacked(data)
        upto, last = np.cumsum(nt), np.repeat(np.cumsum(lens), lens) - 1
        yield (np.array([int((nt * (upto[last] - upto))[head == 1].sum())]),)

    most = _map(lists, solve, "n long", [("n", pa.int64())]).agg(F.max("n")).first()[0] or 0
    return min(most // TASK + 1, 4 * lists.sparkSession.sparkContext.defaultParallelism)


def map_stretches(lists: DataFrame, solve, names: str, least: int, most: int | None, largest: int, turns: int) -> DataFrame:
    """solve(stretches) gives columns of whole numbers of the given names, one table after the other."""
    columns = names.split()

    def run(batches):
        for b in batches:
            for data, turn in zip(b.column("data").to_pylist(), b.column("turn").to_pylist(), strict=True):
                for found in solve(stretches(data, largest, least, most, turn, turns)):
                    yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in found], columns)

    rows = reduce(lambda a, b: a.unionByName(b), (lists.select("data", F.lit(k).alias("turn")) for k in range(turns)))
    return rows.mapInArrow(run, ", ".join(f"{c} long" for c in columns))


def _map(lists: DataFrame, solve, schema: str, kinds: list[tuple[str, pa.DataType]]) -> DataFrame:
    """solve(side, data) gives column lists, one table after the other."""

    def run(batches):
        for b in batches:
            for side, data in zip(b.column("side").to_pylist(), b.column("data").to_pylist(), strict=True):
                for columns in solve(side, data):
                    yield pa.RecordBatch.from_arrays([pa.array(c, kind) for c, (_, kind) in zip(columns, kinds, strict=True)], [name for name, _ in kinds])

    return lists.select("side", "data").mapInArrow(run, schema)


def histogram(lists: DataFrame) -> DataFrame:
    """size, groups of all groups, single wedges too."""
    return folded_histogram(lists, 1).select("size", "groups")


def folded_histogram(lists: DataFrame, fold: int) -> DataFrame:
    """rest, size, groups: the same for ends x of each rest mod fold."""

    def solve(_, data):
        found: list = []
        for _ in blocks(data, sizes=found, fold=fold):
            pass
        yield from found

    kinds = [(c, pa.int64()) for c in ("rest", "size", "groups")]
    return _map(lists, solve, "rest long, size long, groups long", kinds).groupBy("rest", "size").agg(F.sum("groups").alias("groups"))


def points(lists: DataFrame, least: int = 2, share: float = 1.0, seed: int = 0) -> DataFrame:
    """side, x, z, l, r, w, size: signed points of the groups of least wedges or more, equal ones added up; of a share of their wedges."""

    def solve(side, data):
        for b in blocks(data, least, None, share, seed):
            order = np.lexsort((b.r, b.l, b.group))
            group, l, r = b.group[order], b.l[order], b.r[order]  # noqa: E741
            starts = runs(group, l, r)
            w = np.add.reduceat(b.w[order], starts)
            starts, w = starts[w != 0], w[w != 0]
            at = group[starts]
            for k in range(0, len(at), 50_000):
                some, cut = at[k : k + 50_000], starts[k : k + 50_000]
                yield np.full(len(some), side, np.int32), b.x[some], b.z[some], b.times[l[cut]], b.times[r[cut]], w[k : k + 50_000], b.size[some]

    kinds = [("side", pa.int32()), *((c, pa.int64()) for c in ("x", "z", "l", "r", "w", "size"))]
    return _map(lists, solve, "side int, x long, z long, l long, r long, w long, size long", kinds)


def paired(b: Block) -> Iterator[tuple[np.ndarray, ...]]:
    """l, r, w of the pairs of points of each group, as places in times; the same l, r may come again.

    The rule is that of indexes.enumerate_points: pairs of a group's points by their weights, and (w^2 - w) / 2 at each.
    Groups of more than MATES points are added up by their starts and ends, of which there are no more cells than pairs.
    """
    first = runs(b.group)
    n = np.diff(np.append(first, len(b.group)))
    for k in np.flatnonzero(n > MATES):
        some = slice(first[k], first[k] + n[k])
        yield from paired_by_cells(b.l[some], b.r[some], b.w[some])
    few = np.repeat(n <= MATES, n)
    group, l, r, w = b.group[few], b.l[few], b.r[few], b.w[few]  # noqa: E741
    own = w < 0
    yield l[own], r[own], np.ones(int(own.sum()), np.int64)
    i, k = np.arange(len(group)), 1
    while True:
        i = i[i + k < len(group)]
        i = i[group[i + k] == group[i]]
        if not len(i):
            return
        yield np.minimum(l[i], l[i + k]), np.maximum(r[i], r[i + k]), w[i] * w[i + k]
        k += 1


def paired_by_cells(l: np.ndarray, r: np.ndarray, w: np.ndarray) -> Iterator[tuple[np.ndarray, ...]]:  # noqa: E741
    """The same of one group, each l, r once.

    With c the weight of the points inside [l, r], the pairs inside are C(c, 2); what they are more than those inside
    from the next start on, or up to the end before, or both, is the weight at (l, r). Starts are worked off from the last.
    """
    starts, row = np.unique(l, return_inverse=True)
    ends, column = np.unique(r, return_inverse=True)
    order = np.argsort(row, kind="stable")
    row, column, w = row[order], column[order], w[order]
    step = max(1, CELLS // len(ends))
    alive, done = np.zeros(len(ends), np.int64), np.zeros(len(ends), np.int64)
    for high in range(len(starts), 0, -step):
        low = max(0, high - step)
        some = slice(*np.searchsorted(row, [low, high]))
        cells = np.zeros((high - low + 1, len(ends)), np.int64)
        np.add.at(cells, (row[some] - low, column[some]), w[some])
        cells[-1] = alive
        cells = np.cumsum(cells[::-1], axis=0)[::-1]
        alive = cells[0].copy()
        np.cumsum(cells, axis=1, out=cells)
        inside = cells * (cells - 1) // 2
        inside[-1], done = done, inside[0].copy()
        inside = inside[:-1] - inside[1:]
        inside[:, 1:] -= inside[:, :-1].copy()
        at, to = np.nonzero(inside)
        yield starts[at + low], ends[to], inside[at, to]


def enumerated(lists: DataFrame, most: int | None = None) -> DataFrame:
    """l, r, w: one signed point per butterfly of the groups of most wedges at most, equal ones added up."""

    def solve(_, data):
        total: np.ndarray | None = None
        held: list[tuple[np.ndarray, np.ndarray]] = []
        n, room = 0, 4 * WEDGES

        def merged():
            key, w = (np.concatenate(c) for c in zip(*held, strict=True))
            order = np.argsort(key, kind="stable")
            key, w = key[order], w[order]
            starts = runs(key)
            return key[starts], np.add.reduceat(w, starts) if len(starts) else w

        wide, times = 1, np.zeros(0, np.int64)
        for b in blocks(data, 2, most):
            wide, times = len(b.times), b.times
            if total is None and wide * wide <= DENSE:
                total = np.zeros(wide * wide, np.int64)
            for l, r, w in paired(b):  # noqa: E741
                if total is not None:
                    np.add.at(total, l * wide + r, w)
                    continue
                held.append((l * wide + r, w))
                n += len(w)
                if n > room:
                    held[:] = [merged()]
                    n = len(held[0][0])
                    room = 2 * n + 4 * WEDGES
        key, w = (np.flatnonzero(total), total[total != 0]) if total is not None else merged() if held else (times, times)
        for at in range(0, len(key), 50_000):
            some = key[at : at + 50_000]
            yield times[some // wide], times[some % wide], w[at : at + 50_000]

    rows = _map(lists, solve, "l long, r long, w long", [(c, pa.int64()) for c in "lrw"])
    return rows.groupBy("l", "r").agg(F.sum("w").alias("w")).where("w <> 0")


def counted(lists: DataFrame, windows: DataFrame, least: int = 2, share: float = 1.0, seed: int = 0) -> DataFrame:
    """window_id, cnt, spread: the sum of C(c, 2) over groups, c the weight of a group's points inside the window.

    Every point is read for every window, which are a batch on the driver. With a share of the wedges kept,
    spread is the sum over groups of the variance of their estimate.
    """
    ids, starts, ends = (windows.toArrow().column(k).to_numpy() for k in ("window_id", "t_start", "t_end"))
    q = share

    def solve(_, data):
        total, spreads = np.zeros(len(ids), np.int64), np.zeros(len(ids))
        for b in blocks(data, least, None, share, seed):
            first = runs(b.group)
            if not len(first):
                continue
            l, r = b.times[b.l], b.times[b.r]  # noqa: E741
            for k, (start, end) in enumerate(zip(starts.tolist(), ends.tolist(), strict=True)):
                c = np.add.reduceat(np.where((l >= start) & (r <= end), b.w, 0), first)
                total[k] += int((c * (c - 1) // 2).sum())
                if q < 1:
                    n = c / q
                    each = (n * (n - 1) / 2 * (q**2 - q**4) + n * (n - 1) * (n - 2) * (q**3 - q**4)) / q**4
                    spreads[k] += float(np.where(n > 1, np.maximum(each, 0.0), 0.0).sum())
        yield ids, total, spreads

    rows = _map(lists, solve, "window_id long, part long, spreads double", [("window_id", pa.int64()), ("part", pa.int64()), ("spreads", pa.float64())])
    return rows.groupBy("window_id").agg(F.sum("part").alias("cnt"), F.sum("spreads").alias("spread"))
