"""Exact Jaccard join of shingle sets by pivots, rings and cells.

Similarity as a metric: sets that link differ in at most H of their elements, where H follows from the
threshold and the sizes. The first pivot is the empty set: a set's distance to it is its size, so rings
of sizes are Voronoi regions around it, and by the triangle inequality a set can link with its own ring
and the two beside it alone. Each set is therefore replicated to its ring and the next (the window).
Inside a ring the metric is split over m > H blocks of the element space. In each block every distinct
content is a pivot, whose region (cell) holds the sets at distance 0 from it there. Two sets that link
differ in at most H < m blocks, so they share a cell in some block: no link is lost. Blocks that are
empty are not used as pivots unless a set has so many of them that it must be.

Document pivots alone would not cut a whole corpus: nearly all pairs of texts have distance 1, so every
document lies within every region's window. Pivots in blocks make the first regions; document pivots cut these.

Equal sets are one node. The nodes of a cell are held against each other by parity sketches: the parities
of counts in fixed buckets of the element space differ in no more buckets than the sets differ in
elements, so a pair whose sketches differ too much can't link. Nodes that may link, directly or through
others, form a region; every link lies inside one.

Every region is then cut by pivots drawn from it, at any size: each node goes to its nearest pivot (Voronoi)
and to every pivot that is at most twice the linking distance farther (triangle inequality), so two nodes that
link meet where either is at home. Parts are cut again in turn. Where that doesn't shrink a region, the nodes
that link with its pivot are taken out as one connected core, and only nodes within twice the linking distance
are held against them. A region whose sets exceed a task's memory is cut in the same way by several tasks
first; if LEVELS cuts don't bring it down, it is dealt in tiles. The links found are gathered into components.

Defined results: lower-case A-Z, words split at ASCII blanks. Null texts and texts without words have
no set and link with nothing; with fewer than four words the whole sequence is the one shingle. Repeated rows and
copies share a component. Rows with null ids take part; a component of null ids alone has null as its
id. An empty table gives no rows. Extra columns are left alone.
"""

from __future__ import annotations

from collections import Counter
from itertools import pairwise

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut, read_table, stored

ROWS_PER_PART = 1_200_000  # block signatures that one reduce task takes; cells of the same members are told as one inside a task
BLOOM_BITS = 1 << 23
REGION_BYTES = 16 << 20  # sets that one task holds at once; a larger region is cut by its pivots on the cluster first
LEVELS = 6  # cuts on the cluster
PIVOTS = 16
FEW = 48  # nodes up to which a region is worked off pivot by pivot
SHRINK = 0.7
EPSILON = 1e-9
MASK64 = (1 << 64) - 1
SKETCH = 256  # parity buckets of a small set
SKETCH_MOST = 1 << 16
SIZE_LIMIT = 1 << 32
ODD = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F)]


def mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(32))) * ODD[3]
    h = (h ^ (h >> np.uint64(29))) * ODD[4]
    return h ^ (h >> np.uint64(32))


def shingle_set(text: str | None, words: int) -> np.ndarray:
    """Sorted 64-bit hashes of the distinct shingles of a text."""
    found = (text or "").encode("utf-8", "surrogatepass").lower().split()  # bytes: ASCII letters and blanks alone
    if not found:
        return np.zeros(0, np.uint64)
    w = np.fromiter(map(xxhash.xxh3_64_intdigest, found), np.uint64, len(found))
    if len(found) < words:
        return np.array([xxhash.xxh3_64_intdigest(b"\0".join([b"short", *found]))], np.uint64)
    n = len(w) - words + 1
    h = w[:n].copy()
    for k in range(1, words):
        h = mixed(h) + w[k : k + n] * ODD[k % 3]
    return np.unique(mixed(h))


class Rings:
    """Sizes cut into rings, and the blocks of each ring, for a threshold of num / 100."""

    def __init__(self, num: int):
        self.num = num
        bounds = [1]
        while bounds[-1] < SIZE_LIMIT:
            bounds.append(max(bounds[-1] + 1, -(-bounds[-1] * 100 // num)))
        self.bounds = np.array(bounds, np.int64)

    def ring(self, size: int) -> int:
        return int(np.searchsorted(self.bounds, size, "right")) - 1

    def differing(self, ring: int) -> int:
        """The most elements in which two linked sets differ, if neither is above the ring."""
        largest = int(self.bounds[ring + 1]) - 1
        return 2 * largest * (100 - self.num) // (100 + self.num)

    def blocks(self, ring: int) -> int:
        """One more than may differ, and some to spare so that empty blocks hardly ever matter."""
        least, size = self.differing(ring) + 1, int(self.bounds[ring])
        spare = int(np.ceil(2 * least * np.exp(-size / least)))
        return least + spare + (2 if least > 20 else 0)


def cells(hashes: np.ndarray, rings: Rings) -> np.ndarray:
    """Signatures of all cells of a set: ring, block and the block's content."""
    out = []
    own = rings.ring(len(hashes))
    weight = mixed(hashes + ODD[2])
    for ring in (own, own + 1):
        m = rings.blocks(ring)
        block = ((hashes >> np.uint64(32)) * np.uint64(m)) >> np.uint64(32)  # hashes are sorted, so blocks are runs
        starts = np.flatnonzero(np.concatenate([[True], block[1:] != block[:-1]]))
        names = block[starts]
        base = np.uint64(ring * 0x10001 + 77)
        out.append(mixed(np.add.reduceat(weight, starts) + mixed(names * ODD[0] + base)))
        if m - len(names) >= m - rings.differing(ring):
            empty = np.setdiff1d(np.arange(m, dtype=np.uint64), names)
            out.append(mixed(mixed(empty * ODD[0] + base) ^ ODD[1]))
    return np.concatenate(out)


def sketch(hashes: np.ndarray) -> bytes:
    """Parities of the counts in buckets of the element space; a power of two of buckets, more for larger sets."""
    bits = SKETCH
    while bits < min(len(hashes), SKETCH_MOST):
        bits *= 2
    return np.packbits(np.bincount((hashes & np.uint64(bits - 1)).astype(np.int64), minlength=bits) & 1).tobytes()


def folded(sketches: list[bytes]) -> np.ndarray:
    """Sketches as rows of one width, that of the shortest: folding adds up the parities of buckets that fall together."""
    width = min(map(len, sketches))
    return np.stack([np.bitwise_xor.reduce(np.frombuffer(x, np.uint8).reshape(-1, width), axis=0) for x in sketches])


def set_id(hashes: np.ndarray) -> int:
    return xxhash.xxh3_64_intdigest(hashes.tobytes(), seed=11) - (1 << 63)


def signature_pass(docs: DataFrame, words: int, num: int, parts: int) -> DataFrame:
    """One pass over the texts. Rows of kind 0: doc_id, set id, size, sketch. Rows of kind 1: for one part, cells
    as packed 48-bit signatures and 16-bit places in the row's list of set ids."""

    def run(batches):
        rings = Rings(num)
        seen: set[int] = set()

        def flush(held):
            ids = np.array([h[0] for h in held], np.int64)
            sizes = [len(h[1]) for h in held]
            sigs, place = np.concatenate([h[1] for h in held]), np.repeat(np.arange(len(held), dtype=np.uint16), sizes)
            part = (sigs % np.uint64(parts)).astype(np.int64)
            order = np.argsort(part, kind="stable")
            sigs, place, part = (sigs // np.uint64(parts))[order] & np.uint64((1 << 48) - 1), place[order], part[order]
            edges = np.flatnonzero(np.concatenate([[True], part[1:] != part[:-1], [True]]))
            rows = []
            for a, b in pairwise(edges.tolist()):
                used, local = np.unique(place[a:b], return_inverse=True)
                rows.append((int(part[a]), sigs[a:b].astype("<u8").view(np.uint8).reshape(-1, 8)[:, :6].tobytes(), local.astype("<u2").tobytes(), ids[used].tobytes()))
            n = len(rows)
            return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.nulls(n, pa.int64()), pa.nulls(n, pa.int64()), pa.nulls(n, pa.int64()), pa.nulls(n, pa.binary()), *(pa.array([r[k] for r in rows], pa.binary()) for k in (1, 2, 3))], names)

        held, weight = [], 0
        for batch in batches:
            for at in range(0, batch.num_rows, 2000):
                rows = batch.slice(at, 2000)
                keys, sizes, marks = [], [], []
                for text in rows.column(1).to_pylist():
                    hashes = shingle_set(text, words)
                    sizes.append(len(hashes))
                    if not len(hashes):
                        keys.append(None)
                        marks.append(None)
                        continue
                    key = set_id(hashes)
                    keys.append(key)
                    marks.append(None if key in seen else sketch(hashes))
                    if key not in seen:  # a task sends each set once, however many copies it meets
                        if len(seen) > 200_000:
                            seen.clear()
                        seen.add(key)
                        held.append((key, cells(hashes, rings)))
                        weight += len(held[-1][1])
                        if weight > max(400_000, 4000 * parts) or len(held) >= 60_000:
                            yield flush(held)
                            held, weight = [], 0
                spread = [(k or 0) % parts for k in keys]
                n = len(keys)
                yield pa.RecordBatch.from_arrays([pa.array(spread, pa.int32()), rows.column(0).cast(pa.int64()), pa.array(keys, pa.int64()), pa.array(sizes, pa.int64()), pa.array(marks, pa.binary()), *(pa.nulls(n, pa.binary()) for _ in range(3))], names)
        if held:
            yield flush(held)

    names = ["part", "doc_id", "node", "size", "sketch", "sigs", "places", "nodes"]
    return docs.select("doc_id", "text").mapInArrow(run, "part int, doc_id long, node long, size long, sketch binary, sigs binary, places binary, nodes binary")


def gathered(nodes: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Cells, given one after the other with their sizes, gathered so that each pair of a cell still meets: (name, node).

    Near copies share cells that differ by a few members each. From the largest down, a cell joins the one in which
    more than half of its nodes stand first, with the nodes that stand elsewhere, as long as these are no more than the
    cell had of its own; else it stays by itself. So no cell doubles, and rows only become fewer.
    """
    ends, listed = np.cumsum(sizes).tolist(), nodes.tolist()
    home: dict[int, int] = {}
    own: list[list[int]] = []
    guests: list[set[int]] = []
    for k in np.argsort(-sizes, kind="stable").tolist():
        cell = listed[ends[k - 1] if k else 0 : ends[k]]
        homes = [home.get(x, -1) for x in cell]
        best, hits = max(Counter(homes).items(), key=lambda x: (x[1], -x[0]))
        if best >= 0 and 2 * hits > len(cell):
            coming = {x for x, h in zip(cell, homes, strict=True) if h != best}.difference(own[best] if hits < len(cell) else ())
            if len(guests[best] | coming) <= len(own[best]):
                guests[best] |= coming
                continue
        for x in cell:
            home.setdefault(x, len(own))
        own.append(cell)
        guests.append(set())
    counts = np.array([len(o) + len(g) for o, g in zip(own, guests, strict=True)], np.int64)
    out = np.fromiter((x for o, g in zip(own, guests, strict=True) for x in (*o, *g)), np.int64, int(counts.sum()))
    starts = np.cumsum(counts) - counts
    name = mixed(np.add.reduceat(mixed(out.astype(np.uint64)), starts) + counts.astype(np.uint64)).astype(np.int64)
    return np.repeat(name, counts), out


def cell_pass(rows: DataFrame, parts: int) -> DataFrame:
    """Rows of kind 0 go through. From the cells of a part come members (cell, a) of those with two nodes or more.

    A cell is named by its members, so cells with the same members are one; cells that mostly agree are gathered.
    """
    names = ["doc_id", "node", "size", "sketch", "cell", "a"]

    def run(batches):
        sigs, nodes = [], []
        for batch in batches:
            plain = batch.filter(pc.is_null(batch.column(5)))
            if plain.num_rows:
                yield pa.RecordBatch.from_arrays([*plain.columns[1:5], *(pa.nulls(plain.num_rows, pa.int64()) for _ in range(2))], names)
            packed = batch.filter(pc.is_valid(batch.column(5)))
            for s, p, n in zip(*(packed.column(k).to_pylist() for k in (5, 6, 7)), strict=True):
                wide = np.zeros((len(s) // 6, 8), np.uint8)
                wide[:, :6] = np.frombuffer(s, np.uint8).reshape(-1, 6)
                sigs.append(wide.view("<u8").ravel())
                nodes.append(np.frombuffer(n, np.int64)[np.frombuffer(p, "<u2")])
        if not sigs:
            return
        sig, node = np.concatenate(sigs), np.concatenate(nodes)
        del sigs, nodes
        order = np.lexsort((node, sig))
        sig, node = sig[order], node[order]
        fresh = np.concatenate([[True], (sig[1:] != sig[:-1]) | (node[1:] != node[:-1])])
        sig, node = sig[fresh], node[fresh]
        starts = np.flatnonzero(np.concatenate([[True], sig[1:] != sig[:-1]]))
        sizes = np.diff(np.append(starts, len(sig)))
        name = mixed(np.add.reduceat(mixed(node.astype(np.uint64)), starts) + sizes.astype(np.uint64)).astype(np.int64)
        _, first = np.unique(name, return_index=True)
        chosen = np.zeros(len(starts), bool)
        chosen[first] = True
        chosen &= sizes > 1
        if not chosen.any():
            return
        cell, members = gathered(node[np.repeat(chosen, sizes)], sizes[chosen])
        none = pa.nulls(len(cell), pa.int64())
        yield pa.RecordBatch.from_arrays([none, none, none, pa.nulls(len(cell), pa.binary()), pa.array(cell), pa.array(members)], names)

    return rows.repartitionById(parts, "part").mapInArrow(run, "doc_id long, node long, size long, sketch binary, cell long, a long")


def likely_edges(members: DataFrame, num: int) -> DataFrame:
    """Edges (a, b) that connect, in each cell, the nodes whose sizes and sketches allow a link.

    members: cell, a, size, sketch. A cell is read by one task; rows of its matrix are worked off in
    blocks, and only a spanning forest leaves it.
    """

    def forest(nodes: np.ndarray, sizes: np.ndarray, bits: np.ndarray) -> list[tuple[int, int]]:
        left = np.arange(len(nodes))
        out = []
        while len(left):
            front, left = left[:1], left[1:]
            while len(front) and len(left):
                near = np.zeros(len(left), bool)
                by = np.zeros(len(left), np.int64)
                for at in front:
                    total = sizes[left] + sizes[at]
                    gap = np.bitwise_count(bits[left] ^ bits[at]).sum(axis=1, dtype=np.int64)
                    hit = ~near & (gap * (100 + num) <= total * (100 - num)) & (100 * np.minimum(sizes[left], sizes[at]) >= num * np.maximum(sizes[left], sizes[at]))
                    by[hit] = at
                    near |= hit
                    if near.all():
                        break
                out += [(int(nodes[b]), int(nodes[x])) for b, x in zip(by[near], left[near], strict=True)]
                front, left = left[near], left[~near]
        return out

    def run(batches):
        cell, held = None, []
        edges: set[tuple[int, int]] = set()

        def solve():
            edges.update(forest(np.array([h[0] for h in held]), np.array([h[1] for h in held]), folded([h[2] for h in held]).view(np.uint64)))

        for batch in batches:
            for c, a, size, bits in zip(*(batch.column(k).to_pylist() for k in range(4)), strict=True):
                if c != cell:
                    if len(held) > 1:
                        solve()
                    cell, held = c, []
                held.append((a, size, bits))
        if len(held) > 1:
            solve()
        yield pa.RecordBatch.from_arrays([pa.array([e[0] for e in edges], pa.int64()), pa.array([e[1] for e in edges], pa.int64())], ["a", "b"])

    dealt = members.repartition(F.col("cell")).sortWithinPartitions("cell")
    return dealt.select("cell", "a", "size", "sketch").mapInArrow(run, "a long, b long").distinct()


def bloom_words(ids: DataFrame) -> np.ndarray:
    """A Bloom filter over node ids, of fixed size, or-ed together in the cluster."""
    bits = ids.select(F.explode(F.array(F.pmod("id", F.lit(BLOOM_BITS)), F.pmod(F.xxhash64("id"), F.lit(BLOOM_BITS)))).alias("bit"))
    words = bits.groupBy(F.shiftright("bit", 6).alias("word")).agg(F.bit_or(F.expr("shiftleft(1L, cast(bit & 63 as int))")).alias("mask"))
    out = np.zeros(BLOOM_BITS // 64, np.int64)
    rows = words.toArrow()  # bounded: BLOOM_BITS / 64 rows
    out[rows.column("word").to_numpy()] = rows.column("mask").to_numpy()
    return out.view(np.uint64)


def sets_of(docs: DataFrame, ids: DataFrame, words: int) -> DataFrame:
    """node, hashes (packed) of the nodes that some edge needs; a filter of fixed size keeps the others at home."""
    mask = bloom_words(ids)

    def run(batches):
        seen: set[int] = set()
        for batch in batches:
            for at in range(0, batch.num_rows, 2000):
                keys, sets = [], []
                for text in batch.slice(at, 2000).column(0).to_pylist():
                    hashes = shingle_set(text, words)
                    if not len(hashes) or (key := set_id(hashes)) in seen:
                        continue
                    bit = key % BLOOM_BITS
                    if int(mask[bit >> 6]) >> (bit & 63) & 1:
                        seen.add(key)
                        keys.append(key)
                        sets.append(hashes.tobytes())
                yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.array(sets, pa.binary())], ["node", "hashes"])

    return docs.select("text").mapInArrow(run, "node long, hashes binary").join(ids, F.col("node") == F.col("id"), "left_semi").dropDuplicates(["node"])


class Space:
    """The sets of one region. common() holds one set against many at once."""

    def __init__(self, sets: list[np.ndarray]):
        self.sizes = np.array([len(s) for s in sets], np.int64)
        grams, number = np.unique(np.concatenate(sets), return_inverse=True)
        self.own = np.split(number, np.cumsum(self.sizes)[:-1])
        self.mark = np.zeros(len(grams), bool)

    def common(self, ones: list[int], others: np.ndarray) -> np.ndarray:
        """Elements that each of the ones shares with each of the others."""
        flat = np.concatenate([self.own[i] for i in others])
        starts = np.cumsum(self.sizes[others]) - self.sizes[others]
        out = np.empty((len(ones), len(others)), np.int64)
        for row, i in enumerate(ones):
            self.mark[self.own[i]] = True
            out[row] = np.add.reduceat(self.mark[flat], starts, dtype=np.int64)
            self.mark[self.own[i]] = False
        return out

    def compared(self, ones: list[int], others: np.ndarray, num: int) -> tuple[np.ndarray, np.ndarray]:
        """Whether each pair links, and its distance."""
        common = self.common(ones, others)
        union = self.sizes[ones][:, None] + self.sizes[others] - common
        return 100 * common >= num * union, 1 - common / union


class Links:
    """Pairs that connect what is connected."""

    def __init__(self, n: int):
        self.root, self.pairs = list(range(n)), []

    def find(self, i: int) -> int:
        while self.root[i] != i:
            self.root[i] = self.root[self.root[i]]
            i = self.root[i]
        return i

    def join(self, i: int, j: int) -> None:
        a, b = self.find(i), self.find(j)
        if a != b:
            self.root[b] = a
            self.pairs.append((i, j))


def meet(space: Space, links: Links, core: np.ndarray, rim: np.ndarray, num: int) -> None:
    """Links between a core, which is connected, and the nodes around it that are not connected with it yet."""
    for y in rim.tolist():
        if links.find(y) != links.find(int(core[0])):
            hit = np.flatnonzero(space.compared([y], core, num)[0][0])
            if len(hit):
                links.join(int(core[hit[0]]), y)


def near(distances: np.ndarray, num: int) -> np.ndarray:
    """Which pivots' regions each node stands in: that of the nearest pivot, and each at most twice the linking distance farther."""
    return distances <= distances.min(axis=0) + 2 * (100 - num) / 100 + EPSILON


def region_links(nodes: list[int], sets: list[np.ndarray], num: int, core: list[bool] | None = None) -> list[tuple[int, int]]:
    """Links that connect what is connected in one region; exact. Regions are cut by pivots, again and again.

    Pivots are drawn from the region and held against all of it, so all their links are known. Each node goes
    to its nearest pivot and to every pivot whose region it may touch (triangle inequality): two nodes that
    link meet where either is at home. Where this doesn't shrink a region, its pivot takes the nodes that
    link with it out: they are connected, and only nodes within twice the linking distance of the pivot can
    link with one of them. What is left is a smaller region.

    core marks nodes that are connected already; then only links of others with them are asked for.
    """
    space, links = Space(sets), Links(len(nodes))
    order = np.array(sorted(range(len(nodes)), key=lambda i: (nodes[i] * 0x9E3779B97F4A7C15) & MASK64), np.int64)
    if core is not None and any(core):
        inside = np.array(core)[order]
        held = order[inside]
        for i in held[1:].tolist():
            links.root[links.find(i)] = links.find(int(held[0]))
        meet(space, links, held, order[~inside], num)
        return [(nodes[i], nodes[j]) for i, j in links.pairs]
    regions = [order]
    while regions:
        idx = regions.pop()
        if len(idx) < 2:
            continue
        chosen = idx[:PIVOTS].tolist() if len(idx) > FEW else idx[:1].tolist()
        linked, distances = space.compared(chosen, idx, num)
        for row, p in enumerate(chosen):
            for i in idx[linked[row]].tolist():
                links.join(p, i)
        if len(chosen) > 1:
            inside = near(distances, num)
            inside[:, : len(chosen)] = False  # pivots are done
            sizes = inside.sum(axis=1)
            if sizes.max() <= SHRINK * len(idx) and sizes.sum() <= 2 * len(idx):
                regions += [idx[inside[row]] for row in range(len(chosen))]
                continue
        best = int(linked.sum(axis=1).argmax())  # the pivot that takes most out
        ball = linked[best]
        rim = idx[~ball & (distances[best] <= 2 * (100 - num) / 100 + EPSILON)]
        meet(space, links, idx[ball], rim, num)
        regions.append(idx[~ball])
    return [(nodes[i], nodes[j]) for i, j in links.pairs]


CUT = "region long, node long, hashes binary, core boolean, mate long"


def cut_by_pivots(big: DataFrame, sizes: DataFrame, level: int, num: int) -> DataFrame:
    """Regions too large for a task, cut by their pivots on the cluster, by the same rule.

    Rows with a region are its nodes; rows without one are links (node, mate) to a pivot. A node that links
    with a pivot is core in the region of the nearest such pivot: all cores of a region are connected. Cores of
    two regions may link while their pivots don't, so a core also stands around the later pivots within twice
    the linking distance, unless links given out already connect it with them. Another node goes to each core
    within twice the linking distance, and for links among its like to the Voronoi regions that it may touch.
    """
    sized = big.join(sizes.select("region", "n", "rows"), "region")
    drawn = F.pmod(F.xxhash64("node", F.lit(level)), F.greatest(F.lit(1), F.floor(F.col("rows") / PIVOTS)).cast("long")) == 0
    salts = F.ceil(F.col("n") / 4).cast("int")  # n: loads of a task; a share of a load goes with all pivots
    left = sized.withColumn("salt", F.pmod(F.xxhash64("node", F.lit(-level - 1)), salts * 4).cast("int")).select("region", "salt", "node", "hashes")
    right = sized.where(drawn).select(F.col("region").alias("of"), F.explode(F.sequence(F.lit(0), salts * 4 - 1)).alias("copy"), F.col("node").alias("pivot"), F.col("hashes").alias("pivot_hashes"))

    def deal(rows: pa.Table, pivots: pa.Table) -> pa.Table:
        out: list[tuple] = []
        if rows.num_rows:
            region = rows.column("region")[0].as_py()
            nodes, packed = rows.column("node").to_pylist(), rows.column("hashes").to_pylist()
            names = sorted(zip(pivots.column("pivot").to_pylist(), pivots.column("pivot_hashes").to_pylist(), strict=True))
            label = lambda kind, k: xxhash.xxh3_64_intdigest(f"{region} {level} {kind} {names[k][0]}") - (1 << 63)
            if not names:  # none was drawn: the region stays as it is
                out = [(region, node, p, False, None) for node, p in zip(nodes, packed, strict=True)]
            else:
                space = Space([np.frombuffer(x, np.uint64) for x in [x for _, x in names] + packed])
                n = len(names)
                linked, distances = space.compared(list(range(n)), np.arange(n, n + len(nodes)), num)
                inside, reach = near(distances, num), distances <= 2 * (100 - num) / 100 + EPSILON
                home = np.where(linked, distances, 2).argmin(axis=0)
                joined = Links(n)  # pivots that nodes of this share link with one another; these links are given out
                for i in np.flatnonzero(linked.sum(axis=0) > 1).tolist():
                    for k in np.flatnonzero(linked[:, i]).tolist():
                        joined.join(home[i], k)
                root = np.array([joined.find(k) for k in range(n)])
                for i, (node, p) in enumerate(zip(nodes, packed, strict=True)):
                    if linked[:, i].any():
                        out += [(None, node, None, None, names[k][0]) for k in np.flatnonzero(linked[:, i]).tolist() if names[k][0] != node]
                        out.append((label("core", home[i]), node, p, True, None))
                        open_to = reach[:, i] & (np.arange(n) > home[i]) & (root != root[home[i]])
                        out += [(label("core", k), node, p, False, None) for k in np.flatnonzero(open_to).tolist()]
                    else:
                        out += [(label("core", k), node, p, False, None) for k in np.flatnonzero(reach[:, i]).tolist()]
                        out += [(label("rest", k), node, p, False, None) for k in np.flatnonzero(inside[:, i]).tolist()]
        kinds = (pa.int64(), pa.int64(), pa.binary(), pa.bool_(), pa.int64())
        return pa.table({name: pa.array([r[k] for r in out], kind) for k, (name, kind) in enumerate(zip(("region", "node", "hashes", "core", "mate"), kinds, strict=True))})

    return left.groupBy("region", "salt").cogroup(right.groupBy("of", "copy")).applyInArrow(deal, CUT)


def cut_in_tiles(big: DataFrame, sizes: DataFrame) -> DataFrame:
    """Regions that pivots don't shrink: bins of half a load, a region for each pair of bins."""
    sized = big.join(sizes.select("region", "n"), "region")
    bins = (2 * F.col("n")).cast("int")
    own = F.pmod(F.xxhash64("node", F.lit(99)), bins).cast("int")
    mates = sized.withColumn("own", own).withColumn("mate", F.explode(F.sequence(F.lit(0), bins - 1)))
    return mates.select(F.xxhash64("region", F.least("own", "mate"), F.greatest("own", "mate")).alias("region"), "node", "hashes", "core")


def region_sizes(regions: DataFrame) -> DataFrame:
    """region, n (loads of a task), rows, cores, and whether it needs a join at all: two nodes, and one outside its core."""
    load = F.ceil(F.sum(F.octet_length("hashes") + 64) / REGION_BYTES)
    return cut(regions.groupBy("region").agg(load.alias("n"), F.count("*").alias("rows"), F.sum(F.col("core").cast("long")).alias("cores")).where("rows > 1 and cores < rows"))


def dealt_cores(cores: DataFrame, sizes: DataFrame) -> DataFrame:
    """A core of several loads is dealt to as many regions; the nodes around it go to each."""
    sized = cores.join(sizes.select("region", "n"), "region")
    loads = F.col("n").cast("int")
    own = F.pmod(F.xxhash64("node", F.lit(7)), loads).cast("int")
    share = F.explode(F.when(F.col("core"), F.array(own)).otherwise(F.sequence(F.lit(0), loads - 1)))
    return sized.withColumn("share", share).select(F.xxhash64("region", "share").alias("region"), "node", "hashes", "core")


def links_in(regions: DataFrame, num: int) -> DataFrame:
    """Links (a, b) of all regions, each region in one task and one at a time.

    Grouping asks the planner for whole regions. A repartition by the same column as a join below it
    would be taken out as redundant, and an adaptive join may then deal a region to several tasks.
    """

    def solve(rows: pa.Table) -> pa.Table:
        nodes = rows.column("node").to_pylist()
        sets = [np.frombuffer(x, np.uint64) for x in rows.column("hashes").to_pylist()]
        links = region_links(nodes, sets, num, rows.column("core").to_pylist()) if len(nodes) > 1 else []
        return pa.table({"a": pa.array([x[0] for x in links], pa.int64()), "b": pa.array([x[1] for x in links], pa.int64())})

    return regions.select("region", "node", "hashes", "core").groupBy("region").applyInArrow(solve, "a long, b long")


def components(edges: DataFrame) -> DataFrame:
    """node, component (its smallest node), by alternating large and small stars until nothing moves."""
    edges = cut(edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a <> b").distinct())
    mark = None
    while True:
        both = edges.union(edges.select("b", "a"))
        lowest = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.join(lowest, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        down = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(down, "a").select("b", "m").where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).union(down.select("a", F.col("m").alias("b"))).distinct()
        edges = cut(small)
        now = edges.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if now == mark:
            break
        mark = now
    return edges.select(F.col("a").alias("node"), F.col("b").alias("component")).union(edges.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())


def join_nodes(docs: DataFrame, words: int, num: int) -> tuple[DataFrame, DataFrame]:
    """All documents with their node (doc_id, node, size), and the components of linked nodes."""
    spark = docs.sparkSession
    bytes_in = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    share = 0.45 * (100 - num) / 15 + 0.1  # signatures per word, roughly
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), int(bytes_in / 5.5 * share / ROWS_PER_PART) + 1)
    found = stored(cell_pass(signature_pass(docs, words, num, parts), parts), "jaccard-cells")
    keys = found.where("size is not null").select("doc_id", "node", "size")
    members = found.where("cell is not null").select("cell", "a").distinct()
    sketches = found.where("sketch is not null").groupBy(F.col("node").alias("a")).agg(F.first("size").alias("size"), F.first("sketch").alias("sketch"))
    edges = cut(likely_edges(members.join(sketches, "a"), num))
    if edges.isEmpty():
        return keys, spark.createDataFrame([], "node long, component long")
    groups = cut(components(edges).select("node", F.col("component").alias("region")))
    sets = sets_of(docs, groups.select(F.col("node").alias("id")), words)
    rest = stored(sets.join(groups, "node").select("region", "node", "hashes", F.lit(False).alias("core")), "jaccard-sets")
    links: list[DataFrame] = []
    for level in range(LEVELS + 1):
        sizes = region_sizes(rest)
        small = rest.join(sizes.where("n <= 1").select("region"), "region", "left_semi")
        links.append(links_in(small, num))
        heavy = sizes.where("n > 1")
        if heavy.isEmpty():
            break
        cores = dealt_cores(rest, heavy.where("cores > 0"))
        links.append(links_in(cores, num))
        big = heavy.where("cores = 0")
        whole = rest.join(big.select("region"), "region", "left_semi")
        if level == LEVELS:
            links.append(links_in(stored(cut_in_tiles(whole, big), "jaccard-tiles"), num))
            break
        dealt = stored(cut_by_pivots(whole, big, level, num), "jaccard-regions")
        links.append(dealt.where("region is null").select(F.col("node").alias("a"), F.col("mate").alias("b")))
        rest = dealt.where("region is not null").select("region", "node", "hashes", "core")
    every = links[0]
    for more in links[1:]:
        every = every.union(more)
    return keys, components(every)


def join_documents(docs: DataFrame, words: int = 4, num: int = 85) -> DataFrame:
    """doc_id, n_shingles, component_id of every document; links need num hundredths of similarity."""
    keys, part = join_nodes(docs, words, num)
    labelled = keys.join(part, "node", "left").withColumn("label", F.coalesce("component", "node"))
    smallest = labelled.where("label is not null").groupBy("label").agg(F.min("doc_id").alias("smallest"))
    out = labelled.join(smallest, "label", "left")
    return out.select("doc_id", F.col("size").alias("n_shingles"), F.when(F.col("label").isNull(), F.col("doc_id")).otherwise(F.col("smallest")).alias("component_id"))


def one_of_each(docs: DataFrame, words: int = 5, num: int = 80) -> DataFrame:
    """The rows that stand first in their component, with all columns; a row without words stands for itself.

    Rows with one doc_id and one text are one document. Rows whose id is null can't be told apart and stay.
    """
    classes = cut(join_documents(docs, words, num))
    gone = cut(classes.where("component_id is not null and doc_id <> component_id").select(F.col("doc_id").alias("gone_id")).distinct())
    # A bitmap of fixed size tells most rows that stay; only the others are shuffled with their texts.
    place = lambda c: F.pmod(F.xxhash64(c), F.lit(BLOOM_BITS))
    words = gone.groupBy(F.shiftright(place(F.col("gone_id")), 6).alias("gone_word")).agg(F.bit_or(F.expr(f"shiftleft(1L, cast(pmod(xxhash64(gone_id), {BLOOM_BITS}) & 63 as int))")).alias("gone_mask"))
    own = place(docs["doc_id"])
    marked = docs.join(F.broadcast(words), F.shiftright(own, 6) == words["gone_word"], "left")
    maybe = F.coalesce(F.getbit(words["gone_mask"], (own % 64).cast("int")), F.lit(0)) == 1
    columns = [docs[c] for c in docs.columns]
    sure, rest = marked.where(~maybe).select(*columns), marked.where(maybe).select(*columns)
    left = sure.unionByName(rest.join(gone, docs["doc_id"] == gone["gone_id"], "left_anti"))
    twice = classes.groupBy("doc_id").count().where("count > 1 and doc_id is not null").select(F.col("doc_id").alias("twice_id"))
    if twice.isEmpty():
        return left
    twice = cut(twice)
    again = left.join(twice, left["doc_id"] == twice["twice_id"], "left_semi").dropDuplicates(["doc_id", "text"])
    return left.join(twice, left["doc_id"] == twice["twice_id"], "left_anti").unionByName(again)


def op8_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return join_documents(read_table(spark, sf_dir, "documents"))
