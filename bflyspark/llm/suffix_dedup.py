"""Removal of long repeated strings by a family of suffix arrays.

Which suffixes need an index: a string of LENGTH bytes holds LENGTH - GRAM + 1 grams, and the one of
smallest hash (leftmost on ties) is its anchor. Equal strings have equal anchors at equal places, so
strings are dealt to tasks by their anchor's hash and no match is lost. Strings that share an
anchor's place in a text are one stretch, written as the range of their starts.

1. Per stretch, a task sends hashes of its anchor and of its whole content. Stretches whose content
   occurs twice are repeated in full. Anchors with differing contents are left open.
2. Contents of open anchors are sent once per task, and every task runs an index family over them:
   each new batch gets a suffix array (starts sorted by their first LENGTH bytes), is merge-scanned
   against the existing levels, which marks equal strings on both sides, and joins the family; levels
   of like size merge, so there are logarithmically many.
3. Ranges of repeated starts are gathered per text and the bytes they cover are removed.

Texts are known by a hash of their bytes, so copies share one entry; a text met twice is repeated whole.

Defined results: null texts count as empty. Texts under LENGTH bytes lose nothing. Repeated rows lose
all their bytes, as every string in them starts elsewhere too. Null ids are carried along, ties need no
rule, extra columns are left alone and an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from itertools import pairwise

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import per_worker, read_table, stored
from .jaccard_join import mixed

LENGTH = 200
GRAM = 48
CHUNK = 900_000  # bytes worked on at once; places in a chunk need 20 bits
STRETCHES_PER_PART = 700_000
STARTS_PER_PART = 500_000
BLOOM_BITS = 1 << 24
BATCH_STARTS = 100_000
MULTIPLIER = 0xD1342543DE82EF95


def powers() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Random words for bytes, and powers of the multiplier and of its inverse modulo 2^64."""
    table = np.random.default_rng(5).integers(0, 1 << 64, 256, np.uint64)
    out = []
    for base in (MULTIPLIER, pow(MULTIPLIER, -1, 1 << 64)):
        p = np.full(CHUNK + 2 * LENGTH, base, np.uint64)
        p[0] = 1
        out.append(np.multiply.accumulate(p))
    return table, *out


def stretches(data: np.ndarray, valid: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """First and last start, hash of the anchor, hash of the content, of each stretch of a chunk.

    data: bytes of texts; valid: whether a string of LENGTH bytes of one text starts at each place.
    """
    table, up, down = per_worker("suffix_dedup", 0, powers)
    n = len(data)
    if n < LENGTH or not valid.any():
        return (np.zeros(0, np.int64),) * 2 + (np.zeros(0, np.uint64),) * 2
    total = np.zeros(n + 1, np.uint64)
    np.cumsum(table[data] * up[:n], out=total[1:])
    grams = mixed((total[GRAM:] - total[:-GRAM]) * down[: n - GRAM + 1])
    low = grams >> np.uint64(20) << np.uint64(20) | np.arange(len(grams), dtype=np.uint64)
    span, width = LENGTH - GRAM + 1, 1
    while 2 * width <= span:
        low = np.minimum(low[:-width], low[width:])
        width *= 2
    low = np.minimum(low[: len(low) - (span - width)], low[span - width :])
    anchor = (low & np.uint64((1 << 20) - 1)).astype(np.int64)
    starts = np.flatnonzero(valid[: len(anchor)])
    own = anchor[starts]
    new = np.concatenate([[True], (own[1:] != own[:-1]) | (starts[1:] != starts[:-1] + 1)])
    first = starts[new]
    last = starts[np.append(np.flatnonzero(new)[1:] - 1, len(starts) - 1)]
    content = mixed((total[last + LENGTH] - total[first]) * down[first])
    return first, last, grams[own[new]], mixed(content ^ (last - first).astype(np.uint64))


def text_key(data: bytes) -> int:
    return xxhash.xxh3_64_intdigest(data, seed=3) - (1 << 63)


def chunks(texts: list[bytes]):
    """(bytes, valid starts, number of the text at each place, place in its text) in pieces of bounded size."""
    held, size = [], 0

    def pack():
        data = np.frombuffer(b"".join(x[1] for x in held), np.uint8)
        sizes = np.array([len(x[1]) for x in held])
        first = np.cumsum(sizes) - sizes
        valid = np.ones(len(data), bool)
        for f, k in zip(first.tolist(), sizes.tolist(), strict=True):
            valid[max(f, f + k - LENGTH + 1) : f + k] = False
        return data, valid, np.array([x[0] for x in held]), first, np.array([x[2] for x in held])

    for i, text in enumerate(texts):
        if len(text) < LENGTH:
            continue
        for at in range(0, len(text) - LENGTH + 1, CHUNK // 2):
            piece = text[at : at + CHUNK // 2 + LENGTH - 1]
            if size + len(piece) > CHUNK and held:
                yield pack()
                held, size = [], 0
            held.append((i, piece, at))
            size += len(piece)
    if held:
        yield pack()


def located(texts: list[bytes]):
    """Arrays of all stretches of some texts: text number, first and last start in the text, both hashes, and the content's bytes maker."""
    for data, valid, number, first_of, offset in chunks(texts):
        first, last, anchor, content = stretches(data, valid)
        piece = np.searchsorted(first_of, first, "right") - 1
        shift = offset[piece] - first_of[piece]
        yield number[piece], first + shift, last + shift, anchor, content


def encoded(column) -> list[bytes]:
    return [(t or "").encode("utf-8", "surrogatepass") for t in column.to_pylist()]


HASHED = ["part", "key", "first", "last", "packed"]
ENTRY = np.dtype([("anchor", "<u4"), ("anchor2", "<u2"), ("content", "<u4"), ("content2", "<u2"), ("text", "<u2"), ("first", "<u4"), ("more", "u1"), ("known", "u1")])


def hash_pass(docs: DataFrame, parts: int) -> DataFrame:
    """Rows with first and last: ranges known to be repeated. Rows with packed: hashes of stretches for one part."""

    def run(batches):
        seen: set[int] = set()

        def ranges(keys, first, last):
            n = len(keys)
            return pa.RecordBatch.from_arrays([pa.array(np.asarray(keys, np.int64) % parts, pa.int32()), pa.array(keys, pa.int64()), pa.array(first, pa.int64()), pa.array(last, pa.int64()), pa.nulls(n, pa.binary())], HASHED)

        for batch in batches:
            for at in range(0, batch.num_rows, 4000):
                texts, keys, twice = [], [], []
                for data in encoded(batch.slice(at, 4000).column(0)):
                    if len(data) < LENGTH:
                        continue
                    key = text_key(data)
                    if key in seen:
                        twice.append((key, len(data) - LENGTH))
                        continue
                    if len(seen) > 300_000:
                        seen.clear()
                    seen.add(key)
                    texts.append(data)
                    keys.append(key)
                if twice:
                    twice = sorted(set(twice))
                    yield ranges([x[0] for x in twice], [0] * len(twice), [x[1] for x in twice])
                if not texts:
                    continue
                number, first, last, anchor, content = (np.concatenate(x) for x in zip(*located(texts), strict=True))
                key_of = np.array(keys, np.int64)
                order = np.lexsort((content, anchor))
                number, first, last, anchor, content = (x[order] for x in (number, first, last, anchor, content))
                same = (anchor[1:] == anchor[:-1]) & (content[1:] == content[:-1])
                again = np.concatenate([[False], same])
                shared = again | np.concatenate([same, [False]])
                if shared.any():  # repeated within this batch: known here, and one entry goes out for all
                    yield ranges(key_of[number[shared]], first[shared], last[shared])
                keep = ~again
                entry = np.zeros(int(keep.sum()), ENTRY)
                part = (anchor[keep] % np.uint64(parts)).astype(np.int64)
                high = anchor[keep] // np.uint64(parts)
                entry["anchor"], entry["anchor2"] = high & np.uint64(0xFFFFFFFF), high >> np.uint64(32) & np.uint64(0xFFFF)
                entry["content"], entry["content2"] = content[keep] & np.uint64(0xFFFFFFFF), content[keep] >> np.uint64(32) & np.uint64(0xFFFF)
                entry["text"], entry["first"], entry["more"], entry["known"] = number[keep], first[keep], last[keep] - first[keep], shared[keep]
                order = np.argsort(part, kind="stable")
                entry, part = entry[order], part[order]
                edges = np.flatnonzero(np.concatenate([[True], part[1:] != part[:-1], [True]]))
                rows = []
                for a, b in pairwise(edges.tolist()):
                    used, local = np.unique(entry["text"][a:b], return_inverse=True)
                    own = entry[a:b].copy()
                    own["text"] = local
                    head = np.array([len(used)], "<i8").tobytes()
                    rows.append((int(part[a]), head + key_of[used].astype("<i8").tobytes() + own.tobytes()))
                n = len(rows)
                yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.nulls(n, pa.int64()), pa.nulls(n, pa.int64()), pa.nulls(n, pa.int64()), pa.array([r[1] for r in rows], pa.binary())], HASHED)

    return docs.select("text").mapInArrow(run, "part int, key long, first long, last long, packed binary")


def match_pass(rows: DataFrame, parts: int) -> DataFrame:
    """Ranges of repeated starts (key, first, last), and open anchors (anchor, starts) with their number of starts."""
    names = ["key", "first", "last", "anchor", "starts"]

    def run(batches):
        entries, keys, own_part = [], [], []
        for batch in batches:
            plain = batch.filter(pc.is_null(batch.column(4)))
            if plain.num_rows:
                yield pa.RecordBatch.from_arrays([*plain.columns[1:4], *(pa.nulls(plain.num_rows, pa.int64()) for _ in range(2))], names)
            packed = batch.filter(pc.is_valid(batch.column(4)))
            for part, data in zip(packed.column(0).to_pylist(), packed.column(4).to_pylist(), strict=True):
                n = int(np.frombuffer(data, "<i8", 1)[0])
                own = np.frombuffer(data, ENTRY, offset=8 + 8 * n)
                entries.append(own)
                keys.append(np.frombuffer(data, "<i8", n, 8)[own["text"]])
                own_part.append(np.full(len(own), part, np.int64))
        if not entries:
            return
        e, key, part = np.concatenate(entries), np.concatenate(keys), np.concatenate(own_part)
        del entries, keys, own_part
        high = e["anchor"].astype(np.uint64) | e["anchor2"].astype(np.uint64) << np.uint64(32)
        content = e["content"].astype(np.uint64) | e["content2"].astype(np.uint64) << np.uint64(32)
        order = np.lexsort((content, high, part))
        e, key, part, high, content = e[order], key[order], part[order], high[order], content[order]
        new_anchor = np.concatenate([[True], (high[1:] != high[:-1]) | (part[1:] != part[:-1])])
        new_content = new_anchor | np.concatenate([[True], content[1:] != content[:-1]])
        group = np.cumsum(new_content) - 1
        repeated = ((np.bincount(group) > 1) | (np.bincount(group, e["known"]) > 0))[group]
        tell = repeated & (e["known"] == 0)
        if tell.any():
            first = e["first"][tell].astype(np.int64)
            k = int(tell.sum())
            yield pa.RecordBatch.from_arrays([pa.array(key[tell]), pa.array(first), pa.array(first + e["more"][tell]), pa.nulls(k, pa.int64()), pa.nulls(k, pa.int64())], names)
        anchors = np.cumsum(new_anchor) - 1
        opened = np.bincount(anchors, new_content) > 1
        if opened.any():
            starts = np.bincount(anchors, np.where(new_content, e["more"].astype(np.int64) + 1, 0))[opened].astype(np.int64)
            at = np.flatnonzero(new_anchor)[opened]
            k = len(at)
            value = (high[at] * np.uint64(parts) + part[at].astype(np.uint64)).astype(np.int64)
            yield pa.RecordBatch.from_arrays([*(pa.nulls(k, pa.int64()) for _ in range(3)), pa.array(value), pa.array(starts)], names)

    return rows.repartitionById(parts, "part").mapInArrow(run, "key long, first long, last long, anchor long, starts long")


def bloom(ids: DataFrame, bits: int) -> np.ndarray:
    """A Bloom filter over one column `id`, of fixed size, or-ed together in the cluster."""
    places = ids.select(F.explode(F.array(F.pmod("id", F.lit(bits)), F.pmod(F.shiftright("id", 20), F.lit(bits)))).alias("bit"))
    words = places.groupBy(F.shiftright("bit", 6).alias("word")).agg(F.bit_or(F.expr("shiftleft(1L, cast(bit & 63 as int))")).alias("mask"))
    out = np.zeros(bits // 64, np.int64)
    rows = words.toArrow()  # bounded: bits / 64 rows
    out[rows.column("word").to_numpy()] = rows.column("mask").to_numpy()
    return out.view(np.uint64)


def in_bloom(ids: np.ndarray, mask: np.ndarray) -> np.ndarray:
    bits = len(mask) * 64
    out = np.ones(len(ids), bool)
    for place in (ids % bits, (ids >> 20) % bits):
        out &= (mask[place >> 6] >> (place & 63).astype(np.uint64) & np.uint64(1)).astype(bool)
    return out


def anchor_value(anchor: np.ndarray, parts: int) -> np.ndarray:
    """The part of an anchor's hash that entries carry, as in match_pass."""
    high = anchor // np.uint64(parts) & np.uint64((1 << 48) - 1)
    return (high * np.uint64(parts) + anchor % np.uint64(parts)).astype(np.int64)


def content_pass(docs: DataFrame, open_mask: np.ndarray, parts: int, content_parts: int) -> DataFrame:
    """Contents of stretches whose anchor is open, once per task and content."""
    names = ["part", "key", "first", "content"]

    def run(batches):
        seen: set[int] = set()
        sent: set[int] = set()
        for batch in batches:
            for at in range(0, batch.num_rows, 4000):
                texts, keys = [], []
                for data in encoded(batch.slice(at, 4000).column(0)):
                    if len(data) < LENGTH or (key := text_key(data)) in seen:
                        continue
                    if len(seen) > 300_000:
                        seen.clear()
                    seen.add(key)
                    texts.append(data)
                    keys.append(key)
                rows = []
                for number, first, last, anchor, content in located(texts):
                    value = anchor_value(anchor, parts)
                    for i in np.flatnonzero(in_bloom(value, open_mask)).tolist():
                        if (c := int(content[i])) in sent:  # equal contents were found in the first step
                            continue
                        if len(sent) > 500_000:
                            sent.clear()
                        sent.add(c)
                        t, f = int(number[i]), int(first[i])
                        rows.append((int(value[i]) % content_parts, keys[t], f, texts[t][f : int(last[i]) + LENGTH]))
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.int64()), pa.array([r[2] for r in rows], pa.int64()), pa.array([r[3] for r in rows], pa.binary())], names)

    return docs.select("text").mapInArrow(run, "part int, key long, first long, content binary")


class Level:
    """A suffix array: starts in order of their first LENGTH bytes. Equal strings stand once, with a mark if they are repeated."""

    def __init__(self, strings: np.ndarray, owner: np.ndarray, start: np.ndarray, repeated: np.ndarray):
        self.strings, self.owner, self.start, self.repeated = strings, owner, start, repeated

    def __len__(self):
        return len(self.strings)


class IndexFamily:
    """Logarithmic family of suffix arrays. Contents come in batches; repeated starts come out."""

    def __init__(self):
        self.levels: list[Level] = []

    def suffix_array(self, contents: list[bytes], ids: np.ndarray) -> tuple[Level, list[tuple[np.ndarray, np.ndarray]]]:
        data = np.frombuffer(b"".join(contents), np.uint8)
        sizes = np.array([len(c) for c in contents], np.int64)
        base = np.cumsum(sizes) - sizes
        counts = sizes - LENGTH + 1
        owner = np.repeat(ids, counts)
        start = np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts)
        place = np.repeat(base, counts) + start
        view = np.ndarray((len(data) - LENGTH + 1,), f"V{LENGTH}", data, strides=(1,))
        strings = view[place].view(f"S{LENGTH}")
        order = np.argsort(strings, kind="stable")
        strings, owner, start = strings[order], owner[order], start[order]
        raw = strings.view(f"V{LENGTH}")
        same = raw[1:] == raw[:-1]
        repeated = np.concatenate([[False], same]) | np.concatenate([same, [False]])
        found = [(owner[repeated], start[repeated])]
        first = np.concatenate([[True], ~same])
        return Level(strings[first], owner[first], start[first], repeated[first]), found

    def add(self, contents: list[bytes], ids: np.ndarray) -> list[tuple[np.ndarray, np.ndarray]]:
        """Index a batch; the starts (content id, place) that are now known to be repeated."""
        batch, found = self.suffix_array(contents, ids)
        for level in self.levels:
            at = np.searchsorted(level.strings, batch.strings)
            at[at == len(level)] = 0
            hit = level.strings[at].view(f"V{LENGTH}") == batch.strings.view(f"V{LENGTH}")
            old, new = at[hit], np.flatnonzero(hit)
            for side, index in ((level, old), (batch, new)):
                fresh = index[~side.repeated[index]]
                found.append((side.owner[fresh], side.start[fresh]))
                side.repeated[fresh] = True
        while self.levels and len(self.levels[-1]) <= 2 * len(batch):
            batch = self.merged(self.levels.pop(), batch)
        self.levels.append(batch)
        return found

    def merged(self, a: Level, b: Level) -> Level:
        """Two levels in one, strings that stand in both kept once."""
        at = np.searchsorted(a.strings, b.strings)
        inside = np.minimum(at, len(a) - 1)
        new = a.strings[inside].view(f"V{LENGTH}") != b.strings.view(f"V{LENGTH}")
        to = at[new]
        return Level(*(np.insert(x, to, y[new]) for x, y in ((a.strings, b.strings), (a.owner, b.owner), (a.start, b.start), (a.repeated, b.repeated))))


def index_pass(contents: DataFrame, parts: int) -> DataFrame:
    """Ranges of repeated starts inside contents, by an index family per part."""

    def run(batches):
        families: dict[int, IndexFamily] = {}
        keys: list[int] = []
        firsts: list[int] = []
        found: list[tuple[np.ndarray, np.ndarray]] = []
        held: list[bytes] = []
        part, count = None, 0

        def feed():
            ids = np.arange(len(keys) - len(held), len(keys))
            found.extend(families.setdefault(part, IndexFamily()).add(held, ids))

        def ranges():
            owner = np.concatenate([f[0] for f in found]) if found else np.zeros(0, np.int64)
            start = np.concatenate([f[1] for f in found]) if found else np.zeros(0, np.int64)
            if not len(owner):
                return None
            order = np.lexsort((start, owner))
            owner, start = owner[order], start[order]
            new = np.concatenate([[True], (owner[1:] != owner[:-1]) | (start[1:] > start[:-1] + 1)])
            last = start[np.append(np.flatnonzero(new)[1:] - 1, len(start) - 1)]
            own = owner[new]
            shift = np.array(firsts, np.int64)[own]
            return pa.RecordBatch.from_arrays([pa.array(np.array(keys, np.int64)[own]), pa.array(start[new] + shift), pa.array(last + shift)], ["key", "first", "last"])

        for batch in batches:
            for p, key, first, content in zip(*(batch.column(k).to_pylist() for k in range(4)), strict=True):
                if held and (p != part or count > BATCH_STARTS):
                    feed()
                    held, count = [], 0
                if p != part:
                    if part is not None and (out := ranges()) is not None:
                        yield out
                    families.clear()
                    keys, firsts, found = [], [], []
                part = p
                keys.append(key)
                firsts.append(first)
                held.append(content)
                count += len(content) - LENGTH + 1
        if held:
            feed()
            if (out := ranges()) is not None:
                yield out

    dealt = contents.repartitionById(parts, "part").sortWithinPartitions("part")
    return dealt.mapInArrow(run, "key long, first long, last long")


def repeated_ranges(docs: DataFrame) -> DataFrame:
    """key, first, last: ranges of starts of repeated strings, per text."""
    spark = docs.sparkSession
    least = int(spark.conf.get("spark.sql.shuffle.partitions"))
    size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    parts = max(least, size * 2 // (LENGTH - GRAM) // STRETCHES_PER_PART + 1)
    found = stored(match_pass(hash_pass(docs, parts), parts), "suffix-hashes")
    opened = found.where("anchor is not null")
    starts = opened.agg(F.sum("starts")).first()[0] or 0
    known = found.where("key is not null").select("key", "first", "last")
    if not starts:
        return known
    content_parts = max(least, int(starts) // STARTS_PER_PART + 1)
    mask = bloom(opened.select(F.col("anchor").alias("id")), BLOOM_BITS)
    more = stored(index_pass(content_pass(docs, mask, parts, content_parts), content_parts), "suffix-ranges")
    return known.union(more)


def merged_ranges(ranges: DataFrame) -> DataFrame:
    """key, ranges: of each text the ranges that overlap or touch, joined in the order of their starts. A task holds what one text has left."""

    def run(batches):
        key, open_range, done = None, None, []

        def row():
            kinds = pa.list_(pa.struct([("first", pa.int64()), ("last", pa.int64())]))
            return pa.RecordBatch.from_arrays([pa.array([key], pa.int64()), pa.array([[{"first": a, "last": b} for a, b in [*done, open_range]]], kinds)], ["key", "ranges"])

        for batch in batches:
            for k, first, last in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if k == key and first <= open_range[1] + LENGTH:
                    open_range = (open_range[0], max(open_range[1], last))
                    continue
                if k == key:
                    done.append(open_range)
                else:
                    if key is not None:
                        yield row()
                    key, done = k, []
                open_range = (first, last)
        if key is not None:
            yield row()

    dealt = ranges.repartition(F.col("key")).sortWithinPartitions("key", "first")
    return dealt.select("key", "first", "last").mapInArrow(run, "key long, ranges array<struct<first:long,last:long>>")


def remove_repeats(docs: DataFrame, with_text: bool = False) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 (and kept, the bytes left)."""
    ranges = stored(merged_ranges(repeated_ranges(docs)), "suffix-texts").withColumn("hit", F.lit(True))
    mask = bloom(ranges.select(F.col("key").alias("id")), BLOOM_BITS)

    def send(batches):
        number = 0  # rows that nothing is asked for are spread over all tasks by it
        for batch in batches:
            for at in range(0, batch.num_rows, 4000):
                rows = batch.slice(at, 4000)
                data = encoded(rows.column(1))
                keys = np.array([text_key(x) for x in data], np.int64)
                hit = in_bloom(keys, mask) & np.array([len(x) >= LENGTH for x in data], bool)
                yield pa.RecordBatch.from_arrays(
                    [
                        rows.column(0).cast(pa.int64()),
                        pa.array([k if h else number + i for i, (k, h) in enumerate(zip(keys.tolist(), hit.tolist(), strict=True))], pa.int64()),
                        pa.array(hit, pa.bool_()),
                        pa.array([len(x) for x in data], pa.int64()),
                        pa.array([x if h or with_text else None for x, h in zip(data, hit.tolist(), strict=True)], pa.binary()),
                        pa.array([None if h else hashlib.sha256(x).hexdigest() for x, h in zip(data, hit.tolist(), strict=True)], pa.string()),
                    ],
                    ["doc_id", "key", "hit", "n_bytes", "data", "sha"],
                )
                number += rows.num_rows

    def finish(batches):
        for batch in batches:
            out = []
            for doc, n, data, sha, spans in zip(*(batch.column(k).to_pylist() for k in range(5)), strict=True):
                merged: list[list[int]] = []
                for s in sorted((x["first"], x["last"] + LENGTH) for x in spans or []):
                    if merged and s[0] <= merged[-1][1]:
                        merged[-1][1] = max(merged[-1][1], s[1])
                    else:
                        merged.append(list(s))
                if data is not None:
                    kept = b"".join(data[a:b] for a, b in zip([0, *(m[1] for m in merged)], [*(m[0] for m in merged), n], strict=True))
                    sha = hashlib.sha256(kept).hexdigest()
                out.append((doc, n, sum(b - a for a, b in merged), len(merged), sha, kept if with_text else None))
            columns = list(zip(*out, strict=True)) if out else [[]] * 6
            types = [pa.int64()] * 4 + [pa.string(), pa.binary()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types, strict=True)], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"])

    sent = docs.select("doc_id", "text").mapInArrow(send, "doc_id long, key long, hit boolean, n_bytes long, data binary, sha string")
    both = sent.join(ranges, ["key", "hit"], "left").select("doc_id", "n_bytes", "data", "sha", "ranges")
    out = both.mapInArrow(finish, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary")
    return out if with_text else out.drop("kept")


def op10_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(read_table(spark, sf_dir, "documents"))
