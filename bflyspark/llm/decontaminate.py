"""Benchmark decontamination by spaced-seed hashing.

Words of the benchmark get numbers; all other words are 0. Fixed masks pick some of twelve successive
words and skip the others, so a substituted word under a skipped place doesn't hide a match. Seeds of
a document that also occur in the benchmark name an item and a diagonal; there the words of both are
held against each other and the best stretch (matches minus twice the mismatches) is measured.
A document is contaminated if some stretch has enough matching words, or the aligned item as a whole has
that share of them. For items of LIGHT_ITEM words or more, three words in a row are a seed too, once a
diagonal has as many of them as an item with the share of matching words can't fall below.

The benchmark goes out with the plan in blocks of at most BLOCK_WORDS words. Small benchmarks are one
block; larger ones are several, each a further step of the same pass over the documents.

Defined results: null texts and texts without words match nothing; null or short items (under
MIN_ITEM words) are left out, as no leak can be told from chance there. Repeats, ties and null ids
need no care. An empty benchmark leaves all documents clean. Extra columns are left alone.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import read_table

# Places that a seed looks at (1) or skips (0).
MASKS = ("111011011101", "110110111011", "101111001111", "11111111", "111101111", "11101110111")
LIGHT, LIGHT_ITEM = "111", 9
WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
BLOCK_WORDS = 1_000_000
MIN_ITEM = 5
SPAN = 12


@dataclass(frozen=True)
class Limits:
    """A stretch counts if it has so many matching words, or that share of a shorter item."""

    words: int = 12
    share: float = 0.75


def words_of(text: str | None) -> list[str]:
    return WORD.findall((text or "").lower())


def seeds(ids: np.ndarray, mask: str) -> tuple[np.ndarray, np.ndarray]:
    """Start and hash of each place where the mask sees known words alone."""
    n = len(ids) - len(mask) + 1
    if n <= 0:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    at = [k for k, c in enumerate(mask) if c == "1"]
    known = ids > 0
    whole = known[at[0] : at[0] + n].copy()
    for k in at[1:]:
        whole &= known[k : k + n]
    starts = np.flatnonzero(whole)
    h = np.full(len(starts), len(mask), np.uint64)
    for k in at:
        h = (h ^ ids[starts + k].astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
        h ^= h >> np.uint64(31)
    return starts, h


class Block:
    """Seeds and words of some items."""

    def __init__(self, items: list[tuple[int, str]]):
        by_text: dict[tuple[str, ...], list[int]] = {}
        for item, text in items:
            words = tuple(words_of(text))
            if len(words) >= MIN_ITEM:
                by_text.setdefault(words, []).append(item)
        self.vocabulary: dict[str, int] = {}
        self.names = list(by_text.values())
        self.ids = [np.array([self.vocabulary.setdefault(w, len(self.vocabulary) + 1) for w in words], np.int64) for words in by_text]
        short = sorted({len(x) for x in self.ids if len(x) < SPAN})
        self.masks = [*MASKS, *("1" * n for n in short if "1" * n not in MASKS)]
        self.light = [x if len(x) >= LIGHT_ITEM else x[:0] for x in self.ids]
        self.seeds = []
        for mask in [*self.masks, LIGHT]:
            found = [(h, i, s) for i, x in enumerate(self.light if mask == LIGHT else self.ids) for s, h in zip(*(v.tolist() for v in seeds(x, mask)), strict=True) if len(x) >= SPAN or len(mask) == len(x) or mask in (*MASKS, LIGHT)]
            found.sort()
            self.seeds.append((np.array([f[0] for f in found], np.uint64), np.array([f[1] for f in found], np.int64), np.array([f[2] for f in found], np.int64)))


def least_seeds(n: np.ndarray, share: float) -> np.ndarray:
    """Three matching words in a row that n words have at least if that share matches: k others leave k + 1 runs, and each run costs two."""
    k = n - np.ceil(share * n - 1e-9)
    return np.maximum(n - k - 2 * (k + 1), 1)


def best_stretch(match: np.ndarray) -> int:
    """Matching words in the stretch with the largest matches minus twice mismatches."""
    score = np.concatenate([[0], np.cumsum(np.where(match, 1, -2))])
    low = np.minimum.accumulate(score)
    end = int(np.argmax(score - low))
    start = int(np.flatnonzero(score[: end + 1] == low[end])[-1])
    return int(match[start:end].sum())


def find(texts: list[str | None], block: Block, limits: Limits) -> list[dict[int, int]]:
    """For each text, the items it holds and the matching words of each."""
    out: list[dict[int, int]] = [{} for _ in texts]
    get = block.vocabulary.get
    numbers = []
    for t in texts:
        numbers.append(np.array([get(w, 0) for w in words_of(t)] + [0] * SPAN, np.int64))
    if not numbers or not block.ids:
        return out
    sizes = np.array([len(x) for x in numbers])
    first = np.cumsum(sizes) - sizes
    line = np.concatenate(numbers)
    diagonals: set[tuple[int, int]] = set()
    longest = max(len(x) for x in block.ids)
    need = least_seeds(np.array([len(x) for x in block.ids]), limits.share)
    for mask, (hashes, items, offsets) in zip([*block.masks, LIGHT], block.seeds, strict=True):
        if not len(hashes):
            continue
        starts, h = seeds(line, mask)
        low, high = np.searchsorted(hashes, h, "left"), np.searchsorted(hashes, h, "right")
        hit = np.flatnonzero(high > low)
        counts = (high - low)[hit]
        entry = np.repeat(low[hit], counts) + np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts)
        if mask == LIGHT:
            width = 2 * (len(line) + longest)
            keys, times = np.unique(items[entry] * width + np.repeat(starts[hit], counts) - offsets[entry] + longest, return_counts=True)
            keys = keys[times >= need[keys // width]]
            diagonals.update(zip((keys // width).tolist(), (keys % width - longest).tolist(), strict=True))
            continue
        diagonals.update(zip(items[entry].tolist(), (np.repeat(starts[hit], counts) - offsets[entry]).tolist(), strict=True))
    owner = np.searchsorted(first, np.arange(len(line)), "right") - 1 if diagonals else None
    for item, at in diagonals:
        own = block.ids[item]
        a, b = max(0, at), min(len(line), at + len(own))
        # The seed lies in one document; a diagonal may stick out of it, where nothing counts.
        match = line[a:b] == own[a - at : b - at]
        docs = owner[a:b]
        for doc in np.unique(docs[match]).tolist():
            inside = match & (docs == doc)
            n = best_stretch(inside)
            if n < min(limits.words, limits.share * len(own)) and inside.sum() >= limits.share * len(own):
                n = int(inside.sum())
            if n >= min(limits.words, limits.share * len(own)):
                for name in block.names[item]:
                    out[doc][name] = max(n, out[doc].get(name, 0))
    return out


def blocks_of(benchmark: DataFrame) -> list[Block]:
    """The benchmark in blocks of bounded size, by hash of the item."""
    items = benchmark.select("item_id", "text").where(F.col("text").isNotNull())
    words = items.agg(F.sum(F.regexp_count("text", F.lit(r"\S+")))).first()[0] or 0
    n = -(-words // BLOCK_WORDS) or 1
    return [Block([(r.item_id, r.text) for r in items.where(F.pmod(F.xxhash64("text"), F.lit(n)) == k).collect()]) for k in range(n)]


def scan(docs: DataFrame, benchmark: DataFrame, limits: Limits = Limits()) -> DataFrame:
    """doc_id, contaminated, n_items, items (ids of benchmark items found), matched_words (most in one item)."""
    out = docs.select("doc_id", "text", F.array().cast("array<long>").alias("items"), F.lit(0).cast("long").alias("matched_words"))

    def step(block: Block):
        def run(batches):
            for batch in batches:
                for at in range(0, batch.num_rows, 1000):
                    rows = batch.slice(at, 1000)
                    found = find(rows.column(1).to_pylist(), block, limits)
                    items = [sorted({*old, *new}) for old, new in zip(rows.column(2).to_pylist(), found, strict=True)]
                    words = [max([old, *new.values()]) for old, new in zip(rows.column(3).to_pylist(), found, strict=True)]
                    yield pa.RecordBatch.from_arrays([rows.column(0), rows.column(1), pa.array(items, pa.list_(pa.int64())), pa.array(words, pa.int64())], ["doc_id", "text", "items", "matched_words"])

        return run

    schema = out.schema
    for block in blocks_of(benchmark):
        out = out.mapInArrow(step(block), schema)
    return out.select("doc_id", (F.size("items") > 0).alias("contaminated"), F.size("items").cast("long").alias("n_items"), "items", "matched_words")


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, limits: Limits = Limits()) -> DataFrame:
    """The clean rows, with all their columns."""
    at = docs.columns.index("text")

    def step(block: Block):
        def run(batches):
            for batch in batches:
                for start in range(0, batch.num_rows, 1000):
                    rows = batch.slice(start, 1000)
                    found = find(rows.column(at).to_pylist(), block, limits)
                    yield rows.filter(pa.array([not x for x in found], pa.bool_()))

        return run

    schema = docs.schema
    for block in blocks_of(benchmark):
        docs = docs.mapInArrow(step(block), schema)
    return docs


def op9_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "benchmark"))
