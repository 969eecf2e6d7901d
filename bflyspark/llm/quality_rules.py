"""Quality rules by distribution divergence.

A document's character-class histogram and its histogram over common words are compared with
references of each known language by Jensen-Shannon distance. References are sums over all
documents of that language, so they follow the corpus; they have a fixed number of cells.

Defined results: null text counts as empty (no words: base rule fails). Null or unknown languages are
held against every reference. Texts under the minimum lengths are not judged by divergence. Repeated
rows, ties and null ids are judged row by row. Extra columns are left alone.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import per_worker, read_table

# Frequent function words of each language.
COMMON_WORDS = {
    "de": "der die das und ist in zu den von mit auf für im ein eine nicht des dem als auch es an sich bei".split(),
    "en": "the of and to in a is that for it as was with be by on not he this are or at from his have".split(),
    "es": "de la que el en y a los se del las un por con no una su para es al lo como más o pero".split(),
    "fr": "de la le et les des en un du une que est pour qui dans a par plus pas au sur ne se ce avec".split(),
}
# Classes of characters, in the order of the histogram's cells.
CLASSES = ["ascii letter", "other letter", "digit", "blank", "line break", "sentence mark", "symbol", "other"]

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SYMBOL = re.compile(r"[#*$%&|<>]")
WINDOW = 8

OUT = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, char_distance double, word_distance double, kept boolean"


@dataclass(frozen=True)
class DivergenceLimits:
    """Above a distance (0 to 1) the text is rejected; below a length it isn't judged by that histogram."""

    char_distance: float = 0.31
    word_distance: float = 0.45
    min_chars: int = 200
    min_words: int = 80


def class_table() -> np.ndarray:
    """The class of each code point below 0x300; those above count as letters or as other."""
    table = np.full(0x300, 7, np.int8)
    for c in range(0x300):
        s = chr(c)
        if s in "\n\r\x0b\x0c":
            table[c] = 4
        elif s in " \t\xa0":
            table[c] = 3
        elif s.isdigit():
            table[c] = 2
        elif s.isalpha():
            table[c] = 0 if c < 128 else 1
        elif s in ".,;:!?'\"()-":
            table[c] = 5
        elif s.isprintable():
            table[c] = 6
    return table


def class_histogram(text: str, table: np.ndarray) -> np.ndarray:
    points = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
    low = points[points < 0x300]
    out = np.bincount(table[low], minlength=len(CLASSES)).astype(np.float64)
    if len(low) < len(points):
        high = points[points >= 0x300]
        punct = int(((high >= 0x2000) & (high < 0x2070)).sum())
        out[5] += punct
        out[1] += len(high) - punct
    return out


def common_vocabulary() -> dict[str, int]:
    """Cell of each common word; one more cell, the last, holds all other words."""
    return {w: i for i, w in enumerate(sorted({w for words in COMMON_WORDS.values() for w in words}))}


def word_histogram(words: list[str], vocabulary: dict[str, int]) -> np.ndarray:
    other = len(vocabulary)
    cells = [vocabulary.get(w, other) for w in words]
    return np.bincount(np.array(cells, np.int64), minlength=other + 1).astype(np.float64)


def jensen_shannon(p: np.ndarray, q: np.ndarray) -> float:
    """Jensen-Shannon distance to base 2: 0 for equal histograms, 1 for disjoint ones."""
    if not p.sum() or not q.sum():
        return 0.0
    p, q = p / p.sum(), q / q.sum()
    m = (p + q) / 2
    with np.errstate(divide="ignore", invalid="ignore"):
        kl = [np.where(x > 0, x * np.log2(x / m), 0.0).sum() for x in (p, q)]
    return float(np.sqrt(max(0.0, min(1.0, (kl[0] + kl[1]) / 2))))


def repeated_words(words: list[str]) -> int:
    """Words inside windows of eight that the text has twice or more, the first one included."""
    n = len(words) - WINDOW + 1
    if n < 2:
        return 0
    number: dict[str, int] = {}
    ranks = np.array([number.setdefault(w, len(number)) for w in words], np.int64)
    if len(number) == len(words):
        return 0
    for step in (1, 2, 4):  # windows of 2, 4 and 8 words get equal numbers exactly when they are equal
        pairs = ranks[:-step] * (int(ranks.max()) + 1) + ranks[step:]
        kinds, ranks = np.unique(pairs, return_inverse=True)
        if len(kinds) == len(pairs):
            return 0
    again = (np.bincount(ranks) > 1)[ranks]
    edge = np.zeros(len(words) + 1, np.int64)
    np.add.at(edge, np.flatnonzero(again), 1)
    np.add.at(edge, np.flatnonzero(again) + WINDOW, -1)
    return int((np.cumsum(edge[:-1]) > 0).sum())


def repeated_lines(text: str) -> int:
    seen: set[str] = set()
    n = 0
    for line in text.split("\n"):
        if line in seen:
            n += 1
        elif WORD.search(line):
            seen.add(line)
    return n


def _tools():
    return per_worker("quality_rules", 0, lambda: (class_table(), common_vocabulary()))


def references(docs: DataFrame) -> dict[str, tuple[np.ndarray, np.ndarray]]:
    """Per known language, the sums of both histograms over all its documents.

    Each task adds up its own rows, so a row per language and task is shuffled; the driver gets
    at most as many rows as there are known languages.
    """
    names = sorted(COMMON_WORDS)

    def partial(batches):
        table, vocabulary = _tools()
        sums = {k: [np.zeros(len(CLASSES)), np.zeros(len(vocabulary) + 1)] for k in names}
        for batch in batches:
            for text, lang in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if text and lang in sums:
                    sums[lang][0] += class_histogram(text, table)
                    sums[lang][1] += word_histogram(WORD.findall(text.lower()), vocabulary)
        rows = [(k, cell, v) for k, both in sums.items() for cell, v in enumerate(np.concatenate(both)) if v]
        yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.string()), pa.array([r[1] for r in rows], pa.int32()), pa.array([r[2] for r in rows], pa.float64())], ["lang", "cell", "n"])

    total = docs.select("text", "lang").mapInArrow(partial, "lang string, cell int, n double").groupBy("lang", "cell").sum("n")
    cells = len(CLASSES) + len(common_vocabulary()) + 1
    out: dict[str, np.ndarray] = {}
    for lang, cell, n in total.collect():  # bounded: languages times cells
        out.setdefault(lang, np.zeros(cells))[cell] = n
    return {k: (v[: len(CLASSES)], v[len(CLASSES) :]) for k, v in out.items()}


def measure(text: str | None, lang: str | None, refs: dict, limits: DivergenceLimits) -> tuple:
    """All columns of OUT but doc_id for one text."""
    table, vocabulary = _tools()
    text = text or ""
    words = WORD.findall(text)
    n, chars = len(words), sum(map(len, words))
    repeat = repeated_words(words)
    failed = n < 20 or 100 * repeat > 30 * n
    near = [refs[lang]] if lang in refs else list(refs.values())
    char_d = word_d = None
    if near and len(text) >= limits.min_chars:
        own = class_histogram(text, table)
        char_d = min(jensen_shannon(own, r[0]) for r in near)
    if near and n >= limits.min_words:
        own = word_histogram([w.lower() for w in words], vocabulary)
        word_d = min(jensen_shannon(own, r[1]) for r in near)
    bad = (char_d or 0) > limits.char_distance or (word_d or 0) > limits.word_distance
    return n, chars, len(SYMBOL.findall(text)), repeated_lines(text), repeat, failed, char_d, word_d, not failed and not bad


def judge(docs: DataFrame, limits: DivergenceLimits = DivergenceLimits(), refs: dict | None = None) -> DataFrame:
    """One row per document with the rule's figures and verdict."""
    refs = references(docs) if refs is None else refs
    names = [f.split()[0] for f in OUT.split(", ")]
    kinds = {"long": pa.int64(), "boolean": pa.bool_(), "double": pa.float64()}
    types = [kinds[f.split()[1]] for f in OUT.split(", ")]

    def run(batches):
        for batch in batches:
            rows = [(i, *measure(t, g, refs, limits)) for i, t, g in zip(*(batch.column(k).to_pylist() for k in range(3)), strict=True)]
            columns = zip(*rows, strict=True) if rows else [[]] * len(names)
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types, strict=True)], names)

    return docs.select("doc_id", "text", "lang").mapInArrow(run, OUT)


def keep_good(docs: DataFrame, limits: DivergenceLimits = DivergenceLimits()) -> DataFrame:
    """The rows whose verdict is to keep, with all their columns."""
    refs = references(docs)
    at = [docs.columns.index("text"), docs.columns.index("lang")]

    def run(batches):
        for batch in batches:
            texts, langs = (batch.column(k).to_pylist() for k in at)
            yield batch.filter(pa.array([measure(t, g, refs, limits)[-1] for t, g in zip(texts, langs, strict=True)], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def op1_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(read_table(spark, sf_dir, "documents"))
