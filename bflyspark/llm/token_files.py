"""Token files in canonical length-limited Huffman code.

Texts are encoded to ids with the tokenizers library as it comes: cut at the vocabulary's added tokens
first, then into pieces, with a memo of pieces of bounded size that is dropped when encoding ends. Ids are
counted over the whole corpus, which gives one code book of fixed size (package-merge under a length
limit, then canonical codes). Documents are coded, dealt by ranges of doc_id and packed in order into
segments. A segment holds an index of documents, checkpoints (the bit offset of every block of
BLOCK ids) and the bit stream; blocks decode on their own, all blocks of a segment side by side, by
one table look-up per id.

A file is the segments of one range of doc_id, kept as binary rows of Parquet, so any file system that
Spark writes to will do. start counts the ids before a document over all files.

Defined results: null text encodes as empty, so such a document has its end id alone. Null ids come
first; repeated rows and ties keep one entry each. An empty table gives no files and no rows.
"""

from __future__ import annotations

import json
import re
import struct
import zlib
from itertools import chain, pairwise

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import forget, per_worker, read_table, stored
from .pieces import Cutter, Memo

END_ID = 2
BLOCK = 1024
SEGMENT_BYTES = 1 << 20
FILE_BYTES = 24 << 20
FILES_BROADCAST = 1 << 20  # a row of 16 bytes per file; beyond it the starts are joined by a shuffle
IDS_AT_ONCE = 1 << 18  # ids that a task codes side by side
CODE_LIMIT = 18
PIECES_KEPT = 450_000
MAGIC = b"BFH1"


class PieceEncoder:
    """Packed ids of texts by the tokenizers library. Each distinct piece is encoded once."""

    def __init__(self, path: str, pattern: str):
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as described:
            own = json.load(described)
        added = sorted((t["content"] for t in own["added_tokens"]), key=len, reverse=True)
        self.added = re.compile(f"({'|'.join(map(re.escape, added))})") if added else None
        # Added tokens that take in blanks or wait for word ends, and normalizers, are left to the library.
        self.whole = bool(own["normalizer"]) or any(t[k] for t in own["added_tokens"] for k in ("single_word", "lstrip", "rstrip")) or any("\n" in t for t in added)
        self.cut = Cutter(pattern)
        self.dtype = np.dtype("<u2" if self.tokenizer.get_vocab_size() < 1 << 16 else "<u4")
        self.mark = self.tokenizer.encode("\n", add_special_tokens=False).ids
        self.known = Memo(PIECES_KEPT, self.fill)

    def fill(self, pieces: list[str]) -> list[bytes]:
        """Packed ids of new pieces. Lines can't grow together, so pieces without blanks at their end go in as lines."""
        out: dict[str, bytes] = {}
        lined = [p for p in pieces if p.strip() and "\n" not in p]
        width = self.dtype.itemsize
        for at in range(0, len(lined), 64):
            part = lined[at : at + 64]
            ids = np.array(self.tokenizer.encode_batch_fast(["\n".join(part)], add_special_tokens=False)[0].ids, self.dtype)
            breaks = np.flatnonzero(ids == self.mark[0]) if len(self.mark) == 1 else []
            if len(breaks) == len(part) - 1:
                packed = ids.tobytes()
                starts, ends = [0, *((breaks + 1) * width).tolist()], [*(breaks * width).tolist(), len(packed)]
                out.update((p, packed[a:b]) for p, a, b in zip(part, starts, ends, strict=True))
        rest = [p for p in pieces if p not in out]
        out.update((p, np.array(e.ids, self.dtype).tobytes()) for p, e in zip(rest, self.tokenizer.encode_batch_fast(rest, add_special_tokens=False), strict=True))
        return [out[p] for p in pieces]

    def pieces(self, text: str) -> list[str]:
        """Added tokens as they are, and the pieces of what lies between them."""
        if self.added is None or not self.added.search(text):
            return self.cut(text)
        parts = self.added.split(text)
        return list(chain.from_iterable([p] if k % 2 else self.cut(p) for k, p in enumerate(parts)))

    def __call__(self, texts: list[str | None], end: int) -> list[bytes]:
        if self.whole:
            return [np.array([*e.ids, end], self.dtype).tobytes() for e in self.tokenizer.encode_batch_fast([t or "" for t in texts], add_special_tokens=False)]
        cut = [self.pieces(t) if t else [] for t in texts]
        codes = self.known(list(chain.from_iterable(cut)))
        tail, at, out = np.array([end], self.dtype).tobytes(), 0, []
        for pieces in cut:
            out.append(b"".join(codes[at : at + len(pieces)]) + tail)
            at += len(pieces)
        return out


def code_lengths(counts: np.ndarray, limit: int = CODE_LIMIT) -> np.ndarray:
    """Lengths of an optimal prefix code with no code over the limit, by package-merge."""
    used = np.flatnonzero(counts)
    out = np.zeros(len(counts), np.uint8)
    if len(used) < 2:
        out[used] = 1
        return out
    limit = max(limit, int(len(used) - 1).bit_length())
    order = used[np.argsort(counts[used], kind="stable")]
    items = counts[order].astype(np.int64)
    is_item, level = [], items
    for _ in range(limit):
        packages = level[: len(level) // 2 * 2].reshape(-1, 2).sum(axis=1) if is_item else items[:0]
        both = np.concatenate([items, packages])
        rank = np.argsort(both, kind="stable")
        is_item.append(rank < len(items))
        level = both[rank]
    lengths = np.zeros(len(items), np.int64)
    take = 2 * len(items) - 2
    for flags in reversed(is_item):
        chosen = int(flags[:take].sum())
        lengths[:chosen] += 1
        take = 2 * (take - chosen)
    out[order] = lengths
    return out


def canonical_codes(lengths: np.ndarray) -> np.ndarray:
    """Codes in order of length and then id."""
    codes = np.zeros(len(lengths), np.uint32)
    used = np.flatnonzero(lengths)
    order = used[np.argsort(lengths[used], kind="stable")]
    code, before = 0, 0
    for i in order.tolist():
        n = int(lengths[i])
        code <<= n - before
        before = n
        codes[i] = code
        code += 1
    return codes


class CodeBook:
    def __init__(self, lengths: np.ndarray):
        self.lengths = lengths
        self.codes = canonical_codes(lengths)
        self.width = int(lengths.max()) if len(lengths) else 1
        self._tables = None

    def tables(self) -> tuple[np.ndarray, np.ndarray]:
        """For each window of `width` bits, the id that its first code stands for and that code's length."""
        if self._tables is None:
            symbol, size = np.zeros(1 << self.width, np.uint32), np.ones(1 << self.width, np.uint8)
            used = np.flatnonzero(self.lengths)
            used = used[np.lexsort((used, self.lengths[used]))]
            span = 1 << (self.width - self.lengths[used].astype(np.int64))
            symbol[: span.sum()] = np.repeat(used, span)
            size[: span.sum()] = np.repeat(self.lengths[used], span)
            self._tables = symbol, size
        return self._tables

    def encode(self, docs: list[np.ndarray]) -> list[tuple[bytes, np.ndarray]]:
        """Bits of each document from a byte of its own, and the bit offset of each of its blocks."""
        sizes = np.array([len(d) for d in docs], np.int64)
        ids = np.concatenate(docs)
        bits = self.lengths[ids].astype(np.int64)
        ends = np.cumsum(bits)
        first = np.cumsum(sizes) - sizes
        lead = np.concatenate([[0], ends])[first]  # bits before each document
        own = np.concatenate([[0], ends])[first + sizes] - lead
        room = (own + 7) // 8 * 8
        base = np.cumsum(room) - room
        at = ends - bits + np.repeat(base - lead, sizes)
        word, free = at >> 5, 64 - (at & 31) - bits
        value = self.codes[ids].astype(np.uint64) << free.astype(np.uint64)
        n = int(room.sum() // 32) + 3
        words = np.bincount(word, (value >> np.uint64(32)).astype(np.float64), n) + np.bincount(word + 1, (value & np.uint64(0xFFFFFFFF)).astype(np.float64), n)
        stream = words.astype(np.uint32).astype(">u4").tobytes()
        local = at - np.repeat(base, sizes)
        return [(stream[b // 8 : (b + r) // 8], local[f : f + k : BLOCK].astype(np.uint32)) for b, r, f, k in zip(base.tolist(), room.tolist(), first.tolist(), sizes.tolist(), strict=True)]

    def decode(self, stream: bytes, starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
        """Ids of all blocks, one after the other; starts are bit offsets, sizes are counts of ids."""
        symbol, size = self.tables()
        data = np.frombuffer(stream + bytes(8), np.uint8).astype(np.uint32)
        window = data[:-3] << 24 | data[1:-2] << 16 | data[2:-1] << 8 | data[3:]
        order = np.argsort(-sizes, kind="stable")
        at, left = starts[order].astype(np.int64), sizes[order]
        to = (np.cumsum(sizes) - sizes)[order]
        out = np.empty(int(sizes.sum()), np.uint32)
        active = np.searchsorted(-left, -np.arange(int(left[0]) if len(left) else 0), side="left")
        mask = (1 << self.width) - 1
        for step, n in enumerate(active.tolist()):
            pos = at[:n]
            code = window[pos >> 3] >> (32 - self.width - (pos & 7)).astype(np.uint32) & mask
            out[to[:n] + step] = symbol[code]
            at[:n] = pos + size[code]
        return out


def pack_segment(docs: list[tuple[int | None, int, bytes, np.ndarray]]) -> bytes:
    """(doc_id, ids, bits, checkpoints) of documents in order -> one self-contained segment."""
    known = np.array([d[0] is not None for d in docs], np.uint8)
    head = np.array([[d[0] or 0, d[1], len(d[2]), len(d[3])] for d in docs], np.int64).reshape(-1, 4)
    marks = np.concatenate([d[3] for d in docs]).astype("<u4")
    return MAGIC + struct.pack("<II", len(docs), len(marks)) + known.tobytes() + head.astype("<i8").tobytes() + marks.tobytes() + b"".join(d[2] for d in docs)


def unpack_segment(data: bytes, book: CodeBook) -> list[tuple[int | None, np.ndarray]]:
    """(doc_id, ids) of a segment's documents, in order."""
    if data[:4] != MAGIC:
        raise ValueError("not a token segment")
    n, marks = struct.unpack_from("<II", data, 4)
    at = 12
    known = np.frombuffer(data, np.uint8, n, at)
    head = np.frombuffer(data, "<i8", 4 * n, at + n).reshape(-1, 4)
    checkpoints = np.frombuffer(data, "<u4", marks, at + 33 * n).astype(np.int64)
    stream = data[at + 33 * n + 4 * marks :]
    base = (np.cumsum(head[:, 2]) - head[:, 2]) * 8
    blocks = head[:, 3]
    sizes = np.full(marks, BLOCK, np.int64)
    sizes[np.cumsum(blocks) - 1] = head[:, 1] - (blocks - 1) * BLOCK
    ids = book.decode(stream, checkpoints + np.repeat(base, blocks), sizes)
    parts = np.split(ids, np.cumsum(head[:, 1])[:-1])
    return [(int(i) if k else None, p) for i, k, p in zip(head[:, 0].tolist(), known.tolist(), parts, strict=True)]


def token_table(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """doc_id, n_tokens, ids (packed little-endian, the end id last)."""

    def run(batches):
        encoder = per_worker("token_files", (path, pattern), lambda: PieceEncoder(path, pattern))
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                rows = batch.slice(at, 256)
                ids = encoder(rows.column(1).to_pylist(), END_ID)
                n = [len(x) // encoder.dtype.itemsize for x in ids]
                yield pa.RecordBatch.from_arrays([rows.column(0).cast(pa.int64()), pa.array(n, pa.int64()), pa.array(ids, pa.binary())], ["doc_id", "n_tokens", "ids"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_tokens long, ids binary")


def id_dtype(path: str) -> np.dtype:
    from tokenizers import Tokenizer

    return np.dtype("<u2" if Tokenizer.from_file(path).get_vocab_size() < 1 << 16 else "<u4")


def global_counts(tokens: DataFrame, dtype: np.dtype) -> np.ndarray:
    """How often each id occurs in the corpus; every task sums its own first. Bounded by the vocabulary."""

    def run(batches):
        forget("token_files")
        total = np.zeros(0, np.int64)
        for batch in batches:
            for at in range(0, batch.num_rows, 200):
                c = np.bincount(np.frombuffer(b"".join(batch.column(0).slice(at, 200).to_pylist()), dtype), minlength=len(total))
                c[: len(total)] += total
                total = c
        used = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(used, pa.int64()), pa.array(total[used], pa.int64())], ["id", "n"])

    rows = tokens.select("ids").mapInArrow(run, "id long, n long").groupBy("id").agg(F.sum("n").alias("n")).toArrow()
    ids, n = rows.column("id").to_numpy(), rows.column("n").to_numpy()
    out = np.zeros(int(ids.max()) + 1 if len(ids) else 1, np.int64)
    out[ids] = n
    return out


def write_files(docs: DataFrame, path: str, pattern: str) -> tuple[DataFrame, CodeBook]:
    """Segments (file, place, tokens_before, tokens, data) in ascending doc_id, and the code book."""
    dtype = id_dtype(path)
    tokens = stored(token_table(docs, path, pattern), "token-ids")
    counts = global_counts(tokens, dtype)
    book = CodeBook(code_lengths(counts))
    coded_bytes = int((counts * book.lengths).sum()) // 8
    files = max(1, coded_bytes // FILE_BYTES)

    def code(batch):
        """file, doc_id, n_tokens, bits and checkpoints of a batch's documents, some IDS_AT_ONCE ids at a time."""
        part = (np.cumsum(batch.column(2).to_numpy()) // IDS_AT_ONCE).tolist()
        edges = [0, *(i for i in range(1, len(part)) if part[i] != part[i - 1]), len(part)] if part else []
        for a, b in pairwise(edges):
            f, doc, n, ids = (c.to_pylist() for c in batch.slice(a, b - a).columns)
            yield from ((*row, *coded) for row, coded in zip(zip(f, doc, n, strict=True), book.encode([np.frombuffer(x, dtype) for x in ids]), strict=True))

    def pack(batches):
        forget("token_files")
        file, place, before, size, docs = None, 0, 0, 0, []

        def flush():
            n = sum(d[1] for d in docs)
            return pa.RecordBatch.from_arrays([pa.array([file], pa.int32()), pa.array([place], pa.int32()), pa.array([before], pa.int64()), pa.array([n], pa.int64()), pa.array([pack_segment(docs)], pa.binary())], ["file", "place", "tokens_before", "tokens", "data"])

        for batch in batches:
            for f, doc, n, bits, marks in code(batch):
                if docs and (f != file or size > SEGMENT_BYTES):
                    yield flush()
                    place, before = (place + 1, before + sum(d[1] for d in docs)) if f == file else (0, 0)
                    docs, size = [], 0
                elif f != file:
                    place, before = 0, 0
                file = f
                docs.append((doc, n, bits, marks))
                size += len(bits)
        if docs:
            yield flush()

    # Ranges are drawn from two narrow columns; rows that agree in both are told apart inside their file.
    order = (F.col("doc_id").asc_nulls_first(), F.col("n_tokens"))
    dealt = tokens.repartitionByRange(files, *order).withColumn("file", F.spark_partition_id()).sortWithinPartitions(*order, F.crc32("ids"))
    packed = dealt.select("file", "doc_id", "n_tokens", "ids").mapInArrow(pack, "file int, place int, tokens_before long, tokens long, data binary")
    return stored(packed, "token-files", 8 << 20), book


def read_files(files: DataFrame, book: CodeBook) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document, decoded from the files."""
    totals = files.groupBy("file").agg(F.sum("tokens").alias("n"))
    first = totals.select("file", (F.sum("n").over(Window.orderBy("file")) - F.col("n")).alias("first"))  # a row per file
    if files.select("file").distinct().count() <= FILES_BROADCAST:
        first = F.broadcast(first)

    def run(batches):
        for batch in batches:
            for i in range(batch.num_rows):  # one segment at a time
                start, data = batch.column(0)[i].as_py(), batch.column(1)[i].as_py()
                docs = unpack_segment(data, book)
                n = np.array([len(d[1]) for d in docs], np.int64)
                starts = start + np.cumsum(n) - n
                crc = [zlib.crc32(np.ascontiguousarray(d[1], "<u4").data) for d in docs]
                yield pa.RecordBatch.from_arrays([pa.array([d[0] for d in docs], pa.int64()), pa.array(starts), pa.array(n), pa.array(crc, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])

    placed = files.join(first, "file").select((F.col("first") + F.col("tokens_before")).alias("start"), "data")
    return placed.mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def op3_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    docs = read_table(spark, sf_dir, "documents")
    return read_files(*write_files(docs, public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.PATTERN))
