"""Byte-level BPE by automaton and backtracking.

The bytes of a piece are read as Latin-1 characters, so a pyahocorasick automaton over the vocabulary
finds the longest token that starts at each place. Tokens are laid from the left; a token may follow
another only if the two stay apart when their joined bytes are merged (kept in a memo). Where no
token fits, the last one is taken back and its next shorter prefix is tried. A bit per place remembers
dead ends, so each place is left once and the work is linear in the piece.

Defined results: null text encodes as empty; an empty text has no ids. Every row is encoded on its
own, so repeats, ties and null ids need no care; extra columns are left alone.
"""

from __future__ import annotations

import base64
import hashlib

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import per_worker, read_table
from .pieces import Cutter, Memo

CACHE = 220_000  # pieces in a generation of the memo
PAIRS = 400_000  # token pairs likewise
NONE = 1 << 60


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        return {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, lines)}


def merged(piece: bytes, ranks: dict[bytes, int]) -> list[bytes]:
    """Reference merging: join the neighbours of lowest rank, leftmost first, until none joins."""
    parts = [piece[i : i + 1] for i in range(len(piece))]
    while len(parts) > 1:
        best, at = min((ranks.get(a + b, NONE), i) for i, (a, b) in enumerate(zip(parts, parts[1:], strict=False)))
        if best == NONE:
            break
        parts[at : at + 2] = [parts[at] + parts[at + 1]]
    return parts


class Encoder:
    """Encodes pieces; texts are cut into pieces by the pattern."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        import ahocorasick

        self.ranks = ranks
        self.pieces = Cutter(pattern)
        self.bytes_of = {rank: token for token, rank in ranks.items()}
        self.decimal = {str(rank): token for token, rank in ranks.items()}
        self.reach: dict[bytes, bool] = {}
        self.apart: dict[int, bool] = {}
        self.known = Memo(CACHE, lambda words: [",".join(map(str, self.piece(w.encode()))) for w in words])
        self.shorter: dict[int, int] = {}
        trie = ahocorasick.Automaton()
        for token, rank in ranks.items():
            trie.add_word(token.decode("latin-1"), rank)
        trie.make_automaton()
        self.trie = trie

    def prefix(self, token: int) -> int:
        """The longest token that is a proper prefix of this one, or -1."""
        if token not in self.shorter:
            name = self.bytes_of[token].decode("latin-1")[:-1]
            while name and name not in self.trie:
                name = name[:-1]
            self.shorter[token] = self.trie.get(name) if name else -1
        return self.shorter[token]

    def usable(self, token: int) -> bool:
        """Whether merging the token's own bytes leads to the token."""
        name = self.bytes_of[token]
        if name not in self.reach:
            self.reach[name] = len(merged(name, self.ranks)) == 1
        return self.reach[name]

    def fits(self, left: int, right: int) -> bool:
        key = left << 32 | right
        if key not in self.apart:
            if len(self.apart) > PAIRS:
                self.apart.clear()
            a, b = self.bytes_of[left], self.bytes_of[right]
            self.apart[key] = merged(a + b, self.ranks) == [a, b]
        return self.apart[key]

    def starts(self, text: str) -> list[int]:
        """For each place, the longest token that starts there: the automaton reports matches by their ends."""
        best = [-1] * len(text)
        size = [0] * len(text)
        for end, token in self.trie.iter(text):
            n = len(self.bytes_of[token])
            if n > size[end - n + 1]:
                size[end - n + 1], best[end - n + 1] = n, token
        return best

    def piece(self, piece: bytes) -> list[int]:
        whole = self.ranks.get(piece)
        if whole is not None:
            return [whole]
        text = piece.decode("latin-1")
        longest = self.starts(text)
        n, at = len(text), 0
        dead = bytearray(n + 1)
        laid: list[int] = []
        token = longest[0]
        while at < n:
            while token >= 0:
                end = at + len(self.bytes_of[token])
                if not dead[end] and self.usable(token) and (not laid or self.fits(laid[-1], token)):
                    break
                token = self.prefix(token)
            if token >= 0:
                laid.append(token)
                at = end
                token = longest[at] if at < n else -1
            else:
                if not laid:
                    raise ValueError("the vocabulary lacks a byte of the text")
                dead[at] = 1
                back = laid.pop()
                at -= len(self.bytes_of[back])
                token = self.prefix(back)
        return laid

    def joined(self, text: str) -> str:
        """The ids of a text in decimal, with commas between them."""
        return ",".join(self.known(self.pieces(text)))

    def encode(self, text: str) -> list[int]:
        ids = self.joined(text)
        return list(map(int, ids.split(","))) if ids else []

    def decode(self, ids: str) -> bytes:
        return b"".join(map(self.decimal.__getitem__, ids.split(","))) if ids else b""


def encoder(path: str, pattern: str) -> Encoder:
    return per_worker("byte_bpe", (path, pattern), lambda: Encoder(read_ranks(path), pattern))


def encode_documents(docs: DataFrame, path: str, pattern: str, with_ids: bool = True) -> DataFrame:
    """doc_id, n_tokens, ids, ids_sha256, decoded_sha256 of every document."""

    def run(batches):
        own = encoder(path, pattern)
        for batch in batches:
            n, ids, first, second = [], [], [], []
            for text in batch.column(1).to_pylist():
                joined = own.joined(text or "")
                n.append(joined.count(",") + 1 if joined else 0)
                if with_ids:
                    ids.append(list(map(int, joined.split(","))) if joined else [])
                first.append(hashlib.sha256(joined.encode()).hexdigest())
                second.append(hashlib.sha256(own.decode(joined)).hexdigest())
            arrays = [batch.column(0).cast(pa.int64()), pa.array(n, pa.int64()), *([pa.array(ids, pa.list_(pa.int32()))] if with_ids else []), pa.array(first, pa.string()), pa.array(second, pa.string())]
            yield pa.RecordBatch.from_arrays(arrays, names)

    schema = f"doc_id long, n_tokens long, {'ids array<int>, ' * with_ids}ids_sha256 string, decoded_sha256 string"
    names = [f.split()[0] for f in schema.split(", ")]
    return docs.select("doc_id", "text").mapInArrow(run, schema)


def op2_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return encode_documents(read_table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN, with_ids=False)
