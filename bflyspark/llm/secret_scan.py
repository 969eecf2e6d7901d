"""Secret scan with a recursive decoding worklist.

Plain matches come first. Then layers are unwrapped: percent-encoding, backslash-u and backslash-x
escapes, base64 runs (also over line ends), and gzip, zlib, bzip2 or zstandard data inside those. Every new layer goes on a
worklist and is scanned again until nothing new appears; a digest of each layer stops cycles. Each
character of a layer knows the span of the original text that it came from, so a match inside a layer
is reported in places of the original text.

Defined results: null text counts as empty. Rows are scanned on their own: repeats, ties and null ids
need no care, extra columns are left alone. Compressed data is unpacked to its end, through all members
and levels, as a stream over a temporary file, and scanned in windows; there is no guard against bombs.
Bytes that belong to no character are left out, the rest of their run is decoded.
"""

from __future__ import annotations

import base64
import bz2
import codecs
import hashlib
import io
import re
import tempfile
import zlib
from collections.abc import Iterable, Iterator
from dataclasses import dataclass
from typing import BinaryIO

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import read_table

# Bytes of a step, and characters of compressed data that are scanned at once.
PIECE, WINDOW = 64 << 10, 256 << 10
KINDS = ("assign", "access", "hex")
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
HINTS = ("passw", "secret", "token", "api")

PERCENT = re.compile(r"(?:%[0-9A-Fa-f]{2})+")
ESCAPE = re.compile(r"(?:\\u[0-9A-Fa-f]{4}|\\U[0-9A-Fa-f]{8}|\\x[0-9A-Fa-f]{2})+")
ESCAPED = re.compile(r"\\u([0-9A-Fa-f]{4})|\\U([0-9A-Fa-f]{8})|\\x([0-9A-Fa-f]{2})")
BASE64 = re.compile(r"[A-Za-z0-9+/_-]{16,}={0,2}")
WRAPPED = re.compile(r"(?=[A-Za-z0-9+/_-]+\r?\n[A-Za-z0-9+/_-])[A-Za-z0-9+/_-](?:(?:\r?\n)?[A-Za-z0-9+/_-]){15,}={0,2}")
# Decoded bytes without one of these show no match and no further layer.
WORTH = re.compile(rb"(?i:passw|secret|token|api)|AKIA|[0-9a-f]{24}|%[0-9A-Fa-f]{2}|\\[uUx]|[A-Za-z0-9+/_-](?:(?:\r?\n)?[A-Za-z0-9+/_-]){15}")
# No pattern goes over a break: a character of none, the blank between two words, an empty line.
BREAK = re.compile(r"""(?<=[^A-Za-z0-9+/_.="':\x20%\\\r\n-])|(?<=[A-Za-z0-9])(?=\x20[A-Za-z0-9])|(?<=\n)(?=\n)""")
MAGIC = re.compile(rb"\x1f\x8b\x08|BZh[1-9]1AY&SY|\x28\xb5\x2f\xfd")
# Compressed bytes as percent triples or escapes; bytes that are printable may stand as they are.
QUOTED_HEAD = re.compile(r"%1[Ff]%8[Bb]|(?:x|%78)(?:%01|%5[Ee]|\^|%9[Cc]|%[Dd][Aa])|(?:BZh|%42%5[Aa]%68)|(?:\(|%28)%[Bb]5(?:/|%2[Ff])%[Ff][Dd]")
QUOTED = re.compile(r"%([0-9A-Fa-f]{2})|[!-$&-~]")
HEX_UNIT = r"\\(?:x|u00|U000000)"
ESCAPED_HEAD = re.compile(rf"{HEX_UNIT}1[Ff]{HEX_UNIT}8[Bb]|(?:x|{HEX_UNIT}78)(?:{HEX_UNIT}(?:01|5[Ee]|9[Cc]|[Dd][Aa])|\^)|(?:BZh|{HEX_UNIT}42{HEX_UNIT}5[Aa]{HEX_UNIT}68)|(?:\(|{HEX_UNIT}28){HEX_UNIT}[Bb]5(?:/|{HEX_UNIT}2[Ff]){HEX_UNIT}[Ff][Dd]")
ESCAPED_UNIT = re.compile(r"\\u([0-9A-Fa-f]{4})|\\U([0-9A-Fa-f]{8})|\\x([0-9A-Fa-f]{2})|\\([abtnvfr0'\"\\/])|[\x20-\x5b\x5d-~]")
SHORT = dict(zip("abtnvfr0", (7, 8, 9, 10, 11, 12, 13, 0), strict=True))


def quoted_byte(m: re.Match) -> int:
    return int(m[1], 16) if m[1] else ord(m[0])


def escaped_byte(m: re.Match) -> int:
    digits = m[1] or m[2] or m[3]
    return int(digits, 16) if digits else SHORT.get(m[4], ord(m[4])) if m[4] else ord(m[0])


@dataclass
class Layer:
    """A decoded text; starts[i] and ends[i] bound the original characters behind its character i."""

    text: str
    starts: list[int] | range
    ends: list[int] | range


def plain_matches(text: str) -> list[tuple[int, int, int]]:
    """(start, kind number, end) of the base patterns, by start and then kind."""
    out: list[tuple[int, int, int]] = []
    lower = text.lower()
    if any(h in lower for h in HINTS):
        out += [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= 6]
    if "AKIA" in text:
        out += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= 20]
    out += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
    return sorted(out)


def unescaped(run: str) -> list[tuple[str, int, int]] | None:
    """(characters, start, end) for each unit of a run of backslash escapes; what stands for no character stays as it is."""
    units = [(int(m[1] or m[2] or m[3], 16), m.start(), m.end()) for m in ESCAPED.finditer(run)]
    out: list[tuple[str, int, int]] = []
    i, changed = 0, False
    while i < len(units):
        point, start, end = units[i]
        if 0xD800 <= point < 0xDC00 and i + 1 < len(units) and 0xDC00 <= units[i + 1][0] < 0xE000:
            point, end, i = 0x10000 + ((point - 0xD800) << 10) + units[i + 1][0] - 0xDC00, units[i + 1][2], i + 1
        valid = point <= 0x10FFFF and not 0xD800 <= point < 0xE000
        out += [(chr(point), start, end)] if valid else [(run[k], k, k + 1) for k in range(start, end)]
        changed |= valid
        i += 1
    return out if changed else None


def spelled(data: bytes) -> list[tuple[str | None, int, int]]:
    """(character, first byte, end) of UTF-8; None for each byte that belongs to no character."""
    out: list[tuple[str | None, int, int]] = []
    at = 0
    for c in data.decode("utf-8", "surrogateescape"):
        n = 1 if "\udc80" <= c <= "\udcff" else len(c.encode())
        out.append((None if "\udc80" <= c <= "\udcff" else c, at, at + n))
        at += n
    return out


def unquoted(run: str) -> list[tuple[str, int, int]] | None:
    """(character, start, end) for each character of a run of percent triples; bytes that are no UTF-8 stay as they are."""
    units = spelled(bytes.fromhex(run.replace("%", "")))
    if all(c is None for c, _, _ in units):
        return None
    return [x for c, a, b in units for x in ([(c, 3 * a, 3 * b)] if c is not None else [(run[k], k, k + 1) for k in range(3 * a, 3 * b)])]


def substituted(layer: Layer, pattern: re.Pattern, decode) -> Layer | None:
    """The layer with every run of an encoding replaced by what it stands for."""
    parts: list[str] = []
    starts: list[int] = []
    ends: list[int] = []
    at, changed = 0, False
    for m in pattern.finditer(layer.text):
        units = decode(m[0])
        if units is None:
            continue
        changed = True
        parts.append(layer.text[at : m.start()])
        starts += layer.starts[at : m.start()]
        ends += layer.ends[at : m.start()]
        for c, a, b in units:
            parts.append(c)
            starts.append(layer.starts[m.start() + a])
            ends.append(layer.ends[m.start() + b - 1])
        at = m.end()
    if not changed:
        return None
    parts.append(layer.text[at:])
    starts += layer.starts[at:]
    ends += layer.ends[at:]
    return Layer("".join(parts), starts, ends)


def codec_of(head: bytes):
    """A decompressor for data that begins so, or None."""
    if head[:2] == b"\x1f\x8b":
        return zlib.decompressobj(31)
    if head[:1] == b"\x78" and len(head) > 2 and (head[0] * 256 + head[1]) % 31 == 0:
        return zlib.decompressobj()
    if head[:3] == b"BZh":
        return bz2.BZ2Decompressor()
    if head[:4] == b"\x28\xb5\x2f\xfd":
        import zstandard

        return zstandard.ZstdDecompressor().decompressobj()
    return None


def expanded(codec, data: bytes) -> Iterator[tuple[bytes, bytes]]:
    """Pieces of bounded size that the decompressor makes of the data, each with the input that lies behind the member's end."""
    if isinstance(codec, type(zlib.decompressobj())):
        while True:
            out = codec.decompress(data, PIECE)
            yield out, codec.unused_data
            data = codec.unconsumed_tail
            if codec.eof or (not data and len(out) < PIECE):
                return
    elif isinstance(codec, bz2.BZ2Decompressor):
        yield codec.decompress(data, PIECE), codec.unused_data
        while not codec.eof and not codec.needs_input:
            yield codec.decompress(b"", PIECE), codec.unused_data
    else:  # a step of zstandard has no bound of its own; 64 bytes hold few blocks of 128 kB
        for k in range(0, len(data), 64):
            out = codec.decompress(data[k : k + 64])
            yield out, codec.unused_data + data[k + 64 :] if codec.eof else b""
            if codec.eof:
                return


def faulty_data(error: Exception) -> bool:
    """Whether a decompressor complains of its data. Errors of files have a number; zstandard has an error class of its own."""
    return isinstance(error, zlib.error | ValueError | EOFError) or (isinstance(error, OSError) and error.errno is None) or type(error).__name__ == "ZstdError"


def unpacked(source: BinaryIO, target: BinaryIO) -> tuple[list[int], int]:
    """Write all members at the head of the source to the target: where each begins there, and the bytes read for them.

    What is broken ends the last member; what came before that point is kept.
    """
    begun, read, data = [], 0, b""
    while True:
        if len(data) < 8:
            data += source.read(PIECE)
        if (codec := codec_of(data)) is None:
            return begun, read
        start, used = target.tell(), 0
        try:
            while data:
                for out, rest in expanded(codec, data):
                    target.write(out)
                used += len(data) - len(rest)
                data = rest
                if codec.eof:
                    break
                data = source.read(PIECE)
        except Exception as error:
            if not faulty_data(error):
                raise
        if target.tell() > start:
            begun.append(start)
            read += used
        if not codec.eof:
            return begun, read


def windows(source: BinaryIO) -> Iterator[str]:
    """The text of a stream in windows, cut where no pattern can run on; bytes that are no UTF-8 become U+FFFD."""
    decoder = codecs.getincrementaldecoder("utf-8")("replace")
    held, least = "", WINDOW
    while data := source.read(PIECE):
        held += decoder.decode(data)
        if len(held) < least:
            continue
        cut = next((k for k in range(len(held) - 1, 0, -1) if BREAK.match(held, k)), 0) if BREAK.search(held, 1) else 0
        if cut:
            yield held[:cut]
        held, least = held[cut:], WINDOW if cut else 2 * len(held)
    yield held + decoder.decode(b"", True)


def streams(data: bytes) -> tuple[list[BinaryIO], int]:
    """What data compressed at its head holds, and all that is compressed in that again, as streams; the bytes it takes."""
    out: list[BinaryIO] = []
    seen: set[bytes] = set()
    taken = None
    work: list[tuple[BinaryIO, list[int]]] = [(io.BytesIO(data), [0])]
    while work:
        source, places = work.pop()
        source.seek(places[0])
        target = tempfile.SpooledTemporaryFile(WINDOW)
        begun, read = unpacked(source, target)
        taken = read if taken is None else taken
        if later := [k for k in places[1:] if k >= places[0] + read]:
            work.append((source, later))
        target.seek(0)
        key = hashlib.md5()
        while piece := target.read(PIECE):
            key.update(piece)
        if not begun or key.digest() in seen:
            target.close()
            continue
        seen.add(key.digest())
        out.append(target)
        heads = []
        for k in begun:
            target.seek(k)
            if codec_of(target.read(8)) is not None:
                heads.append(k)
        if heads:
            work.append((target, heads))
    return out, taken


def opened(found: list[BinaryIO], start: int, end: int) -> Iterator[Layer]:
    """The streams as layers; any part of compressed data may stand behind a character."""
    for stream in found:
        with stream:
            stream.seek(0)
            for text in windows(stream):
                yield Layer(text, [start] * len(text), [end] * len(text))


def broken(data: bytes) -> bool:
    try:
        for _ in expanded(codec_of(data), data):
            pass
    except Exception as error:
        if not faulty_data(error):
            raise
        return True
    return False


def packed_runs(layer: Layer, head: re.Pattern, unit: re.Pattern, value) -> Iterator[Layer]:
    """Layers of compressed data whose bytes stand as escapes and plain characters, from a head as far as units go."""
    at = 0
    while m := head.search(layer.text, at):
        at = m.end()
        data, bounds, k = bytearray(), [], m.start()
        while (u := unit.match(layer.text, k)) and (byte := value(u)) < 256:
            data.append(byte)
            bounds.append((k, u.end()))
            k = u.end()
            if len(data) == 256 and (codec_of(bytes(data)) is None or broken(bytes(data))):
                break
        found, taken = streams(bytes(data))
        if found:
            yield from opened(found, layer.starts[m.start()], layer.ends[bounds[taken - 1][1] - 1])
            at = bounds[taken - 1][1]


def from_base64(layer: Layer, m: re.Match) -> Iterator[Layer]:
    """Layers behind a base64 run. A run over several lines may begin or end with words that don't belong to it: all four phases are read."""
    body = m[0].rstrip("=")
    at = [m.start() + k for k, c in enumerate(body) if c not in "\r\n"]
    joined = "".join(c for c in body if c not in "\r\n")
    wrapped = len(joined) < len(body)
    for phase in range(4 if wrapped else 1):
        n = len(joined) - phase
        n -= n % 4 == 1
        if n < 2:
            continue
        data = base64.b64decode(joined[phase : phase + n].replace("-", "+").replace("_", "/") + "=" * (-n % 4))
        first = lambda i, phase=phase: at[phase + i * 8 // 6]
        last = lambda i, phase=phase, size=len(data): m.end() if i >= size else at[phase + (i * 8 - 1) // 6] + 1
        heads = [(k - phase + 3) // 4 * 3 for k in range(phase, len(joined)) if (k - phase) % 4 == 0 and (k == 0 or at[k] > at[k - 1] + 1)] if wrapped else []
        upto, rest = 0, bytearray(data)
        for head in sorted({0, *heads, *(x.start() for x in MAGIC.finditer(data))}):
            if head < upto or codec_of(data[head : head + 8]) is None:
                continue
            found, taken = streams(data[head:])
            if found:
                upto = head + taken
                rest[head:upto] = b"\xff" * taken
                yield from opened(found, layer.starts[first(head)], layer.ends[last(upto) - 1])
        if not WORTH.search(rest):
            continue
        units = spelled(bytes(rest))
        text = "".join("\ufffd" if c is None else c for c, _, _ in units)
        yield Layer(text, [layer.starts[first(a)] for _, a, _ in units], [layer.ends[at[phase + (b * 8 - 1) // 6]] for _, _, b in units])


def layers_in(layer: Layer) -> Iterator[Layer | None]:
    """The layers one step below."""
    if "%" in layer.text:
        yield substituted(layer, PERCENT, unquoted)
        yield from packed_runs(layer, QUOTED_HEAD, QUOTED, quoted_byte)
    if "\\" in layer.text:
        yield substituted(layer, ESCAPE, unescaped)
        yield from packed_runs(layer, ESCAPED_HEAD, ESCAPED_UNIT, escaped_byte)
    for m in BASE64.finditer(layer.text):
        yield from from_base64(layer, m)
    if "\n" in layer.text:
        for m in WRAPPED.finditer(layer.text):
            yield from from_base64(layer, m)


def hidden_matches(text: str, plain: list[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
    """(start, kind number, end) of matches that only a decoded layer shows, in places of the text."""
    work = [layers_in(Layer(text, range(len(text)), range(1, len(text) + 1)))]
    seen = {hashlib.md5(text.encode("utf-8", "surrogatepass")).digest()}
    found = set(plain)
    out: list[tuple[int, int, int]] = []
    while work:  # one layer of each depth at a time, as windows of compressed data may be many
        try:
            x = next(work[-1])
        except StopIteration:
            work.pop()
            continue
        if x is None or (key := hashlib.md5(x.text.encode("utf-8", "surrogatepass") + repr((x.starts[:1], x.ends[-1:])).encode()).digest()) in seen:
            continue
        seen.add(key)
        work.append(layers_in(x))
        for start, kind, end in plain_matches(x.text):
            span = (x.starts[start], kind, x.ends[end - 1])
            if span not in found:
                found.add(span)
                out.append(span)
    return sorted(out)


def scan_text(text: str) -> tuple[list[tuple[int, int, int]], list[tuple[int, int, int]]]:
    plain = plain_matches(text)
    return plain, hidden_matches(text, plain)


def spans_text(spans: list[tuple[int, int, int]], prefix: str = "") -> list[tuple[int, int, str]]:
    return [(start, kind + 3 * bool(prefix), f"{prefix}{KINDS[kind]}:{start}:{end}") for start, kind, end in spans]


def scan(docs: DataFrame) -> DataFrame:
    """One row per document: counts, digest of the base spans, all spans."""
    names = ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans", "n_hidden"]

    def run(batches):
        for batch in batches:
            rows = []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                plain, hidden = scan_text(text or "")
                kinds = [k for _, k, _ in plain]
                base = spans_text(plain)
                both = sorted(base + spans_text(hidden, "decoded_"))
                rows.append((doc, *(kinds.count(k) for k in range(3)), hashlib.sha256(",".join(x[2] for x in base).encode()).hexdigest(), ",".join(x[2] for x in both), len(hidden)))
            columns = zip(*rows, strict=True) if rows else [[]] * len(names)
            types = [pa.int64()] * 4 + [pa.string()] * 2 + [pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types, strict=True)], names)

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_hidden long")


def redacted_text(text: str) -> str:
    """The text with every span of a secret, overlaps joined, replaced by a mark."""
    spans = sorted((s, e) for part in scan_text(text) for s, _, e in part)
    if not spans:
        return text
    out, at, end = [], 0, -1
    for s, e in spans:
        if s >= end:
            if end >= 0:
                at = end
            out += [text[at:s], "[secret]"]
        end = max(end, e)
    return "".join([*out, text[end:]])


def redact(docs: DataFrame) -> DataFrame:
    """All rows and columns; secrets are masked in text, and n_chars, where there is one, follows."""
    names = docs.columns
    at = names.index("text")
    count = names.index("n_chars") if "n_chars" in names else None

    def run(batches):
        for batch in batches:
            old = batch.column(at).to_pylist()
            new = [t and redacted_text(t) for t in old]
            columns = list(batch.columns)
            columns[at] = pa.array(new, columns[at].type)
            if count is not None:
                counts = [c if a == b else len(b) for a, b, c in zip(old, new, columns[count].to_pylist(), strict=True)]
                columns[count] = pa.array(counts, columns[count].type)
            yield pa.RecordBatch.from_arrays(columns, batch.schema.names)

    return docs.mapInArrow(run, docs.schema)


def op6_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(read_table(spark, sf_dir, "documents"))
