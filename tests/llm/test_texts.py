"""Operators that judge each document alone, against plain versions."""

import base64
import bz2
import gzip
import hashlib
import itertools
import json
import random
import re
import urllib.parse
import zlib

import numpy as np
import public_tokenizers
import pytest
import tiktoken
import zstandard
from tokenizers import Tokenizer

from bflyspark.llm import byte_bpe, decontaminate, license_scan, quality_classifier, quality_rules, secret_scan, shard_balance, token_files

MULTI = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
BPE = public_tokenizers.path("byte_bpe_50k.json")


# 1


def plain_base(text):
    w = re.findall(r"[^\x20\x09-\x0D]+", text or "")
    n, seen, dup = len(w), set(), 0
    for line in (text or "").split("\n"):
        if re.search(r"[^\x20\x09-\x0D]", line):
            dup += line in seen
            seen.add(line)
    grams = [tuple(w[i : i + 8]) for i in range(n - 7)]
    inside = {k for i, g in enumerate(grams) if grams.count(g) > 1 for k in range(i, i + 8)} if n < 400 else None
    return n, sum(map(len, w)), sum((text or "").count(c) for c in "#*$%&|<>"), dup, inside and len(inside) or 0


def test_quality_base_columns(tiny):
    got = {r.doc_id: r for r in quality_rules.judge(tiny).collect()}
    for r in tiny.collect():
        n, chars, symbols, dup, repeat = plain_base(r.text)
        g = got[r.doc_id]
        assert (g.n_words, g.word_chars, g.n_symbols, g.n_dup_lines) == (n, chars, symbols, dup)
        if n < 400:
            assert g.n_repeat_words == repeat
        assert g.base_failed == (n < 20 or 100 * g.n_repeat_words > 30 * n)
        assert not (g.base_failed and g.kept)


def test_quality_divergence(spark, tiny):
    assert quality_rules.jensen_shannon(np.array([1.0, 0]), np.array([0, 2.0])) == pytest.approx(1)
    assert quality_rules.jensen_shannon(np.array([1.0, 3]), np.array([2.0, 6])) == pytest.approx(0)
    clean = [r for r in tiny.collect() if r.lang == "en"][1]
    noise = " ".join(w + "###" for w in clean.text.split())
    df = spark.createDataFrame([(10_000, noise, "en", "s", 1), (10_001, clean.text, "en", "s", 1)], tiny.schema)
    kept = {r.doc_id: r.kept for r in quality_rules.judge(df, refs=quality_rules.references(tiny)).collect()}
    assert kept == {10_000: False, 10_001: True}


def test_quality_odd_inputs(odd, none):
    assert quality_rules.judge(odd).count() == odd.count()
    assert quality_rules.judge(none).count() == 0
    assert quality_rules.keep_good(none).count() == 0
    kept = quality_rules.keep_good(odd)
    assert kept.columns == odd.columns and kept.count() < odd.count()


# 2


def reference_encoding():
    return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=byte_bpe.read_ranks(MULTI), special_tokens={})


def test_byte_bpe_equals_library(tiny, odd, none):
    own = reference_encoding()
    for df in (tiny, odd):
        got = sorted((r.doc_id or -1, r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in byte_bpe.encode_documents(df, MULTI, public_tokenizers.PATTERN).collect())
        want = []
        for r in df.select("doc_id", "text").collect():
            ids = own.encode_ordinary(r.text or "")
            want.append((r.doc_id or -1, len(ids), hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256((r.text or "").encode()).hexdigest()))
        assert got == sorted(want)
    assert byte_bpe.encode_documents(none, MULTI, public_tokenizers.PATTERN).count() == 0


def test_byte_bpe_random_strings():
    own, lib = byte_bpe.Encoder(byte_bpe.read_ranks(MULTI), public_tokenizers.PATTERN), reference_encoding()
    rnd = random.Random(2)
    for _ in range(3000):
        text = "".join(rnd.choice("ab e\n\t1234é漢字ñ'sZ!?thing \x1c") for _ in range(rnd.randint(0, 60)))
        assert own.encode(text) == lib.encode_ordinary(text)
    for text in ("a" * 3000, "ab" * 3000, "0" * 999):
        assert own.encode(text) == lib.encode_ordinary(text)


# 3


def test_token_files_round_trip(tiny, odd, none):
    lib = Tokenizer.from_file(BPE)  # as it comes: added tokens in a text are found
    marked = tiny.sparkSession.createDataFrame([(5, "a <|endoftext|> b"), (3, "<|endoftext|><|endoftext|>x"), (4, " <|endoftext|>\n"), (1, "<|endoftext|"), (2, None)], "doc_id long, text string")
    assert 50256 in lib.encode("a <|endoftext|> b", add_special_tokens=False).ids
    for df in (tiny, odd, marked):
        files, book = token_files.write_files(df, BPE, public_tokenizers.PATTERN)
        got = sorted((r.start, r.n_tokens, r.ids_crc32, r.doc_id if r.doc_id is not None else -1) for r in token_files.read_files(files, book).collect())
        start, want = 0, []
        texts = sorted(((-1 if r.doc_id is None else r.doc_id, r.text or "") for r in df.select("doc_id", "text").collect()), key=lambda x: x[0])
        for doc, text in texts:
            ids = lib.encode(text, add_special_tokens=False).ids + [2]
            want.append((start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()), doc))
            start += len(ids)
        assert got == want
    assert token_files.read_files(*token_files.write_files(none, BPE, public_tokenizers.PATTERN)).count() == 0


def test_huffman_codes():
    rng = np.random.default_rng(1)
    for limit, n in ((6, 40), (18, 300), (4, 16), (3, 1), (5, 2)):
        counts = (rng.pareto(0.5, n) * 10 + 1).astype(np.int64)
        lengths = token_files.code_lengths(counts, limit)
        assert lengths.max() <= limit and (2.0 ** -lengths[lengths > 0].astype(float)).sum() <= 1
        book = token_files.CodeBook(lengths)
        docs = [rng.integers(0, n, k).astype(np.uint16) for k in (1, 5, 3000)]
        coded = book.encode(docs)
        data = token_files.pack_segment([(i, len(d), *c) for i, (d, c) in enumerate(zip(docs, coded, strict=True))])
        back = token_files.unpack_segment(data, book)
        assert all((a == b[1]).all() for a, b in zip(docs, back, strict=True))
    free = token_files.code_lengths(np.array([8, 4, 2, 1, 1]), 18)
    assert free.tolist() == [1, 2, 3, 4, 4]


# 4


def test_sharding(tiny, odd, none):
    for df in (tiny, odd):
        rows = shard_balance.shard_by_bytes(df).collect()
        assert len(rows) == df.count()
        for k in range(8):
            assert sorted(r.slot for r in rows if r.shard == k) == list(range(sum(r.shard == k for r in rows)))
        text = {}
        for r in df.select("doc_id", "text").collect():
            text.setdefault(r.doc_id, r.text or "")
        for r in rows:
            assert r["size"] == len(text[r.doc_id].encode()) + 1 and r.text_crc32 == zlib.crc32(text[r.doc_id].encode()) and r.law == "bytes"
        shard_of = {}
        for r in rows:
            assert shard_of.setdefault(text[r.doc_id], r.shard) == r.shard
    assert shard_balance.shard_by_bytes(none).count() == 0
    sums = [sum(r["size"] for r in shard_balance.shard_by_bytes(tiny).collect() if r.shard == k) for k in range(8)]
    assert max(sums) - min(sums) <= 0.02 * sum(sums)


def test_differencing():
    rnd = random.Random(1)
    sizes = [rnd.randint(1, 1000) for _ in range(400)]
    sums, parts = shard_balance.difference([shard_balance.single(n, i, 8) for i, n in enumerate(sizes)], 8)
    members = [shard_balance.flatten(p) for p in parts]
    assert sorted(x for m in members for x in m) == list(range(400))
    assert [sum(sizes[i] for i in m) for m in members] == sums and max(sums) - min(sums) <= 8
    assert shard_balance.difference([], 8)[0] == [0] * 8


# 5


def test_license_base_and_rules(spark, tiny, odd, none):
    word = re.compile("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+")
    for df in (tiny, odd):
        got = {r.doc_id: r for r in license_scan.scan(df).collect()}
        for r in df.select("doc_id", "text").collect():
            w = word.findall((r.text or "").translate({i: i + 32 for i in range(65, 91)}))
            at = [(i, label) for phrase, label in license_scan.BASE.items() for i in range(len(w)) if w[i : i + len(phrase.split())] == phrase.split()]
            g = got[r.doc_id]
            assert (g.n_words, g.n_base) == (len(w), len(at))
            assert (g.first_word, g.last_word) == ((min(at)[0], max(at)[0]) if at else (None, None))
            assert g.base_labels == ",".join(sorted({x for _, x in at}))
            assert set(filter(None, g.base_labels.split(","))) <= set(g.labels.split(",")) and 0 <= g.score <= 1
    assert license_scan.scan(none).count() == 0
    texts = {"Licensed under the Apache License, Version 2.0": "apache-2.0", "GNU Lesser General Public License v3": "gpl,lgpl-3", "CC BY-SA 4.0": "cc-by,cc-by-sa-4.0", "the MIT license": "mit", "nothing to see": ""}
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    got = [r.labels for r in license_scan.scan(df).orderBy("doc_id").collect()]
    assert got == list(texts.values())
    plan = license_scan.scan(df)._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan and len(license_scan.rules()) > 300


def samples(tree):
    """Strings of a parsed expression in which each of its alternatives occurs at least once."""
    out = [""]
    for op, arg in tree:
        name = str(op)
        if name == "LITERAL":
            part = [chr(arg)]
        elif name == "IN":
            part = [chr(v if str(k) == "LITERAL" else v[0]) for k, v in arg]
        elif name == "BRANCH":
            part = [x for branch in arg[1] for x in samples(branch)]
        elif name == "SUBPATTERN":
            part = samples(arg[3])
        elif name == "MAX_REPEAT":
            part = [x * n for n in {arg[0], arg[1]} for x in samples(arg[2])]
        else:
            assert name == "ASSERT_NOT"
            continue
        out = [out[i % len(out)] + part[i % len(part)] for i in range(len(out) * len(part) if len(out) * len(part) < 200 else max(len(out), len(part)))]
    return out


def test_license_alternatives_pass_their_gate(spark):
    for keyword, rx, *_ in license_scan.rules():
        for text in samples(re._parser.parse(rx)):
            assert re.fullmatch(rx, text) and keyword in f" {text} ", (keyword, text)
    by_hand = [(stem, *entry) for stem, entries in license_scan.SIGNATURES.items() for entry in entries]
    assert len({rx for _, _, rx, *_ in by_hand}) == len(by_hand) >= 200
    for stem, _, rx, keyword, conf in by_hand:
        for text in samples(re._parser.parse(rx)):
            assert stem in text and f" {keyword} " in f" {text} " and 0 < conf < 1, (stem, text)


def plain_detections(text):
    """All rules on all places, without keywords or gates, then suppression by containment."""
    joined = " ".join(re.findall("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", text.translate({i: i + 32 for i in range(65, 91)})))
    spans = sorted((joined[: m.start()].count(" "), -joined[: m.end()].count(" "), -priority, label, conf) for _, rx, label, priority, conf in license_scan.rules() for m in re.finditer(rx, joined))
    kept, end = [], -1
    for _, last, _, label, conf in spans:
        if -last > end:
            kept.append((label, conf))
            end = -last
    base = {label for phrase, label in license_scan.BASE.items() if f" {phrase} " in f" {joined} "}
    return ",".join(sorted(base | {x for x, _ in kept})), max([c for _, c in kept] + [0.7 if base else 0.0]), len(kept)


def test_license_suppression_against_plain_rules(spark, tiny):
    mixes = ["the MIT license, see LICENSE. Released into the public domain. All rights reserved",
             "Licensed under the GNU Lesser General Public License version 2.1 or later; GPL-3.0 applies to tools, copyright (c) 2011 A",
             "Redistribution and use in source and binary forms ... 3-clause BSD license, simplified BSD License; Apache License 2.0 or SIL Open Font License 1.1",
             "This is free and unencumbered software released into the public domain. CC BY-NC-SA 4.0. Creative Commons Attribution ShareAlike 3.0",
             "business source license 1.1, server side public license, elastic license 2.0; for personal use only; unauthorised copying"]
    rows = [(i, t) for i, t in enumerate([*mixes, *(r.text for r in tiny.where("text is not null and length(text) < 6000").limit(60).collect())])]
    got = {r.doc_id: (r.labels, r.score, r.n_detections) for r in license_scan.scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    for i, text in rows:
        labels, score, n = plain_detections(text)
        assert got[i][0] == labels and got[i][1] == pytest.approx(score) and got[i][2] == n, (i, got[i], labels)


def test_license_fused_and_split_names(spark):
    texts = {"unauthorized reproduction": "proprietary", "Unauthorised distribution": "proprietary", "unauthorised copying": "proprietary", "FreeBSD License": "bsd-2-clause", "GPLv2": "gpl-2", "under LGPLv2.1+": "lgpl-2.1", "LGPLv3": "lgpl-3", "GPL3": "gpl-3", "AGPLv1": "agpl", "Oslo, gplvx": ""}
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    assert [r.labels for r in license_scan.scan(df).orderBy("doc_id").collect()] == list(texts.values())


# 6


def secret_layers():
    t = "x password=hunter2hunter y"
    yield urllib.parse.quote(t, safe="")
    yield "".join("\\u%04x" % ord(c) for c in t)
    yield base64.b64encode(t.encode()).decode()
    yield base64.b64encode(gzip.compress(t.encode())).decode()
    yield base64.b64encode(zlib.compress(t.encode())).decode()
    yield urllib.parse.quote(base64.b64encode(base64.b64encode(t.encode())).decode())
    yield json.dumps("".join("%%%02X" % c for c in t.encode()))


def test_secrets_in_layers():
    for layer in secret_layers():
        text = f"lead é {layer} tail"
        plain, hidden = secret_scan.scan_text(text)
        assert not plain and len(hidden) == 1, layer
        start, kind, end = hidden[0]
        assert kind == 0 and 7 <= start < end <= len(text) - 5
        clean = secret_scan.redacted_text(text)
        assert secret_scan.scan_text(clean) == ([], []) and clean.startswith("lead é") and clean.endswith("tail")


def kinds(text):
    return [k for _, k, _ in secret_scan.scan_text(text)[1]]


@pytest.mark.parametrize("pack", [gzip.compress, zlib.compress, bz2.compress, zstandard.compress])
def test_secrets_in_all_of_compressed_data(pack):
    t = b"x password=hunter2hunter y"
    coded = lambda data: "see " + base64.b64encode(data).decode() + " tail"
    assert kinds(coded(pack(b"." * (33 << 20) + t))) == [0]  # behind 32 MiB
    assert kinds(coded(pack("\u00e9,".encode() * (11 << 20) + t))) == [0]
    assert kinds(coded(pack(b"clean") + pack(b"more") + pack(t))) == [0]  # in a later member
    deep = t
    for _ in range(70):
        deep = pack(deep)
    assert kinds(coded(deep)) == [0]
    assert kinds(coded(pack(pack(b"clean")) + pack(pack(t)))) == [0]
    assert kinds(coded(pack(t + b"\xff" * 3))) == [0]
    half = pack(random.Random(4).randbytes(5000) + t)
    assert kinds(coded(half[: len(half) // 2])) == []


def test_secret_over_the_end_of_a_window():
    t = b"x password=hunter2hunter y"
    for shift in range(0, 60, 7):
        assert kinds("see " + base64.b64encode(gzip.compress(b"a b, " * 52_420 + b"." * shift + t + b" a" * 200_000)).decode()) == [0]
    key = b"AKIA" + b"Q" * 600_000
    text = base64.b64encode(gzip.compress(b"a " + key + b" b")).decode()
    assert kinds(f"see {text} tail") == [1]


def test_secrets_in_compressed_escapes():
    t = "x password=hunter2hunter y " + " ".join(str(i * i) for i in range(60))
    for pack in (gzip.compress, zlib.compress, bz2.compress, zstandard.compress):
        data = pack(t.encode())
        for coded in ("".join(f"%{b:02X}" for b in data), urllib.parse.quote(data, safe=""), "".join(f"\\x{b:02x}" for b in data), repr(data), json.dumps(data.decode("latin-1"))):
            text = f"lead {coded}&tail"
            hidden = secret_scan.scan_text(text)[1]
            assert hidden and all(kind == 0 and 5 <= start < end <= len(text) - 5 for start, kind, end in hidden)
            assert secret_scan.redacted_text(text).endswith("&tail")


def test_secrets_next_to_foreign_bytes():
    assert kinds("a %E9%74%6F%6B%65%6E=hunter2hunter b") == [0]
    assert kinds("a %74%6F%6B%65%6E%3Dhunter2%E9 b") == [0]
    assert kinds(r"a \ud800\u0074\u006f\u006b\u0065\u006e=hunter2hunter b") == [0]
    assert kinds("a %E9%FF b") == [] and kinds(r"a \ud800\udbff b") == []


@pytest.mark.parametrize("width", [20, 64, 76])
@pytest.mark.parametrize("end", ["\n", "\r\n"])
def test_secrets_in_wrapped_base64(width, end):
    t = "x " * 17 + "password=hunter2hunter " + " ".join(str(i * i) for i in range(60))
    for data in (t.encode(), gzip.compress(t.encode()), zlib.compress(t.encode()), bz2.compress(t.encode())):
        coded = base64.b64encode(data).decode()
        lines = end.join(coded[k : k + width] for k in range(0, len(coded), width))
        for lead in ("lead:", "lead\n", "Dear all\n"):
            text = f"{lead}{lines}\n\nBest regards"
            assert 0 in kinds(text)
            assert 0 not in kinds(secret_scan.redacted_text(text)) and secret_scan.redacted_text(text).endswith("Best regards")


def test_secrets_base_and_odd(tiny, odd, none):
    got = {r.doc_id: r for r in secret_scan.scan(tiny).collect()}
    assign = re.compile(r"""((?:[pP][aA][sS][sS][wW][oO][rR][dD])|(?:[pP][aA][sS][sS][wW][dD])|(?:[sS][eE][cC][rR][eE][tT])|(?:[tT][oO][kK][eE][nN])|(?:[aA][pP][iI]_?[kK][eE][yY]))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")
    for r in tiny.collect():
        spans = [(m.start(), 0, m.end()) for m in assign.finditer(r.text) if len(m[2]) >= 6]
        spans += [(m.start(), 1, m.end()) for m in re.finditer("AKIA[A-Z0-9]+", r.text) if len(m[0]) >= 20]
        spans += [(m.start(), 2, m.end()) for m in re.finditer("[0-9a-f]+", r.text) if len(m[0]) >= 24]
        text = ",".join(f"{('assign', 'access', 'hex')[k]}:{s}:{e}" for s, k, e in sorted(spans))
        assert got[r.doc_id].base_sha256 == hashlib.sha256(text.encode()).hexdigest()
        assert set(filter(None, text.split(","))) <= set(got[r.doc_id].spans.split(","))
    assert secret_scan.scan(odd).count() == odd.count() and secret_scan.scan(none).count() == 0
    assert secret_scan.redact(odd).columns == odd.columns
    loop = base64.b64encode(b"A" * 40).decode()
    assert secret_scan.scan_text(loop * 3)[1] == []


# 7


def test_classifier(spark, small, odd, none, tiny):
    docs, labels = spark.read.parquet("/root/testdata/sf0.01/documents.parquet"), spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    model = quality_classifier.fit(docs, labels)
    rows = {r.doc_id: r for r in quality_classifier.score(docs, model).collect()}
    truth = {r.doc_id: r.quality for r in labels.collect()}
    held = [(rows[i].score, y) for i, y in truth.items() if rows[i].held_out]
    assert all(rows[i].held_out == (zlib.crc32(str(i).encode()) % 5 == 0) for i in truth)
    good, bad = [s for s, y in held if y], [s for s, y in held if not y]
    auc = sum((a > b) + (a == b) / 2 for a in good for b in bad) / (len(good) * len(bad))
    assert auc > 0.85
    for r in quality_classifier.score(odd, model).collect():
        assert 0 <= r.score <= 1 and r.predicted == int(r.score >= 0.3)
    assert quality_classifier.score(none, model).count() == 0
    empty = quality_classifier.fit(none, labels.limit(0))
    assert [r.score for r in quality_classifier.score(tiny.limit(2), empty).collect()] == pytest.approx([0.5, 0.5])
    one_label = quality_classifier.fit(docs, labels.where("quality = 1"))
    assert all(r.score > 0.99 for r in quality_classifier.score(tiny, one_label).collect())
    unknown = quality_classifier.fit(docs, labels.selectExpr("doc_id", "cast(null as int) as quality"))
    assert all(r.score == 0.5 for r in quality_classifier.score(tiny, unknown).collect())


def plain_score(model, text):
    """The score by the definition: feature by feature, no tables, nothing remembered."""
    s = model.settings

    def vector(word):
        marked = b"<" + word + b">"
        found = [zlib.crc32(word) % s.buckets]
        for n in s.grams:
            for i in range(len(marked) - n + 1):
                h = 14695981039346656037
                for b in marked[i : i + n]:
                    h = ((h ^ (b + 1)) * 1099511628211) % (1 << 64)
                found.append((h ^ (h >> 29)) % s.buckets)
        return np.mean([model.vectors[f] for f in found], axis=0)

    words = text.encode("utf-8", "replace").split()
    out = np.mean([vector(w) for w in quality_classifier.shape_tokens(words, text)], axis=0) * s.shape_weight
    if words:
        out = out + np.mean([vector(w) for w in words], axis=0)
    z = np.exp(out @ model.weights + model.bias)
    return z[1] / z.sum()


def test_classifier_models_stay_apart(spark, tiny, odd):
    """Two models from one seed, one after the other in the same workers, and both against the definition."""
    rows = tiny.where("text is not null").orderBy("doc_id").limit(80).collect()
    texts = [r.text[:2000] for r in rows]
    models = [quality_classifier.train(texts, [f(i) for i in range(len(texts))]) for f in (lambda i: i % 2, lambda i: int(i < 40))]
    assert models[0].digest != models[1].digest
    sample = spark.createDataFrame([(i, t) for i, t in enumerate([*texts[:12], "", "é漢字 ñ", "x" * 300])], "doc_id long, text string").coalesce(1)
    for model in (*models, models[0]):
        for r in quality_classifier.score(sample, model).collect():
            text = [*texts[:12], "", "é漢字 ñ", "x" * 300][r.doc_id]
            assert r.score == pytest.approx(plain_score(model, text), abs=1e-9)


# 9


def test_decontamination(spark, small, tiny, odd, none):
    benchmark = spark.read.parquet(f"{small}/benchmark.parquet")
    items = [(r.item_id, decontaminate.words_of(r.text)) for r in benchmark.collect()]
    rnd = random.Random(3)
    clean = [" ".join(f"other{rnd.randint(0, 99)}" for _ in range(80)) for _ in range(20)]
    planted, want = [], []
    for k, (item, words) in enumerate(items[:20]):
        changed = list(words)
        for at in range(6, len(changed), 11):  # a substituted word here and there
            changed[at] = "swapped"
        half = clean[k].split()
        planted.append((1000 + k, " ".join([*half[:40], *changed, *half[40:]])))
        want.append(item)
    df = spark.createDataFrame(planted + [(2000 + k, t) for k, t in enumerate(clean)], "doc_id long, text string")
    got = {r.doc_id: r for r in decontaminate.scan(df, benchmark).collect()}
    for k, item in enumerate(want):
        assert got[1000 + k].contaminated and item in got[1000 + k]["items"]
    assert not any(got[2000 + k].contaminated for k in range(20))
    exact = {r.doc_id: any(" ".join(w) in " ".join(decontaminate.words_of(r.text)) for _, w in items) for r in tiny.collect()}
    scanned = {r.doc_id: r.contaminated for r in decontaminate.scan(tiny, benchmark).collect()}
    assert all(scanned[i] for i, e in exact.items() if e)
    assert decontaminate.scan(odd, benchmark).where("contaminated").count() == 0
    assert decontaminate.scan(none, benchmark).count() == 0
    assert decontaminate.scan(tiny, benchmark.limit(0)).where("contaminated").count() == 0
    assert decontaminate.drop_contaminated(odd, benchmark).columns == odd.columns


@pytest.mark.parametrize("n,changed", [(9, 2), (12, 3), (15, 2), (15, 3), (18, 3), (20, 5)])
def test_any_few_words_of_a_short_item_replaced(n, changed):
    words = [f"w{k}" for k in range(n)]
    block = decontaminate.Block([(7, " ".join(words))])
    texts = ["lead in " + " ".join("swapped" if k in at else w for k, w in enumerate(words)) + " and out" for at in itertools.combinations(range(n), changed)]
    assert all(found == {7: max(found.values(), default=0)} for found in decontaminate.find(texts, block, decontaminate.Limits()))


@pytest.mark.parametrize("period", [4, 5])
def test_every_fourth_or_fifth_word_replaced(period):
    words = [f"w{k}" for k in range(59)]
    block = decontaminate.Block([(7, " ".join(words + ["more"] * 40))])
    for phase in range(period):
        text = " ".join("swapped" if k % period == phase else w for k, w in enumerate(words))
        assert 7 in decontaminate.find([text], block, decontaminate.Limits())[0]


def test_benchmark_in_blocks(spark, small, tiny, monkeypatch):
    benchmark = spark.read.parquet(f"{small}/benchmark.parquet")
    one = {r.doc_id: (r.contaminated, r.matched_words) for r in decontaminate.scan(tiny, benchmark).collect()}
    monkeypatch.setattr(decontaminate, "BLOCK_WORDS", 300)
    many = {r.doc_id: (r.contaminated, r.matched_words) for r in decontaminate.scan(tiny, benchmark).collect()}
    assert one == many
