"""License scan by ordered signature rules, in DataFrame functions alone.

A rule is a keyword (a word or phrase between blanks, or the start of one after a blank), a regular expression over the text's
words (joined by single blanks), a label, a priority and a confidence. Only rules whose keyword stands in the text are tried, so
every match of a rule holds its keyword. Detections are word
intervals. They are sorted by start, longest first, then priority; one that lies inside an earlier one
is suppressed, so a specific rule hides the general one that matches a part of the same words.

Signatures are written by hand (license_signatures.py), with a stem for each of their groups. Families of
licences, their versions and phrasings give further rules. A text is looked at only if it holds a stem or
a word of a family's keyword, which every match of a rule does.

Defined results: null text counts as empty: no words, no places, empty labels, score 0. Rows are judged
on their own: repeats, ties and null ids need no care, extra columns are left alone.
"""

from __future__ import annotations

from functools import reduce
from itertools import product

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ascii_lower, read_table
from .license_signatures import SIGNATURES

WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"

# The base phrases and their labels.
BASE = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}

# Families of licences with their versions and what they are called.
FAMILIES = [
    ("gpl", ["gnu general public license", "general public license", "gnu gpl", "gpl"], ["1 0", "2 0", "3 0", "1", "2", "3"]),
    ("lgpl", ["gnu lesser general public license", "gnu library general public license", "lesser general public license", "gnu lgpl", "lgpl"], ["2 0", "2 1", "3 0", "2", "3"]),
    ("agpl", ["gnu affero general public license", "affero general public license", "gnu agpl", "agpl"], ["1 0", "3 0", "3"]),
    ("gfdl", ["gnu free documentation license", "free documentation license", "gfdl"], ["1 1", "1 2", "1 3"]),
    ("apache", ["apache software license", "apache license", "asl"], ["1 0", "1 1", "2 0", "2"]),
    ("mpl", ["mozilla public license", "mpl"], ["1 0", "1 1", "2 0", "2"]),
    ("epl", ["eclipse public license", "epl"], ["1 0", "2 0"]),
    ("cddl", ["common development and distribution license", "cddl"], ["1 0", "1 1"]),
    ("eupl", ["european union public licence", "european union public license", "eupl"], ["1 0", "1 1", "1 2"]),
    ("bsl", ["boost software license", "bsl"], ["1 0"]),
    ("osl", ["open software license", "osl"], ["1 0", "2 0", "2 1", "3 0"]),
    ("artistic", ["artistic license"], ["1 0", "2 0"]),
    ("cc-by", ["creative commons attribution license", "creative commons attribution", "cc by"], ["1 0", "2 0", "2 5", "3 0", "4 0"]),
    ("cc-by-sa", ["creative commons attribution sharealike license", "creative commons attribution sharealike", "cc by sa"], ["1 0", "2 0", "2 5", "3 0", "4 0"]),
    ("cc-by-nc", ["creative commons attribution noncommercial license", "creative commons attribution noncommercial", "cc by nc"], ["1 0", "2 0", "2 5", "3 0", "4 0"]),
    ("cc-by-nd", ["creative commons attribution noderivatives license", "creative commons attribution noderivatives", "cc by nd"], ["2 0", "2 5", "3 0", "4 0"]),
    ("cc-by-nc-sa", ["creative commons attribution noncommercial sharealike license", "cc by nc sa"], ["2 0", "2 5", "3 0", "4 0"]),
    ("cc0", ["creative commons zero", "cc0"], ["1 0"]),
]
PHRASINGS = [
    (r"(?:licensed|released|distributed|available|published|covered) under (?:the )?(?:terms of (?:the )?)?{name}(?: license| licence)?", 0.96, 3),
    (r"(?:under|per|see) (?:the )?(?:terms (?:and conditions )?of )?(?:the )?{name}(?: license| licence)?", 0.93, 2),
    (r"(?:the )?{name}(?: license| licence)?", 0.8, 0),
]


def words_left(name: str) -> list[str]:
    """The words of a name that every phrasing keeps."""
    return [w for w in name.split() if w not in ("license", "licence")]


def shortest(stems: set[str]) -> list[str]:
    """Stems that hold no other one: whoever holds a longer one holds the shorter one too."""
    return sorted(s for s in stems if not any(o != s and o in s for o in stems))


def rules() -> list[tuple[str, str, str, int, float]]:
    """(keyword, expression, label, priority, confidence); hundreds, in order of priority."""
    out = [(f" {word} ", rf"(?<![^ ])(?:{rx})(?![^ ])", label, 5, conf) for entries in SIGNATURES.values() for label, rx, word, conf in entries]
    for label, names, versions in FAMILIES:
        keys = sorted({" ".join(words_left(n)) for n in names})
        for key in keys:
            own = "(?:" + "|".join(n for n in names if f" {key} " in f" {n} ") + ")"
            for phrase, conf, rank in PHRASINGS:
                out.append((f" {key}", rf"(?<![^ ])(?:{phrase.format(name=own)}(?:v?[0-9])?)(?![^ ])", label, rank, round(conf - 0.1, 2)))
            for (phrase, conf, rank), version in product(PHRASINGS, versions):
                tail = f"(?:(?: version| ?v)? )?v?{version}(?: or (?:any )?later(?: version)?)?"
                out.append((f" {key}", rf"(?<![^ ])(?:{phrase.format(name=own)}{tail})(?![^ ])", f"{label}-{version.replace(' ', '.')}", rank + 1, conf))
    return sorted(set(out), key=lambda r: (-r[3], -r[4], r[2], r[1]))


def quoted(text: str) -> str:
    return "'" + text.replace("\\", "\\\\").replace("'", "\\'") + "'"


def places(joined: Column, expression: Column) -> Column:
    """array<struct<first, last>>: word intervals of all matches. A word's number is the blanks before it."""
    gaps = F.split(joined, expression, -1)
    hits = F.regexp_extract_all(joined, expression, F.lit(0))
    blanks = lambda s: F.length(s) - F.length(F.replace(s, F.lit(" "), F.lit("")))
    pairs = F.arrays_zip(gaps.alias("gap"), hits.alias("hit"))
    empty = F.array().cast("array<struct<first:int,last:int>>")
    walked = F.aggregate(
        F.filter(pairs, lambda p: p["hit"].isNotNull()),
        F.struct(F.lit(0).alias("at"), empty.alias("found")),
        lambda acc, p: F.struct(
            (acc["at"] + blanks(p["gap"]) + blanks(p["hit"])).alias("at"),
            F.concat(acc["found"], F.array(F.struct((acc["at"] + blanks(p["gap"])).alias("first"), (acc["at"] + blanks(p["gap"]) + blanks(p["hit"])).alias("last")))).alias("found"),
        ),
    )
    return walked["found"]


def scan(docs: DataFrame) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, detections."""
    table = rules()
    keywords = sorted({r[0] for r in table})
    family = {max(words_left(n), key=len) for _, names, _ in FAMILIES for n in names}
    stems = shortest({*SIGNATURES, *family, *(max(phrase.split(), key=len) for phrase in BASE)})
    text = ascii_lower(F.coalesce(F.col("text"), F.lit("")))
    words = F.regexp_extract_all("lower", F.lit(WORD), F.lit(0))
    gate = reduce(lambda a, b: a | b, (F.contains("lower", F.lit(k)) for k in stems))
    base = docs.select("doc_id", text.alias("lower"))
    base = base.select("doc_id", F.regexp_count("lower", F.lit(WORD)).cast("long").alias("n_words"), F.when(gate, F.array_join(words, " ")).alias("joined"))
    rule_array = F.expr("array(" + ", ".join(f"named_struct('keyword', {quoted(k)}, 'rx', {quoted(x)}, 'label', {quoted(n)}, 'priority', {p}, 'confidence', {c}D)" for k, x, n, p, c in table) + ")")
    joined = F.col("joined")
    padded = F.concat(F.lit(" "), joined, F.lit(" "))
    present = F.filter(F.array(*map(F.lit, keywords)), lambda k: F.contains(padded, k))
    # One step per column, so that nothing is worked out twice.
    step = base.withColumn("present", F.when(joined.isNotNull(), present))
    step = step.withColumn("tried", F.when(F.size("present") > 0, F.filter(rule_array, lambda r: F.array_contains(F.col("present"), r["keyword"]))))
    step = step.withColumn("hit", F.when(F.col("tried").isNotNull(), F.filter("tried", lambda r: F.rlike(joined, r["rx"]))))
    step = step.withColumn(
        "spans",
        F.when(
            F.size("hit") > 0,
            F.array_sort(
                F.flatten(
                    F.transform(
                        "hit",
                        lambda r: F.transform(
                            places(joined, r["rx"]),
                            lambda s: F.struct(s["first"].alias("first"), (-s["last"]).alias("minus_last"), (-r["priority"]).alias("minus_priority"), r["label"].alias("label"), r["confidence"].alias("confidence")),
                        ),
                    )
                )
            ),
        ),
    )
    kept = F.aggregate(
        F.col("spans"),
        F.struct(F.lit(-1).alias("end"), F.array().cast("array<string>").alias("labels"), F.lit(0.0).alias("score"), F.lit(0).alias("n")),
        lambda acc, s: F.when(-s["minus_last"] > acc["end"], F.struct((-s["minus_last"]).alias("end"), F.array_union(acc["labels"], F.array(s["label"])).alias("labels"), F.greatest(acc["score"], s["confidence"]).alias("score"), (acc["n"] + 1).alias("n"))).otherwise(acc),
    )
    step = step.withColumn("kept", F.when(F.size("spans") > 0, kept))
    found = {label: F.when(F.contains(padded, F.lit(f" {phrase} ")), places(joined, F.lit(rf"(?<![^ ]){phrase}(?![^ ])"))) for phrase, label in BASE.items()}
    for label, column in found.items():
        step = step.withColumn(f"at_{label}", column)
    all_places = F.concat(*(F.transform(F.coalesce(F.col(f"`at_{x}`"), F.array().cast("array<struct<first:int,last:int>>")), lambda s: s["first"].cast("long")) for x in found))
    base_labels = F.array_compact(F.array(*(F.when(F.size(F.col(f"`at_{x}`")) > 0, F.lit(x)) for x in sorted(found))))
    step = step.withColumn("places", all_places).withColumn("base", base_labels)
    every = F.array_sort(F.array_distinct(F.concat("base", F.coalesce(F.col("kept.labels"), F.array().cast("array<string>")))))
    return step.select(
        "doc_id",
        "n_words",
        F.size("places").cast("long").alias("n_base"),
        F.array_min("places").alias("first_word"),
        F.array_max("places").alias("last_word"),
        F.array_join(F.array_sort("base"), ",").alias("base_labels"),
        F.array_join(every, ",").alias("labels"),
        F.greatest(F.coalesce(F.col("kept.score"), F.lit(0.0)), F.when(F.size("places") > 0, F.lit(0.7)).otherwise(F.lit(0.0))).alias("score"),
        F.coalesce(F.col("kept.n"), F.lit(0)).cast("long").alias("n_detections"),
    )


def op5_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(read_table(spark, sf_dir, "documents"))
