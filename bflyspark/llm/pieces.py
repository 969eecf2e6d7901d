"""Cutting texts into the pieces of byte-level BPE, fast for Latin text and exact for all."""

from __future__ import annotations

import re

import regex

# The letters and the numbers below U+0250, and its white space.
LATIN_LETTER = "A-Za-z\xaa\xb5\xba\xc0-\xd6\xd8-\xf6\xf8-ɏ"
LATIN_NUMBER = "0-9\xb2\xb3\xb9\xbc-\xbe"
LATIN_BLANK = r"\t-\r \x85\xa0"

WORD_BYTES = 64

BEYOND_LATIN = re.compile("[^\x00-ɏ]")


class Cutter:
    """Cuts by a pattern that is made of \\p{L}, \\p{N}, \\s and \\S as Unicode properties."""

    def __init__(self, pattern: str):
        exact = pattern.replace(r"[^\s", r"[^\p{White_Space}").replace(r"\s", r"\p{White_Space}").replace(r"\S", r"\P{White_Space}")
        self.exact = regex.compile(exact).findall
        latin = pattern.replace(r"[^\s\p{L}\p{N}]", f"[^{LATIN_BLANK}{LATIN_LETTER}{LATIN_NUMBER}]")
        for name, chars in ((r"\p{L}", LATIN_LETTER), (r"\p{N}", LATIN_NUMBER), (r"\s", LATIN_BLANK)):
            latin = latin.replace(name, f"[{chars}]")
        self.latin = re.compile(latin.replace(r"\S", f"[^{LATIN_BLANK}]")).findall

    def __call__(self, text: str) -> list[str]:
        return (self.exact if BEYOND_LATIN.search(text) else self.latin)(text)


class Memo:
    """Values of words, the recent ones kept: two generations of bounded size, the older one dropped when the newer is full.

    size is in words that take WORD_BYTES at most; longer ones count as several.
    """

    def __init__(self, size: int, fill):
        self.size, self.fill = size, fill
        self.new: dict[str, object] = {}
        self.old: dict[str, object] = {}
        self.long = 0

    def __call__(self, words: list[str]) -> list:
        new = self.new
        out = list(map(new.get, words))
        if None in out:
            gaps = [i for i, x in enumerate(out) if x is None]
            missing: dict[str, None] = {}
            for i in gaps:
                if (value := self.old.get(words[i])) is None:
                    missing[words[i]] = None
                else:
                    new[words[i]] = value
            if missing:
                new.update(zip(missing, self.fill(list(missing)), strict=True))
                self.long += sum(len(w) // WORD_BYTES for w in missing if len(w) > WORD_BYTES)
            for i in gaps:
                out[i] = new[words[i]]
            if len(new) + self.long > self.size:
                self.old, self.new, self.long = new, {}, 0
        return out
