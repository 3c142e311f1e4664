"""The text rules in plain Python, for UDFs, streams and tests; equal to the Column forms."""

from __future__ import annotations

import re

#: Unicode's space separators; as BLANKS of the Column forms.
BLANKS = " \u00a0\u1680\u2000\u2001\u2002\u2003\u2004\u2005\u2006\u2007\u2008\u2009\u200a\u202f\u205f\u3000"


def paragraphs(text: str) -> list[str]:
    return [p for x in text.split("\n") if (p := x.strip(BLANKS))]


def sentences(text: str) -> list[str]:
    return [s for x in re.sub(r"([.!?]+)[ \t\r\f\n]+", "\\1\x01", text).split("\x01") if (s := x.strip(BLANKS))]


def all_sentences(text: str) -> list[str]:
    return [s for p in paragraphs(text) for s in sentences(p)]


def cue(sentence: str, idx: int) -> float:
    return 1 / (1 + (len(sentence) + idx) % 7)


def segmented(text: str) -> list[str]:
    out, held = [], []
    for i, s in enumerate(all_sentences(text)):
        held.append(s)
        if cue(s, i) > 0.5:
            out.append(" ".join(held))
            held = []
    return out + ([" ".join(held)] if held else [])


def edits(a: str, b: str) -> int:
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1]
