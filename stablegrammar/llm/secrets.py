"""Secret scans: fixed patterns, and sliding-window Shannon entropy per character class."""

from __future__ import annotations

import math
import re
from collections.abc import Iterator

from pyspark.sql import DataFrame

from stablegrammar.llm.common import map_texts, texts

# The base patterns and the order of their kinds.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
KINDS = ("assign", "access", "hex", "entropy_hex", "entropy_base64")

#: Candidate strings, and per character class its alphabet, window and least bits per character.
CANDIDATE = re.compile(r"[A-Za-z0-9+/_=-]{20,}")
CLASSES = {"entropy_hex": (frozenset("0123456789abcdefABCDEF"), 24, 3.0), "entropy_base64": (frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_-="), 20, 3.9)}
#: Candidates that are known to be harmless: one class of letters only, words joined by hyphens or underscores, dates, UUIDs, paths.
ALLOW = re.compile(r"[A-Z]?[a-z]+|[A-Z]+|[A-Za-z]+(?:[-_/][A-Za-z]+)+|[-_=+/]+|\d+|\d{4}-\d\d-\d\d[-_T0-9]*|[0-9a-fA-F]{8}(?:-[0-9a-fA-F]{4}){3}-[0-9a-fA-F]{12}")


def entropy_spans(s: str, alphabet: frozenset, window: int, least: float) -> list[tuple[int, int]]:
    """Maximal unions of windows, within runs over the alphabet, whose entropy is at least `least` bits; counts move by one character in and one out."""
    plogp = [0.0] + [-(c / window) * math.log2(c / window) for c in range(1, window + 1)]
    out: list[tuple[int, int]] = []
    counts: dict[str, int] = {}
    h, run = 0.0, 0
    for j, ch in enumerate(s):
        if ch not in alphabet:
            counts, h, run = {}, 0.0, 0
            continue
        run += 1
        if run > window:
            old = s[j - window]
            c = counts[old]
            h += plogp[c - 1] - plogp[c]
            counts[old] = c - 1
        c = counts.get(ch, 0)
        h += plogp[c + 1] - plogp[c]
        counts[ch] = c + 1
        if run >= window and h >= least - 1e-9:
            a = j - window + 1
            if out and a <= out[-1][1]:
                out[-1] = (out[-1][0], j + 1)
            else:
                out.append((a, j + 1))
    return out


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """Matches of the three base patterns, leftmost and non-overlapping per kind, ordered by start, then kind."""
    found = [(m.start(), m.end(), "assign") for m in ASSIGN.finditer(text) if len(m[2]) >= 6]
    found += [(m.start(), m.end(), "access") for m in ACCESS.finditer(text) if len(m[0]) >= 20]
    found += [(m.start(), m.end(), "hex") for m in HEX.finditer(text)]
    return sorted(found, key=lambda x: (x[0], KINDS.index(x[2])))


def method_spans(text: str) -> list[tuple[int, int, str]]:
    """High-entropy windows in candidate strings that the allow-list doesn't suppress."""
    found = []
    for m in CANDIDATE.finditer(text):
        if ALLOW.fullmatch(m[0]):
            continue
        for kind, (alphabet, window, least) in CLASSES.items():
            if kind == "entropy_base64" and not (re.search("[0-9]", m[0]) and re.search("[A-Za-z]", m[0])):
                continue
            found += [(m.start() + a, m.start() + b, kind) for a, b in entropy_spans(m[0], alphabet, window, least)]
    return found


def secret_scan(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, spans: array of (kind, start, end) in code points, end exclusive, ordered by start, then kind as in KINDS.

    Base spans always stay; entropy spans come besides. One narrow pass. Null and empty texts have no spans; texts of any
    length are scanned whole; spans that start together are ordered by kind; null ids stay null; repeated rows give repeated rows; other columns are ignored; an empty table gives an empty result.
    """

    def kernel(lists: Iterator) -> Iterator[dict]:
        for ids, held in lists:
            spans = [[{"kind": k, "start": a, "end": b} for a, b, k in sorted([*base_spans(t), *method_spans(t)], key=lambda x: (x[0], KINDS.index(x[2])))] for t in held]
            yield {"doc_id": ids, "spans": spans}

    return map_texts(texts(docs, id_col, text_col), kernel, "doc_id long, spans array<struct<kind:string,start:long,end:long>>")

