"""Substring dedup: runs of consecutive sentences that an earlier document or place already has are removed."""

from __future__ import annotations

import re
from collections.abc import Iterable, Iterator
from itertools import accumulate
from zlib import crc32

import numpy as np
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stablegrammar.llm.common import map_texts, settled, texts

#: Marks before white space, or line ends; it begins with one class of characters, for which the search looks fast.
_END = re.compile(r"[.!?\n](?:(?<=\n)|[.!?]*(?=\s))\s*")
_WORD = re.compile(r"\S+")
#: A sentence of more words counts as several parts of at most so many, cut where its words say so.
LONG = 16


def _cuts(words: list[str]) -> list[int]:
    """Word numbers before which a long sentence is cut: the last least hash of two neighbouring words in each LONG - 1 places in a row.

    They depend on the words near by alone, so the parts of a passage agree again after at most so many words, whatever stands before it.
    Runs of one repeated word, where no place differs from the next, are cut after every LONG words.
    """
    bare = "\n".join(words).encode("utf-8", "surrogatepass")
    spaced = (bare.replace(b"\n", b" \n") + b" ").split(b"\n")
    hashes = list(map(crc32, [*bare.split(b"\n")[1:], b""], map(crc32, spaced)))  # of "word next"
    if len(words) < LONG:
        return []
    out, last = [], 0

    def least(end: int) -> tuple[int, int]:
        window = hashes[end : end - LONG + 1 : -1]
        return (low := min(window)), end - window.index(low)

    low, at = least(LONG - 1)
    for end, h in enumerate([low, *hashes[LONG:]], LONG - 1):
        if end >= LONG:
            if h <= low:
                low, at = h, end
            elif at <= end - LONG + 1:  # the least one has left: the last least one of what remains
                low, at = least(end)
            else:
                continue
        if at > last and (hashes[at] != hashes[at - 1] or at - last >= LONG):
            out.append(at)
            last = at
    return out


def _starts(text: str, a: int, b: int, words: list[str]) -> list[int]:
    """Where the words of text[a:b] begin; where one character of white space stands between any two, their lengths tell."""
    if text.startswith(words[0], a) and sum(map(len, words)) + len(words) - 1 == len(text[a:b].rstrip()):
        return [x + k for k, x in enumerate(accumulate(map(len, words[:-1]), initial=a))]
    return [m.start() for m in _WORD.finditer(text, a, b)]


def sentences(text: str) -> list[tuple[int, int]]:
    """Half-open code-point ranges that tile the text: sentences with the white space after them; long ones in parts of up to LONG words."""
    out, a = [], 0
    for b in [*(m.end() for m in _END.finditer(text)), len(text)]:
        if b > a:
            words = text[a:b].split() if b - a > 2 * LONG else ()
            if len(words) > LONG:
                starts = _starts(text, a, b, words)
                cuts = [starts[k] for k in _cuts(words)]
                out += zip([a, *cuts], [*cuts, b], strict=True)
            else:
                out.append((a, b))
        a = max(a, b)
    return out


def _words(text: str, a: int, b: int) -> str:
    return " ".join(text[a:b].split())


def _run_hashes(parts: list[str], starts: Iterable[int], run: int) -> np.ndarray:
    """128 bits, as two signed longs, of the runs of `run` consecutive parts that begin at `starts`."""
    digests = [xxhash.xxh3_128_digest("\n".join(parts[k : k + run])) for k in starts]
    return np.frombuffer(b"".join(digests), ">i8").reshape(-1, 2).astype(np.int64)


def sentence_runs(docs: DataFrame, run: int) -> DataFrame:
    """(hi, lo, doc_id, at) of every run of `run` consecutive sentences; `at` numbers the run's first sentence; white space doesn't count."""

    def kernel(lists: Iterator) -> Iterator[dict]:
        for ids, held in lists:
            hashes, sizes = [np.empty((0, 2), np.int64)], []
            for t in held:
                s = [_words(t, a, b) for a, b in sentences(t)]
                hashes.append(_run_hashes(s, range(len(s) - run + 1), run))
                sizes.append(len(hashes[-1]))
            flat = np.concatenate(hashes)
            at = np.concatenate([np.arange(n, dtype=np.int32) for n in sizes] or [np.empty(0, np.int32)])
            yield {"hi": flat[:, 0], "lo": flat[:, 1], "doc_id": np.repeat(np.array(ids, np.int64), sizes), "at": at}

    return map_texts(docs, kernel, "hi long, lo long, doc_id long, at int")


def _stretches(places: list[int]) -> list[list[int]]:
    """Sorted sentence numbers in groups of consecutive ones."""
    out: list[list[int]] = []
    for k in places:
        if out and out[-1][-1] == k - 1:
            out[-1].append(k)
        else:
            out.append([k])
    return out


def _without_repeats(text: str, marks: list[dict], run: int, least_words: int) -> tuple[int, int, int, list[dict], str]:
    """(sentences, removed ones, their words, removed ranges, text that stays) for marks(at, lo) of repeated runs.

    A mark holds only where the text's own run has its hash: rows that share an id but not the text don't lose each other's places.
    """
    s = sentences(text)
    if not marks:
        return len(s), 0, 0, [], text
    marks = [m for m in marks if m["at"] + run <= len(s)]
    near = {k: _words(text, *s[k]) for m in marks for k in range(m["at"], m["at"] + run)}
    own = [int(_run_hashes([near[m["at"] + d] for d in range(run)], (0,), run)[0, 1]) for m in marks]
    starts = [m["at"] for m, lo in zip(marks, own, strict=True) if lo == m["lo"]]
    cut, words, n = [], 0, 0
    for group in _stretches(sorted({k + d for k in starts for d in range(run)})):
        a, b = s[group[0]][0], s[group[-1]][1]
        if (w := len(text[a:b].split())) >= least_words:
            cut.append((a, b))
            words += w
            n += len(group)
    kept = "".join(text[a:b] for a, b in zip([0, *(b for _, b in cut)], [*(a for a, _ in cut), len(text)], strict=True))
    return len(s), n, words, [{"start": a, "end": b} for a, b in cut], kept


def remove_repeated_spans(docs: DataFrame, *, run: int = 2, least_words: int = 0, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_sentences, n_removed, removed_words, removed (array of half-open code-point ranges), clean_text, for every row.

    Every run of `run` consecutive sentences (parts of up to 16 words, cut by content, where a sentence is long) is hashed to 128 bits
    and joined globally; the first place by (doc_id, position) keeps it, and the sentences of all other places go. `least_words` is an
    option: then only removed stretches of so many words go. Counts come before the join, with partial sums, and only hashes of several
    places are joined back, a hot one being left to the skew join. Null and empty texts are unchanged (clean text empty); texts of any
    length are cut whole; rows with a null id neither remove nor lose anything; rows that share an id count as one document, whose equal
    runs at one position are one place, and each loses what its own text repeats. Other columns are ignored; an empty table gives an
    empty result.
    """
    own = texts(docs, id_col, text_col)
    runs = sentence_runs(own.where("doc_id is not null"), run)
    places = runs.groupBy("hi", "lo").agg(F.min("doc_id").alias("_doc"), F.max("doc_id").alias("_last"), F.min("at").alias("_lo"), F.max("at").alias("_hi"))
    first = places.where("_doc < _last or _lo < _hi").select("hi", "lo", "_doc")
    repeated = settled(runs.join(settled(first), ["hi", "lo"]))
    keeper = repeated.where("doc_id = _doc").groupBy("hi", "lo").agg(F.min("at").alias("_at"))
    later = repeated.join(settled(keeper), ["hi", "lo"]).where("doc_id <> _doc or at > _at")
    marks = later.groupBy("doc_id").agg(F.collect_set(F.struct("at", "lo")).alias("marks"))  # of one document: as many as its runs
    marked = own.join(settled(marks), "doc_id", "left").select("doc_id", "text", "marks")

    def kernel(batches: Iterator) -> Iterator:
        import pyarrow as pa

        kinds = {"n_sentences": pa.int32(), "n_removed": pa.int32(), "removed_words": pa.int64(), "removed": pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())])), "clean_text": pa.string()}
        for x in batches:
            rows = [_without_repeats(t.as_py(), m.as_py() or [], run, least_words) for t, m in zip(x.column("text"), x.column("marks"), strict=True)]
            columns = [pa.array([r[k] for r in rows], kind) for k, kind in enumerate(kinds.values())]
            yield pa.RecordBatch.from_arrays([x.column("doc_id"), *columns], ["doc_id", *kinds])

    return marked.mapInArrow(kernel, "doc_id long, n_sentences int, n_removed int, removed_words long, removed array<struct<start:int,end:int>>, clean_text string")
