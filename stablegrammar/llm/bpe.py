"""Byte-level BPE encoding and decoding with vectorised pre-tokenisation.

Pre-tokens of the public byte-level pattern are found without a regex. Code points become classes through one table; each class is a
transition function over four states, packed in a byte; composing the functions with an associative scan tells for every character
whether an apostrophe there opens a contraction; all other boundaries follow from neighbouring classes. The slices between boundaries
feed a cached pair merging, and byte offsets are kept.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
import sys
import unicodedata
from collections.abc import Iterator
from itertools import chain

import numpy as np
import public_tokenizers
from pyspark.sql import DataFrame

from stablegrammar.llm.common import map_texts, texts

# Code points with the White_Space property.
WHITE_SPACE = (9, 10, 11, 12, 13, 32, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000)

LETTER, NUMBER, OTHER, SPACE, BLANK, SHORT, LONG = range(7)  # SPACE: U+0020, BLANK: other white space, SHORT and LONG: an apostrophe before 's and 're etc.
FRESH, CLOSED, LAST, LAST_BUT_ONE = range(4)


def _pack(targets: tuple[int, int, int, int]) -> int:
    return sum(t << 2 * s for s, t in enumerate(targets))


#: Transition of each class from the states FRESH, CLOSED, LAST, LAST_BUT_ONE. The last two are inside a contraction.
_INSIDE = (FRESH, LAST)
TRANSITIONS = np.array([_pack((first, second, *_INSIDE)) for first, second in ((FRESH, FRESH), (FRESH, FRESH), (CLOSED, CLOSED), (CLOSED, CLOSED), (FRESH, FRESH), (LAST, CLOSED), (LAST_BUT_ONE, CLOSED))], np.uint8)


def _composition() -> np.ndarray:
    f, g = np.meshgrid(np.arange(256), np.arange(256), indexing="ij")
    out = np.zeros((256, 256), np.uint8)
    for s in range(4):
        out |= (((g >> 2 * ((f >> 2 * s) & 3)) & 3) << 2 * s).astype(np.uint8)
    return out.ravel()


def class_table() -> np.ndarray:
    """The class of each code point."""
    out = np.full(sys.maxunicode + 1, OTHER, np.uint8)
    for cp in chain(range(0xD800), range(0xF900, 0x32400)):
        kind = unicodedata.category(chr(cp))[0]
        if kind in "LN":
            out[cp] = LETTER if kind == "L" else NUMBER
    out[list(WHITE_SPACE)] = BLANK
    out[32] = SPACE
    return out


def scan_states(functions: np.ndarray, compose: np.ndarray, block: int = 32) -> np.ndarray:
    """State before each position, from FRESH, by composing packed functions: within blocks, then over blocks, then within again."""
    n = len(functions)
    if n <= block:
        states, s = np.zeros(n, np.uint8), 0
        for i, f in enumerate(functions.tolist()):
            states[i] = s
            s = (f >> 2 * s) & 3
        return states
    identity = _pack((0, 1, 2, 3))
    grid = np.full(-(-n // block) * block, identity, np.uint8)
    grid[:n] = functions
    grid = np.ascontiguousarray(grid.reshape(-1, block).T)  # one row for each place in a block
    total = grid[0]
    for row in grid[1:]:
        total = compose[(total.astype(np.uint16) << 8) | row]
    states = np.empty_like(grid)
    states[0] = scan_states(total, compose, block)
    for k in range(1, block):
        states[k] = (grid[k - 1] >> (2 * states[k - 1])) & 3
    return np.ascontiguousarray(states.T).ravel()[:n]


def boundaries(cps: np.ndarray, text_starts: np.ndarray, table: np.ndarray, compose: np.ndarray) -> np.ndarray:
    """Mask of the characters at which a pre-token starts. cps: code points of texts laid end to end; text_starts: where each text begins."""
    n = len(cps)
    kind = table[cps]
    first = np.zeros(n + 1, bool)
    first[text_starts] = True
    first[n] = True
    last = first[1:]  # of each text's last character
    nxt = np.zeros((2, n + 2), cps.dtype)
    nxt[0, : n - 1] = np.where(last[:-1], 0, cps[1:])
    nxt[1, : max(0, n - 2)] = np.where(last[:-2] | last[1:-1], 0, cps[2:])
    a, b = nxt[0, :n], nxt[1, :n]
    quote = cps == ord("'")
    short = quote & ((a == ord("s")) | (a == ord("t")) | (a == ord("m")) | (a == ord("d")))
    long = quote & (((a == ord("r")) & (b == ord("e"))) | ((a == ord("v")) & (b == ord("e"))) | ((a == ord("l")) & (b == ord("l"))))
    coarse = kind.copy()
    kind = np.where(short, SHORT, np.where(long, LONG, kind)).astype(np.uint8)
    functions = TRANSITIONS[kind]
    at_start = (functions[text_starts] & 3) * 0b01010101  # at a text's start, whatever the state was: as from FRESH
    functions[text_starts] = at_start
    states = scan_states(functions, compose)
    states[text_starts] = FRESH

    blank = (coarse == SPACE) | (coarse == BLANK)
    group = np.where(blank, BLANK, coarse)
    start = np.empty(n, bool)
    start[0] = True
    start[1:] = (group[1:] != group[:-1]) & ((coarse[:-1] != SPACE) | blank[1:])
    before_other = np.zeros(n, bool)  # the last of a run of white space which something follows
    before_other[:-1] = blank[:-1] & ~blank[1:]
    start |= before_other & ~last
    inside = states >= LAST
    after = np.zeros(n, bool)
    after[1:] = states[:-1] == LAST
    start = (start & ~inside) | (after & ~inside)
    start[text_starts] = True
    return start


def merge_pairs(piece: bytes, ranks: dict[bytes, int]) -> tuple[int, ...]:
    """Ids of a slice: the adjacent pair of lowest rank merges first, the leftmost among equals."""
    if (r := ranks.get(piece)) is not None:
        return (r,)
    if len(piece) > 64:
        return _merge_long(piece, ranks)
    parts = [piece[i : i + 1] for i in range(len(piece))]
    none = len(ranks) + 1
    pair = [ranks.get(parts[i] + parts[i + 1], none) for i in range(len(parts) - 1)]
    while pair and (best := min(pair)) < none:
        i = pair.index(best)
        parts[i : i + 2] = [parts[i] + parts[i + 1]]
        del pair[i]
        if i:
            pair[i - 1] = ranks.get(parts[i - 1] + parts[i], none)
        if i < len(pair):
            pair[i] = ranks.get(parts[i] + parts[i + 1], none)
    return tuple(ranks[p] for p in parts)


def _merge_long(piece: bytes, ranks: dict[bytes, int]) -> tuple[int, ...]:
    """The same with a heap and linked places, for slices without any boundary."""
    n = len(piece)
    end = list(range(1, n + 1))  # end of the part that begins here; 0: no part begins here
    prev = list(range(-1, n - 1))
    heap = [(r, i, i + 2) for i in range(n - 1) if (r := ranks.get(piece[i : i + 2])) is not None]
    heapq.heapify(heap)
    while heap:
        _, i, stop = heapq.heappop(heap)
        mid = end[i]
        if not mid or mid >= n or not end[mid] or end[mid] != stop:
            continue
        end[i], end[mid] = stop, 0
        if stop < n:
            prev[stop] = i
            if (r := ranks.get(piece[i : end[stop]])) is not None:
                heapq.heappush(heap, (r, i, end[stop]))
        if i and (r := ranks.get(piece[prev[i] : stop])) is not None:
            heapq.heappush(heap, (r, prev[i], stop))
    return tuple(ranks[piece[i : end[i]]] for i in range(n) if end[i])


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}


class Encoder:
    """Encodes lists of texts and decodes ids; keeps the ids of slices seen, up to `cached` of them."""

    def __init__(self, path: str, cached: int = 200_000):
        self.ranks = load_ranks(path)
        self.tokens = {v: k for k, v in self.ranks.items()}
        self.table, self.compose, self.cached = class_table(), _composition(), cached
        self.cache: dict[bytes, tuple[tuple[int, ...], str]] = {}

    def slices(self, held: list[str]) -> Iterator[tuple[bytes, list[int]]]:
        """Per text its UTF-8 bytes and the byte offsets of its pre-tokens, the end included."""
        raw = "".join(held)
        cps = np.frombuffer(raw.encode("utf-32-le"), np.uint32)
        sizes = np.fromiter(map(len, held), np.int64, len(held))
        starts = np.cumsum(sizes) - sizes
        if len(cps):
            mask = boundaries(cps, starts[sizes > 0], self.table, self.compose)
            width = 1 + (cps >= 0x80).astype(np.int64) + (cps >= 0x800) + (cps >= 0x10000)
            before = np.cumsum(width) - width
            at = np.flatnonzero(mask)
            offsets, cut = before[at], np.searchsorted(at, starts)
        for k, t in enumerate(held):
            if not t:
                yield b"", [0]
                continue
            own = offsets[cut[k] : cut[k + 1] if k + 1 < len(held) else None]
            data = t.encode()
            yield data, [*(own - own[0]).tolist(), len(data)]

    def encode(self, held: list[str]) -> Iterator[tuple[list[int], str, list[int]]]:
        """Per text: ids, the ids as decimal numbers joined by commas, and the byte offsets of the pre-tokens."""
        cache, ranks = self.cache, self.ranks
        for data, at in self.slices(held):
            if len(cache) > self.cached:
                cache.clear()
            pieces = [data[a:b] for a, b in zip(at, at[1:], strict=False)]
            found = list(map(cache.get, pieces))
            if None in found:
                for k, x in enumerate(found):
                    if x is None:
                        if (x := cache.get(pieces[k])) is None:
                            ids = merge_pairs(pieces[k], ranks)
                            x = (ids, ",".join(map(str, ids)))
                            if len(pieces[k]) <= 64:
                                cache[pieces[k]] = x
                        found[k] = x
            yield list(chain.from_iterable(x[0] for x in found)), ",".join([x[1] for x in found]), at

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.tokens.__getitem__, ids))


def bpe_round_trip(docs: DataFrame, vocabulary: str | None = None, *, id_col: str = "doc_id", text_col: str = "text", keep: tuple[str, ...] = ("ids", "offsets")) -> DataFrame:
    """Encode every text, decode the ids, and return doc_id, n_tokens, ids_sha256, decoded_sha256 and the columns named in `keep`.

    ids: array of token ids; offsets: byte offsets of the pre-tokens, the end included. Digests are lowercase hex, of the decimal ids
    joined by commas and of the decoded bytes. One narrow pass; batches hold about 1 MB. Null and empty texts have no ids. Null ids of
    documents stay null; repeated rows give repeated rows; other columns are ignored; an empty table gives an empty result.
    """
    path = vocabulary or public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
    kinds = {"ids": "array<int>", "offsets": "array<long>"}
    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + "".join(f", {k} {kinds[k]}" for k in keep)

    def kernel(lists: Iterator) -> Iterator[dict]:
        enc = Encoder(path)
        for doc_ids, held in lists:
            out: dict[str, list] = {"doc_id": doc_ids, "n_tokens": [], "ids_sha256": [], "decoded_sha256": [], **{k: [] for k in keep}}
            for ids, joined, at in enc.encode(held):
                out["n_tokens"].append(len(ids))
                out["ids_sha256"].append(hashlib.sha256(joined.encode()).hexdigest())
                out["decoded_sha256"].append(hashlib.sha256(enc.decode(ids)).hexdigest())
                for k, v in (("ids", ids), ("offsets", at)):
                    if k in keep:
                        out[k].append(v)
            yield out

    return map_texts(texts(docs, id_col, text_col), kernel, schema, 1 << 20)
