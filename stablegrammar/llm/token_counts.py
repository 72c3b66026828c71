"""Token counts: batch encoding in Arrow functions that return lengths only."""

from __future__ import annotations

import re
from collections.abc import Iterator

import public_tokenizers
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stablegrammar.llm.common import map_texts, texts

#: A cut may stand before white space that follows other characters: no pre-token and no special string spans it.
_CUT = re.compile(r"(?<=[^\s])(?=[ \n\t])")


def safe_pieces(text: str, size: int) -> list[str]:
    """Cut a text into pieces of at least `size` characters whose token counts add up to the count of the whole."""
    if len(text) <= size:
        return [text]
    cuts, at = [0], size
    while at < len(text) and (m := _CUT.search(text, at)):
        cuts.append(m.start())
        at = m.start() + size
    return [text[a:b] for a, b in zip(cuts, [*cuts[1:], len(text)], strict=True)]


def balanced(sizes: list[int], most: int) -> list[tuple[int, int]]:
    """Half-open ranges of consecutive pieces that hold about `most` bytes each; a larger piece is a range of its own."""
    out, begin, held = [], 0, 0
    for k, size in enumerate(sizes):
        if k > begin and held + size > most:
            out.append((begin, k))
            begin, held = k, 0
        held += size
    if begin < len(sizes):
        out.append((begin, len(sizes)))
    return out


def token_counts(docs: DataFrame, vocabulary: str | None = None, *, limit: int = 512, piece_chars: int = 1 << 16, encode_bytes: int = 1 << 18, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit for every row.

    One narrow pass without a shuffle. Batches hold about 4 MB of UTF-8 bytes and reach the encoder in parts of about
    `encode_bytes`; texts beyond `piece_chars` are cut before white space, where byte-level pre-tokens end anyway. Texts of any length are counted whole. Null and empty texts: 0 bytes, 0 tokens. Null ids stay null. Repeated rows give repeated
    rows; other columns are ignored; an empty table gives an empty result.
    """
    path = vocabulary or public_tokenizers.path("byte_bpe_50k.json")

    def kernel(lists: Iterator) -> Iterator[dict]:
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        tok = Tokenizer.from_file(path)
        for ids, held in lists:
            pieces, owner = [], []
            for k, t in enumerate(held):
                own = safe_pieces(t, piece_chars)
                pieces += own
                owner += [k] * len(own)
            n = [0] * len(held)
            for a, b in balanced([len(x.encode()) for x in pieces], encode_bytes):
                for k, e in zip(owner[a:b], tok.encode_batch_fast(pieces[a:b], add_special_tokens=False), strict=True):
                    n[k] += len(e)
            yield {"doc_id": ids, "n_tokens": n, "n_bytes": [len(t.encode()) for t in held]}

    out = map_texts(texts(docs, id_col, text_col), kernel, "doc_id long, n_tokens long, n_bytes long")
    return out.select("doc_id", "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))
