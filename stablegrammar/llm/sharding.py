"""Sharding: contiguous partition of ordered atomic groups that minimises the largest shard. DataFrame operations only."""

from __future__ import annotations

from bisect import bisect_right
from itertools import accumulate

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from stablegrammar.llm.common import settled

#: Equal texts fall into one of so many ordered groups. Their sizes are all the driver ever sees of the input.
GROUPS = 1 << 16
#: Slots are counted within cells of a shard, so that no task sorts a whole shard.
CELLS = 1 << 12


def fits(prefix: list[int], capacity: int, shards: int) -> list[int] | None:
    """Greedy cuts for a capacity: the first group of each further shard, or None if more shards would be needed."""
    cuts, at = [], 0
    for _ in range(shards):
        at = bisect_right(prefix, prefix[at] + capacity) - 1
        if at == len(prefix) - 1:
            return cuts
        cuts.append(at)
    return None


def minimax_cuts(sizes: list[int], shards: int) -> tuple[int, list[int]]:
    """The smallest capacity for which greedy filling needs at most `shards` contiguous shards, and its cuts."""
    prefix = list(accumulate(sizes, initial=0))
    lo, hi = max(max(sizes, default=0), -(-prefix[-1] // shards)), prefix[-1]
    while lo < hi:
        mid = (lo + hi) // 2
        if fits(prefix, mid, shards) is None:
            lo = mid + 1
        else:
            hi = mid
    return lo, fits(prefix, lo, shards) or []


def shard_by_bytes(docs: DataFrame, shards: int = 8, *, groups: int = GROUPS, cells: int = CELLS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard: every row in one of `shards` shards of nearly equal bytes.

    Size: UTF-8 bytes of the text (null: none) plus 1. Rows with equal texts share an atomic group, the value of a hash of the text
    taken modulo `groups`, and groups lie in that value's order. The driver gets one size for each of at most `groups` groups at any
    input size, searches the least feasible capacity, and the cuts return as literals. Slots number a shard's rows from 0 without
    gaps: rows are spread over cells by a hash of id and text, counted per (shard, cell), and numbered within their cell by doc_id.
    Null texts form a group of their own size 1 each; null ids are placed by their text; repeated rows get slots of their own; other
    columns are ignored; an empty table gives an empty result. One group of copies larger than a fair share bounds the balance.
    """
    text = docs[text_col]
    slim = settled(
        docs.select(
            docs[id_col].cast("long").alias("doc_id"),
            (F.coalesce(F.octet_length(text), F.lit(0)) + 1).cast("long").alias("size"),
            F.crc32(F.coalesce(text, F.lit("")).cast("binary")).alias("text_crc32"),
            F.pmod(F.xxhash64(text), F.lit(groups)).cast("int").alias("_group"),
            F.pmod(F.xxhash64(docs[id_col], text, F.lit(1)), F.lit(cells)).cast("int").alias("_cell"),
        )
    )
    found = slim.groupBy("_group").agg(F.sum("size").alias("size")).collect()  # at most `groups` rows
    sizes = [0] * groups
    for g, size in found:
        sizes[g] = size
    _, cuts = minimax_cuts(sizes, shards)
    shard: Column = F.lit(0)
    for c in cuts:
        shard = shard + (F.col("_group") >= c).cast("int")
    placed = slim.withColumn("shard", shard.cast("int"))
    counts = placed.groupBy("shard", "_cell").agg(F.count(F.lit(1)).alias("_n"))
    base = counts.select("shard", "_cell", (F.sum("_n").over(Window.partitionBy("shard").orderBy("_cell")) - F.col("_n")).alias("_base"))  # at most shards * cells rows
    within = placed.withColumn("_row", F.row_number().over(Window.partitionBy("shard", "_cell").orderBy("doc_id", "text_crc32")))
    return within.join(F.broadcast(base), ["shard", "_cell"]).select(
        "doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("_base") + F.col("_row") - 1).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard")
    )
