"""Locally consistent parsing rounds over tables seq(string_id, pos, sym, fp): the DataFrame engine.

A break is a position that starts a run of equal fingerprints between a larger one on its left and a larger one as the first different
one on its right. That closed form needs neighbours only, so window sorts on string_id serve a round.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from stablegrammar.functions.hashing import HashFamily, affine_hash, poly_hash


def symbols(strings: DataFrame, family: HashFamily) -> DataFrame:
    """seq of strings(string_id, text) by characters, or of strings(string_id, syms) by integers; empty strings have no rows."""
    if "syms" in strings.columns:
        rows = strings.select("string_id", F.posexplode("syms").alias("_p", "_c"))
    else:
        rows = strings.where("text <> ''").select("string_id", F.posexplode(F.split("text", "")).alias("_p", "_ch")).select("string_id", "_p", F.ascii("_ch").alias("_c"))
    return rows.select("string_id", (F.col("_p") + 1).cast("long").alias("pos"), F.col("_c").cast("string").alias("sym"), affine_hash(F.col("_c"), family[0]).alias("fp"))


def _by():
    return Window.partitionBy("string_id").orderBy("pos")


def _back():
    """From the current position to the end, as a running frame of the reverse order: linear, unlike a frame that shrinks."""
    return Window.partitionBy("string_id").orderBy(F.desc("pos")).rowsBetween(Window.unboundedPreceding, Window.currentRow)


def position_types(seq: DataFrame, by: str = "fp") -> DataFrame:
    """seq with type (L, S, or null in the last run) and is_break (S-type after L-type)."""
    step = F.signum(F.lead(by).over(_by()) - F.col(by))
    typed = seq.withColumn("_step", F.when(step != 0, step))
    typed = typed.withColumn("_next", F.last("_step", ignorenulls=True).over(_back())).withColumn("_prev", F.lag(by).over(_by()))
    kind = F.when(F.col("_next") > 0, "S").when(F.col("_next") < 0, "L")
    return typed.select(*seq.columns, kind.alias("type"), F.coalesce((F.col("_next") > 0) & (F.col("_prev") > F.col(by)), F.lit(False)).alias("is_break"))


def local_min_breaks(seq: DataFrame, width: int = 2) -> DataFrame:
    """Alternative rule: a break where the fingerprint is the strict minimum of `width` neighbours on each side, all of which exist."""
    side = lambda f, k: F.coalesce(f("fp", k).over(_by()) > F.col("fp"), F.lit(False))
    low = F.lit(True)
    for k in range(1, width + 1):
        low = low & side(F.lag, k) & side(F.lead, k)
    return seq.withColumn("is_break", low)


def hash_mod_breaks(seq: DataFrame, d: int = 4) -> DataFrame:
    """Alternative rule: a break where the fingerprint is 0 modulo d, unless the position before would be one too."""
    hit = lambda c: F.pmod(c, F.lit(d)) == 0
    prev = F.lag("fp").over(_by())
    return seq.withColumn("is_break", F.coalesce(hit(F.col("fp")) & prev.isNotNull() & ~hit(prev), F.lit(False)) & (F.col("pos") > 2))


def value_order_breaks(seq: DataFrame) -> DataFrame:
    """The deterministic ancestor: types compare the symbols' own values instead of fingerprints."""
    return position_types(seq.withColumn("value", F.col("sym").cast("long")), by="value").drop("value")


def cut_phrases(marked: DataFrame, level: int, family: HashFamily) -> DataFrame:
    """Phrases of a marked seq: (string_id, phrase_no, start, len, sym, fp, rhs), named by the digest of level and content."""
    no = F.sum(F.col("is_break").cast("long")).over(_by().rowsBetween(Window.unboundedPreceding, 0)) + 1
    parts = marked.withColumn("phrase_no", no).groupBy("string_id", "phrase_no").agg(F.array_sort(F.collect_list(F.struct("pos", "sym", "fp"))).alias("_x"))
    return parts.select(
        "string_id", "phrase_no", F.col("_x")[0]["pos"].alias("start"), F.size("_x").alias("len"),
        content_name(F.col("_x.sym"), level).alias("sym"), poly_hash(F.col("_x.fp"), family[level]).alias("fp"), F.col("_x.sym").alias("rhs"),
    )


def content_name(rhs: Column, level: int) -> Column:
    return F.md5(F.concat(F.lit(f"{level}:"), F.array_join(rhs, ",")))


def run_round(seq: DataFrame, level: int, family: HashFamily, breaks=position_types) -> tuple[DataFrame, DataFrame]:
    """One round over active strings: the next seq, and the phrases that it was made from."""
    phrases = cut_phrases(breaks(seq), level, family)
    return phrases.select("string_id", F.col("phrase_no").alias("pos"), "sym", "fp"), phrases
