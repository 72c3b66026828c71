"""Cost and quality measures of grammars, strings and stages."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from stablegrammar.operators.model import Grammar
from stablegrammar.operators.post import as_items


def level_stats(g: Grammar) -> DataFrame:
    """level, g_i nonterminals, size_i symbols of right-hand sides, exp_i characters below."""
    return g.rules.groupBy("level").agg(F.count(F.lit(1)).alias("g_i"), F.sum("rhs_len").cast("long").alias("size_i"), F.sum("exp_len").alias("exp_i"))


def totals(g: Grammar) -> dict[str, int]:
    """g (nonterminals, run rules included), G (sizes, run rules counting 2), k strings, and the largest level's g and G."""
    n, size = g.rules.agg(F.count(F.lit(1)), F.coalesce(F.sum("rhs_len"), F.lit(0))).first()
    runs = g.runs.count() if g.runs is not None else 0
    most = level_stats(g).agg(F.max("g_i"), F.max("size_i")).first()
    return {"g": n + runs, "G": size + 2 * runs, "k": g.roots.count(), "runs": runs, "largest_g": most[0] or 0, "largest_G": most[1] or 0}


def stage_stats(before: dict[str, int], after: dict[str, int]) -> dict[str, float]:
    """Percent of nonterminals added and removed, and of size saved, between two stages' totals."""
    share = lambda x, of: round(100 * x / of, 5) if of else 0.0
    return {"pct_added": share(after["runs"] - before["runs"], before["g"]), "pct_deleted": share(max(0, before["g"] - after["g"]), before["g"]), "pct_smaller": share(before["G"] - after["G"], before["G"])}


def encoded_bits(t: dict[str, int], sigma: int) -> int:
    """Size model: each symbol of a right-hand side or root in ceil(log2(g + sigma)) bits, each rule's end in ceil(log2 G)."""
    sym, end = max(1, (t["g"] + sigma - 1).bit_length()), max(1, t["G"].bit_length())
    return t["G"] * sym + t["g"] * end + t["k"] * sym


def plain_bytes(strings: DataFrame) -> int:
    return strings.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]


def fingerprint_collisions(g: Grammar) -> DataFrame:
    """level, symbols, collisions: symbols that share their level's fingerprint with an earlier one."""
    return g.rules.groupBy("level", "fp").agg(F.count(F.lit(1)).alias("n")).groupBy("level").agg(F.sum("n").alias("symbols"), F.sum(F.col("n") - 1).alias("collisions"))


def adjacent_collisions(seq: DataFrame) -> DataFrame:
    """Neighbours with equal fingerprints but different symbols: the only collisions that can lose a break."""
    w = Window.partitionBy("string_id").orderBy("pos")
    hit = (F.lag("fp").over(w) == F.col("fp")) & (F.lag("sym").over(w) != F.col("sym"))
    return seq.select(F.coalesce(hit, F.lit(False)).cast("long").alias("h")).agg(F.count(F.lit(1)).alias("positions"), F.coalesce(F.sum("h"), F.lit(0)).alias("collisions"))


def key_bytes(g: Grammar) -> DataFrame:
    """fixed32 and vbyte bytes of all phrase keys of a dense grammar, by level."""
    size = lambda x: F.when(x < 1 << 7, 1).when(x < 1 << 14, 2).when(x < 1 << 21, 3).when(x < 1 << 28, 4).otherwise(5)
    v = F.aggregate("rhs", F.lit(0), lambda acc, x: acc + size(x))
    return g.rules.groupBy("level").agg(F.sum(4 * F.size("rhs")).cast("long").alias("fixed32"), F.sum(v).cast("long").alias("vbyte"))


def string_complexity(strings: DataFrame, ks: tuple[int, ...] = (1, 2, 4, 8, 16)) -> DataFrame:
    """k, distinct k-grams of the whole collection, and their number over k; the largest quotient is the string complexity."""
    parts = None
    for k in ks:
        chars = strings.where(F.length("text") >= k).select(F.split("text", "").alias("c"))
        one = chars.select(F.explode(F.transform(F.sequence(F.lit(1), F.size("c") - k + 1), lambda i: F.array_join(F.slice("c", i, k), ""))).alias("g"))  # noqa: B023
        one = one.distinct().agg(F.lit(k).alias("k"), F.count(F.lit(1)).alias("distinct_grams"))
        parts = one if parts is None else parts.unionByName(one)
    return parts.withColumn("per_k", F.round(F.col("distinct_grams") / F.col("k"), 6))


def empirical_entropy(strings: DataFrame, k: int) -> DataFrame:
    """Bits per symbol given the k characters before it."""
    chars = strings.where(F.length("text") > k).select(F.split("text", "").alias("c"))
    gram = lambda i: F.struct(F.array_join(F.slice("c", i, k), "").alias("ctx"), F.get("c", i + k - 1).alias("ch"))
    seq = chars.select(F.explode(F.transform(F.sequence(F.lit(1), F.size("c") - k), gram)).alias("x"))
    counts = seq.groupBy("x.ctx", "x.ch").agg(F.count(F.lit(1)).alias("n"))
    by = counts.groupBy("ctx").agg(F.sum("n").alias("n_ctx"), F.sum(F.col("n") * F.log2("n")).alias("nl"))
    return by.agg(F.lit(k).alias("k"), F.sum("n_ctx").alias("n"), F.round(F.sum(F.col("n_ctx") * F.log2("n_ctx") - F.col("nl")) / F.sum("n_ctx"), 6).alias("entropy"))


def plain_bits(strings: DataFrame) -> DataFrame:
    """n, sigma, and n * ceil(log2 sigma) bits."""
    chars = strings.select(F.explode(F.split("text", "")).alias("ch"), F.lit(1).alias("one")).where("ch <> ''").groupBy("ch").agg(F.count("one").alias("n"))
    return chars.agg(F.sum("n").alias("n"), F.count(F.lit(1)).alias("sigma"), (F.sum("n") * F.ceil(F.log2(F.greatest(F.count(F.lit(1)), F.lit(2))))).cast("long").alias("bits"))


def irreducibility(g: Grammar) -> DataFrame:
    """what, n: symbols used once, pairs of neighbours that don't overlap and occur twice or more, and unary rules."""
    from stablegrammar.operators.post import adjacent_pairs, occurrences

    once = occurrences(g).where("uses = 1 and level > 0").agg(F.lit("used once").alias("what"), F.count(F.lit(1)).alias("n"))
    items = as_items(g).rules.select(F.struct("level", "sym").alias("sequence"), F.posexplode("rhs").alias("pos", "sym"))
    repeated = adjacent_pairs(items).where("uses > 1").agg(F.lit("repeated pairs").alias("what"), F.count(F.lit(1)).alias("n"))
    unary = g.rules.where("rhs_len = 1").agg(F.lit("unary rules").alias("what"), F.count(F.lit(1)).alias("n"))
    return once.unionByName(repeated).unionByName(unary)


def entropy_coded_bits(g: Grammar) -> DataFrame:
    """Bits of an ideal order-0 code for all symbols of right-hand sides and roots."""
    used = as_items(g).rules.select(F.explode("rhs").alias("x")).select("x.level", "x.sym").unionAll(g.roots.where("root_level >= 0").select("root_level", "root_sym"))
    n = used.groupBy("level", "sym").agg(F.count(F.lit(1)).alias("n"))
    return n.agg(F.sum("n").alias("symbols"), F.round(F.sum("n") * F.log2(F.sum("n")) - F.sum(F.col("n") * F.log2("n")), 0).alias("bits"))


def timed(df: DataFrame) -> float:
    """Seconds of running a plan to the end without keeping its rows."""
    t = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - t
