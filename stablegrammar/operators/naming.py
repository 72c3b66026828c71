"""Names: content digests, dense ids in a reproducible order, and level-local ids."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from stablegrammar.operators.lineage import settled
from stablegrammar.operators.model import Grammar


def distributed_rank(df: DataFrame, group: str, order: list[str], name: str = "rank", buckets: int = 64) -> DataFrame:
    """Rank from 1 within each group without sorting a group in one task: rows are counted per range bucket, then numbered within it."""
    ranged = settled(df.repartitionByRange(buckets, group, *order).withColumn("_part", F.spark_partition_id()))
    sizes = ranged.groupBy(group, "_part").agg(F.count(F.lit(1)).alias("_n"))  # at most groups + buckets rows
    base = sizes.select(F.col(group).alias("_g"), F.col("_part").alias("_q"), (F.sum("_n").over(Window.partitionBy(group).orderBy("_part")) - F.col("_n")).alias("_base"))
    row = F.row_number().over(Window.partitionBy(group, "_part").orderBy(*order))
    return ranged.withColumn("_row", row).join(F.broadcast(base), (F.col(group) == F.col("_g")) & (F.col("_part") == F.col("_q"))).withColumn(name, F.col("_base") + F.col("_row")).drop("_part", "_row", "_base", "_g", "_q")


def to_dense(g: Grammar) -> Grammar:
    """Dense long ids: terminals 1..sigma by code, then level after level by content name. A packed grammar's aren't stored, but made when read."""
    if g.packed is not None:
        from stablegrammar.operators.packed import dense_packed

        return dense_packed(g)
    binary = dict(g.rules.dtypes)["sym"] == "binary"
    text = lambda c: F.hex(c) if binary else c
    alphabet = g.alphabet().select(F.lit(0).alias("level"), F.col("sym"))
    key = F.when(F.col("level") == 0, F.lpad(text(F.col("sym")), 34, "0")).otherwise(text(F.col("sym")))
    ids = distributed_rank(alphabet.unionByName(g.rules.select("level", "sym")).withColumn("_key", key), "level", ["_key"]).drop("_key")
    off = offsets(ids)
    ids = settled(ids.join(F.broadcast(off), "level").select(F.col("level").alias("_l"), F.col("sym").alias("_s"), (F.col("rank") + F.col("off")).alias("id")))
    rhs = g.rules.select("level", "sym", F.posexplode("rhs").alias("_p", "_c")).join(ids.withColumnRenamed("id", "_cid"), (F.col("_l") == F.col("level") - 1) & (F.col("_s") == F.col("_c"))).drop("_l", "_s", "_c")
    rhs = rhs.groupBy("level", "sym").agg(F.transform(F.array_sort(F.collect_list(F.struct("_p", "_cid"))), lambda x: x["_cid"]).alias("rhs"))
    rules = g.rules.drop("rhs").join(rhs, ["level", "sym"]).join(ids, (F.col("_l") == F.col("level")) & (F.col("_s") == F.col("sym"))).select("level", F.col("id").alias("sym"), "rhs", "rhs_len", "exp_len", "fp")
    roots = g.roots.join(ids, (F.col("_l") == F.col("root_level")) & (F.col("_s") == F.col("root_sym")), "left").select("string_id", F.col("id").alias("root_sym"), "root_level", "n_symbols")
    return Grammar(settled(rules), settled(roots), g.family)


def offsets(symbols: DataFrame) -> DataFrame:
    """(level, off): how many symbols lie below a level; one row per level, at most the family's number of levels."""
    counts = symbols.groupBy("level").agg(F.count(F.lit(1)).alias("n"))
    w = Window.orderBy("level").rowsBetween(Window.unboundedPreceding, -1)
    return counts.select("level", F.coalesce(F.sum("n").over(w), F.lit(0)).cast("long").alias("off"))


def dense_offsets(g: Grammar, sigma: int) -> list[int]:
    """Offsets of levels 0, 1, … of a dense grammar over terminals 1..sigma."""
    counts = dict(g.rules.groupBy("level").count().collect())  # one row per level
    out = [0, sigma]
    for level in range(1, max(counts, default=0) + 1):
        out.append(out[-1] + counts.get(level, 0))
    return out


def to_local(g: Grammar, off: list[int]) -> DataFrame:
    """Rules whose ids count within their levels."""
    base = F.array(*(F.lit(x).cast("long") for x in off))
    return g.rules.withColumn("sym", F.col("sym") - F.get(base, F.col("level"))).withColumn("rhs", F.transform("rhs", lambda x: x - F.get(base, F.col("level") - 1)))


def to_global(rules: DataFrame, off: list[int]) -> DataFrame:
    base = F.array(*(F.lit(x).cast("long") for x in off))
    return rules.withColumn("sym", F.col("sym") + F.get(base, F.col("level"))).withColumn("rhs", F.transform("rhs", lambda x: x + F.get(base, F.col("level") - 1)))
