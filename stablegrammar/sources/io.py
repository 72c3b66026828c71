"""Grammar directories: rules by level, roots, runs and the hash parameters that any later merge needs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stablegrammar.functions.hashing import HashFamily, Level
from stablegrammar.operators.model import Grammar


def write_grammar(g: Grammar, path: str, mode: str = "errorifexists") -> None:
    spark = g.rules.sparkSession
    g.rules.write.mode(mode).option("compression", "zstd").partitionBy("level").parquet(f"{path}/rules")
    g.roots.write.mode(mode).option("compression", "zstd").parquet(f"{path}/roots")
    if g.runs is not None:
        g.runs.write.mode(mode).parquet(f"{path}/runs")
    g.family.rows(spark).withColumns({"seed": F.lit(g.family.seed), "bits": F.lit(g.family.bits)}).coalesce(1).write.mode(mode).parquet(f"{path}/hash_params")


def read_grammar(spark: SparkSession, path: str, with_runs: bool = False) -> Grammar:
    params = spark.read.parquet(f"{path}/hash_params").orderBy("level").collect()  # one row per level
    family = HashFamily(params[0]["seed"], params[0]["bits"], tuple(Level(r["p"], r["m"], r["a"], r["b"], r["c"]) for r in params))
    rules = spark.read.parquet(f"{path}/rules")
    order = ["level", "sym", "rhs", "rhs_len", "exp_len", "fp"]
    return Grammar(rules.select(*order), spark.read.parquet(f"{path}/roots"), family, spark.read.parquet(f"{path}/runs") if with_runs else None)


def append_to_sink(g: Grammar, path: str, batch_id: int) -> None:
    """Rules that the sink lacks, and roots, under the batch's own directories: a replayed batch overwrites what it wrote."""
    spark = g.rules.sparkSession
    new = g.rules
    try:
        known = spark.read.parquet(f"{path}/rules").where(F.col("batch") != batch_id).select("level", "sym")
        new = new.join(known, ["level", "sym"], "left_anti")
    except Exception as e:  # the first batch finds no directory
        if "PATH_NOT_FOUND" not in str(e) and "UNABLE_TO_INFER_SCHEMA" not in str(e):
            raise
    new.write.mode("overwrite").parquet(f"{path}/rules/batch={batch_id}")
    g.roots.write.mode("overwrite").parquet(f"{path}/roots/batch={batch_id}")


def read_sink(spark: SparkSession, path: str, family: HashFamily) -> Grammar:
    return Grammar(spark.read.parquet(f"{path}/rules").drop("batch"), spark.read.parquet(f"{path}/roots").drop("batch"), family)


def export_dense(g: Grammar, path: str, mode: str = "errorifexists") -> int:
    """Dense ids as Parquet (zstd) by level; bytes at rest."""
    from stablegrammar.operators.naming import to_dense

    dense = to_dense(g)
    dense.rules.select("level", "sym", "rhs").write.mode(mode).option("compression", "zstd").partitionBy("level").parquet(f"{path}/rules")
    dense.roots.select("string_id", "root_sym").write.mode(mode).option("compression", "zstd").parquet(f"{path}/roots")
    return bytes_at(g.rules.sparkSession, path)


def bytes_at(spark: SparkSession, path: str) -> int:
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(where).getLength()


def read_texts(spark: SparkSession, path: str, whole_files: bool = False) -> DataFrame:
    """strings(string_id, text) of text files: one per line, or one per file."""
    rows = spark.read.text(path, wholetext=whole_files)
    return rows.select(F.xxhash64(F.input_file_name() if whole_files else F.concat_ws("\x01", F.input_file_name(), F.monotonically_increasing_id())).alias("string_id"), F.col("value").alias("text"))
