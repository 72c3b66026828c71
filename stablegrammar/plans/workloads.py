"""The experiment inputs on the given tables: collections (string_id, text) or (string_id, syms)."""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def _t(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _sequence(df: DataFrame, key: str, order: list[str], value: Column) -> DataFrame:
    """One array of integers per key, in order."""
    rows = df.select(F.col(key).cast("long").alias("string_id"), F.struct(*order, value.cast("int").alias("_v")).alias("_x"))
    return rows.groupBy("string_id").agg(F.transform(F.array_sort(F.collect_list("_x")), lambda x: x["_v"]).alias("syms"))


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _t(spark, sf_dir, "documents").select(F.col("doc_id").alias("string_id"), "text")


def benchmark(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _t(spark, sf_dir, "benchmark").select(F.col("item_id").alias("string_id"), "text")


def _codes(text: Column, modulus: int) -> Column:
    return F.transform(F.split(text, ""), lambda c: (F.ascii(c) % modulus).cast("int"))


def w1(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A tiny alphabet: code points modulo 5."""
    return documents(spark, sf_dir).where("text <> ''").select("string_id", _codes(F.col("text"), 5).alias("syms"))


def w2(spark: SparkSession, sf_dir: str, text: bool = False) -> DataFrame:
    """Few long strings with filler runs: documents of a source, modulo 15, each followed by 1 + doc_id % 200 fillers.

    With `text`, as the letters that reports.as_text() makes of the codes: a byte for each, where arrays of codes take many times that.
    """
    if text:
        return _w2_texts(spark, sf_dir)
    docs = _t(spark, sf_dir, "documents")
    part = F.concat(_codes(F.col("text"), 15), F.array_repeat(F.lit(15), (1 + F.col("doc_id") % 200).cast("int")))
    rows = docs.where("text <> ''").select(F.regexp_extract("source", r"(\d+)", 1).cast("long").alias("string_id"), F.struct("doc_id", part.alias("p")).alias("x"))
    return rows.groupBy("string_id").agg(F.flatten(F.transform(F.array_sort(F.collect_list("x")), lambda x: x["p"])).alias("syms"))


class _Codes(dict):
    """Code points to their remainder modulo 15 in decimal and a comma, for str.translate."""

    def __missing__(self, cp: int) -> str:
        self[cp] = out = f"{cp % 15},"
        return out


class _Letters(dict):
    """Code points to the letter of their remainder modulo 15, for str.translate."""

    def __missing__(self, cp: int) -> str:
        self[cp] = out = chr(65 + cp % 15)
        return out


def _w2_texts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents come to the text of their source in order, one after another; a source with a null doc_id has a null text, as in w2()."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        letters, last, parts, key = _Letters(), None, None, None

        def done() -> pa.RecordBatch:
            text = None if None in parts else "".join("".join(sorted(x)) for x in parts)
            return pa.RecordBatch.from_pydict({"string_id": [last], "text": [text]}, schema=schema)

        for x in batches:
            for source, doc, text in zip(x.column(0).to_pylist(), x.column(1).to_pylist(), x.column(2), strict=True):
                if parts is None or source != last:
                    if parts is not None:
                        yield done()
                    last, parts, key = source, [], None
                if doc is None:
                    parts.append(None)
                    continue
                part = text.as_py().translate(letters) + "P" * (1 + int(math.fmod(doc, 200)))
                if parts and doc == key:  # documents of one id are in order of their codes
                    parts[-1].append(part)
                else:
                    parts.append([part])
                key = doc
        if parts is not None:
            yield done()

    schema = pa.schema([("string_id", pa.int64()), ("text", pa.string())])
    docs = _t(spark, sf_dir, "documents").where("text <> ''")
    rows = docs.select(F.regexp_extract("source", r"(\d+)", 1).cast("long").alias("string_id"), "doc_id", "text")
    return rows.repartition("string_id").sortWithinPartitions("string_id", "doc_id").mapInArrow(run, "string_id long, text string")


def w2_digests(spark: SparkSession, sf_dir: str) -> DataFrame:
    """string_id, n, digest: length and MD5 of the comma-joined symbols of each string of w2, none of which is held whole.

    Documents come to the digest of their source in order, one after another: a task holds a batch of them, however long the string.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codes, last, n, digest = _Codes(), None, 0, None
        done = lambda: pa.RecordBatch.from_pydict({"string_id": [last], "n": [n], "digest": [digest.hexdigest()]}, schema=schema)
        for x in batches:
            for key, fillers, text in zip(x.column(0).to_pylist(), x.column(1).to_pylist(), x.column(2), strict=True):
                if digest is None or key != last:
                    if digest is not None:
                        yield done()
                    last, n, digest = key, 0, hashlib.md5(usedforsecurity=False)
                text = text.as_py()
                digest.update((("," if n else "") + text.translate(codes) + "15," * fillers)[:-1].encode())
                n += len(text) + fillers
        if digest is not None:
            yield done()

    schema = pa.schema([("string_id", pa.int64()), ("n", pa.int64()), ("digest", pa.string())])
    docs = _t(spark, sf_dir, "documents").where("text <> '' and doc_id is not null")
    rows = docs.select(F.regexp_extract("source", r"(\d+)", 1).cast("long").alias("string_id"), (1 + F.col("doc_id") % 200).cast("int").alias("fillers"), "text", "doc_id")
    rows = rows.repartition("string_id").sortWithinPartitions("string_id", "doc_id", "text").select("string_id", "fillers", "text")
    return rows.mapInArrow(run, "string_id long, n long, digest string")


def w3(spark: SparkSession, sf_dir: str, versions: int = 50) -> DataFrame:
    """Near-identical strings: versions of the benchmark passages with one character changed."""
    v = _t(spark, sf_dir, "benchmark").select("item_id", "text", F.explode(F.sequence(F.lit(0), F.lit(versions - 1))).alias("v"))
    at = 1 + (F.col("v") * 37) % F.length("text")
    text = F.when(F.col("v") == 0, F.col("text")).otherwise(F.concat(F.substr("text", F.lit(1), (at - 1).cast("int")), F.lit("#"), F.substr("text", (at + 1).cast("int"), F.length("text"))))
    return v.select((F.col("item_id") * versions + F.col("v")).cast("long").alias("string_id"), text.alias("text"))


def w4(spark: SparkSession, sf_dir: str, versions: int = 10) -> DataFrame:
    """Versions of web pages with one edit each."""
    v = _t(spark, sf_dir, "pages").select("page_id", "html", F.explode(F.sequence(F.lit(0), F.lit(versions - 1))).alias("v"))
    return v.select((F.col("page_id") * versions + F.col("v")).cast("long").alias("string_id"), F.regexp_replace("html", F.concat(F.lit("<p>"), F.lit("")), F.concat(F.lit("<p>"), F.repeat(F.lit("v"), F.col("v")))).alias("text"))


def w5(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Dialogues: turns joined by newlines."""
    return _t(spark, sf_dir, "conversations").groupBy(F.col("conv_id").alias("string_id")).agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", "text"))), lambda x: x["text"]), "\n").alias("text"))


def w6(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Event types of each user by time, coded by their alphabetical rank."""
    events = _t(spark, sf_dir, "events")
    types = sorted(r[0] for r in events.select("event_type").distinct().collect())  # five
    code = F.array_position(F.array(*map(F.lit, types)), F.col("event_type"))
    return _sequence(events, "user_id", ["ts", "event_id"], code)


def w7(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hardly repetitive, large alphabet: parts of each supplier by ship date."""
    return _sequence(_t(spark, sf_dir, "lineitem"), "l_suppkey", ["l_shipdate", "l_orderkey", "l_linenumber"], F.col("l_partkey"))


def w8(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order priorities of each customer by date."""
    orders = _t(spark, sf_dir, "orders").select("o_custkey", F.struct("o_orderdate", "o_orderkey", F.substr("o_orderpriority", F.lit(1), F.lit(1)).alias("p")).alias("x"))
    return orders.groupBy(F.col("o_custkey").alias("string_id")).agg(F.array_join(F.transform(F.array_sort(F.collect_list("x")), lambda x: x["p"]), "").alias("text"))


def w9(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Extreme repetition of short strings: part names, and names of nations and regions."""
    part = _t(spark, sf_dir, "part").select(F.col("p_partkey").cast("long").alias("string_id"), F.col("p_name").alias("text"))
    nation = _t(spark, sf_dir, "nation").select((F.col("n_nationkey") - 1000).cast("long"), "n_name")
    return part.union(nation).union(_t(spark, sf_dir, "region").select((F.col("r_regionkey") - 2000).cast("long"), "r_name"))


def w10(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vectors in 16 levels."""
    level = lambda x: F.greatest(F.lit(0), F.least(F.lit(15), F.floor((x.cast("double") + 1) * 8))).cast("int")
    return _t(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("long").alias("string_id"), F.transform("embedding", level).alias("syms"))


ALL = {"w1": w1, "w2": w2, "w3": w3, "w4": w4, "w5": w5, "w6": w6, "w7": w7, "w8": w8, "w9": w9, "w10": w10}
