"""Connected components of a link table by repeated hooking and contraction; nothing but counts reaches the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stablegrammar.llm.common import settled


def components(links: DataFrame) -> DataFrame:
    """links(a, b) -> (node, root): the smallest id reachable, for every node that has a link.

    Each turn hooks every node to its smallest smaller neighbour, flattens these pointers by doubling, and renames the ends of
    the links; links within one root go. Both steps are keyed joins of settled tables, whose skewed sides AQE may split.
    """
    e = settled(links.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a < b").distinct())
    roots = e.select(F.col("a").alias("node")).union(e.select("b")).distinct().select("node", F.col("node").alias("root"))
    while not e.isEmpty():
        up = settled(e.groupBy("b").agg(F.min("a").alias("to")).withColumnRenamed("b", "at"))
        while True:
            nxt = up.select(F.col("at").alias("_at"), F.col("to").alias("_to"))
            up = settled(up.join(nxt, up["to"] == nxt["_at"], "left").select("at", F.coalesce("_to", "to").alias("to"), F.col("_to").isNotNull().alias("moved")))
            if up.where("moved").isEmpty():
                break
            up = up.select("at", "to")
        to = up.select("at", "to")
        rename = lambda df, col: df.join(to, df[col] == to["at"], "left").withColumn(col, F.coalesce("to", col)).select(*df.columns)
        roots = settled(rename(roots, "root"))
        e = settled(rename(rename(e, "a"), "b").where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct())
    return roots
