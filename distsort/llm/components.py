"""Connected components over edge tables, by label contraction in joins; nothing is collected."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import written

#: Edges that a task of a round takes at least; few edges make few tasks.
EDGES_A_TASK = 100_000


def components(edges: DataFrame, most: int | None = None) -> DataFrame:
    """(node, component): the smallest node that each node of edges (a, b) reaches; most: their number at most, if known.

    Rounds of two star steps: each node's larger neighbours are tied to its smallest neighbour, then its smaller
    ones are.  The edge table never grows, paths shorten to stars, and the rounds are logarithmic in practice."""

    def kept(df: DataFrame, most: int | None) -> tuple[DataFrame, tuple]:
        table = written(df, "edges", most)
        mark = tuple(table.agg(F.count(F.lit(1)), F.sum(F.xxhash64("hi", "lo").cast("decimal(38,0)"))).first())
        return table.coalesce(1 + mark[0] // EDGES_A_TASK), mark

    now, mark = kept(edges.select(F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo")).where("hi <> lo"), most)
    before = None
    while mark != before:
        both = now.select(F.col("hi").alias("u"), F.col("lo").alias("v")).unionByName(now.select(F.col("lo").alias("u"), F.col("hi").alias("v")))
        both = both.coalesce(1 + mark[0] // EDGES_A_TASK)
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("hi"), F.col("m").alias("lo")).where("hi <> lo").distinct()
        # smaller neighbours of each node go to its smallest one
        floor = large.groupBy("hi").agg(F.min("lo").alias("m"))
        small = large.join(floor, "hi").select(F.explode(F.array(F.struct(F.col("hi"), F.col("m").alias("lo")), F.struct(F.col("lo").alias("hi"), F.col("m").alias("lo")))).alias("e"))
        before = mark
        now, mark = kept(small.select("e.hi", "e.lo").where("hi <> lo").distinct(), 2 * mark[0])
    ends = now.select(F.col("hi").alias("node"), F.col("lo").alias("component"))
    return ends.unionByName(now.select(F.col("lo").alias("node"), F.col("lo").alias("component")).distinct())
