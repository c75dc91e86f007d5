"""The block view of one distribution step, as relations: stripes, flushed blocks, boundaries, targets, gaps.

A block here is metadata: its slot, its bucket, its rows' span.  Nothing in it is moved; ranks replace the pointers that
threads would claim.  Windows are over RUN places at most, and the counts of the runs before give the rest: the position that stripes are cut from comes
from the distribution sort."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.classify import SplitterTree
from ..plans.params import SortParams
from .sort import sort_global


#: Places that a window takes at most.
RUN = 1 << 20


def numbered(df: DataFrame, keys: list[str], at: str, out: str, places: int) -> DataFrame:
    """df with out: the number of each row (from 0) among those of equal keys, in the order of the integer column `at`, which is under `places`.

    Runs of `at` are numbered by themselves and the counts of the runs before are added; a run of RUN places is a window's task at most."""
    own = F.row_number().over(Window.partitionBy(*keys, "_run").orderBy(at)) - 1
    cut = df.withColumn("_run", F.floor(F.col(at) / RUN))
    if places <= RUN:
        return cut.withColumn(out, own).drop("_run")
    counts = cut.groupBy(*keys, "_run").agg(F.count(F.lit(1)).alias("_m"))
    base = counts.select(*keys, "_run", (F.sum("_m").over(Window.partitionBy(*keys).orderBy("_run")) - F.col("_m")).alias("_base"))
    return cut.withColumn(out, own).join(base, [*keys, "_run"]).withColumn(out, F.col(out) + F.col("_base")).drop("_run", "_base")


@dataclass(frozen=True)
class Striped:
    """Rows with rnk (place in input order), stripe, bucket and q (place within stripe and bucket)."""

    rows: DataFrame
    n: int
    b: int
    t: int
    k: int

    @property
    def blocks(self) -> int:
        return -(-self.n // self.b)

    def starts(self) -> list[int]:
        """First row of each stripe, and the number of rows."""
        return [min(self.n, self.b * (self.blocks * r // self.t)) for r in range(self.t)] + [self.n]


def ranked(df: DataFrame, rowid: list[str], p: SortParams = SortParams()) -> tuple[DataFrame, int]:
    n = df.count()
    return sort_global(df, rowid, p, rows=n, pos="rnk"), n


def local_classify(df: DataFrame, n: int, tree: SplitterTree, b: int, t: int) -> Striped:
    """df has rnk.  Stripes are equal runs of whole blocks."""
    shape = Striped(df, n, b, t, tree.buckets)
    inner = shape.starts()[1:-1]
    stripe = sum(((F.col("rnk") >= s).cast("int") for s in inner), F.lit(0))
    rows = tree.with_bucket(df.withColumn("stripe", stripe), "bucket")
    return Striped(numbered(rows, ["stripe", "bucket"], "rnk", "q", n), n, b, t, tree.buckets)


def stripe_counts(s: Striped) -> DataFrame:
    return s.rows.groupBy("stripe", "bucket").agg(F.count(F.lit(1)).alias("n"))


def _start_of(s: Striped, of: Column) -> Column:
    return F.get(F.array(*map(F.lit, s.starts())), of)


def flushed_blocks(s: Striped, key: str, eager: bool = False) -> DataFrame:
    """stripe, slot, bucket, m, first_rowid, n_rows, min_key, max_key, at (the row whose arrival or completion flushed it).

    Lazily, a buffer is flushed when a row for it arrives and it is full; eagerly, as soon as it is full."""
    per = s.rows.withColumn("m", F.floor(F.col("q") / s.b).cast("long"))
    made = per.groupBy("stripe", "bucket", "m").agg(F.min("rnk").alias("first_rowid"), F.max("rnk").alias("last"), F.count(F.lit(1)).alias("n_rows"), F.min(key).alias("min_key"), F.max(key).alias("max_key"))
    after = F.lead("first_rowid").over(Window.partitionBy("stripe", "bucket").orderBy("m"))
    made = made.where(F.col("n_rows") == s.b).withColumn("at", F.col("last")) if eager else made.withColumn("at", after).where("at is not null")
    first = (_start_of(s, F.col("stripe")) / s.b).cast("long")
    return numbered(made, ["stripe"], "at", "local", s.n).withColumn("slot", (first + F.col("local")).cast("long"))


def flush_room(s: Striped, key: str) -> DataFrame:
    """stripe, min_room: over all flushes, rows scanned before the one that flushes less rows written before it; b or more."""
    room = F.col("at") - _start_of(s, F.col("stripe")) - F.col("local") * s.b
    return flushed_blocks(s, key).groupBy("stripe").agg(F.min(room).cast("long").alias("min_room"))


def prefix_offsets(s: Striped) -> DataFrame:
    """bucket, size, start; a table of k rows, so its window over all of them is small."""
    sizes = s.rows.groupBy("bucket").agg(F.count(F.lit(1)).alias("size"))
    every = s.rows.sparkSession.range(s.k).select(F.col("id").cast("int").alias("bucket"))
    sizes = every.join(F.broadcast(sizes), "bucket", "left").fillna(0, ["size"])
    return sizes.withColumn("start", F.sum("size").over(Window.orderBy("bucket")) - F.col("size"))


def delimiters(s: Striped) -> DataFrame:
    """bucket, start, size, delim, next_delim, full_blocks, overflow."""
    full = stripe_counts(s).groupBy("bucket").agg(F.sum(F.floor((F.col("n") - 1) / s.b)).cast("long").alias("full_blocks"))
    at = prefix_offsets(s).withColumn("delim", F.ceil(F.col("start") / s.b).cast("long"))
    at = at.withColumn("next_delim", F.ceil((F.col("start") + F.col("size")) / s.b).cast("long")).join(F.broadcast(full), "bucket", "left").fillna(0, ["full_blocks"])
    return at.withColumn("overflow", (F.col("delim") + F.col("full_blocks")) * s.b > s.n)


def block_targets(s: Striped, key: str) -> DataFrame:
    """stripe, slot, bucket, target: each bucket's blocks in the order of their slots, from its delimiter on."""
    blocks = flushed_blocks(s, key).join(F.broadcast(delimiters(s).select("bucket", "delim")), "bucket")
    return numbered(blocks, ["bucket"], "slot", "_r", s.blocks).select("stripe", "slot", "bucket", (F.col("delim") + F.col("_r")).alias("target"))


def empty_compaction(s: Striped, key: str) -> DataFrame:
    """bucket, occupied, moves: blocks in a bucket's slots, and those to be moved for its empty slots to come last."""
    slots = flushed_blocks(s, key).select("slot")
    area = delimiters(s).select("bucket", "delim", "next_delim")
    held = slots.join(F.broadcast(area), (F.col("slot") >= F.col("delim")) & (F.col("slot") < F.col("next_delim")))
    occupied = held.groupBy("bucket").agg(F.count(F.lit(1)).alias("occupied"))  # one row for each bucket
    counted = held.join(F.broadcast(occupied), "bucket").groupBy("bucket").agg(F.first("occupied").alias("occupied"), F.sum((F.col("slot") >= F.col("delim") + F.col("occupied")).cast("long")).alias("moves"))
    return area.select("bucket").join(F.broadcast(counted), "bucket", "left").fillna(0, ["occupied", "moves"])


def blocks_in_place(s: Striped, key: str) -> DataFrame:
    """bucket, blocks, in_place, to_move: blocks that stand where their bucket's full blocks will."""
    area = delimiters(s).select("bucket", "delim", "full_blocks")
    inside = (F.col("slot") >= F.col("delim")) & (F.col("slot") < F.col("delim") + F.col("full_blocks"))
    got = flushed_blocks(s, key).join(F.broadcast(area), "bucket").groupBy("bucket").agg(F.count(F.lit(1)).alias("blocks"), F.sum(inside.cast("long")).alias("in_place"))
    return got.withColumn("to_move", F.col("blocks") - F.col("in_place"))


def heads_tails(s: Striped) -> DataFrame:
    """bucket, head, overhang, leftovers, gap: what cleanup has to write into each bucket."""
    d = delimiters(s)
    end = F.col("start") + F.col("size")
    head = F.least(F.col("delim") * s.b - F.col("start"), F.col("size"))
    over = F.when(F.col("full_blocks") == 0, 0).otherwise(F.greatest(F.lit(0), (F.col("delim") + F.col("full_blocks")) * s.b - end))
    d = d.select("bucket", head.cast("long").alias("head"), over.cast("long").alias("overhang"), (F.col("size") - F.col("full_blocks") * s.b).alias("leftovers"))
    return d.withColumn("gap", F.col("leftovers") + F.col("overhang"))


def cleaned_up(s: Striped, key: str) -> DataFrame:
    """rnk, bucket, place: where every row comes to stand.

    A row of a full block has its place from the block's target.  Rows that this puts behind their bucket's end (into the head of the next one, or into
    the overflow block) and rows that are left in buffers are numbered in each bucket, and fill its empty entries: the head first, then what is behind its blocks."""
    d = delimiters(s).select("bucket", "start", "size", "delim", "full_blocks")
    placed = flushed_blocks(s, key).select("stripe", "slot", F.col("bucket"), "m").join(block_targets(s, key), ["stripe", "slot", "bucket"]).select("stripe", "bucket", "m", "target")
    rows = s.rows.select("rnk", "stripe", "bucket", "q", F.floor(F.col("q") / s.b).cast("long").alias("m")).join(placed, ["stripe", "bucket", "m"], "left").join(F.broadcast(d), "bucket")
    end = F.col("start") + F.col("size")
    own = F.col("target") * s.b + F.pmod(F.col("q"), F.lit(s.b))
    rows = rows.withColumn("place", F.when(own < end, own))
    stays = rows.where("place is not null").select("rnk", "bucket", F.col("place").cast("long").alias("place"))
    # at most a block for each buffer and one more: few rows a bucket
    number = F.row_number().over(Window.partitionBy("bucket").orderBy("rnk")) - 1
    head = F.least(F.col("delim") * s.b, end) - F.col("start")
    behind = F.least((F.col("delim") + F.col("full_blocks")) * s.b, end)
    gap = F.when(F.col("r") < head, F.col("start") + F.col("r")).otherwise(behind + F.col("r") - head)
    moved = rows.where("place is null").withColumn("r", number).select("rnk", "bucket", gap.cast("long").alias("place"))
    return stays.unionByName(moved)


def saved_heads(s: Striped, workers: int) -> DataFrame:
    """worker, next_bucket, head: rows of the head that a worker reads before the next worker's first bucket is cleaned up."""
    heads = heads_tails(s).select("bucket", "head", F.floor(F.col("bucket") * workers / s.k).cast("int").alias("worker")).where("worker > 0")
    first = heads.groupBy("worker").agg(F.min(F.struct("bucket", "head")).alias("x"))
    return first.select((F.col("worker") - 1).alias("worker"), F.col("x.bucket").alias("next_bucket"), F.col("x.head").alias("head"))


def relabel_manifest(s: Striped, key: str) -> DataFrame:
    """seq, stripe, slot, bucket: the order in which blocks are read as if they had been moved; no row is."""
    blocks = flushed_blocks(s, key).select("stripe", "slot", "bucket")
    sizes = blocks.groupBy("bucket").agg(F.count(F.lit(1)).alias("m"))
    base = sizes.select("bucket", (F.sum("m").over(Window.orderBy("bucket")) - F.col("m")).alias("base"))
    return numbered(blocks, ["bucket"], "slot", "r", s.blocks).join(F.broadcast(base), "bucket").select((F.col("base") + F.col("r")).cast("long").alias("seq"), "stripe", "slot", "bucket")


def affinity(s: Striped) -> DataFrame:
    """bucket, stripe, n: the stripe that holds most of each bucket (the smallest of equals)."""
    return stripe_counts(s).groupBy("bucket").agg(F.max_by(F.struct("stripe", "n"), F.struct("n", -F.col("stripe"))).alias("x")).select("bucket", "x.stripe", "x.n")
