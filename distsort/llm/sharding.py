"""Sharding by best-fit-decreasing bin packing of indivisible groups of equal texts.

The groups' sizes are a histogram (size class, groups), which is all that the packing needs: groups of one
size are interchangeable.  Its rows are bounded whatever the data: sizes below 2**16 are classes of their own,
larger ones are rounded up to 12 leading bits.  The driver packs the histogram, largest class first, each run of
equal groups into the bin with the tightest remaining capacity, found in a balanced search tree.  Spark then
numbers the groups of each class and looks their bins up.

Defined results: a null text counts as the empty text (size 8, crc 0) and forms one group with it; repeated rows
are rows of their own in the same group; an empty table gives an empty result; only doc_id and text are
read, so further columns of any name do no harm; a null doc_id is kept as it is.
"""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import small, written

#: Sub-groups over which rows of one size class or one shard are dealt for numbering.
NUMBERING = 1024
#: A group with over 1/HEAVY of all rows is looked up by broadcast; there are fewer than HEAVY of them.
HEAVY = 4096
EXACT_BITS, LEADING_BITS = 16, 12


class CapacityTree:
    """Bins by (remaining capacity, bin) in a height-balanced search tree; each change and search takes log steps."""

    __slots__ = ("root",)

    def __init__(self) -> None:
        self.root = None  # [key, left, right, height]

    @staticmethod
    def _fix(node: list) -> list:
        def height(x):
            return x[3] if x else 0

        def sized(x):
            x[3] = 1 + max(height(x[1]), height(x[2]))
            return x

        def turned(x, side):  # the child on `side` becomes the top
            top = x[side]
            x[side] = top[3 - side]
            top[3 - side] = sized(x)
            return sized(top)

        tilt = height(node[1]) - height(node[2])
        for side, much in ((1, tilt > 1), (2, tilt < -1)):
            if much:
                child = node[side]
                if height(child[3 - side]) > height(child[side]):
                    node[side] = turned(child, 3 - side)
                return turned(node, side)
        return sized(node)

    def add(self, key: tuple) -> None:
        def put(node):
            if node is None:
                return [key, None, None, 1]
            side = 1 if key < node[0] else 2
            node[side] = put(node[side])
            return self._fix(node)

        self.root = put(self.root)

    def remove(self, key: tuple) -> None:
        def cut(node, key):
            if key != node[0]:
                side = 1 if key < node[0] else 2
                node[side] = cut(node[side], key)
            elif node[1] is None or node[2] is None:
                return node[1] or node[2]
            else:
                least = node[2]
                while least[1]:
                    least = least[1]
                node[0] = least[0]
                node[2] = cut(node[2], least[0])
            return self._fix(node)

        self.root = cut(self.root, key)

    def tightest(self, size: int) -> tuple | None:
        """The entry with the least remaining capacity of at least size."""
        node, best = self.root, None
        while node:
            if node[0][0] >= size:
                node, best = node[1], node[0]
            else:
                node = node[2]
        return best


def best_fit_decreasing(classes: list[tuple[int, int]], capacity: int, most: int | None = None) -> list[tuple[int, int, int]] | None:
    """Pack (size, groups), largest first; returns runs (size, groups, bin).  None if over `most` bins are needed.

    A group of its bin's remaining capacity leaves the bin the tightest one for the next group of the same size, so a
    run of equal groups fills one bin after another, at one search for each bin it touches."""
    tree, runs, bins = CapacityTree(), [], 0
    for size, left in sorted(classes, reverse=True):
        if size > capacity:
            raise ValueError(f"a group of {size} exceeds the capacity {capacity}")
        while left:
            found = tree.tightest(size)
            if found:
                tree.remove(found)
                room, at = found
            else:
                if bins == most:
                    return None
                room, at, bins = capacity, bins, bins + 1
            n = min(left, room // size) if size else left
            runs.append((size, n, at))
            left -= n
            if room - n * size:
                tree.add((room - n * size, at))
            elif not size:
                tree.add((room, at))
    return runs


def pack_evenly(classes: Iterable[tuple[int, int]], shards: int) -> list[tuple[int, int, int]]:
    """Runs (size, groups, shard) for a fixed number of shards: the least capacity for which best fit needs no more.

    A group larger than an even share of what is left takes a shard of its own first, so that one huge group
    leaves the other shards even."""
    todo, runs, free = sorted(((s, n) for s, n in classes if n), reverse=True), [], shards
    total = sum(s * n for s, n in todo)
    while todo and free > 1 and todo[0][0] * free > total:
        (size, n), free = todo[0], free - 1
        runs.append((size, 1, free))
        todo = ([(size, n - 1)] if n > 1 else []) + todo[1:]
        total -= size
    if not todo:
        return runs
    low = max(todo[0][0], -(-total // free))
    high, best = low, None
    while best is None:
        best = best_fit_decreasing(todo, high, free)
        if best is None:
            low, high = high + 1, high + max(1, high // 64)
    while low < high:
        middle = (low + high) // 2
        found = best_fit_decreasing(todo, middle, free)
        if found is None:
            low = middle + 1
        else:
            best, high = found, middle
    return runs + best


def size_class(size: F.Column) -> F.Column:
    """Size, with all but its leading bits rounded up where it has more than EXACT_BITS."""
    step = F.pow(F.lit(2.0), F.greatest(F.lit(0.0), F.floor(F.log2(F.greatest(size, F.lit(1)).cast("double"))) - LEADING_BITS)).cast("long")
    return F.when(size < 2**EXACT_BITS, size).otherwise(F.ceil(size / step) * step).cast("long")


def shard_by_bytes(docs: DataFrame, shards: int | None = 24, capacity: int | None = None) -> DataFrame:
    """Put every document into a shard; equal texts stay together.

    shards: so many shards of near equal bytes; or capacity: as few shards of at most so many bytes as best fit needs.
    Returns doc_id, size, text_crc32, law, shard, slot, grown_shard."""
    spark = docs.sparkSession
    text = F.coalesce(F.col("text"), F.lit(""))
    thin = written(
        docs.select(
            "doc_id",
            (F.octet_length(text) + 8).cast("long").alias("size"),
            F.crc32(text.cast("binary")).alias("text_crc32"),
            F.xxhash64(text).alias("k1"),
            F.xxhash64(F.lit(17), text).alias("k2"),
        ),
        "shard-rows",
    )
    groups = written(
        thin.groupBy("k1", "k2")
        .agg(F.count(F.lit(1)).alias("n"), F.sum("size").alias("bytes"))
        .withColumn("class", size_class(F.col("bytes")))
        .withColumn("deal", F.pmod("k1", F.lit(NUMBERING)).cast("int")),
        "shard-groups",
    )
    sizes = groups.groupBy("class").agg(F.count(F.lit(1)).alias("groups"), F.sum("n").alias("rows")).collect()  # bounded: see size_class
    classes = [(r["class"], r["groups"]) for r in sizes]
    runs = pack_evenly(classes, shards) if capacity is None else best_fit_decreasing(classes, capacity)
    plan, at = [], {}
    for size, n, shard in runs:
        plan.append((size, at.get(size, 0), at.get(size, 0) + n, shard))
        at[size] = at.get(size, 0) + n
    plan = spark.createDataFrame(plan, "class long, first long, after long, shard int")

    # number the groups of a class: the sub-groups' sizes give each sub-group its first number
    subs = groups.groupBy("class", "deal").agg(F.count(F.lit(1)).alias("m"))
    subs = subs.withColumn("base", F.sum("m").over(Window.partitionBy("class").orderBy("deal")) - F.col("m")).drop("m")
    numbered = groups.withColumn("rank", F.row_number().over(Window.partitionBy("class", "deal").orderBy("k1", "k2")) - 1).join(subs, ["class", "deal"])
    rank = F.col("rank") + F.col("base")
    placed = written(
        numbered.withColumn("rank", rank).join(F.broadcast(plan), "class").where((F.col("rank") >= F.col("first")) & (F.col("rank") < F.col("after"))).select("k1", "k2", "n", "shard"),
        "shard-plan",
    )
    rows = sum(r["rows"] for r in sizes)
    heavy = F.col("n") * HEAVY > rows
    hot = placed.where(heavy).select("k1", "k2", F.col("shard").alias("hot_shard"))
    both = thin.join(F.broadcast(hot), ["k1", "k2"], "left")
    dealt = (
        both.where(F.col("hot_shard").isNotNull())
        .withColumnRenamed("hot_shard", "shard")
        .unionByName(both.where(F.col("hot_shard").isNull()).drop("hot_shard").join(placed.where(~heavy).drop("n"), ["k1", "k2"]))
        .withColumn("deal", F.pmod(F.xxhash64("doc_id", "k1"), F.lit(NUMBERING)).cast("int"))
    )
    dealt = written(dealt.drop("k2"), "shard-dealt")
    counts = dealt.groupBy("shard", "deal").agg(F.count(F.lit(1)).alias("m"))
    counts = counts.withColumn("base", F.sum("m").over(Window.partitionBy("shard").orderBy("deal")) - F.col("m")).drop("m")
    order = Window.partitionBy("shard", "deal").orderBy("doc_id", "k1")
    return dealt.withColumn("slot", F.row_number().over(order) - 1).join(small(counts, 0 if shards and shards * NUMBERING < 500_000 else None), ["shard", "deal"]).select(
        "doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("slot") + F.col("base")).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard")
    )
