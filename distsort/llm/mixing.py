"""Mixing sources to target weights by a multivariate-hypergeometric splitting tree.

Every source has a target of words.  Its documents stand in an order fixed by a keyed digest of their id and are cut into
blocks of near equal numbers of words.  An epoch is a permutation of the source's blocks, fixed by a digest as well; epoch after
epoch, blocks are drawn until the target is reached, so that blocks of the last epoch are a random part of the source.  The drawn blocks are the
source's exact quota.  A binary tree over the output shards splits the quotas of all sources: at a node, the blocks that go left are
a draw without replacement from all blocks that stand there, so that each source's part is multivariate hypergeometric and every shard
gets the same number of blocks (one more or less).  Each source's permuted blocks then fill its quotas in the shards one after another,
disjointly, and within a shard documents are shuffled by a digest of their own; place is where they come to stand.

A node's draw is made by ranking its blocks by a digest keyed with the node.  The tree works on blocks, which are about
SHARDS * BLOCKS_A_SHARD and one or two more for each source whatever the number of documents; so it runs on the driver.

Defined results: a null text or one without words has size 0 and is never taken; a null source is a source of its
own, after all others; a null doc_id is digested as the empty id; rows of one doc_id are ordered by size and text, so that reruns agree
whatever the layout; rows that are equal in all of it count as documents of their own; an
empty table gives an empty result; only doc_id, text and source are read.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import small, unused, words, written

SEED = 20260
#: Weights of the sources by code point, repeating; words of the mix as a share of all words; most epochs of a source.
WEIGHTS, SHARE, EPOCHS = (5, 2, 1), 1.5, 2.0
SHARDS, BLOCKS_A_SHARD = 24, 256


def source_targets(thin: DataFrame, weights=WEIGHTS, share: float = SHARE, epochs: float = EPOCHS) -> DataFrame:
    """source, source_size, rank, target; one row for each source.

    Sharing again what is above the caps ends where every uncapped source has the same target per weight.  So the sources are sorted by cap
    over weight: the level at which the k first are capped decides how many are."""
    sums = thin.groupBy("source").agg(F.sum("size").alias("source_size"))
    ordered = Window.orderBy(F.col("source").asc_nulls_last())
    cap, w = F.col("source_size") * F.lit(epochs), F.col("w")
    named = sums.withColumn("rank", F.row_number().over(ordered) - 1).withColumn("w", F.element_at(F.array(*map(F.lit, weights)), (F.col("rank") % len(weights) + 1).cast("int")).cast("double"))
    by_ratio = Window.orderBy(cap / w, "rank")
    everything = Window.partitionBy()
    leveled = (
        named.withColumn("total", F.sum("source_size").over(everything) * F.lit(share))
        .withColumn("capped", F.coalesce(F.sum(cap).over(by_ratio.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)))
        .withColumn("open", F.sum("w").over(by_ratio.rowsBetween(Window.currentRow, Window.unboundedFollowing)))
        .withColumn("level", (F.col("total") - F.col("capped")) / F.col("open"))
        .withColumn("level", F.max(F.when(F.col("level") <= cap / w, F.col("level"))).over(everything))
    )
    return leveled.select("source", "source_size", "rank", F.round(F.when(F.col("level").isNull(), cap).otherwise(F.least(cap, F.col("level") * w)), 6).alias("target"))


def _digest(*parts) -> str:
    return hashlib.md5(":".join(map(str, parts)).encode()).hexdigest()


def splitting_tree(blocks, shards: int, seed=SEED) -> np.ndarray:
    """Quotas [source][shard]: rows sum to blocks; the shards' totals differ by one at most.

    The draw at a node ranks its blocks (source, number) by digest and sends the first ones left."""
    quotas = np.zeros((len(blocks), shards), dtype=np.int64)
    nodes = [(0, shards, [(s, i) for s, n in enumerate(blocks) for i in range(n)])]
    while nodes:
        low, high, here = nodes.pop()
        if high - low == 1:
            for s, _ in here:
                quotas[s, low] += 1
            continue
        middle, n = (low + high) // 2, high - low
        left = len(here) // n * (middle - low) + min(len(here) % n, middle - low)
        ranked = sorted(here, key=lambda x: _digest(seed, low, high, *x))  # noqa: B023
        nodes += [(low, middle, ranked[:left]), (middle, high, ranked[left:])]
    return quotas


def permuted(docs: DataFrame, seed: int = SEED) -> DataFrame:
    """doc_id, source, size, key and t: the digests of the id, which orders the documents of a source, and of the text."""
    key = F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))))
    return docs.select("doc_id", "source", F.size(words("text")).cast("long").alias("size"), key.alias("key"), text_digest().alias("t"))


def text_digest() -> Column:
    return F.md5(F.coalesce(F.col("text"), F.lit("")))


def _running(rows: DataFrame, keys: list[str], levels: list[str], amount: str, out: str) -> DataFrame:
    """rows (keys, *levels, amount), one for each group, with the sum of all groups of the keys before each.

    Groups are nested: a window sees the groups of one group of the level above, never all of a key's rows."""
    base = None
    for i, level in enumerate(levels):
        above = [*keys, *levels[:i]]
        own = rows.groupBy(*above, level).agg(F.sum(amount).alias("m"))
        own = own.withColumn("base", F.sum("m").over(Window.partitionBy(*above).orderBy(level)) - F.col("m")).drop("m")
        if base is not None:
            up = base.select(*[F.col(c).alias(f"{c}_") for c in above], F.col("base").alias("base_"))
            on = [F.col(c).eqNullSafe(F.col(f"{c}_")) for c in above]
            own = own.join(small(written(up, "mix-sums")), on).select(*above, level, (F.col("base") + F.col("base_")).alias("base"))
        base = own
    return base.withColumnRenamed("base", out)


def ordered_documents(docs: DataFrame, weights, share: float, epochs: float, shards: int, seed: int) -> DataFrame:
    """doc_id, source, size, key, t, row, rank, source_size, target, before (words in front of a document in its source's order), block."""
    # prefixes of the key cut a source into nested parts; their sums give each part its first word
    thin = written(permuted(docs, seed).withColumn("p1", F.substring("key", 1, 2)).withColumn("p2", F.substring("key", 3, 2)), "mix-rows")
    targets = written(source_targets(thin, weights, share, epochs), "mix-targets")
    sums = written(thin.groupBy("source", "p1", "p2").agg(F.sum("size").alias("size")), "mix-parts")
    parts = written(_running(sums, ["source"], ["p1", "p2"], "size", "base"), "mix-starts")
    each = F.greatest(F.lit(1), F.ceil(F.sum("source_size").over(Window.partitionBy()) * F.lit(share) / F.lit(shards * BLOCKS_A_SHARD))).cast("long")
    inside = Window.partitionBy("source", "p1", "p2").orderBy("key", "doc_id", "size", "t").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    at = thin.withColumn("upto", F.sum("size").over(inside))
    p = parts.select(F.col("source").alias("s2"), F.col("p1").alias("q1"), F.col("p2").alias("q2"), "base")
    at = at.join(small(p), F.col("source").eqNullSafe(F.col("s2")) & (F.col("p1") == F.col("q1")) & (F.col("p2") == F.col("q2")))
    t = targets.select(F.col("source").alias("s3"), "source_size", "rank", "target", each.alias("each"))
    at = at.join(small(t), F.col("source").eqNullSafe(F.col("s3"))).withColumn("before", F.col("upto") + F.col("base") - F.col("size"))
    at = at.withColumn("block", F.expr("before div each")).withColumn("row", F.monotonically_increasing_id())
    return written(at.select("doc_id", "source", "size", "key", "t", "row", "rank", "source_size", "target", "before", "block"), "mix-order")


def drawn_blocks(at: DataFrame, epochs: float, shards: int, seed: int) -> DataFrame:
    """rank, block, copy, first, start, seq, shard: the blocks that the targets draw.

    first: words in front of the block in its source; start: words of the mix in front of it; seq: its number among the source's drawn blocks."""
    spark = at.sparkSession
    blocks = at.where("size > 0").groupBy("rank", "block").agg(F.min("before").alias("first"), F.sum("size").alias("m"), F.first("target").alias("target"))
    copies = F.explode(F.sequence(F.lit(0), F.lit(max(0, -int(-epochs // 1) - 1)))).alias("copy")
    mixed_up = F.md5(F.concat_ws(":", F.lit(seed), "copy", "rank", "block"))
    order = Window.partitionBy("rank").orderBy("copy", "mixed_up", "block")
    several = blocks.select("*", copies).withColumn("mixed_up", mixed_up)
    placed = several.withColumn("seq", F.row_number().over(order) - 1).withColumn("start", F.sum("m").over(order) - F.col("m"))
    drawn = written(placed.where("start < target").select("rank", "block", "copy", "first", "start", "seq"), "mix-blocks")
    quota = drawn.groupBy("rank").agg(F.count(F.lit(1)).alias("n")).orderBy("rank").collect()  # one row for each source
    runs = []
    for r, own in zip(quota, splitting_tree([r["n"] for r in quota], shards, seed)):
        upto = 0
        for shard, n in enumerate(own.tolist()):
            if n:
                runs.append((r["rank"], upto, upto + n, shard))
                upto += n
    runs = spark.createDataFrame(runs, "r2 int, low int, high int, shard int")
    inside = (F.col("rank") == F.col("r2")) & (F.col("seq") >= F.col("low")) & (F.col("seq") < F.col("high"))
    return written(drawn.join(F.broadcast(runs), inside).drop("r2", "low", "high"), "mix-quotas")


def draws(docs: DataFrame, weights=WEIGHTS, share: float = SHARE, epochs: float = EPOCHS, shards: int = SHARDS, seed: int = SEED, whole: bool = False) -> tuple[DataFrame, DataFrame]:
    """The mix: (thin, draws).

    thin: doc_id, source, size, key, t, source_size, target, row.  draws: row, doc_id, source, t, copy, words, shard, block, place; a row for
    each time that a document is taken; block is the number of the drawn block in its source, place that of the document in its shard.
    The document that reaches its source's target is cut there; with whole, it is taken if at least half of it is wanted."""
    at = ordered_documents(docs, weights, share, epochs, shards, seed)
    blocks = drawn_blocks(at, epochs, shards, seed)
    wanted = F.col("target") - F.col("start") - F.col("before") + F.col("first")
    take = F.when(wanted * 2 >= F.col("size"), F.col("size")).otherwise(0) if whole else F.greatest(F.lit(0), F.least(F.col("size").cast("double"), F.floor(wanted)))
    out = at.where("size > 0").join(small(blocks), ["rank", "block"]).withColumn("words", take.cast("long")).where("words > 0")
    mixed_up = F.md5(F.concat_ws(":", "shard", "copy", "key"))
    out = out.select("row", "doc_id", "source", "t", "size", "copy", "words", "shard", F.col("seq").cast("int").alias("block"), mixed_up.alias("mixed_up"))
    # a prefix of the digest cuts a shard into parts that are numbered by themselves
    out = out.withColumn("p1", F.substring("mixed_up", 1, 3))
    counts = written(out.groupBy("shard", "p1").agg(F.count(F.lit(1)).alias("m")), "mix-counts")
    base = _running(counts, ["shard"], ["p1"], "m", "base")
    order = Window.partitionBy("shard", "p1").orderBy("mixed_up", "copy", "doc_id", "size", "t", "source", "block")
    placed = out.withColumn("place", F.row_number().over(order) - 1).join(small(written(base, "mix-places")), ["shard", "p1"])
    placed = placed.select("row", "doc_id", "source", "t", "copy", "words", "shard", "block", (F.col("place") + F.col("base")).cast("long").alias("place"))
    return at, placed


def mixed(docs: DataFrame, epochs: float = EPOCHS, **options) -> DataFrame:
    """doc_id, size, source_size, target, taken, for every document; and shard_i, block_i, place_i of its i-th copy, -1 where it isn't taken."""
    thin, taken = draws(docs, epochs=epochs, **options)
    each = [F.max(F.when(F.col("copy") == i, F.col(c))).alias(f"{c}_{i}") for i in range(max(1, -int(-epochs // 1))) for c in ("shard", "block", "place")]
    sums = taken.groupBy("row").agg(F.sum("words").alias("taken"), *each)
    named = [c for c in sums.columns if c not in ("row", "taken")]
    return thin.join(sums, "row", "left").select("doc_id", "size", "source_size", "target", F.coalesce("taken", F.lit(0)).cast("long").alias("taken"), *[F.coalesce(c, F.lit(-1)).alias(c) for c in named])


def mix_documents(docs: DataFrame, shards: int = SHARDS, **options) -> DataFrame:
    """The rows of docs, each as often as the mix takes it (whole documents), with docs' columns; shard after shard, in each shard's shuffled order."""
    thin, taken = draws(docs, whole=True, shards=shards, **options)
    key = ["doc_id", "source", "t"]
    names = unused(docs, *(f"drawn_{k}" for k in key), "drawn_i", "own_i", "draws", "draw", "digest")
    other, (i, own, drawn_, draw, digest) = names[:3], names[3:]
    # rows that are equal in doc_id, source and text are told apart by a number
    copies = taken.groupBy("row", *key).agg(F.collect_list(F.struct("shard", "place")).alias(drawn_))  # at most one for each epoch
    copies = copies.withColumn(i, F.row_number().over(Window.partitionBy(*key).orderBy("row"))).select(*[F.col(k).alias(o) for k, o in zip(key, other)], i, drawn_)
    twice = thin.where("size > 0").groupBy(*key).agg(F.count(F.lit(1)).alias("m")).where("m > 1")
    twice = written(twice.select(*[F.col(k).alias(o) for k, o in zip(key, other)]), "mix-twice")
    here = [F.col("doc_id").eqNullSafe(F.col(other[0])), F.col("source").eqNullSafe(F.col(other[1])), F.col(digest) == F.col(other[2])]
    named = docs.withColumn(digest, text_digest())
    copies = written(copies, "mix-copies")
    once = named.join(small(twice), here, "left_anti").join(copies.where(F.col(i) == 1), here).select(*docs.columns, drawn_)
    again = named.join(small(twice), here, "left_semi").withColumn(own, F.row_number().over(Window.partitionBy("doc_id", "source", digest).orderBy(digest)))
    again = again.join(copies, [*here, F.col(own) == F.col(i)]).select(*docs.columns, drawn_)
    rows = once.unionByName(again).withColumn(draw, F.explode(drawn_))
    return rows.repartition(shards, F.col(draw)["shard"]).sortWithinPartitions(F.col(draw)["shard"], F.col(draw)["place"]).select(*docs.columns)


_WORDS = "regexp_split_to_array(coalesce(text, ''), '[\\x20\\x09-\\x0D]+')"
ORACLE = f"""
with recursive thin as (select doc_id, source, len(list_filter({_WORDS}, lambda w: w <> ''))::bigint as size, md5('{SEED}:' || coalesce(doc_id::varchar, '')) as key, md5(coalesce(text, '')) as t, row_number() over () as rid from documents),
sums as (select source, sum(size)::bigint as source_size from thin group by source),
named as (select *, (row_number() over (order by source nulls last) - 1)::int as rnk from sums),
w as (select *, ([{", ".join(f"{x}.0" for x in WEIGHTS)}])[rnk % {len(WEIGHTS)} + 1]::double as w, source_size * {EPOCHS}::double as cap from named),
l as (select *, (sum(source_size) over ())::double * {SHARE}::double as total,
   coalesce(sum(cap) over (order by cap / w, rnk rows between unbounded preceding and 1 preceding), 0.0) as capped,
   sum(w) over (order by cap / w, rnk rows between current row and unbounded following) as opened from w),
v as (select *, max(case when (total - capped) / opened <= cap / w then (total - capped) / opened end) over () as level from l),
t as (select source, rnk, source_size, round(case when level is null then cap else least(cap, level * w) end, 6)::double as target from v),
e as (select greatest(1, ceil(sum(source_size)::double * {SHARE}::double / {SHARDS * BLOCKS_A_SHARD}))::bigint as each_ from t),
o as (select thin.*, rnk, source_size, target, coalesce(sum(size) over (partition by thin.source order by key, doc_id, size, t, rid rows between unbounded preceding and 1 preceding), 0)::bigint as before from thin join t on thin.source is not distinct from t.source),
p as (select o.*, before // each_ as block from o, e),
b as (select rnk, block, min(before) as first_, sum(size)::bigint as m, any_value(target) as target from p where size > 0 group by rnk, block),
q as (select b.*, copy, (row_number() over s - 1)::int as seq, (sum(m) over s - m)::bigint as start_ from b, (values (0), (1)) as c(copy) window s as (partition by rnk order by copy, md5('{SEED}:' || copy || ':' || rnk || ':' || block), block rows unbounded preceding)),
d as (select * from q where start_ < target),
i as (select rnk, seq, row_number() over (partition by rnk order by seq) - 1 as i, dense_rank() over (order by rnk) - 1 as s from d),
tree(low, high, s, i) as (
  select 0, {SHARDS}, s, i from i
  union all
  select case when n <= go then low else mid end, case when n <= go then mid else high end, s, i
  from (select low, high, (low + high) // 2 as mid, s, i, row_number() over (partition by low order by md5('{SEED}:' || low || ':' || high || ':' || s || ':' || i)) as n,
          (count(*) over (partition by low)) // (high - low) * ((low + high) // 2 - low) + least((count(*) over (partition by low)) % (high - low), (low + high) // 2 - low) as go
        from tree where high - low > 1)),
slots as (select s, low as shard, row_number() over (partition by s order by low) - 1 as i from tree where high - low = 1),
placed as (select d.*, shard from d join i on d.rnk = i.rnk and d.seq = i.seq join slots on slots.s = i.s and slots.i = i.i),
took as (select p.*, copy, seq, shard, greatest(0, least(size, floor(p.target - start_ - before + first_)))::bigint as words from p join placed on p.rnk = placed.rnk and p.block = placed.block where size > 0),
numbered as (select rid, copy, words, shard, seq, row_number() over (partition by shard order by md5(shard || ':' || copy || ':' || key), copy, doc_id, size, t, source, seq) - 1 as place from took where words > 0),
s as (select rid, sum(words)::bigint as taken, {", ".join(f"max(case when copy = {i} then {c} end)::{k} as {n}_{i}" for i in (0, 1) for c, k, n in (("shard", "int", "shard"), ("seq", "int", "block"), ("place", "bigint", "place")))} from numbered group by rid)
select doc_id, size, source_size, target, coalesce(taken, 0)::bigint as taken, {", ".join(f"coalesce({n}_{i}, -1) as {n}_{i}" for i in (0, 1) for n in ("shard", "block", "place"))}
from o left join s on o.rid = s.rid
"""
