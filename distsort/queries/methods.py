"""The steps of the method as queries over lineitem: sample, splitters, buckets, blocks, offsets, plans."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..catalog import query
from ..functions.classify import SplitterTree
from ..operators import blocks as B
from ..operators.sort import sort_global
from ..plans.params import SortParams, block_rows, level_plan, oversampling
from ..plans.recursion import pack_buckets, plan_recursion
from ..plans.sampling import SplitterSet, dedupe_splitters, draw_sample, pick_splitters, sketched_quantiles
from ..sources.io import LINE_ID, load

K, ALPHA, BLOCK, STRIPES, SEED = 16, 4, 64, 4, 7
ID = ", ".join(LINE_ID)
DIGEST = f"md5(concat_ws('-', {', '.join(f'{c}::varchar' for c in LINE_ID)}) || ':{SEED}')"


def line_keys(spark: SparkSession, d: str, key: str = "l_extendedprice") -> DataFrame:
    return load(spark, d, "lineitem", *LINE_ID, key)


def line_splitters(df: DataFrame, key: str = "l_extendedprice") -> list[tuple]:
    sample = draw_sample(df, [key], ALPHA * K - 1, SEED, "digest", LINE_ID)
    return pick_splitters([(r[key],) for r in sample.orderBy(key, *LINE_ID).collect()], K)


def line_tree(df: DataFrame, key: str = "l_extendedprice") -> SplitterTree:
    return SplitterTree.build(df, [key], dedupe_splitters(line_splitters(df, key)))


def line_blocks(spark: SparkSession, d: str) -> B.Striped:
    df = line_keys(spark, d)
    ranked, n = B.ranked(df, LINE_ID)
    return B.local_classify(ranked, n, line_tree(df), BLOCK, STRIPES)


def cte(key: str = "l_extendedprice") -> str:
    return f"""
t as (select {ID}, {key} as key, row_number() over (order by {ID}) - 1 as rnk from lineitem),
sample as (select * from t order by {DIGEST}, {ID} limit {ALPHA * K - 1}),
picked as (select row_number() over (order by key, {ID}) as r, key from sample),
sp0 as (select (r // {ALPHA})::int as idx, key as splitter from picked where r % {ALPHA} = 0),
sp as (select (row_number() over (order by splitter))::int as idx, splitter from (select distinct splitter from sp0)),
bk as (select t.*, (select count(*) from sp where splitter <= t.key)::int as bucket from t),
nn as (select count(*) as n, ceil(count(*) / {BLOCK}.0)::bigint as nb from t),
st as (select r::int as stripe, least(n, {BLOCK} * ((nb * r) // {STRIPES})) as lo, least(n, {BLOCK} * ((nb * (r + 1)) // {STRIPES})) as hi from nn, range({STRIPES}) as x(r)),
rows_ as (select bk.*, stripe, lo, row_number() over (partition by stripe, bucket order by rnk) - 1 as q from bk join st on rnk >= lo and rnk < hi),
pm as (select stripe, bucket, lo, q // {BLOCK} as m, min(rnk) as first_rowid, count(*) as n_rows, min(key) as min_key, max(key) as max_key from rows_ group by stripe, bucket, lo, q // {BLOCK}),
fl as (select *, lead(first_rowid) over (partition by stripe, bucket order by m) as trig from pm),
bl as (select *, row_number() over (partition by stripe order by trig) - 1 as local_, lo // {BLOCK} + row_number() over (partition by stripe order by trig) - 1 as slot from fl where trig is not null),
ks as (select unnest(range((select count(*) + 1 from sp)))::int as bucket),
sz as (select ks.bucket, count(rows_.rnk) as size from ks left join rows_ on ks.bucket = rows_.bucket group by ks.bucket),
off as (select bucket, size, (sum(size) over (order by bucket) - size)::bigint as start from sz),
fb as (select bucket, sum((n - 1) // {BLOCK})::bigint as full_blocks from (select stripe, bucket, count(*) as n from rows_ group by stripe, bucket) group by bucket),
dl as (select off.bucket, start, size, ceil(start / {BLOCK}.0)::bigint as delim, ceil((start + size) / {BLOCK}.0)::bigint as next_delim, coalesce(full_blocks, 0) as full_blocks,
  (ceil(start / {BLOCK}.0)::bigint + coalesce(full_blocks, 0)) * {BLOCK} > (select n from nn) as overflow from off left join fb on off.bucket = fb.bucket)"""


def sorted_sql(table: str, cols: str, order: str, ids: str) -> str:
    return f"select row_number() over (order by {order}, {ids}) - 1 as pos, {cols}, {ids} from {table}"


@query(sorted_sql("lineitem", "l_extendedprice", "l_extendedprice", ID))
def q_sort_uniform(spark: SparkSession, d: str) -> DataFrame:
    return sort_global(line_keys(spark, d), ["l_extendedprice", *LINE_ID])


@query(f"with {cte()} select {ID}, key from sample")
def q_sample_digest(spark, d):
    return draw_sample(line_keys(spark, d), ["l_extendedprice"], ALPHA * K - 1, SEED, "digest", LINE_ID).withColumnRenamed("l_extendedprice", "key")


@query(f"with {cte()} select idx, splitter from sp0")
def q_splitters(spark, d):
    found = line_splitters(line_keys(spark, d))
    return spark.createDataFrame([(i + 1, v[0]) for i, v in enumerate(found)], "idx int, splitter double")


@query(f"with {cte('l_quantity')} select idx, splitter, (select count(*) from sp) < {K - 1} as use_equality from sp")
def q_splitters_dedup(spark, d):
    s = dedupe_splitters(line_splitters(line_keys(spark, d, "l_quantity"), "l_quantity"))
    return spark.createDataFrame([(i + 1, v[0], s.use_equality) for i, v in enumerate(s.values)], "idx int, splitter double, use_equality boolean")


_BUCKETS = f"with {cte()} select bucket, count(*) as n, min(key) as min_key, max(key) as max_key from bk group by bucket"


def _bucket_ids(method: str):
    def run(spark, d):
        df = line_keys(spark, d)
        placed = line_tree(df).with_bucket(df, "bucket", method)
        return placed.groupBy("bucket").agg(F.count(F.lit(1)).alias("n"), F.min("l_extendedprice").alias("min_key"), F.max("l_extendedprice").alias("max_key"))

    return run


for _m, _name in (("chained", "q_bucket_ids"), ("case", "q_bucket_ids_case"), ("hof", "q_bucket_ids_hof"), ("arrow", "q_bucket_ids_arrow"), ("rangejoin", "q_bucket_ids_rangejoin")):
    query(_BUCKETS, _name)(_bucket_ids(_m))


@query(f"with {cte('l_quantity')} select (2 * bucket - (key in (select splitter from sp))::int)::int as cls, count(*) as n, min(key) as min_key, max(key) as max_key from bk group by 1")
def q_class_ids(spark, d):
    df = line_keys(spark, d, "l_quantity")
    tree = line_tree(df, "l_quantity")
    return tree.with_class(tree.with_bucket(df)).groupBy("cls").agg(F.count(F.lit(1)).alias("n"), F.min("l_quantity").alias("min_key"), F.max("l_quantity").alias("max_key"))


@query(f"with {cte()} select stripe, bucket, count(*) as n from rows_ group by stripe, bucket")
def q_stripe_counts(spark, d):
    return B.stripe_counts(line_blocks(spark, d))


@query(f"with {cte()} select stripe, slot, bucket, first_rowid, n_rows, min_key, max_key from bl")
def q_block_table(spark, d):
    return B.flushed_blocks(line_blocks(spark, d), "l_extendedprice").select("stripe", "slot", "bucket", "first_rowid", "n_rows", "min_key", "max_key")


@query(f"with {cte()} select stripe, count(*) as blocks from (select stripe, bucket, lo, m from pm where n_rows = {BLOCK}) group by stripe")
def q_block_table_eager(spark, d):
    return B.flushed_blocks(line_blocks(spark, d), "l_extendedprice", eager=True).groupBy("stripe").agg(F.count(F.lit(1)).alias("blocks"))


@query(f"with {cte()} select stripe, min(trig - lo - local_ * {BLOCK})::bigint as min_room from bl group by stripe")
def q_flush_room(spark, d):
    return B.flush_room(line_blocks(spark, d), "l_extendedprice")


@query(f"with {cte()} select bucket, size, start from off")
def q_prefix_offsets(spark, d):
    return B.prefix_offsets(line_blocks(spark, d))


@query(f"with {cte()} select bucket, start, delim, next_delim, full_blocks, overflow from dl")
def q_delimiters(spark, d):
    return B.delimiters(line_blocks(spark, d)).drop("size")


@query(f"with {cte()} select stripe, slot, bl.bucket, delim + row_number() over (partition by bl.bucket order by slot) - 1 as target from bl join dl on bl.bucket = dl.bucket")
def q_block_targets(spark, d):
    return B.block_targets(line_blocks(spark, d), "l_extendedprice")


@query(f"""with {cte()}, h as (select dl.bucket, delim, slot, count(slot) over (partition by dl.bucket) as occ from dl left join bl on slot >= delim and slot < next_delim)
select bucket, max(occ) as occupied, coalesce(sum((slot >= delim + occ)::int), 0)::bigint as moves from h group by bucket""")
def q_empty_compaction(spark, d):
    return B.empty_compaction(line_blocks(spark, d), "l_extendedprice")


_PLACE = f"with {cte()} select bl.bucket, count(*) as blocks, sum((slot >= delim and slot < delim + full_blocks)::int)::bigint as in_place, (count(*) - sum((slot >= delim and slot < delim + full_blocks)::int))::bigint as to_move from bl join dl on bl.bucket = dl.bucket group by bl.bucket"


@query(_PLACE)
def q_blocks_in_place(spark, d):
    return B.blocks_in_place(line_blocks(spark, d), "l_extendedprice")


@query(f"""with {cte()}, h as (select bucket, least(delim * {BLOCK} - start, size)::bigint as head,
 case when full_blocks = 0 then 0 else greatest(0, (delim + full_blocks) * {BLOCK} - (start + size)) end::bigint as overhang, (size - full_blocks * {BLOCK})::bigint as leftovers from dl)
select *, leftovers + overhang as gap from h""")
def q_heads_tails(spark, d):
    return B.heads_tails(line_blocks(spark, d))


@query(f"with {cte()} select bucket, (bucket * {STRIPES}) // (select count(*) from ks) as worker from ks")
def q_bucket_workers(spark, d):
    k = line_tree(line_keys(spark, d)).buckets
    return spark.range(k).select(F.col("id").cast("int").alias("bucket"), F.floor(F.col("id") * STRIPES / k).alias("worker"))


def _sizes(spark, d, key="l_extendedprice") -> list[int]:
    df = line_keys(spark, d, key)
    tree = line_tree(df, key)
    got = dict(tree.with_bucket(df.select(key)).groupBy("bucket").count().collect())
    return [got.get(b, 0) for b in range(tree.buckets)]


@query(f"""with {cte('l_quantity')} select bucket, size, case when size * {STRIPES} >= 0.3 * (select n from nn) and size >= 3000 then 'split' when size < 3000 then 'base' else 'pack' end as action from sz""")
def q_recursion_plan(spark, d):
    sizes = _sizes(spark, d, "l_quantity")
    plan = plan_recursion(sizes, STRIPES, 0.3, 3000)
    return spark.createDataFrame(list(zip(range(len(sizes)), sizes, plan)), "bucket int, size long, action string")


@query(f"with {cte()} select bucket, least({STRIPES - 1}, ((2 * start + size) * {STRIPES}) // (2 * (select n from nn)))::int as pid from off")
def q_pack_contiguous(spark, d):
    return spark.createDataFrame(list(enumerate(pack_buckets(_sizes(spark, d), STRIPES))), "bucket int, pid int")


@query(f"with {cte()}, p as (select least({STRIPES - 1}, ((2 * start + size) * {STRIPES}) // (2 * (select n from nn)))::int as pid, size from off) select {STRIPES} as workers, max(load)::bigint as longest, (select n from nn) as rows from (select pid, sum(size) as load from p group by pid)")
def q_pack_balance(spark, d):
    """The longest load by contiguous packing; packing the longest first never does worse here, which the tests check."""
    sizes = _sizes(spark, d)
    load = [0] * STRIPES
    for s, w in zip(sizes, pack_buckets(sizes, STRIPES)):
        load[w] += s
    return spark.createDataFrame([(STRIPES, max(load), sum(sizes))], "workers int, longest long, rows long")


@query("""with recursive ns(l_returnflag, l_linenumber, n) as (select l_returnflag, l_linenumber, count(*) from lineitem group by l_returnflag, l_linenumber),
a(l_returnflag, l_linenumber, n, bits, lev) as (select l_returnflag, l_linenumber, n, log2(n / 16.0), 0 from ns where n > 16 union all select l_returnflag, l_linenumber, n, bits - 8, lev + 1 from a where ceil(bits / 8) > 2)
select l_returnflag, l_linenumber, n, lev::int as level, 256 as k from a where lev > 0
union all select l_returnflag, l_linenumber, n, (lev + i + 1)::int, (2 ** floor(bits / left_))::int from (select *, ceil(bits / 8)::int as left_ from a where ceil(bits / 8) <= 2 and bits >= 1), (values (0), (1)) as x(i) where i < left_""")
def q_level_plan(spark, d):
    """The levels for the rows of each part of lineitem."""
    parts = load(spark, d, "lineitem", "l_returnflag", "l_linenumber").groupBy("l_returnflag", "l_linenumber").agg(F.count(F.lit(1)).alias("n"))
    levels = F.udf(level_plan, "array<int>")
    return parts.select("*", F.posexplode(levels("n")).alias("level", "k")).withColumn("level", F.col("level") + 1)


@query("""select r as record, s, greatest(1, (2 ** floor(11 - log2(s)))::int)::int as b, greatest(1, round(0.2 * log2(n)))::int as alpha
from (values ('float', 8), ('pair', 16), ('quartet', 32), ('bytes100', 100)) as x(r, s), (select count(*) as n from lineitem)""")
def q_params_by_record(spark, d):
    n = load(spark, d, "lineitem").count()
    return spark.createDataFrame([(r, s, block_rows(s), oversampling(n)) for r, s in (("float", 8), ("pair", 16), ("quartet", 32), ("bytes100", 100))], "record string, s int, b int, alpha int")


@query(f"with {cte()} select (row_number() over (order by bl.bucket, slot) - 1)::bigint as seq, stripe, slot, bucket from bl")
def q_relabel_manifest(spark, d):
    return B.relabel_manifest(line_blocks(spark, d), "l_extendedprice")


@query(f"with {cte()}, c as (select stripe, bucket, count(*) as n from rows_ group by stripe, bucket), r as (select *, row_number() over (partition by bucket order by n desc, stripe) as x from c) select bucket, stripe, n from r where x = 1")
def q_affinity(spark, d):
    return B.affinity(line_blocks(spark, d))


@query(f"select row_number() over (order by l_extendedprice, {ID}) - 1 as pos, {ID} from lineitem")
def q_positions(spark, d):
    return sort_global(line_keys(spark, d), ["l_extendedprice", *LINE_ID]).drop("l_extendedprice")


@query(f"with x as (values (0.0), (1000.0), (50000.0), (104000.0), (1e9)) select col0::double as x, (select count(*) from lineitem where l_extendedprice <= col0)::bigint as pos from x")
def q_next_larger(spark, d):
    """For each x the first position with a larger key, or the number of rows."""
    ordered = sort_global(line_keys(spark, d), ["l_extendedprice", *LINE_ID]).select("pos", "l_extendedprice")
    n = load(spark, d, "lineitem").count()
    xs = spark.createDataFrame([(0.0,), (1000.0,), (50000.0,), (104000.0,), (1e9,)], "x double")
    hit = [F.min(F.when(F.col("l_extendedprice") > v, F.col("pos"))).alias(f"p{i}") for i, v in enumerate((0.0, 1000.0, 50000.0, 104000.0, 1e9))]
    found = ordered.agg(*hit).select(F.posexplode(F.array(*[f"p{i}" for i in range(5)])).alias("i", "pos"))
    numbered = xs.withColumn("i", F.row_number().over(Window.orderBy("x")) - 1)
    return numbered.join(found, "i").select("x", F.coalesce("pos", F.lit(n)).cast("long").alias("pos"))


@query(sorted_sql("lineitem", "l_quantity", "l_quantity", ID))
def q_sort_equality(spark, d):
    """Few distinct keys: the row id breaks ties, so that heavy keys are split by it."""
    return sort_global(line_keys(spark, d, "l_quantity"), ["l_quantity", *LINE_ID])


@query("select (row_number() over (order by l_quantity) - 1)::bigint as pos, l_quantity from lineitem")
def q_sort_spread_classes(spark, d):
    """No tie-breaker: classes of equal keys are spread over partitions and not sorted."""
    return sort_global(load(spark, d, "lineitem", "l_quantity"), ["l_quantity"], SortParams(equality=True, partitions=8))


@query(f"with {cte()} select bucket, size as n, start as first, (start + size - 1)::bigint as last, size as places from off where size > 0")
def q_cleanup(spark, d):
    """Every bucket's rows at places of their own that are its span exactly."""
    placed = B.cleaned_up(line_blocks(spark, d), "l_extendedprice")
    return placed.groupBy("bucket").agg(F.count(F.lit(1)).alias("n"), F.min("place").alias("first"), F.max("place").alias("last"), F.count_distinct("place").alias("places"))


@query(f"with {cte()}, wk as (select bucket, (bucket * {STRIPES} // (select count(*) from ks))::int as worker, least(delim * {BLOCK} - start, size)::bigint as head from dl) select worker - 1 as worker, min(bucket) as next_bucket, arg_min(head, bucket)::bigint as head from wk where worker > 0 group by worker")
def q_saved_heads(spark, d):
    return B.saved_heads(line_blocks(spark, d), STRIPES)


def _same_rows_each_time(spark, d, method):
    df, m = line_keys(spark, d), 64
    draw = lambda: draw_sample(df, ["l_extendedprice"], m, SEED, method, LINE_ID)
    one = draw().agg(F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64(*LINE_ID).cast("decimal(38,0)")).alias("s"))
    two = draw().agg(F.sum(F.xxhash64(*LINE_ID).cast("decimal(38,0)")).alias("s2"))
    few = F.col("n") == m if method in ("digest", "hash") else (F.col("n") >= m // 4) & (F.col("n") <= 4 * m)
    return one.join(F.broadcast(two)).select(F.lit(method).alias("method"), few.alias("as_many"), (F.col("s") == F.col("s2")).alias("same"))


_METHODS = ("bernoulli", "digest", "hash", "per_partition")


@query(" union all ".join(f"select '{m}' as method, true as as_many, true as same" for m in _METHODS))
def q_sample_methods(spark, d):
    """Each way of sampling: whether it draws as many rows as it says, and the same ones again."""
    return reduce(DataFrame.unionByName, [_same_rows_each_time(spark, d, m) for m in _METHODS])


@query(f"select i as idx, true as close from range(1, {K}) as x(i)")
def q_sample_sketch(spark, d):
    """Splitters from a mergeable sketch: whether each has its share of the rows at or under it, to within 1 %."""
    df = line_keys(spark, d)
    cuts = sketched_quantiles(df, "l_extendedprice", K)
    shares = [F.avg((F.col("l_extendedprice") <= c).cast("double")).alias(f"s{i}") for i, c in enumerate(cuts, 1)]
    each = F.array(*[F.struct(F.lit(i).cast("long").alias("idx"), (F.abs(F.col(f"s{i}") - i / K) <= 0.01).alias("close")) for i in range(1, K)])
    return df.agg(*shares).select(F.explode(each).alias("x")).select("x.idx", "x.close")
