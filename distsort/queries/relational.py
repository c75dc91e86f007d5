"""Relational operators: filters, joins, aggregations, windows, top-k, sets, functions, UDFs."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..catalog import query
from ..functions.udtfs import BlocksOf
from ..operators import relational as R
from ..plans.params import SortParams
from ..sources import io
from ..sources.io import LINE_ID, load
from .methods import ID, line_keys


def plain(name: str, sql: str, *tables: str):
    """A query whose Spark form is built from DataFrames by the decorated function of the loaded tables."""

    def put(f):
        query(sql, name)(lambda spark, d: f(*[load(spark, d, t) for t in tables]))
        return f

    return put


def spark_sql(name: str, sql: str, *tables: str, oracle: str | None = None):
    """A query in SQL that both engines read."""

    def run(spark, d):
        # views of names of their own, so that none of the session's is replaced
        own = {t: f"{t}_{uuid.uuid4().hex}" for t in tables}
        io.register_views(spark, d, own)
        named = ", ".join(f"{t} as (select * from {v})" for t, v in own.items())
        out = spark.sql(f"with {named}, {sql[5:]}" if sql.startswith("with ") else f"with {named} {sql}")
        for v in own.values():
            spark.catalog.dropTempView(v)
        return out

    query(oracle or sql, name)(run)


# ---- projections and filters ---------------------------------------------------------------------
plain("q_project", f"select {ID}, l_extendedprice * (1 - l_discount) as revenue, l_quantity::int as qty from lineitem", "lineitem")(lambda t: t.select(*LINE_ID, (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("revenue"), F.col("l_quantity").cast("int").alias("qty")))
plain("q_filter_range", f"select {ID} from lineitem where l_extendedprice between 1000 and 5000 and l_discount > 0.05", "lineitem")(lambda t: t.where(F.col("l_extendedprice").between(1000, 5000) & (F.col("l_discount") > 0.05)).select(*LINE_ID))
plain("q_filter_in", "select c_custkey, c_mktsegment from customer where c_nationkey in (1, 5, 7)", "customer")(lambda t: t.where(F.col("c_nationkey").isin(1, 5, 7)).select("c_custkey", "c_mktsegment"))
plain("q_filter_like", "select p_partkey, p_type from part where p_type like '%E%' and not p_name like '%a'", "part")(lambda t: t.where(F.col("p_type").like("%E%") & ~F.col("p_name").like("%a")).select("p_partkey", "p_type"))
plain("q_filter_null", "select event_id, (value is null or value > 100) as flag from events where props is not null", "events")(lambda t: t.where("props is not null").select("event_id", (F.col("value").isNull() | (F.col("value") > 100)).alias("flag")))


@query("select event_id, value from events where value between 40 and 45")
def q_range_prune(spark, d):
    """A sorted table's zone map tells which files a range can be in."""
    path, zones = io.fresh_path(spark, "by-value"), io.fresh_path(spark, "zones")
    io.write_sorted(load(spark, d, "events", "event_id", "value"), ["value", "event_id"], path, SortParams(partitions=8))
    return io.lookup(spark, io.write_index(spark.read.parquet(path), "value", zones), "value", 40.0, 45.0)


@query("select o_orderkey, o_totalprice from orders where o_totalprice between 1000 and 9000")
def q_index_lookup(spark, d):
    path, zones = io.fresh_path(spark, "by-price"), io.fresh_path(spark, "zones")
    io.write_sorted(load(spark, d, "orders", "o_orderkey", "o_totalprice"), ["o_totalprice", "o_orderkey"], path, SortParams(partitions=8))
    return io.lookup(spark, io.write_index(spark.read.parquet(path), "o_totalprice", zones), "o_totalprice", 1000.0, 9000.0)


for _f in ("csv", "json", "orc", "parquet"):
    query("select c_custkey, c_name, c_nationkey, c_acctbal, c_mktsegment from customer", f"q_scan_{_f}_roundtrip")(lambda spark, d, f=_f: io.round_trip(load(spark, d, "customer", "c_custkey", "c_name", "c_nationkey", "c_acctbal", "c_mktsegment"), f))


@query("select n_regionkey, count(*) as n from nation group by n_regionkey")
def q_write_partitioned(spark, d):
    path = io.fresh_path(spark, "by-region")
    io.write_partitioned(load(spark, d, "nation"), ["n_regionkey"], path)
    return spark.read.parquet(path).groupBy(F.col("n_regionkey").cast("int").alias("n_regionkey")).agg(F.count(F.lit(1)).alias("n"))


@query("select 0::bigint as out_of_order, count(*) as n from orders")
def q_relabel_files(spark, d):
    """Files in the manifest's order hold keys in order: no bucket reaches into the next one."""
    df = load(spark, d, "orders", "o_orderkey", "o_totalprice")
    path = io.fresh_path(spark, "relabelled")
    manifest = io.write_relabelled(df, ["o_totalprice"], path, SortParams(partitions=4))
    zones = spark.read.parquet(path).groupBy("bucket").agg(F.min("o_totalprice").alias("lo"), F.max("o_totalprice").alias("hi"))
    edges = zones.withColumn("before", F.lag("hi").over(Window.orderBy("bucket"))).agg(F.sum((F.col("lo") < F.col("before")).cast("long")).alias("out_of_order"))
    return edges.crossJoin(manifest.agg(F.sum("n").alias("n")))


@query("select o_custkey, count(*) as n from orders group by o_custkey")
def q_write_bucketed(spark, d):
    name, path = f"orders_{uuid.uuid4().hex}", io.fresh_path(spark, "counted")
    table = io.write_bucketed(load(spark, d, "orders", "o_custkey", "o_orderkey"), "o_custkey", 4, name)
    table.groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n")).write.parquet(path)
    spark.sql(f"drop table {name}")  # nothing stays in the warehouse
    return spark.read.parquet(path)


# ---- joins ---------------------------------------------------------------------------------------
_J = "select o_orderkey, c_custkey, c_mktsegment from orders {} join customer on o_custkey = c_custkey"
def _on():
    return F.col("o_custkey") == F.col("c_custkey")


_cols = ("o_orderkey", "c_custkey", "c_mktsegment")
plain("q_join_hash", _J.format(""), "orders", "customer")(lambda o, c: o.join(c.hint("shuffle_hash"), _on()).select(*_cols))
plain("q_join_broadcast", "select o_orderkey, n_name from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey", "orders", "customer", "nation")(lambda o, c, n: o.join(c, _on()).join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).select("o_orderkey", "n_name"))
plain("q_join_sortmerge", "select l_orderkey, l_linenumber, l_partkey, l_suppkey, o_totalprice from lineitem join orders on l_orderkey = o_orderkey", "lineitem", "orders")(
    lambda line, o: R.distribution_merge_join(line.select(*LINE_ID), o.select(F.col("o_orderkey").alias("l_orderkey"), "o_totalprice"), "l_orderkey")
)
plain("q_join_skew", f"select {ID}, n from lineitem join (select l_returnflag as f, count(*) as n from lineitem group by 1) on l_returnflag = f", "lineitem")(
    lambda t: R.skew_join(t.select("l_returnflag", *LINE_ID), t.groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n")), "l_returnflag").select(*LINE_ID, "n")
)
plain("q_join_theta", "select s_suppkey, r_regionkey from supplier join region on s_nationkey % 7 > r_regionkey", "supplier", "region")(lambda s, r: s.join(F.broadcast(r), F.col("s_nationkey") % 7 > F.col("r_regionkey")).select("s_suppkey", "r_regionkey"))
_RANGES = "(select p_partkey, p_retailprice * 50 as lo, p_retailprice * 50 + 20 as hi from part where p_partkey % 10 = 0)"
plain("q_join_range", f"select o_orderkey, p_partkey from orders join {_RANGES} on o_totalprice >= lo and o_totalprice < hi", "orders", "part")(
    lambda o, p: R.range_join(o.select("o_orderkey", "o_totalprice"), p.where("p_partkey % 10 = 0").select("p_partkey", (F.col("p_retailprice") * 50).alias("lo"), (F.col("p_retailprice") * 50 + 20).alias("hi")), "o_totalprice", "lo", "hi").select("o_orderkey", "p_partkey")
)
plain("q_join_interval", "select a.event_id as a, b.event_id as b from events a join (select event_id, ts as lo, ts + interval 1 minute as hi from events where event_id % 100 = 0) b on a.ts >= lo and a.ts < hi", "events")(
    lambda e: R.range_join(e.select(F.col("event_id").alias("a"), "ts"), e.where("event_id % 100 = 0").select(F.col("event_id").alias("b"), F.col("ts").alias("lo"), (F.col("ts") + F.expr("interval 1 minute")).alias("hi")), "ts", "lo", "hi").select("a", "b")
)
# the same joins over all parts and all events
plain("q_join_range_full", "select o_orderkey, p_partkey from orders join (select p_partkey, p_retailprice * 50 as lo, p_retailprice * 50 + 20 as hi from part) on o_totalprice >= lo and o_totalprice < hi", "orders", "part")(
    lambda o, p: R.range_join(o.select("o_orderkey", "o_totalprice"), p.select("p_partkey", (F.col("p_retailprice") * 50).alias("lo"), (F.col("p_retailprice") * 50 + 20).alias("hi")), "o_totalprice", "lo", "hi").select("o_orderkey", "p_partkey")
)
plain("q_join_interval_full", "select a.event_id as a, b.event_id as b from events a join (select event_id, ts as lo, ts + interval 1 minute as hi from events) b on a.ts >= lo and a.ts < hi", "events")(
    lambda e: R.range_join(e.select(F.col("event_id").alias("a"), "ts"), e.select(F.col("event_id").alias("b"), F.col("ts").alias("lo"), (F.col("ts") + F.expr("interval 1 minute")).alias("hi")), "ts", "lo", "hi").select("a", "b")
)
plain("q_join_asof", "select a.event_id, b.value as purchase from (select * from events where event_type <> 'purchase') a asof left join (select user_id, ts, value from events where event_type = 'purchase') b on a.user_id = b.user_id and a.ts >= b.ts", "events")(
    lambda e: R.asof_join(e.where("event_type <> 'purchase'").select("event_id", "user_id", "ts"), e.where("event_type = 'purchase'").select("user_id", "ts", "value"), "user_id", "ts", "value", "purchase").select("event_id", "purchase")
)
plain("q_join_left", "select c_custkey, o_orderkey from customer left join orders on o_custkey = c_custkey and o_totalprice > 150000", "customer", "orders")(lambda c, o: c.join(o.where("o_totalprice > 150000"), _on(), "left").select("c_custkey", "o_orderkey"))
plain("q_join_full", "select s_suppkey, p_partkey from supplier full join part on s_suppkey = p_partkey", "supplier", "part")(lambda s, p: s.join(p, F.col("s_suppkey") == F.col("p_partkey"), "full").select("s_suppkey", "p_partkey"))
plain("q_join_cross", "select n_name, r_name from nation cross join region", "nation", "region")(lambda n, r: n.crossJoin(F.broadcast(r)).select("n_name", "r_name"))
plain("q_join_semi", "select c_custkey from customer where exists (select 1 from orders where o_custkey = c_custkey)", "customer", "orders")(lambda c, o: c.join(o, _on(), "left_semi").select("c_custkey"))
plain("q_join_anti", "select c_custkey from customer where not exists (select 1 from orders where o_custkey = c_custkey)", "customer", "orders")(lambda c, o: c.join(o, _on(), "left_anti").select("c_custkey"))
spark_sql("q_join_lateral", "select c_custkey, x.most from customer, lateral (select max(o_totalprice) as most from orders where o_custkey = c_custkey) x", "customer", "orders")

# ---- aggregations --------------------------------------------------------------------------------
def _agg():
    return [F.count(F.lit(1)).alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("qty"), F.max("l_extendedprice").alias("most")]


_AGG = "select l_returnflag, l_linestatus, count(*) as n, sum(l_quantity::bigint)::bigint as qty, max(l_extendedprice) as most from lineitem group by all"
plain("q_agg_hash", _AGG, "lineitem")(lambda t: t.groupBy("l_returnflag", "l_linestatus").agg(*_agg()))
plain("q_agg_sorted", "select l_partkey, count(*) as n, sum(l_quantity::bigint)::bigint as qty, max(l_extendedprice) as most from lineitem group by l_partkey", "lineitem")(lambda t: R.sorted_group(t.select("l_partkey", "l_quantity", "l_extendedprice"), ["l_partkey"], _agg()))
plain("q_agg_stats", "select l_returnflag, round(avg(l_quantity), 6) as a, round(stddev_samp(l_quantity), 6) as s, round(var_pop(l_quantity), 6) as v, round(corr(l_quantity, l_extendedprice), 6) as c from lineitem group by l_returnflag", "lineitem")(
    lambda t: t.groupBy("l_returnflag").agg(F.round(F.avg("l_quantity"), 6).alias("a"), F.round(F.stddev_samp("l_quantity"), 6).alias("s"), F.round(F.var_pop("l_quantity"), 6).alias("v"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("c"))
)
plain("q_agg_distinct", "select l_returnflag, count(distinct l_partkey) as parts, count(distinct l_suppkey) as supps from lineitem group by l_returnflag", "lineitem")(lambda t: t.groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("supps")))
plain("q_distinct_sorted", "select distinct l_quantity, l_discount from lineitem", "lineitem")(lambda t: R.distinct_sorted(t, ["l_quantity", "l_discount"]))


@query("select 'parts' as sketch, true as close union all select 'quartile 1', true union all select 'quartile 2', true union all select 'quartile 3', true union all select 'median', true")
def q_agg_approx(spark, d):
    """Sketches beside exact figures of the same table: within 15 % (distinct keys), and within 2 % of all rows (ranks)."""
    t = load(spark, d, "lineitem", "l_partkey", "l_extendedprice")
    quartiles = F.percentile_approx("l_extendedprice", [0.25, 0.5, 0.75], 1000)
    got = t.agg(F.approx_count_distinct("l_partkey").alias("parts"), quartiles.alias("q"), F.kll_sketch_get_quantile_double(F.kll_sketch_agg_double("l_extendedprice"), F.lit(0.5)).alias("median"))
    x = F.col("l_extendedprice")
    share = lambda v: F.avg((x <= v).cast("double"))
    beside = t.join(F.broadcast(got)).agg(F.first("parts").alias("parts"), F.count_distinct("l_partkey").alias("exact"), *[share(F.col("q")[i]).alias(f"s{i}") for i in range(3)], share(F.col("median")).alias("m"))
    near = lambda c, goal: F.abs(F.col(c) - goal) <= 0.02
    rows = [("parts", F.abs(F.col("parts") / F.col("exact") - 1) <= 0.15), *[(f"quartile {i + 1}", near(f"s{i}", (i + 1) / 4)) for i in range(3)], ("median", near("m", 0.5))]
    return beside.select(F.explode(F.array(*[F.struct(F.lit(n).alias("sketch"), c.alias("close")) for n, c in rows])).alias("r")).select("r.sketch", "r.close")


_dims = ("l_returnflag", "l_linestatus")
for _k, _w in (("cube", "cube(l_returnflag, l_linestatus)"), ("rollup", "rollup(l_returnflag, l_linestatus)")):
    plain(f"q_{_k}", f"select l_returnflag, l_linestatus, grouping(l_returnflag) * 2 + grouping(l_linestatus) as g, count(*) as n from lineitem group by {_w}", "lineitem")(lambda t, k=_k: getattr(t, k)(*_dims).agg(F.grouping_id().cast("long").alias("g"), F.count(F.lit(1)).alias("n")))
plain("q_grouping_sets", "select l_returnflag, l_linestatus, count(*) as n from lineitem group by grouping sets ((l_returnflag), (l_linestatus), ())", "lineitem")(
    lambda t: t.groupingSets([[F.col("l_returnflag")], [F.col("l_linestatus")], []], F.col("l_returnflag"), F.col("l_linestatus")).agg(F.count(F.lit(1)).alias("n"))
)
plain("q_pivot", "select l_returnflag, sum((l_linestatus = 'F')::int)::bigint as F, sum((l_linestatus = 'O')::int)::bigint as O from lineitem group by l_returnflag", "lineitem")(lambda t: t.groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.count(F.lit(1))).fillna(0))
plain("q_unpivot", "select s_suppkey, 'nation' as what, s_nationkey::double as v from supplier union all select s_suppkey, 'balance', s_acctbal from supplier", "supplier")(
    lambda t: t.select("s_suppkey", F.col("s_nationkey").cast("double").alias("nation"), F.col("s_acctbal").alias("balance")).unpivot("s_suppkey", ["nation", "balance"], "what", "v")
)
plain("q_agg_collect", "select c_nationkey, array_to_string(list_sort(list(c_custkey)), ',') as ids from customer group by c_nationkey", "customer")(lambda t: t.groupBy("c_nationkey").agg(F.array_join(F.sort_array(F.collect_list("c_custkey")), ",").alias("ids")))
plain("q_agg_maxby", "select o_custkey, arg_max(o_orderkey, (o_totalprice, o_orderkey)) as best, arg_min(o_orderkey, (o_totalprice, o_orderkey)) as least from orders group by o_custkey", "orders")(
    lambda t: t.groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("best"), F.min_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("least"))
)
plain("q_agg_having", "select o_custkey, count(*) as n from orders group by o_custkey having count(*) > 15", "orders")(lambda t: t.groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n")).where("n > 15"))


@query("select l_extendedprice, rank from (select l_extendedprice, row_number() over (order by l_extendedprice) - 1 as rank from lineitem) where rank = (select (count(*) - 1) // 2 from lineitem)")
def q_select_median(spark, d):
    df = load(spark, d, "lineitem", "l_extendedprice")
    return R.select_ranks(df, ["l_extendedprice"], [(df.count() - 1) // 2])


@query("select l_quantity, rank from (select l_quantity, row_number() over (order by l_quantity) - 1 as rank from lineitem) where rank in (select (count(*) - 1) * q // 10 from lineitem, (values (1), (5), (9)) as x(q) group by q)")
def q_quantiles_exact(spark, d):
    df = load(spark, d, "lineitem", "l_quantity")
    n = df.count()
    return R.select_ranks(df, ["l_quantity"], [(n - 1) * q // 10 for q in (1, 5, 9)])


# ---- windows, top-k, sets ------------------------------------------------------------------------
_OW = "over (order by o_totalprice, o_orderkey)"
_OR = "over (order by o_custkey)"


def _ranked(spark, d):
    return R.global_rank(load(spark, d, "orders", "o_custkey", "o_orderkey"), ["o_custkey"], ["o_orderkey"], 10)


query(f"select o_orderkey, row_number() over (order by o_custkey, o_orderkey) as row_number, rank() {_OR} as rank, dense_rank() {_OR} as dense_rank from orders", "q_rank_global")(lambda spark, d: _ranked(spark, d).select("o_orderkey", "row_number", "rank", "dense_rank"))
query("select o_orderkey, ntile(10) over (order by o_custkey, o_orderkey)::int as ntile from orders", "q_ntile_global")(lambda spark, d: _ranked(spark, d).select("o_orderkey", "ntile"))
query(f"select o_orderkey, round(cume_dist() {_OR}, 9) as cume_dist, round(percent_rank() {_OR}, 9) as percent_rank from orders", "q_cume_dist")(lambda spark, d: _ranked(spark, d).select("o_orderkey", F.round("cume_dist", 9).alias("cume_dist"), F.round("percent_rank", 9).alias("percent_rank")))
query(f"select o_orderkey, sum(o_custkey) over (order by o_totalprice, o_orderkey rows unbounded preceding)::bigint as running from orders", "q_cumsum_global")(lambda spark, d: R.global_cumsum(load(spark, d, "orders", "o_orderkey", "o_totalprice", "o_custkey"), ["o_totalprice", "o_orderkey"], F.col("o_custkey")).select("o_orderkey", "running"))
def _w():
    return Window.partitionBy("user_id").orderBy("ts", "event_id")


_DW = "over (partition by user_id order by ts, event_id)"
plain("q_win_analytic", f"select event_id, lag(value) {_DW} as before, lead(value, 2) {_DW} as after, first_value(value) {_DW} as first, nth_value(value, 2) {_DW} as second from events", "events")(
    lambda e: e.select("event_id", F.lag("value").over(_w()).alias("before"), F.lead("value", 2).over(_w()).alias("after"), F.first("value").over(_w()).alias("first"), F.nth_value("value", 2).over(_w()).alias("second"))
)
plain("q_win_rows", "select event_id, max(value) over (partition by user_id order by ts, event_id rows between 2 preceding and 1 following) as m from events", "events")(lambda e: e.select("event_id", F.max("value").over(_w().rowsBetween(-2, 1)).alias("m")))
plain("q_win_range", "select o_orderkey, count(*) over (partition by o_orderstatus order by o_orderkey range between 10 preceding and 10 following) as n from orders", "orders")(lambda o: o.select("o_orderkey", F.count(F.lit(1)).over(Window.partitionBy("o_orderstatus").orderBy("o_orderkey").rangeBetween(-10, 10)).alias("n")))
query(f"select row_number() over (order by l_extendedprice desc, {ID}) - 1 as pos, l_extendedprice, {ID} from lineitem qualify pos < 100", "q_topk")(lambda spark, d: R.top_k(line_keys(spark, d), ["-l_extendedprice", *LINE_ID], 100))
query(f"select row_number() over (order by l_extendedprice, {ID}) - 1 as pos, l_extendedprice, {ID} from lineitem qualify pos >= 500 and pos < 600", "q_limit_offset")(lambda spark, d: R.top_k(line_keys(spark, d), ["l_extendedprice", *LINE_ID], 100, 500))
plain("q_topk_group", "select o_custkey, o_orderkey, r from (select o_custkey, o_orderkey, row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey)::int as r from orders) where r <= 3", "orders")(
    lambda o: o.select("o_custkey", "o_orderkey", F.row_number().over(Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")).alias("r")).where("r <= 3")
)
_A, _B = "select c_nationkey as k from customer", "select s_nationkey as k from supplier"
_sa, _sb = (lambda c: c.select(F.col("c_nationkey").alias("k"))), (lambda s: s.select(F.col("s_nationkey").alias("k")))
for _n, _s, _f in (
    ("union", "union all", lambda a, b: a.unionByName(b)),
    ("union_distinct", "union", lambda a, b: a.unionByName(b).distinct()),
    ("intersect", "intersect", lambda a, b: a.intersect(b)),
    ("intersect_all", "intersect all", lambda a, b: a.intersectAll(b)),
    ("except", "except", lambda a, b: a.subtract(b)),
    ("except_all", "except all", lambda a, b: a.exceptAll(b)),
):
    plain(f"q_{_n}", f"{_A} {_s} {_B}", "customer", "supplier")(lambda c, s, f=_f: f(_sa(c), _sb(s)))
spark_sql("q_sql_cte", "with big as (select o_custkey, sum(o_orderkey) as total from orders group by o_custkey) select c_mktsegment, count(*) as n, cast(max(total) as bigint) as most from big join customer on o_custkey = c_custkey group by c_mktsegment", "orders", "customer")
spark_sql("q_sql_subquery", "select p_partkey from part a where p_retailprice > (select avg(p_retailprice) from part b where b.p_brand = a.p_brand)", "part")
spark_sql("q_sql_exists", "select s_suppkey from supplier where exists (select 1 from lineitem where l_suppkey = s_suppkey and l_quantity > 49) and s_nationkey in (select n_nationkey from nation where n_regionkey = 1)", "supplier", "lineitem", "nation")

# ---- functions -----------------------------------------------------------------------------------
plain("q_fn_string", "select c_custkey, upper(c_mktsegment) as u, lower(c_name) as l, length(c_name)::int as n, substr(c_name, 3, 4) as s, c_name || '/' || c_mktsegment as c, rpad(c_mktsegment, 12, '.') as r, trim('  ' || c_name || ' ') as t, instr(c_name, '0')::int as i, replace(c_mktsegment, 'E', 'e') as p, string_split(c_name, '#')[1] as f, regexp_extract(c_name, '([0-9]+)', 1) as x, md5(c_name) as m from customer", "customer")(
    lambda c: c.select("c_custkey", F.upper("c_mktsegment").alias("u"), F.lower("c_name").alias("l"), F.length("c_name").alias("n"), F.substring("c_name", 3, 4).alias("s"), F.concat("c_name", F.lit("/"), "c_mktsegment").alias("c"), F.rpad("c_mktsegment", 12, ".").alias("r"), F.trim(F.concat(F.lit("  "), "c_name", F.lit(" "))).alias("t"), F.instr("c_name", "0").alias("i"), F.replace("c_mktsegment", F.lit("E"), F.lit("e")).alias("p"), F.split("c_name", "#")[0].alias("f"), F.regexp_extract("c_name", "([0-9]+)", 1).alias("x"), F.md5("c_name").alias("m"))
)
plain("q_fn_date", "select event_id, date_trunc('hour', ts)::timestamp as h, year(ts)::int as y, month(ts)::int as m, day(ts)::int as d, datediff('day', date '2020-01-01', ts::date)::int as days, ts + interval 90 minute as later, epoch_us(ts) as us from events", "events")(
    lambda e: e.select("event_id", F.date_trunc("hour", "ts").cast("timestamp_ntz").alias("h"), F.year("ts").alias("y"), F.month("ts").alias("m"), F.dayofmonth("ts").alias("d"), F.datediff(F.to_date("ts"), F.lit("2020-01-01").cast("date")).alias("days"), (F.col("ts") + F.expr("interval 90 minute")).alias("later"), F.unix_micros(F.to_timestamp_ltz(F.date_format("ts", "yyyy-MM-dd HH:mm:ss.SSSSSSXXX".replace("XXX", "")))).alias("us"))
)
plain("q_fn_math", "select o_orderkey, round(log2(o_totalprice), 6) as lg, floor(o_totalprice)::bigint as f, ceil(o_totalprice)::bigint as c, round(sqrt(o_totalprice), 6) as s, power(o_orderkey % 7, 3)::double as p, ((o_orderkey - 5) % 7 + 7) % 7 as pm, (o_orderkey << 2) as sl, (o_orderkey >> 1) as sr, (o_orderkey & 12) as ba, xor(o_orderkey, 5) as bx from orders", "orders")(
    lambda o: o.select("o_orderkey", F.round(F.log2("o_totalprice"), 6).alias("lg"), F.floor("o_totalprice").alias("f"), F.ceil("o_totalprice").alias("c"), F.round(F.sqrt("o_totalprice"), 6).alias("s"), F.pow(F.col("o_orderkey") % 7, 3).alias("p"), F.pmod(F.col("o_orderkey") - 5, F.lit(7)).alias("pm"), F.shiftleft("o_orderkey", 2).alias("sl"), F.shiftright("o_orderkey", 1).alias("sr"), F.col("o_orderkey").bitwiseAND(F.lit(12)).alias("ba"), F.col("o_orderkey").bitwiseXOR(F.lit(5)).alias("bx"))
)
plain("q_width_bucket", "select least(11, greatest(0, floor((o_totalprice - 0) / 50000.0)::bigint + 1)) as b, count(*) as n from orders group by 1", "orders")(lambda o: o.groupBy(F.width_bucket("o_totalprice", F.lit(0.0), F.lit(500000.0), F.lit(10)).cast("long").alias("b")).agg(F.count(F.lit(1)).alias("n")))
plain("q_fn_array", "select vec_id, len(embedding)::int as n, embedding[1]::double as a, list_min(embedding)::double as lo, list_max(embedding)::double as hi, len(list_filter(embedding, lambda x: x > 0))::int as pos, list_position(embedding, list_max(embedding))::bigint as at from embeddings", "embeddings")(
    lambda e: e.select("vec_id", F.size("embedding").alias("n"), F.element_at("embedding", 1).cast("double").alias("a"), F.array_min("embedding").cast("double").alias("lo"), F.array_max("embedding").cast("double").alias("hi"), F.size(F.filter("embedding", lambda x: x > 0)).alias("pos"), F.array_position("embedding", F.array_max("embedding")).alias("at"))
)
plain("q_sort_within_array", "select vec_id, i::int as i, x::double as x from (select vec_id, unnest(list_sort(embedding)) as x, unnest(range(len(embedding))) as i from embeddings) where i < 5", "embeddings")(lambda e: e.select("vec_id", F.posexplode(F.slice(F.array_sort("embedding"), 1, 5)).alias("i", "x")).withColumn("x", F.col("x").cast("double")))
plain("q_sort_within_array_full", "select vec_id, i::int as i, x::double as x from (select vec_id, unnest(list_sort(embedding)) as x, unnest(range(len(embedding))) as i from embeddings)", "embeddings")(lambda e: e.select("vec_id", F.posexplode(F.array_sort("embedding")).alias("i", "x")).withColumn("x", F.col("x").cast("double")))
plain("q_fn_map", "select n_nationkey, n_name as v, 2 as n from nation", "nation")(
    lambda n: n.withColumn("m", F.map_from_arrays(F.array(F.lit("name"), F.lit("region")), F.array("n_name", F.col("n_regionkey").cast("string")))).select("n_nationkey", F.element_at("m", "name").alias("v"), F.size(F.map_keys(F.map_filter("m", lambda k, v: v.isNotNull()))).alias("n"))
)
plain("q_fn_json", "select event_id, json_extract(props, '$.k')::int as k from events", "events")(lambda e: e.select("event_id", F.from_json("props", "k int")["k"].alias("k")))
plain("q_fn_cond", "select o_orderkey, coalesce(nullif(o_orderstatus, 'O'), 'open') as s, case when o_totalprice > 200000 then 'high' when o_totalprice > 100000 then 'mid' else 'low' end as c, greatest(o_custkey, 700) as g, least(o_custkey, 700) as l from orders", "orders")(
    lambda o: o.select("o_orderkey", F.coalesce(F.nullif(F.col("o_orderstatus"), F.lit("O")), F.lit("open")).alias("s"), F.when(F.col("o_totalprice") > 200000, "high").when(F.col("o_totalprice") > 100000, "mid").otherwise("low").alias("c"), F.greatest("o_custkey", F.lit(700)).alias("g"), F.least("o_custkey", F.lit(700)).alias("l"))
)
plain("q_fn_hash", "select c_custkey, md5(c_name) as m, hex(c_custkey) as h from customer", "customer")(lambda c: c.select("c_custkey", F.md5("c_name").alias("m"), F.hex("c_custkey").alias("h")))


# ---- user functions ------------------------------------------------------------------------------
@F.pandas_udf(T.DoubleType())
def middle(x: pd.Series) -> float:
    return float(x.median())


plain("q_udaf_median", "select c_nationkey, median(c_acctbal) as m from customer group by c_nationkey", "customer")(lambda c: c.groupBy("c_nationkey").agg(middle("c_acctbal").alias("m")))
plain("q_udf_scalar", "select c_custkey, c_mktsegment || ':' || c_nationkey as r from customer", "customer")(lambda c: c.select("c_custkey", F.udf(lambda s, k: f"{s}:{k}", "string")("c_mktsegment", "c_nationkey").alias("r")))


@query("select n_regionkey::bigint as bucket, i * 2 as lo, least(n, i * 2 + 2) as hi from (select n_regionkey, count(*) as n from nation group by 1), range(100) as x(i) where i * 2 < n")
def q_udtf_blocks(spark, d):
    spark.udtf.register("blocks_of", F.udtf(BlocksOf, returnType="bucket long, lo long, hi long"))
    load(spark, d, "nation").createOrReplaceTempView("nation")
    return spark.sql("select b.* from (select cast(n_regionkey as bigint) as k, count(*) as n from nation group by 1) x, lateral blocks_of(x.k, x.n, cast(2 as bigint)) b")


@query("select o_orderkey, floor(o_totalprice / 1000)::bigint as thousands from orders")
def q_sql_udf(spark, d):
    spark.sql("create or replace temporary function thousands_of(x double) returns bigint return floor(x / 1000)")
    load(spark, d, "orders").createOrReplaceTempView("orders")
    return spark.sql("select o_orderkey, thousands_of(o_totalprice) as thousands from orders")
