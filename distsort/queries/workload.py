"""The experiment workloads: every distribution and record type sorted on the given tables, and their profiles."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..catalog import query
from ..operators.sort import sort_global
from ..plans.keys import SortKey
from ..plans.params import SortParams
from ..sources import workloads as W
from ..sources.io import LINE_ID, load
from .methods import ID, line_keys, sorted_sql

_MOD = "(select count(*) from orders)"
_ROOT = f"(select floor(sqrt(count(*)))::bigint from orders)"
KEY_SQL = {
    "uniform": "select o_orderkey as i, o_totalprice as key from orders",
    "exponential": "select event_id as i, value as key from events",
    "almost_sorted": f"select o_orderkey as i, (case when o_orderkey % {_ROOT} = 0 and o_orderkey + 1 < {_MOD} then o_orderkey + 1 when o_orderkey % {_ROOT} = 1 then o_orderkey - 1 else o_orderkey end)::double as key from orders",
    "root_dups": f"select o_orderkey as i, (o_orderkey % {_ROOT})::double as key from orders",
    "square_dups": f"select o_orderkey as i, ((o_orderkey * o_orderkey % {_MOD} + {_MOD} // 2) % {_MOD})::double as key from orders",
    "eighth_dups": f"select i, ((p * p % {_MOD} + {_MOD} // 2) % {_MOD})::double as key from (select i, p * p % {_MOD} as p from (select o_orderkey as i, o_orderkey * o_orderkey % {_MOD} as p from orders))",
    "sorted": "select event_id as i, event_id::double as key from events",
    "reverse": "select event_id as i, ((select count(*) from events) - 1 - event_id)::double as key from events",
    "ones": "select event_id as i, 1.0::double as key from events",
}


def _workload(name):
    return lambda spark, d: sort_global(W.on_table(spark, d, name), ["key", "i"])


for _n in W.NAMES:
    query(f"select row_number() over (order by key, i) - 1 as pos, i, key from ({KEY_SQL[_n]})", f"q_w_{_n}")(_workload(_n))


@query(f"select row_number() over (order by l_returnflag, l_discount, {ID}) - 1 as pos, l_returnflag, l_discount, {ID} from lineitem")
def q_w_table_dups(spark, d):
    return sort_global(load(spark, d, "lineitem", "l_returnflag", "l_discount", *LINE_ID), ["l_returnflag", "l_discount", *LINE_ID])


@query("select row_number() over (order by value, event_id) - 1 as pos, value as key, event_id::double as payload from events")
def q_t_pair(spark, d):
    df = load(spark, d, "events", "event_id", "value").select(F.col("value").alias("key"), F.col("event_id").cast("double").alias("payload"))
    return sort_global(df, ["key", "payload"])


@query(f"select row_number() over (order by l_quantity, l_discount, l_extendedprice, {ID}) - 1 as pos, l_quantity, l_discount, l_extendedprice, l_tax, {ID} from lineitem")
def q_t_quartet(spark, d):
    df = load(spark, d, "lineitem", "l_quantity", "l_discount", "l_extendedprice", "l_tax", *LINE_ID)
    return sort_global(df, ["l_quantity", "l_discount", "l_extendedprice", *LINE_ID])


@query("select row_number() over (order by key, event_id) - 1 as pos, key, payload, event_id from (select substr(md5(event_id::varchar), 1, 10) as key, rpad(event_type || coalesce(props, ''), 90, '.') as payload, event_id from events)")
def q_t_bytes100(spark, d):
    df = load(spark, d, "events", "event_id", "event_type", "props")
    df = df.select(F.substring(F.md5(F.col("event_id").cast("string")), 1, 10).alias("key"), F.rpad(F.concat("event_type", F.coalesce("props", F.lit(""))), 90, ".").alias("payload"), "event_id")
    return sort_global(df, ["key", "event_id"])


@query("select row_number() over (order by key, doc_id) - 1 as pos, key, payload, doc_id from (select substr(text, 1, 10) as key, substr(text, 11, 90) as payload, doc_id from documents)")
def q_t_bytes100_documents(spark, d):
    df = load(spark, d, "documents", "doc_id", "text").select(F.substring("text", 1, 10).alias("key"), F.substring("text", 11, 90).alias("payload"), "doc_id")
    return sort_global(df, ["key", "doc_id"])


@query(" union all ".join(f"select '{n}' as workload, count(*) as n, count(distinct key) as n_keys, (select max(c) from (select count(*) as c from ({s}) group by key)) as most, (select coalesce(sum((key < p)::int), 0)::bigint from (select key, lag(key) over (order by i) as p from ({s}))) as descents from ({s})" for n, s in KEY_SQL.items()))
def q_dist_profile(spark, d):
    """Rows, distinct keys, the highest frequency and descents of each workload."""
    out = None
    for name in W.NAMES:
        df = W.on_table(spark, d, name)
        freq = df.groupBy("key").agg(F.count(F.lit(1)).alias("c")).agg(F.sum("c").alias("n"), F.count(F.lit(1)).alias("n_keys"), F.max("c").alias("most"))
        part = F.floor(F.col("i") / 4096)
        # descents within runs of the index, and between their edges
        inside = df.withColumn("p", part).withColumn("before", F.lag("key").over(Window.partitionBy("p").orderBy("i")))
        each = inside.groupBy("p").agg(F.sum((F.col("key") < F.col("before")).cast("long")).alias("down"), F.min_by("key", "i").alias("a"), F.max_by("key", "i").alias("z"))
        edges = each.withColumn("e", F.lag("z").over(Window.orderBy("p")))
        total = edges.agg((F.coalesce(F.sum("down"), F.lit(0)) + F.coalesce(F.sum((F.col("a") < F.col("e")).cast("long")), F.lit(0))).alias("descents"))
        one = freq.join(F.broadcast(total)).select(F.lit(name).alias("workload"), "n", "n_keys", "most", "descents")
        out = one if out is None else out.unionByName(one)
    return out


_SORTED = sorted_sql("lineitem", "l_quantity, l_extendedprice", "l_quantity, l_extendedprice", ID)
ABLATIONS = {
    "equality": SortParams(equality=True),
    "no_equality": SortParams(equality=False),
    "k": SortParams(k=8),
    "alpha": SortParams(alpha=1),
    "beta": SortParams(beta=4.0),
    "base_case": SortParams(n0=1000),
    "case_backend": SortParams(backend="case", k=32),
    "partitions": SortParams(partitions=3),
    "one_level": SortParams(most_levels=1),
    "seed": SortParams(seed=99),
}


def _ablation(p):
    return lambda spark, d: sort_global(load(spark, d, "lineitem", "l_quantity", "l_extendedprice", *LINE_ID), ["l_quantity", "l_extendedprice", *LINE_ID], p)


for _n, _p in ABLATIONS.items():
    query(_SORTED, f"q_ablate_{_n}")(_ablation(_p))


MULTI_SQL = f"select row_number() over (order by l_shipdate desc nulls last, l_returnflag nulls first, {ID}) - 1 as pos, l_shipdate, l_returnflag, {ID} from lineitem"
DESC_NULLS_SQL = f"select row_number() over (order by x desc nulls first, {ID}) - 1 as pos, x, {ID} from (select case when l_linenumber % 3 = 0 then null else l_extendedprice end as x, {ID} from lineitem)"


def multi(spark, d):
    return load(spark, d, "lineitem", "l_shipdate", "l_returnflag", *LINE_ID), ["-l_shipdate", "l_returnflag", *LINE_ID]


def desc_nulls(spark, d):
    df = line_keys(spark, d).select(F.when(F.col("l_linenumber") % 3 != 0, F.col("l_extendedprice")).alias("x"), *LINE_ID)
    return df, [SortKey("x", False, True), *[SortKey(c) for c in LINE_ID]]


@query(MULTI_SQL)
def q_sort_multi(spark, d):
    return sort_global(*multi(spark, d))


@query(DESC_NULLS_SQL)
def q_sort_desc_nulls(spark, d):
    return sort_global(*desc_nulls(spark, d))


@query("select row_number() over (order by c_name desc, c_custkey) - 1 as pos, c_name, c_custkey from customer")
def q_sort_string(spark, d):
    return sort_global(load(spark, d, "customer", "c_name", "c_custkey"), ["-c_name", "c_custkey"])


@query("select row_number() over (order by ts, event_id) - 1 as pos, ts, event_id from events")
def q_sort_timestamp(spark, d):
    return sort_global(load(spark, d, "events", "ts", "event_id"), ["ts", "event_id"])


@query("select row_number() over (order by k, event_id) - 1 as pos, k, event_id from (select json_extract(props, '$.k')::int as k, event_id from events)")
def q_sort_json_key(spark, d):
    df = load(spark, d, "events", "event_id", "props").select(F.get_json_object("props", "$.k").cast("int").alias("k"), "event_id")
    return sort_global(df, ["k", "event_id"])
