"""URL filter: a blocked Bloom filter of listed canonical URLs, then an exact hash join of its hits.

Rules (host and path prefix) are a parameter, some hundreds at most: a page's host suffixes with each listed path length are looked up in a map of
them within its row, and nothing is exchanged for them.  Where no rule fits, the page's canonical URL asks the filter, a table of blocks of
512 bits (eight longs); a key's block comes from one half of its hash, its bits in the block from the other.  What
passes is joined to the list by its full key, so that a false positive never decides; what doesn't is exchanged with nothing.

The filter has a block for each KEYS_A_BLOCK keys, but at most MOST_BLOCKS of them (64 bytes each), whatever the list's length; a longer list
only makes more keys pass.

Defined results: a null url, or one without `://`, has an empty host and path, fits no rule and is allowed; repeated
rows are judged each; an empty table gives an empty result; only page_id and url are read.
"""

from __future__ import annotations

from functools import partial, reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower, rows_of, small, written

#: (verdict, host, path prefix) of the contract.  Fixed values.
RULES = (
    ("block", "com", "/en/"),
    ("allow", "example.com", "/en/7"),
    ("allow", "net", "/de/"),
    ("block", "example.net", "/de/8"),
    ("block", "org", "/es/"),
)
BLOCKS, WORDS, PROBES = 1 << 15, 8, 5
#: A filter's size: so many keys a block (with 5 probes, one key in 300 passes that isn't listed), and blocks at most.
KEYS_A_BLOCK, MOST_BLOCKS = 32, 1 << 20
#: Query parameters that don't change the page.  Fixed values.
TRACKING = "^(utm_[^=]*|ref|fbclid|gclid)(=|$)"


def parts(url: Column) -> tuple[Column, Column, Column]:
    """Host (A-Z lower-cased), path, query."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substr(url, at + 3)).otherwise("")
    rest = F.coalesce(rest, F.lit(""))
    host = F.regexp_extract(rest, "^([^/?#]*)", 1)
    tail = F.substr(rest, F.length(host) + 1)
    path = F.regexp_extract(tail, "^([^?#]*)", 1)
    query = F.regexp_extract(F.substr(tail, F.length(path) + 1), r"^\?([^#]*)", 1)
    return ascii_lower(host), path, query


def canonical(host: Column, path: Column, query: Column) -> Column:
    """Host without www. and a usual port, path without slashes at its end, query sorted and without tracking."""
    kept = F.array_sort(F.filter(F.split(query, "&"), lambda x: (x != "") & ~x.rlike(TRACKING)))
    q = F.when(F.size(kept) > 0, F.concat(F.lit("?"), F.array_join(kept, "&"))).otherwise("")
    return F.concat(F.regexp_replace(F.regexp_replace(host, r"^www\.", ""), ":(80|443)$", ""), F.regexp_replace(path, "/+$", ""), q)


def parsed(pages: DataFrame) -> DataFrame:
    """page_id, host, path, canonical."""
    host, path, query = parts(F.col("url"))
    split = pages.select("page_id", host.alias("host"), path.alias("path"), query.alias("query"))
    return split.select("page_id", "host", "path", canonical(F.col("host"), F.col("path"), F.col("query")).alias("canonical"))


def key_hash(key: Column) -> Column:
    return F.xxhash64(key)


def blocks_for(keys: int) -> int:
    """A power of two."""
    return min(MOST_BLOCKS, 1 << max(0, -(-keys // KEYS_A_BLOCK) - 1).bit_length())


def block_of(h: Column, blocks: int = BLOCKS) -> Column:
    return F.pmod(F.shiftrightunsigned(h, 32), F.lit(blocks).cast("long")).cast("int")


def bits_of(h: Column) -> list[Column]:
    """PROBES bit numbers within a block, 9 bits each of a second mix of the hash."""
    mixed = F.xxhash64(h)
    return [F.shiftrightunsigned(mixed, 9 * i).bitwiseAND(F.lit(WORDS * 64 - 1)).cast("int") for i in range(PROBES)]


def blocked_filter(keys: DataFrame, blocks: int = BLOCKS) -> DataFrame:
    """block, w0 .. w7: one row for each block that has a bit; at most `blocks` rows."""
    h = key_hash(F.col("key"))
    each = keys.select(block_of(h, blocks).alias("block"), F.explode(F.array(*bits_of(h))).alias("bit"))
    one = F.expr("shiftleft(1L, bit % 64)")
    return each.groupBy("block").agg(*[F.bit_or(F.when(F.floor(F.col("bit") / 64) == w, one).otherwise(F.lit(0).cast("long"))).alias(f"w{w}") for w in range(WORDS)])


def may_contain(h: Column) -> Column:
    """Whether all of a key's bits are set in the block row that was joined to it."""
    words = F.array(*[F.col(f"w{w}") for w in range(WORDS)])
    tests = [F.getbit(F.get(words, F.floor(b / 64).cast("int")), b % 64) == 1 for b in bits_of(h)]
    return reduce(Column.__and__, tests)


def _with_prefix(n: int, suffix: Column) -> Column:
    return F.concat(suffix, F.substring("path", 1, n))


def best_rule(rules) -> Column:
    """The longest rule that fits host and path, as a struct (length, rule, says); null if none does."""
    if not rules:
        return F.lit(None).cast("struct<length:int,rule:string,says:string>")
    says = F.create_map(*[F.lit(x) for v, h, p in rules for x in (h + p, v)])
    labels = F.split(F.col("host"), r"\.")
    suffixes = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    asked = F.array_distinct(F.concat(*[F.transform(suffixes, partial(_with_prefix, n)) for n in sorted({len(p) for _, _, p in rules})]))
    fits = F.filter(asked, lambda k: F.map_contains_key(says, k))
    return F.when(F.col("host") != "", F.array_max(F.transform(fits, lambda k: F.struct(F.length(k).alias("length"), k.alias("rule"), F.element_at(says, k).alias("says")))))


def judge(pages: DataFrame, listed: DataFrame, rules=RULES) -> DataFrame:
    """page_id, host, path, rule, verdict.

    listed: canonical URLs (column canonical) that are blocked where no rule fits; rules: (verdict, host, path prefix)."""
    entries = written(listed.where("canonical is not null").select(F.col("canonical").alias("key")).distinct(), "url-list")
    blocks = blocks_for(rows_of(entries))
    bloom = written(blocked_filter(entries, blocks), "url-bloom", blocks)
    urls = parsed(pages).withColumn("best", best_rule(rules)).withColumn("h", key_hash(F.col("canonical"))).withColumn("at", block_of(F.col("h"), blocks))
    asked = urls.join(F.broadcast(bloom), (F.col("at") == F.col("block")) & F.col("best").isNull() & (F.col("host") != ""), "left")  # MOST_BLOCKS rows at most
    passes = F.col("block").isNotNull() & may_contain(F.col("h"))
    names = ["page_id", "host", "path", F.col("best.rule").alias("rule")]
    rest = asked.where(~F.coalesce(passes, F.lit(False))).select(*names, F.coalesce("best.says", F.lit("allow")).alias("verdict"))
    # in the list by its full key, or not after all
    met = asked.where(passes).join(small(entries), F.col("canonical") == F.col("key"), "left")
    return rest.unionByName(met.select(*names, F.when(F.col("key").isNotNull(), "block").otherwise("allow").alias("verdict")))


def standing_list(pages: DataFrame) -> DataFrame:
    """The listing of the query, as the given tables hold none: canonical URLs of the pages whose id is divisible by 50."""
    return parsed(pages.where(F.col("page_id") % 50 == 0)).where("host <> ''").select("canonical")


_HOST = "translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_RULES = ", ".join(f"('{v}', '{h}', '{p}')" for v, h, p in RULES)
ORACLE = f"""
with a as (select page_id, row_number() over () as rid, case when instr(url, '://') > 0 then substr(url, instr(url, '://') + 3) else '' end as rest from pages),
b as (select page_id, rid, {_HOST} as host, substr(coalesce(rest, ''), length(regexp_extract(coalesce(rest, ''), '^[^/?#]*')) + 1) as tail from a),
c as (select page_id, rid, coalesce(host, '') as host, regexp_extract(tail, '^[^?#]*') as path, regexp_extract(substr(tail, length(regexp_extract(tail, '^[^?#]*')) + 1), '^\\?([^#]*)', 1) as query from b),
k as (select *, list_sort(list_filter(string_split(query, '&'), lambda x: x <> '' and not regexp_matches(x, '{TRACKING}'))) as kept from c),
d as (select page_id, rid, host, path, regexp_replace(regexp_replace(host, '^www\\.', ''), ':(80|443)$', '') || regexp_replace(path, '/+$', '') || case when len(kept) > 0 then '?' || array_to_string(kept, '&') else '' end as canonical from k),
listed as (select distinct canonical from d where page_id % 50 = 0 and host <> ''),
rules(says, rhost, rpath) as (values {_RULES}),
fits as (select rid, rhost || rpath as rule, says, row_number() over (partition by rid order by length(rhost || rpath) desc) as n
  from d join rules on (host = rhost or ends_with(host, '.' || rhost)) and starts_with(path, rpath))
select page_id, host, path, rule, coalesce(says, case when listed.canonical is not null then 'block' end, 'allow') as verdict
from d left join fits on d.rid = fits.rid and n = 1 left join listed on d.canonical = listed.canonical and d.host <> ''
"""
