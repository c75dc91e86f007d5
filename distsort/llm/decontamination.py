"""Benchmark decontamination by size-partitioned MinHash containment search, with DataFrame functions only.

A test item is a short set of word shingles, a document a long one; the share of the item that the document holds can't be seen from
their Jaccard similarity.  So the item is sketched, and the document's part of the sketch is what of it the document holds.  A sketch are the least of
an item's shingles, by the number of items that have the shingle, in powers of two, and then by hash, so that phrases which many items share are in
few sketches.  Items are partitioned by their set size; each partition has its own sketch length and asks for its own overlap: an item of q
shingles that has `share` of them in a document lacks at most (1 - share) * q, so a sketch that is SLACK times as long and one more must meet but for so many values.
Documents are scanned once, their shingle hashes looked up in the sketches, the values that meet are counted for each pair, and pairs with the overlap of
the item's partition are verified on the full shingle sets, as texts.

Words are runs of letters and digits, lower-cased; shingles are five words, or the whole item if it has fewer.

Defined results: a null or empty text, or one without letters and digits, contains nothing and is contained nowhere; rows
with a null doc_id or item_id are not paired; items that repeat an id count each, and the pair has the larger share;
an empty table gives an empty result; only doc_id and text, item_id and text are read.  Dropping goes by texts, so that rows with a null doc_id
are judged as any other.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import rows_of, small, unused, written

GAPS = "[^\\p{L}\\p{N}]+"
SHARE = (80, 100)
WORDS = 5
#: Values of a sketch for each one that a match may lack.
SLACK = 3


def tokens(text: Column) -> Column:
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), GAPS), lambda w: w != "")


def shingle_hashes(hashes: str, n: Column, size: int) -> Column:
    """64-bit hashes of all runs of `size` words, of an array of word hashes."""
    run = lambda i: F.xxhash64(F.lit(size), *[F.get(F.col(hashes), i + k) for k in range(size)])
    return F.when(n >= size, F.transform(F.sequence(F.lit(0), n - size), run)).otherwise(F.array().cast("array<long>"))


def shingle_texts(toks: str, size: Column) -> Column:
    """The distinct runs of `size` words as texts."""
    t = F.col(toks)
    run = lambda i: F.array_join(F.slice(t, i, size), " ")
    return F.array_distinct(F.when((F.size(t) >= size) & (size > 0), F.transform(F.sequence(F.lit(1), F.size(t) - size + 1), run)).otherwise(F.array().cast("array<string>")))


def item_sketches(items: DataFrame, share: tuple[int, int] = SHARE, words: int = WORDS) -> tuple[DataFrame, DataFrame]:
    """(sets, sketches): item, item_id, length, texts; and item, h, overlap (values that must meet), one row for each sketch value.  item names a row."""
    base = items.where("item_id is not null").select("item_id", tokens(F.col("text")).alias("toks"))
    base = base.withColumn("length", F.least(F.size("toks"), F.lit(words))).where("length > 0")
    base = base.withColumn("hashed", F.transform("toks", lambda w: F.xxhash64(w))).withColumn("texts", shingle_texts("toks", F.col("length")))
    hashes = F.array().cast("array<long>")
    for size in range(words, 0, -1):
        hashes = F.when(F.col("length") == size, shingle_hashes("hashed", F.size("hashed"), size)).otherwise(hashes)
    sets = base.select(F.monotonically_increasing_id().alias("item"), "item_id", "length", "texts", F.array_distinct(hashes).alias("hashes"))
    sets = written(sets, "items")
    each = sets.select("item", F.size("hashes").alias("q"), F.explode("hashes").alias("h"))
    common = written(each.groupBy("h").agg(F.count(F.lit(1)).alias("m")).where("m > 1").select("h", F.floor(F.log2(F.col("m").cast("double"))).cast("int").alias("spread")), "item-common")
    ranked = each.join(small(common), "h", "left").select("item", "q", F.struct(F.coalesce("spread", F.lit(0)).alias("spread"), "h").alias("v"))
    ordered = ranked.groupBy("item", "q").agg(F.array_sort(F.collect_list("v")).alias("v"))  # the shingles of one item
    # the partition of q holds sizes from 2**p to 2**(p + 1) - 1, and sketches as its largest size needs
    largest = F.pow(F.lit(2), F.floor(F.log2(F.col("q").cast("double"))) + 1) - 1
    lacking = lambda n: F.floor(n * (share[1] - share[0]) / share[1])
    width = F.least(F.col("q"), (lacking(largest) * SLACK + 1).cast("int"))
    sketches = ordered.select("item", (width - lacking(F.col("q"))).cast("long").alias("overlap"), F.explode(F.slice("v", F.lit(1), width)).alias("v"))
    return sets, written(sketches.select("item", "overlap", "v.h"), "item-sketches")


def _held(docs: DataFrame, items: DataFrame, share: tuple[int, int], words: int) -> DataFrame:
    """key, item_id, n_item_shingles, n_shared, containment of the pairs with at least this share; docs: key and text, of which rows that repeat a key count each."""
    sets, sketches = item_sketches(items, share, words)
    lengths = [r[0] for r in sets.select("length").distinct().collect()]  # at most `words` values
    hashed = docs.select("key", tokens(F.col("text")).alias("toks"))
    hashed = hashed.select("key", F.transform("toks", lambda w: F.xxhash64(w)).alias("hashed"))
    runs = F.concat(F.array().cast("array<long>"), *[shingle_hashes("hashed", F.size("hashed"), n) for n in lengths])
    values = written(sketches.select("h").distinct(), "sketch-values", rows_of(sketches))
    met = written(hashed.select("key", F.explode(F.array_distinct(runs)).alias("h")).join(small(values), "h", "left_semi").distinct(), "met")
    counted = met.join(small(sketches), "h").groupBy("key", "item").agg(F.count(F.lit(1)).alias("m"), F.first("overlap").alias("overlap"))
    pairs = written(counted.where("m >= overlap").select("key", "item"), "item-pairs")
    keys = written(pairs.select(F.col("key").alias("k")).distinct(), "met-keys", rows_of(pairs))
    texts = docs.join(small(keys), F.col("key") == F.col("k"), "left_semi").select("key", tokens(F.col("text")).alias("toks"))
    wanted = pairs.join(small(sets.select("item", "item_id", "length", "texts"), table=sets), "item")
    both = texts.join(wanted, "key").withColumn("own", shingle_texts("toks", F.col("length")))
    size, shared = F.size("texts").cast("long"), F.size(F.array_intersect("own", "texts")).cast("long")
    found = both.select("key", "item_id", size.alias("n_item_shingles"), shared.alias("n_shared")).where(F.col("n_shared") * share[1] >= F.col("n_item_shingles") * share[0])
    best = found.groupBy("key", "item_id").agg(F.max(F.struct((F.col("n_shared") / F.col("n_item_shingles")).alias("containment"), "n_item_shingles", "n_shared")).alias("b"))
    return best.select("key", "item_id", "b.n_item_shingles", "b.n_shared", "b.containment")


def contained_items(docs: DataFrame, items: DataFrame, share: tuple[int, int] = SHARE, words: int = WORDS) -> DataFrame:
    """doc_id, item_id, n_item_shingles, n_shared, containment, for every pair with at least this share."""
    return _held(docs.where("doc_id is not null").select(F.col("doc_id").alias("key"), "text"), items, share, words).withColumnRenamed("key", "doc_id")


def drop_contaminated(docs: DataFrame, items: DataFrame, share: tuple[int, int] = SHARE, words: int = WORDS) -> DataFrame:
    """docs without the rows that contain a test item."""
    (digest,) = unused(docs, "digest")
    gone = _held(docs.where("text is not null").select(F.md5("text").alias("key"), "text"), items, share, words).select(F.col("key").alias(digest)).distinct()
    return docs.join(small(written(gone, "contaminated")), F.md5(F.coalesce("text", F.lit(""))) == F.col(digest), "left_anti")


_TOKENS = "list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[^\\p{L}\\p{N}]+'), lambda w: w <> '')"
ORACLE = f"""
with i as (select item_id, {_TOKENS} as t from benchmark),
il as (select item_id, t, least(len(t), {WORDS}) as k from i where len(t) > 0),
ish as (select distinct item_id, k, array_to_string(t[j:j + k - 1], ' ') as s from (select item_id, t, k, unnest(range(1, len(t) - k + 2)) as j from il)),
n as (select item_id, count(*) as n from ish group by item_id),
d as (select doc_id, {_TOKENS} as t from documents),
k as (select distinct k from il),
dsh as (select distinct doc_id, k, array_to_string(t[j:j + k - 1], ' ') as s from (select doc_id, t, k, unnest(range(1, len(t) - k + 2)) as j from d, k where len(t) >= k))
select doc_id, ish.item_id, n as n_item_shingles, count(*) as n_shared, count(*) / n as containment
from dsh join ish on dsh.s = ish.s and dsh.k = ish.k join n on n.item_id = ish.item_id
group by doc_id, ish.item_id, n having 100 * count(*) >= 80 * n
"""
