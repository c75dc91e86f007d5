"""Near duplicates by fast similarity sketching, banding and exact verification.

Every text's shingle set gets a sketch of WIDTH coordinates; a band is the hash of ROWS of them.  Texts of equal sets are one
class and stand for each other from here on; classes have ids of their own, and a class's text is found again by doc_id and the text's hash.  Classes that share a band meet in a bucket.  First, each bucket's members are held
against its smallest one, on their full sets, and linked ones become one component: in buckets of 8 bands at once, then of 2, leaving out
pairs that are in one component by then.  Documents in buckets of one band that are of several components after that
are settled by their rarest shingles (linked ones share one of as many as a link may lack and one more), in rounds: a few members of
a shingle's bucket, from its small components, are held against the rest and leave, with each round eight times as many.  No bucket is
expanded into all its pairs unless all of them must be known to be unlinked, and none is dropped.

A pair at the threshold of 0.8 misses all 32 bands of 4 with a probability of 5e-8.

Defined results: a null text, and one without words, has the empty set, is linked with nothing and kept; a row with a
null doc_id can't be named: it is linked with nothing, its component is null, and it is kept; rows that repeat a doc_id
share a component, whatever their texts; an empty table gives an empty result; only doc_id and text are read.  Dropping
goes by rows instead: texts of one doc_id are judged each for itself, and rows with a null doc_id like any other.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import textkernel as tk
from .common import passing, rows_of, small, unused, written
from .components import components

BANDS, ROWS = 32, 4
#: Bands that a bucket of the first rounds stands for.
LEVELS = (8, 2)
#: Texts, or pairs of them, that a task takes at least.
TEXTS_A_FILE = 2_000
#: Cells of shingle counts by which shingles are ordered; 8 bytes each.
CELLS = 1 << 18
#: A class of over 1/HEAVY of all rows is looked up by broadcast; there are fewer than HEAVY of them.
HEAVY = 4096


def _sketched(size: int, bands: int, rows: int, lower: bool, slices: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, j, data, at in tk.slices(batch.column("text")):
                hashes, first = tk.word_hashes(data, at, lower)
                values, begin = tk.distinct(*tk.shingles(hashes, first, size))
                n = np.diff(begin)
                keys = tk.bands(tk.fast_sketch(values, begin, bands * rows), rows)
                sums = np.concatenate([[np.uint64(0)], np.cumsum(values)])
                other = np.concatenate([[np.uint64(0)], np.cumsum(tk.mix(values ^ tk.U(0xA5A5A5A5A5A5A5A5)))])
                f1, f2 = (x[begin[1:]] - x[begin[:-1]] for x in (sums, other))
                keys = keys[n > 0]
                offsets = pa.array(np.concatenate([[0], np.cumsum((n > 0) * (bands // slices))]).astype(np.int32))
                parts = [pa.ListArray.from_arrays(offsets, pa.array(np.ascontiguousarray(x).reshape(-1).view(np.int64))) for x in np.split(keys, slices, axis=1)]
                yield pa.RecordBatch.from_arrays(
                    [batch.column("doc_id").slice(i, j - i), batch.column("t").slice(i, j - i), pa.array(n), pa.array(f1.view(np.int64)), pa.array(f2.view(np.int64)), *parts],
                    ["doc_id", "t", "n", "f1", "f2", *_slices(slices)],
                )

    return run


def _slices(slices: int) -> list[str]:
    return ["bands"] if slices == 1 else [f"bands{i}" for i in range(slices)]


def _overlap(size: int, lower: bool):
    """Rows (a, b, ta, tb) to (a, b, both, na, nb), on full sets; a pivot's set is kept while its rows pass."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept: dict = {}
        for batch in batches:
            for i in range(0, batch.num_rows, 256):
                part = batch.slice(i, 256)
                sets = tk.text_sets(part.column("ta"), size, lower)
                b = part.column("b").to_numpy(zero_copy_only=False)
                _, where = np.unique(b, return_index=True)
                new = [w for w in where if b[w] not in kept]
                if len(kept) > 64:
                    kept = {k: v for k, v in kept.items() if k in set(b)}
                kept.update(zip(b[new], tk.text_sets(part.column("tb").take(pa.array(new, pa.int64())), size, lower)))
                both = [len(np.intersect1d(s, kept[k], assume_unique=True)) for s, k in zip(sets, b)]
                yield pa.RecordBatch.from_arrays([part.column("a"), part.column("b"), pa.array(both, pa.int64()), pa.array([len(s) for s in sets], pa.int64()), pa.array([len(kept[k]) for k in b], pa.int64())], ["a", "b", "both", "na", "nb"])

    return run


def _cells(size: int, lower: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(0, batch.num_rows, 256):
                sets = tk.text_sets(batch.column("text").slice(i, 256), size, lower)
                yield pa.RecordBatch.from_arrays([pa.array((np.concatenate(sets) & tk.U(CELLS - 1)).astype(np.int32))], ["cell"])

    return run


def _rarest(counts: np.ndarray, size: int, lower: bool, top: int, bottom: int):
    """Each text's rarest shingles, one more than a linked text may lack; counts by cell order all shingles alike everywhere."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(0, batch.num_rows, 256):
                ids = batch.column("doc_id").slice(i, 256)
                sets = tk.text_sets(batch.column("text").slice(i, 256), size, lower)
                n = np.array([len(x) for x in sets])
                first = [x[np.lexsort((x, counts[x & tk.U(CELLS - 1)]))[: len(x) + -(-len(x) * top // -bottom) + 1]] for x in sets]
                each = np.array([len(x) for x in first])
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(first).view(np.int64)), ids.take(pa.array(np.repeat(np.arange(len(n)), each))), pa.array(np.repeat(n, each)), pa.array(np.concatenate([np.arange(k) for k in each]))], ["key", "doc_id", "n", "i"])

    return run


def with_class(rows: DataFrame, classes: DataFrame, total: int) -> DataFrame:
    """rows joined to classes by (f1, f2); classes has n_rows.  Very large classes are looked up by broadcast."""
    heavy = F.col("n_rows") * HEAVY > total
    hot = F.broadcast(classes.where(heavy).withColumnRenamed("rep", "hot").drop("n_rows"))
    both = rows.join(hot, ["f1", "f2"], "left")
    rest = both.where(F.col("hot").isNull()).drop("hot").join(classes.where(~heavy).drop("n_rows"), ["f1", "f2"], "left")
    return both.where(F.col("hot").isNotNull()).withColumnRenamed("hot", "rep").unionByName(rest)


def _clustered(docs: DataFrame, *how) -> tuple[DataFrame, DataFrame]:
    """What `_linked` gives; its other tables go."""
    with passing(docs.sparkSession) as keep:
        placed, linked = _linked(docs, *how)
        return keep(placed), keep(linked)


def _classes(named: DataFrame, most: int) -> DataFrame:
    """f1, f2, rep, own, rep_doc, rep_t, n_rows of the classes of named rows."""
    grouped = named.groupBy("f1", "f2").agg(F.min(F.struct(F.col("doc_id").isNull().alias("unnamed"), "doc_id", "t")).alias("own"), F.count(F.lit(1)).alias("n_rows"))
    return written(grouped.select("f1", "f2", F.monotonically_increasing_id().alias("rep"), "own", F.col("own.doc_id").alias("rep_doc"), F.col("own.t").alias("rep_t"), "n_rows"), "near-classes", most)


def _met(named: DataFrame, classes: DataFrame, total: int, bands: int, slices: int) -> DataFrame:
    """key, doc_id, n, band of the classes that share a band with others, doc_id being the class; named has a column for each slice of bands.

    One slice goes over the network after another, and with a number of 64 bits for its class instead of a join that would send all bands.  Copies in
    very large classes are left out by broadcast, so that no bucket is as large as a class."""
    heavy = classes.where(F.col("n_rows") * HEAVY > total).select("f1", "f2", "rep_doc", "rep_t")
    first = F.col("rep_t").isNull() | F.col("doc_id").eqNullSafe(F.col("rep_doc")) & (F.col("t") == F.col("rep_t"))
    thin = named.join(F.broadcast(heavy), ["f1", "f2"], "left").where(first)
    width, parts = bands // slices, None
    for i, column in enumerate(_slices(slices)):
        each = thin.select("f1", "f2", "n", F.posexplode(column).alias("at", "key"))
        shared = each.groupBy("key").agg(F.min("f1").alias("lo"), F.max("f1").alias("hi")).where("lo <> hi").select("key")
        shared = written(shared, "near-buckets", total * width // 2)
        own = written(each.join(small(shared.hint("shuffle_hash"), table=shared), "key").select("f1", "f2", "n", (F.col("at") + i * width).alias("band"), "key").distinct(), "near-met", total * width)
        parts = own if parts is None else parts.unionByName(own)
    return parts.join(classes.select("f1", "f2", F.col("rep").alias("doc_id")), ["f1", "f2"]).select("key", "doc_id", "n", "band")


def _linked(docs: DataFrame, threshold: tuple[int, int], size: int, bands: int, rows: int, lower: bool, unnamed: bool, slices: int = 1) -> tuple[DataFrame, DataFrame]:
    """(placed, linked): doc_id, t, n, rep, own for every row, and node, component, own for the classes that have links.

    t is the text's hash, rep the row's class, and own the class's first row (unnamed, doc_id, t).  Rows without words have no class; with
    unnamed, rows with a null doc_id have one."""
    top, bottom = threshold
    texts = docs.select("doc_id", "text", F.xxhash64("text").alias("t"))
    kind = dict(texts.dtypes)["doc_id"]
    columns = ", ".join(f"{c} array<long>" for c in _slices(slices))
    named_of = lambda df: df.where("n > 0") if unnamed else df.where("n > 0 and doc_id is not null")
    with passing(docs.sparkSession) as keep:
        sketched = written(texts.mapInArrow(_sketched(size, bands, rows, lower, slices), f"doc_id {kind}, t long, n long, f1 long, f2 long, {columns}"), "near-sketches")
        named, total = named_of(sketched), rows_of(sketched)
        classes = keep(_classes(named, total))
        if slices > 1:  # bands go as soon as it is known which classes share them
            met = keep(written(_met(named, classes, total, bands, slices), "near-met", total * bands))
            sketched = written(sketched.select("doc_id", "t", "n", "f1", "f2"), "near-sets")
        keep(sketched)
    n_classes = rows_of(classes)
    lookup = classes.select("f1", "f2", F.struct("rep", "own").alias("rep"), "n_rows")

    # a class's representative carries its bands; buckets of one class are done
    firsts = classes.select("f1", "f2", F.col("rep").alias("node"), "rep_doc", "rep_t")
    is_first = F.col("doc_id").eqNullSafe(F.col("rep_doc")) & (F.col("t") == F.col("rep_t"))
    if slices > 1:
        members = met
    else:
        reps = named.join(firsts, ["f1", "f2"]).where(is_first).select(F.col("node").alias("doc_id"), "n", "bands").dropDuplicates(["doc_id"])
        rows_ = reps.select("doc_id", "n", F.explode("bands").alias("key"))
        shared = written(rows_.groupBy("key").agg(F.count(F.lit(1)).alias("m")).where("m > 1"), "near-buckets", n_classes * bands // 2)
        members = written(rows_.join(small(shared.select("key"), rows_of(shared)), "key").select("key", "doc_id", "n"), "near-members", n_classes * bands)
    ids = written(members.select(F.col("doc_id").alias("id")).distinct(), "near-ids", n_classes)
    n_ids = rows_of(ids)
    if slices == 1:
        banded = written(reps.join(small(ids), F.col("doc_id") == F.col("id"), "left_semi").select("doc_id", "n", "bands"), "near-bands", n_ids)

    def keys_of(level: int) -> DataFrame:
        """doc_id, n, key: buckets of so many bands at once.  Where bands are gone, classes that share all bands of a bucket do."""
        if slices == 1:
            return banded.select("doc_id", "n", F.explode(F.transform(F.sequence(F.lit(0), F.lit(bands // level - 1)), lambda i: F.xxhash64(i, F.slice("bands", i * level + 1, level)))).alias("key"))
        group = members.groupBy("doc_id", "n", F.expr(f"band div {level}").alias("g")).agg(F.bit_xor(F.xxhash64("band", "key")).alias("x"), F.count(F.lit(1)).alias("m"))
        return group.where(F.col("m") == level).select("doc_id", "n", F.xxhash64("g", "x").alias("key"))

    wanted = written(classes.join(small(ids), F.col("rep") == F.col("id"), "left_semi").select(F.col("rep").alias("node"), "rep_doc", "rep_t"), "near-wanted", n_ids)
    cand = written(texts.join(small(wanted), is_first).select(F.col("node").alias("doc_id"), "text").dropDuplicates(["doc_id"]), "near-texts", n_ids, TEXTS_A_FILE)
    # from here on, doc_id is a class's id
    kind = "long"

    def verified(pairs: DataFrame) -> DataFrame:
        """The linked ones of pairs (a, b), a written table."""
        one = cand.select(F.col("doc_id").alias("a"), F.col("text").alias("ta"))
        two = cand.select(F.col("doc_id").alias("b"), F.col("text").alias("tb"))
        rows2 = pairs.join(one, "a").join(two, "b").select("a", "b", "ta", "tb")
        found = rows2.mapInArrow(_overlap(size, lower), f"a {kind}, b {kind}, both long, na long, nb long")
        return written(found.where(F.col("both") * bottom >= (F.col("na") + F.col("nb") - F.col("both")) * top).select("a", "b"), "near-links", rows_of(pairs), TEXTS_A_FILE)

    def alike(x: str, y: str) -> F.Column:
        """Sizes that leave a link possible."""
        return F.least(x, y) * bottom >= F.greatest(x, y) * top

    links = tested = found = None
    n_links = 0

    def tell(pairs: DataFrame, most: int | None) -> None:
        """Verify pairs (a, b), a > b, that aren't tested or in one component yet, and bring the components up to date; most: their number at most."""
        nonlocal links, tested, found, n_links
        if tested is not None:
            label = small(found)
            ca, cb = (label.select(F.col("node").alias(x), F.col("component").alias(f"c{x}")) for x in "ab")
            apart = F.coalesce("ca", "a") != F.coalesce("cb", "b")
            pairs = pairs.join(ca, "a", "left").join(cb, "b", "left").where(apart).select("a", "b").join(tested, ["a", "b"], "left_anti")
        pairs = written(pairs, "near-pairs", most)
        new = verified(pairs)
        n_links += rows_of(new)
        links = new if links is None else links.unionByName(new)
        tested = pairs if tested is None else tested.unionByName(pairs)
        if found is None or rows_of(new):
            found = written(components(links, n_links), "near-components", 2 * n_links)

    # stars in buckets of several bands at once, then of fewer: what is most alike is linked first, and what is one component is not compared again
    for level in LEVELS:
        if bands % level:
            continue
        keys = keys_of(level)
        pivot = keys.groupBy("key").agg(F.min(F.struct("doc_id", "n")).alias("p"), F.count(F.lit(1)).alias("m")).where("m > 1").select("key", F.col("p.doc_id").alias("b"), F.col("p.n").alias("bn"))
        star = keys.join(small(written(pivot, "near-pivots", n_ids * (bands // level))), "key").where((F.col("doc_id") > F.col("b")) & alike("n", "bn"))
        tell(star.select(F.col("doc_id").alias("a"), "b").distinct(), n_ids * (bands // level))

    def mixed(members: DataFrame) -> DataFrame:
        """The members (key, doc_id, n, .., c) of buckets that are of several components; members is a written table."""
        labelled = members.join(small(found), F.col("doc_id") == F.col("node"), "left").select(*members.columns, F.coalesce("component", "doc_id").alias("c"))
        several = labelled.groupBy("key").agg(F.min("c").alias("c0"), F.max("c").alias("c1")).where("c0 <> c1").select("key")
        return written(labelled.join(small(written(several, "near-mixed", rows_of(members))), "key"), "near-open", rows_of(members))

    # documents in buckets of several components meet again, by the rarest shingles of each: linked ones share one of these
    left = written(mixed(members).select(F.col("doc_id").alias("id")).distinct(), "near-left", n_ids)
    texts_left = cand.join(small(left), F.col("doc_id") == F.col("id"), "left_semi").select("doc_id", "text")
    counts = np.zeros(CELLS, dtype=np.int64)
    counted = texts_left.mapInArrow(_cells(size, lower), "cell int").groupBy("cell").agg(F.count(F.lit(1)).alias("m")).toArrow()  # CELLS rows at most
    counts[counted.column("cell").to_numpy()] = counted.column("m").to_numpy()
    rare = written(texts_left.mapInArrow(_rarest(counts, size, lower, top, bottom), f"key long, doc_id {kind}, n long, i long"), "near-rarest")
    met = rare.groupBy("key").agg(F.count(F.lit(1)).alias("m")).where("m > 1").select("key")
    members = written(rare.join(small(written(met, "near-buckets", rows_of(rare))), "key").select("key", "doc_id", "n", "i"), "near-members", rows_of(rare))

    # pivots come from a bucket's small components; they are held against the rest and leave
    pivots = 512
    while True:
        open_ = mixed(members)
        if not rows_of(open_):
            break
        part = open_.groupBy("key", "c").agg(F.count(F.lit(1)).alias("m"))
        order = Window.partitionBy("key").orderBy("m", "c")
        upto = part.withColumn("before", F.sum("m").over(order) - F.col("m")).where(F.col("before") < pivots).select("key", "c")
        chosen = open_.join(upto, ["key", "c"]).withColumn("k", F.row_number().over(Window.partitionBy("key").orderBy("doc_id"))).where(F.col("k") <= pivots)
        chosen = written(chosen.select("key", F.col("doc_id").alias("b"), F.col("n").alias("bn"), F.col("i").alias("bi"), F.col("c").alias("bc")), "near-pivots", rows_of(open_))
        # a linked pair's first common shingle leaves enough behind it in both
        enough = F.least(F.col("n") - F.col("i"), F.col("bn") - F.col("bi")) * (top + bottom) >= (F.col("n") + F.col("bn")) * top
        pairs = open_.join(small(chosen), "key").where((F.col("c") != F.col("bc")) & alike("n", "bn") & enough)
        tell(pairs.select(F.greatest("doc_id", "b").alias("a"), F.least("doc_id", "b").alias("b")).distinct(), None)
        members = written(open_.join(small(chosen.select("key", F.col("b").alias("doc_id")), rows_of(chosen)), ["key", "doc_id"], "left_anti").select("key", "doc_id", "n", "i"), "near-members", rows_of(open_))
        pivots *= 8

    unplaced = sketched.select("doc_id", "t", "n", "f1", "f2")
    if not unnamed:
        nameless = unplaced.where("doc_id is null").withColumn("rep", F.lit(None).cast(lookup.schema["rep"].dataType))
        unplaced = unplaced.where("doc_id is not null")
    placed = with_class(unplaced, lookup, total)
    if not unnamed:
        placed = placed.unionByName(nameless)
    linked = found.join(classes.select("rep", "own"), F.col("node") == F.col("rep")).select("node", "component", "own")
    return written(placed.select("doc_id", "t", "n", "rep.rep", "rep.own"), "near-placed", total), written(linked, "near-linked", rows_of(found))


def near_duplicates(docs: DataFrame, threshold: tuple[int, int] = (80, 100), size: int = 5, bands: int = BANDS, rows: int = ROWS, lower: bool = True, slices: int = 1) -> DataFrame:
    """doc_id, n_shingles, component_id, kept; threshold: links have intersection / union of at least this fraction.

    slices: bands are dealt out in so many parts, one after another; for short texts, whose bands are longer than themselves."""
    placed, linked = _clustered(docs, threshold, size, bands, rows, lower, False, slices)
    # a doc_id of several texts ties their classes
    several = placed.where("doc_id is not null").groupBy("doc_id").agg(F.min("rep").alias("b"), F.max("rep").alias("last"), F.count(F.lit(1)).alias("m"), F.count("rep").alias("with"))
    several = written(several.where("b < last or (with > 0 and with < m)").select(F.col("doc_id").alias("_id"), "b"), "near-several", rows_of(placed))
    tied = rows_of(several) > 0
    if tied:
        here = written(placed.join(small(several), F.col("doc_id") == F.col("_id")).where("rep is not null").select("rep", "b", "own").distinct(), "near-ties", rows_of(placed))
        edges = linked.select(F.col("node").alias("a"), F.col("component").alias("b")).unionByName(here.where("rep > b").select(F.col("rep").alias("a"), "b"))
        known = linked.select("node", "own").unionByName(here.select(F.col("rep").alias("node"), "own")).distinct()
        n = rows_of(linked) + rows_of(here)
        linked = written(components(edges, n).join(known, "node").select("node", "component", "own"), "near-linked", 2 * n)
    least = written(linked.groupBy("component").agg(F.min("own.doc_id").alias("component_id")), "near-least", rows_of(linked))
    label = written(linked.join(small(least), "component").select("node", "component_id"), "near-labels", rows_of(linked))
    component = F.coalesce("component_id", "own.doc_id", "doc_id")
    out = placed.join(small(label), F.col("rep") == F.col("node"), "left").select("doc_id", F.col("n").alias("n_shingles"), component.alias("component_id"))
    if tied:
        # rows without words go with the others of their doc_id
        other = out.join(small(several), F.col("doc_id") == F.col("_id")).groupBy("_id").agg(F.min("component_id").alias("_c"))
        out = out.join(small(written(other, "near-tied", rows_of(several))), F.col("doc_id") == F.col("_id"), "left").select("doc_id", "n_shingles", F.coalesce("_c", "component_id").alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def drop_near_duplicates(docs: DataFrame, threshold: tuple[int, int] = (80, 100), size: int = 5, bands: int = BANDS, rows: int = ROWS, lower: bool = True) -> DataFrame:
    """docs with one row of each component of texts, that of the least doc_id (null ones last); of rows that repeat doc_id and text, one stays."""
    placed, linked = _clustered(docs, threshold, size, bands, rows, lower, True)
    first = written(linked.groupBy("component").agg(F.min("own").alias("first")), "near-firsts", rows_of(linked))
    label = written(linked.join(small(first), "component").select("node", "first"), "near-labels", rows_of(linked))
    stays = F.coalesce("first", "own")
    behind = ~(F.col("doc_id").eqNullSafe(stays["doc_id"]) & (F.col("t") == stays["t"]))
    # docs may have columns of any name
    id_, t = unused(docs, "id", "t")
    named = F.col("doc_id").alias(id_), F.col("t").alias(t)
    here = F.col("doc_id").eqNullSafe(F.col(id_)) & (F.xxhash64("text") == F.col(t))
    gone = placed.where("rep is not null").join(small(label), F.col("rep") == F.col("node"), "left").where(behind).select(*named).distinct()
    left = docs.join(small(written(gone, "near-gone", rows_of(placed))), here, "left_anti")
    twice = placed.where("doc_id is not null or n > 0").groupBy("doc_id", "t").agg(F.count(F.lit(1)).alias("m")).where("m > 1")
    twice = written(twice.select(*named), "near-twice", rows_of(placed))
    if not rows_of(twice):
        return left
    one = left.join(small(twice), here, "left_semi").dropDuplicates(["doc_id", "text"])
    return left.join(small(twice), here, "left_anti").unionByName(one)


ORACLE = """
with recursive w as (select doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') as w from documents),
s as (select doc_id, case when len(w) >= 2 then list_distinct(list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1])) when len(w) = 1 then w else [] end as s from w),
n as (select doc_id, len(s)::bigint as n, hash(list_sort(s)) as h, list_sort(s) as s from s),
rep as (select min(doc_id) as doc_id, any_value(n) as n, any_value(s) as s from n where n > 0 group by list_sort(s)),
u as (select doc_id, n, unnest(s) as x from rep),
pairs as (select a.doc_id as a, b.doc_id as b from u a join u b on a.x = b.x and a.doc_id < b.doc_id and 100 * least(a.n, b.n) >= 80 * greatest(a.n, b.n) group by a.doc_id, b.doc_id, a.n, b.n having 100 * count(*) >= 80 * (a.n + b.n - count(*))),
copies as (select r.doc_id as a, d.doc_id as b from n d join rep r on d.s = r.s and d.doc_id <> r.doc_id),
e as (select a, b from pairs union select b, a from pairs union select a, b from copies union select b, a from copies),
reach(x, y) as (select doc_id, doc_id from n union select reach.x, e.b from reach join e on reach.y = e.a)
select n.doc_id, n.n as n_shingles, min(y) as component_id, n.doc_id = min(y) as kept from n join reach on n.doc_id = reach.x group by n.doc_id, n.n
"""
