"""Substring deduplication by paragraph MinHash banding.

A paragraph is a line of SHINGLE words or more, so that it has a whole shingle.  Paragraphs are sketched, banded, joined where they collide, verified by the
exact Jaccard similarity of their five-word shingles and clustered by components (the machinery of near_dup and
its 32 bands of 4: a pair at the threshold of 0.8 shares no band with a probability of 5e-8).  In each component the paragraph that comes first stays.

A passage may also stand inside longer lines, at other places in each.  So the sequence of words is also cut into overlapping pieces
of LEAST words that start at content-defined places: the least hash of every AHEAD starts in a row.  A
passage of LEAST + AHEAD - 1 words or more has an equal piece wherever it stands; equal pieces, of one document or of several, are grouped by their hash, the
first by document and place stays, those that don't overlap it are repeats, and adjoining ones become one span.

Defined results: a null text, a text without a long paragraph or passage, and rows with a null doc_id have no rows here; rows
that repeat doc_id and text are one document; an empty table gives an empty result; only doc_id and text are read; very
long texts are taken whole.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import textkernel as tk
from .common import freed, passing, rows_of, small, written
from .near_dup import near_duplicates

SHINGLE = 5
#: Parts in which bands are dealt out: a paragraph's 32 are longer than itself.
SLICES = 8
LEAST, AHEAD = 24, 26

_PIECES = "doc_id long, start long, end long, c long"


def pieces(data: np.ndarray, at: np.ndarray, least: int = LEAST, ahead: int = AHEAD) -> tuple[np.ndarray, ...]:
    """(text, start, end, hash) of the pieces; places are bytes in the slice."""
    starts, ends, first = tk.word_bounds(data, at)
    hashes, _ = tk.word_hashes(data, at)
    n = len(hashes)
    if n < least:
        return tuple(np.zeros(0, np.int64) for _ in range(3)) + (np.zeros(0, np.uint64),)
    up, down = tk.powers(n + 1)
    sums = np.concatenate([[tk.U(0)], np.cumsum(hashes * up[:n])])
    p = np.arange(n - least + 1)
    content = tk.mix((sums[p + least] - sums[p]) * down[p])
    # the order of starts depends on the words that follow them only
    rank = (content & ~tk.U((1 << 24) - 1)) if n < 1 << 24 else content
    chosen = np.zeros(n, dtype=bool)
    for a, b in zip(first[:-1], first[1:]):
        m = b - least + 1 - a
        if m <= 0:
            continue
        own = rank[a : a + m]
        if m <= ahead:
            chosen[a + int(own.argmin())] = True
            continue
        view = np.lib.stride_tricks.sliding_window_view(own, ahead)
        chosen[a + np.arange(len(view)) + view.argmin(axis=1)] = True
    at_ = np.flatnonzero(chosen)
    return np.searchsorted(at, starts[at_], side="right") - 1, starts[at_], ends[at_ + least - 1], content[at_]


def _pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        ids = batch.column("doc_id").to_numpy(zero_copy_only=False)
        for i, _, data, at in tk.slices(batch.column("text")):
            text, start, end, c = pieces(data, at)
            yield pa.RecordBatch.from_arrays([pa.array(ids[i + text], pa.int64()), pa.array(start - at[text]), pa.array(end - at[text]), pa.array(c.view(np.int64))], ["doc_id", "start", "end", "c"])


def paragraphs(docs: DataFrame) -> DataFrame:
    """doc_id, line, text, words: lines of SHINGLE words or more."""
    lines = docs.select("doc_id", F.split("text", "\n").alias("lines"))
    each = lines.select("doc_id", F.posexplode("lines").alias("line", "text"))
    return each.withColumn("words", F.size(F.filter(F.split("text", "[\\x20\\x09-\\x0D]+"), lambda w: w != "")).cast("long")).where(F.col("words") >= SHINGLE)


def repeated_passages(docs: DataFrame) -> DataFrame:
    """doc_id, kind, line, start, end, n_words, kept_doc_id: every paragraph and span that repeats an earlier one.

    kind `paragraph`: line is its number, from 0, and kept_doc_id has the one that stays (it may be the same document).  kind `passage`: start and end are bytes, and
    the document of the first occurrence of its first piece is kept_doc_id (it may be the same document)."""
    with freed(docs.sparkSession):
        return _repeated(docs)


def _repeated(docs: DataFrame) -> DataFrame:
    texts = docs.where("doc_id is not null and text is not null").select(F.col("doc_id").cast("long").alias("doc_id"), "text")

    with passing(docs.sparkSession) as keep:
        lines = written(paragraphs(texts).withColumn("id", F.monotonically_increasing_id()), "paragraphs")
        near = near_duplicates(lines.select(F.col("id").alias("doc_id"), "text"), size=SHINGLE, slices=SLICES)
        classes = near.select(F.col("doc_id").alias("id"), F.col("component_id").alias("class"))
        placed = keep(written(lines.select("id", "doc_id", "line", "words").join(classes, "id"), "paragraph-classes", rows_of(lines)))
    first = placed.groupBy("class").agg(F.min(F.struct("doc_id", "line")).alias("first"), F.count(F.lit(1)).alias("m")).where("m > 1").select("class", "first")
    behind = (F.col("doc_id") != F.col("first.doc_id")) | (F.col("line") != F.col("first.line"))
    gone = placed.join(small(written(first, "paragraph-firsts", rows_of(placed) // 2)), "class").where(behind).select("doc_id", "line", "words", F.col("first.doc_id").alias("kept_doc_id")).distinct()
    gone = gone.select("doc_id", F.lit("paragraph").alias("kind"), "line", F.lit(None).cast("long").alias("start"), F.lit(None).cast("long").alias("end"), F.col("words").alias("n_words"), "kept_doc_id")

    with passing(docs.sparkSession) as keep:
        every = written(texts.mapInArrow(_pieces, _PIECES), "pieces")
        # most pieces are there once: these are done before their places are sent
        met = written(every.groupBy("c").agg(F.count(F.lit(1)).alias("m")).where("m > 1").select("c"), "met-pieces", rows_of(every) // 2)
        found = keep(written(every.join(small(met.hint("shuffle_hash"), table=met), "c").select(*every.columns), "several-pieces", rows_of(every)))
    # a piece that overlaps the kept one in its document is no repeat: words that run on equal would be repeats of themselves
    place = F.struct("doc_id", "start", "end")
    shared = found.groupBy("c").agg(F.min(place).alias("kept"), F.max(place).alias("last"))
    shared = shared.where("kept.doc_id < last.doc_id or kept.end <= last.start").select("c", F.col("kept.doc_id").alias("kept_doc_id"), F.col("kept.end").alias("kept_end"))
    again = found.join(small(written(shared, "shared-pieces", rows_of(found) // 2)), "c").where("doc_id > kept_doc_id or start >= kept_end").select("doc_id", "start", "end", "kept_doc_id").distinct()
    inside = Window.partitionBy("doc_id").orderBy("start")
    upto = F.max("end").over(inside.rowsBetween(Window.unboundedPreceding, -1))
    marked = again.withColumn("new", F.when(F.col("start") <= upto, 0).otherwise(1)).withColumn("span", F.sum("new").over(inside))
    spans = marked.groupBy("doc_id", "span").agg(F.min("start").alias("start"), F.max("end").alias("end"), F.min_by("kept_doc_id", "start").alias("kept_doc_id"), F.count(F.lit(1)).alias("n"))
    spans = spans.select("doc_id", F.lit("passage").alias("kind"), F.lit(None).cast("int").alias("line"), "start", "end", F.lit(None).cast("long").alias("n_words"), "kept_doc_id")
    return gone.unionByName(spans)
