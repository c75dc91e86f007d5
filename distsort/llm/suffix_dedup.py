"""Exact repeats of LENGTH bytes, by bucket-pointer refinement over sampled suffixes.

A byte is removed if a string of LENGTH bytes covers it that also starts earlier (smaller doc_id, or earlier in the
document).  Every string holds one anchor: the start of its least q-gram by hash, the leftmost of equals.  Equal
strings have their anchors at the same place, so only suffixes that start in front of anchors of one q-gram can share a
string: these q-grams are the initial buckets.  An anchor serves a run of consecutive starts; the bytes of all their strings are its
context.

1. Each task finds the anchors of its texts, and settles what it sees itself: of equal contexts all but the first are repeats.
2. Anchors are dealt by q-gram.  Of equal contexts all but the first are repeats; a q-gram with one context is done; the
   first ones of q-grams with several contexts stay open.
3. Open contexts are cut from their texts and dealt by q-gram.  Within a task, their suffixes fall into buckets by
   their first 8 bytes, and buckets that still hold several are refined by sorting on the bucket pointers of later offsets.  A round takes the
   buckets in several parts, and every part's new pointers are used by the parts after it, so that depths grow faster than they double.  Neighbours in
   the order that results are compared byte by byte.
   A q-gram with over HOT open contexts is refined by longer ones first: strings whose starts lie in the same PIECE starts before the anchor
   share length - PIECE + 1 bytes, and are dealt by these.  Where such a piece is still shared by over HOT, its strings are.
4. The runs of repeated starts of each document become removed spans.

Equality of whole contexts is that of two 64-bit hashes of different make; everything else is compared byte by byte.

Defined results: a null text is empty; documents of under LENGTH bytes lose nothing; a null doc_id comes after all
others; rows that repeat doc_id and text are one document and get one answer each, rows that repeat only doc_id are ordered by a hash of their text;
an empty table gives an empty result; only doc_id and text are read; a very long text is taken in pieces.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textkernel as tk
from .common import passing, small, written

LENGTH, GRAM = 100, 32
#: Open contexts of one q-gram from which on longer ones are taken, and how many starts share one of these.
HOT, PIECE = 1 << 14, 18
#: Bytes of contexts that are refined at a time, unless one q-gram has more, and the parts of a round.
CHUNK, PARTS = 1 << 19, 4
#: Runs or spans, over all documents, up to which their lists are broadcast (40 bytes each); beyond it the texts are dealt out to meet them.
LISTED = 3_000_000
#: Contexts that a task remembers to settle repeats by itself.
REMEMBERED = 1 << 16
_POSITION = tk.U((1 << 22) - 1)
_LAST = (1 << 63) - 1


def anchors(data: np.ndarray, at: np.ndarray, length: int = LENGTH, gram: int = GRAM) -> tuple[np.ndarray, ...]:
    """(text, anchor, first start, last start, q-gram hash, two context hashes) of all anchors; at most 2**22 bytes at a time."""
    n = len(data)
    if n < length:
        return tuple(np.zeros(0, t) for t in (np.int64, np.int64, np.int64, np.int64, np.uint64, np.uint64, np.uint64))
    up, down = tk.powers(n + 1)
    sums = np.zeros(n + 1, dtype=np.uint64)
    np.cumsum(tk._BYTE[data] * up[:n], out=sums[1:])
    grams = tk.mix((sums[gram:] - sums[:-gram]) * down[: n - gram + 1])
    least = (grams & ~_POSITION) | np.arange(len(grams), dtype=np.uint64)
    width, size = length - gram + 1, 1
    while size * 2 <= width:
        least = np.minimum(least[:-size], least[size:])
        size *= 2
    if size < width:
        least = np.minimum(least[: size - width], least[width - size :])
    change = np.zeros(n + 1, dtype=np.int32)
    long_ = np.diff(at) >= length
    np.add.at(change, at[:-1][long_], 1)
    np.add.at(change, at[1:][long_] - length + 1, -1)
    p = np.flatnonzero(np.cumsum(change)[: n - length + 1])
    if not len(p):
        return anchors(data[:0], at[:1], length, gram)
    a = (least[p] & _POSITION).astype(np.int64)
    first = np.flatnonzero(np.concatenate([[True], (a[1:] != a[:-1]) | (p[1:] != p[:-1] + 1)]))
    lo, hi, a = p[first], p[np.concatenate([first[1:], [len(p)]]) - 1], a[first]
    shape = tk.mix(((a - lo) + ((hi - lo) << 16)).astype(np.uint64))
    context = tk.mix((sums[hi + length] - sums[lo]) * down[lo] ^ shape)
    # the other hash is one of the sequence of scrambled q-grams, which has no sums in common with the first
    over = np.zeros(len(grams) + 1, dtype=np.uint64)
    np.cumsum(tk.mix(grams ^ tk.U(0x5851F42D4C957F2D)) * up[: len(grams)], out=over[1:])
    other = tk.mix((over[hi + length - gram + 1] - over[lo]) * down[lo] ^ shape)
    return np.searchsorted(at, lo, side="right") - 1, a, lo, hi, grams[a], context, other


def packed(lo, hi, a, settled=0):
    """First start, last start and anchor of a run as one long that sorts by the first start; the last bit says whether it is settled."""
    return (lo << 24) | (hi - lo) << 12 | (a - lo) << 1 | settled


def unpacked(place):
    lo = place >> 24
    return lo, lo + (place >> 12 & 4095), lo + (place >> 1 & 2047)


#: The same in SQL: first and last start.
LO, HI = "shiftright(place, 24)", "shiftright(place, 24) + (shiftright(place, 12) & 4095)"
_ANCHORS = "h long, c long, e long, doc long, row long, place long"


def _found(length: int, gram: int):
    def pieces(batch):
        """Slices of whole texts, and of a very long text its pieces; base is where a piece begins."""
        for i, j, data, at in tk.slices(batch.column("text")):
            if len(data) <= tk.SLICE:
                yield np.arange(i, j), data, at, 0
            else:
                for base in range(0, len(data), tk.SLICE):
                    part = data[base : base + tk.SLICE + length - 1]
                    yield np.array([i]), part, np.array([0, len(part)]), base

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[int, tuple] = {}
        for batch in batches:
            doc, row = (batch.column(k).to_numpy(zero_copy_only=False) for k in ("doc", "row"))
            for rows, data, at, base in pieces(batch):
                text, a, lo, hi, h, c, e = anchors(data, at, length, gram)
                if not len(a):
                    continue
                d, r = doc[rows[text]], row[rows[text]]
                lo, hi, a = (x - at[text] + base for x in (lo, hi, a))
                h, c, e = (x.view(np.int64) for x in (h, c, e))
                order = np.lexsort((lo, r, d, e, c))
                d, r, lo, hi, a, h, c, e = (x[order] for x in (d, r, lo, hi, a, h, c, e))
                new = np.concatenate([[True], (c[1:] != c[:-1]) | (e[1:] != e[:-1])])
                group = np.cumsum(new) - 1
                heads = np.flatnonzero(new)
                head = heads[group]
                settled = (d != d[head]) | (r != r[head]) | (lo != lo[head])
                for k in heads[np.bincount(group) >= 3]:
                    me, name = (d[k], r[k], lo[k]), (c[k], e[k])
                    before = known.get(name)
                    if before is not None and before < me:
                        settled[k] = True
                    elif len(known) < REMEMBERED or before is not None:
                        known[name] = me
                if known:
                    for k in np.flatnonzero(new & ~settled):
                        before = known.get((c[k], e[k]))
                        if before is not None and before < (d[k], r[k], lo[k]):
                            settled[k] = True
                spread = np.where(settled, tk.mix((r + lo).astype(np.uint64)).view(np.int64), h)
                place = packed(lo, hi, a, settled.astype(np.int64))
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in (spread, c, e, d, r, place)], [x.split()[0] for x in _ANCHORS.split(", ")])

    return run


_RUNS = "h long, doc long, row long, place long, open boolean"


def _settled_by_gram(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows by (h, c, e, doc, row, place): repeats of a context, and the first rows of contexts of q-grams with several."""

    def out(h, d, r, p, is_open):
        return pa.RecordBatch.from_arrays([pa.array(h), pa.array(d), pa.array(r), pa.array(p), pa.array(np.full(len(h), is_open))], ["h", "doc", "row", "place", "open"])

    last = None  # (h, c, e, key of the first row of the context); what is known of the q-gram that a batch ends in
    waiting = None  # the first row of its first context, as long as it has one
    for batch in batches:
        h, c, e, d, r, p = (batch.column(i).to_numpy(zero_copy_only=False) for i in range(6))
        done = (p & 1) == 1
        if done.any():
            yield out(h[done], d[done], r[done], p[done], False)
            h, c, e, d, r, p = (x[~done] for x in (h, c, e, d, r, p))
        if not len(h):
            continue
        goes_on = last is not None and last[0] == h[0]
        same = goes_on and last[1] == c[0] and last[2] == e[0]
        new_h = np.concatenate([[not goes_on], h[1:] != h[:-1]])
        new = np.concatenate([[not same], (h[1:] != h[:-1]) | (c[1:] != c[:-1]) | (e[1:] != e[:-1])])
        heads = np.flatnonzero(new)
        number = np.cumsum(new) - 1
        fd, fr, fp = (np.where(number >= 0, x[heads[np.maximum(number, 0)]] if len(heads) else 0, k) for x, k in zip((d, r, p), last[3] if last else (0, 0, 0)))
        again = (d != fd) | (r != fr) | (p >> 24 != fp >> 24)
        if again.any():
            yield out(h[again], d[again], r[again], p[again], False)
        # contexts of each q-gram in this batch; the one that goes on has had one or more before
        gram = np.cumsum(new_h) - (0 if goes_on else 1)  # 0: the one that goes on, if any
        contexts = np.bincount(gram[heads], minlength=int(gram[-1]) + 1) if len(heads) else np.zeros(int(gram[-1]) + 1, np.int64)
        if goes_on:
            contexts[0] += 1
            if contexts[0] > 1 and waiting is not None:
                yield out(*[np.array([x]) for x in waiting], True)
                waiting = None
        several = heads[contexts[gram[heads]] > 1] if len(heads) else heads
        if len(several):
            yield out(h[several], d[several], r[several], p[several], True)
        k = heads[-1] if len(heads) else None
        if gram[-1] > 0 or not goes_on:  # a q-gram began here
            waiting = (h[k], d[k], r[k], p[k]) if contexts[gram[-1]] == 1 else None
        last = (h[-1], c[-1], e[-1], (fd[-1], fr[-1], fp[-1]))


_CONTEXTS = "h long, doc long, row long, lo int, hi int, bytes binary"


def _contexts(rows: list[tuple]) -> pa.RecordBatch:
    columns = list(zip(*rows)) if rows else [()] * 6
    kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.binary())
    return pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(columns, kinds)], [x.split()[0] for x in _CONTEXTS.split(", ")])


def _name(raw: bytes) -> int:
    return int.from_bytes(hashlib.blake2b(raw, digest_size=8).digest(), "little", signed=True)


def _cut(length: int, gram: int):
    """Contexts of open runs; of hot q-grams the pieces, each under the hash of the bytes that all its strings have."""

    def pieces(raw, doc, row, place):
        lo, hi, a = unpacked(place)
        for ahead in range(0, length - gram + 1, PIECE):  # strings that start from ahead to ahead + PIECE - 1 before the anchor
            first, last = max(lo, a - ahead - PIECE + 1), min(hi, a - ahead)
            if first <= last:
                shared = raw[a - ahead : a - ahead + length - PIECE + 1]
                yield _name(ahead.to_bytes(4, "little") + shared), doc, row, first, last, raw[first : last + length]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(0, batch.num_rows, 128):
                part, out = batch.slice(i, 128), []
                for doc, row, text, runs in zip(*(part.column(k).to_pylist() for k in ("doc", "row", "text", "runs"))):
                    raw = text.encode()
                    for x in runs:
                        if x["hot"]:
                            out += pieces(raw, doc, row, x["place"])
                        else:
                            lo, hi, _ = unpacked(x["place"])
                            out.append((x["h"], doc, row, lo, hi, raw[lo : hi + length]))
                yield _contexts(out)

    return run


def _strings(length: int):
    """Each string of a piece by itself, under its own hash."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(0, batch.num_rows, 256):
                rows = zip(*(x.to_pylist() for x in batch.slice(i, 256).columns))
                cut = ((doc, row, lo + j, raw[j : j + length]) for _, doc, row, lo, hi, raw in rows for j in range(hi - lo + 1))
                yield _contexts([(_name(x), doc, row, p, p, x) for doc, row, p, x in cut])

    return run


def bucket_pointers(data: np.ndarray, depth: int, at: np.ndarray | None = None, parts: int = PARTS) -> np.ndarray:
    """For the suffixes at these places of data (all; data must be padded by `depth` bytes) a bucket pointer; equal ones mean `depth` equal bytes.

    A pointer is the number of suffixes that come before the bucket.  Buckets of one suffix are final.  Within a round buckets are refined part by part;
    what a part has found out is used from the next part on.  So suffixes may be told apart by more than `depth` bytes; in the end neighbours of the order
    that results are compared byte by byte, and equal ones share a bucket again."""
    n = len(data) - depth
    step = 8
    padded = np.concatenate([data, np.zeros(step, np.uint8)])
    word = np.zeros(len(data), dtype=np.uint64)
    for k in range(step):
        word = (word << tk.U(8)) | padded[k : k + len(data)]
    order = np.argsort(word, kind="stable").astype(np.int32)
    new = np.concatenate([[True], word[order[1:]] != word[order[:-1]]])
    del word
    pointer = np.empty(len(data), dtype=np.int32)
    pointer[order] = np.flatnonzero(new)[np.cumsum(new) - 1]
    sizes = np.bincount(pointer, minlength=len(data))
    live = order[sizes[pointer[order]] > 1]  # by bucket
    del order, sizes
    known = step
    while known < depth and len(live):
        edges = np.flatnonzero(np.concatenate([[True], pointer[live[1:]] != pointer[live[:-1]]]))
        # whole buckets to each part
        cuts = edges[np.searchsorted(edges, np.arange(1, parts) * len(live) // parts, side="right") - 1]
        rest = []
        for members in np.split(live, np.unique(cuts[cuts > 0])):
            # a suffix that ends before the offset comes first; what is behind data's end is padding
            later = members.astype(np.int64) + known
            key = pointer[members].astype(np.int64) * (len(data) + 1) + np.where(later < len(data), pointer[np.minimum(later, len(data) - 1)] + 1, 0)
            by = np.argsort(key, kind="stable")
            key, members = key[by], members[by]
            opened = np.concatenate([[True], key[1:] != key[:-1]])
            start = np.flatnonzero(opened)
            old = pointer[members[start]].astype(np.int64)
            first = np.flatnonzero(np.concatenate([[True], old[1:] != old[:-1]]))
            rank = start - start[first][np.searchsorted(first, np.arange(len(start)), side="right") - 1] + old
            size = np.diff(np.concatenate([start, [len(key)]]))
            pointer[members] = np.repeat(rank, size)
            rest.append(members[np.repeat(size > 1, size)])
        live = np.concatenate(rest)
        known *= 2
    at = np.arange(n) if at is None else at
    order = np.argsort(pointer[at], kind="stable")
    new = np.ones(len(order), dtype=bool)
    for i in range(1, len(order), 4096):
        text = data[at[order[i - 1 : i + 4096]][:, None] + np.arange(depth)]
        new[i : i + 4096] = (text[1:] != text[:-1]).any(axis=1)
    out = np.empty(len(order), dtype=np.int32)
    out[order] = np.flatnonzero(new)[np.cumsum(new) - 1]
    return out


def _refined(length: int):
    def solve(doc, row, lo, hi, parts):
        """Runs of repeated starts among whole groups of contexts."""
        sizes = np.fromiter(map(len, parts), dtype=np.int64, count=len(parts))
        begin = np.concatenate([[0], np.cumsum(sizes)])
        data = np.concatenate([np.frombuffer(b"".join(parts), dtype=np.uint8), np.zeros(length, np.uint8)])
        count = hi.astype(np.int64) - lo + 1
        owner = np.repeat(np.arange(len(parts), dtype=np.int32), count)
        inside = np.arange(len(owner)) - np.repeat(np.cumsum(count) - count, count)
        at, start = begin[owner] + inside, lo[owner] + inside
        pointer = bucket_pointers(data, length, at)
        order = np.lexsort((start, row[owner], doc[owner], pointer))
        o, s, q = owner[order], start[order], pointer[order]
        new = np.concatenate([[True], q[1:] != q[:-1]])
        head = np.flatnonzero(new)[np.cumsum(new) - 1]
        again = (doc[o] != doc[o[head]]) | (row[o] != row[o[head]]) | (s != s[head])
        o, s = o[again], s[again]
        order = np.lexsort((s, o))
        o, s = o[order], s[order]
        if not len(o):
            return None
        first = np.flatnonzero(np.concatenate([[True], (o[1:] != o[:-1]) | (s[1:] != s[:-1] + 1)]))
        end = s[np.concatenate([first[1:], [len(s)]]) - 1]
        found = doc[o[first]], row[o[first]], s[first].astype(np.int32), end.astype(np.int32)
        return pa.RecordBatch.from_arrays([pa.array(x) for x in found], ["doc", "row", "lo", "hi"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list = []
        size = 0

        def flush(upto: int | None):
            """Settle all groups but the one that goes on."""
            nonlocal held, size
            columns = [np.concatenate([x[k] for x in held]) for k in range(5)]
            parts = [b for x in held for b in x[5]]
            cut = len(parts) if upto is None else int(np.searchsorted(columns[0], upto))
            found = solve(*[x[:cut] for x in columns[1:]], parts[:cut])
            held = [[x[cut:] for x in columns] + [parts[cut:]]] if cut < len(parts) else []
            size = sum(map(len, parts[cut:]))
            return found

        for batch in batches:
            for i in range(0, batch.num_rows, 2048):
                part = batch.slice(i, 2048)
                numbers = [part.column(k).to_numpy(zero_copy_only=False) for k in range(5)]
                held.append([*numbers, part.column(5).to_pylist()])
                size += sum(map(len, held[-1][5]))
                if size > CHUNK and held[0][0][0] != numbers[0][-1] and (found := flush(numbers[0][-1])) is not None:
                    yield found
        if held and (found := flush(None)) is not None:
            yield found

    return run


def _merged(length: int):
    """Runs of repeated starts to the removed spans of each document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            starts, ends = [], []
            for runs in batch.column("runs"):
                at = runs.values.field("lo").to_numpy(), runs.values.field("hi").to_numpy()
                order = np.argsort(at[0])
                lo, hi = at[0][order].astype(np.int64), np.maximum.accumulate(at[1][order].astype(np.int64) + length)
                first = np.concatenate([[True], lo[1:] > hi[:-1]])
                starts.append(lo[first].tolist())
                ends.append(hi[np.concatenate([np.flatnonzero(first)[1:], [len(lo)]]) - 1].tolist())
            yield pa.RecordBatch.from_arrays([batch.column("doc"), batch.column("row"), pa.array(starts, pa.list_(pa.int64())), pa.array(ends, pa.list_(pa.int64()))], ["doc", "row", "starts", "ends"])

    return run


def identified(docs: DataFrame) -> DataFrame:
    """doc and row: what orders and names a document in here."""
    return docs.select("doc_id", F.coalesce(F.col("doc_id").cast("long"), F.lit(_LAST)).alias("doc"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("row"), F.coalesce("text", F.lit("")).alias("text"))


def _hot(rows: DataFrame, name: str) -> DataFrame:
    return rows.groupBy("h").agg(F.count(F.lit(1)).alias("m")).where(F.col("m") > HOT).select("h", F.lit(True).alias(name))


def _first_of_strings(strings: DataFrame) -> DataFrame:
    """The repeats among strings; the firsts have no more to be settled and go.  Sums of each task meet, not strings; Spark splits a joined key that is large."""
    strings = written(strings, "strings")
    place = F.struct("doc", "row", "lo")
    first = strings.groupBy("bytes").agg(F.min(place).alias("first"), F.count(F.lit(1)).alias("m")).where("m > 1").select(F.col("bytes").alias("b"), "first")
    again = strings.join(small(written(first, "first-strings")), F.col("bytes") == F.col("b")).where(place != F.col("first"))
    return again.select("h", "doc", "row", "lo", "hi", F.lit(None).cast("binary").alias("bytes"))


def repeated_spans(docs: DataFrame, length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """doc, row, starts, ends: the removed spans (bytes, end exclusive) of each document that loses some."""
    with passing(docs.sparkSession) as keep:
        return keep(_spans(docs, length, gram))


def _spans(docs: DataFrame, length: int, gram: int) -> DataFrame:
    texts = identified(docs)
    partitions = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    found = texts.where(F.octet_length("text") >= length).select("doc", "row", "text").mapInArrow(_found(length, gram), _ANCHORS)
    dealt = found.repartition(partitions, "h").sortWithinPartitions("h", "c", "e", "doc", "row", "place")
    runs = written(dealt.mapInArrow(_settled_by_gram, _RUNS), "runs")
    open_ = runs.where("open")
    hot = written(_hot(open_, "hot"), "hot-grams")
    flagged = open_.join(small(hot), "h", "left").select("doc", "row", F.struct("h", "place", F.coalesce("hot", F.lit(False)).alias("hot")).alias("x"))
    wanted = written(flagged.groupBy("doc", "row").agg(F.collect_list("x").alias("runs")), "open-runs")
    cut = texts.select("doc", "row", "text").join(small(wanted, open_.count(), LISTED), ["doc", "row"]).mapInArrow(_cut(length, gram), _CONTEXTS)
    if not hot.isEmpty():
        cut = written(cut, "pieces")
        again = written(_hot(cut, "again"), "hot-pieces")
        if not again.isEmpty():
            several = cut.join(small(again), "h", "left_semi")
            cut = cut.join(small(again), "h", "left_anti").unionByName(_first_of_strings(several.mapInArrow(_strings(length), _CONTEXTS)))
    # a string by itself has lost its bytes if it is a repeat
    refined = cut.where("bytes is not null").repartition(partitions, "h").sortWithinPartitions("h").mapInArrow(_refined(length), "doc long, row long, lo int, hi int")
    everything = runs.where("not open").selectExpr("doc", "row", f"cast({LO} as int) as lo", f"cast({HI} as int) as hi").unionByName(refined)
    if not hot.isEmpty():
        everything = everything.unionByName(cut.where("bytes is null").select("doc", "row", "lo", "hi"))
    by_doc = everything.groupBy("doc", "row").agg(F.collect_list(F.struct("lo", "hi")).alias("runs"))
    return written(by_doc.mapInArrow(_merged(length), "doc long, row long, starts array<long>, ends array<long>"), "spans")


def _digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        sizes, removed, spans, digests = [], [], [], []
        for text, starts, ends in zip(batch.column("text"), batch.column("starts"), batch.column("ends")):
            raw = memoryview(text.as_buffer())
            starts, ends = starts.as_py() or [], ends.as_py() or []
            digest, at = hashlib.sha256(), 0
            for a, b in zip(starts, ends):
                digest.update(raw[at:a])
                at = b
            digest.update(raw[at:])
            sizes.append(len(raw)), spans.append(len(starts)), removed.append(sum(ends) - sum(starts)), digests.append(digest.hexdigest())
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(sizes, pa.int64()), pa.array(removed, pa.int64()), pa.array(spans, pa.int64()), pa.array(digests, pa.string())], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])


def removal_digests(docs: DataFrame, length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256, for every document."""
    spans = repeated_spans(docs, length, gram)
    listed = spans.agg(F.coalesce(F.sum(F.size("starts")), F.lit(0))).first()[0]
    joined = identified(docs).join(small(spans, listed, LISTED), ["doc", "row"], "left").select("doc_id", "text", "starts", "ends")
    return joined.mapInArrow(_digest, f"doc_id {dict(docs.dtypes)['doc_id']}, n_bytes long, n_removed long, n_spans long, kept_sha256 string")
