"""The pipeline against a plain version, and on odd tables."""

import random
import re
import zlib
from collections import Counter, defaultdict

import pytest

import corpus_pipeline

from .test_operators import plain_statistics, shingle_set, words
from .test_plain_operators import plain_mix

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def prose(r, n):
    return " ".join("".join(r.choice("abcdefghij") for _ in range(r.randint(3, 9))) for _ in range(n))


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    """48 documents at most are judged by base rules alone; they hold copies, near copies, test items, repeats, short, empty and null texts."""
    r = random.Random(31)
    item = prose(r, 30)
    texts = [prose(r, r.randint(30, 120)) for _ in range(24)]
    texts += [texts[0], texts[1].rsplit(" ", 1)[0] + " changed", f"{prose(r, 40)} {item} {prose(r, 25)}", prose(r, 5), None, "", "a b c d e f g h " * 20, texts[3].upper()]
    rows = [(i * 2, t, "en", r.choice(["a", "b", None]), len(t or "")) for i, t in enumerate(texts)]
    rows += [(None, prose(r, 50), None, "a", 1), (None, f"{item} {prose(r, 20)}", None, "a", 1), rows[5], rows[5]]
    path = tmp_path_factory.mktemp("corpus")
    spark.createDataFrame(rows, SCHEMA).repartition(3).write.parquet(f"{path}/documents.parquet")
    spark.createDataFrame([(1, item), (2, None), (3, "")], "item_id long, text string").write.parquet(f"{path}/benchmark.parquet")
    return str(path), rows, item


def plain_pipeline(rows, item):
    def fine(t):
        n, *_, repeats = plain_statistics(t)
        return n >= 20 and 100 * repeats <= 30 * n

    rejected = {d for d, t, *_ in rows if not fine(t)}
    rows = [x for x in rows if x[0] not in rejected]
    rows = sorted(set(rows), key=lambda x: (x[0] is None, x[0] or 0, x[1]))
    label = list(range(len(rows)))
    sets = [shingle_set(x[1], 5) for x in rows]
    for _ in rows:
        for a in range(len(rows)):
            for b in range(a):
                if 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                    label[a] = label[b] = min(label[a], label[b])
    rows = [x for i, x in enumerate(rows) if label[i] == i]
    toks = lambda t: [x for x in re.split(r"[\W_]+", (t or "").lower()) if x]
    grams = lambda t: {tuple(toks(t)[i : i + 5]) for i in range(len(toks(t)) - 4)}
    asked = grams(item)
    rows = [x for x in rows if 100 * len(asked & grams(x[1])) < 80 * len(asked)]
    _, _, taken = plain_mix([(d, t, s) for d, t, _, s, _ in rows], True)
    return [rows[i] for i, *_ in taken]


def test_run_against_plain_version(spark, folder):
    path, rows, item = folder
    want = plain_pipeline(rows, item)
    got = corpus_pipeline.run(spark, path).collect()
    assert want and Counter((r.doc_id, r.size, r.text_crc32) for r in got) == Counter((d, len(t.encode()) + 8, zlib.crc32(t.encode())) for d, t, *_ in want)
    shards = defaultdict(list)
    for r in got:
        shards[r.shard].append(r.slot)
    assert all(sorted(x) == list(range(len(x))) for x in shards.values())
    assert all(len({r.shard for r in got if r.text_crc32 == c}) == 1 for c in {r.text_crc32 for r in got})


def test_clashing_columns_and_empty_tables(spark, folder):
    """Extra columns of the names that stages use themselves, in any case; then no rows at all."""
    path, rows, _ = folder
    extra = ("_id", "_ID2", "_t", "_copies", "_n", "_copy", "_draw", "_draws", "_digest", "_drawn_doc_id", "key", "row", "size", "shard", "rep", "m")
    docs = spark.createDataFrame([(*x, *[1] * len(extra)) for x in rows], f"{SCHEMA}, {', '.join(f'`{c}` int' for c in extra)}")
    for frame in (docs, docs.limit(0)):
        now = frame
        for name, stage in corpus_pipeline.STAGES:
            out = stage(spark, now, path)
            if name != "sharding":
                assert out.columns == docs.columns
                now = out
            else:
                assert (out.count() > 0) == (frame is docs)


def test_stages_keep_what_they_should(folder, spark):
    """Rows without an id are judged like any other."""
    path, rows, item = folder
    docs = spark.read.parquet(f"{path}/documents.parquet")
    stages = dict(corpus_pipeline.STAGES)
    clean = Counter((r.doc_id, r.text) for r in stages["decontamination"](spark, docs, path).collect())
    assert clean == Counter((d, t) for d, t, *_ in rows if item not in (t or ""))
    assert all(words(t) for _, t in ((r.doc_id, r.text) for r in stages["mixing"](spark, docs, path).collect()))
