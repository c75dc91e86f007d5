"""Places where an operator once did less than the whole job."""

import random
from collections import Counter

import numpy as np

from distsort.llm import mixing, near_dup, paragraph_dedup, secret_scan


def prose(r, n):
    return " ".join("".join(r.choice("abcdefghij") for _ in range(r.randint(3, 9))) for _ in range(n))


def found(spark, rows):
    return {(x.doc_id, x.kind, x.kept_doc_id) for x in paragraph_dedup.repeated_passages(spark.createDataFrame(rows, "doc_id long, text string")).collect()}


# ---- 6: paragraphs


def test_short_lines_are_paragraphs(spark):
    r = random.Random(21)
    five, eight, fourteen = prose(r, 5), prose(r, 8), prose(r, 14)
    near = fourteen.rsplit(" ", 1)[0] + " changed"
    lines = lambda x: f"{prose(r, 30)}\n{x}\n{prose(r, 30)}"
    rows = [(1, lines(eight)), (2, lines(eight)), (3, lines(fourteen)), (4, lines(near)), (5, lines(five)), (6, lines(five)), (7, lines("one two three four")), (8, lines("one two three four"))]
    assert found(spark, rows) == {(2, "paragraph", 1), (4, "paragraph", 3), (6, "paragraph", 5)}


def test_no_near_paragraph_is_missed(spark):
    """350 pairs at a similarity of 0.8 exactly; 8 bands of 3 miss four of them."""
    r = random.Random(30)
    rows = []
    for i in range(1350):
        line = prose(r, 40).split(" ")
        near = [*line[:3], "changed", *line[4:]]
        rows += [(2 * i, " ".join(line)), (2 * i + 1, " ".join(near))]
    got = {(d, k) for d, kind, k in found(spark, rows[2000:]) if kind == "paragraph"}
    assert got == {(2 * i + 1, 2 * i) for i in range(1000, 1350)}


def test_passages_that_one_document_repeats(spark):
    r = random.Random(22)
    passage = prose(r, 60)
    text = f"{prose(r, 10)} {passage} {prose(r, 15)} {passage} {prose(r, 12)}"
    rows = [(1, text), (1, text), (2, prose(r, 100)), (3, "x " * 40)]
    got = [(x.doc_id, x.kind, x.kept_doc_id, x.start, x.end) for x in paragraph_dedup.repeated_passages(spark.createDataFrame(rows, "doc_id long, text string")).collect()]
    second = text.rindex(passage)
    assert [x[:3] for x in got] == [(1, "passage", 1)] and second <= got[0][3] and got[0][4] <= second + len(passage)


# ---- 9: near duplicates


def test_texts_of_one_doc_id(spark):
    """Held against the SQL; and the stage keeps each clean text."""
    import duckdb
    import pandas as pd

    r = random.Random(23)
    a, b, c = prose(r, 40), prose(r, 40), prose(r, 40)
    near = c.rsplit(" ", 1)[0] + " changed"
    rows = [(3, a), (7, a), (7, b), (8, near), (9, ""), (9, c), (10, b), (11, None), (12, "")]
    frame = pd.DataFrame(rows, columns=["doc_id", "text"])
    con = duckdb.connect()
    con.register("documents", frame)
    want = {tuple(map(int, x)) for x in con.execute(near_dup.ORACLE).fetchall()}
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    assert {(x.doc_id, x.n_shingles, x.component_id, int(x.kept)) for x in near_dup.near_duplicates(df, size=2).collect()} == want
    got = sorted((x.doc_id, x.text or "") for x in near_dup.drop_near_duplicates(df, size=2).collect())
    assert got == sorted([(3, a), (7, b), (8, near), (9, ""), (11, ""), (12, "")])


def test_rows_without_id_are_judged(spark):
    r = random.Random(24)
    a, b = prose(r, 40), prose(r, 40)
    rows = [(None, a), (3, a), (None, b), (None, b), (None, ""), (None, ""), (None, None)]
    got = near_dup.drop_near_duplicates(spark.createDataFrame(rows, "doc_id long, text string").repartition(3)).collect()
    assert sorted((x.doc_id or 0, x.text or "") for x in got) == sorted([(3, a), (0, b), (0, ""), (0, ""), (0, "")])


def test_mix_draws_rows(spark):
    """Rows of one doc_id, of two texts and sources, are taken as their own draws say."""
    r = random.Random(25)
    rows = [(i % 40, prose(r, 5 + i % 30), "ab"[i // 40 % 2]) for i in range(160)] + [(1, "same text", "a")] * 3
    df = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(3)
    thin, taken = mixing.draws(df, whole=True)
    want = Counter((x.doc_id, x.source, x.size) for x in thin.join(taken.select("row"), "row").collect())
    got = Counter((x.doc_id, x.source, len(x.text.split())) for x in mixing.mix_documents(df).collect())
    assert got == want and len(want) > 50


# ---- 7: secrets


class Everything:
    """A network that finds all that it sees."""

    threshold = 0.5

    def score(self, windows):
        return np.ones(len(windows))


def test_network_sees_every_run(spark):
    hex_ = "0123456789abcdef01234567"
    texts = [f"key {hex_}ZZxx99 end", "a" * 9 + "Bcdefghij x", "1234567890123456", "token=abcdefghijklmnopq1 x", f"é {hex_} x"]
    got = [x.spans for x in secret_scan.scan(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), Everything()).orderBy("doc_id").collect()]
    assert got == ["hex:4:28,cnn:4:34", "cnn:0:18", "cnn:0:16", "assign:0:24", "hex:2:26"]


def _shuffle_files(spark) -> int:
    files = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
    return sum(files.apply(i).getName().startswith("shuffle_") for i in range(files.size()))


def test_paragraphs_leave_no_shuffle_files(docs):
    """What a step of paragraph deduplication has sent is deleted when it has ended, and so are its tables of texts and bands."""
    import time

    from distsort.llm import common

    name = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    spark = docs.sparkSession
    before, setting, open_ = _shuffle_files(spark), spark.conf.get(name), []
    common._passing.append(open_)
    try:
        paragraph_dedup.repeated_passages(docs)
    finally:
        common._passing.pop()
    for _ in range(20):
        if _shuffle_files(spark) <= before:
            break
        time.sleep(0.5)
    assert _shuffle_files(spark) <= before
    assert spark.conf.get(name) == setting
    assert not [p for p in open_ if "/paragraphs-" in p or "/near-sketches-" in p]


def test_near_duplicates_by_slices(docs):
    """Bands that are dealt out slice by slice find the same components; large classes of copies, empty texts and rows without id included."""
    from pyspark.sql import functions as F

    more = docs.select("doc_id", "text").where("doc_id % 3 = 0")
    copies = more.limit(1).crossJoin(docs.sparkSession.range(200)).select((F.col("id") + 10_000_000).alias("doc_id"), "text")
    odd = docs.sparkSession.createDataFrame([(20_000_000, ""), (20_000_001, None), (None, "a b c d e f g"), (None, "a b c d e f g"), (20_000_002, "a b c d e f g")], "doc_id long, text string")
    rows = more.unionByName(copies).unionByName(odd)
    one, eight = (sorted(map(str, near_dup.near_duplicates(rows, size=5, slices=s).collect())) for s in (1, 8))
    assert one == eight and len(one) > 205
