"""Odd rows that single operators had no test of."""

import random
import re

import pytest

from distsort.llm import decontamination, paragraph_dedup, url_filter


def prose(r, n):
    return " ".join("".join(r.choice("abcdefghij") for _ in range(r.randint(3, 9))) for _ in range(n))


def test_items_that_repeat_an_id(spark):
    """The pair has the larger share; equal items under several ids are pairs of their own; common phrases in all items lose none."""
    r = random.Random(41)
    phrase, one, two = prose(r, 12), prose(r, 20), prose(r, 20)
    items = [(1, one), (1, prose(r, 20)), (2, two), (3, two), (None, one)] + [(10 + i, f"{phrase} {prose(r, 6)}") for i in range(40)]
    docs = [(1, f"{prose(r, 50)} {one} {prose(r, 30)}"), (2, f"{two} {prose(r, 9)}"), (3, f"{prose(r, 9)} {phrase} {prose(r, 9)}"), (4, f"{items[9][1]} {prose(r, 20)}"), (None, one)]
    toks = lambda t: re.findall(r"[^\W_]+", t.lower())
    grams = lambda t: {tuple(toks(t)[i : i + 5]) for i in range(len(toks(t)) - 4)}
    want = {}
    for d, text in docs:
        for i, item in items:
            share = len(grams(item) & grams(text)) / len(grams(item))
            if d is not None and i is not None and share >= 0.8:
                want[(d, i)] = max(share, want.get((d, i), 0))
    found = decontamination.contained_items(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")).collect()
    assert {(x.doc_id, x.item_id): x.containment for x in found} == pytest.approx(want) and len(want) >= 4


def test_pages_of_all_kinds(spark):
    """Repeated rows, null ids, extra columns of clashing names, a very long URL, a host of many labels."""
    long_ = "http://site.info/" + "x" * 200_000
    urls = ["http://site.info/a", "http://site.info/a", long_, "http://" + ".".join("abcdef") * 30 + ".example.com/en/7", "HTTP://EXAMPLE.COM/en/6", "://", "http://", None]
    rows = [(i if i != 1 else None, u, "block", "x", 1) for i, u in enumerate(urls)] + [(0, urls[0], "block", "x", 1)]
    pages = spark.createDataFrame(rows, "page_id long, url string, block string, `key` string, w0 int")
    listed = spark.createDataFrame([("site.info/a",), ("site.info/a",), (None,), (long_.removeprefix("http://"),)], "canonical string")
    got = sorted(((x.page_id, x.rule, x.verdict) for x in url_filter.judge(pages, listed).collect()), key=str)
    want = [(0, None, "block"), (None, None, "block"), (2, None, "block"), (3, "example.com/en/7", "allow"), (4, "com/en/", "block"), (5, None, "allow"), (6, None, "allow"), (7, None, "allow"), (0, None, "block")]
    assert got == sorted(want, key=str)
    none = listed.limit(0)
    assert {x.verdict for x in url_filter.judge(pages, none, ()).collect()} == {"allow"}


def test_filter_grows_with_the_list():
    assert [url_filter.blocks_for(n) for n in (0, 1, 32, 33, 1000, 10**6, 10**9)] == [1, 1, 1, 2, 32, 32768, url_filter.MOST_BLOCKS]


def test_passages_of_very_long_texts(spark):
    """Texts of over a slice of bytes, without line ends, that share a passage; and one line of 60,000 words twice."""
    r = random.Random(42)
    passage = prose(r, 60)
    one, two = prose(r, 120_000), prose(r, 1000)
    line = prose(r, 60_000)
    rows = [(1, f"{one} {passage} {two}"), (2, f"{two[:5000]} {passage}"), (3, line), (4, line)]
    got = {(x.doc_id, x.kind, x.kept_doc_id) for x in paragraph_dedup.repeated_passages(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert {(2, "passage", 1), (4, "paragraph", 3)} <= got and all(d in (2, 4) for d, *_ in got)
