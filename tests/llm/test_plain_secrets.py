"""Secret scans against a plain version: one text at a time, patterns by re, every window scored alone."""

import hashlib
import re
import zlib

import numpy as np
import pytest

from distsort.llm import secret_scan

ASSIGNED = r"""([Pp][Aa][Ss][Ss][Ww][Oo][Rr][Dd]|[Pp][Aa][Ss][Ss][Ww][Dd]|[Ss][Ee][Cc][Rr][Ee][Tt]|[Tt][Oo][Kk][Ee][Nn]|[Aa][Pp][Ii]_?[Kk][Ee][Yy])["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""


def plain(net, text):
    """Spans (start, kind, end, score) and the number of candidates."""

    def score(lo, hi):
        windows = secret_scan.encoded(text[max(0, lo - 20) : lo], text[lo:hi], text[hi : hi + 8])
        return max(float(net.score(np.array([w]))[0]) for w in windows)

    spans = [(m.start(), "assign", m.end(), score(*m.span(2))) for m in re.finditer(ASSIGNED, text) if len(m[2]) > 5]
    spans += [(m.start(), "access", m.end(), score(*m.span())) for m in re.finditer("AKIA[A-Z0-9]+", text) if len(m[0]) > 19]
    spans += [(m.start(), "hex", m.end(), score(*m.span())) for m in re.finditer("[0-9a-f]+", text) if len(m[0]) > 23]
    base, n = list(spans), len(spans)
    for m in re.finditer("[A-Za-z0-9+/_=-]{16,}", text):
        n += 1
        if score(*m.span()) >= net.threshold and not any(s <= m.start() and m.end() <= e for s, _, e, _ in base):
            spans.append((*(m.start(), "cnn", m.end()), score(*m.span())))
    order = ("assign", "access", "hex", "cnn")
    return sorted(spans, key=lambda x: (x[0], order.index(x[1]))), n


@pytest.fixture(scope="module")
def found(spark):
    """The network that the query learns, its rows on the given table, and the texts."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    net = secret_scan.learned(docs)
    return net, docs, secret_scan.scan(docs, net).collect(), {r.doc_id: r.text or "" for r in docs.collect()}


def test_query_against_plain_version(found):
    net, _, rows, texts = found
    assert len(rows) == len(texts)
    for r in rows:
        spans, n = plain(net, texts[r.doc_id])
        said = [f"{k}:{s}:{e}" for s, k, e, _ in spans]
        assert r.spans == ",".join(said) and r.n_candidates == n
        assert [r.n_assign, r.n_access, r.n_hex] == [sum(k == x for _, k, _, _ in spans) for x in ("assign", "access", "hex")]
        assert r.base_sha256 == hashlib.sha256(",".join(x for x in said if not x.startswith("cnn")).encode()).hexdigest()
        assert np.allclose([float(x) for x in r.scores.split(",") if x], [x[3] for x in spans], atol=2e-4)
    assert sum(r.n_candidates for r in rows) > 20  # every one of them scored


def test_recall_on_documents_kept_apart(spark):
    docs = spark.read.parquet("/root/testdata/sf0.1/documents.parquet").select("doc_id", "text")
    net = secret_scan.learned(docs)
    apart = secret_scan.base_findings(docs, kept_apart=True).collect()
    assert apart and all(zlib.crc32(str(r.doc_id).encode()) % 5 == 0 for r in apart)
    hit = [net.score(np.array(secret_scan.encoded(r.left, r.run, r.right))).max() >= net.threshold for r in apart]
    assert np.mean(hit) >= 0.9


def test_learning_survives_odd_tables(spark):
    schema = "doc_id long, text string"
    for rows in ([], [(None, None), (1, ""), (None, "password=abcdefgh1")], [(5, "token: 'zzzzzz'")] * 3):
        df = spark.createDataFrame(rows, schema)
        assert secret_scan.scan(df, secret_scan.learned(df)).count() == len(rows)


def test_learns_from_every_finding(spark):
    """However little all findings weigh together, each of them that is learned from, or calibrates, changes the network."""
    df = spark.createDataFrame([(i, f"word token={'abcdefgh'[i % 8] * 3}{i * 7919}xyz word") for i in range(24)], "doc_id long, text string").coalesce(1).cache()
    ids = [r.doc_id for r in secret_scan.folded(df).where("fold < 4").orderBy("doc_id").collect()]
    state = lambda d: (net := secret_scan.learned(d, 2)).flat().tobytes() + repr((net.scale, net.threshold)).encode()
    whole = state(df)
    assert len(ids) > 6 and whole == state(df)
    assert all(state(df.where(df.doc_id != i)) != whole for i in ids[:3])
