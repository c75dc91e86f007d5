"""Quality verdicts, classifier scores, paragraphs and mixes against plain versions."""

import hashlib
import math
import random
import re
from collections import Counter, defaultdict

import numpy as np
import pytest

from distsort.llm import mixing, paragraph_dedup, quality_rules, rule_classifier

from .test_operators import plain_statistics, shingle_set, words

D = "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def given(spark):
    return spark.read.parquet(f"{D}/documents.parquet")


# ---- 2: the verdict


def plain_outliers(x):
    """Reweighed minimum covariance determinant by steps over sorted distances; squared distances of all rows."""
    d = x.shape[1]
    ridge, h = np.diag(quality_rules.RIDGE), quality_rules.H
    far = lambda m, c: np.einsum("ij,jk,ik->i", x - m, np.linalg.inv(c), x - m)
    cov = lambda a: (a - a.mean(0)).T @ (a - a.mean(0)) / len(a)
    median = np.median(x, axis=0)
    spread = 1.4826 * np.median(np.abs(x - median), axis=0)
    found = []
    for m, c in ((median, np.diag(spread**2) + ridge), (x.mean(0), cov(x) + ridge)):
        for _ in range(quality_rules.STEPS):
            near = x[np.argsort(far(m, c), kind="stable")[: math.ceil(h * len(x))]]
            m, c = near.mean(0), cov(near) * quality_rules.consistency(h, d) + ridge
        found.append((np.linalg.det(c), m, c))
    _, m, c = min(found, key=lambda f: f[0])
    near = x[far(m, c) <= quality_rules.chi2_quantile(quality_rules.REWEIGH, d)]
    return far(near.mean(0), cov(near) * quality_rules.consistency(quality_rules.REWEIGH, d) + ridge)


def test_verdict_against_plain_version(given):
    rows = {r.doc_id: r for r in given.select("doc_id", "text", "lang", "source").collect()}
    got = {r.doc_id: r for r in quality_rules.judge(given).collect()}
    assert got.keys() == rows.keys()
    cells, vectors = defaultdict(list), {}
    for i, r in rows.items():
        n, chars, symbols, lines, repeats = plain_statistics(r.text)
        assert got[i].base_failed == (n < 20 or 100 * repeats > 30 * n)
        if not got[i].base_failed:
            n, chars = max(n, 1), max(chars, 1)
            raw = (math.log1p(n), math.log(chars / n), math.log1p(symbols * 1000 / chars), math.log1p(lines * 1000 / n), math.log1p(repeats * 100 / n))
            vectors[i] = [round(v * quality_rules.SCALE) / quality_rules.SCALE for v in raw]
            cells[(r.lang, r.source)].append(i)
    small = defaultdict(list)
    for cell in [c for c, ids in cells.items() if len(ids) < quality_rules.LEAST]:
        small[cell[0]] += cells.pop(cell)
    rest = [i for lang in [k for k, ids in small.items() if len(ids) < quality_rules.LEAST] for i in small.pop(lang)]
    groups = [*cells.values(), *small.values(), *([rest] if len(rest) >= quality_rules.LEAST else [])]
    cut, judged, differ = quality_rules.chi2_quantile(quality_rules.REJECT, 5), 0, []
    for ids in groups:
        d2 = plain_outliers(np.array([vectors[i] for i in ids]))
        judged += len(ids)
        differ += [(i, v) for i, v in zip(ids, d2) if got[i].kept != (v <= cut)]
    assert judged > 800 and len(differ) <= 0.005 * judged and all(0.7 * cut <= v <= 1.4 * cut for _, v in differ)
    assert 0 < sum(not r.kept and not r.base_failed for r in got.values()) < 0.15 * judged


# ---- 5: scores


def plain_features(text):
    t, w = text or "", words(text)
    n, lines = max(len(w), 1), (text or "").split("\n")
    count = lambda pattern: len(re.findall(pattern, t))
    chars = max(len(t), 1)
    raw = [sum(map(len, w)) / n, count(r"[#*$%&<>@^~=+{}\\\[\]]") / n, count("[!?]") / n, count("[0-9]") / chars, count("[A-ZÀ-Þ]") / chars, count("[|]") / n, len(set(w)) / n, sum(a == b for a, b in zip(w, w[1:])) / n, (len(lines) - len(set(lines))) / len(lines), len(lines) / n]
    return [float(len(w)), *raw]


def test_scores_against_plain_version(spark, given):
    labels = spark.read.parquet(f"{D}/labels.parquet")
    model = rule_classifier.learned(given, labels)
    texts = given.select("doc_id", "text").collect()
    x = np.array([plain_features(r.text) for r in texts])
    x[:, 1:] = np.floor(x[:, 1:] * 1e6 + 0.5) / 1e6
    want = dict(zip((r.doc_id for r in texts), model.score(x)))
    got = rule_classifier.classify(given, labels).collect()
    assert len(got) == len(want) and sum(abs(r.score - want[r.doc_id]) < 1e-6 for r in got) >= 0.995 * len(got)


# ---- 6: paragraphs


def test_paragraphs_against_plain_version(docs, corpus):
    lines = sorted({(d, i, line) for d, t, *_ in corpus if d is not None and t for i, line in enumerate(t.split("\n")) if len(words(line)) >= 5})
    sets = [shingle_set(x[2], 5) for x in lines]
    label = list(range(len(lines)))

    def root(i):
        while label[i] != i:
            i = label[i]
        return i

    for a in range(len(lines)):
        for b in range(a):
            if 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]) and root(a) != root(b):
                label[max(root(a), root(b))] = min(root(a), root(b))
    want = {(lines[i][0], lines[i][1], lines[root(i)][0]) for i in range(len(lines)) if root(i) != i}
    rows = paragraph_dedup.repeated_passages(docs).collect()
    assert {(r.doc_id, r.line, r.kept_doc_id) for r in rows if r.kind == "paragraph"} == want and want
    # every run of 49 words that an earlier document has is covered by spans, but for a piece's length less one at its ends
    spans = defaultdict(list)
    texts = {d: t for d, t, *_ in corpus}
    for r in rows:
        if r.kind == "passage":
            spans[r.doc_id].append((r.start, r.end))
    seen, checked = {}, 0
    for d in sorted(x for x in texts if x is not None):
        at = [(m.start(), m.end()) for m in re.finditer(r"[^\x20\x09-\x0D]+", texts[d] or "")]
        own = {}
        for i in range(len(at) - 48):
            key = tuple((texts[d][a:b]) for a, b in at[i : i + 49])
            if key in seen:
                lo, hi = len(texts[d][: at[i][0]].encode()), len(texts[d][: at[i + 48][1]].encode())
                assert any(a < hi and lo < b for a, b in spans[d]), (d, i)
                checked += 1
            own[key] = d
        seen |= own
    assert checked


# ---- 10: mixes


def plain_mix(rows, whole, weights=(5, 2, 1), share=1.5, epochs=2.0, shards=24, seed=mixing.SEED):
    """rows (doc_id, text, source): for each row and copy taken (index of the row, copy, words, shard); ties of equal rows in the rows' order."""
    md5 = lambda *x: hashlib.md5(":".join(map(str, x)).encode()).hexdigest()
    size = [len(words(t)) for _, t, _ in rows]
    sources = sorted({s for *_, s in rows}, key=lambda s: (s is None, s or ""))
    total = {s: sum(n for n, r in zip(size, rows) if r[2] == s) for s in sources}
    w = {s: weights[i % len(weights)] for i, s in enumerate(sources)}
    goal, capped = share * sum(total.values()), set()
    while True:  # share again until no source is above its cap
        left = goal - sum(epochs * total[s] for s in capped)
        unit = left / sum(w[s] for s in sources if s not in capped) if len(capped) < len(sources) else 0
        over = {s for s in sources if s not in capped and unit * w[s] > epochs * total[s] + 1e-9}
        if not over:
            break
        capped |= over
    target = {s: round(epochs * total[s] if s in capped else unit * w[s], 6) for s in sources}
    each = max(1, math.ceil(sum(total.values()) * share / (shards * mixing.BLOCKS_A_SHARD)))
    sequence = {}  # drawn blocks of each source, in order
    for k, s in enumerate(sources):
        order = sorted((i for i, r in enumerate(rows) if r[2] == s), key=lambda i: (md5(seed, "" if rows[i][0] is None else rows[i][0]), rows[i][0] is not None, rows[i][0] or 0, size[i], hashlib.md5((rows[i][1] or "").encode()).hexdigest()))
        blocks, before = defaultdict(list), 0
        for i in order:
            if size[i]:
                blocks[before // each].append(i)
            before += size[i]
        drawn, start = [], 0
        for copy in range(math.ceil(epochs)):
            for b in sorted(blocks, key=lambda b: (md5(seed, copy, k, b), b)):  # noqa: B023
                if start < target[s]:
                    drawn.append((copy, blocks[b], start))
                start += sum(size[i] for i in blocks[b])
        if drawn:
            sequence[s] = drawn
    kept = [s for s in sources if s in sequence]
    quota = mixing.splitting_tree([len(sequence[s]) for s in kept], shards, seed)
    out = []
    for s, own in zip(kept, quota):
        owners = [shard for shard, n in enumerate(own) for _ in range(n)]
        for (copy, members, at), shard in zip(sequence[s], owners):
            for i in members:
                wanted = target[s] - at
                n = (size[i] if 2 * wanted >= size[i] else 0) if whole else max(0, min(size[i], math.floor(wanted)))
                at += size[i]
                if n:
                    out.append((i, copy, n, shard))
    return size, target, out


@pytest.mark.parametrize("whole", [False, True])
def test_mix_against_plain_version(spark, docs, corpus, whole):
    rows = sorted(((d, t, s) for d, t, _, s, *_ in corpus), key=lambda r: (str(r[0]), str(r[1])))
    size, target, want = plain_mix(rows, whole)
    _, taken = mixing.draws(docs, whole=whole)
    got = Counter((r.doc_id, r.source, r.copy, r.words, r.shard) for r in taken.collect())
    assert got == Counter((rows[i][0], rows[i][2], copy, n, shard) for i, copy, n, shard in want)
    per = Counter(r.shard for r in taken.select("shard", "block", "source").distinct().collect())
    assert max(per.values()) - min(per.values()) <= 2
    if not whole:
        sums = Counter()
        for i, _, n, _ in want:
            sums[rows[i][2]] += n
        assert all(target[s] - 1 <= sums[s] <= target[s] for s in target)


def test_mix_agrees_in_any_layout(spark):
    """Rows of one doc_id, of several sizes and texts."""
    r = random.Random(26)
    prose = lambda n: " ".join(r.choice("abcdefgh") * r.randint(1, 5) for _ in range(n))
    rows = [(7, prose(r.randint(1, 40)), "a") for _ in range(39)] + [(i, prose(20), "b") for i in range(30)] + [(7, None, "a"), (7, "", "b")]
    rows += rows[:3]
    results = []
    for k in (1, 2, 5, 7):
        r.shuffle(rows)
        df = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(k)
        results.append(Counter(tuple(x) for x in mixing.mixed(df).collect()))
    assert all(x == results[0] for x in results)


def test_shards_are_shuffled_runs(spark, docs):
    _, taken = mixing.draws(docs)
    rows = taken.collect()
    for s in {r.shard for r in rows}:
        assert sorted(r.place for r in rows if r.shard == s) == list(range(sum(r.shard == s for r in rows)))
