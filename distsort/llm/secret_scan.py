"""Secret scans: base patterns, then a character convolutional network over every candidate and its context.

Candidates are the findings of the base patterns and all maximal runs of 16 or more of A-Z a-z 0-9 + / _ = -, also those that base spans cover or
overlap.  The network scores every one.  Base spans stay whatever the score; a run that the network finds is one more span if no base span covers it
whole.  The network, in numpy, sees
windows of characters with a mark on the candidate: an embedding, one convolution, pooling, a
logistic output.  It is trained on labelled findings of two kinds, each in its context: all base findings of the documents (but
those of documents whose crc32(doc_id as text) mod 5 is 0, which are kept for measuring), in rounds: each task goes on from the common weights
over its findings, and the driver averages what comes back; and
random secrets of public shapes, and what resembles them, drawn from a seeded rule.  So that the drawn ones count however many findings there are, findings weigh as `labelled` of
them together at most.  A Platt scale fitted on a second part calibrates it; the threshold is the highest one with the
required recall on a third; of both parts all margins are counted, in cells of 1 / CELLS.  A candidate longer than a window is seen by several windows, and the highest counts.

Runs are found in whole columns of bytes at once; only texts with a keyword or a run reach per-text code.

Defined results: a null text is empty and has no findings; repeated rows are scanned each; a null doc_id is kept; an
empty table gives an empty result; only doc_id and text are read; texts of any length are scanned whole.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textkernel as tk
from .common import written

#: Fixed values of the contract.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
KEYWORDS = (b"password", b"passwd", b"secret", b"token", b"apikey", b"api_key")
ASSIGN_LEAST, ACCESS_LEAST, HEX_LEAST, RUN_LEAST = 6, 20, 24, 16
KINDS = ("assign", "access", "hex", "cnn")

WINDOW, LEFT, RIGHT = 64, 20, 8
INSIDE = WINDOW - LEFT - RIGHT
SYMBOLS = "\0 abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789+/_=-.:\"'@,()\n"
RECALL = 0.97
#: All base findings of the documents weigh as so many drawn ones at most.
LABELLED = 2000
#: Rounds of training, and cells of margins between two whole numbers; margins beyond FAR count as that.
ROUNDS, CELLS, FAR = 8, 1024, 64


def _table(chars: str) -> np.ndarray:
    out = np.zeros(256, dtype=bool)
    out[[ord(c) for c in chars]] = True
    return out


_DIGITS, _LETTERS = "0123456789", "abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ"
_RUN, _HEX, _UPPER = _table(_LETTERS + _DIGITS + "+/_=-"), _table(_DIGITS + "abcdef"), _table(_LETTERS[26:] + _DIGITS)
_CODE = np.full(0x250, len(SYMBOLS), dtype=np.int64)
for _i, _c in enumerate(SYMBOLS):
    _CODE[ord(_c)] = _i


def encoded(left: str, run: str, right: str) -> list[np.ndarray]:
    """Symbol numbers of the windows of a candidate; those of the run are in a second alphabet."""
    out = []
    for i in range(0, len(run), INSIDE):
        piece = run[i : i + INSIDE]
        parts = left[-LEFT:].rjust(LEFT, "\0"), piece.ljust(INSIDE, "\0"), right[:RIGHT].ljust(RIGHT, "\0")
        codes = _CODE[np.minimum(np.frombuffer("".join(parts).encode("utf-32-le"), dtype=np.uint32), 0x24F)]
        codes[LEFT : LEFT + len(piece)] += len(SYMBOLS) + 1
        out.append(codes)
    return out


class CharNet:
    """Embedding, convolution of width 5, ReLU, mean and maximum over places, logistic."""

    def __init__(self, seed: int = 5, dims: int = 8, filters: int = 16, width: int = 5) -> None:
        rng = np.random.default_rng(seed)
        self.width = width
        self.w = {"e": rng.normal(0, 0.3, (2 * (len(SYMBOLS) + 1), dims)), "k": rng.normal(0, (width * dims) ** -0.5, (width * dims, filters)), "b": np.zeros(filters), "v": rng.normal(0, 0.2, 2 * filters), "c": np.zeros(1)}
        self.scale = (1.0, 0.0)
        self.threshold = 0.5

    def _forward(self, x: np.ndarray) -> tuple:
        w, n = self.w, x.shape[1] - self.width + 1
        e = w["e"][x]
        cols = np.concatenate([e[:, k : k + n] for k in range(self.width)], axis=2)
        a = np.maximum(cols @ w["k"] + w["b"], 0)
        top = a.argmax(axis=1)
        pooled = np.concatenate([a.mean(axis=1), np.take_along_axis(a, top[:, None], 1)[:, 0]], axis=1)
        return cols, a, top, pooled, pooled @ w["v"] + w["c"]

    def flat(self) -> np.ndarray:
        """All weights in a row."""
        return np.concatenate([self.w[k].reshape(-1) for k in sorted(self.w)])

    def load(self, flat: np.ndarray) -> None:
        at = 0
        for k in sorted(self.w):
            self.w[k] = flat[at : at + self.w[k].size].reshape(self.w[k].shape).copy()
            at += self.w[k].size

    def margin(self, x: np.ndarray) -> np.ndarray:
        return np.concatenate([self._forward(x[i : i + 2048])[4] for i in range(0, len(x), 2048)]) if len(x) else np.zeros(0)

    def score(self, x: np.ndarray) -> np.ndarray:
        a, b = self.scale
        return 1 / (1 + np.exp(-(a * self.margin(x) + b)))

    def fit(self, x: np.ndarray, y: np.ndarray, epochs: int = 8, batch: int = 64, rate: float = 0.01, seed: int = 6, weight: np.ndarray | None = None) -> None:
        rng, w = np.random.default_rng(seed), self.w
        m, v = ({k: np.zeros_like(a) for k, a in w.items()} for _ in range(2))
        t = 0
        for _ in range(epochs):
            for at in np.array_split(rng.permutation(len(x)), max(1, len(x) // batch)):
                cols, a, top, pooled, z = self._forward(x[at])
                n, f = a.shape[1], a.shape[2]
                g = (1 / (1 + np.exp(-z)) - y[at]) / len(at)
                g = g if weight is None else g * weight[at]
                back = g[:, None] * w["v"]
                da = np.repeat(back[:, None, :f] / n, n, axis=1)
                np.put_along_axis(da, top[:, None], np.take_along_axis(da, top[:, None], 1) + back[:, None, f:], 1)
                da *= a > 0
                dcols = (da @ w["k"].T).reshape(len(at), n, self.width, -1)
                de = np.zeros_like(w["e"])
                for k in range(self.width):
                    np.add.at(de, x[at][:, k : k + n], dcols[:, :, k])
                grad = {"e": de, "k": np.einsum("ijk,ijl->kl", cols, da, optimize=True), "b": da.sum((0, 1)), "v": pooled.T @ g, "c": np.array([g.sum()])}
                t += 1
                for key, d in grad.items():
                    m[key] = 0.9 * m[key] + 0.1 * d
                    v[key] = 0.999 * v[key] + 0.001 * d * d
                    w[key] -= rate * (m[key] / (1 - 0.9**t)) / (np.sqrt(v[key] / (1 - 0.999**t)) + 1e-8)

    def calibrate(self, z: np.ndarray, y: np.ndarray, weight: np.ndarray) -> None:
        """Platt's scale of margins by Newton steps."""
        a, b, true = 1.0, 0.0, (weight * (y > 0)).sum()
        goal = np.where(y > 0, (true + 1) / (true + 2), 1 / (weight.sum() - true + 2))
        for _ in range(50):
            p = 1 / (1 + np.exp(-np.clip(a * z + b, -30, 30)))
            s, d = (p * (1 - p) + 1e-9) * weight, (p - goal) * weight
            hessian = np.array([[(s * z * z).sum() + 1e-6, (s * z).sum()], [(s * z).sum(), s.sum() + 1e-6]])
            da, db = np.linalg.solve(hessian, [(d * z).sum(), d.sum()])
            a, b = a - da, b - db
        self.scale = (float(a), float(b))

    def constrain(self, z: np.ndarray, weight: np.ndarray, recall: float) -> None:
        """The highest threshold that finds at least this share of the true findings, of which z are the margins."""
        a, b = self.scale
        score = 1 / (1 + np.exp(-(a * z + b)))
        order = np.argsort(score, kind="stable")
        upto = np.cumsum(weight[order])
        self.threshold = float(score[order[min(len(z) - 1, int(np.searchsorted(upto, upto[-1] * (1 - recall), side="right")))]])


def labelled_findings(n: int, seed: int) -> tuple[list[tuple[str, str, str]], np.ndarray]:
    """(left, run, right) and labels: half secrets of public shapes, half of what resembles them."""
    rng = np.random.default_rng(seed)
    pick = lambda chars, k: "".join(rng.choice(list(chars), k))
    upper, lower, both = _LETTERS[26:], _LETTERS[:26], _LETTERS + _DIGITS
    word = lambda: pick(lower, int(rng.integers(2, 9)))
    num = lambda k: pick(_DIGITS, k)
    true = (
        lambda: pick(both, int(rng.integers(20, 65))),
        lambda: pick(both + "+/", 40),
        lambda: pick(both + "+/", int(rng.integers(22, 60))) + "==",
        lambda: "ghp_" + pick(both, 36),
        lambda: "sk_live_" + pick(both, 24),
        lambda: "AIza" + pick(both + "_-", 35),
        lambda: f"xoxb-{num(11)}-{num(12)}-{pick(both, 24)}",
        lambda: "eyJ" + pick(both + "_-", int(rng.integers(30, 90))),
        lambda: pick(upper + _DIGITS, int(rng.integers(24, 41))),
        lambda: pick("0123456789ABCDEF", int(rng.integers(32, 65))),
    )
    false = (
        lambda: "-".join(word() for _ in range(int(rng.integers(3, 7)))) + "-" + num(int(rng.integers(1, 5))),
        lambda: "_".join(word() for _ in range(int(rng.integers(3, 7)))) + num(2),
        lambda: "/".join(word() for _ in range(int(rng.integers(3, 7)))) + "/" + num(4),
        lambda: word() + word() + word() + num(int(rng.integers(1, 5))),
        lambda: f"2{num(3)}-0{num(1)}-1{num(1)}T1{num(1)}",
        lambda: word().upper() + "-" + "-".join(num(4) for _ in range(4)),
        lambda: f"{word()}{num(2)}-{word()}{num(1)}-{word()}{num(2)}/{word()}",
        lambda: "=" * int(rng.integers(14, 30)) + num(2) + word(),
        lambda: (word() + num(1)) * 4,
        lambda: word().capitalize() + word().capitalize() + word().capitalize() + word().capitalize() + num(1),
    )
    before = ('key = "', "auth: ", "Bearer ", "pwd=", "credential ", "", "see ", "id ", "the ", "file ", "(")
    rows, labels = [], np.zeros(n)
    for i in range(n):
        labels[i] = i % 2
        kinds = true if labels[i] else false
        run = kinds[int(rng.integers(len(kinds)))]()
        run = run if len(run) >= RUN_LEAST else (run * 8)[: RUN_LEAST + 2]
        left = " ".join(word() for _ in range(3)) + " " + before[int(rng.integers(len(before)))]
        rows.append((left, run, ('" ' if rng.random() < 0.3 else " ") + word()))
    return rows, labels


def _drawn(n: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """Windows of drawn findings, and their labels."""
    rows, y = labelled_findings(n, seed)
    windows = [encoded(*r) for r in rows]
    return np.array([w for ws in windows for w in ws]), np.repeat(y, [len(w) for w in windows])


def trained(n: int = 2400, seed: int = 11, recall: float = RECALL, found: DataFrame | None = None, labelled: int = LABELLED) -> CharNet:
    """The network; found: left, run, right and fold (0 to 4) of true findings, of which three fifths are learned from and a fifth each calibrates and sets the threshold."""
    net, (x, y), *rest = CharNet(), _drawn(n, seed), _drawn(n // 2, seed + 1), _drawn(n // 2, seed + 2)
    for k in range(ROUNDS if found is not None else 0):
        parts = found.where("fold < 3").mapInArrow(_round(net, x, y, 3 * labelled / 5, 6 + k), "rows long, weights binary").collect()  # one row for each task
        if not parts:
            found = None  # nothing to learn from but what is drawn
            break
        share = np.array([r["rows"] for r in parts], dtype=np.float64)
        flat = np.average([np.frombuffer(r["weights"], dtype=np.float64) for r in parts], axis=0, weights=share)
        net.load(flat)
    if found is None:
        net.fit(x, y, ROUNDS)
    cells = [] if found is None else found.where("fold >= 3").mapInArrow(_margins(net), "fold long, cell long").groupBy("fold", "cell").count().collect()  # 2 * 2 * FAR * CELLS rows at most
    for fold, (x, y) in zip((3, 4), rest):
        own = sorted((r["cell"], r["count"]) for r in cells if r["fold"] == fold)
        m = np.array([c for _, c in own], dtype=np.float64)
        z = np.concatenate([net.margin(x), np.array([c for c, _ in own], dtype=np.float64) / CELLS])
        weight = np.concatenate([np.ones(len(x)), m * min(1.0, labelled / 5 / max(1.0, m.sum()))])
        y = np.concatenate([y, np.ones(len(own))])
        if fold == 3:
            net.calibrate(z, y, weight)
        else:
            net.constrain(z[y > 0], weight[y > 0], recall)
    return net


def _encoded(batch: pa.RecordBatch) -> list[list[np.ndarray]]:
    return [encoded(*x) for x in zip(*[batch.column(c).to_pylist() for c in ("left", "run", "right")])]


def _round(net: CharNet, x: np.ndarray, y: np.ndarray, most: float, seed: int):
    """One pass of a task over its findings and the drawn ones x, y, from net's weights; its findings weigh as `most` drawn ones at most."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = [w for batch in batches for ws in _encoded(batch) for w in ws]
        if own:
            weight = np.concatenate([np.ones(len(x)), np.full(len(own), min(1.0, most / len(own)))])
            net.fit(np.concatenate([x, np.array(own)]), np.concatenate([y, np.ones(len(own))]), 1, seed=seed, weight=weight)
            yield pa.RecordBatch.from_arrays([pa.array([len(own)]), pa.array([net.flat().tobytes()], pa.binary())], ["rows", "weights"])

    return run


def _margins(net: CharNet):
    """The fold of each window of a finding, and the cell that its margin is in."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                windows = _encoded(batch)
                z = np.clip(net.margin(np.array([w for ws in windows for w in ws])), -FAR, FAR)
                fold = np.repeat(batch.column("fold").to_numpy(zero_copy_only=False), [len(w) for w in windows])
                yield pa.RecordBatch.from_arrays([pa.array(fold, pa.int64()), pa.array(np.floor(z * CELLS).astype(np.int64))], ["fold", "cell"])

    return run


def _runs(inside: np.ndarray, at: np.ndarray, least: int) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the maximal runs within one text of at least so many bytes."""
    n = len(inside)
    edge = np.zeros(n + 1, dtype=bool)
    edge[at] = True
    first = inside.copy()
    first[1:] &= ~inside[:-1] | edge[1:n]
    last = inside.copy()
    last[:-1] &= ~inside[1:] | edge[1:n]
    starts, ends = np.flatnonzero(first), np.flatnonzero(last) + 1
    long_ = ends - starts >= least
    return starts[long_], ends[long_]


def _lowered(data: np.ndarray) -> bytes:
    return data.tobytes().lower()  # bytes.lower touches A-Z only


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind, end) by the base patterns, of one text; the plain form that whole columns are tested against."""
    out = [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m.group(2)) >= ASSIGN_LEAST]
    out += [(m.start(), 1, m.end()) for m in re.finditer("AKIA[A-Z0-9]+", text) if m.end() - m.start() >= ACCESS_LEAST]
    out += [(m.start(), 2, m.end()) for m in re.finditer("[0-9a-f]+", text) if m.end() - m.start() >= HEX_LEAST]
    return sorted(out)


def _candidates(data: np.ndarray, at: np.ndarray) -> tuple[dict[int, list], list]:
    """Base spans (start, kind, end) by text, and all candidates (text, base span or None, start, end, left, run, right); places are code points."""
    lowered, owners = _lowered(data), set()
    for word in KEYWORDS:
        i = lowered.find(word)
        while i >= 0:
            k = int(np.searchsorted(at, i, side="right")) - 1
            owners.add(k)
            i = lowered.find(word, int(at[k + 1]) - len(word) + 1 if at[k + 1] > i + len(word) else i + 1)
    spans: dict[int, list] = {}
    asked: list[tuple] = []
    whole: dict[int, str] = {}

    def text_of(k):
        if k not in whole:
            whole[k] = data[at[k] : at[k + 1]].tobytes().decode()
        return whole[k]

    def points(k, s, e):
        """Code points of a run of ASCII bytes."""
        lead = int(np.count_nonzero((data[at[k] : s] & 0xC0) != 0x80))
        return lead, lead + int(e - s)

    def ask(k, span, lo, hi):
        t = text_of(k)
        asked.append((k, span, lo, hi, t[max(0, lo - LEFT) : lo], t[lo:hi], t[hi : hi + RIGHT]))

    def based(k, span, lo, hi):
        spans.setdefault(k, []).append(span)
        ask(k, span, lo, hi)

    for k in sorted(owners):
        for m in ASSIGN.finditer(text_of(k)):
            if len(m.group(2)) >= ASSIGN_LEAST:
                based(k, (m.start(), 0, m.end()), *m.span(2))
    s, e = _runs(_HEX[data], at, HEX_LEAST)
    for k, a, b in zip(np.searchsorted(at, s, side="right") - 1, s, e):
        lo, hi = points(k, a, b)
        based(int(k), (lo, 2, hi), lo, hi)
    s, e = _runs(_UPPER[data], at, ACCESS_LEAST)
    for k, a, b in zip(np.searchsorted(at, s, side="right") - 1, s, e):
        i = data[a:b].tobytes().find(b"AKIA")
        if i >= 0 and b - a - i >= ACCESS_LEAST:
            lo, hi = points(k, a + i, b)
            based(int(k), (lo, 1, hi), lo, hi)
    s, e = _runs(_RUN[data], at, RUN_LEAST)
    for k, a, b in zip(np.searchsorted(at, s, side="right") - 1, s, e):
        lo, hi = points(k, a, b)
        ask(int(k), None, lo, hi)
    return spans, asked


def _scanned(net: CharNet):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, j, data, at in tk.slices(batch.column("text")):
                spans, asked = _candidates(data, at)
                known: dict[tuple, float] = {}
                n_asked = np.zeros(j - i, np.int64)
                if asked:
                    windows = [encoded(*x[4:]) for x in asked]
                    scores = net.score(np.array([w for ws in windows for w in ws]))
                    best = np.maximum.reduceat(scores, np.cumsum([0] + [len(w) for w in windows[:-1]]))
                    np.add.at(n_asked, [x[0] for x in asked], 1)
                    for (k, span, lo, hi, *_), score in zip(asked, best):
                        if span is not None:
                            known[(k, *span)] = score
                        elif score >= net.threshold and not any(a <= lo and hi <= b for a, kind, b in spans.get(k, ()) if kind < 3):
                            spans.setdefault(k, []).append((lo, 3, hi))
                            known[(k, lo, 3, hi)] = score
                counts, digests, all_, said_scores = np.zeros((3, j - i), np.int64), [], [], []
                none = hashlib.sha256(b"").hexdigest()
                for k in range(j - i):
                    own = sorted(spans.get(k, ()))
                    if not own:
                        digests.append(none), all_.append(""), said_scores.append("")
                        continue
                    for x in own:
                        if x[1] < 3:
                            counts[x[1], k] += 1
                    said = [(x[1], f"{KINDS[x[1]]}:{x[0]}:{x[2]}") for x in own]
                    digests.append(hashlib.sha256(",".join(s for kind, s in said if kind < 3).encode()).hexdigest())
                    all_.append(",".join(s for _, s in said))
                    said_scores.append(",".join(f"{known[(k, *x)]:.4f}" for x in own))
                columns = [*[pa.array(c) for c in counts], *[pa.array(x, pa.string()) for x in (digests, all_, said_scores)], pa.array(n_asked)]
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(i, j - i), *columns], ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans", "scores", "n_candidates"])

    return run


def _found(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        ids = batch.column("doc_id")
        for i, _, data, at in tk.slices(batch.column("text")):
            base = [x for x in _candidates(data, at)[1] if x[1] is not None]
            where = pa.array([i + x[0] for x in base], pa.int64())
            yield pa.RecordBatch.from_arrays([ids.take(where), pa.array([x[2] for x in base], pa.int64()), *[pa.array([x[k] for x in base], pa.string()) for k in (4, 5, 6)]], ["doc_id", "start", "left", "run", "right"])


def base_findings(docs: DataFrame, kept_apart: bool = False) -> DataFrame:
    """doc_id, start, left, run, right: what the base patterns find in the documents that are learned from, or in those that are kept apart."""
    kind = dict(docs.dtypes)["doc_id"]
    apart = F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0, F.lit(False))
    return docs.where(apart if kept_apart else ~apart).select("doc_id", "text").mapInArrow(_found, f"doc_id {kind}, start long, left string, run string, right string")


def folded(docs: DataFrame) -> DataFrame:
    """The base findings that are learned from, and the fold of each."""
    names = ("left", "run", "right")
    return base_findings(docs).select("doc_id", *names, F.pmod(F.xxhash64("doc_id", "start", *names), F.lit(5)).alias("fold"))


def learned(docs: DataFrame, labelled: int = LABELLED) -> CharNet:
    """The network, trained on all base findings of docs that aren't kept apart and on drawn ones; labelled: what the former weigh at most."""
    return trained(found=written(folded(docs).drop("doc_id"), "findings"), labelled=labelled)


def scan(docs: DataFrame, net: CharNet | None = None) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans, scores (of the spans, in their order), n_candidates, for every document."""
    kind = dict(docs.dtypes)["doc_id"]
    return docs.select("doc_id", "text").mapInArrow(_scanned(net or learned(docs)), f"doc_id {kind}, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, scores string, n_candidates long")
