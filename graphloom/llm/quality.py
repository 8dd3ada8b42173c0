"""Quality classifier: histogram gradient-boosted trees over document statistics.

Statistics of whole texts are array passes over the bytes of many documents at once. Trees are grown
level by level on binned columns and stored flat (feature, threshold and leaf arrays), so that scoring
is a few numpy gathers for a whole batch. The training sample is bounded by a parameter; everything
that is scored is scored whole.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphloom.llm.common import arrow_rows, by_bytes, joined_bytes, lean
from graphloom.llm.shingles import U, mix, word_hashes

NAMES = (
    "log_bytes log_words word_length longest_word upper digits stops symbols marks spaces breaks foreign "
    "distinct_words top_word distinct_pairs again symbol_words capital_words repeated_lines"
).split()
TRAIN_ROWS = 20_000
_SLICE = 1 << 20


def _table(chars: str) -> np.ndarray:
    t = np.zeros(256, bool)
    t[list(chars.encode())] = True
    return t


_CLASS = {
    "upper": _table("ABCDEFGHIJKLMNOPQRSTUVWXYZ"),
    "letter": _table("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz"),
    "digits": _table("0123456789"),
    "stops": _table(".,;:"),
    "symbols": _table("#$%&*@^~|<>{}[]\\/+=_`"),
    "marks": _table("!?"),
    "spaces": _table(" \t\n\v\f\r"),
    "breaks": _table("\n"),
}
_CLASS["foreign"] = np.arange(256) > 127


def statistics(column: pa.Array) -> np.ndarray:
    """One row of NAMES a text. Empty texts are all zeros."""
    data, offsets = joined_bytes(column)
    out = np.zeros((len(offsets) - 1, len(NAMES)))
    lo, n = 0, len(offsets) - 1
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + _SLICE, "right")) - 1)
        cut = offsets[lo : hi + 1]
        with np.errstate(over="ignore"):
            _fill(data[cut[0] : cut[-1]], cut - cut[0], out[lo:hi])
        lo = hi
    return out


def _fill(data: np.ndarray, offsets: np.ndarray, out: np.ndarray) -> None:
    size = np.diff(offsets)
    count = {}
    for name, t in _CLASS.items():
        sums = np.zeros(len(data) + 1, np.int64)
        np.cumsum(t[data], out=sums[1:])
        count[name] = sums[offsets[1:]] - sums[offsets[:-1]]
    words, at, start, end = word_hashes(data, offsets)
    n = np.diff(at)
    length = end - start
    tail_symbol = (_CLASS["symbols"] | _CLASS["marks"])[data[end - 1]] if len(end) else np.zeros(0, bool)
    capital = _CLASS["upper"][data[start]] if len(start) else np.zeros(0, bool)
    pairs = mix(words[:-1] * U(31) + words[1:]) if len(words) > 1 else np.zeros(0, U)
    rows = zip(range(len(size)), size.tolist(), n.tolist(), at[:-1].tolist(), at[1:].tolist(), strict=True)
    for i, bytes_, m, a, b in rows:
        if not bytes_:
            continue
        w, f = max(m, 1), out[i]
        f[0], f[1] = np.log1p(bytes_), np.log1p(m)
        if m:
            f[2], f[3] = length[a:b].mean(), np.log1p(length[a:b].max())
            ordered = np.sort(words[a:b])
            change = np.flatnonzero(ordered[1:] != ordered[:-1]) + 1
            runs = np.diff(np.r_[0, change, m])
            f[12], f[13] = len(runs) / m, runs.max() / m
            f[16], f[17] = tail_symbol[a:b].mean(), capital[a:b].mean()
            if m > 1:
                f[14] = len(np.unique(pairs[a : b - 1])) / (m - 1)
                f[15] = (words[a + 1 : b] == words[a : b - 1]).mean()
        f[4] = count["upper"][i] / max(count["letter"][i], 1)
        for k, name in ((5, "digits"), (6, "stops"), (7, "symbols"), (8, "marks"), (9, "spaces"), (11, "foreign")):
            f[k] = count[name][i] / bytes_
        f[10] = count["breaks"][i] / w
        if count["breaks"][i] > 0:
            lines = [x for x in data[offsets[i] : offsets[i + 1]].tobytes().split(b"\n") if x.strip()]
            f[18] = 1 - len(set(lines)) / max(len(lines), 1)


@dataclass
class BoostedTrees:
    """Complete binary trees of one depth, flat: inner nodes in heap order, then leaves."""

    base: float
    feature: np.ndarray
    threshold: np.ndarray
    leaf: np.ndarray

    def margin(self, x: np.ndarray) -> np.ndarray:
        out = np.full(len(x), self.base)
        rows = np.arange(len(x))
        inner = self.feature.shape[1]
        for feature, threshold, leaf in zip(self.feature, self.threshold, self.leaf, strict=True):
            at = np.zeros(len(x), np.int64)
            for _ in range(inner.bit_length()):
                at = 2 * at + 1 + (x[rows, feature[at]] > threshold[at])
            out += leaf[at - inner]
        return out

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-self.margin(x)))

    def scorer(self):
        return lambda column: self.score(statistics(column))


def grow(x: np.ndarray, y: np.ndarray, trees: int = 80, depth: int = 4, rate: float = 0.15, bins: int = 64, ridge: float = 1.0, least: float = 4.0) -> BoostedTrees:
    """Fit logistic loss. Without both labels the score is the label's share, 0.5 without rows."""
    share = float(np.clip(y.mean() if len(y) else 0.5, 0.01, 0.99))
    base, inner = float(np.log(share / (1 - share))), (1 << depth) - 1
    feature, threshold, leaf = [], [], []
    if len(np.unique(y)) == 2:
        cuts = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, bins + 1)[1:-1])) for f in range(x.shape[1])]
        code = np.stack([np.searchsorted(c, x[:, f], "left") for f, c in enumerate(cuts)], axis=1)
        margin = np.full(len(y), base)
        for _ in range(trees):
            p = 1 / (1 + np.exp(-margin))
            grad, hess = p - y, p * (1 - p)
            at = np.zeros(len(y), np.int64)
            fs, ts = np.zeros(inner, np.int64), np.full(inner, np.inf)
            for level in range(depth):
                first, width = (1 << level) - 1, 1 << level
                best = np.full(width, 1e-6)
                for f, c in enumerate(cuts):
                    if not len(c):
                        continue
                    key = (at - first) * (bins + 1) + code[:, f]
                    g = np.bincount(key, grad, width * (bins + 1)).reshape(width, -1).cumsum(axis=1)
                    h = np.bincount(key, hess, width * (bins + 1)).reshape(width, -1).cumsum(axis=1)
                    gl, hl, gt, ht = g[:, : len(c)], h[:, : len(c)], g[:, -1:], h[:, -1:]
                    gain = gl**2 / (hl + ridge) + (gt - gl) ** 2 / (ht - hl + ridge) - gt**2 / (ht + ridge)
                    gain[(hl < least) | (ht - hl < least)] = 0
                    pick = gain.argmax(axis=1)
                    better = gain[np.arange(width), pick] > best
                    best = np.where(better, gain[np.arange(width), pick], best)
                    fs[first : first + width] = np.where(better, f, fs[first : first + width])
                    ts[first : first + width] = np.where(better, c[pick], ts[first : first + width])
                at = 2 * at + 1 + (x[np.arange(len(y)), fs[at]] > ts[at])
            g = np.bincount(at - inner, grad, inner + 1)
            h = np.bincount(at - inner, hess, inner + 1)
            values = -rate * g / (h + ridge)
            margin += values[at - inner]
            feature.append(fs)
            threshold.append(ts)
            leaf.append(values)
    return BoostedTrees(base, np.array(feature, np.int64).reshape(-1, inner), np.array(threshold).reshape(-1, inner), np.array(leaf).reshape(-1, inner + 1))


def in_fold(doc_id) -> object:
    """The held-out fold: crc32 of the id as text, modulo 5, is 0."""
    return F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0


def training_ids(labels: DataFrame, label: str, rows: int) -> DataFrame:
    """A sample of at most `rows` labelled ids outside the held-out fold, decided by the hash of the id."""
    usable = labels.where(labels[label].isNotNull() & labels["doc_id"].isNotNull() & ~in_fold(labels["doc_id"]))
    return usable.select(labels["doc_id"].cast("bigint").alias("doc_id"), labels[label].cast("int").alias("label")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)


def fit_quality(docs: DataFrame, labels: DataFrame, rows: int = TRAIN_ROWS) -> BoostedTrees:
    """Fit on the bounded sample; its statistics (not its texts) come to the driver."""
    schema = "label int, x binary"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                yield arrow_rows(schema, {"label": b.column(0), "x": [r.tobytes() for r in statistics(b.column(1))]})

    sample = F.broadcast(training_ids(labels, "quality", rows))
    found = by_bytes(docs).select(docs["doc_id"].cast("bigint").alias("doc_id"), docs["text"]).join(sample, "doc_id").select("label", "text").mapInArrow(lean(run), schema)
    got = sorted((r.label, bytes(r.x)) for r in found.collect())
    x = np.frombuffer(b"".join(r[1] for r in got), float).reshape(-1, len(NAMES))
    return grow(x, np.array([r[0] for r in got], float))


SCORED = "doc_id bigint, score double"


def score_quality(docs: DataFrame, model: BoostedTrees) -> DataFrame:
    """(doc_id, score) of each row of docs; null and empty texts are scored as empty."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield arrow_rows(SCORED, {"doc_id": b.column(0), "score": model.score(statistics(b.column(1)))})

    return by_bytes(docs).select(docs["doc_id"].cast("bigint"), docs["text"]).mapInArrow(lean(run), SCORED)


def judge(scored: DataFrame, least: float) -> DataFrame:
    """doc_id, held_out, score, predicted from (doc_id, score)."""
    return scored.select("doc_id", F.coalesce(in_fold(F.col("doc_id")), F.lit(False)).alias("held_out"), "score", (F.col("score") >= least).cast("int").alias("predicted"))


def classify_quality(docs: DataFrame, labels: DataFrame, least: float = 0.3) -> DataFrame:
    """One row a document: higher scores are likelier quality 1. Repeated rows repeat; extra columns are not read."""
    return judge(score_quality(docs, fit_quality(docs, labels)), least)
