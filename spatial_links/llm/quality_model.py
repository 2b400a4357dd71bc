"""Quality classifier: random Fourier features of document statistics, ridge scores, isotonic calibration.

Statistics of every whole text are computed in one pass. Random Fourier features approximate a Gaussian kernel over
them; the partitions' normal equations are summed (in two steps, so that no task holds many of them) and solved on the
driver, whose work depends on the number of features alone. Scores are then calibrated by isotonic regression on
training rows whose scores come from models that did not see them (`FOLDS` folds), binned to `BINS` bins, so calibration, too, is
a bounded sum over all of them. Every labelled training row is used; there is no sample.

Null and empty texts have zero statistics and get a score like any other. Labels that are null are not learned from;
repeated rows count as often as they stand. With no labels at all, or of one class only, the score is their mean (0.5 without any).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spatial_links.llm import textops as T
from spatial_links.llm.common import materialise

DIM, GAMMA, RIDGE, FOLDS, BINS, SEED, THRESHOLD = 256, 0.08, 1e-3, 4, 512, 17, 0.7
STATS = (
    "log_words", "log_bytes", "word_length", "word_length_sd", "letter_share", "upper_share", "digit_share", "space_share", "symbol_share", "mark_share", "bang_share", "pipe_share", "high_share", "line_words", "lines",
    "stop_end_share", "upper_word_share", "symbol_word_share", "one_char_share", "distinct_share", "dup_line_share", "byte_entropy", "longest_word", "sentence_words", "title_share",
)


def _class(chars: bytes) -> np.ndarray:
    x = np.zeros(256)
    x[list(chars)] = 1
    return x


_UP = _class(bytes(range(65, 91)))
_LOW = _class(bytes(range(97, 123)))
_DIGIT = _class(bytes(range(48, 58)))
_SYMBOL = _class(b"#*$%&|<>@^~_=+\\{}[]")
_MARK = _class(b".,;:?'\"()-")


def statistics(raw: np.ndarray, off: np.ndarray) -> np.ndarray:
    """A row of STATS for each document of a block."""
    m = len(off) - 1
    size = np.diff(off).astype(float)
    own = np.repeat(np.arange(m), np.diff(off))
    total = lambda values: np.bincount(own, weights=values, minlength=m)
    high = (raw >= 128).astype(float)
    up, low = total(_UP[raw]), total(_LOW[raw])
    start, end, doc = T.words(raw, off)
    per = lambda values=None: np.bincount(doc, weights=values, minlength=m)
    n = per()
    length = (end - start).astype(float)
    some = np.maximum(n, 1)
    bytes_ = np.maximum(size, 1)
    first, last = (raw[start], raw[end - 1]) if len(start) else (raw[:0], raw[:0])
    sums = lambda table: np.concatenate([[0.0], np.cumsum(table[raw])])
    inside = lambda c: c[end] - c[start]
    low_sum, up_sum = sums(_LOW), sums(_UP)
    upper_word = (inside(up_sum) > 1) & (inside(low_sum) == 0)
    title = (_UP[first] > 0) & (inside(low_sum) > 0)
    symbol_word = (_SYMBOL[last] > 0) | (_SYMBOL[first] > 0)
    stop = np.isin(last, np.frombuffer(b".!?", np.uint8))
    key = T.span_hash(raw, start, end)
    order = np.lexsort((key, doc))
    new = np.ones(len(key), bool)
    new[1:] = (key[order][1:] != key[order][:-1]) | (doc[order][1:] != doc[order][:-1])
    distinct = np.bincount(doc[order][new], minlength=m)
    mean = per(length) / some
    sd = np.sqrt(np.maximum(per(length**2) / some - mean**2, 0))
    longest = np.zeros(m)
    np.maximum.at(longest, doc, length)
    ls, le, ld = T.lines(raw, off)
    n_lines = np.bincount(ld, minlength=m)
    lk = T.span_hash(raw, ls, le)
    order = np.lexsort((lk, ld))
    same = np.zeros(len(lk), bool)
    same[1:] = (lk[order][1:] == lk[order][:-1]) & (ld[order][1:] == ld[order][:-1])
    dup = np.bincount(ld[order][same], minlength=m)
    counts = np.zeros((m, 64))
    np.add.at(counts, (own, raw >> 2), 1)
    p = counts / bytes_[:, None]
    entropy = -(p * np.log2(np.where(p > 0, p, 1))).sum(1)
    stops = per(stop.astype(float))
    cols = [
        np.log1p(n), np.log1p(size), mean, sd, (up + low + total(high)) / bytes_, up / bytes_, total(_DIGIT[raw]) / bytes_, total(T.SPACE[raw].astype(float)) / bytes_, total(_SYMBOL[raw]) / bytes_, total(_MARK[raw]) / bytes_,
        total((raw == 33).astype(float)) / bytes_, total((raw == 124).astype(float)) / bytes_, total(high) / bytes_, np.log1p(n / n_lines), np.log1p(n_lines),
        stops / some, per(upper_word.astype(float)) / some, per(symbol_word.astype(float)) / some, per((length == 1).astype(float)) / some, distinct / some, dup / n_lines, entropy, np.log1p(longest), np.log1p(n / np.maximum(stops, 1)), per(title.astype(float)) / some,
    ]
    return np.column_stack(cols).astype(np.float32)


def _statistics(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for rows, raw, off in T.blocks(batches):
        x = statistics(raw, off)
        yield pa.RecordBatch.from_arrays([rows.column(0), _rows(x)], names=["doc_id", "stats"])


def _rows(x: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * x.shape[1]), pa.array(np.ascontiguousarray(x, np.float32).ravel()))


def _matrix(column: pa.Array) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), len(STATS)).astype(float)


class Features:
    """Statistics, standardised, to random Fourier features."""

    def __init__(self, mean: np.ndarray, sd: np.ndarray, dim: int = DIM, gamma: float = GAMMA, seed: int = SEED):
        rng = np.random.default_rng(seed)
        self.mean, self.sd = mean, np.where(sd > 1e-9, sd, 1.0)
        self.w = rng.normal(0, np.sqrt(2 * gamma), (len(STATS), dim))
        self.b = rng.uniform(0, 2 * np.pi, dim)

    def __call__(self, stats: np.ndarray) -> np.ndarray:
        z = np.clip((stats - self.mean) / self.sd, -6, 6)
        wave = np.sqrt(2 / self.w.shape[1]) * np.cos(z @ self.w + self.b)
        return np.column_stack([wave, 0.3 * z, np.ones(len(z))])


def _equations(phi: Features):
    """A partition's sums of normal equations for each fold: fold, n, positive, binary of [gram | moment]."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[int, list] = {}
        for b in batches:
            x, y, fold = phi(_matrix(b.column(0))), b.column(1).to_numpy(zero_copy_only=False), b.column(2).to_numpy(zero_copy_only=False)
            for f in np.unique(fold):
                z, t = x[fold == f], y[fold == f].astype(float)
                part = [len(t), int(t.sum()), np.column_stack([z.T @ z, z.T @ t])]
                total[int(f)] = [p + q for p, q in zip(total[int(f)], part, strict=True)] if int(f) in total else part
        for f, (n, p, a) in total.items():
            yield pa.RecordBatch.from_arrays([pa.array([f], pa.int32()), pa.array([n], pa.int64()), pa.array([p], pa.int64()), pa.array([a.tobytes()], pa.binary())], names=["fold", "n", "positive", "sums"])

    return run


def _add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    total: dict[int, list] = {}
    for b in batches:
        for f, n, p, s in zip(*(c.to_pylist() for c in b.columns), strict=True):
            part = [n, p, np.frombuffer(s)]
            total[f] = [x + y for x, y in zip(total[f], part, strict=True)] if f in total else part
    for f, (n, p, a) in total.items():
        yield pa.RecordBatch.from_arrays([pa.array([f], pa.int32()), pa.array([n], pa.int64()), pa.array([p], pa.int64()), pa.array([a.tobytes()], pa.binary())], names=["fold", "n", "positive", "sums"])


_SUMS = "fold int, n long, positive long, sums binary"


def isotonic(weight: np.ndarray, hits: np.ndarray) -> np.ndarray:
    """Pool-adjacent-violators: the non-decreasing shares closest to hits / weight; bins without weight take their neighbours'."""
    blocks: list[list[float]] = []  # hits, weight, bins
    for w, h in zip(weight, hits, strict=True):
        blocks.append([float(h), float(w), 1])
        while len(blocks) > 1 and (not blocks[-1][1] or not blocks[-2][1] or blocks[-2][0] / blocks[-2][1] >= blocks[-1][0] / blocks[-1][1]):
            h2, w2, b2 = blocks.pop()
            blocks[-1] = [blocks[-1][0] + h2, blocks[-1][1] + w2, blocks[-1][2] + b2]
    return np.concatenate([np.full(int(b), h / w if w else 0.5) for h, w, b in blocks])


class Model:
    def __init__(self, phi: Features | None, weights: np.ndarray | None, shares: np.ndarray, constant: float):
        self.phi, self.weights, self.shares, self.constant = phi, weights, shares, constant

    def __call__(self, stats: np.ndarray) -> np.ndarray:
        if self.weights is None or not len(stats):
            return np.full(len(stats), self.constant)
        raw = self.phi(stats) @ self.weights
        centre = (np.arange(len(self.shares)) + 0.5) / len(self.shares) * 2 - 0.5
        # A little of the ridge score keeps the order inside a step.
        return np.clip(0.999 * np.interp(raw, centre, self.shares) + 0.001 * np.clip(raw, 0, 1), 0, 1)


def bin_of(raw: np.ndarray, bins: int) -> np.ndarray:
    return np.clip(((raw + 0.5) / 2 * bins).astype(np.int64), 0, bins - 1)


def fit(labelled: DataFrame, dim: int = DIM, gamma: float = GAMMA, ridge: float = RIDGE, folds: int = FOLDS, bins: int = BINS, seed: int = SEED) -> Model:
    """From (stats, label, fold) rows; folds are numbered from 0."""
    k = len(STATS)
    moments = labelled.agg(F.count(F.lit(1)), *(F.avg(F.get("stats", F.lit(i))) for i in range(k)), *(F.stddev_pop(F.get("stats", F.lit(i))) for i in range(k)), F.avg("label")).first()
    if not moments[0] or moments[-1] in (0.0, 1.0):
        return Model(None, None, np.zeros(1), float(moments[-1]) if moments[0] else 0.5)
    phi = Features(np.array(moments[1 : k + 1], float), np.array(moments[k + 1 : 2 * k + 1], float), dim, gamma, seed)
    sums = labelled.select("stats", "label", "fold").mapInArrow(_equations(phi), _SUMS)
    width = dim + k + 1
    parts = sums.repartition(16).mapInArrow(_add, _SUMS).coalesce(1).mapInArrow(_add, _SUMS).collect()
    by = {r.fold: (r.n, np.frombuffer(r.sums).reshape(width, width + 1)) for r in parts}
    n, every = sum(v[0] for v in by.values()), sum(v[1] for v in by.values())

    def solve(a: np.ndarray, rows: int) -> np.ndarray:
        return np.linalg.solve(a[:, :width] + ridge * max(rows, 1) * np.eye(width), a[:, width])

    without = {f: solve(every - a, n - m) for f, (m, a) in by.items()}
    binned = labelled.select("stats", "label", "fold").mapInArrow(_bins(phi, without, bins), "bin int, n long, hits long")
    weight, hits = np.zeros(bins), np.zeros(bins)
    for r in binned.groupBy("bin").agg(F.sum("n").alias("n"), F.sum("hits").alias("hits")).collect():
        weight[r.bin], hits[r.bin] = r.n, r.hits
    return Model(phi, solve(every, n), isotonic(weight, hits), 0.5)


def _bins(phi: Features, without: dict[int, np.ndarray], bins: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, hits = np.zeros(bins, np.int64), np.zeros(bins, np.int64)
        for b in batches:
            x, y, fold = phi(_matrix(b.column(0))), b.column(1).to_numpy(zero_copy_only=False), b.column(2).to_numpy(zero_copy_only=False)
            for f in np.unique(fold):
                at = bin_of(x[fold == f] @ without[int(f)], bins)
                n += np.bincount(at, minlength=bins)
                hits += np.bincount(at, weights=y[fold == f], minlength=bins).astype(np.int64)
        some = np.flatnonzero(n)
        yield pa.RecordBatch.from_arrays([pa.array(some.astype(np.int32)), pa.array(n[some]), pa.array(hits[some])], names=["bin", "n", "hits"])

    return run


def _score(model: Model):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(model(_matrix(b.column(1))))], names=["doc_id", "score"])

    return run


def held_out(doc_id, parts: int = 4, part: int = 2):
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % parts == part, F.lit(False))


def scored(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """(doc_id, held_out, score, predicted) for every row of docs(doc_id, text), learned from labels(doc_id, quality)."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    stats = materialise(docs.mapInArrow(_statistics, "doc_id long, stats array<float>"), "stats")
    known = labels.where("quality is not null").select(F.col("doc_id").cast("long").alias("doc_id"), (F.col("quality") > 0).cast("int").alias("label"))
    known = known.where(~held_out(F.col("doc_id")))
    train = materialise(stats.join(known, "doc_id").select("stats", "label", F.pmod(F.xxhash64("doc_id"), F.lit(FOLDS)).cast("int").alias("fold")), "labelled")
    model = fit(train)
    out = stats.mapInArrow(_score(model), "doc_id long, score double")
    return out.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
