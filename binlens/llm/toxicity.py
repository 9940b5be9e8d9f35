"""Toxicity by cumulative-link ordinal regression over sparse hashed text features.

P(grade > k) = sigmoid(w.x - c_k): one weight vector for all thresholds c_1 < c_2 < ..., so what separates mild
from clean also helps to separate severe from mild.  The output is the expected grade and P(grade > 0).

The labels are binary, so grades are made from them: rows that aren't labelled toxic are 0; toxic rows are split at the
median of their evidence, the summed smoothed log odds of their features, into 1 (mild) and 2 (severe).

The fit uses at most ``max_labelled`` labelled ids (those with the smallest hash), one row of each, and of those the
rows with at most ``max_words`` different words, so that it is bounded in rows and bytes; scoring covers every row and
every word.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from binlens.llm.common import mix64, narrow, slices, text_buffers
from binlens.llm.words import ALPHA, words

BITS = 20  # feature buckets, as a power of two
MAX_LABELLED = 12_000
MAX_WORDS = 8_192


def features(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Bucket of each word, row bounds."""
    w = words(data, offsets, ALPHA)
    return (mix64(w.hashes) & np.uint64((1 << BITS) - 1)).astype(np.int32), w.first


@dataclass(frozen=True)
class OrdinalModel:
    weights: np.ndarray  # float32, one for each bucket
    cuts: np.ndarray  # ascending thresholds

    def latent(self, buckets: np.ndarray, bounds: np.ndarray) -> np.ndarray:
        run = np.concatenate([[0.0], np.cumsum(self.weights[buckets], dtype=np.float64)])
        return run[bounds[1:]] - run[bounds[:-1]]

    def above(self, latent: np.ndarray) -> np.ndarray:
        """P(grade > k) for each row and threshold; columns descend."""
        return 1.0 / (1.0 + np.exp(-np.clip(latent[:, None] - self.cuts[None, :], -60, 60)))


def _counted(buckets: np.ndarray, weights: np.ndarray | None = None, step: int = 1 << 20) -> np.ndarray:
    """Occurrences of each bucket, a stretch at a time, so a long training set needs no wide temporaries."""
    out = np.zeros(1 << BITS)
    for k in range(0, len(buckets), step):
        out += np.bincount(buckets[k : k + step], weights=None if weights is None else weights[k : k + step], minlength=1 << BITS)
    return out


def screened(buckets: np.ndarray, bounds: np.ndarray, toxic: np.ndarray, min_rows: int = 5, screen: float = 4.0) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Used buckets, then column and row of each entry in them.  A row's buckets must be distinct.

    A bucket is used if its shares among toxic and clean rows differ by ``screen`` standard errors.
    """
    row = np.repeat(np.arange(len(toxic), dtype=np.int32), np.diff(bounds))
    seen, hit = _counted(buckets), _counted(buckets, toxic.astype(np.float32)[row])
    n_bad, n_good = max(1, int(toxic.sum())), max(1, int((toxic == 0).sum()))
    share = seen / max(1, len(toxic))
    gap = (hit / n_bad - (seen - hit) / n_good) / np.sqrt(np.maximum(share * (1 - share), 1e-12) * (1 / n_bad + 1 / n_good))
    used = np.flatnonzero((seen >= min_rows) & (np.abs(gap) >= screen))
    place = np.full(1 << BITS, -1, np.int32)
    place[used] = np.arange(len(used))
    col = place[buckets]
    keep = col >= 0
    return used, col[keep], row[keep]


def grades(col: np.ndarray, row: np.ndarray, toxic: np.ndarray, used: int) -> np.ndarray:
    """0 for clean rows; toxic rows 1 or 2, split at the median of their summed smoothed log odds."""
    hit = np.bincount(col[toxic[row] > 0], minlength=used)
    rest = np.bincount(col[toxic[row] == 0], minlength=used)
    odds = np.log((hit + 0.5) / (toxic.sum() + 1.0)) - np.log((rest + 0.5) / ((toxic == 0).sum() + 1.0))
    evidence = np.bincount(row, weights=np.maximum(odds, 0.0)[col], minlength=len(toxic))
    out = toxic.astype(np.int64)
    if toxic.any():
        out[(toxic > 0) & (evidence > np.median(evidence[toxic > 0]))] = 2
    return out


def fit_ordinal(buckets: np.ndarray, bounds: np.ndarray, toxic: np.ndarray, rounds: int = 300, ridge: float = 1e-4, lasso: float = 5e-5,
    min_rows: int = 5, screen: float = 4.0, balance: float = 0.7) -> OrdinalModel:
    """Accelerated proximal gradient on the cumulative-link likelihood; features are a row's distinct buckets.

    Screening and ``lasso`` leave ordinary words without weight, so long clean texts gather no score.  With one
    class only, or no rows, the model has no weights and rejects nothing.
    """
    size = 1 << BITS
    nothing = OrdinalModel(np.zeros(size, np.float32), np.arange(1.0, 3.0) * 10)
    if not len(toxic) or toxic.all() or not toxic.any():
        return nothing
    used, col, row = screened(buckets, bounds, toxic, min_rows, screen)
    if not len(col):
        return nothing
    grade = grades(col, row, toxic, len(used))
    bad, n, top = grade > 0, len(grade), int(grade.max())
    cuts = np.array([np.log(max((grade < k).mean(), 1e-3) / max((grade >= k).mean(), 1e-3)) for k in range(1, top + 1)])
    passed = (grade[:, None] >= np.arange(1, top + 1)[None, :]).astype(float)
    # 0: rows weigh alike; 1: clean and other rows weigh alike in sum
    weight = np.where(bad, (0.5 / bad.mean()) ** balance, (0.5 / (~bad).mean()) ** balance) / n
    w, look, speed = np.zeros(len(used)), np.zeros(len(used)), 1.0
    step = np.full(len(used), 4.0 / top) / np.sqrt(np.maximum(np.bincount(col, weights=weight[row], minlength=len(used)), 1e-3)) / 8
    for _ in range(rounds):
        score = np.bincount(row, weights=look[col], minlength=n)
        p = 1.0 / (1.0 + np.exp(-np.clip(score[:, None] - cuts[None, :], -60, 60)))
        slack = (p - passed) * weight[:, None]
        grad = np.bincount(col, weights=slack.sum(axis=1)[row], minlength=len(used)) + ridge * look
        new = look - step * grad
        new = np.sign(new) * np.maximum(np.abs(new) - step * lasso, 0)
        cuts = np.maximum.accumulate(cuts + 2.0 * slack.sum(axis=0)) + 1e-6 * np.arange(top)
        faster = (1 + np.sqrt(1 + 4 * speed * speed)) / 2
        look = new + (speed - 1) / faster * (new - w)
        if np.dot(look - new, new - w) < 0:
            look, faster = new, 1.0
        w, speed = new, faster
    full = np.zeros(size, np.float32)
    full[used] = w
    return OrdinalModel(full, cuts)


def training_rows(docs: DataFrame, labels: DataFrame, label: str = "toxic", max_labelled: int = MAX_LABELLED,
    max_words: int = MAX_WORDS) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Features, row bounds and labels of at most ``max_labelled`` rows, each of at most ``max_words`` features, gathered
    from the executors.  Of an id's several rows one is taken, by a hash of its features, and of its labels the largest."""
    few = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("int").alias("y")).where("doc_id is not null and y is not null")
    few = few.groupBy("doc_id").agg(F.max("y").alias("y")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_labelled)

    def run(batches):
        for b in batches:
            data, off = text_buffers(b.column(1))
            for i, j in slices(off):
                col, bounds = features(data[off[i] : off[j]], off[i : j + 1] - off[i])
                rows = []
                for r in range(j - i):
                    rows.append(np.unique(col[bounds[r] : bounds[r + 1]]).astype(np.int32).tobytes())
                yield pa.RecordBatch.from_arrays([b.column(0)[i:j], b.column(2)[i:j], pa.array(rows, pa.binary())], ["doc_id", "y", "cols"])

    # the sample is bounded by max_labelled ids, so it is small enough to broadcast
    joined = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(few), "doc_id").select("doc_id", "text", "y")
    rows = narrow(joined, run, "doc_id long, y int, cols binary").where(F.octet_length("cols") <= 4 * max_words)
    rows = rows.groupBy("doc_id").agg(F.min(F.struct(F.xxhash64("cols").alias("k"), "y", "cols")).alias("r")).select("doc_id", "r.y", "r.cols")
    got = rows.toArrow().sort_by([("doc_id", "ascending"), ("y", "ascending"), ("cols", "ascending")])
    raw, off = text_buffers(got.column("cols"))
    return raw.view(np.int32), off // 4, got.column("y").to_numpy()


def fit(docs: DataFrame, labels: DataFrame, max_labelled: int = MAX_LABELLED) -> OrdinalModel:
    col, bounds, toxic = training_rows(docs, labels, max_labelled=max_labelled)
    return fit_ordinal(col, bounds, (toxic > 0).astype(np.int64))


def _scored(model: OrdinalModel, texts: pa.Array) -> Iterator[np.ndarray]:
    """For runs of rows: columns latent, P(> 0), ..., P(> K - 1).  A row's features count once."""
    data, off = text_buffers(texts)
    for i, j in slices(off):
        col, bounds = features(data[off[i] : off[j]], off[i : j + 1] - off[i])
        live = model.weights[col] != 0  # only these matter; most words have no weight
        row = np.repeat(np.arange(j - i, dtype=np.int64), np.diff(bounds))[live]
        key = np.unique((row << BITS) | col[live])
        latent = np.bincount(key >> BITS, weights=model.weights[key & ((1 << BITS) - 1)], minlength=j - i)
        yield np.column_stack([latent, model.above(latent)])


def score(docs: DataFrame, model: OrdinalModel, reject_at: float = 0.5) -> DataFrame:
    """doc_id, severity (expected grade), p_toxic, grade (most probable), rejected, for every row.

    Null and empty texts score as texts without features.  Repeated rows are scored alike.  Only doc_id and text
    are read.  Rejected where P(grade > 0) reaches ``reject_at``.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        m = shared.value
        for b in batches:
            parts = list(_scored(m, b.column(1))) or [np.zeros((0, 1 + len(m.cuts)))]
            above = np.concatenate(parts)[:, 1:]
            mass = -np.diff(np.column_stack([np.ones(len(above)), above, np.zeros(len(above))]), axis=1)
            yield pa.RecordBatch.from_arrays(
                [b.column(0), pa.array(above.sum(axis=1)), pa.array(above[:, 0]), pa.array(mass.argmax(axis=1), pa.int32()), pa.array(above[:,
                    0] >= reject_at)], ["doc_id", "severity", "p_toxic", "grade", "rejected"]
            )

    return narrow(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), run, "doc_id long, severity double, p_toxic double, grade int, rejected boolean")


def keep_clean(docs: DataFrame, model: OrdinalModel, reject_at: float = 0.5) -> DataFrame:
    """The rows of ``docs``, all columns, that aren't rejected; a narrow pass.

    Null and empty texts have no features and stay, unless the cuts alone reject them; repeated rows go or stay alike."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    at = docs.columns.index("text")

    def run(batches):
        m = shared.value
        for b in batches:
            parts = list(_scored(m, b.column(at))) or [np.zeros((0, 2))]
            yield b.filter(pa.array(np.concatenate(parts)[:, 1] < reject_at))

    return narrow(docs, run, docs.schema)
