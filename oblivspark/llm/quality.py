"""A regularised quadratic discriminant over document statistics."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.shared import materialise
from .base import column, id_and_text, map_batches, texts_of

#: Share of the pooled covariance, then of the diagonal, in each class's covariance.
SHRINK_POOLED, SHRINK_DIAGONAL = 0.3, 0.1
#: Standardised statistics are held within this many deviations.
CLIP = 6.0
#: Log-odds are divided by this before the logistic curve, so that scores don't all round to 0 or 1.
TEMPER = 4.0
_LOWER, _UPPER, _DIGIT = slice(97, 123), slice(65, 91), slice(48, 58)
#: Frequent short words of English, French, German and Spanish.
STOP = frozenset(
    w.encode()
    for w in "the of and to in is that it for was on are as with be by at or from this an le la les de des du un une et en est que qui pour dans par sur au der die das und ist ein eine den von zu mit auf dem im el los las y es por con para se del al".split()
)
NAMES = ("word_length", "symbols", "marks", "bars", "upper", "digits", "lines", "stops", "distinct", "repeats", "wide", "ends")


def share(k: int, of: int, prior: float, weight: float) -> float:
    """Log-odds of a share, drawn towards ``prior`` as by ``weight`` more cases: a short text is no outlier for being short."""
    p = (k + weight * prior) / (of + weight)
    return math.log((p + 0.003) / (1 - p + 0.003))


def statistics(text: bytes) -> list[float]:
    """Transformed statistics of one text."""
    n = len(text)
    hist = np.bincount(np.frombuffer(text, np.uint8), minlength=256)
    words = text.lower().split()
    m = len(words)
    lines = text.split(b"\n")
    letters = int(hist[_LOWER].sum() + hist[_UPPER].sum())
    odd = int(sum(hist[ord(c)] for c in "$%&#*@^~_=+<>\\{}[]"))
    return [
        math.log((n + 60) / (m + 10)),
        share(odd, n, 0.0, 30),
        share(int(hist[33]), n, 0.0, 30),
        share(int(hist[124]), n, 0.0, 30),
        share(int(hist[_UPPER].sum()), letters, 0.03, 60),
        share(int(hist[_DIGIT].sum()), n, 0.0, 30),
        share(len(lines) - 1, n, 0.005, 200),
        share(sum(1 for w in words if w in STOP), m, 0.35, 20),
        share(m - len(set(words)), m, 0.3, 40),
        share(len(lines) - len(set(lines)), len(lines), 0.0, 5),
        share(int(hist[128:].sum()), n, 0.05, 200),
        share(int(hist[46]), m, 0.08, 30),
    ]


def with_statistics(base: DataFrame) -> DataFrame:
    """(doc_id, x), or (doc_id, row, x): one narrow pass over the texts."""
    own = [c for c in ("doc_id", "row") if c in base.columns]

    def kernel(batches):
        for batch in batches:
            rows = [statistics(t) for t in texts_of(batch)]
            yield pa.record_batch([*(column(batch, c) for c in own), pa.array(rows, pa.list_(pa.float64()))], names=[*own, "x"])

    kinds = ", ".join(f"{c} {base.schema[c].dataType.simpleString()}" for c in own)
    return map_batches(base, kernel, f"{kinds}, x array<double>")


def remainder(doc_id, by: int):
    """crc32 of the id as text, modulo ``by``; a null id counts as the empty text."""
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(by))


def moments(labelled: DataFrame) -> dict[int, np.ndarray]:
    """For each class the sums of (1, x)(1, x)': each task sums its rows, then the exchange sums the tasks' entries."""
    k = len(NAMES) + 1

    def kernel(batches):
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            y = column(batch, "y").to_numpy(zero_copy_only=False)
            x = np.array(column(batch, "x").flatten()).reshape(-1, k - 1)
            x = np.hstack((np.ones((len(x), 1)), x))
            for c in np.unique(y):
                mine = x[y == c]
                sums[int(c)] = sums.get(int(c), np.zeros((k, k))) + mine.T @ mine
        for c, s in sums.items():
            yield pa.record_batch(
                [pa.array([c] * (k * k), pa.int32()), pa.array(range(k * k), pa.int32()), pa.array(s.ravel())], names=["y", "at", "s"]
            )

    rows = map_batches(labelled.select("y", "x"), kernel, "y int, at int, s double").groupBy("y", "at").agg(F.sum("s").alias("s")).collect()
    out: dict[int, np.ndarray] = {}
    for y, at, s in rows:
        out.setdefault(y, np.zeros(k * k))[at] = s
    return {y: s.reshape(k, k) for y, s in out.items()}


class Discriminant:
    """Class means and Cholesky factors of shrunken covariances, on standardised statistics."""

    def __init__(self, sums: dict[int, np.ndarray], pooled: float = SHRINK_POOLED, diagonal: float = SHRINK_DIAGONAL):
        k = len(NAMES)
        counts = {c: s[0, 0] for c, s in sums.items()}
        total = sum(sums.values()) if sums else np.zeros((k + 1, k + 1))
        n = max(total[0, 0], 1.0)
        self.centre = total[0, 1:] / n
        spread = np.sqrt(np.maximum(np.diag(total)[1:] / n - self.centre**2, 0))
        self.scale = np.where(spread > 1e-9, spread, 1.0)
        #: with one class or none there is nothing to tell apart: the score is that class's share
        self.only = None if len(counts) == 2 else (0.5 if not counts else float(next(iter(counts))))
        self.parts = {}
        if self.only is not None:
            return
        cov = {}
        for c, s in sums.items():
            mean = (s[0, 1:] / counts[c] - self.centre) / self.scale
            raw = (s[1:, 1:] / counts[c] - np.outer(self.centre, s[0, 1:] / counts[c]) - np.outer(s[0, 1:] / counts[c], self.centre) + np.outer(self.centre, self.centre)) / np.outer(self.scale, self.scale)
            cov[c] = (mean, raw - np.outer(mean, mean))
        both = sum(counts[c] * v for c, (_, v) in cov.items()) / n
        for c, (mean, own) in cov.items():
            mixed = (1 - pooled) * own + pooled * both
            mixed = (1 - diagonal) * mixed + diagonal * np.diag(np.diag(mixed)) + 1e-3 * np.eye(k)
            low = np.linalg.cholesky(mixed)
            self.parts[c] = (mean, np.linalg.inv(low), float(np.log(np.diag(low)).sum()), math.log(counts[c] / n))

    def score(self, x: np.ndarray) -> np.ndarray:
        """The tempered posterior of class 1."""
        if self.only is not None:
            return np.full(len(x), self.only)
        z = np.clip((x - self.centre) / self.scale, -CLIP, CLIP)
        log = {c: prior - half - 0.5 * (((z - mean) @ inv.T) ** 2).sum(1) for c, (mean, inv, half, prior) in self.parts.items()}
        return 1 / (1 + np.exp(-np.clip((log[1] - log[0]) / TEMPER, -500, 500)))


def fit(features: DataFrame, labels: DataFrame, label_col: str = "quality", by: int = 3, held: int = 1) -> Discriminant:
    """Fit on all labelled rows outside the held-out remainder. An id with several labels takes their majority, a tie is left out; null and other labels too."""
    y = labels.select(F.col("doc_id"), F.col(label_col).cast("int").alias("q")).filter(F.col("q").isin(0, 1))
    y = y.groupBy("doc_id").agg(F.avg("q").alias("q")).filter(F.col("q") != 0.5)
    y = y.select("doc_id", F.when(F.col("q") > 0.5, 1).otherwise(0).alias("y"))
    rows = features.filter(remainder(F.col("doc_id"), by) != held).join(y, "doc_id")
    return Discriminant(moments(rows))


def quality(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", row_col: str | None = None) -> DataFrame:
    """One row per document: doc_id, held_out, score (0 to 1), predicted (1 from 0.5 on); with ``row_col`` that column too, as row.

    Statistics of each whole text are computed once and written down; class moments are summed over
    every labelled row that isn't held out (crc32 of the id as text modulo 3 is 1), so nothing is
    sampled; the score compares two Gaussian log-densities by their cached Cholesky factors. Labels, language, source and id are
    never part of a score.

    Null or empty text: the statistics of the empty text, scored like any other. Null id: not held out,
    never labelled. Repeated rows: a row each. Empty documents: no rows. No usable labels: every score is 0.5; one class only: that class.
    Other columns are ignored.
    """
    more = [] if row_col is None else [F.col(f"`{row_col}`").alias("row")]
    features = materialise(with_statistics(id_and_text(docs, id_col, text_col, *more)), "statistics")
    own = ["doc_id", *(["row"] if more else []), "held_out"]
    shared = docs.sparkSession.sparkContext.broadcast(fit(features, labels))

    def kernel(batches):
        for batch in batches:
            x = np.array(column(batch, "x").flatten()).reshape(-1, len(NAMES))
            score = shared.value.score(x)
            yield pa.record_batch(
                [*(column(batch, c) for c in own), pa.array(score), pa.array((score >= 0.5).astype(np.int32))],
                names=[*own, "score", "predicted"],
            )

    rows = features.withColumn("held_out", remainder(F.col("doc_id"), 3) == 1)
    kinds = ", ".join(f"{c} {rows.schema[c].dataType.simpleString()}" for c in own)
    return map_batches(rows, kernel, f"{kinds}, score double, predicted int")
