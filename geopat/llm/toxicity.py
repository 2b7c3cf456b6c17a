"""Toxicity: cumulative-link ordinal regression on sparse text features.

A text's features are its distinct words and word beginnings (five bytes), lower-cased
and hashed.  One weight vector w is shared by all ordered thresholds t1 < t2 < ...:
P(grade <= k) = logistic(t_k - w x).  The output is the expected grade, the chance of a
grade above 0, and flagged where that chance is at least a half.

The fit reads at most MOST_LABELS labelled rows outside the held-out third and keeps at most
MOST_FEATURES features (documented bounds).  Their grades are given, or, where labels only say toxic or not, derived: 0 if
not toxic, else 1 to 3 by how many of the words that mark toxic rows a text holds.
Features are those whose presence differs between the classes by more than the largest difference that
chance would give among so many (a limit that falls with their number), or, where none does, those that
differ most; of equal ones those of smaller hash stay.
Scoring reads every text whole and takes only the text.  Null and empty texts have no
features and get the grade of the intercept.  Without labels of both classes there is nothing to
learn: every grade is 0, and a warning says so.
Repeated rows score alike; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import warnings
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ship, table
from .labelled import held_out, training_rows
from .wordhash import Words, blocks, mix

MOST_LABELS = 8000
MOST_FEATURES = 20_000
BEGINNING = 5
#: A feature must be in so many rows, and its shares in the two classes differ by more than so many times what the largest of as many chance differences would.
LEAST_ROWS = 3
BEYOND_CHANCE = 1.1
#: Where no feature passes, as in small tables, so many that differ most are left to the penalty.
FALLBACK = 40
GRADES = 4
RIDGE = 0.02

#: Bytes that part words here: all of ASCII but letters and digits.
_PART = np.array([not (48 <= b <= 57 or 65 <= b <= 90 or 97 <= b <= 122 or b >= 128) for b in range(256)])
_CLEAN = np.where(_PART, 32, np.arange(256)).astype(np.uint8).tobytes()


def features(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(index of text, feature hash), each pair once."""
    w = Words([t.translate(_CLEAN) for t in texts], lower=True)
    owner = w.owner()
    long = (w.ends - w.starts) > BEGINNING
    if long.any():
        bytes_of = [w.data[w.starts[long] + i].astype(np.uint64) << np.uint64(8 * i) for i in range(BEGINNING)]
        starts = mix(sum(bytes_of[1:], bytes_of[0]) + np.uint64(0x51ED270B << 32))
    else:
        starts = np.zeros(0, np.uint64)
    h = np.concatenate((w.hash, starts))
    o = np.concatenate((owner, owner[long]))
    order = np.lexsort((h, o))
    h, o = h[order], o[order]
    fresh = np.ones(len(h), bool)
    fresh[1:] = (h[1:] != h[:-1]) | (o[1:] != o[:-1])
    return o[fresh], h[fresh]


@dataclass
class Ordinal:
    """Shared weights by sorted feature hash, and ordered thresholds."""

    keys: np.ndarray
    weights: np.ndarray
    thresholds: np.ndarray

    def above(self, texts: list[bytes]) -> np.ndarray:
        """P(grade > k) for every text and threshold."""
        o, h = features(texts)
        total = np.zeros(len(texts))
        if len(self.keys):
            at = np.minimum(np.searchsorted(self.keys, h), len(self.keys) - 1)
            hit = self.keys[at] == h
            total = np.bincount(o[hit], self.weights[at[hit]], len(texts))
        return 1 / (1 + np.exp(np.clip(self.thresholds[None, :] - total[:, None], -40, 40)))


def select(rows: np.ndarray, hashes: np.ndarray, toxic: np.ndarray, most: int = MOST_FEATURES) -> tuple[np.ndarray, np.ndarray]:
    """Features whose share differs between classes, and which of them mark toxic rows."""
    keys, at = np.unique(hashes, return_inverse=True)
    n1, n0 = max(toxic.sum(), 1), max((~toxic).sum(), 1)
    c1 = np.bincount(at, toxic[rows], len(keys))
    c0 = np.bincount(at, ~toxic[rows], len(keys))
    p1, p0 = (c1 + 0.5) / (n1 + 1), (c0 + 0.5) / (n0 + 1)
    pool = (c1 + c0 + 1) / (n1 + n0 + 2)
    z = (p1 - p0) / np.sqrt(pool * (1 - pool) * (1 / n1 + 1 / n0))
    often = np.flatnonzero(c1 + c0 >= LEAST_ROWS)
    least = BEYOND_CHANCE * np.sqrt(2 * np.log(max(len(often), 2)))
    good = often[np.abs(z[often]) > least]
    if not len(good):
        good = often[np.argsort(-z[often], kind="stable")][:FALLBACK]
    good = np.sort(good[np.argsort(-np.abs(z[good]), kind="stable")][:most])
    return keys[good], ((z > 0) & (p1 > 8 * p0))[good]


def fit(rows: np.ndarray, columns: np.ndarray, grade: np.ndarray, n_features: int, grades: int = GRADES, ridge: float = RIDGE, steps: int = 400) -> tuple[np.ndarray, np.ndarray]:
    """Weights and thresholds by full-batch adaptive gradient steps on the penalised likelihood."""
    n, k = len(grade), grades - 1
    w = np.zeros(n_features)
    share = np.clip(np.array([(grade <= j).mean() for j in range(k)]), 1e-3, 1 - 1e-3)
    t = np.log(share / (1 - share))
    gaps = np.log(np.maximum(np.diff(t), 0.05))
    first = t[:1].copy()
    params = [w, first, gaps]
    m, v = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params]
    upper = np.minimum(grade, k - 1)
    for step in range(1, steps + 1):
        t = first[0] + np.concatenate(([0.0], np.cumsum(np.exp(gaps))))
        s = np.bincount(rows, w[columns], n)
        c = 1 / (1 + np.exp(-np.clip(t[None, :] - s[:, None], -40, 40)))
        high = np.where(grade < k, c[np.arange(n), upper], 1.0)
        low = np.where(grade > 0, c[np.arange(n), np.maximum(grade - 1, 0)], 0.0)
        p = np.maximum(high - low, 1e-12)
        d_high = np.where(grade < k, high * (1 - high), 0.0) / p
        d_low = np.where(grade > 0, low * (1 - low), 0.0) / p
        g_s = (d_high - d_low) / n
        g_t = np.bincount(upper, np.where(grade < k, -d_high, 0.0), k) / n
        g_t += np.bincount(np.maximum(grade - 1, 0), np.where(grade > 0, d_low, 0.0), k) / n
        g_w = np.bincount(columns, g_s[rows], n_features) + ridge * w / n
        tail = np.cumsum(g_t[::-1])[::-1]
        for i, g in enumerate((g_w, tail[:1], tail[1:] * np.exp(gaps))):
            m[i] = 0.9 * m[i] + 0.1 * g
            v[i] = 0.99 * v[i] + 0.01 * g * g
            params[i] -= 0.05 * (m[i] / (1 - 0.9**step)) / (np.sqrt(v[i] / (1 - 0.99**step)) + 1e-9)
    return w, first[0] + np.concatenate(([0.0], np.cumsum(np.exp(gaps))))


def train(rows: np.ndarray, hashes: np.ndarray, toxic: np.ndarray, grade: np.ndarray | None = None, grades: int = GRADES) -> Ordinal | None:
    """Select features and fit.  `grade` holds the rows' grades; None derives them."""
    if not toxic.any() or toxic.all():
        return None
    keys, marks = select(rows, hashes, toxic)
    if not len(keys):
        return None  # no word is in LEAST_ROWS rows
    at = np.minimum(np.searchsorted(keys, hashes), len(keys) - 1)
    hit = keys[at] == hashes
    rows, at = rows[hit], at[hit]
    if grade is None:
        found = np.bincount(rows, marks[at], len(toxic))
        cuts = np.unique(np.quantile(found[toxic], (1 / 3, 2 / 3)))
        grade = np.where(toxic, 1 + np.searchsorted(cuts, found, side="left"), 0)
    weights, thresholds = fit(rows, at, grade.astype(np.int64), len(keys), grades)
    return Ordinal(keys, weights, thresholds)


def learn(docs: DataFrame, labels: DataFrame, most: int = MOST_LABELS) -> Ordinal | None:
    """Fit on at most `most` labelled rows: distinct feature hashes of those come to the driver."""

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, block in blocks(batch["text"].to_pylist()):
                o, h = features(block)
                edges = np.searchsorted(o, np.arange(len(block) + 1))
                sets = pa.array([h[a:b].tobytes() for a, b in zip(edges[:-1], edges[1:], strict=True)], pa.binary())
                yield pa.RecordBatch.from_arrays([batch["doc_id"].slice(first, len(block)), batch["toxic"].slice(first, len(block)), sets], names=["doc_id", "toxic", "h"])

    ship(docs.sparkSession)
    rows = training_rows(docs, labels, ["toxic"], most).select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("toxic"), "text")
    got = rows.mapInArrow(measure, "doc_id long, toxic int, h binary").toPandas()
    if got["toxic"].nunique() < 2:
        warnings.warn("no labels of both classes: every expected severity is 0", stacklevel=2)
        return None
    got = got.sort_values("doc_id", kind="stable").reset_index(drop=True)
    sets = [np.frombuffer(h, np.uint64) for h in got["h"]]
    owner = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    return train(owner, np.concatenate(sets), got["toxic"].to_numpy() > 0)


def score(docs: DataFrame, model: Ordinal | None) -> DataFrame:
    """doc_id, expected_severity, p_toxic, flagged of every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, block in blocks(batch["text"].to_pylist()):
                above = model.above(block) if model else np.zeros((len(block), 1))
                yield pa.RecordBatch.from_arrays(
                    [batch["doc_id"].slice(first, len(block)), pa.array(above.sum(axis=1)), pa.array(above[:, 0]), pa.array(above[:, 0] >= 0.5)],
                    names=["doc_id", "expected_severity", "p_toxic", "flagged"],
                )

    ship(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, expected_severity double, p_toxic double, flagged boolean")


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    scored = score(docs, learn(docs, table(spark, sf_dir, "labels")))
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "expected_severity", "p_toxic", "flagged")
