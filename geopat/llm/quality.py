"""Quality classifier: regularised quadratic discriminant over transformed document statistics.

Each text gives a dozen statistics (lengths, shares of marks, capitals, digits,
repetition), made nearly normal by logarithms.  Each class has a mean and a covariance
shrunk towards the pooled covariance and then towards a multiple of the identity; its
Cholesky factor is computed once, inverted once as a triangle, and kept in the model.  A text's score is the
posterior of class 1 from the difference of the two log densities, whose Mahalanobis
terms are one product with the triangle per class and batch.

The fit reads at most MOST_LABELS labelled rows outside the held-out third (a documented
bound); scoring reads every text whole.  Only the text is an input.  Texts without a word (null, empty,
blank) have no statistics: they all get the share of class 1 among labelled texts without words,
one text of class 0 added, so 0 where none is labelled.  Without labels of both
classes every text gets 0.5.  Repeated rows and ties get equal scores; extra columns, whatever their
names, are ignored; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ship, table
from .labelled import held_out, training_rows
from .wordhash import Words, blocks

MOST_LABELS = 6000
BLANK = b" \t\n\x0b\x0c\r"
TO_POOLED = 0.1
TO_SPHERE = 0.02
#: Each share counts so many ordinary characters or words besides the text's own, so that a short text is not an outlier.
PRIOR_CHARS = 80.0
PRIOR_WORDS = 16.0
#: Statistics in order.
NAMES = (
    "log_words", "mean_length", "spread_length", "symbols", "exclamations", "capitals", "digits",
    "distinct", "same_as_last", "bars", "line_words", "full_stops", "short_words",
)

_SYMBOL = np.zeros(256, bool)
_SYMBOL[[ord(c) for c in "#*$%&<>"]] = True


def _per_text(values: np.ndarray, edges: np.ndarray) -> np.ndarray:
    total = np.concatenate(([0.0], np.cumsum(values, dtype=np.float64)))
    return total[edges[1:]] - total[edges[:-1]]


def statistics(texts: list[bytes]) -> np.ndarray:
    """One row of transformed statistics per text."""
    w = Words(texts)
    n = np.diff(w.first).astype(np.float64)
    data, edges = w.data, w.text_start
    size = (w.ends - w.starts).astype(np.float64)
    chars = _per_text(size, w.first)

    def share(mask: np.ndarray, prior: float, by: np.ndarray = chars, at: np.ndarray = edges, weight: float = PRIOR_CHARS) -> np.ndarray:
        return np.log((_per_text(mask, at) + prior * weight) / (by + weight) + 0.002)

    owner = w.owner()
    order = np.lexsort((w.hash, owner))
    h, o = w.hash[order], owner[order]
    fresh = np.ones(len(h), bool)
    fresh[1:] = (h[1:] != h[:-1]) | (o[1:] != o[:-1])
    distinct = (np.bincount(o[fresh], minlength=len(n)) + 0.8 * PRIOR_WORDS) / (n + PRIOR_WORDS)
    same = np.zeros(len(owner))
    same[1:] = (w.hash[1:] == w.hash[:-1]) & (owner[1:] == owner[:-1])
    mean = (chars + 5 * PRIOR_WORDS) / (n + PRIOR_WORDS)
    spread = np.sqrt(np.maximum((_per_text(size * size, w.first) + 35 * PRIOR_WORDS) / (n + PRIOR_WORDS) - mean * mean, 0))
    lines = _per_text(data == 10, edges) + 1
    return np.column_stack([
        np.log(n + 2 * PRIOR_WORDS), np.log(mean), np.log1p(spread), share(_SYMBOL[data], 0.0005), share(data == ord("!"), 0.0005),
        share((data >= 65) & (data <= 90), 0.03), share((data >= 48) & (data <= 57), 0.0005),
        np.log(distinct + 0.01), share(same, 0.01, n, w.first, PRIOR_WORDS), share(data == ord("|"), 0.0005),
        np.log((n + PRIOR_WORDS) / (lines + 1)), share(data == ord("."), 0.02), share(size <= 3, 0.4, n, w.first, PRIOR_WORDS),
    ])


@dataclass
class Discriminant:
    """Two Gaussian classes with cached Cholesky factors, as the inverse triangles, and the score of texts without words."""

    mean: np.ndarray
    whiten: np.ndarray
    constant: np.ndarray
    blank: float = 0.0

    def log_odds(self, x: np.ndarray) -> np.ndarray:
        out = []
        for k in (0, 1):
            z = (x - self.mean[k]) @ self.whiten[k].T
            out.append(self.constant[k] - 0.5 * (z * z).sum(axis=1))
        return out[1] - out[0]

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.log_odds(x), -40, 40)))


def lower_inverse(factor: np.ndarray) -> np.ndarray:
    """Inverse of a lower triangle by forward substitution."""
    out = np.zeros_like(factor)
    for i in range(len(factor)):
        out[i, i] = 1.0
        out[i] = (out[i] - factor[i, :i] @ out[:i]) / factor[i, i]
    return out


def fit(x: np.ndarray, y: np.ndarray, to_pooled: float = TO_POOLED, to_sphere: float = TO_SPHERE) -> Discriminant | None:
    """Shrinkage estimate from rows and 0/1 labels; None where a class has under two rows."""
    if min((y == 0).sum(), (y == 1).sum()) < 2:
        return None
    own = [np.cov(x[y == k].T, bias=True) for k in (0, 1)]
    pooled = sum(c * (y == k).mean() for k, c in enumerate(own))
    means, factors, constants = [], [], []
    for k, c in enumerate(own):
        c = (1 - to_pooled) * c + to_pooled * pooled
        c = (1 - to_sphere) * c + to_sphere * (np.trace(c) / len(c) + 1e-6) * np.eye(len(c))
        factor = np.linalg.cholesky(c)
        means.append(x[y == k].mean(axis=0))
        factors.append(lower_inverse(factor))
        constants.append(np.log((y == k).mean()) - np.log(np.diag(factor)).sum())
    return Discriminant(np.array(means), np.array(factors), np.array(constants))


def learn(docs: DataFrame, labels: DataFrame, most: int = MOST_LABELS) -> Discriminant | None:
    """Fit on at most `most` labelled rows; only their statistics leave the executors."""

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch["text"].to_pylist()
            for first, block in blocks(texts):
                x = statistics(block)
                worded = pa.array([bool(t.strip(BLANK)) for t in block])
                yield pa.RecordBatch.from_arrays([batch["quality"].slice(first, len(block)), batch["doc_id"].slice(first, len(block)), worded, pa.array(list(x), pa.list_(pa.float64()))], names=["y", "doc_id", "worded", "x"])

    ship(docs.sparkSession)
    rows = training_rows(docs, labels, ["quality"], most).select(F.col("quality").cast("int").alias("quality"), F.col("doc_id").cast("long").alias("doc_id"), "text")
    got = rows.mapInArrow(measure, "y int, doc_id long, worded boolean, x array<double>").toPandas()
    if got.empty:
        return None
    got = got.sort_values("doc_id", kind="stable")
    blank, worded = got[~got["worded"]], got[got["worded"]]
    if worded.empty:
        return None
    model = fit(np.array(worded["x"].tolist()), worded["y"].to_numpy())
    if model is not None:
        model.blank = float(blank["y"].sum()) / (len(blank) + 1)
    return model


def score(docs: DataFrame, model: Discriminant | None, carry: bool = False) -> DataFrame:
    """doc_id, score and predicted for every row; with `carry` also row, the whole row."""
    ship(docs.sparkSession)
    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns]) if carry else F.struct("doc_id")
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), row.alias("row"), "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, block in blocks(batch["text"].to_pylist()):
                if model is None:
                    s = np.full(len(block), 0.5)
                else:
                    s = model.score(statistics(block))
                s[np.fromiter((not t.strip(BLANK) for t in block), bool, len(block))] = model.blank if model else 0.5
                given = [batch[name].slice(first, len(block)) for name in ("doc_id", "row")]
                yield pa.RecordBatch.from_arrays([*given, pa.array(s), pa.array((s >= 0.5).astype("int32"))], names=["doc_id", "row", "score", "predicted"])

    return slim.mapInArrow(run, slim.select("doc_id", "row").schema.add("score", "double").add("predicted", "integer"))


def op3_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = learn(docs, table(spark, sf_dir, "labels"))
    return score(docs, model).select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", "predicted")


def keep_good(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The documents that the classifier does not reject; columns as in `docs`.  Rows that share an id are judged each by its own text."""
    return score(docs, learn(docs, labels), carry=True).where("predicted = 1").select("row.*")
