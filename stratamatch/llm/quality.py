"""Quality scores by regularised quadratic discriminant analysis.

Each whole text becomes a short vector of transformed statistics (logs and
log-odds of character classes, word shapes and repetition). Per class, count,
sum and cross products are added up over all training rows, so the fit needs no
sample (``keep_good`` takes a bounded one, to read fewer texts twice); each class covariance shrinks towards the pooled one and its diagonal.
A score is the logistic of the difference of the two Mahalanobis log densities,
with inverse Cholesky factors that are computed once.

Defined results: null text counts as empty, and empty texts have scores; several
labels of one id count as the lowest; rows with null id or label are scored but
do not train; if a class has fewer rows than statistics, every score is the
smoothed share of label 1 (0.5 without labels).
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .durable import stored
from .wordhash import WordHasher, blobs, portions, windows

#: Labelled rows that ``keep_good`` fits on at most (about).
SAMPLE = 50_000
#: Names of the statistics, in the order of the vectors.
STATISTICS = (
    "upper", "digits", "stops", "symbols", "bangs", "bars", "line_ends", "word_length", "distinct_words",
    "distinct_pairs", "distinct_lines", "non_ascii", "capitals", "entropy", "symbol_words", "one_letter_words",
)


@dataclass(frozen=True)
class Discriminant:
    """Class means, inverse Cholesky factors and log-density offsets; ``None`` if unfitted."""

    means: np.ndarray | None
    factors: np.ndarray | None
    offsets: np.ndarray | None
    share: float

    def score(self, x: np.ndarray) -> np.ndarray:
        if self.means is None:
            return np.full(len(x), self.share)
        z = [np.einsum("ij,nj->ni", f, x - m) for m, f in zip(self.means, self.factors)]
        log = [o - 0.5 * np.einsum("ni,ni->n", v, v) for v, o in zip(z, self.offsets)]
        return 1 / (1 + np.exp(np.clip(log[0] - log[1], -500, 500)))


def _odds(part, whole, usual, weight):
    """Log-odds of a share, drawn to a usual share by ``weight`` imagined cases: what a short
    text cannot tell stays near the usual value."""
    p = (part + usual * weight) / (max(whole, part) + weight)
    return np.log(p / (1 - p))


def statistics(text: bytes, hasher: WordHasher) -> list[float]:
    """The transformed statistics of one text."""
    raw = np.frombuffer(text, dtype=np.uint8)
    count = np.bincount(raw, minlength=256)
    n = len(raw)
    upper, lower, digits = int(count[65:91].sum()), int(count[97:123].sum()), int(count[48:58].sum())
    stops = int(count[[44, 46]].sum())
    punct = int(count[33:48].sum() + count[58:65].sum() + count[91:97].sum() + count[123:127].sum())
    hashes, starts, ends = hasher.words(text)
    k = len(hashes)
    lengths = ends - starts
    pairs = windows(hashes, 2)
    lines = text.split(b"\n")
    share = count[count > 0] / max(n, 1)
    head, tail = raw[starts] if k else raw[:0], raw[ends - 1] if k else raw[:0]
    ends_odd = ((tail >= 33) & (tail <= 47) & (tail != 44) & (tail != 46)) | ((tail >= 91) & (tail <= 96)) | (tail >= 123) & (tail < 127)
    most = float(-(share * np.log(share)).sum()) if n else 0.0
    return [
        _odds(upper, upper + lower, 0.03, 60),
        _odds(digits, n, 0.01, 60),
        _odds(stops, n, 0.025, 60),
        _odds(punct - stops, n, 0.005, 60),
        _odds(int(count[33]), n, 0.003, 60),
        _odds(int(count[124]), n, 0.003, 60),
        _odds(int(count[10]), k, 0.03, 30),
        np.log((float(lengths.sum()) + 30 * 5.5) / (k + 30)),
        np.log((len(np.unique(hashes)) + 30) / (k + 30)),
        np.log((len(np.unique(pairs)) + 30) / (len(pairs) + 30)),
        np.log((len(set(lines)) + 10) / (len(lines) + 10)),
        _odds(int(count[128:].sum()), n, 0.05, 60),
        _odds(int(((head >= 65) & (head <= 90)).sum()), k, 0.12, 30),
        (n * most + 100 * 3.0) / (n + 100),
        _odds(int(ends_odd.sum()), k, 0.01, 30),
        _odds(int((lengths == 1).sum()), k, 0.02, 30),
    ]


def document_statistics(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id and its vector ``x`` (array of double)."""

    def run(batches):
        hasher = WordHasher()
        for batch in portions(batches, "text"):
            texts = blobs(batch, "text")
            x = [statistics(t or b"", hasher) for t in texts]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(x, type=pa.list_(pa.float64()))], names=[id_col, "x"])

    return docs.select(F.col(id_col).cast("long").alias(id_col), F.col(text_col).cast("string").alias("text")).mapInArrow(run, f"{id_col} long, x array<double>")


def fit(training: DataFrame, shrink: float = 0.1, ridge: float = 0.02) -> Discriminant:
    """Fit from (x, label 0/1) rows. ``shrink`` pulls a class covariance to the pooled
    one, ``ridge`` that to its diagonal. One pass; moments only reach the driver."""
    d = len(STATISTICS)

    def moments(batches):
        total = np.zeros((2, 1 + d + d * d))
        for batch in batches:
            if not batch.num_rows:
                continue
            x = np.array(batch.column(0).to_pylist())
            y = batch.column(1).to_numpy(zero_copy_only=False)
            for c in (0, 1):
                own = x[y == c]
                total[c] += np.concatenate([[len(own)], own.sum(0), (own.T @ own).ravel()])
        at = np.flatnonzero(total.ravel())
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(total.ravel()[at])], names=["at", "part"])

    sums = np.zeros(2 * (1 + d + d * d))
    for row in training.where("x is not null and label in (0, 1)").select("x", F.col("label").cast("int").alias("label")).mapInArrow(moments, "at int, part double").groupBy("at").agg(F.sum("part").alias("v")).collect():
        sums[row["at"]] = row["v"]
    sums = sums.reshape(2, -1)
    n = sums[:, 0]
    share = float((n[1] + 1) / (n.sum() + 2))
    if n.min() < d:
        return Discriminant(None, None, None, share)
    means = sums[:, 1 : 1 + d] / n[:, None]
    own = np.array([s[1 + d :].reshape(d, d) / k - np.outer(m, m) for s, k, m in zip(sums, n, means)])
    pooled = (own * n[:, None, None]).sum(0) / n.sum()
    target = (1 - ridge) * pooled + ridge * np.diag(np.maximum(np.diag(pooled), 1e-6))
    covariances = [(1 - shrink) * c + shrink * target + 1e-9 * np.eye(d) for c in own]
    roots = [np.linalg.cholesky(c) for c in covariances]
    offsets = np.array([np.log(k / n.sum()) - np.log(np.diag(r)).sum() for k, r in zip(n, roots)])
    return Discriminant(means, np.array([np.linalg.inv(r) for r in roots]), offsets, share)


def score_documents(docs: DataFrame, labels: DataFrame, train_on, id_col: str = "doc_id", text_col: str = "text", threshold: float = 0.3) -> DataFrame:
    """id, score and predicted of every row. ``train_on``: a condition on ``id_col`` that
    says which labelled rows may train; ``labels`` has ``id_col`` and ``quality``."""
    rows = stored(document_statistics(docs, id_col, text_col), "statistics")
    marks = labels.where(F.col("quality").isin(0, 1)).groupBy(F.col(id_col).cast("long").alias(id_col)).agg(F.min("quality").alias("label"))
    model = fit(rows.where(train_on).join(marks, id_col).select("x", "label"))

    def run(batches):
        for batch in batches:
            x = np.array(batch.column(1).to_pylist()).reshape(-1, len(STATISTICS))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(model.score(x))], names=[id_col, "score"])

    return rows.mapInArrow(run, f"{id_col} long, score double").withColumn("predicted", (F.col("score") >= threshold).cast("int"))


def keep_good(docs: DataFrame, labels: DataFrame, threshold: float = 0.3, sample: int = SAMPLE) -> DataFrame:
    """The rows of ``docs`` (with their columns) whose score reaches the threshold. Fits on about
    ``sample`` labelled rows (all, if fewer), drawn by a hash of the id: their ids are broadcast, so
    that only their texts are read for it. Scores in place, in one pass over the texts."""
    marks = labels.where(F.col("quality").isin(0, 1)).where("doc_id is not null").groupBy(F.col("doc_id").cast("long").alias("mark_id")).agg(F.min("quality").alias("label"))
    marks = stored(marks, "labels")
    n = marks.count()
    if n > sample:
        marks = marks.where(F.pmod(F.xxhash64(F.lit("fit"), "mark_id"), F.lit(n)) < sample)
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).join(F.broadcast(marks.select("mark_id")), F.col("doc_id") == F.col("mark_id"), "left_semi")
    rows = document_statistics(own).join(F.broadcast(marks), F.col("doc_id") == F.col("mark_id"))
    model = fit(rows.select("x", "label"))

    def run(batches):
        hasher = WordHasher()
        for batch in portions(batches, "text"):
            good = model.score(np.array([statistics(t or b"", hasher) for t in blobs(batch, "text")])) >= threshold
            yield batch.filter(pa.array(good))

    return docs.mapInArrow(run, docs.schema)
