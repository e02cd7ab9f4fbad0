"""Toxicity: a linear classifier over character n-grams scaled by naive Bayes log-count ratios."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import held_out, map_arrow, mix64, settle, texts_of, window_hashes

#: Lengths of the n-grams, bits of the feature space, and the most labelled rows that the weights are fitted on.
LENGTHS = (4, 5, 6)
BITS = 19
MOST_ROWS = 16_000
_SMOOTH = 1.0
#: Likelihood-ratio statistic of presence against label from which a feature takes part.
EVIDENCE = 12.0


def features(text: str, lengths=LENGTHS, bits: int = BITS) -> np.ndarray:
    """Sorted distinct feature numbers of the character n-grams of a lower-cased text, with a blank on each side.

    A feature counts once, however often it occurs.
    """
    points = np.frombuffer(f" {text.lower()} ".encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    points = mix64(points + np.uint64(7))
    found = np.concatenate([(window_hashes(points, n) >> np.uint64(64 - bits)).astype(np.uint32) for n in lengths])
    found.sort()
    return found[np.flatnonzero(np.diff(found, prepend=np.uint32(0xFFFFFFFF)))].astype(np.int32)


class Model:
    """ratio: log-count ratio of each feature; weight: fitted on ratio-scaled features; bias."""

    def __init__(self, ratio: np.ndarray, weight: np.ndarray, bias: float):
        self.value, self.bias = (ratio * weight).astype(np.float32), bias

    def margin(self, found: np.ndarray) -> float:
        return float(self.value[found].sum(dtype=np.float64) + self.bias)

    def score(self, text: str) -> float:
        return float(1 / (1 + np.exp(-np.clip(self.margin(features(text)), -30, 30))))


def labelled_sample(docs: DataFrame, labels: DataFrame, most_rows: int = MOST_ROWS) -> DataFrame:
    """text and toxic of at most most_rows labelled rows, those of least hash of the id; never a held-out one.

    One label for each id, the greater of several, and one text, the least of several: repeated ids don't add rows. The
    ids of the sample are few by the bound, so they are broadcast to the texts and only the sample's texts are shuffled.
    """
    picked = F.xxhash64(F.lit("toxicity"), "doc_id")
    known = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
    known = known.groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic_label")).orderBy(picked, "doc_id").limit(most_rows)
    known = known.withColumnRenamed("doc_id", "label_id")
    rows = docs.select("doc_id", "text").join(F.broadcast(known), F.col("doc_id") == F.col("label_id"))
    rows = rows.groupBy("label_id").agg(F.min("text").alias("text"), F.max("toxic_label").alias("toxic"))
    return settle(rows.select("text", "toxic"), "toxicity-sample")


def presence(rows: DataFrame, bits: int = BITS) -> tuple[np.ndarray, np.ndarray]:
    """How many of the other and of the toxic rows have each feature, and the rows of both classes."""
    width = 1 << bits

    def count(batches):
        total = np.zeros((2, width + 1), np.int64)
        for batch in batches:
            for t, y in zip(texts_of(batch), batch.column("toxic").to_pylist(), strict=True):
                total[int(y > 0), features(t, bits=bits)] += 1
                total[int(y > 0), width] += 1
        at = np.flatnonzero(total.any(0))
        yield pa.RecordBatch.from_pydict({"feature": pa.array(at, pa.int32()), "neg": pa.array(total[0, at]), "pos": pa.array(total[1, at])})

    sums = rows.coalesce(8).mapInArrow(count, "feature int, neg bigint, pos bigint").groupBy("feature").agg(F.sum("neg").alias("neg"), F.sum("pos").alias("pos"))
    got = sums.toArrow()  # at most a row for each feature of the fixed space
    feature, counts = got.column("feature").to_numpy(), np.zeros((2, width + 1))
    counts[0, feature], counts[1, feature] = got.column("neg").to_numpy(), got.column("pos").to_numpy()
    return counts[:, :width], counts[:, width]


def log_count_ratios(counts: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Log of the smoothed share of toxic rows with each feature over that of the others."""
    share = (counts + _SMOOTH) / (n[:, None] + 2 * _SMOOTH)
    return np.log(share[1] / share[0])


def evidence(counts: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Likelihood-ratio statistic (G) of each feature's presence against the label."""
    rate = counts.sum(0) / max(n.sum(), 1)
    term = lambda o, e: np.where(o > 0, o * np.log(np.maximum(o, 1e-9) / np.maximum(e, 1e-9)), 0)
    return 2 * sum(term(counts[k], n[k] * rate) + term(n[k] - counts[k], n[k] * (1 - rate)) for k in (0, 1))


def fit(docs: DataFrame, labels: DataFrame, most_rows: int = MOST_ROWS, epochs: int = 30) -> Model:
    """Ratios and weights (logistic regression) from a sample of at most most_rows labelled rows (documented bound).

    Labels of rows whose crc32(doc_id) leaves no remainder by 5 are never read. With one class or none the model
    gives a constant.
    """
    rows = labelled_sample(docs, labels, most_rows)
    counts, n = presence(rows)
    if not n.min():
        return Model(np.zeros(1 << BITS), np.zeros(1 << BITS), -3.0 if n[0] >= n[1] else 3.0)
    ratio = log_count_ratios(counts, n)
    strong = np.flatnonzero(evidence(counts, n) >= EVIDENCE)
    place = np.full(1 << BITS, -1, np.int32)
    place[strong] = np.arange(len(strong))

    def extract(batch):
        found = [f[f >= 0] for f in (place[features(t)] for t in texts_of(batch))]
        return {"toxic": batch.column("toxic"), "found": pa.array(found, pa.list_(pa.int32()))}

    got = map_arrow(rows, extract, "toxic int, found array<int>").toArrow()
    y = (got.column("toxic").to_numpy() > 0).astype(np.float64)
    lists = got.column("found").combine_chunks()
    weight, bias = _logistic(lists.flatten().to_numpy(), lists.value_lengths().to_numpy(), y, ratio[strong], epochs)
    whole = np.zeros(1 << BITS)
    whole[strong] = weight
    return Model(ratio, whole, bias)


def _logistic(flat, sizes, y, ratio, epochs, ridge: float = 1e-4, rate: float = 0.5, batch: int = 256):
    """Logistic regression on binary features scaled by ratio, with a ridge; adaptive gradient steps."""
    ends = np.concatenate([[0], np.cumsum(sizes)])
    norm = np.mean([np.sqrt(max((ratio[flat[a:z]] ** 2).sum(), 1e-9)) for a, z in zip(ends, ends[1:], strict=False)])
    x = ratio / norm
    w, b = np.zeros(len(ratio)), 0.0
    g2, gb2 = np.full(len(ratio), 1e-8), 1e-8
    balance = np.where(y > 0, 0.5 / max(y.mean(), 1e-6), 0.5 / max(1 - y.mean(), 1e-6)) ** 0.5
    rng = np.random.default_rng(0)
    # Rows in one fixed order, so that equal samples give equal weights however Spark returns them.
    fixed = np.lexsort((np.array([int(flat[a:z].astype(np.int64).sum()) for a, z in zip(ends, ends[1:], strict=False)]), sizes, y))
    for _ in range(epochs):
        order = fixed[rng.permutation(len(y))]
        for lo in range(0, len(y), batch):
            rows = order[lo : lo + batch]
            at = np.concatenate([flat[ends[r] : ends[r + 1]] for r in rows])
            own = np.repeat(np.arange(len(rows)), sizes[rows])
            z = np.bincount(own, w[at] * x[at], len(rows)) + b
            err = (1 / (1 + np.exp(-np.clip(z, -30, 30))) - y[rows]) * balance[rows] / len(rows)
            g = np.bincount(at, err[own] * x[at], len(w))
            used = np.flatnonzero(g)
            g = g[used] + ridge * w[used]
            g2[used] += g * g
            w[used] -= rate * g / np.sqrt(g2[used])
            gb2 += err.sum() ** 2
            b -= rate * err.sum() / np.sqrt(gb2)
    return w / norm, b


def score(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, held_out, score and predicted of every row from the whole text alone; null and empty texts too; no shuffle."""
    kind = next(f.dataType for f in docs.schema if f.name == "doc_id").simpleString()

    def run(batch):
        s = np.array([model.score(t) for t in texts_of(batch)])
        return {"doc_id": batch.column("doc_id"), "held_out": batch.column("held_out"), "score": s, "predicted": (s >= 0.5).astype(np.int32)}

    return map_arrow(docs.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "text"), run, f"doc_id {kind}, held_out boolean, score double, predicted int")


def without_toxic(docs: DataFrame, model: Model) -> DataFrame:
    """The rows of docs whose text is not predicted toxic, with all their columns."""
    @F.pandas_udf("boolean")
    def toxic(texts):
        return texts.fillna("").map(lambda t: model.score(t) >= 0.5)

    return docs.where(~toxic(F.col("text")))
