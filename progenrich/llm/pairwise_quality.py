"""Text quality by pairwise ranking: a Bradley-Terry model on feature differences, cut at a score quantile.

Features of a whole text come from byte classes and word repetition, computed over Arrow buffers. A
bounded sample of labelled rows gives preference pairs (a good text is preferred to a bad one); logistic
loss on the differences of their features gives the weights. The cut is the quantile of training scores
that balances both classes' errors; a logistic curve maps the cut to the decision value.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bound_batches, map_slices, texts_of

FEATURES = ("letters", "upper", "digits", "space", "stops", "marks", "high", "words_marked", "repeats", "distinct", "word_size", "words_upper", "lines")
#: Bytes at which a text's own shares weigh as much as those of a typical good text.
SHORT = 40
SCHEMA = "doc_id long, held_out boolean, score double, predicted int"


def _classes() -> np.ndarray:
    kind = np.full(256, 6, np.uint8)  # other marks
    for c in range(256):
        ch = chr(c)
        if c >= 128:
            kind[c] = 7
        elif ch.islower():
            kind[c] = 0
        elif ch.isupper():
            kind[c] = 1
        elif ch.isdigit():
            kind[c] = 2
        elif ch in " \t\n\v\f\r":
            kind[c] = 3
        elif ch in ".,;:?'\"()-":
            kind[c] = 5
    return kind


_KIND = _classes()


def features(texts: list[str]) -> np.ndarray:
    """A row per text: shares in 0..1, then how far they count (0 for an empty text, near 1 for a long one)."""
    out = np.zeros((len(texts), len(FEATURES) + 1))
    for i, text in enumerate(texts):
        raw = text.encode("utf-8", "surrogatepass")
        n = len(raw)
        if not n:
            continue
        buf = np.frombuffer(raw, np.uint8)
        kind = _KIND[buf]
        c = np.bincount(kind, minlength=8) / n
        words = raw.split()
        k = max(1, len(words))
        last = buf[np.flatnonzero((kind[:-1] != 3) & (kind[1:] == 3))]
        last = np.append(last, buf[-1:]) if kind[-1] != 3 else last
        marked = float((_KIND[last] == 6).sum()) / k
        same = sum(map(bytes.__eq__, words, words[1:])) / k if len(words) > 1 else 0.0
        letters = c[0] + c[1] + c[7]
        out[i] = (
            letters, c[1] / max(letters, 1e-9), c[2], c[3], c[5], c[6], c[7], marked, same,
            len(set(words)) / k, min(1.0, n / k / 30), float(c[1] > 0.5 * letters), min(1.0, raw.count(b"\n") / k * 10), n / (n + SHORT),
        )
    return out


def standard(x: np.ndarray, neutral: np.ndarray, scale: np.ndarray) -> np.ndarray:
    """Deviations from a typical good text, drawn in for short texts, whose shares say little."""
    return (x[:, :-1] - neutral) / scale * x[:, -1:]


@dataclass
class PairwiseModel:
    neutral: np.ndarray
    scale: np.ndarray
    weights: np.ndarray
    cut: float
    steep: float
    decision: float

    def raw(self, x: np.ndarray) -> np.ndarray:
        return standard(x, self.neutral, self.scale) @ self.weights

    def score(self, x: np.ndarray) -> np.ndarray:
        z = self.steep * (self.raw(x) - self.cut) + np.log(self.decision / (1 - self.decision))
        return 1 / (1 + np.exp(-np.clip(z, -35, 35)))


def fit(x: np.ndarray, y: np.ndarray, decision: float = 0.3, pairs: int = 20_000, steps: int = 300, decay: float = 1e-3, seed: int = 7) -> PairwiseModel:
    """Fit on features and 0/1 labels. With one class only, all scores lie on that class's side."""
    good, bad = np.flatnonzero(y == 1), np.flatnonzero(y == 0)
    if not len(good) or not len(bad):
        side = -1.0 if len(bad) else 1.0
        return PairwiseModel(np.zeros(len(FEATURES)), np.ones(len(FEATURES)), np.zeros(len(FEATURES)), -side, 2.0, decision)
    neutral, scale = x[good, :-1].mean(0), np.maximum(x[:, :-1].std(0), 1e-3)
    rng = np.random.default_rng(seed)
    z = standard(x, neutral, scale)
    d = z[rng.choice(good, pairs)] - z[rng.choice(bad, pairs)]
    w, m, v = (np.zeros(len(FEATURES)) for _ in range(3))
    for t in range(1, steps + 1):
        g = -(d / (1 + np.exp(np.clip(d @ w, -35, 35)))[:, None]).mean(0) + decay * w
        m, v = 0.9 * m + 0.1 * g, 0.99 * v + 0.01 * g * g
        w -= 0.1 * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.99**t)) + 1e-9)
    s = z @ w
    # the quantile of all training scores at which the mean of both classes' errors is least; the middle of such
    grid = np.unique(np.quantile(s, np.linspace(0, 1, 1001)))
    sg, sb = np.sort(s[good]), np.sort(s[bad])
    err = np.searchsorted(sg, grid) / len(sg) + 1 - np.searchsorted(sb, grid) / len(sb)
    best = np.flatnonzero(err <= err.min() + 1e-12)
    low = sb[sb < grid[best[0]]]
    cut = (grid[best[0]] + (low[-1] if len(low) else grid[best[0]])) / 2
    spread = max(1e-6, abs(float(np.median(sg) - np.median(sb))))
    return PairwiseModel(neutral, scale, w, float(cut), 8.0 / spread, decision)


def labelled_sample(docs: DataFrame, labels: DataFrame, rows: int, fold: int = 5) -> DataFrame:
    """At most ``rows`` labelled texts of the learning folds, by smallest hash of the id."""
    ids = (
        labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("quality"))
        .where(F.col("doc_id").isNotNull() & F.col("quality").isin(0, 1) & (F.crc32(F.col("doc_id").cast("string")) % fold != 0))
        .groupBy("doc_id").agg(F.max("quality").alias("quality"))
    )
    each = [ids.where(F.col("quality") == q).orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows // 2) for q in (0, 1)]
    few = each[0].unionByName(each[1])
    return texts_of(docs).join(F.broadcast(few), "doc_id").groupBy("doc_id", "quality").agg(F.max("text").alias("text"))


def learn(docs: DataFrame, labels: DataFrame, rows: int = 4000, decision: float = 0.3) -> PairwiseModel:
    """Fit on a sample of at most ``rows`` labelled rows, half of each class; ``rows`` bounds what the driver gets."""

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        x = features(batch["text"].to_pylist())
        return pa.RecordBatch.from_arrays([batch["doc_id"], batch["quality"], pa.array(list(x), pa.list_(pa.float64()))], names=["doc_id", "quality", "x"])

    got = map_slices(labelled_sample(docs, labels, rows), run, "doc_id long, quality int, x array<double>").orderBy("doc_id", "quality").collect()
    x = np.array([r["x"] for r in got], float).reshape(len(got), len(FEATURES) + 1)
    return fit(x, np.array([r["quality"] for r in got], int), decision)


def score(docs: DataFrame, model: PairwiseModel, key: str = "doc_id", text: str = "text", fold: int = 5) -> DataFrame:
    """``doc_id, held_out, score, predicted`` of every whole text.

    Null texts count as empty and get a score too; a null key has no fold and is not held out; repeated
    rows pass through; an empty table gives no rows; other columns are not read.
    """

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        s = model.score(features(batch["text"].to_pylist()))
        return pa.RecordBatch.from_arrays([batch["doc_id"], pa.array(s), pa.array((s >= model.decision).astype(np.int32))], names=["doc_id", "score", "predicted"])

    scored = map_slices(texts_of(docs, key, text), run, "doc_id long, score double, predicted int")
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % fold == 0, F.lit(False))
    return scored.select("doc_id", held.alias("held_out"), "score", "predicted")


def filter_documents(docs: DataFrame, model: PairwiseModel) -> DataFrame:
    """The rows of ``docs``, all columns, whose text reaches the decision value."""

    def keep(batches):
        for b in batches:
            for at in range(0, b.num_rows, 256):
                part = b.slice(at, 256)
                s = model.score(features([t or "" for t in part["text"].to_pylist()]))
                yield part.filter(pa.array(s >= model.decision))

    bound_batches(docs.sparkSession)
    return docs.mapInArrow(keep, docs.schema)
