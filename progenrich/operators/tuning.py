"""Choice of the epoch size: the least completion over sizes, then the share of it whose run scores best."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from .enrich import CURVE, EnrichmentRun
from .metrics import progressiveness


@dataclass(frozen=True)
class Trial:
    stage: str  # size or share
    size: float
    epochs: int
    completion: float
    score: float | None


@dataclass(frozen=True)
class Tuned:
    completion: float
    size: float
    trials: tuple[Trial, ...]

    def report(self, spark: SparkSession) -> DataFrame:
        """One row for each trial; ``chosen`` marks the size that won."""
        rows = [(t.stage, t.size, t.epochs, t.completion, t.score, t.stage == "share" and t.size == self.size) for t in self.trials]
        return spark.createDataFrame(rows, "stage string, size double, epochs int, completion double, score double, chosen boolean")


def tune_epoch(start: Callable[[float], EnrichmentRun], sizes: list[float], shares: list[float], value: str | None = None, most: int = 10_000) -> Tuned:
    """``start(size)`` begins a run with epochs of that size. Runs go on until nothing is left: one that has not ended
    before ``most`` epochs is refused, as it has no completion.

    Scores are the progressiveness of ``value`` (true F1, or the expected F where truth is unknown) over sample points
    that all shares have in common. Of equal scores the smaller size wins.
    """

    def finished(stage: str, size: float) -> tuple[Trial, list[tuple]]:
        run = start(size)
        if stage == "size":
            run.truth = None  # the completion alone counts, so the quality of its answers is not looked up
        rows = run.curve(most)
        if rows[-1][1] >= most:
            raise ValueError(f"epochs of {size} do not end within {most}")
        return Trial(stage, size, rows[-1][1], rows[-1][2], None), rows

    tried = [finished("size", s)[0] for s in sizes]
    least = min(t.completion for t in tried)
    runs = [finished("share", s * least) for s in sorted(shares)]
    if value is None:
        value = "expected_f" if any(r[6] is None for _, rows in runs for r in rows) else "f1"
    spark = SparkSession.active()
    curves = spark.createDataFrame([(str(i), *r[1:]) for i, (_, rows) in enumerate(runs) for r in rows], CURVE)
    scores = {r["approach"]: float(r["progressiveness"]) for r in progressiveness(curves, value).collect()}
    scored = [Trial(t.stage, t.size, t.epochs, t.completion, scores.get(str(i), 0.0)) for i, (t, _) in enumerate(runs)]
    best = max(scored, key=lambda t: (t.score, -t.size))
    return Tuned(least, best.size, (*tried, *scored))
