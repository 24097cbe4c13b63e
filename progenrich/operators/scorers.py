"""Scorers: simulated ones of tunable quality, and adapters for columns, pandas functions and fitted models."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import Catalog, Scorer, TagType

# Fixed values of the simulated scorers: cost, noise width, quality (area under the ROC curve).
LADDER = ((1.0, 0.85, 0.66), (3.0, 0.80, 0.719), (10.0, 0.70, 0.837), (40.0, 0.60, 0.944))


def noise(key: Column, tag_no: int, scorer: int) -> Column:
    """A number in [0, 1) from key, tag and scorer, by modular arithmetic that SQL can repeat."""
    low, high = F.pmod(key, F.lit(10007)), F.pmod(whole(key, 97), F.lit(10007))  # small first: products of large keys would not fit
    mixed = 7919 * low + F.lit(31337 * tag_no + 104729 * scorer) + F.lit(613 * (13 * scorer + 7 * tag_no + 1)) * high
    return F.pmod(mixed, F.lit(10007)) / F.lit(10007.0)


def whole(key: Column, by: int) -> Column:
    """The whole part of a key over a number, in whole numbers: keys beyond 2^53 are no doubles."""
    return F.call_function("div", key - F.pmod(key, F.lit(by)), F.lit(by))


def simulated(width: float, scorer: int):
    def column(key: Column, has_tag: Column, tag_no: int) -> Column:
        u = noise(key, tag_no, scorer)
        return F.when(has_tag, 1.0 - width * u).otherwise(width * u)

    return column


def simulated_catalog(types: tuple[TagType, ...]) -> Catalog:
    """Four scorers for each type; the first has the best quality per cost and so is the seed."""
    return Catalog(types, tuple(Scorer(t.name, i, c, q, simulated(w, i)) for t in types for i, (c, w, q) in enumerate(LADDER)))


def from_column(tag_type: str, number: int, cost: float, quality: float, make) -> Scorer:
    """``make(tag)`` gives a Column of the payload."""
    return Scorer(tag_type, number, cost, quality, apply=lambda payload, tag: payload.select("object_id", make(tag).cast("double").alias("prob")))


def from_pandas(tag_type: str, number: int, cost: float, quality: float, fn, columns: list[str]) -> Scorer:
    """``fn(tag, *series)`` gives a series of probabilities over Arrow batches."""

    def apply(payload: DataFrame, tag) -> DataFrame:
        def run(batches):
            import pandas as pd

            for b in batches:
                yield pd.DataFrame({"object_id": b["object_id"], "prob": fn(tag, *[b[c] for c in columns])})

        return payload.select("object_id", *columns).mapInPandas(run, "object_id long, prob double")

    return Scorer(tag_type, number, cost, quality, apply=apply)


def from_service(tag_type: str, number: int, cost: float, quality: float, connect, columns: list[str]) -> Scorer:
    """``connect()`` opens a client once in each partition; ``client(tag, frame)`` gives the probabilities of a batch."""

    def apply(payload: DataFrame, tag) -> DataFrame:
        def run(batches):
            import pandas as pd

            client = connect()
            for b in batches:
                yield pd.DataFrame({"object_id": b["object_id"], "prob": client(tag, b[columns])})

        return payload.select("object_id", *columns).mapInPandas(run, "object_id long, prob double")

    return Scorer(tag_type, number, cost, quality, apply=apply)


def from_model(tag_type: str, number: int, cost: float, quality: float, model, tags: list) -> Scorer:
    """A fitted pyspark.ml classifier whose probability vector follows ``tags``."""
    from pyspark.ml.functions import vector_to_array

    def apply(payload: DataFrame, tag) -> DataFrame:
        return model.transform(payload).select("object_id", vector_to_array("probability")[tags.index(tag)].alias("prob"))

    return Scorer(tag_type, number, cost, quality, apply=apply)


def outputs(payload: DataFrame, tag_type: TagType, tag, scorers: list[Scorer], key: str = "object_id") -> list[Column]:
    """Raw outputs of simulated scorers for one tag."""
    has_tag = F.col(tag_type.truth) == F.lit(tag)
    return [s.column(F.col(key), has_tag, tag_type.number(tag)) for s in scorers]
