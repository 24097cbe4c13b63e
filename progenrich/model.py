"""What a query is about: tag types, scorers, catalogs."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession


@dataclass(frozen=True)
class TagType:
    """A column whose values are not known at query time; ``truth`` names the hidden column."""

    name: str
    domain: tuple
    truth: str

    def number(self, tag) -> int:
        return self.domain.index(tag)


@dataclass(frozen=True)
class Scorer:
    """A function from objects to the probability of a tag, with a cost and a quality.

    ``column(payload key, truth is the tag, tag number)`` gives a Column for simulated scorers;
    ``apply(payload, type, tag)`` gives ``object_id, prob`` for any other kind.
    """

    tag_type: str
    number: int
    cost: float
    quality: float
    column: Callable[..., Column] | None = field(default=None, compare=False)
    apply: Callable[..., DataFrame] | None = field(default=None, compare=False)

    @property
    def ratio(self) -> float:
        return self.quality / self.cost


@dataclass(frozen=True)
class Catalog:
    types: tuple[TagType, ...]
    scorers: tuple[Scorer, ...]

    def type(self, name: str) -> TagType:
        return next(t for t in self.types if t.name == name)

    def of(self, type_name: str) -> list[Scorer]:
        return sorted((s for s in self.scorers if s.tag_type == type_name), key=lambda s: s.number)

    def seed(self, type_name: str) -> Scorer:
        """The scorer of best quality per cost, the least number among equals."""
        return max(self.of(type_name), key=lambda s: (s.ratio, -s.number))

    def weights(self, type_name: str) -> list[float]:
        """Quality shares within the type."""
        q = [s.quality for s in self.of(type_name)]
        return [x / sum(q) for x in q]

    def to_df(self, spark: SparkSession) -> DataFrame:
        rows = [(s.tag_type, s.number, float(s.quality), float(s.cost), s.number == self.seed(s.tag_type).number) for s in self.scorers]
        return spark.createDataFrame(rows, "tag_type string, scorer int, quality double, cost double, is_seed boolean")
