"""Uncertainty of probabilities, and its inverse, as Column expressions inside code generation."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def entropy_bits(p: Column) -> Column:
    """Binary entropy in bits; 0 at 0 and 1, and outside of them."""
    q = 1.0 - p
    return F.when((p <= 0) | (p >= 1), F.lit(0.0)).otherwise(-p * F.log2(p) - q * F.log2(q))


def entropy_of(ps: list[Column]) -> Column:
    """Entropy of a distribution over tags."""
    total = F.lit(0.0)
    for p in ps:
        total = total + F.when(p <= 0, F.lit(0.0)).otherwise(-p * F.log2(p))
    return total


#: Bounds within which Newton steps stay.
LOW, HIGH = 0.5 + 1e-9, 1 - 1e-12


def root_start(h: Column) -> Column:
    """A closed guess of the upper root, close for all h."""
    return F.least(F.greatest(0.5 * (1 + F.sqrt(F.greatest(F.lit(0.0), 1 - F.pow(h, F.lit(4 / 3))))), F.lit(LOW)), F.lit(HIGH))


def root_step(p: Column, h: Column) -> Column:
    """One Newton step on entropy(p) = h, clamped."""
    return F.least(F.greatest(p - (entropy_bits(p) - h) / F.log2((1 - p) / p), F.lit(LOW)), F.lit(HIGH))


def root_end(p: Column, h: Column) -> Column:
    return F.when(h >= 1, F.lit(0.5)).when(h <= 0, F.lit(1.0)).otherwise(p)


def upper_root(h: Column, steps: int = 4) -> Column:
    """The probability of at least one half whose entropy is ``h``, as one expression.

    The steps are folded over an array, so that the expression does not grow with them.
    """
    return root_end(F.aggregate(F.array(*[F.lit(0.0)] * steps), root_start(h), lambda p, _: root_step(p, h)), h)


def with_upper_root(df: DataFrame, hs: dict[str, str], steps: int = 4) -> DataFrame:
    """Adds the upper root of each column of ``hs`` (new name -> column). Each step is a projection of its own:
    the optimizer keeps them apart as their results are used often, and all of them are compiled."""
    for columns in root_columns(hs, steps):
        df = df.withColumns(columns)
    return df


def root_columns(hs: dict[str, str], steps: int = 4) -> list[dict[str, Column]]:
    """The projections of ``with_upper_root``, in order."""
    step = {out: root_step(F.col(out), F.col(h)) for out, h in hs.items()}
    return [{out: root_start(F.col(h)) for out, h in hs.items()}, *[step] * steps, {out: root_end(F.col(out), F.col(h)) for out, h in hs.items()}]


def inverse_entropy(h: Column, branch: str = "upper") -> Column:
    """``upper``, ``lower`` or ``both`` roots (a struct ``low, high``)."""
    high = upper_root(h)
    if branch == "upper":
        return high
    if branch == "lower":
        return 1 - high
    return F.struct((1 - high).alias("low"), high.alias("high"))


def raised(p: Column, high: Column) -> Column:
    """Of the roots ``high`` and 1 - ``high``, the one that raises ``p``: the lower one if it is not below p,
    else the upper one; never less than p."""
    low = 1 - high
    return F.greatest(p, F.when(low >= p, low).otherwise(high))


def raised_probability(p: Column, h_new: Column) -> Column:
    """The probability that ``p`` rises to when its uncertainty becomes ``h_new``."""
    return raised(p, upper_root(h_new))
