"""Blenders: the probability of a predicate from the outputs of the scorers that have run."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F


def has(mask: Column, scorer: int) -> Column:
    return mask.bitwiseAND(F.lit(1 << scorer)) != 0


def blend(mask: Column, outputs: list[Column], weights: list[float], op: str = "=", missing: str = "renormalize", kind: str | Callable = "weighted") -> Column:
    """Probability from ``outputs`` of the scorers in ``mask``; for ``!=`` every output is flipped.

    ``missing='renormalize'`` weighs by the executed scorers alone, ``'literal'`` by all (what has not
    run adds 0). No executed scorer gives 0.5 by renormalising, 0 otherwise.
    """
    outs = [1.0 - x if op == "!=" else x for x in outputs]
    on = [has(mask, i) for i in range(len(outs))]
    if callable(kind):
        return kind(on, outs, weights)
    none = mask == 0
    if kind == "weighted":
        total = sum((F.when(o, w * x).otherwise(0.0) for o, x, w in zip(on, outs, weights)), F.lit(0.0))
        if missing == "literal":
            return total
        mass = sum((F.when(o, F.lit(w)).otherwise(0.0) for o, w in zip(on, weights)), F.lit(0.0))
        return F.when(none, F.lit(0.5)).otherwise(total / mass)
    if kind == "mean":
        total = sum((F.when(o, x).otherwise(0.0) for o, x in zip(on, outs)), F.lit(0.0))
        return F.when(none, F.lit(0.5)).otherwise(total / F.bit_count(mask))
    if kind == "max":
        return F.when(none, F.lit(0.5)).otherwise(F.greatest(*[F.when(o, x).otherwise(0.0) for o, x in zip(on, outs)], F.lit(0.0)))
    if kind == "noisy_or":
        rest = F.lit(1.0)
        for o, x in zip(on, outs):
            rest = rest * F.when(o, 1 - x).otherwise(1.0)
        return F.when(none, F.lit(0.5)).otherwise(1 - rest)
    if kind == "log_odds":
        z = F.lit(0.0)
        for o, x in zip(on, outs):
            c = F.least(F.greatest(x, F.lit(1e-6)), F.lit(1 - 1e-6))
            z = z + F.when(o, F.ln(c / (1 - c))).otherwise(0.0)
        return F.when(none, F.lit(0.5)).otherwise(1 / (1 + F.exp(-z / F.greatest(F.bit_count(mask), F.lit(1)))))
    raise ValueError(f"unknown blender {kind!r}")
