"""Entropies of token distributions, as column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def token_entropy(dist: Column) -> Column:
    """Entropy in nats of a map token -> probability; zero probabilities add nothing."""
    return F.aggregate(F.map_values(dist), F.lit(0.0), lambda a, p: a - F.when(p > 0, p * F.ln(p)).otherwise(0.0))


def entropy_bounds(top: Column, vocabulary: int) -> tuple[Column, Column]:
    """Lower and upper bound for a log that keeps the likeliest tokens only (an array of probabilities): the rest as
    one token, and spread evenly over the tokens left."""
    held = F.aggregate(top, F.lit(0.0), lambda a, p: a + p)
    seen = F.aggregate(top, F.lit(0.0), lambda a, p: a - F.when(p > 0, p * F.ln(p)).otherwise(0.0))
    tail = F.greatest(1 - held, F.lit(0.0))
    left = F.greatest(F.lit(vocabulary) - F.size(top), F.lit(1))
    lower = seen - F.when(tail > 0, tail * F.ln(tail)).otherwise(0.0)
    return lower, lower + F.when(tail > 0, tail * F.ln(left)).otherwise(0.0)
