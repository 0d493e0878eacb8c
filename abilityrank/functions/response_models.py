"""Item-response models as column expressions; arrays run over options."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from .draws import logistic, unit_step


def p_correct(theta: Column, a: Column | float = 1.0, b: Column | float = 0.0, c: Column | float = 0.0) -> Column:
    """Binary: a floor for guesses, discrimination and difficulty; defaults give the smaller models."""
    a, b, c = (F.lit(x) if not isinstance(x, Column) else x for x in (a, b, c))
    return c + (1.0 - c) * logistic(a * (theta - b))


def _between(passing: Column) -> Column:
    """Probabilities of 0..k-1 passed thresholds, from those of passing each."""
    upper = F.concat(F.array(F.lit(1.0)), passing)
    lower = F.concat(passing, F.array(F.lit(0.0)))
    return F.zip_with(upper, lower, lambda x, y: x - y)


def p_graded(theta: Column, a: Column, thresholds: Column) -> Column:
    """Ordered options: logistic curves of one slope at rising thresholds."""
    return _between(F.transform(thresholds, lambda b: logistic(a * (theta - b))))


def p_step(theta: Column, thresholds: Column) -> Column:
    """The ideal case: the option is how many thresholds ability has reached."""
    return _between(F.transform(thresholds, lambda b: unit_step(theta - b)))


def _weights(theta: Column, slopes: Column, places: Column) -> Column:
    return F.zip_with(slopes, places, lambda a, b: F.exp(a * (theta - b)))


def _total(x: Column) -> Column:
    return F.aggregate(x, F.lit(0.0), lambda s, y: s + y)


def p_nominal(theta: Column, slopes: Column, places: Column) -> Column:
    """Unordered options: each option's own line, normalised exponentially."""
    w = _weights(theta, slopes, places)
    return F.transform(w, lambda x: x / _total(w))


def p_nominal_guess(theta: Column, slopes: Column, places: Column, hidden: Column | float = 0.0) -> Column:
    """Nominal with a hidden option "does not know", whose mass the visible ones share alike."""
    w = _weights(theta, slopes, places)
    z = F.exp(hidden if isinstance(hidden, Column) else F.lit(float(hidden)))
    return F.transform(w, lambda x: (x + z / F.size(w)) / (_total(w) + z))


def draw_option(u: Column, probabilities: Column) -> Column:
    """The first option (from 0) whose cumulative probability exceeds u."""
    start = F.struct(F.lit(0.0).alias("cum"), F.lit(0).alias("passed"))
    walked = F.aggregate(probabilities, start, lambda s, p: F.struct((s["cum"] + p).alias("cum"), (s["passed"] + F.when(u >= s["cum"] + p, 1).otherwise(0)).alias("passed")))
    return F.least(walked["passed"], F.size(probabilities) - 1)


def n_params(model: str, k: int) -> int:
    """Free parameters of one item."""
    return {"binary1": 1, "binary2": 2, "binary3": 3, "graded": k, "nominal": 2 * (k - 1), "nominal_guess": 2 * k, "step": k - 1}[model]
