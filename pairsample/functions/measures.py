"""Similarity measures for biased pair sampling.

A measure is usable if the co-occurrence count k of a pair times a weight f(ci, cj, s) is 1 exactly when its similarity is s, f falling
in each argument. Every formula is kept as SQL text that Spark and DuckDB read alike, built from double operands, so that a plan and its
check evaluate the same double expression; the array form does the same steps in the same order.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def dbl(x) -> str:
    """A double literal both engines read as DOUBLE."""
    return f"{float(x)!r}e0" if "e" not in repr(float(x)) else repr(float(x))


@dataclass(frozen=True)
class Measure:
    """Formulas over operand texts: ``weight(ci, cj, s, m)``, ``sim(k, ci, cj, m)`` and ``solve(ci, cj, x, m)``, the s at which the weight is x
    (null where there is none and any s will do). ``array`` is the weight over arrays. ``uses_m`` tells whether the number of transactions enters.
    """

    name: str
    weight: Callable[[str, str, str, str], str]
    sim: Callable[[str, str, str, str], str]
    solve: Callable[[str, str, str, str], str]
    array: Callable
    uses_m: bool = False

    def weight_col(self, delta: float, ci: str = "ci", cj: str = "cj", m: str = "m") -> Column:
        return F.expr(self.weight_sql(delta, ci, cj, m))

    def weight_sql(self, delta: float, ci: str = "ci", cj: str = "cj", m: str = "m") -> str:
        return self.weight(_d(ci), _d(cj), dbl(delta), _d(m))

    def sim_sql(self, k: str = "k", ci: str = "ci", cj: str = "cj", m: str = "m") -> str:
        return self.sim(_d(k), _d(ci), _d(cj), _d(m))

    def solve_sql(self, x: str, ci: str = "ci", cj: str = "cj", m: str = "m") -> str:
        return self.solve(_d(ci), _d(cj), x, _d(m))


def _d(x: str) -> str:
    return f"CAST({x} AS DOUBLE)"


def _power(name: str, of: Callable[[str, str], str], array: Callable) -> Measure:
    """Measures k / g(ci, cj), whose weight is 1 / (s g)."""
    return Measure(
        name,
        lambda ci, cj, s, m: f"(1e0 / ({s} * {of(ci, cj)}))",
        lambda k, ci, cj, m: f"({k} / {of(ci, cj)})",
        lambda ci, cj, x, m: f"(1e0 / ({x} * {of(ci, cj)}))",
        lambda ci, cj, s, m: 1.0 / (s * array(ci, cj)),
    )


COSINE = _power("cosine", lambda a, b: f"sqrt({a} * {b})", lambda a, b: np.sqrt(a * b))
ALL_CONFIDENCE = _power("all_confidence", lambda a, b: f"greatest({a}, {b})", np.maximum)
DICE = _power("dice", lambda a, b: f"({a} + {b})", lambda a, b: a + b)
OVERLAP = _power("overlap", lambda a, b: f"least({a}, {b})", np.minimum)
DICE_STD = _power("dice_std", lambda a, b: f"(({a} + {b}) / 2e0)", lambda a, b: (a + b) / 2.0)
LIFT_RAW = _power("lift_raw", lambda a, b: f"({a} * {b})", lambda a, b: a * b)
LIFT = Measure(
    "lift",
    lambda ci, cj, s, m: f"({m} / ({s} * ({ci} * {cj})))",
    lambda k, ci, cj, m: f"({m} * {k} / ({ci} * {cj}))",
    lambda ci, cj, x, m: f"({m} / ({x} * ({ci} * {cj})))",
    lambda ci, cj, s, m: m / (s * (ci * cj)),
    uses_m=True,
)
JACCARD = Measure(
    "jaccard",
    lambda ci, cj, s, m: f"((1e0 + {s}) / ({s} * ({ci} + {cj})))",
    lambda k, ci, cj, m: f"({k} / ({ci} + {cj} - {k}))",
    # (1 + s) / (s c) = x gives s = 1 / (x c - 1); at x c <= 1 the weight is larger for every s
    lambda ci, cj, x, m: f"(CASE WHEN {x} * ({ci} + {cj}) > 1e0 THEN 1e0 / ({x} * ({ci} + {cj}) - 1e0) END)",
    lambda ci, cj, s, m: (1.0 + s) / (s * (ci + cj)),
)
#: k / ci + k / cj: bounds every measure but lift from above.
TWO_SIDED = Measure(
    "two_sided",
    lambda ci, cj, s, m: f"((1e0 / {ci} + 1e0 / {cj}) / {s})",
    lambda k, ci, cj, m: f"({k} * (1e0 / {ci} + 1e0 / {cj}))",
    lambda ci, cj, x, m: f"((1e0 / {ci} + 1e0 / {cj}) / {x})",
    lambda ci, cj, s, m: (1.0 / ci + 1.0 / cj) / s,
)
MEASURES = {x.name: x for x in (COSINE, JACCARD, LIFT, ALL_CONFIDENCE, DICE, OVERLAP, DICE_STD, LIFT_RAW, TWO_SIDED)}


def register_measure(measure: Measure) -> Measure:
    """Make a measure of the user's own known by its name; check it with ``monotone_violations`` first."""
    MEASURES[measure.name] = measure
    return measure


def get(measure: str | Measure) -> Measure:
    return measure if isinstance(measure, Measure) else MEASURES[measure]


def all_of(parts: list[tuple[str | Measure, float, float]], name: str = "all_of") -> Measure:
    """Both conditions at once: the least of the weighted parts, each (measure, delta, factor), which falls where all of them do."""
    return _joined(parts, name, "least", np.minimum)


def any_of(parts: list[tuple[str | Measure, float, float]], name: str = "any_of") -> Measure:
    """Either condition: the greatest of the weighted parts."""
    return _joined(parts, name, "greatest", np.maximum)


def blend(parts: list[tuple[str | Measure, float, float]], name: str = "blend") -> Measure:
    """The weighted sum of the parts' weights."""
    return _joined(parts, name, None, np.add)


def _joined(parts, name, function, fold) -> Measure:
    known = [(get(p), d, a) for p, d, a in parts]

    def weight(ci, cj, s, m):
        each = [f"({dbl(a)} * {p.weight(ci, cj, dbl(d), m)} / {s})" for p, d, a in known]
        return f"{function}({', '.join(each)})" if function else f"({' + '.join(each)})"

    def array(ci, cj, s, m):
        each = [a * p.array(ci, cj, d, m) / s for p, d, a in known]
        out = each[0]
        for x in each[1:]:
            out = fold(out, x)
        return out

    # the joint similarity is k times the joint weight at s = 1, so the threshold is 1
    return Measure(
        name, weight, lambda k, ci, cj, m: f"({k} * {weight(ci, cj, '1e0', m)})", lambda ci, cj, x, m: f"({weight(ci, cj, '1e0', m)} / {x})", array, any(p.uses_m for p, _, _ in known),
    )


def monotone_violations(measure: str | Measure, grid: DataFrame, m: float = 1000.0) -> DataFrame:
    """Points (ci, cj, s) of a grid at which the weight grows when one argument grows by a step: none for a usable measure."""
    of = get(measure)
    at = grid.select(F.col("ci").cast("double").alias("ci"), F.col("cj").cast("double").alias("cj"), F.col("s").cast("double").alias("s"))
    here = F.expr(of.weight("ci", "cj", "s", dbl(m)))
    moved = [F.expr(of.weight(a, b, s, dbl(m))) for a, b, s in (("(ci + 1e0)", "cj", "s"), ("ci", "(cj + 1e0)", "s"), ("ci", "cj", "(s * 1.25e0)"))]
    tolerance = F.abs(here) * 1e-12
    return at.where((moved[0] > here + tolerance) | (moved[1] > here + tolerance) | (moved[2] > here + tolerance))
