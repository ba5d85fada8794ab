"""Selection criteria as folds over the chosen features.

A criterion keeps accumulators per candidate.  When a feature j is chosen, each accumulator takes in d = I(i; j) and
e = I(i; j | Y); the score is a function of the relevance r = I(i; Y), the accumulators and the number of chosen
features.  Folds and scores are written with an ``ops`` argument (maximum, minimum), so that the same definition works on Spark
columns, which stay in generated code, and on NumPy arrays.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field
from typing import Any

import numpy as np
from pyspark.sql import functions as F


class ColumnOps:
    maximum = staticmethod(lambda a, b: F.greatest(_column(a), _column(b)))
    minimum = staticmethod(lambda a, b: F.least(_column(a), _column(b)))


class ArrayOps:
    maximum = staticmethod(np.maximum)
    minimum = staticmethod(np.minimum)


def _column(x):
    return x if hasattr(x, "alias") else F.lit(float(x))


@dataclass(frozen=True)
class Fold:
    init: float
    combine: Callable[[Any, Any, Any, Any], Any]  # ops, accumulator, d, e -> accumulator


@dataclass(frozen=True)
class Criterion:
    name: str
    folds: dict[str, Fold] = field(default_factory=dict)
    #: ops, relevance, accumulators, number chosen -> score
    score: Callable[[Any, Any, dict[str, Any], int], Any] = lambda ops, r, acc, s: r
    #: Whether a score can only fall as more chosen features are folded in, the number chosen being fixed.
    falling: bool = False
    #: Whether no score is above the relevance.
    bounded: bool = False
    beta: float | None = None
    gamma: float | None = None


_RED = Fold(0.0, lambda ops, a, d, e: a + d)
_CRED = Fold(0.0, lambda ops, a, d, e: a + e)
_GAP = Fold(float("-inf"), lambda ops, a, d, e: ops.maximum(a, d - e))
_CAPPED = Fold(0.0, lambda ops, a, d, e: a + ops.maximum(d - e, 0.0))


def _linear(beta, gamma) -> Callable:
    """beta and gamma: numbers, or None for 1 / number chosen."""

    def score(ops, r, acc, s):
        if not s:
            return r
        b, c = (1 / s if w is None else w for w in (beta, gamma))
        out = r
        if b:
            out = out - b * acc["red"]
        if c:
            out = out + c * acc["cred"]
        return out

    return score


def _folds(beta, gamma) -> dict[str, Fold]:
    return ({"red": _RED} if beta is None or beta else {}) | ({"cred": _CRED} if gamma is None or gamma else {})


def linear(name: str, beta: float | None, gamma: float | None) -> Criterion:
    return Criterion(name, _folds(beta, gamma), _linear(beta, gamma), falling=gamma == 0 and (beta is None or beta >= 0), bounded=gamma == 0 and (beta is None or beta >= 0), beta=beta, gamma=gamma)


_REGISTERED: dict[str, Callable[[float | None, float | None], Criterion]] = {
    "mim": lambda b, c: linear("mim", 0, 0),
    "mifs": lambda b, c: linear("mifs", 1.0 if b is None else b, 0),
    "jmi": lambda b, c: linear("jmi", None, None),
    "cmi": lambda b, c: linear("cmi", 1.0, 1.0),
    "mrmr": lambda b, c: linear("mrmr", None, 0),
    "cmim": lambda b, c: Criterion("cmim", {"gap": _GAP}, lambda ops, r, acc, s: r - acc["gap"] if s else r, falling=True),
    "icap": lambda b, c: Criterion("icap", {"cap": _CAPPED}, lambda ops, r, acc, s: r - acc["cap"] if s else r, falling=True, bounded=True),
    "generic": lambda b, c: linear("generic", 1.0 if b is None else b, 1.0 if c is None else c),
}
_REGISTERED["if"] = lambda b, c: Criterion("if", *(lambda x: (x.folds, x.score, x.falling))(_REGISTERED["cmim"](b, c)))
#: Those that come with the engine.
BUILT_IN = frozenset(_REGISTERED)


def get_criterion(name: str | Criterion, beta: float | None = None, gamma: float | None = None) -> Criterion:
    if isinstance(name, Criterion):
        return name
    try:
        return _REGISTERED[name.lower()](beta, gamma)
    except KeyError:
        raise ValueError(f"unknown criterion {name!r}; known: {', '.join(sorted(_REGISTERED))}") from None


def register_criterion(criterion: Criterion) -> None:
    """Makes a user's criterion available by name."""
    _REGISTERED[criterion.name.lower()] = lambda b, c: criterion


def criteria() -> list[str]:
    return sorted(_REGISTERED)


def original_score(name: str, relevance: float, rounds: list[dict[str, float]], beta: float = 1.0, joint: float | None = None) -> float:
    """A criterion in its first published form, for one candidate.

    ``rounds`` has for each chosen feature j: mi = I(i; j), cmi = I(i; j | Y), pair = I(i j; Y), j_rel = I(j; Y).
    ``joint`` is I(i; Y | S), which the conditional criterion needs.
    """
    if not rounds:
        return relevance
    given = [x["pair"] - x["j_rel"] for x in rounds]  # I(i; Y | j)
    red = sum(x["mi"] for x in rounds)
    match name:
        case "mim":
            return relevance
        case "mifs":
            return relevance - beta * red
        case "mrmr":
            return relevance - red / len(rounds)
        case "jmi":
            return sum(x["pair"] for x in rounds)
        case "cmi":
            if joint is None:
                raise ValueError("the original conditional form needs I(i; Y | S)")
            return joint
        case "cmim" | "if":
            return min(given)
        case "icap":
            return relevance - sum(max(0.0, x["mi"] - x["cmi"]) for x in rounds)
    raise ValueError(f"no original form of {name!r}")
