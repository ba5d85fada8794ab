"""Entropy, mutual information and conditional mutual information from counts.

Everything works on tables of counts ("cells").  With g(c) = c log c, N H(A) = N log N - sum g(c_a), so a measure is a
signed sum of sums of g over roll-ups of the same cells: no division before the end and no branch for empty cells.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Negative results of this size are rounding and become 0.
NOISE = 1e-9


def log_base(x: Column, base: str = "2") -> Column:
    return F.log2(x) if base == "2" else F.log(x)


def g(c: Column, base: str = "2") -> Column:
    """c log c; 0 for an empty cell."""
    c = c.cast("double")
    return F.when(c > 0, c * log_base(F.greatest(c, F.lit(1e-300)), base)).otherwise(0.0)


def clamp(x: Column) -> Column:
    return F.when((x < 0) & (x > -NOISE), 0.0).otherwise(x)


def _rolled(cells: DataFrame, by: list[str], sets: dict[str, list[str]], c: str, base: str) -> DataFrame:
    """Per ``by``: n, and for each named set of columns the sum of g over the counts rolled up to it.  One pass over the cells."""
    over = sorted({x for s in sets.values() for x in s})
    grouping = [[*by, *s] for s in sets.values()]
    keys = [F.col(x) for x in (*by, *over)]
    rolled = cells.groupingSets(grouping, *keys).agg(F.sum(c).alias("_c"), *[F.grouping(x).alias(f"_g_{x}") for x in over])
    terms = []
    for name, s in sets.items():
        here = F.lit(True)
        for x in over:
            here = here & (F.col(f"_g_{x}") == (0 if x in s else 1))
        terms.append(F.sum(F.when(here, g(F.col("_c"), base)).otherwise(0.0)).alias(name))
        if not s:
            terms.append(F.sum(F.when(here, F.col("_c"))).cast("double").alias("n"))
    return rolled.groupBy(*by).agg(*terms) if by else rolled.agg(*terms)


def entropy(cells: DataFrame, by: list[str], over: list[str], c: str = "c", base: str = "2") -> DataFrame:
    """H of the joint distribution of ``over`` within each ``by``: entropy."""
    r = _rolled(cells, by, {"all": [], "joint": over}, c, base)
    return r.select(*by, clamp(log_base(F.col("n"), base) - F.col("joint") / F.col("n")).alias("entropy"))


def cond_entropy(cells: DataFrame, a: str, b: list[str], by: list[str], c: str = "c", base: str = "2") -> DataFrame:
    """H(A | B): cond_entropy."""
    r = _rolled(cells, by, {"all": [], "ab": [a, *b], "b": list(b)}, c, base)
    return r.select(*by, clamp((F.col("b") - F.col("ab")) / F.col("n")).alias("cond_entropy"))


def mutual_info(cells: DataFrame, a: str, b: str, by: list[str], c: str = "c", base: str = "2") -> DataFrame:
    """I(A; B): mi."""
    r = _rolled(cells, by, {"all": [], "ab": [a, b], "a": [a], "b": [b]}, c, base)
    return r.select(*by, clamp(log_base(F.col("n"), base) + (F.col("ab") - F.col("a") - F.col("b")) / F.col("n")).alias("mi"))


def cond_mutual_info(cells: DataFrame, a: str, b: str, given: list[str], by: list[str], c: str = "c", base: str = "2") -> DataFrame:
    """I(A; B | given): cmi.  ``given`` may be several columns."""
    given = list(given)
    r = _rolled(cells, by, {"all": [], "abc": [a, b, *given], "ac": [a, *given], "bc": [b, *given], "c": given}, c, base)
    return r.select(*by, clamp((F.col("abc") + F.col("c") - F.col("ac") - F.col("bc")) / F.col("n")).alias("cmi"))


def mi_and_cmi(cells: DataFrame, by: str = "feature", base: str = "2") -> DataFrame:
    """I(x; j) and I(x; j | y) of each feature from its cells (x, j, y): mi, cmi, in one pass."""
    sets = {"all": [], "xjy": ["x", "j", "y"], "xj": ["x", "j"], "xy": ["x", "y"], "jy": ["j", "y"], "x": ["x"], "j": ["j"], "y": ["y"]}
    r = _rolled(cells, [by], sets, "c", base)
    n = F.col("n")
    mi = log_base(n, base) + (F.col("xj") - F.col("x") - F.col("j")) / n
    cmi = (F.col("xjy") + F.col("y") - F.col("xy") - F.col("jy")) / n
    return r.select(by, clamp(mi).alias("mi"), clamp(cmi).alias("cmi"))


def cube_information(cube: np.ndarray) -> tuple[float, float]:
    """I(x; j) and I(x; j | y) in bits of a table of counts (x, j, y); zeros for an empty one."""

    def s(c: np.ndarray) -> float:
        c = c[c > 0].astype(np.float64)
        return float((c * np.log2(c)).sum())

    n = float(cube.sum())
    if not n:
        return 0.0, 0.0
    xj = cube.sum(2)
    mi = np.log2(n) + (s(xj) - s(xj.sum(1)) - s(xj.sum(0))) / n
    cmi = (s(cube) + s(cube.sum((0, 1))) - s(cube.sum(1)) - s(cube.sum(0))) / n
    return tuple(0.0 if -NOISE < v < 0 else float(v) for v in (mi, cmi))


def pair_info(cells: DataFrame, by: str = "feature", base: str = "2") -> DataFrame:
    """I(x j; y), what a feature and the chosen one tell together: pair_info = I(j; y) + I(x; y | j)."""
    r = _rolled(cells, [by], {"all": [], "xjy": ["x", "j", "y"], "xj": ["x", "j"], "y": ["y"]}, "c", base)
    n = F.col("n")
    return r.select(by, clamp(log_base(n, base) + (F.col("xjy") - F.col("xj") - F.col("y")) / n).alias("pair_info"))


def proportions(cells: DataFrame, keep: list[str], c: str = "c") -> DataFrame:
    """Joint or marginal proportions of the columns to keep: p.  The total joins as one row."""
    total = cells.agg(F.sum(c).cast("double").alias("_n"))
    return cells.groupBy(*keep).agg(F.sum(c).alias("c")).crossJoin(F.broadcast(total)).select(*keep, (F.col("c") / F.col("_n")).alias("p"))


def cond_mutual_info_set(df: DataFrame, a: str, y: str, given: list[str], base: str = "2") -> DataFrame:
    """I(A; Y | S) for a small set S of columns, counted jointly: cells grow with the product of cardinalities."""
    return cond_mutual_info(df.groupBy(a, y, *given).agg(F.count("*").alias("c")), a, y, given, [], base=base)
