"""Column expressions for the test: variance, z, p, verdicts."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

# Rational approximation of erfc (error below 1.5e-7).
ERFC_P = 0.3275911
ERFC_A = (0.254829592, -0.284496736, 1.421413741, -1.453152027, 1.061405429)


def upper_p(z: Column) -> Column:
    """Chance of a standard normal above ``z``."""
    x = F.abs(z) / F.lit(2**0.5)
    t = 1 / (1 + ERFC_P * x)
    poly = F.lit(0.0)
    for a in reversed(ERFC_A):
        poly = (poly + a) * t
    tail = poly * F.exp(-x * x) / 2
    return F.when(z >= 0, tail).otherwise(1 - tail)


def var_no_ties(n: Column) -> Column:
    """Variance of the mean vote t without ties."""
    return 2 * (2 * n + 5) / (9 * n * (n - 1))


def var_with_ties(n: Column, a: dict[str, Column], b: dict[str, Column]) -> Column:
    """Variance of the vote sum S; a, b hold the tie sums t2 = sum u(u-1), t3 = sum u(u-1)(u-2), t5 = sum u(u-1)(2u+5).

    Terms whose denominator vanishes are 0 when their numerator is."""
    n = n.cast("double")
    main = (n * (n - 1) * (2 * n + 5) - a["t5"] - b["t5"]) / 18
    third = F.when(n > 2, a["t3"] * b["t3"] / (9 * n * (n - 1) * (n - 2))).otherwise(0.0)
    second = F.when(n > 1, a["t2"] * b["t2"] / (2 * n * (n - 1)))
    return main + third + second


def verdict(z: Column, alpha: float = 0.05) -> Column:
    """attraction, repulsion, none, or undetermined where z is null; each tail at ``alpha``."""
    return F.when(z.isNull(), "undetermined").when(upper_p(z) < alpha, "attraction").when(upper_p(-z) < alpha, "repulsion").otherwise("none")


def var_bound(n: Column, tau: Column) -> Column:
    return 2 * (1 - tau * tau) / n


def required_n(tau: float, se: float) -> int:
    """References that keep the standard error of t below ``se``."""
    return -int(-(2 * (1 - tau * tau) / se**2) // 1)


def references_for(tau: Column, se: Column) -> Column:
    """The same from columns."""
    return F.ceil(2 * (1 - tau * tau) / (se * se)).cast("long")


def two_sided(z: Column) -> Column:
    """Chance of a standard normal farther from 0 than ``z`` on either side."""
    return 2 * upper_p(F.abs(z))
