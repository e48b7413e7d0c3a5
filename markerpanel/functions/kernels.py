"""Statistics of a 2x2 table given by a count pair and two group sizes, as columns.

Counts stay integers until the products are done. Beta functions of integer counts are prefix sums of
logarithms, held as array literals of length n + 1 up to TABLE individuals, and given by Stirling's series beyond.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from decimal import Decimal

from pyspark.sql import Column
from pyspark.sql import functions as F

from markerpanel.errors import PanelError, ProfileError
from markerpanel.functions.erfc import chi2_1df_sf

GUARD = 20.0
#: Group sizes up to which log tables are sent as literals.
TABLE = 2_000
#: From here on the series is exact to double precision.
SERIES = 32


def _c(c) -> Column:
    return F.col(c) if isinstance(c, str) else c


def _table(start: float, n: int) -> Column:
    """Sums of ln(start + i) for i below k, k = 0..n."""
    parts, out = [], [0.0]
    for i in range(n):
        parts.append(math.log(start + i))
        out.append(math.fsum(parts))
    return F.array(*[F.lit(v) for v in out])


def _log_gamma(x: Column) -> Column:
    """For x >= SERIES."""
    y = 1 / x
    return (x - 0.5) * F.ln(x) - x + 0.5 * math.log(2 * math.pi) + y * (1 / 12 - y * y * (1 / 360 - y * y * (1 / 1260 - y * y / 1680)))


def _sums(start: float, n: int):
    """k -> sum of ln(start + i) for i below k, for an integer k or column of 0..n."""
    head = _table(start, n if n <= TABLE else SERIES)
    at = lambda k: k.cast("int") if isinstance(k, Column) else F.lit(int(k))
    if n <= TABLE:
        return lambda k: F.get(head, at(k))
    return lambda k: F.when(at(k) <= SERIES, F.get(head, at(k))).otherwise(_log_gamma(at(k) + start) - math.lgamma(start))


def yates_chi2(g1, g2, n1: int, n2: int, correct: bool = True) -> Column:
    """Chi-squared of the table, shrunk by half the total (not below zero) if correct; 0 if a margin is 0."""
    a, b = _c(g1).cast("long"), _c(g2).cast("long")
    n = n1 + n2
    cross = F.abs(a * (n2 - b) - b * (n1 - a))
    # twice the shrunk gap stays an integer
    gap = F.greatest(2 * cross - (n if correct else 0), F.lit(0)).cast("double") / 2
    carriers, margins = a + b, F.lit(n1 * n2).cast("double")
    rest = F.lit(n).cast("long") - carriers
    return F.when((carriers == 0) | (rest == 0) | F.lit(n1 * n2 == 0), F.lit(0.0)).otherwise(gap * gap * n / (margins * carriers * rest))


def g_stat(g1, g2, n1: int, n2: int) -> Column:
    """Twice the sum of observed * ln(observed / expected); empty cells add nothing."""
    a, b = _c(g1).cast("double"), _c(g2).cast("double")
    n = float(n1 + n2)
    cell = lambda o, row, group: F.when((o > 0) & (row > 0), o * F.ln(o * n / (row * group))).otherwise(F.lit(0.0))
    has, lacks = a + b, n - a - b
    total = cell(a, has, float(n1)) + cell(b, has, float(n2)) + cell(n1 - a, lacks, float(n1)) + cell(n2 - b, lacks, float(n2))
    return F.greatest(2 * total, F.lit(0.0))


def fisher_exact(g1, g2, n1: int, n2: int, alternative: str = "two-sided") -> Column:
    """Hypergeometric p: the outcomes no likelier than the observed one (slack 1e-7), or one tail."""
    if alternative not in ("two-sided", "greater", "less"):
        raise PanelError(f"alternative {alternative!r}")
    n = n1 + n2
    at = _sums(1.0, n)
    a, k = _c(g1).cast("int"), (_c(g1) + _c(g2)).cast("int")
    fixed = at(n1) + at(n2) - at(n) + at(k) + at(F.lit(n) - k)
    log_p = lambda x: fixed - at(x) - at(F.lit(n1) - x) - at(k - x) - at(F.lit(n2) - k + x)
    lo, hi = F.greatest(F.lit(0), k - n2), F.least(F.lit(n1), k)
    seen = log_p(a)
    keep = {"two-sided": lambda x: log_p(x) <= seen + 1e-7, "greater": lambda x: x >= a, "less": lambda x: x <= a}[alternative]
    total = F.aggregate(F.sequence(lo, hi), F.lit(0.0), lambda s, x: s + F.when(keep(x), F.exp(log_p(x))).otherwise(F.lit(0.0)))
    return F.least(F.lit(1.0), total)


def log_evidence_beta(k, size: int, a: float, b: float) -> Column:
    """ln of the Beta(a, b) integral over k presences among ``size``."""
    if not (math.isfinite(a) and math.isfinite(b) and a > 0 and b > 0):
        raise ProfileError(f"Beta shapes must be finite and positive: {a}, {b}")
    k = _c(k).cast("int")
    return _sums(a, size)(k) + _sums(b, size)(F.lit(size) - k) - _sums(a + b, size)(size)


def log_bf(g1, g2, n1: int, n2: int, shapes=(1.0,) * 6) -> Column:
    """ln Bayes factor: two rates against one shared. shapes: a1, b1, a2, b2, a0, b0."""
    a1, b1, a2, b2, a0, b0 = shapes
    return log_evidence_beta(g1, n1, a1, b1) + log_evidence_beta(g2, n2, a2, b2) - log_evidence_beta(_c(g1) + _c(g2), n1 + n2, a0, b0)


@dataclass(frozen=True)
class Fixed:
    """Presence with one given probability."""

    q: float

    def __post_init__(self):
        if not 0 < self.q < 1:
            raise ProfileError(f"prevalence must be in (0, 1): {self.q}")

    def log_evidence(self, k, size: int) -> Column:
        # 1 - q in decimals: the binary 1 - 0.9 isn't 0.1, and the gap adds up over individuals
        rest = float(1 - Decimal(str(self.q)))
        return _c(k) * math.log(self.q) + (F.lit(size) - _c(k)) * math.log(rest)


@dataclass(frozen=True)
class Beta:
    """Presence with a probability that is integrated out."""

    a: float
    b: float

    def __post_init__(self):
        if not (math.isfinite(self.a) and math.isfinite(self.b) and self.a > 0 and self.b > 0):
            raise ProfileError(f"Beta shapes must be finite and positive: {self.a}, {self.b}")

    def log_evidence(self, k, size: int) -> Column:
        return log_evidence_beta(k, size, self.a, self.b)


@dataclass(frozen=True)
class Prior:
    linked: Fixed | Beta = Fixed(0.9)
    null: Fixed | Beta = Fixed(0.5)
    w: float = 0.5
    pi: float = 0.01
    shapes: tuple = (1.0,) * 6

    def __post_init__(self):
        if not (0 < self.w < 1 and 0 < self.pi < 1):
            raise ProfileError("w and pi must be in (0, 1)")
        if len(self.shapes) != 6 or not all(math.isfinite(s) and s > 0 for s in self.shapes):
            raise ProfileError("six finite positive shapes are needed")


def log_sum_exp(a: Column, b: Column) -> Column:
    high = F.greatest(a, b)
    return high + F.log1p(F.exp(F.least(a, b) - high))


def log_likelihood_ratio(g1, g2, n1: int, n2: int, prior: Prior) -> Column:
    """ln of linked over null evidence, before the prior odds."""
    a, b, n = _c(g1), _c(g2), n1 + n2
    one, two = a + (n2 - b), (n1 - a) + b
    linked = log_sum_exp(prior.linked.log_evidence(one, n) + math.log(prior.w), prior.linked.log_evidence(two, n) + math.log(1 - prior.w))
    return linked - prior.null.log_evidence(a + b, n)


def log_odds(g1, g2, n1: int, n2: int, prior: Prior = Prior()) -> Column:
    return log_likelihood_ratio(g1, g2, n1, n2, prior) + math.log(prior.pi / (1 - prior.pi))


def logistic_guard(odds: Column, guard: float = GUARD) -> Column:
    return 1 / (1 + F.exp(-F.greatest(F.least(odds, F.lit(guard)), F.lit(-guard))))


def posterior(g1, g2, n1: int, n2: int, prior: Prior = Prior()) -> Column:
    return logistic_guard(log_odds(g1, g2, n1, n2, prior))


TESTS = ("yates", "pearson", "g", "fisher")


def p_value(test: str, g1, g2, n1: int, n2: int) -> Column:
    if test == "yates":
        return chi2_1df_sf(yates_chi2(g1, g2, n1, n2))
    if test == "pearson":
        return chi2_1df_sf(yates_chi2(g1, g2, n1, n2, correct=False))
    if test == "g":
        return chi2_1df_sf(g_stat(g1, g2, n1, n2))
    if test == "fisher":
        return F.greatest(fisher_exact(g1, g2, n1, n2), F.lit(1e-16))
    raise PanelError(f"test {test!r}; known: {', '.join(TESTS)}")


def fmt6(x) -> Column:
    """Six significant digits like C's %g: trailing zeros of the mantissa go, a bare point goes."""
    s = F.printf(F.lit("%.6g"), _c(x).cast("double"))
    return F.when(_c(x) == 0, F.lit("0")).otherwise(F.regexp_replace(F.regexp_replace(s, r"(\.\d*?)0+(e|$)", "$1$2"), r"\.(e|$)", "$1"))
