"""erfc by panels: [0, 6) in 24 panels of width 1/4, degree 14 in the centred variable, 0 beyond.

The coefficients are made here: interpolation at Chebyshev points in 50-digit decimals. Beside them: p of a
chi-squared statistic with one degree of freedom, and the floor below which no p is reported.
"""

from __future__ import annotations

import functools
import math
from decimal import Decimal, getcontext, localcontext

from pyspark.sql import Column
from pyspark.sql import functions as F

PANELS, WIDTH, DEGREE, END = 24, 0.25, 14, 6.0
P_FLOOR = 1e-16


def _erfc_decimal(t: Decimal) -> Decimal:
    """1 - erf by its all-positive series, with digits to spare for the subtraction."""
    pi = Decimal("3.14159265358979323846264338327950288419716939937510582097494459230781640628620899")
    total = term = t
    k = 0
    while abs(term) > Decimal(10) ** -70:
        k += 1
        term = term * 2 * t * t / (2 * k + 1)
        total += term
    return 1 - 2 / pi.sqrt() * (-t * t).exp() * total


@functools.cache
def coefficients() -> tuple[tuple[float, ...], ...]:
    """One row per panel, from the constant up."""
    out = []
    with localcontext() as ctx:
        ctx.prec = 75
        getcontext().prec = 75
        n = DEGREE + 1
        nodes = [Decimal(repr(math.cos(math.pi * (2 * k + 1) / (2 * n)) * WIDTH / 2)) for k in range(n)]
        for panel in range(PANELS):
            centre = Decimal(repr((panel + 0.5) * WIDTH))
            table = [_erfc_decimal(centre + u) for u in nodes]
            for gap in range(1, n):  # divided differences in place
                for k in range(n - 1, gap - 1, -1):
                    table[k] = (table[k] - table[k - 1]) / (nodes[k] - nodes[k - gap])
            poly = [Decimal(0)] * n
            for k in range(n - 1, -1, -1):  # Newton form to powers
                poly = [(poly[i - 1] if i else Decimal(0)) - nodes[k] * poly[i] for i in range(n)]
                poly[0] += table[k]
            out.append(tuple(float(c) for c in poly))
    return tuple(out)


def erfc_panels(t: Column) -> Column:
    """erfc of t >= 0."""
    grid = F.array(*[F.array(*[F.lit(c) for c in reversed(row)]) for row in coefficients()])
    panel = F.least(F.floor(t / WIDTH), F.lit(PANELS - 1)).cast("int")
    u = t - (panel + 0.5) * WIDTH
    value = F.aggregate(F.get(grid, panel), F.lit(0.0), lambda acc, c: acc * u + c)
    return F.when(t >= END, F.lit(0.0)).otherwise(value)


def erfc_value(t: float) -> float:
    """The same on the driver."""
    if t >= END:
        return 0.0
    panel = min(int(t / WIDTH), PANELS - 1)
    u, out = t - (panel + 0.5) * WIDTH, 0.0
    for c in reversed(coefficients()[panel]):
        out = out * u + c
    return out


def chi2_1df_sf(x: Column) -> Column:
    """Upper tail of chi-squared with one degree of freedom, floored."""
    return F.greatest(erfc_panels(F.sqrt(x / 2)), F.lit(P_FLOOR))


def neglog10(p: Column) -> Column:
    return -F.log10(p)
