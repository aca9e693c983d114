"""The Gumbel law as columns: distribution, density, quantile, moments, shift-rounding."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

EULER_GAMMA = 0.5772156649015329
VARIANCE = math.pi**2 / 6
#: A uniform on a unit interval adds this to the variance of a shift-rounded register.
ROUNDING_VARIANCE = 1 / 12
#: Largest double below one; keeps log1p(-u) finite.
TOP = 1 - 2.0**-53


def gumbel_cdf(x: Column, mu: Column | float = 0.0) -> Column:
    return F.exp(-F.exp(-(x - mu)))


def gumbel_pdf(x: Column, mu: Column | float = 0.0) -> Column:
    z = x - mu
    return F.exp(-F.exp(-z) - z)


def gumbel_quantile(t: Column, mu: Column | float = 0.0) -> Column:
    """The x whose distribution is t, for t inside (0, 1)."""
    return F.lit(mu) - F.ln(-F.ln(t))


def exponential_from_hash(w: Column, bits: int) -> Column:
    """-ln(1-u), u = (w + 1/2) / 2**bits: standard exponential, exact for small u, finite at both ends."""
    u = F.least((w.cast("double") + 0.5) / F.lit(2.0**bits), F.lit(TOP))
    return -F.log1p(-u)


def gumbel_from_hash(w: Column, bits: int) -> Column:
    """The register's real value: standard Gumbel for uniform w, falling in w."""
    return -F.ln(exponential_from_hash(w, bits))


def gumbel_moments(mu: float = 0.0) -> dict[str, float]:
    return {"mean": mu + EULER_GAMMA, "variance": VARIANCE, "mean_exp_neg": math.exp(-mu), "variance_exp_neg": math.exp(-2 * mu)}


def moment_columns(mu: Column) -> dict[str, Column]:
    """gumbel_moments for a column mu."""
    return {"mean": mu + EULER_GAMMA, "variance": F.lit(VARIANCE), "mean_exp_neg": F.exp(-mu), "variance_exp_neg": F.exp(-2 * mu)}


def max_law_cdf(x: Column, n: Column | int) -> Column:
    """Distribution of the maximum of n standard draws: Gumbel at ln n."""
    return gumbel_cdf(x, F.ln(F.lit(n) if isinstance(n, int) else n))


def shift_round(x: Column, c: Column) -> Column:
    return F.floor(x + c).cast("double") - c


def geometric_bias(k: int) -> float:
    """E[Z]/n of the geometric average over k registers: e**-gamma * Gamma(1 - 1/k)**k, for k > 1."""
    return math.exp(-EULER_GAMMA + k * math.lgamma(1 - 1 / k)) if k > 1 else math.inf
