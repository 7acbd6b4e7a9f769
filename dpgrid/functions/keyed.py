"""Keyed random draws as column expressions.

A draw is a hash of (key, purpose, run, place), so a task that is run again, on whatever executor or partitioning,
draws the same noise. That is a matter of privacy as well as of reproducibility: two draws for
one count would let it be averaged. A public key serves evaluation only; a release needs a secret key.
"""

from __future__ import annotations

import math
from fractions import Fraction

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Hex digits of the digest that make a 52-bit integer.
DIGITS = 13
_STEPS = float(2**52)
#: Least and largest uniform draw.
LEAST, MOST = 0.5 / _STEPS, (_STEPS - 0.5) / _STEPS


def _digest(key: str, purpose: str, parts: tuple[Column | str, ...], source: str) -> Column:
    text = F.concat_ws("|", F.lit(key), F.lit(purpose), *[F.col(p).cast("string") if isinstance(p, str) else p.cast("string") for p in parts])
    if source not in ("keyed", "secret"):
        raise ValueError(f"noise source {source!r}")
    return F.substring(F.md5(text.cast("binary")) if source == "keyed" else F.sha2(text.cast("binary"), 256), 1, DIGITS)


def keyed_uniform(key: str, purpose: str, *parts: Column | str, source: str = "keyed") -> Column:
    """Uniform on (0, 1), never an end point. ``source="secret"`` hashes with SHA-256 instead of MD5."""
    return (F.conv(_digest(key, purpose, parts, source), 16, 10).cast("long").cast("double") + 0.5) / F.lit(_STEPS)


def keyed_below(share: float, key: str, purpose: str, *parts: Column | str, source: str = "keyed") -> Column:
    """``keyed_uniform(...) < share``, decided on the digits as text: draws are in their order, and none is turned into a number."""
    least = math.ceil(Fraction(share) * 16**DIGITS - Fraction(1, 2))  # of the integers whose draw is not below
    if not 0 < least < 16**DIGITS:
        return F.lit(least > 0)
    return _digest(key, purpose, parts, source) < F.lit(f"{least:0{DIGITS}x}")


def laplace(u: Column, scale: Column | float) -> Column:
    """Laplace draw of that scale by the inverse distribution function."""
    b = F.lit(float(scale)) if isinstance(scale, (int, float)) else scale
    return -b * F.signum(u - 0.5) * F.log(F.lit(1.0) - 2.0 * F.abs(u - 0.5))


def gumbel(u: Column) -> Column:
    """Standard Gumbel draw."""
    return -F.log(-F.log(u))


def geometric(u1: Column, u2: Column, scale: Column | float) -> Column:
    """Two-sided geometric draw, an integer: the difference of two one-sided draws of ratio exp(-1/scale)."""
    b = F.lit(float(scale)) if isinstance(scale, (int, float)) else scale
    return F.floor(F.log(u1) * -b) - F.floor(F.log(u2) * -b)
