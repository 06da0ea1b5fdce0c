"""Reproducible randomness as column expressions.

Every draw is a function of a text key (seed, purpose, id), so a task that runs again publishes the same noise: a fresh
draw for the same release would cost privacy.  A uniform is the first 52 bits of md5 of the key; a Laplace draw is the
inverse distribution function on it.  In lattice mode a draw is rounded to a whole number.  Counts are whole, so
that is rounding the released value, which is post-processing; sums then do not depend on their order.
"""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

TWO_52 = float(2**52)
SPLIT = float(2**40)
WHOLE = "decimal(38,0)"


def hashed(*key: Column, hasher: str = "md5") -> Column:
    """A whole number of 52 bits from the key's parts joined by colons."""
    text = F.concat_ws(":", *[k.cast("string") for k in key])
    if hasher == "md5":
        return F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("long")
    if hasher == "sha2":
        return F.conv(F.substring(F.sha2(text, 256), 1, 13), 16, 10).cast("long")
    if hasher == "xxhash64":  # the fastest; not cryptographic, for experiments
        return F.shiftrightunsigned(F.xxhash64(text), 12)
    raise ValueError(f"unknown hasher {hasher!r}")


def uniform(*key: Column, hasher: str = "md5") -> Column:
    """In (0, 1), never either end."""
    return (hashed(*key, hasher=hasher).cast("double") + 0.5) / TWO_52


def laplace(scale: Column, *key: Column, hasher: str = "md5") -> Column:
    """Zero-mean Laplace noise of the given scale, continuous."""
    u = uniform(*key, hasher=hasher) - 0.5
    return -scale * F.signum(u) * F.ln(1.0 - 2.0 * F.abs(u))


def to_whole(x: Column) -> Column:
    """A whole-valued double, exact up to 2^93, as a decimal."""
    high = F.floor(x / SPLIT)
    return (high.cast("bigint").cast("decimal(20,0)") * F.lit(int(SPLIT)).cast("decimal(13,0)") + (x - high.cast("double") * SPLIT).cast("bigint").cast("decimal(20,0)")).cast(WHOLE)


def lattice_laplace(scale: Column, *key: Column, hasher: str = "md5") -> Column:
    """Laplace noise rounded to whole numbers, as a decimal."""
    return to_whole(F.round(laplace(scale, *key, hasher=hasher)))


def mark(node: Column, k: int, seed: Column) -> Column:
    """The public uniform mark 0..k of a node."""
    return (hashed(seed, F.lit("mark"), node) % (k + 1)).cast("int")


def keep_probability(eps: float) -> float:
    """With which randomized response keeps a bit."""
    return math.exp(eps) / (1 + math.exp(eps))


def randomized_response(bit: Column, eps: float, *key: Column) -> Column:
    """The bit, flipped with probability 1 / (1 + e^eps)."""
    return F.when(uniform(*key) < keep_probability(eps), bit).otherwise(1 - bit)


def unbiased_bit(noisy: Column, eps: float) -> Column:
    """An estimate of the bit whose mean is the bit."""
    p = keep_probability(eps)
    return (noisy.cast("double") - (1 - p)) / (2 * p - 1)


def laplace_mechanism(value: Column, sensitivity: float, eps: float | Column, *key: Column) -> Column:
    """A scalar query's value with noise for its global sensitivity."""
    return value.cast("double") + laplace(F.lit(float(sensitivity)) / (eps if isinstance(eps, Column) else F.lit(check_epsilon(eps))), *key)


def check_epsilon(eps: float) -> float:
    if not (isinstance(eps, (int, float)) and eps > 0 and not math.isinf(eps)):
        raise ValueError(f"epsilon must be positive and finite: {eps!r}")
    return float(eps)
