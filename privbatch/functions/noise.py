"""Noise as a column: a deterministic function of a seed and a key.

Recomputing a lost task gives the same noise, which a generator seeded per partition would not; two
noisy copies of one answer would weaken the guarantee.  The md5 lane is for tests (who knows the seed
can take the noise off again); ``secret``, a column made by ``secret_key``, switches to sha2 under a key
that is read when the query runs and stands in no plan.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def secret_key(spark: SparkSession, path: str) -> Column:
    """The first line of a file that only releases may read, as a scalar subquery: plans and logs show the path alone."""
    return spark.read.text(path).agg(F.min("value")).scalar()


def uniform(seed: int | str, key: Column, lane: int = 0, secret: Column | None = None) -> Column:
    """In (0, 1), from 52 bits."""
    if isinstance(secret, str):
        raise TypeError("a key given as text would stand in the plan: use secret_key")
    text = F.concat_ws(":", F.lit(str(seed)), key.cast("string"), F.lit(str(lane)))
    hashed = F.md5(text) if secret is None else F.sha2(F.concat(secret, F.lit(":"), text), 256)
    return (F.conv(F.substring(hashed, 1, 13), 16, 10).cast("double") + 0.5) / F.lit(float(2**52))


def gaussian(seed: int | str, key: Column, secret: Column | None = None) -> Column:
    u, v = uniform(seed, key, 0, secret), uniform(seed, key, 1, secret)
    return F.sqrt(-2 * F.log(u)) * F.cos(F.lit(2 * math.pi) * v)


def laplace(seed: int | str, key: Column, secret: Column | None = None) -> Column:
    """Scale one, by the inverse distribution function."""
    u = uniform(seed, key, 0, secret) - 0.5
    return -F.signum(u) * F.log(1 - 2 * F.abs(u))


def noise_constant(eps: float, delta: float) -> float:
    """P(eps, delta) = 2 ln(2/delta) / eps^2, the factor of every expected error."""
    _check(eps)
    if not 0 < delta < 1:
        raise ValueError("the Gaussian rule needs 0 < delta < 1")
    return 2 * math.log(2 / delta) / eps**2


def gauss_sigma(sensitivity: float, eps: float, delta: float) -> float:
    return sensitivity * math.sqrt(noise_constant(eps, delta))


def laplace_scale(sensitivity: float, eps: float) -> float:
    _check(eps)
    return sensitivity / eps


def _check(eps: float) -> None:
    if not eps > 0:
        raise ValueError("eps must be positive")
