"""Keyed noise: every draw is a function of a secret and a key, so a recomputed partition never draws anew."""

from __future__ import annotations

import hashlib
import math
import secrets

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Published key of tests and registered queries, never a default: Release.write and sinks.write refuse it unless told that they test.
TEST_SECRET = "public-test-key"

#: L1 sensitivities: a count, the unevenness of a split, the rank utility of a median, a sum of positions per unit of extent.
COUNT, UNEVENNESS, RANK = 1.0, 2.0, 1.0

_BITS = 48


def fresh_secret() -> str:
    """256 random bits for one release; never stored with it."""
    return secrets.token_hex(32)


def _c(x) -> Column:
    return x if isinstance(x, Column) else F.lit(x)


def held(secret: str | None) -> str:
    """The secret, or an error: noise that anyone can draw again protects nothing, so no release has a default."""
    if not secret:
        raise ValueError("a release needs a secret of its own: noise.fresh_secret()")
    return secret


def key_of(secret: str | None, *parts) -> Column:
    held(secret)
    return F.concat_ws("/", F.lit(secret), *(_c(p).cast("string") for p in parts))


def keyed_uniform(secret: str, *parts) -> Column:
    """A uniform in (0, 1): 48 bits of SHA-256 of the key."""
    head = F.substring(F.sha2(key_of(secret, *parts).cast("binary"), 256), 1, _BITS // 4)
    return (F.conv(head, 16, 10).cast("double") + 0.5) / float(1 << _BITS)


def laplace(value, scale, secret: str, *parts) -> Column:
    """value plus Laplace noise of the given scale, by the inverse distribution function."""
    u = keyed_uniform(secret, *parts) - 0.5
    return _c(value) - F.signum(u) * F.log(1 - 2 * F.abs(u)) * _c(scale)


def gumbel(secret: str, *parts) -> Column:
    return -F.log(-F.log(keyed_uniform(secret, *parts)))


def two_sided_geometric(value, eps, secret: str, *parts) -> Column:
    """value plus integer noise with weight exp(-eps * abs(z)): the difference of two geometric draws."""
    draw = lambda side: F.floor(F.log(keyed_uniform(secret, *parts, side)) / -_c(eps))
    return _c(value) + draw("up") - draw("down")


def gaussian_pair(secret: str, *parts) -> tuple[Column, Column]:
    """Two independent standard normals (Box-Muller)."""
    radius = F.sqrt(-2 * F.log(keyed_uniform(secret, *parts, "r")))
    angle = 2 * math.pi * keyed_uniform(secret, *parts, "a")
    return radius * F.cos(angle), radius * F.sin(angle)


def exponential_score(utility, eps, sensitivity, secret: str, *parts) -> Column:
    """The item of largest score is drawn with weight exp(eps * utility / (2 * sensitivity))."""
    return _c(utility) * _c(eps) / (2.0 * sensitivity) + gumbel(secret, *parts)


def uniform_of(secret: str, *parts) -> float:
    """keyed_uniform for code that runs inside a task."""
    key = "/".join(map(str, (held(secret), *parts))).encode()
    return (int.from_bytes(hashlib.sha256(key).digest()[: _BITS // 8], "big") + 0.5) / float(1 << _BITS)


def laplace_of(scale: float, secret: str, *parts) -> float:
    u = uniform_of(secret, *parts) - 0.5
    return -math.copysign(1, u) * math.log(1 - 2 * abs(u)) * scale


def gumbel_of(secret: str, *parts) -> float:
    return -math.log(-math.log(uniform_of(secret, *parts)))
