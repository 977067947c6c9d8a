"""Noise that is a function of a secret salt, a purpose and a key.

A retried or speculative task, or another partitioning, draws the same values, so repeated execution never releases a second draw.
Every purpose has its own tag, and every release a salt of its own that follows from the secret one, the method, the budget, the matrix, the
options and a label of the data's state, so that no draw is used twice: two releases never share noise that could be solved for a count.
"""

from __future__ import annotations

import hashlib
import math
import secrets

from pyspark.sql import Column
from pyspark.sql import functions as F

SEPARATOR = "|"
PURPOSES = ("total", "count", "leaf", "cand", "pos", "query", "cell", "sample", "point")


def fresh_salt() -> str:
    """A salt for production; it is never stored with a release."""
    return secrets.token_hex(32)


def release_salt(salt: str, method: str, eps: float, matrix: str, *details: object) -> str:
    """The salt of one release, as hexadecimal text. ``details`` holds all options that change what is released, and the label of the data's state."""
    if not salt:
        raise ValueError("a release needs a secret salt")
    return hashlib.sha256(SEPARATOR.join(map(str, (salt, method, repr(float(eps)), matrix, *details))).encode()).hexdigest()


def _text(key: Column | str | int) -> Column:
    return F.lit(str(key)) if isinstance(key, int) else (F.col(key) if isinstance(key, str) else key).cast("string")


def keyed_uniform(salt: str, purpose: str, *keys: Column | str | int) -> Column:
    """A double in (0, 1): the first 52 bits of a SHA-256, plus one half. Strings name columns, integers are literals."""
    digest = F.sha2(F.concat_ws(SEPARATOR, F.lit(salt), F.lit(purpose), *map(_text, keys)), 256)
    return (F.conv(F.substring(digest, 1, 13), 16, 10).cast("bigint") + F.lit(0.5)) / F.lit(float(1 << 52))


def laplace_of(u: Column, scale: Column | float) -> Column:
    """The inverse distribution function of a Laplace variable with mean 0."""
    scale = F.lit(float(scale)) if not isinstance(scale, Column) else scale
    return -scale * F.signum(u - 0.5) * F.log(1 - 2 * F.abs(u - 0.5))


def laplace(salt: str, purpose: str, scale: Column | float, *keys: Column | str | int) -> Column:
    """Keyed Laplace noise; a counting query of sensitivity s with budget e takes the scale s / e."""
    return laplace_of(keyed_uniform(salt, purpose, *keys), scale)


def geometric(salt: str, purpose: str, scale: Column | float, *keys: Column | str | int) -> Column:
    """Keyed two-sided geometric noise: integers, so that no low-order bits of a float can tell the true count."""
    scale = F.lit(float(scale)) if not isinstance(scale, Column) else scale
    side = lambda tag: F.floor(-scale * F.log(keyed_uniform(salt, f"{purpose}{tag}", *keys)))
    return (side("+") - side("-")).cast("double")


def sensitivity(kind: str = "disjoint", unit_bound: int = 1) -> float:
    """How far one unit moves the released values: 1 for disjoint counts, 2 for the homogeneity objective, for each record of a unit."""
    return {"disjoint": 1.0, "objective": 2.0}[kind] * unit_bound


def standard_deviation(scale: float) -> float:
    return math.sqrt(2) * scale
