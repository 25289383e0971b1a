"""Seeds that are a hash of the key: the same on every element, task, retry and engine."""

from __future__ import annotations

from pyspark.sql import Column, functions as F

SCALE = float(1 << 52)


def seed_bits(key: Column, salt: str | Column) -> Column:
    """52 bits of md5(salt|key)."""
    salted = F.concat(salt.cast("string") if isinstance(salt, Column) else F.lit(salt), F.lit("|"), key)
    return F.conv(F.substring(F.md5(salted.cast("binary")), 1, 13), 16, 10).cast("bigint")


def unit_seed(key: Column, salt: str | Column = "s") -> Column:
    """Uniform in (0, 1)."""
    return (seed_bits(key, salt) + F.lit(0.5)) / F.lit(SCALE)


def fast_unit_seed(key: Column, salt: str | Column = "s") -> Column:
    """Uniform in (0, 1) from xxhash64: cheaper, but only this engine can follow it."""
    salted = salt if isinstance(salt, Column) else F.lit(salt)
    return (F.shiftrightunsigned(F.xxhash64(salted, key), 12) + F.lit(0.5)) / F.lit(SCALE)


def exp_of(u: Column) -> Column:
    """An Exp(1) draw that grows with ``u``, so that samples of several kinds share keys."""
    return -F.log(F.lit(1.0) - u)


def draw(key: Column, salt: str | Column = "s", scheme: str = "ppswor", fast: bool = False) -> Column:
    """The random draw of a key: Exp(1) for ppswor, U(0, 1) for priority."""
    u = fast_unit_seed(key, salt) if fast else unit_seed(key, salt)
    if scheme == "ppswor":
        return exp_of(u)
    if scheme == "priority":
        return u
    raise ValueError(scheme)


def inclusion(scheme: str, weight: Column, tau: Column) -> Column:
    """Chance that a key of ``weight`` has a seed below ``tau``; a null threshold includes always, a zero weight never."""
    p = -F.expm1(-weight * tau) if scheme == "ppswor" else F.least(F.lit(1.0), weight * tau)
    return F.when(weight <= 0, F.lit(0.0)).when(tau.isNull(), F.lit(1.0)).otherwise(p)


def wr_inclusion(q: Column, k: int) -> Column:
    """Chance that k draws with replacement meet a key of single-draw chance q."""
    return F.when(q >= 1, F.lit(1.0)).otherwise(-F.expm1(F.lit(float(k)) * F.log1p(-q)))
