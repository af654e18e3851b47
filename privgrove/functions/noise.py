"""Keyed noise: every draw is a function of a secret key and of ids, so a task that is run again draws the same.

The uniform takes 52 bits of a SHA-256, plus a half, over 2**52: strictly inside (0, 1) and equal in every engine.
"""

from __future__ import annotations

import hashlib
import math
from fractions import Fraction

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

SCALE = float(1 << 52)


def uniform(key: str, *ids: Column | str) -> Column:
    """A uniform number for the key and ids; ids are joined as text."""
    parts = [F.lit(key), *[(F.col(i) if isinstance(i, str) else i).cast("string") for i in ids]]
    return (F.conv(F.substring(F.sha2(F.concat_ws("|", *parts), 256), 1, 13), 16, 10).cast("long") + 0.5) / F.lit(SCALE)


def below(share: float, key: Column | str, id_col: str) -> Column:
    """Whether the uniform for the key and an id is below `share`, by its digits alone: no number is parsed."""
    text, least = keyed_text(key, id_col), least_digits(share)
    return text.isNotNull() if least is None else F.sha2(text, 256) < F.lit(least)


def keyed_text(key: Column | str, id_col: str) -> Column:
    """Key and id as they are hashed."""
    key = F.lit(key) if isinstance(key, str) else key
    return F.coalesce(F.concat(key, F.lit("|"), F.col(id_col).cast("string")), key)


def least_digits(share: float) -> str | None:
    """The 13 hex digits of the first whole number that is not below a share; None where all are."""
    least = math.ceil(Fraction(share) * (1 << 52) - Fraction(1, 2))
    return None if least >= 1 << 52 else f"{max(least, 0):013x}"


def digests_of(key: str, ids: list[bytes | None]) -> np.ndarray:
    """The hashes of a key with each id, a row of 32 bytes each."""
    base = f"{key}|".encode()
    return np.frombuffer(b"".join([hashlib.sha256(base + i if i is not None else base[:-1]).digest() for i in ids]), np.uint8).reshape(-1, 32)


def uniform_of(*parts: object) -> float:
    """The same uniform on the driver."""
    return (int(hashlib.sha256("|".join(map(str, parts)).encode()).hexdigest()[:13], 16) + 0.5) / SCALE


def uniforms_of(ids: tuple, lasts: list[str]) -> np.ndarray:
    """uniform_of(*ids, last) for many last parts; the common ids are hashed once."""
    base, out = hashlib.sha256("|".join(map(str, ids)).encode() + b"|"), []
    for last in lasts:
        h = base.copy()
        h.update(last.encode())
        out.append(h.digest())
    return numbers_of(np.frombuffer(b"".join(out), np.uint8))


def numbers_of(digests: np.ndarray) -> np.ndarray:
    """The uniforms of hashes of 32 bytes."""
    return ((digests.view(">u8").ravel()[::4] >> 12).astype(np.float64) + 0.5) / SCALE


def uniform_sql(text: str) -> str:
    """The same uniform in DuckDB SQL, for an expression that gives the joined text."""
    return f"((CAST('0x' || substr(sha256({text}), 1, 13) AS BIGINT) + 0.5) / 4503599627370496.0)"


def laplace(u: Column, scale: Column | float) -> Column:
    """Laplace noise of the scale by inverse distribution; no noise at scale 0."""
    scale = F.lit(float(scale)) if isinstance(scale, (int, float)) else scale
    return -scale * F.signum(u - 0.5) * F.ln(1 - 2 * F.abs(u - 0.5))


def laplace_of(u: float, scale: float) -> float:
    return -scale * math.copysign(1.0, u - 0.5) * math.log(1 - 2 * abs(u - 0.5)) if scale else 0.0


def laplace_sql(u: str, scale: str) -> str:
    return f"(-({scale}) * sign({u} - 0.5) * ln(1 - 2 * abs({u} - 0.5)))"


def race_key(log_weight: Column, u: Column) -> Column:
    """The key of one candidate in a race; the smallest wins with probability in proportion to exp(log_weight)."""
    return F.ln(-F.ln(u)) - log_weight


def race_keys(log_weight: np.ndarray, u: np.ndarray) -> np.ndarray:
    return np.log(-np.log(u)) - log_weight


def in_race(log_weight: np.ndarray) -> np.ndarray:
    """Places of those that can win a race. A uniform of 52 bits and a half moves a key by -36.8 to 3.7, so one whose weight
    is over 41 below the largest loses by any draw, and needs none."""
    return np.flatnonzero(~(log_weight < log_weight.max() - 41))
