"""Keyed noise as pure functions of (key, tag, index).

``rand()`` draws again when a task is retried or a plan is run twice, which would show two draws for one charge of the
budget. Here every draw is a hash, so it comes out the same whenever it is computed, as a column and on the driver.

A uniform is read from 208 bits of a SHA-256 digest, as a floating number is written: the first of three blocks of 52
bits that isn't zero sets its size, the next block its fraction. So it has 52 significant bits wherever it lies, and the
least is 2**-209: tails of noise reach down to 1e-62, where a fixed 52-bit uniform ends at 2e-16. Laws take their rare
side from small uniforms. Above ``LEAST`` a probability is resolved to 38 bits at least; plans that need less refuse.
"""

from __future__ import annotations

import hashlib
import math
import secrets

from pyspark.sql import Column
from pyspark.sql import functions as F

_TWO52 = float(1 << 52)
_BELOW_ONE = 1 - 2.0**-53
#: Least probability that draws may be asked for.
LEAST = 2.0**-170


def new_key(seed: int | None) -> str:
    """A fresh 128-bit key, or the seed itself for reproducible (and so not private) runs."""
    return secrets.token_hex(16) if seed is None else str(seed)


def _index(parts: tuple) -> Column:
    pieces = []
    for p in parts:
        pieces += [F.lit(":"), p.cast("bigint").cast("string") if isinstance(p, Column) else F.lit(str(p))]
    return F.concat(*pieces[1:])


def _block(digest: Column, k: int) -> Column:
    return F.conv(F.substring(digest, 13 * k + 1, 13), 16, 10).cast("double")


def uniform(key: str | Column, *parts: Column | str | int) -> Column:
    """The key is one for all rows, or a column of strings."""
    head = F.concat(key, F.lit(":")) if isinstance(key, Column) else F.lit(f"{key}:")
    digest = F.sha2(F.concat(head, _index(parts)), 256)
    one, two, three, four = (_block(digest, k) for k in range(4))
    sized = lambda big, small, scale: (big + (small + 0.5) / _TWO52) / scale
    u = F.when(one > 0, sized(one, two, _TWO52)).when(two > 0, sized(two, three, _TWO52**2)).otherwise(sized(three, four, _TWO52**3))
    return F.least(u, F.lit(_BELOW_ONE))


def uniform_of(key: str, *parts: str | int) -> float:
    digest = hashlib.sha256(f"{key}:{':'.join(map(str, parts))}".encode()).hexdigest()
    return from_blocks([float(int(digest[13 * k : 13 * k + 13], 16)) for k in range(4)])


def from_blocks(blocks: list[float]) -> float:
    k = 0 if blocks[0] > 0 else 1 if blocks[1] > 0 else 2
    return min((blocks[k] + (blocks[k + 1] + 0.5) / _TWO52) / _TWO52 ** (k + 1), _BELOW_ONE)


def two_sided_geometric(key: str, scale: float, *parts: Column | str | int) -> Column:
    """P(x) proportional to exp(-|x| / scale): the difference of two geometric draws."""
    one = lambda k: F.floor(F.log(uniform(key, *parts, k)) / F.lit(-1.0 / scale))
    return (one(0) - one(1)).cast("bigint")


def two_sided_geometric_of(key: str, scale: float, *parts: str | int) -> int:
    one = lambda k: math.floor(math.log(uniform_of(key, *parts, k)) / (-1.0 / scale))
    return one(0) - one(1)


def laplace(key: str, scale: float, *parts: Column | str | int) -> Column:
    return F.when(uniform(key, *parts, 1) < 0.5, 1.0).otherwise(-1.0) * scale * F.log(uniform(key, *parts, 0))


def laplace_of(key: str, scale: float, *parts: str | int) -> float:
    return (1.0 if uniform_of(key, *parts, 1) < 0.5 else -1.0) * scale * math.log(uniform_of(key, *parts, 0))


def gumbel(key: str | Column, *parts: Column | str | int) -> Column:
    """Large values come from small uniforms, where ln(1 - u) is taken from its series."""
    u = uniform(key, *parts)
    return -F.log(F.when(u < 1e-5, u * (1 + u * (0.5 + u / 3))).otherwise(-F.log(1 - u)))


def gumbel_of(key: str, *parts: str | int) -> float:
    u = uniform_of(key, *parts)
    return -math.log(u * (1 + u * (0.5 + u / 3)) if u < 1e-5 else -math.log(1 - u))


def gaussian(key: str, sigma: float, *parts: Column | str | int) -> Column:
    radius = F.sqrt(-2 * F.log(uniform(key, *parts, 0)))
    return sigma * radius * F.cos(2 * math.pi * uniform(key, *parts, 1))
