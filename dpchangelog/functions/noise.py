"""Keyed noise. A draw is a function of (key, release, layer, interval, group, coordinate), so a task that is run again
publishes the same number, and two readers of one node see one answer.

A key has a secret, or says that it is public. With a secret the draw is HMAC-SHA-256, built from Spark's own sha2, so it stays
within whole-stage code; the plan then holds a key that the driver derives for that release alone, never the secret itself, and
whoever may read plans and event logs can undo that release's noise: keep them as closed as the data. The public key draws
through MD5, which anyone can repeat and subtract: for tests and studies only.
"""

from __future__ import annotations

import hashlib
import hmac
import math
from dataclasses import dataclass, replace

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Key:
    name: str
    release: str
    secret: bytes | None = None
    public: bool = False

    def __post_init__(self):
        if (self.secret is None) != self.public:
            raise ValueError("a key has a secret, or is public=True for tests; noise of a public key protects nothing")

    def of(self, release: str) -> "Key":
        return replace(self, release=release)


def message(key: Key, *parts: Column | str | int, salt: str = "") -> Column:
    cols = [p if isinstance(p, Column) else F.lit(str(p)) for p in parts]
    cols = [F.coalesce(c.cast("string"), F.lit("")) for c in cols]
    return F.concat_ws("|", F.lit(key.name), F.lit(key.release), *cols, F.lit(salt))


def keyed_digest(key: Key, data: Column) -> Column:
    """HMAC-SHA-256 of a binary column as lowercase hex, under the release's own key."""
    own = hmac.new(key.secret, f"{key.name}|{key.release}".encode(), hashlib.sha256).digest().ljust(64, b"\0")
    inner, outer = (bytearray(b ^ pad for b in own) for pad in (0x36, 0x5C))
    return F.sha2(F.concat(F.lit(outer), F.unhex(F.sha2(F.concat(F.lit(inner), data), 256))), 256)


def uniform(key: Key, *parts, salt: str = "") -> Column:
    """A number in (0, 1): the first 52 bits of the digest, and a half."""
    text = message(key, *parts, salt=salt)
    digest = F.md5(text.cast("binary")) if key.public else keyed_digest(key, text.cast("binary"))
    return (F.conv(F.substring(digest, 1, 13), 16, 10).cast("double") + 0.5) / float(1 << 52)


def laplace(scale: float | Column, key: Key, *parts) -> Column:
    u = uniform(key, *parts) - 0.5
    s = scale if isinstance(scale, Column) else F.lit(float(scale))
    return -s * F.signum(u) * F.log(1 - 2 * F.abs(u))


def gaussian(sigma: float | Column, key: Key, *parts) -> Column:
    """Box-Muller from two keyed uniforms."""
    s = sigma if isinstance(sigma, Column) else F.lit(float(sigma))
    return s * F.sqrt(-2 * F.log(uniform(key, *parts))) * F.cos(2 * math.pi * uniform(key, *parts, salt="b"))


def geometric(scale: float, key: Key, *parts) -> Column:
    """Two-sided geometric: the difference of two geometric draws with ratio exp(-1 / scale); whole numbers."""
    d = -1.0 / scale
    one = lambda salt: F.floor(F.log(uniform(key, *parts, salt=salt)) / F.lit(d))
    return (one("") - one("b")).cast("long")


def laplace_variance(scale: float) -> float:
    return 2 * scale * scale


def geometric_variance(scale: float) -> float:
    a = math.exp(-1 / scale)
    return 2 * a / (1 - a) ** 2


def sigma_classic(l2: float, eps: float, delta: float) -> float:
    if not 0 < eps < 1:
        raise ValueError("the classic calibration holds for eps below 1")
    return l2 * math.sqrt(2 * math.log(1.25 / delta)) / eps


def sigma_zcdp(l2: float, rho: float) -> float:
    return l2 / math.sqrt(2 * rho)


def gaussian_delta(l2: float, sigma: float, eps: float) -> float:
    """delta of Gaussian noise at eps, exactly."""
    phi = lambda x: math.erfc(-x / math.sqrt(2)) / 2
    a, b = l2 / (2 * sigma), eps * sigma / l2
    return phi(a - b) - math.exp(min(700.0, eps)) * phi(-a - b)


def sigma_analytic(l2: float, eps: float, delta: float) -> float:
    """Least sigma with that delta at eps, by bisection."""
    lo, hi = 1e-6 * l2, l2
    while gaussian_delta(l2, hi, eps) > delta:
        hi *= 2
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if gaussian_delta(l2, mid, eps) > delta else (lo, mid)
    return hi


@dataclass(frozen=True)
class Noise:
    """kind: laplace, geometric, gaussian or off. l1 and l2: sensitivity of the query it is for."""

    kind: str
    eps: float = 0.0
    delta: float = 0.0
    rho: float = 0.0

    def scale(self, l1: float, l2: float) -> float:
        if self.kind in ("laplace", "geometric"):
            return l1 / self.eps
        if self.kind == "gaussian":
            return sigma_zcdp(l2, self.rho) if self.rho else sigma_classic(l2, self.eps, self.delta) if self.eps < 1 else sigma_analytic(l2, self.eps, self.delta)
        return 0.0

    def variance(self, l1: float, l2: float) -> float:
        s = self.scale(l1, l2)
        return {"laplace": laplace_variance, "geometric": geometric_variance, "gaussian": lambda x: x * x}.get(self.kind, lambda x: 0.0)(s)

    def draw(self, l1: float, l2: float, key: Key, *parts) -> Column:
        s = self.scale(l1, l2)
        if self.kind == "off":
            return F.lit(0.0)
        return {"laplace": laplace, "geometric": geometric, "gaussian": gaussian}[self.kind](s, key, *parts).cast("double")


OFF = Noise("off")
