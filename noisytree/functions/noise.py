"""Noise as column expressions, drawn from a hash of a key.

A retried or recomputed task draws the same noise for the same node, so a release never changes and
is never paid twice. ``secure`` takes a secret of 256 bits once on the driver and SHA-256 in place of MD5.
"""

from __future__ import annotations

import secrets
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Noise:
    seed: str = "7"
    secure: bool = False

    @staticmethod
    def fresh() -> Noise:
        return Noise(secrets.token_hex(32), True)

    def uniform(self, *key) -> Column:
        """Within (0, 1): the middle of one of 2**52 equal steps."""
        text = F.concat_ws(":", F.lit(self.seed), *[(k if isinstance(k, Column) else F.lit(str(k))).cast("string") for k in key])
        digest = F.sha2(text.cast("binary"), 256) if self.secure else F.md5(text.cast("binary"))
        return (F.conv(F.substring(digest, 1, 13), 16, 10).cast("long") + 0.5) / F.lit(float(1 << 52))

    def laplace(self, scale, *key) -> Column:
        u = self.uniform(*key)
        return (scale if isinstance(scale, Column) else F.lit(float(scale))) * F.when(u < 0.5, F.log(2 * u)).otherwise(-F.log(2 * (1 - u)))

    def gumbel(self, *key) -> Column:
        return -F.log(-F.log(self.uniform(*key)))

    def two_sided_geometric(self, eps, *key) -> Column:
        """Whole-number noise: the difference of two geometric draws of ratio exp(-eps)."""
        draw = lambda side: F.floor(F.log(self.uniform(side, *key)) / -(eps if isinstance(eps, Column) else F.lit(float(eps))))
        return draw("up") - draw("down")


DEFAULT = Noise()
