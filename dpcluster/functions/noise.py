"""Replayable noise: a function of a secret, a step and a key, never of partitioning or retries.

A task that runs twice must not publish two noises for one true value, so nothing here uses rand().
Both engines can evaluate the expressions; ``*_sql`` give the text for DuckDB.
"""

from __future__ import annotations

import math
import secrets
from dataclasses import dataclass
from hashlib import md5

from pyspark.sql import Column
from pyspark.sql import functions as F

_STEPS = float(1 << 52)


@dataclass(frozen=True)
class NoiseSource:
    """seed: a fixed word in tests; ``secret()`` draws 256 bits from the system."""

    seed: str = "fixed"

    @staticmethod
    def secret() -> NoiseSource:
        return NoiseSource(secrets.token_hex(32))

    def uniform(self, step: str, *key: Column | str) -> Column:
        """In (0, 1), from whole-number or text keys."""
        parts = [F.lit(f"{self.seed}|{step}"), *((F.col(k) if isinstance(k, str) else k).cast("string") for k in key)]
        return (F.conv(F.substring(F.md5(F.concat_ws("|", *parts).cast("binary")), 1, 13), 16, 10).cast("bigint").cast("double") + 0.5) / F.lit(_STEPS)

    def uniform_sql(self, step: str, *key: str) -> str:
        parts = ", ".join(f"CAST({k} AS VARCHAR)" for k in key)
        return f"((CAST(CAST(('0x' || substr(md5(concat_ws('|', '{self.seed}|{step}', {parts})), 1, 13)) AS BIGINT) AS DOUBLE) + 0.5) / {_STEPS:.1f})"

    def draw(self, step: str, *key) -> float:
        """The same number on the driver."""
        text = "|".join([self.seed, step, *map(str, key)])
        return (int(md5(text.encode()).hexdigest()[:13], 16) + 0.5) / _STEPS

    def laplace(self, scale, step: str, *key: Column | str) -> Column:
        u = self.uniform(step, *key) - 0.5
        scale = scale if isinstance(scale, Column) else F.lit(float(scale))
        return -scale * F.signum(u) * F.log(1 - 2 * F.abs(u))

    def laplace_sql(self, scale, step: str, *key: str) -> str:
        u = f"({self.uniform_sql(step, *key)} - 0.5)"
        return f"(-({scale}) * sign{u} * ln(1 - 2 * abs{u}))"

    def gumbel(self, step: str, *key: Column | str) -> Column:
        return -F.log(-F.log(self.uniform(step, *key)))

    def gumbel_sql(self, step: str, *key: str) -> str:
        return f"(-ln(-ln({self.uniform_sql(step, *key)})))"

    def geometric(self, eps: float, step: str, *key: Column | str) -> Column:
        """Two-sided geometric noise for whole counts: a hardened twin of Laplace noise."""
        a = math.exp(-eps)
        one, two = (F.floor(F.log(self.uniform(f"{step}{s}", *key)) / F.lit(math.log(a))) for s in "+-")
        return (one - two).cast("long")

    def normal(self, step: str, *key: Column | str) -> Column:
        """Box-Muller."""
        return F.sqrt(-2 * F.log(self.uniform(step + "r", *key))) * F.cos(2 * math.pi * self.uniform(step + "a", *key))

    def normal_sql(self, step: str, *key: str) -> str:
        return f"(sqrt(-2 * ln({self.uniform_sql(step + 'r', *key)})) * cos({2 * math.pi!r} * {self.uniform_sql(step + 'a', *key)}))"


def laplace_pdf(x: float, b: float) -> float:
    return math.exp(-abs(x) / b) / (2 * b)


def laplace_cdf(x: float, b: float) -> float:
    return math.exp(x / b) / 2 if x < 0 else 1 - math.exp(-x / b) / 2


def laplace_var(b: float) -> float:
    return 2 * b * b
