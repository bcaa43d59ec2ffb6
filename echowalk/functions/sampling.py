"""Length plans: how many walks of each length every node gets."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bounds
from .rng import SPAN, draw


@dataclass(frozen=True)
class SamplingPlan:
    """``ideal[i]`` and ``actual[i]``: real and whole number of walks of length i; ``z``: ideal walks
    of a node. Under rounding "bernoulli" ``actual`` is the whole part, and a node gets one more of a
    length by a coin with the rest's probability."""

    n: int
    c: float
    eps: float
    z: float
    ideal: tuple[float, ...]
    actual: tuple[int, ...]
    truncation: str
    rounding: str

    @classmethod
    def create(cls, n: int, c: float = 0.6, eps: float = 0.1, delta: float | None = None, scope: str = "per_node", truncation: str = "drop", rounding: str = "ceil") -> SamplingPlan:
        """``scope``: failure 1/n for each node, or 1/n**2 so that all hold together; ``truncation``:
        lengths beyond the cut-off are dropped, or clipped to it; ``rounding``: ceil, floor or
        bernoulli."""
        if not 0 < c < 1 or truncation not in ("drop", "clip") or rounding not in ("ceil", "floor", "bernoulli"):
            raise ValueError("c in (0, 1), truncation drop or clip, rounding ceil, floor or bernoulli")
        z, r, last = bounds.walks_per_node(n, eps, scope, delta), math.sqrt(c), bounds.cut_off(n, c)
        ideal = [z * r**i * (1 - r) for i in range(last + 1)]
        if truncation == "clip":
            ideal[-1] = z * r**last
        whole = [math.ceil(x) if rounding == "ceil" else math.floor(x) for x in ideal]
        return cls(n, c, eps, z, tuple(ideal), tuple(whole), truncation, rounding)

    @property
    def longest(self) -> int:
        return len(self.ideal) - 1

    @property
    def total(self) -> int:
        """Walks of a node (bernoulli: at most)."""
        return sum(self.actual) + (len(self.actual) if self.rounding == "bernoulli" else 0)

    @property
    def steps(self) -> int:
        return sum(i * k for i, k in enumerate(self.actual))

    def shares(self) -> list[float]:
        """Ideal over expected actual number of walks for each length; 0 where a length has none."""
        got = self.ideal if self.rounding == "bernoulli" else self.actual
        return [x / k if k else 0.0 for x, k in zip(self.ideal, got)]

    def expected_total(self) -> float:
        return sum(self.ideal) if self.rounding == "bernoulli" else float(sum(self.actual))

    def frame(self, spark: SparkSession) -> DataFrame:
        """len, ideal, actual, lo, hi (walk numbers from lo up to but without hi), share."""
        rows, at = [], 0
        for i, (x, k, s) in enumerate(zip(self.ideal, self.actual, self.shares())):
            rows.append((i, x, k, at, at + k, s))
            at += k
        return spark.createDataFrame(rows, "len int, ideal double, actual int, lo int, hi int, share double")

    def lengths_of(self, start: Column, seed: int) -> Column:
        """The lengths of a start's walks, as an array in the order of walk numbers (from 1)."""
        if self.rounding != "bernoulli":
            return F.flatten(F.array(*(F.array_repeat(F.lit(i), k) for i, k in enumerate(self.actual))))
        # one draw for all lengths: an expression for each would be compiled for each
        whole, rest = F.array(*(F.lit(k) for k in self.actual)), F.array(*(F.lit(int((x - k) * SPAN)).cast("long") for x, k in zip(self.ideal, self.actual)))
        more = lambda i: F.when(draw(seed, "round", start, i) < F.element_at(rest, i + 1), 1).otherwise(0)
        return F.flatten(F.transform(F.sequence(F.lit(0), F.lit(self.longest)), lambda i: F.array_repeat(i, F.element_at(whole, i + 1) + more(i))))

    def summary(self) -> dict[str, float]:
        return {"z": self.z, "walks": self.total, "longest": self.longest, "steps": self.steps, "mean_length": self.steps / max(1, self.total), "bias": self.z / self.expected_total()}
