"""The calls that a user of the test needs, over the operators.

``Pair(g, "a", "b").radius(2).sample(900, "importance").test()`` reads as a sentence; each
step returns a new object, so a pair may be tested at several radii from one start.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .operators import kendall, samplers
from .operators.balls import cut
from .plans import planner
from .sources.graphs import EventGraph


@dataclass(frozen=True)
class Pair:
    g: EventGraph
    a: str
    b: str
    h: int = 1
    n: int | None = None
    sampler: str = "enumerate"
    seed: int = 42

    def radius(self, h: int) -> Pair:
        if h < 0:
            raise ValueError("a radius is at least 0")
        return replace(self, h=h)

    def sample(self, n: int, sampler: str = "enumerate", seed: int = 42) -> Pair:
        """At most ``n`` references; ``auto`` leaves the way to the planner."""
        if sampler != "auto" and sampler not in samplers.SAMPLERS:
            raise ValueError(f"no sampler {sampler!r}; there are {sorted(samplers.SAMPLERS)} and 'auto'")
        return replace(self, n=n, sampler=sampler, seed=seed)

    def planned(self) -> Pair:
        """With ``auto`` replaced by the planner's choice."""
        return self if self.sampler != "auto" else replace(self, sampler=planner.choose_sampler(self.g, self.a, self.b, self.h, self.n).sampler)

    def references(self) -> DataFrame:
        """(node, w): the whole population, or the sample asked for."""
        if self.n is None:
            return kendall.reference_population(self.g, self.a, self.b, self.h).select("node", F.lit(1).cast("long").alias("w"))
        return samplers.SAMPLERS[self.planned().sampler](self.g, self.a, self.b, self.h, self.n, seed=self.seed).select("node", "w")

    def densities(self) -> DataFrame:
        return kendall.densities(self.g, self.references(), self.a, self.b, self.h)

    def test(self, alpha: float = 0.05) -> DataFrame:
        """One row: a, b, h, n, t, z, p_upper, p_lower, verdict; after importance draws from the reweighted estimate, else with s and var_s."""
        named = [F.lit(self.a).alias("a"), F.lit(self.b).alias("b"), F.lit(self.h).alias("h")]
        me = self.planned()
        if me.n is None or me.sampler != "importance":
            return kendall.kendall_test(me.densities(), alpha=alpha).select(*named, "*")
        refs = cut(me.references())
        return kendall.weighted_test(kendall.densities(me.g, refs, me.a, me.b, me.h).join(refs, "node"), alpha=alpha).select(*named, "*")

    def profile(self, hs: tuple[int, ...] = (1, 2, 3)) -> DataFrame:
        """The test at each radius over that radius' own population, one row each."""
        rows = [replace(self, h=h).test() for h in hs]
        out = rows[0]
        for r in rows[1:]:
            out = out.unionByName(r)
        return out
