"""Fluent surface: FadingHitters(spec, family).fit(stream).gossip(schedule).query(support, asof)."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame

from fadegossip import gossip, planner, query
from fadegossip.decay import DecaySpec
from fadegossip.hashing import HashFamily
from fadegossip.local import build_local
from fadegossip.plans import cut
from fadegossip.schedule import Schedule


@dataclass(frozen=True)
class FadingHitters:
    """Immutable; every step returns a new object. site_cap bounds the number of sites the slack is computed for."""

    spec: DecaySpec
    family: HashFamily
    fail_gossip: float = 0.01
    site_cap: int | None = None
    mode: str = "partition"
    state: DataFrame | None = None
    share: DataFrame | None = None
    rounds: int = field(default=0)

    @classmethod
    def planned(cls, spec: DecaySpec, strategy: str, support: float, tol: float, site_cap: int, fail: float = 0.05, fail_gossip: float = 0.01) -> tuple[FadingHitters, planner.Plan]:
        """Sizes from wanted guarantees; the plan says how many rounds to schedule."""
        plan = planner.plan(strategy, support, tol, site_cap, fail, fail_gossip)
        return cls(spec, HashFamily(plan.depth, plan.width), fail_gossip, site_cap), plan

    def fit(self, stream: DataFrame) -> FadingHitters:
        return replace(self, state=build_local(stream, self.spec, self.family, self.mode), share=None, rounds=0)

    def gossip(self, schedule: Schedule) -> FadingHitters:
        """Averages all sites' grids; called again, it goes on from where it was (shares need one schedule)."""
        state = cut(gossip.gossip_by_cell(self.state, schedule, self.family).drop("round"))
        return replace(self, state=state, share=gossip.share_table(state.sparkSession, schedule), rounds=self.rounds + schedule.rounds, site_cap=self.site_cap or schedule.sites)

    def slack(self) -> float:
        return planner.slack(self.site_cap, self.rounds, self.fail_gossip) if self.rounds else 0.0

    def query(self, support: float, asof: int, sites: list[int] | None = None, strict: bool = True) -> DataFrame:
        return query.peer_query(self.state, self.family, self.spec, support, self.slack(), asof, self.share, sites, strict)

    def estimate(self, items: DataFrame, asof: int) -> DataFrame:
        return query.point_estimate(self.state, items, self.family, self.spec, asof)
