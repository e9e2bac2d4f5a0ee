"""Memory of the components of a phase: each gets lambda times its priority, clipped to its interval."""

from __future__ import annotations

import math
from dataclasses import dataclass
from fractions import Fraction

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


class MemoryPlanError(ValueError):
    """Requests that can't be met, or make no sense."""


@dataclass(frozen=True)
class MemoryAsk:
    """Bytes from lo to hi (infinite by default), by priority. A static component asks for lo = hi = 0."""

    lo: int = 0
    hi: float = math.inf
    prio: float = 1

    def at(self, lam: float) -> float:
        return max(self.lo, min(self.hi, lam * self.prio)) if lam < math.inf else self.hi


def total(asks: dict[str, MemoryAsk], lam: float) -> float:
    return sum(a.at(lam) for a in asks.values())


def check(asks: dict[str, MemoryAsk], available: float) -> None:
    for n, a in asks.items():
        if a.lo < 0 or a.lo > a.hi or a.prio <= 0:
            raise MemoryPlanError(f"{n}: the request {a} is not a valid one")
    if (least := sum(a.lo for a in asks.values())) > available:
        raise MemoryPlanError(f"the least requests sum up to {least}, more than the {available} there are")


def assign(asks: dict[str, MemoryAsk], available: float, method: str = "exact") -> tuple[float, dict[str, float]]:
    """lambda and the bytes of each; lambda is infinite if everyone can have the most they ask for."""
    check(asks, available)
    if sum(a.hi for a in asks.values()) <= available:
        return math.inf, {n: a.hi for n, a in asks.items()}
    lam = _bisect(asks, available) if method == "bisect" else _exact(asks, available)
    return lam, {n: a.at(lam) for n, a in asks.items()}


def _bisect(asks: dict[str, MemoryAsk], available: float) -> float:
    low, high = 0.0, 1.0
    while total(asks, high) <= available:
        low, high = high, 2 * high
    for _ in range(200):
        mid = (low + high) / 2
        if mid in (low, high):
            break
        low, high = (mid, high) if total(asks, mid) <= available else (low, mid)
    return low


def _exact(asks: dict[str, MemoryAsk], available: float) -> float:
    """The total is a broken line: it gains the slope prio at lo / prio and loses it at hi / prio."""
    turns: dict[Fraction, Fraction] = {}
    for a in asks.values():
        c = Fraction(a.prio)
        turns[a.lo / c] = turns.get(a.lo / c, Fraction(0)) + c
        if a.hi < math.inf:
            turns[Fraction(a.hi) / c] = turns.get(Fraction(a.hi) / c, Fraction(0)) - c
    have, slope, at = Fraction(sum(a.lo for a in asks.values())), Fraction(0), Fraction(0)
    for lam in sorted(turns):
        if slope and have + slope * (lam - at) > available:
            break
        have, at = have + slope * (lam - at), lam
        slope += turns[lam]
    return float(at + (Fraction(available) - have) / slope) if slope else float(at)


def equal_split(asks: dict[str, MemoryAsk], available: float) -> dict[str, float]:
    """The plain baseline: the same for all, whatever they ask."""
    return dict.fromkeys(asks, available / max(len(asks), 1))


def manual_three_phase(memory: int, read_buffer: int, write_buffer: int) -> tuple[int, int, int]:
    """The manual baseline's bytes for a sorter in each of three phases."""
    if min(memory - read_buffer, memory - write_buffer) <= 0:
        raise MemoryPlanError("the buffers leave no memory for sorting")
    return memory, (memory - read_buffer) // 2, memory - write_buffer


def assign_df(asks: DataFrame, budgets: DataFrame) -> DataFrame:
    """asks (phase, node, lo, hi or null, prio), budgets (phase, available) of many phases -> (phase, node, lam, assigned).

    One shuffle by phase; the breakpoints' windows and the join back keep to it. lam is null where everyone gets the most.
    Phases whose least requests don't fit have null in both.
    """
    turn = F.array(F.struct((F.col("lo") / F.col("prio")).alias("lam"), F.col("prio").cast("double").alias("turn")), F.struct((F.col("hi") / F.col("prio")).alias("lam"), (-F.col("prio")).cast("double").alias("turn")))
    points = asks.select("phase", F.explode(turn).alias("t")).select("phase", "t.*").where("lam is not null").groupBy("phase", "lam").agg(F.sum("turn").alias("turn"))
    by = Window.partitionBy("phase").orderBy("lam")
    upto = by.rowsBetween(Window.unboundedPreceding, 0)
    line = points.withColumn("slope", F.sum("turn").over(upto)).withColumn("grown", F.coalesce(F.lag("slope").over(by) * (F.col("lam") - F.lag("lam").over(by)), F.lit(0.0)))
    sums = asks.groupBy("phase").agg(F.sum("lo").alias("least"), F.when(F.count("hi") == F.count("*"), F.sum("hi")).alias("most"))
    line = line.withColumn("grown", F.sum("grown").over(upto)).join(sums, "phase").join(budgets, "phase")
    fits = F.col("least") + F.col("grown") <= F.col("available") + 1e-9
    pick = line.where(fits).groupBy("phase").agg(F.max(F.struct("lam", "slope", "grown", "least", "most", "available")).alias("p")).select("phase", "p.*")
    left = F.col("available") - F.col("least") - F.col("grown")
    lam = F.when(F.col("most") <= F.col("available"), None).when(F.col("slope") > 1e-9, F.col("lam") + left / F.col("slope")).otherwise(F.col("lam"))
    solved = pick.where(F.col("least") <= F.col("available")).select("phase", lam.alias("lam"), (F.col("most") <= F.col("available")).alias("all"))
    clipped = F.greatest(F.col("lo").cast("double"), F.least(F.coalesce(F.col("hi").cast("double"), F.lit(float("inf"))), F.col("lam") * F.col("prio")))
    return asks.join(solved, "phase", "left").select("phase", "node", "lam", F.when(F.col("all"), F.col("hi").cast("double")).when(F.col("lam").isNotNull(), clipped).alias("assigned"))


def curve_df(asks: DataFrame, lambdas: list[float]) -> DataFrame:
    """(phase, lam, total): the memory that each phase takes at given lambdas."""
    each = F.greatest(F.col("lo").cast("double"), F.least(F.coalesce(F.col("hi").cast("double"), F.lit(float("inf"))), F.col("lam") * F.col("prio")))
    return asks.withColumn("lam", F.explode(F.array(*map(F.lit, lambdas)))).groupBy("phase", "lam").agg(F.sum(each).alias("total"))


def plan_bytes(df) -> int:
    """Bytes that the leaves of df's plan hold, where Spark knows them: what a blocking component has to sort, about."""
    leaves = df._jdf.queryExecution().optimizedPlan().collectLeaves()
    sizes = [int(leaves.apply(i).stats().sizeInBytes()) for i in range(leaves.size())]
    return sum(s for s in sizes if s < 1 << 60)  # unknown sizes are near 2^63


def partitions_for(est_bytes: int, share: float, cores: int, most: int = 200_000) -> int:
    """Partitions of a blocking component so that what a core sorts at a time fits its part of the share."""
    return int(min(most, max(cores, math.ceil(est_bytes * cores / max(share, 1)))))
