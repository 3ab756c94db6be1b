"""The space of plans: algorithm x transformation x sampler."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Users' samplers come after these.
SAMPLERS = ["bernoulli", "random", "shuffle"]
TRANSFORMS = ("eager", "lazy")
#: Whether an algorithm samples; users' algorithms come after these.
SAMPLED = {"bgd": False, "mgd": True, "sgd": True}
#: How often an iteration of a user's algorithm scans all units; one that samples by itself has a share of one.
SCANS: dict[str, float] = {}


@dataclass(frozen=True)
class PlanSpec:
    algorithm: str
    transform: str = "eager"
    sampler: str = "none"

    @property
    def key(self) -> str:
        return self.algorithm if self.sampler == "none" else f"{self.algorithm}-{self.transform}-{self.sampler}"


def legal(plan: PlanSpec) -> bool:
    """A full scan transforms eagerly; Bernoulli reads everything anyway, so laziness gains nothing there."""
    if not SAMPLED[plan.algorithm]:
        return plan.transform == "eager" and plan.sampler == "none"
    return plan.sampler != "none" and not (plan.transform == "lazy" and plan.sampler == "bernoulli")


def enumerate_plans(algorithms=None, samplers=None, transforms=TRANSFORMS, commute: bool = True) -> list[PlanSpec]:
    """All legal plans in a fixed order, which also breaks ties. Without ``commute`` Transform stays before Sample: no lazy plan."""
    every = [PlanSpec(a, t, s) for a in (algorithms or SAMPLED) for t in transforms if commute or t == "eager" for s in ("none", *(samplers or SAMPLERS))]
    return [p for p in every if legal(p)]


def plan_space(spark: SparkSession) -> DataFrame:
    """The same as a table, by a cross join of three short lists and a filter."""
    a = spark.createDataFrame([(k, v) for k, v in (("bgd", False), ("mgd", True), ("sgd", True))], "algorithm string, sampled boolean")
    t = spark.createDataFrame([(x,) for x in TRANSFORMS], "transform string")
    s = spark.createDataFrame([(x,) for x in ("none", "bernoulli", "random", "shuffle")], "sampler string")
    keep = (~F.col("sampled") & (F.col("transform") == "eager") & (F.col("sampler") == "none")) | (F.col("sampled") & (F.col("sampler") != "none") & ~((F.col("transform") == "lazy") & (F.col("sampler") == "bernoulli")))
    name = F.when(F.col("sampled"), F.concat_ws("-", "algorithm", "transform", "sampler")).otherwise(F.col("algorithm"))
    return a.crossJoin(t).crossJoin(s).where(keep).select(name.alias("plan"), "algorithm", "transform", "sampler")


def commutes(transform_is_one_to_one: bool, deterministic: bool, needs_only_unit_and_stats: bool) -> bool:
    """Whether Transform may move below Sample, into the loop; where it may not, ``optimise`` plans eagerly."""
    return transform_is_one_to_one and deterministic and needs_only_unit_and_stats
