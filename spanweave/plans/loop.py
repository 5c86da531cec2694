"""Supersteps: one job computes the next state, checkpoints it and fills the counters that decide how to go on."""

from __future__ import annotations

import time
from dataclasses import asdict, dataclass, field

from pyspark.sql import Column, DataFrame, Observation, SparkSession

from spanweave.session import delete_path, settings, shared_dir

STEP_SCHEMA = (
    "phase string, stage int, guess int, step int, delta double, messages long, combined long, updates long, "
    "covered long, uncovered long, seconds double"
)
COUNTED = ("messages", "combined", "updates", "covered", "uncovered")
#: Checkpoints of the state that stay on disk while a loop runs: the newest, and the one it was made from.
KEPT = 2


@dataclass
class Step:
    phase: str
    stage: int
    guess: int
    step: int
    delta: float
    messages: int
    combined: int
    updates: int
    covered: int
    uncovered: int
    seconds: float


def checkpoint_path(df: DataFrame) -> str | None:
    """The folder that a checkpointed frame reads; null for any other."""
    plan = df._jdf.queryExecution().logical()
    if plan.getClass().getSimpleName() != "LogicalRDD":
        return None
    file = plan.rdd().getCheckpointFile()
    return file.get() if file.isDefined() else None


@dataclass
class Superstep:
    """Runs steps, keeps their figures and drops the checkpoints that no later step reads."""

    spark: SparkSession
    steps: list[Step] = field(default_factory=list)
    kept: list[str] = field(default_factory=list)

    def __post_init__(self) -> None:
        shared_dir(self.spark)

    def start(self, state: DataFrame, partitions: int, key: str = "node") -> DataFrame:
        """The first state, dealt by its key as the edges are."""
        return self._hold(state.repartition(partitions, key).checkpoint(eager=True))

    def run(
        self, plan: DataFrame, counters: dict[str, Column], drop: tuple[str, ...] = ()
    ) -> tuple[DataFrame, dict[str, int], float]:
        """The checkpointed next state without the working columns ``drop``, its counters (null over no rows), the seconds."""
        seen, began = Observation(), time.time()
        observed = plan.observe(seen, *[c.alias(k) for k, c in counters.items()])
        state = self._hold(observed.drop(*drop).checkpoint(eager=True))
        return state, dict(seen.get), time.time() - began

    def _hold(self, state: DataFrame) -> DataFrame:
        path = checkpoint_path(state)
        if path:
            self.kept.append(path)
        while len(self.kept) > KEPT:
            delete_path(self.spark, self.kept.pop(0))
        return state

    def release(self) -> None:
        """Drops the states still kept; what was derived from them must have been written by then."""
        while self.kept:
            delete_path(self.spark, self.kept.pop())

    def note(self, phase: str, stage: int, guess: int, delta, got: dict, seconds: float) -> Step:
        step = Step(
            phase, stage, guess, len(self.steps), float(delta), *(int(got.get(k) or 0) for k in COUNTED), seconds
        )
        self.steps.append(step)
        return step

    @property
    def growing_steps(self) -> int:
        return len(self.steps)

    @property
    def work(self) -> int:
        """Node updates and messages generated."""
        return sum(s.updates + s.messages for s in self.steps)

    def frame(self) -> DataFrame:
        return self.spark.createDataFrame([asdict(s) for s in self.steps], STEP_SCHEMA)


def fixed_plan(spark: SparkSession, partitions: int | None = None):
    """Settings inside a loop: every step has one plan shape and as many partitions as the edges have buckets.

    Neither edges nor state are moved then; only offers are exchanged. Automatic broadcasts are off, so that the plan
    does not depend on estimated sizes; what is broadcast is marked and has a proven bound. Run-time filters are off: one
    would read all edges once more in every step."""
    return settings(
        spark,
        spark__sql__adaptive__enabled="false",
        spark__sql__autoBroadcastJoinThreshold="-1",
        spark__sql__optimizer__runtime__bloomFilter__enabled="false",
        **({"spark__sql__shuffle__partitions": str(partitions)} if partitions else {}),
    )
