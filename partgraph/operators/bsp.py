"""Supersteps: a driver loop over DataFrames with a count of messages, phases and votes to halt."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field
from enum import Enum

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..storage import spill


class Phase(Enum):
    """States of the methods' programs."""

    DRAW = "draw"
    ASSIGN = "assign"
    CUT = "cut"
    DECIDE = "decide"
    LOCAL = "local"
    QUESTION = "question"
    MERGE = "merge"
    EXCHANGE = "exchange"
    DONE = "done"


STEP = "superstep bigint, phase string, active bigint, msgs_local bigint, msgs_remote bigint"


@dataclass
class MessageLog:
    """What each superstep did: rows of (superstep, phase, active, msgs_local, msgs_remote)."""

    steps: list[tuple] = field(default_factory=list)

    def add(self, phase: Phase, active: int, msgs_local: int = 0, msgs_remote: int = 0) -> None:
        self.steps.append((len(self.steps), phase.value, int(active), int(msgs_local), int(msgs_remote)))

    def table(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.steps, STEP)


def send(outbox: DataFrame, log: MessageLog, phase: Phase, remote: Column | None = None) -> DataFrame:
    """Write the messages of a superstep once, and note how many there are and how many leave their subgraph."""
    kept = spill(outbox)
    flag = F.lit(True) if remote is None else remote
    n, far = kept.agg(F.count("*"), F.count_if(flag)).first()
    log.add(phase, n, n - far, far)
    return kept


def send_to_all(rows: DataFrame, subgraphs: DataFrame) -> DataFrame:
    """One copy of each row for every subgraph, as ``to_sg``: for few rows, such as candidates of a draw."""
    return F.broadcast(rows).crossJoin(subgraphs.select(F.col("sg").alias("to_sg")).distinct())


def all_vote(active: DataFrame, subgraphs: DataFrame) -> bool:
    """The master's test: as many subgraphs are idle in this superstep as there are; votes never carry over."""
    total = subgraphs.select("sg").distinct()
    busy = active.select("sg").distinct()
    return total.count() == total.join(busy, "sg", "left_anti").count()


def run_bsp(state, compute: Callable, max_supersteps: int = 1000):
    """Call ``compute(superstep, state)`` until it votes to halt by giving (state, True)."""
    for k in range(max_supersteps):
        state, halted = compute(k, state)
        if halted:
            return state
    raise RuntimeError(f"not done in {max_supersteps} supersteps")
