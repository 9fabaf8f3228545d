"""The superstep driver: state in, one relaxation out, one exchange of offers a round, a ledger of what each round cost."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark import StorageLevel
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from hopline.session import drop_checkpoint, setting, shared_dir

CHECKPOINT_EVERY = 4


@dataclass
class Ledger:
    """One row a round that improved something: rows of the state, rows that improved, offers sent, seconds."""

    rows: list[tuple] = field(default_factory=list)
    scale: int = -1

    def note(self, phase: str, round_: int, state: int, improved: int, messages: int, seconds: float) -> None:
        self.rows.append((phase, self.scale, round_, state, improved, messages, float(seconds)))

    def rounds(self, phase: str | None = None) -> int:
        return sum(phase in (None, r[0]) for r in self.rows)

    def messages(self, phase: str | None = None) -> int:
        return sum(r[5] for r in self.rows if phase in (None, r[0]))

    def frame(self, spark) -> DataFrame:
        return spark.createDataFrame(self.rows, "phase string, scale int, round int, state_rows long, improved long, messages long, seconds double")


def loop(state: DataFrame, step: Callable[[DataFrame, Observation], DataFrame], rounds: int | None, phase: str, ledger: Ledger | None = None, every: int = CHECKPOINT_EVERY, most: int | None = None) -> DataFrame:
    """Applies ``step`` until no row is ``fresh`` or ``rounds`` are done; fails where it would need more than ``most``.

    ``step`` observes the offers that it sends. Each round's state is kept in memory or on disk until the burst of
    ``every`` rounds ends in a checkpoint on reliable storage, so no round is computed twice and lineage stays short.
    Adaptive execution is off inside, so that the state keeps its partitioning by node and only offers are exchanged.
    """
    spark, done, last = state.sparkSession, 0, None
    shared_dir(spark)
    with setting(spark, spark__sql__adaptive__enabled="false"):
        while rounds is None or done < rounds:
            if most is not None and done + every > most:
                raise OverflowError(f"{phase}: still open after {done} rounds")
            burst, began = every if rounds is None else min(every, rounds - done), time.time()
            seen, held = [], []
            for k in range(burst):
                offers, after = Observation(), Observation()
                state = step(state, offers).observe(after, F.count_if("fresh").alias("fresh"), F.count("*").alias("rows"))
                seen.append((offers, after))
                if k < burst - 1:
                    state = state.persist(StorageLevel.MEMORY_AND_DISK)
                    held.append(state)
            state = state.checkpoint()
            for h in held:
                h.unpersist()
            if last is not None:
                drop_checkpoint(last)
            last = state
            seconds = (time.time() - began) / burst
            for offers, after in seen:
                if not after.get["fresh"]:
                    return state
                done += 1
                if ledger is not None:
                    ledger.note(phase, done, after.get["rows"], after.get["fresh"], offers.get["offers"], seconds)
    return state
