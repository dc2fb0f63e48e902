"""Keyed state: the last k visits of a subject, and labels that mature with time."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle


class TrajectoryState(StatefulProcessor):
    """Gives out a window of the last k visits at each new visit. State per subject: k ids, so it doesn't grow with a history."""

    def __init__(self, k: int):
        self.k = k

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.last = handle.getListState("last", "visit_id long")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:  # noqa: N802
        new = pd.concat(list(rows)).sort_values(["admit_ts", "visit_id"])
        held = [r[0] for r in self.last.get()]
        out = []
        for visit in new["visit_id"]:
            if len(held) == self.k:
                out.append((key[0], int(visit), ",".join(map(str, held))))
            held = [*held, int(visit)][-self.k :]
        self.last.put([(v,) for v in held])
        yield pd.DataFrame(out, columns=["subject_id", "target_visit", "visit_ids"])

    def close(self) -> None:
        pass


def trajectories(visits: DataFrame, k: int) -> DataFrame:
    """(subject_id, target_visit, visit_ids): full windows with their next visit, as the batch form gives them."""
    return visits.groupBy("subject_id").transformWithStateInPandas(statefulProcessor=TrajectoryState(k), outputStructType="subject_id long, target_visit long, visit_ids string", outputMode="Append", timeMode="None")


class LabelTimer(StatefulProcessor):
    """Gives out a visit's label when it is known: 1 as the next visit comes in time, 0 when the horizon has passed."""

    def __init__(self, days: int):
        self.horizon = days * 86_400_000

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.open = handle.getValueState("open", "visit_id long, discharge_ms long")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:  # noqa: N802
        out = []
        for r in pd.concat(list(rows)).sort_values(["admit_ts", "visit_id"]).itertuples():
            held = self.open.get() if self.open.exists() else None
            admit = int(r.admit_ts.timestamp() * 1000)
            if held is not None:
                out.append((key[0], int(held[0]), int(admit - held[1] < self.horizon)))
            for t in list(self.handle.listTimers()):
                self.handle.deleteTimer(t)
            end = int(r.discharge_ts.timestamp() * 1000)
            self.open.update((int(r.visit_id), end))
            self.handle.registerTimer(end + self.horizon)
        yield pd.DataFrame(out, columns=["subject_id", "visit_id", "y_return"])

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:  # noqa: N802
        out = []
        if self.open.exists():
            out.append((key[0], int(self.open.get()[0]), 0))
            self.open.clear()
        yield pd.DataFrame(out, columns=["subject_id", "visit_id", "y_return"])

    def close(self) -> None:
        pass


def matured_labels(visits: DataFrame, days: int = 30) -> DataFrame:
    """(subject_id, visit_id, y_return) from a watermarked stream of visits (subject_id, visit_id, admit_ts, discharge_ts)."""
    return visits.groupBy("subject_id").transformWithStateInPandas(statefulProcessor=LabelTimer(days), outputStructType="subject_id long, visit_id long, y_return int", outputMode="Append", timeMode="EventTime")
