"""The running set of each environment as state of a stream: completion samples as events arrive.

Rows: env, run_id, query_id, kind ("submit" or "finish"), t_us. A finish closes its run and gives a sample:
how many ran, which query ended first since the last sample, and the time from that sample to the finish.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import Any

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

SAMPLES = "env string, running_n int, next_query_id long, since_us long, t_us long"
STATE = "runs array<long>, queries array<long>, last_us long"


def _step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    runs, queries, last = ([list(x) if isinstance(x, list | tuple) else x for x in state.get] if state.exists else ([], [], None))
    open_: dict[int, int] = dict(zip(runs, queries, strict=True))
    rows: list[tuple[Any, ...]] = []
    events = pd.concat(list(frames)).sort_values(["t_us", "kind", "run_id"])
    for e in events.itertuples():
        if e.kind == "submit":
            open_[e.run_id] = e.query_id
            last = e.t_us if last is None else last
        elif e.run_id in open_:
            rows.append((key[0], len(open_), open_.pop(e.run_id), e.t_us - last, e.t_us))
            last = e.t_us
    state.update((list(open_), list(open_.values()), last))
    yield pd.DataFrame(rows, columns=[c.split()[0] for c in SAMPLES.split(", ")])


def completion_stream(events: DataFrame) -> DataFrame:
    """Samples of a stream of submit and finish events; state holds the open runs of an environment only."""
    return events.groupBy("env").applyInPandasWithState(_step, SAMPLES, STATE, "append", GroupStateTimeout.NoTimeout)
