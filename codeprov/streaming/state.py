"""Arbitrary state: each user's execution-order chain as it grows, without recursion."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

OUT = "user_id long, events long, last_type string, open_signup boolean"
STATE = "events long, last_ts timestamp, last_id long, last_type string, signup boolean"


def chains(stream: DataFrame) -> DataFrame:
    """``user_id, events, last_type, open_signup`` after every batch: a signup is open until a purchase or an error.

    State is one short row for each user.
    """

    def step(key: tuple, rows: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, ts, last, kind, open_ = state.get if state.exists else (0, pd.Timestamp(0), -1, "", False)
        every = pd.concat(list(rows)).sort_values(["ts", "event_id"])
        for r in every.itertuples(index=False):
            n += 1
            ts, last, kind = r.ts, r.event_id, r.event_type
            open_ = True if kind == "signup" else False if kind in ("purchase", "error") else open_
        state.update((n, ts, last, kind, open_))
        yield pd.DataFrame({"user_id": [key[0]], "events": [n], "last_type": [kind], "open_signup": [bool(open_)]})

    return stream.groupBy("user_id").applyInPandasWithState(step, OUT, STATE, "update", GroupStateTimeout.NoTimeout)
