"""The mutable tier as keyed state: recent events of each user, with retention."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

OUT = "user_id long, n long, first_us long, last_us long"
STATE = "us array<long>, event_id array<long>"


def mutable_state(stream: DataFrame, retention_us: int) -> DataFrame:
    """(user_id, n, first_us, last_us) whenever a user's recent events change: appended, ordered, each once, and those

    older than the user's newest by more than the retention dropped.
    """

    def update(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held = dict(zip(state.get[1], state.get[0])) if state.exists else {}
        for part in parts:
            held.update(zip(part["event_id"].tolist(), part["us"].tolist()))
        newest = max(held.values())
        kept = sorted((us, i) for i, us in held.items() if us >= newest - retention_us)
        state.update(([us for us, _ in kept], [i for _, i in kept]))
        yield pd.DataFrame({"user_id": [key[0]], "n": [len(kept)], "first_us": [kept[0][0]], "last_us": [newest]})

    return stream.groupBy("user_id").applyInPandasWithState(update, OUT, STATE, "update", GroupStateTimeout.NoTimeout)
