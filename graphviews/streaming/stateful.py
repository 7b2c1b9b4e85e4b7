"""Custom state: running counts by key."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout


def running_counts(stream: DataFrame, key: str) -> DataFrame:
    """(key, n): the number of rows of each key so far, given anew whenever it changes."""
    def count(group: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n = state.get[0] if state.exists else 0
        n += sum(len(b) for b in batches)
        state.update((n,))
        yield pd.DataFrame({key: [group[0]], "n": [n]})

    return stream.groupBy(key).applyInPandasWithState(count, f"{key} long, n long", "n long", "update", GroupStateTimeout.NoTimeout)
