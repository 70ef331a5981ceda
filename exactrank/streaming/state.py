"""A rank summary for each key as streaming state: bounded memory, any quantile at any time."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from exactrank.functions.summaries import BufferedSummary, RankSummary


def summary_state(stream: DataFrame, key: str, col: str, eps: float = 0.01, q: float = 0.5) -> DataFrame:
    """(key, n, value) after each batch for the keys it touched; state is the serialised summary."""

    def step(name: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        s = BufferedSummary(eps)
        if state.exists:
            s.body = RankSummary.from_bytes(bytes(state.get[0]))
        for b in batches:
            s.insert_many(b[col].dropna().to_numpy(np.float64))
        done = s.summary()
        state.update((done.to_bytes(),))
        yield pd.DataFrame({key: [name[0]], "n": [done.n], "value": [done.query(max(0, int(np.ceil(q * done.n)) - 1))]})

    kind = stream.schema[key].dataType.simpleString()
    return stream.groupBy(key).applyInPandasWithState(step, f"{key} {kind}, n long, value double", "payload binary", "update", GroupStateTimeout.NoTimeout)
