"""A stateful operator that keeps one stage's aggregates inside the stream: no read of the graph, but the neighbours' messages as state."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

_STATE = "src array<long>, vec array<array<double>>"
OUT = "dst long, vec array<double>"


def keep_aggregates(events: DataFrame, how: str = "min") -> DataFrame:
    """(dst, vec) whenever a target's aggregate changes, from events (dst, src, op, vec); an empty one is null.

    A target's state holds the messages of its present in-neighbours, so a cancelled best value needs no look at the
    graph; memory is a vector for each edge, which suits graphs without hubs.
    """
    best = np.minimum if how == "min" else np.maximum

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held: dict[int, np.ndarray] = {}
        if state.exists:
            sources, vectors = state.get
            held = {int(s): np.asarray(v, float) for s, v in zip(sources, vectors, strict=True)}
        fold = lambda: best.reduce(list(held.values())) if held else None
        before = fold()
        for rows in batches:
            for src, op, vec in sorted(zip(rows["src"], rows["op"], rows["vec"], strict=True), key=lambda r: r[1] == "add"):
                if op == "add":
                    held[int(src)] = np.asarray(vec, float)
                else:
                    held.pop(int(src), None)
        after = fold()
        state.update((list(held), [v.tolist() for v in held.values()]))
        if (before is None) != (after is None) or before is not None and not np.array_equal(before, after):
            yield pd.DataFrame({"dst": [key[0]], "vec": [None if after is None else after.tolist()]})

    return events.groupBy("dst").applyInPandasWithState(step, OUT, _STATE, "append", GroupStateTimeout.NoTimeout)
