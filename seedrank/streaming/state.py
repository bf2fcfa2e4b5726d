"""A bottom-k sample kept in the state of a stream of final weights, for each assignment.

The state of an assignment is its k+1 least ranks; a batch of new keys is ranked before it gets here and
only ranks below the largest kept one change anything.  Every change is emitted with the thresholds.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from seedrank.functions import ranks as R

_STATE = "ranks array<double>, keys array<string>, weights array<double>"
_OUT = "assignment string, version int, pos int, key string, weight double, rank double"


def maintained(weights: DataFrame, k: int, family: str = "ipps", salt: str = "v1") -> DataFrame:
    """A streaming frame of samples: for each assignment and version, its k+1 least ranks so far.

    ``weights``: a stream of (assignment, key, weight) in which no key of an assignment comes twice.
    """

    def update(group: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        ranks, keys, kept = (list(x) for x in state.get) if state.exists else ([], [], [])
        held = list(zip(ranks, keys, kept, strict=True))
        for frame in frames:
            fresh = zip(frame["rank"], frame["key"], frame["weight"], strict=True)
            held = sorted([*held, *fresh])[: k + 1]
        state.update(([r for r, _, _ in held], [x for _, x, _ in held], [w for _, _, w in held]))
        rows = [(group[0], 1, i + 1, x, w, r) for i, (r, x, w) in enumerate(held)]
        yield pd.DataFrame(rows, columns=["assignment", "version", "pos", "key", "weight", "rank"])

    ranked = R.rank_long(weights, family, "shared", salt).select("assignment", "key", "weight", "rank")
    return ranked.groupBy("assignment").applyInPandasWithState(update, _OUT, _STATE, "update", GroupStateTimeout.NoTimeout)


def latest(rows: DataFrame, batch: str = "batch") -> DataFrame:
    """The newest sample of each assignment among the emitted ones, by batch number."""
    newest = rows.groupBy("assignment").agg(F.max(batch).alias(batch))
    return rows.join(F.broadcast(newest), ["assignment", batch]).select("assignment", "pos", "key", "weight", "rank")
