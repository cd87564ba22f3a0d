"""Custom state: each user's most recent items."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

OUT = "user_id long, items string, n long"


def recent_items(purchases: DataFrame, n: int = 3) -> DataFrame:
    """user_id, items (newest first), n: updated whenever a user buys; state holds n items a user."""

    def update(key, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held = list(zip(*state.get, strict=True)) if state.exists and state.get[0] else []
        for pdf in batches:
            held += [(t.value, int(e), int(i)) for t, e, i in zip(pd.to_datetime(pdf["ts"]), pdf["event_id"], pdf["item_id"], strict=True)]
        held = sorted(held, reverse=True)[:n]
        state.update(tuple(list(x) for x in zip(*held, strict=True)))
        yield pd.DataFrame({"user_id": [key[0]], "items": [",".join(str(i) for _, _, i in held)], "n": [len(held)]})

    return purchases.groupBy("user_id").applyInPandasWithState(update, OUT, "t array<long>, e array<long>, i array<long>", "update", GroupStateTimeout.NoTimeout)
