"""Error feedback as keyed state: each client's residual lives in the state store between micro-batches."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql.streaming.state import GroupStateTimeout

OUT = "client_id INT, param_idx BIGINT, sent DOUBLE, kept_back BIGINT"
STATE = "idx ARRAY<BIGINT>, val ARRAY<DOUBLE>"


def stream_error_feedback(deltas: DataFrame, k: int) -> DataFrame:
    """Of a stream (client_id, param_idx, delta): each micro-batch's top k of update plus residual per client.

    The state of a client is its residual as two arrays; ties go to the lower coordinate.
    """

    def step(key, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        idx, val = (np.array(x, t) for x, t in zip(state.get if state.exists else ((), ()), (np.int64, np.float64), strict=True))
        for f in frames:
            idx, val = np.concatenate([idx, f["param_idx"].to_numpy(np.int64)]), np.concatenate([val, f["delta"].to_numpy(np.float64)])
        idx, place = np.unique(idx, return_inverse=True)
        val = np.bincount(place, val, minlength=len(idx))
        idx, val = idx[val != 0], val[val != 0]
        size = np.abs(val)
        sent = np.ones(len(idx), bool)
        if len(idx) > k:  # a partition finds the cut; only what is sent is sorted
            cut = -np.partition(-size, k - 1)[k - 1]
            sent = size > cut
            sent[np.flatnonzero(size == cut)[: k - int(sent.sum())]] = True
        state.update((idx[~sent].tolist(), val[~sent].tolist()))
        order = np.lexsort((idx[sent], -size[sent]))
        yield pd.DataFrame({"client_id": np.full(len(order), int(key[0]), np.int32), "param_idx": idx[sent][order], "sent": val[sent][order], "kept_back": np.full(len(order), int((~sent).sum()))})

    return deltas.groupBy("client_id").applyInPandasWithState(step, OUT, STATE, "append", GroupStateTimeout.NoTimeout)
