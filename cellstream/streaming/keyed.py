"""Many live tensors in one query: each key's state is its snapshot, kept by Spark's state store.

Closed windows arrive per tensor; a tensor's slices of a batch are sorted by step and fed to its stream. The
state is one JSON or pickled value a key, of a size that does not grow with the number of steps.
"""

from __future__ import annotations

import pickle

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..model import HyperParams, TensorSpec
from .fold import Stream


def run(slices: DataFrame, spec: TensorSpec, hp: HyperParams, starts: int = 1, idle_ms: int | None = None) -> DataFrame:
    """(tensor_id, modes.., t, kind, x_hat, outlier) from a stream of cells (tensor_id, modes.., t, y).

    A slice must be whole within a batch, as the append mode of a windowed aggregate makes it. idle_ms: the state of a
    tensor without cells for so long is dropped; it starts anew when cells come again.
    """
    modes = spec.modes
    columns = ["tensor_id", *modes, "t", "kind", "x_hat", "outlier"]

    def go(key, frames, state: GroupState):
        if state.hasTimedOut:
            state.remove()
            return
        stream = pickle.loads(state.get[0]) if state.exists else Stream(spec, hp, starts)
        rows = pd.concat(list(frames))
        out = []
        for t, part in rows.sort_values(["t", *modes]).groupby("t"):
            for kind, step, idx, x, o in stream.feed(int(t), part[modes].to_numpy(np.int64), part["y"].to_numpy(float)):
                out.append(pd.DataFrame(idx.astype(np.int32), columns=modes).assign(tensor_id=key[0], t=np.int32(step), kind=kind, x_hat=x, outlier=o)[columns])
        state.update((pickle.dumps(stream),))
        if idle_ms is not None:
            state.setTimeoutDuration(idle_ms)
        if out:
            yield pd.concat(out)

    schema = "tensor_id string, " + ", ".join(f"{m} int" for m in modes) + ", t int, kind string, x_hat double, outlier double"
    return slices.select("tensor_id", *modes, "t", "y").groupBy("tensor_id").applyInPandasWithState(go, schema, "stream binary", "append", GroupStateTimeout.NoTimeout if idle_ms is None else GroupStateTimeout.ProcessingTimeTimeout)
