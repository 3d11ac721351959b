"""SQL face: table functions over cells, partitioned by tensor and ordered by step, and views of the cubes."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from .sources import cubes


def _method(kind: str):
    class Run:
        """Arguments: cells (i1, i2, t, y) ordered by t, sizes as 'a,b', period, rank and, for forecasts, horizon."""

        def __init__(self):
            self.stream, self.slice, self.t = None, [], None

        def eval(self, row, sizes: str, period: int, rank: int, horizon: int):
            from .model import HyperParams, TensorSpec
            from .streaming.fold import Stream

            if self.stream is None:
                self.spec = TensorSpec(tuple(map(int, sizes.split(","))), period, rank)
                self.stream = Stream(self.spec, HyperParams(lambda1=0.01, lambda2=0.01, max_iter=40), 1)
                self.horizon = horizon
            if self.t is not None and row["t"] != self.t:
                yield from self.flush()
            self.t = row["t"]
            self.slice.append((row["i1"], row["i2"], row["y"]))

        def flush(self):
            import numpy as np

            idx = np.array([(a, b) for a, b, _ in self.slice])
            out = self.stream.feed(self.t, idx, np.array([y for _, _, y in self.slice], float))
            self.slice = []
            if kind == "outliers":
                for _, t, i, x, o in out:
                    for (a, b), v, w in zip(i.tolist(), x.tolist(), o.tolist()):
                        if w != 0:
                            yield a, b, int(t), v, w
            elif kind == "impute" and out and out[-1][0] == "update":
                yield from self.full(self.t, idx)

        def full(self, t, seen=None, h=0):
            import numpy as np

            from .streaming import kernel

            g = np.stack(np.unravel_index(np.arange(int(np.prod(self.spec.sizes))), self.spec.sizes), 1)
            if seen is not None:
                on = np.ones(len(g), bool)
                on[np.ravel_multi_index(seen.T, self.spec.sizes)] = False
                g = g[on]
            x = kernel.forecast(self.stream.state, g, h) if h else kernel.impute(self.stream.state, g)
            for (a, b), v in zip(g.tolist(), x.tolist()):
                yield a, b, int(t), v, 0.0

        def terminate(self):
            if self.stream is None:
                return
            yield from self.flush()
            if self.stream.state is None:
                self.stream.begin()
            if kind == "forecast":
                for h in range(1, self.horizon + 1):
                    yield from self.full(self.stream.state.t + h, None, h)

    return udtf(Run, returnType="i1 int, i2 int, t int, x_hat double, outlier double")


def register(spark: SparkSession) -> None:
    for kind in ("forecast", "impute", "outliers"):
        spark.udtf.register(f"tensor_{kind}", _method(kind))


def views(spark: SparkSession, directory: str) -> None:
    """A temporary view cube_<name> for every cube."""
    for name in cubes.CUBES:
        cubes.cells(spark, directory, name).createOrReplaceTempView(f"cube_{name}")
