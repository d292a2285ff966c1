"""Stateful operators: running Gram sums by key."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle


class GramState(StatefulProcessor):
    """Keeps (n, sum of x, sum of x x') of a key, d + d^2 doubles however many rows come, and emits them per batch."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.sums = handle.getValueState("sums", "n long, s array<double>, g array<double>")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        old = self.sums.get()
        n, s, g = (0, None, None) if old is None else (int(old[0]), np.array(old[1]), np.array(old[2]))
        for pdf in rows:
            x = np.stack(pdf["x"].to_numpy()).astype(float)
            n += len(x)
            s = x.sum(0) + (0 if s is None else s)
            g = (x.T @ x).ravel() + (0 if g is None else g)
        self.sums.update((n, s.tolist(), g.tolist()))
        yield pd.DataFrame({"key": [key[0]], "n": [n], "s": [s.tolist()], "g": [g.tolist()]})

    def close(self) -> None:
        pass


def running_gram(stream: DataFrame, key: str, features: list[str]) -> DataFrame:
    """(key, n, s, g) after each batch for the keys it touched; the last row of a key is its state."""
    x = stream.select(F.col(key).cast("string").alias("key"), F.array(*(F.col(f).cast("double") for f in features)).alias("x"))
    return x.groupBy("key").transformWithStateInPandas(GramState(), "key string, n long, s array<double>, g array<double>", "Update", "None")
