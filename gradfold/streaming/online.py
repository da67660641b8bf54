"""Online learning: each micro-batch is folded into the model that the last one left."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import folds
from ..operators.tasks import LinearTask
from ..sources.files import scratch


class OnlineLearner:
    """The model and its number of steps, kept between batches; a batch seen twice is folded once."""

    def __init__(self, task: LinearTask, d: int, alpha: float, start=None):
        self.task, self.alpha = task, alpha
        self.w = np.zeros(d) if start is None else np.array(start, float)
        self.rows, self.done = 0, -1

    def __call__(self, batch: DataFrame, number: int) -> None:
        if number <= self.done:
            return
        one = batch.select(F.lit(0).cast("long").alias("seg"), "k", "x", "y").repartition(1, "seg")
        for r in folds.fold_arrow(one, self.task, self.w, self.alpha).collect():
            self.w, self.rows = np.array(r.w), self.rows + r.n
        self.done = number


def learn(stream: DataFrame, learner: OnlineLearner) -> OnlineLearner:
    """Replay a stream of (k, x, y) through a learner."""
    q = stream.writeStream.foreachBatch(learner).option("checkpointLocation", scratch(stream.sparkSession, "online")).trigger(availableNow=True).start()
    q.awaitTermination()
    return learner
