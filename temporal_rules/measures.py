"""Cost measures: elapsed time, rows through nodes, exchanges of a plan, growth, speed-up."""

from __future__ import annotations

import math
import re
import time
from collections import Counter

from pyspark.sql import DataFrame


def elapsed(make, runs: int = 3, timeout_s: float = 4000) -> dict:
    """Mean seconds of evaluating a frame from scratch; censored beyond the time-out."""
    took = []
    for _ in range(runs):
        t = time.time()
        make().write.format("noop").mode("overwrite").save()
        took.append(time.time() - t)
        if took[-1] > timeout_s:
            break
    return {"seconds": sum(took) / len(took), "runs": len(took), "censored": took[-1] > timeout_s}


def plan_counts(df: DataFrame) -> Counter:
    """Operators of the physical plan by name."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return Counter(re.findall(r"\b(Exchange|BroadcastExchange|SortMergeJoin|ShuffledHashJoin|BroadcastHashJoin|CartesianProduct|BroadcastNestedLoopJoin|Window|Sort|HashAggregate|Generate|MapInArrow|FlatMapGroupsInArrow)\b", text))


def growth(points: list[tuple[float, float]]) -> float:
    """Slope of log seconds over log size; 1 is linear."""
    xs, ys = [math.log(a) for a, _ in points], [math.log(b) for _, b in points]
    mx, my = sum(xs) / len(xs), sum(ys) / len(ys)
    return sum((x - mx) * (y - my) for x, y in zip(xs, ys)) / sum((x - mx) ** 2 for x in xs)


def speed_up(rival_s: float, own_s: float) -> float:
    return rival_s / own_s
