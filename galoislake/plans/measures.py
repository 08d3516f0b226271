"""Cost measures of runs, and profiles of contexts."""

from __future__ import annotations

import time
from collections.abc import Callable, Sequence

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from galoislake.functions import bits
from galoislake.operators.context import FormalContext
from galoislake.plans.rounds import MiningResult


def profiles(contexts: dict[str, FormalContext]) -> DataFrame:
    """context, objects, attributes, crosses, density and distinct_rows of each context."""
    out = None
    for name, ctx in contexts.items():
        row = ctx.profile().select(F.lit(name).alias("context"), "objects", "attributes", "crosses", "density", "distinct_rows")
        out = row if out is None else out.unionByName(row)
    return out


def written(spark: SparkSession) -> dict[str, int]:
    """Bytes that tasks of this session wrote to shuffles, and milliseconds that they ran, so far."""
    time.sleep(0.3)  # executors' sums are published with a delay
    each = spark.sparkContext._jsc.sc().statusStore().executorList(False)
    own = [each.apply(i) for i in range(each.size())]
    return {"shuffle_bytes": sum(e.totalShuffleWrite() for e in own), "task_ms": sum(e.totalDuration() for e in own)}


def timed(run: Callable[[], MiningResult], spark: SparkSession | None = None) -> dict:
    """Seconds, rounds and intents of one run, the local closures that its merges met (one for each part
    and seed at most), and with a session the bytes shipped and the task time, as measured."""
    before = written(spark) if spark else {}
    began = time.time()
    result = run()
    intents = result.concepts.count()
    out = {
        "elapsed_s": time.time() - began, "rounds": result.rounds, "productive_rounds": result.productive_rounds, "intents": intents,
        "pairs": sum(m["pairs"] for m in result.metrics), "seeds": sum(m["seeds"] for m in result.metrics), "local_closures": sum(m["merges"] for m in result.metrics),
    }
    return out | ({k: v - before[k] for k, v in written(spark).items()} if spark else {})


def saving(seconds: float, base: float) -> float:
    """Share of the base time that is saved."""
    return 1 - seconds / base


def ratio(seconds: float, base: float) -> float:
    return base / seconds


def scaling_curve(spark: SparkSession, points: Sequence[tuple[int, float]]) -> DataFrame:
    """parts, seconds, speed_up against the first point, efficiency, and the gain over the point before."""
    df = spark.createDataFrame(list(points), "parts int, seconds double")
    by = Window.orderBy("parts")  # one row for each tried number of parts
    first = F.first("seconds").over(by)
    base = F.first("parts").over(by)
    return df.select("parts", "seconds", (first / F.col("seconds")).alias("speed_up"), (first * base / (F.col("seconds") * F.col("parts"))).alias("efficiency"), (F.lag("seconds").over(by) / F.col("seconds")).alias("gain"))


def best_parts(points: Sequence[tuple[int, float]]) -> int:
    return min(points, key=lambda p: p[1])[0]


def same_family(a: DataFrame, b: DataFrame) -> bool:
    """Completeness: both hold the same intents, each once."""
    x, y = a.select("intent"), b.select("intent")
    return x.exceptAll(y).isEmpty() and y.exceptAll(x).isEmpty()


def histogram(result: MiningResult) -> DataFrame:
    """Intents by round and size, with subtotals."""
    return result.concepts.groupBy("round", bits.size_of(result.context.columns()).alias("n")).count().rollup("round", "n").agg(F.sum("count").alias("intents"))
