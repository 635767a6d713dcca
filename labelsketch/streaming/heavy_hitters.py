"""Heavy hitters of event streams, and label propagation kept up to date with arriving edges."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import sketch as S
from ..operators.graph import symmetrize
from ..operators.propagate import LPConfig, label_propagation


def stream_heavy_hitters(stream: DataFrame, key: str, item: str, weight: str, time: str, window: str = "1 hour", slide: str | None = None, watermark: str = "10 minutes") -> DataFrame:
    """window start, key, item, weight: sums per window, the input of ``top_slots``; late rows beyond the watermark drop."""
    timed = stream.withColumn("__time", F.col(time).cast("timestamp")).withWatermark("__time", watermark)
    span = F.window("__time", window, slide) if slide else F.window("__time", window)
    return timed.groupBy(span.alias("window"), key, item).agg(F.sum(weight).alias("weight")).select(F.col("window.start").alias("start"), key, F.col(item).alias("item"), "weight")


def top_slots(sums: DataFrame, key: str, k: int) -> DataFrame:
    """start, key, item, weight of the sketch of each window and key (items numbered in the pairs by their hash)."""
    pairs = sums.groupBy("start", key).agg(F.array_sort(F.collect_list(F.struct(F.xxhash64("item").alias("ord"), F.xxhash64("item").alias("label"), F.col("weight").cast("double").alias("weight")))).alias("pairs"))
    slots = pairs.select("start", key, F.explode(S.mg_fold(F.col("pairs"), k)).alias("s"))
    return slots.join(sums.select("start", key, "item", F.xxhash64("item").alias("h")), ["start", key]).filter("s.label = h").select("start", key, "item", F.col("s.weight").alias("weight"))


def start(sums: DataFrame, path: str, checkpoint: str, sink: Callable[[DataFrame, int], None] | None = None):
    """Runs to the end of the available input. A batch writes to a folder of its own number, so a repeat changes nothing."""

    def write(batch: DataFrame, number: int) -> None:
        (sink or (lambda df, n: df.write.mode("overwrite").parquet(f"{path}/batch={n}")))(batch, number)

    return sums.writeStream.outputMode("append").foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def sketch_per_key(stream: DataFrame, key: str, label: str, weight: str, k: int) -> DataFrame:
    """key and its slots after each batch, kept as state of at most k slots per key."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    def update(group, frames, state):
        sketch = S.Sketch(k, slots=list(zip(*state.get, strict=True)) if state.exists else ())
        for frame in frames:
            for x, w in zip(frame[label].tolist(), frame[weight].tolist(), strict=True):
                sketch.add(int(x), float(w))
        slots = sorted(sketch.slots.items())
        state.update(([x for x, _ in slots], [w for _, w in slots]))
        yield pd.DataFrame({"key": [group[0]] * len(slots), "label": [x for x, _ in slots], "weight": [w for _, w in slots]})

    return stream.groupBy(key).applyInPandasWithState(update, "key long, label long, weight double", "labels array<long>, weights array<double>", "update", GroupStateTimeout.NoTimeout)


def incremental_lp(spark: SparkSession, stream: DataFrame, path: str, checkpoint: str, config: LPConfig = LPConfig()):
    """Edges (src, dst, weight) arrive in batches; each batch adds to the stored graph and writes labels of its number."""

    def update(batch: DataFrame, number: int) -> None:
        batch.select("src", "dst", "weight").write.mode("overwrite").parquet(f"{path}/edges/batch={number}")
        edges = symmetrize(spark.read.parquet(f"{path}/edges").select("src", "dst", "weight"))
        label_propagation(edges, config).labels.write.mode("overwrite").parquet(f"{path}/labels/batch={number}")

    return stream.writeStream.foreachBatch(update).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
