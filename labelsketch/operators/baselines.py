"""The methods compared with: three exact label propagation set-ups, and the related methods that are only mentioned."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..store import written
from .graph import contract, drop_self_loops, weighted_degrees
from .metrics import community_weights
from .propagate import LPConfig, LPResult, PickLess, Schedule, Stop, initial_labels, label_propagation
from .selectors import Exact, linking_weights

NO_PICK_LESS = PickLess(period=None)


def baseline_parallel_lp(edges: DataFrame, max_iterations: int = 20, tolerance: float = 1e-5) -> LPResult:
    """A: a multicore library routine; exact, in-place updates stood for by batches, tight tolerance, no symmetry breaker."""
    return label_propagation(edges, LPConfig(Exact(), NO_PICK_LESS, Stop(tolerance, max_iterations), Schedule(8)))


def baseline_thread_map_lp(edges: DataFrame, max_iterations: int = 20, tolerance: float = 0.05) -> LPResult:
    """B: multicore, a full-size map per thread; exact, batches, the common tolerance."""
    return label_propagation(edges, LPConfig(Exact(), NO_PICK_LESS, Stop(tolerance, max_iterations), Schedule(8)))


def baseline_vertex_map_lp(edges: DataFrame, max_iterations: int = 20, tolerance: float = 0.05) -> LPResult:
    """C: one open-addressing map per vertex; exact, simultaneous, pick-less every 4 iterations."""
    return label_propagation(edges, LPConfig(Exact(), PickLess(4), Stop(tolerance, max_iterations)))


def louvain_pass(edges: DataFrame, rounds: int = 1, labels: DataFrame | None = None) -> DataFrame:
    """Labels after rounds of local moving: each vertex goes where modularity gains most (least label on a tie).

    Moves are simultaneous; even rounds allow moves to smaller labels alone, so that neighbours don't swap for ever.
    """
    labels = labels if labels is not None else initial_labels(edges)
    k = weighted_degrees(edges)
    two_m = edges.agg(F.sum("weight")).first()[0] or 1.0
    for t in range(rounds):
        pairs = drop_self_loops(edges).join(labels.select(F.col("id").alias("src"), "label"), "src").select("dst", "label", "weight")
        total = community_weights(edges, labels).select("label", "total")
        own = labels.select(F.col("id").alias("dst"), F.col("label").alias("own"))
        link = linking_weights(pairs).join(own, "dst").join(k.withColumnRenamed("id", "dst"), "dst").join(total, "label")
        # gain of joining a community, the vertex's own weight taken out of the one it is in
        gain = F.col("weight") - F.col("k") * (F.col("total") - F.when(F.col("label") == F.col("own"), F.col("k")).otherwise(0.0)) / F.lit(two_m)
        stay = own.join(k.withColumnRenamed("id", "dst"), "dst").join(total.withColumnRenamed("label", "own"), "own").select("dst", F.col("own").alias("label"), "own", (-F.col("k") * (F.col("total") - F.col("k")) / F.lit(two_m)).alias("gain"))
        options = link.select("dst", "label", "own", gain.alias("gain")).unionByName(stay)
        best = options.groupBy("dst", "own", "label").agg(F.max("gain").alias("gain")).groupBy("dst", "own").agg(F.max_by("label", F.struct(F.round("gain", 9), F.col("label") == F.col("own"), -F.col("label"))).alias("to"))
        moves = F.when((F.lit(t % 2 == 1)) | (F.col("to") < F.col("own")), F.col("to")).otherwise(F.col("own"))
        labels = written(best.select(F.col("dst").alias("id"), moves.alias("label")), "louvain")
    return labels


def louvain(edges: DataFrame, levels: int = 3, rounds: int = 4) -> DataFrame:
    """Labels after levels of local moving and contraction."""
    labels = louvain_pass(edges, rounds)
    for _ in range(levels - 1):
        upper = written(contract(edges, labels), "contracted")
        above = louvain_pass(upper, rounds)
        labels = written(labels.join(above.select(F.col("id").alias("label"), F.col("label").alias("up")), "label").select("id", F.col("up").alias("label")), "louvain")
    return labels


def labelrank(edges: DataFrame, iterations: int = 3, inflation: float = 2.0, cutoff: float = 0.1) -> DataFrame:
    """id, label by label distributions that are spread, inflated, cut off and normalised (self-loops added)."""
    loops = edges.select("dst").distinct().select(F.col("dst").alias("src"), "dst", F.lit(1.0).alias("weight"))
    whole = drop_self_loops(edges).unionByName(loops)
    p = whole.select(F.col("dst").alias("id"), F.col("src").alias("label"), (F.col("weight") / F.sum("weight").over(Window.partitionBy("dst"))).alias("p"))
    w = Window.partitionBy("id")
    for _ in range(iterations):
        spread = whole.join(p.select(F.col("id").alias("src"), "label", "p"), "src").groupBy(F.col("dst").alias("id"), "label").agg(F.sum(F.col("weight") * F.col("p")).alias("p"))
        spread = spread.withColumn("p", F.pow(F.col("p") / F.sum("p").over(w), F.lit(inflation))).withColumn("p", F.col("p") / F.sum("p").over(w))
        cut = spread.withColumn("top", F.max("p").over(w)).filter((F.col("p") >= cutoff) | (F.col("p") == F.col("top")))
        p = written(cut.withColumn("p", F.col("p") / F.sum("p").over(w)).select("id", "label", "p"), "labelrank")
    return p.groupBy("id").agg(F.max_by("label", F.struct(F.round("p", 9), -F.col("label"))).alias("label"))


def copra(edges: DataFrame, v: int = 2, iterations: int = 5) -> DataFrame:
    """id, label, share: overlapping communities by belonging coefficients; those below 1/v are dropped, the largest kept."""
    b = initial_labels(edges).select("id", "label", F.lit(1.0).alias("share"))
    w = Window.partitionBy("id")
    for _ in range(iterations):
        spread = drop_self_loops(edges).join(b.select(F.col("id").alias("src"), "label", "share"), "src").groupBy(F.col("dst").alias("id"), "label").agg(F.sum(F.col("weight") * F.col("share")).alias("share"))
        spread = spread.withColumn("share", F.col("share") / F.sum("share").over(w))
        rank = F.row_number().over(w.orderBy(F.desc(F.round("share", 9)), "label"))
        kept = spread.withColumn("r", rank).filter((F.col("share") >= 1.0 / v) | (F.col("r") == 1))
        b = written(kept.withColumn("share", F.col("share") / F.sum("share").over(w)).select("id", "label", "share"), "copra")
    return b


def slpa(edges: DataFrame, iterations: int = 5, threshold: float = 0.2) -> DataFrame:
    """id, label, share: each listener takes the most spoken label; speakers draw from their memory by a seeded hash."""
    memory = initial_labels(edges).select("id", "label", F.lit(1).alias("n"))
    for t in range(iterations):
        order = Window.partitionBy("id").orderBy("label")
        total = F.sum("n").over(Window.partitionBy("id"))
        upto = memory.select("id", "label", F.sum("n").over(order).alias("hi"), (F.sum("n").over(order) - F.col("n")).alias("lo"), total.alias("total"))
        spoken = drop_self_loops(edges).join(upto.withColumnRenamed("id", "src"), "src").withColumn("draw", F.pmod(F.xxhash64("src", "dst", F.lit(t)), F.col("total"))).filter("draw >= lo and draw < hi")
        heard = spoken.groupBy("dst", "label").agg(F.sum("weight").alias("w")).groupBy(F.col("dst").alias("id")).agg(F.max_by("label", F.struct(F.col("w"), -F.col("label"))).alias("label"))
        memory = written(memory.unionByName(heard.withColumn("n", F.lit(1))).groupBy("id", "label").agg(F.sum("n").cast("int").alias("n")), "memory")
    share = F.col("n") / F.sum("n").over(Window.partitionBy("id"))
    return memory.withColumn("share", share).filter(F.col("share") >= threshold).select("id", "label", "share")
