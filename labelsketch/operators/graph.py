"""Construction and shaping of edge tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..store import written

#: Degree from which a vertex is a hub, and the number of subsets of a hub's neighbours.
HUB_DEGREE, HUB_CHUNKS = 128, 32
#: Neighbours of a hub's chunk at most; a vertex with more than HUB_CHUNKS times as many has more chunks.
CHUNK_ROWS = 4096


def with_unit_weights(edges: DataFrame) -> DataFrame:
    return edges.select("src", "dst", F.lit(1.0).alias("weight"))


def symmetrize(pairs: DataFrame, combine: str = "sum") -> DataFrame:
    """Undirected pairs or directed edges to both directions; parallel edges combined by sum, max or min.

    Every pair is first put as (least, greatest), so both directions get the very same weight.
    """
    how = {"sum": F.sum, "max": F.max, "min": F.min}[combine]
    one = pairs.select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b"), "weight").groupBy("a", "b").agg(how("weight").alias("weight"))
    both = F.when(F.col("a") == F.col("b"), F.array(F.struct(F.col("a").alias("src"), F.col("b").alias("dst")))).otherwise(F.array(F.struct(F.col("a").alias("src"), F.col("b").alias("dst")), F.struct(F.col("b").alias("src"), F.col("a").alias("dst"))))
    return one.select(F.explode(both).alias("e"), F.col("weight").cast("double").alias("weight")).select("e.src", "e.dst", "weight")


def drop_self_loops(edges: DataFrame) -> DataFrame:
    return edges.filter("src <> dst")


def filter_weight(edges: DataFrame, low: float, high: float) -> DataFrame:
    return edges.filter(F.col("weight").between(low, high))


def degrees(edges: DataFrame) -> DataFrame:
    """id, degree: neighbours other than itself."""
    return drop_self_loops(edges).groupBy(F.col("dst").alias("id")).agg(F.count("*").alias("degree"))


def weighted_degrees(edges: DataFrame) -> DataFrame:
    """id, k: all weight at a vertex, self-loops included."""
    return edges.groupBy(F.col("dst").alias("id")).agg(F.sum("weight").alias("k"))


def graph_stats(edges: DataFrame) -> DataFrame:
    """One row: n vertices, m_edges directed edges, total_weight (half of the directed sum), d_avg, max_degree."""
    per = edges.groupBy("dst").agg(F.count("*").alias("d"), F.sum("weight").alias("w"))
    return per.agg(F.count("*").alias("n"), F.sum("d").alias("m_edges"), (F.sum("w") / 2).alias("total_weight"), F.round(F.sum("d") / F.count("*"), 6).alias("d_avg"), F.max("d").alias("max_degree"))


def degree_histogram(edges: DataFrame) -> DataFrame:
    return degrees(edges).groupBy("degree").agg(F.count("*").alias("vertices"))


def filter_degree(edges: DataFrame, low: int, high: int) -> DataFrame:
    """Edges into vertices whose degree is between low and high."""
    some = degrees(edges).filter(F.col("degree").between(low, high)).select(F.col("id").alias("dst"))
    return edges.join(some, "dst", "left_semi").select("src", "dst", "weight")


def split_by_degree(edges: DataFrame, threshold: int = HUB_DEGREE) -> tuple[DataFrame, DataFrame]:
    """(edges into low-degree vertices, edges into hubs)."""
    hubs = degrees(edges).filter(F.col("degree") >= threshold).select(F.col("id").alias("dst"))
    return edges.join(hubs, "dst", "left_anti").select("src", "dst", "weight"), edges.join(hubs, "dst", "left_semi").select("src", "dst", "weight")


def scan_positions(edges: DataFrame, hub_degree: int = HUB_DEGREE, chunks: int = HUB_CHUNKS) -> DataFrame:
    """dst, src, weight, ord, chunk, hub, degree: neighbours numbered by ascending id; a hub's are dealt into chunks by that number.

    Chunks never come from a physical partition, so labels don't depend on the cluster.
    """
    w = Window.partitionBy("dst")
    placed = drop_self_loops(edges).select("dst", "src", "weight", (F.row_number().over(w.orderBy("src")) - 1).alias("ord"), F.count("*").over(w).alias("degree"))
    dealt = F.pmod(F.col("ord"), F.greatest(F.lit(chunks), F.ceil(F.col("degree") / CHUNK_ROWS)))
    hub = F.col("degree") >= hub_degree
    return placed.select("dst", "src", "weight", "ord", F.when(hub, dealt).otherwise(0).cast("int").alias("chunk"), hub.alias("hub"), "degree")


def dense_ids(df: DataFrame, column: str, id_name: str = "dense_id") -> DataFrame:
    """column, id_name: the distinct values numbered from 0 in byte order, without a global window.

    The sorted ranges are written once, so counts and ranks see the same ranges; their offsets are a row per range.
    """
    ranges = written(df.select(column).distinct().repartitionByRange(F.col(column).cast("binary")).withColumn("part", F.spark_partition_id()), "ranges")
    counts = ranges.groupBy("part").count()
    offset = counts.select("part", (F.sum("count").over(Window.orderBy("part")) - F.col("count")).alias("before"))
    inside = F.row_number().over(Window.partitionBy("part").orderBy(F.col(column).cast("binary"))) - 1
    return ranges.withColumn("inside", inside).join(F.broadcast(offset), "part").select(column, (F.col("before") + F.col("inside")).cast("long").alias(id_name))


def induced_subgraph(edges: DataFrame, ids: DataFrame) -> DataFrame:
    """Edges with both ends among ids(id)."""
    return edges.join(ids.select(F.col("id").alias("src")), "src", "left_semi").join(ids.select(F.col("id").alias("dst")), "dst", "left_semi").select("src", "dst", "weight")


def with_labels(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """src, dst, weight and the labels of both ends, src_label and dst_label."""
    return edges.join(labels.select(F.col("id").alias("src"), F.col("label").alias("src_label")), "src").join(labels.select(F.col("id").alias("dst"), F.col("label").alias("dst_label")), "dst")


def intra_edges(edges: DataFrame, labels: DataFrame) -> DataFrame:
    return with_labels(edges, labels).filter("src_label = dst_label")


def boundary_edges(edges: DataFrame, labels: DataFrame) -> DataFrame:
    return with_labels(edges, labels).filter("src_label <> dst_label")


def contract(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """The graph of communities: src, dst are labels, weight the sum between them (a loop holds the inner weight)."""
    return with_labels(edges, labels).groupBy(F.col("src_label").alias("src"), F.col("dst_label").alias("dst")).agg(F.sum("weight").alias("weight"))


def bipartite_project(pairs: DataFrame, item: str, via: str) -> DataFrame:
    """Items that share a ``via``, each tied to the least item there: a star, linear in the members of a group."""
    least = pairs.groupBy(via).agg(F.min(item).alias("src"))
    return pairs.join(least, via).filter(F.col("src") != F.col(item)).groupBy("src", F.col(item).alias("dst")).agg(F.count("*").cast("double").alias("weight"))


def sample_edges(edges: DataFrame, fraction: float) -> DataFrame:
    """A preview that keeps both directions of an edge or none."""
    return edges.filter(F.pmod(F.xxhash64(F.least("src", "dst"), F.greatest("src", "dst")), F.lit(1_000_000)) < int(fraction * 1_000_000))


def validate(edges: DataFrame) -> DataFrame:
    """Counts of what breaks the contract: nulls, weights not above 0, repeated rows, edges without an equal reverse."""
    reverse = edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.col("weight").alias("back"))
    merged = edges.groupBy("src", "dst").agg(F.count("*").alias("rows"), F.max("weight").alias("weight"))
    joined = merged.join(reverse.groupBy("src", "dst").agg(F.max("back").alias("back")), ["src", "dst"], "left")
    return joined.agg(
        F.count_if(F.col("src").isNull() | F.col("dst").isNull() | F.col("weight").isNull()).alias("nulls"), F.count_if(F.col("weight") <= 0).alias("not_positive"),
        F.count_if(F.col("rows") > 1).alias("repeated"), F.count_if(~F.col("back").eqNullSafe(F.col("weight"))).alias("one_way"),
    )


def load_graph(spark, table: str) -> DataFrame:
    """A graph that ``save_graph`` wrote, with its buckets."""
    return spark.table(table).select("src", "dst", "weight")


def active_edges(edges: DataFrame, frontier: DataFrame) -> DataFrame:
    """Edges into the vertices of frontier(id)."""
    return edges.join(frontier.select(F.col("id").alias("dst")), "dst", "left_semi")


def save_graph(edges: DataFrame, table: str, buckets: int) -> None:
    """Bucketed and sorted by dst, so that folds and label joins on dst need no shuffle."""
    edges.write.mode("overwrite").bucketBy(buckets, "dst").sortBy("dst", "src").saveAsTable(table)
