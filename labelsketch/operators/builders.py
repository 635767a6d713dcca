"""Graphs of the experiment workloads on the given tables; all give EDGE_SCHEMA, both directions, over whole tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.tables import table
from .graph import bipartite_project, dense_ids, symmetrize
from .windows import window_graph


def two_types(pairs: DataFrame, left: str, right: str, weight) -> DataFrame:
    """Edges between two kinds of keys: the first kind gets even ids, the second odd ones."""
    return symmetrize(pairs.select((2 * F.col(left)).cast("long").alias("src"), (2 * F.col(right) + 1).cast("long").alias("dst"), weight.cast("double").alias("weight")))


def weblink(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Page and link target, for every distinct href of the page."""
    links = table(spark, sf_dir, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("target")).distinct()
    return two_types(links.join(dense_ids(links, "target"), "target"), "page_id", "dense_id", F.lit(1.0))


def copurchase(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two parts of one order, weighted by the line pairs."""
    line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    other = line.select("l_orderkey", F.col("l_partkey").alias("other"))
    pairs = line.join(other, "l_orderkey").filter("l_partkey < other").groupBy(F.col("l_partkey").alias("src"), F.col("other").alias("dst")).agg(F.count("*").cast("double").alias("weight"))
    return symmetrize(pairs)


def supply(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Supplier and part, weighted by quantity."""
    pairs = table(spark, sf_dir, "lineitem").groupBy("l_suppkey", "l_partkey").agg(F.sum("l_quantity").alias("w"))
    return two_types(pairs, "l_suppkey", "l_partkey", F.col("w"))


def trade(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customer and supplier, weighted by quantity."""
    line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey", "l_quantity")
    orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
    return two_types(line.join(orders, "l_orderkey").groupBy("o_custkey", "l_suppkey").agg(F.sum("l_quantity").alias("w")), "o_custkey", "l_suppkey", F.col("w"))


def order_path(spark: SparkSession, sf_dir: str) -> DataFrame:
    """An order and the previous one of its customer."""
    before = F.lag("o_orderkey").over(Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey"))
    return symmetrize(table(spark, sf_dir, "orders").select(before.alias("src"), F.col("o_orderkey").alias("dst"), F.lit(1.0).alias("weight")).filter("src is not null"))


def kmer(spark: SparkSession, sf_dir: str, k: int = 12) -> DataFrame:
    """Successive k-character windows of every text; equal neighbours are dropped."""
    return window_graph(table(spark, sf_dir, "documents"), "text", k)


def text_graph(pairs: DataFrame, a: str, b: str, weight, combine: str = "sum") -> DataFrame:
    """Edges between strings, numbered in byte order."""
    ids = dense_ids(pairs.select(F.explode(F.array(a, b)).alias("word")), "word")
    first, second = ids.select(F.col("word").alias(a), F.col("dense_id").alias("src")), ids.select(F.col("word").alias(b), F.col("dense_id").alias("dst"))
    return symmetrize(pairs.join(first, a).join(second, b).select("src", "dst", weight.cast("double").alias("weight")), combine)


def words(text="text"):
    return F.filter(F.split(F.lower(text), "[^a-z]+"), lambda w: w != "")


def bigram(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Neighbouring words of every text, weighted by count."""
    cut = table(spark, sf_dir, "documents").select(F.explode(F.array(words())).alias("w")).filter(F.size("w") > 1)
    pair = cut.select(F.explode(F.arrays_zip(F.slice("w", 1, F.size("w") - 1).alias("a"), F.slice("w", 2, F.size("w") - 1).alias("b"))).alias("p")).select("p.a", "p.b")
    return text_graph(pair.filter("a <> b").groupBy("a", "b").agg(F.count("*").alias("n")), "a", "b", F.col("n"))


def docword(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Document and distinct word."""
    pairs = table(spark, sf_dir, "documents").select("doc_id", F.explode(F.array_distinct(words())).alias("word"))
    return two_types(pairs.join(dense_ids(pairs, "word"), "word"), "doc_id", "dense_id", F.lit(1.0))


#: Documents of a line up to which all its pairs are edges; the rest of a hotter line hangs on its least document.
LINE_DOCS = 200


def lines_of(spark: SparkSession, sf_dir: str, least: int) -> DataFrame:
    """doc_id, line: the distinct lines of so many characters, as checksums."""
    lines = table(spark, sf_dir, "documents").select("doc_id", F.explode(F.array_distinct(F.split("text", "\n"))).alias("line")).filter(F.length("line") >= least)
    return lines.select("doc_id", F.md5("line").alias("line")).distinct()


def shared_line(spark: SparkSession, sf_dir: str, least: int = 20, most: int = LINE_DOCS) -> DataFrame:
    """Documents that share a line of so many characters, weighted by the lines.

    A line of at most ``most`` documents ties them all; a hotter one is a star around its least document, so that no line costs
    the square of its documents and none is dropped.
    """
    lines = lines_of(spark, sf_dir, least)
    count = lines.groupBy("line").agg(F.count("*").alias("n"), F.min("doc_id").alias("src")).filter("n > 1")
    rare, hot = count.filter(F.col("n") <= most).select("line"), count.filter(F.col("n") > most).select("line", "src")
    some = lines.join(rare, "line")
    pairs = some.join(some.select("line", F.col("doc_id").alias("dst")), "line").filter("doc_id < dst").select(F.col("doc_id").alias("src"), "dst")
    stars = lines.join(hot, "line").filter("src <> doc_id").select("src", F.col("doc_id").alias("dst"))
    return symmetrize(pairs.unionByName(stars).groupBy("src", "dst").agg(F.count("*").cast("double").alias("weight")))


def shared_line_star(spark: SparkSession, sf_dir: str, least: int = 20) -> DataFrame:
    """The same documents, every line a star around its least document: linear in the lines."""
    return symmetrize(bipartite_project(lines_of(spark, sf_dir, least), "doc_id", "line"))


def user_activity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User and (day, event type), weighted by cents."""
    events = table(spark, sf_dir, "events").select("user_id", F.concat_ws("|", F.date_format("ts", "yyyy-MM-dd"), "event_type").alias("slot"), F.round(F.col("value") * 100).cast("long").alias("cents"))
    sums = events.groupBy("user_id", "slot").agg(F.sum("cents").alias("w")).filter("w > 0")
    return two_types(sums.join(dense_ids(sums, "slot"), "slot"), "user_id", "dense_id", F.col("w"))


def turn_path(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Successive turns of a conversation; a turn's id is conv_id * 2^20 + turn."""
    turn = table(spark, sf_dir, "conversations").select("conv_id", "turn").distinct()
    at = F.col("conv_id") * 1048576 + F.col("turn")
    after = F.lead("turn").over(Window.partitionBy("conv_id").orderBy("turn"))
    return symmetrize(turn.select(at.alias("src"), (F.col("conv_id") * 1048576 + after).alias("dst"), F.lit(1.0).alias("weight")).filter("dst is not null"))


#: Vectors of each side of a tile of similarities.
TILE = 1024


def knn(spark: SparkSession, sf_dir: str, n: int = 5, block_rows: int = 20_000) -> DataFrame:
    """Each vector's n nearest by cosine (ties by id), weight round(10^6 (1 + cos)).

    The vectors are queries in blocks of block_rows: each block is broadcast to one scan that keeps n best per query and
    task, so memory is bounded and only n rows per query and task are shuffled.
    """
    import numpy as np
    import pyarrow as pa

    vectors = table(spark, sf_dir, "embeddings").select("vec_id", "embedding").filter("embedding is not null")
    total = vectors.count()
    found = None
    for k in range(max(1, -(-total // block_rows))):
        rows = vectors.filter(F.pmod(F.xxhash64("vec_id"), F.lit(max(1, -(-total // block_rows)))) == k).toArrow()
        if not rows.num_rows:
            continue
        q_ids, q = rows.column("vec_id").to_numpy(), np.stack(rows.column("embedding").to_numpy(zero_copy_only=False)).astype(np.float64)
        held = spark.sparkContext.broadcast((q_ids, q / np.maximum(np.linalg.norm(q, axis=1, keepdims=True), 1e-12)))

        def run(batches, held=held):
            q_ids, q = held.value
            for batch in batches:
                ids, x = batch.column("vec_id").to_numpy(), np.stack(batch.column("embedding").to_numpy(zero_copy_only=False)).astype(np.float64)
                x = x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)
                for a in range(0, len(q), TILE):  # a tile's product is TILE x TILE
                    for b in range(0, len(x), TILE):
                        cos, there = np.round(1e6 * (1 + q[a : a + TILE] @ x[b : b + TILE].T)), ids[b : b + TILE]
                        cos[q_ids[a : a + TILE, None] == there] = -1
                        for i, row in enumerate(cos):
                            cut = np.partition(row, max(0, len(row) - n))[max(0, len(row) - n)]
                            some = np.nonzero((row >= cut) & (row >= 0))[0]
                            best = some[np.lexsort((there[some], -row[some]))][:n]
                            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(best), q_ids[a + i])), pa.array(there[best]), pa.array(row[best])], ["src", "dst", "weight"])

        near = vectors.mapInArrow(run, "src long, dst long, weight double")
        found = near if found is None else found.unionByName(near)
    rank = F.row_number().over(Window.partitionBy("src").orderBy(F.desc("weight"), "dst"))
    return symmetrize(found.withColumn("r", rank).filter(F.col("r") <= n).drop("r"), "max")


#: Literal toy graphs, undirected.
TOYS: dict[str, list[tuple[int, int]]] = {
    "two_triangles": [(1, 2), (1, 3), (2, 3), (3, 4), (4, 5), (4, 6), (5, 6)],
    "single_edge": [(1, 2)],
    "star": [(0, i) for i in range(1, 201)],
    "path": [(i, i + 1) for i in range(1, 10)],
    "clique_ring": [(5 * c + i, 5 * c + j) for c in range(4) for i in range(5) for j in range(i + 1, 5)] + [(5 * c + 4, (5 * c + 5) % 20) for c in range(4)],
}


def toy(spark: SparkSession, name: str) -> DataFrame:
    return symmetrize(spark.createDataFrame([(a, b, 1.0) for a, b in TOYS[name]], "src long, dst long, weight double"))


def toy_on_parts(spark: SparkSession, sf_dir: str, name: str = "two_triangles") -> DataFrame:
    """A toy graph of vertices 1 to n on every n successive part keys from a multiple of n, where the table has both ends of an edge."""
    n = max(v for e in TOYS[name] for v in e)
    keys = table(spark, sf_dir, "part").select(F.col("p_partkey").cast("long").alias("src")).filter("src is not null").distinct()
    steps = F.create_map(*[x for v in range(1, n + 1) for x in (F.lit(v), F.array(*[F.lit(b - a) for a, b in TOYS[name] if a == v]).cast("array<int>"))])
    pairs = keys.select("src", F.explode(steps[(F.pmod("src", F.lit(n)) + 1).cast("int")]).alias("step")).select("src", (F.col("src") + F.col("step")).alias("dst"))
    return symmetrize(pairs.join(keys.select(F.col("src").alias("dst")), "dst", "left_semi").select("src", "dst", F.lit(1.0).alias("weight")))


BUILDERS = {f.__name__: f for f in (weblink, copurchase, supply, trade, order_path, kmer, bigram, docword, shared_line, shared_line_star, user_activity, turn_path, knn)}
