"""Cost and accuracy measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .graph import degrees, drop_self_loops, weighted_degrees, with_labels
from .selectors import Exact, HeavyHitter, linking_weights


def community_weights(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """label, inside (weight of directed edges within), total (weight of directed edges at its vertices)."""
    both = with_labels(edges, labels)
    return both.groupBy(F.col("dst_label").alias("label")).agg(F.sum(F.when(F.col("src_label") == F.col("dst_label"), F.col("weight")).otherwise(0.0)).alias("inside"), F.sum("weight").alias("total"))


def modularity(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """One row: q, communities, m."""
    per = community_weights(edges, labels)
    sums = per.agg(F.sum("inside").alias("i"), F.sum("total").alias("t"), F.sum(F.col("total") * F.col("total")).alias("tt"), F.count("*").alias("communities"))
    return sums.select((F.col("i") / F.col("t") - F.col("tt") / (F.col("t") * F.col("t"))).alias("q"), "communities", (F.col("t") / 2).alias("m"))


def modularity_pairwise(edges: DataFrame, labels: DataFrame, most: int = 1000) -> float:
    """The all-pairs form, as a check on graphs of at most ``most`` vertices (the driver's loop is bounded by that)."""
    k = {r["id"]: r["k"] for r in weighted_degrees(edges).limit(most + 1).collect()}
    if len(k) > most:
        raise ValueError("too many vertices for the pairwise form")
    at = {r["id"]: r["label"] for r in labels.collect()}
    w = {(r["src"], r["dst"]): r["weight"] for r in edges.collect()}
    two_m = sum(k.values())
    return sum(w.get((i, j), 0.0) - k[i] * k[j] / two_m for i in k for j in k if at[i] == at[j]) / two_m


def delta_modularity(edges: DataFrame, labels: DataFrame, moves: DataFrame) -> DataFrame:
    """id, target, dq for moves (id, target): the change of modularity if the vertex alone moved there."""
    pairs = drop_self_loops(edges).join(labels.select(F.col("id").alias("src"), "label"), "src").select("dst", "label", "weight")
    link = linking_weights(pairs).select(F.col("dst").alias("id"), "label", "weight")
    total = community_weights(edges, labels).select("label", "total")
    m2 = edges.agg(F.sum("weight").alias("m2"))
    rows = moves.join(labels, "id").join(weighted_degrees(edges), "id").join(F.broadcast(m2))
    rows = rows.join(link.select("id", F.col("label").alias("target"), F.col("weight").alias("to")), ["id", "target"], "left")
    rows = rows.join(link.select("id", "label", F.col("weight").alias("from")), ["id", "label"], "left")
    rows = rows.join(total.select(F.col("label").alias("target"), F.col("total").alias("s_to")), "target", "left").join(total.select("label", F.col("total").alias("s_from")), "label")
    m = F.col("m2") / 2
    dq = (F.coalesce("to", F.lit(0.0)) - F.coalesce("from", F.lit(0.0))) / m - F.col("k") * (F.col("k") + F.coalesce("s_to", F.lit(0.0)) - F.col("s_from")) / (2 * m * m)
    return rows.select("id", "target", F.when(F.col("target") == F.col("label"), F.lit(0.0)).otherwise(dq).alias("dq"))


def community_count(labels: DataFrame) -> DataFrame:
    return labels.agg(F.countDistinct("label").alias("communities"))


def community_sizes(labels: DataFrame) -> DataFrame:
    return labels.groupBy("label").agg(F.count("*").alias("members"))


def nmi(labels: DataFrame, truth: DataFrame) -> DataFrame:
    """One row: normalised mutual information of labels(id, label) and truth(id, truth), arithmetic mean in the norm."""
    cell = labels.join(truth, "id").groupBy("label", "truth").agg(F.count("*").alias("n"))
    rows = cell.groupBy("label").agg(F.sum("n").alias("a"))
    columns = cell.groupBy("truth").agg(F.sum("n").alias("b"))
    total = cell.agg(F.sum("n").alias("t"))
    p = cell.join(rows, "label").join(columns, "truth").join(F.broadcast(total))
    mutual = p.agg(F.sum(F.col("n") / F.col("t") * F.log(F.col("n") * F.col("t") / (F.col("a") * F.col("b")))).alias("i"))

    def entropy(df: DataFrame, n: str, name: str) -> DataFrame:
        return df.join(F.broadcast(total)).agg((-F.sum(F.col(n) / F.col("t") * F.log(F.col(n) / F.col("t")))).alias(name))

    both = mutual.join(entropy(rows, "a", "ha")).join(entropy(columns, "b", "hb"))
    return both.select(F.when(F.col("ha") + F.col("hb") == 0, F.lit(1.0)).otherwise(2 * F.col("i") / (F.col("ha") + F.col("hb"))).alias("nmi"))


#: Bytes: of a label or id, of a weight, of a flag.
LABEL_BYTES, WEIGHT_BYTES, FLAG_BYTES = 4, 4, 1


def working_set_bytes(stats: DataFrame, threads: int = 64) -> DataFrame:
    """method, bytes beside the input graph, from graph_stats: labels and flags for all; a full-size map per thread, or two
    entries per directed edge, for the methods with maps."""
    own = F.col("n") * (LABEL_BYTES + FLAG_BYTES)
    methods = {"mg": own, "vote": own, "thread_map": own + F.col("n") * threads * (LABEL_BYTES + WEIGHT_BYTES), "vertex_map": own + 2 * F.col("m_edges") * (LABEL_BYTES + WEIGHT_BYTES)}
    return stats.select(F.explode(F.array(*[F.struct(F.lit(k).alias("method"), v.cast("long").alias("bytes")) for k, v in methods.items()])).alias("x")).select("x.method", "x.bytes")


def vertex_map_layout(edges: DataFrame) -> DataFrame:
    """id, degree, capacity of its open-addressing map (next power of two, less one); its reservation is 2 * degree entries.

    The offset of a map is twice the edges before the vertex; it needs a running sum and is given by ``map_offsets``.
    """
    d = F.col("degree")
    return degrees(edges).select("id", "degree", (F.pow(F.lit(2.0), F.ceil(F.log2(d.cast("double") + 1e-9))) - 1).cast("long").alias("capacity"), (2 * d).alias("reserved"))


def map_offsets(edges: DataFrame, parts: int = 64) -> DataFrame:
    """id, offset: running sums inside id ranges plus the ranges' sums, so no window holds all vertices."""
    d = degrees(edges)
    bounds = d.agg(F.min("id").alias("lo"), F.max("id").alias("hi")).first()
    width = max(1, ((bounds["hi"] or 0) - (bounds["lo"] or 0)) // parts + 1)
    d = d.withColumn("part", F.floor((F.col("id") - F.lit(bounds["lo"] or 0)) / width))
    inner = F.sum("degree").over(Window.partitionBy("part").orderBy("id")) - F.col("degree")
    before = d.groupBy("part").agg(F.sum("degree").alias("s")).select("part", (F.sum("s").over(Window.orderBy("part")) - F.col("s")).alias("before"))
    return d.withColumn("inner", inner).join(F.broadcast(before), "part").select("id", (2 * (F.col("before") + F.col("inner"))).cast("long").alias("offset"))


def selection_agreement(pairs: DataFrame, k: int = 8) -> DataFrame:
    """One row: vertices, and how many pick the same label by single scan and double scan, and by double scan and exactly."""
    single = HeavyHitter(k=k).candidates(pairs).withColumnRenamed("candidate", "one")
    double = HeavyHitter(k=k, scan="double").candidates(pairs).withColumnRenamed("candidate", "two")
    exact = Exact().candidates(pairs).withColumnRenamed("candidate", "all")
    return exact.join(single, "id", "left").join(double, "id", "left").agg(F.count("*").alias("vertices"), F.count_if(F.col("one") == F.col("two")).alias("single_double"), F.count_if(F.col("two") == F.col("all")).alias("double_exact"), F.count_if(F.col("one") == F.col("all")).alias("single_exact"))


def sketch_guarantee_violations(pairs: DataFrame, k: int = 8) -> DataFrame:
    """One row: labels above K/(k+1) that the sketch lost, estimates above the truth, errors above (K - estimates)/(k+1)."""
    truth = linking_weights(pairs).withColumn("total", F.sum("weight").over(Window.partitionBy("dst")))
    slots = HeavyHitter(k=k, consolidation="shared").sketch(pairs).select("dst", F.explode("slots").alias("s")).select("dst", "s.label", F.col("s.weight").alias("estimate"))
    kept = slots.groupBy("dst").agg(F.sum("estimate").alias("kept"))
    j = truth.join(slots, ["dst", "label"], "left").join(kept, "dst", "left").fillna(0.0, ["estimate", "kept"])
    return j.agg(F.count_if((F.col("weight") * (k + 1) > F.col("total")) & (F.col("estimate") == 0)).alias("lost"), F.count_if(F.col("estimate") > F.col("weight")).alias("over"), F.count_if((F.col("weight") - F.col("estimate")) * (k + 1) > F.col("total") - F.col("kept") + 1e-9).alias("beyond"))


def shuffle_model(pairs: DataFrame, k: int = 8) -> DataFrame:
    """One row, a model: rows that an exact aggregation, chunked sketches and chunked votes of all vertices come to.

    With broadcast labels only hubs' chunks are shuffled, so the engine moves less; ``shuffled_bytes`` measures that.
    """
    exact = pairs.groupBy("dst", "label").agg(F.count("*").alias("n")).agg(F.count("*").alias("exact_rows"))
    per = pairs.groupBy("dst", "chunk").agg(F.countDistinct("label").alias("d")).agg(F.sum(F.least("d", F.lit(k))).alias("sketch_rows"), F.count("*").alias("vote_rows"))
    return exact.join(per)


def swap_count(older: DataFrame, newer: DataFrame, between: DataFrame) -> DataFrame:
    """One row: vertices that have the label of two iterations ago again, but not that of the last one."""
    j = older.select("id", F.col("label").alias("a")).join(between.select("id", F.col("label").alias("b")), "id").join(newer.select("id", F.col("label").alias("c")), "id")
    return j.agg(F.count_if((F.col("a") == F.col("c")) & (F.col("a") != F.col("b"))).alias("swaps"))


def shuffled_bytes(spark) -> int:
    """Bytes that all executors have written to shuffles so far; the difference around a run is what the run moved."""
    executors = spark.sparkContext._jsc.sc().statusStore().executorList(False)
    return sum(executors.apply(i).totalShuffleWrite() for i in range(executors.size()))
