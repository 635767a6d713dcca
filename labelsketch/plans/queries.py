"""Every method, variant, baseline, measure and workload as a query over the given tables."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import sketch as S
from ..operators import baselines, communities, graph, metrics
from ..operators.builders import BUILDERS, toy_on_parts
from ..operators.propagate import LPConfig, PickLess, Schedule, Stop, label_pairs, label_propagation, step, initial_labels
from ..operators.selectors import Exact, HeavyHitter, MajorityVote, linking_weights
from ..sources.tables import table
from ..store import written

#: Labels of the sketch queries: id modulo this, so that hubs see more labels than a sketch has slots.
SPREAD = 50
OFF = PickLess(period=None)


def edges_of(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return written(BUILDERS[name](spark, sf_dir), name)


def run_lp(name: str, config: LPConfig, spark: SparkSession, sf_dir: str) -> DataFrame:
    return label_propagation(edges_of(spark, sf_dir, name), config).labels


def lp(selector, iterations: int, pick_less: PickLess = PickLess(), tolerance: float = 0.0, batches: int = 1) -> LPConfig:
    return LPConfig(selector, pick_less, Stop(tolerance, iterations), Schedule(batches))


#: name -> (graph, configuration); the oracles unroll the same list.
LP_RUNS: dict[str, tuple[str, LPConfig]] = {
    "exact_lp_1": ("copurchase", lp(Exact(), 1)),
    "exact_lp_3": ("copurchase", lp(Exact(), 3)),
    "exact_lp_8": ("weblink", lp(Exact(), 8)),
    "exact_lp_shared_line": ("shared_line", lp(Exact(), 6)),
    "exact_lp_supply": ("supply", lp(Exact(), 3)),
    "mg_lp_1": ("copurchase", lp(HeavyHitter(), 1)),
    "mg_lp_3": ("copurchase", lp(HeavyHitter(), 3)),
    "mg_lp_8": ("weblink", lp(HeavyHitter(), 8)),
    "mg_lp_shared_line": ("shared_line", lp(HeavyHitter(), 6)),
    "mg_lp_order_path": ("order_path", lp(HeavyHitter(), 4)),
    "mg_lp_user_activity": ("user_activity", lp(HeavyHitter(), 4)),
    "mg_lp_turn_path": ("turn_path", lp(HeavyHitter(), 6)),
    "mg_lp_k2": ("trade", lp(HeavyHitter(k=2), 3)),
    "mg_lp_k4": ("trade", lp(HeavyHitter(k=4), 3)),
    "mg_lp_k16": ("trade", lp(HeavyHitter(k=16), 3)),
    "mg_lp_k32": ("trade", lp(HeavyHitter(k=32), 3)),
    "mg_lp_floor": ("trade", lp(HeavyHitter(overflow="floor"), 3)),
    "mg_lp_as_described": ("trade", lp(HeavyHitter(overflow="as_described"), 3)),
    "mg_lp_double_scan": ("trade", lp(HeavyHitter(scan="double"), 3)),
    "mg_lp_shared_sketch": ("trade", lp(HeavyHitter(consolidation="shared"), 3)),
    "mg_lp_subtract": ("trade", lp(HeavyHitter(merge="subtract"), 3)),
    "mg_lp_arrow": ("trade", lp(HeavyHitter(engine="arrow"), 3)),
    "vote_lp_1": ("copurchase", lp(MajorityVote(), 1)),
    "vote_lp_3": ("copurchase", lp(MajorityVote(), 3)),
    "vote_lp_8": ("weblink", lp(MajorityVote(), 8)),
    "vote_lp_residual": ("trade", lp(MajorityVote(rule="residual"), 3)),
    "vote_lp_merge": ("trade", lp(MajorityVote(combine="merge"), 3)),
    "vote_lp_arrow": ("trade", lp(MajorityVote(engine="arrow"), 3)),
    "pickless_none": ("weblink", lp(HeavyHitter(), 5, OFF)),
    "pickless_1": ("weblink", lp(HeavyHitter(), 5, PickLess(1))),
    "pickless_2": ("weblink", lp(HeavyHitter(), 5, PickLess(2))),
    "pickless_4": ("weblink", lp(HeavyHitter(), 6, PickLess(4))),
    "pickless_16": ("weblink", lp(HeavyHitter(), 6, PickLess(16))),
    "pickless_first": ("weblink", lp(HeavyHitter(), 6, PickLess(first_only=True))),
    "baseline_a": ("weblink", lp(Exact(), 2, OFF, 1e-5, 8)),
    "baseline_b": ("shared_line", lp(Exact(), 2, OFF, 0.0, 8)),
    "baseline_c": ("weblink", lp(Exact(), 8, PickLess(4))),
}


def spread_pairs(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Scan positions of a graph with labels id modulo SPREAD."""
    prepared = graph.scan_positions(BUILDERS[name](spark, sf_dir))
    return prepared.select("dst", "chunk", "ord", F.pmod("src", F.lit(SPREAD)).alias("label"), "weight")


def slots_of(selector: HeavyHitter, name: str, whole: bool, spark: SparkSession, sf_dir: str) -> DataFrame:
    pairs = spread_pairs(spark, sf_dir, name)
    rows = selector.sketch(pairs).withColumn("chunk", F.lit(0)) if whole else selector.partial(pairs)
    return rows.select("dst", F.col("chunk").cast("long").alias("chunk"), F.explode("slots").alias("s")).select("dst", "chunk", "s.label", "s.weight")


def vote_state(spark: SparkSession, sf_dir: str) -> DataFrame:
    return MajorityVote().partial(spread_pairs(spark, sf_dir, "trade")).select("dst", F.col("chunk").cast("long").alias("chunk"), "label", "weight")


def picked(selector, name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    return selector.candidates(spread_pairs(spark, sf_dir, name)).select("id", F.col("candidate").alias("label"))


def stats(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    return graph.graph_stats(BUILDERS[name](spark, sf_dir))


def quality(run: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    name, config = LP_RUNS[run]
    edges = edges_of(spark, sf_dir, name)
    return metrics.modularity(edges, label_propagation(edges, config).labels).select(F.round("q", 6).alias("q"), "communities")


def of_run(run: str, spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    name, config = LP_RUNS[run]
    edges = edges_of(spark, sf_dir, name)
    return edges, label_propagation(edges, config).labels


def community_sizes(spark, sf_dir):
    return metrics.community_sizes(of_run("mg_lp_8", spark, sf_dir)[1])


def top_communities(spark, sf_dir):
    return communities.top_communities(of_run("mg_lp_8", spark, sf_dir)[1], 10)


def boundary_edges(spark, sf_dir):
    return graph.boundary_edges(*of_run("mg_lp_8", spark, sf_dir)).select("src", "dst", "weight")


def contract_graph(spark, sf_dir):
    return graph.contract(*of_run("mg_lp_8", spark, sf_dir))


def delta_modularity(spark, sf_dir):
    edges, labels = of_run("mg_lp_8", spark, sf_dir)
    moves = graph.drop_self_loops(edges).join(labels.select(F.col("id").alias("src"), F.col("label").alias("target")), "src").select(F.col("dst").alias("id"), "target").distinct()
    return metrics.delta_modularity(edges, labels, moves).select("id", "target", F.round(F.col("dq") * 1e6, 3).alias("dq_millionths"))


def community_profile_nation(spark, sf_dir):
    labels = of_run("exact_lp_supply", spark, sf_dir)[1]
    nation = table(spark, sf_dir, "supplier").join(F.broadcast(table(spark, sf_dir, "nation")), F.col("s_nationkey") == F.col("n_nationkey"))
    return communities.profile(labels, nation.select((2 * F.col("s_suppkey")).alias("id"), "n_name"), "n_name")


def nmi_lang(spark, sf_dir):
    labels = of_run("exact_lp_shared_line", spark, sf_dir)[1]
    truth = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), F.col("lang").alias("truth")).filter("truth is not null")
    return metrics.nmi(labels, truth).select(F.round("nmi", 6).alias("nmi"))


def working_set_memory(spark, sf_dir):
    return metrics.working_set_bytes(stats("copurchase", spark, sf_dir))


def selection_agreement(spark, sf_dir):
    return metrics.selection_agreement(spread_pairs(spark, sf_dir, "trade"))


def sketch_guarantee(spark, sf_dir):
    return metrics.sketch_guarantee_violations(spread_pairs(spark, sf_dir, "trade"))


def shuffle_model(spark, sf_dir):
    return metrics.shuffle_model(spread_pairs(spark, sf_dir, "copurchase"))


def neighbor_label_weights(spark, sf_dir):
    return linking_weights(spread_pairs(spark, sf_dir, "trade"))


def vertex_map_layout(spark, sf_dir):
    edges = BUILDERS["trade"](spark, sf_dir)
    return metrics.vertex_map_layout(edges).join(metrics.map_offsets(edges), "id")


def pickless_step(spark, sf_dir):
    edges = edges_of(spark, sf_dir, "copurchase")
    return step(graph.scan_positions(edges), initial_labels(edges), HeavyHitter(), True).select("id", "label", "moved", "refused")


def label_delta(spark, sf_dir):
    edges = edges_of(spark, sf_dir, "weblink")
    a, b = (label_propagation(edges, lp(HeavyHitter(), n)).labels for n in (2, 3))
    return communities.compare(a, b)


def swap_count(spark, sf_dir):
    edges = edges_of(spark, sf_dir, "weblink")
    config = LPConfig(**{**lp(Exact(), 3, OFF).__dict__, "keep_history_labels": True})
    s = label_propagation(edges, config).snapshots
    return metrics.swap_count(s[0], s[2], s[1])


def mg_slot_sweep(spark, sf_dir):
    edges = edges_of(spark, sf_dir, "trade")
    out = None
    for k in (2, 4, 8, 16, 32):
        row = metrics.modularity(edges, label_propagation(edges, lp(HeavyHitter(k=k), 3)).labels).select(F.lit(k).alias("k"), F.round("q", 6).alias("q"), "communities")
        out = row if out is None else out.unionByName(row)
    return out


def mg_frequent_items(spark, sf_dir):
    return communities.mg_frequent(table(spark, sf_dir, "events").select("user_id", "event_id"), "user_id", "event_id", 50)


def majority_item(spark, sf_dir):
    return communities.majority_item(table(spark, sf_dir, "lineitem").select(F.when(F.col("l_linestatus") == "F", 1).otherwise(0).alias("late"), (F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("at")), "late", "at")


def heavy_hitters_udtf(spark, sf_dir):
    S.register(spark)
    pairs = spread_pairs(spark, sf_dir, "trade").select("dst", "label", "weight", "ord")
    pairs.createOrReplaceTempView("labelsketch_pairs")
    return spark.sql("SELECT key AS dst, label, weight FROM heavy_hitters(TABLE(SELECT dst, label, weight, ord FROM labelsketch_pairs) PARTITION BY dst ORDER BY (ord), 8)")


def method_recommendation(spark, sf_dir):
    out = None
    for name in ("weblink", "copurchase", "order_path", "turn_path"):
        row = communities.recommend(stats(name, spark, sf_dir)).select(F.lit(name).alias("graph"), "d_avg", "method")
        out = row if out is None else out.unionByName(row)
    return out


def louvain_one_pass(spark, sf_dir):
    return baselines.louvain_pass(edges_of(spark, sf_dir, "weblink"), 1)


def louvain_levels(spark, sf_dir):
    edges = edges_of(spark, sf_dir, "weblink")
    return metrics.modularity(edges, baselines.louvain(edges)).select(F.round("q", 6).alias("q"), "communities")


def labelrank(spark, sf_dir):
    return baselines.labelrank(edges_of(spark, sf_dir, "turn_path"))


def copra(spark, sf_dir):
    return baselines.copra(edges_of(spark, sf_dir, "weblink")).select("id", "label", F.round("share", 6).alias("share"))


def slpa(spark, sf_dir):
    return baselines.slpa(edges_of(spark, sf_dir, "weblink")).select("id", "label", F.round("share", 6).alias("share"))


def toy_two_triangles(spark, sf_dir):
    """The default loop on two triangles with a bridge, laid over every six successive parts."""
    return label_propagation(written(toy_on_parts(spark, sf_dir), "two_triangles"), LPConfig(HeavyHitter())).labels


def converged(selector, spark, sf_dir):
    """The default loop to its own end on the web graph."""
    return label_propagation(edges_of(spark, sf_dir, "weblink"), LPConfig(selector)).labels


def baseline_converged(baseline, spark, sf_dir):
    """A baseline with its own tolerance and limit on the web graph."""
    return baseline(edges_of(spark, sf_dir, "weblink")).labels


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found: dict[str, Callable] = {f"graph_{name}_edges": build for name, build in BUILDERS.items()}
    found |= {run: partial(run_lp, *spec) for run, spec in LP_RUNS.items()}
    found |= {
        "graph_stats": partial(stats, "copurchase"),
        "graph_stats_trade": partial(stats, "trade"),
        "degree_histogram": lambda s, d: graph.degree_histogram(BUILDERS["trade"](s, d)),
        "degree_split": lambda s, d: graph.split_by_degree(BUILDERS["trade"](s, d))[1],
        "weighted_degrees": lambda s, d: graph.weighted_degrees(BUILDERS["trade"](s, d)),
        "mg_partial_k8": partial(slots_of, HeavyHitter(), "trade", False),
        "mg_sketch_k8": partial(slots_of, HeavyHitter(consolidation="shared"), "trade", False),
        "mg_sketch_k2_floor": partial(slots_of, HeavyHitter(k=2, overflow="floor", consolidation="shared"), "supply", False),
        "mg_sketch_as_described": partial(slots_of, HeavyHitter(overflow="as_described", consolidation="shared"), "trade", False),
        "mg_merge_replay": partial(slots_of, HeavyHitter(), "trade", True),
        "mg_merge_subtract": partial(slots_of, HeavyHitter(merge="subtract"), "trade", True),
        "mg_sketch_arrow": partial(slots_of, HeavyHitter(engine="arrow"), "trade", True),
        "vote_combine_max": partial(picked, MajorityVote(), "trade"),
        "mg_pick_double": partial(picked, HeavyHitter(scan="double"), "trade"),
        "exact_pick": partial(picked, Exact(), "trade"),
        "modularity_exact": partial(quality, "exact_lp_8"),
        "modularity_mg": partial(quality, "mg_lp_8"),
        "modularity_vote": partial(quality, "vote_lp_8"),
        "modularity_baseline_c": partial(quality, "baseline_c"),
        "mg_lp_converged": partial(converged, HeavyHitter()),
        "exact_lp_converged": partial(converged, Exact()),
        "vote_lp_converged": partial(converged, MajorityVote()),
        "baseline_a_converged": partial(baseline_converged, baselines.baseline_parallel_lp),
        "baseline_b_converged": partial(baseline_converged, baselines.baseline_thread_map_lp),
        "baseline_c_converged": partial(baseline_converged, baselines.baseline_vertex_map_lp),
    }
    plain = (vote_state, community_sizes, top_communities, boundary_edges, contract_graph, delta_modularity, community_profile_nation, nmi_lang, working_set_memory, selection_agreement, sketch_guarantee, shuffle_model, neighbor_label_weights, vertex_map_layout, pickless_step, label_delta, swap_count, mg_slot_sweep, mg_frequent_items, majority_item, heavy_hitters_udtf, method_recommendation, louvain_one_pass, louvain_levels, labelrank, copra, slpa, toy_two_triangles)
    return found | {f.__name__: f for f in plain}
