"""The loop: every vertex takes the label its selector picks, until few change."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..store import drop, written
from . import local
from .graph import HUB_CHUNKS, HUB_DEGREE, scan_positions
from .selectors import Exact, HeavyHitter, MajorityVote

#: Bytes of labels (8 for an id, 8 for a label) up to which they are broadcast and the fold goes to the edges.
BROADCAST_BYTES = 64 << 20
#: Share of the vertices up to which only edges into active ones are read; beyond it a full scan is cheaper.
FRONTIER_SHARE = 0.3


@dataclass(frozen=True)
class PickLess:
    """Symmetry breaker: in iterations t = 0, period, 2 period, ... a vertex may only move to a smaller label."""

    period: int | None = 8
    first_only: bool = False

    def applies(self, t: int) -> bool:
        return t == 0 if self.first_only else bool(self.period) and t % self.period == 0

    @property
    def always(self) -> bool:
        return self.period == 1 and not self.first_only


@dataclass(frozen=True)
class Stop:
    tolerance: float = 0.05
    max_iterations: int = 20


@dataclass(frozen=True)
class Schedule:
    """Simultaneous updates, or ``batches`` classes of the vertices (by a mix of the id's bits) one after another in every iteration."""

    batches: int = 1


@dataclass(frozen=True)
class LPConfig:
    selector: Exact | HeavyHitter | MajorityVote = field(default_factory=HeavyHitter.headline)
    pick_less: PickLess = PickLess()
    stop: Stop = Stop()
    schedule: Schedule = Schedule()
    frontier: bool = True
    hub_degree: int = HUB_DEGREE
    hub_chunks: int = HUB_CHUNKS
    keep_history_labels: bool = False
    #: Labels by ``broadcast`` or ``shuffle``; ``auto`` goes by the number of vertices.
    delivery: str = "auto"


@dataclass
class LPResult:
    labels: DataFrame
    history: list[dict]
    snapshots: list[DataFrame]


def initial_labels(edges: DataFrame) -> DataFrame:
    """Every vertex is its own label."""
    return edges.select(F.col("dst").alias("id")).distinct().select("id", F.col("id").alias("label"))


def label_pairs(prepared: DataFrame, labels: DataFrame) -> DataFrame:
    """dst, chunk, ord, label, weight: each neighbour's label, in scan positions."""
    return prepared.join(labels.select(F.col("id").alias("src"), "label"), "src").select("dst", "chunk", "ord", "label", "weight")


def allowed(candidate: Column, current: Column, pick_less: bool) -> Column:
    """May the vertex move? The iteration's rule is a literal, so the branch folds away."""
    return (candidate < current) if pick_less else (candidate != current)


def step(prepared: DataFrame, labels: DataFrame, selector, pick_less: bool) -> DataFrame:
    """id, label (new), moved, refused (by pick-less) of all vertices in labels."""
    found = selector.candidates(label_pairs(prepared, labels))
    joined = labels.join(found, "id", "left")
    may = F.coalesce(allowed(F.col("candidate"), F.col("label"), pick_less), F.lit(False))
    differs = F.coalesce(F.col("candidate") != F.col("label"), F.lit(False))
    return joined.select("id", F.when(may, F.col("candidate")).otherwise(F.col("label")).alias("label"), may.alias("moved"), (differs & ~may).alias("refused"))


def delivery(config: LPConfig, n: int) -> str:
    """How labels reach the edges: by a broadcast of checked size, else by a shuffle."""
    if config.delivery != "auto":
        return config.delivery
    return "broadcast" if 16 * n <= BROADCAST_BYTES and local.supported(config.selector) else "shuffle"


def label_propagation(edges: DataFrame, config: LPConfig = LPConfig(), prepared: DataFrame | None = None) -> LPResult:
    """Labels of all vertices, and per iteration whether pick-less applied, active and changed vertices, seconds."""
    labels = written(initial_labels(edges), "labels")
    n = labels.count()
    if delivery(config, n) == "broadcast":
        found = folded(scan_positions(edges, config.hub_degree, config.hub_chunks) if prepared is None else prepared, labels, config)
        drop(labels)
        return found
    if prepared is not None:
        return shuffled(prepared, labels, n, config)
    own = written(scan_positions(edges, config.hub_degree, config.hub_chunks), "prepared")
    found = shuffled(own, labels, n, config)
    drop(own)
    return found


def folded(prepared: DataFrame, labels: DataFrame, config: LPConfig) -> LPResult:
    """The loop with broadcast labels; they are at most ``BROADCAST_BYTES``. ``prepared`` is read once."""
    spark = prepared.sparkSession
    ids = np.sort(labels.select("id").toArrow().column("id").to_numpy())
    lists = local.neighbour_lists(prepared, ids, config.hub_chunks)
    now, b = ids.copy(), config.schedule.batches

    def table() -> DataFrame:
        return written(spark.createDataFrame(pa.table({"id": ids, "label": now})), "labels")

    history, snapshots, active = [], [], None
    for t in range(config.stop.max_iterations):
        began, less = time.time(), config.pick_less.applies(t)
        moved, refused = np.zeros(len(ids), bool), np.zeros(len(ids), bool)
        for j in range(b):
            at, best = local.wishes(lists, config.selector, now, active, b, j)
            may = best < now[at] if less else np.ones(len(at), bool)
            refused[at[~may]] = True
            moved[at[may]] = True
            now = now.copy()
            now[at[may]] = best[may]
        changed = int(moved.sum())
        history.append({"iteration": t, "pick_less": less, "active": len(ids) if active is None else int(active.sum()), "changed": changed, "seconds": time.time() - began})
        if config.keep_history_labels:
            snapshots.append(table())
        if (not less or config.pick_less.always) and changed <= config.stop.tolerance * len(ids) or not (moved | refused).any():
            break
        active = None
        if config.frontier and changed <= FRONTIER_SHARE * len(ids):
            active = local.touched(lists, moved) | refused
    lists.drop()
    return LPResult(table(), history, snapshots)


def shuffled(prepared: DataFrame, labels: DataFrame, n: int, config: LPConfig) -> LPResult:
    """The loop for labels of any size: they are joined to the edges in every iteration."""
    history, snapshots, frontier, active = [], [], None, n
    b = config.schedule.batches
    for t in range(config.stop.max_iterations):
        began, less, changed = time.time(), config.pick_less.applies(t), 0
        steps = []
        for j in range(b):
            rows = prepared
            if frontier is not None:
                rows = rows.join(frontier.select(F.col("id").alias("dst")), "dst", "left_semi")
            if b > 1:
                rows = rows.filter(f"{local.mix_sql('dst', b)} = {j}")
            after = written(step(rows, labels, config.selector, less), "step")
            changed += after.filter("moved").count()
            labels = after.select("id", "label")
            steps.append(after)
        history.append({"iteration": t, "pick_less": less, "active": active, "changed": changed, "seconds": time.time() - began})
        if config.keep_history_labels:
            snapshots.append(written(labels, "snapshot"))
        if (not less or config.pick_less.always) and changed <= config.stop.tolerance * n:
            break
        if config.frontier:
            moved = refused = None
            for after in steps:
                m, r = after.filter("moved").select("id"), after.filter("refused").select("id")
                moved, refused = (m, r) if moved is None else (moved.unionByName(m), refused.unionByName(r))
            next_frontier = prepared.join(moved.distinct().select(F.col("id").alias("src")), "src", "left_semi").select(F.col("dst").alias("id")).unionByName(refused).distinct()
            drop(frontier)
            next_frontier = written(next_frontier, "frontier")
            active = next_frontier.count()
            frontier = next_frontier if active <= FRONTIER_SHARE * n else None
            if active == 0:
                break
        drop(*steps[:-1])
        labels = written(labels, "labels")
        drop(steps[-1])
    return LPResult(labels, history, snapshots)


def sweep_slots(edges: DataFrame, ks: list[int], config: LPConfig = LPConfig()) -> list[dict]:
    """One row per number of slots: k, seconds, modularity, communities."""
    from .metrics import modularity

    out = []
    prepared = written(scan_positions(edges, config.hub_degree, config.hub_chunks), "prepared")
    for k in ks:
        began = time.time()
        found = label_propagation(edges, LPConfig(**{**config.__dict__, "selector": HeavyHitter(k=k)}), prepared)
        seconds = time.time() - began
        row = modularity(edges, found.labels).first()
        out.append({"k": k, "seconds": seconds, "modularity": row["q"], "communities": row["communities"]})
    return out


def tune(space: dict[str, list], objective, rounds: int = 2) -> tuple[dict, float]:
    """Cyclic coordinate descent: one parameter at a time, the others held, until a round brings nothing."""
    best = {name: values[0] for name, values in space.items()}
    cost = objective(best)
    for _ in range(rounds):
        before = cost
        for name, values in space.items():
            for value in values:
                if value != best[name] and (c := objective(best | {name: value})) < cost:
                    best, cost = best | {name: value}, c
        if cost == before:
            break
    return best, cost
