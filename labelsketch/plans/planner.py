"""Which physical strategy a run takes, from a graph's totals."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from ..operators.graph import CHUNK_ROWS
from ..operators.propagate import LPConfig, delivery
from ..operators.selectors import Exact, HeavyHitter, MajorityVote


@dataclass(frozen=True)
class Strategy:
    labels: str  # broadcast to the neighbour lists, or joined by a shuffle; what label_propagation does
    chunk_rows: int  # neighbours that a fold takes at once, at most
    state_rows: int  # rows of sums, slots or votes that cross the shuffle in a full iteration, at most


def choose(config: LPConfig, stats: DataFrame) -> Strategy:
    """stats: one row of graph_stats."""
    s = stats.first()
    n, m, top = int(s["n"]), int(s["m_edges"]), int(s["max_degree"])
    labels = delivery(config, n)
    per_chunk = m if isinstance(config.selector, Exact) else 1 if isinstance(config.selector, MajorityVote) else config.selector.k
    hubs = min(n, m // config.hub_degree) if top >= config.hub_degree else 0
    chunks = hubs * config.hub_chunks + m // CHUNK_ROWS if hubs else 0
    if labels == "shuffle":
        chunks += n
    return Strategy(labels, min(top, max(config.hub_degree, CHUNK_ROWS)), min(m, chunks * per_chunk))


def explain(config: LPConfig, stats: DataFrame) -> str:
    found = choose(config, stats)
    kind = {Exact: "exact", HeavyHitter: "heavy hitters", MajorityVote: "majority vote"}[type(config.selector)]
    return f"{kind}: labels by {found.labels}, folds of at most {found.chunk_rows} neighbours, at most {found.state_rows} state rows shuffled an iteration"
