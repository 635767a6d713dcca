"""The fold where the edges lie: labels travel to the neighbour lists, and only sketches of hubs' chunks are shuffled.

Used while labels fit a broadcast of checked size (``plans.planner``). Neighbour lists are built and written once, in scan
order, as indices into the sorted ids; low-degree vertices, hubs and great hubs have tables, and paths, of their own. In an
iteration each task reads its lists with the broadcast labels: a low-degree vertex is decided there, a hub's chunks are
folded apart and merged there, a great hub's chunk yields its sums, sketch or vote, which meet in one small shuffle. Only the
vertices that want another label come back to the driver. A list holds ``LOCAL_ROWS`` neighbours, and a great hub's chunk
``graph.CHUNK_ROWS``, at most, so memory is a batch of lists and the labels.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import sketch as S
from ..store import drop, written
from .graph import CHUNK_ROWS
from .selectors import Exact, HeavyHitter, MajorityVote, heaviest, merged

#: Lists, and pairs about, that one pass of numpy takes.
PART, PAIRS = 4096, 1 << 20
#: Neighbours up to which a hub's chunks are merged in the task that has its list.
LOCAL_ROWS = 65536
#: Lists below which a step of numpy over all of them costs more than plain Python.
FEW = 64


def supported(selector) -> bool:
    """A second scan, and one sketch shared by all neighbours of a hub, need plans of their own."""
    return not isinstance(selector, HeavyHitter) or (selector.scan == "single" and selector.consolidation == "partial" and selector.engine == "expr")


def mix(ids, batches: int):
    """The class of ids in a batched schedule; integers, arrays and, with ``mix_sql``, expressions agree."""
    return ids % 2147483648 * 2654435761 % 4294967296 // 65536 % batches


def mix_sql(column: str, batches: int) -> str:
    return f"cast(floor({column} % 2147483648 * 2654435761 % 4294967296 / 65536) as bigint) % {batches}"


@dataclass
class Lists:
    ids: np.ndarray
    rows: DataFrame
    chunks: int

    def __post_init__(self) -> None:
        self.low, self.hubs, self.great = (self.rows.filter(F.col("kind") == k).drop("kind") for k in ("low", "hub", "great"))
        self.great_any = not self.great.isEmpty()

    def drop(self) -> None:
        drop(self.rows)


def neighbour_lists(prepared: DataFrame, ids: np.ndarray, chunks: int) -> Lists:
    """at, chunk (-1: all of a vertex), near, weights: indices of a vertex and of its neighbours, in scan order."""
    held = prepared.sparkSession.sparkContext.broadcast(ids)
    part = F.when(F.col("degree") <= LOCAL_ROWS, F.lit(-1)).otherwise(F.col("chunk")).alias("part")
    rows = prepared.groupBy("dst", part, "hub").agg(F.array_sort(F.collect_list(F.struct("ord", "src", "weight"))).alias("p"))
    kind = F.when(F.col("part") >= 0, "great").when(F.col("hub"), "hub").otherwise("low").alias("kind")
    rows = rows.select("dst", F.col("part").alias("chunk"), kind, F.col("p.src").alias("near"), F.col("p.weight").alias("weights"))

    def index(batches):
        for batch in batches:
            near = batch.column("near")
            place = pa.array(np.searchsorted(held.value, near.flatten().to_numpy()).astype(np.int32))
            offsets = pa.array(near.offsets.to_numpy() - near.offsets[0].as_py(), pa.int32())
            at = pa.array(np.searchsorted(held.value, batch.column("dst").to_numpy()).astype(np.int32))
            yield pa.RecordBatch.from_arrays([at, batch.column("chunk"), batch.column("kind"), pa.ListArray.from_arrays(offsets, place), batch.column("weights")], ["at", "chunk", "kind", "near", "weights"])

    return Lists(ids, written(rows.mapInArrow(index, "at int, chunk int, kind string, near array<int>, weights array<double>"), "lists", "kind"), chunks)


def sums_of(owner: np.ndarray, labels: np.ndarray, weights: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(owner, label, weight) of every label around every owner, by owner, then label."""
    order = np.lexsort((labels, owner))
    owner, labels, weights = owner[order], labels[order], weights[order]
    first = np.r_[True, (owner[1:] != owner[:-1]) | (labels[1:] != labels[:-1])] if len(owner) else np.zeros(0, bool)
    starts = np.nonzero(first)[0]
    return owner[starts], labels[starts], np.add.reduceat(weights, starts) if len(starts) else weights


def tops(owner: np.ndarray, labels: np.ndarray, weights: np.ndarray, n: int) -> np.ndarray:
    """The heaviest label of each owner below n, the smaller one on a tie; -1 where there is none above 0."""
    order = np.lexsort((-labels, weights, owner))
    best = np.full(n, -1, np.int64)
    above = order[weights[order] > 0]
    best[owner[above]] = labels[above]  # the last of an owner counts
    return best


def slots_of(selector: HeavyHitter, label: np.ndarray, weight: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(owner, label, weight) of the slots of every list, in the order of their filling."""
    if selector.overflow == "residual" and (not len(weight) or weight.min() > 0):
        return folded(label, weight, bounds, selector.k)
    found = []
    for r in range(len(bounds) - 1):
        sketch = S.Sketch(selector.k, selector.overflow)
        sketch.fold(label[bounds[r] : bounds[r + 1]].tolist(), weight[bounds[r] : bounds[r + 1]].tolist())
        found += [(r, a, b) for a, b in sketch.slots.items()]
    return tuple(np.array([t[i] for t in found], kind) for i, kind in enumerate((np.int64, np.int64, np.float64)))


def folded(label: np.ndarray, weight: np.ndarray, bounds: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The fold by the default rule of positive weights, of all lists side by side: the first pair of each, the second, and so on.

    Lists go from the longest to the shortest, so those not yet at their end are a prefix. Once fewer than ``FEW`` are left,
    plain Python takes over from their slots.
    """
    size = np.diff(bounds)
    order = np.argsort(-size, kind="stable")
    size, start = size[order], bounds[:-1][order]
    left = np.searchsorted(-size, -np.arange(size[0] if len(size) else 0), side="left")  # lists longer than p
    labels, weights, since = np.zeros((k, len(size)), np.int64), np.zeros((k, len(size))), np.zeros((k, len(size)), np.int32)
    tail = int(np.searchsorted(-left, -FEW, side="right"))  # lists are fewer from here on
    for p in range(tail):
        n = left[p]
        x, w, held = label[start[:n] + p], weight[start[:n] + p], weights[:, :n]
        same = (labels[:, :n] == x) & (held > 0)
        held += same * w
        w[same.any(0)] = 0
        by = np.minimum(w, held.min(0))  # 0 where a slot is free
        held -= by
        w -= by
        row = np.nonzero(w > 0)[0]  # there the least slot is free
        at = held[:, row].argmin(0)
        labels[at, row], weights[at, row], since[at, row] = x[row], w[row], p
    at, row = np.nonzero(weights > 0)
    by_filling = np.lexsort((since[at, row], row))
    row, at = row[by_filling], at[by_filling]
    o, x, w = row, labels[at, row], weights[at, row]
    if tail < len(left):
        rest, more = int(left[tail]), []
        ends = np.searchsorted(o, np.arange(rest + 1))
        for r in range(rest):
            sketch = S.Sketch(k, "residual", zip(x[ends[r] : ends[r + 1]].tolist(), w[ends[r] : ends[r + 1]].tolist(), strict=True))
            span = slice(start[r] + tail, start[r] + size[r])
            sketch.fold(label[span].tolist(), weight[span].tolist())
            more += [(r, a, b) for a, b in sketch.slots.items()]
        mo, mx, mw = (np.array([t[i] for t in more], kind) for i, kind in enumerate((np.int64, np.int64, np.float64)))
        o, x, w = np.r_[mo, o[ends[rest] :]], np.r_[mx, x[ends[rest] :]], np.r_[mw, w[ends[rest] :]]
    owner = order[o]
    by_owner = np.argsort(owner, kind="stable")
    return owner[by_owner], x[by_owner], w[by_owner]


def votes_of(selector: MajorityVote, label: np.ndarray, weight: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(owner, label, weight) of the candidate of every list; lists side by side, as in ``folded``."""
    size, replace = np.diff(bounds), selector.rule == "replace"
    order = np.argsort(-size, kind="stable")
    size, start = size[order], bounds[:-1][order]
    left = np.searchsorted(-size, -np.arange(size[0] if len(size) else 0), side="left")
    at, held = np.zeros(len(size), np.int64), np.zeros(len(size))
    tail = int(np.searchsorted(-left, -FEW, side="right"))
    for p in range(tail):
        n = left[p]
        x, w = label[start[:n] + p], weight[start[:n] + p]
        now = held[:n]
        same, less = (at[:n] == x) & (now > 0), now > w
        takes = ~same & ~less
        held[:n] = np.where(same, now + w, np.where(less, now - w, w if replace else w - now))
        at[:n][takes] = x[takes]
    for r in range(int(left[tail]) if tail < len(left) else 0):
        vote = S.Vote(selector.rule)
        vote.label, vote.weight = int(at[r]), float(held[r])
        for x, w in zip(label[start[r] + tail : start[r] + size[r]].tolist(), weight[start[r] + tail : start[r] + size[r]].tolist(), strict=True):
            vote.add(x, w)
        at[r], held[r] = vote.label, vote.weight
    owner = np.argsort(order, kind="stable")
    some = held[owner] > 0
    return np.nonzero(some)[0], at[owner][some], held[owner][some]


def states(selector, label: np.ndarray, weight: np.ndarray, bounds: np.ndarray, owner: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(owner, label, weight): sums, slots or votes of the lists."""
    if isinstance(selector, Exact):
        return sums_of(owner, label, weight)
    if isinstance(selector, HeavyHitter):
        return slots_of(selector, label, weight, bounds)
    return votes_of(selector, label, weight, bounds)


def merged_states(selector, state: tuple, owner_of: np.ndarray, n: int) -> np.ndarray:
    """Best label of each of n hubs from the states of its chunks, which come in the order of chunks; -1 for none."""
    o, x, w = owner_of[state[0]], state[1], state[2]
    if isinstance(selector, HeavyHitter) and selector.merge == "replay":
        return tops(*slots_of(selector, x, w, np.searchsorted(o, np.arange(n + 1))), n)
    if isinstance(selector, MajorityVote) and selector.combine == "max":
        return tops(o, x, w, n)
    o, x, w = sums_of(o, x, w)
    if isinstance(selector, MajorityVote):  # equal candidates add up, others cancel
        keep = 2 * w - np.bincount(o, w, n)[o] >= 0
        return tops(o[keep], x[keep], w[keep], n)
    if isinstance(selector, HeavyHitter):  # less the (k + 1)-th largest
        order = np.lexsort((x, -w, o))
        rank = np.arange(len(o)) - np.searchsorted(o[order], o[order])
        cut = np.zeros(n)
        cut[o[order][rank == selector.k]] = w[order][rank == selector.k]
        w = w - cut[o]
    return tops(o, x, w, n)


def best_of_hubs(selector, chunks: int, label: np.ndarray, weight: np.ndarray, bounds: np.ndarray, owner: np.ndarray) -> np.ndarray:
    """Best label of each list: its pairs are dealt into chunks by position, folded apart and merged."""
    n = len(bounds) - 1
    if isinstance(selector, Exact):
        return tops(*sums_of(owner, label, weight), n)
    size = np.diff(bounds)
    each = np.maximum(chunks, -(-size // CHUNK_ROWS))
    base = np.cumsum(each) - each
    place = np.arange(len(owner)) - bounds[owner]
    chunk = base[owner] + place % each[owner]
    order = np.argsort(chunk, kind="stable")
    ends = np.r_[0, np.cumsum(np.bincount(chunk, minlength=int(each.sum())))]
    return merged_states(selector, states(selector, label[order], weight[order], ends, chunk[order]), np.repeat(np.arange(n), each), n)


def parts(batch: pa.RecordBatch, labels: np.ndarray):
    """(at, chunk, labels of the neighbours, weights, bounds, owner) of runs of lists."""
    sizes = np.diff(batch.column("near").offsets.to_numpy())
    step = max(1, min(PART, int(PAIRS / max(1.0, sizes.mean() if len(sizes) else 1.0))))
    for start in range(0, batch.num_rows, step):
        some = batch.slice(start, step)
        near = some.column("near")
        bounds = (near.offsets.to_numpy() - near.offsets[0].as_py()).astype(np.int64)
        yield some.column("at").to_numpy(), some.column("chunk").to_numpy(), labels[near.flatten().to_numpy()], some.column("weights").flatten().to_numpy(), bounds, np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))


def wishes(lists: Lists, selector, labels: np.ndarray, active: np.ndarray | None, batches: int = 1, j: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """(indices, labels) of the vertices that would rather have another label.

    ``active`` marks the vertices whose low-degree lists are looked at; hubs are always.
    """
    spark = lists.low.sparkSession
    held = spark.sparkContext.broadcast((labels, active))

    def mine(batch: pa.RecordBatch, active: np.ndarray | None) -> pa.RecordBatch:
        at = batch.column("at").to_numpy()
        some = np.ones(len(at), bool) if active is None else active[at]
        if batches > 1:
            some = some & (mix(ids.value[at], batches) == j)
        return batch if some.all() else batch.filter(pa.array(some))

    ids = spark.sparkContext.broadcast(lists.ids) if batches > 1 else None

    chunks = lists.chunks

    def decide(rows, hubs: bool):
        now, live = held.value
        for batch in rows:
            for at, _, label, weight, bounds, owner in parts(mine(batch, None if hubs else live), now):
                best = best_of_hubs(selector, chunks, label, weight, bounds, owner) if hubs else tops(*states(selector, label, weight, bounds, owner), len(at))
                differs = (best >= 0) & (best != now[at])
                yield pa.RecordBatch.from_arrays([pa.array(at[differs].astype(np.int64)), pa.array(best[differs])], ["id", "candidate"])

    def partial(rows):
        now, _ = held.value
        for batch in rows:
            for at, chunk, label, weight, bounds, owner in parts(mine(batch, None), now):
                o, x, w = states(selector, label, weight, bounds, owner)
                slot = np.arange(len(o), dtype=np.int32)
                yield pa.RecordBatch.from_arrays([pa.array(at[o].astype(np.int64)), pa.array(chunk[o]), pa.array(slot), pa.array(x), pa.array(w)], ["dst", "chunk", "slot", "label", "weight"])

    low = lists.low.mapInArrow(lambda rows: decide(rows, False), "id long, candidate long")
    low = low.unionByName(lists.hubs.mapInArrow(lambda rows: decide(rows, True), "id long, candidate long"))
    state = lists.great.mapInArrow(partial, "dst long, chunk int, slot int, label long, weight double")
    if isinstance(selector, HeavyHitter):
        slots = F.transform(F.array_sort(F.collect_list(F.struct("slot", "label", "weight"))), lambda e: F.struct(e["label"].alias("label"), e["weight"].alias("weight")))
        high = merged(state.groupBy("dst", "chunk").agg(slots.alias("slots")), selector).select(F.col("dst").alias("id"), S.of_column(S.mg_top, "slots").alias("candidate")).filter("candidate is not null")
    elif isinstance(selector, MajorityVote):
        high = selector.combined(state)
    else:
        high = heaviest(state.groupBy("dst", "label").agg(F.sum("weight").alias("weight")))
    found = (low.unionByName(high) if lists.great_any else low).toArrow()
    at, best = found.column("id").to_numpy(), found.column("candidate").to_numpy()
    differs = best != labels[at]
    held.unpersist()
    return at[differs], best[differs]


def touched(lists: Lists, moved: np.ndarray) -> np.ndarray:
    """Marks of the vertices that have a moved neighbour; low-degree lists alone matter, hubs are always looked at."""
    held = lists.low.sparkSession.sparkContext.broadcast(moved)

    def run(rows):
        for batch in rows:
            near = batch.column("near")
            hit = held.value[near.flatten().to_numpy()]
            bounds = near.offsets.to_numpy() - near.offsets[0].as_py()
            some = np.add.reduceat(hit, bounds[:-1]) > 0 if len(hit) else np.zeros(0, bool)
            yield pa.RecordBatch.from_arrays([pa.array(batch.column("at").to_numpy()[some])], ["at"])

    marks = np.zeros(len(moved), bool)
    marks[lists.low.select("at", "near").mapInArrow(run, "at int").toArrow().column("at").to_numpy()] = True
    return marks
