"""Weighted heavy-hitter sketches and majority votes as Catalyst expressions and as Arrow folds.

A sketch is an array of at most k (label, weight) slots, empty ones left out. Rules for a pair that finds no slot:
``residual`` takes the smaller of its weight and the least slot off all slots and files what is left of it; ``floor`` takes
its weight off all slots, none below 0; ``as_described`` takes its weight off all slots, which may go below 0, and
only a slot at exactly 0 is free again. With unit weights the three agree in one scan.
"""

from __future__ import annotations

import functools
from collections.abc import Callable, Iterable

from pyspark import SparkContext
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

EMPTY = "cast(array() as array<struct<label:bigint,weight:double>>)"
OVERFLOW = ("residual", "floor", "as_described")


@functools.lru_cache(maxsize=256)
def _built(gateway, make: Callable[..., Column], name: str, *args) -> Column:
    return make(F.col(name), *args)


def of_column(make: Callable[..., Column], name: str, *args) -> Column:
    """``make(F.col(name), *args)``, built once: a fold is hundreds of calls to the JVM, and a loop needs it in every iteration."""
    return _built(SparkContext._gateway, make, name, *args)


def slot(label: Column, weight: Column) -> Column:
    return F.struct(label.cast("long").alias("label"), weight.cast("double").alias("weight"))


def mg_accumulate(sketch: Column, label: Column, weight: Column, k: int, overflow: str = "residual", slot_pick: str = "last") -> Column:
    """The sketch with one more pair in it. ``slot_pick``: a new pair takes the last or the first free slot; the labels and
    weights are the same."""
    lowered = lambda by: F.transform(sketch, lambda e: slot(e["label"], e["weight"] - by))
    if overflow == "residual":
        least = F.array_min(F.transform(sketch, lambda e: e["weight"]))
        by = F.least(weight, least)
        full = F.concat(F.filter(lowered(by), lambda e: e["weight"] > 0), F.filter(F.array(slot(label, weight - by)), lambda e: e["weight"] > 0))
    elif overflow == "floor":
        full = F.filter(lowered(weight), lambda e: e["weight"] > 0)
    elif overflow == "as_described":
        full = F.filter(lowered(weight), lambda e: e["weight"] != 0)
    else:
        raise ValueError(overflow)
    added = F.transform(sketch, lambda e: slot(e["label"], F.when(e["label"] == label, e["weight"] + weight).otherwise(e["weight"])))
    kept = added if overflow != "as_described" else F.filter(added, lambda e: e["weight"] != 0)
    return F.when(F.exists(sketch, lambda e: e["label"] == label), kept).when(F.size(sketch) < k, F.concat(*([sketch, F.array(slot(label, weight))] if slot_pick == "last" else [F.array(slot(label, weight)), sketch]))).otherwise(full)


def mg_fold(pairs: Column, k: int, overflow: str = "residual", slot_pick: str = "last") -> Column:
    """Sketch of an array of structs with label and weight, in the array's order."""
    return F.aggregate(pairs, F.expr(EMPTY), lambda s, x: mg_accumulate(s, x["label"], x["weight"], k, overflow, slot_pick))


def mg_merge(sketches: Column, k: int, overflow: str = "residual") -> Column:
    """Merge by replay: the slots of all sketches (an array of sketches) are accumulated one after the other."""
    return mg_fold(F.flatten(sketches), k, overflow)


def mg_top(sketch: Column) -> Column:
    """Label of the heaviest slot, the smaller label on a tie; null if no slot is above 0."""
    best = F.array_max(F.transform(F.filter(sketch, lambda e: e["weight"] > 0), lambda e: F.struct(e["weight"].alias("weight"), (-e["label"]).alias("minus"))))
    return -best["minus"]


def vote_accumulate(state: Column, label: Column, weight: Column, rule: str = "replace") -> Column:
    """The vote's candidate after one more pair; an empty state has weight 0.

    ``replace``: a pair at least as heavy as the candidate takes its place with full weight; ``residual``: with what is left.
    """
    taken = weight if rule == "replace" else weight - state["weight"]
    return F.when((state["label"] == label) & (state["weight"] > 0), slot(state["label"], state["weight"] + weight)).when(state["weight"] > weight, slot(state["label"], state["weight"] - weight)).otherwise(slot(label, taken))


def vote_fold(pairs: Column, rule: str = "replace") -> Column:
    return F.aggregate(pairs, slot(F.lit(None), F.lit(0.0)), lambda s, x: vote_accumulate(s, x["label"], x["weight"], rule))


class Sketch:
    """The same fold in plain Python, for Arrow engines, table functions and streams: k slots of state."""

    def __init__(self, k: int, overflow: str = "residual", slots: Iterable[tuple[int, float]] = ()):
        self.k, self.overflow, self.slots = k, overflow, dict(slots)

    def add(self, label: int, weight: float) -> None:
        slots = self.slots
        if label in slots:
            slots[label] += weight
            if slots[label] == 0:
                del slots[label]
        elif len(slots) < self.k:
            slots[label] = weight
        elif self.overflow == "residual":
            by = min(weight, min(slots.values()))
            self.slots = {x: w - by for x, w in slots.items() if w > by}
            if weight > by:
                self.slots[label] = weight - by
        elif self.overflow == "floor":
            self.slots = {x: w - weight for x, w in slots.items() if w > weight}
        else:
            self.slots = {x: w - weight for x, w in slots.items() if w != weight}

    def fold(self, labels: list[int], weights: list[float]) -> None:
        """``add`` for many pairs, with the common cases of the default rule spelt out."""
        if self.overflow != "residual":
            for x, w in zip(labels, weights, strict=True):
                self.add(x, w)
            return
        slots, k = self.slots, self.k
        for x, w in zip(labels, weights, strict=True):
            if x in slots:
                slots[x] += w
            elif len(slots) < k:
                slots[x] = w
            else:
                by = min(slots.values())
                if w <= by:
                    slots = {y: v - w for y, v in slots.items() if v > w}
                else:
                    slots = {y: v - by for y, v in slots.items() if v > by}
                    slots[x] = w - by
        self.slots = slots

    def top(self) -> int | None:
        above = [(-w, x) for x, w in self.slots.items() if w > 0]
        return min(above)[1] if above else None


class Vote:
    def __init__(self, rule: str = "replace"):
        self.rule, self.label, self.weight = rule, None, 0.0

    def add(self, label: int, weight: float) -> None:
        if self.weight > 0 and label == self.label:
            self.weight += weight
        elif self.weight > weight:
            self.weight -= weight
        else:
            self.label, self.weight = label, weight if self.rule == "replace" else weight - self.weight

    def top(self) -> int | None:
        return self.label if self.weight > 0 else None


def register(spark: SparkSession) -> None:
    """SQL surface: mg_sketch(array, k), mg_merge_sketches(array of sketches, k), mg_top_label(sketch), vote_label(array) and
    the table function heavy_hitters(table, k)."""
    from pyspark.sql.functions import udtf

    slots, one = "ARRAY<STRUCT<label: BIGINT, weight: DOUBLE>>", "named_struct('label', x.label, 'weight', x.weight)"
    least = "array_min(transform(a, e -> e.weight))"
    folded = (
        f"aggregate(s, cast(array() as {slots}), (a, x) -> CASE WHEN exists(a, e -> e.label = x.label) THEN transform(a, e -> named_struct('label', e.label, 'weight', CASE WHEN e.label = x.label THEN e.weight + x.weight ELSE e.weight END)) "
        f"WHEN size(a) < k THEN concat(a, array({one})) ELSE concat(filter(transform(a, e -> named_struct('label', e.label, 'weight', e.weight - least(x.weight, {least}))), e -> e.weight > 0), "
        f"filter(array(named_struct('label', x.label, 'weight', x.weight - least(x.weight, {least}))), e -> e.weight > 0)) END)"
    )
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION mg_sketch(s {slots}, k INT) RETURNS {slots} RETURN {folded}")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION mg_merge_sketches(p ARRAY<{slots}>, k INT) RETURNS {slots} RETURN mg_sketch(flatten(p), k)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION mg_top_label(s ARRAY<STRUCT<label: BIGINT, weight: DOUBLE>>) RETURNS BIGINT RETURN -(array_max(transform(filter(s, e -> e.weight > 0), e -> named_struct('weight', e.weight, 'minus', -e.label))).minus)")
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION vote_label(s ARRAY<STRUCT<label: BIGINT, weight: DOUBLE>>) RETURNS BIGINT RETURN aggregate(s, named_struct('label', cast(null as bigint), 'weight', 0D), "
        "(a, x) -> CASE WHEN a.label = x.label AND a.weight > 0 THEN named_struct('label', a.label, 'weight', a.weight + x.weight) WHEN a.weight > x.weight THEN named_struct('label', a.label, 'weight', a.weight - x.weight) ELSE named_struct('label', x.label, 'weight', x.weight) END).label"
    )

    class HeavyHitters:
        """Rows of (key, label, weight) in the order given, one partition per key; emits key, label, weight of each slot."""

        def __init__(self):
            self.sketch, self.key = None, None

        def eval(self, row, k: int):
            if self.sketch is None:
                self.sketch, self.key = Sketch(k), row[0]
            self.sketch.add(row[1], row[2])

        def terminate(self):
            if self.sketch is not None:
                for label, weight in sorted(self.sketch.slots.items()):
                    yield self.key, label, weight

    spark.udtf.register("heavy_hitters", udtf(HeavyHitters, returnType="key: bigint, label: bigint, weight: double"))
