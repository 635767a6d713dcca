"""Worked examples and guarantees of the sketches and votes, in both engines."""

import itertools
import random

import numpy as np
import pytest
from labelsketch.functions import sketch as S
from labelsketch.operators import local
from labelsketch.operators.selectors import HeavyHitter, MajorityVote
from pyspark.sql import functions as F

A, B, C, D = 1, 2, 3, 4
STREAMS = [
    ([(A, 1), (B, 1), (A, 1), (C, 1), (C, 1)], 2, dict.fromkeys(S.OVERFLOW, {A: 1, C: 1})),
    ([(A, 1), (B, 1), (C, 1)], 2, dict.fromkeys(S.OVERFLOW, {})),
    ([(A, 1), (B, 10)], 1, {"as_described": {A: -9}, "floor": {}, "residual": {B: 9}}),
]
MERGES = [
    ([[(A, 2), (B, 1)], [(B, 2), (C, 1)]], dict.fromkeys(S.OVERFLOW, {A: 1, B: 2})),
    ([[(A, 1), (B, 3)], [(C, 2), (D, 1)]], {"as_described": {A: -2}, "floor": {B: 1, D: 1}, "residual": {B: 1}}),
]
VOTES = [([(A, 1), (B, 1), (A, 1), (C, 1), (C, 1)], {"replace": (C, 2)}), ([(A, 10), (B, 10)] + [(A, 1)] * 5, {"replace": (B, 5), "residual": (A, 5)})]


def python_sketch(stream, k, rule):
    s = S.Sketch(k, rule)
    for x, w in stream:
        s.add(x, w)
    return s.slots


def array(spark, stream):
    return spark.createDataFrame([([{"label": x, "weight": float(w)} for x, w in stream],)], "p array<struct<label:bigint,weight:double>>")


def slots(row):
    return {s["label"]: s["weight"] for s in row}


@pytest.mark.parametrize("rule", S.OVERFLOW)
def test_streams(spark, rule):
    for stream, k, want in STREAMS:
        assert python_sketch(stream, k, rule) == want[rule]
        assert slots(array(spark, stream).select(S.mg_fold(F.col("p"), k, rule)).first()[0]) == want[rule]


@pytest.mark.parametrize("rule", S.OVERFLOW)
def test_merges(spark, rule):
    for parts, want in MERGES:
        df = spark.createDataFrame([([[{"label": x, "weight": float(w)} for x, w in p] for p in parts],)], "s array<array<struct<label:bigint,weight:double>>>")
        assert slots(df.select(S.mg_merge(F.col("s"), 2, rule)).first()[0]) == want[rule]


def test_votes(spark):
    for stream, want in VOTES:
        for rule, (label, weight) in want.items():
            v = S.Vote(rule)
            for x, w in stream:
                v.add(x, w)
            got = array(spark, stream).select(S.vote_fold(F.col("p"), rule).alias("v")).first().v
            assert (v.label, v.weight) == (got.label, got.weight) == (label, weight)


def test_engines_agree_and_bounds_hold(spark):
    rng = random.Random(4)
    cases = [([(rng.randint(0, 7), rng.randint(1, 5)) for _ in range(rng.randint(1, 40))], rng.randint(1, 5)) for _ in range(60)]
    for k in range(1, 6):
        some = [s for s, n in cases if n == k]
        df = spark.createDataFrame([([{"label": x, "weight": float(w)} for x, w in s],) for s in some], "p array<struct<label:bigint,weight:double>>")
        for rule in S.OVERFLOW:
            assert [slots(r[0]) for r in df.select(S.mg_fold(F.col("p"), k, rule)).collect()] == [python_sketch(s, k, rule) for s in some]
    for stream, k in cases:
        truth = {x: sum(w for y, w in stream if y == x) for x, _ in stream}
        total, got = sum(truth.values()), python_sketch(stream, k, "residual")
        assert all(x in got for x, w in truth.items() if w * (k + 1) > total)
        assert all(0 <= truth[x] - got.get(x, 0) <= (total - sum(got.values())) / (k + 1) + 1e-9 for x in truth)
        if len(truth) <= k:
            assert got == truth


@pytest.mark.parametrize("few", [1, 6, 64])
def test_folds_side_by_side_equal_one_after_another(few, monkeypatch):
    monkeypatch.setattr(local, "FEW", few)
    rng = np.random.default_rng(7)
    for kinds, longest, heaviest in itertools.product((2, 6, 30), (3, 50), (2, 9)):
        bounds = np.r_[0, np.cumsum(rng.integers(0, longest, 90))]
        labels, weights = rng.integers(-2, kinds, bounds[-1]), rng.integers(1, heaviest, bounds[-1]).astype(float)
        streams = [list(zip(labels[a:b].tolist(), weights[a:b].tolist(), strict=True)) for a, b in itertools.pairwise(bounds)]
        for k, rule in itertools.product((1, 2, 8), S.OVERFLOW):
            got = local.slots_of(HeavyHitter(k=k, overflow=rule), labels, weights, bounds)
            assert list(zip(*map(np.ndarray.tolist, got), strict=True)) == [(r, x, w) for r, s in enumerate(streams) for x, w in python_sketch(s, k, rule).items()]
        for rule in ("replace", "residual"):
            want = []
            for r, s in enumerate(streams):
                v = S.Vote(rule)
                for x, w in s:
                    v.add(x, w)
                want += [(r, v.label, v.weight)] if v.weight > 0 else []
            assert list(zip(*map(np.ndarray.tolist, local.votes_of(MajorityVote(rule=rule), labels, weights, bounds)), strict=True)) == want


def test_unit_votes_keep_a_majority():
    for n in range(1, 8):
        for stream in itertools.product((A, B, C), repeat=n):
            v = S.Vote()
            for x in stream:
                v.add(x, 1)
            for x in (A, B, C):
                if 2 * stream.count(x) > n:
                    assert v.top() == x
