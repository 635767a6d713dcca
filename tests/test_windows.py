"""The graph of windows against brute force, and what it shuffles."""

import numpy as np
import pytest
from labelsketch.operators import windows
from labelsketch.operators.builders import BUILDERS
from pyspark.sql import functions as F

ODD = [
    None, "", "abc", "a" * 12, "a" * 13, "a" * 40, "abcdefghijkl", "abcdefghijklm", "ab" * 9, "ba" * 9, "x" + "ba" * 20 + "y", "zyzyzyzyzyzyz", "b" + "a" * 12, "a" * 12 + "b", "c" + "a" * 30 + "b",
    "\0\1\0\1\0\1\0\1\0\1\0\1\0\1\0", "\0" * 5 + "q" * 20 + "\0", "žluťoučký kůň úpěl ďábelské ódy", "日本語のテキストを十分に長く書いておく", "\U0001f600￮\U0001f600￮" * 6, "퟿￿\U00010000" * 5, "The same line.\nThe same line.\nThe same line.\n",
]


def brute(texts, k):
    pairs = {(t[i : i + k], t[i + 1 : i + k + 1]) for t in texts if t for i in range(len(t) - k)}
    pairs = {(a, b) for a, b in pairs if a != b}
    ids = {w: i for i, w in enumerate(sorted({w for p in pairs for w in p}, key=lambda w: w.encode()))}
    return sorted({(ids[x], ids[y], 1.0) for a, b in pairs for x, y in ((a, b), (b, a))})


def graph_of(spark, texts, k):
    found = windows.window_graph(spark.createDataFrame([(t,) for t in texts], "text string").repartition(3), "text", k)
    assert found.dtypes == [("src", "bigint"), ("dst", "bigint"), ("weight", "double")]
    return sorted(tuple(r) for r in found.collect())


@pytest.mark.parametrize("k", [2, 3, 12, 13])
def test_odd_texts(spark, k):
    assert graph_of(spark, ODD, k) == brute(ODD, k)
    assert graph_of(spark, [None, "", "a" * 50], k) == []


def test_any_cut_and_alphabet(spark, monkeypatch):
    """Many passes, ranges, sorts and pieces, and an alphabet of three words a record, change no number."""
    rng = np.random.default_rng(1)
    wide = "".join(map(chr, range(0x4E00, 0x4E00 + 3000)))
    texts = ODD + ["".join(rng.choice(list("abc é"), 400)) for _ in range(6)] + ["".join(rng.choice(list("ab"), 3000)), wide, wide[::-1], *["common line of all texts" + wide[i : i + 9] for i in range(30)]]
    for name, value in {"PASS_WINDOWS": 4000, "RANGE_WINDOWS": 300, "SORT_ROWS": 500, "PIECE": 64, "SAMPLE": 7, "OUT_ROWS": 50}.items():
        monkeypatch.setattr(windows, name, value)
    assert graph_of(spark, texts, 12) == brute(texts, 12)


@pytest.mark.parametrize("bits", [[63, 28], [64, 40], [60, 60, 60], [21] * 5])
def test_sort_distinct(bits):
    rng = np.random.default_rng(2)
    for n in (0, 1, 5000):
        words = [rng.integers(0, 5, n).astype(np.uint64) << np.uint64(b - 3) | rng.integers(0, 3, n).astype(np.uint64) for b in bits]
        found = windows.sort_distinct(words, bits)
        assert list(zip(*map(np.ndarray.tolist, found))) == sorted(set(zip(*map(np.ndarray.tolist, words))))


def test_little_is_shuffled_and_kept(spark, sf):
    """The strings of the windows took 90 bytes a character of the texts in shuffles, at sf0.001."""

    def written() -> int:
        stages = spark.sparkContext._jsc.sc().statusStore().executorList(False)
        return sum(stages.apply(i).totalShuffleWrite() for i in range(stages.size()))

    chars = spark.read.parquet(f"{sf}/documents.parquet").agg(F.sum(F.length("text"))).first()[0]
    before = written()
    found = BUILDERS["kmer"](spark, sf)
    assert found.count() > chars
    assert written() - before < 8 * chars
