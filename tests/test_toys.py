"""The worked example on a given table."""

from labelsketch.operators.builders import toy_on_parts
from labelsketch.plans import queries as plans


def test_two_triangles_on_parts(spark, sf, tmp_path):
    keys = sorted(r[0] for r in spark.read.parquet(f"{sf}/part.parquet").select("p_partkey").collect())
    found = {r.id: r.label for r in plans.queries()["toy_two_triangles"](spark, sf).collect()}
    assert set(found) == set(keys)
    whole = [k for k in keys if set(range(k - k % 6, k - k % 6 + 6)) <= set(keys)]
    assert len(whole) >= 6
    for k in whole:
        first = k - k % 6
        assert found[k] == first + (2 if k - first > 2 else 0)
    assert toy_on_parts(spark, sf).inputFiles()


def test_gaps_and_nulls(spark, tmp_path):
    """An edge needs both ends; keys may be absent, null or there twice."""
    spark.createDataFrame([(k,) for k in (7, 8, 8, 10, 11, None, 13, 3, 4)], "p_partkey long").write.parquet(f"{tmp_path}/part.parquet")
    edges = sorted((r.src, r.dst) for r in toy_on_parts(spark, str(tmp_path)).collect())
    assert edges == [(3, 4), (4, 3), (7, 8), (8, 7), (10, 11), (11, 10)]
