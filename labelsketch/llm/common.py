"""What the operators share: row-wise Arrow maps, held-out split, bounded label samples, shared scratch tables."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..store import drop, shared_dir, written

__all__ = ["drop", "shared_dir", "written"]

#: ASCII upper and lower case, for lower-casing A-Z alone.
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: The same as a table of str.translate.
ASCII_LOWER = str.maketrans(UPPER, LOWER)


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def held_out(doc_id: Column) -> Column:
    """True for the fifth of the rows that no model may learn from (a null id counts as the empty string)."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % 5 == 0


def map_texts(df: DataFrame, keep: list[str], inputs: list[str], fields: list[T.StructField], make: Callable[[], Callable[..., list]]) -> DataFrame:
    """``keep`` columns of every row plus new ``fields``, computed from the ``inputs`` columns.

    ``make`` is called once in each task and returns a function from lists (one per input) to lists (one per field).
    State is one Arrow batch at a time; a lost task is simply run again.
    """
    from pyspark.sql.pandas.types import to_arrow_type

    columns = list(dict.fromkeys([*keep, *inputs]))
    names = [f.name for f in fields]
    kinds = [to_arrow_type(f.dataType) for f in fields]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        work = make()
        for batch in batches:
            for part in slices(batch, inputs):
                made = work(*[part.column(c).to_pylist() for c in inputs])
                yield pa.RecordBatch.from_arrays([*(part.column(c) for c in keep), *(pa.array(v, k) for v, k in zip(made, kinds, strict=True))], [*keep, *names])

    schema = T.StructType([*(df.schema[c] for c in keep), *fields])
    return df.select(*columns).mapInArrow(run, schema)


def slices(batch: pa.RecordBatch, inputs: list[str], most: int = 16 << 20) -> Iterator[pa.RecordBatch]:
    """Parts of a batch with about ``most`` bytes of input each, one row at least."""
    size = sum(batch.column(c).nbytes for c in inputs)
    step = max(1, batch.num_rows * most // max(size, 1))
    for at in range(0, batch.num_rows, step):
        yield batch.slice(at, step)


#: Labels up to which their counts are broadcast.
BROADCAST_LABELS = 100_000


def hash_bound(n: Column, per_label: int) -> Column:
    """The 64-bit hash up to which rows are taken so that about ``per_label`` of n rows are, whatever n is."""
    some = F.lit(-(2.0**63)) + F.lit(float(per_label)) / n * F.lit(2.0**64)
    return F.when(n <= per_label, F.lit(2**63 - 1)).otherwise(some.cast("long"))


def label_sample(rows: DataFrame, label: str, per_label: int, seed: str) -> DataFrame:
    """About ``per_label`` rows of each label value, chosen by a hash of doc_id; a documented bound for training only.

    The labels are counted first, then each is thinned by a bound of its own on the full hash; there is no most or least count.
    """
    counts = written(rows.filter(F.col(label).isNotNull()).groupBy(label).agg(F.count("*").alias("__n")), "labels")
    bounds = counts.select(label, hash_bound(F.col("__n"), per_label).alias("__bound"))
    if counts.count() <= BROADCAST_LABELS:
        bounds = F.broadcast(bounds)
    return rows.join(bounds, label).filter(F.xxhash64("doc_id", F.lit(seed)) <= F.col("__bound")).select(*rows.columns)
