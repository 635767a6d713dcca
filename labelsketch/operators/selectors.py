"""How a vertex picks its label from its neighbours': exactly, from a heavy-hitter sketch, or by majority vote."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import sketch as S


def heaviest(sums: DataFrame, weight: str = "weight") -> DataFrame:
    """id, candidate from rows dst, label, weight: the heaviest label, the smaller one on a tie."""
    return sums.groupBy(F.col("dst").alias("id")).agg(F.max_by("label", F.struct(F.col(weight), -F.col("label"))).alias("candidate"))


def linking_weights(pairs: DataFrame) -> DataFrame:
    """dst, label, weight: what links each vertex to each label around it."""
    return pairs.groupBy("dst", "label").agg(F.sum("weight").alias("weight"))


def neighbor_label_map(pairs: DataFrame) -> DataFrame:
    """dst and its complete map of label to linking weight, for inspection."""
    return linking_weights(pairs).groupBy("dst").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("label", "weight")))).alias("weights"))


def ordered(pairs: DataFrame) -> DataFrame:
    """dst, chunk and the pairs of the chunk in scan order."""
    return pairs.groupBy("dst", "chunk").agg(F.array_sort(F.collect_list(F.struct("ord", "label", "weight"))).alias("pairs"))


def arrow_fold(pairs: DataFrame, make, emit, schema: str) -> DataFrame:
    """The fold as one sorted pass over Arrow batches with constant state per (dst, chunk); no neighbourhood is collected."""
    import pyarrow as pa
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType

    target = to_arrow_schema(StructType.fromDDL(schema))

    def run(batches):
        key, state = None, None
        for batch in batches:
            out = []
            for dst, chunk, label, weight in zip(*(batch.column(c).to_pylist() for c in ("dst", "chunk", "label", "weight")), strict=True):
                if (dst, chunk) != key:
                    if key is not None:
                        out.append({"dst": key[0], "chunk": key[1], **emit(state)})
                    key, state = (dst, chunk), make()
                state.add(label, weight)
            yield pa.RecordBatch.from_pylist(out, schema=target)
        if key is not None:
            yield pa.RecordBatch.from_pylist([{"dst": key[0], "chunk": key[1], **emit(state)}], schema=target)

    return pairs.select("dst", "chunk", "ord", "label", "weight").repartition("dst").sortWithinPartitions("dst", "chunk", "ord").mapInArrow(run, schema)


@dataclass(frozen=True)
class Exact:
    """Complete linking weights."""

    def candidates(self, pairs: DataFrame) -> DataFrame:
        return heaviest(linking_weights(pairs))


@dataclass(frozen=True)
class HeavyHitter:
    """A k-slot sketch per vertex.

    ``merge``: ``replay`` of the chunks' slots or ``subtract`` of the (k+1)-th largest sum. ``scan``: ``single`` takes the
    heaviest slot, ``double`` weighs the surviving labels again. ``consolidation``: ``partial`` sketches per chunk or one
    ``shared`` sketch per vertex.
    """

    k: int = 8
    overflow: str = "residual"
    merge: str = "replay"
    scan: str = "single"
    consolidation: str = "partial"
    engine: str = "expr"
    slot_pick: str = "last"

    @staticmethod
    def headline() -> HeavyHitter:
        return HeavyHitter()

    def partial(self, pairs: DataFrame) -> DataFrame:
        """dst, chunk, slots."""
        if self.consolidation == "shared":
            pairs = pairs.withColumn("chunk", F.lit(0))
        if self.engine == "arrow":
            k, rule = self.k, self.overflow
            return arrow_fold(pairs, lambda: S.Sketch(k, rule), lambda s: {"slots": [{"label": x, "weight": w} for x, w in s.slots.items()]}, "dst long, chunk int, slots array<struct<label:bigint,weight:double>>")
        return ordered(pairs).select("dst", "chunk", S.of_column(S.mg_fold, "pairs", self.k, self.overflow, self.slot_pick).alias("slots"))

    def sketch(self, pairs: DataFrame) -> DataFrame:
        """dst, slots: chunks merged."""
        return merged(self.partial(pairs), self)

    def candidates(self, pairs: DataFrame) -> DataFrame:
        whole = self.sketch(pairs)
        if self.scan == "single":
            return whole.select(F.col("dst").alias("id"), S.of_column(S.mg_top, "slots").alias("candidate")).filter("candidate is not null")
        survivors = whole.select("dst", F.explode("slots.label").alias("label"))
        return heaviest(linking_weights(pairs.join(survivors, ["dst", "label"], "left_semi")))


def merged(parts: DataFrame, selector: HeavyHitter) -> DataFrame:
    """dst, slots from dst, chunk, slots, by the selector's merge."""
    if selector.merge == "subtract":
        return subtracted(parts, selector.k)
    by_chunk = F.transform(F.array_sort(F.collect_list(F.struct("chunk", "slots"))), lambda x: x["slots"])
    whole = parts.groupBy("dst").agg(by_chunk.alias("s"))
    return whole.select("dst", F.when(F.size("s") == 1, F.get("s", 0)).otherwise(S.of_column(S.mg_merge, "s", selector.k, selector.overflow)).alias("slots"))


def subtracted(parts: DataFrame, k: int) -> DataFrame:
    """Merge that no order can change: sums per label, less the (k+1)-th largest, positive ones kept."""
    sums = parts.select("dst", F.explode("slots").alias("s")).groupBy("dst", F.col("s.label").alias("label")).agg(F.sum("s.weight").alias("weight"))
    ranked = sums.withColumn("r", F.row_number().over(Window.partitionBy("dst").orderBy(F.desc("weight"), "label")))
    cut = F.coalesce(F.max(F.when(F.col("r") == k + 1, F.col("weight"))).over(Window.partitionBy("dst")), F.lit(0.0))
    left = ranked.withColumn("weight", F.col("weight") - cut).filter("weight > 0")
    return left.groupBy("dst").agg(F.array_sort(F.collect_list(F.struct("label", "weight"))).alias("slots"))


@dataclass(frozen=True)
class MajorityVote:
    """One candidate per chunk; chunks meet in a maximum (``max``) or cancel each other (``merge``)."""

    rule: str = "replace"
    combine: str = "max"
    engine: str = "expr"

    def partial(self, pairs: DataFrame) -> DataFrame:
        """dst, chunk, label, weight."""
        if self.engine == "arrow":
            rule = self.rule
            return arrow_fold(pairs, lambda: S.Vote(rule), lambda v: {"label": v.label, "weight": v.weight}, "dst long, chunk int, label long, weight double").filter("weight > 0")
        voted = ordered(pairs).select("dst", "chunk", S.of_column(S.vote_fold, "pairs", self.rule).alias("v"))
        return voted.select("dst", "chunk", "v.label", "v.weight").filter("weight > 0")

    def candidates(self, pairs: DataFrame) -> DataFrame:
        return self.combined(self.partial(pairs))

    def combined(self, states: DataFrame) -> DataFrame:
        """id, candidate from the chunks' states."""
        if self.combine == "max":
            return heaviest(states)
        sums = states.groupBy("dst", "label").agg(F.sum("weight").alias("weight"))
        total = F.sum("weight").over(Window.partitionBy("dst"))
        return heaviest(sums.withColumn("left", 2 * F.col("weight") - total).filter(F.col("left") >= 0))
