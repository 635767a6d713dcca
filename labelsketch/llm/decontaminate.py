"""Benchmark decontamination by a prefix-filtered set join on word shingles.

A window is ``WINDOW`` consecutive words of an item, or all words of a shorter one; it contains shingles of ``SHINGLE`` words
(or itself, if it is shorter). A document that holds a window holds all its shingles, so one is prefix enough. One pass over
the documents joins their shingles with the benchmark's; the few that match are written and counted, which orders the
shingles by rarity. A window with a shingle that no document has is out; each other one is filed under its rarest shingle
with that shingle's offset. Joined with the matches, offset and length place the window in the document (one that would
stick out is dropped), and a second pass compares its words there.

The benchmark is a table of windows and may be of any size: sides of a join, and the benchmark's shingle hashes that the
first pass looks up, are broadcast only up to ``BROADCAST_ROWS`` rows; beyond it Spark shuffles. What moves is matches, not
pairs, and the texts that are candidates. Shingles are hashed in Arrow batches, since JVM lambdas took four times as long.

Null and empty texts have no words, null item ids count as the empty string, repeated items as one. Very long texts are
handled whole. Equal texts share their matches, so copies cost one row each. Extra columns are ignored, empty tables give no
hits.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common

WINDOW, SHINGLE = 10, 5
#: What is between words, once A-Z are lower case: everything in ASCII but digits and letters.
SEPARATOR = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: The same separators before the letters are made lower case, and words in lower-cased UTF-8 bytes.
RAW_SEPARATOR = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
WORD = re.compile(rb"[0-9a-z\x80-\xff]+")
#: Rows of a join's side up to which it is broadcast.
BROADCAST_ROWS = 500_000
KEY = ["__k1", "__k2"]


def words(text: Column) -> Column:
    lower = F.translate(F.coalesce(text, F.lit("")), common.UPPER, common.LOWER)
    return F.filter(F.split(lower, SEPARATOR, -1), lambda w: w != "")


def small(df: DataFrame) -> DataFrame:
    """df, to be broadcast if it has few rows."""
    return F.broadcast(df) if df.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS else df


def windows(benchmark: DataFrame, size: int = WINDOW) -> DataFrame:
    """window, words, items: the distinct windows and the ids of the items that have them."""
    item = F.coalesce(F.col("item_id").cast("string"), F.lit("")).alias("item")
    rows = benchmark.select(item, F.explode(F.array(words(F.col("text")))).alias("w")).filter(F.size("w") > 0)
    starts = F.sequence(F.lit(0), F.greatest(F.size("w") - size, F.lit(0)))
    rows = rows.select("item", F.explode(F.transform(starts, lambda i: F.slice("w", i + 1, size))).alias("words"))
    return rows.groupBy("words").agg(F.collect_set("item").alias("items")).withColumn("window", F.monotonically_increasing_id())


class Hashes(dict):
    """64-bit hashes of words, each computed once."""

    def __missing__(self, word: bytes) -> int:
        if len(self) > 1_000_000:
            self.clear()
        value = self[word] = xxhash.xxh64_intdigest(word)
        return value

    def of(self, texts: list[list[bytes]]) -> tuple[np.ndarray, np.ndarray]:
        """The hashes of all words and how many each text has."""
        sizes = np.array([len(t) for t in texts], np.int64)
        return np.fromiter((self[w] for t in texts for w in t), np.uint64, int(sizes.sum())), sizes


def shingles(hashes: np.ndarray, sizes: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(text, place, hash) of every run of ``size`` words inside a text."""
    n = max(0, len(hashes) - size + 1)
    run = np.zeros(n, np.uint64)
    for k in range(size):
        run = (run ^ (run >> np.uint64(29))) * np.uint64(0x9E3779B97F4A7C15) + hashes[k : k + n]
    owner = np.repeat(np.arange(len(sizes)), sizes)[:n]
    place = np.arange(n) - (np.cumsum(sizes) - sizes)[owner]
    inside = place + size <= sizes[owner]
    return owner[inside], place[inside], run[inside].view(np.int64)


def window_shingles(filed: DataFrame) -> DataFrame:
    """window, length, offset, token: the shingles of each window."""

    def run(batches):
        held = Hashes()
        for batch in batches:
            texts = [[w.encode("utf-8", "replace") for w in x] for x in batch.column("words").to_pylist()]
            hashes, sizes = held.of(texts)
            ids = batch.column("window").to_numpy()
            for size in np.unique(np.minimum(sizes, SHINGLE)):
                owner, place, token = shingles(hashes, sizes, int(size))
                mine = np.minimum(sizes, SHINGLE)[owner] == size
                parts = [ids[owner[mine]], np.full(mine.sum(), size, np.int32), place[mine].astype(np.int32), token[mine]]
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in parts], ["window", "length", "offset", "token"])

    return filed.select("window", "words").mapInArrow(run, "window long, length int, offset int, token long")


def keyed(docs: DataFrame, keep: list[str]) -> DataFrame:
    """``keep`` columns, the text and a 128-bit checksum of it."""
    text = F.coalesce(F.col("text"), F.lit(""))
    return docs.select(*keep, text.alias("__text"), F.xxhash64(text).alias(KEY[0]), F.xxhash64(F.lit(1), text).alias(KEY[1]))


def matches(docs: DataFrame, tokens: DataFrame, sizes: list[int]) -> DataFrame:
    """text key, place, token, n (words) wherever a text has a shingle of the benchmark; equal texts once."""
    distinct = common.written(tokens.select("token").distinct(), "tokens")
    few = distinct.count() <= BROADCAST_ROWS
    known = docs.sparkSession.sparkContext.broadcast(np.sort(distinct.toArrow().column("token").to_numpy()) if few else None)

    def run(batches):
        held, wanted = Hashes(), known.value
        if wanted is not None:
            coarse = np.zeros(1 << 22, bool)
            coarse[wanted & (len(coarse) - 1)] = True
        for whole in batches:
            for batch in common.slices(whole, ["__text"], 4 << 20):
                hashes, counts = held.of([WORD.findall(x.encode("utf-8", "replace").lower()) for x in batch.column("__text").to_pylist()])
                keys = [batch.column(k).to_numpy() for k in KEY]
                for size in sizes:
                    owner, place, token = shingles(hashes, counts, size)
                    if wanted is not None:
                        some = np.nonzero(coarse[token & (len(coarse) - 1)])[0]
                        some = some[wanted[np.minimum(np.searchsorted(wanted, token[some]), len(wanted) - 1)] == token[some]]
                        owner, place, token = owner[some], place[some], token[some]
                    parts = [keys[0][owner], keys[1][owner], place.astype(np.int32), counts[owner].astype(np.int32), token]
                    yield pa.RecordBatch.from_arrays([pa.array(x) for x in parts], [*KEY, "place", "n", "token"])

    found = keyed(docs, []).mapInArrow(run, f"{KEY[0]} long, {KEY[1]} long, place int, n int, token long")
    if not few:
        found = found.join(distinct, "token", "left_semi")
    return found.dropDuplicates([*KEY, "place", "token"])


def candidates(docs: DataFrame, benchmark: DataFrame, size: int) -> DataFrame | None:
    """text key and ``c``: the places (start, words, items) where a window may be; None if the benchmark has no words."""
    filed = common.written(windows(benchmark, size), "windows")
    tokens = common.written(window_shingles(filed), "shingles")
    sizes = sorted(r[0] for r in tokens.select("length").distinct().collect())  # at most SHINGLE values
    if not sizes:
        return None
    found = common.written(matches(docs, tokens, sizes), "matches")
    frequency = found.groupBy("token").agg(F.count("*").alias("n"))
    ranked = tokens.join(frequency, "token", "left")
    rarest = ranked.groupBy("window").agg(F.min(F.struct("n", "token", "offset")).alias("r"), F.count_if(F.col("n").isNull()).alias("absent")).filter("absent = 0")
    prefix = common.written(filed.join(rarest.select("window", "r.token", "r.offset"), "window").drop("window"), "prefixes")
    placed = found.join(small(prefix), "token").withColumn("start", F.col("place") - F.col("offset"))
    placed = placed.filter((F.col("start") >= 0) & (F.col("start") + F.size("words") <= F.col("n")))
    return common.written(placed.groupBy(*KEY).agg(F.collect_list(F.struct("start", "words", "items")).alias("c")), "candidates")


def contamination(docs: DataFrame, benchmark: DataFrame, keep: list[str], size: int = WINDOW) -> DataFrame:
    """``keep`` columns plus n_words, n_hit, n_items, items_sha256, contaminated."""
    kept, none = [F.col(c) for c in keep], F.lit(0).cast("long")
    names = ["n_words", "n_hit", "n_items", "items_sha256", "contaminated"]

    def rest(*values: Column) -> list[Column]:
        return [*kept, *(v.alias(n) for v, n in zip(values, names, strict=True))]

    found = candidates(docs, benchmark, size)
    rows = keyed(docs, keep)
    # Texts without candidates are done where they are read; the others meet their candidates.
    marked = rows.withColumn("__some", F.lit(None)) if found is None else rows.join(small(found.select(*KEY, F.lit(True).alias("__some"))), KEY, "left")
    cut = F.split("__text", RAW_SEPARATOR, -1)
    clean = marked.filter("__some is null").select(*kept, F.explode(F.array(F.struct(F.size(cut).alias("n"), F.get(cut, F.lit(0)).alias("first"), F.element_at(cut, -1).alias("last")))).alias("__cut"))
    n_words = F.when(F.col("__cut.n") == 1, F.when(F.col("__cut.first") == "", 0).otherwise(1)).otherwise(F.col("__cut.n") - F.when(F.col("__cut.first") == "", 1).otherwise(0) - F.when(F.col("__cut.last") == "", 1).otherwise(0))
    clean = clean.select(*rest(n_words.cast("long"), none, none, F.sha2(F.lit("").cast("binary"), 256), F.lit(False)))
    if found is None:
        return clean
    cut = marked.filter("__some").join(found, KEY).select(*kept, "c", F.explode(F.array(words(F.col("__text")))).alias("__w"))
    held = F.filter("c", lambda x: F.slice("__w", x["start"] + 1, F.size(x["words"])) == x["words"])
    cut = cut.select(*kept, F.size("__w").cast("long").alias("__n"), F.explode(F.array(held)).alias("__spans"))
    ends = F.array_sort(F.transform("__spans", lambda s: F.struct(s["start"].alias("a"), (s["start"] + F.size(s["words"])).alias("b"))))
    more = lambda t, s: F.struct(F.greatest(t["end"], s["b"]).alias("end"), (t["n"] + F.greatest(F.lit(0), s["b"] - F.greatest(t["end"], s["a"]))).alias("n"))
    n_hit = F.aggregate(ends, F.struct(F.lit(0).alias("end"), F.lit(0).alias("n")), more)["n"].cast("long")
    items = F.array_sort(F.array_distinct(F.flatten(F.transform("__spans", lambda s: s["items"]))))
    dirty = cut.select(*rest(F.col("__n"), n_hit, F.size(items).cast("long"), F.sha2(F.concat_ws(",", items).cast("binary"), 256), n_hit > 0))
    return clean.unionByName(dirty)


#: The query's rows in DuckDB.
SQL = r"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
b AS (SELECT coalesce(CAST(item_id AS VARCHAR), '') AS item, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
win AS (SELECT DISTINCT item, array_to_string(w[i : i + 9], ' ') AS s, least(len(w), 10) AS l FROM (SELECT item, w, unnest(range(1, greatest(len(w) - 9, 1) + 1)) AS i FROM b WHERE len(w) > 0)),
ls AS (SELECT DISTINCT l FROM win),
dw AS (SELECT r, i, l, array_to_string(w[i : i + l - 1], ' ') AS s FROM (SELECT r, w, l, unnest(range(1, len(w) - l + 2)) AS i FROM d, ls WHERE len(w) >= l)),
hit AS (SELECT r, i, l, item FROM dw JOIN win USING (l, s)),
pos AS (SELECT r, count(DISTINCT p) AS n FROM (SELECT r, unnest(range(i, i + l)) AS p FROM (SELECT DISTINCT r, i, l FROM hit)) GROUP BY 1),
its AS (SELECT r, count(*) AS n, sha256(string_agg(item, ',' ORDER BY item)) AS h FROM (SELECT DISTINCT r, item FROM hit) GROUP BY 1)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(pos.n, 0) AS BIGINT) AS n_hit, CAST(coalesce(its.n, 0) AS BIGINT) AS n_items, coalesce(its.h, sha256('')) AS items_sha256, pos.n IS NOT NULL AS contaminated
FROM d LEFT JOIN pos USING (r) LEFT JOIN its USING (r)
"""
