"""Near-duplicate classes by one-permutation MinHash with optimal densification.

Every set of word shingles is hashed once into ``BANDS * ROWS`` bins; empty bins borrow from the first filled bin of a
random order of their own, the same in all documents. Equal sets are one class from the start. Bands of bins are buckets; a
bucket proposes a star around one member. In each of ``STARS`` turns a class is tested on the full sets against one centre,
the one that most of its buckets propose, so candidate edges are one per class and turn. Buckets whose classes have all
been joined are done. The buckets that still hold several components form clusters; of a cluster, the classes outside its
largest component are compared with all classes of a fitting size in bounded blocks, and a block returns a spanning forest
of its links: no proposal is dropped. That step costs outside x all products inside a cluster, without rows for pairs.

Nulls and texts without words have empty sets and are linked with nothing; a text shorter than a shingle is one shingle.
Very long texts are used whole. doc_id may be of any type that can be ordered. Rows that share a doc_id are judged each by its
own text; rows without one stay alone or take the component of their copies. Extra columns are ignored, an empty table gives
an empty result. A group of copies of any size is a partial aggregate; joins on buckets, centres and components deal the
rows of one key into parts of ``SALT_ROWS``.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

SHINGLE, PERCENT = 5, 80
#: At a similarity of 0.8 a pair is missed with probability (1 - 0.8^6)^50 = 2.5e-7.
ROWS, BANDS = 6, 50
STARS = 2
#: Members and shingles of a block, on average at most, and columns of a block's product taken at a time.
BLOCK_ROWS, BLOCK_SHINGLES, COLUMNS = 512, 400_000, 4096
#: Rows of one key that a task joins, about.
SALT_ROWS = 256
#: Ids that are broadcast at most; beyond it they are joined by a shuffle.
BROADCAST_IDS = 2_000_000
NONE = np.uint64(0xFFFFFFFFFFFFFFFF)


def shingle_sets(docs: DataFrame, size: int) -> DataFrame:
    """doc_id and the set of 64-bit shingle hashes; JVM functions only."""
    text = F.translate(F.coalesce(F.col("text"), F.lit("")), common.UPPER, common.LOWER)
    words = F.filter(F.split(text, r"[\x20\x09-\x0D]+", -1), lambda w: w != "")
    # Exploding an array of one keeps the optimizer from copying the split into the lambda.
    rows = docs.select("doc_id", F.explode(F.array(words)).alias("w"))
    n = F.size("w")
    hashes = F.transform(F.sequence(F.lit(0), n - size), lambda i: F.xxhash64(*[F.get("w", i + k) for k in range(size)]))
    whole = F.array(F.xxhash64("w"))
    return rows.select("doc_id", F.when(n == 0, F.array().cast("array<long>")).when(n < size, whole).otherwise(F.array_distinct(hashes)).alias("set"))


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)
    return x ^ (x >> np.uint64(29))


def borrow_order(bins: int, seed: int = 11) -> np.ndarray:
    """Row j: a random rank of every bin; an empty bin j takes the filled bin of the least rank."""
    return np.random.default_rng(seed).random((bins, bins), np.float32)


def signatures(values: np.ndarray, sizes: np.ndarray, order: np.ndarray) -> np.ndarray:
    """One row of bins per set; sets must not be empty. values: all hashes, set by set."""
    bins = len(order)
    h = mixed(values.astype(np.uint64))
    owner = np.repeat(np.arange(len(sizes)), sizes)
    out = np.full(len(sizes) * bins, NONE)
    np.minimum.at(out, owner * bins + (h % np.uint64(bins)).astype(np.int64), h // np.uint64(bins))
    out = out.reshape(len(sizes), bins)
    filled = out != NONE
    for d in np.nonzero(~filled.all(1))[0]:
        have, lack = np.nonzero(filled[d])[0], np.nonzero(~filled[d])[0]
        out[d, lack] = out[d, have[order[np.ix_(lack, have)].argmin(1)]]
    return out


def bucket_keys(signature: np.ndarray, bands: int, rows: int) -> np.ndarray:
    """A 64-bit key per band, the band's number in it."""
    parts = signature.reshape(len(signature), bands, rows)
    key = np.broadcast_to(mixed(np.arange(1, bands + 1, dtype=np.uint64)), (len(signature), bands)).copy()
    for r in range(rows):
        key = mixed(key * np.uint64(0xD6E8FEB86659FD93) + parts[:, :, r])
    return key.view(np.int64)


def fingerprints(docs: DataFrame, size: int, extra: str, make) -> DataFrame:
    """doc_id, n_shingles, a 128-bit checksum of the set (f1, f2) and what ``make`` gives for a batch of sets."""
    schema = f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, n_shingles long, f1 long, f2 long, {extra}"
    names = ["doc_id", "n_shingles", "f1", "f2", extra.split()[0]]

    def run(batches):
        work = make()
        for whole in batches:
            for batch in common.slices(whole, ["set"], 4 << 20):
                sets = batch.column("set")
                sizes = np.diff(sets.offsets.to_numpy())
                values = sets.flatten().to_numpy().view(np.uint64)
                some = np.nonzero(sizes)[0]
                f1, f2 = np.zeros(len(sizes), np.uint64), np.zeros(len(sizes), np.uint64)
                if len(some):
                    starts = (np.cumsum(sizes) - sizes)[some]
                    f1[some] = np.add.reduceat(mixed(values), starts)
                    f2[some] = np.bitwise_xor.reduceat(mixed(values + np.uint64(0x632BE59BD9B4E019)), starts)
                columns = [batch.column("doc_id"), pa.array(sizes.astype(np.int64)), pa.array(f1.view(np.int64)), pa.array(f2.view(np.int64)), work(sets, sizes, values)]
                yield pa.RecordBatch.from_arrays(columns, names)

    return shingle_sets(docs, size).mapInArrow(run, schema)


def profiles(docs: DataFrame, size: int, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """doc_id, n_shingles, f1, f2 and the buckets of each set (none of an empty one)."""

    def make():
        order = borrow_order(bands * rows)

        def work(sets, sizes: np.ndarray, values: np.ndarray) -> pa.Array:
            some = sizes[sizes > 0]
            parts = [bucket_keys(signatures(values[a:b], part, order), bands, rows) for a, b, part in grouped(some)] if len(some) else []
            keys = np.concatenate(parts) if parts else np.zeros((0, bands), np.int64)
            offsets = np.r_[0, np.cumsum(np.where(sizes > 0, bands, 0))].astype(np.int32)
            return pa.ListArray.from_arrays(pa.array(offsets), pa.array(keys.ravel()))

        return work

    return fingerprints(docs, size, "buckets array<long>", make)


def grouped(sizes: np.ndarray, most: int = 512):
    """(first value, end, sizes) of runs of up to ``most`` sets."""
    ends = np.cumsum(sizes)
    for at in range(0, len(sizes), most):
        part = sizes[at : at + most]
        yield ends[at] - sizes[at], ends[at + len(part) - 1], part


def with_ids(rows: DataFrame, ids: DataFrame, how: str) -> DataFrame:
    """rows semi- or anti-joined on doc_id; the ids are broadcast if they are few enough, so that no text is shuffled."""
    return rows.join(F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids, "doc_id", how)


def spread(rows: DataFrame, lookup: DataFrame, key: str, how: str = "inner", widths: DataFrame | None = None) -> DataFrame:
    """rows joined with the one row of lookup that has their key, without a hot task however many rows share the key.

    Rows carry ``id`` and ``salts``, a number of parts; each joins by (key, part), and lookup rows are repeated for as many
    parts as the rows of their key ask for.
    """
    width = (rows if widths is None else widths).groupBy(key).agg(F.max("salts").alias("__width"))
    repeated = lookup.join(width, key).withColumn("__salt", F.explode(F.sequence(F.lit(0), F.col("__width") - 1))).drop("__width")
    dealt = rows.withColumn("__salt", F.pmod(F.xxhash64("id"), F.col("salts")).cast("int"))
    return dealt.join(repeated, [key, "__salt"], how).drop("__salt")


def components(edges: DataFrame) -> DataFrame:
    """(id, component) of every id in an edge (a, b): the least id reachable, by alternating large and small stars."""

    def least(pairs: DataFrame) -> DataFrame:
        return pairs.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))

    now = common.written(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).filter("u <> v").distinct(), "edges")
    seen = None
    while True:
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = both.join(least(both), "u").filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v").distinct()
        down = large.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
        small = down.join(least(down), "u")
        small = small.select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(small.select("u", F.col("m").alias("v"))).filter("u <> v").distinct()
        now = common.written(small, "stars")
        state = now.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if state == seen:
            return now.select(F.col("u").alias("id"), F.col("v").alias("component"))
        seen = state


def hooked(links: DataFrame) -> DataFrame:
    """(id, component) of every component in links (id, to, salts), which tie components to smaller ones.

    A component with one target that nothing is tied to takes what the target ends in, so only the others go through the
    rounds of stars, and the many members of a group cost one row each.
    """
    links = common.written(links.groupBy("id", "to").agg(F.max("salts").alias("salts")), "links")
    target = links.select(F.col("to").alias("id")).distinct()
    several = links.groupBy("id").agg(F.count("*").alias("n")).filter("n > 1").select("id")
    inside = target.unionByName(several).distinct()
    core = components(links.join(inside, "id", "left_semi").select(F.col("id").alias("a"), F.col("to").alias("b")))
    ends = target.join(core, "id", "left").select(F.col("id").alias("to"), F.coalesce("component", "id").alias("component"))
    leaves = spread(links.join(inside, "id", "left_anti"), ends, "to").select("id", "component")
    return common.written(leaves.unionByName(core), "hooked")


def relabelled(labels: DataFrame | None, found: DataFrame, links: DataFrame) -> DataFrame:
    """labels (id, component, salts) after components were joined: found is (component, new one), links say who was new."""
    fresh = found.join(links.groupBy("id").agg(F.max("salts").alias("salts")), "id", "left").select("id", "component", F.coalesce("salts", F.lit(1)).alias("salts"))
    if labels is None:
        return common.written(fresh, "labels")
    up = found.select(F.col("id").alias("component"), F.col("component").alias("up"))
    old = spread(labels, up, "component", "left").select("id", F.coalesce("up", "component").alias("component"), "salts")
    return common.written(old.unionByName(fresh.join(labels, "id", "left_anti")), "labels")


def compared(left: pa.Table, right: pa.Table, percent: int) -> pa.Table:
    """A spanning forest of the links between the components in two blocks of sets.

    The sizes of the intersections are a product of the blocks' 0/1 matrices, by columns.
    """
    at = [t.column("component").to_numpy() for t in (left, right)]
    sets = [t.column("set").combine_chunks() for t in (left, right)]
    values = [x.flatten().to_numpy() for x in sets]
    sizes = [np.diff(x.offsets.to_numpy()) for x in sets]
    shared = np.intersect1d(values[0], values[1])
    cells = []
    for v, n in zip(values, sizes, strict=True):
        column = np.searchsorted(shared, v)
        hit = (column < len(shared)) & (shared[np.minimum(column, len(shared) - 1)] == v) if len(shared) else np.zeros(len(v), bool)
        row, column = np.repeat(np.arange(len(n)), n)[hit], column[hit]
        order = np.argsort(column, kind="stable")
        cells.append((row[order], column[order]))
    both = np.zeros((len(sizes[0]), len(sizes[1])), np.float32)
    for start in range(0, len(shared), COLUMNS):
        width, parts = min(COLUMNS, len(shared) - start), []
        for (row, column), n in zip(cells, sizes, strict=True):
            a, b = np.searchsorted(column, [start, start + width])
            dense = np.zeros((len(n), width), np.float32)
            dense[row[a:b], column[a:b] - start] = 1
            parts.append(dense)
        both += parts[0] @ parts[1].T
    union = sizes[0][:, None] + sizes[1][None, :] - both
    linked = (100 * both >= percent * union) & (at[0][:, None] != at[1][None, :])
    i, j = np.nonzero(linked)
    found = forest(np.unique(np.stack([np.maximum(at[0][i], at[1][j]), np.minimum(at[0][i], at[1][j])], 1), axis=0))
    return pa.table({"id": pa.array([x for x, _ in found], pa.int64()), "to": pa.array([y for _, y in found], pa.int64())})


def forest(edges: np.ndarray) -> list[tuple[int, int]]:
    """The edges that join what those before them have not."""
    parent: dict[int, int] = {}

    def root(x: int) -> int:
        while parent.setdefault(x, x) != x:
            parent[x] = x = parent[parent[x]]
        return x

    kept = []
    for x, y in edges.tolist():
        a, b = root(x), root(y)
        if a != b:
            parent[max(a, b)] = min(a, b)
            kept.append((x, y))
    return kept


def blockwise(rows: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Links (id, to) between components among the rows of ``opened`` buckets, by exhaustive comparison.

    A cluster is what buckets connect. Its classes are banded by size, neighbouring bands alone can hold similar sets. Of a
    cluster only the classes outside its largest component are held against all; both sides are dealt into blocks of bounded
    size, and each pair of blocks is one group.
    """
    near = rows.filter("component <> c.component").select(F.col("component").alias("id"), F.col("c.component").alias("to"), "salts")
    cluster = hooked(near).select(F.col("id").alias("component"), F.col("component").alias("cluster"))
    each = rows.groupBy("id", "component", "n_shingles").agg(F.max("salts").alias("salts"))
    each = common.written(spread(each, cluster, "component", "left").withColumn("cluster", F.coalesce("cluster", "component")), "clusters")
    count = each.groupBy("cluster", "component").agg(F.count("*").alias("n"), F.max("salts").alias("salts"))
    largest = count.groupBy("cluster").agg(F.max(F.struct("n", "component"))["component"].alias("largest"), F.sum("n").alias("n"))
    each = each.withColumn("salts", F.greatest("salts", F.lit(8)))
    level = F.floor(F.log(F.col("n_shingles")) / F.log(F.lit(100 / percent + 1e-9)))
    member = spread(each, largest, "cluster").withColumn("outside", F.col("component") != F.col("largest")).withColumn("level", level.cast("int"))
    member = common.written(member.select("id", "component", "cluster", "n_shingles", "outside", "level"), "members")

    def blocks(some: DataFrame, name: str) -> DataFrame:
        return some.groupBy("cluster", "level").agg(F.greatest(F.ceil(F.count("*") / BLOCK_ROWS), F.ceil(F.sum("n_shingles") / BLOCK_SHINGLES), F.lit(1)).cast("int").alias(name))

    wide = member.withColumn("level", F.explode(F.array(F.col("level") - 1, F.col("level"), F.col("level") + 1)))
    n = common.written(blocks(member.filter("outside"), "n_left").join(blocks(wide, "n_right"), ["cluster", "level"]), "blocks")
    own = lambda name: F.pmod(F.xxhash64("id", F.lit(name)), F.col(name)).cast("int")
    every = lambda name: F.explode(F.sequence(F.lit(0), F.col(name) - 1))
    key = ["cluster", "level", "i", "j"]
    left = member.filter("outside").join(n, ["cluster", "level"]).join(sets, "id").select("cluster", "level", "component", "set", own("n_left").alias("i"), every("n_right").alias("j"))
    right = wide.join(n, ["cluster", "level"]).join(sets, "id").select("cluster", "level", "component", "set", every("n_left").alias("i"), own("n_right").alias("j"))
    right = right.select(*[F.col(c).alias(c) for c in right.columns])  # else the two sides share column ids
    return left.groupBy(*key).cogroup(right.groupBy(*key)).applyInArrow(lambda a, b: compared(a, b, percent), "id long, to long")


def confirmed(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (id, centre, salts, ...) whose full sets (id, set) are similar enough; the member's set travels."""
    own = pairs.join(sets.withColumnRenamed("set", "__own"), "id")
    both = spread(own, sets.select(F.col("id").alias("centre"), F.col("set").alias("__other")), "centre", widths=pairs)
    shared = F.size(F.array_intersect("__own", "__other"))
    return both.filter(100 * shared >= percent * (F.size("__own") + F.size("__other") - shared)).drop("__own", "__other")


def duplicates(docs: DataFrame, size: int = SHINGLE, percent: int = PERCENT, bands: int = BANDS, rows: int = ROWS, stars: int = STARS) -> DataFrame:
    """doc_id, n_shingles, component_id (least doc_id reachable), kept; one row per row of docs."""
    key = ["n_shingles", "f1", "f2"]
    every = common.written(profiles(docs, size, bands, rows), "profiles")
    classes = every.filter("n_shingles > 0 and doc_id is not null").groupBy(*key).agg(F.min("doc_id").alias("rep"))
    classes = common.written(classes.withColumn("id", F.monotonically_increasing_id()), "classes")
    # A class's buckets come from its representative's row; equal sets have equal buckets.
    reps = every.join(classes.withColumnRenamed("rep", "doc_id"), [*key, "doc_id"]).dropDuplicates(["id"])
    member = reps.select(F.explode("buckets").alias("bucket"), "id", "n_shingles")
    shared = member.groupBy("bucket").agg(F.count("*").alias("n")).filter("n > 1").select("bucket", F.ceil(F.col("n") / SALT_ROWS).cast("int").alias("salts"))
    active = common.written(member.join(shared, "bucket"), "members")
    ids = common.written(active.select("id").distinct().join(classes, "id"), "ids")
    sets = common.written(class_sets(docs, ids, size), "sets")
    labels = tested = None
    for turn in range(stars + 1):
        now = opened(active, labels, turn)
        if now.isEmpty():
            break
        if turn == stars:
            links = common.written(blockwise(now, sets, percent).withColumn("salts", F.lit(1)), "links")
        else:
            active = now.select("bucket", "id", "n_shingles", "salts")
            pairs = common.written(one_each(now, tested, percent), "pairs")
            tested = pairs.select("id", "centre") if tested is None else tested.unionByName(pairs.select("id", "centre"))
            links = common.written(confirmed(pairs, sets, percent).select(F.col("component").alias("id"), "to", "salts"), "links")
        if not links.isEmpty():
            labels = relabelled(labels, hooked(links), links)
    least = F.col("rep")
    if labels is not None:
        # a component's own class, its smallest, is not in labels
        labels = labels.unionByName(labels.groupBy("component").agg(F.max("salts").alias("salts")).select(F.col("component").alias("id"), "component", "salts"))
        ends = labels.join(classes.select("id", "rep"), "id").groupBy("component").agg(F.min("rep").alias("least"))
        classes = classes.join(spread(labels, ends, "component").select("id", "least"), "id", "left")
        least = F.coalesce("least", "rep")
    out = every.join(classes.select(*key, least.alias("component_id")), key, "left")
    component = F.coalesce("component_id", "doc_id")
    kept = F.coalesce(F.col("doc_id") == component, component.isNull())
    return out.select("doc_id", "n_shingles", component.alias("component_id"), kept.alias("kept"))


def one_each(rows: DataFrame, tested: DataFrame | None, percent: int) -> DataFrame:
    """(id, centre, salts, component, to): for each class the centre that most of its buckets propose, of those not tested."""
    fits = 100 * F.least("n_shingles", "c.n_shingles") >= percent * F.greatest("n_shingles", "c.n_shingles")
    offers = rows.filter(F.expr("component <> c.component") & fits).groupBy("id", F.col("c.id").alias("centre"), "component", F.col("c.component").alias("to")).agg(F.count("*").alias("n"), F.max("salts").alias("salts"))
    if tested is not None:
        offers = offers.join(tested, ["id", "centre"], "left_anti")
    best = F.max(F.struct("n", (-F.col("centre")).alias("__order"), "centre", "salts", "component", "to")).alias("p")
    return offers.groupBy("id").agg(best).select("id", "p.centre", "p.salts", "p.component", "p.to")


def class_sets(docs: DataFrame, ids: DataFrame, size: int) -> DataFrame:
    """(id, set) of the classes in ids, from their representatives' texts."""

    def make():
        return lambda sets, sizes, values: sets

    some = with_ids(docs.select("doc_id", "text"), ids.select(F.col("rep").alias("doc_id")).distinct(), "left_semi")
    found = fingerprints(some, size, "set array<long>", make)
    return found.join(ids.withColumnRenamed("rep", "doc_id"), ["doc_id", "n_shingles", "f1", "f2"]).select("id", "set").dropDuplicates(["id"])


def opened(active: DataFrame, labels: DataFrame | None, turn: int) -> DataFrame:
    """Rows of the buckets that hold more than one component, with their component and the bucket's centre as ``c``.

    The centre is a member of the least component; which one changes with the turn.
    """
    at = active.withColumn("component", F.col("id")) if labels is None else active.join(labels.select("id", "component"), "id", "left").withColumn("component", F.coalesce("component", "id"))
    place = F.struct("component", F.xxhash64("id", F.lit(turn)).alias("__draw"), "id", "n_shingles")
    centre = at.groupBy("bucket").agg(F.min(place).alias("c"), F.max("component").alias("__most")).filter("c.component <> __most").drop("__most")
    return common.written(spread(at, centre, "bucket"), "open")


def numbered(docs: DataFrame) -> DataFrame:
    """The rows as __row and their text, with numbers of their own as doc_id in the order of the old ones, nulls last.

    Copies are spread by their place in the input, so that no id or text has to fit into one task.
    """
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("__row"), "text", F.monotonically_increasing_id().alias("place"))
    rows = rows.orderBy(F.col("__row.doc_id").asc_nulls_last(), F.xxhash64("text"), "place")
    return common.written(rows.select("__row", "text", F.monotonically_increasing_id().alias("doc_id")), "numbered")


def kept_rows(docs: DataFrame, size: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """The documents with one of each group left (that of the least id), all columns and no others.

    Where ids repeat or are missing, every row is judged under a number of its own.
    """
    unique = docs.groupBy("doc_id").count().filter("count > 1 or doc_id is null").isEmpty()
    rows = docs if unique else numbered(docs)
    gone = common.written(duplicates(rows, size, percent).filter("not kept").select("doc_id").distinct(), "gone")
    left = with_ids(rows, gone, "left_anti")
    return left.select(*docs.columns) if unique else left.select("__row.*").dropDuplicates(["doc_id", "text"])
