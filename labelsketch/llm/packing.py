"""Packing into fixed windows by Karmarkar-Karp multiway differencing.

Every document is tokenised whole, with an end id behind it. Full windows are cut off first; the tail is cut into pieces
of at most ``TAIL`` ids. Those cuts depend on the document alone, so tokenising and checksums need one pass and only small
piece rows are shuffled. Tails are then differenced, block by block: each piece starts as a partial partition with one
filled window; the two partial partitions of the largest spread are merged with their imbalances opposed, until one is
left. If its fullest window exceeds the capacity, the window count rises and the block is done again.

Nulls and empty texts are a document of the end id alone. Very long texts give many full windows. Repeated rows are
packed one by one, extra columns are ignored, an empty table gives an empty result. Blocks hold at most ``BLOCK`` pieces
whatever the keys are, and their order comes from the rows alone, so a task that runs again gives the same windows.
"""

from __future__ import annotations

import heapq
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import common

CAPACITY = 1024
#: Ids of a tail piece at most: an eighth of a window, so that a window takes many pieces and the sums come out near equal.
TAIL = 128
#: Tail pieces that are differenced together at most.
BLOCK = 6000
END_ID = 0
#: Characters up to here are split alike by both libraries' patterns (their Unicode tables may differ beyond).
PLAIN = re.compile(r"[^\x00-ɏ]")


class Tokens:
    """ids of the byte-level vocabulary: the fast library where both give the same ids, else the one that owns the file."""

    def __init__(self, path: str):
        import json

        from tokenizers import Tokenizer

        self.own = Tokenizer.from_file(path)
        spec = json.load(open(path, encoding="utf-8"))
        self.special = [x["content"] for x in spec.get("added_tokens", [])]
        self.fast = self._fast(spec)

    @staticmethod
    def _fast(spec: dict):
        """The same vocabulary for the other library, if it is plain byte-level BPE with the usual pattern."""
        import public_tokenizers
        import tiktoken

        kind = spec.get("pre_tokenizer") or {}
        if kind.get("type") != "ByteLevel" or kind.get("add_prefix_space") or spec.get("normalizer"):
            return None
        visible = [*range(33, 127), *range(161, 173), *range(174, 256)]
        byte_of = {chr(b): b for b in visible} | {chr(256 + i): b for i, b in enumerate(b for b in range(256) if b not in visible)}
        added = {x["content"] for x in spec.get("added_tokens", [])}
        ranks = {bytes(byte_of[c] for c in piece): i for piece, i in spec["model"]["vocab"].items() if piece not in added}
        return tiktoken.Encoding("corpus", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})

    def ids(self, text: str) -> np.ndarray:
        if self.fast is not None and not PLAIN.search(text) and not any(s in text for s in self.special):
            return np.array(self.fast.encode_ordinary(text), np.uint32)
        return np.array(self.own.encode(text, add_special_tokens=False).ids, np.uint32)


KNOWN: dict[str, Tokens] = {}


def tokens(path: str) -> Tokens:
    if path not in KNOWN:
        KNOWN[path] = Tokens(path)
    return KNOWN[path]


def cuts(n: int, capacity: int, tail: int) -> list[tuple[int, int]]:
    """(start, length) of the pieces of a document of n ids: full windows, then pieces of ``tail`` and what is left."""
    full = n // capacity
    found = [(i * capacity, capacity) for i in range(full)]
    rest = n - full * capacity
    found += [(n - rest + i, min(tail, rest - i)) for i in range(0, rest, tail)]
    return found


PIECES = T.ArrayType(T.StructType([T.StructField("start", T.LongType()), T.StructField("length", T.LongType()), T.StructField("ids_crc32", T.LongType()), T.StructField("ids", T.BinaryType())]))


def pieces(docs: DataFrame, tokenizer_path: str, capacity: int = CAPACITY, tail: int = TAIL, with_ids: bool = False) -> DataFrame:
    """doc_id, doc_tokens, start, length, ids_crc32: one row per piece; and its ids, little-endian unsigned 32-bit, if wanted."""

    def make():
        coder = tokens(tokenizer_path)

        def work(texts: list[str | None]) -> list:
            found, sizes = [], []
            for text in texts:
                ids = np.append(coder.ids(text or ""), np.uint32(END_ID)).astype("<u4")
                sizes.append(len(ids))
                raw = ((a, n, ids[a : a + n].tobytes()) for a, n in cuts(len(ids), capacity, tail))
                found.append([{"start": a, "length": n, "ids_crc32": zlib.crc32(x), "ids": x if with_ids else None} for a, n, x in raw])
            return [found, sizes]

        return work

    made = common.map_texts(docs, ["doc_id"], ["text"], [T.StructField("pieces", PIECES), T.StructField("doc_tokens", T.LongType())], make)
    made = made.select("doc_id", "doc_tokens", F.inline("pieces"))
    return made if with_ids else made.drop("ids")


def difference(sizes: np.ndarray, windows: int) -> np.ndarray:
    """Window of each item, by multiway differencing into ``windows`` near-equal windows.

    A partial partition is its vector of window sums in ascending order, less the smallest; one of a single item has one
    filled window. Merging adds the largest sums of one to the smallest of the other.
    """
    n = len(sizes)
    if windows == 1:
        return np.zeros(n, np.int64)
    single = np.zeros(windows, np.int64)
    heap, sums = [], {}
    for i, s in enumerate(sizes.tolist()):
        heap.append((-s, i))
    heapq.heapify(heap)
    built: list[tuple[int, int, np.ndarray]] = []  # node n + k: two nodes and the order of its windows
    while len(heap) > 1:
        _, a = heapq.heappop(heap)
        _, b = heapq.heappop(heap)
        vectors = []
        for node in (a, b):
            if node < n:
                vector = single.copy()
                vector[-1] = sizes[node]
            else:
                vector = sums.pop(node)
            vectors.append(vector)
        total = vectors[0] + vectors[1][::-1]
        order = np.argsort(total, kind="stable")
        total = total[order]
        total -= total[0]
        node = n + len(built)
        sums[node] = total
        built.append((a, b, order.astype(np.int32)))
        heapq.heappush(heap, (-int(total[-1]), node))
    window = np.zeros(n, np.int64)
    place = {n + len(built) - 1: np.arange(windows)}  # of a node's windows, in its own order: the final windows
    for k in range(len(built) - 1, -1, -1):
        a, b, order = built[k]
        own = place.pop(n + k)
        before = np.empty(windows, np.int64)
        before[order] = own
        for node, where in ((a, before), (b, before[::-1])):
            if node < n:
                window[node] = where[-1]
            else:
                place[node] = where
    return window


def pack(sizes: np.ndarray, capacity: int) -> np.ndarray:
    """Window of each item; the window count starts at its lower bound and rises whenever a window overflows."""
    if not len(sizes):
        return np.zeros(0, np.int64)
    windows = max(1, -(-int(sizes.sum()) // capacity))
    while True:
        found = difference(sizes, windows) if windows < len(sizes) else np.arange(len(sizes))
        if np.bincount(found, sizes).max() <= capacity:
            return found
        windows += max(1, windows // 256)


def sequences(found: DataFrame, capacity: int = CAPACITY, block: int = BLOCK) -> DataFrame:
    """Adds sequence_id and offset to piece rows. Windows never cross a task; ids are the task's number and a counter."""
    schema = T.StructType([*found.schema.fields, T.StructField("sequence_id", T.LongType()), T.StructField("offset", T.LongType())])
    names = found.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        serial = TaskContext.get().partitionId() << 36

        def close(table: pa.Table) -> Iterator[pa.RecordBatch]:
            nonlocal serial
            sizes = table.column("length").to_numpy()
            full = sizes >= capacity
            window = np.empty(len(sizes), np.int64)
            tails = pack(sizes[~full], capacity)
            window[~full] = tails
            used = int(tails.max()) + 1 if len(tails) else 0
            window[full] = used + np.arange(int(full.sum()))
            order = np.argsort(window, kind="stable")
            ends = np.cumsum(sizes[order])
            first = np.r_[True, np.diff(window[order]) != 0] if len(order) else np.zeros(0, bool)
            base = np.maximum.accumulate(np.where(first, ends - sizes[order], 0))
            out = table.take(pa.array(order))
            out = out.append_column("sequence_id", pa.array(serial + window[order])).append_column("offset", pa.array(ends - sizes[order] - base))
            serial += used + int(full.sum())
            yield from out.to_batches()

        held: list[pa.RecordBatch] = []
        rows = 0
        for batch in batches:
            at = 0
            while at < batch.num_rows:
                part = batch.slice(at, block - rows)
                held.append(part)
                at += part.num_rows
                rows += part.num_rows
                if rows >= block:
                    yield from close(pa.Table.from_batches(held))
                    held, rows = [], 0
        if held:
            yield from close(pa.Table.from_batches(held))

    order = [c for c in ("doc_id", "start", "length", "ids_crc32", "doc_tokens") if c in names]
    dealt = found.repartition(F.xxhash64(*order)).sortWithinPartitions(F.xxhash64(*order), *order)
    return dealt.mapInArrow(run, schema)


def packed(docs: DataFrame, tokenizer_path: str, capacity: int = CAPACITY, tail: int = TAIL, with_ids: bool = False) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset, and ids if wanted."""
    made = sequences(pieces(docs, tokenizer_path, capacity, tail, with_ids), capacity)
    return made.select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", *(["ids"] if with_ids else []))
