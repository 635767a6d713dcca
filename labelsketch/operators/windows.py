"""The graph of successive windows of k characters of whole texts, for texts of any alphabet.

An inner string w of k - 1 characters, with the character c before it and d after it, stands for the edge from window cw to
window wd. A window's number is its rank in character order. Among the windows that begin with c that is the rank of what
follows, and among those that begin with w the rank of d: so records that are cut into ranges of w, and sorted there, give both
numbers up to offsets, which are a count for each range and character. Windows are never joined with their numbers.

Records cross one shuffle, sorted, packed and without copies, in passes over ranges of w; what a pass leaves is a few bits
an edge, and numbers are made of it where the result is read.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..store import written

#: Windows of a pass and of a range, about; records that a task sorts at once; characters that it packs at once.
PASS_WINDOWS, RANGE_WINDOWS, SORT_ROWS, PIECE = 600_000_000, 4_000_000, 4_000_000, 1 << 20
#: One window in so many is looked at to place the ranges; results don't depend on it.
SAMPLE = 2048
#: Edges of an Arrow batch of the result.
OUT_ROWS = 1 << 15
#: A pass's shuffle files go when it ends; left to the driver's garbage collection, two passes' lie side by side.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"

U = np.uint64


class Layout:
    """How a record's characters (w, then c, then d) lie in 64-bit words, in order; 0 stands for no character."""

    def __init__(self, alphabet: np.ndarray, k: int):
        self.alphabet, self.k, self.b = alphabet, k, max(1, int(len(alphabet)).bit_length())
        per = 64 // self.b
        places = [*range(1, k), 0, k]  # from c's place in the text
        self.words = [places[i : i + per] for i in range(0, k + 1, per)]
        self.bits = [self.b * len(w) for w in self.words]
        self.kind = np.uint8 if self.b <= 8 else np.uint16 if self.b <= 16 else np.uint32

    def codes(self) -> np.ndarray:
        """By code point, its rank in the alphabet from 1."""
        table = np.zeros(0x110000, self.kind)
        table[self.alphabet] = np.arange(1, len(self.alphabet) + 1)
        return table

    def char(self, words: list[np.ndarray], place: int) -> np.ndarray:
        for word, places in zip(words, self.words):
            if place in places:
                return word >> U(self.b * (len(places) - 1 - places.index(place))) & U((1 << self.b) - 1)
        raise ValueError(place)

    def bound(self, w: str) -> tuple[int, ...]:
        """The words of w with no character beside it: not above any record of w."""
        code = {int(c): i + 1 for i, c in enumerate(self.alphabet)}
        at = [0, *(code[ord(x)] for x in w), 0]
        out = []
        for places in self.words:
            value = 0
            for p in places:
                value = value << self.b | at[p]
            out.append(value)
        return tuple(out)

    def pack(self, words: list[np.ndarray]) -> bytes:
        """A plane of bytes for each place, compressed."""
        planes = [self.char(words, p).astype(self.kind).tobytes() for places in self.words for p in places]
        return pa.compress(b"".join(planes), codec="zstd", asbytes=True)

    def unpack(self, data: bytes, n: int) -> list[np.ndarray]:
        size = n * (self.k + 1) * np.dtype(self.kind).itemsize
        planes, out, i = np.frombuffer(pa.decompress(data, size, codec="zstd", asbytes=True), self.kind).reshape(self.k + 1, n), [], 0
        for places in self.words:
            word = np.zeros(n, U)
            for _ in places:
                word = word << U(self.b) | planes[i]
                i += 1
            out.append(word)
        return out


def first_of(sorted_values: np.ndarray) -> np.ndarray:
    """Which values differ from the one before."""
    out = np.ones(len(sorted_values), bool)
    np.not_equal(sorted_values[1:], sorted_values[:-1], out=out[1:])
    return out


def regroup(pieces: list[tuple[np.ndarray, int]], widths: list[int]) -> list[np.ndarray]:
    """The same bits in columns of other widths; pieces are columns with theirs."""
    pieces, out = list(pieces), []
    for want in widths:
        value, got = None, 0
        while got < want:
            piece, n = pieces.pop(0)
            if n > want - got:
                low = n - (want - got)
                pieces.insert(0, (piece & U((1 << low) - 1), low))
                piece, n = piece >> U(low), n - low
            value, got = piece if value is None else value << U(n) | piece, got + n
        out.append(value)
    return out


def sort_distinct(words: list[np.ndarray], bits: list[int]) -> list[np.ndarray]:
    """The distinct records in order.

    As many leading bits as fit beside a row's number are sorted; their ranks, which are short, then stand for them.
    """
    if not (rows := len(words[0])):
        return words
    index, rest = max(1, (rows - 1).bit_length()), list(zip(words, bits))
    levels: list[tuple[np.ndarray | None, int]] = []  # what the ranks of a key stand for, and its bits behind the rank
    above, rank, have = None, None, 0
    while have + (left := sum(n for _, n in rest)) > 64:
        take = 64 - index - have
        widths = [take, *[64] * ((left - take) // 64), *filter(None, [(left - take) % 64])]
        key, *others = regroup(rest, widths)
        key = (key if rank is None else rank << U(take) | key) << U(index)
        key |= np.arange(rows, dtype=U)
        key.sort()
        order = (key & U((1 << index) - 1)).astype(np.int64)
        key >>= U(index)
        new = first_of(key)
        levels.append((above, take))
        above = key[new]
        rank, have = (np.cumsum(new) - 1).astype(U), max(1, (len(above) - 1).bit_length())
        rest = [(v[order], n) for v, n in zip(others, widths[1:])]
        del key, others, order
    key = regroup(rest, [left])[0]
    key = np.sort(key if rank is None else rank << U(left) | key)
    key = key[first_of(key)]
    levels.append((above, left))
    pieces = []
    for above, n in reversed(levels):
        pieces.append((key & U((1 << n) - 1), n))
        if above is not None:
            key = above[(key >> U(n)).astype(np.int64)]
    return regroup(pieces[::-1], bits)


def grams(x: np.ndarray, n: int, b: int) -> np.ndarray:
    """Every n successive codes in one word."""
    if n == 1:
        return x
    half = grams(x, n // 2, b)
    both = half[: len(half) - n // 2] << U(b * (n // 2)) | half[n // 2 :]
    return both[:-1] << U(b) | x[n - 1 :] if n % 2 else both


def runs(places: list[int]) -> list[tuple[int, int]]:
    """First and length of each run of successive places."""
    out: list[tuple[int, int]] = []
    for p in places:
        if out and p == sum(out[-1]):
            out[-1] = (out[-1][0], out[-1][1] + 1)
        else:
            out.append((p, 1))
    return out


def text_pieces(batches: Iterable[pa.RecordBatch], k: int) -> Iterator[str]:
    """Texts of over k characters that are not one character throughout, cut so that each k + 1 characters lie in a piece.

    What a cut adds, a window with nothing before or behind it, is a window of the text anyway.
    """
    for batch in batches:
        for value in batch.column(0):
            text = value.as_py()
            if text is not None and len(text) > k and (text[0] != text[-1] or text.count(text[0]) < len(text)):
                for a in range(0, len(text) - k, PIECE):
                    yield text[a : a + PIECE + k]


def blocks(pieces: Iterable[str]) -> Iterator[list[str]]:
    held, size = [], 0
    for piece in pieces:
        held.append(piece)
        size += len(piece)
        if size >= PIECE:
            yield held
            held, size = [], 0
    if held:
        yield held


def points(pieces: list[str]) -> np.ndarray:
    """Code points of the pieces, with a place before, between and behind them."""
    return np.frombuffer(("\0" + "\0".join(pieces) + "\0").encode("utf-32-le", "surrogatepass"), np.uint32)


def gaps(pieces: list[str]) -> np.ndarray:
    return np.concatenate([[0], np.cumsum([len(p) + 1 for p in pieces])])


def look(k: int):
    """Of each task: the code points of its texts, how many windows they have, and some inner strings."""

    def run(batches):
        seen, windows, some = np.zeros(0x110000, bool), 0, []
        for held in blocks(text_pieces(batches, k)):
            for piece in held:
                some += [piece[i : i + k - 1] for i in range(-windows % SAMPLE, len(piece) - k, SAMPLE)]
                windows += len(piece) - k + 1
            raw = points(held).copy()
            raw[gaps(held)] = raw[1]
            seen[raw] = True
        yield pa.RecordBatch.from_arrays([pa.array([np.flatnonzero(seen).astype(np.int32)], pa.list_(pa.int32())), pa.array([windows], pa.int64()), pa.array([some], pa.list_(pa.string()))], ["points", "windows", "some"])

    return run


def turned(x: np.ndarray, held: list[str], k: int) -> list[str]:
    """For strings of k + 1 characters that swap two, the greater one first: the same with the less one first.

    Both are the same undirected edge; the second stands for it.
    """
    same = np.flatnonzero(x[:-2] == x[2:])
    if len(same) < k - 1:
        return []
    at = same[: len(same) - k + 2][same[k - 2 :] - same[: len(same) - k + 2] == k - 2]
    at = at[x[at] > x[at + 1]]
    if not len(at):
        return []
    raw = points(held)
    return [(chr(a) + chr(b)) * (k // 2 + 1) for a, b in sorted({(int(raw[i + 1]), int(raw[i])) for i in at if x[i + 1]})]


def cut(layout: Layout, bounds: list[str], first: int, last: int):
    """Packed records of the ranges from first to before last, by range; range i ends before bounds[i]."""
    k, b = layout.k, layout.b
    low = layout.bound(bounds[first - 1]) if first else None
    ends = [layout.bound(w) for w in bounds[first : min(last, len(bounds))]]

    def records(table: np.ndarray, held: list[str], again: bool = True) -> Iterator[list[np.ndarray]]:
        x, gap = table[points(held)].astype(U), gaps(held)
        x[gap] = 0
        n = len(x) - k
        packed = {m: grams(x, m, b) for m in {m for places in layout.words for _, m in runs(places)}}

        def word(j: int, at=slice(None)) -> np.ndarray:
            out = None
            for p, m in runs(layout.words[j]):
                value = packed[m][p : p + n][at]
                out = value if out is None else out << U(b * m) | value
            return out

        head, valid = word(0), np.ones(n, bool)
        for j in range(1, k):  # an inner string has no gap
            there = gap - j
            valid[there[(there >= 0) & (there < n)]] = False
        if low:
            valid &= head >= U(low[0])
        if last <= len(bounds):
            valid &= head <= U(ends[-1][0])
        at = np.flatnonzero(valid)
        yield [head[at], *(word(j, at) for j in range(1, len(layout.words)))]
        if again and (more := turned(x, held, k)):
            yield from records(table, more, False)

    def sliced(found: list[list[np.ndarray]]) -> Iterator[pa.RecordBatch]:
        words = sort_distinct([np.concatenate(v) for v in zip(*found)], layout.bits)

        def place(bound: tuple[int, ...]) -> int:
            a, z = 0, len(words[0])
            for word, value in zip(words, bound):
                a, z = a + int(np.searchsorted(word[a:z], U(value), "left")), a + int(np.searchsorted(word[a:z], U(value), "right"))
            return a

        at = [place(low) if low else 0, *map(place, ends)]
        if last > len(bounds):
            at.append(len(words[0]))
        for i, (a, z) in enumerate(zip(at, at[1:])):
            if z > a:
                yield pa.RecordBatch.from_arrays([pa.array([first + i], pa.int32()), pa.array([z - a], pa.int64()), pa.array([layout.pack([w[a:z] for w in words])], pa.binary())], ["r", "n", "data"])

    def run(batches):
        table, found, size = layout.codes(), [], 0
        for held in blocks(text_pieces(batches, k)):
            for words in records(table, held):
                found.append(words)
                size += len(words[0])
            if size >= SORT_ROWS:
                yield from sliced(found)
                found, size = [], 0
        if size:
            yield from sliced(found)

    return run


def small(values: np.ndarray) -> bytes:
    """Integers in the narrowest type that holds them, compressed; the type comes first."""
    low, high = (int(values.min()), int(values.max())) if len(values) else (0, 0)
    kind = next(t for t in ("i1", "i2", "i4", "i8") if np.iinfo(t).min <= low and high <= np.iinfo(t).max)
    return kind.encode() + pa.compress(values.astype(kind).tobytes(), codec="zstd", asbytes=True)


def unsmall(data: bytes, n: int) -> np.ndarray:
    kind = np.dtype(data[:2].decode())
    return np.frombuffer(pa.decompress(data[2:], n * kind.itemsize, codec="zstd", asbytes=True), kind)


RANGE = "r int, n long, before binary, flags binary, steps binary, starts binary, windows long"


def number(layout: Layout):
    """Of a range: its records in order as c, whether cw is new, whether it is an edge, and the step to the rank of wd; the
    windows cw by c (starts) and all windows wd."""
    k, b = layout.k, layout.b

    def run(key, group):
        held, size = [], 0
        for n, data in zip(group.column("n").to_pylist(), group.column("data")):
            held.append(layout.unpack(data.as_py(), n))
            size += n
            if size >= 3 * SORT_ROWS:
                held = [sort_distinct([np.concatenate(v) for v in zip(*held)], layout.bits)]
                size = len(held[0][0]) if len(held[0][0]) < 2 * SORT_ROWS else 0
        words = sort_distinct([np.concatenate(v) for v in zip(*held)], layout.bits)
        del held
        before, behind = layout.char(words, 0), layout.char(words, k)
        inner = np.zeros(len(before), bool)
        for word, places in zip(words, layout.words):
            if ends := sum(p in (0, k) for p in places):
                word = word >> U(b * ends) if len(places) > ends else None
            if word is not None:
                inner |= first_of(word)
        inner[:1] = True
        start = (inner | first_of(before)) & (before > 0)

        edge, one = (before > 0) & (behind > 0), layout.char(words, 1)
        swap = np.flatnonzero(before >= one)  # all of c and w's first character by turns: a loop, or turned
        for p in range(2, k + 1):
            swap = swap[layout.char([w[swap] for w in words], p) == (one if p % 2 else before)[swap]]
        edge[swap] = False

        some = np.flatnonzero(behind)
        value = ((np.cumsum(inner) - 1).astype(U) << U(b) | behind)[some]
        order = np.argsort(value)
        new = first_of(value[order])
        rank = np.empty(len(some), np.int64)
        rank[order] = np.cumsum(new) - 1
        steps = np.zeros(len(before), np.int64)
        steps[some] = np.diff(rank, prepend=0)
        starts = np.bincount(before[start].astype(np.int64), minlength=len(layout.alphabet) + 1)
        return pa.table({
            "r": pa.array([group.column("r")[0].as_py()], pa.int32()), "n": pa.array([len(before)], pa.int64()), "before": pa.array([small(before.astype(np.int64))], pa.binary()),
            "flags": pa.array([small(start + 2 * edge.astype(np.int8))], pa.binary()), "steps": pa.array([small(steps)], pa.binary()),
            "starts": pa.array([small(starts)], pa.binary()), "windows": pa.array([int(new.sum())], pa.int64()),
        })

    return run


def edges_out(start_at: dict[int, np.ndarray], window_at: dict[int, int]):
    """Both directions of each edge of the ranges, with the ranks from which a range's own start."""

    def run(batches):
        for batch in batches:
            for row in batch.to_pylist():
                n = row["n"]
                before, flags = unsmall(row["before"], n), unsmall(row["flags"], n)
                order = np.argsort(before, kind="stable")
                count = np.cumsum(flags[order] & 1)
                held = before[order]
                head = np.flatnonzero(first_of(held))
                base = np.zeros(len(start_at[row["r"]]), np.int64)
                base[held[head]] = count[head] - (flags[order[head]] & 1)
                rank = np.empty(n, np.int64)
                rank[order] = count - 1 + (start_at[row["r"]] - base)[held]
                some = np.flatnonzero(flags & 2)
                a, z = rank[some], (np.cumsum(unsmall(row["steps"], n), dtype=np.int64) + window_at[row["r"]])[some]
                del order, count, held, rank
                for i in range(0, len(some), OUT_ROWS):
                    x, y = a[i : i + OUT_ROWS], z[i : i + OUT_ROWS]
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([x, y])), pa.array(np.concatenate([y, x]))], ["src", "dst"])

    return run


def window_graph(texts: DataFrame, column: str, k: int) -> DataFrame:
    """EDGE_SCHEMA: successive, different windows of k characters of every text, numbered in byte order, weight 1."""
    if k < 2:
        raise ValueError("windows have two characters or more")
    spark, texts = texts.sparkSession, texts.select(column).filter(F.length(column) > k)
    found = texts.mapInArrow(look(k), "points array<int>, windows long, some array<string>").collect()
    alphabet, windows = np.array(sorted({p for row in found for p in row.points}), np.int64), sum(row.windows for row in found)
    if not windows:
        return spark.createDataFrame([], "src long, dst long, weight double")
    layout, some = Layout(alphabet, k), sorted(w for row in found for w in row.some)
    ranges = max(-(-windows // RANGE_WINDOWS), min(16, -(-windows // (RANGE_WINDOWS // 16))))
    bounds = sorted({some[i * len(some) // ranges] for i in range(1, ranges)})
    passes = -(-windows // PASS_WINDOWS)
    turns = [(len(bounds) + 1) * i // passes for i in range(passes + 1)]

    parts, kept = None, spark.conf.get(CLEANUP, "false")
    spark.conf.set(CLEANUP, "true")
    try:
        for first, last in zip(turns, turns[1:]):
            if first < last:
                part = written(texts.mapInArrow(cut(layout, bounds, first, last), "r int, n long, data binary").groupBy("r").applyInArrow(number(layout), RANGE), "windows")
                parts = part if parts is None else parts.unionByName(part)
    finally:
        spark.conf.set(CLEANUP, kept)

    totals = sorted(parts.select("r", "starts", "windows").collect())
    starts = np.array([unsmall(bytes(row.starts), len(alphabet) + 1) for row in totals], np.int64).reshape(len(totals), -1)
    every = starts.sum(axis=0)
    offsets = np.cumsum(starts, axis=0) - starts + np.cumsum(every) - every
    window_at, total = {}, 0
    for row in totals:
        window_at[row.r] = total
        total += row.windows
    if total != every.sum():
        raise RuntimeError(f"{total} windows by their beginning, {every.sum()} by their end")
    return parts.mapInArrow(edges_out({row.r: offsets[i] for i, row in enumerate(totals)}, window_at), "src long, dst long").withColumn("weight", F.lit(1.0))
