"""Token counts by byte-pair merging over a heap and a linked list, for sentencepiece BPE models with byte fallback.

The lowest-rank adjacent pair is popped again and again; the count is the number of initial symbols minus the merges, and
no identifiers are made. Text is first cut where no piece of the vocabulary can reach across, and the counts of such
segments are kept in a bounded memo, so that a corpus pays for its distinct segments.

Nulls and empty texts have 0 tokens. Special strings in a text are ordinary text, as the library's default has it. Very
long texts cost n log n. Repeated rows count alike, extra columns are ignored, an empty table gives an empty result.
"""

from __future__ import annotations

import heapq
import re

from pyspark.sql import DataFrame
from pyspark.sql import types as T

from . import common

#: Segments that a worker remembers; beyond it the memo starts anew.
MEMO = 1_500_000
SPACE = "▁"


def piece_scores(path: str) -> tuple[dict[str, float], set[str]]:
    """(score of every ordinary piece, all ordinary single-character pieces) of a sentencepiece model."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    scores = {}
    for i in range(model.get_piece_size()):
        if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i) or model.is_unused(i)):
            scores[model.id_to_piece(i)] = model.get_score(i)
    return scores, {p for p in scores if len(p) == 1}


def merged_count(text: str, scores: dict[str, float], single: set[str]) -> int:
    """Tokens of one segment: symbols minus merges; a character that the vocabulary lacks costs its UTF-8 bytes."""
    symbol = list(text)
    n = len(symbol)
    extra = 0
    for x in symbol:
        if x not in single:
            extra += len(x.encode("utf-8", "replace")) - 1
    right, left = list(range(1, n + 1)), list(range(-1, n - 1))
    heap = []
    get = scores.get
    for i in range(n - 1):
        if (rank := get(symbol[i] + symbol[i + 1])) is not None:
            heap.append((-rank, i, i + 1, symbol[i] + symbol[i + 1]))
    heapq.heapify(heap)
    merges = 0
    while heap:
        _, i, j, piece = heapq.heappop(heap)
        if symbol[i] is None or symbol[j] is None or right[i] != j or len(symbol[i]) + len(symbol[j]) != len(piece):
            continue  # one of its sides has been merged since
        symbol[i], symbol[j] = piece, None
        merges += 1
        right[i] = after = right[j]
        if after < n:
            left[after] = i
            if (rank := get(piece + symbol[after])) is not None:
                heapq.heappush(heap, (-rank, i, after, piece + symbol[after]))
        before = left[i]
        if before >= 0 and (rank := get(symbol[before] + piece)) is not None:
            heapq.heappush(heap, (-rank, before, i, symbol[before] + piece))
    return n - merges + extra


class Segments(dict):
    """Memo of segment counts."""

    def __init__(self, path: str):
        super().__init__()
        self.scores, self.single = piece_scores(path)
        inside = {p for p in self.scores if SPACE in p[1:]}
        if any(set(p) != {SPACE} for p in inside):
            raise ValueError("a piece crosses a word boundary; this cutting rule doesn't hold for the model")
        joined = {c for p in self.scores if len(p) > 1 for c in p}
        self.alone = {c: 1 if c in self.single else None for c in "\n\t" if c not in joined}
        if len(self.alone) != 2:
            raise ValueError("line ends or tabs are part of pieces; this cutting rule doesn't hold for the model")
        self.cut = re.compile(r" *[^ \n\t]+| +|[\n\t]")

    def __missing__(self, segment: str) -> int:
        if len(self) >= MEMO:
            self.clear()
        self[segment] = n = merged_count(segment.replace(" ", SPACE), self.scores, self.single)
        return n

    def count(self, text: str | None) -> int:
        """The model's normaliser puts a blank in front and writes blanks as SPACE, so the two are the same to it."""
        return sum(map(self.__getitem__, self.cut.findall(" " + text.replace(SPACE, " ")))) if text else 0


KNOWN: dict[str, Segments] = {}


def counter(path: str) -> Segments:
    """One per worker process and model."""
    if path not in KNOWN:
        KNOWN[path] = Segments(path)
    return KNOWN[path]


def token_counts(docs: DataFrame, model_path: str, limit: int = 4096) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit of every text."""

    def make():
        memo = counter(model_path)

        def work(texts: list[str | None]) -> list:
            n = [memo.count(x) for x in texts]
            return [[len(x.encode("utf-8", "replace")) if x else 0 for x in texts], n, [k > limit for k in n]]

        return work

    fields = [T.StructField("n_bytes", T.LongType()), T.StructField("n_tokens", T.LongType()), T.StructField("over_limit", T.BooleanType())]
    return common.map_texts(docs, ["doc_id"], ["text"], fields, make)
