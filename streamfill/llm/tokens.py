"""Token counts by byte-pair merging with a heap over a linked list of symbols, without making identifiers.

The pair with the best rank (ties: the leftmost) is popped and merged until no pair has a rank, so the count is the
symbols at first less the merges; a symbol outside the vocabulary counts as its UTF-8 bytes. No piece of the
vocabulary has a space after another character, so merges stay within a word and its spaces before: texts are cut
there, and a task counts each different word once.
"""

from __future__ import annotations

import heapq
import re
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SPACE = "▁"
#: Words whose counts a task remembers; it forgets all and starts again beyond that.
REMEMBERED = 400_000


def read_piece_model(path: str) -> tuple[dict[str, float], frozenset[str]]:
    """(cost of each piece that merges make, least first; all pieces) of a byte-pair model with byte fallback."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    plain = [i for i in range(model.get_piece_size()) if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i) or model.is_unused(i))]
    pieces = {model.id_to_piece(i): -model.get_score(i) for i in plain}
    if any(SPACE in p.lstrip(SPACE) for p in pieces):
        raise ValueError("this vocabulary has pieces that go on after a space")
    return {p: c for p, c in pieces.items() if len(p) > 1}, frozenset(pieces)


def merge(symbols: list, rank: Callable) -> list:
    """Symbols after all merges. rank(a + b): the pair's rank, None if it has none."""
    n = len(symbols)
    after, before = list(range(1, n + 1)), list(range(-1, n - 1))
    heap = []

    def offer(i: int, k: int) -> None:
        both = symbols[i] + symbols[k]
        if (r := rank(both)) is not None:
            heapq.heappush(heap, (r, i, k, both))

    for i in range(n - 1):
        offer(i, i + 1)
    while heap:
        _, i, k, both = heapq.heappop(heap)
        if symbols[i] is None or symbols[k] is None or after[i] != k or symbols[i] + symbols[k] != both:
            continue  # one of the two has gone into another pair
        symbols[i], symbols[k] = both, None
        after[i] = after[k]
        if after[i] < n:
            before[after[i]] = i
            offer(i, after[i])
        if before[i] >= 0:
            offer(before[i], i)
    return [x for x in symbols if x is not None]


def count_word(word: str, rank: Callable, known: frozenset[str]) -> int:
    """Tokens of a word, the space before it included."""
    left = merge([SPACE, *word.replace(" ", SPACE)], rank)
    return sum(1 if x in known else len(x.encode()) for x in left)


def count_tokens(docs: DataFrame, model_path: str, limit: int = 4096, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (doc_id, n_bytes, n_tokens, over_limit), one for each row of docs.

    A null text counts as empty, with no bytes and no tokens. Repeated rows are counted each; an empty table gives
    an empty result; other columns are ignored. The vocabulary, read on the driver, is sent with the tasks.
    """
    cost, known = read_piece_model(model_path)

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rank, cut = cost.get, re.compile("(?<=[^ ]) ").split

        class Words(dict):
            def __missing__(self, word: str) -> int:
                if len(self) >= REMEMBERED:
                    self.clear()
                self[word] = n = count_word(word, rank, known)
                return n

        count = Words().__getitem__
        for batch in batches:
            sizes, totals = [], []
            for text in batch["t"].to_pylist():
                text = (text or "").replace(SPACE, " ")
                words = cut(text) if text.startswith(" ") or "  " in text else text.split(" ")
                totals.append(sum(map(count, words)) if text else 0)
            sizes = batch["b"]
            yield pa.RecordBatch.from_arrays(
                [batch["i"], sizes, pa.array(totals, pa.int64()), pa.array([n > limit for n in totals])],
                names=["doc_id", "n_bytes", "n_tokens", "over_limit"],
            )

    rows = docs.select(F.col(id_col).cast("long").alias("i"), F.coalesce(F.octet_length(text_col), F.lit(0)).cast("long").alias("b"), F.col(text_col).alias("t"))
    return rows.mapInArrow(counted, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
