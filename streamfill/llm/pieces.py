"""Documents as lists of places among their different pieces, by Arrow's kernels: what the tokenizing operators share.

A text is cut before every space that follows a character that is no white space; a piece is what lies between, with
the space before it. No token of a byte-level vocabulary goes across such a cut, so a task tokenizes each different
piece of a chunk once.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Characters of text in a chunk, about; they bound a task's memory.
CHUNK = 24_000_000
#: Pieces of documents that are put together at a time, about.
TAKEN = 1 << 20


@dataclass
class Chunk:
    """The pieces are `rests` (without the space before them), then `heads`, that start a text; document k is the
    next lengths[k] of places. Null and empty texts have no pieces."""

    ids: list
    rests: pa.Array
    heads: list[str]
    places: np.ndarray
    lengths: np.ndarray

    def plain(self) -> np.ndarray:
        """Which of rests have no space inside and no white space at the end: strung together, each is found again by
        the space before it."""
        odd = pc.or_(pc.match_substring(self.rests, " "), pc.not_equal(self.rests, pc.utf8_rtrim_whitespace(self.rests)))
        return ~odd.to_numpy(zero_copy_only=False) & (pc.utf8_length(self.rests).to_numpy() > 0)

    def parts(self) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
        """(first, past the last, places, lengths) of so many documents at a time."""
        yield from in_parts(self.places, self.lengths)


def in_parts(places: np.ndarray, lengths: np.ndarray) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    ends, first = np.concatenate([[0], np.cumsum(lengths)]), 0
    while first < len(lengths):
        last = max(first + 1, int(np.searchsorted(ends, ends[first] + TAKEN, "right")) - 1)
        yield first, last, places[ends[first] : ends[last]], lengths[first:last]
        first = last


def ragged(values: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """values[start : start + size] of each, one after another."""
    ends = np.cumsum(sizes)
    return values[np.arange(ends[-1] if len(ends) else 0) + np.repeat(starts - (ends - sizes), sizes)]


def sums(values: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The sums of so many values at a time."""
    return np.diff(np.concatenate([[0], np.cumsum(values)])[np.concatenate([[0], np.cumsum(sizes)])])


def chunks(batches: Iterator[pa.RecordBatch], size: int = CHUNK) -> Iterator[Chunk]:
    """Chunks of batches of (i, t). Documents come in another order: those with a space after white space, which is no
    place to cut, are last."""
    cut, odd = re.compile(r"(?<=\S) ").split, re.compile(r"\s ").search

    def made(ids: list, texts: list[str], odd_ids: list, odd_texts: list[str]) -> Chunk:
        parts = [pc.split_pattern(pa.array(texts, pa.large_string()), " "), pa.array([cut(t) for t in odd_texts], pa.large_list(pa.large_string()))]
        lengths = np.concatenate([pc.list_value_length(x).to_numpy() for x in parts]).astype(np.int64)
        flat, starts = pa.concat_arrays([x.flatten() for x in parts]), np.cumsum(lengths) - lengths
        behind = np.ones(len(flat), bool)
        behind[starts] = False
        rests = flat.filter(pa.array(behind)).dictionary_encode()
        heads = flat.take(pa.array(starts))
        filled = pc.greater(pc.binary_length(heads), 0).to_numpy(zero_copy_only=False)  # before a first space is no piece
        heads = heads.dictionary_encode()
        places = np.empty(len(flat), np.int32)
        places[behind], places[starts] = rests.indices.to_numpy(), heads.indices.to_numpy() + len(rests.dictionary)
        behind[starts] = filled  # from here on: what counts
        return Chunk([*ids, *odd_ids], rests.dictionary, heads.dictionary.to_pylist(), places[behind], lengths - ~filled)

    held: tuple[list, list, list, list] = ([], [], [], [])
    total = 0
    for batch in batches:
        for doc, text in zip(batch["i"].to_pylist(), batch["t"].to_pylist(), strict=True):
            text = text or ""
            way = 2 if odd(text) else 0
            held[way].append(doc)
            held[way + 1].append(text)
            total += len(text)
            if total >= size:
                yield made(*held)
                held, total = ([], [], [], []), 0
    if held[0] or held[2]:
        yield made(*held)
