"""Packing by powers of two: a document's tokens are cut into pieces whose lengths are its length in binary, and
pieces of one length share a bucket. Every piece is a sequence of its own, so none crosses documents and none needs
padding. Nothing is shuffled: a bucket is a column that a writer partitions by.
"""

from __future__ import annotations

import json
import os
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import light
from .pieces import Chunk, ragged

#: Pieces of text that are encoded in one go.
TOGETHER = 10_000
#: Characters of text in a chunk, about; the rest of a task is the vocabulary.
CHUNK = 8_000_000
#: Different texts whose ids a task holds from chunk to chunk, about; a chunk's own come on top.
HELD = 600_000
#: A word and the sign behind it. The letters are of Unicode's first version, which all libraries agree on.
WORD = r"^([A-Za-z\x{C0}-\x{D6}\x{D8}-\x{F6}\x{F8}-\x{2AF}\x{410}-\x{44F}]+)([\x00-@\[-`{-\x7F])"
SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, bucket int, ids binary"


def pieces(n: int, most: int) -> Iterator[tuple[int, int]]:
    """(start, length) of the pieces of n tokens: as many of the longest as fit, then the bits of the rest."""
    start = 0
    for start in range(0, n - n % most, most):
        yield start, most
    start, rest = n - n % most, n % most
    while rest:
        length = 1 << (rest.bit_length() - 1)
        yield start, length
        start, rest = start + length, rest - length


class Held:
    """Ids of texts, held from chunk to chunk; beyond HELD texts, those that came in one chunk only are let go, and met again
    they are encoded again. encode: texts to (their ids, how many each has)."""

    def __init__(self, encode: Callable[[list[str]], tuple[list[np.ndarray], np.ndarray]]) -> None:
        self.encode, self.made = encode, 0
        self.clear()

    def clear(self) -> None:
        self.known: dict[str, int] = {}
        self.ids = np.zeros(0, "<u4")
        self.starts, self.sizes, self.uses = (np.zeros(0, np.int64) for _ in range(3))

    def let_go(self) -> None:
        kept = np.flatnonzero(self.uses > 1)
        if len(kept) > HELD // 2:
            return self.clear()
        texts = list(self.known)
        self.known = {texts[k]: at for at, k in enumerate(kept.tolist())}
        self.ids, self.sizes = ragged(self.ids, self.starts[kept], self.sizes[kept]), self.sizes[kept]
        self.starts, self.uses = np.cumsum(self.sizes) - self.sizes, np.zeros(len(kept), np.int64)

    def places(self, texts: list[str]) -> np.ndarray:
        """Where the ids of different texts are held; those that are not yet are encoded."""
        if len(self.known) > HELD:
            self.let_go()
        new = [t for t in texts if t not in self.known]
        self.made += len(new)
        parts, sizes = self.encode(new)
        self.known.update(zip(new, range(len(self.known), len(self.known) + len(new)), strict=True))
        self.ids, self.sizes = np.concatenate([self.ids, *parts]), np.concatenate([self.sizes, sizes])
        self.starts, self.uses = np.cumsum(self.sizes) - self.sizes, np.concatenate([self.uses, np.zeros(len(new), np.int64)])
        at = np.fromiter(map(self.known.__getitem__, texts), np.int64, len(texts))
        self.uses[at] += 1
        return at


class Encoder:
    """The library's ids of pieces. A piece that is a word of letters and then a sign is cut between them, where a token of
    the pattern ends, and word and rest are encoded once each while they are held."""

    def __init__(self, definition: str) -> None:
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_str(definition)
        vocabulary = self.tokenizer.get_vocab()
        self.spaced = np.zeros(max(vocabulary.values()) + 1, bool)
        self.spaced[[k for token, k in vocabulary.items() if token.startswith("\u0120")]] = True  # the format's sign for a space
        self.specials = [t["content"] for t in json.loads(definition)["added_tokens"]]
        self.words, self.tails = Held(self.strung), Held(self.each)

    def ids_of(self, text: str) -> np.ndarray:
        return np.array(self.tokenizer.encode_batch_fast([text], add_special_tokens=False)[0].ids, "<u4")

    def each(self, texts: list[str]) -> tuple[list[np.ndarray], np.ndarray]:
        parts = [np.array(e.ids, "<u4") for k in range(0, len(texts), TOGETHER) for e in self.tokenizer.encode_batch_fast(texts[k : k + TOGETHER], add_special_tokens=False)]
        return parts, np.array([len(p) for p in parts], np.int64)

    def strung(self, texts: list[str]) -> tuple[list[np.ndarray], np.ndarray]:
        """Of plain pieces, each behind a space."""
        parts, sizes = [], [np.zeros(0, np.int64)]
        for k in range(0, len(texts), TOGETHER):
            some = texts[k : k + TOGETHER]
            own = self.ids_of(" " + " ".join(some))
            begins = np.flatnonzero(self.spaced[own])
            if len(begins) != len(some):
                raise ValueError("the vocabulary has tokens that go on after a space")
            parts.append(own)
            sizes.append(np.diff([*begins, len(own)]))
        return parts, np.concatenate(sizes)

    def encoded(self, chunk: Chunk) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(ids, where those of each piece start, how many each has)."""
        bare = np.ones(len(chunk.rests), bool)
        for special in self.specials:
            bare &= ~pc.match_substring(chunk.rests, special).to_numpy(zero_copy_only=False)
        at = np.flatnonzero(bare)
        rests = chunk.rests.take(pa.array(at))
        cut = pc.match_substring_regex(rests, WORD)
        words = pc.replace_substring_regex(rests, f"{WORD}(?s:.*)$", r"\1")
        tails = pc.if_else(cut, pc.replace_substring_regex(rests, WORD, r"\2"), "")
        fit = cut.to_numpy(zero_copy_only=False) | chunk.plain()[at]
        at, words, tails = at[fit], words.filter(pa.array(fit)).dictionary_encode(), tails.filter(pa.array(fit)).dictionary_encode()
        sizes = np.zeros((len(bare) + len(chunk.heads), 2), np.int64)
        starts, first = sizes.copy(), 0
        for side, held, texts in ((0, self.words, words), (1, self.tails, tails)):
            place = held.places(texts.dictionary.to_numpy(zero_copy_only=False).tolist())[texts.indices.to_numpy()]
            starts[at, side], sizes[at, side] = held.starts[place] + first, held.sizes[place]
            first += len(held.ids)
        parts, slow = [self.words.ids, self.tails.ids], np.ones(len(sizes), bool)
        slow[at] = False
        slow = np.flatnonzero(slow)
        own, many = self.each([" " + chunk.rests[k].as_py() if k < len(bare) else chunk.heads[k - len(bare)] for k in slow.tolist()])
        sizes[slow, 0], starts[slow, 0] = many, first + np.cumsum(many) - many
        parts += own
        flat, totals = ragged(np.concatenate(parts), starts.ravel(), sizes.ravel()), sizes.sum(axis=1)
        return flat, np.cumsum(totals) - totals, totals


def pack(docs: DataFrame, tokenizer_path: str, max_len: int = 1024, end_id: int = 0, *, with_ids: bool = True, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (doc_id, start, length, ids_crc32, doc_tokens, bucket, ids, sequence_id, offset), one for each piece.

    ids holds the piece's token ids as little-endian unsigned 32-bit numbers (null if with_ids is off); bucket is
    log2 of its length. max_len must be a power of two. Every document ends with end_id, so a null or empty text is
    one piece of one token. Repeated rows are packed each; an empty table gives an empty result; other columns
    are ignored. sequence_id is unique, and the same when a lost task runs again.

    Token ids are those of the tokenizers library. With its pattern no token spans the place before a space that
    follows another character, so texts are cut there, and a task encodes what is different in the pieces
    once while it is held (see Encoder), many of them in one call; a token that starts with a space then starts a piece.
    """
    if max_len < 1 or max_len & (max_len - 1):
        raise ValueError("max_len must be a power of two")
    with open(tokenizer_path, encoding="utf-8") as f:
        definition = f.read()
    end = end_id.to_bytes(4, "little")

    def packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from .packing import Encoder
        from .pieces import chunks, sums

        encoder = Encoder(definition)

        for chunk in chunks(batches, CHUNK):
            flat, starts, sizes = encoder.encoded(chunk)
            for first, last, places, lengths in chunk.parts():
                ids = ragged(flat, starts[places], sizes[places])
                totals = sums(sizes[places], lengths)
                out: list[list] = [[] for _ in range(7)]
                for doc, at, n in zip(chunk.ids[first:last], (np.cumsum(totals) - totals).tolist(), totals.tolist(), strict=True):
                    whole = ids[at : at + n].tobytes() + end
                    for start, length in pieces(n + 1, max_len):
                        own = whole[4 * start : 4 * (start + length)]
                        for column, value in zip(out, (doc, start, length, zlib.crc32(own), n + 1, length.bit_length() - 1, own if with_ids else None), strict=True):
                            column.append(value)
                types = [pa.int64()] * 5 + [pa.int32(), pa.binary()]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, types, strict=True)], names=["doc_id", "start", "length", "ids_crc32", "doc_tokens", "bucket", "ids"])

    rows = docs.select(F.col(id_col).cast("long").alias("i"), F.col(text_col).alias("t"))
    return rows.mapInArrow(light(packed), SCHEMA).withColumns({"sequence_id": F.monotonically_increasing_id(), "offset": F.lit(0).cast("long")})


def write_buckets(packed: DataFrame, path: str) -> None:
    """Sequences in one folder a length, so that a batch is read from one bucket and needs no padding."""
    packed.write.partitionBy("bucket").parquet(path)
