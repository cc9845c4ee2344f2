"""Byte-level BPE: encoding and decoding.

Merges are folded by Spark's higher-order functions over the byte arrays of the different words, with the ranks as
literals in the plan: a table of the pairs of bytes, and for the others a hash table without collisions in two flat
arrays, for a lookup in a map goes through all its keys. A word's state is one array with a number for each pair of
neighbours, made of the pair's rank, its place in the word and its two symbols: the least number is the next merge,
and a merge changes the two numbers beside it.

Words are found, and their ids put together again, in Arrow batches: a task turns its documents into chunks and sends
a chunk's different words on, some thousands in a row, and then a row with the documents as lists of places among
them. Rows are dealt by chunk, so that a task has one Python process at a time; the fold runs row by row; then a
document's ids and the bytes they stand for are strung together. Texts are not shuffled.
"""

from __future__ import annotations

import base64
import hashlib
import json
import random
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .tokens import merge

#: What is sent beside a chunk's words, and how it is written as bytes.
BLOBS = {"state": "i1", "ready": "<i4", "heap": "<i4", "heap_sizes": "<i8", "codes": "<i4", "counts": "<i8", "places": "<i4", "lengths": "<i8"}
#: States of a word that is not folded: a token itself, or too long.
READY, HEAP = 1, 2
#: Words in a row that is folded.
ROW = 4096
#: Bits of a symbol or rank, and of a place, in a pair's number.
SYMBOL_BITS, PLACE_BITS = 17, 12
#: What no pair has as its rank.
NO_RANK = (1 << SYMBOL_BITS) - 1
#: The fold takes the square of a word's bytes; words over so many, whose places have no room, merge through a heap.
FOLDED = (1 << PLACE_BITS) - 2


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, f)}


def pair_ranks(ranks: dict[bytes, int]) -> dict[tuple[int, int], int]:
    """The rank of what two tokens spell together, for all that are a token again."""
    cuts = ((t[:i], t[i:], r) for t, r in ranks.items() for i in range(1, len(t)))
    return {(ranks[a], ranks[b]): r for a, b, r in cuts if a in ranks and b in ranks}


def long(n: int) -> Column:
    return F.lit(n).cast("long")


def bound(value: Column, use: Callable[[Column], Column]) -> Column:
    """use(value), the value computed once: a fold over nothing, whose end is use."""
    return F.aggregate(F.array_repeat(F.lit(0), 0), value, lambda a, _: a, use)


def prime_from(n: int) -> int:
    while any(n % d == 0 for d in range(2, int(n**0.5) + 1)):
        n += 1
    return n


def displaced(keys: list[int], n_slots: int, n_groups: int) -> tuple[list[int], dict[int, int]]:
    """(shift of each group, slot of each key): no two keys meet in slot (key + shift of key % n_groups) % n_slots.

    Keys of one group differ modulo n_slots if the two coprime numbers have a product over all keys.
    """
    groups: dict[int, list[int]] = {}
    for key in keys:
        groups.setdefault(key % n_groups, []).append(key)
    shifts, taken, slots = [0] * n_groups, bytearray(n_slots), {}
    tries = random.Random(7)
    free = iter(range(n_slots))
    for group, members in sorted(groups.items(), key=lambda g: -len(g[1])):
        if len(members) > 1:
            while any(taken[(k + shifts[group]) % n_slots] for k in members):
                shifts[group] = tries.randrange(n_slots)
        else:
            shifts[group] = (next(s for s in free if not taken[s]) - members[0]) % n_slots
        for k in members:
            slots[k] = (k + shifts[group]) % n_slots
            taken[slots[k]] = 1
    return shifts, slots


class RankTable:
    """The ranks of pairs as flat constant arrays: `first` has the number of a pair of bytes, at place 0; the others
    are found by the shift of their key's group, which leads to the slot that holds rank and key."""

    def __init__(self, ranks: dict[bytes, int]) -> None:
        self.edge = max(ranks.values()) + 1  #: stands before the first and after the last symbol; in no pair
        if self.edge >= NO_RANK:
            raise ValueError("ranks are too large for the table")
        pairs = {a << SYMBOL_BITS | b: rank for (a, b), rank in pair_ranks(ranks).items()}
        self.n_slots = prime_from(max(1009, len(pairs) * 7 // 5))
        self.n_groups = prime_from(max(len(pairs) // 4, (self.edge << SYMBOL_BITS) // self.n_slots + 1))
        if self.n_groups == self.n_slots:
            self.n_groups = prime_from(self.n_groups + 1)
        shifts, places = displaced(list(pairs), self.n_slots, self.n_groups)
        slots = [-1] * self.n_slots
        for key, slot in places.items():
            slots[slot] = pairs[key] << 2 * SYMBOL_BITS | key
        single = [ranks[bytes([b])] for b in range(256)]
        first = [pairs.get(a << SYMBOL_BITS | b, NO_RANK) << 2 * SYMBOL_BITS + PLACE_BITS | a << SYMBOL_BITS | b for a in single for b in single]
        last = [NO_RANK << 2 * SYMBOL_BITS + PLACE_BITS | a << SYMBOL_BITS | self.edge for a in single]
        head = [NO_RANK << 2 * SYMBOL_BITS + PLACE_BITS | self.edge << SYMBOL_BITS | a for a in single]
        self.arrays = (shifts, slots, first, head, last)

    def literals(self) -> list[Column]:
        return [F.from_json(F.lit(json.dumps(x, separators=(",", ":"))), "array<bigint>") for x in self.arrays]


def fold(words: Column, table: RankTable) -> Column:
    """The symbols that are left of each word (array of its two or more bytes) after merging the best pair, leftmost of
    equals, again and again."""
    rank_at = 2 * SYMBOL_BITS + PLACE_BITS
    left = lambda x: F.shiftright(x, SYMBOL_BITS).bitwiseAND(long(NO_RANK))
    right = lambda x: x.bitwiseAND(long(NO_RANK))
    placed = lambda x: x.bitwiseAND(long(((1 << PLACE_BITS) - 1) << 2 * SYMBOL_BITS))
    key_of = long((1 << 2 * SYMBOL_BITS) - 1)

    def folded(word: Column, shifts: Column, slots: Column, first: Column, head: Column, last: Column) -> Column:
        def number(a: Column, b: Column, place: Column) -> Column:
            def ranked(key: Column) -> Column:
                slot = F.get(slots, ((key + F.get(shifts, (key % long(table.n_groups)).cast("int"))) % long(table.n_slots)).cast("int"))
                rank = bound(slot, lambda v: F.when(v.bitwiseAND(key_of) == key, F.shiftright(v, 2 * SYMBOL_BITS)).otherwise(long(NO_RANK)))
                return F.shiftleft(rank, rank_at).bitwiseOR(place).bitwiseOR(key)

            return bound(F.shiftleft(a, SYMBOL_BITS).bitwiseOR(b), ranked)

        def merged(pairs: Column, best: Column, i: Column) -> Column:
            """Pair i, best, becomes one symbol: the pairs beside it are new."""
            symbol = F.shiftright(best, rank_at)
            before = bound(F.get(pairs, i - 2), lambda x: number(left(x), symbol, placed(x)))
            after = bound(F.get(pairs, i), lambda x: number(symbol, right(x), placed(best)))
            return bound(i - 2, lambda j: F.array_remove(F.transform(pairs, lambda x, k: F.when(k == j, before).when(k == i, after).otherwise(x)), best))

        def step(pairs: Column) -> Column:
            found = lambda best: bound(F.array_position(pairs, best).cast("int"), lambda i: merged(pairs, best, i))
            return bound(F.array_min(pairs), lambda best: F.when(best < long(NO_RANK << rank_at), found(best)).otherwise(pairs))

        byte = lambda i: F.get(word, i).cast("int").bitwiseAND(255)
        inner = F.transform(F.sequence(F.lit(0), F.size(word) - 2), lambda i: F.get(first, byte(i) * 256 + byte(i + 1)).bitwiseOR(F.shiftleft((i + 1).cast("long"), 2 * SYMBOL_BITS)))
        start = F.concat(F.array(F.get(head, byte(F.lit(0)))), inner, F.array(F.get(last, byte(F.size(word) - 1))))
        turns = F.slice(word, F.lit(2), F.size(word))  # a merge less than bytes
        return F.aggregate(turns, start, lambda pairs, _: step(pairs), lambda pairs: F.transform(F.slice(pairs, F.lit(1), F.size(pairs) - 1), lambda x: right(x).cast("int")))

    def within(found: list[Column], rest: list[Column]) -> Column:
        if rest:
            return bound(rest[0], lambda x: within([*found, x], rest[1:]))
        return F.transform(words, lambda w: folded(w, *found))

    return within([], table.literals())


def encode(docs: DataFrame, ranks_path: str, pattern: str, *, with_ids: bool = True, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (doc_id, n_tokens, ids, ids_sha256, decoded_sha256), one for each row of docs.

    ids (null if with_ids is off) are those of the rank file; the digests are of the decimal ids with single spaces,
    and of the bytes that the ids decode to. A null text counts as empty. Repeated rows are encoded each; an empty
    table gives an empty result; other columns are ignored. Strings of special tokens are ordinary text. The pattern
    must not match across the place before a space that follows another character.
    """
    ranks = read_ranks(ranks_path)
    if any(bytes([b]) not in ranks for b in range(256)):
        raise ValueError("the ranks lack some single bytes")

    def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np
        import pyarrow.compute as pc
        import regex
        from pyspark import TaskContext

        from .pieces import chunks

        tokens = regex.compile(pattern).findall
        known, ids_known = pa.array([*ranks], pa.large_binary()), pa.array([*ranks.values()], pa.int32())
        squeeze = pa.Codec("zstd", 1).compress
        own_number = TaskContext.get().partitionId() << 33

        def row(chunk: int, at: int, words: pa.Array, ids: pa.Array = pa.array([], pa.int64()), **blobs) -> pa.RecordBatch:  # noqa: B008
            whole = lambda x: pa.ListArray.from_arrays(pa.array([0, len(x)], pa.int32()), x)
            packed = []
            for name, kind in BLOBS.items():
                raw = np.asarray(blobs[name], kind).tobytes() if blobs else None
                packed.append(pa.array([raw and len(raw).to_bytes(8, "little") + squeeze(raw, asbytes=True) or raw], pa.binary()))
            return pa.RecordBatch.from_arrays([pa.array([own_number | chunk]), pa.array([at], pa.int32()), whole(words), whole(ids), *packed], names=["chunk", "at", "words", "ids", *BLOBS])

        def spelled(chunk) -> tuple[pa.Array, np.ndarray]:
            """(the words of all pieces, how many each has). Plain pieces are matched in one go: a word that starts with
            a space then starts a piece."""
            plain = chunk.plain()
            words = tokens("".join([" " + x for x in chunk.rests.filter(pa.array(plain)).to_pylist()]))
            begins = [k for k, w in enumerate(words) if w[0] == " "]
            if len(begins) != plain.sum():
                raise ValueError("the pattern matches across the start of a piece")
            counts = np.zeros(len(plain) + len(chunk.heads), np.int64)
            counts[np.flatnonzero(plain)] = np.diff([*begins, len(words)])
            others = [(k, tokens(" " + chunk.rests[k].as_py())) for k in np.flatnonzero(~plain).tolist()]
            others += [(len(plain) + k, tokens(x)) for k, x in enumerate(chunk.heads)]
            ends, parts, last = np.concatenate([[0], np.cumsum(counts)]), [], 0
            for k, own in others:
                parts += [words[last : ends[k]], own]
                last, counts[k] = ends[k], len(own)
            return pa.array([w for part in [*parts, words[last:]] for w in part], pa.large_string()), counts

        for number, chunk in enumerate(chunks(batches)):
            words, counts = spelled(chunk)
            coded = words.dictionary_encode()
            words, codes = coded.dictionary.cast(pa.large_binary()), coded.indices.to_numpy()
            found = pc.index_in(words, known)
            state = np.where(found.is_valid().to_numpy(zero_copy_only=False), READY, np.where(pc.binary_length(words).to_numpy() > FOLDED, HEAP, 0))
            fresh, rows = words.filter(pa.array(state == 0)), 0
            for rows, at in enumerate(range(0, len(fresh), ROW), 1):
                some = fresh.slice(at, ROW)
                flat = pa.array(np.frombuffer(b"".join(some.to_pylist()), np.int8))
                yield row(number, rows - 1, pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(pc.binary_length(some).to_numpy())]), pa.int32()), flat))
            heap = [[ranks[x] for x in merge([w[i : i + 1] for i in range(len(w))], ranks.get)] for w in words.filter(pa.array(state == HEAP)).to_pylist()]
            yield row(
                number, rows, pa.array([], pa.list_(pa.int8())), pa.array(chunk.ids, pa.int64()), state=state, ready=pc.take(ids_known, found.drop_null()).to_numpy(),
                heap=[i for w in heap for i in w], heap_sizes=[len(w) for w in heap], codes=codes, counts=counts, places=chunk.places, lengths=chunk.lengths,
            )

    def strung(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np
        import pyarrow.compute as pc

        from .pieces import in_parts, ragged, sums

        expand = pa.Codec("zstd").decompress
        top = max(ranks.values()) + 1
        by_id: list[bytes] = [b""] * top
        for token, rank in ranks.items():
            by_id[rank] = token
        names, tokens = (pa.array(x, pa.large_binary()) for x in ([str(k).encode() for k in range(top)], by_id))

        def joined(values: pa.Array, at: np.ndarray, sizes: np.ndarray, sign: bytes) -> pa.Array:
            """The values at the places, so many at a time strung together."""
            ends = np.concatenate([[0], np.cumsum(sizes)])
            return pc.binary_join(pa.LargeListArray.from_arrays(pa.array(ends), values.take(pa.array(at))), pa.scalar(sign, pa.large_binary()))

        def blob(batch: pa.RecordBatch, k: int, name: str) -> np.ndarray:
            raw = batch[name][k].as_py()
            return np.frombuffer(expand(raw[8:], int.from_bytes(raw[:8], "little")) if raw else b"", BLOBS[name])

        def documents(batch: pa.RecordBatch, k: int, flat: np.ndarray, sizes: np.ndarray) -> Iterator[pa.RecordBatch]:
            get = {name: blob(batch, k, name) for name in BLOBS}
            # words in their order: folded, ready, and from the heap
            order = np.concatenate([np.flatnonzero(get["state"] == s) for s in (0, READY, HEAP)])
            made = np.concatenate([flat, get["ready"], get["heap"]])
            n_ids = np.concatenate([sizes, np.ones(len(get["ready"]), np.int64), get["heap_sizes"]])
            starts, width = np.empty_like(n_ids), np.empty_like(n_ids)
            starts[order], width[order] = np.cumsum(n_ids) - n_ids, n_ids
            codes = get["codes"]
            piece_ids, piece_width = ragged(made, starts[codes], width[codes]), sums(width[codes], get["counts"])
            piece_start = np.cumsum(piece_width) - piece_width
            lines, texts = joined(names, piece_ids, piece_width, b" "), joined(tokens, piece_ids, piece_width, b"")
            ids = batch["ids"].values.slice(batch["ids"].offsets[k].as_py(), len(get["lengths"]))
            for first, last, at, n in in_parts(get["places"], get["lengths"]):
                own = piece_width[at]
                totals = sums(own, n)
                each = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(totals)]), pa.int32()), pa.array(ragged(piece_ids, piece_start[at], own), pa.int32())) if with_ids else pa.nulls(len(n), pa.list_(pa.int32()))
                digests = [pa.array([hashlib.sha256(x.as_buffer()).hexdigest() for x in joined(of, at, n, sign)], pa.string()) for of, sign in ((lines, b" "), (texts, b""))]
                yield pa.RecordBatch.from_arrays([ids.slice(first, last - first), pa.array(totals, pa.int64()), each, *digests], names=["doc_id", "n_tokens", "ids", "ids_sha256", "decoded_sha256"])

        sizes, flat = [np.zeros(0, np.int64)], [np.zeros(0, np.int32)]
        for batch in batches:
            for k in range(batch.num_rows):
                if len(folded := batch["made"][k]):
                    sizes.append(pc.list_value_length(folded.values).to_numpy().astype(np.int64))
                    flat.append(folded.values.flatten().to_numpy().copy())
                if batch["state"][k].is_valid:
                    yield from documents(batch, k, np.concatenate(flat), np.concatenate(sizes))
                    sizes, flat = [np.zeros(0, np.int64)], [np.zeros(0, np.int32)]

    rows = docs.select(F.col(id_col).cast("long").alias("i"), F.col(text_col).alias("t"))
    chunks = rows.mapInArrow(split, "chunk long, at int, words array<array<tinyint>>, ids array<long>, " + ", ".join(f"{name} binary" for name in BLOBS))
    n = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    chunks = chunks.repartition(n, "chunk").sortWithinPartitions("chunk", "at")
    chunks = chunks.select(fold(F.col("words"), RankTable(ranks)).alias("made"), "ids", *BLOBS)
    return chunks.mapInArrow(strung, "doc_id long, n_tokens long, ids array<int>, ids_sha256 string, decoded_sha256 string")


def decode(encoded: DataFrame, ranks_path: str, *, ids_col: str = "ids", text_col: str = "text") -> DataFrame:
    """encoded with `text_col`: what the ids stand for, as text (bytes that are no UTF-8 become U+FFFD)."""
    spelled = {rank: token for token, rank in read_ranks(ranks_path).items()}

    def decoded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [None if ids is None else b"".join([spelled[i] for i in ids]).decode(errors="replace") for ids in batch[ids_col].to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(texts, pa.string())], names=[*batch.schema.names, text_col])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in encoded.schema)
    return encoded.mapInArrow(decoded, f"{schema}, `{text_col}` string")
