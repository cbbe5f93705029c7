"""Sequence packing: first-fit decreasing over a tournament tree, in random groups.

Documents become token ids plus an end id and are cut into pieces of at most
one sequence. Pieces are dealt into groups by a seeded hash; each group is
packed on its own, so no task holds more than a group and a lost task repeats
with the same result.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import freed, materialise, prepare, text_or_empty
from .tokens import crc32_ids, encoded_slices, forget_pieces

CAPACITY = 2048
GROUP_PIECES = 4096
GROUP_SPAN = 1 << 32


class BinTournament:
    """Leftmost bin with enough room, by a tree of the largest room below each node."""

    def __init__(self, bins: int, capacity: int):
        self.leaves = 1
        while self.leaves < max(1, bins):
            self.leaves *= 2
        self.room = [capacity] * (2 * self.leaves)
        self.capacity = capacity

    def place(self, size: int) -> tuple[int, int]:
        """Puts an item into the first bin it fits; returns (bin, offset in it)."""
        room = self.room
        if room[1] < size:
            raise ValueError("no bin has room")
        node = 1
        while node < self.leaves:
            node *= 2
            if room[node] < size:
                node += 1
        offset = self.capacity - room[node]
        room[node] -= size
        leaf = node - self.leaves
        while node > 1:
            node //= 2
            left, right = room[2 * node], room[2 * node + 1]
            best = left if left > right else right
            if room[node] == best:
                break
            room[node] = best
        return leaf, offset


def first_fit_decreasing(lengths: np.ndarray, capacity: int = CAPACITY) -> tuple[np.ndarray, np.ndarray]:
    """(bin, offset) of each item; items are taken by falling length, ties in the given order."""
    lengths = np.asarray(lengths, np.int64)
    if len(lengths) and (lengths.min() < 1 or lengths.max() > capacity):
        raise ValueError("lengths must lie in 1..capacity")
    bins, offsets = np.zeros(len(lengths), np.int64), np.zeros(len(lengths), np.int64)
    order = np.argsort(-lengths, kind="stable")
    full = int((lengths == capacity).sum())
    bins[order[:full]] = np.arange(full)
    tree = BinTournament(len(lengths) - full, capacity)
    for i in order[full:].tolist():
        place, offsets[i] = tree.place(int(lengths[i]))
        bins[i] = full + place
    return bins, offsets


PIECE = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long"
#: Tells apart pieces that are alike in all else; 0 for a document met for the first time.
SALT = "pack_salt"


def _cut(path: str | None, capacity: int, with_ids: bool):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, row = TaskContext.get().partitionId() << 40, 0
        for (doc_ids,), encoded in encoded_slices(batches, path):
            rows: list[list] = [[], [], [], [], [], [], []]
            met = set()
            for doc_id, ids in zip(doc_ids, encoded):
                # rows without an id, and further copies of a row, are spread by their place
                row += 1
                key = (doc_id, len(ids), crc32_ids(ids))
                salt = task + row if doc_id is None or key in met else 0
                met.add(key)
                for start in range(0, len(ids), capacity):
                    piece = ids[start : start + capacity]
                    crc = key[2] if len(piece) == len(ids) else crc32_ids(piece)
                    for column, value in zip(rows, (doc_id, start, len(piece), crc, len(ids), salt, piece.tobytes() if with_ids else None)):
                        column.append(value)
            arrays = [pa.array(r, pa.int64()) for r in rows[:6]] + ([pa.array(rows[6], pa.binary())] if with_ids else [])
            yield pa.RecordBatch.from_arrays(arrays, ["doc_id", "start", "length", "ids_crc32", "doc_tokens", SALT, "ids"][: len(arrays)])
        forget_pieces()

    return run


def token_pieces(docs: DataFrame, tokenizer_path: str | None = None, capacity: int = CAPACITY, with_ids: bool = False, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Pieces of at most capacity ids, each document's end id included; ids as little-endian uint32 bytes on demand."""
    prepare(docs.sparkSession)
    text = text_or_empty(text_col)
    slim = docs.select(F.col(id_col).cast("long").alias("doc_id"), text.alias("text"), F.length(text).alias("chars"))
    return slim.mapInArrow(freed(_cut(tokenizer_path, capacity, with_ids)), f"{PIECE}, {SALT} long" + (", ids binary" if with_ids else ""))


def _pack_group(capacity: int):
    def run(table: pa.Table) -> pa.Table:
        keys = [table[c].fill_null(np.iinfo(np.int64).max).to_numpy() for c in ("doc_id", "start", "doc_tokens", "ids_crc32", SALT)]
        table = table.take(pa.array(np.lexsort(keys[::-1])))
        bins, offsets = first_fit_decreasing(table["length"].to_numpy(), capacity)
        group = table["pack_group"][0].as_py() if table.num_rows else 0
        table = table.drop_columns(["pack_group", SALT])
        return table.append_column("sequence_id", pa.array(bins + group * GROUP_SPAN, pa.int64())).append_column("offset", pa.array(offsets, pa.int64()))

    return run


def pack_pieces(pieces: DataFrame, n_pieces: int, capacity: int = CAPACITY, group_pieces: int = GROUP_PIECES, seed: int = 17) -> DataFrame:
    """Adds sequence_id and offset to token_pieces; groups depend on what a piece is, not on where it lay."""
    groups = max(1, -(-n_pieces // group_pieces))
    dealt = pieces.withColumn("pack_group", F.pmod(F.xxhash64(F.lit(seed), "doc_id", "start", "doc_tokens", "ids_crc32", SALT), F.lit(groups)).cast("long"))
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in pieces.schema if f.name != SALT) + ", sequence_id long, offset long"
    return dealt.groupBy("pack_group").applyInArrow(_pack_group(capacity), schema)


def pack(docs: DataFrame, tokenizer_path: str | None = None, capacity: int = CAPACITY, group_pieces: int = GROUP_PIECES, seed: int = 17, with_ids: bool = False, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset[, ids].

    A null or empty text is its end id alone. Rows that repeat an id are packed
    as documents of their own. A document longer than a sequence is cut at
    multiples of the capacity; every id lies in exactly one piece. Ties in
    length are placed by doc id, start and content, so reruns agree; only rows
    without an id and full repeats of a row are told apart by where they lie,
    which spreads them over the groups. An empty table gives no piece.
    """
    pieces = materialise(token_pieces(docs, tokenizer_path, capacity, with_ids, id_col, text_col), "pieces")
    return pack_pieces(pieces, pieces.count(), capacity, group_pieces, seed)


def sequences(packed: DataFrame, capacity: int = CAPACITY, pad_id: int = 0) -> DataFrame:
    """pack(with_ids=True) -> (sequence_id, n_tokens, ids): the ids of each sequence as little-endian uint32 bytes.

    Padded with pad_id to the capacity unless the sequence's length is a power of two.
    """

    def join(table: pa.Table) -> pa.Table:
        table = table.sort_by("offset")
        ids = b"".join(table["ids"].to_pylist())
        n = len(ids) // 4
        full = n if n & (n - 1) == 0 else capacity
        return pa.table({"sequence_id": pa.array([table["sequence_id"][0].as_py()], pa.int64()), "n_tokens": pa.array([n], pa.int64()), "ids": pa.array([ids + np.full(full - n, pad_id, "<u4").tobytes()], pa.binary())})

    return packed.select("sequence_id", "offset", "ids").groupBy("sequence_id").applyInArrow(join, "sequence_id long, n_tokens long, ids binary")
