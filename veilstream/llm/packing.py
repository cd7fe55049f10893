"""Best-fit-decreasing packing of token pieces into sequences of a fixed capacity.

The order in which best-fit decreasing treats pieces depends on their lengths alone, and
at most `capacity` lengths exist. So the exact algorithm runs on the histogram of lengths:
open bins are counted by remaining capacity in a segment tree, each step finds the
tightest remaining capacity that holds the length in logarithmic time, and treats all
equal bins at once. Its outcome is a list of placements (length, first rank, first bin,
pieces a bin, offset), from which every piece finds its bin by its rank among the pieces
of its length. Ranks come from counts by (length, salt) and a window inside each salt; a length has a salt for
every CROWD pieces, so one that a third of all rows share is spread over many tasks.

Defined results: a null text is empty and packs its end id; repeated doc_ids are packed
once a row; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import materialize, unused
from .words import end_of_task, word_encoder

#: Pieces of a length that a task ranks.
CROWD = 100_000


class TightestFit:
    """Segment tree over remaining capacities 0..capacity; a leaf counts the open bins with it."""

    def __init__(self, capacity: int):
        self.size = 1 << capacity.bit_length()
        self.tree = [0] * (2 * self.size)

    def add(self, remaining: int, bins: int) -> None:
        i = remaining + self.size
        while i:
            self.tree[i] += bins
            i >>= 1

    def find(self, need: int) -> int:
        """The smallest remaining capacity >= need that an open bin has, or -1."""
        i = need + self.size
        if self.tree[i]:
            return need
        while i > 1:
            if not i & 1 and self.tree[i + 1]:
                i += 1
                while i < self.size:
                    i = 2 * i if self.tree[2 * i] else 2 * i + 1
                return i - self.size
            i >>= 1
        return -1


def best_fit_decreasing(histogram: dict[int, int], capacity: int) -> tuple[list[tuple[int, int, int, int, int]], int]:
    """Placements (length, first rank, first bin, pieces a bin, offset) and the number of bins.

    Pieces first_rank, first_rank + 1, ... of a length fill bins first_bin, first_bin + 1, ...,
    so many a bin, from the offset on, up to the next placement of the length.
    """
    tree, stock, out, bins = TightestFit(capacity), {}, [], 0
    for length in sorted((k for k, n in histogram.items() if n), reverse=True):
        if not 0 < length <= capacity:
            raise ValueError(f"a piece of {length} tokens does not fit {capacity}")
        left, rank = histogram[length], 0
        while left:
            room = tree.find(length)
            if room < 0:  # new bins for all that is left
                per = capacity // length
                full, rest = divmod(left, per)
                for n, each in ((full, per), (1, rest)):
                    if n and each:
                        out.append((length, rank, bins, each, 0))
                        spare = capacity - each * length
                        if spare:
                            stock.setdefault(spare, []).append((bins, n))
                            tree.add(spare, n)
                        bins, rank = bins + n, rank + n * each
                break
            per = room // length
            first, n = stock[room].pop()
            use, each = min(n, left // per), per
            if not use:
                use, each = 1, left
            if n > use:
                stock[room].append((first + use, n - use))
            tree.add(room, -use)
            out.append((length, rank, first, each, capacity - room))
            spare = room - each * length
            if spare:
                stock.setdefault(spare, []).append((first, use))
                tree.add(spare, use)
            rank, left = rank + use * each, left - use * each
    return out, bins


def pack(pieces: DataFrame, capacity: int, order: list[str]) -> DataFrame:
    """Add sequence_id and offset to rows that have a `length` of 1..capacity.

    order: columns that rank the pieces of a length; rows equal in them are interchangeable.
    pieces is read twice, so it must be a table or a deterministic plan.
    """
    spark = pieces.sparkSession
    length_, salts_, salt_, n_ = unused(pieces, "length", "salts", "salt", "n")
    sizes = pieces.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()  # at most capacity rows
    per = spark.createDataFrame([(int(r["length"]), -(-r["n"] // CROWD)) for r in sizes], f"`{length_}` long, `{salts_}` int")
    salted = pieces.join(F.broadcast(per), F.col("length") == F.col(length_)).withColumn(salt_, F.pmod(F.xxhash64(*order), F.col(salts_)).cast("int"))
    cells = salted.groupBy(length_, salt_).agg(F.count(F.lit(1)).alias("n")).collect()  # at most capacity + pieces / CROWD rows
    first, hist = {}, {}
    for k, salt, n in sorted(map(tuple, cells)):
        first[(k, salt)] = hist.get(k, 0)
        hist[k] = hist.get(k, 0) + n
    placed, _ = best_fit_decreasing(hist, capacity)
    grouped: dict[int, list] = {}
    for length, *p in placed:
        grouped.setdefault(length, []).append(p)
    by_length = {k: (rows[:, 0], rows) for k, v in grouped.items() for rows in [np.asarray(v, np.int64)]}
    at, names = len(pieces.columns), pieces.columns

    def place(batches):
        for b in batches:
            if not b.num_rows:
                continue
            length = b.column(at).to_numpy(zero_copy_only=False)
            salt, local = b.column(at + 1).to_numpy(zero_copy_only=False), b.column(at + 2).to_numpy(zero_copy_only=False)
            seq, off = np.zeros(len(length), np.int64), np.zeros(len(length), np.int64)
            for k in np.unique(length):
                rows = np.flatnonzero(length == k)
                rank = local[rows] - 1 + np.asarray([first[(int(k), int(s))] for s in salt[rows]])
                ranks, p = by_length[int(k)]
                j = np.searchsorted(ranks, rank, side="right") - 1
                inside = rank - ranks[j]
                seq[rows] = p[j, 1] + inside // p[j, 2]
                off[rows] = p[j, 3] + inside % p[j, 2] * k
            yield pa.RecordBatch.from_arrays([*b.columns[:at], pa.array(seq), pa.array(off)], [*names, "sequence_id", "offset"])

    ranked = salted.withColumn(n_, F.row_number().over(Window.partitionBy(length_, salt_).orderBy(*order)))
    ranked = ranked.select(*names, length_, salt_, n_)
    schema = pieces.schema.add("sequence_id", "long").add("offset", "long")
    return ranked.mapInArrow(place, schema)


def token_pieces(docs: DataFrame, tokenizer: str, capacity: int, end_id: int = 0) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32: each text's ids and the end id, cut only if longer than capacity."""
    end, done = np.asarray([end_id], "<u4").tobytes(), end_of_task

    def run(batches):
        enc = word_encoder(tokenizer)
        kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
        for batch in batches:
            for k in range(0, batch.num_rows, 512):  # texts become Python strings a slice at a time
                b = batch.slice(k, 512)
                cols: list[list] = [[], [], [], [], []]
                for d, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                    raw = enc.raw(t) + end
                    n = len(raw) // 4
                    for piece, s in enumerate(range(0, n, capacity)):
                        part = raw[4 * s : 4 * (s + capacity)]
                        for c, v in zip(cols, (d, piece, s, len(part) // 4, zlib.crc32(part))):
                            c.append(v)
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds)], ["doc_id", "piece", "start", "length", "ids_crc32"])
        done()

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long")


def pack_documents(docs: DataFrame, tokenizer: str, capacity: int = 2048, end_id: int = 0) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset of every piece."""
    pieces = materialize(token_pieces(docs, tokenizer, capacity, end_id), "pieces")
    return pack(pieces, capacity, ["doc_id", "piece", "ids_crc32"])
