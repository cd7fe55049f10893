"""Token-id output: frequency-ranked ids, byte-aligned variable-length coding.

Ids are renumbered by falling corpus frequency (ties: smaller id first), so the 256 most
frequent ids take one byte. Each document is coded as two byte strings: the data bytes of
its ranks (1 to 4 each, least significant first) and, apart from them, control bytes that
hold four 2-bit lengths each. Decoding looks each control byte up in a 256 x 4 table of
lengths and gathers the data with numpy.

File format: a folder with `ranks` (Parquet: rank, id, n), `docs` (Parquet, one row a
document in ascending doc_id order within a file and from file to file: part, doc_id, before, n_tokens,
control, data) and `parts` (Parquet: part, base), where a document starts at its part's base plus `before`.
Parts are ranges of (doc_id, checksum) of about PART_BYTES, so their number follows the table and an id that very many rows
share spreads over several. Parquet is the container, so a job that loses executors commits whole
files or none and any store that Spark reaches will do.

Defined results: a null text is empty (its end id only); repeated doc_ids keep a row each,
ordered by their ids' checksum; null doc_ids come first; extra columns are ignored; an
empty table gives an empty folder with the right schema.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialize, partitions_for, shared_path
from .words import end_of_task, word_encoder

#: Words that a worker keeps: more than elsewhere, as this job's memory holds little else.
CACHED_WORDS = 1_600_000
DOCS = "part int, doc_id long, before long, n_tokens long, control binary, data binary"
#: Bytes of ids in a part of the output.
PART_BYTES = 48 << 20
#: lengths of the four values that a control byte describes
LENGTHS = ((np.arange(256)[:, None] >> np.array([0, 2, 4, 6])) & 3).astype(np.int64) + 1


def encode_ranks(ranks: np.ndarray) -> tuple[bytes, bytes]:
    """(control, data) of unsigned 32-bit values."""
    n = len(ranks)
    if not n:
        return b"", b""
    v = np.ascontiguousarray(ranks, dtype="<u4")
    extra = (v > 0xFF).astype(np.uint8) + (v > 0xFFFF) + (v > 0xFFFFFF)
    codes = np.zeros(-(-n // 4) * 4, np.uint8)
    codes[:n] = extra
    codes = codes.reshape(-1, 4)
    control = codes[:, 0] | codes[:, 1] << 2 | codes[:, 2] << 4 | codes[:, 3] << 6
    wide = int(extra.max()) + 1
    data = v.view(np.uint8).reshape(n, 4)[:, :wide][np.arange(wide) <= extra[:, None]]
    return control.tobytes(), data.tobytes()


def decode_ranks(control: bytes, data: bytes, n: int) -> np.ndarray:
    if not n:
        return np.zeros(0, np.uint32)
    size = LENGTHS[np.frombuffer(control, np.uint8)].reshape(-1)[:n]
    ends = np.cumsum(size)
    at = ends - size
    raw = np.frombuffer(data + b"\0\0\0", np.uint8)
    out = raw[at].astype(np.uint32)
    for k in (1, 2, 3):
        more = np.flatnonzero(size > k)
        if not len(more):
            break
        out[more] |= raw[at[more] + k].astype(np.uint32) << np.uint32(8 * k)
    return out


def binaries(data: np.ndarray, ends: np.ndarray) -> pa.Array:
    """Binary values that stand in a row in data (bytes), by their ends."""
    return pa.Array.from_buffers(pa.binary(), len(ends), [None, pa.py_buffer(np.r_[0, ends].astype(np.int32)), pa.py_buffer(np.ascontiguousarray(data))])


def slots(sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Where the values of rows of the given sizes stand when every row begins at a multiple of four, and the ends of the rows there."""
    padded = -(-sizes // 4) * 4
    ends = np.cumsum(padded)
    return np.arange(int(sizes.sum())) + np.repeat(ends - padded - (np.cumsum(sizes) - sizes), sizes), ends


def encode_rows(ranks: np.ndarray, sizes: np.ndarray) -> tuple[pa.Array, pa.Array]:
    """(control, data) of rows of unsigned 32-bit values, as encode_ranks gives them one by one."""
    v = np.ascontiguousarray(ranks, dtype="<u4")
    extra = (v > 0xFF).astype(np.uint8) + (v > 0xFFFF) + (v > 0xFFFFFF)
    at, ends = slots(sizes)
    codes = np.zeros(int(ends[-1]) if len(ends) else 0, np.uint8)
    codes[at] = extra
    codes = codes.reshape(-1, 4)
    control = codes[:, 0] | codes[:, 1] << 2 | codes[:, 2] << 4 | codes[:, 3] << 6
    wide = int(extra.max(initial=0)) + 1
    data = v.view(np.uint8).reshape(len(v), 4)[:, :wide][np.arange(wide) <= extra[:, None]]
    return binaries(control, ends // 4), binaries(data, np.r_[0, np.cumsum(extra + 1, dtype=np.int64)][np.cumsum(sizes)])


def decode_rows(control: list[bytes], data: list[bytes], sizes: np.ndarray) -> np.ndarray:
    """The values of all rows, one row behind the other."""
    size = LENGTHS[np.frombuffer(b"".join(control), np.uint8)].reshape(-1)[slots(sizes)[0]]
    at = np.cumsum(size) - size
    raw = np.frombuffer(b"".join(data) + b"\0\0\0", np.uint8)
    out = raw[at].astype(np.uint32)
    for k in (1, 2, 3):
        more = np.flatnonzero(size > k)
        if not len(more):
            break
        out[more] |= raw[at[more] + k].astype(np.uint32) << np.uint32(8 * k)
    return out


def tokenize(docs: DataFrame, tokenizer: str, end_id: int | None) -> DataFrame:
    """doc_id, n_tokens, tie (checksum of the ids), wide, ids (little-endian 16- or 32-bit, see wide) of every whole text.

    The last row of a task has no n_tokens and, in hist, how often the task met each id.
    """
    kinds = (pa.int64(), pa.int64(), pa.int64(), pa.bool_(), pa.binary(), pa.binary())
    add, as_rows = add_counts, binaries

    def rows(*cols):
        return pa.RecordBatch.from_arrays([c if isinstance(c, pa.Array) else pa.array(c, k) for c, k in zip(cols, kinds)], ["doc_id", "n_tokens", "tie", "wide", "ids", "hist"])

    end = b"" if end_id is None else np.asarray([end_id], "<u4").tobytes()

    def run(batches):
        enc = word_encoder(tokenizer, CACHED_WORDS)
        total = np.zeros(0, np.int64)
        for b in batches:
            for k in range(0, b.num_rows, 256):
                part = b.slice(k, 256)
                raws = [enc.raw(t) + end for t in part.column(1).to_pylist()]
                counts, ties = [len(x) // 4 for x in raws], list(map(zlib.crc32, raws))
                u4 = np.frombuffer(b"".join(raws), "<u4")
                total = add(total, np.bincount(u4))
                wide = [False] * len(raws)
                if u4.max(initial=0) > 0xFFFF:
                    wide = [bool(x) and int(np.frombuffer(x, "<u4").max()) > 0xFFFF for x in raws]
                    out = [x if w else np.frombuffer(x, "<u4").astype("<u2").tobytes() for w, x in zip(wide, raws)]
                else:
                    out = as_rows(u4.astype("<u2").view(np.uint8), 2 * np.cumsum(counts))
                yield rows(part.column(0), counts, ties, wide, out, [None] * len(counts))
        yield rows([None], [None], [None], [None], [None], [total.tobytes()])  # the word dictionary stays for the worker's next task

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, n_tokens long, tie long, wide boolean, ids binary, hist binary")


def add_counts(total: np.ndarray, c: np.ndarray) -> np.ndarray:
    if len(c) > len(total):
        c[: len(total)] += total
        return c
    total[: len(c)] += c
    return total


def frequencies(tokens: DataFrame) -> DataFrame:
    """id, n over all documents; a task sends a row for each id it met."""
    add = add_counts

    def run(batches):
        total = np.zeros(0, np.int64)
        for b in batches:
            for x in b.column(0).to_pylist():
                total = add(total, np.frombuffer(x, np.int64).copy())
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at, pa.int64()), pa.array(total[at], pa.int64())], ["id", "n"])

    return tokens.filter("n_tokens is null").select("hist").mapInArrow(run, "id long, n long").groupBy("id").agg(F.sum("n").alias("n"))


def write_tokens(docs: DataFrame, tokenizer: str, path: str, end_id: int | None = None) -> None:
    """Tokenize every text and write the folder described above to path."""
    spark = docs.sparkSession
    tokens = materialize(tokenize(docs, tokenizer, end_id), "tokens", "lz4_raw")
    freq = frequencies(tokens).collect()  # bounded by the vocabulary
    tokens = tokens.filter("n_tokens is not null").drop("hist")
    order = sorted(freq, key=lambda r: (-r["n"], r["id"]))
    schema = "rank long, id long, n long"
    spark.createDataFrame([(i, r["id"], r["n"]) for i, r in enumerate(order)], schema).coalesce(1).write.parquet(f"{path}/ranks")
    rank = np.zeros(max((r["id"] for r in order), default=0) + 1, np.uint32)
    rank[[r["id"] for r in order]] = np.arange(len(order))
    parts = max(partitions_for(spark), 2 * sum(r["n"] for r in order) // PART_BYTES + 1)
    # rows equal in id and checksum may stand in any order, so their place in the written table tells them apart
    place = [F.col("doc_id").asc_nulls_first(), F.col("tie").asc(), F.col("row").asc()]
    dealt = tokens.withColumn("row", F.monotonically_increasing_id()).repartitionByRange(parts, *place).sortWithinPartitions(*place)

    done, encode = end_of_task, encode_rows

    def code(batches):
        from pyspark import TaskContext

        part, at = TaskContext.get().partitionId(), 0
        for b in batches:
            for k in range(0, b.num_rows, 256):
                rows = b.slice(k, 256)
                wide, held = rows.column(2).to_pylist(), rows.column(3).to_pylist()
                if any(wide):
                    ids = np.concatenate([np.frombuffer(x, "<u4" if w else "<u2").astype(np.uint32) for w, x in zip(wide, held)])
                else:
                    ids = np.frombuffer(b"".join(held), "<u2")
                n = rows.column(1).to_numpy(zero_copy_only=False)
                control, data = encode(rank[ids], n)
                ends = at + np.cumsum(n)
                at = int(ends[-1])
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(n), part, np.int32)), rows.column(0), pa.array(ends - n), rows.column(1), control, data], ["part", "doc_id", "before", "n_tokens", "control", "data"])
        done()

    coded = dealt.select("doc_id", "n_tokens", "wide", "ids").mapInArrow(code, DOCS)
    coded.write.option("compression", "zstd").parquet(f"{path}/docs")
    counts = spark.read.schema(DOCS).parquet(f"{path}/docs").groupBy("part").agg(F.sum("n_tokens").alias("n")).collect()  # a row a part
    bases, at = [], 0
    for r in sorted(counts, key=lambda r: r["part"]):
        bases.append((r["part"], at))
        at += r["n"]
    spark.createDataFrame(bases, "part int, base long").coalesce(1).write.parquet(f"{path}/parts")


def read_tokens(spark: SparkSession, path: str, as_ids: bool = False) -> DataFrame:
    """Decode the folder: doc_id, start, n_tokens, ids_crc32 and, if wanted, ids (array<int>)."""
    ranks = spark.read.parquet(f"{path}/ranks").orderBy("rank").collect()  # bounded by the vocabulary
    ids = np.asarray([r["id"] for r in ranks], "<u4")
    base = {r["part"]: r["base"] for r in spark.read.parquet(f"{path}/parts").collect()}  # a row a part

    decode = decode_rows

    def run(batches):
        for whole in batches:
            for k in range(0, whole.num_rows, 256):
                b = whole.slice(k, 256)
                n = b.column(3).to_numpy(zero_copy_only=False)
                x = ids[decode(b.column(4).to_pylist(), b.column(5).to_pylist(), n)]
                ends = np.cumsum(n)
                raw, cuts = memoryview(x.view(np.uint8)), (4 * np.r_[0, ends]).tolist()
                crc = [zlib.crc32(raw[p:q]) for p, q in zip(cuts, cuts[1:])]
                start = np.array([base[p] for p in b.column(0).to_pylist()], np.int64) + b.column(2).to_numpy(zero_copy_only=False)
                cols = [b.column(1), pa.array(start, pa.int64()), b.column(3), pa.array(crc, pa.int64())]
                if as_ids:
                    cols.append(pa.array(np.split(x.astype(np.int32), ends[:-1]), pa.list_(pa.int32())))
                yield pa.RecordBatch.from_arrays(cols, ["doc_id", "start", "n_tokens", "ids_crc32", "ids"][: len(cols)])

    schema = "doc_id long, start long, n_tokens long, ids_crc32 long" + (", ids array<int>" if as_ids else "")
    return spark.read.schema(DOCS).parquet(f"{path}/docs").mapInArrow(run, schema)


def token_output(docs: DataFrame, tokenizer: str, end_id: int = 1) -> DataFrame:
    path = shared_path(docs.sparkSession, "token-output")
    write_tokens(docs, tokenizer, path, end_id)
    return read_tokens(docs.sparkSession, path)
