"""Benchmark decontamination by spaced-seed hashing.

A seed is a fixed mask over `SPAN` token positions; ignored positions may hold any token,
so a substitution under them does not hide a passage. Every window of the benchmark is
hashed under every mask into a table of seeds (hash, item, place). One scan hashes the documents' windows the
same way; those that a Bloom filter of the seeds lets through, a filter of bounded size, are joined with
the seeds by hash. So the benchmark may have any size: a fuller filter only lets more rows reach the join.

Each hit fixes a diagonal between a document and an item; along it the longest stretch of
identity of at least 0.8 is found (match +1, substitution -4: total not below zero), and the overlap
counts if it covers min(MIN_TOKENS, item length) matching tokens. Texts with a hit are read once more, and only these,
to meet their diagonals in the order of documents.

Tokens: runs of letters and digits, lower-cased. Items with fewer tokens than SPAN have one seed over all
of them: they must occur whole.

Defined results: null or empty texts match nothing; repeated documents or items give a row
each pair once (doc_id, item_id); null doc_ids and item_ids are kept; empty tables give no rows; extra columns are
kept by `decontaminate`, whatever their names, and of rows that share a doc_id only those with a passage go.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize, partitions_for, small, unused
from .words import end_of_task, per_worker

SPAN = 11
#: positions that count, of 11. The last mask closes the gaps of the others: all placings of substitutions that leave 13
#: matches at identity 0.8 on 13 to 31 tokens (tried out) leave a window free; longer stretches have a part of such a length.
MASKS = ((0, 1, 2, 3, 4, 5, 6), (0, 1, 2, 4, 7, 8, 10), (0, 2, 3, 6, 8, 9, 10), (0, 1, 4, 5, 6, 9, 10), (0, 5, 7, 9, 10))
MIN_TOKENS = 13
#: Cost of a substitution: stretches of identity 0.8 come to zero.
MISMATCH = 4
WORD = re.compile(r"[^\W_]+")
#: Bits of the Bloom filter: 32 a seed, up to 16 MB in all; and of the coarse table before it.
PER_SEED, MOST_BITS, COARSE_BITS, PROBES = 32, 27, 22, 4


class TokenHasher:
    """Token -> 64-bit hash, with a bounded dictionary."""

    def __init__(self):
        self.known: dict[str, int] = {}

    def hashes(self, text: str | None) -> np.ndarray:
        import xxhash

        if not text:
            return np.zeros(0, np.uint64)
        words = WORD.findall(text.lower())
        known = self.known
        try:
            return np.fromiter(map(known.__getitem__, words), np.uint64, len(words))
        except KeyError:
            pass
        if len(known) > 300_000:
            known.clear()
        one = xxhash.xxh64_intdigest
        for w in words:
            if w not in known:
                known[w] = one(w)
        return np.fromiter(map(known.__getitem__, words), np.uint64, len(words))


def token_hasher() -> TokenHasher:
    return per_worker(("decontam",), TokenHasher)


def masks(short: list[int]) -> list[tuple[int, tuple[int, ...]]]:
    """(span, positions) of all seeds: the spaced ones, and one over all tokens of each length of short items."""
    return [*((SPAN, m) for m in MASKS), *((n, tuple(range(n))) for n in sorted(short))]


def seed_hashes(h: np.ndarray, span: int, positions: tuple[int, ...]) -> np.ndarray:
    """The hash of each window of `span` tokens under a mask."""
    n = max(len(h) - span + 1, 0)
    out = np.full(n, (0x9E3779B97F4A7C15 + span * 0x1000193 + sum(1 << p for p in positions)) & 0xFFFFFFFFFFFFFFFF, np.uint64)
    for p in positions:
        out = (out ^ h[p : p + n]) * np.uint64(0xBF58476D1CE4E5B9)
        out ^= out >> np.uint64(29)
    return out


class SeedFilter:
    """A coarse table of leading bits, then a Bloom filter; what it lets through may be a seed."""

    def __init__(self, bits: int, raw: bytes | None = None):
        self.bits = bits
        self.bloom = np.zeros(1 << (bits - 3), np.uint8) if raw is None else np.frombuffer(raw, np.uint8)
        self.coarse: np.ndarray | None = None

    def places(self, s: np.ndarray, probe: int) -> np.ndarray:
        """Bit places of a probe; that of probe 0 begins with the leading bits of the seed."""
        x = s if not probe else (s ^ (s >> np.uint64(7 + 6 * probe))) * np.uint64(0x9E3779B97F4A7C15 + 2 * probe)
        return x >> np.uint64(64 - self.bits)

    def add(self, s: np.ndarray) -> None:
        for k in range(PROBES):
            at = self.places(s, k)
            np.bitwise_or.at(self.bloom, at >> np.uint64(3), np.uint8(1) << (at & np.uint64(7)).astype(np.uint8))

    def ready(self) -> SeedFilter:
        """Make the coarse table, a byte a leading part, from the first probe's bits."""
        set_ = np.flatnonzero(np.unpackbits(self.bloom, bitorder="little"))
        bits = min(self.bits, COARSE_BITS)
        self.coarse = np.zeros(1 << bits, bool)
        self.coarse[set_ >> (self.bits - bits)] = True
        self.shift = np.uint64(64 - bits)
        return self

    def hits(self, s: np.ndarray) -> np.ndarray:
        """Places of s whose seeds pass."""
        at = np.flatnonzero(self.coarse[s >> self.shift])
        for k in range(PROBES):
            if not len(at):
                break
            bit = self.places(s[at], k)
            at = at[self.bloom[bit >> np.uint64(3)] >> (bit & np.uint64(7)).astype(np.uint8) & 1 == 1]
        return at


def best_stretch(same: np.ndarray) -> tuple[int, int, int]:
    """(begin, end, matches) of the longest stretch of a diagonal at identity of at least four fifths, less mismatches at its ends; ties: the first.

    No other such stretch has more matches: one that had could be lengthened until it were longer, too.
    """
    total = np.concatenate([[0], np.cumsum(np.where(same, 1, -MISMATCH))])
    low = np.minimum.accumulate(total)
    begins = np.searchsorted(-low, -total)  # for each end the first begin at which the score is not above its own
    end = int(np.argmax(np.arange(len(total)) - begins))
    begin = int(begins[end])
    at = np.flatnonzero(same[begin:end])
    if not len(at):
        return 0, 0, 0
    return begin + int(at[0]), begin + int(at[-1]) + 1, len(at)


def best_overlap(t: np.ndarray, item: np.ndarray, diagonal: int) -> tuple[int, int, int, int] | None:
    """(doc token, item token, span, matches) of the overlap on a diagonal, if it counts."""
    a, b = max(0, diagonal), min(len(t), diagonal + len(item))
    same = t[a:b] == item[a - diagonal : b - diagonal]
    need = min(MIN_TOKENS, len(item))
    if np.count_nonzero(same) < need:
        return None
    i, j, n = best_stretch(same)
    return (a + i, a + i - diagonal, j - i, n) if n >= need else None


def item_tokens(benchmark: DataFrame) -> DataFrame:
    """item (a hash of id and text), item_id, tokens (hashes) of every different item with tokens."""
    hasher, done = token_hasher, end_of_task

    def run(batches):
        h = hasher()
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([h.hashes(t).tobytes() for t in b.column(2).to_pylist()], pa.binary())], ["item", "item_id", "tokens"])
        done()

    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), "text").filter(F.length("text") > 0).distinct()
    items = items.select(F.xxhash64("item_id", "text").alias("item"), "item_id", "text").mapInArrow(run, "item long, item_id long, tokens binary")
    return materialize(items.filter(F.octet_length("tokens") > 0), "bench-items")


def seeds_of(items: DataFrame) -> DataFrame:
    """seed, item, place, span of every window of the items."""
    make, forms, span = seed_hashes, masks([]), SPAN

    def run(batches):
        for b in batches:
            for item, raw in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                t = np.frombuffer(raw, np.uint64)
                own = forms if len(t) >= span else [(len(t), tuple(range(len(t))))]
                for width, positions in own:
                    s = make(t, width, positions).view(np.int64)
                    n = len(s)
                    yield pa.RecordBatch.from_arrays([pa.array(s), pa.array(np.full(n, item)), pa.array(np.arange(n, dtype=np.int32)), pa.array(np.full(n, width, np.int32))], ["seed", "item", "place", "span"])

    return materialize(items.select("item", "tokens").mapInArrow(run, "seed long, item long, place int, span int"), "bench-seeds")


def filter_of(seeds: DataFrame) -> tuple[int, bytes]:
    """Bits and content of the seeds' filter, put together from a few tasks'."""
    n = seeds.count()
    bits = min(MOST_BITS, max(16, (n * PER_SEED).bit_length()))
    make = SeedFilter

    def run(batches):
        f = make(bits)
        for b in batches:
            f.add(b.column(0).to_numpy(zero_copy_only=False).view(np.uint64))
        yield pa.RecordBatch.from_arrays([pa.array([f.bloom.tobytes()], pa.binary())], ["bloom"])

    out = np.zeros(1 << (bits - 3), np.uint8)
    for r in seeds.select("seed").coalesce(4).mapInArrow(run, "bloom binary").toLocalIterator():  # at most four, of 16 MB
        out |= np.frombuffer(r["bloom"], np.uint8)
    return bits, out.tobytes()


def keyed(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("th"), "text")


def seed_hits(docs: DataFrame, seeds: DataFrame) -> DataFrame:
    """doc_id, th, seed, at of the documents' windows that pass the filter."""
    spark = docs.sparkSession
    short = [r["span"] for r in seeds.filter(F.col("span") < SPAN).select("span").distinct().collect()]  # at most SPAN - 1
    state = spark.sparkContext.broadcast(filter_of(seeds))
    forms, make_filter, hasher, make, done = masks(short), SeedFilter, token_hasher, seed_hashes, end_of_task

    def run(batches):
        known, h = make_filter(*state.value).ready(), hasher()
        for b in batches:
            for k in range(0, b.num_rows, 256):
                part = b.slice(k, 256)
                tokens = [h.hashes(t) for t in part.column(2).to_pylist()]
                size = np.array([len(t) for t in tokens], np.int64)
                ends = np.cumsum(size)
                every = np.concatenate(tokens) if len(tokens) else np.zeros(0, np.uint64)
                who, at, found = [], [], []
                for width, positions in forms:  # over all texts of the slice at once; windows across two texts go
                    s = make(every, width, positions)
                    hit = known.hits(s)
                    own = np.searchsorted(ends, hit, side="right")
                    inside = hit + width <= ends[own] if len(hit) else np.zeros(0, bool)
                    hit, own = hit[inside], own[inside]
                    who.append(own)
                    at.append(hit - (ends - size)[own])
                    found.append(s[hit].view(np.int64))
                rows = pa.array(np.concatenate(who))
                yield pa.RecordBatch.from_arrays([part.column(0).take(rows), part.column(1).take(rows), pa.array(np.concatenate(found)), pa.array(np.concatenate(at).astype(np.int32))], ["doc_id", "th", "seed", "at"])
        done()

    return materialize(keyed(docs).mapInArrow(run, "doc_id long, th long, seed long, at int"), "seed-hits")


def overlaps(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """doc_id, th (hash of the text), item_id, doc_token, item_token, span, matches: the best verified overlap of each text and item."""
    spark = docs.sparkSession
    items = item_tokens(benchmark)
    seeds = seeds_of(items)
    hits = seed_hits(docs, seeds)
    joined = hits.join(small(seeds.select("seed", "item", "place")), "seed")
    lines = materialize(joined.select("doc_id", "th", "item", (F.col("at") - F.col("place")).alias("diagonal")).distinct(), "diagonals")
    who = small(materialize(lines.select(F.col("doc_id").alias("d"), F.col("th").alias("t")).distinct(), "hit-texts"))
    src = keyed(docs)
    texts = src.join(who, src.doc_id.eqNullSafe(F.col("d")) & (src.th == F.col("t")), "left_semi")
    nothing = lambda kind: F.lit(None).cast(kind)
    texts = texts.select("doc_id", "th", F.lit(0).alias("kind"), "text", nothing("long").alias("item_id"), nothing("binary").alias("tokens"), nothing("int").alias("diagonal"))
    wanted = lines.join(small(items), "item").select("doc_id", "th", F.lit(1).alias("kind"), nothing("string").alias("text"), "item_id", "tokens", "diagonal")
    # each text in front of its diagonals
    sent = texts.unionByName(wanted).repartition(partitions_for(spark), "doc_id", "th").sortWithinPartitions("doc_id", "th", "kind", "item_id", "diagonal")
    hasher, best, done = token_hasher, best_overlap, end_of_task
    names = ["doc_id", "th", "item_id", "doc_token", "item_token", "span", "matches"]

    def run(batches):
        h, now, t = hasher(), None, None
        for b in batches:
            out: list[list] = [[] for _ in names]
            for d, th, kind, text, item_id, raw, diagonal in zip(*(b.column(c).to_pylist() for c in range(7))):
                if not kind:
                    if (d, th) != now:  # a text given more than once is judged once
                        now, t = (d, th), h.hashes(text)
                    continue
                if (got := best(t, np.frombuffer(raw, np.uint64), diagonal)) is not None:
                    for col, v in zip(out, (d, th, item_id, *got)):
                        col.append(v)
            yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in out], names)
        done()

    found = sent.mapInArrow(run, ", ".join(f"{n} long" for n in names))
    top = F.max_by(F.struct("doc_token", "item_token", "span", "matches"), F.struct("matches", -F.col("doc_token"), -F.col("item_token"))).alias("o")
    return found.groupBy("doc_id", "th", "item_id").agg(top).select("doc_id", "th", "item_id", "o.*")


def find_leaks(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """doc_id, item_id, doc_token, item_token, span, matches: the best verified overlap of each pair."""
    top = F.max_by(F.struct("doc_token", "item_token", "span", "matches"), F.struct("matches", -F.col("doc_token"), -F.col("item_token"))).alias("o")
    return overlaps(docs, benchmark).groupBy("doc_id", "item_id").agg(top).select("doc_id", "item_id", "o.*")


def decontaminate(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """docs without those that hold a benchmark passage."""
    d, t, th = unused(docs, "d", "t", "th")
    bad = small(materialize(overlaps(docs, benchmark).select(F.col("doc_id").alias(d), F.col("th").alias(t)).distinct(), "leaks"))
    src = docs.withColumn(th, F.xxhash64("text"))
    return src.join(bad, F.col("doc_id").cast("long").eqNullSafe(F.col(d)) & (F.col(th) == F.col(t)), "left_anti").select(*docs.columns)
