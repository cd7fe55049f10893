"""SimHash near-duplicates by meet-in-the-middle ball hashing.

Two 64-bit fingerprints that differ in at most 2h bits have a common variant within h bits
of each. Every distinct fingerprint therefore meets every other at a variant of its ball
of radius h. The shuffle key is the leading bits of the variant: a fingerprint is sent
once for each leading part that its ball reaches, and the variants behind one leading part
are made, sorted and matched inside the task that owns it, so the ball (2,081 variants for
h = 2) is never written to disk. A bucket whose variants exceed the memory bound is split
again by further bits, in the same task, until the pieces fit; no variant is left out.

Equal variants link all their fingerprints to the smallest one (any two are within 2h, so
this keeps every component), each bucket hands on a spanning forest of its links, and
components are contracted in Spark. Copies collapse to one fingerprint beforehand.

`keep_similar` reaches a similarity of shingle sets with the same balls. Two sets of Jaccard
similarity 0.8 differ in 15 % of their bits, too many for one ball, so a set gets a sketch of
several independent fingerprints of BALL bits each: every fingerprint is joined by balls of
radius h, every pair that meets there is compared by 128 bits of the sketch in the same task, and what
remains is verified by the exact Jaccard similarity. The number of fingerprints follows from the wanted
recall. A bucket hands on a spanning forest of the pairs that pass, which no later test cuts, so the groups
to verify are those that all such pairs would give.

Defined results: null and empty texts have fingerprint zero and link like any other;
repeated doc_ids keep a row each; null doc_ids keep a row and name a component only if no
other id can; an empty table gives no rows; extra columns are kept, whatever their names.
"""

from __future__ import annotations

import math
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import connected_components, discard, materialize, partitions_for, small, unused
from .words import end_of_task

SEED = 42
BITS = 64
#: Variants that a task holds at once.
VARIANTS_IN_MEMORY = 1 << 21


def shingles(text: bytes | None, words: int) -> np.ndarray:
    """The hash of every run of `words` words; of a shorter text that of the whole."""
    import xxhash

    w = (text or b"").lower().split()  # bytes: lower-cases A-Z, splits at U+0020 and U+0009..U+000D
    if not w:
        return np.zeros(0, np.uint64)
    joined = b" ".join(w)
    size = np.fromiter(map(len, w), np.int64, len(w))
    ends = np.cumsum(size + 1) - 1
    begins = (ends - size).tolist()
    k = min(words, len(w))
    ends = ends[k - 1 :].tolist()
    h64 = xxhash.xxh64_intdigest
    return np.fromiter((h64(joined[a:b], SEED) for a, b in zip(begins, ends)), np.uint64, len(ends))


def ones_of(x: np.ndarray) -> np.ndarray:
    """How many rows of x (rows x words of 64 bits) have each bit set."""
    bits = np.unpackbits(x.view(np.uint8).reshape(len(x), -1), axis=1, bitorder="little").view(np.uint64)
    ones = np.zeros(8 * bits.shape[1], np.int64)
    for k in range(0, len(bits), 255):  # eight counters of a byte each in a word, none of which runs over
        ones += np.add.reduce(bits[k : k + 255], axis=0).view(np.uint8)
    return ones


def fingerprint(text: bytes | None, words: int) -> int:
    h = shingles(text, words)
    if not len(h):
        return 0
    ones = np.zeros(BITS, np.int64)
    for s in range(0, len(h), 1 << 16):
        ones += ones_of(h[s : s + (1 << 16), None])
    return int(np.packbits(2 * ones > len(h), bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, words: int = 4) -> DataFrame:
    """doc_id, th (hash of the text) and the fingerprint as a signed long."""

    done = end_of_task

    def run(batches):
        for b in batches:
            fp = np.fromiter((fingerprint(t.as_py(), words) for t in b.column(2)), np.uint64, b.num_rows)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(fp.view(np.int64))], ["doc_id", "th", "fp"])
        done()

    return docs.select(F.col("doc_id").cast("long"), F.xxhash64("text"), F.col("text").cast("binary")).mapInArrow(run, "doc_id long, th long, fp long")


def flips(bits: int, most: int) -> list[int]:
    """All masks over the lowest `bits` bits with at most `most` bits set."""
    from itertools import combinations

    return [sum(1 << i for i in c) for k in range(most + 1) for c in combinations(range(bits), k)]


def popcount(x: np.ndarray) -> np.ndarray:
    return np.bitwise_count(x)


class BallJoin:
    """Links of one bucket: fingerprints whose variants with a given leading part coincide; the ball spans the leading `width` bits."""

    def __init__(self, half: int, width: int = BITS):
        self.half, self.width = half, width
        self.masks: dict[tuple[int, int], np.ndarray] = {}
        self.links: list[np.ndarray] = []

    def of(self, bits: int, most: int) -> np.ndarray:
        if (bits, most) not in self.masks:
            self.masks[(bits, most)] = np.asarray(flips(bits, most), np.uint64)
        return self.masks[(bits, most)]

    def join(self, fps: np.ndarray, left: np.ndarray, low: int) -> None:
        """fps: distinct, leading bits above `low` (of the ball's) already fixed; left: flips that each may still make below."""
        if len(fps) < 2:
            return
        behind = np.uint64(BITS - self.width)
        total = sum(int((left == k).sum()) * len(self.of(low, k)) for k in range(self.half + 1))
        if total > VARIANTS_IN_MEMORY and low > 4:
            step = min(6, low - 1)
            part = (fps >> (np.uint64(low - step) + behind)) & np.uint64((1 << step) - 1)
            for v in range(1 << step):
                rest = left - popcount(part ^ np.uint64(v)).astype(np.int64)
                keep = rest >= 0
                self.join(fps[keep], rest[keep], low - step)
            return
        keep = np.uint64((1 << low) - 1)
        made, who = [], []
        for k in range(self.half + 1):
            rows = np.flatnonzero(left == k)
            if len(rows):
                m = self.of(low, k)
                made.append((((fps[rows] >> behind) & keep)[:, None] ^ m[None, :]).reshape(-1))
                who.append((rows, len(m)))
        v = np.concatenate(made)
        s = np.sort(v)
        twice = np.unique(s[1:][s[1:] == s[:-1]])
        if not len(twice):
            return
        at = np.searchsorted(twice, v)
        at[at == len(twice)] = 0
        hit = np.flatnonzero(twice[at] == v)
        owner = np.concatenate([np.repeat(rows, n) for rows, n in who])[hit]
        group = at[hit]
        order = np.lexsort((fps[owner], group))
        self.meet(group[order], fps[owner][order])

    def meet(self, group: np.ndarray, f: np.ndarray) -> None:
        """f: fingerprints by the variant (group) at which they meet, in rising order."""
        starts = np.flatnonzero(np.r_[True, group[1:] != group[:-1]])
        least = np.repeat(f[starts], np.diff(np.r_[starts, len(f)]))
        ok = least != f
        if ok.any():
            self.links.append(np.unique(np.stack([least[ok], f[ok]], axis=1), axis=0))

    def forest(self) -> np.ndarray:
        """A spanning forest, of stars, of the links so far, of which it forgets the rest."""
        links, self.links = self.links, []
        if not links:
            return np.zeros((0, 2), np.uint64)
        up: dict[int, int] = {}

        def top(x: int) -> int:
            while (p := up.get(x, x)) != x:
                up[x] = up.get(p, p)
                x = p
            return x

        for block in links:
            for a, b in block.tolist():
                x, y = top(a), top(b)
                if x != y:
                    up[max(x, y)] = min(x, y)
        return np.array([(top(x), x) for x in up if top(x) != x], np.uint64).reshape(-1, 2)


class NearJoin(BallJoin):
    """Links of one bucket where meeting is not enough: rows whose leading bits meet and that differ in at most `most` of 128 bits.

    Rows with the same leading bits (a lead) make one ball. Every pair of rows that meets is tested, but for
    those that links already join, so the forest connects what all passing pairs would connect.
    """

    def __init__(self, half: int, width: int, most: int, x: np.ndarray):
        """x: two words a row, the leading bits first."""
        super().__init__(half, width)
        behind = np.uint64(BITS - width)
        lead = x[:, 0] >> behind << behind
        self.order = np.argsort(lead, kind="stable")
        self.x, self.most, lead = x[self.order], most, lead[self.order]
        self.begin = np.flatnonzero(np.r_[True, lead[1:] != lead[:-1]])
        self.end = np.r_[self.begin[1:], len(x)]
        self.leads, self.many = lead[self.begin], self.end - self.begin > 1
        self.up, self.tree, self.crossed = list(range(len(x))), [], set()
        self.refresh()
        for i in np.flatnonzero(self.many).tolist():
            self.cross(i, i)
        self.refresh()

    def top(self, x: int) -> int:
        up = self.up
        while (p := up[x]) != x:
            up[x] = up[p]
            x = p
        return x

    def refresh(self) -> None:
        """label: of each row, the smallest row that links join it to; whole: leads whose rows are all joined. Old labels cost time only."""
        label = np.array(self.up)
        while (label[label] != label).any():
            label = label[label]
        self.label, self.news = label, 0
        self.whole = np.minimum.reduceat(label, self.begin) == np.maximum.reduceat(label, self.begin)

    def link(self, a: np.ndarray, b: np.ndarray) -> None:
        new = self.label[a] != self.label[b]
        for p in np.unique(a[new] * len(self.x) + b[new]).tolist():
            a_, b_ = divmod(p, len(self.x))
            x, y = self.top(a_), self.top(b_)
            if x != y:
                self.up[max(x, y)] = min(x, y)
                self.tree.append((a_, b_))
                self.news += 1

    def test(self, a: np.ndarray, b: np.ndarray) -> None:
        ok = popcount(self.x[a] ^ self.x[b]).sum(axis=-1) <= self.most
        a, b = np.broadcast_arrays(a, b)
        self.link(a[ok], b[ok])

    def cross(self, i: int, j: int) -> None:
        """All pairs of a row of lead i and one of lead j, but for those that the first rows' links join."""
        a, b = np.arange(self.begin[i], self.end[i]), np.arange(self.begin[j], self.end[j])
        self.test(a[:1], b)
        self.test(a, b[:1])
        main = self.top(int(a[0]))
        far_a, far_b = (np.array([r for r in rows.tolist() if self.top(r) != main], np.int64) for rows in (a, b))
        for rows, others in ((far_a, b),) if i == j else ((far_a, b), (far_b, a)):
            step = max(1, (1 << 18) // len(others))
            for k in range(0, len(rows), step):
                self.test(rows[k : k + step, None], others[None, :])

    def pairs(self, i: np.ndarray, j: np.ndarray) -> None:
        """Tests the rows of leads that meet."""
        if self.news * 64 > len(self.x):
            self.refresh()
        left = ~(self.whole[i] & self.whole[j] & (self.label[self.begin[i]] == self.label[self.begin[j]]))
        i, j = i[left], j[left]
        many = self.many[i] | self.many[j]
        self.test(self.begin[i[~many]], self.begin[j[~many]])
        for p in np.unique(i[many] * len(self.leads) + j[many]).tolist():
            if p not in self.crossed:
                self.crossed.add(p)
                self.cross(*divmod(p, len(self.leads)))

    def meet(self, group: np.ndarray, f: np.ndarray) -> None:
        at = np.searchsorted(self.leads, f)
        starts = np.flatnonzero(np.r_[True, group[1:] != group[:-1]])
        size = np.diff(np.r_[starts, len(at)])
        first = np.repeat(at[starts], size)
        self.pairs(first[first != at], at[first != at])
        if size.max() < 3:
            return
        if self.news:
            self.refresh()
        joined = self.whole[at] & (self.label[self.begin[at]] == self.label[self.begin[first]])
        keep = np.repeat((size > 2) & ~np.logical_and.reduceat(joined, starts), size)
        at, group = at[keep], group[keep]
        lag, left = 1, np.flatnonzero(group[1:] == group[:-1])
        while len(left):
            self.pairs(at[left], at[left + lag])
            lag += 1
            left = left[left + lag < len(at)]
            left = left[group[left + lag] == group[left]]

    def forest(self) -> np.ndarray:
        """Pairs of rows of the given x."""
        return self.order[np.array(self.tree, np.int64).reshape(-1, 2)]


def prefix_bits(n: int, half: int, width: int = BITS, rows: int = 4000, least: int = 4) -> int:
    """Leading bits, `least` of them or more, that make the fingerprints sent to a bucket about `rows` or fewer, on average, for n distinct ones."""
    for bits in range(least, min(25, width - 4)):
        if n * len(flips(bits, half)) / 2**bits <= rows:
            return bits
    return min(24, width - 5)


def to_buckets(rows: DataFrame, half: int, bits: int) -> DataFrame:
    """rows once for each leading part that its ball reaches, in order of the bucket (long); fp and perhaps table (int) are columns of rows."""
    parts = F.array(*[F.shiftrightunsigned("fp", BITS - bits).bitwiseXOR(F.lit(m).cast("long")) for m in flips(bits, half)])
    table = (F.col("table") if "table" in rows.columns else F.lit(0)).cast("long")
    held = [c for c in rows.columns if c != "table"]
    sent = rows.select(*held, table.alias("_table"), F.explode(parts).alias("_part"))
    sent = sent.select(F.shiftleft("_table", bits).bitwiseOR(F.col("_part")).alias("bucket"), *held)
    return sent.repartition(partitions_for(rows.sparkSession), "bucket").sortWithinPartitions("bucket")


def each_bucket(batches):
    """(bucket, its other columns as arrays) of batches in order of their first column."""
    now, held = None, []
    for batch in batches:
        if not batch.num_rows:
            continue
        b, *cols = (c.to_numpy(zero_copy_only=False) for c in batch.columns)
        cuts = np.flatnonzero(np.r_[True, b[1:] != b[:-1]]).tolist()
        for s, e in zip(cuts, [*cuts[1:], len(b)]):
            if b[s] != now:
                if held:
                    yield now, [np.concatenate(c) for c in zip(*held)]
                now, held = int(b[s]), []
            held.append([c[s:e] for c in cols])
    if held:
        yield now, [np.concatenate(c) for c in zip(*held)]


def link_batches(a: np.ndarray, b: np.ndarray):
    for s in range(0, len(a), 50_000):
        yield pa.RecordBatch.from_arrays([pa.array(a[s : s + 50_000]), pa.array(b[s : s + 50_000])], ["a", "b"])


def ball_links(fps: DataFrame, radius: int = 4, bits: int | None = None) -> DataFrame:
    """a, b: links that connect exactly the fingerprints (fp, long, distinct) that chains of <= radius differing bits connect."""
    half = radius // 2
    if radius % 2:
        raise ValueError("the radius must be even: each side takes half of it")
    bits = bits or prefix_bits(fps.count(), half)
    low, done, ball_join, ones, buckets, out = BITS - bits, end_of_task, BallJoin, popcount, each_bucket, link_batches

    def run(batches):
        ball = ball_join(half)
        for bucket, (f,) in buckets(batches):
            x = f.view(np.uint64)
            ball.join(x, half - ones((x >> np.uint64(low)) ^ np.uint64(bucket)).astype(np.int64), low)
            got = ball.forest().view(np.int64)
            yield from out(got[:, 0], got[:, 1])
        done()

    return to_buckets(fps.select("fp"), half, bits).mapInArrow(run, "a long, b long")


def near_links(rows: DataFrame, width: int, most: int) -> DataFrame:
    """a, b: links of sids that connect what all pairs connect that meet within RADIUS of the leading `width` bits of fp and differ in at most `most` of the 128 bits.

    rows: table (int), fp, more (long), sid, written; only rows of one table meet.
    """
    half = RADIUS // 2
    tables = rows.select("table").distinct().count()
    bits = prefix_bits(rows.count() // max(tables, 1), half, width, BUCKET, 2)
    lead, done, near_join, ones, buckets, out = np.int64((1 << bits) - 1), end_of_task, NearJoin, popcount, each_bucket, link_batches

    def run(batches):
        for bucket, (fp, more, sid) in buckets(batches):
            ball = near_join(half, width, most, np.stack([fp, more], axis=1).view(np.uint64))
            own = ball.leads >> np.uint64(BITS - bits)
            ball.join(ball.leads, half - ones(own ^ np.uint64(bucket & lead)).astype(np.int64), width - bits)
            got = sid[ball.forest()]
            yield from out(got[:, 0], got[:, 1])
        fp = more = sid = ball = own = got = None  # so that all of it goes back to the machine
        done()

    return to_buckets(rows.select("table", "fp", "more", "sid"), half, bits).mapInArrow(run, "a long, b long")


def groups(docs: DataFrame, words: int = 4, radius: int = 4) -> DataFrame:
    """doc_id, th, fp, component_id of every row."""
    rows = materialize(fingerprints(docs, words), "fingerprints")
    least = rows.groupBy("fp").agg(F.min("doc_id").alias("least"))
    comp = connected_components(ball_links(least.select("fp"), radius))
    members = least.join(comp, least.fp == comp.node, "left").select(F.col("fp").alias("_fp"), F.coalesce("component", "fp").alias("component"), "least")
    tops = members.groupBy("component").agg(F.min("least").alias("component_id"))
    of_fp = members.join(tops, "component").select("_fp", "component_id")
    return rows.join(of_fp, rows.fp == of_fp["_fp"]).select("doc_id", "th", "fp", "component_id")


def near_duplicates(docs: DataFrame, words: int = 4, radius: int = 4) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id (smallest doc_id reachable) of every row."""
    return groups(docs, words, radius).select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame, words: int = 4, radius: int = 4) -> DataFrame:
    """docs with one document of each group: that with the smallest doc_id (of rows that share it, smallest text hash)."""
    near = materialize(groups(docs, words, radius), "near-groups")
    first = near.filter("doc_id <=> component_id").groupBy("component_id").agg(F.min("th").alias("_first"))
    first = first.withColumnRenamed("component_id", "_top")
    judged = near.join(first, near.component_id.eqNullSafe(F.col("_top")))
    return drop_rows(docs, near, judged.filter("not (doc_id <=> component_id) or th <> _first"))


def drop_rows(docs: DataFrame, near: DataFrame, gone: DataFrame) -> DataFrame:
    """docs without the (doc_id, th) of gone, each row once; near: doc_id, th of every row, written."""
    d, t, th = unused(docs, "d", "t", "th")
    gone = small(materialize(gone.select(F.col("doc_id").alias(d), F.col("th").alias(t)).distinct(), "near-gone"))
    out = docs.withColumn(th, F.xxhash64("text"))
    out = out.join(gone, F.col("doc_id").cast("long").eqNullSafe(F.col(d)) & (F.col(th) == F.col(t)), "left_anti")
    if not near.groupBy("doc_id", "th").agg(F.count(F.lit(1)).alias("n")).filter("n > 1").isEmpty():
        out = out.dropDuplicates(["doc_id", th])  # rows given more than once
    return out.select(*docs.columns)


# --- similarity of shingle sets -----------------------------------------------------------

#: Bits of a sketch's fingerprint that balls span, radius of a meeting, and share of similar pairs that the balls may miss.
BALL, RADIUS, MISSED = 32, 4, 0.01
#: Fingerprints that a bucket of a table holds at most, on average: 8 bytes each; more buckets would mean more copies of each.
BUCKET = 1_000_000
#: Fixed odd multipliers and offsets that make independent bits from one hash of a shingle.
SKETCH_SEED = 11
#: Sets that a task holds at once when a group is compared in blocks.
BLOCK = 256


def differing(similarity: float) -> float:
    """Share of sketch bits in which two sets of about equal size differ, by the angle between them."""
    return math.acos(2 * similarity / (1 + similarity)) / math.pi


def at_most(bits: int, p: float, k: int) -> float:
    return sum(math.comb(bits, i) * p**i * (1 - p) ** (bits - i) for i in range(k + 1))


def ball_bits(n: int) -> int:
    """Bits of a fingerprint for n sets: so many more than log2(n) that chance meetings grow with n, not with its square."""
    return min(52, max(BALL, math.ceil(math.log2(max(n, 2))) + 16))


def tables_for(similarity: float, bits: int) -> int:
    """Fingerprints that a pair of the given similarity needs to meet in one of them, but for MISSED of the pairs."""
    return math.ceil(math.log(MISSED) / math.log1p(-at_most(bits, differing(similarity), RADIUS)))


@cache
def mixers(words64: int) -> tuple[np.ndarray, np.ndarray]:
    draw = np.random.default_rng(SKETCH_SEED)
    return draw.integers(0, 1 << 64, words64, np.uint64), draw.integers(0, 1 << 64, words64, np.uint64) | np.uint64(1)


def sketch(s: np.ndarray, words64: int) -> np.ndarray:
    """words64 x 64 majority bits of a set of shingle hashes; a tie is a one."""
    flip, times = mixers(words64)
    ones = np.zeros(64 * words64, np.int64)
    for k in range(0, len(s), 1 << 14):
        x = (s[k : k + (1 << 14), None] ^ flip) * times
        x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
        x ^= x >> np.uint64(29)
        ones += ones_of(x)
    return np.packbits(2 * ones >= len(s), bitorder="little").view("<u8")


def windows(sk: np.ndarray, bits: int, tables: int) -> np.ndarray:
    """Fingerprint t of sketches (a row each): two words from bit t * bits on, going round; the leading `bits` are its own."""
    n, out = sk.shape[1], np.zeros((len(sk), tables, 2), np.uint64)
    for t in range(tables):
        i, o = divmod(t * bits, 64)
        for k in range(2):
            a, b = sk[:, (i + k) % n], sk[:, (i + k + 1) % n]
            out[:, t, k] = a if not o else (a << np.uint64(o)) | (b >> np.uint64(64 - o))
    return out


def sketches(docs: DataFrame, words: int, words64: int) -> DataFrame:
    """doc_id, th (hash of the text), sid (hash of the set of shingles), sketch (array of longs)."""
    done, make, cut = end_of_task, sketch, shingles

    def run(batches):
        import xxhash

        for b in batches:
            for k in range(0, b.num_rows, 512):
                part = b.slice(k, 512)
                sid, sk = [], []
                for t in part.column(2):
                    s = np.unique(cut(t.as_py(), words))
                    sid.append(xxhash.xxh64_intdigest(s.tobytes()))
                    sk.append(make(s, words64).view(np.int64))
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(np.array(sid, np.uint64).view(np.int64)), pa.array(sk, pa.list_(pa.int64()))], ["doc_id", "th", "sid", "sketch"])
        done()

    return docs.select(F.col("doc_id").cast("long"), F.xxhash64("text"), F.col("text").cast("binary")).mapInArrow(run, "doc_id long, th long, sid long, sketch array<long>")


def sketch_words(bits: int, tables: int) -> int:
    """Words of 64 bits that hold a fingerprint's 128 bits and all tables."""
    return max(2, -(-bits * tables // 64))


def candidates(once: DataFrame, bits: int, tables: int, similarity: float) -> DataFrame:
    """a, b: pairs of sids that connect all that a ball brings together with near sketches, written; once: sid, sketch, written."""
    cut = windows

    def run(batches):
        for b in batches:
            for k in range(0, b.num_rows, 4096):
                part = b.slice(k, 4096)
                sk = part.column(1).flatten().to_numpy(zero_copy_only=False).view(np.uint64).reshape(part.num_rows, -1)
                fp = cut(sk, bits, tables).view(np.int64).reshape(-1, 2)
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(part.column(0).to_numpy(zero_copy_only=False), tables)), pa.array(np.tile(np.arange(tables, dtype=np.int32), len(sk))), pa.array(fp[:, 0]), pa.array(fp[:, 1])], ["sid", "table", "fp", "more"])

    own = materialize(once.select("sid", "sketch").mapInArrow(run, "sid long, table int, fp long, more long"), "near-fingerprints")
    p = differing(similarity)
    expected = (2 * BITS - bits) * p
    most = RADIUS + math.ceil(expected + 3 * math.sqrt(expected * (1 - p)))
    out = materialize(near_links(own, bits, most).distinct(), "near-pairs")
    discard(own)
    return out


def jaccard_at_least(a: np.ndarray, b: np.ndarray, similarity: float) -> bool:
    """Whether two sorted sets of distinct hashes are that similar."""
    if min(len(a), len(b)) < similarity * max(len(a), len(b)) - 1e-9:
        return False
    if not len(a):
        return True
    both = int(np.count_nonzero(b[np.minimum(np.searchsorted(b, a), len(b) - 1)] == a))
    return both >= similarity * (len(a) + len(b) - both) - 1e-9


def verified(groups_: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """a, b: links that connect all sets of a group that chains of similar sets connect.

    groups_: sid, top (smallest sid of a group of candidates); sets: sid, shingles; both written. Every
    set is compared with its group's smallest; those that are not similar to it are compared, in blocks, with all
    sets of the group. So a group of any size is spread over tasks, and one of copies costs one comparison each.
    """
    spark, done, similar = sets.sparkSession, end_of_task, jaccard_at_least
    sized = groups_.groupBy("top").agg(F.count(F.lit(1)).alias("n"))
    held = groups_.join(sized, "top").join(sets, "sid")
    salts = F.ceil(F.col("n") / (2 * BLOCK)).cast("int")
    held = materialize(held.withColumn("salt", F.pmod(F.xxhash64("sid"), salts).cast("int")), "near-held")
    first = held.filter("sid = top").select("top", F.col("shingles").alias("first"), F.explode(F.sequence(F.lit(0), salts - 1)).alias("salt"))

    def against_first(batches):
        for b in batches:
            ok = [similar(np.frombuffer(x.as_py(), np.uint64), np.frombuffer(y.as_py(), np.uint64), similarity) for x, y in zip(b.column(2), b.column(3))]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(ok, pa.bool_())], ["top", "sid", "ok"])
        done()

    tried = held.filter("sid <> top").join(first, ["top", "salt"]).select("top", "sid", "shingles", "first").mapInArrow(against_first, "top long, sid long, ok boolean")
    tried = materialize(tried, "near-tried")
    links = tried.filter("ok").select(F.col("top").alias("a"), F.col("sid").alias("b"))
    rest = tried.filter("not ok").select("top", "sid")
    if rest.isEmpty():
        return links
    counts = rest.groupBy("top").agg(F.ceil(F.count(F.lit(1)) / BLOCK).cast("int").alias("blocks"))
    block = F.pmod(F.xxhash64("sid", F.lit(1)), F.col("blocks")).cast("int")
    left = rest.join(counts, "top").withColumn("block", block).join(held.select("sid", "shingles", "n"), "sid")
    left = left.select("top", "block", F.explode(F.sequence(F.lit(0), salts - 1)).alias("salt"), F.lit(0).alias("side"), "sid", "shingles")
    right = held.join(counts, "top").select("top", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("block"), "salt", F.lit(1).alias("side"), "sid", "shingles")
    sent = left.unionByName(right).repartition(partitions_for(spark), "top", "block", "salt").sortWithinPartitions("top", "block", "salt", "side", "sid")

    def blocks(batches):
        now, ids, own, found = None, [], [], []
        for b in batches:
            for *cell, side, sid, s in zip(*(b.column(c).to_pylist() for c in range(6))):
                if cell != now:
                    now, ids, own = cell, [], []
                s = np.frombuffer(s, np.uint64)
                if not side:
                    ids.append(sid)
                    own.append(s)
                    continue
                found += [(i, sid) for i, x in zip(ids, own) if i != sid and similar(x, s, similarity)]
            yield pa.RecordBatch.from_arrays([pa.array([x for x, _ in found], pa.int64()), pa.array([y for _, y in found], pa.int64())], ["a", "b"])
            found = []
        done()

    return links.unionByName(sent.mapInArrow(blocks, "a long, b long"))


def similar_groups(docs: DataFrame, words: int, similarity: float) -> DataFrame:
    """doc_id, th, component of every row: documents that chains of similar shingle sets connect share a component."""
    n = docs.count()
    bits = ball_bits(n)
    tables = tables_for(similarity, bits)
    rows = materialize(sketches(docs, words, sketch_words(bits, tables)), "near-rows")
    once = rows.groupBy("sid").agg(F.min_by(F.struct("doc_id", "th"), F.struct(F.col("doc_id").isNull(), "doc_id", "th")).alias("of"), F.first("sketch").alias("sketch"))
    once = materialize(once, "near-sketches")
    met = connected_components(candidates(once, bits, tables, similarity))
    groups_ = materialize(met.select(F.col("node").alias("sid"), F.col("component").alias("top")), "near-candidates")
    who = groups_.join(once.select("sid", F.col("of.doc_id").alias("d"), F.col("of.th").alias("t")), "sid").select("sid", "d", "t")
    who = small(materialize(who, "near-who"))
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("th"), F.col("text").cast("binary").alias("text"))
    texts = texts.join(who, texts.doc_id.eqNullSafe(F.col("d")) & (texts.th == F.col("t"))).select("sid", "text")
    done, cut = end_of_task, shingles

    def to_sets(batches):
        for b in batches:
            for k in range(0, b.num_rows, 512):
                part = b.slice(k, 512)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([np.unique(cut(t.as_py(), words)).tobytes() for t in part.column(1)], pa.binary())], ["sid", "shingles"])
        done()

    sets = materialize(texts.mapInArrow(to_sets, "sid long, shingles binary").dropDuplicates(["sid"]), "near-sets")
    comp = connected_components(verified(groups_, sets, similarity)).select(F.col("node").alias("sid"), "component")
    return rows.select("doc_id", "th", "sid").join(comp, "sid", "left").select("doc_id", "th", F.coalesce("component", "sid").alias("component"))


def keep_similar(docs: DataFrame, words: int = 5, similarity: float = 0.8) -> DataFrame:
    """docs with one document of each group that chains of similar texts connect: that with the smallest doc_id, then text hash."""
    near = materialize(similar_groups(docs, words, similarity), "near-groups")
    first = near.groupBy("component").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "th")).alias("first"))
    gone = near.join(first, "component").filter(~(F.col("doc_id").eqNullSafe(F.col("first.doc_id")) & (F.col("th") == F.col("first.th"))))
    return drop_rows(docs, near, gone)
