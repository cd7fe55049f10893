"""Line dedup by a segment-partition edit join, in DataFrame functions only.

Every line that is not blank is judged. It goes if an earlier line, in (doc_id, line_no) order, is the
same or, from MIN_CHARS characters on (shorter ones are alike by chance), lies within the edit
threshold: 1 edit up to LONG - 1 characters (of the shorter line), 2 from LONG on.

Of two lines within k edits, one of the k + 1 segments of the shorter occurs unchanged in
the longer, near its place. Every line is the shorter of some pairs and the longer of
others, so it gets the hashes of its own segments and those of the substrings at which
segments of lines 0 to k characters shorter may occur (for its own length these include
its segments): 12 for a long line. A first pass keeps, with two fixed-size aggregates a
hash, the hashes that different lines share; only rows with those are joined. Pairs whose
letter counts differ too much are refused inside the join; the others are verified by the
banded bit-parallel edit distance. Exact copies collapse before anything is joined. A segment that very many
different lines share is split by salt: one side of its pairs is dealt out, the other goes to every part.

Defined results: null texts have no lines and stay as they are; empty texts stay; a text
all of whose lines go is dropped by `dedup_lines`; rows equal in doc_id and text count as
one document; null doc_ids sort first; extra columns are kept by `dedup_lines`, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import discard, materialize, small, unused

MIN_CHARS = 20
#: What a blank line consists of.
BLANK = " \t\r\f\x0b"
#: Different lines with one segment that a task compares with each other.
CROWD = 256
LONG = 40
MOST = 2


def lines_of(docs: DataFrame) -> DataFrame:
    """doc_id, th (hash of the text), line_no, line, n (characters), k1, k2 (two independent hashes) of every judged line."""
    split = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("th"), F.posexplode(F.split("text", "\n")).alias("line_no", "line"))
    split = split.filter(F.length(F.btrim("line", F.lit(BLANK))) > 0).withColumn("n", F.length("line"))
    return split.select("doc_id", "th", "line_no", "line", "n", F.xxhash64("line").alias("k1"), F.xxhash64(F.lit(1), "line").alias("k2"))


def places(k: int, segment: int, delta: int) -> range:
    """Shifts at which a segment of a line `delta` shorter may occur, for k edits in all."""
    i = segment
    return range(max(-i, delta - (k - i)), min(i, delta + (k - i)) + 1)


def signatures(wide: Column, size: Column) -> Column:
    """Hashes of (length, segment, text) at which this line may meet lines of its own length or shorter.

    wide: the line with four bytes a character, which can be cut anywhere without a walk from its start.
    """

    def own(delta: int, k: int) -> list[Column]:
        short = size - delta if delta else size
        cut = lambda i: F.call_function("div", short * i, F.lit(k + 1)).cast("int")
        out = []
        for i in range(k + 1):
            width = cut(i + 1) - cut(i) if i < k else short - cut(i)
            out += [F.xxhash64(short, F.lit(i), F.substring(wide, (cut(i) + p) * 4 + 1 if i else F.lit(1 + 4 * p), width * 4)) for p in places(k, i, delta)]
        return out

    none = F.array().cast("array<bigint>")
    mixed = [
        F.when(size - delta >= LONG, F.array(*own(delta, 2))).when(F.lit(delta <= 1) & (size - delta >= MIN_CHARS), F.array(*own(min(delta, 1), 1))).otherwise(none)
        for delta in range(MOST + 1)
    ]
    every = [s for delta in range(MOST + 1) for s in own(delta, 2)]
    return F.when(size - MOST >= LONG, F.array(*every)).otherwise(F.flatten(F.array(*mixed)))


def letter_counts(line: Column) -> Column:
    """How often some frequent characters occur, by the length left without each."""
    low = F.lower(line)
    return F.array(*[F.length(low) - F.length(F.replace(low, F.lit(c), F.lit(""))) for c in "etaoinshrdlucmfgpwbvy ,.é"])


def far_apart(a: Column, b: Column, most: Column) -> Column:
    """Whether letter counts alone rule `most` edits out: an edit changes them by 2 at most."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: F.abs(x - y)), F.lit(0), lambda s, x: s + x) > 2 * most


def banded_distance(a: Column, b: Column, k: int) -> Column:
    """Edit distance if it is at most k, else some number over k; len(a) <= len(b) <= len(a) + k, len(a) >= k.

    Bits 0..2k of a word stand for rows j - k..j + k of column j of the edit matrix; vp and vn
    hold the vertical steps up and down. The distance is carried along the lower edge of
    the band, then along the last row.
    """
    chars = lambda s: F.regexp_extract_all(s, F.lit("(?s)."), F.lit(0))
    mask = (1 << (2 * k + 1)) - 1
    inv = lambda x: F.bitwise_not(x).bitwiseAND(F.lit(mask))
    let = lambda x, f: F.get(F.transform(F.array(x), f), F.lit(0))

    def over(ab: Column) -> Column:
        ca, cb = ab["a"], ab["b"]
        m = F.size(ca)

        def column(s: Column, j: Column) -> Column:
            c = F.get(cb, j - 1)
            match = sum((F.when(F.get(ca, j - k + t - 1) == c, F.lit(1 << t)).otherwise(F.lit(0)) for t in range(2 * k + 1)), F.lit(0)).cast("int")

            def with_match(x: Column) -> Column:
                vp, vn = s["vp"], s["vn"]
                d0 = ((x.bitwiseAND(vp) + vp).bitwiseXOR(vp)).bitwiseOR(x).bitwiseOR(vn).bitwiseAND(F.lit(mask))

                def with_d0(d: Column) -> Column:
                    def with_h(h: Column) -> Column:
                        half = F.shiftright(d, 1)
                        row = m - j + k
                        step = F.when(row >= 2 * k, 1 - F.getbit(d, F.lit(2 * k)).cast("int")).otherwise(F.getbit(h["hp"], F.greatest(row, F.lit(0))).cast("int") - F.getbit(h["hn"], F.greatest(row, F.lit(0))).cast("int"))
                        return F.struct(
                            h["hn"].bitwiseOR(inv(half.bitwiseOR(h["hp"]))).cast("int").alias("vp"),
                            half.bitwiseAND(h["hp"]).cast("int").alias("vn"),
                            (s["dist"] + step).cast("int").alias("dist"),
                        )

                    return let(F.struct(vn.bitwiseOR(inv(d.bitwiseOR(vp))).alias("hp"), d.bitwiseAND(vp).alias("hn")), with_h)

                return let(d0, with_d0)

            return let(match, with_match)

        start = F.struct(F.lit(mask & ~((1 << k) - 1)).cast("int").alias("vp"), F.lit(0).cast("int").alias("vn"), F.lit(k).cast("int").alias("dist"))
        return F.aggregate(F.sequence(F.lit(1), F.size(cb)), start, column, lambda s: s["dist"])

    return let(F.struct(chars(a).alias("a"), chars(b).alias("b")), over)


def allowed(shorter: Column) -> Column:
    return F.when(shorter >= LONG, F.lit(2)).otherwise(F.lit(1))


def line_keys(docs: DataFrame) -> DataFrame:
    """doc_id, th, line_no, k1, k2, sigs of every judged line, written once and read by column."""
    lines = lines_of(docs).withColumn("wide", F.encode("line", "UTF-32"))
    return materialize(lines.select("doc_id", "th", "line_no", "k1", "k2", signatures(F.col("wide"), F.col("n")).alias("sigs")), "line-keys")


def edit_links(docs: DataFrame, keys: DataFrame) -> DataFrame:
    """k1, k2, l1, l2, first, later of every pair of different lines within the threshold.

    `first` and `later` are the earliest (doc_id, th, line_no) of the two lines, in order.
    """
    sig = F.explode("sigs").alias("sig")
    shared = keys.select("k1", sig).groupBy("sig").agg(F.min("k1").alias("lo"), F.max("k1").alias("hi")).filter("lo <> hi").select("sig")
    shared = materialize(shared, "shared-segments")
    met = materialize(keys.select("k1", "k2", sig).join(small(shared), "sig", "left_semi").distinct(), "met-segments")
    discard(shared)
    who = materialize(met.select("k1", "k2").distinct(), "met-lines")
    texts = lines_of(docs).join(small(who), ["k1", "k2"], "left_semi").groupBy("k1", "k2").agg(F.min(F.struct("doc_id", "th", "line_no", "line")).alias("f"))
    once = met.join(texts, ["k1", "k2"])
    cand = once.select("sig", "k1", "k2", F.struct("f.doc_id", "f.th", "f.line_no").alias("at"), F.col("f.line").alias("line"), F.length("f.line").alias("n"), letter_counts(F.col("f.line")).alias("letters"))
    cand = materialize(cand, "edit-candidates")
    a, b = cand.withColumn("part", F.lit(0)), cand.withColumn("part", F.lit(0))
    crowded = materialize(met.groupBy("sig").agg(F.ceil(F.count(F.lit(1)) / CROWD).cast("int").alias("parts")).filter("parts > 1"), "crowded-segments")
    if not crowded.isEmpty():
        parted = cand.join(small(crowded), "sig", "left").withColumn("parts", F.coalesce("parts", F.lit(1)))
        a = parted.withColumn("part", F.pmod("k2", F.col("parts")).cast("int")).drop("parts")
        b = parted.withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).drop("parts")
    a, b = (x.select(*[F.col(c).alias(f"{side}_{c}") for c in a.columns]) for side, x in (("a", a), ("b", b)))
    most = allowed(F.least("a_n", "b_n"))
    ordered = (F.col("a_n") < F.col("b_n")) | ((F.col("a_n") == F.col("b_n")) & (F.col("a_line") < F.col("b_line")))
    near = (F.col("a_sig") == F.col("b_sig")) & (F.col("a_part") == F.col("b_part")) & ordered & (F.col("b_n") - F.col("a_n") <= most) & ~far_apart(F.col("a_letters"), F.col("b_letters"), most)
    pairs = a.join(b, near).select("a_k1", "a_k2", "b_k1", "b_k2", "a_at", "b_at", "a_line", "b_line", "a_n").dropDuplicates(["a_k1", "a_k2", "b_k1", "b_k2"])
    two, one = banded_distance(F.col("a_line"), F.col("b_line"), 2), banded_distance(F.col("a_line"), F.col("b_line"), 1)
    pairs = pairs.filter(F.when(F.col("a_n") >= LONG, two <= 2).otherwise(one <= 1))
    swap = F.col("b_at") < F.col("a_at")
    pick = lambda x, y: F.when(swap, F.col(y)).otherwise(F.col(x))
    out = pairs.select(pick("a_k1", "b_k1").alias("k1"), pick("a_k2", "b_k2").alias("k2"), pick("b_k1", "a_k1").alias("l1"), pick("b_k2", "a_k2").alias("l2"), pick("a_at", "b_at").alias("first"), pick("b_at", "a_at").alias("later"))
    links = materialize(out, "edit-links")
    discard(met, who, cand, crowded)
    return links


def repeats(docs: DataFrame) -> tuple[DataFrame, list[DataFrame]]:
    """doc_id, th, line_no, exact, near, links of every judged line that is a copy or has an edit link; and the tables behind it.

    exact: not the first occurrence of its text; near: an earlier line lies within the threshold.
    """
    keys = line_keys(docs)
    links = edit_links(docs, keys)
    twice = keys.groupBy("k1", "k2").agg(F.min(F.struct("doc_id", "th", "line_no")).alias("first"), F.count(F.lit(1)).alias("n")).filter("n > 1")
    ends = links.select("k1", "k2", F.lit(False).alias("near")).unionByName(links.select(F.col("l1").alias("k1"), F.col("l2").alias("k2"), F.lit(True).alias("near")))
    linked = ends.groupBy("k1", "k2").agg(F.max("near").alias("near"), F.count(F.lit(1)).alias("links"))
    flagged = materialize(twice.join(linked, ["k1", "k2"], "full_outer").select("k1", "k2", "first", F.coalesce("near", F.lit(False)).alias("near"), F.coalesce("links", F.lit(0)).alias("links")), "line-flags")
    discard(links)
    hit = keys.join(small(flagged), ["k1", "k2"])
    return hit.select("doc_id", "th", "line_no", (F.col("first").isNotNull() & ~F.struct("doc_id", "th", "line_no").eqNullSafe(F.col("first"))).alias("exact"), "near", "links"), [keys, flagged]


def line_report(docs: DataFrame) -> DataFrame:
    """doc_id, n_lines, n_judged, n_exact, n_near, n_kept, n_links of every document.

    n_near counts first occurrences with an earlier line within the threshold; n_links the
    edit links of the document's lines.
    """
    found, _ = repeats(docs)
    found = found.groupBy("doc_id", "th").agg(
        F.sum(F.col("exact").cast("long")).alias("n_exact"),
        F.sum((F.col("near") & ~F.col("exact")).cast("long")).alias("n_near"),
        F.sum("links").alias("n_links"),
    )
    lines = F.split("text", "\n")
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("th"), F.coalesce(F.size(lines), F.lit(0)).cast("long").alias("n_lines"), F.coalesce(F.size(F.filter(lines, lambda x: F.length(F.btrim(x, F.lit(BLANK))) > 0)), F.lit(0)).cast("long").alias("n_judged"))
    own = own.withColumn("n_lines", F.greatest("n_lines", F.lit(0))).withColumn("n_judged", F.greatest("n_judged", F.lit(0)))
    f = found.select(F.col("doc_id").alias("_d"), F.col("th").alias("_t"), "n_exact", "n_near", "n_links")
    zero = lambda c: F.coalesce(c, F.lit(0)).cast("long").alias(c)
    out = own.join(f, own.doc_id.eqNullSafe(F.col("_d")) & (own.th == F.col("_t")), "left")
    return out.select("doc_id", "n_lines", "n_judged", zero("n_exact"), zero("n_near"), zero("n_links")).withColumn("n_kept", F.col("n_lines") - F.col("n_exact") - F.col("n_near"))


def dedup_lines(docs: DataFrame) -> DataFrame:
    """docs with the text of each rebuilt from the lines that stay; texts of which none stays go."""
    d, t, h, lost = unused(docs, "d", "t", "h", "lost")
    hit, behind = repeats(docs)
    drop = hit.filter("exact or near").groupBy("doc_id", "th").agg(F.collect_set("line_no").alias(lost))  # at most a document's lines
    drop = small(materialize(drop.select(F.col("doc_id").alias(d), F.col("th").alias(t), lost), "lines-gone"))
    discard(*behind)
    joined = docs.withColumn(h, F.xxhash64("text")).join(drop, F.col("doc_id").cast("long").eqNullSafe(F.col(d)) & (F.col(h) == F.col(t)), "left")
    left = F.filter(F.split("text", "\n"), lambda x, i: ~F.array_contains(lost, i))
    text = F.when(F.col(lost).isNull(), F.col("text")).otherwise(F.array_join(left, "\n"))
    kept = joined.withColumn("text", text).filter(F.col(lost).isNull() | (F.length(F.btrim("text", F.lit(BLANK + "\n"))) > 0))
    return kept.select(*docs.columns)
