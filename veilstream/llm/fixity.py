"""Merkle fixity audit of WARC replicas, in SQL functions.

A page is a WARC response record. Records of SEGMENT consecutive page ids make a segment, ordered by
(page_id, digest); inside it a record has an offset and a length. The tree stands on page ids, not on places:
level 0 has a node a page_id, and FANOUT neighbouring nodes of a level share a parent, through the segments
up to one root a replica. A node hashes its children with the offset ranges that they take inside it, in order,
so a lost, gained or rotten record changes the nodes above it and no others.

The trees are written by level. An audit compares the two roots and descends, level by level, only below
nodes that differ: of a sound replica it reads the root, else the pages below bad nodes. There records
are matched by digest; what is left of a page on both sides is corrupt, what is left on one side missing
or extra.

Records of one page_id (or none) may be a third of all: they are hashed by sums over their digests, which are
partially aggregated, and get their offsets in parts by the leading digits of their digests.

Exact copies collapse to one record that carries their number; a copy lost or gained makes the record missing
or extra. Defined results: null columns count as empty strings; a null page_id is a page and a segment of its own;
extra columns are ignored; an empty table has no segments.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import materialize, small

FANOUT = 16
LEVELS = 3
SEGMENT = FANOUT**LEVELS
#: The capture time that records carry where the table has none.
DATE = "1970-01-01T00:00:00Z"
END = "\r\n\r\n"


def record_id(page_id: Column) -> Column:
    """The identity that a record keeps when its content rots."""
    return F.concat(F.lit("<urn:page:"), F.coalesce(page_id.cast("string"), F.lit("")), F.lit(">"))


def record_bytes(page_id: Column, url: Column, body: Column, date: Column | None = None) -> Column:
    """A WARC/1.0 response record as text, without the two line ends behind it; Content-Length counts the bytes of the body."""
    url, body = F.coalesce(url, F.lit("")), F.coalesce(body, F.lit(""))
    fields = {
        "WARC-Type": F.lit("response"),
        "WARC-Record-ID": record_id(page_id),
        "WARC-Date": F.lit(DATE) if date is None else date,
        "WARC-Target-URI": url,
        "Content-Type": F.lit("application/http"),
        "Content-Length": F.octet_length(body).cast("string"),
    }
    head = [F.concat(F.lit(f"{k}: "), v, F.lit("\r\n")) for k, v in fields.items()]
    return F.concat(F.lit("WARC/1.0\r\n"), *head, F.lit("\r\n"), body)


def segment_of(page_id: Column) -> Column:
    return F.floor(page_id / SEGMENT).cast("long")


def write_warc(pages: DataFrame, path: str) -> None:
    """Write the records as WARC files of at most SEGMENT records, in (page_id, url) order inside a file."""
    rec = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", "html")
    dealt = rec.repartitionByRange("page_id").sortWithinPartitions("page_id", "url")
    lines = dealt.select(record_bytes(F.col("page_id"), F.col("url"), F.col("html")).alias("value"))
    lines.write.option("lineSep", END).option("maxRecordsPerFile", SEGMENT).text(path)


def read_warc(spark: SparkSession, path: str) -> DataFrame:
    """file, offset, record_id, url, body of every record of a folder of WARC files, found by their lengths."""
    import pyarrow as pa

    def run(batches):
        for b in batches:
            for name, data in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                at, out = 0, []
                while at < len(data):
                    end = data.index(b"\r\n\r\n", at)
                    head = dict(x.split(": ", 1) for x in data[at:end].decode().split("\r\n")[1:])
                    size = int(head["Content-Length"])
                    out.append((name, at, head["WARC-Record-ID"], head["WARC-Target-URI"], data[end + 4 : end + 4 + size].decode("utf-8", "replace")))
                    at = end + 4 + size + 4
                cols = list(zip(*out)) or [()] * 5
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.string(), pa.int64(), pa.string(), pa.string(), pa.string()))], ["file", "offset", "record_id", "url", "body"])

    files = spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path)
    return files.select("path", "content").mapInArrow(run, "file string, offset long, record_id string, url string, body string")


def records(pages: DataFrame, tag: str = "records") -> DataFrame:
    """page_id, digest, bytes, copies of every distinct record."""
    rec = F.concat(record_bytes(F.col("page_id").cast("long"), F.col("url"), F.col("html")), F.lit(END))
    hashed = pages.select(F.col("page_id").cast("long").alias("page_id"), F.sha2(rec, 256).alias("digest"), F.octet_length(rec).cast("long").alias("bytes"))
    return materialize(hashed.groupBy("page_id", "digest", "bytes").agg(F.count(F.lit(1)).alias("copies")), tag)


def page_nodes(rec: DataFrame) -> DataFrame:
    """node (page_id), bytes, digest: a page's records hashed by sums of parts of their hashes, in any order."""
    h = F.sha2(F.concat_ws(":", "digest", F.col("copies").cast("string")), 256)
    part = lambda k: F.sum(F.conv(F.substring(h, 1 + 15 * k, 15), 16, 10).cast("decimal(38,0)")).cast("string")
    sums = rec.groupBy(F.col("page_id").alias("node")).agg(F.sum(F.col("bytes") * F.col("copies")).alias("bytes"), F.count(F.lit(1)).cast("string").alias("n"), *[part(k).alias(f"p{k}") for k in range(4)])
    return sums.select("node", "bytes", F.sha2(F.concat_ws(":", F.lit("0"), "n", "p0", "p1", "p2", "p3"), 256).alias("digest"))


def parent(nodes: DataFrame) -> DataFrame:
    """The level above: each node with the offset ranges of its children, at most FANOUT."""
    kids = F.array_sort(F.collect_list(F.struct("node", "bytes", "digest")))
    up = nodes.groupBy(F.floor(F.col("node") / FANOUT).cast("long").alias("node")).agg(F.sum("bytes").alias("bytes"), kids.alias("kids"))
    start = F.struct(F.lit(0).cast("long").alias("at"), F.lit("").alias("text"))

    def add(s: Column, k: Column) -> Column:
        end = s["at"] + k["bytes"]
        text = F.concat(s["text"], F.coalesce(k["node"].cast("string"), F.lit("")), F.lit("@"), s["at"].cast("string"), F.lit("-"), end.cast("string"), F.lit(":"), k["digest"], F.lit(","))
        return F.struct(end.alias("at"), text.alias("text"))

    return up.select("node", "bytes", F.sha2(F.aggregate("kids", start, add, lambda s: s["text"]), 256).alias("digest"))


def height(*sides: DataFrame) -> int:
    """Levels above the pages that bring the page ids of all replicas under one node (of the same sign: two) and at least to segments."""
    ends = [r for s in sides for r in [s.agg(F.min("page_id").alias("lo"), F.max("page_id").alias("hi")).first()] if r["lo"] is not None]
    lo, hi = min((r["lo"] for r in ends), default=0), max((r["hi"] for r in ends), default=0)
    levels = LEVELS
    while hi // FANOUT**levels > 0 or lo // FANOUT**levels < -1:
        levels += 1
    return levels


def tree(rec: DataFrame, levels: int, tag: str = "tree") -> list[DataFrame]:
    """Written levels from the pages (0) up; the last one has at most three nodes (negative ids, others, none)."""
    out = [materialize(page_nodes(rec), tag)]
    for _ in range(levels):
        out.append(materialize(parent(out[-1]), tag))
    return out


def root(levels: list[DataFrame]) -> str:
    """The replica's root: the hash of the top nodes in order."""
    import hashlib

    tops = sorted(((r["node"] is not None, r["node"] or 0, r["digest"]) for r in levels[-1].collect()))  # at most three
    return hashlib.sha256(",".join(d for *_, d in tops).encode()).hexdigest()


def mismatches(ours: list[DataFrame], theirs: list[DataFrame]) -> DataFrame | None:
    """node (page_id) of the pages that differ, found from the roots down; None if the roots are equal."""
    if root(ours) == root(theirs):
        return None
    bad = None
    for a, b in zip(reversed(ours), reversed(theirs)):
        if bad is not None:
            up = small(bad.select(F.col("node").alias("_up")))
            a, b = (x.join(up, F.floor(x.node / FANOUT).cast("long").eqNullSafe(F.col("_up")), "left_semi") for x in (a, b))
        b = b.select(F.col("node").alias("_n"), F.col("digest").alias("_d"), F.lit(True).alias("_there"))
        both = a.withColumn("_here", F.lit(True)).join(b, a.node.eqNullSafe(F.col("_n")), "full_outer")
        bad = materialize(both.filter(~F.col("digest").eqNullSafe(F.col("_d"))).select(F.when(F.col("_here"), F.col("node")).otherwise(F.col("_n")).alias("node")), "fixity-bad")
    return bad


def offsets(rec: DataFrame, pages: DataFrame) -> DataFrame:
    """rec with segment and offset: of the page in its segment, of the leading digits in the page, of the record behind these."""
    size = F.col("bytes") * F.col("copies")
    before = lambda w: F.coalesce(F.sum("bytes").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    page = pages.select(F.col("node").alias("_p"), before(Window.partitionBy(segment_of(F.col("node"))).orderBy("node")).alias("_at"))  # at most SEGMENT rows
    parts = rec.groupBy(F.col("page_id").alias("_q"), F.substring("digest", 1, 2).alias("_d")).agg(F.sum(size).alias("bytes"))
    parts = parts.select("_q", "_d", before(Window.partitionBy("_q").orderBy("_d")).alias("_in"))  # at most 256 rows
    own = Window.partitionBy("page_id", F.substring("digest", 1, 2)).orderBy("digest").rowsBetween(Window.unboundedPreceding, -1)
    out = rec.withColumn("_own", F.coalesce(F.sum(size).over(own), F.lit(0)))
    out = out.join(parts, out.page_id.eqNullSafe(F.col("_q")) & (F.substring("digest", 1, 2) == F.col("_d"))).join(page, out.page_id.eqNullSafe(F.col("_p")))
    return out.select(segment_of(F.col("page_id")).alias("segment"), "page_id", "digest", "bytes", "copies", (F.col("_at") + F.col("_in") + F.col("_own")).alias("offset"))


def audit(pages: DataFrame, replica: DataFrame) -> DataFrame:
    """Every record of the reference, and those that only the replica has: segment, page_id, digest, offset, bytes, copies, root, status.

    offset: in the segment of the replica that holds the record; root: of the reference's segment; status: ok,
    corrupt (the page has another record instead), missing, extra.
    """
    a, b = records(pages, "records-a"), records(replica, "records-b")
    levels = height(a, b)
    ta, tb = tree(a, levels, "tree-a"), tree(b, levels, "tree-b")
    roots = ta[LEVELS].select(F.col("node").alias("_seg"), F.col("digest").alias("root"))
    mine = offsets(a, ta[0])
    bad = mismatches(ta, tb)
    if bad is None:
        rows = mine.withColumn("status", F.lit("ok"))
    else:
        bad = small(bad.select(F.col("node").alias("_bad")))
        under = lambda x: x.join(bad, x.page_id.eqNullSafe(F.col("_bad")), "left_semi")
        other = under(b).select(F.col("page_id").alias("_p"), F.col("digest").alias("_d"), F.col("bytes").alias("_b"), F.col("copies").alias("_c"))
        both = under(a).join(other, F.col("page_id").eqNullSafe(F.col("_p")) & (F.col("digest") == F.col("_d")), "full_outer")
        # what has no equal on the other side, in digest order: the k-th of a page here and there are versions of one record
        side = F.when(F.col("_d").isNull(), "a").when(F.col("digest").isNull(), "b")
        left = both.filter(side.isNotNull()).select(side.alias("side"), F.coalesce("page_id", "_p").alias("page_id"), F.coalesce("digest", "_d").alias("digest"))
        left = materialize(left.withColumn("k", F.row_number().over(Window.partitionBy("side", "page_id").orderBy("digest"))), "fixity-left")
        la, lb = (left.filter(F.col("side") == s).select(F.col("page_id").alias(f"{s}p"), F.col("digest").alias(f"{s}d"), F.col("k").alias(f"{s}k")) for s in "ab")
        pairs = la.join(lb, F.col("ap").eqNullSafe(F.col("bp")) & (F.col("ak") == F.col("bk")), "full_outer")
        counted = both.filter("digest = _d and copies <> _c").select(F.col("page_id").alias("ap"), F.col("digest").alias("ad"), F.when(F.col("copies") > F.col("_c"), "missing").otherwise("extra").alias("status"))
        found = pairs.filter("ad is not null").select("ap", "ad", F.when(F.col("bd").isNull(), "missing").otherwise("corrupt").alias("status")).unionByName(counted)
        found = small(materialize(found, "fixity-found"))
        mine = mine.join(found, F.col("page_id").eqNullSafe(F.col("ap")) & (F.col("digest") == F.col("ad")), "left").drop("ap", "ad").withColumn("status", F.coalesce("status", F.lit("ok")))
        gained = small(materialize(pairs.filter("ad is null").select("bp", "bd"), "fixity-gained"))
        # offsets of the replica's segments that hold such records
        hit = small(materialize(gained.select(segment_of(F.col("bp")).alias("_s")).distinct(), "fixity-segments"))
        near = b.join(hit, segment_of(b.page_id).eqNullSafe(F.col("_s")), "left_semi")
        nodes = tb[0].join(hit, segment_of(tb[0].node).eqNullSafe(F.col("_s")), "left_semi")
        theirs = offsets(near, nodes).join(gained, F.col("page_id").eqNullSafe(F.col("bp")) & (F.col("digest") == F.col("bd")), "left_semi").withColumn("status", F.lit("extra"))
        rows = mine.unionByName(theirs)
    out = rows.join(small(roots), F.col("segment").eqNullSafe(F.col("_seg")), "left")
    return out.select("segment", "page_id", "digest", "offset", "bytes", "copies", "root", "status")


def damaged(pages: DataFrame) -> DataFrame:
    """A replica with deterministic damage for audits to find: some bodies have another first character, some
    records are lost, and some pages gain a record."""
    mark = F.substring(F.sha2(F.coalesce(F.col("page_id").cast("string"), F.lit("")), 256), 1, 2)
    rot = (mark < "03") & (F.length("html") > 0)
    kept = pages.select("page_id", "url", F.when(rot, F.concat(F.lit("?"), F.expr("substring(html, 2)"))).otherwise(F.col("html")).alias("html"), mark.alias("_mark"))
    gained = pages.select("page_id", "url", F.lit("gained").alias("html"), mark.alias("_mark")).filter("_mark = '04'")
    return kept.filter("_mark <> '03'").unionByName(gained).drop("_mark")
