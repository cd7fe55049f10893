"""Shared plumbing: table access, names, checked broadcasts, connected components."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, BinaryType, StringType

from ..shared import discard, materialize, shared_dir, shared_path

__all__ = ["BROADCAST_BYTES", "connected_components", "discard", "materialize", "partitions_for", "read_table", "shared_dir", "shared_path", "small", "unused"]


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def unused(df: DataFrame, *stems: str) -> list[str]:
    """A column name for each stem that df has not, whatever its case: operators add their own columns under these."""
    have, out = {c.lower() for c in df.columns}, []
    for s in stems:
        name = s
        while name.lower() in have:
            name += "_"
        have.add(name.lower())
        out.append(name)
    return out


#: Size, by a measure of the rows themselves, up to which a written table is broadcast.
BROADCAST_BYTES = 16 << 20


def small(df: DataFrame) -> DataFrame:
    """A written table, marked for broadcast if its measured size is bounded; else as it is.

    A row counts 16 bytes and 8 a column, and what its strings, binaries and arrays hold.
    """
    held = F.lit(16 + 8 * len(df.columns)).cast("long")
    for f in df.schema.fields:
        if isinstance(f.dataType, (StringType, BinaryType)):
            held = held + F.coalesce(F.octet_length(f.name), F.lit(0))
        elif isinstance(f.dataType, ArrayType):
            held = held + 8 * F.greatest(F.coalesce(F.size(f.name), F.lit(0)), F.lit(0))
    return F.broadcast(df) if (df.agg(F.sum(held)).first()[0] or 0) <= BROADCAST_BYTES else df


def partitions_for(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions", "200"))


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Smallest reachable node for every node of an edge list.

    edges: columns a, b (any orderable type); self loops and repeats are allowed.
    Returns node, component for nodes that have at least one edge to another node.
    Alternates large-star and small-star contraction, so a chain of n nodes needs
    O(log n) rounds and a hub never gathers its neighbours in one row. Each round is
    written to the shared folder, so a lost executor costs at most one round.
    """

    def canon(e: DataFrame) -> DataFrame:
        return e.filter("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()

    def state(e: DataFrame) -> tuple:
        r = e.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        return (r[0], r[1])

    cur = materialize(canon(edges), "cc")
    seen = state(cur)
    for _ in range(max_rounds):
        if not seen[0]:
            break
        both = cur.unionByName(cur.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.join(low, "a").filter("b > a").select(F.col("b").alias("a"), F.col("m").alias("b"))
        large = canon(large)
        low2 = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(low2, "a").filter("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))
        nxt = materialize(canon(small.unionByName(low2.select("a", F.col("m").alias("b")))), "cc")
        now = state(nxt)
        discard(cur)
        cur = nxt
        if now == seen:
            break
        seen = now
    else:
        raise RuntimeError("connected components did not settle")
    tops = cur.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct()
    return cur.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(tops)
