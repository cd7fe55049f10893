"""Approximate nearest neighbours by a robust-pruned directed graph on each shard.

Distinct vectors are dealt to shards of bounded size by hash. A shard's graph is built in
one task: points enter in batches, greedy searches from the medoid propose neighbours, and
relaxed distance pruning keeps an edge only if no kept neighbour is nearer to its end by
the factor ALPHA, so edges stay diverse; reverse edges are pruned alike. A second pass
over all points refines the graph. The query vectors are sent to every shard behind its points, so the
task that has just built a graph searches it, a beam search a block of queries, and forgets it:
graphs are never written or shuffled, and a task holds one at a time. The best of all shards are kept. Scores are
cosines of the original vectors in double precision; unit vectors and squared distances serve inside the graph.

Equal vectors are one point of the graph that stands for its smallest `k + 1` ids (a query
may be one of them), so thousands of copies neither fill an adjacency list nor lose their
tie order. Defined results: vectors that are null, empty, zero or
with null or non-finite components take no part; null ids neither; vectors meet those of their own
length; an id with several vectors is asked for with all of them and found by the nearest, once;
with fewer candidates than k all are returned; an empty table gives no rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import materialize, partitions_for, small

#: Points of a shard: at least, and at most (a shard is held by one task); between them all are in SHARDS shards.
SHARD, MOST, SHARDS = 4096, 65_536, 32
DEGREE = 32
BEAM = 64
ALPHA = 1.2
#: Queries searched together.
BLOCK = 128


def pairwise(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Squared distances of unit vectors: x (b, d), y (b, c, d)."""
    return 2.0 - 2.0 * np.einsum("bd,bcd->bc", x, y, optimize=False)


class PrunedGraph:
    def __init__(self, x: np.ndarray, degree: int = DEGREE, beam: int = BEAM, alpha: float = ALPHA):
        self.x, self.degree, self.beam, self.alpha = np.ascontiguousarray(x, np.float32), degree, beam, alpha
        n = len(x)
        self.edges = np.full((n, degree), -1, np.int32)
        self.start = int(np.argmax(self.x @ self.x.mean(axis=0))) if n else 0

    def search(self, q: np.ndarray, beam: int) -> tuple[np.ndarray, np.ndarray]:
        """Ids and squared distances, nearest first, of the beam of each query; -1 and inf fill up."""
        b, n = len(q), len(self.x)
        q = q.astype(np.float32)
        ids = np.full((b, beam), -1, np.int32)
        dist = np.full((b, beam), np.inf, np.float32)
        done = np.ones((b, beam), bool)
        ids[:, 0], done[:, 0] = self.start, False
        dist[:, 0] = 2 - 2 * (q @ self.x[self.start])
        seen = np.zeros((b, n), bool)
        seen[:, self.start] = True
        active = np.arange(b)
        while len(active):
            first = np.argmin(done[active], axis=1)  # lists are sorted: the nearest not expanded
            node = ids[active, first]
            done[active, first] = True
            near = self.edges[node]
            ok = (near >= 0) & ~seen[active[:, None], np.maximum(near, 0)]
            seen[active[:, None], np.where(ok, near, node[:, None])] = True
            d = np.where(ok, pairwise(q[active], self.x[np.maximum(near, 0)]), np.inf).astype(np.float32)
            all_d = np.concatenate([dist[active], d], axis=1)
            order = np.argsort(all_d, axis=1, kind="stable")[:, :beam]
            dist[active] = np.take_along_axis(all_d, order, 1)
            ids[active] = np.take_along_axis(np.concatenate([ids[active], np.where(ok, near, -1)], axis=1), order, 1)
            done[active] = np.take_along_axis(np.concatenate([done[active], ~ok], axis=1), order, 1)
            active = active[~done[active].all(axis=1)]
        return ids, dist

    def prune(self, p: np.ndarray, cand: np.ndarray, dist: np.ndarray) -> np.ndarray:
        """At most `degree` diverse neighbours of points p from candidates (-1: none), nearest first."""
        order = np.argsort(np.where(cand < 0, np.inf, dist), axis=1, kind="stable")
        cand, dist = np.take_along_axis(cand, order, 1), np.take_along_axis(dist, order, 1)
        alive = (cand >= 0) & (cand != p[:, None])
        alive[:, 1:] &= cand[:, 1:] != cand[:, :-1]
        vec = self.x[np.maximum(cand, 0)]
        out = np.full((len(p), self.degree), -1, np.int32)
        rows = np.arange(len(p))
        for slot in range(self.degree):
            any_ = alive.any(axis=1)
            if not any_.any():
                break
            best = np.argmax(alive, axis=1)
            out[:, slot] = np.where(any_, cand[rows, best], -1)
            alive &= ~(self.alpha * pairwise(vec[rows, best], vec) <= dist)
            alive[rows, best] = False
        return out

    def insert(self, points: np.ndarray) -> None:
        ids, dist = self.search(self.x[points], self.beam)
        own = self.edges[points]
        own_d = np.where(own >= 0, pairwise(self.x[points], self.x[np.maximum(own, 0)]), np.inf)
        ids, dist = np.concatenate([ids, own], axis=1), np.concatenate([dist, own_d], axis=1)
        self.edges[points] = self.prune(points, ids, dist)
        # reverse edges, grouped by the point that gets them
        src = np.repeat(points, self.degree).astype(np.int32)
        dst = self.edges[points].reshape(-1)
        src, dst = src[dst >= 0], dst[dst >= 0]
        order = np.argsort(dst, kind="stable")
        src, dst = src[order], dst[order]
        to, begin, count = np.unique(dst, return_index=True, return_counts=True)
        most = int(count.max()) if len(count) else 0
        for s in range(0, len(to), 1024):
            t, b, c = to[s : s + 1024], begin[s : s + 1024], count[s : s + 1024]
            more = np.full((len(t), most), -1, np.int32)
            for j in range(int(c.max())):
                has = c > j
                more[has, j] = src[b[has] + j]
            both = np.concatenate([self.edges[t], more], axis=1)
            d = np.where(both >= 0, pairwise(self.x[t], self.x[np.maximum(both, 0)]), np.inf)
            # equal candidates stand next to each other once sorted by distance and id
            order = np.lexsort((both, d), axis=1)
            both, d = np.take_along_axis(both, order, 1), np.take_along_axis(d, order, 1)
            self.edges[t] = self.prune(t, both, d)

    def build(self, seed: int = 0) -> PrunedGraph:
        n = len(self.x)
        rng = np.random.default_rng(seed)
        for _ in range(2):
            order, at, step = rng.permutation(n), 0, 8
            while at < n:
                self.insert(order[at : at + step])
                at += step
                step = min(2 * step, 512)
        return self


def usable(vectors: DataFrame, id_col: str, vec_col: str) -> DataFrame:
    """id, v (array<double>) of the rows that take part."""
    v = F.col(vec_col).cast("array<double>")
    rows = vectors.select(F.col(id_col).cast("long").alias("id"), v.alias("v")).filter("id is not null and v is not null and size(v) > 0")
    fine = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("v", lambda x: x != 0)
    return rows.filter(fine)


class Shard:
    """The points of one shard as they come, and their graph once it is asked for."""

    def __init__(self, make, k: int):
        self.make, self.k = make, k
        self.vectors: list[np.ndarray] = []
        self.ids: list[list[int]] = []
        self.graph = None

    def add(self, vectors: np.ndarray, ids: list[list[int]]) -> None:
        self.vectors.append(vectors)
        self.ids += ids

    @staticmethod
    def unit(x: np.ndarray) -> np.ndarray:
        x = x / np.abs(x).max(axis=1, keepdims=True)
        return x / np.linalg.norm(x, axis=1, keepdims=True)

    def nearest(self, q: np.ndarray, query_ids: list[int], beam: int) -> list[tuple[int, int, float]]:
        """(query id, id, cosine) of the k best ids of each query vector; none of a query's own."""
        if not self.vectors:
            return []
        if self.graph is None:
            self.raw = np.concatenate(self.vectors)
            order = sorted(range(len(self.ids)), key=lambda i: self.ids[i][0])  # the graph depends on the points, not on their order
            self.raw, self.ids = self.raw[order], [self.ids[i] for i in order]
            self.graph = self.make(self.unit(self.raw)).build()
            self.norm = np.linalg.norm(self.raw, axis=1)
        found, _ = self.graph.search(self.unit(q), beam)
        norms, out = np.linalg.norm(q, axis=1), []
        for j, near in enumerate(found):
            near = near[near >= 0]
            score = (self.raw[near] @ q[j]) / (self.norm[near] * norms[j])
            best: dict[int, float] = {}
            for o in np.argsort(-score, kind="stable").tolist():
                if len(best) > self.k and score[o] < min(best.values()):
                    break
                for v in self.ids[near[o]]:
                    if v != query_ids[j]:
                        best.setdefault(v, float(score[o]))
            out += [(query_ids[j], v, s) for v, s in sorted(best.items(), key=lambda r: (-r[1], r[0]))[: self.k]]
        return out


def nearest(vectors: DataFrame, id_col: str, vec_col: str, is_query, k: int = 5, beam: int = BEAM, shard: int | None = None) -> DataFrame:
    """query_id, rank, id, score: the k nearest found of each row for which is_query(id column) holds."""
    spark = vectors.sparkSession
    rows = usable(vectors, id_col, vec_col).distinct()
    # a point a distinct vector, standing for its smallest k + 1 ids
    ranked = rows.withColumn("r", F.row_number().over(Window.partitionBy("v").orderBy("id"))).filter(F.col("r") <= k + 1)
    points = materialize(ranked.groupBy("v").agg(F.array_sort(F.collect_list("id")).alias("ids")), "ann-points")  # at most k + 1
    counts = points.groupBy(F.size("v").alias("dim")).agg(F.count(F.lit(1)).alias("n"))
    size = F.lit(shard) if shard else F.least(F.lit(MOST), F.greatest(F.lit(SHARD), F.ceil(F.col("n") / SHARDS)))
    dims = materialize(counts.withColumn("shards", F.ceil(F.col("n") / size).cast("int")), "ann-dims")
    total = int(dims.agg(F.sum("shards")).first()[0] or 1)
    of_dim = small(dims.select("dim", "shards"))
    key = lambda s: F.shiftleft(F.col("dim").cast("long"), 32) + s
    dealt = points.withColumn("dim", F.size("v")).join(of_dim, "dim").select(key(F.pmod(F.xxhash64("v"), F.col("shards"))).alias("shard"), F.lit(0).alias("kind"), "v", "ids")
    asked = rows.filter(is_query(F.col("id"))).withColumn("dim", F.size("v")).join(of_dim, "dim")
    asked = asked.withColumn("s", F.explode(F.sequence(F.lit(0), F.col("shards") - 1))).select(key(F.col("s")).alias("shard"), F.lit(1).alias("kind"), "v", F.array("id").alias("ids"))
    # points first, then queries; two partitions a shard, so that few tasks get several
    sent = dealt.unionByName(asked).repartition(max(partitions_for(spark), 2 * total), "shard").sortWithinPartitions("shard", "kind")
    make, part_of, width = PrunedGraph, Shard, BLOCK

    def run(batches):
        now, here, held, names = None, None, [], []

        def search():
            out = here.nearest(np.concatenate(held), names, beam) if held else []
            cols = list(zip(*out)) or [()] * 3
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.float64()))], ["query_id", "id", "score"])

        for b in batches:
            if not b.num_rows:
                continue
            shards, kinds = (b.column(c).to_numpy(zero_copy_only=False) for c in (0, 1))
            cuts = np.flatnonzero(np.r_[True, (shards[1:] != shards[:-1]) | (kinds[1:] != kinds[:-1])]).tolist()
            for s, e in zip(cuts, [*cuts[1:], b.num_rows]):
                if shards[s] != now:
                    yield search()
                    now, here, held, names = shards[s], part_of(make, k), [], []
                for at in range(s, e, width):
                    part = b.slice(at, min(width, e - at))
                    v = part.column(2).flatten().to_numpy(zero_copy_only=False).reshape(part.num_rows, -1)
                    ids = part.column(3).to_pylist()
                    if not kinds[s]:
                        here.add(v, ids)
                        continue
                    held.append(v)
                    names += [x[0] for x in ids]
                    if len(names) >= width:
                        yield search()
                        held, names = [], []
        yield search()

    found = sent.mapInArrow(run, "query_id long, id long, score double").groupBy("query_id", "id").agg(F.max("score").alias("score"))
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "id"))
    return found.withColumn("rank", rank).filter(F.col("rank") <= k).select("query_id", "rank", "id", "score")
