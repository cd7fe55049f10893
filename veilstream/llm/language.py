"""Language identification by nearest centroids of normalised TF-IDF character n-grams.

Features: counts of character 1- to 3-grams of the lower-cased whole text (letters kept,
every run of other characters one space), hashed to a fixed number of dimensions. A
bounded sample of labelled texts for each language (sample_per_lang, chosen by hash) gives
the inverse document frequencies and, by spherical k-means, several centroids a language.
Prediction maps over the table without a shuffle: the language of the centroid with the
largest cosine; a text whose best cosine is below the reach of its length class is
rejected (distance-based rejection).

Defined results: null texts and texts without a letter are `und` with score 0 and are
rejected; ties go to the language that sorts first; with nothing to learn from, every text
is `und`; extra columns are kept, whatever their names; repeated rows keep a row each and count once in
the sample.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import unused
from .words import end_of_task

DIMS = 4096
ORDERS = (1, 2, 3)
CHUNK = 1 << 18
FINAL_SIGMA = 0x3C2


def grams(text: str | None) -> tuple[np.ndarray, int]:
    """Hashed n-gram counts of a whole text and its number of letters."""
    out, letters = np.zeros(DIMS, np.float64), 0
    if not text:
        return out, 0
    before = np.zeros(0, np.uint32)  # what n-grams may reach back to
    for s in range(0, len(text), CHUNK):
        c = np.frombuffer(text[s : s + CHUNK].lower().encode("utf-32-le", "surrogatepass"), "<u4").astype(np.uint32)
        c[c == FINAL_SIGMA] = FINAL_SIGMA + 1  # lower() writes it at the end of what it sees as a word
        alpha = (c >= 97) & (c <= 122)
        odd = np.flatnonzero(c > 127)
        if len(odd):
            kinds = {int(x): chr(x).isalpha() for x in np.unique(c[odd])}
            alpha[odd] = [kinds[x] for x in c[odd].tolist()]
        letters += int(alpha.sum())
        c = np.concatenate([before, np.where(alpha, c, 32)])
        keep = np.r_[True, (c[1:] != 32) | (c[:-1] != 32)]
        keep[: len(before)] = True
        c = c[keep]
        with np.errstate(over="ignore"):
            h = np.zeros(len(c), np.uint32)
            for n in range(1, max(ORDERS) + 1):
                if len(c) < n:
                    break
                h = h[: len(c) - n + 1] * np.uint32(0x01000193) ^ (c[n - 1 :] * np.uint32(0x9E3779B1))
                if n in ORDERS:
                    new = h[max(0, len(before) - n + 1) :]  # those that end in this chunk
                    slot = ((new ^ (new >> 15)) * np.uint32(0x85EBCA6B) >> np.uint32(20)).astype(np.int64) & (DIMS - 1)
                    out += np.bincount(slot, minlength=DIMS)
        before = c[-(max(ORDERS) - 1) :]
    return out, letters


class CentroidModel:
    """Languages in order, centroids (unit rows), their languages, idf and reach by length class."""

    def __init__(self, langs: list[str], centroids: np.ndarray, owner: np.ndarray, idf: np.ndarray, reach: np.ndarray):
        self.langs, self.centroids, self.owner, self.idf, self.reach = langs, centroids, owner, idf, reach

    @staticmethod
    def length_class(n: np.ndarray) -> np.ndarray:
        return np.minimum(np.log2(np.maximum(n, 1)).astype(np.int64), 15)

    @staticmethod
    def unit(x: np.ndarray) -> np.ndarray:
        size = np.linalg.norm(x, axis=1, keepdims=True)
        return np.divide(x, size, out=np.zeros_like(x), where=size > 0)

    def vectors(self, counts: np.ndarray) -> np.ndarray:
        return self.unit(np.log1p(counts) * self.idf.astype(counts.dtype))

    @classmethod
    def fit(cls, counts: np.ndarray, letters: np.ndarray, labels: list[str], per_lang: int, slack: float) -> CentroidModel:
        langs = sorted(set(labels))
        idf = np.log((1 + len(counts)) / (1 + (counts > 0).sum(axis=0))) + 1
        model = cls(langs, np.zeros((0, DIMS)), np.zeros(0, np.int64), idf, np.zeros(16))
        x, y = model.vectors(counts), np.asarray([langs.index(v) for v in labels])
        rows, owner = [], []
        for k in range(len(langs)):
            own = x[y == k]
            # spherical k-means from rows far from each other
            pick = [int(np.argmax(own @ own.mean(axis=0)))]
            while len(pick) < min(per_lang, len(own)):
                pick.append(int(np.argmin((own @ own[pick].T).max(axis=1))))
            c = own[pick]
            for _ in range(12):
                near = np.argmax(own @ c.T, axis=1)
                c = cls.unit(np.stack([own[near == j].sum(axis=0) if (near == j).any() else c[j] for j in range(len(c))]))
            rows.append(c)
            owner += [k] * len(c)
        model.centroids, model.owner = np.concatenate(rows) if rows else np.zeros((0, DIMS)), np.asarray(owner, np.int64)
        if len(x):
            best, size = (x @ model.centroids.T).max(axis=1), cls.length_class(letters)
            low = 1.0
            for k in range(15, -1, -1):  # a shorter class never reaches less far than a longer one
                if (size == k).any():
                    low = min(low, float(best[size == k].min()))
                model.reach[k] = low * slack if low < 1 else 0.0
        return model

    def predict(self, counts: np.ndarray, letters: np.ndarray) -> tuple[list[str], np.ndarray, np.ndarray]:
        n = len(counts)
        if not len(self.centroids):
            return ["und"] * n, np.zeros(n), np.ones(n, bool)
        cos = np.clip(self.vectors(counts) @ self.centroids.T, 0, 1)
        by = np.stack([cos[:, self.owner == k].max(axis=1) for k in range(len(self.langs))], axis=1)
        best = by.argmax(axis=1)
        score = by[np.arange(n), best]
        none = letters == 0
        out = ["und" if z else self.langs[k] for k, z in zip(best.tolist(), none.tolist())]
        return out, np.where(none, 0.0, score), none | (score < self.reach[self.length_class(letters)])


def held_out(doc_id) -> F.Column:
    return F.crc32(F.coalesce(F.col(doc_id).cast("string"), F.lit(""))) % 4 == 2


def train(docs: DataFrame, sample_per_lang: int = 600, centroids: int = 4, slack: float = 0.5) -> CentroidModel:
    """Fit on at most sample_per_lang different labelled, not held-out texts of each language, those of lowest hash.

    A threshold on the hash, from the approximate number of different texts of a language, leaves about twice as
    many before anything is shuffled; so no task gets the rows of a language.
    """
    learn = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", "lang").filter(F.col("lang").isNotNull() & F.col("text").isNotNull() & ~held_out("doc_id"))
    learn = learn.withColumn("h", F.xxhash64("doc_id", "text"))
    sizes = learn.groupBy("lang").agg(F.approx_count_distinct("h", 0.02).alias("n"))  # a row a language
    share = F.pmod(F.xxhash64("h"), F.lit(1 << 40)) / float(1 << 40)
    few = learn.join(F.broadcast(sizes), "lang").filter(share < 2.0 * sample_per_lang / F.col("n")).dropDuplicates(["lang", "h"])
    rank = F.row_number().over(Window.partitionBy("lang").orderBy(share, "h"))
    picked = few.withColumn("r", rank).filter(F.col("r") <= sample_per_lang)

    def run(batches):
        for b in batches:
            got = [grams(t) for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), pa.array([n for _, n in got], pa.int64()), pa.array([g.astype("<f4").tobytes() for g, _ in got], pa.binary())], ["doc_id", "lang", "letters", "counts"])

    rows = picked.select("doc_id", "text", "lang").mapInArrow(run, "doc_id long, lang string, letters long, counts binary").collect()
    rows = sorted((r for r in rows if r["letters"]), key=lambda r: (r["lang"], r["doc_id"] is None, r["doc_id"], r["letters"], r["counts"]))
    counts = np.stack([np.frombuffer(r["counts"], "<f4") for r in rows]) if rows else np.zeros((0, DIMS))
    return CentroidModel.fit(counts, np.asarray([r["letters"] for r in rows], np.int64), [r["lang"] for r in rows], centroids, slack)


def classify(docs: DataFrame, model: CentroidModel, keep: list[str]) -> DataFrame:
    """The columns `keep` and lang_pred, score, rejected (under other names if `keep` has these); `text` is the only input of the prediction."""
    spark = docs.sparkSession
    state = spark.sparkContext.broadcast((model.langs, model.centroids, model.owner, model.idf, model.reach))  # languages x centroids x DIMS
    cls, done = CentroidModel, end_of_task
    k = len(keep)

    def run(batches):
        model = cls(*state.value)
        for b in batches:
            for s in range(0, b.num_rows, 64):
                part = b.slice(s, 64)
                got = [grams(t) for t in part.column(k).to_pylist()]
                lang, score, bad = model.predict(np.stack([g for g, _ in got]), np.asarray([n for _, n in got]))
                yield pa.RecordBatch.from_arrays([*part.columns[:k], pa.array(lang, pa.string()), pa.array(score, pa.float64()), pa.array(bad, pa.bool_())], [*keep, *names])
        done()

    names = unused(docs.select(*keep), "lang_pred", "score", "rejected")
    schema = docs.select(*keep).schema
    for name, kind in zip(names, ("string", "double", "boolean")):
        schema = schema.add(name, kind)
    return docs.select(*keep, F.col("text").alias(unused(docs.select(*keep), "text")[0])).mapInArrow(run, schema)


def identify(docs: DataFrame, **params) -> DataFrame:
    """doc_id, held_out, lang_pred, score, rejected of every document."""
    model = train(docs, **params)
    ids = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").withColumn("held_out", held_out("doc_id"))
    return classify(ids, model, ["doc_id", "held_out"])


def keep_identified(docs: DataFrame, **params) -> DataFrame:
    """docs without those that the classifier rejects."""
    rejected = unused(docs, "lang_pred", "score", "rejected")[2]
    return classify(docs, train(docs, **params), docs.columns).filter(~F.col(rejected)).select(*docs.columns)
