"""Two quality judgements: boosted trees over statistics, and a vote of labelled neighbours."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cityweave.llm import gbt
from cityweave.llm.kernel import blocks, buffers, gram_counts, mapped
from cityweave.llm.langid import held_out
from cityweave.llm.statistics import BASE, DECREASING, FEATURES, features, statistics


def labelled(docs: DataFrame, labels: DataFrame, label: str, bound: int) -> DataFrame:
    """(doc_id, text, y): at most about `bound` labelled documents that aren't held out, drawn by a hash of the id.

    `bound` bounds what is drawn, so the drawn ids may be broadcast. Labels that
    come several times for an id count once, by the smallest.
    """
    own = labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"))).groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.min(label).cast("int").alias("y"))
    n = own.count()
    drawn = own.where(F.pmod(F.xxhash64("doc_id", F.lit(29)), F.lit(1 << 20)) < int(min(1.0, bound / max(n, 1)) * (1 << 20)))
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    return texts.join(F.broadcast(drawn), "doc_id").select("doc_id", "text", "y")


def train_rules(docs: DataFrame, labels: DataFrame, bound: int = 20_000) -> gbt.FlatTrees:
    """Trees over document statistics; the statistics are made where the documents lie."""

    def run(batches):
        for batch in blocks(batches):
            x = features(statistics(*buffers(batch.column(1))))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(list(x))], ["doc_id", "y", "x"])

    rows = sorted((r.doc_id, r.y, tuple(r.x)) for r in mapped(labelled(docs, labels, "quality", bound), run, "doc_id long, y int, x array<double>").collect())
    x = np.array([r[2] for r in rows]).reshape(len(rows), len(FEATURES))
    return gbt.fit(x, np.array([r[1] for r in rows], float), [FEATURES.index(f) for f in DECREASING])


def judged_by_rules(docs: DataFrame, trees: gbt.FlatTrees, least: float = 0.5) -> DataFrame:
    """(doc_id, the counts of BASE, base_failed, kept, score) for each row of docs.

    Null text counts as empty, which fails the base rules. Without labels the
    trees score everything alike at the prior.
    """

    def run(batches):
        for batch in blocks(batches):
            stats = statistics(*buffers(batch.column(1)))
            failed = (stats["n_words"] < 10) | (100 * stats["n_repeat_words"] > 20 * stats["n_words"])
            score = trees.score(features(stats))
            cols = [batch.column(0), *(pa.array(stats[c].astype(np.int64)) for c in BASE), pa.array(failed), pa.array(~failed & (score >= least)), pa.array(score)]
            yield pa.RecordBatch.from_arrays(cols, ["doc_id", *BASE, "base_failed", "kept", "score"])

    schema = "doc_id long, " + ", ".join(f"{c} long" for c in BASE) + ", base_failed boolean, kept boolean, score double"
    return mapped(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), run, schema)


def document_frequency(docs: DataFrame, dims: int) -> tuple[np.ndarray, int]:
    """Documents with a trigram in each bucket, and documents, over all of docs; a fixed number of sums."""

    def run(batches):
        seen, n = np.zeros(dims, np.int64), 0
        for batch in blocks(batches):
            seen += (gram_counts(*buffers(batch.column(0)), dims, fold=False) > 0).sum(axis=0)
            n += batch.num_rows
        yield pa.RecordBatch.from_arrays([pa.array(np.append(seen, n).tolist(), pa.int64()), pa.array(range(dims + 1), pa.int64())], ["n", "bucket"])

    sums = dict(mapped(docs.select(F.col("text").cast("string").alias("text")), run, "n long, bucket long").groupBy("bucket").agg(F.sum("n")).collect())
    return np.array([sums.get(k, 0) for k in range(dims)]), sums.get(dims, 0)


@dataclass
class NeighbourModel:
    """Labelled vectors in latent space: at most `bound` of them, whatever the corpus."""

    dims: int
    idf: np.ndarray
    mean: np.ndarray
    spread: np.ndarray
    axes: np.ndarray
    vectors: np.ndarray
    labels: np.ndarray
    prior: float
    neighbours: int

    def terms(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        return self.weighted(gram_counts(data, offsets, self.dims, fold=False), features(statistics(data, offsets)))

    def weighted(self, counts: np.ndarray, x: np.ndarray) -> np.ndarray:
        """TF-IDF of trigrams, with the statistics as further terms."""
        grams = np.log1p(counts) * self.idf
        grams /= np.maximum(np.linalg.norm(grams, axis=1, keepdims=True), 1e-9)
        stats = np.clip((x - self.mean) / self.spread, -3, 3) / np.sqrt(len(FEATURES))
        return np.concatenate((grams, stats.astype(np.float32)), axis=1)

    def latent(self, terms: np.ndarray) -> np.ndarray:
        z = terms @ self.axes
        return z / np.maximum(np.linalg.norm(z, axis=1, keepdims=True), 1e-9)

    def vote(self, z: np.ndarray) -> np.ndarray:
        """Share of label 1 among the nearest labelled vectors, weighted by similarity."""
        out = np.full(len(z), self.prior)
        k = min(self.neighbours, len(self.labels))
        for at in range(0, len(z) if k else 0, 256):
            near = z[at : at + 256] @ self.vectors.T
            best = np.argpartition(near, -k, axis=1)[:, -k:]
            weight = np.maximum(np.take_along_axis(near, best, axis=1), 0) ** 8 + 1e-12
            out[at : at + 256] = (weight * self.labels[best]).sum(axis=1) / weight.sum(axis=1)
        return out


def train_neighbours(docs: DataFrame, labels: DataFrame, bound: int = 6_000, dims: int = 2048, rank: int = 48, neighbours: int = 15) -> NeighbourModel:
    """Axes of latent space from the labelled sample, weights of terms from all documents.

    Of the sample only counts and statistics of fixed size go to the driver, never texts.
    """
    seen, n = document_frequency(docs, dims)
    idf = (np.log((1 + n) / (1 + seen)) + 0.1).astype(np.float32)

    def run(batches):
        for batch in blocks(batches):
            data, offsets = buffers(batch.column(1))
            counts, x = gram_counts(data, offsets, dims, fold=False).astype(np.int32), features(statistics(data, offsets))
            packed = [np.flatnonzero(c).astype("<u2").tobytes() + c[c > 0].astype("<i4").tobytes() for c in counts]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(packed, pa.binary()), pa.array(list(x))], ["doc_id", "y", "counts", "x"])

    rows = sorted((r.doc_id, r.y, bytes(r.counts), tuple(r.x)) for r in mapped(labelled(docs, labels, "quality", bound), run, "doc_id long, y int, counts binary, x array<double>").collect())
    y = np.array([r[1] for r in rows], float)
    model = NeighbourModel(dims, idf, np.zeros(len(FEATURES)), np.ones(len(FEATURES)), np.zeros((dims + len(FEATURES), 0), np.float32), np.zeros((0, 0), np.float32), y, float(y.mean()) if len(y) else 0.5, neighbours)
    if not rows:
        return model
    counts = np.zeros((len(rows), dims), np.float32)
    for k, r in enumerate(rows):
        n = len(r[2]) // 6
        counts[k, np.frombuffer(r[2][: 2 * n], "<u2")] = np.frombuffer(r[2][2 * n :], "<i4")
    x = np.array([r[3] for r in rows])
    model.mean, model.spread = x.mean(axis=0), np.maximum(x.std(axis=0), 1e-6)
    terms = model.weighted(counts, x)
    values, vectors = np.linalg.eigh((terms.T @ terms).astype(np.float64))
    model.axes = vectors[:, np.argsort(-values)[:rank]].astype(np.float32)
    model.vectors = model.latent(terms)
    return model


def scored_by_neighbours(docs: DataFrame, model: NeighbourModel, least: float = 0.3) -> DataFrame:
    """(doc_id, score, predicted) for each row of docs; null text counts as empty."""

    def run(batches):
        for batch in blocks(batches):
            score = model.vote(model.latent(model.terms(*buffers(batch.column(1))))).clip(0, 1)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(score.astype(float)), pa.array((score >= least).astype(np.int32))], ["doc_id", "score", "predicted"])

    return mapped(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), run, "doc_id long, score double, predicted int")
