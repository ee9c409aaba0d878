"""Language identification in two steps: family first, then language within it.

A linear machine for each family (against the others) picks the family;
within a family, one machine for every pair of its languages votes. Features
are byte trigrams in a fixed number of hash buckets. Everything that is learnt
comes from the training rows handed in.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from cityweave.llm.kernel import blocks, buffers, gram_counts, has_letter, mapped, parts
from cityweave.llm.svm import linear_svm
from cityweave.session import ship

UNDETERMINED = "und"

# Languages by family.
FAMILIES = {
    "germanic": "en de nl sv da no nb nn is af fy lb yi".split(),
    "romance": "fr es it pt ca ro gl oc la".split(),
    "slavic": "ru uk be pl cs sk sl hr sr bs bg mk".split(),
    "uralic": "fi et hu".split(),
    "indic": "hi bn pa gu mr ur ne si".split(),
    "turkic": "tr az kk ky uz tk".split(),
    "semitic": "ar he mt am".split(),
}
FAMILY_OF = {lang: family for family, langs in FAMILIES.items() for lang in langs}


@dataclass
class LanguageModel:
    """Weights of fixed size: buckets x (families + pairs of languages within families)."""

    dims: int
    families: dict[str, list[str]]
    family_weight: np.ndarray
    family_bias: np.ndarray
    pairs: dict[str, list[tuple[int, int]]]
    pair_weight: dict[str, np.ndarray]
    pair_bias: dict[str, np.ndarray]

    def predict(self, counts: np.ndarray) -> tuple[list[str], np.ndarray]:
        x = features(counts)
        n, names = len(x), list(self.families)
        margin = x @ self.family_weight + self.family_bias
        chosen = margin.argmax(axis=1)
        score = 1 / (1 + np.exp(-3 * margin[np.arange(n), chosen])) if len(names) > 1 else np.ones(n)
        out = np.empty(n, object)
        for k, family in enumerate(names):
            rows, langs = np.flatnonzero(chosen == k), self.families[family]
            if not len(rows):
                continue
            if len(langs) == 1:
                out[rows] = langs[0]
                continue
            votes = x[rows] @ self.pair_weight[family] + self.pair_bias[family]
            points, total = np.zeros((len(rows), len(langs))), np.zeros((len(rows), len(langs)))
            for j, (a, b) in enumerate(self.pairs[family]):
                first = votes[:, j] > 0
                points[:, a] += first
                points[:, b] += ~first
                total[:, a] += votes[:, j]
                total[:, b] -= votes[:, j]
            best = (points + 1e-3 * np.tanh(total)).argmax(axis=1)
            out[rows] = np.array(langs, object)[best]
            score[rows] *= 1 / (1 + np.exp(-3 * total[np.arange(len(rows)), best] / (len(langs) - 1)))
        return list(out), score


def features(counts: np.ndarray) -> np.ndarray:
    """Logarithms of counts, rows of length one; works in place."""
    np.log1p(counts, out=counts)
    counts /= np.maximum(np.linalg.norm(counts, axis=1, keepdims=True), 1e-9)
    return counts


def fit(x: np.ndarray, langs: list[str], penalty: float = 1e-3) -> LanguageModel:
    """Machines from counts of trigrams, one row for each text; x is worked on in place."""
    dims = x.shape[1]
    x, langs_ = features(x), np.array(langs, object)
    families: dict[str, list[str]] = {}
    for lang in sorted(set(langs)):
        families.setdefault(FAMILY_OF.get(lang, f"only {lang}"), []).append(lang)
    of = np.array([FAMILY_OF.get(lang, f"only {lang}") for lang in langs], object)
    solved = [linear_svm(x, np.where(of == f, 1.0, -1.0), penalty) for f in families] if len(families) > 1 else [(np.zeros(dims), 0.0) for _ in families]
    pairs, weight, bias = {}, {}, {}
    for family, members in families.items():
        pairs[family] = list(combinations(range(len(members)), 2))
        own = []
        for a, b in pairs[family]:
            rows = np.flatnonzero((langs_ == members[a]) | (langs_ == members[b]))
            own.append(linear_svm(x[rows], np.where(langs_[rows] == members[a], 1.0, -1.0), penalty))
        weight[family] = np.array([w for w, _ in own]).T.astype(np.float32)
        bias[family] = np.array([b for _, b in own], np.float32)
    return LanguageModel(dims, families, np.array([w for w, _ in solved]).T.astype(np.float32).reshape(dims, len(families)), np.array([b for _, b in solved], np.float32), pairs, weight, bias)


def held_out(doc_id) -> F.Column:
    """Rows that no model learns from: CRC-32 of the id as text divisible by 5."""
    return F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0


def training_sample(docs: DataFrame, label: str, per_class: int, text: str = "text") -> DataFrame:
    """About per_class rows of each label, chosen by a hash of doc_id from rows that aren't held out."""
    own = docs.where(~held_out(F.col("doc_id")) & F.col(label).isNotNull() & F.col(text).isNotNull())
    counts = {r[label]: r["count"] for r in own.groupBy(label).count().collect()}
    share = F.lit(0.0)
    for value, n in counts.items():
        share = F.when(F.col(label) == value, F.lit(min(1.0, per_class / n))).otherwise(share)
    return own.where(F.pmod(F.xxhash64(F.col("doc_id"), F.lit(17)), F.lit(1 << 20)) < share * (1 << 20)).select("doc_id", text, label)


def train(docs: DataFrame, per_class: int = 500, dims: int = 4096) -> LanguageModel:
    """Learns from a bounded sample (per_class rows of each language) of rows not held out."""

    def run(batches):
        for batch in blocks(batches):
            counts = gram_counts(*buffers(batch.column(1)), dims).astype(np.int32)
            packed = [np.flatnonzero(c).astype("<u2").tobytes() + c[c > 0].astype("<i4").tobytes() for c in counts]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(packed, pa.binary())], ["doc_id", "lang", "counts"])

    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang"))
    # counts of fixed size go to the driver, never texts
    rows = sorted((r.doc_id, r.lang, bytes(r.counts)) for r in mapped(training_sample(own, "lang", per_class), run, "doc_id long, lang string, counts binary").collect())
    x = np.zeros((len(rows), dims), np.float32)
    for k, (_, _, counts) in enumerate(rows):
        n = len(counts) // 6
        x[k, np.frombuffer(counts[: 2 * n], "<u2")] = np.frombuffer(counts[2 * n :], "<i4")
    return fit(x, [r[1] for r in rows])


def _predicted(texts: pa.Array, model: LanguageModel) -> tuple[list[str], np.ndarray]:
    data, offsets = buffers(texts)
    if model.families:
        lang, score = model.predict(gram_counts(data, offsets, model.dims))
    else:
        lang, score = [UNDETERMINED] * len(texts), np.zeros(len(texts))
    letters = has_letter(data, offsets)
    return [x if ok else UNDETERMINED for x, ok in zip(lang, letters, strict=True)], np.where(letters, score, 0.0)


def identify(docs: DataFrame, model: LanguageModel) -> DataFrame:
    """(doc_id, lang_pred, score) for each row; text without a letter, or null, is `und` with score 0."""

    def run(batches):
        for batch in blocks(batches):
            lang, score = _predicted(batch.column(1), model)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(lang, pa.string()), pa.array(score.astype(float))], ["doc_id", "lang_pred", "score"])

    return mapped(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), run, "doc_id long, lang_pred string, score double")


def keep_identified(docs: DataFrame, model: LanguageModel) -> DataFrame:
    """docs, in its own columns, without rows whose language can't be told (no letters, or null text).

    Only the text goes through Python; the rows stay where they are.
    """

    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for batch in batches:
            yield pa.array([lang != UNDETERMINED for _, part in parts(batch) for lang in _predicted(part, model)[0]], pa.bool_())

    ship(docs.sparkSession)
    return docs.where(F.arrow_udf(run, T.BooleanType())(F.col("text").cast("string")))
